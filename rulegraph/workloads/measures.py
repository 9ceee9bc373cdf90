"""Cost measures: load, encoding, translation and execution times, rules for a query, rounds, and how much is demanded."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.baselines import loops
from rulegraph.engine import Engine, goal_of
from rulegraph.plans.parser import parse_query
from rulegraph.plans.reason import Reasoner
from rulegraph.plans.translate import NotTranslatable, parse_rule_text, query_to_triples, to_rule_text, translate, triples_to_rule
from rulegraph.storage import new_path
from rulegraph.workloads import recursive

SCHEMA = "system string, workload string, phase string, run int, seconds double, status string"


def timed(fn) -> tuple[float, object]:
    began = time.perf_counter()
    out = fn()
    return time.perf_counter() - began, out


class Stopped(RuntimeError):
    """An execution went beyond its time limit and was cancelled."""


def run_within(spark: SparkSession, fn: Callable, seconds: float) -> object:
    """What fn gives; its jobs are cancelled, and Stopped raised, when the time is over."""
    sc, group, over, ended = spark.sparkContext, f"limit-{uuid.uuid4().hex}", threading.Event(), threading.Event()

    def watch() -> None:
        if not ended.wait(seconds):
            over.set()
            # a loop on the driver may start another job of the group
            while not ended.wait(0.2):
                sc.cancelJobGroup(group)

    thread = threading.Thread(target=watch, daemon=True)
    sc.setJobGroup(group, "with a time limit", interruptOnCancel=True)
    thread.start()
    try:
        out = fn()
    except Exception as e:
        if over.is_set():
            raise Stopped(f"stopped after {seconds} s") from e
        raise
    finally:
        ended.set()
        thread.join()
        for name in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel"):
            sc.setLocalProperty(name, None)
    if over.is_set():
        raise Stopped(f"stopped after {seconds} s")
    return out


def rules_per_query(texts: list[str]) -> list[int]:
    """Rules in the text that each query's translation gives, counted by reading it back."""
    return [len(parse_rule_text(to_rule_text(translate(parse_query(t))))) for t in texts]


def translation_times(texts: list[str]) -> tuple[float, float]:
    """(seconds to encode as triples, seconds to make rules of that)."""
    encode, coded = timed(lambda: [query_to_triples(parse_query(t)) for t in texts])
    make, _ = timed(lambda: [to_rule_text(triples_to_rule(c)) for c in coded])
    return encode, make


def measure(spark: SparkSession, sf_dir: str, workloads: list[str], strategies: list[str], repeat: int = 5, timeout: float = 3600.0) -> list[tuple]:
    """Rows of SCHEMA; an execution beyond the time limit is stopped, and not tried again."""
    rows = []
    for w in workloads:
        spec = recursive.WORKLOADS[w]
        texts = [t for t in spec.rules(spark, sf_dir) if t.lstrip().upper().startswith("CONSTRUCT")]
        for run in range(repeat):
            try:
                encode, make = translation_times(texts)
                rows += [("rules", w, "encode", run, encode, "ok"), ("rules", w, "translate", run, make, "ok")]
            except NotTranslatable as e:
                rows.append(("rules", w, "encode", run, 0.0, f"not translatable: {e}"))
        graph = Engine(spark).mapped_graph(sf_dir).graph
        load, _ = timed(lambda: [graph.view(p).df.count() for p in spec.reads])
        rows.append(("rules", w, "load", 0, load, "ok"))
        if "persistent" in strategies:
            load, _ = timed(lambda: loops.load_triples(graph, spec.reads, new_path(spark, "load")))
            rows.append(("persistent", w, "load", 0, load, "ok"))
        for s in strategies:
            for run in range(repeat):
                began = time.perf_counter()
                try:
                    run_within(spark, lambda: recursive.run(spark, sf_dir, w, s).count(), timeout)
                    status = "ok"
                except Stopped:
                    status = "timeout"
                rows.append((s, w, "exec", run, time.perf_counter() - began, status))
                if status == "timeout":
                    break
    return rows


def summary(rows: DataFrame) -> DataFrame:
    """Mean, median and least seconds by system, workload and phase, with totals of each."""
    return rows.rollup("phase", "system", "workload").agg(F.avg("seconds").alias("mean_s"), F.median("seconds").alias("median_s"), F.min("seconds").alias("min_s"), F.count(F.lit(1)).alias("runs"))


def summary_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five runs of the goal-bound and of two quick workloads, by the rules and by both baselines."""
    rows = measure(spark, sf_dir, ["motivating_chain", "screening_ontology"], ["seminaive", "demand", "query_loop", "persistent"], timeout=600)
    rows += measure(spark, sf_dir, ["deep_taxonomy"], ["demand"], timeout=600)
    return summary(spark.createDataFrame(rows, SCHEMA))


def demanded_fraction(spark: SparkSession, sf_dir: str, depth: int = 32) -> DataFrame:
    """Facts that goal-directed and bottom-up evaluation of a taxonomy of chains derive for the same goal."""
    engine = Engine(spark).mapped_graph(sf_dir, chain=depth)
    texts, goal = recursive.TAXONOMY, f"?item ex:memberOf <class{{{depth - 1}}}>"
    rules = engine.rules(texts)
    whole = Reasoner(engine.graph).forward(rules)
    _, part = Reasoner(engine.graph).backward(goal_of(goal), rules)
    a, b = whole.derived_count(), part.derived_count()
    return spark.createDataFrame([("deep_taxonomy", a, b, b / a if a else 0.0)], "workload string, forward_facts bigint, demanded_facts bigint, fraction double")
