"""The public interface: graphs, queries, rules, reasoning and measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.functions import expressions
from rulegraph.plans import algebra as A
from rulegraph.plans.compile import Compiler
from rulegraph.plans.parser import COMPLIANCE, parse_query, parse_rules
from rulegraph.plans.reason import Reasoner, Result
from rulegraph.plans.translate import expand, query_to_triples, to_rule_text, translate, triples_to_rule
from rulegraph.sources.graphs import Graph, MappedGraph, TripleGraph
from rulegraph.sources.vocabulary import tables_graph
from rulegraph.terms import Rule, Triple


class Engine:
    """Queries and rules over one graph."""

    def __init__(self, spark: SparkSession, graph: Graph | None = None):
        self.spark, self.graph = spark, graph
        self.timings: list[dict] = []

    # -------------------------------------------------------- graphs

    def mapped_graph(self, sf_dir: str, **params) -> Engine:
        return Engine(self.spark, tables_graph(self.spark, sf_dir, **params))

    def triples(self, triples: DataFrame | Iterable[Triple]) -> Engine:
        graph = TripleGraph(triples) if isinstance(triples, DataFrame) else TripleGraph.of(self.spark, triples)
        return Engine(self.spark, graph)

    # -------------------------------------------------------- queries

    def query(self, text: str | A.Query, *, unbound: str = "drop") -> DataFrame:
        """Solutions of a SELECT, triples of a CONSTRUCT; one application, no recursion."""
        q = parse_query(text) if isinstance(text, str) else text
        comp = Compiler(self.graph)
        return comp.construct(q, unbound) if q.form == "construct" else comp.query(q).df

    def query_by_rule(self, text: str, mode: str = "strict") -> DataFrame:
        """The same by the other way: the query's rule, expanded by the runtime library."""
        q = parse_query(text)
        back = A.Query(q.form, q.template if q.form != "select_star" else (), expand(translate(q, mode=mode)))
        if q.form == "select_star":
            back = A.Query("select", tuple(A.scope(q.pattern)), back.pattern)
        return self.query(back)

    def ask(self, text: str) -> bool:
        """Whether a pattern has any solution."""
        return self.query(text).limit(1).count() > 0

    def as_result_triples(self, text: str) -> DataFrame:
        """A SELECT's rows in the form of result triples: subject, predicate, list of values, list of names."""
        df = self.query(text)
        return df.select(F.lit("_:result").alias("s"), F.lit("rt:result").alias("p"), F.array(*[F.col(f"`{c}`").cast("string") for c in df.columns]).alias("o"), F.array(*[F.lit(c) for c in df.columns]).alias("names"))

    # -------------------------------------------------------- rules

    def rules(self, texts: Iterable[str]) -> list[Rule | A.Query]:
        """CONSTRUCT queries and rule text, mixed."""
        out: list[Rule | A.Query] = []
        for i, t in enumerate(texts):
            if "construct" in t.lower().split("{")[0]:
                out.append(translate(parse_query(t), f"q{i}"))
            else:
                out += parse_rules(t)
        return out

    def translate(self, text: str) -> Rule:
        return translate(parse_query(text))

    def rule_text(self, text: str) -> str:
        return to_rule_text(self.translate(text))

    def encode(self, text: str) -> DataFrame:
        """The query itself as triples."""
        return self.spark.createDataFrame(query_to_triples(parse_query(text)), "s string, p string, o string")

    def rule_of_encoding(self, triples: DataFrame) -> Rule:
        return triples_to_rule([tuple(r) for r in triples.collect()])

    def forward(self, texts: Iterable[str], strategy: str = "seminaive", **params) -> Result:
        with self.phase("forward", strategy=strategy) as made:
            result = made["result"] = Reasoner(self.graph, **params).forward(self.rules(texts), strategy)
        return result

    def closure(self, texts: Iterable[str], **params) -> Graph:
        return self.forward(texts, **params).graph

    def backward(self, goal: str, texts: Iterable[str], strategy: str = "demand", **params) -> tuple[DataFrame, Result]:
        with self.phase("backward", strategy=strategy) as made:
            df, made["result"] = Reasoner(self.graph, **params).backward(goal_of(goal), self.rules(texts), strategy)
        return df, made["result"]

    def reason(self, texts: Iterable[str], goal: str | None = None, **params):
        return Reasoner(self.graph, **params).reason(self.rules(texts), goal_of(goal) if goal else None)

    def sql_view(self, name: str, texts: Iterable[str], predicate: str) -> None:
        """Answers of a derived predicate as a view for SQL."""
        self.forward(texts).view(predicate).createOrReplaceTempView(name)

    def explain(self, text: str) -> str:
        df = self.query(text)
        return df._jdf.queryExecution().explainString(self.spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))

    # -------------------------------------------------------- extension

    def register_filter(self, name: str, column_fn: Callable[..., Column]) -> None:
        expressions.register_filter(name, column_fn)

    def register_aggregate(self, name: str, column_fn: Callable[..., Column]) -> None:
        """An aggregate of a column, built in or a grouped-aggregate Pandas UDF, for query text."""
        expressions.register_aggregate(name, column_fn)

    def register_table_function(self, name: str, handler: type, return_type: str) -> None:
        """A Python table function for SQL over the views of ``sql_view``."""
        self.spark.udtf.register(name, F.udtf(handler, returnType=return_type))

    def register_pandas_udf(self, name: str, fn: Callable, return_type: str) -> None:
        udf = F.pandas_udf(fn, return_type)
        expressions.register_filter(name, lambda *a: udf(*a))

    # -------------------------------------------------------- measures

    @contextmanager
    def phase(self, name: str, **tags):
        """Times what stands inside; a Result put into the yielded dict adds its rounds to the metrics."""
        began, made = time.perf_counter(), {}
        yield made
        self.timings.append({"phase": name, "seconds": time.perf_counter() - began, **tags})
        if "result" in made:
            self.timings += [{"phase": f"{name} round", "seconds": r.seconds, "stratum": r.stratum, "round": r.number, "predicate": r.predicate, "rows": r.kept, **tags} for r in made["result"].rounds]

    def metrics(self) -> DataFrame:
        """Seconds of every phase so far, and rows and seconds of every round of reasoning."""
        names = ("phase", "strategy", "stratum", "round", "predicate", "rows", "seconds")
        rows = [tuple(t.get(n) for n in names) for t in self.timings]
        return self.spark.createDataFrame(rows, "phase string, strategy string, stratum int, round int, predicate string, rows bigint, seconds double")

    def compliance(self) -> DataFrame:
        return self.spark.createDataFrame(list(COMPLIANCE), "form string, supported boolean")


def goal_of(text: str) -> Triple:
    from rulegraph.plans.parser import Parser

    return Parser(text).triples()[0]


__all__ = ["Engine", "MappedGraph", "goal_of"]
