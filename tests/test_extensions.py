"""Chained rounds, bound goals, provenance, time limits, sources and user extensions."""

import time

import pytest
from pyspark.sql import functions as F

from rulegraph.baselines import loops
from rulegraph.engine import Engine, goal_of
from rulegraph.operators import paths
from rulegraph.plans.parser import parse_query
from rulegraph.plans.reason import DepthExceeded, Reasoner
from rulegraph.sources.graphs import read_ntriples, read_table, read_turtle, write_ntriples
from rulegraph.streaming import incremental
from rulegraph.workloads import measures
from tests.toys import engine

LEFT = ["CONSTRUCT { ?x :t ?y } WHERE { ?x :e ?y }", "CONSTRUCT { ?x :t ?z } WHERE { ?x :t ?y . ?y :e ?z }"]
RIGHT = [LEFT[0], "CONSTRUCT { ?x :t ?z } WHERE { ?x :e ?y . ?y :t ?z }"]
MAZE = "a e b; b e c; c e a; c e d; d e f; f e g; g e h; h e i; i e j; j e k; x e y; y e d; k e d"


def pairs(df):
    return {tuple(r) for r in df.collect()}


@pytest.mark.parametrize("rules", [LEFT, RIGHT])
def test_chained_rounds_find_what_single_ones_do(spark, rules):
    e = engine(spark, MAZE)
    one = e.forward(rules, max_hops=1)
    want = pairs(one.view("t"))
    for hops, rows in ((8, 100_000), (3, 100_000), (8, 0)):
        got = e.forward(rules, max_hops=hops, hop_rows=rows)
        assert pairs(got.view("t")) == want and got.derived_count() == len(want)
    assert len(e.forward(rules, max_hops=8).rounds) < len(one.rounds)


def test_chained_rounds_of_rules_that_need_each_other(spark):
    rules = ["CONSTRUCT { ?x :odd ?y } WHERE { ?x :e ?y }", "CONSTRUCT { ?x :even ?z } WHERE { ?x :odd ?y . ?y :e ?z }", "CONSTRUCT { ?x :odd ?z } WHERE { ?x :even ?y . ?y :e ?z }"]
    e = engine(spark, MAZE)
    for p in ("odd", "even"):
        assert pairs(e.forward(rules, max_hops=8).view(p)) == pairs(e.forward(rules, "naive").view(p))


@pytest.mark.parametrize("rules", [LEFT, RIGHT])
@pytest.mark.parametrize("goal", [":a :t ?y", "?x :t :k", ":x :t ?y", "?x :t :nowhere", ":k :t ?y"])
def test_bound_goals_over_linear_rules_equal_the_closure(spark, rules, goal):
    e = engine(spark, MAZE)
    direct = Reasoner(e.graph).linear_goal(goal_of(goal), [c for c in __import__("rulegraph.plans.reason", fromlist=["clauses_of"]).clauses_of(e.rules(rules))])
    assert direct is not None
    want = pairs(Engine(spark, e.forward(rules).graph).query(f"SELECT * {{ {goal} }}"))
    assert pairs(direct[0]) == want == pairs(e.backward(goal, rules)[0])


def test_goals_that_are_not_linear_are_left_to_the_rewriting(spark):
    e = engine(spark, MAZE)
    from rulegraph.plans.reason import clauses_of

    square = [LEFT[0], "CONSTRUCT { ?x :t ?z } WHERE { ?x :t ?y . ?y :t ?z }"]
    for rules, goal in ((square, ":a :t ?y"), (LEFT, "?x :t ?y"), (LEFT, ":a :t :b"), (LEFT[:1], ":a :t ?y")):
        assert Reasoner(e.graph).linear_goal(goal_of(goal), clauses_of(e.rules(rules))) is None


def test_reachable_takes_several_steps_in_a_job(spark, monkeypatch):
    n = 40
    edges = spark.createDataFrame([(i, i + 1) for i in range(n)] + [(n, 5), (7, 30)], "s bigint, o bigint")
    start = spark.createDataFrame([(3,)], "x bigint")
    for hops, rows in ((8, 100_000), (1, 100_000), (8, 0)):
        monkeypatch.setattr(paths, "HOP_ROWS", rows)
        assert {r["x"] for r in paths.reachable(edges, start, hops=hops).collect()} == set(range(4, n + 1))
    with pytest.raises(RuntimeError):
        paths.reachable(edges, start, max_rounds=3)
    assert not paths.one_ended(edges)
    tree = edges.where("not (s = 7 and o = 30)")
    ring = [(i, (i + 1) % 13) for i in range(13)]
    for rows, begin in ((ring, [4]), ([(i // 2, i) for i in range(2, 60)], [3]), ([(i, i // 2) for i in range(2, 60)], [37, 41]), ([], [1])):
        e, b = spark.createDataFrame(rows, "s bigint, o bigint"), spark.createDataFrame([(x,) for x in begin], "x bigint")
        assert paths.one_ended(e)
        assert pairs(paths.reachable_by_doubling(e, b)) == pairs(paths.reachable(e, b))
    assert paths.one_ended(tree) and pairs(paths.reachable_by_doubling(tree, start)) == pairs(paths.reachable(tree, start))


def test_derivations_name_rule_and_round(spark):
    e = engine(spark, "a e b; b e c; c e d; a t z")
    got = e.forward(LEFT, explain_derivations=True).derivations("t")
    want = {("a", "z", "given", 0), ("a", "b", "q0", 0), ("b", "c", "q0", 0), ("c", "d", "q0", 0), ("a", "c", "q1", 1), ("b", "d", "q1", 1), ("a", "d", "q1", 2)}
    assert {(r["s"].strip("<>"), r["o"].strip("<>"), r["rule"], r["round"]) for r in got.collect()} == want
    flat = e.forward(LEFT[:1], explain_derivations=True)
    assert {(r["rule"], r["round"]) for r in flat.derivations("t").collect()} == {("given", 0), ("q0", 0)}
    assert pairs(flat.view("t")) == pairs(e.forward(LEFT[:1]).view("t"))


def test_baselines_raise_when_rounds_run_out(spark):
    e = engine(spark, MAZE)
    for run in (loops.query_loop, loops.persistent_recursive):
        with pytest.raises(DepthExceeded):
            run(e.graph, e.rules(LEFT), ("e",), max_rounds=2)
    held = loops.query_loop(e.graph, e.rules(LEFT), ("e",))
    assert pairs(held.view("t").df.select("s", "o")) == pairs(e.forward(LEFT).view("t"))


def test_row_budget(spark):
    with pytest.raises(DepthExceeded):
        engine(spark, MAZE).forward(LEFT, row_budget=15)


def test_an_execution_beyond_its_limit_is_stopped(spark):
    slow = F.udf(lambda x: time.sleep(0.5) or x, "bigint")
    job = lambda: spark.range(0, 400, 1, 4).select(slow("id").alias("x")).agg(F.sum("x")).collect()
    began = time.perf_counter()
    with pytest.raises(measures.Stopped):
        measures.run_within(spark, lambda: [job() for _ in range(20)], 2.0)
    assert time.perf_counter() - began < 20
    assert measures.run_within(spark, lambda: spark.range(5).count(), 60) == 5
    with pytest.raises(ZeroDivisionError):
        measures.run_within(spark, lambda: 1 // 0, 60)
    rows = measures.measure(spark, "/root/testdata/sf0.001", ["bacon_any"], ["seminaive"], repeat=5, timeout=0.5)
    assert [r[5] for r in rows if r[2] == "exec"] == ["timeout"]


def test_rules_for_a_query_are_counted(spark):
    assert measures.rules_per_query(["CONSTRUCT { ?x :a ?y } WHERE { { ?x :p ?y } UNION { ?x :q ?y } OPTIONAL { ?y :r ?z } }"]) == [1]


def test_metrics_tell_phases_and_rounds(spark):
    e = engine(spark, MAZE)
    e.forward(LEFT)
    e.backward(":a :t ?y", LEFT)
    rows = e.metrics().collect()
    assert {r["phase"] for r in rows} == {"forward", "forward round", "backward", "backward round"}
    assert sum(r["rows"] for r in rows if r["phase"] == "forward round") == e.forward(LEFT).derived_count()


def test_user_aggregates_table_functions_and_filters(spark):
    e = engine(spark, "a v 1; a v 2; b v 5")
    e.register_aggregate("spread", lambda c: F.max(F.regexp_extract(c, r"(\d+)", 1).cast("int")) - F.min(F.regexp_extract(c, r"(\d+)", 1).cast("int")))
    assert {r["d"] for r in e.query("SELECT ?x (SPREAD(?v) AS ?d) { ?x :v ?v } GROUP BY ?x").collect()} == {0, 1}
    e.register_filter("isone", lambda c: c.cast("string").contains("1"))
    assert e.query("SELECT ?x { ?x :v ?v FILTER(ISONE(?v)) }").count() == 1

    class Twice:
        def eval(self, n: int):
            yield n,
            yield n * 2,

    e.register_table_function("twice", Twice, "n: int")
    engine(spark, "a e b; b e c").sql_view("closure_pairs", LEFT, "t")
    assert spark.sql("SELECT count(*) AS n FROM closure_pairs, LATERAL twice(3)").first()["n"] == 6
    e.register_pandas_udf("longer", lambda s: s.str.len() > 0, "boolean")
    assert e.query("SELECT ?x { ?x :v ?v FILTER(LONGER(?v)) }").count() == 2


def test_sources_read_the_same_triples(spark, tmp_path):
    (tmp_path / "g.ttl").write_text('@prefix ex: <http://e/> .\n@prefix : <urn:> .\n# a remark\nex:a a ex:Thing ;\n  ex:p 1, 2.5 , true ;\n  :q "x ; y, z" .\n:b ex:p _:n1 .\n')
    turtle = read_turtle(spark, str(tmp_path / "g.ttl"))
    want = {
        ("<http://e/a>", "<a>", "<http://e/Thing>"), ("<http://e/a>", "<http://e/p>", '"1"^^integer'), ("<http://e/a>", "<http://e/p>", '"2.5"^^decimal'),
        ("<http://e/a>", "<http://e/p>", '"true"^^boolean'), ("<http://e/a>", "<urn:q>", '"x ; y, z"'), ("<urn:b>", "<http://e/p>", "_:n1"),
    }
    assert pairs(turtle.all_triples()) == want
    write_ntriples(turtle, str(tmp_path / "nt"))
    assert pairs(read_ntriples(spark, str(tmp_path / "nt")).all_triples()) == want
    turtle.all_triples().write.mode("overwrite").parquet(str(tmp_path / "pq"))
    assert pairs(read_table(spark, str(tmp_path / "pq")).all_triples()) == want


def test_windows_and_joins_over_streams(spark, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").select("user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    events.repartition(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    run = lambda df, name, mode: df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start().awaitTermination()
    run(incremental.factor_windows(stream), "factors", "complete")
    assert pairs(spark.table("factors").select("w.start", "event_type", "n")) == pairs(incremental.factor_windows(events).select("w.start", "event_type", "n"))
    run(incremental.session_stream(stream, late="400 days"), "sessions", "complete")
    assert spark.table("sessions").agg(F.sum("n")).first()[0] == events.count()
    join = lambda df: incremental.symptomatic_after_exposure(df.where("event_type = 'click'"), df.where("event_type = 'purchase'"), late="400 days")
    run(join(stream), "after", "append")
    assert pairs(spark.table("after")) == pairs(join(events)) and spark.table("after").count()


def test_parse_errors_name_unsupported_forms():
    with pytest.raises(Exception, match="(?i)describe|unsupported"):
        parse_query("DESCRIBE ?x { ?x :p ?y }")
