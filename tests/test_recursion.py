"""Recursion: both directions, strata, guards, made-up terms, and streams."""

import duckdb
import pytest

from rulegraph.baselines import brute
from rulegraph.engine import Engine
from rulegraph.plans.parser import parse_query
from rulegraph.plans.reason import DepthExceeded, UnstratifiedRecursion, clauses_of, stratify
from rulegraph.streaming.incremental import IncrementalClosure, NonMonotoneStreamingRule, check_monotone
from rulegraph.workloads import measures, recursive
from tests.toys import engine, triples

SF = "/root/testdata/sf0.001"
CLOSURE = ["CONSTRUCT { ?x :t ?y } WHERE { ?x :e ?y }", "CONSTRUCT { ?x :t ?z } WHERE { ?x :t ?y . ?y :e ?z }"]
SQUARE = [CLOSURE[0], "CONSTRUCT { ?x :t ?z } WHERE { ?x :t ?y . ?y :t ?z }"]


def pairs(df):
    return {(r["s"], r["o"]) for r in df.collect()}


@pytest.mark.parametrize("strategy, rules", [("seminaive", CLOSURE), ("naive", CLOSURE), ("doubling", SQUARE), ("seminaive", SQUARE)])
def test_cycle_ends_and_equals_enumeration(spark, strategy, rules):
    graph = "a e b; b e c; c e a; c e d"
    got = pairs(engine(spark, graph).forward(rules, strategy).view("t"))
    parsed = [parse_query(r) for r in rules]
    whole = brute.closure([(q.template, q.pattern) for q in parsed], triples(graph))
    assert got == {(f"<{t.s.value}>", f"<{t.o.value}>") for t in whole if t.p.value == "t"} and len(got) == 12


@pytest.mark.parametrize("strategy", ["demand", "tabled"])
@pytest.mark.parametrize("goal", [":a :t ?y", "?x :t :d", ":a :t :d", "?x :t ?y"])
def test_goal_directed_answers_equal_forward(spark, strategy, goal):
    e = engine(spark, "a e b; b e c; c e d; x e y; y e z")
    df, _ = e.backward(goal, CLOSURE, strategy)
    expected = Engine(spark, e.forward(CLOSURE).graph).query(f"SELECT * {{ {goal} }}")
    assert {tuple(sorted(r.asDict().items())) for r in df.collect()} == {tuple(sorted(r.asDict().items())) for r in expected.collect()} or not df.columns


def test_demand_leaves_other_branches_alone(spark):
    e = engine(spark, "; ".join(f"n{i} e n{i + 1}; m{i} e m{i + 1}" for i in range(6)))
    whole = e.forward(CLOSURE).derived_count()
    _, part = e.backward(":n4 :t ?y", CLOSURE)
    assert part.derived_count() < whole / 2


def test_negation_sees_the_finished_stratum(spark):
    e = engine(spark, "a e b; b e c; n node a; n node b; n node c")
    rules = [*CLOSURE, "CONSTRUCT { ?x :unreached ?x } WHERE { ?n :node ?x FILTER NOT EXISTS { :a :t ?x } }"]
    assert pairs(e.forward(rules).view("unreached")) == {("<a>", "<a>")}


def test_negative_cycle_is_rejected():
    rules = ["CONSTRUCT { ?x :q ?x } WHERE { ?x :n ?y FILTER NOT EXISTS { ?x :r ?x } }", "CONSTRUCT { ?x :r ?x } WHERE { ?x :n ?y FILTER NOT EXISTS { ?x :q ?x } }"]
    with pytest.raises(UnstratifiedRecursion):
        stratify(clauses_of([parse_query(r) for r in rules]))


def test_made_up_terms_end_by_depth_and_are_stable(spark):
    e = engine(spark, "a t n")
    rule = ["CONSTRUCT { ?x :t _:fresh } WHERE { ?y :t ?x }", ]
    got = e.forward(rule, max_skolem_depth=3).view("t")
    assert got.count() < 10
    once = e.query("CONSTRUCT { _:b :of ?x } WHERE { ?x :t ?y }").collect()
    assert once == e.query("CONSTRUCT { _:b :of ?x } WHERE { ?x :t ?y }").collect()


def test_round_limit(spark):
    e = engine(spark, "a e b; b e c; c e d; d e f")
    with pytest.raises(DepthExceeded):
        e.forward(CLOSURE, max_rounds=2)


def test_mixed_directions_and_native_rules(spark):
    e = engine(spark, "a e b; b e c; c k 7")
    rules = [*CLOSURE, "{ ?x :value ?v } <= { ?x :t ?y . ?y :k ?v } ."]
    assert {r["v"] for r in e.reason(rules, ":a :value ?v").collect()} == {'"7"^^integer'}
    native = "{ { ?x :e ?y } rt:union { ?y :e ?x } } => { ?x :near ?y } ."
    assert len(pairs(e.forward([native]).view("near"))) == 4


@pytest.mark.parametrize("name", ["bacon_any", "married_us_property", "geo_contained", "link_closure"])
@pytest.mark.parametrize("strategy", ["seminaive", "persistent"])
def test_workloads_equal_recursive_sql(spark, name, strategy):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "conversations", "pages"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    assert {tuple(r) for r in recursive.run(spark, SF, name, strategy).collect()} == {tuple(r) for r in con.execute(recursive.ORACLES[name]).fetchall()}


def test_incremental_closure_is_idempotent(spark):
    c = IncrementalClosure(spark)
    a = spark.createDataFrame([(1, 2), (3, 4)], "s bigint, o bigint")
    b = spark.createDataFrame([(2, 3)], "s bigint, o bigint")
    c(a, 0)
    c(b, 1)
    c(b, 1)
    assert pairs(c.result()) == {(1, 2), (3, 4), (2, 3), (1, 3), (1, 4), (2, 4)}


def test_streams_take_monotone_rules_only():
    with pytest.raises(NonMonotoneStreamingRule):
        check_monotone([parse_query("CONSTRUCT { ?x :a ?x } WHERE { ?x :p ?y MINUS { ?x :q ?z } }")])


def test_demanded_fraction_walks_the_chains_of_the_workload(spark):
    sf_dir = "/root/testdata/sf0.001"
    keys = {k for (k,) in duckdb.sql(f"select p_partkey from '{sf_dir}/part.parquet'").fetchall()}
    steps = 0
    for k in keys:
        while k in keys and k % 32 != 31:
            k, steps = k + 1, steps + 1
    (row,) = measures.demanded_fraction(spark, sf_dir).collect()
    # the given memberships are counted too
    assert row["forward_facts"] == len(keys) + steps and 0 < row["demanded_facts"] < steps
