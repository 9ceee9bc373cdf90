"""Plans and inputs that decide how queries behave on large tables."""

from rulegraph.operators import solutions as S
from rulegraph.workloads import registry

SMALL = "/root/testdata/sf0.001"


def test_a_cycle_is_not_joined_by_products(spark, monkeypatch):
    """Customers and suppliers of a nation are all pairs of both; orders and items come first."""
    met = []
    join = S.join
    monkeypatch.setattr(S, "join", lambda l, r, *a: (met.append(set(l.names) & set(r.names)), join(l, r, *a))[1])
    got = registry.queries()["bgp_triangle"](spark, SMALL)
    assert {"n"} not in met and {"s", "n"} in met
    assert got.count() == 59


def agrees(spark, name, sf_dir=SMALL):
    """Rows of a query, which equal its SQL's."""
    import duckdb

    con = duckdb.connect()
    for t in ("customer", "supplier", "part", "orders", "lineitem", "events", "nation", "region", "labels", "documents"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    df = registry.queries()[name](spark, sf_dir)
    got = sorted(map(repr, map(tuple, df.collect())))
    want = con.execute(registry.oracles()[name])
    assert [c[0] for c in want.description] == df.columns
    assert got == sorted(map(repr, want.fetchall()))
    assert df.inputFiles()
    return got


def test_repeated_variable_selects_rows_of_tables(spark):
    assert agrees(spark, "bgp_repeated_var")


def test_difference_example_over_tables(spark):
    got = agrees(spark, "listing1_minus")
    assert 0 < sum("whole" in r for r in got) < sum("control" in r for r in got)


def test_nested_optional_example_over_tables(spark):
    got = agrees(spark, "listing2_optional")
    assert {("whole" in r, "None" in r) for r in got} == {(True, True), (False, False)}


def test_rules_of_queries_over_values_of_a_table(spark):
    assert len(agrees(spark, "rules_of_queries")) == 8 * len(registry._translatable())


def over_values(spark, name):
    df = registry.queries()[name](spark, SMALL)
    assert df.inputFiles()
    rows = df.collect()
    assert {r["query"] for r in rows} <= set(registry._translatable()) and len({r["value"] for r in rows}) == 8
    return rows


def test_inventory_over_values_of_a_table(spark):
    rows = over_values(spark, "translate_inventory")
    assert all(r["rules"] == 1 for r in rows) and any((r["relational_rules"] or 0) > 1 for r in rows)


def test_round_trip_over_values_of_a_table(spark):
    rows = over_values(spark, "rule_text_roundtrip")
    assert all(r["same"] for r in rows) and any(r["value"] == "1-URGENT" and '"1-URGENT"' in r["rule"] for r in rows)


def test_encoding_over_values_of_a_table(spark):
    assert any("5-LOW" in r["o"] for r in over_values(spark, "triples_encoding") if r["value"] == "5-LOW")


def test_forms_are_tried_on_tables(spark):
    from rulegraph.plans.parser import COMPLIANCE

    agrees(spark, "compliance")
    assert {(r["form"], r["supported"]) for r in registry.compliance(spark, SMALL).collect()} == set(COMPLIANCE)
