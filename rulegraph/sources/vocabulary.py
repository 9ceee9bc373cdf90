"""The virtual vocabulary of the given tables: predicates over native keys.

Places of several tables share one template: the table's number stands above the
key, so that a single bigint column serves the recursive predicate ``locatedIn``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.sources.graphs import Kind, MappedGraph, View

PLACE = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "order": 5}
PLACE_UNIT = 1 << 40
CONCEPT = {"code": 1, "group": 2, "chapter": 3}


def place(kind: str, key: Column) -> Column:
    return key.cast("bigint") + F.lit(PLACE[kind] * PLACE_UNIT)


def concept(kind: str, key: Column) -> Column:
    return key.cast("bigint") + F.lit(CONCEPT[kind] * PLACE_UNIT)


def iri(name: str) -> Kind:
    return Kind("iri", name)


def lit(name: str) -> Kind:
    return Kind("lit", name)


def tables_graph(spark: SparkSession, sf_dir: str, chain: int = 32) -> MappedGraph:
    """The mapped graph over a folder of the given tables; ``chain`` is the length of the class chains."""
    cache: dict[str, DataFrame] = {}

    def t(name: str) -> DataFrame:
        if name not in cache:
            cache[name] = spark.read.parquet(f"{sf_dir}/{name}.parquet")
        return cache[name]

    def pair(df: DataFrame, s, o, sk: Kind, ok: Kind, distinct: bool = True, functional: bool = False) -> View:
        s, o = (F.col(x) if isinstance(x, str) else x for x in (s, o))
        out = df.select(s.alias("s"), o.alias("o")).where("s is not null and o is not null")
        return View(out.distinct() if distinct else out, sk, ok, functional)

    def attribute(table: str, key: str, template: str, col, kind: Kind):
        """A column of a table whose key is unique: no distinct is needed."""
        c = F.col(col) if isinstance(col, str) else col
        if kind.sort == "iri" or kind.name == "integer":
            c = c.cast("bigint") if kind.name not in ("name",) else c
        return lambda: pair(t(table), F.col(key).cast("bigint"), c, iri(template), kind, distinct=False, functional=True)

    def located() -> View:
        n, c, s, o = t("nation"), t("customer"), t("supplier"), t("orders")
        parts = [
            n.select(place("nation", F.col("n_nationkey")).alias("s"), place("region", F.col("n_regionkey")).alias("o")),
            c.select(place("customer", F.col("c_custkey")).alias("s"), place("nation", F.col("c_nationkey")).alias("o")),
            s.select(place("supplier", F.col("s_suppkey")).alias("s"), place("nation", F.col("s_nationkey")).alias("o")),
            o.select(place("order", F.col("o_orderkey")).alias("s"), place("customer", F.col("o_custkey")).alias("o")),
        ]
        df = parts[0]
        for p in parts[1:]:
            df = df.unionByName(p)
        return View(df.where("s is not null and o is not null"), iri("place"), iri("place"), True)

    def married() -> View:
        bought = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("c"), F.col("l_partkey").alias("p"), F.col("l_shipdate").alias("d")).distinct()
        a, b = bought.select(F.col("c").alias("s"), "p", "d"), bought.select(F.col("c").alias("o"), "p", "d")
        return View(a.join(b, ["p", "d"]).where("s <> o").select("s", "o").distinct(), iri("customer"), iri("customer"))

    def owns() -> View:
        df = t("lineitem").where("l_returnflag = 'A' and l_quantity = 50").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        return pair(df, "o_custkey", place("supplier", F.col("l_suppkey")), iri("customer"), iri("place"))

    def event(kind: str, where: str = "true", obj: str = "ts", ok: Kind = lit("dateTime")):
        k = F.get_json_object("props", "$.k").try_cast("bigint")
        return lambda: pair(t("events").withColumn("k", k).where(f"event_type = '{kind}'").where(where), "user_id", obj, iri("user"), ok)

    def links() -> View:
        href = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
        return pair(t("pages").select("page_id", href.alias("href")), "page_id", "href", iri("page"), lit("string"))

    def broader() -> View:
        """Exposure codes below groups of ten, groups below chapters of five groups."""
        k = t("events").select(F.get_json_object("props", "$.k").try_cast("bigint").alias("k")).where("k is not null").distinct()
        g = k.select(F.floor(F.col("k") / 10).cast("bigint").alias("g")).distinct()
        up = k.select(concept("code", F.col("k")).alias("s"), concept("group", F.floor(F.col("k") / 10)).alias("o"))
        return View(up.unionByName(g.select(concept("group", F.col("g")).alias("s"), concept("chapter", F.floor(F.col("g") / 5)).alias("o"))), iri("concept"), iri("concept"), True)

    def typed(name: str, table: str, key: str, where: str | None = None):
        def make() -> View:
            df = t(table).where(where) if where else t(table)
            return View(df.select(F.col(key).cast("bigint").alias("s"), F.lit(name).alias("o")), iri(key.split("_", 1)[1].removesuffix("key")), iri("name"), True)

        return make

    cents = lambda c: (F.round(F.col(c) * 100)).cast("bigint")
    code = F.get_json_object("props", "$.k").try_cast("bigint")
    views = {
        "ex:actedIn": lambda: pair(t("lineitem").where("l_returnflag = 'R' and l_quantity > 25"), "l_partkey", "l_orderkey", iri("person"), iri("movie")),
        "ex:directedBy": lambda: pair(t("orders"), "o_orderkey", F.col("o_custkey") * 2, iri("movie"), iri("person"), distinct=False, functional=True),
        "ex:locatedIn": located,
        "ex:marriedTo": married,
        "ex:owns": owns,
        "ex:subClassOf": lambda: pair(t("part").where(f"p_partkey % {chain} <> {chain - 1}"), "p_partkey", F.col("p_partkey") + 1, iri("class"), iri("class"), distinct=False, functional=True),
        "ex:memberOf": lambda: pair(t("part"), "p_partkey", "p_partkey", iri("item"), iri("class"), distinct=False, functional=True),
        "ex:repliesTo": lambda: pair(t("conversations").where("turn > 0"), F.col("conv_id") * 1000 + F.col("turn"), F.col("conv_id") * 1000 + F.col("turn") - 1, iri("turn"), iri("turn"), distinct=False, functional=True),
        "ex:symptom": event("error", "value > 100"),
        "ex:exposure": event("purchase", "k < 10"),
        "ex:pregnant": event("signup", "value > 150", "ts"),
        "ex:tested": event("click", "value > 170"),
        "ex:exposureConcept": lambda: pair(t("events").where("event_type = 'purchase' and value > 150"), "user_id", concept("code", code), iri("user"), iri("concept")),
        "ex:broader": broader,
        "ex:coding": lambda: pair(t("events").where("event_type = 'purchase'").select("user_id", F.explode(F.array(F.struct(F.lit("k").alias("system"), code.alias("code"), F.col("ts").alias("at")))).alias("c")).where("c.code < 10"), "user_id", "c.at", iri("user"), lit("dateTime")),
        "ex:text": attribute("documents", "doc_id", "doc", "text", lit("string")),
        "ex:lang": attribute("documents", "doc_id", "doc", "lang", lit("string")),
        "ex:source": attribute("documents", "doc_id", "doc", "source", lit("string")),
        "ex:quality": attribute("labels", "doc_id", "doc", "quality", lit("integer")),
        "ex:toxic": attribute("labels", "doc_id", "doc", "toxic", lit("integer")),
        "ex:linksTo": links,
        "ex:placedBy": attribute("orders", "o_orderkey", "order", "o_custkey", iri("customer")),
        "ex:status": attribute("orders", "o_orderkey", "order", "o_orderstatus", lit("string")),
        "ex:total": attribute("orders", "o_orderkey", "order", "o_totalprice", lit("double")),
        "ex:totalCents": attribute("orders", "o_orderkey", "order", cents("o_totalprice"), lit("integer")),
        "ex:date": attribute("orders", "o_orderkey", "order", "o_orderdate", lit("dateTime")),
        "ex:priority": attribute("orders", "o_orderkey", "order", "o_orderpriority", lit("string")),
        "ex:hasPart": lambda: pair(t("lineitem"), "l_orderkey", "l_partkey", iri("order"), iri("part")),
        "ex:hasSupplier": lambda: pair(t("lineitem"), "l_orderkey", "l_suppkey", iri("order"), iri("supplier")),
        "ex:returnFlag": lambda: pair(t("lineitem"), "l_orderkey", "l_returnflag", iri("order"), lit("string")),
        "ex:customerName": attribute("customer", "c_custkey", "customer", "c_name", lit("string")),
        "ex:customerNation": attribute("customer", "c_custkey", "customer", "c_nationkey", iri("nation")),
        "ex:balance": attribute("customer", "c_custkey", "customer", "c_acctbal", lit("double")),
        "ex:segment": attribute("customer", "c_custkey", "customer", "c_mktsegment", lit("string")),
        "ex:supplierNation": attribute("supplier", "s_suppkey", "supplier", "s_nationkey", iri("nation")),
        "ex:supplierBalance": attribute("supplier", "s_suppkey", "supplier", "s_acctbal", lit("double")),
        "ex:nationName": attribute("nation", "n_nationkey", "nation", "n_name", lit("string")),
        "ex:nationRegion": attribute("nation", "n_nationkey", "nation", "n_regionkey", iri("region")),
        "ex:regionName": attribute("region", "r_regionkey", "region", "r_name", lit("string")),
        "ex:partName": attribute("part", "p_partkey", "part", "p_name", lit("string")),
        "ex:partSize": attribute("part", "p_partkey", "part", "p_size", lit("integer")),
        "ex:partType": attribute("part", "p_partkey", "part", "p_type", lit("string")),
        "ex:passage": attribute("benchmark", "item_id", "item", "text", lit("string")),
        "ex:label": attribute("embeddings", "vec_id", "vec", "label", lit("integer")),
        "ex:vector": lambda: View(t("embeddings").select(F.col("vec_id").alias("s"), F.col("embedding").alias("o")), iri("vec"), lit("list"), True),
        "ex:isBuilding": typed("ex:Building", "customer", "c_custkey", "c_mktsegment = 'BUILDING'"),
        "ex:isCustomer": typed("ex:Customer", "customer", "c_custkey"),
    }
    fix = {"ex:isBuilding": "customer", "ex:isCustomer": "customer"}
    for p, name in fix.items():
        views[p] = lambda make=views[p], name=name: View(make().df, iri(name), iri("name"), True)
    return MappedGraph(spark, views)
