"""The recursive workloads on the given tables: rules, goals and ways of running them.

Every workload is given as CONSTRUCT queries that feed one another and a predicate
or goal. ``run`` evaluates it by any strategy or baseline.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.baselines import loops
from rulegraph.engine import Engine
from rulegraph.sources.vocabulary import CONCEPT, PLACE, PLACE_UNIT


def bacon_root(spark: SparkSession, sf_dir: str) -> int:
    """The actor with most movies, the smallest key of equal ones."""
    cast = spark.read.parquet(f"{sf_dir}/lineitem.parquet").where("l_returnflag = 'R' and l_quantity > 25").select("l_partkey", "l_orderkey").distinct()
    best = cast.groupBy("l_partkey").count().orderBy(F.desc("count"), "l_partkey").first()
    return best["l_partkey"] if best else -1


def region_place(spark: SparkSession, sf_dir: str, name: str) -> int:
    r = spark.read.parquet(f"{sf_dir}/region.parquet").where(F.col("r_name") == name).select(F.min("r_regionkey")).first()[0]
    return PLACE["region"] * PLACE_UNIT + (-1 if r is None else r)


def first_page(spark: SparkSession, sf_dir: str) -> int:
    p = spark.read.parquet(f"{sf_dir}/pages.parquet").where(F.col("html").rlike('href="[^"]*"')).select(F.min("page_id")).first()[0]
    return -1 if p is None else p


@dataclass(frozen=True)
class Workload:
    """rules and the derived predicate, over the predicates it reads; ``goal`` binds an end."""

    name: str
    rules: Callable[[SparkSession, str], list[str]]
    predicate: str
    reads: tuple[str, ...]
    #: output columns from (s, o)
    columns: tuple[tuple[str, str], ...]
    goal: Callable[[SparkSession, str], str] | None = None


def _bacon(spark, d):
    r = f"<person{{{bacon_root(spark, d)}}}>"
    return [
        f"CONSTRUCT {{ ?x ex:bacon {r} }} WHERE {{ {r} ex:actedIn ?m . ?x ex:actedIn ?m }}",
        f"CONSTRUCT {{ ?y ex:bacon {r} }} WHERE {{ ?x ex:bacon {r} . ?x ex:actedIn ?m . ?y ex:actedIn ?m }}",
    ]


def _same_director(spark, d):
    r = f"<person{{{bacon_root(spark, d)}}}>"
    return [
        f"CONSTRUCT {{ ?x ex:chain ?d }} WHERE {{ {r} ex:actedIn ?m . ?m ex:directedBy ?d . ?x ex:actedIn ?m }}",
        "CONSTRUCT { ?y ex:chain ?d } WHERE { ?x ex:chain ?d . ?x ex:actedIn ?m . ?m ex:directedBy ?d . ?y ex:actedIn ?m }",
        "CONSTRUCT { ?x ex:chained ?x } WHERE { ?x ex:chain ?d }",
    ]


def _director_actor(spark, d):
    r = f"<person{{{bacon_root(spark, d)}}}>"
    return [
        "CONSTRUCT { ?x ex:actedUnderActor ?m } WHERE { ?x ex:actedIn ?m . ?m ex:directedBy ?d FILTER EXISTS { ?d ex:actedIn ?other } }",
        f"CONSTRUCT {{ ?x ex:bacon {r} }} WHERE {{ {r} ex:actedUnderActor ?m . ?x ex:actedUnderActor ?m }}",
        f"CONSTRUCT {{ ?y ex:bacon {r} }} WHERE {{ ?x ex:bacon {r} . ?x ex:actedUnderActor ?m . ?y ex:actedUnderActor ?m }}",
    ]


GEO = ["CONSTRUCT { ?x ex:within ?y } WHERE { ?x ex:locatedIn ?y }", "CONSTRUCT { ?x ex:within ?z } WHERE { ?x ex:within ?y . ?y ex:locatedIn ?z }"]
GEO_DOWN = ["CONSTRUCT { ?x ex:within ?y } WHERE { ?x ex:locatedIn ?y }", "CONSTRUCT { ?x ex:within ?z } WHERE { ?x ex:locatedIn ?y . ?y ex:within ?z }"]
TAXONOMY = ["CONSTRUCT { ?x ex:memberOf ?d } WHERE { ?x ex:memberOf ?c . ?c ex:subClassOf ?d }"]


def _married(spark, d):
    us = f"<place{{{region_place(spark, d, 'AMERICA')}}}>"
    return [
        *GEO,
        f"CONSTRUCT {{ ?y ex:ownsThere {us} }} WHERE {{ ?y ex:owns ?p . ?p ex:within {us} }}",
        f"CONSTRUCT {{ ?x ex:marriedToOwner {us} }} WHERE {{ ?x ex:marriedTo ?y . ?y ex:ownsThere {us} }}",
        f"CONSTRUCT {{ ?x ex:marriedToOwner {us} }} WHERE {{ ?x ex:marriedTo ?y . ?y ex:marriedToOwner {us} }}",
    ]


def _links(spark, d):
    r = f"<page{{{first_page(spark, d)}}}>"
    return [
        f"CONSTRUCT {{ ?y ex:reached {r} }} WHERE {{ {r} ex:linksTo ?t . ?y ex:linksTo ?t }}",
        f"CONSTRUCT {{ ?y ex:reached {r} }} WHERE {{ ?x ex:reached {r} . ?x ex:linksTo ?t . ?y ex:linksTo ?t }}",
    ]


ONTOLOGY = [
    "CONSTRUCT { ?c ex:under ?g } WHERE { ?c ex:broader ?g }",
    "CONSTRUCT { ?c ex:under ?h } WHERE { ?c ex:broader ?g . ?g ex:under ?h }",
    "CONSTRUCT { ?u ex:exposedTo ?h } WHERE { ?u ex:exposureConcept ?c . ?c ex:under ?h }",
]

WORKLOADS = {
    w.name: w
    for w in (
        Workload("bacon_any", _bacon, "ex:bacon", ("ex:actedIn",), (("person", "s"),), lambda s, d: f"?person ex:bacon <person{{{bacon_root(s, d)}}}>"),
        Workload("bacon_same_director", _same_director, "ex:chained", ("ex:actedIn", "ex:directedBy"), (("person", "s"),), lambda s, d: "?person ex:chained ?q"),
        Workload("bacon_director_actor", _director_actor, "ex:bacon", ("ex:actedIn", "ex:directedBy"), (("person", "s"),), lambda s, d: f"?person ex:bacon <person{{{bacon_root(s, d)}}}>"),
        Workload("geo_containers", lambda s, d: GEO, "ex:within", ("ex:locatedIn",), (("place", "s"), ("container", "o")), lambda s, d: "?place ex:within ?container"),
        Workload("geo_contained", lambda s, d: GEO_DOWN, "ex:within", ("ex:locatedIn",), (("place", "s"),), lambda s, d: f"?place ex:within <place{{{region_place(s, d, 'EUROPE')}}}>"),
        Workload("married_us_property", _married, "ex:marriedToOwner", ("ex:locatedIn", "ex:owns", "ex:marriedTo"), (("customer", "s"),), lambda s, d: f"?customer ex:marriedToOwner <place{{{region_place(s, d, 'AMERICA')}}}>"),
        Workload("screening_ontology", lambda s, d: ONTOLOGY, "ex:exposedTo", ("ex:broader", "ex:exposureConcept"), (("user", "s"),), lambda s, d: f"?user ex:exposedTo <concept{{{CONCEPT['chapter'] * PLACE_UNIT}}}>"),
        Workload("deep_taxonomy", lambda s, d: TAXONOMY, "ex:memberOf", ("ex:memberOf", "ex:subClassOf"), (("item", "s"),), lambda s, d: "?item ex:memberOf <class{31}>"),
        Workload("reply_thread", lambda s, d: ["CONSTRUCT { ?x ex:answers ?y } WHERE { ?x ex:repliesTo ?y }", "CONSTRUCT { ?x ex:answers ?z } WHERE { ?x ex:answers ?y . ?y ex:repliesTo ?z }"], "ex:answers", ("ex:repliesTo",), (("turn", "s"), ("ancestor", "o")), lambda s, d: "?turn ex:answers ?ancestor"),
        Workload("link_closure", _links, "ex:reached", ("ex:linksTo",), (("page", "s"),), lambda s, d: f"?page ex:reached <page{{{first_page(s, d)}}}>"),
        Workload("motivating_chain", lambda s, d: ["CONSTRUCT { ?x ex:isPreferred <ex:Preferred> } WHERE { ?x ex:isBuilding ?b }", "CONSTRUCT { ?x ex:isContactable <ex:Contactable> } WHERE { ?x ex:isPreferred ?p }"], "ex:isContactable", ("ex:isBuilding",), (("customer", "s"),), lambda s, d: "?customer ex:isContactable ?k"),
    )
}

STRATEGIES = ("seminaive", "naive", "doubling", "demand", "tabled", "unfold", "query_loop", "persistent")


def run(spark: SparkSession, sf_dir: str, name: str, strategy: str = "seminaive") -> DataFrame:
    """Answers of a workload's goal, by a strategy or a baseline; every way gives the same rows."""
    w = WORKLOADS[name]
    engine = Engine(spark).mapped_graph(sf_dir)
    texts, goal = w.rules(spark, sf_dir), w.goal(spark, sf_dir)
    if strategy in ("demand", "tabled", "unfold"):
        df, _ = engine.backward(goal, texts, strategy)
    elif strategy in ("seminaive", "naive", "doubling"):
        result = engine.forward(texts, strategy)
        df = Engine(spark, result.graph).query(f"SELECT * WHERE {{ {goal} }}")
    elif strategy == "query_loop":
        df = Engine(spark, loops.query_loop(engine.graph, engine.rules(texts), w.reads)).query(f"SELECT * WHERE {{ {goal} }}")
    elif strategy == "persistent":
        graph = loops.persistent_recursive(engine.graph, engine.rules(texts), w.reads)
        df = Engine(spark, graph).query(f"SELECT * WHERE {{ {goal} }}")
        df = df.select(*[F.regexp_extract(c, r"\{(-?\d+)\}", 1).cast("bigint").alias(c) for c, _ in w.columns])
    else:
        raise ValueError(f"unknown strategy {strategy}")
    return df.select(*[c for c, _ in w.columns]).distinct()


def bacon_depth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least number of steps from the root: the round in which semi-naive evaluation first finds a person."""
    w = WORKLOADS["bacon_any"]
    root = bacon_root(spark, sf_dir)
    result = Engine(spark).mapped_graph(sf_dir).forward(w.rules(spark, sf_dir), max_hops=1)
    rows = result.derived["ex:bacon"].df
    number = F.regexp_extract(F.input_file_name(), r"round=(\d+)/", 1).cast("bigint") + 1
    return rows.select(F.col("s").alias("person"), number.alias("depth")).where(F.col("person") != root)


#: Recursive SQL that gives each workload's rows, written from the tables alone.
_CAST = "casts as (select distinct l_partkey as a, l_orderkey as m from lineitem where l_returnflag = 'R' and l_quantity > 25), root as (select a from casts group by a order by count(*) desc, a limit 1)"
_U = PLACE_UNIT
_LOC = (
    f"loc as (select n_nationkey + {2 * _U} as s, n_regionkey + {1 * _U} as o from nation union all select c_custkey + {3 * _U}, c_nationkey + {2 * _U} from customer "
    f"union all select s_suppkey + {4 * _U}, s_nationkey + {2 * _U} from supplier union all select o_orderkey + {5 * _U}, o_custkey + {3 * _U} from orders)"
)
ORACLES = {
    "bacon_any": f"with recursive {_CAST}, t(a) as (select y.a from root r join casts x on x.a = r.a join casts y on y.m = x.m union select y.a from t join casts x on x.a = t.a join casts y on y.m = x.m) select distinct a::bigint as person from t",
    "bacon_depth": f"with recursive {_CAST}, t(a, depth) as (select y.a, 1 from root r join casts x on x.a = r.a join casts y on y.m = x.m union select y.a, depth + 1 from t join casts x on x.a = t.a join casts y on y.m = x.m where depth < 20) select t.a::bigint as person, min(depth)::bigint as depth from t, root where t.a <> root.a group by t.a",
    "bacon_same_director": f"with recursive {_CAST}, d as (select o_orderkey as m, o_custkey as d from orders), t(a, d) as (select y.a, d.d from root r join casts x on x.a = r.a join d on d.m = x.m join casts y on y.m = x.m union select y.a, t.d from t join casts x on x.a = t.a join d on d.m = x.m and d.d = t.d join casts y on y.m = x.m) select distinct a::bigint as person from t",
    "bacon_director_actor": f"with recursive {_CAST}, good as (select c.a, c.m from casts c join orders o on o.o_orderkey = c.m where exists (select 1 from casts k where k.a = 2 * o.o_custkey)), t(a) as (select y.a from root r join good x on x.a = r.a join good y on y.m = x.m union select y.a from t join good x on x.a = t.a join good y on y.m = x.m) select distinct a::bigint as person from t",
    "geo_containers": f"with recursive {_LOC}, t(s, o) as (select s, o from loc union select t.s, loc.o from t join loc on t.o = loc.s) select s::bigint as place, o::bigint as container from t",
    "geo_contained": f"with recursive {_LOC}, t(s) as (select s from loc where o = (select min(r_regionkey) + {_U} from region where r_name = 'EUROPE') union select loc.s from t join loc on loc.o = t.s) select s::bigint as place from t",
    "married_us_property": f"with recursive {_LOC}, b as (select distinct o_custkey as c, l_partkey as p, l_shipdate as d from lineitem join orders on l_orderkey = o_orderkey), mar as (select distinct x.c as s, y.c as o from b x join b y on x.p = y.p and x.d = y.d where x.c <> y.c), us(s) as (select s from loc where o = (select min(r_regionkey) + {_U} from region where r_name = 'AMERICA') union select loc.s from us join loc on loc.o = us.s), own as (select distinct o_custkey as c from lineitem join orders on l_orderkey = o_orderkey where l_returnflag = 'A' and l_quantity = 50 and l_suppkey + {4 * _U} in (select s from us)), t(s) as (select mar.s from mar join own on own.c = mar.o union select mar.s from t join mar on mar.o = t.s) select distinct s::bigint as customer from t",
    "screening_ontology": "with e as (select user_id, json_extract_string(props, '$.k')::bigint as k from events where event_type = 'purchase' and value > 150) select distinct user_id::bigint as \"user\" from e where (k // 10) // 5 = 0",
    "deep_taxonomy": "with recursive t(x, c) as (select p_partkey, p_partkey from part union select t.x, p.p_partkey + 1 from t join part p on p.p_partkey = t.c where p.p_partkey % 32 <> 31) select distinct x::bigint as item from t where c = 31",
    "reply_thread": "with recursive e as (select conv_id * 1000 + turn as s, conv_id * 1000 + turn - 1 as o from conversations where turn > 0), t(s, o) as (select s, o from e union select t.s, e.o from t join e on t.o = e.s) select s::bigint as turn, o::bigint as ancestor from t",
    "link_closure": "with recursive l as (select distinct page_id as p, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as h from pages), r as (select min(p) as p from l), t(p) as (select y.p from r join l x on x.p = r.p join l y on y.h = x.h union select y.p from t join l x on x.p = t.p join l y on y.h = x.h) select distinct p::bigint as page from t",
    "motivating_chain": "select c_custkey::bigint as customer from customer where c_mktsegment = 'BUILDING'",
}
