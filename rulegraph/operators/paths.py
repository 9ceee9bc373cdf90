"""Property paths as predicate views, and closures of binary relations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulegraph.plans import algebra as A
from rulegraph.sources.graphs import TERM, Graph, View, to_text
from rulegraph.storage import cut, drop_cut, new_path, remove


def closure(edges: DataFrame, *, doubling: bool = False, max_rounds: int = 1000) -> DataFrame:
    """Pairs (s, o) joined by one or more edges.

    By default each round joins the pairs found last with the edges, so every
    edge is used once for each pair; with ``doubling`` all pairs are joined with all,
    in as many rounds as the logarithm of the longest path. Rounds are
    written next to each other in one folder; a round reads the others through it.
    """
    spark = edges.sparkSession
    edges = cut(edges.select("s", "o").distinct())
    path = new_path(spark, "closure")
    edges.write.parquet(f"{path}/round=0")
    delta, rounds = edges, 0
    while True:
        rounds += 1
        known = spark.read.schema(edges.schema).parquet(*[f"{path}/round={r}" for r in range(rounds)])
        step = known if doubling else edges
        first = delta if not doubling else known
        new = first.alias("a").join(step.alias("b"), F.col("a.o") == F.col("b.s")).select(F.col("a.s").alias("s"), F.col("b.o").alias("o")).distinct().join(known, ["s", "o"], "left_anti")
        new.write.parquet(f"{path}/round={rounds}")
        delta = spark.read.schema(edges.schema).parquet(f"{path}/round={rounds}")
        if delta.limit(1).count() == 0:
            break
        if rounds >= max_rounds:
            raise RuntimeError(f"no end after {max_rounds} rounds")
    return known.select("s", "o")


#: Rows up to which a frontier may take several steps in one job.
HOP_ROWS = 100_000


def reachable(edges: DataFrame, start: DataFrame, max_rounds: int = 1000, hops: int = 8) -> DataFrame:
    """(x,) reached from start's x by one or more edges: a frontier that never visits twice.

    While it is small, one job takes it two, four, up to ``hops`` steps on: rows keep the
    number of steps they took, and each step hands on what it came from along with
    what it found, so the plan is one chain of joins. Those that took all steps are
    where the next job starts.
    """
    edges = cut(edges.select("s", "o").distinct())
    spark = edges.sparkSession
    path = new_path(spark, "reach")
    frontier, folders, rounds, many = start.select("x", F.lit(0).alias("d")).distinct(), [], 0, 1
    rows = None
    while True:
        if rounds >= max_rounds:
            raise RuntimeError(f"no end after {max_rounds} rounds")
        many = min(2 * many, hops, max_rounds - rounds) if rows is not None and rows <= HOP_ROWS else 1
        found = frontier
        for k in range(many):
            # d = 0 are the starting points themselves, which count only if an edge leads to them
            step = F.array(F.struct("x", "d"), F.struct(F.col("o").alias("x"), (F.col("d") + 1).alias("d")))
            ahead = F.col("d") == k
            found = found.join(edges, (F.col("x") == F.col("s")) & ahead, "left").select(F.explode(step).alias("r")).select("r.x", "r.d").where("x is not null")
            found = found.groupBy("x", (F.col("d") == 0).alias("first")).agg(F.min("d").alias("d")).select("x", "d")
        found = found.where("d > 0")
        if folders:
            found = found.join(spark.read.schema(schema).parquet(*folders).select("x"), "x", "left_anti")
        schema = found.schema
        folders.append(f"{path}/round={rounds}")
        found.write.parquet(folders[-1])
        rounds += many
        frontier = spark.read.schema(schema).parquet(folders[-1]).where(F.col("d") == many).select("x", F.lit(0).alias("d"))
        rows = frontier.count()
        if rows == 0:
            break
    drop_cut(edges)
    return spark.read.schema(schema).parquet(*folders).select("x").distinct()


def reachable_by_doubling(edges: DataFrame, start: DataFrame, max_rounds: int = 60) -> DataFrame:
    """The same where one end of an edge determines the other: steps of 1, 2, 4 and so on, each made of the one before.

    Such a relation's powers never have more rows than itself, so the rounds are as many
    as the logarithm of the longest path, and each is two joins. Whatever is farther
    than the nodes found so far has a node at each distance before it, so a
    round that finds nothing new is the last.
    """
    leap = cut(edges.select("s", "o").distinct())
    spark = edges.sparkSession
    path = new_path(spark, "leap")
    begin, folders = start.select("x").distinct(), []
    for r in range(max_rounds):
        seen = spark.read.schema(schema).parquet(*folders) if folders else None
        at = begin if seen is None else begin.unionByName(seen)
        found = at.join(leap, F.col("x") == F.col("s")).select(F.col("o").alias("x")).distinct()
        if seen is not None:
            found = found.join(seen, "x", "left_anti")
        schema = found.schema
        folders.append(f"{path}/round={r}")
        found.write.parquet(folders[-1])
        if spark.read.schema(schema).parquet(folders[-1]).limit(1).count() == 0:
            break
        last, leap = leap, cut(leap.alias("a").join(leap.alias("b"), F.col("a.o") == F.col("b.s")).select(F.col("a.s").alias("s"), F.col("b.o").alias("o")))
        drop_cut(last)
    else:
        raise RuntimeError(f"no end after {max_rounds} rounds")
    drop_cut(leap)
    return spark.read.schema(schema).parquet(*folders)


def one_ended(edges: DataFrame) -> bool:
    """Whether one end of each edge determines the other."""
    for end, other in (("s", "o"), ("o", "s")):
        if not edges.groupBy(end).agg(F.min(other).alias("a"), F.max(other).alias("z")).where("a != z").limit(1).count():
            return True
    return False


def path_view(graph: Graph, p: A.Path, s: object = None, o: object = None) -> View:
    """The pairs that a path joins. A bound end makes closures start there."""
    go = lambda x, a=None, b=None: path_view(graph, x, a, b)
    if p.op == "link":
        v = graph.view(p.args[0].value)
        if v is None:
            raise KeyError(p.args[0].value)
        return v
    if p.op == "inv":
        v = go(p.args[0], o, s)
        return View(v.df.select(F.col("o").alias("s"), F.col("s").alias("o")), v.o, v.s)
    if p.op == "seq":
        v = go(p.args[0])
        for x in p.args[1:]:
            w = go(x)
            if not v.o.meets(w.s):
                return View(v.df.select("s").crossJoin(w.df.select("o")).limit(0), v.s, w.o)
            df = v.df.alias("a").join(w.df.alias("b"), F.col("a.o") == F.col("b.s")).select(F.col("a.s").alias("s"), F.col("b.o").alias("o"))
            v = View(df.distinct(), v.s, w.o)
        return v
    if p.op == "alt":
        views = [go(x) for x in p.args]
        df = views[0].df.select("s", "o")
        for w in views[1:]:
            df = df.unionByName(w.df.select("s", "o"))
        return View(df.distinct(), views[0].s, views[0].o)
    if p.op == "neg":
        no = {x.args[0].value for x in p.args if x.op == "link"}
        back = {x.args[0].args[0].value for x in p.args if x.op == "inv"}
        views = [v for name in graph.predicates() if name not in no and (v := graph.view(name)) is not None]
        if back:
            views += [View(v.df.select(F.col("o").alias("s"), F.col("s").alias("o")), v.o, v.s) for name in graph.predicates() if name not in back and (v := graph.view(name)) is not None]
        # ends of several kinds are only comparable as text
        same = all(v.s == views[0].s and v.o == views[0].o for v in views)
        out = None
        for v in views:
            df = v.df.select("s", "o") if same else v.df.select(to_text(F.col("s"), v.s).alias("s"), to_text(F.col("o"), v.o).alias("o"))
            out = df if out is None else out.unionByName(df)
        return View(out.distinct(), views[0].s if same else TERM, views[0].o if same else TERM)
    v = go(p.args[0])
    zero = v.df.select(F.col("s").alias("x")).unionByName(v.df.select(F.col("o").alias("x"))).distinct().select(F.col("x").alias("s"), F.col("x").alias("o")) if v.s.meets(v.o) else None
    if p.op == "opt":
        return View(v.df.select("s", "o").unionByName(zero).distinct(), v.s, v.o)
    if s is not None:
        const = graph.constant(s, v.s)
        start = v.df.select(const.alias("x")).limit(1)
        got = reachable(v.df, start).select(const.alias("s"), F.col("x").alias("o"))
    elif o is not None:
        const = graph.constant(o, v.o)
        back = v.df.select(F.col("o").alias("s"), F.col("s").alias("o"))
        got = reachable(back, v.df.select(const.alias("x")).limit(1)).select(F.col("x").alias("s"), const.alias("o"))
    else:
        # both ends free: few rounds matter more than joining each pair once
        got = closure(v.df, doubling=True)
    if p.op == "plus":
        return View(got, v.s, v.o)
    return View(got.unionByName(zero).distinct(), v.s, v.o)


def drop_path(spark, path: str) -> None:
    remove(spark, path)
