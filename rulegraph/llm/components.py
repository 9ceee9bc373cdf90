"""Connected components of a graph whose edges are rows, without collecting them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulegraph.llm.common import cut, drop_cut


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of an edge, root being the smallest node of its component.

    Alternates large-star and small-star steps (each links a node's neighbours to
    the smallest of them) until every edge points at a root and no node has two.
    Each round is two pre-aggregated minima and two joins; hubs are never gathered
    in one row. An empty edge table gives an empty result; loops and repeated edges
    are fine. Raises RuntimeError if max_rounds do not reach the end.
    """
    both = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
    now = cut(both.where("u != v").distinct())
    for _ in range(max_rounds):
        either = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = either.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("m", "u").alias("m"))
        large = either.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        new = cut(small.where("u != v").distinct())
        # done when no node is both a child and a parent and each child has one parent
        mixed = new.join(new.select(F.col("v").alias("u")).distinct(), "u", "left_semi").limit(1).count() or new.groupBy("u").agg(F.min("v").alias("a"), F.max("v").alias("z")).where("a != z").limit(1).count()
        drop_cut(now)
        now = new
        if not mixed:
            break
    else:
        raise RuntimeError(f"no end after {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
