"""The systems that the rule engine is compared with, as ways of running the same rules."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import functions as F

from rulegraph.plans.compile import Compiler
from rulegraph.plans.reason import DepthExceeded, Reasoner, clauses_of, stratify
from rulegraph.plans.translate import relational_rules
from rulegraph.sources.graphs import Graph, MappedGraph, TripleGraph, View, to_text
from rulegraph.storage import cut, new_path
from rulegraph.terms import Rule


def query_loop(graph: Graph, rules: list[Rule], reads: tuple[str, ...], max_rounds: int = 500) -> Graph:
    """A query engine in a loop: the graph in memory, every rule over all facts in each round, forward only."""
    held = {}
    for p in reads:
        v = graph.view(p)
        held[p] = View(v.df.select("s", "o").persist(StorageLevel.MEMORY_AND_DISK), v.s, v.o, v.functional)
    base = MappedGraph(graph.spark, {p: (lambda v=v: v) for p, v in held.items()})
    base.constant = graph.constant
    clauses = clauses_of(rules)
    known: dict[str, View] = {}
    sizes: dict[str, int] = {}
    try:
        # negation still needs the strata below to be finished
        for group in stratify(clauses):
            for _ in range(max_rounds):
                now = base.with_views(known)
                reasoner = Reasoner(now)
                ready = [c for c in group if _ready(c, now)]
                grown = False
                for p, v in reasoner._gather(ready, now).items():
                    df = v.df.select("s", "o")
                    if p in known:
                        df = df.unionByName(known[p].df.select("s", "o"))
                    elif p in held:
                        df = df.unionByName(held[p].df.select("s", "o"))
                    made = cut(df.distinct())
                    n = made.count()
                    grown |= n != sizes.get(p, -1)
                    known[p], sizes[p] = View(made, v.s, v.o), n
                if not grown:
                    break
            else:
                raise DepthExceeded(f"no end after {max_rounds} rounds")
    finally:
        for v in held.values():
            v.df.unpersist()
    return graph.with_views(known)


def _ready(c, graph: Graph) -> bool:
    from rulegraph.plans.reason import uses

    return all(not pos or p == "*" or p in graph.predicates() for p, pos in uses(c.body))


def load_triples(graph: Graph, reads: tuple[str, ...], path: str) -> TripleGraph:
    """The load phase of a triple database: the predicates as text, a sorted folder for each."""
    parts = None
    for p in reads:
        v = graph.view(p)
        df = v.df.select(to_text(F.col("s"), v.s).alias("s"), F.lit(f"<{p}>").alias("p"), to_text(F.col("o"), v.o).alias("o"))
        parts = df if parts is None else parts.unionByName(df)
    TripleGraph(parts).write(path)
    return TripleGraph.read(graph.spark, path)


class _Stored(TripleGraph):
    """Views read their folder again each time."""

    def __init__(self, spark, folders: dict[str, list[str]]):
        self.spark, self.folders = spark, folders

    def predicates(self) -> list[str]:
        return sorted(self.folders)

    def view(self, predicate: str) -> View | None:
        from rulegraph.sources.graphs import TERM

        if predicate not in self.folders:
            return None
        return View(self.spark.read.schema("s string, o string").parquet(*self.folders[predicate]), TERM, TERM)


def persistent_recursive(graph: Graph, rules: list[Rule], reads: tuple[str, ...], path: str | None = None, max_rounds: int = 500) -> TripleGraph:
    """Recursive queries over a persistent triple database: loaded first, read from storage in every round, new triples appended."""
    spark = graph.spark
    path = path or new_path(spark, "triples")
    load_triples(graph, reads, path)
    stored = _Stored(spark, {p: [f"{path}/p={_escaped(p)}"] for p in reads})
    clauses, number = clauses_of(rules), 0
    for group in stratify(clauses):
        for _ in range(max_rounds):
            ready = [c for c in group if _ready(c, stored)]
            found = Reasoner(stored)._gather(ready, stored)
            grown = False
            for p, v in found.items():
                new = v.df.select("s", "o").distinct()
                old = stored.view(p)
                if old is not None:
                    new = new.join(old.df, ["s", "o"], "left_anti")
                number += 1
                target = f"{path}/derived/{number}"
                new.write.parquet(target)
                if spark.read.parquet(target).limit(1).count():
                    stored.folders[p] = [*stored.folders.get(p, []), target]
                    grown = True
            if not grown:
                break
        else:
            raise DepthExceeded(f"no end after {max_rounds} rounds")
    return stored


def _escaped(p: str) -> str:
    """Folder name of a predicate's partition, as the writer escapes it."""
    return "".join(f"%{ord(c):02X}" if c in ':"#%\'*/=?\\{[]^' else c for c in f"<{p}>")


def datalog_sql(graph: Graph, query, name: str = "q"):
    """A query by plain relational rules, one for each choice of branches: (solutions, number of rules)."""
    rules = relational_rules(query, name)
    from rulegraph.plans import algebra as A
    from rulegraph.plans.translate import expand

    comp, out = Compiler(graph), None
    names = list(query.template) if query.form == "select" else list(A.scope(query.pattern))
    for r in rules:
        sol = comp.query(A.Query("select", tuple(names), expand(r)))
        out = sol.df if out is None else out.unionByName(sol.df)
    return out.distinct(), len(rules)
