"""Graphs: a generic table of triples, or a virtual graph over ordinary tables.

A graph gives a view for each predicate: a DataFrame of distinct (s, o) with the
kinds of both columns. In a mapped graph an IRI is a template's tag and the
table's native key, so patterns become joins of native keys, and columns of
different templates never meet. In a generic graph terms are text.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.terms import Blank, Iri, Lit


@dataclass(frozen=True)
class Kind:
    """What a column holds: keys of an IRI template, literals of a datatype, or terms as text."""

    sort: str  # iri, lit or term
    name: str = ""

    def meets(self, other: Kind) -> bool:
        if "term" in (self.sort, other.sort):
            return self.sort == other.sort
        return self.sort == other.sort and (self.sort == "lit" or self.name == other.name)


TERM = Kind("term")


@dataclass(frozen=True)
class View:
    df: DataFrame
    s: Kind
    o: Kind
    #: the subject determines the row
    functional: bool = False


def term_text(t: object) -> str:
    """N-Triples form of a term."""
    if isinstance(t, Iri):
        return f"<{t.value}>"
    if isinstance(t, Blank):
        return f"_:{t.name}"
    v = str(t.value).lower() if isinstance(t.value, bool) else str(t.value)
    return f'"{v}"' if t.dt == "string" else f'"{v}"^^{t.dt}'


class Graph:
    """Predicate views; ``types`` (the predicate ``a``) are views (s, class name) by class."""

    spark: SparkSession

    def predicates(self) -> list[str]:
        raise NotImplementedError

    def view(self, predicate: str) -> View:
        raise NotImplementedError

    def constant(self, term: object, kind: Kind) -> Column | None:
        """The term as a value of a column of that kind; None if no such column can hold it."""
        if kind.sort == "term":
            return F.lit(term_text(term))
        if isinstance(term, Lit) and kind.sort == "lit":
            return F.lit(term.value)
        if isinstance(term, Iri) and kind.sort == "iri":
            name, _, key = term.value.partition("{")
            if key and name == kind.name:
                key = key.rstrip("}")
                return F.lit(int(key)).cast("bigint") if key.lstrip("-").isdigit() else F.lit(key)
            if not key and kind.name == "name":
                return F.lit(term.value)
        return None

    def all_triples(self) -> DataFrame:
        """Every triple as text (s, p, o)."""
        parts = None
        for p in self.predicates():
            v = self.view(p)
            df = v.df.select(to_text(F.col("s"), v.s).alias("s"), F.lit(f"<{p}>").alias("p"), to_text(F.col("o"), v.o).alias("o"))
            parts = df if parts is None else parts.unionByName(df)
        return parts.distinct() if parts is not None else self.spark.createDataFrame([], "s string, p string, o string")

    def with_views(self, views: dict[str, View]) -> OverlayGraph:
        return OverlayGraph(self, views)

    def check_proper(self) -> tuple[bool, DataFrame]:
        """Whether the graph is ground and free of rule-language predicates, with the rows that are not."""
        t = self.all_triples()
        bad = t.where(F.col("s").startswith("_:") | F.col("o").startswith("_:") | F.col("p").rlike("^<(rt|math):"))
        return bad.limit(1).count() == 0, bad


def to_text(c: Column, kind: Kind) -> Column:
    if kind.sort == "term":
        return c
    if kind.sort == "iri":
        if kind.name == "name":
            return F.concat(F.lit("<"), c, F.lit(">"))
        return F.concat(F.lit(f"<{kind.name}{{"), c.cast("string"), F.lit("}>"))
    if kind.name == "string":
        return F.concat(F.lit('"'), c, F.lit('"'))
    return F.concat(F.lit('"'), c.cast("string"), F.lit(f'"^^{kind.name}'))


class MappedGraph(Graph):
    """A virtual graph: views are built from tables when a pattern asks for them."""

    def __init__(self, spark: SparkSession, views: dict[str, Callable[[], View]], lists: dict[str, str] | None = None):
        self.spark, self._make, self._made = spark, views, {}

    def predicates(self) -> list[str]:
        return list(self._make)

    def view(self, predicate: str) -> View | None:
        if predicate not in self._made:
            self._made[predicate] = self._make[predicate]() if predicate in self._make else None
        return self._made[predicate]


class TripleGraph(Graph):
    """Triples as text (s, p, o), as a set."""

    def __init__(self, df: DataFrame):
        self.spark, self.df = df.sparkSession, df
        self._known: list[str] | None = None

    @classmethod
    def of(cls, spark: SparkSession, triples) -> TripleGraph:
        rows = [(term_text(t.s), term_text(t.p), term_text(t.o)) for t in triples]
        return cls(spark.createDataFrame(rows, "s string, p string, o string"))

    def predicates(self) -> list[str]:
        if self._known is None:
            self._known = sorted(r["p"][1:-1] for r in self.df.select("p").distinct().collect())
        return self._known

    def view(self, predicate: str) -> View:
        return View(self.df.where(F.col("p") == f"<{predicate}>").select("s", "o").distinct(), TERM, TERM)

    def all_triples(self) -> DataFrame:
        return self.df.select("s", "p", "o").distinct()

    def write(self, path: str) -> None:
        """Parquet, a folder for each predicate, sorted by subject."""
        self.df.distinct().repartition("p").sortWithinPartitions("p", "s").write.partitionBy("p").mode("overwrite").parquet(path)

    @classmethod
    def read(cls, spark: SparkSession, path: str) -> TripleGraph:
        return cls(spark.read.schema("s string, o string, p string").parquet(path).select("s", "p", "o"))


class OverlayGraph(Graph):
    """A graph with some views added or replaced."""

    def __init__(self, base: Graph, views: dict[str, View]):
        self.spark, self.base, self.views = base.spark, base, views

    def predicates(self) -> list[str]:
        return list(dict.fromkeys([*self.base.predicates(), *(p for p in self.views if not p.startswith("Δ"))]))

    def view(self, predicate: str) -> View | None:
        return self.views[predicate] if predicate in self.views else self.base.view(predicate)

    def constant(self, term: object, kind: Kind) -> Column | None:
        return self.base.constant(term, kind)


# ---------------------------------------------------------------- formats

_NT = r"^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|\"(?:[^\"\\]|\\.)*\"(?:\^\^\S+|@\S+)?)\s*\.\s*$"


def read_ntriples(spark: SparkSession, path: str) -> TripleGraph:
    """Lines of N-Triples by column expressions alone; comments and broken lines give no triple."""
    line = spark.read.text(path).where(F.col("value").rlike(_NT))
    return TripleGraph(line.select(*[F.regexp_extract("value", _NT, i + 1).alias(n) for i, n in enumerate("spo")]))


#: Behind a separator, as many quotes as close one another.
_OUTSIDE = r'(?=(?:[^"]*"[^"]*")*[^"]*$)'


def read_turtle(spark: SparkSession, path: str) -> TripleGraph:
    """A subset of Turtle: @prefix lines, ``a``, lists with ``;`` and ``,``, numbers and booleans; a statement ends with " ." at a line's end.

    Prefixes are read first (a file has few); statements go through column expressions alone.
    Nested blank nodes, collections, long strings and escaped quotes are not covered.
    """
    text = spark.read.option("lineSep", " .\n").text(path).select(F.trim(F.regexp_replace(F.regexp_replace("value", r"(?m)^\s*#.*$", ""), r"\s+", " ")).alias("value"))
    text = text.select(F.regexp_replace("value", r"\s*\.$", "").alias("value"))
    prefix = r"^@prefix\s+([^:\s]*):\s+<([^>]*)>"
    names = {r[0]: r[1] for r in text.where(F.col("value").rlike(prefix)).select(F.regexp_extract("value", prefix, 1), F.regexp_extract("value", prefix, 2)).collect()}
    iris = F.create_map(*[F.lit(x) for kv in names.items() for x in kv]) if names else F.create_map(F.lit(""), F.lit(""))

    def term(c: Column) -> Column:
        short = F.regexp_extract(c, r"^([^:\s\"<]*):(.*)$", 1)
        return (
            F.when(c == "a", F.lit("<a>"))
            .when(c.rlike(r"^[+-]?\d+$"), F.concat(F.lit('"'), c, F.lit('"^^integer')))
            .when(c.rlike(r"^[+-]?\d*\.\d+$"), F.concat(F.lit('"'), c, F.lit('"^^decimal')))
            .when(c.isin("true", "false"), F.concat(F.lit('"'), c, F.lit('"^^boolean')))
            .when(c.startswith("<") | c.startswith('"') | c.startswith("_:"), c)
            .otherwise(F.concat(F.lit("<"), F.element_at(iris, short), F.regexp_extract(c, r"^[^:\s]*:(.*)$", 1), F.lit(">")))
        )

    first = r"^(\S+)\s+(.*)$"
    lines = text.where((F.col("value") != "") & ~F.col("value").startswith("@"))
    lines = lines.select(F.regexp_extract("value", first, 1).alias("s"), F.regexp_extract("value", first, 2).alias("rest"))
    lines = lines.select("s", F.explode(F.split("rest", r"\s*;\s*" + _OUTSIDE)).alias("part")).where("part != ''")
    lines = lines.select("s", F.regexp_extract("part", first, 1).alias("p"), F.explode(F.split(F.regexp_extract("part", first, 2), r"\s*,\s*" + _OUTSIDE)).alias("o"))
    return TripleGraph(lines.select(*[term(F.trim(F.col(c))).alias(c) for c in "spo"]).where("s is not null and p is not null and o is not null"))


def write_ntriples(graph: Graph, path: str) -> None:
    graph.all_triples().select(F.concat_ws(" ", "s", "p", "o", F.lit(".")).alias("value")).write.mode("overwrite").text(path)


def read_table(spark: SparkSession, path: str, kind: str = "parquet") -> TripleGraph:
    """Columns s, p, o of text from Parquet, CSV or JSON."""
    reader = spark.read.option("header", True) if kind == "csv" else spark.read
    return TripleGraph(getattr(reader.schema("s string, p string, o string"), kind)(path))


def typed(view: View, **kinds: Kind) -> View:
    return replace(view, **kinds)
