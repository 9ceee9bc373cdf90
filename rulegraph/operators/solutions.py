"""Solutions: tables whose columns are variables, and the operators of the algebra on them.

A variable that a solution leaves unbound is NULL. Two solutions are compatible
where both bind a variable only if they agree; joins of sides that may leave a
shared variable unbound are split by which variables are bound, so that each part is
an equi-join (never a join on ``a = b or a is null``, which would compare all pairs).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulegraph.sources.graphs import Kind


@dataclass(frozen=True)
class Solutions:
    df: DataFrame
    kinds: dict[str, Kind]
    certain: frozenset[str]
    #: no repeated rows
    is_set: bool = False

    @property
    def names(self) -> list[str]:
        return list(self.kinds)

    def distinct(self) -> Solutions:
        return self if self.is_set else Solutions(self.df.distinct(), self.kinds, self.certain, True)

    def project(self, names: list[str]) -> Solutions:
        keep = [n for n in names if n in self.kinds]
        if len(keep) == len(self.kinds) and keep:
            return Solutions(self.df.select(*map(q, keep)), {n: self.kinds[n] for n in keep}, self.certain, self.is_set)
        df = self.df.select(*map(q, keep)) if keep else self.df.select(F.lit(1).alias("__unit"))
        return Solutions(df, {n: self.kinds[n] for n in keep}, self.certain & set(keep), False)


def q(name: str) -> Column:
    return F.col(f"`{name}`")


def unit(spark) -> Solutions:
    """The one empty mapping."""
    return Solutions(spark.range(1).select(F.lit(1).alias("__unit")), {}, frozenset(), True)


def nothing(spark, kinds: dict[str, Kind], types: dict[str, str] | None = None) -> Solutions:
    df = spark.range(0).select(*[F.lit(None).cast((types or {}).get(n, "string")).alias(n) for n in kinds], F.lit(1).alias("__unit"))
    return Solutions(df.select(*map(q, kinds)) if kinds else df, kinds, frozenset(kinds), True)


def clashing(l: Solutions, r: Solutions) -> set[str]:
    """Shared variables whose kinds can never hold equal terms."""
    return {n for n in l.kinds if n in r.kinds and not l.kinds[n].meets(r.kinds[n])}


def _masks(l: Solutions, r: Solutions, shared: list[str]) -> list[tuple[list[str], Column | None, Column | None]]:
    """(variables bound on both sides, condition on the left, condition on the right), covering all combinations."""
    lm = [n for n in shared if n not in l.certain]
    rm = [n for n in shared if n not in r.certain]

    def split(names: list[str]) -> list[tuple[frozenset[str], Column | None]]:
        out = []
        for bits in product((True, False), repeat=len(names)):
            cond = None
            for n, b in zip(names, bits, strict=True):
                c = q(n).isNotNull() if b else q(n).isNull()
                cond = c if cond is None else cond & c
            out.append((frozenset(n for n, b in zip(names, bits, strict=True) if not b), cond))
        return out

    return [([n for n in shared if n not in lu and n not in ru], lc, rc) for lu, lc in split(lm) for ru, rc in split(rm)]


def join(l: Solutions, r: Solutions, how: str = "inner") -> Solutions:
    """All unions of compatible solutions. Sides without a shared variable give a product."""
    shared = [n for n in l.names if n in r.kinds]
    kinds = {**r.kinds, **l.kinds}
    order = [*l.names, *(n for n in r.names if n not in l.kinds)]
    parts = None
    for on, lc, rc in _masks(l, r, shared):
        a = l.df.where(lc) if lc is not None else l.df
        b = r.df.where(rc) if rc is not None else r.df
        if clashing(l, r) & set(on):
            a = a.where(F.lit(False))
        b = b.select(*[q(n).alias(f"__r_{n}") for n in r.names], *([] if r.names else [F.lit(1).alias("__r_unit")]))
        if on:
            cond = None
            for n in on:
                c = (q(n) == q(f"__r_{n}")) if not clashing(l, r) & {n} else F.lit(False)
                cond = c if cond is None else cond & c
            df = a.join(b, cond, "inner")
        else:
            df = a.crossJoin(b)
        cols = [(F.coalesce(q(n), q(f"__r_{n}")) if n in shared and n not in l.certain and n not in clashing(l, r) else q(n) if n in l.kinds else q(f"__r_{n}")).alias(n) for n in order]
        df = df.select(*cols) if cols else df.select(F.lit(1).alias("__unit"))
        parts = df if parts is None else parts.unionByName(df)
    return Solutions(parts, {n: kinds[n] for n in order}, l.certain | r.certain, l.is_set and r.is_set and all(n in l.certain and n in r.certain for n in shared))


def _same(l: Solutions, names: list[str]) -> Column:
    """Null-safe equality of left columns with their renamed copies."""
    cond = F.lit(True)
    for n in names:
        cond = cond & (q(n) == q(f"__k_{n}") if n in l.certain else q(n).eqNullSafe(q(f"__k_{n}")))
    return cond


def semi(l: Solutions, keys: DataFrame, names: list[str], how: str) -> Solutions:
    """Left solutions that occur (or do not occur) among keys on the given variables, unbound matching unbound."""
    k = keys.select(*[q(n).alias(f"__k_{n}") for n in names], *([] if names else [F.lit(1).alias("__k")])).distinct()
    return Solutions(l.df.join(k, _same(l, names), how), l.kinds, l.certain, l.is_set)


def left_join(l: Solutions, r: Solutions, cond: Callable[[Solutions], Column] | None) -> Solutions:
    """Matches whose union satisfies cond, and every left solution without one."""
    shared = [n for n in l.names if n in r.kinds]
    kinds = {**{n: k for n, k in r.kinds.items()}, **l.kinds}
    order = [*l.names, *(n for n in r.names if n not in l.kinds)]
    if all(n in l.certain and n in r.certain for n in shared):
        # one left join, the filter inside its condition
        b = r.df.select(*[q(n).alias(f"__r_{n}") for n in r.names], F.lit(1).alias("__hit"))
        on = F.lit(True)
        for n in shared:
            on = on & (F.lit(False) if clashing(l, r) & {n} else q(n) == q(f"__r_{n}"))
        if cond is not None:
            on = on & cond(Solutions(l.df, kinds, l.certain), lambda n: q(n) if n in l.kinds else q(f"__r_{n}"))
        df = l.df.join(b, on, "left").select(*[(q(n) if n in l.kinds else q(f"__r_{n}")).alias(n) for n in order])
        return Solutions(df, {n: kinds[n] for n in order}, l.certain, l.is_set and r.is_set)
    l = l.distinct()
    both = join(l, r)
    if cond is not None:
        both = Solutions(both.df.where(cond(both, q)), both.kinds, both.certain)
    # which left solution a match comes from: matched on a copy of its columns
    tagged = Solutions(l.df.select(*[q(n).alias(n) for n in l.names], *[q(n).alias(f"__k_{n}") for n in l.names]), {**l.kinds, **{f"__k_{n}": l.kinds[n] for n in l.names}}, l.certain | {f"__k_{n}" for n in l.certain})
    hit = join(tagged, r)
    hit_df = hit.df.where(cond(hit, q)) if cond is not None else hit.df
    keys = hit_df.select(*[q(f"__k_{n}").alias(n) for n in l.names])
    rest = semi(l, keys, l.names, "left_anti")
    return union(both, rest)


def union(l: Solutions, r: Solutions) -> Solutions:
    """Solutions of either side; variables of one side only are unbound in the other's."""
    kinds = dict(l.kinds)
    for n, k in r.kinds.items():
        if n in kinds and not kinds[n].meets(k) and kinds[n] != k:
            raise TypeError(f"?{n} has two kinds in a union: {kinds[n]} and {k}")
        kinds.setdefault(n, k)
    a = l.df.select(*map(q, l.names)) if l.names else l.df.select("__unit")
    b = r.df.select(*map(q, r.names)) if r.names else r.df.select("__unit")
    df = a.unionByName(b, allowMissingColumns=True)
    df = df.select(*map(q, kinds)) if kinds else df
    return Solutions(df, kinds, l.certain & r.certain, False).distinct()


def minus(l: Solutions, r: Solutions, fixed: frozenset[str] = frozenset()) -> Solutions:
    """Left solutions that no right solution is compatible with and shares a bound variable with.

    ``fixed`` variables stand for constants of an outer solution: they must agree
    but do not count as shared.
    """
    shared = [n for n in l.names if n in r.kinds]
    if not [n for n in shared if n not in fixed]:
        return l
    if all(n in l.certain and n in r.certain for n in shared):
        if clashing(l, r) & set(shared):
            return l
        return semi(l, r.df.select(*map(q, shared)), shared, "left_anti")
    l = l.distinct()
    gone = None
    for on, lc, rc in _masks(l, r, shared):
        if not [n for n in on if n not in fixed] or clashing(l, r) & set(on):
            continue
        a = l.df.where(lc) if lc is not None else l.df
        b = r.df.where(rc) if rc is not None else r.df
        k = b.select(*[q(n).alias(f"__k_{n}") for n in on]).distinct()
        cond = F.lit(True)
        for n in on:
            cond = cond & (q(n) == q(f"__k_{n}"))
        hit = a.join(k, cond, "left_semi").select(*map(q, l.names))
        gone = hit if gone is None else gone.unionByName(hit)
    return l if gone is None else semi(l, gone, l.names, "left_anti")
