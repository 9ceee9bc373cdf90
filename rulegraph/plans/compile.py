"""From the algebra to DataFrames."""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulegraph.functions.expressions import Expr, expr_vars, to_column
from rulegraph.functions import expressions
from rulegraph.operators import paths
from rulegraph.operators import solutions as S
from rulegraph.operators.solutions import Solutions, q
from rulegraph.plans import algebra as A
from rulegraph.sources.graphs import TERM, Graph, Kind, View, to_text
from rulegraph.terms import Blank, Iri, Lit, Triple, Var

_LIT_KINDS = {"integer": "bigint", "double": "double", "decimal": "double", "string": "string", "boolean": "boolean"}


class Compiler:
    """Evaluates patterns over a graph. ``seed`` in the methods below holds outer solutions that are constants inside an EXISTS."""

    def __init__(self, graph: Graph):
        self.graph, self.spark = graph, graph.spark
        self.generic = _is_generic(graph)

    # ------------------------------------------------------------ expressions

    def column(self, e: object, sol: Solutions, pick=q) -> Column:
        """Spark column; a variable that the solutions do not have is NULL."""
        col = lambda n: pick(n) if n in sol.kinds else F.lit(None)
        const = lambda t: F.lit(t.value) if isinstance(t, Lit) else self._constant_like(t, e, sol)
        return to_column(e, col, const, self.generic)

    def _constant_like(self, t: Iri, e: object, sol: Solutions) -> Column:
        if self.generic:
            return F.lit(f"<{t.value}>")
        for n in expr_vars(e):
            if n in sol.kinds and sol.kinds[n].sort == "iri":
                c = self.graph.constant(t, sol.kinds[n])
                if c is not None:
                    return c
        return F.lit(None)

    # ------------------------------------------------------------ patterns

    def run(self, p: object, seed: Solutions | None = None, need: frozenset[str] | None = None) -> Solutions:
        if isinstance(p, A.BGP):
            return self.bgp(p, seed, need)
        if isinstance(p, A.And):
            return S.join(self.run(p.left, seed), self.run(p.right, seed))
        if isinstance(p, A.Union):
            return S.union(self.run(p.left, seed, need), self.run(p.right, seed, need))
        if isinstance(p, A.Opt):
            return self.opt(p, seed)
        if isinstance(p, A.Minus):
            left = self.run(p.left, seed)
            fixed = frozenset(seed.names) if seed else frozenset()
            if not (set(A.scope(p.left)) - fixed) & (set(A.scope(p.right)) - fixed):
                return left
            return S.minus(left, self.run(p.right, seed), fixed)
        if isinstance(p, (A.Exists, A.NotExists)):
            left = self.run(p.left, seed)
            return self.exists(left, p.right, "left_semi" if isinstance(p, A.Exists) else "left_anti")
        if isinstance(p, A.Filter):
            keep = None if need is None else need | expr_vars(p.cond)
            sol = self.run(p.left, seed, keep)
            return Solutions(sol.df.where(F.coalesce(self.column(p.cond, sol), F.lit(False))), sol.kinds, sol.certain, sol.is_set)
        if isinstance(p, A.Extend):
            sol = self.run(p.left, seed)
            c = self.column(p.expr, sol)
            kind = Kind("lit", "computed")
            if isinstance(p.expr, Var) and p.expr.name in sol.kinds:
                kind = sol.kinds[p.expr.name]
            return Solutions(sol.df.select(*map(q, sol.names), c.alias(p.var)), {**sol.kinds, p.var: kind}, sol.certain, sol.is_set)
        if isinstance(p, A.Values):
            return self.values(p)
        if isinstance(p, A.Group):
            return self.group(p, seed)
        if isinstance(p, A.SubSelect):
            return self.query(p.query)
        raise TypeError(p)

    def opt(self, p: A.Opt, seed: Solutions | None) -> Solutions:
        left, right = self.run(p.left, seed), self.run(p.right, seed)
        if p.cond == A.TRUE:
            return S.left_join(left, right, None)
        if isinstance(p.cond, Expr) and p.cond.op in ("exists", "not exists"):
            # pairs first, then the test on their unions, then the rest of the left side
            left = left.distinct()
            both = self.exists(S.join(left, right), p.cond.args[0], "left_semi" if p.cond.op == "exists" else "left_anti")
            if not all(n in left.certain for n in left.names if n in right.kinds):
                raise NotImplementedError("EXISTS inside OPTIONAL over variables that may be unbound")
            return S.union(both, S.semi(left, both.df.select(*map(q, left.names)), left.names, "left_anti"))
        return S.left_join(left, right, lambda sol, pick: F.coalesce(self.column(p.cond, sol, pick), F.lit(False)))

    def exists(self, left: Solutions, right: object, how: str) -> Solutions:
        """Semi- or anti-join with the right pattern, evaluated with the left solutions' values as constants."""
        need = [n for n in left.names if n in A.variables(right)]
        unsure = [n for n in need if n not in left.certain]
        parts = None
        for bits in product((True, False), repeat=len(unsure)):
            part = left
            for n, b in zip(unsure, bits, strict=True):
                part = Solutions(part.df.where(q(n).isNotNull() if b else q(n).isNull()), part.kinds, part.certain | {n} if b else part.certain, part.is_set)
            bound = [n for n in need if n in part.certain]
            seed = part.project(bound).distinct()
            # the free variables are local to the test
            inner = A.rename(right, frozenset(bound), "x") if unsure else right
            sol = self.run(inner, seed if bound else None)
            got = S.semi(part, sol.df.select(*map(q, bound)) if bound else sol.df.limit(1), bound, how)
            parts = got if parts is None else Solutions(parts.df.unionByName(got.df), left.kinds, left.certain, left.is_set)
        return parts

    def values(self, p: A.Values) -> Solutions:
        kinds, schema, cols = {}, [], []
        for i, n in enumerate(p.names):
            first = next((r[i] for r in p.rows if r[i] is not None), Lit(""))
            if self.generic:
                kinds[n] = TERM
            else:
                kinds[n] = Kind("lit", first.dt) if isinstance(first, Lit) else Kind("iri", first.value.partition("{")[0] if "{" in first.value else "name")
            kind = "string" if self.generic else _LIT_KINDS.get(first.dt, "string") if isinstance(first, Lit) else "bigint" if "{" in first.value else "string"
            schema.append(f"`{n}` {kind}")
            cols.append(n)
        from rulegraph.sources.graphs import term_text

        def plain(t):
            if t is None:
                return None
            if self.generic:
                return term_text(t)
            if isinstance(t, Lit):
                return t.value
            key = t.value.partition("{")[2].rstrip("}")
            return int(key) if key else t.value

        df = self.spark.createDataFrame([tuple(map(plain, r)) for r in p.rows], ", ".join(schema))
        return Solutions(df, kinds, A.certain(p), False).distinct()

    def group(self, p: A.Group, seed: Solutions | None) -> Solutions:
        sol = self.run(p.left, seed).distinct()
        out, kinds = [], {k: sol.kinds[k] for k in p.keys}
        for name, fn, arg, distinct in p.aggs:
            c = self.column(arg, sol) if arg is not None else F.lit(1)
            builtin = {
                "count": lambda c: F.count_distinct(c) if distinct else F.count(c),
                "sum": lambda c: F.sum_distinct(c) if distinct else F.sum(c),
                "min": F.min,
                "max": F.max,
                "avg": F.avg,
                "sample": F.min,
                "group_concat": lambda c: F.concat_ws(" ", F.sort_array(F.collect_set(c.cast("string")) if distinct else F.collect_list(c.cast("string")))),
            }
            made = expressions.AGGREGATES[fn](c) if fn in expressions.AGGREGATES else builtin[fn](c)
            out.append(made.alias(name))
            kinds[name] = Kind("lit", "integer" if fn == "count" else "computed")
        df = sol.df.groupBy(*map(q, p.keys)).agg(*out) if p.keys else sol.df.agg(*out)
        return Solutions(df, kinds, frozenset(k for k in p.keys if k in sol.certain) | {a[0] for a in p.aggs if a[1] == "count"}, True)

    # ------------------------------------------------------------ triple groups

    def _views(self, t: Triple) -> list[tuple[View, str | None]]:
        if isinstance(t.p, A.Path):
            s, o = (x if isinstance(x, (Iri, Lit)) else None for x in (t.s, t.o))
            return [(paths.path_view(self.graph, t.p, s, o), None)]
        if isinstance(t.p, Var):
            return [(v, p) for p in self.graph.predicates() if (v := self.graph.view(p)) is not None]
        v = self.graph.view(t.p.value)
        return [] if v is None else [(v, None)]

    def triple(self, t: Triple) -> Solutions | None:
        """Solutions of a triple pattern; None if it can have none."""
        parts: Solutions | None = None
        many = isinstance(t.p, Var)
        for view, p in self._views(t):
            df, ok = view.df, True
            text = many and not self.generic
            for c, x, kind in (("s", t.s, view.s), ("o", t.o, view.o)):
                if isinstance(x, (Iri, Lit)):
                    const = self.graph.constant(x, kind)
                    if const is None:
                        ok = False
                        break
                    df = df.where(F.col(c) == const)
            if not ok:
                continue
            name = lambda x: x.name if isinstance(x, Var) else f"_b_{x.name}"
            s_var, o_var = isinstance(t.s, (Var, Blank)), isinstance(t.o, (Var, Blank))
            if s_var and o_var and name(t.s) == name(t.o):
                if not view.s.meets(view.o):
                    continue
                df = df.where(F.col("s") == F.col("o"))
            cols, kinds = {}, {}
            if s_var:
                cols[name(t.s)], kinds[name(t.s)] = (to_text(F.col("s"), view.s), TERM) if text else (F.col("s"), view.s)
            if many:
                cols[t.p.name] = F.lit(f"<{p}>")
                kinds[t.p.name] = TERM
            if o_var and not (s_var and name(t.s) == name(t.o)):
                cols[name(t.o)], kinds[name(t.o)] = (to_text(F.col("o"), view.o), TERM) if text else (F.col("o"), view.o)
            df = df.select(*[c.alias(n) for n, c in cols.items()]) if cols else df.select(F.lit(1).alias("__unit"))
            whole = s_var and o_var or view.functional and s_var
            sol = Solutions(df, kinds, frozenset(kinds), whole)
            if parts is None:
                parts = sol
            else:
                parts = Solutions(parts.df.unionByName(sol.df), parts.kinds, parts.certain, False)
        return parts

    def bgp(self, p: A.BGP, seed: Solutions | None, need: frozenset[str] | None = None) -> Solutions:
        """Joins triple patterns, constants and small sides first and connected ones before products; variables that nothing needs any more are dropped on the way.

        A join on what determines the rows of a side gives no more rows than the other has; one on less may give the
        product of both, so it waits until nothing else is left.
        """
        todo = [(t, self.triple(t)) for t in p.triples]
        names = [*A.scope(p)]
        if any(s is None for _, s in todo):
            kinds = {n: next((s.kinds[n] for _, s in todo if s is not None and n in s.kinds), TERM) for n in names}
            if seed:
                kinds = {**kinds, **seed.kinds}
            types = {n: dict(s.df.dtypes)[n] for s in [*(s for _, s in todo if s is not None), *([seed] if seed else [])] for n in s.kinds}
            return S.nothing(self.spark, kinds, types)
        now, key = seed, frozenset(seed.names) if seed else frozenset()
        if now is None and not todo:
            return S.unit(self.spark)
        used = frozenset().union(*(frozenset(s.kinds) for _, s in todo)) if todo else frozenset()
        want = (frozenset(names) if need is None else need & frozenset(names)) | (frozenset(seed.names) if seed else frozenset())

        def weight(item) -> tuple:
            t, s = item
            fixed = sum(isinstance(x, (Iri, Lit)) for x in (t.s, t.o))
            linked = bool(now is not None and set(now.names) & set(s.names)) if now is not None else True
            delta = isinstance(t.p, Iri) and t.p.value.startswith("Δ")
            return (not linked, not delta, now is not None and many(t, s), -fixed, len(s.names))

        def determined_by(t: Triple, s: Solutions) -> frozenset[str]:
            """Variables that determine a row of the pattern."""
            views = self._views(t) if not isinstance(t.p, A.Path) else []
            return frozenset(s.names[:1]) if isinstance(t.s, (Var, Blank)) and len(views) == 1 and views[0][0].functional else frozenset(s.names)

        def many(t: Triple, s: Solutions) -> bool:
            """Whether rows of both sides may repeat in the join."""
            shared = set(now.names) & set(s.names)
            return not (key <= shared or keys[id(t)] <= shared)

        keys = {id(t): determined_by(t, s) for t, s in todo}
        left, dropped = list(todo), False
        while left:
            left.sort(key=weight)
            t, s = left.pop(0)
            if now is not None and now.df is not None:
                shared = frozenset(now.names) & frozenset(s.names)
                if dropped and not frozenset(s.names) <= shared:
                    # the next join starts from a set
                    now, dropped = now.distinct(), False
                if clash := S.clashing(now, s):
                    kinds = {**s.kinds, **now.kinds, **{n: k for _, x in left for n, k in x.kinds.items() if n not in now.kinds and n not in s.kinds}}
                    types = {n: dict(x.df.dtypes)[n] for x in (now, s, *(x for _, x in left)) for n in x.kinds}
                    out = S.nothing(self.spark, kinds, types)
                    return out.project([n for n in out.names if n in want])
                now = S.join(now, s)
                if not keys[id(t)] <= shared:
                    key = keys[id(t)] if key <= shared else key | keys[id(t)]
            else:
                now, key = s, keys[id(t)]
            later = frozenset().union(*(frozenset(x.kinds) for _, x in left)) if left else frozenset()
            keep = [n for n in now.names if n in want or n in later]
            if len(keep) < len(now.names):
                now = now.project(keep)
                key = key if key <= frozenset(keep) else frozenset(keep)
                # a projection on the way keeps one row for each value, once the patterns that only test rows are through
                dropped = dropped or need is not None
        now = now if now is not None else S.unit(self.spark)
        return now.project([n for n in now.names if n in want])

    # ------------------------------------------------------------ queries

    def query(self, qy: A.Query) -> Solutions:
        """Solutions of a SELECT, or of a CONSTRUCT's pattern."""
        A.validate(qy)
        names = list(qy.template) if qy.form == "select" else [n for n in A.scope(qy.pattern)]
        need = frozenset(names) | {n for n, _ in qy.order} if qy.form == "select" else None
        sol = self.run(A.rewrite(qy.pattern), None, need)
        if qy.order or qy.limit is not None or qy.offset:
            sol = sol.distinct() if qy.form != "select" or set(names) | {n for n, _ in qy.order} >= set(sol.names) else sol
            if not sol.is_set:
                sol = sol.project([*names, *(n for n, _ in qy.order if n not in names)]).distinct()
            df = sol.df.orderBy(*[q(n).desc() if down else q(n) for n, down in qy.order]) if qy.order else sol.df
            if qy.offset:
                df = df.offset(qy.offset)
            if qy.limit is not None:
                df = df.limit(qy.limit)
            sol = Solutions(df, sol.kinds, sol.certain, True)
        missing = {n for n in names if n not in sol.kinds}
        if missing:
            sol = Solutions(sol.df.select(*map(q, sol.names), *[F.lit(None).cast("string").alias(n) for n in missing]), {**sol.kinds, **{n: TERM for n in missing}}, sol.certain, sol.is_set)
        return sol.project(names).distinct()

    def construct(self, qy: A.Query, unbound: str = "drop", rule: str = "q") -> DataFrame:
        """Triples (s, p, o) as text; a variable left unbound drops its triple or becomes a marker."""
        sol = self.query(qy)
        names = sorted(sol.names)
        key = F.sha2(F.concat_ws("\x1f", F.lit(rule), *[F.concat(F.lit(f"{n}="), F.coalesce(to_text(q(n), sol.kinds[n]), F.lit("~"))) for n in names]), 256)

        def term(x: object) -> Column:
            if isinstance(x, Var):
                c = to_text(q(x.name), sol.kinds[x.name])
                return c if unbound == "drop" else F.coalesce(c, F.lit("_:unbound"))
            if isinstance(x, Blank):
                return F.concat(F.lit(f"_:{x.name}."), F.substring(key, 1, 32))
            from rulegraph.sources.graphs import term_text

            return F.lit(term_text(x))

        rows = F.explode(F.array(*[F.struct(term(t.s).alias("s"), term(t.p).alias("p"), term(t.o).alias("o")) for t in qy.template]))
        out = sol.df.select(rows.alias("t")).select("t.s", "t.p", "t.o")
        if unbound == "drop":
            out = out.where("s is not null and p is not null and o is not null")
        return out.distinct()


def _is_generic(graph: Graph) -> bool:
    from rulegraph.sources.graphs import OverlayGraph, TripleGraph

    while isinstance(graph, OverlayGraph):
        graph = graph.base
    return isinstance(graph, TripleGraph)
