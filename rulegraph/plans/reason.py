"""Recursive rules: bottom-up, goal-directed, and mixed.

A program is a list of rules over a graph. Each rule's pattern is compiled by the
ordinary compiler, with derived predicates laid over the graph's views. Bottom-up
evaluation is semi-naive: in each round a rule runs once for each place where a
recursive predicate stands, with that place reading only what the round before has
found. New pairs are written to a folder for each round; the known ones are read
from all those folders, so plans stay small whatever the depth, and a lost executor
costs a re-read. Rounds of a few rows, up to a fixed number, are kept in the plan
itself: a goal-directed walk along a chain then costs one small job a step. Views that the loop does not change are written once before it.

Goal-directed evaluation rewrites the program first: constants of the goal become
demand, and rules derive only what is demanded (see ``demand``).
"""

from __future__ import annotations

import time
from collections.abc import Iterable
from dataclasses import dataclass, field
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from rulegraph.operators import paths
from rulegraph.operators.solutions import Solutions, q
from rulegraph.plans import algebra as A
from rulegraph.plans.compile import Compiler
from rulegraph.plans.translate import expand
from rulegraph.sources.graphs import TERM, Graph, View
from rulegraph.storage import cut, new_path
from rulegraph.terms import Blank, Iri, Lit, Rule, Triple, Var


class UnstratifiedRecursion(ValueError):
    """A rule depends on the absence of something that depends on the rule."""


class DepthExceeded(RuntimeError):
    """The round limit was reached: the closure may be infinite."""


@dataclass(frozen=True)
class Clause:
    """One derived triple pattern with the algebra of its premise."""

    name: str
    head: Triple
    body: object
    direction: str = "forward"


def clauses_of(rules: Iterable[Rule | A.Query]) -> list[Clause]:
    """A clause for every head triple of every rule; queries of CONSTRUCT form count as rules."""
    out = []
    for i, r in enumerate(rules):
        if isinstance(r, A.Query):
            A.validate(r)
            out += [Clause(f"q{i}", t, A.rewrite(r.pattern)) for t in r.template]
        else:
            body = A.rewrite(expand(r))
            out += [Clause(r.name, t, body, r.direction) for t in r.head]
    return out


def uses(p: object, positive: bool = True) -> list[tuple[str, bool]]:
    """(predicate, positive) of every triple pattern; a place under difference, absence or the optional side of OPTIONAL is not positive."""
    if isinstance(p, A.BGP):
        out = []
        for t in p.triples:
            if isinstance(t.p, Iri):
                out.append((t.p.value, positive))
            elif isinstance(t.p, A.Path):
                out += [(x, False) for x in _path_predicates(t.p)]
            else:
                out.append(("*", positive))
        return out
    if isinstance(p, (A.And, A.Union, A.Exists)):
        return uses(p.left, positive) + uses(p.right, positive)
    if isinstance(p, (A.Opt, A.Minus, A.NotExists)):
        return uses(p.left, positive) + uses(p.right, False)
    if isinstance(p, (A.Filter, A.Extend)):
        return uses(p.left, positive)
    if isinstance(p, A.Group):
        return uses(p.left, False)
    if isinstance(p, A.SubSelect):
        return uses(p.query.pattern, False)
    return []


def _path_predicates(p: A.Path) -> list[str]:
    return [p.args[0].value] if p.op == "link" else [x for a in p.args for x in _path_predicates(a)]


def stratify(clauses: list[Clause], on_cycle: str = "error") -> list[list[Clause]]:
    """Strata in order: each needs only itself (positively) and those before it."""
    derived = {c.head.p.value for c in clauses}
    edges: dict[str, set[tuple[str, bool]]] = {d: set() for d in derived}
    for c in clauses:
        for p, pos in uses(c.body):
            for d in derived if p == "*" else [p] if p in derived else []:
                edges[c.head.p.value].add((d, pos))
    # strongly connected components (Tarjan)
    index, low, stack, on, out = {}, {}, [], set(), []
    counter = count()

    def visit(v: str) -> None:
        index[v] = low[v] = next(counter)
        stack.append(v)
        on.add(v)
        for w, _ in sorted(edges[v]):
            if w not in index:
                visit(w)
                low[v] = min(low[v], low[w])
            elif w in on:
                low[v] = min(low[v], index[w])
        if low[v] == index[v]:
            group = set()
            while True:
                w = stack.pop()
                on.discard(w)
                group.add(w)
                if w == v:
                    break
            out.append(group)

    for v in sorted(derived):
        if v not in index:
            visit(v)
    for group in out:
        for v in group:
            for w, pos in edges[v]:
                if w in group and not pos and on_cycle == "error":
                    raise UnstratifiedRecursion(f"{v} needs the absence of {w}")
    return [[c for c in clauses if c.head.p.value in group] for group in out]


def _replace(p: object, at: int, name: str, targets: set[str], seen: list[int]) -> object:
    """p with the at-th positive use of a target predicate renamed."""
    if isinstance(p, A.BGP):
        ts = []
        for t in p.triples:
            if isinstance(t.p, Iri) and t.p.value in targets:
                if seen[0] == at:
                    t = Triple(t.s, Iri(name + t.p.value), t.o)
                seen[0] += 1
            ts.append(t)
        return A.BGP(tuple(ts))
    if isinstance(p, (A.And, A.Union, A.Exists)):
        left = _replace(p.left, at, name, targets, seen)
        return type(p)(left, _replace(p.right, at, name, targets, seen))
    if isinstance(p, A.Opt):
        return A.Opt(_replace(p.left, at, name, targets, seen), p.right, p.cond)
    if isinstance(p, (A.Minus, A.NotExists)):
        return type(p)(_replace(p.left, at, name, targets, seen), p.right)
    if isinstance(p, A.Filter):
        return A.Filter(_replace(p.left, at, name, targets, seen), p.cond)
    if isinstance(p, A.Extend):
        return A.Extend(_replace(p.left, at, name, targets, seen), p.var, p.expr)
    return p


def positive_uses(p: object, targets: set[str]) -> int:
    seen = [0]
    _replace(p, -1, "", targets, seen)
    return seen[0]


@dataclass
class Round:
    stratum: int
    number: int
    predicate: str
    kept: int
    seconds: float


@dataclass
class Result:
    """Derived views, and what it took."""

    graph: Graph
    derived: dict[str, View]
    rounds: list[Round] = field(default_factory=list)
    #: with ``explain_derivations``: (s, o, rule, round) by predicate
    origins: dict[str, DataFrame] = field(default_factory=dict)

    def derivations(self, predicate: str) -> DataFrame:
        """The round in which each pair was first found, and a rule that found it then (the first by name; "given" for the graph's own)."""
        return self.origins[predicate]

    def view(self, predicate: str) -> DataFrame:
        return self.derived[predicate].df.select("s", "o")

    def derived_count(self) -> int:
        return sum(r.kept for r in self.rounds)


class Reasoner:
    def __init__(self, graph: Graph, *, max_hops: int = 1, hop_rows: int = 100_000, max_rounds: int = 500, max_skolem_depth: int = 8, row_budget: int | None = None, on_cycle: str = "error", explain_derivations: bool = False):
        self.graph, self.spark = graph, graph.spark
        #: Whether to keep the rule and the round of each pair; rounds are then run one by one.
        self.explaining, self.origins = explain_derivations, {}
        #: Rounds that one job may chain, and the rows that the round before it may have found for that.
        self.max_hops, self.hop_rows = 1 if explain_derivations else max_hops, hop_rows
        self.max_rounds, self.max_skolem_depth, self.row_budget, self.on_cycle = max_rounds, max_skolem_depth, row_budget, on_cycle

    # -------------------------------------------------------- one clause

    def head_rows(self, c: Clause, graph: Graph) -> View:
        """Pairs that a clause derives over a graph."""
        comp = Compiler(graph)
        need = frozenset(x.name for x in (c.head.s, c.head.o) if isinstance(x, Var))
        sol = comp.run(c.body, None, need)
        cols, kinds = {}, {}
        for n, x in (("s", c.head.s), ("o", c.head.o)):
            cols[n], kinds[n] = self._term(x, sol, comp, c)
        df = sol.df.select(*[v.alias(k) for k, v in cols.items()])
        if not need <= sol.certain:
            df = df.where("s is not null and o is not null")
        return View(df, kinds["s"], kinds["o"])

    def _term(self, x: object, sol: Solutions, comp: Compiler, c: Clause):
        if isinstance(x, Var):
            return q(x.name), sol.kinds[x.name]
        if isinstance(x, Blank):
            from rulegraph.sources.graphs import to_text

            parts = [to_text(q(n), sol.kinds[n]) for n in sorted(sol.names)]
            # the nesting of made-up terms is counted in their names, so that endless making of terms ends
            depth = F.greatest(F.lit(0), *[F.coalesce(F.regexp_extract(p, r"^_:k(\d+)\.", 1).try_cast("int"), F.lit(0)) for p in parts]) + 1
            made = F.concat(F.lit("_:k"), depth.cast("string"), F.lit("."), F.substring(F.sha2(F.concat_ws("\x1f", F.lit(f"{c.name}/{x.name}"), *parts), 256), 1, 24))
            return F.when(depth <= self.max_skolem_depth, made), TERM
        if comp.generic:
            return self.graph.constant(x, TERM), TERM
        from rulegraph.sources.graphs import Kind

        if isinstance(x, Lit):
            return F.lit(x.value), Kind("lit", x.dt)
        name, _, key = x.value.partition("{")
        return (F.lit(int(key.rstrip("}"))).cast("bigint"), Kind("iri", name)) if key else (F.lit(x.value), Kind("iri", "name"))

    def _gather(self, clauses: list[Clause], graph: Graph) -> dict[str, View]:
        out: dict[str, View] = {}
        for c in clauses:
            v = self.head_rows(c, graph)
            p = c.head.p.value
            if any(isinstance(x, Blank) for x in (c.head.s, c.head.o)):
                v = View(v.df.where("s is not null and o is not null"), v.s, v.o)
            if self.explaining:
                v = View(v.df.select("s", "o", F.lit(c.name).alias("rule")), v.s, v.o)
            if p in out:
                if not (out[p].s.meets(v.s) and out[p].o.meets(v.o)):
                    raise TypeError(f"{p} is derived with different kinds: {out[p].s}, {v.s}; {out[p].o}, {v.o}")
                v = View(out[p].df.unionByName(v.df), out[p].s, out[p].o)
            out[p] = v
        return out

    # -------------------------------------------------------- bottom-up

    def _once(self, v: View, base: View | None = None) -> DataFrame:
        """Distinct pairs, with one rule each if derivations are kept."""
        cols = ["s", "o", "rule"] if self.explaining else ["s", "o"]
        df = v.df.select(*cols)
        if base is not None:
            own = base.df.select("s", "o")
            df = df.unionByName(own.withColumn("rule", F.lit("given")) if self.explaining else own)
        if not self.explaining:
            return df.distinct()
        # what is given is not derived; else the first rule by name
        return df.groupBy("s", "o").agg(F.coalesce(F.max(F.when(F.col("rule") == "given", F.lit("given"))), F.min("rule")).alias("rule"))

    def forward(self, rules, strategy: str = "seminaive", clauses: list[Clause] | None = None) -> Result:
        """All that the rules derive. strategy: seminaive, naive (all facts, each round) or doubling (transitive rules by squaring)."""
        clauses = clauses if clauses is not None else clauses_of(rules)
        graph, derived, rounds = self.graph, {}, []
        for i, group in enumerate(stratify(clauses, self.on_cycle)):
            names = {c.head.p.value for c in group}
            recursive = any(positive_uses(c.body, names) or any(p in names for p, _ in uses(c.body)) for c in group)
            if not recursive:
                made = {}
                for p, v in self._gather(group, graph).items():
                    base = graph.view(p) if p in graph.predicates() else None
                    df = self._once(v, base)
                    if self.explaining:
                        self.origins[p] = df.withColumn("round", F.lit(0))
                    made[p] = View(df, v.s, v.o)
            elif strategy == "doubling" and not self.explaining and (fast := self._transitive(group, graph)):
                made = fast
            else:
                made = self._fixpoint(group, graph, names, strategy, i, rounds)
            derived |= made
            graph = graph.with_views(made)
        return Result(graph, derived, rounds, dict(self.origins))

    def _transitive(self, group: list[Clause], graph: Graph) -> dict[str, View] | None:
        """The closure of a lone predicate whose only recursive rule is transitivity."""
        names = {c.head.p.value for c in group}
        if len(names) != 1:
            return None
        (p,) = names
        step = [c for c in group if positive_uses(c.body, names)]
        rest = [c for c in group if not positive_uses(c.body, names)]
        if len(step) != 1 or not isinstance(step[0].body, A.BGP) or len(step[0].body.triples) != 2:
            return None
        s, o, (a, b) = step[0].head.s, step[0].head.o, step[0].body.triples
        if a.s != s:
            a, b = b, a
        chained = a.s == s and a.o == b.s and b.o == o and len({s, o, a.o}) == 3 and all(isinstance(x, Var) for x in (s, o, a.o))
        seeds = {t.p.value for c in rest if isinstance(c.body, A.BGP) and len(c.body.triples) == 1 for t in c.body.triples if (c.head.s, c.head.o) == (t.s, t.o)}
        if not chained or {a.p.value, b.p.value} - names - seeds or len(seeds) != len(rest) or len(seeds) > 1:
            return None
        base = self._gather(rest, graph)[p] if rest else graph.view(p)
        if rest and p in graph.predicates():
            return None
        return {p: View(paths.closure(base.df, doubling=True, max_rounds=self.max_rounds), base.s, base.o)}

    def _fixpoint(self, group: list[Clause], graph: Graph, names: set[str], strategy: str, stratum: int, rounds: list[Round]) -> dict[str, View]:
        spark = self.spark
        # what the loop only reads is computed once
        fixed = {p for c in group for p, _ in uses(c.body) if p not in names and p != "*"}
        views = {}
        for p in sorted(fixed):
            v = graph.view(p)
            if v is not None:
                views[p] = View(cut(v.df.select("s", "o")), v.s, v.o, v.functional)
        graph = graph.with_views(views)
        once = [c for c in group if not positive_uses(c.body, names)]
        loop = [c for c in group if positive_uses(c.body, names)]
        first = self._gather(once, graph) if once else {}
        path, kinds, schema = new_path(spark, "fix"), {}, {}
        for p in sorted(names):
            base = graph.view(p) if p in graph.predicates() else None
            if p in first:
                first[p] = View(self._once(first[p], base), first[p].s, first[p].o)
            elif base is not None:
                df = base.df.select("s", "o")
                first[p] = View(self._once(View(df.withColumn("rule", F.lit("given")) if self.explaining else df, base.s, base.o)), base.s, base.o)
        # kinds of predicates without a start follow from the rules, as soon as these can run
        pending = [p for p in names if p not in first]
        delta: dict[str, View] = {}
        filled: dict[str, list[str]] = {p: [] for p in names}

        linear = strategy != "naive" and all(sum(p in names for p, _ in uses(c.body)) <= 1 for c in loop)

        def folder(p: str, number: int) -> str:
            return f"{path}/{sorted(names).index(p)}/round={number}"

        def write(p: str, number: int, df: DataFrame, hops: int = 1) -> int:
            """Rows written; those of the last of several hops, marked as such, are the next delta."""
            cols = [F.col(x.name).cast(x.dataType) for x in schema[p]]
            target = folder(p, number)
            df.select(*cols, *(["rule"] if self.explaining else []), *(["last"] if hops > 1 else [])).write.parquet(target)
            filled[p].append(target)
            made = spark.read.schema(schema[p] if hops == 1 else StructType([*schema[p].fields]).add("last", "boolean")).parquet(target)
            n, fresh = made.agg(F.count(F.lit(1)), F.count_if(F.col("last")) if hops > 1 else F.count(F.lit(1))).first()
            if fresh:
                delta[p] = View(made.where("last").select("s", "o") if hops > 1 else made, *kinds[p])
                found_rows[p] = fresh
            return n

        def known(p: str) -> View:
            return View(spark.read.schema(schema[p]).parquet(*filled[p]), *kinds[p])

        def start(p: str, v: View, number: int) -> int:
            kinds[p], schema[p] = (v.s, v.o), v.df.select("s", "o").schema
            return write(p, number, self._once(v))

        def step(now: Graph, deltas: dict[str, View]) -> dict[str, View]:
            """What the rules derive from the deltas; from all facts if naive."""
            found: dict[str, View] = {}
            live = names & set(kinds)
            for c in loop:
                if any(p in names and p not in kinds for p, pos in uses(c.body) if pos):
                    continue
                if strategy == "naive":
                    variants = [c]
                else:
                    variants = []
                    for k in range(positive_uses(c.body, live)):
                        body = _replace(c.body, k, "Δ", live, [0])
                        if next(p[1:] for p, _ in uses(body) if p.startswith("Δ")) in deltas:
                            variants.append(Clause(c.name, c.head, body))
                for p, v in self._gather(variants, now.with_views({"Δ" + p: x for p, x in deltas.items()})).items():
                    if p in kinds and not (kinds[p][0].meets(v.s) and kinds[p][1].meets(v.o)):
                        raise TypeError(f"{p} is derived with different kinds")
                    found[p] = v if p not in found else View(found[p].df.unionByName(v.df), v.s, v.o)
            return {p: View(self._once(v), v.s, v.o) for p, v in found.items()}

        found_rows: dict[str, int] = {}
        began = time.perf_counter()
        for p, v in first.items():
            n = start(p, v, 0)
            rounds.append(Round(stratum, 0, p, n, time.perf_counter() - began))
        number, hops = 0, 1
        while True:
            if number >= self.max_rounds:
                raise DepthExceeded(f"no end after {self.max_rounds} rounds")
            few = linear and number > 0 and set(kinds) == names and sum(found_rows.values()) <= self.hop_rows
            hops = min(2 * hops, self.max_hops, self.max_rounds - number) if few else 1
            number += hops
            began = time.perf_counter()
            now, deltas = graph.with_views({p: known(p) for p in kinds}), dict(delta)
            found: dict[str, list[View]] = {}
            for _ in range(hops):
                deltas = step(now, deltas)
                for p, v in deltas.items():
                    found.setdefault(p, []).append(v)
            last = deltas if hops > 1 else {}
            delta.clear()
            found_rows.clear()
            total = 0
            for p, views in found.items():
                if p in kinds:
                    if hops == 1:
                        df = views[0].df
                    else:
                        marked = [v.df.select("s", "o", F.lit(v is last.get(p)).alias("last")) for v in views]
                        df = marked[0]
                        for x in marked[1:]:
                            df = df.unionByName(x)
                        df = df.groupBy("s", "o").agg(F.max("last").alias("last"))
                    n = write(p, number, df.join(known(p).df, ["s", "o"], "left_anti"), hops)
                else:
                    n = start(p, views[0], number)
                rounds.append(Round(stratum, number, p, n, time.perf_counter() - began))
                total += n
            if not delta:
                break
            if self.row_budget is not None and sum(r.kept for r in rounds) > self.row_budget:
                raise DepthExceeded(f"more than {self.row_budget} derived rows")
        out = {p: known(p) for p in kinds}
        if self.explaining:
            number = F.regexp_extract(F.input_file_name(), r"round=(\d+)/", 1).cast("int")
            for p in kinds:
                self.origins[p] = spark.read.schema(StructType([*schema[p].fields]).add("rule", "string")).parquet(*filled[p]).withColumn("round", number)
        for p in pending:
            if p not in out:
                out[p] = View(spark.createDataFrame([], "s bigint, o bigint"), TERM, TERM)
        return out

    # -------------------------------------------------------- goal-directed

    def backward(self, goal: Triple, rules, strategy: str = "demand") -> tuple[DataFrame, Result]:
        """Pairs (s, o) of the goal. strategy: demand (rewrite, then bottom-up), tabled (demand and answers in turn) or unfold (no recursion)."""
        clauses = clauses_of(rules)
        if strategy == "unfold":
            body = unfold(A.BGP((goal,)), clauses, set(self.graph.predicates()))
            df = self._goal_rows(goal, Compiler(self.graph).run(A.rewrite(body)))
            return df, Result(self.graph, {})
        if strategy == "demand" and (direct := self.linear_goal(goal, clauses)):
            return direct
        answer, program = demand(goal, clauses, set(self.graph.predicates()))
        if strategy == "tabled":
            result = self._tabled(program)
        else:
            result = self.forward([], clauses=program)
        comp = Compiler(result.graph)
        sol = comp.run(A.BGP((Triple(goal.s, Iri(answer), goal.o),)))
        return self._goal_rows(goal, sol), result

    def linear_goal(self, goal: Triple, clauses: list[Clause]) -> tuple[DataFrame, Result] | None:
        """A goal with a bound end over a lone linear rule: p(x, z) from p(x, y), e(y, z), or from e(x, y), p(y, z).

        All that is demanded for the goal is demanded for the goal alone, so answers need not be
        handed back step by step. Where the bound end is the one that the rule moves, a frontier
        from it over e gives the values whose facts are answers; where it is the other end, its
        own facts start the frontier, and what that reaches are the answers.
        """
        p = goal.p.value if isinstance(goal.p, Iri) else None
        at_o = isinstance(goal.s, Var)
        if at_o == isinstance(goal.o, Var) or isinstance(goal.s, Blank) or isinstance(goal.o, Blank):
            return None
        mine, derived = [c for c in clauses if c.head.p.value == p], {c.head.p.value for c in clauses}
        step = [c for c in mine if any(x == p for x, _ in uses(c.body))]
        rest = [c for c in mine if c not in step]
        if len(step) != 1 or any(x in derived or x == "*" for c in rest for x, _ in uses(c.body)):
            return None
        c = step[0]
        if not isinstance(c.body, A.BGP) or len(c.body.triples) != 2 or any(not isinstance(t.p, Iri) for t in c.body.triples):
            return None
        own = next((t for t in c.body.triples if t.p.value == p), None)
        edge = next((t for t in c.body.triples if t.p.value != p), None)
        if own is None or edge is None or edge.p.value in derived or edge.p.value not in self.graph.predicates():
            return None
        s, o = c.head.s, c.head.o
        left = own.s == s and own.o == edge.s and edge.o == o
        right = own.o == o and own.s == edge.o and edge.s == s
        if not (left or right) or len({s, o, own.o if left else own.s}) != 3 or not all(isinstance(x, Var) for x in (s, o, own.s, own.o)):
            return None
        facts = self._gather(rest, self.graph).get(p)
        if p in self.graph.predicates():
            base = self.graph.view(p)
            facts = base if facts is None else View(facts.df.select("s", "o").unionByName(base.df.select("s", "o")), base.s, base.o)
        view = self.graph.view(edge.p.value)
        if facts is None or not (facts.o if left else facts.s).meets(view.s if left else view.o) or not view.s.meets(view.o):
            return None
        began = time.perf_counter()
        bound, kind = (goal.o, facts.o) if at_o else (goal.s, facts.s)
        const = self.graph.constant(bound, kind)
        if const is None:
            return None
        edges = view.df.select("s", "o") if not at_o else view.df.select(F.col("o").alias("s"), F.col("s").alias("o"))
        moved, fixed = ("o", "s") if left else ("s", "o")
        fast = view.functional or paths.one_ended(view.df)
        reach = (lambda begin: paths.reachable_by_doubling(edges, begin)) if fast else (lambda begin: paths.reachable(edges, begin, max_rounds=self.max_rounds))
        if left == at_o:
            # the frontier starts at the bound value itself
            begin = self.spark.range(1).select(const.alias("x"))
            reached = begin.unionByName(reach(begin)).distinct()
            answers = facts.df.join(reached, F.col(moved) == F.col("x"), "left_semi").select(F.col(fixed).alias("y"))
        else:
            begin = cut(facts.df.where(F.col(fixed) == const).select(F.col(moved).alias("x")).distinct())
            reached = reach(begin)
            answers = begin.unionByName(reached).select(F.col("x").alias("y"))
        answers = cut(answers.distinct())
        out = answers.select(F.col("y").alias((goal.s if at_o else goal.o).name))
        rounds = [Round(0, 0, f"demand:{p}", reached.count(), time.perf_counter() - began), Round(0, 1, p, answers.count(), time.perf_counter() - began)]
        kept = answers.select(F.col("y").alias("s"), const.alias("o")) if at_o else answers.select(const.alias("s"), F.col("y").alias("o"))
        return out, Result(self.graph.with_views({p: View(kept, facts.s, facts.o)}), {p: View(kept, facts.s, facts.o)}, rounds)

    def _goal_rows(self, goal: Triple, sol: Solutions) -> DataFrame:
        names = [x.name for x in (goal.s, goal.o) if isinstance(x, Var)]
        return sol.df.select(*[q(n) for n in dict.fromkeys(names)]).distinct() if names else sol.df.limit(1)

    def _tabled(self, program: list[Clause]) -> Result:
        """Set-at-a-time tabling: demand is completed for the answers known, then answers for that demand, until neither grows."""
        tables: dict[str, View] = {}
        rounds: list[Round] = []
        asks = [c for c in program if c.head.p.value.startswith("demand:")]
        proofs = [c for c in program if not c.head.p.value.startswith("demand:")]
        before = -1
        for number in range(self.max_rounds):
            for part in (asks, proofs):
                graph = self.graph.with_views(tables)
                ready = [c for c in part if all(p in tables or p in self.graph.predicates() for p, _ in uses(c.body))]
                inner = Reasoner(graph, max_rounds=self.max_rounds, on_cycle="inflationary")
                got = inner.forward([], clauses=ready)
                for p, v in got.derived.items():
                    n = (made := cut(v.df.select("s", "o").distinct())).count()
                    tables[p] = View(made, v.s, v.o)
                    rounds.append(Round(0, number, p, n, 0.0))
            total = sum(v.df.count() for v in tables.values())
            if total == before:
                break
            before = total
        else:
            raise DepthExceeded(f"no end after {self.max_rounds} rounds")
        last = {r.predicate: r for r in rounds}
        return Result(self.graph.with_views(tables), tables, list(last.values()))

    def reason(self, rules, goal: Triple | None = None) -> DataFrame | Result:
        """Forward rules are run bottom-up; backward ones on demand of the goal, over the forward rules' closure."""
        clauses = clauses_of(rules)
        eager = [c for c in clauses if c.direction == "forward"]
        lazy = [c for c in clauses if c.direction == "backward"]
        result = self.forward([], clauses=eager) if eager else Result(self.graph, {})
        if goal is None:
            return result
        if not lazy:
            return self._goal_rows(goal, Compiler(result.graph).run(A.BGP((goal,))))
        inner = Reasoner(result.graph, max_rounds=self.max_rounds)
        answer, program = demand(goal, lazy, set(result.graph.predicates()))
        done = inner.forward([], clauses=program)
        return self._goal_rows(goal, Compiler(done.graph).run(A.BGP((Triple(goal.s, Iri(answer), goal.o),))))


# ---------------------------------------------------------------- demand


def demand(goal: Triple, clauses: list[Clause], base: set[str]) -> tuple[str, list[Clause]]:
    """A program that derives only what the goal needs: (name of the answers, clauses).

    For each derived predicate and each choice of bound ends there are demanded
    values and answers. A clause's patterns are taken with bound ends first;
    what stands before a derived pattern, with the clause's own demand, tells what is
    demanded of it. Patterns below optionals, differences and absences are derived
    in full, as demand through them could unsettle the strata.
    """
    derived = {c.head.p.value for c in clauses}
    out: list[Clause] = []
    done: set[tuple[str, str]] = set()
    todo: list[tuple[str, str]] = []
    full: set[str] = set()

    def ask(p: str, ad: str) -> str:
        if (p, ad) not in done:
            done.add((p, ad))
            todo.append((p, ad))
        return f"{p}@{ad}"

    def demanded(p: str, ad: str, s: object, o: object) -> Triple:
        if ad == "bb":
            return Triple(s, Iri(f"demand:{p}@bb"), o)
        x = s if ad == "bf" else o
        return Triple(x, Iri(f"demand:{p}@{ad}"), x)

    def need_full(p: object) -> None:
        for name, _ in uses(p):
            if name in derived and name not in full:
                full.add(name)
                for c in clauses:
                    if c.head.p.value == name:
                        out.append(c)
                        need_full(c.body)

    def adorn(body: A.BGP, bound: set[str], guard: list[Triple], name: str) -> A.BGP:
        ready: list[Triple] = list(guard)
        left = list(body.triples)
        bound = set(bound)

        def is_bound(x: object) -> bool:
            return not isinstance(x, (Var, Blank)) or isinstance(x, Var) and x.name in bound

        while left:
            left.sort(key=lambda t: (-sum(map(is_bound, (t.s, t.o))), isinstance(t.p, Iri) and t.p.value in derived))
            t = left.pop(0)
            if isinstance(t.p, Iri) and t.p.value in derived:
                ad = ("b" if is_bound(t.s) else "f") + ("b" if is_bound(t.o) else "f")
                target = ask(t.p.value, ad)
                if ad != "ff":
                    d = demanded(t.p.value, ad, t.s, t.o)
                    if ready and d not in ready:
                        out.append(Clause(f"{name}/demand", d, A.BGP(tuple(ready))))
                    elif not ready:
                        out.append(Clause(f"{name}/demand", d, A.BGP(())))
                ready.append(Triple(t.s, Iri(target), t.o))
            else:
                ready.append(t)
            bound |= {x.name for x in (t.s, t.o) if isinstance(x, Var)}
        return A.BGP(tuple(ready))

    def body_of(p: object, bound: set[str], guard: list[Triple], name: str) -> object:
        if isinstance(p, A.BGP):
            return adorn(p, bound, guard, name)
        if isinstance(p, A.Filter):
            return A.Filter(body_of(p.left, bound, guard, name), p.cond)
        if isinstance(p, A.Union):
            return A.Union(body_of(p.left, bound, guard, name), body_of(p.right, bound, guard, name))
        need_full(p)
        return A.And(A.BGP(tuple(guard)), p) if guard else p

    def const(x: object) -> str:
        return "f" if isinstance(x, (Var, Blank)) else "b"

    p = goal.p.value
    ad = const(goal.s) + const(goal.o)
    answer = ask(p, ad) if p in derived else p
    if p in derived and ad != "ff":
        out.append(Clause("goal", demanded(p, ad, goal.s, goal.o), A.BGP(())))
    while todo:
        p, ad = todo.pop()
        heads = [c for c in clauses if c.head.p.value == p]
        if p in base:
            s, o = Var("s"), Var("o")
            guard = [] if ad == "ff" else [demanded(p, ad, s, o)]
            out.append(Clause(f"{p}/base", Triple(s, Iri(f"{p}@{ad}"), o), A.BGP((*guard, Triple(s, Iri(p), o)))))
        for c in heads:
            body = c.body
            guard = [] if ad == "ff" else [demanded(p, ad, c.head.s, c.head.o)]
            bound = {x.name for x, b in ((c.head.s, ad[0]), (c.head.o, ad[1])) if b == "b" and isinstance(x, Var)}
            out.append(Clause(c.name, Triple(c.head.s, Iri(f"{p}@{ad}"), c.head.o), body_of(body, bound, guard, c.name)))
    unique = []
    for c in out:
        if c not in unique:
            unique.append(c)
    return answer, unique


def unfold(p: object, clauses: list[Clause], base: set[str], depth: int = 0) -> object:
    """p with derived patterns replaced by the premises of their rules; for programs without recursion."""
    if depth > 50:
        raise UnstratifiedRecursion("recursive rules cannot be unfolded")
    if isinstance(p, A.BGP):
        out: object = A.BGP(())
        plain = []
        for t in p.triples:
            choices: list[object] = []
            for i, c in enumerate(clauses):
                if not isinstance(t.p, Iri) or c.head.p != t.p:
                    continue
                bind = {}
                ok = True
                for h, g in ((c.head.s, t.s), (c.head.o, t.o)):
                    if isinstance(h, Var):
                        if h.name in bind and bind[h.name] != g:
                            ok = False
                        bind[h.name] = g
                    elif not isinstance(g, (Var, Blank)) and h != g:
                        ok = False
                if not ok:
                    continue
                body = _substitute(A.rename(c.body, frozenset(), f"u{depth}_{i}"), {f"{k}__u{depth}_{i}": v for k, v in bind.items()})
                for h, g in ((c.head.s, t.s), (c.head.o, t.o)):
                    if not isinstance(h, Var) and isinstance(g, Var):
                        body = A.And(body, A.Values((g.name,), ((h,),)))
                choices.append(unfold(body, clauses, base, depth + 1))
            if not choices:
                plain.append(t)
                continue
            if t.p.value in base:
                choices.append(A.BGP((t,)))
            keep = [x.name for x in (t.s, t.o) if isinstance(x, Var)]
            one = [A.SubSelect(A.Query("select", tuple(dict.fromkeys(keep)), x)) for x in choices]
            both = one[0]
            for x in one[1:]:
                both = A.Union(both, x)
            out = A.And(out, both)
        return A.And(A.BGP(tuple(plain)), out) if plain else out
    if isinstance(p, (A.And, A.Union, A.Minus, A.Exists, A.NotExists)):
        return type(p)(unfold(p.left, clauses, base, depth), unfold(p.right, clauses, base, depth))
    if isinstance(p, A.Opt):
        return A.Opt(unfold(p.left, clauses, base, depth), unfold(p.right, clauses, base, depth), p.cond)
    if isinstance(p, A.Filter):
        return A.Filter(unfold(p.left, clauses, base, depth), p.cond)
    return p


def _substitute(p: object, b: dict[str, object]) -> object:
    from rulegraph.functions.expressions import Expr

    def term(x: object) -> object:
        if isinstance(x, Var):
            return b.get(x.name, x)
        if isinstance(x, Expr):
            return Expr(x.op, tuple(term(a) for a in x.args))
        return x

    if isinstance(p, A.BGP):
        return A.BGP(tuple(Triple(term(t.s), t.p, term(t.o)) for t in p.triples))
    if isinstance(p, (A.And, A.Union, A.Minus, A.Exists, A.NotExists)):
        return type(p)(_substitute(p.left, b), _substitute(p.right, b))
    if isinstance(p, A.Opt):
        return A.Opt(_substitute(p.left, b), _substitute(p.right, b), term(p.cond))
    if isinstance(p, A.Filter):
        return A.Filter(_substitute(p.left, b), term(p.cond))
    return p


def transitive_cte(graph: Graph, predicate: str, name: str = "edges", max_level: int = 100, seed: str | None = None) -> DataFrame:
    """The closure by the SQL engine's own recursion; for acyclic relations only, as it keeps repeated rows. A cross-check."""
    graph.view(predicate).df.createOrReplaceTempView(name)
    where = f" WHERE {seed}" if seed else ""
    return graph.spark.sql(
        f"WITH RECURSIVE t(s, o) MAX RECURSION LEVEL {max_level} AS (SELECT s, o FROM {name}{where} UNION ALL SELECT t.s, e.o FROM t JOIN {name} e ON t.o = e.s) SELECT DISTINCT s, o FROM t"
    )
