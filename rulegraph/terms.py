"""Terms, triples and rules: the vocabulary of patterns and of the rule language."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True, order=True)
class Var:
    name: str

    def __str__(self) -> str:
        return f"?{self.name}"


@dataclass(frozen=True, order=True)
class Blank:
    """Existential, local to its graph."""

    name: str

    def __str__(self) -> str:
        return f"_:{self.name}"


@dataclass(frozen=True, order=True)
class Iri:
    """An IRI; ``template{key}`` forms are native keys of a mapped table."""

    value: str

    def __str__(self) -> str:
        return f"<{self.value}>"


@dataclass(frozen=True)
class Lit:
    value: object
    dt: str = ""

    def __post_init__(self) -> None:
        if not self.dt:
            v = self.value
            object.__setattr__(self, "dt", "boolean" if isinstance(v, bool) else "integer" if isinstance(v, int) else "decimal" if isinstance(v, float) else "string")

    def __str__(self) -> str:
        if self.dt == "string":
            text = str(self.value).replace("\\", "\\\\").replace('"', '\\"').replace("\n", "\\n")
            return f'"{text}"'
        if self.dt == "boolean":
            return "true" if self.value else "false"
        if self.dt == "integer":
            return str(self.value)
        if self.dt == "decimal":
            return repr(float(self.value))
        return f'"{self.value}"^^{self.dt}'


@dataclass(frozen=True)
class ListTerm:
    items: tuple

    def __str__(self) -> str:
        return "(" + " ".join(map(str, self.items)) + ")"


@dataclass(frozen=True)
class GraphTerm:
    """A quoted graph."""

    triples: frozenset

    def __str__(self) -> str:
        return "{ " + " . ".join(sorted(str(t) for t in self.triples)) + " }"


@dataclass(frozen=True)
class Triple:
    s: object
    p: object
    o: object

    def __str__(self) -> str:
        return f"{self.s} {self.p} {self.o}"

    def terms(self) -> tuple:
        return (self.s, self.p, self.o)


@dataclass(frozen=True)
class Rule:
    """One implication: the head holds wherever the premise does."""

    name: str
    premise: frozenset
    head: tuple
    direction: str = "forward"

    def __str__(self) -> str:
        body, head = "{ " + " . ".join(sorted(map(str, self.premise))) + " }", "{ " + " . ".join(map(str, self.head)) + " }"
        return f"{body} => {head} ." if self.direction == "forward" else f"{head} <= {body} ."


#: The empty subject of closure-wide tests.
CLOSURE = Blank("closure")
INCLUDES, NOT_INCLUDES, UNION, OPT, MINUS_P, TEST, RESULT = (Iri(f"rt:{x}") for x in ("includes", "notIncludes", "union", "opt", "minus", "test", "result"))
COPY, CONJUNCTION, EQUAL_TO, NOT_EQUAL_TO = (Iri(f"rt:{x}") for x in ("copy", "conjunction", "equalTo", "notEqualTo"))
#: Comparison builtins of the rule language.
COMPARE = {"<": Iri("math:lessThan"), ">": Iri("math:greaterThan"), "<=": Iri("math:notGreaterThan"), ">=": Iri("math:notLessThan"), "=": Iri("math:equalTo"), "!=": Iri("math:notEqualTo")}
BUILTINS = frozenset(COMPARE.values())


def term_vars(t: object) -> frozenset[str]:
    """Names of all variables in a term, quoted graphs and lists included."""
    if isinstance(t, Var):
        return frozenset((t.name,))
    if isinstance(t, ListTerm):
        return frozenset().union(*map(term_vars, t.items))
    if isinstance(t, GraphTerm):
        return graph_vars(t.triples)
    if isinstance(t, Triple):
        return frozenset().union(*map(term_vars, t.terms()))
    if hasattr(t, "expr_vars"):
        return t.expr_vars()
    return frozenset()


def graph_vars(triples) -> frozenset[str]:
    return frozenset().union(*map(term_vars, triples))


def is_closed(t: object) -> bool:
    """No variables; lists hold closed items only."""
    return not term_vars(t)


def copy_graph(g: GraphTerm, tag: str) -> GraphTerm:
    """The same graph with a fresh name for every variable."""
    return relabel(g, frozenset(), tag)


def conjunction(*graphs: GraphTerm) -> GraphTerm:
    return GraphTerm(frozenset().union(*(g.triples for g in graphs)))


def same_shape(g: GraphTerm, predicate: Iri) -> bool:
    """Whether the graph is a single triple between two graphs with that predicate."""
    if len(g.triples) != 1:
        return False
    (t,) = g.triples
    return t.p == predicate and isinstance(t.s, GraphTerm) and isinstance(t.o, GraphTerm)


def relabel(t: object, keep: frozenset[str], tag: str) -> object:
    """t with every variable outside ``keep`` renamed by a suffix that occurs nowhere else."""
    if isinstance(t, Var):
        return t if t.name in keep else Var(f"{t.name}__{tag}")
    if isinstance(t, ListTerm):
        return ListTerm(tuple(relabel(x, keep, tag) for x in t.items))
    if isinstance(t, GraphTerm):
        return GraphTerm(frozenset(relabel(x, keep, tag) for x in t.triples))
    if isinstance(t, Triple):
        return Triple(*(relabel(x, keep, tag) for x in t.terms()))
    if isinstance(t, frozenset):
        return frozenset(relabel(x, keep, tag) for x in t)
    if hasattr(t, "relabel"):
        return t.relabel(keep, tag)
    return t
