"""Small graphs and comparisons for the tests."""

from rulegraph.engine import Engine
from rulegraph.sources.graphs import TripleGraph, term_text
from rulegraph.terms import Iri, Lit, Triple


def triples(text):
    """``s p o; s p 1``: names are IRIs, numbers literals."""
    out = []
    for part in filter(None, (x.strip() for x in text.split(";"))):
        s, p, o = part.split()
        out.append(Triple(Iri(s), Iri(p), Lit(int(o)) if o.lstrip("-").isdigit() else Iri(o)))
    return out


def engine(spark, text):
    return Engine(spark, TripleGraph.of(spark, triples(text)))


def rows(df):
    """Rows as a set of frozen (variable, text) pairs, unbound left out."""
    return {frozenset((c, r[c]) for c in df.columns if r[c] is not None and not c.startswith("__")) for r in df.collect()}


def as_text(mappings):
    return {frozenset((k, term_text(v)) for k, v in m) for m in mappings}
