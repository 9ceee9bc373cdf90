"""Language identification with hyperdimensional profiles.

Every letter has a random +1/-1 vector. An n-gram is the elementwise product of
its letters' vectors, each rotated by its place from the end, so order matters.
A text is the sum of its n-grams' vectors, and a language's prototype is the sum
over its training texts. A text gets the language of the nearest prototype by
cosine.

Letters are lower-cased; everything else counts as one boundary mark. Prototype
sums are integers, so the result does not depend on how rows are partitioned.

Defined results: a text that is null, empty or has no letter is ``und`` with
score 0; so is every text if there is no labelled training row. Equal cosines go
to the language that sorts first. A negative cosine scores 0. Null labels are
never learned; repeated rows count as often as they occur; other columns than
those named are ignored, and any called ``lang_pred``, ``score`` or ``margin`` is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulegraph.llm.common import chunks

UNKNOWN = "und"
#: Texts are taken in blocks of about so many bytes, n-gram vectors in slices of so many rows.
BLOCK_BYTES, SLICE_ROWS = 2_000_000, 8192


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


@lru_cache(maxsize=20_000)
def _letter_vector(code: int, dims: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, code]).integers(0, 2, dims, dtype=np.int8) * np.int8(2) - np.int8(1)


class Profiler:
    """Turns blocks of texts into n-gram counts and bundled vectors."""

    def __init__(self, dims: int, n: int, seed: int):
        self.dims, self.n, self.seed = dims, n, seed

    def grams(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
        """Symbols of the block, the distinct n-grams as rows of symbol places, and (n-gram place, count) arrays per text."""
        parts = [np.frombuffer((" " + (t or "").lower() + " ").encode("utf-32-le", "surrogatepass"), np.uint32) for t in texts]
        flat = np.concatenate(parts)
        letter = _letters()[flat]
        flat = np.where(letter, flat, 32)
        # runs of non-letters become one mark; texts always begin with one
        keep = letter.copy()
        keep[1:] |= letter[:-1]
        keep[0] = True
        owner = np.repeat(np.arange(len(parts)), [len(p) for p in parts])
        keep[1:] |= owner[1:] != owner[:-1]
        flat, owner = flat[keep], owner[keep]
        present = np.bincount(flat, minlength=33) > 0
        symbols = np.flatnonzero(present)
        place = np.cumsum(present) - 1
        seq = place[flat]
        a, n = len(symbols), self.n
        code = seq[: len(seq) - n + 1].astype(np.int64)
        for k in range(1, n):
            code = code * a + seq[k : len(seq) - n + 1 + k]
        whole = owner[: len(code)] == owner[n - 1 :]
        # an n-gram of marks only says nothing
        code, owner = code[whole], owner[: len(whole)][whole]
        if a**n <= 1 << 23:
            seen = np.zeros(a**n, bool)
            seen[code] = True
            distinct = np.flatnonzero(seen)
            of = (np.cumsum(seen) - 1)[code]
        else:
            distinct, of = np.unique(code, return_inverse=True)
        rows = np.empty((len(distinct), n), np.int64)
        rest = distinct.copy()
        for k in range(n - 1, -1, -1):
            rest, rows[:, k] = np.divmod(rest, a)
        ends = np.searchsorted(owner, np.arange(len(texts) + 1))
        of = of.astype(np.uint16 if len(distinct) < 65536 else np.int64)
        out = []
        for i in range(len(texts)):
            own = np.sort(of[ends[i] : ends[i + 1]], kind="stable")
            first = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1]))) if len(own) else np.zeros(0, np.int64)
            out.append((own[first].astype(np.int64), np.diff(np.append(first, len(own)))))
        return symbols, rows, out

    def vectors(self, symbols: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """The bound vectors of n-grams, one a row."""
        base = np.stack([_letter_vector(int(c), self.dims, self.seed) for c in symbols])
        out = None
        for k in range(self.n):
            part = np.roll(base, self.n - 1 - k, axis=1)[rows[:, k]]
            out = part if out is None else out * part
        return out.astype(np.float32)

    def bundle(self, texts: list[str | None]) -> np.ndarray:
        """One vector a text: the count-weighted sum of its n-grams' vectors."""
        symbols, rows, counted = self.grams(texts)
        out = np.zeros((len(texts), self.dims), np.float64)
        for lo in range(0, len(rows), SLICE_ROWS):
            v = self.vectors(symbols, rows[lo : lo + SLICE_ROWS])
            for i, (at, n) in enumerate(counted):
                x, y = np.searchsorted(at, (lo, lo + SLICE_ROWS))
                if x < y:
                    out[i] += n[x:y].astype(np.float32) @ v[at[x:y] - lo]
        return out

    def bundle_groups(self, texts: list[str | None], group: list[int], groups: int) -> np.ndarray:
        """Exact integer sums over the texts of each group."""
        symbols, rows, counted = self.grams(texts)
        counts = np.zeros((groups, len(rows)))
        for g, (at, n) in zip(group, counted, strict=True):
            counts[g, at] += n
        out = np.zeros((groups, self.dims))
        for lo in range(0, len(rows), SLICE_ROWS):
            out += counts[:, lo : lo + SLICE_ROWS] @ self.vectors(symbols, rows[lo : lo + SLICE_ROWS]).astype(np.float64)
        return out.astype(np.int64)


def train_prototypes(docs: DataFrame, *, text: str = "text", lang: str = "lang", dims: int = 1024, n: int = 3, seed: int = 7) -> dict[str, np.ndarray]:
    """Prototype of each label: label -> integer vector. The driver gets labels x dims numbers, whatever the input's size."""
    profiler = Profiler(dims, n, seed)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                labels = part.column(1).to_pylist()
                names = sorted(set(labels))
                got = profiler.bundle_groups(part.column(0).to_pylist(), [names.index(x) for x in labels], len(names))
                for name, v in zip(names, got, strict=True):
                    total[name] = total[name] + v if name in total else v
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([v.tolist() for v in total.values()], pa.list_(pa.int64()))], ["label", "sums"])

    rows = docs.where(F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(text).alias("text"), F.col(lang).cast("string").alias("label"))
    partial = rows.mapInArrow(sums, "label string, sums array<bigint>")
    added = partial.select("label", F.posexplode("sums").alias("at", "x")).groupBy("label", "at").agg(F.sum("x").alias("x"))
    out: dict[str, np.ndarray] = {}
    for r in added.collect():
        out.setdefault(r["label"], np.zeros(dims, np.int64))[r["at"]] = r["x"]
    return dict(sorted(out.items()))


def predict_language(docs: DataFrame, prototypes: dict[str, np.ndarray], *, text: str = "text", keep: list[str] | None = None, dims: int = 1024, n: int = 3, seed: int = 7) -> DataFrame:
    """docs' columns ``keep`` (all by default) with ``lang_pred``, ``score`` and ``margin`` (lead over the second language)."""
    profiler, labels = Profiler(dims, n, seed), list(prototypes)
    proto = np.stack([prototypes[x] / max(1e-12, np.linalg.norm(prototypes[x])) for x in labels]) if labels else np.zeros((0, dims))
    keep = [c for c in docs.columns if c not in ("lang_pred", "score", "margin")] if keep is None else keep

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                texts = part.column(0).to_pylist()
                v = profiler.bundle(texts)
                has = [bool(t) and any(map(str.isalpha, t)) for t in texts]
                cos = v @ proto.T / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)
                ok = np.array(has) & (len(labels) > 0)
                best = cos.argmax(axis=1) if labels else np.zeros(len(texts), int)
                top = np.sort(cos, axis=1) if labels else np.zeros((len(texts), 1))
                lead = top[:, -1] - (top[:, -2] if top.shape[1] > 1 else 0)
                cols = [pa.array([labels[b] if o else UNKNOWN for b, o in zip(best, ok, strict=True)])]
                cols += [pa.array(np.where(ok, np.clip(x, 0, 1), 0).round(9)) for x in (top[:, -1], lead)]
                yield pa.RecordBatch.from_arrays([*part.columns[1:], *cols], [*[f"k{i}" for i in range(len(keep))], "lang_pred", "score", "margin"])

    picked = docs.select(F.col(text).alias("_text"), *[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)])
    fields = ", ".join(f"k{i} {t}" for i, t in enumerate(docs.schema[c].dataType.simpleString() for c in keep))
    out = picked.mapInArrow(score, f"{fields}, lang_pred string, score double, margin double")
    return out.select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(keep)], "lang_pred", "score", "margin")


def identify_language(docs: DataFrame, *, held_out: Column, keep: list[str] | None = None, **params) -> DataFrame:
    """Learn from the labelled rows that are not held out, then predict all rows."""
    return predict_language(docs, train_prototypes(docs.where(~held_out), **params), keep=keep, **params)
