"""SimHash fingerprints and near-duplicate groups by segment bit counts.

A fingerprint is embedded as the vector of its segments' bit counts (32 segments
of two bits). The Manhattan distance of two such vectors never exceeds the
Hamming distance of the fingerprints, so a range join under it loses no pair.
The range is cut into grid cells by pigeonholes: vectors at distance 3 or less
agree on one of four blocks of the segments, then on one of four blocks of the rest, and
once more, so they meet in one of 64 cells, each of which fixes 18 or 19 segments.
Of unrelated fingerprints one pair in a million meets in any cell. Pairs that meet
are verified on the fingerprints.

Groups of close copies would make that join quadratic. Before it, fingerprints
that lie in one ball of radius 1 (at most 65 different ones, any two of them at
2 bits or less) are linked to the smallest of the ball; the join then returns
only links between components that are still apart.

Defined results: null and empty texts and texts without a word have fingerprint
zero and are linked like any other; equal fingerprints are always linked; rows
with equal doc_id are rows of their own; null doc_ids are skipped when the
smallest is sought.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulegraph.llm.common import chunks, cut, number_rows, words_of
from rulegraph.llm.components import connected_components

BLOCK_BYTES = 2_000_000


def fingerprint(text: str | None, width: int = 3, seed: int = 42) -> int:
    """64-bit SimHash of a text's word shingles, repeats included; signed."""
    w = words_of(text)
    if not w:
        return 0
    h = xxhash.xxh64_intdigest
    if len(w) <= width:
        hashes = [h(b" ".join(w), seed)]
    else:
        hashes = [h(b" ".join(s), seed) for s in zip(*(w[k:] for k in range(width)), strict=False)]
    bits = np.unpackbits(np.array(hashes, ">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(bits * 2 > len(hashes)).view(">i8")[0])


def fingerprints(docs: DataFrame, *, text: str = "text", keep: list[str], width: int = 3, seed: int = 42) -> DataFrame:
    """Columns ``keep`` with ``fp`` (bigint)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                fp = pa.array([fingerprint(t, width, seed) for t in part.column(0).to_pylist()], pa.int64())
                yield pa.RecordBatch.from_arrays([*part.columns[1:], fp], [*[f"k{i}" for i in range(len(keep))], "fp"])

    fields = ", ".join(f"k{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    out = docs.select(F.col(text).alias("_text"), *[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)]).mapInArrow(run, f"{fields}, fp bigint")
    return out.select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(keep)], "fp")


def _ball(fp: Column) -> Column:
    """The fingerprint and its 64 neighbours at one bit."""
    return F.array(fp, *[fp.bitwiseXOR(F.lit(1 << i if i < 63 else -(1 << 63)).cast("bigint")) for i in range(64)])


def _counts(fp: Column) -> Column:
    """Bit counts of the 32 two-bit segments, packed two bits each."""
    low = F.lit(0x5555555555555555)
    even, odd = fp.bitwiseAND(low), F.shiftrightunsigned(fp, 1).bitwiseAND(low)
    # a sum of two bits without a carry out of the highest segment
    return even.bitwiseXOR(odd).bitwiseOR(F.shiftleft(even.bitwiseAND(odd), 1))


def cell_masks(levels: int = 3, blocks: int = 4, segments: int = 32) -> list[int]:
    """Segments that a cell fixes, as masks of the packed counts: one block of those left, at each level."""
    out = [([], list(range(segments)))]
    for _ in range(levels):
        deeper = []
        for fixed, rest in out:
            for k in range(blocks):
                own = rest[k * len(rest) // blocks : (k + 1) * len(rest) // blocks]
                deeper.append((fixed + own, [x for x in rest if x not in own]))
        out = deeper
    return [sum(3 << 2 * x for x in fixed) for fixed, _ in out]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _cells(fp: Column) -> Column:
    """Hashes of a fingerprint's grid cells."""
    counts = _counts(fp)
    return F.array(*[F.xxhash64(F.lit(k), counts.bitwiseAND(F.lit(_signed(m)).cast("bigint"))) for k, m in enumerate(cell_masks())])


def close_links(nodes: DataFrame, max_bits: int = 3) -> DataFrame:
    """(a, b) links whose components are those of all pairs of ``nodes.fp`` at max_bits or less; fp are distinct."""
    if not 0 <= max_bits <= 3:
        raise ValueError("four blocks hold one that agrees: 0 to 3 bits")
    ball = nodes.select("fp", F.explode(_ball(F.col("fp"))).alias("key")) if max_bits >= 2 else nodes.select("fp", F.col("fp").alias("key"))
    # one ball holds 65 fingerprints at most
    held = ball.groupBy("key").agg(F.min("fp").alias("a"), F.max("fp").alias("z"), F.collect_list("fp").alias("all")).where("a != z")
    stars = cut(held.select("a", F.explode("all").alias("b")).where("a != b").distinct())
    roots = connected_components(stars)
    apart = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"))
    own = apart.select("fp", "root", F.explode(_cells(F.col("fp"))).alias("cell"))
    seek = own.select(F.col("fp").alias("fp2"), F.col("root").alias("root2"), F.col("cell").alias("cell2"))
    found = own.join(seek, (F.col("cell") == F.col("cell2")) & (F.col("root") < F.col("root2")) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= max_bits))
    far = found.select(F.col("root").alias("a"), F.col("root2").alias("b")).distinct()
    return stars.select("a", "b").unionByName(far)


def _grouped(marked: DataFrame, least: Column, max_bits: int) -> DataFrame:
    """(fp, least) of marked rows: the least value of the group that each fingerprint belongs to."""
    nodes = cut(marked.groupBy("fp").agg(F.min(least).alias("least")))
    roots = cut(connected_components(close_links(nodes.select("fp"), max_bits)))
    in_group = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    return in_group.join(in_group.groupBy("root").agg(F.min("least").alias("smallest")), "root").select("fp", F.col("smallest").alias("least"))


def near_duplicates(docs: DataFrame, *, text: str = "text", id: str = "doc_id", max_bits: int = 3, width: int = 3, seed: int = 42) -> DataFrame:
    """One row a document: id, fp, component_id (smallest id reachable over links of max_bits or less)."""
    marked = cut(fingerprints(docs, text=text, keep=[id], width=width, seed=seed))
    named = _grouped(marked, F.col(id), max_bits)
    return marked.join(named, "fp").select(id, "fp", F.col("least").alias("component_id"))


def drop_near_duplicates(docs: DataFrame, *, text: str = "text", id: str = "doc_id", max_bits: int = 3, width: int = 3, seed: int = 42) -> DataFrame:
    """docs with one row of each group: that with the smallest id (null is the last), then text hash, then row."""
    numbered, row, th = number_rows(docs, text)
    marked = cut(fingerprints(numbered, text=text, keep=[id, row, th], width=width, seed=seed))
    least = F.struct(F.col(id).isNull().alias("null"), F.col(id).alias("id"), F.col(th).alias("th"), F.col(row).alias("row"))
    stay = _grouped(marked, least, max_bits).select(F.col("least.row").alias(row)).distinct()
    return numbered.join(stay, row, "left_semi").select(*docs.columns)
