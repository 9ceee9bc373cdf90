"""Packing token sequences by shortest-pack-first over the length histogram.

Documents become pieces: whole sequences of ``max_tokens`` and a rest. The rests'
lengths are counted, and the histogram (at most ``max_tokens`` entries, whatever
the corpus) is packed on the driver: lengths are placed longest first, each into
the fullest pattern of packs that it still fits (the one with the shortest room
left), whose count is split as the histogram tells; what fits nowhere opens new
packs. The patterns then become intervals of ranks, and pieces find theirs by
their rank within their length, which is counted by blocks so that no length,
however frequent, is ranked in one task.

Ids are cut at white space before the tokenizer sees them, and words already seen
by a worker are not encoded again; that gives the tokenizer's own ids, as its
patterns never cross white space.

Defined results: null and empty texts are the end id alone; rows with equal ids
are packed as documents of their own; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import re
import struct
import unicodedata
import zlib
from array import array
from bisect import bisect_left, insort
from collections import defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rulegraph.llm.common import chunks, cut

BLOCK_BYTES = 2_000_000
#: Words of which a worker keeps the ids, twice: when full, the younger half becomes the older.
CACHE_WORDS = 700_000


def _byte_letters() -> dict[int, int]:
    """The letter that byte-level models write for each byte: printable ones for themselves, the others from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = (b for b in range(256) if b not in plain)
    return {b: b for b in plain} | {b: 256 + i for i, b in enumerate(rest)}


class WordTokenizer:
    """Ids of texts by a tokenizer whose patterns never cross white space, with a bounded memory of words.

    Words of Latin letters, digits and signs are normalised and split here, by the
    tokenizer's own pattern, and only their pieces go to its model; any other word
    goes through the whole tokenizer.
    """

    def __init__(self, path: str, cache_words: int = CACHE_WORDS):
        import json
        import os

        import regex

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.bpe = self.tokenizer.model.tokenize
        with open(path) as f:
            spec = json.load(f)
        steps = [x["type"] for x in (spec["normalizer"] or {}).get("normalizers", [])]
        splits = (spec["pre_tokenizer"] or {}).get("pretokenizers", [])
        # the short way is for this kind of tokenizer alone
        self.short = steps == ["NFC", "Replace", "Lowercase"] and [x["type"] for x in splits] == ["Split", "ByteLevel"] and splits[0]["invert"] and not splits[1]["add_prefix_space"]
        self.pieces = regex.compile(splits[0]["pattern"]["Regex"]).findall if self.short else None
        self.letters = _byte_letters()
        self.latin = re.compile("[\x21-\x7e\xa1-\u024f]+").fullmatch
        self.cache_words = cache_words
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.signs: dict[str, bytes] = {}
        # characters that str.split() would cut at, but the tokenizer does not
        self.odd = re.compile("[\x1c-\x1f]")
        self.space = re.compile("[ \t\n\r\x0b\x0c]+")

    def _piece(self, x: str) -> bytes:
        """Ids of a piece, which are those of the word that is nothing else."""
        got = self.known.get(x) or self.older.get(x) or self.signs.get(x)
        if got is None:
            ids = [t.id for t in self.bpe(x if x.isascii() else x.encode().decode("latin-1").translate(self.letters))]
            got = struct.pack(f"<{len(ids)}I", *ids)
            # signs follow many words and seldom stand alone
            if len(x) <= 4 and not x.isalpha() and len(self.signs) < 50_000:
                self.signs[x] = got
        return got

    def _word(self, w: str) -> bytes:
        got = self.older.get(w)
        if got is None:
            if self.short and w.isascii() and w.isalpha():
                # most words: one piece, nothing to normalise
                low = w.lower()
                got = self.older.get(low) if low != w else None
                if got is None:
                    got = array("I", [t.id for t in self.bpe(low)]).tobytes()
            elif self.short and "<|" not in w and self.latin(w):
                low = w.lower() if w.isascii() else "".join(map(str.lower, unicodedata.normalize("NFC", w)))
                if low.isalpha():
                    got = self._piece(low)
                elif low[:-1].isalpha():
                    got = self._piece(low[:-1]) + self._piece(low[-1])
                else:
                    got = b"".join(map(self._piece, self.pieces(low)))
            else:
                ids = self.tokenizer.encode(w, add_special_tokens=False).ids
                got = struct.pack(f"<{len(ids)}I", *ids)
        if len(self.known) >= self.cache_words:
            self.older, self.known = self.known, {}
        self.known[w] = got
        return got

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian 32-bit numbers."""
        out = []
        for t in texts:
            t = t or ""
            words = [w for w in self.space.split(t) if w] if self.odd.search(t) else t.split()
            parts = [*map(self.known.get, words)]
            at = 0
            while True:
                try:
                    at = parts.index(None, at)
                except ValueError:
                    break
                parts[at] = self.known.get(words[at]) or self._word(words[at])
                at += 1
            out.append(b"".join(parts))
        return out


def pieces(docs: DataFrame, *, tokenizer: str, text: str = "text", id: str = "doc_id", max_tokens: int = 2048, end_id: int = 1) -> DataFrame:
    """(id, row, start, length, ids_crc32, doc_tokens) of every piece; row tells documents with equal ids apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = WordTokenizer(tokenizer)
        last = struct.pack("<I", end_id)
        n_rows = 0
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                at, rows = [], []
                for i, ids in enumerate(encoder.encode(part.column(0).to_pylist())):
                    ids += last
                    n = len(ids) // 4
                    for start in range(0, n, max_tokens):
                        own = ids[4 * start : 4 * (start + max_tokens)]
                        at.append(i)
                        rows.append((n_rows + i, start, len(own) // 4, zlib.crc32(own), n))
                n_rows += part.num_rows
                cols = [pa.array(c, pa.int64()) for c in zip(*rows, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(1).take(pa.array(at)), *cols], ["id", "row", "start", "length", "ids_crc32", "doc_tokens"])

    kind = docs.schema[id].dataType.simpleString()
    got = docs.select(F.col(text).alias("t"), F.col(id).alias("id")).mapInArrow(run, f"id {kind}, row bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint")
    return got.withColumn("part", F.spark_partition_id())


def shortest_pack_first(histogram: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Packing patterns and their counts: (lengths in order of placing, packs of that pattern)."""
    rooms: list[int] = []
    by_room: dict[int, list[list]] = defaultdict(list)

    def put(pattern: tuple[int, ...], count: int, room: int) -> None:
        if not by_room[room]:
            insort(rooms, room)
        by_room[room].append([pattern, count])

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            k = bisect_left(rooms, length)
            if k == len(rooms):
                # as many of the length as fit go into one new pack
                each = capacity // length
                if left >= each:
                    put((length,) * each, left // each, capacity - each * length)
                    left %= each
                if left:
                    put((length,) * left, 1, capacity - left * length)
                left = 0
                break
            room = rooms[k]
            pattern, count = by_room[room].pop()
            if not by_room[room]:
                rooms.pop(k)
            each = room // length
            full = min(count, left // each)
            if full:
                put(pattern + (length,) * each, full, room - each * length)
                left -= full * each
                count -= full
            if count and left and left < each:
                put(pattern + (length,) * left, 1, room - left * length)
                left = 0
                count -= 1
            if count:
                put(pattern, count, room)
    merged: dict[tuple[int, ...], int] = defaultdict(int)
    for groups in by_room.values():
        for pattern, count in groups:
            merged[pattern] += count
    return sorted(merged.items())


def _intervals(patterns: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, count, first sequence, offset) of each place in each pattern."""
    used: dict[int, int] = defaultdict(int)
    out, sequence = [], 0
    for pattern, count in patterns:
        offset = 0
        for length in pattern:
            out.append((length, used[length], count, sequence, offset))
            used[length] += count
            offset += length
        sequence += count
    return out


def pack(docs: DataFrame, *, tokenizer: str, text: str = "text", id: str = "doc_id", max_tokens: int = 2048, end_id: int = 1) -> DataFrame:
    """One row a piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    spark = docs.sparkSession
    cut_up = cut(pieces(docs, tokenizer=tokenizer, text=text, id=id, max_tokens=max_tokens, end_id=end_id))
    # rank within the length: places before the block, and the place in it
    blocks = cut_up.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    ahead = blocks.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).select("length", "part", F.coalesce("before", F.lit(0)).alias("before"))
    ranked = cut_up.withColumn("k", F.row_number().over(Window.partitionBy("length", "part").orderBy("row", "start")))
    ranked = ranked.join(ahead, ["length", "part"]).withColumn("rank", F.col("before") + F.col("k") - 1)
    histogram = {r["length"]: r["n"] for r in cut_up.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    rows = _intervals(shortest_pack_first(histogram, max_tokens))
    slots = spark.createDataFrame(pa.table({n: pa.array([r[i] for r in rows], pa.int64()) for i, n in enumerate(("l", "first", "count", "sequence", "offset"))}).to_pandas() if rows else [], "l bigint, first bigint, count bigint, sequence bigint, offset bigint")
    # as many intervals as patterns have places: bounded by max_tokens, not by the corpus
    at = (F.col("length") == F.col("l")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("first") + F.col("count"))
    out = ranked.join(F.broadcast(slots), at)
    return out.select(F.col("id").alias(id), "start", "length", "ids_crc32", "doc_tokens", (F.col("sequence") + F.col("rank") - F.col("first")).alias("sequence_id"), "offset")


def padding(histogram: dict[int, int], capacity: int) -> float:
    """Share of padded places that shortest_pack_first leaves."""
    patterns = shortest_pack_first(histogram, capacity)
    packs = sum(c for _, c in patterns)
    return 1 - sum(k * v for k, v in histogram.items()) / (packs * capacity) if packs else 0.0
