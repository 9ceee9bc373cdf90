"""Line de-duplication with a deletion-neighbourhood join.

Two lines within one edit of each other share a variant: either both lose the
same character at the same place and become equal, or one loses a character and
becomes the other. So every line emits hashed keys of itself and of its
one-character deletions, equal keys are joined, pairs are verified by edit
distance, and the earliest line of the corpus stays.

Emitting a key a character for all lines would be far larger than the corpus.
Lines within one edit also share their first or last half, cut by the shorter
one's length; four half keys a line, counted, show the few lines that can have a
partner at all, and only those emit variants. Nothing is lost by that: a line
whose half keys nobody shares has no partner.

A line occurrence is removed if an equal line, or one within ``max_edits``,
occurs earlier (by document id, then text hash, then row, then place). All is judged
on the input, not on what is left. Lines are compared trimmed and in lower case.
Lines shorter than ``min_chars`` are never removed, those shorter than
``min_fuzzy_chars`` are only compared exactly, as one edit makes another line of them.

Rows are numbered and written once before anything else, and everything goes by that
number: equal ids with different texts stay apart, and of equal rows one keeps its
lines. Lines or keys that very many rows share are dealt to several tasks by a salt.

Defined results: null texts stay null and have no lines; blank lines stay; ids may be
of any type, null ones come first; extra columns pass through. Keys are 64-bit hashes
of pairs of which the near ones are verified on the texts; equality rests on a
128-bit hash.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulegraph.llm.common import chunks, cut, fresh, number_rows

BLOCK_BYTES = 2_000_000
#: Tasks that share the rows of one frequent key: the bits of a bigint.
SALTS = 64
_h64 = lambda s: xxhash.xxh3_64_intdigest(s) - (1 << 63)


def _h128(s: bytes) -> tuple[int, int]:
    a, b = divmod(xxhash.xxh3_128_intdigest(s), 1 << 64)
    return a - (1 << 63), b - (1 << 63)


def normal(line: str) -> str:
    return line.strip().lower()


def half_keys(line: str) -> list[int]:
    """Keys that two lines within one edit share at least one of: halves by the shorter line's length."""
    n, out = len(line), []
    for shorter in (n - 1, n):
        h = shorter // 2
        out.append(_h64(f"p{shorter}:{line[:h]}".encode("utf-8", "surrogatepass")))
        out.append(_h64(f"s{shorter}:{line[n - h :]}".encode("utf-8", "surrogatepass")))
    return out


def variants(line: str) -> list[tuple[int, int]]:
    """(place, key): the line itself at place -1, then the line without its character at each place."""
    raw = line
    return [(-1, _h64(raw.encode("utf-8", "surrogatepass")))] + [(i, _h64((raw[:i] + raw[i + 1 :]).encode("utf-8", "surrogatepass"))) for i in range(len(raw))]


def _lines(rows: DataFrame, min_chars: int, min_fuzzy: int, fuzzy: bool) -> DataFrame:
    """(id, th, row, no, h, h2, halves) of every line that takes part; h and h2 are its 128-bit hash."""
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                at, nos, h1, h2, halves = [], [], [], [], []
                for k, t in enumerate(part.column(0).to_pylist()):
                    for no, line in enumerate((t or "").split("\n")):
                        x = normal(line)
                        if len(x) >= min_chars and x:
                            at.append(k)
                            nos.append(no)
                            a, b = _h128(x.encode("utf-8", "surrogatepass"))
                            h1.append(a)
                            h2.append(b)
                            halves.append(half_keys(x) if fuzzy and len(x) >= min_fuzzy else [])
                own = part.select([1, 2, 3]).take(pa.array(at, pa.int64()))
                yield pa.RecordBatch.from_arrays([*own.columns, pa.array(nos, pa.int32()), pa.array(h1, pa.int64()), pa.array(h2, pa.int64()), pa.array(halves, pa.list_(pa.int64()))], ["id", "th", "row", "no", "h", "h2", "halves"])

    return rows.select("t", "id", "th", "row").mapInArrow(run, f"id {kind}, th bigint, row bigint, no int, h bigint, h2 bigint, halves array<bigint>")


def _variant_rows(lines: DataFrame) -> DataFrame:
    """(h, place, key) of lines given as (h, line)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 1, 40_000):
                hs, places, keys = [], [], []
                for h, line in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    for p, k in variants(line):
                        hs.append(h)
                        places.append(p)
                        keys.append(k)
                yield pa.RecordBatch.from_arrays([pa.array(hs, pa.int64()), pa.array(places, pa.int32()), pa.array(keys, pa.int64())], ["h", "place", "key"])

    return lines.select("h", "line").mapInArrow(run, "h bigint, place int, key bigint")


def _salts(bits: str) -> Column:
    """The salts that an or of their bits holds."""
    return F.explode(F.filter(F.sequence(F.lit(0), F.lit(SALTS - 1)), lambda k: F.getbit(F.col(bits), k) == 1))


def _bit(salt: str) -> Column:
    return F.bit_or(F.expr(f"shiftleft(1L, {salt})"))


def _with_shared_key(rows: DataFrame) -> DataFrame:
    """Rows (h, key, ...) whose key another h has too.

    The rows are dealt out once, by key and a salt of h, and both the counting and
    the picking read that exchange; a key that very many lines share is spread
    over as many tasks as there are salts.
    """
    dealt = rows.withColumn("salt", F.pmod("h", F.lit(SALTS)).cast("int")).repartition("key", "salt")
    part = dealt.groupBy("key", "salt").agg(F.min("h").alias("a"), F.max("h").alias("z"))
    shared = part.groupBy("key").agg(F.min("a").alias("a"), F.max("z").alias("z"), _bit("salt").alias("bits")).where("a != z")
    return dealt.join(shared.select("key", _salts("bits").alias("salt")), ["key", "salt"], "left_semi").drop("salt")


def repeated_lines(docs: DataFrame, *, text: str = "text", id: str = "doc_id", max_edits: int = 1, min_chars: int = 1, min_fuzzy_chars: int = 24) -> DataFrame:
    """(id, no) of every line occurrence to remove."""
    numbered, row, th = number_rows(docs, text)
    gone = _repeated(numbered, text, id, row, th, max_edits, min_chars, min_fuzzy_chars)
    return gone.join(numbered.select(F.col(row).alias("row"), F.col(id).alias("id")), "row").select("id", "no")


def _repeated(numbered: DataFrame, text: str, id: str, row: str, th: str, max_edits: int, min_chars: int, min_fuzzy_chars: int) -> DataFrame:
    """(row, no) of every line occurrence to remove."""
    if max_edits not in (0, 1):
        raise ValueError("deletion keys are emitted for 0 or 1 edits")
    rows = numbered.where(F.col(text).isNotNull()).select(F.col(text).alias("t"), F.col(id).alias("id"), F.col(th).alias("th"), F.col(row).alias("row"))
    lines = cut(_lines(rows, min_chars, min_fuzzy_chars, max_edits > 0))
    place = F.struct("id", "th", "row", "no")
    dealt = lines.select("h", "h2", "id", "th", "row", "no", F.pmod("row", F.lit(SALTS)).cast("int").alias("salt")).repartition("h", "h2", "salt")
    part = dealt.groupBy("h", "h2", "salt").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("n"))
    several = part.groupBy("h", "h2").agg(F.min("first").alias("first"), F.sum("n").alias("n"), _bit("salt").alias("bits")).where("n > 1")
    several = several.select("h", "h2", F.col("first.row").alias("_row"), F.col("first.no").alias("_no"), _salts("bits").alias("salt"))
    late = dealt.join(several.hint("merge"), ["h", "h2", "salt"]).where((F.col("row") != F.col("_row")) | (F.col("no") != F.col("_no"))).select("row", "no")
    if not max_edits:
        return late
    # lines of which a half occurs in another line of fitting length
    half = lines.select("h", F.explode("halves").alias("key"))
    may = _with_shared_key(half).select("h").distinct()
    # one occurrence gives the text
    may_first = cut(lines.select("h", "id", "th", "row", "no").join(may, "h").groupBy("h").agg(F.min(place).alias("first")))
    wanted = may_first.groupBy(F.col("first.row").alias("row")).agg(F.collect_list(F.struct(F.col("first.no").alias("no"), "h", "first")).alias("_want"))
    # dealt out at every size: the wanted lines grow with the corpus, so they are never sent to all tasks
    picked = rows.select("row", F.split("t", "\n").alias("_l")).join(wanted.hint("merge"), "row").select("_l", F.explode("_want").alias("w")).select(F.col("w.h").alias("h"), F.col("w.first").alias("first"), F.get("_l", F.col("w.no")).alias("line"))
    near = cut(_normal_lines(picked))
    live = _with_shared_key(_variant_rows(near)).join(near.select("h", "first"), "h")
    live = cut(live)
    same_place = live.where("place >= 0")
    least = same_place.groupBy("key", "place").agg(F.min(F.struct("first", "h")).alias("e"))
    subs = same_place.join(least, ["key", "place"]).where("h != e.h").select("h", F.col("e.h").alias("other"))
    whole = live.where("place < 0").select("key", F.col("h").alias("wh"), F.col("first").alias("wf"))
    less = live.where("place >= 0").join(whole, "key").where("h != wh")
    ins = less.select(F.when(F.col("first") > F.col("wf"), F.col("h")).otherwise(F.col("wh")).alias("h"), F.when(F.col("first") > F.col("wf"), F.col("wh")).otherwise(F.col("h")).alias("other"))
    links = subs.unionByName(ins).distinct()
    one, two = near.select("h", F.col("line").alias("x")), near.select(F.col("h").alias("other"), F.col("line").alias("y"))
    true_links = links.join(one, "h").join(two, "other").where(F.levenshtein("x", "y", max_edits).between(0, max_edits))
    gone = cut(true_links.select("h").distinct())
    return late.unionByName(lines.select("row", "no", "h").join(gone, "h", "left_semi").select("row", "no")).distinct()


def _normal_lines(picked: DataFrame) -> DataFrame:
    """Normal forms by the same code that hashed them."""
    first = picked.schema["first"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lines = [normal(x or "") for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(lines, pa.string())], ["h", "first", "line"])

    return picked.select("h", "first", "line").mapInArrow(run, f"h bigint, first {first}, line string")


def dedup_lines(docs: DataFrame, *, text: str = "text", id: str = "doc_id", max_edits: int = 1, min_chars: int = 1, min_fuzzy_chars: int = 24) -> DataFrame:
    """docs with ``text`` without repeated lines, and ``n_lines``, ``n_removed`` (lines with a word)."""
    numbered, row, th = number_rows(docs, text)
    gone = _repeated(numbered, text, id, row, th, max_edits, min_chars, min_fuzzy_chars)
    one, nos, every = (fresh(numbered, n) for n in ("of_row", "gone", "every"))
    gone = gone.groupBy(F.col("row").alias(one)).agg(F.sort_array(F.collect_list("no")).alias(nos))
    df = numbered.join(gone.hint("merge"), F.col(row) == F.col(one), "left").drop(one)
    df = df.withColumn(every, F.split(F.col(text), "\n"))
    kept = F.transform(F.array_except(F.sequence(F.lit(0), F.size(every) - 1), nos), lambda i: F.get(every, i))
    df = df.withColumn("n_lines", F.coalesce(F.size(F.filter(every, lambda x: x.rlike("\\S"))), F.lit(0)).cast("bigint"))
    df = df.withColumn("n_removed", F.coalesce(F.size(nos), F.lit(0)).cast("bigint"))
    df = df.withColumn(text, F.when(F.col(nos).isNull(), F.col(text)).otherwise(F.concat_ws("\n", kept)))
    return df.drop(every, nos, row, th)
