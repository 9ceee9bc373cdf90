"""Repeated substrings by a distributed merge sort of suffixes that carries common prefixes.

Every window of ``passage`` bytes has an anchor: the place of the smallest hash among
its first 16-byte grams, the first of equal ones. Equal windows have their anchor at
the same place, so only suffixes that start at anchors, one byte in about 97, have
to be sorted to bring equal windows together. What an anchor's windows need lies
between its first window and ``length`` bytes behind the start of its last: its context.

Two merge sorts, as prefix doubling has it. The first tells which suffixes share their
first 48 bytes with another at all: tasks sort the suffixes of their texts, cut them into
ranges by common splitters and send each range as a front-coded run, for each suffix the
length of the prefix that it shares with the one before, and the rest. A range's
runs are merged by a tree of losers whose players carry the length of the prefix they
share with the last winner: where two lengths differ, the longer one wins without a
look at the bytes; where they are equal, comparison starts behind that prefix, so no
known prefix is compared again. The second sorts the rest: of suffixes that are not
alone, the whole suffix as far as its context goes is front-coded and merged in the
same way, and now the merge's own prefix lengths say how far two suffixes agree to the right.
Within a group they are joined from the longest prefix down; where two parts of a group
meet, neighbours in the order of the bytes before the anchor, read backwards, say how
far they agree to the left. Left and right together are a match; a byte is removed if
a match of ``length`` bytes or more covers it. So lengths are decided on bytes, and copies
are never paired with one another.

Contexts that are equal as a whole, by a 128-bit hash, are one class and repeated by
that alone. Classes are made in each run before it is sent, so that copies cost a row a
run; a key that turns up often in a sample of keys is dealt to several ranges by
class; and groups of more than ``GROUP_CLASSES`` classes have their windows counted by
shuffle, since a task could not hold them. These ways give the same result.

Beside what is removed, passages are reported: runs of bytes covered by strings of
``passage`` bytes that also start elsewhere, if they hold more than ``passage_words`` words.

A byte is removed if any string of ``length`` bytes over it occurs anywhere else, in the
same text as well; strings are judged on the input.

Defined results: null and empty texts have no bytes and nothing to remove; texts
shorter than ``length`` never lose a byte; rows with equal ids and texts count as
two occurrences; ids may be of any type and null; extra columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulegraph.llm.common import chunks, cut

GRAM, KEY = 16, 48
BLOCK_BYTES, RUN_SUFFIXES = 2_000_000, 150_000
#: Classes of a group up to which one task holds it.
GROUP_CLASSES = 20_000
#: Bytes of text for each range of the sorted order, and classes for each part of the second sort.
RANGE_TEXT, PART_CLASSES = 16_000_000, 20_000
#: Ranges that share a frequent key.
HOT_RANGES = 16
#: Window starts whose grams are hashed at once.
ANCHOR_BLOCK = 1 << 22
_MASK = (1 << 28) - 1


def anchors(data: bytes, length: int, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, first window, last window) of the text's windows; every window start lies in one of the ranges."""
    n = len(data) - length + 1
    if n <= ANCHOR_BLOCK:
        return _anchors(data, length, window)
    # a range that a block's end cuts is two ranges with one anchor
    parts = []
    for at in range(0, n, ANCHOR_BLOCK):
        got = _anchors(data[at : at + ANCHOR_BLOCK + length - 1], length, window)
        parts.append([x + at for x in got])
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _anchors(data: bytes, length: int, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n = len(data) - length + 1
    if n <= 0:
        return (np.zeros(0, np.int64),) * 3
    need = n + window - 1
    raw = np.frombuffer(data, np.uint8)
    words = np.lib.stride_tricks.sliding_window_view(raw[: need + GRAM - 1], 8)
    words = np.ascontiguousarray(words).view("<u8").ravel()
    h = words[:need] * np.uint64(0x9E3779B97F4A7C15)
    h ^= words[8 : 8 + need] * np.uint64(0xC2B2AE3D27D4EB4F)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h &= np.uint64(0xFFFFFFFFFFFFFFFF ^ _MASK)
    h |= np.arange(need, dtype=np.uint64)
    # sliding minimum: minima towards both ends of blocks as long as the window
    pad = -need % window
    a = np.concatenate([h, np.full(pad, 0xFFFFFFFFFFFFFFFF, np.uint64)]).reshape(-1, window)
    ahead = np.minimum.accumulate(a, axis=1).ravel()
    back = np.minimum.accumulate(a[:, ::-1], axis=1)[:, ::-1].ravel()
    least = np.minimum(back[:n], ahead[window - 1 : window - 1 + n])
    at = (least & np.uint64(_MASK)).astype(np.int64)
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    return at[first], first, np.append(first[1:], n) - 1


def _shared(a: bytes, b: bytes, start: int) -> int:
    """Length of the common prefix, known to be ``start`` at least."""
    n = min(len(a), len(b))
    if a[start:n] == b[start:n]:
        return n
    while n - start > 8:
        mid = (start + n) >> 1
        if a[start:mid] == b[start:mid]:
            start = mid
        else:
            n = mid
    while a[start] == b[start]:
        start += 1
    return start


def front_code(keys: list[bytes]) -> tuple[np.ndarray, list[bytes]]:
    """Shared prefix lengths with the key before, and the rests, of sorted keys."""
    shared, rests, last = np.zeros(len(keys), "<u2"), [], b""
    for i, k in enumerate(keys):
        n = _shared(last, k, 0)
        shared[i] = n
        rests.append(k[n:])
        last = k
    return shared, rests


class Run:
    """A front-coded sorted run; ``key`` is the head, ``lcp`` what it shares with the key before it."""

    __slots__ = ("shared", "rests", "ends", "at", "key", "lcp")

    def __init__(self, shared: np.ndarray, lengths: np.ndarray, rests: bytes):
        self.shared, self.rests = shared.tolist(), rests
        self.ends = [0, *np.cumsum(lengths, dtype=np.int64).tolist()]
        self.at, self.key, self.lcp = -1, b"", 0
        self.step()

    def step(self) -> None:
        self.at += 1
        if self.at == len(self.shared):
            self.key = None
            return
        self.lcp = self.shared[self.at]
        self.key = self.key[: self.lcp] + self.rests[self.ends[self.at] : self.ends[self.at + 1]]


def merge_runs(runs: list[Run]) -> Iterator[tuple[int, int, int, bytes]]:
    """(run, place in it, prefix shared with the key before, key) in sorted order, by a tree of losers over prefix lengths.

    Every player's ``lcp`` is what it shares with the last winner: for the run
    that has just won that is its own front coding, and for a loser what the game that it
    lost has found.
    """
    k = 1
    while k < len(runs):
        k *= 2
    losers: list[int] = [-1] * k

    def play(x: int, y: int) -> tuple[int, int]:
        """(winner, loser); the loser's lcp becomes what it shares with the winner."""
        if x < 0 or runs[x].key is None:
            return y, x
        if y < 0 or runs[y].key is None:
            return x, y
        a, b = runs[x], runs[y]
        if a.lcp != b.lcp:
            # the one that shares more with the last winner is smaller, and the other differs from both at its own lcp
            return (x, y) if a.lcp > b.lcp else (y, x)
        n = _shared(a.key, b.key, a.lcp)
        if a.key[n:] <= b.key[n:]:
            b.lcp = n
            return x, y
        a.lcp = n
        return y, x

    for r in runs:
        r.lcp = 0
    level = list(range(len(runs))) + [-1] * (k - len(runs))
    node = k
    while len(level) > 1:
        node //= 2
        above = []
        for i in range(0, len(level), 2):
            w, lost = play(level[i], level[i + 1])
            losers[node + i // 2] = lost
            above.append(w)
        level = above
    winner = level[0] if level else -1
    while winner >= 0 and runs[winner].key is not None:
        r = runs[winner]
        yield winner, r.at, r.lcp, r.key
        r.step()
        node = (winner + k) >> 1
        while node:
            # most games are decided by the lengths alone
            other = losers[node]
            winner, losers[node] = play(winner, other)
            node >>= 1


_u2, _u4, _i8 = "<u2", "<u4", "<i8"


def _pack(values: list[int], kind: str) -> bytes:
    return np.array(values, kind).tobytes()


def _record(cols: list[tuple[str, pa.DataType, object]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(v, t) for _, t, v in cols], [n for n, _, _ in cols])


# ---------------------------------------------------------------- first sort: which suffixes are not alone

#: A run of one range: front-coded keys, classes, places, and the texts (two hashes each) that places refer to.
_RUN = "range int, shared binary, lengths binary, rests binary, classes binary, texts binary, at binary, first binary, size binary, many binary, docs binary, whole binary"
_MEMBER = "gid bigint, k1 bigint, k2 bigint, at bigint, a bigint, z bigint"


class Ranges:
    """Ranges of the sorted order; frequent keys have several of their own, dealt by class."""

    def __init__(self, splitters: list[bytes], hot: dict[bytes, int]):
        self.splitters, self.hot = splitters, hot

    def of(self, key: bytes, cls: bytes) -> int:
        k = self.hot.get(key)
        return bisect.bisect_right(self.splitters, key) if k is None else len(self.splitters) + 1 + k * HOT_RANGES + cls[0] % HOT_RANGES


def make_ranges(sample: list[bytes], ranges: int) -> Ranges:
    """Splitters at the quantiles of a sample of keys; a key that fills two quantiles or more is frequent."""
    if not sample:
        return Ranges([], {})
    sample = sorted(sample)
    at = [sample[len(sample) * k // ranges] for k in range(1, ranges)]
    often = sorted({x for x, y in zip(at, at[1:], strict=False) if x == y})
    return Ranges(sorted(set(at)), {k: i for i, k in enumerate(often)})


def _runs(rows: DataFrame, ranges: Ranges, length: int, passage: int) -> DataFrame:
    window = passage - KEY + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        texts: list[tuple[int, int]] = []

        def flush() -> Iterator[pa.RecordBatch]:
            # equal contexts of this run are one entry, and known to be repeated
            held.sort(key=lambda r: (r[0], r[1]))
            kept, whole, i = [], [], 0
            while i < len(held):
                j = i + 1
                while j < len(held) and held[j][1] == held[i][1] and held[j][0] == held[i][0]:
                    j += 1
                kept.append((*held[i], j - i > 1))
                if j - i > 1:
                    whole += [(r[2], r[4], r[4] + r[5]) for r in held[i:j]]
                i = j
            by: dict[int, list[tuple]] = {}
            for r in kept:
                by.setdefault(ranges.of(r[0], r[1]), []).append(r)
            done = _pack([x for r in _joined(whole, length) for x in r], _i8)
            for which, own in by.items():
                shared, rests = front_code([r[0] for r in own])
                used = sorted({r[2] for r in own} | ({r[0] for r in _triples(done)} if done else set()))
                index = {d: k for k, d in enumerate(used)}
                cols = [
                    shared.tobytes(), _pack([len(x) for x in rests], _u2), b"".join(rests), b"".join(r[1] for r in own), _pack([index[r[2]] for r in own], _u4), _pack([r[3] for r in own], _u4),
                    _pack([r[4] for r in own], _u4), _pack([r[5] for r in own], _u2), _pack([r[6] for r in own], "u1"), _pack([x for d in used for x in texts[d]], _i8), _pack([x for d, a, z in _triples(done) for x in (index[d], a, z)], _i8) if done else b"",
                ]
                yield pa.RecordBatch.from_arrays([pa.array([which], pa.int32()), *[pa.array([c], pa.binary()) for c in cols]], [f.split()[0] for f in _RUN.split(", ")])
                # the repeated stretches found here go along with the first run
                done = b""
            held.clear()
            texts.clear()

        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                for t, k1, k2 in zip(*(part.column(i).to_pylist() for i in range(3)), strict=True):
                    data = t.encode("utf-8", "surrogatepass")
                    doc = len(texts)
                    texts.append((k1, k2))
                    for a, first, last in zip(*anchors(data, passage, window), strict=True):
                        a, first = int(a), int(first)
                        context = data[first : last + length]
                        # the anchor's place in its context is part of the class
                        held.append((data[a : a + KEY], xxhash.xxh3_128_digest(context, a - first), doc, a, first, len(context)))
                        if len(held) >= RUN_SUFFIXES:
                            yield from flush()
                            doc = 0
                            texts.append((k1, k2))
        yield from flush()

    return rows.select("t", "k1", "k2").mapInArrow(run, _RUN)


def _triples(data: bytes) -> list[tuple[int, int, int]]:
    return [tuple(x) for x in np.frombuffer(data, _i8).reshape(-1, 3).tolist()]


def _joined(spans: list[tuple[int, int, int]], length: int) -> list[tuple[int, int, int]]:
    """(text, start, end) with those of one text that overlap joined, the long ones apart from the short ones."""
    out: list[tuple[int, int, int]] = []
    for long in (True, False):
        last = None
        for d, a, z in sorted(x for x in spans if (x[2] - x[1] >= length) == long):
            if long and last is not None and last[0] == d and a <= last[2]:
                last = (d, last[1], max(z, last[2]))
                out[-1] = last
            else:
                last = (d, a, z)
                out.append(last)
    return out


def _merge(table: pa.Table, plain: int) -> pa.Table:
    """Of a range (a frequent key's, if numbered above ``plain``): stretches that are repeated as a whole (gid null), and one row for each class of groups that have several."""
    col = {n: table.column(n).to_pylist() for n in table.column_names}
    array = lambda name, kind: [np.frombuffer(x, kind) for x in col[name]]
    texts, docs = [x.reshape(-1, 2) for x in array("docs", _i8)], array("texts", _u4)
    at, first, size, many = array("at", _u4), array("first", _u4), array("size", _u2), array("many", "u1")
    out: list[tuple] = []
    for r, data in enumerate(col["whole"]):
        for d, a, z in _triples(data):
            out.append((None, *texts[r][d].tolist(), None, a, z))

    def end(group: list[tuple[int, int]], key: bytes) -> None:
        if len(group) == 1 and not hot:
            return
        classes: dict[bytes, list[tuple[int, int]]] = {}
        for r, i in group:
            classes.setdefault(col["classes"][r][16 * i : 16 * i + 16], []).append((r, i))
        gid = xxhash.xxh3_64_intdigest(key) - (1 << 63)
        for members in classes.values():
            if len(members) > 1:
                for r, i in members:
                    if not many[r][i]:
                        a = int(first[r][i])
                        out.append((None, *texts[r][docs[r][i]].tolist(), None, a, a + int(size[r][i])))
            if len(classes) > 1 or hot:
                r, i = members[0]
                a = int(first[r][i])
                out.append((gid, *texts[r][docs[r][i]].tolist(), int(at[r][i]), a, a + int(size[r][i])))

    hot = col["range"][0] > plain
    runs = [Run(np.frombuffer(s, _u2), np.frombuffer(n, _u2), x) for s, n, x in zip(col["shared"], col["lengths"], col["rests"], strict=True)]
    group, key = [], b""
    for r, i, lcp, now in merge_runs(runs):
        if lcp < KEY and group:
            end(group, key)
            group = []
        key = now
        group.append((r, i))
    if group:
        end(group, key)
    return pa.table({n: pa.array([x[k] for x in out], pa.int64()) for k, n in enumerate(("gid", "k1", "k2", "at", "a", "z"))})


# ---------------------------------------------------------------- second sort: how far they agree

_OPEN = "part int, shared binary, lengths binary, rests binary, lefts binary, sizes binary, docs binary"
_SPAN = "k1 bigint, k2 bigint, a bigint, z bigint"


def _contexts(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """(gid, k1, k2, at, left, right) of the classes' members, bytes before and from the anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                out, held = [], 0
                for t, k1, k2, places in zip(*(part.column(i).to_pylist() for i in range(4)), strict=True):
                    data = t.encode("utf-8", "surrogatepass")
                    for p in places:
                        at, a, z = p["at"], p["a"], p["z"]
                        out.append((p["gid"], k1, k2, at, data[a:at], data[at:z]))
                        held += z - a
                        if held > 4 * BLOCK_BYTES:
                            yield _rows(out)
                            out, held = [], 0
                if out:
                    yield _rows(out)

    def _rows(out: list[tuple]) -> pa.RecordBatch:
        kinds = (("gid", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("at", pa.int64()), ("left", pa.binary()), ("right", pa.binary()))
        return _record([(n, k, [r[i] for r in out]) for i, (n, k) in enumerate(kinds)])

    texts = rows.join(wanted.withColumnsRenamed({"k1": "_1", "k2": "_2"}), (F.col("k1") == F.col("_1")) & (F.col("k2") == F.col("_2")))
    return texts.select("t", "k1", "k2", "places").mapInArrow(run, "gid bigint, k1 bigint, k2 bigint, at bigint, left binary, right binary")


def _open_runs(contexts: DataFrame, parts: int) -> DataFrame:
    """Front-coded sorted runs of group and suffix, for each part of the groups."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def flush() -> Iterator[pa.RecordBatch]:
            by: dict[int, list[tuple]] = {}
            # rows with equal ids and texts give the same contexts, and their classes are known to be repeated
            for r in {r[:4]: r for r in held}.values():
                by.setdefault(r[0] % parts, []).append(r)
            for part, own in by.items():
                own = sorted(((r[0] + (1 << 63)).to_bytes(8, "big") + r[5], *r[1:5]) for r in own)
                shared, rests = front_code([r[0] for r in own])
                cols = [shared.tobytes(), _pack([len(x) for x in rests], _u2), b"".join(rests), b"".join(r[4] for r in own), _pack([len(r[4]) for r in own], _u2), _pack([x for r in own for x in r[1:4]], _i8)]
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), *[pa.array([c], pa.binary()) for c in cols]], [f.split()[0] for f in _OPEN.split(", ")])
            held.clear()

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                held.append(row)
                size += len(row[4]) + len(row[5]) + 150
                if size > 16 * BLOCK_BYTES:
                    yield from flush()
                    size = 0
        yield from flush()

    return contexts.select("gid", "k1", "k2", "at", "left", "right").mapInArrow(run, _OPEN)


def group_matches(lefts: list[bytes], prefixes: list[int], least: int) -> list[tuple[int, int, int]]:
    """(member, bytes left, bytes right) of matches of ``least`` bytes or more between members in merged order.

    ``prefixes`` holds what each member's suffix shares with the one before it, from the
    merge; ``lefts`` the bytes before it. Parts are joined from the longest shared prefix
    down, the smaller into the larger, each sorted by its left bytes read backwards;
    what a new neighbour in that order shares is the most that any member of the other part
    does, or no more than what a neighbour of its own part has shown at a prefix no shorter.
    """
    out: list[tuple[int, int, int]] = []
    part: list[list[tuple[bytes, int]]] = [[(x[::-1], i)] for i, x in enumerate(lefts)]
    up = list(range(len(lefts)))

    def find(i: int) -> int:
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    for i in sorted(range(1, len(lefts)), key=lambda i: -prefixes[i]):
        right, x, y = prefixes[i], find(i - 1), find(i)
        if len(part[x]) < len(part[y]):
            x, y = y, x
        large, small = part[x], part[y]
        up[y] = x
        for item in small:
            at = bisect.bisect_left(large, item)
            for other in large[max(0, at - 1) : at + 1]:
                left = _shared(item[0], other[0], 0)
                if left + right >= least:
                    out.append((item[1], left, right))
                    out.append((other[1], left, right))
            large.insert(at, item)
        part[y] = []
    return out


def _compare(table: pa.Table, least: int) -> pa.Table:
    """Matches of the groups of a part, from the merge's prefix lengths and the bytes to the left."""
    col = {n: table.column(n).to_pylist() for n in table.column_names}
    runs = [Run(np.frombuffer(s, _u2), np.frombuffer(n, _u2), x) for s, n, x in zip(col["shared"], col["lengths"], col["rests"], strict=True)]
    docs = [np.frombuffer(x, _i8).reshape(-1, 3) for x in col["docs"]]
    ends = [np.concatenate(([0], np.cumsum(np.frombuffer(x, _u2), dtype=np.int64))) for x in col["sizes"]]
    out: dict[tuple, int] = {}

    def end(group: list[tuple[int, int, int]]) -> None:
        if len(group) < 2:
            return
        lefts = [col["lefts"][r][ends[r][i] : ends[r][i + 1]] for r, i, _ in group]
        for m, left, right in group_matches(lefts, [n - 8 for _, _, n in group], least):
            r, i, _ = group[m]
            k1, k2, at = docs[r][i].tolist()
            start = (k1, k2, at - left)
            out[start] = max(out.get(start, 0), at + right)

    group: list[tuple[int, int, int]] = []
    for r, i, lcp, _ in merge_runs(runs):
        if lcp < 8 + KEY:
            end(group)
            group = []
        group.append((r, i, lcp))
    end(group)
    return pa.table({"k1": pa.array([k[0] for k in out], pa.int64()), "k2": pa.array([k[1] for k in out], pa.int64()), "a": pa.array([k[2] for k in out], pa.int64()), "z": pa.array(list(out.values()), pa.int64())})


def _windows(contexts: DataFrame, lengths: tuple[int, ...]) -> DataFrame:
    """(w, k1, k2, a, z) of every window of these lengths over contexts that are too many for a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part, out = batch.slice(at, 200), []
                for k1, k2, place, left, right in zip(*(part.column(i).to_pylist() for i in range(1, 6)), strict=True):
                    data, a = left + right, place - len(left)
                    for n in lengths:
                        # a window belongs to the anchor at this place in it
                        out += [(xxhash.xxh3_128_digest(data[s : s + n], n), k1, k2, a + s, a + s + n) for s in range(min(len(left), len(data) - n) + 1)]
                yield _record([("w", pa.binary(), [r[0] for r in out]), *[(n, pa.int64(), [r[i + 1] for r in out]) for i, n in enumerate(("k1", "k2", "a", "z"))]])

    return contexts.select("gid", "k1", "k2", "at", "left", "right").mapInArrow(run, "w binary, k1 bigint, k2 bigint, a bigint, z bigint")


# ---------------------------------------------------------------- the operator


def _sample_keys(rows: DataFrame, passage: int, most: int) -> list[bytes]:
    """Keys of some anchors; they only balance the ranges, so a bounded sample is enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = []
            for t in batch.column(0).to_pylist():
                data = t.encode("utf-8", "surrogatepass")[:20_000]
                keys += [data[a : a + KEY] for a in anchors(data, passage, passage - KEY + 1)[0].tolist()[::8]]
            yield _record([("key", pa.binary(), keys)])

    some = rows.orderBy(F.xxhash64("k2", "k1")).limit(most).select("t").mapInArrow(run, "key binary")
    return [bytes(r["key"]) for r in some.collect()]


def repeated_spans(docs: DataFrame, *, text: str = "text", id: str = "doc_id", length: int = 400, passage: int = 240) -> DataFrame:
    """(k1, k2, spans): matches of each text with another place, as byte ranges [a, z) of ``passage`` bytes or more; k1 and k2 are hashes of id and text."""
    if not GRAM + KEY <= passage <= length <= 60_000:
        raise ValueError("an anchor's gram and key must lie in every passage, a passage in the length, and a context in 64 KB")
    rows = _keyed(docs, text, id).where(F.octet_length("t") >= passage)
    size, n = rows.agg(F.sum(F.octet_length("t").cast("bigint")), F.count(F.lit(1))).first()
    count = max(12, -(-(size or 0) // RANGE_TEXT))
    ranges = make_ranges(_sample_keys(rows, passage, 2_000), count) if n else Ranges([], {})
    plain = len(ranges.splitters)
    sent = _runs(rows, ranges, length, passage)
    members = cut(sent.groupBy("range").applyInArrow(lambda t: _merge(t, plain), _MEMBER))
    whole, open_ = members.where("gid is null").select("k1", "k2", "a", "z"), members.where("gid is not null")
    sizes = open_.groupBy("gid").agg(F.count(F.lit(1)).alias("n"))
    most, classes = sizes.agg(F.max("n"), F.sum("n")).first()
    wanted = open_.groupBy("k1", "k2").agg(F.collect_list(F.struct("gid", "at", "a", "z")).alias("places"))
    contexts = _contexts(rows, wanted)
    parts = max(12, -(-(classes or 0) // PART_CLASSES))
    if (most or 0) > GROUP_CLASSES:
        # of groups that no task could hold, windows are counted by shuffle
        contexts = cut(contexts)
        huge = sizes.where(F.col("n") > GROUP_CLASSES).select("gid")
        single = cut(_windows(contexts.join(huge, "gid", "left_semi"), (length, passage) if passage < length else (length,)))
        twice = single.select("w", F.xxhash64("k1", "k2", "a").alias("x")).groupBy("w").agg(F.min("x").alias("x"), F.max("x").alias("y")).where("x != y").select("w")
        whole = whole.unionByName(single.join(twice, "w", "left_semi").select("k1", "k2", "a", "z"))
        contexts = contexts.join(huge, "gid", "left_anti")
    matched = _open_runs(contexts, parts).repartition(parts, "part").groupBy("part").applyInArrow(lambda t: _compare(t, passage), _SPAN)
    return whole.unionByName(matched).groupBy("k1", "k2").agg(F.collect_list(F.struct("a", "z")).alias("spans"))


def _keyed(docs: DataFrame, text: str, id: str, *more) -> DataFrame:
    """(t, k1, k2): two hashes of id and text name a row; rows with both equal have equal results."""
    name = F.coalesce(F.concat(F.lit("="), F.col(id).cast("string")), F.lit("null"))
    return docs.select(F.col(text).alias("t"), F.xxhash64(name, F.col(text)).alias("k1"), F.xxhash64(F.col(text), F.lit("|"), name).alias("k2"), *more)


def merged_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Byte ranges [start, end) joined where they meet."""
    out: list[tuple[int, int]] = []
    for a, z in sorted(spans):
        if out and a <= out[-1][1]:
            if z > out[-1][1]:
                out[-1] = (out[-1][0], z)
        else:
            out.append((a, z))
    return out


def whole_words(data: bytes, a: int, z: int) -> int:
    """Words of data[a:z], without those that its ends cut."""
    n = len(data[a:z].split())
    space = b" \t\n\x0b\x0c\r"
    if n and a and data[a - 1] not in space and data[a] not in space:
        n -= 1
    if n and z < len(data) and data[z] not in space and data[z - 1] not in space:
        n -= 1
    return n


def remove_repeats(docs: DataFrame, *, text: str = "text", id: str = "doc_id", length: int = 400, passage: int = 240, passage_words: int = 50, with_bytes: bool = True) -> DataFrame:
    """One row a document: id, n_bytes, n_removed, n_spans, kept_sha256, n_passages, n_passage_words, removed and passage ranges, and the kept bytes if asked for."""
    spans = repeated_spans(docs, text=text, id=id, length=length, passage=passage).withColumnsRenamed({"k1": "_1", "k2": "_2"})
    df = _keyed(docs, text, id, F.col(id).alias("id")).join(spans, (F.col("k1") == F.col("_1")) & (F.col("k2") == F.col("_2")), "left").select("t", "spans", "id")
    ranges = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                rows = []
                for t, found in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    data = (t or "").encode("utf-8", "surrogatepass")
                    matches = [(x["a"], x["z"]) for x in found or ()]
                    gone = merged_spans([x for x in matches if x[1] - x[0] >= length])
                    told = [(a, z, n) for a, z in merged_spans(matches) if (n := whole_words(data, a, z)) > passage_words]
                    kept, at = [], 0
                    for a, z in gone:
                        kept.append(data[at:a])
                        at = z
                    kept = b"".join([*kept, data[at:]])
                    rows.append((len(data), len(data) - len(kept), len(gone), hashlib.sha256(kept).hexdigest(), len(told), sum(n for _, _, n in told), [{"start": a, "end": z} for a, z in gone], [{"start": a, "end": z} for a, z, _ in told], kept if with_bytes else None))
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), ranges, ranges, pa.binary())
                names = ["n_bytes", "n_removed", "n_spans", "kept_sha256", "n_passages", "n_passage_words", "removed", "passages", "kept"]
                yield pa.RecordBatch.from_arrays([part.column(2), *[pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]], ["id", *names])

    kind = docs.schema[id].dataType.simpleString()
    out = df.mapInArrow(run, f"id {kind}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string, n_passages bigint, n_passage_words bigint, removed array<struct<start:bigint,end:bigint>>, passages array<struct<start:bigint,end:bigint>>, kept binary")
    return out.withColumnRenamed("id", id) if with_bytes else out.drop("kept").withColumnRenamed("id", id)
