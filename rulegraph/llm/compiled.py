"""The network of ``attention`` as graphs that onnxruntime runs, where it is installed: the same weights, gradient and scores.

Symbols in classes are worked on in tiles: places are sorted by the class of what
follows them and cut into tiles of ``ROWS`` places of one class, so that one batched
product serves all classes. Classes are laid out over as many cells as the largest
has symbols; what the pair counts say of a cell without a symbol makes it impossible.
"""

from __future__ import annotations

import math
import struct
from functools import cache
from typing import TYPE_CHECKING

import numpy as np

try:
    import onnxruntime
except ImportError:
    onnxruntime = None

if TYPE_CHECKING:
    from rulegraph.llm.attention import ModelShape, Table

#: Places of a tile.
ROWS = 32
FLOAT, INT = 1, 7


# ---------------------------------------------------------------- a writer of the graph format


def _number(n: int) -> bytes:
    n &= (1 << 64) - 1
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _bytes(field: int, value: bytes | str) -> bytes:
    value = value.encode() if isinstance(value, str) else value
    return _number(field << 3 | 2) + _number(len(value)) + value


def _int(field: int, n: int) -> bytes:
    return _number(field << 3) + _number(n)


class Graph:
    """Nodes in order; ``do`` adds one and names its result."""

    def __init__(self) -> None:
        self.nodes: list[bytes] = []
        self.constants: list[bytes] = []
        self.ends: list[bytes] = []
        self.count = 0

    def _end(self, field: int, name: str, kind: int, shape: tuple[int | str, ...]) -> None:
        dims = b"".join(_bytes(1, _int(1, d) if isinstance(d, int) else _bytes(2, d)) for d in shape)
        self.ends.append(_bytes(field, _bytes(1, name) + _bytes(2, _bytes(1, _int(1, kind) + _bytes(2, dims)))))

    def input(self, name: str, *shape: int | str, kind: int = FLOAT) -> str:
        self._end(11, name, kind, shape)
        return name

    def output(self, name: str, value: str, *shape: int | str) -> None:
        self.nodes.append(_bytes(1, _bytes(1, value) + _bytes(2, name) + _bytes(4, "Identity")))
        self._end(12, name, FLOAT, shape)

    def constant(self, value: np.ndarray) -> str:
        self.count += 1
        name, kind = f"k{self.count}", FLOAT if value.dtype == np.float32 else INT
        self.constants.append(_bytes(5, b"".join(_int(1, d) for d in value.shape) + _int(2, kind) + _bytes(8, name) + _bytes(9, np.ascontiguousarray(value).tobytes())))
        return name

    def shape(self, *dims: int) -> str:
        return self.constant(np.array(dims, np.int64))

    def do(self, kind: str, *inputs: str, **attributes: int | str | list[int]) -> str:
        self.count += 1
        name, own = f"v{self.count}", b""
        for k, v in attributes.items():
            if isinstance(v, int):
                value = _int(3, v) + _int(20, 2)
            elif isinstance(v, str):
                value = _bytes(4, v) + _int(20, 3)
            else:
                value = b"".join(_int(8, i) for i in v) + _int(20, 7)
            own += _bytes(5, _bytes(1, k) + value)
        self.nodes.append(_bytes(1, b"".join(_bytes(1, x) for x in inputs) + _bytes(2, name) + _bytes(4, kind) + own))
        return name

    def session(self) -> onnxruntime.InferenceSession:
        o = onnxruntime.SessionOptions()
        # a task has one core
        o.intra_op_num_threads = o.inter_op_num_threads = 1
        o.log_severity_level = 3
        # the number of tiles changes from run to run, and freed memory is kept by the process
        o.enable_mem_pattern = o.enable_cpu_mem_arena = False
        graph = b"".join(self.nodes) + _bytes(2, "g") + b"".join(self.constants) + b"".join(self.ends)
        return onnxruntime.InferenceSession(_int(1, 8) + _bytes(8, _bytes(1, "") + _int(2, 16)) + _bytes(7, graph), o, providers=["CPUExecutionProvider"])


# ---------------------------------------------------------------- the network


def _forward(g: Graph, s: ModelShape) -> dict[str, str]:
    """Inputs and the hidden states, (places, width), with what the backward pass needs."""
    d, t, k = s.width, s.context, s.classes
    v = {n: g.input(n, *shape) for n, shape in (("E", (s.symbols, d)), ("P", (t, d)), ("A", (d, d)), ("B", (d, d)), ("U", (d, k)), ("c", (k,)), ("V", (s.symbols, d)))}
    v["x"] = g.input("x", "n", t, kind=INT)
    v["windows"], v["places"] = g.shape(-1, t, d), g.shape(-1, d)
    e3 = v["e3"] = g.do("Add", g.do("Gather", "E", "x"), "P")
    e = v["e"] = g.do("Reshape", e3, v["places"])
    v["scale"] = g.constant(np.array(1 / math.sqrt(d), np.float32))
    q3 = v["q3"] = g.do("Reshape", g.do("MatMul", e, g.do("Mul", "A", v["scale"])), v["windows"])
    v["e3t"] = g.do("Transpose", e3, perm=[0, 2, 1])
    mask = g.constant(np.triu(np.full((t, t), -1e9, np.float32), 1))
    a = v["a"] = g.do("Softmax", g.do("Add", g.do("MatMul", q3, v["e3t"]), mask), axis=-1)
    m3 = v["m3"] = g.do("MatMul", a, e3)
    v["m"] = g.do("Reshape", m3, v["places"])
    v["o"] = g.do("Gemm", v["m"], "B", e)
    return v


def _class_logits(g: Graph, o: str, s: ModelShape) -> str:
    g.input("after", s.symbols, s.classes)
    g.input("before", "f", kind=INT)
    return g.do("Gemm", o, "U", g.do("Gather", g.do("Add", "after", "c"), "before"))


def _tile_logits(g: Graph, o: str, s: ModelShape) -> tuple[str, str, str]:
    """(logits of the tiles' cells, hidden states of the tiles' places, weights of the tiles' cells)."""
    g.input("pairs", "cells", "w")
    g.input("members", s.classes, "w", kind=INT)
    g.input("tiles", "m", kind=INT)
    g.input("source", "m", ROWS, kind=INT)
    g.input("row", "m", ROWS, kind=INT)
    own, v = g.do("Gather", o, "source"), g.do("Gather", g.do("Gather", "V", "members"), "tiles")
    return g.do("Add", g.do("MatMul", own, g.do("Transpose", v, perm=[0, 2, 1])), g.do("Gather", "pairs", "row")), own, v


@cache
def _gradient_session(s: ModelShape):
    g = Graph()
    v = _forward(g, s)
    o, places, windows = v["o"], v["places"], v["windows"]
    last = g.shape(-1)
    column = lambda x, at=last: g.do("Unsqueeze", x, at)
    wt, to = g.input("weight", "f"), g.input("to", "f", kind=INT)
    p = g.do("Softmax", _class_logits(g, o, s), axis=-1)
    p = g.do("ScatterElements", g.do("Mul", p, column(wt)), column(to), column(g.do("Neg", wt)), axis=1, reduction="add")
    logits, own, rows = _tile_logits(g, o, s)
    twt, cell = g.input("tile_weight", "m", ROWS), g.input("cell", "m", ROWS, kind=INT)
    pt = g.do("ScatterElements", g.do("Mul", g.do("Softmax", logits, axis=-1), column(twt)), column(cell), column(g.do("Neg", twt)), axis=2, reduction="add")
    # a padding row adds zero to the first place
    back = g.do("Reshape", g.do("MatMul", pt, rows), places)
    dy = g.do("ScatterND", g.do("Gemm", p, "U", transB=1), column(g.do("Reshape", "source", g.shape(-1))), back, reduction="add")
    zero = g.do("Mul", g.do("Gather", "V", "members"), g.constant(np.array(0, np.float32)))
    g.output("gV", g.do("ScatterND", zero, column("tiles"), g.do("MatMul", g.do("Transpose", pt, perm=[0, 2, 1]), own), reduction="add"), s.classes, "w", s.width)
    g.output("gU", g.do("Gemm", o, p, transA=1), s.width, s.classes)
    g.output("gc", g.do("ReduceSum", p, g.shape(0), keepdims=0), s.classes)
    g.output("gB", g.do("Gemm", v["m"], dy, transA=1), s.width, s.width)
    dm = g.do("Reshape", g.do("Gemm", dy, "B", transB=1), windows)
    da = g.do("Mul", g.do("MatMul", dm, v["e3t"]), v["a"])
    da = g.do("Sub", da, g.do("Mul", v["a"], g.do("ReduceSum", da, last, keepdims=1)))
    dq = g.do("Mul", g.do("Reshape", g.do("MatMul", da, v["e3"]), places), v["scale"])
    g.output("gA", g.do("Gemm", v["e"], dq, transA=1), s.width, s.width)
    # a place is read as a key and as a value
    key = g.do("MatMul", g.do("Transpose", da, perm=[0, 2, 1]), v["q3"])
    value = g.do("MatMul", g.do("Transpose", v["a"], perm=[0, 2, 1]), dm)
    de = g.do("Add", g.do("Gemm", dq, "A", dy, transB=1), g.do("Reshape", g.do("Add", key, value), places))
    g.output("gP", g.do("ReduceSum", g.do("Reshape", de, windows), g.shape(0), keepdims=0), s.context, s.width)
    g.output("gE", g.do("ScatterND", g.constant(np.zeros((s.symbols, s.width), np.float32)), column(g.do("Reshape", "x", g.shape(-1))), de, reduction="add"), s.symbols, s.width)
    return g.session()


@cache
def _score_session(s: ModelShape):
    g = Graph()
    v = _forward(g, s)
    o = g.do("Gather", v["o"], g.input("fresh", "f", kind=INT))
    last = g.shape(-1)
    pick = lambda logits, at, axis: g.do("Squeeze", g.do("GatherElements", g.do("LogSoftmax", logits, axis=-1), g.do("Unsqueeze", at, last), axis=axis), last)
    g.output("of_class", pick(_class_logits(g, o, s), g.input("to", "f", kind=INT), 1), "f")
    logits, _, _ = _tile_logits(g, o, s)
    g.output("inside", pick(logits, g.input("cell", "m", ROWS, kind=INT), 2), "m", ROWS)
    return g.session()


class Compiled:
    """Gradients and scores of one table's network."""

    def __init__(self, table: Table, s: ModelShape):
        self.shape, self.after = s, table.after
        self.class_of = table.class_of.astype(np.int64)
        sizes = np.bincount(self.class_of, minlength=s.classes)
        order = np.argsort(self.class_of, kind="stable")
        self.place = np.zeros(s.symbols, np.int64)
        self.place[order] = np.arange(s.symbols) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        width = int(sizes.max())
        self.cells = self.class_of * width + self.place
        self.members = np.zeros(s.classes * width, np.int64)
        self.members[self.cells] = np.arange(s.symbols)
        self.members = self.members.reshape(s.classes, width)
        pairs = np.full((s.symbols, s.classes * width), -1e9, np.float32)
        pairs[:, self.cells] = table.within
        self.pairs = pairs.reshape(-1, width)

    def _tiles(self, before: np.ndarray, after: np.ndarray, classes: np.ndarray) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
        """(places by class, cell of each among those of the tiles, what a session is fed of the tiles)."""
        k = self.shape.classes
        order = np.argsort(classes.astype(np.uint16), kind="stable")
        many = np.bincount(classes, minlength=k)
        per = -(-many // ROWS)
        slot = np.arange(len(order)) + np.repeat((np.cumsum(per) - per) * ROWS - (np.cumsum(many) - many), many)
        total = int(per.sum())
        source, row, cell = (np.zeros(total * ROWS, np.int64) for _ in range(3))
        source[slot], row[slot], cell[slot] = order, (before * k + classes)[order], self.place[after][order]
        shape = (total, ROWS)
        return order, slot, {"tiles": np.repeat(np.arange(k), per), "source": source.reshape(shape), "row": row.reshape(shape), "cell": cell.reshape(shape), "members": self.members, "pairs": self.pairs, "after": self.after}

    def gradient(self, w: dict[str, np.ndarray], x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
        """Gradient of the mean loss of the weighted places."""
        x, y = x.astype(np.int64), y.reshape(-1).astype(np.int64)
        before, to = x.reshape(-1), self.class_of[y]
        wt = weight.reshape(-1) / np.float32(max(1.0, float(weight.sum())))
        order, slot, fed = self._tiles(before, y, to)
        twt = np.zeros(fed["source"].size, np.float32)
        twt[slot] = wt[order]
        names = ("E", "P", "A", "B", "U", "c", "V")
        got = dict(zip(names, _gradient_session(self.shape).run([f"g{n}" for n in names], w | fed | {"x": x, "before": before, "to": to, "weight": wt, "tile_weight": twt.reshape(-1, ROWS)}), strict=True))
        got["V"] = got["V"].reshape(-1, self.shape.width)[self.cells]
        return got

    def log_probability(self, w: dict[str, np.ndarray], x: np.ndarray, y: np.ndarray, fresh: np.ndarray) -> np.ndarray:
        """Of the symbols that follow, at the places ``fresh`` of the windows."""
        x, y = x.astype(np.int64), y.reshape(-1)[fresh].astype(np.int64)
        before, to = x.reshape(-1)[fresh], self.class_of[y]
        order, slot, fed = self._tiles(before, y, to)
        out, inside = _score_session(self.shape).run(["of_class", "inside"], w | fed | {"x": x, "fresh": fresh, "before": before, "to": to})
        out = out.astype(np.float64)
        out[order] += inside.reshape(-1)[slot]
        return out


def can_run(s: ModelShape) -> bool:
    return onnxruntime is not None and s.inner and not s.hidden
