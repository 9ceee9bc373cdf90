"""Media columns: payloads in archives, read by a custom Spark data source.

Texts become media: their bytes, padded with zeros to whole rows of 64, are the
8-bit grey samples of a PNG image, which stores them losslessly and compressed.
Each writing task puts its images into zip archives in the shared folder, under
a name of its own, and moves an archive to its final name when it is whole;
only archives that the finished job has reported are read.

The data source ``archive_members`` plans partitions as byte ranges of the
archives. A reading task opens the directory at the archive's end, takes the
members whose headers lie in its range, and streams them as Arrow batches. Every
member is read by its offset, checked against its checksum and tried again on
its own; one that stays broken gives a row with an error and no payload, and the
others are not touched.

Defined results: null and empty texts have a payload of 64 zeros; equal texts
give equal values; null ids stay null; rows with equal ids are members of their
own; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import json
import struct
import time
import uuid
import zipfile
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from rulegraph.llm.common import chunks, ensure_checkpoint_dir

ROW = 64
ARCHIVE_BYTES, RANGE_BYTES, BATCH_BYTES = 64_000_000, 16_000_000, 4_000_000
_PNG = b"\x89PNG\r\n\x1a\n"


def open_fs(uri: str) -> tuple[pyarrow.fs.FileSystem, str]:
    """File system and path of a URI of any store that Arrow knows."""
    if uri.startswith("file:/") and not uri.startswith("file://"):
        uri = "file://" + uri[5:]
    return pyarrow.fs.FileSystem.from_uri(uri)


def padded(data: bytes) -> bytes:
    """data and zeros up to a positive multiple of 64."""
    return data + bytes(-len(data) % ROW if data else ROW)


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def to_png(payload: bytes) -> bytes:
    """A grey image of 64 samples a row."""
    rows = np.zeros((len(payload) // ROW, ROW + 1), np.uint8)
    rows[:, 1:] = np.frombuffer(payload, np.uint8).reshape(-1, ROW)
    return _PNG + _chunk(b"IHDR", struct.pack(">IIBBBBB", ROW, len(rows), 8, 0, 0, 0, 0)) + _chunk(b"IDAT", zlib.compress(rows.tobytes(), 1)) + _chunk(b"IEND", b"")


def from_png(data: bytes) -> bytes:
    """Samples of an image made by to_png."""
    if data[:8] != _PNG:
        raise ValueError("no PNG signature")
    at, size, idat = 8, None, []
    while at < len(data):
        n, kind = struct.unpack_from(">I4s", data, at)
        body = data[at + 8 : at + 8 + n]
        if zlib.crc32(kind + body) != struct.unpack_from(">I", data, at + 8 + n)[0]:
            raise ValueError(f"wrong checksum in {kind!r}")
        if kind == b"IHDR":
            size = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            idat.append(body)
        at += 12 + n
    if size is None or size[2:] != (8, 0, 0, 0, 0):
        raise ValueError("not 8-bit grey")
    rows = np.frombuffer(zlib.decompress(b"".join(idat)), np.uint8).reshape(size[1], size[0] + 1)
    if rows[:, 0].any():
        raise ValueError("filtered rows")
    return rows[:, 1:].tobytes()


def features(samples: bytes) -> str:
    """Mean, deviation, entropy and number of distinct values of the samples, and mean step between neighbours."""
    a = np.frombuffer(samples, np.uint8)
    count = np.bincount(a, minlength=256)
    p = count[count > 0] / len(a)
    mean = float((count * np.arange(256)).sum() / len(a))
    var = max(0.0, float((count * np.arange(256) ** 2).sum() / len(a)) - mean * mean)
    step = float(np.abs(np.diff(a.astype(np.int16))).sum(dtype=np.int64) / (len(a) - 1))
    return f"mean={mean:.6f};std={var**0.5:.6f};entropy={-(p * np.log2(p)).sum() + 0.0:.6f};distinct={len(p)};step={step:.6f}"


def write_archives(docs: DataFrame, folder: str, *, text: str = "text", id: str = "doc_id") -> list[dict]:
    """Store every text as a member of an archive under folder; the archives' paths and sizes. A member is named by place, id and unpadded bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = open_fs(folder)
        fs.create_dir(base, recursive=True)
        out = zf = name = None
        made, n, written = [], 0, 0

        def finish() -> None:
            zf.close()
            size = out.tell()
            out.close()
            fs.move(f"{base}/{name}.part", f"{base}/{name}.zip")
            made.append((f"{name}.zip", size, n))

        for batch in batches:
            for part in chunks(batch, 0, BATCH_BYTES):
                for t, k in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    if zf is None:
                        name = uuid.uuid4().hex
                        out = fs.open_output_stream(f"{base}/{name}.part")
                        zf, n, written = zipfile.ZipFile(out, "w", zipfile.ZIP_STORED), 0, 0
                    data = (t or "").encode("utf-8", "surrogatepass")
                    png = to_png(padded(data))
                    zf.writestr(zipfile.ZipInfo(f"{n:09d}/{'' if k is None else k}/{len(data)}.png"), png)
                    n, written = n + 1, written + len(png)
                    if written >= ARCHIVE_BYTES:
                        finish()
                        zf = None
        if zf is not None:
            finish()
        if made:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*made, strict=True)], ["archive", "bytes", "members"])

    rows = docs.select(F.col(text).alias("t"), F.col(id).cast("string").alias("i")).mapInArrow(run, "archive string, bytes bigint, members bigint")
    # a row for each archive of 64 MB or each task
    return [r.asDict() for r in rows.collect()]


class _Range(InputPartition):
    def __init__(self, path: str, start: int, stop: int):
        self.path, self.start, self.stop = path, start, stop


def directory(read_at, size: int) -> list[tuple[str, int, int, int]]:
    """(name, header offset, stored bytes, crc32) of an archive's members, from the directory at its end."""
    tail = read_at(min(size, 65_557), max(0, size - 65_557))
    at = tail.rfind(b"PK\x05\x06")
    if at < 0:
        raise ValueError("no archive directory")
    count, length, start = struct.unpack_from("<HII", tail, at + 10)
    if 0xFFFFFFFF in (length, start) or count == 0xFFFF:
        where = struct.unpack_from("<Q", tail, at - 20 + 8)[0]
        count, length, start = struct.unpack_from("<QQQ", read_at(56, where), 32)
    data, out, p = read_at(length, start), [], 0
    for _ in range(count):
        crc, stored, whole, a, b, c = struct.unpack_from("<III3H", data, p + 16)
        offset = struct.unpack_from("<I", data, p + 42)[0]
        name = data[p + 46 : p + 46 + a]
        extra = data[p + 46 + a : p + 46 + a + b]
        if 0xFFFFFFFF in (stored, whole, offset):
            q = extra.find(b"\x01\x00") + 4
            for key, v in (("whole", whole), ("stored", stored), ("offset", offset)):
                if v == 0xFFFFFFFF:
                    v = struct.unpack_from("<Q", extra, q)[0]
                    q += 8
                    stored, offset = (v, offset) if key == "stored" else (stored, v) if key == "offset" else (stored, offset)
        out.append((name.decode(), offset, stored, crc))
        p += 46 + a + b + c
    return out


class ArchiveReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder = options["path"]
        self.range_bytes = int(options.get("rangebytes", RANGE_BYTES))
        self.tries = int(options.get("tries", 3))
        self.archives = json.loads(options["archives"]) if "archives" in options else None

    def partitions(self) -> list[InputPartition]:
        fs, base = open_fs(self.folder)
        if self.archives is None:
            found = fs.get_file_info(pyarrow.fs.FileSelector(base))
            self.archives = [[f.base_name, f.size] for f in found if f.base_name.endswith(".zip")]
        return [_Range(f"{base}/{name}", at, min(size, at + self.range_bytes)) for name, size in self.archives for at in range(0, size, self.range_bytes)]

    def read(self, partition: _Range) -> Iterator[pa.RecordBatch]:
        fs, _ = open_fs(self.folder)
        size = fs.get_file_info(partition.path).size

        def fetch(n: int, at: int) -> bytes:
            for k in range(self.tries):
                try:
                    with fs.open_input_file(partition.path) as f:
                        return f.read_at(n, at)
                except OSError:
                    if k + 1 == self.tries:
                        raise
                    time.sleep(0.1 * 2**k)
            raise AssertionError

        members = [m for m in directory(fetch, size) if partition.start <= m[1] < partition.stop]
        with fs.open_input_file(partition.path) as f:
            rows, held = [], 0
            for name, offset, stored, crc in members:
                data = why = None
                for k in range(self.tries):
                    try:
                        if k:
                            time.sleep(0.1 * 2**k)
                        head = f.read_at(30, offset) if k == 0 else fetch(30, offset)
                        if head[:4] != b"PK\x03\x04":
                            raise ValueError("no member at this offset")
                        skip = 30 + sum(struct.unpack_from("<HH", head, 26))
                        got = f.read_at(stored, offset + skip) if k == 0 else fetch(stored, offset + skip)
                        if zlib.crc32(got) != crc:
                            raise ValueError("wrong checksum")
                        data, why = got, None
                        break
                    except (OSError, ValueError, struct.error) as e:
                        why = f"{type(e).__name__}: {e}"
                rows.append((partition.path, name, offset, data, why))
                held += stored
                if held >= BATCH_BYTES:
                    yield _batch(rows)
                    rows, held = [], 0
            if rows:
                yield _batch(rows)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.string(), pa.string(), pa.int64(), pa.binary(), pa.string())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["archive", "member", "offset", "payload", "error"])


class ArchiveMembers(DataSource):
    """Members of zip archives as rows: archive, member, offset, payload, error."""

    @classmethod
    def name(cls) -> str:
        return "archive_members"

    def schema(self) -> str:
        return "archive string, member string, offset bigint, payload binary, error string"

    def reader(self, schema) -> DataSourceReader:
        return ArchiveReader({k.lower(): v for k, v in self.options.items()})


def read_archives(spark: SparkSession, folder: str, archives: list[dict] | None = None) -> DataFrame:
    spark.dataSource.register(ArchiveMembers)
    reader = spark.read.format("archive_members").option("path", folder)
    if archives is not None:
        reader = reader.option("archives", json.dumps([[a["archive"], a["bytes"]] for a in archives]))
    return reader.load()


_RESULT = "id string, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string"


def media_columns(docs: DataFrame, *, text: str = "text", id: str = "doc_id", folder: str | None = None) -> DataFrame:
    """Store every text as media, read it back and describe it: one row a document. The archives stay in ``folder``."""
    spark = docs.sparkSession
    folder = folder or f"{ensure_checkpoint_dir(spark)}/media-{uuid.uuid4().hex}"
    archives = write_archives(docs, folder, text=text, id=id)

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for name, png, why in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if png is None:
                    raise OSError(f"{name}: {why}")
                key, rest = name.split("/", 1)[1].rsplit("/", 1)
                samples = from_png(png)
                rows.append((key or None, int(rest.removesuffix(".png")), len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-ROW:]), len(png), hashlib.sha256(png).hexdigest(), features(samples)))
            kinds = (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], [f.split()[0] for f in _RESULT.split(", ")])

    if archives:
        out = read_archives(spark, folder, archives).select("member", "payload", "error").mapInArrow(describe, _RESULT)
    else:
        out = spark.createDataFrame([], _RESULT)
    return out.select(F.col("id").cast(docs.schema[id].dataType).alias(id), *[F.col(f.split()[0]) for f in _RESULT.split(", ")[1:]])
