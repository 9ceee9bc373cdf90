"""Helpers shared by the corpus operators."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Byte table that lowers A-Z and leaves every other byte alone.
ASCII_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Words ``[^\\x20\\x09-\\x0D]+`` of a text in UTF-8, A-Z lowered; none for null."""
    if not text:
        return []
    # bytes.split() cuts at exactly the six white-space characters above
    return text.encode("utf-8", "surrogatepass").translate(ASCII_LOWER).split()


def keep_memory() -> None:
    """Lets this process keep freed blocks of up to 8 MB.

    By default the C library hands every freed array of some 128 KB back to the system, and
    the next one pays for its pages again, which costs as much as the arithmetic on
    it. Freeing one large block raises that threshold for good.
    """
    bytearray(8 << 20)


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder for checkpoints: the session's own, else (in tests) a temporary one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="ckpt-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Write df as a table in the shared checkpoint folder and go on from there.

    Any executor can read it again, its size is known to the planner, and what
    comes after does not recompute what comes before.
    """
    spark = df.sparkSession
    path = f"{ensure_checkpoint_dir(spark)}/cut-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def number_rows(docs: DataFrame, text: str) -> tuple[DataFrame, str, str]:
    """docs written with a number for each row and a hash of its text, and the names of these columns."""
    row, th = fresh(docs, "row"), fresh(docs, "text_hash")
    return cut(docs.withColumn(row, F.monotonically_increasing_id()).withColumn(th, F.xxhash64(text))), row, th


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df does not have, whatever the case."""
    taken = {c.lower() for c in df.columns}
    while name in taken:
        name += "_"
    return name


def drop_cut(df: DataFrame) -> None:
    """Delete a table made by cut() that nothing reads any more."""
    jvm = df.sparkSession.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(df._cut_path)
    path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def crc_mod(col: str | Column, n: int) -> Column:
    """crc32 of the value as text, mod n; null for null."""
    return F.pmod(F.crc32((F.col(col) if isinstance(col, str) else col).cast("string").cast("binary")), F.lit(n))


def chunks(batch: pa.RecordBatch, text_at: int, limit: int):
    """Slices of a record batch whose texts have about ``limit`` bytes each, one row at least."""
    text = batch.column(text_at)
    start = size = 0
    for i, n in enumerate(pa.compute.binary_length(text).to_pylist()):
        size += n or 0
        if size >= limit:
            yield batch.slice(start, i + 1 - start)
            start, size = i + 1, 0
    if start < batch.num_rows:
        yield batch.slice(start)


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once a context, so that their workers find it wherever they run."""
    sc = spark.sparkContext
    if getattr(sc, "_rulegraph_shipped", False):
        return
    root = Path(__file__).resolve().parents[2]
    target = Path(tempfile.mkdtemp(prefix="ship-")) / "rulegraph_src.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted((root / "rulegraph").rglob("*.py")):
            z.write(p, p.relative_to(root).as_posix())
    sc.addPyFile(str(target))
    sc._rulegraph_shipped = True
