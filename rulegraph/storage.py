"""Tables in the shared folder that cut lineage, and code for the workers."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder, which all executors see; a temporary one only where none is set (tests)."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="ckpt-"))
    return sc.getCheckpointDir()


def new_path(spark: SparkSession, kind: str) -> str:
    return f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """df as a written table: read again by any executor, of a size that the planner knows."""
    path = new_path(df.sparkSession, "cut")
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def remove(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def drop_cut(df: DataFrame) -> None:
    """Delete a table made by cut() that nothing reads any more."""
    remove(df.sparkSession, df._cut_path)


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once a context, so that their workers find it wherever they run."""
    sc = spark.sparkContext
    if getattr(sc, "_rulegraph_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    target = Path(tempfile.mkdtemp(prefix="ship-")) / "rulegraph_src.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted((root / "rulegraph").rglob("*.py")):
            z.write(p, p.relative_to(root).as_posix())
    sc.addPyFile(str(target))
    sc._rulegraph_shipped = True
