"""Table access, shared-folder tables and small helpers of the pipeline operators."""

from __future__ import annotations

import ctypes
import os
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_REPO = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table; the path may be in any store that Spark reads."""
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def prepare(spark: SparkSession) -> None:
    """Let Python workers import this package even when it is not installed."""
    env = spark.sparkContext.environment
    if _REPO not in env.get("PYTHONPATH", ""):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (env.get("PYTHONPATH"), _REPO) if x)


def shared_folder(spark: SparkSession) -> str:
    """A fresh path under spark.checkpoint.dir. Where that is unset, a folder of our own: on one machine only."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "/tmp/checkpoints"
    return f"{base.rstrip('/')}/thriftvec-{uuid.uuid4().hex}"


_made: list[str] = []  # folders of stored tables that still exist


def stored(df: DataFrame) -> DataFrame:
    """Cut the lineage: write df once to the shared folder and read it back from there."""
    spark = df.sparkSession
    path = shared_folder(spark)
    _made.append(path)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._folder = path
    return out


def _delete(spark: SparkSession, paths: list[str]) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for p in paths:
        where = jvm.org.apache.hadoop.fs.Path(p)
        where.getFileSystem(conf).delete(where, True)


def discard(*tables: DataFrame | None) -> None:
    """Delete stored tables whose last reader is done: everything made of them has been stored itself."""
    for t in tables:
        path = getattr(t, "_folder", None)
        if path in _made:
            _delete(t.sparkSession, [path])
            _made.remove(path)


def discard_since(mark: int, docs: DataFrame) -> None:
    """Delete the tables stored since `mark` tables were (see held), but for those that docs is read from."""
    names = {p.rsplit("/", 1)[1] for f in docs.inputFiles() for p in _made if p.rsplit("/", 1)[1] in f}
    gone = [p for p in _made[mark:] if p.rsplit("/", 1)[1] not in names]
    _delete(docs.sparkSession, gone)
    _made[mark:] = [p for p in _made[mark:] if p not in gone]


def held() -> int:
    return len(_made)


def release() -> None:
    """Give memory that is free back to the system: a Python worker keeps it otherwise, from task to task."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim:
        trim(0)


def crc_residue(id_col: str, modulus: int) -> Column:
    """crc32 of the id's decimal text, modulo."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % F.lit(modulus)
