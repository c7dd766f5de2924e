"""Materialised intermediate tables, size-checked broadcasts and free names."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share (``spark.checkpoint.dir``); only where the
    session has none, as in tests on one machine, a temporary one."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="evenkeel-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return _own[0]


def materialise(df: DataFrame) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back: computed once,
    lineage cut, and nothing lost with an executor."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/evenkeel-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def make_folder(spark: SparkSession, folder: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).mkdirs(path)


def fresh(taken, base: str) -> str:
    """A column name that is not among ``taken`` (compared without case)."""
    low, name = {c.lower() for c in taken}, base
    while name.lower() in low:
        name += "_"
    return name


def sample_by_hash(df: DataFrame, most: int, *keys: str) -> DataFrame:
    """At most ``most`` rows, the same in every run.  A share by hash comes first, so that
    what is put in order is about as large as the sample, however large ``df`` is."""
    total, h = df.count(), F.xxhash64(*keys)
    if total > 2 * most:
        df = df.where(F.pmod(h, F.lit(1 << 30)) < int(1.5 * most / total * (1 << 30)) + 1)
    return df.orderBy(h, *keys).limit(most)


def small(df: DataFrame, rows: int) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``rows`` rows, else barred from broadcasts:
    by the size of its files Spark may still take it for small."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df.hint("merge")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
