"""The filter table on storage, tables in the folder that all executors share, and key sources."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.functions.hashing import with_premix

_OWN: dict[str, str] = {}

#: One row a subfilter; ``spec`` holds all parameters, ``bits`` the packed table.
FILTER_SCHEMA = (
    "filter_id string, sub int, kind string, variant string, k int, subs int, spec string, n_keys long, n_stored long, "
    "n_skipped long, n_slots long, max_walk long, sum_walk long, status string, payload_bits long, padded_bits long, bits binary"
)


def shared_dir(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a temporary folder only where that is unset and all runs in one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "dir" not in _OWN:
        _OWN["dir"] = "file://" + tempfile.mkdtemp(prefix="fpfilter-")
        spark.sparkContext.setCheckpointDir(_OWN["dir"])
    return _OWN["dir"]


def written(df: DataFrame, name: str, codec: str | None = None) -> DataFrame:
    """``df`` as a Parquet table in the shared folder, read back: lineage ends here and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tables/{name}-{uuid.uuid4().hex}"
    writer = df.write
    if codec:
        writer = writer.option("compression", codec)
    writer.parquet(path)
    atexit.register(_drop, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def _drop(spark: SparkSession, path: str) -> None:
    try:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may be gone at exit; nothing else to tidy
        pass


def save_filter(table: DataFrame, path: str, mode: str = "error") -> None:
    """Write a filter table, one folder a filter. Tables of failed subfilters are refused."""
    bad = table.where("status <> 'ok'").select("filter_id", "sub").take(1)
    if bad:
        raise ValueError(f"subfilter {bad[0]} failed and cannot be published")
    table.write.mode(mode).partitionBy("filter_id").parquet(path)


def load_filter(spark: SparkSession, path: str, filter_id: str | None = None) -> DataFrame:
    """The filter table at ``path``; with ``filter_id`` only that folder is read."""
    table = spark.read.schema(FILTER_SCHEMA).parquet(path)
    return table.where(F.col("filter_id") == filter_id) if filter_id else table


def random_keys(spark: SparkSession, start: int, end: int) -> DataFrame:
    """Keys that look random and never repeat over disjoint ranges, as the premixing is a bijection."""
    return with_premix(spark.range(start, end), F.col("id"), "key").select("key")


def lineitem_key() -> Column:
    """A line item's four keys in one long; free of collisions up to a tenth of scale one."""
    part = lambda c, bits: F.shiftleft(F.col(c).cast("long"), bits)
    return part("l_orderkey", 28).bitwiseOR(part("l_partkey", 13)).bitwiseOR(part("l_suppkey", 3)).bitwiseOR(F.col("l_linenumber").cast("long"))


def hashed_key(*columns: str | Column) -> Column:
    """A 64-bit key for any columns."""
    return F.xxhash64(*columns)
