"""What the operators of this subpackage share: shared-folder tables that leave no shuffle files, components."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder. A folder of our own only where none is configured and all runs on one machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="hopbound-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


_WRITTEN: list[str] = []
_TABLES: list[str] = []


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def _shuffles_end(spark: SparkSession) -> Iterator[None]:
    """Within, Spark removes the shuffle files of a write as the write ends, not when its plan happens to be collected."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


def written(df: DataFrame, name: str = "cut") -> DataFrame:
    """df as a Parquet table in the shared folder, read back: cuts lineage and survives lost executors. See clean()."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    with _shuffles_end(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, key: str, name: str) -> DataFrame:
    """df as a table in the shared folder bucketed by key, which joins and groups by key read without a shuffle. See clean()."""
    spark = df.sparkSession
    table = f"{name}_{uuid.uuid4().hex}"
    path = f"{shared_dir(spark)}/{table}"
    _WRITTEN.append(path)
    _TABLES.append(table)
    with _shuffles_end(spark):
        df.write.bucketBy(int(spark.conf.get("spark.sql.shuffle.partitions")), key).sortBy(key).option("path", path).saveAsTable(table)
    return spark.table(table)


def clean(spark: SparkSession) -> None:
    """Delete what written() and bucketed() have made so far; frames that still read it are then of no use."""
    while _TABLES:
        spark.sql(f"DROP TABLE IF EXISTS {_TABLES.pop()}")
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    while _WRITTEN:
        at = path(_WRITTEN.pop())
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def give_back() -> None:
    """Return a Python worker's freed memory to the machine: workers live on, and would hold their largest block through later stages."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def slim(docs: DataFrame, needed: list[str]) -> DataFrame:
    """The needed columns of docs, and all others as one struct `_rest`, so that their names cannot clash with ours."""
    others = [c for c in docs.columns if c not in needed]
    rest = F.struct(*[F.col(f"`{c}`") for c in others]) if others else F.struct(F.lit(0).alias("_none"))
    return docs.select(*needed, rest.alias("_rest"))


def widened(df: DataFrame, docs: DataFrame, **changed: Column) -> DataFrame:
    """docs' columns in their order from a slim frame; `changed` gives new values of some of the others."""
    return df.select(*[(changed[c] if c in changed else F.col(c) if c in df.columns else F.col("_rest").getField(c)).alias(c) for c in docs.columns])


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def word_count(c: Column) -> Column:
    return F.when(c.isNull(), F.lit(0)).otherwise(F.regexp_count(c, F.lit(WORD))).cast("long")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) of the undirected edges (a, b), component the least node reachable.

    Alternating large-star and small-star rounds: every round is two aggregations over the edges, a
    node's neighbours are never collected into one row, and the edges stay on the cluster; only their
    count and checksum come to the driver. Empty edges give no rows; loops and repeats are harmless.
    """
    cur = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    seen = None
    for _ in range(max_rounds):
        both = cur.unionByName(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        small = large.groupBy("a").agg(F.min("b").alias("m"))
        nxt = large.join(small, "a").select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        cur = written(nxt, "edges")
        state = tuple(cur.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first())
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    pairs = cur.groupBy("a").agg(F.min("b").alias("component")).withColumnRenamed("a", "node")
    roots = pairs.select(F.col("component").alias("node"), "component").distinct()
    return pairs.unionByName(roots)
