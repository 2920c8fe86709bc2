"""Sources and sinks of edges and paths: files, adjacency lists, bucketed tables, and a Python data source of generated graphs."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from hopbound.operators.cut import cut, shared_dir
from hopbound.operators.paths import path_string

from .generators import FAMILIES


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst", schema: str | None = None) -> DataFrame:
    """(src, dst) from Parquet, ORC, JSON or CSV files (with header); columns are pruned at the scan."""
    reader = spark.read.format(fmt).option("header", "true")
    df = (reader.schema(schema) if schema else reader).load(path)
    return df.select(F.col(src).alias("src"), F.col(dst).alias("dst"))


def adjacency(lines: DataFrame, kind: str = "bigint") -> DataFrame:
    """(src, dst, ord) from lines `node successor successor ...` (column value); a line with no successors gives no rows."""
    part = F.split(F.trim("value"), " +")
    each = lines.select(F.get(part, 0).alias("src"), F.posexplode(F.slice(part, 2, 1_000_000)).alias("ord", "dst"))
    return each.select(F.col("src").cast(kind).alias("src"), F.col("dst").cast(kind).alias("dst"), (F.col("ord") + 1).alias("ord"))


def write_paths(paths: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Paths as strings, partitioned by length."""
    paths.select("len", path_string().alias("path_str")).write.format(fmt).partitionBy("len").mode("overwrite").save(path)


def sink_roundtrip(paths: DataFrame) -> DataFrame:
    spark = paths.sparkSession
    at = f"{shared_dir(spark)}/paths-{uuid.uuid4().hex}"
    write_paths(paths, at)
    return spark.read.schema("path_str string, len int").parquet(at)  # no paths leave no file to take a schema from


def bucketed(edges: DataFrame, name: str, by: str, buckets: int = 8) -> DataFrame:
    """Edges as a table bucketed and sorted by src or dst, so that joins on it do not shuffle it."""
    spark = edges.sparkSession
    table = f"{name}_{by}_{uuid.uuid4().hex}"
    edges.write.bucketBy(buckets, by).sortBy(by).option("path", f"{shared_dir(spark)}/{table}").saveAsTable(table)
    return spark.table(table)


def bucketed_two_hop(edges: DataFrame) -> DataFrame:
    """Two-hop walks counted over two co-bucketed copies of the edges: the join has no exchange."""
    a, b = bucketed(edges, "hops", "dst"), bucketed(edges, "hops", "src")
    met = a.select("src", F.col("dst").alias("mid")).hint("merge").join(b.select(F.col("src").alias("mid"), "dst"), "mid")
    return met.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("walks"))


class _Seeds(InputPartition):
    def __init__(self, seeds: list[int]):
        self.seeds = seeds


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.family = options.get("family", "uniform_digraph")
        self.first, self.count, self.parts = int(options.get("first", 0)), int(options.get("count", 1)), int(options.get("partitions", 4))

    def partitions(self):
        seeds = range(self.first, self.first + self.count)
        return [_Seeds(list(seeds[i :: self.parts])) for i in range(min(self.parts, len(seeds)))]

    def read(self, partition):
        for seed in partition.seeds:
            for a, b, o in FAMILIES[self.family](seed)[0]:
                yield seed, a, b, o


class GraphSource(DataSource):
    """format('hopbound_graph'): edges of generated graphs; options family, first (seed or size), count, partitions."""

    @classmethod
    def name(cls) -> str:
        return "hopbound_graph"

    def schema(self) -> str:
        return "instance_id bigint, src bigint, dst bigint, ord int"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def generated(spark: SparkSession, family: str, first: int, count: int = 1) -> DataFrame:
    spark.dataSource.register(GraphSource)
    return spark.read.format("hopbound_graph").options(family=family, first=str(first), count=str(count)).load()


def generated_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for family, first in (("clique_trap", 8), ("hub_breaker", 8), ("small_world", 3)):
        one = generated(spark, family, first).agg(F.lit(family).alias("family"), F.count(F.lit(1)).alias("edges"))
        out = one if out is None else out.unionByName(one)
    return cut(out)
