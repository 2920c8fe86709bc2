"""SQL functions: pandas UDFs over paths, and a table function that lists bounded paths of each partition of edges."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import BooleanType, LongType, StringType, StructType

from hopbound.functions.search import Csr, search

# workers import this module without a session, so types are objects here
FOUND = StructType().add("len", LongType()).add("path_str", StringType())


@pandas_udf(BooleanType())
def is_simple(path: pd.Series) -> pd.Series:
    """Whether no node repeats, the closing node of a cycle aside."""
    return path.map(lambda p: p is not None and len(set(p[:-1])) == len(p) - 1 and p[-1] not in list(p[1:-1]))


@pandas_udf(StringType())
def canonical_cycle(path: pd.Series) -> pd.Series:
    """A closed path turned to begin at its least node."""

    def turn(p) -> str | None:
        if p is None or len(p) < 2 or p[0] != p[-1]:
            return None
        ring = list(p[:-1])
        i = ring.index(min(ring))
        return ">".join(map(str, [*ring[i:], *ring[:i], ring[i]]))

    return path.map(turn)


@pandas_udf(LongType())
def max_delay(steps_at: pd.Series) -> int:
    """Grouped: the largest gap of a run's output times."""
    at = sorted(steps_at)
    return max((b - a for a, b in zip([0, *at], at)), default=0)


class _BoundedPaths:
    """One row per path of a partition: its rows are (src, dst, ord, s, t, k)."""

    def __init__(self):
        self.edges, self.asked = [], None

    def eval(self, row):
        self.edges.append((row["src"], row["dst"], row["ord"]))
        self.asked = (row["s"], row["t"], row["k"])

    def terminate(self):
        if self.asked:
            csr = Csr.of(self.edges)
            s, t = csr.index(self.asked[0]), csr.index(self.asked[1])
            if s is not None and t is not None:
                for p in search(csr, s, t, self.asked[2]).outputs:
                    yield len(p) - 1, ">".join(str(csr.names[i]) for i in p)


bounded_paths = udtf(_BoundedPaths, returnType=FOUND)


class _PathsUpTo:
    """One row per path from s to t of at most k edges, over edges written as src>dst pairs with spaces between."""

    def eval(self, edges: str, s: int, t: int, k: int):
        csr = Csr.of(tuple(map(int, e.split(">"))) for e in edges.split())
        a, b = csr.index(s), csr.index(t)
        if a is not None and b is not None:
            for p in search(csr, a, b, k).outputs:
                yield len(p) - 1, ">".join(str(csr.names[i]) for i in p)


paths_up_to = udtf(_PathsUpTo, returnType=FOUND)


def register(spark: SparkSession) -> None:
    """is_simple, canonical_cycle, max_delay, bounded_paths(TABLE ... PARTITION BY ...) and paths_up_to for SQL."""
    for name, f in (("is_simple", is_simple), ("canonical_cycle", canonical_cycle), ("max_delay", max_delay)):
        spark.udf.register(name, f)
    spark.udtf.register("bounded_paths", bounded_paths)
    spark.udtf.register("paths_up_to", paths_up_to)


def udtf_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    from hopbound.sources.tables import graph

    register(spark)
    e = graph(spark, sf_dir, "trade100").edges.select(F.lit(0).alias("instance"), "src", "dst", "ord", F.lit(3).cast("long").alias("s"), F.lit(9).cast("long").alias("t"), F.lit(3).alias("k"))
    e.createOrReplaceTempView("hopbound_udtf")
    return spark.sql("SELECT len, path_str FROM bounded_paths(TABLE(hopbound_udtf) PARTITION BY instance)")


def lateral_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries joined laterally with the table function."""
    from hopbound.sources.tables import graph

    register(spark)
    edges = graph(spark, sf_dir, "trade100").edges.agg(F.array_join(F.sort_array(F.collect_list(F.concat_ws(">", "src", "dst"))), " ").alias("edges"))
    edges.crossJoin(spark.createDataFrame([(3,), (4,)], "q int")).createOrReplaceTempView("hopbound_lateral")
    return spark.sql("SELECT CAST(q AS BIGINT) AS q, count(*) AS paths FROM hopbound_lateral, LATERAL paths_up_to(edges, 3, 9, q) GROUP BY q")
