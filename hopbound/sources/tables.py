"""Graphs derived from the relational tables: edges (src, dst, w), loops dropped, parallel rows merged.

Each derivation is Spark SQL over the Parquet files; `ORACLE` has the same derivation for DuckDB, where it differs.
w is the number of merged rows, unless said otherwise.
"""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hopbound.operators.graph import Graph

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(c: str) -> Column:
    """Microseconds since 1970 of a timestamp without time zone, whatever the session's zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', {c})")


def sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """Spark SQL in which {table} stands for a Parquet file of sf_dir."""
    return spark.sql(re.sub(r"\{(\w+)\}", lambda m: f"parquet.`{sf_dir}/{m[1]}.parquet`", text))


def duck(text: str) -> str:
    """The same text for DuckDB, where the tables are views."""
    return re.sub(r"\{(\w+)\}", r"\1", text)


def merged(pairs: str) -> str:
    return f"SELECT src, dst, count(*) AS w FROM ({pairs}) p WHERE src IS NOT NULL AND dst IS NOT NULL AND src <> dst GROUP BY src, dst"


TRADE_ALL = merged("SELECT CAST(c.c_nationkey AS BIGINT) AS src, CAST(s.s_nationkey AS BIGINT) AS dst FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey JOIN {customer} c ON o.o_custkey = c.c_custkey JOIN {supplier} s ON l.l_suppkey = s.s_suppkey")


def trade_sql(top: int) -> str:
    return f"SELECT src, dst, w FROM ({TRADE_ALL}) t ORDER BY w DESC, src, dst LIMIT {top}"


def _line_pairs(column: str, where: str = "") -> str:
    return merged(f"SELECT a.{column} AS src, b.{column} AS dst FROM {{lineitem}} a JOIN {{lineitem}} b ON a.l_orderkey = b.l_orderkey AND b.l_linenumber = a.l_linenumber + 1 {where}")


PURCHASES = "SELECT event_id, ts, user_id FROM {events} WHERE event_type = 'purchase'"
PAYFLOW = merged(f"SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM ({PURCHASES}) e")
_ITEM = "1000000 + CAST({json} AS BIGINT)"
_USERITEM = "SELECT CASE WHEN event_type = 'click' THEN user_id ELSE item END AS src, CASE WHEN event_type = 'click' THEN item ELSE user_id END AS dst FROM (SELECT event_type, user_id, 1000000 + CAST(JSON AS BIGINT) AS item FROM {events} WHERE event_type IN ('click', 'purchase')) e"
CUSTCHAIN = merged("SELECT o_custkey AS src, lead(o_custkey) OVER (PARTITION BY o_orderpriority ORDER BY o_orderdate, o_orderkey) AS dst FROM {orders}")
SCHEMA = merged(
    "SELECT 'R' || r_regionkey AS src, 'N' || n_nationkey AS dst FROM {nation} JOIN {region} ON n_regionkey = r_regionkey "
    "UNION ALL SELECT 'N' || c_nationkey, 'C' || c_custkey FROM {customer} "
    "UNION ALL SELECT 'C' || o_custkey, 'P' || l_partkey FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey "
    "UNION ALL SELECT 'P' || l_partkey, 'S' || l_suppkey FROM {lineitem} "
    "UNION ALL SELECT 'S' || s_suppkey, 'N' || s_nationkey FROM {supplier}"
)
_BIGRAMS = "SELECT src, dst, w FROM (SELECT src, dst, count(*) AS w FROM (SELECT w[I] AS src, w[J] AS dst FROM (SELECT w, i FROM WORDS) x) p WHERE src <> dst AND src <> '' AND dst <> '' GROUP BY src, dst) q WHERE w >= 3"

GRAPHS = {
    **{f"trade{m}": trade_sql(m) for m in (25, 50, 100, 200, 400)},
    "trade600": TRADE_ALL,
    "partchain": _line_pairs("l_partkey", "WHERE a.l_returnflag = 'R'"),
    "partchain_all": _line_pairs("l_partkey"),
    "supplychain": _line_pairs("l_suppkey"),
    "payflow": PAYFLOW,
    "useritem": merged(_USERITEM.replace("JSON", "get_json_object(props, '$.k')")),
    "custchain": CUSTCHAIN,
    "schema": SCHEMA,
    "navlinks": merged(r"SELECT h AS src, lead(h) OVER (PARTITION BY page_id ORDER BY pos) AS dst FROM (SELECT page_id, pos, h FROM {pages} LATERAL VIEW posexplode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) t AS pos, h) x"),
    "bigrams": "SELECT src, dst, count(*) AS w FROM (SELECT split(lower(text), ' ') AS ws FROM {documents} WHERE lang = 'en') d LATERAL VIEW inline(arrays_zip(ws, slice(ws, 2, greatest(size(ws) - 1, 0)))) p AS src, dst WHERE src <> dst AND src <> '' AND dst <> '' GROUP BY src, dst HAVING count(*) >= 3",
    "doclines": merged("SELECT doc_id AS src, lead(doc_id) OVER (PARTITION BY line ORDER BY doc_id) AS dst FROM (SELECT DISTINCT doc_id, line FROM {documents} LATERAL VIEW explode(split(text, '\\n')) t AS line) x WHERE length(line) >= 20"),
    "turns": merged("SELECT element_at(ws, -1) AS src, n AS dst FROM (SELECT split(lower(text), ' ') AS ws, lead(split(lower(text), ' ')[0]) OVER (PARTITION BY conv_id ORDER BY turn) AS n FROM {conversations}) x"),
    "knn": "WITH p AS (SELECT a.vec_id AS src, b.vec_id AS dst, aggregate(zip_with(a.q, b.q, (x, y) -> (x - y) * (x - y)), 0L, (s, x) -> s + x) AS d FROM (SELECT vec_id, transform(embedding, x -> CAST(round(CAST(x AS DOUBLE) * 10000) AS BIGINT)) AS q FROM {embeddings}) a CROSS JOIN (SELECT vec_id, transform(embedding, x -> CAST(round(CAST(x AS DOUBLE) * 10000) AS BIGINT)) AS q FROM {embeddings}) b WHERE a.vec_id <> b.vec_id), n AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY d, dst) AS r FROM p) z WHERE r <= 3) SELECT src, dst, CAST(1 AS BIGINT) AS w FROM (SELECT src, dst FROM n UNION SELECT dst, src FROM n) u",
    "passages": "WITH x AS (SELECT 'B' || item_id AS a, 'D' || doc_id AS b FROM (SELECT item_id, split(text, '[.]')[0] AS s FROM {benchmark}) i JOIN {documents} d ON contains(d.text, i.s)) SELECT src, dst, CAST(1 AS BIGINT) AS w FROM (SELECT a AS src, b AS dst FROM x UNION SELECT b, a FROM x) u",
}

_DUCK = {
    "useritem": merged(_USERITEM.replace("JSON", "json_extract_string(props, '$.k')")),
    "navlinks": merged("SELECT h AS src, lead(h) OVER (PARTITION BY page_id ORDER BY pos) AS dst FROM (SELECT page_id, unnest(hs) AS h, generate_subscripts(hs, 1) AS pos FROM (SELECT page_id, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS hs FROM {pages}) y) x"),
    "bigrams": "SELECT src, dst, count(*) AS w FROM (SELECT ws[i] AS src, ws[i + 1] AS dst FROM (SELECT ws, unnest(generate_series(1, len(ws) - 1)) AS i FROM (SELECT string_split(lower(text), ' ') AS ws FROM {documents} WHERE lang = 'en') d) e) q WHERE src <> dst AND src <> '' AND dst <> '' GROUP BY src, dst HAVING count(*) >= 3",
    "doclines": merged("SELECT doc_id AS src, lead(doc_id) OVER (PARTITION BY line ORDER BY doc_id) AS dst FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM {documents}) x WHERE length(line) >= 20"),
    "turns": merged("SELECT ws[-1] AS src, n AS dst FROM (SELECT string_split(lower(text), ' ') AS ws, lead(string_split(lower(text), ' ')[1]) OVER (PARTITION BY conv_id ORDER BY turn) AS n FROM {conversations}) x"),
    "knn": "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 10000) AS BIGINT)) AS q FROM {embeddings}), p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_sum(list_transform(list_zip(a.q, b.q), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS d FROM v a CROSS JOIN v b WHERE a.vec_id <> b.vec_id), n AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY d, dst) AS r FROM p) z WHERE r <= 3) SELECT src, dst, CAST(1 AS BIGINT) AS w FROM (SELECT src, dst FROM n UNION SELECT dst, src FROM n) u",
    "passages": "WITH x AS (SELECT 'B' || item_id AS a, 'D' || doc_id AS b FROM (SELECT item_id, string_split(text, '.')[1] AS s FROM {benchmark}) i JOIN {documents} d ON contains(d.text, i.s)) SELECT src, dst, CAST(1 AS BIGINT) AS w FROM (SELECT a AS src, b AS dst FROM x UNION SELECT b, a FROM x) u",
}


def oracle(name: str) -> str:
    """DuckDB SQL of a graph's edges (src, dst, w)."""
    return duck(_DUCK.get(name, GRAPHS[name]))


def ordered_lead(df: DataFrame, order: list[str], value: str, bucket: str) -> DataFrame:
    """df with `next`, the value of the next row in global order; bucket is a column that rises with the order.

    Rows are ordered per bucket; only the first row of each bucket, one a bucket, is ordered globally.
    """
    w = Window.partitionBy(bucket).orderBy(*order)
    led = df.withColumn("_in", F.lead(value).over(w)).withColumn("_last", F.lead(F.lit(1)).over(w).isNull())
    heads = df.groupBy(bucket).agg(F.min_by(value, F.struct(*order)).alias("_head"))
    heads = heads.withColumn("_after", F.lead("_head").over(Window.orderBy(bucket))).select(F.col(bucket).alias("_b"), "_after")
    return led.join(heads, led[bucket] == heads["_b"]).withColumn("next", F.when(F.col("_last"), F.col("_after")).otherwise(F.col("_in"))).drop("_in", "_last", "_b", "_after")


def payflow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user -> next purchasing user in time, ordered day by day and stitched."""
    e = sql(spark, sf_dir, PURCHASES).withColumn("day", F.date_trunc("day", "ts"))
    pairs = ordered_lead(e, ["ts", "event_id"], "user_id", "day").select(F.col("user_id").alias("src"), F.col("next").alias("dst"))
    return pairs.where("dst IS NOT NULL AND src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))


def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items tied to the documents that hold their first sentence, by a join on two neighbouring inner words of it and a check of the whole.

    A text that holds the sentence has those words between spaces. Sentences of under four words have no such pair and are looked for in every
    document, in blocks of the broadcast items; there are at most as many as the benchmark has items.
    """
    items = table(spark, sf_dir, "benchmark").select(F.concat(F.lit("B"), "item_id").alias("a"), F.split("text", "[.]")[0].alias("s")).where("s is not null")
    items = items.withColumn("w", F.split("s", " "))
    docs = table(spark, sf_dir, "documents").select(F.concat(F.lit("D"), "doc_id").alias("b"), "text").where("text is not null")
    keyed = items.where("size(w) >= 4").select("a", "s", F.xxhash64(F.get("w", F.lit(1)), F.get("w", F.lit(2))).alias("key"))
    pairs = F.array_distinct(F.zip_with(F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(0))), F.slice("w", 2, F.greatest(F.size("w") - 1, F.lit(0))), lambda x, y: F.xxhash64(x, y)))
    probes = docs.withColumn("w", F.split("text", " ")).select("b", F.explode(pairs).alias("key"))
    likely = probes.join(keyed, "key").select("a", "s", "b")
    hits = likely.join(docs, "b").where(F.contains("text", F.col("s"))).select("a", "b")
    short = items.where("size(w) < 4").select("a", "s")
    if short.limit(1).count():
        hits = hits.unionByName(docs.join(F.broadcast(short), F.contains("text", F.col("s"))).select("a", "b"))
    both = hits.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(hits.select(F.col("b").alias("src"), F.col("a").alias("dst")))
    return both.distinct().withColumn("w", F.lit(1).cast("long"))


NEAREST, KNN_BLOCK = 3, 4096  # neighbours; vectors of a block, whose distances to another block are one matrix product


def knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each vector tied to its NEAREST others, exactly: every pair of blocks gives the nearest ones of its rows, and the least of those remain.

    Distances are between whole numbers (10,000 times the values), so they are exact in doubles; ties go to the lesser id. Vectors
    travel once for each block, distances never leave a task.
    """
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: F.round(x.cast("double") * 10000)).alias("q")).where("vec_id is not null and q is not null")
    blocks = max(1, -(-v.count() // KNN_BLOCK))
    own = v.withColumn("i", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = own.select("vec_id", "q", "i", every.alias("j"))
    right = own.select(F.col("vec_id").alias("dst"), F.col("q").alias("p"), F.col("i").alias("jj"), every.alias("ii"))

    def nearest(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"src": [], "dst": [], "d": []})
        b = b.sort_values("dst")
        x, y, ids = np.stack(a["q"].to_numpy()), np.stack(b["p"].to_numpy()), b["dst"].to_numpy()
        out = []
        for k in range(0, len(x), 512):
            part, src = x[k : k + 512], a["vec_id"].to_numpy()[k : k + 512]
            d = (part**2).sum(1)[:, None] + (y**2).sum(1)[None, :] - 2 * part @ y.T
            d[src[:, None] == ids[None, :]] = np.inf
            at = np.argsort(d, axis=1, kind="stable")[:, :NEAREST]
            near = np.take_along_axis(d, at, axis=1)
            kept = np.isfinite(near)
            out.append(pd.DataFrame({"src": np.repeat(src, at.shape[1]).reshape(at.shape)[kept], "dst": ids[at][kept], "d": near[kept]}))
        return pd.concat(out)

    found = left.groupBy("i", "j").cogroup(right.groupBy("ii", "jj")).applyInPandas(nearest, "src long, dst long, d double")
    top = found.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy("d", "dst"))).where(F.col("r") <= NEAREST)
    return top.select("src", "dst").unionByName(top.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct().withColumn("w", F.lit(1).cast("long"))


DERIVED = {"payflow": payflow, "passages": passages, "knn": knn}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A derived graph by name; its scan order is by dst."""
    edges = DERIVED[name](spark, sf_dir) if name in DERIVED else sql(spark, sf_dir, GRAPHS[name])
    return Graph(edges).ordered()
