"""Structured Streaming over a stream of edges: cycles closed by new edges, windowed counts, late data, standing queries.

The stream is the purchase events in time, replayed through the file source; an edge goes from one purchaser to the next.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hopbound.functions.search import Csr, search
from hopbound.operators.cut import cut, shared_dir
from hopbound.operators.paths import path_string, simple_paths
from hopbound.sources.tables import PURCHASES, micros, ordered_lead, sql, table

REGISTERED: list[tuple[str, Callable, str | None]] = []


def instant(ts: str, name: str = "ts") -> Column:
    """A timestamp without time zone as an instant in UTC: watermarks need one."""
    return F.timestamp_micros(micros(ts)).alias(name)


def edge_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, ts, src, dst): each purchase with the next purchaser, at the time of the later one."""
    e = sql(spark, sf_dir, PURCHASES).withColumn("day", F.date_trunc("day", "ts")).withColumn("me", F.struct("event_id", "ts", "user_id"))
    nxt = ordered_lead(e, ["ts", "event_id"], "me", "day").where("next IS NOT NULL AND next.user_id <> user_id")
    return nxt.select("next.event_id", instant("next.ts"), F.col("user_id").alias("src"), F.col("next.user_id").alias("dst"))


def replay(df: DataFrame, order: str, files: int, late: str | None = None) -> DataFrame:
    """df as a stream of `files` files in order of a column; rows for which `late` holds come two files later."""
    spark = df.sparkSession
    at = f"{shared_dir(spark)}/replay-{uuid.uuid4().hex}"
    df = cut(df)
    lo, hi = df.agg(F.min(F.unix_micros(order)), F.max(F.unix_micros(order))).first()
    width = max(1, ((hi or 0) - (lo or 0)) // files + 1)
    part = F.floor((F.unix_micros(order) - F.lit(lo or 0)) / width).cast("int")
    part = part if late is None else F.least(F.when(F.expr(late), part + 2).otherwise(part), F.lit(files + 1))
    parts = df.withColumn("_part", part)
    for i in range(files + 2):  # one file a step, in order
        one = parts.where(F.col("_part") == i).drop("_part")
        if one.take(1):
            one.coalesce(1).write.mode("append").parquet(at)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(at)


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a streaming query over what is there and returns what it wrote: a folder a micro-batch in the shared folder, of which `complete` reads the last."""
    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/sink-{uuid.uuid4().hex}"
    ids = [-1]

    def on_batch(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/batch={batch_id}")
        ids.append(batch_id)

    stream.writeStream.foreachBatch(on_batch).outputMode(mode).option("checkpointLocation", f"{at}-checkpoint").trigger(availableNow=True).start().awaitTermination()
    if len(ids) == 1:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{at}/batch={max(ids)}" if mode == "complete" else f"{at}/batch=*")


def _window_subgraphs(new: DataFrame, kept: DataFrame, k: int, wide: int) -> DataFrame:
    """(event_id, s, t, src, dst): for every new edge t -> s the earlier edges of its window on a walk from s to t of at most k - 1 edges.

    Joins are keyed by node and time bin: backwards from t first, then forwards from s over edges that can still reach t in time.
    """
    older = (F.col("at") > F.col("now") - wide) & ((F.col("at") < F.col("now")) | ((F.col("at") == F.col("now")) & (F.col("e") < F.col("event_id"))))
    asked = new.select("event_id", F.col("at").alias("now"), F.col("dst").alias("s"), F.col("src").alias("t"))
    ends = ["event_id", "now", "s", "t"]

    def step(front: DataFrame, end: str) -> DataFrame:
        at = F.floor(F.col("now") / wide)
        return front.withColumn("bin", F.explode(F.array(at, at - 1))).join(kept.withColumn("node", F.col(end)), ["bin", "node"]).where(older)

    front = asked.withColumn("node", F.col("t"))
    back = front.select("event_id", "node", F.lit(0).alias("left"))
    for j in range(1, k - 1):
        front = cut(step(front, "dst").where("src <> s AND src <> t").select(*ends, F.col("src").alias("node")).distinct())
        back = back.unionByName(front.select("event_id", "node", F.lit(j).alias("left")))
    back = cut(back.groupBy("event_id", F.col("node").alias("dst")).agg(F.min("left").alias("left")))
    front, found = asked.withColumn("node", F.col("s")), []
    for i in range(k - 1):
        on = step(front, "src").where("dst <> s").select(*ends, "src", "dst").distinct()
        found.append(cut(on.join(back, ["event_id", "dst"]).where(F.col("left") <= k - 2 - i).select(*ends, "src", "dst")))
        front = found[-1].where("dst <> t").select(*ends, F.col("dst").alias("node")).distinct()
    return reduce(DataFrame.unionByName, found).select("event_id", "s", "t", "src", "dst").distinct()


def closing_cycles(stream: DataFrame, k: int, hours: int, sink: str, late_hours: int | None = None) -> None:
    """Writes to `sink` every simple cycle of at most k edges (k at least 2) that a new edge closes with edges less than `hours` before it.

    Kept edges lie in folders by time bin of the window's width, of which a micro-batch reads those from one before its first edge to its last.
    A cycle through (u, v) is a path v -> u of at most k - 1 edges: every new edge's own graph is first cut down to the walks of that
    length, then searched. With late_hours, bins are deleted once only edges that come later than that could still need them; without, all are kept.
    """
    spark = stream.sparkSession
    kept = f"{sink}-edges"
    wide = hours * 3_600_000_000

    def expire(before: int) -> None:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        at = path(kept)
        fs = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        for f in fs.listStatus(at):
            name = f.getPath().getName()
            if name.startswith("bin=") and int(name[4:]) < before:
                fs.delete(f.getPath(), True)

    def go(part: pd.DataFrame) -> pd.DataFrame:
        first = part.iloc[0]
        csr = Csr.of(zip(part["src"].tolist(), part["dst"].tolist()))
        s, t = csr.index(first["s"]), csr.index(first["t"])
        out = [] if s is None or t is None else search(csr, s, t, k - 1, "tight_seeded").outputs
        paths = [[csr.names[i] for i in p] for p in out]
        told = [">".join(map(str, [p[-1], *p])) for p in paths]
        return pd.DataFrame({"event_id": pd.Series([first["event_id"]] * len(out), dtype="int64"), "len": pd.Series([len(p) for p in paths], dtype="int64"), "cycle_str": pd.Series(told, dtype=object)})

    def on_batch(batch: DataFrame, batch_id: int) -> None:
        new = cut(batch.select("event_id", F.unix_micros("ts").alias("at"), "src", "dst"))
        lo, hi = new.agg(F.min(F.floor(F.col("at") / wide)), F.max(F.floor(F.col("at") / wide))).first()
        if lo is None:
            return
        dated = new.withColumn("bin", F.floor(F.col("at") / wide)).withColumn("batch", F.lit(batch_id).cast("long"))
        dated.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("bin", "batch").parquet(kept)
        old = spark.read.schema(dated.schema).parquet(kept).where(F.col("bin").between(lo - 1, hi) & (F.col("batch") <= batch_id))
        near = _window_subgraphs(new, old.select(F.col("event_id").alias("e"), "at", "src", "dst", "bin"), k, wide)
        near.groupBy("event_id").applyInPandas(go, "event_id bigint, len bigint, cycle_str string").write.mode("overwrite").parquet(f"{sink}/batch={batch_id}")
        if late_hours is not None:
            expire(hi - 1 - -(-late_hours // hours))

    stream.writeStream.foreachBatch(on_batch).option("checkpointLocation", f"{sink}-checkpoint").trigger(availableNow=True).start().awaitTermination()


def _closing(spark: SparkSession, d: str) -> DataFrame:
    sink = f"{shared_dir(spark)}/cycles-{uuid.uuid4().hex}"
    closing_cycles(replay(edge_events(spark, d), "ts", 4), 3, 6, sink)
    return spark.read.schema("event_id bigint, len bigint, cycle_str string").parquet(f"{sink}/batch=*")


_E = "SELECT event_id, ts, prev AS src, user_id AS dst FROM (SELECT event_id, ts, user_id, lag(user_id) OVER (ORDER BY ts, event_id) AS prev FROM events WHERE event_type = 'purchase') x WHERE prev IS NOT NULL AND prev <> user_id"
REGISTERED.append((
    "stream_closing_cycles", _closing,
    f"WITH e AS ({_E}), two AS (SELECT DISTINCT n.event_id, n.src AS u, n.dst AS v FROM e n JOIN e a ON a.src = n.dst AND a.dst = n.src WHERE a.ts > n.ts - INTERVAL 6 HOUR AND (a.ts < n.ts OR (a.ts = n.ts AND a.event_id < n.event_id))), "
    "three AS (SELECT DISTINCT n.event_id, n.src AS u, n.dst AS v, a.dst AS x FROM e n JOIN e a ON a.src = n.dst JOIN e b ON b.src = a.dst AND b.dst = n.src WHERE a.dst <> n.src AND a.dst <> n.dst AND a.ts > n.ts - INTERVAL 6 HOUR AND (a.ts < n.ts OR (a.ts = n.ts AND a.event_id < n.event_id)) AND b.ts > n.ts - INTERVAL 6 HOUR AND (b.ts < n.ts OR (b.ts = n.ts AND b.event_id < n.event_id))) "
    "SELECT event_id, CAST(2 AS BIGINT) AS len, u || '>' || v || '>' || u AS cycle_str FROM two UNION ALL SELECT event_id, 3, u || '>' || v || '>' || x || '>' || u FROM three",
))


def _windowed(kind: str) -> Callable:
    def run(spark: SparkSession, d: str) -> DataFrame:
        s = replay(edge_events(spark, d), "ts", 3).withWatermark("ts", "1 hour")
        w = F.window("ts", "1 day") if kind == "tumbling" else F.window("ts", "1 day", "12 hours")
        out = run_to_table(s.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("edges")), "complete")
        return out.select(F.unix_micros("w.start").alias("start_us"), "edges")

    return run


REGISTERED.append(("stream_tumbling_edges", _windowed("tumbling"), f"SELECT epoch_us(date_trunc('day', ts)) AS start_us, count(*) AS edges FROM ({_E}) e GROUP BY 1"))
REGISTERED.append(("stream_sliding_edges", _windowed("sliding"), f"SELECT (epoch_us(ts) // 43200000000 - o) * 43200000000 AS start_us, count(*) AS edges FROM ({_E}) e CROSS JOIN (VALUES (0), (1)) v(o) GROUP BY 1"))


def _sessions(spark: SparkSession, d: str) -> DataFrame:
    s = replay(table(spark, d, "events").select("event_id", instant("ts"), "user_id"), "ts", 3).withWatermark("ts", "1 hour")
    out = run_to_table(s.groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events")), "complete")
    return out.select("user_id", F.unix_micros("w.start").alias("start_us"), "events")


REGISTERED.append((
    "stream_session_users", _sessions,
    "SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS events FROM (SELECT user_id, ts, sum(brk) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > ts - INTERVAL 6 HOUR THEN 0 ELSE 1 END AS brk FROM events) a) b GROUP BY user_id, s",
))


def _dedup(spark: SparkSession, d: str) -> DataFrame:
    s = replay(edge_events(spark, d), "ts", 3)
    return run_to_table(s.dropDuplicates(["src", "dst"]).select("src", "dst"))


REGISTERED.append(("stream_dedup_edges", _dedup, f"SELECT DISTINCT src, dst FROM ({_E}) e"))


def _static_join(spark: SparkSession, d: str) -> DataFrame:
    """Stream edges with how often their source errs, from a static table."""
    errors = table(spark, d, "events").where("event_type = 'error'").groupBy(F.col("user_id").alias("src")).agg(F.count(F.lit(1)).alias("errors"))
    return run_to_table(replay(edge_events(spark, d), "ts", 3).join(cut(errors), "src").select("event_id", "errors"))


REGISTERED.append(("stream_static_join", _static_join, f"SELECT e.event_id, x.errors FROM ({_E}) e JOIN (SELECT user_id, count(*) AS errors FROM events WHERE event_type = 'error' GROUP BY user_id) x ON x.user_id = e.src"))


def _interval_join(spark: SparkSession, d: str) -> DataFrame:
    """Clicks followed by a purchase of the same user within an hour, stream to stream."""
    e = table(spark, d, "events").select("event_id", instant("ts"), "user_id", "event_type")
    a = replay(e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("ts").alias("t1"), F.col("user_id").alias("u1")), "t1", 3).withWatermark("t1", "1 hour")
    b = replay(e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("ts").alias("t2"), F.col("user_id").alias("u2")), "t2", 3).withWatermark("t2", "1 hour")
    return run_to_table(a.join(b, F.expr("u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL 1 HOUR")).select("click", "purchase"))


REGISTERED.append(("stream_interval_join", _interval_join, "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"))


def watch_paths(stream: DataFrame, s, t, k: int, sink: str) -> None:
    """Standing query: after each micro-batch, the s-t paths of at most k edges that use an edge not seen before."""
    spark = stream.sparkSession

    def on_batch(batch: DataFrame, batch_id: int) -> None:
        batch.select("src", "dst").distinct().write.mode("overwrite").parquet(f"{sink}-edges/batch={batch_id}")
        seen = spark.read.option("basePath", f"{sink}-edges").parquet(f"{sink}-edges/batch=*").where(F.col("batch") <= batch_id)
        first = cut(seen.groupBy("src", "dst").agg(F.min("batch").alias("since")))
        edges = first.withColumn("ord", F.col("dst"))
        q = spark.createDataFrame([(0, s, t, k)], "instance_id bigint, s bigint, t bigint, k int")
        p = simple_paths(edges, q, k).select(F.col("len").cast("long").alias("len"), "path", path_string().alias("path_str"))
        hops = p.select("path_str", "len", F.inline(F.transform(F.sequence(F.lit(1).cast("long"), "len"), lambda i: F.struct(F.element_at("path", i.cast("int")).alias("src"), F.element_at("path", (i + 1).cast("int")).alias("dst")))))
        fresh = hops.join(first, ["src", "dst"]).groupBy("path_str", "len").agg(F.max("since").alias("last")).where(F.col("last") == batch_id)
        fresh.select("len", "path_str").write.mode("overwrite").parquet(f"{sink}/batch={batch_id}")

    stream.writeStream.foreachBatch(on_batch).option("checkpointLocation", f"{sink}-checkpoint").trigger(availableNow=True).start().awaitTermination()


def _watch(spark: SparkSession, d: str) -> DataFrame:
    sink = f"{shared_dir(spark)}/watch-{uuid.uuid4().hex}"
    watch_paths(replay(edge_events(spark, d), "ts", 3), 8, 46, 3, sink)
    return spark.read.schema("len bigint, path_str string").parquet(f"{sink}/batch=*")


REGISTERED.append((
    "stream_watch_paths", _watch,
    f"WITH RECURSIVE e AS (SELECT DISTINCT src, dst FROM ({_E}) x), w(tail, path, len) AS (SELECT CAST(8 AS BIGINT), [CAST(8 AS BIGINT)], 0 UNION ALL SELECT e.dst, list_append(w.path, e.dst), w.len + 1 FROM w JOIN e ON e.src = w.tail WHERE w.len < 3 AND w.tail <> 46 AND NOT list_contains(w.path, e.dst)) SELECT CAST(len AS BIGINT) AS len, array_to_string(path, '>') AS path_str FROM w WHERE tail = 46 AND len > 0",
))


def reciprocated(stream: DataFrame) -> DataFrame:
    """(event_id, other): each edge with the latest earlier edge between the same two nodes the other way; state by unordered pair.

    Within a micro-batch edges of a pair are taken in order of time and id; the state is one id a direction.
    """

    def on_group(key, parts, state):
        last = dict(zip((False, True), state.get)) if state.exists else {False: -1, True: -1}
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        out = []
        for event, a, b in zip(rows["event_id"].tolist(), rows["src"].tolist(), rows["dst"].tolist()):
            back = last[not a > b]
            if back >= 0:
                out.append((event, back))
            last[a > b] = event
        state.update((last[False], last[True]))
        yield pd.DataFrame(out, columns=["event_id", "other"]).astype("int64")

    pair = stream.withColumns({"u": F.least("src", "dst"), "v": F.greatest("src", "dst")})
    return pair.groupBy("u", "v").applyInPandasWithState(on_group, "event_id bigint, other bigint", "forth bigint, back bigint", "append", "NoTimeout")


REGISTERED.append((
    "stream_reciprocated", lambda spark, d: run_to_table(reciprocated(replay(edge_events(spark, d), "ts", 3))),
    f"WITH e AS ({_E}) SELECT event_id, other FROM (SELECT n.event_id, (SELECT max_by(a.event_id, row(a.ts, a.event_id)) FROM e a WHERE a.src = n.dst AND a.dst = n.src AND (a.ts < n.ts OR (a.ts = n.ts AND a.event_id < n.event_id))) AS other FROM e n) x WHERE other IS NOT NULL",
))


def late_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts behind a watermark of one hour, when every 50th edge comes two files late: what is dropped stays dropped."""
    s = replay(edge_events(spark, sf_dir), "ts", 6, late="event_id % 50 = 7").withWatermark("ts", "1 hour")
    out = run_to_table(s.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("edges")))
    return out.select(F.unix_micros("w.start").alias("start_us"), "edges")


REGISTERED.append(("stream_late_edges", late_edges, None))
