"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Every source gets a word target by water filling. Its documents are taken in whole epochs first; what
is left of the target is filled with documents in order of exponential keys scaled by quality weights
(key = -ln(u) / weight, least first) up to the budget. Prefix sums over a source are distributed: keys
are dealt to bins, bin totals are summed, and only the bin in which the budget runs out is ordered,
twice over, so no task gets a whole source.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, slim, widened, word_count, written

BINS = 1024


def targets(sizes: DataFrame, weights: Sequence[float], share: float, max_epochs: float) -> DataFrame:
    """(source, source_size, target) from (source, source_size); weights repeat over the sources by code point, null last.

    share times all words are dealt by weight; a source gets max_epochs times its size at most, the
    excess going to the others by weight until none is above. Sources with no words get 0. The fill level
    is found in one ordered pass: capped sources are those with the least cap/weight.
    """
    order = Window.orderBy(F.col("source").isNull(), F.hex(F.encode("source", "UTF-8")))
    ws = F.array(*[F.lit(float(w)) for w in weights])
    s = sizes.withColumn("w", F.element_at(ws, (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
    s = s.withColumn("cap", max_epochs * F.col("source_size"))
    total = Window.partitionBy()
    by = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").isNull(), F.hex(F.encode("source", "UTF-8"))).rowsBetween(Window.unboundedPreceding, -1)
    s = s.withColumns({"budget": share * F.sum("source_size").over(total), "ws": F.sum("w").over(total)})
    s = s.withColumn("level", (F.col("budget") - F.coalesce(F.sum("cap").over(by), F.lit(0.0))) / (F.col("ws") - F.coalesce(F.sum("w").over(by), F.lit(0.0))))
    # sources with the least cap/weight are capped first; the first that is not sets the level of all that follow
    place = F.row_number().over(Window.orderBy(F.col("cap") / F.col("w"), F.col("source").isNull(), F.hex(F.encode("source", "UTF-8"))))
    s = s.withColumn("place", place)
    s = s.withColumn("fill", F.min(F.when(F.col("level") * F.col("w") <= F.col("cap"), F.struct("place", "level"))).over(total))
    s = s.select("*", F.col("fill.place").alias("first"), F.col("fill.level").alias("lv")).drop("fill").withColumnRenamed("lv", "fill")
    s = s.withColumn("fill", F.when(F.col("place") >= F.col("first"), F.col("fill")))
    return s.select("source", "source_size", F.least(F.col("cap"), F.coalesce(F.col("fill") * F.col("w"), F.col("cap"))).alias("target"))


def _upto(rows: DataFrame, budget: str, key: Column, unit: list[str]) -> DataFrame:
    """Of rows (size, budget column, unit columns), bins of key: `_sure` where the bin ends within budget, `_rest` before the bin."""
    bins = rows.groupBy(*unit, key.alias("_bin")).agg(F.sum("size").alias("_n"))
    w = Window.partitionBy(*unit).orderBy("_bin").rowsBetween(Window.unboundedPreceding, 0)
    return bins.withColumn("_end", F.sum("_n").over(w)).withColumn("_start", F.col("_end") - F.col("_n"))


def mix(docs: DataFrame, quality: DataFrame | None = None, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, max_epochs: int = 2, seed: int = 42) -> DataFrame:
    """docs' rows with _id, size, source_size, target, epochs (whole copies) and extra (1 if in the fractional part).

    docs has doc_id, text, source; quality has doc_id and weight (positive; 1 where missing). Null texts
    have size 0, null sources are one source, ordered last. Rows of size 0 are taken in whole epochs only.
    Repeated rows are separate documents. The document at the budget's end is taken if that comes
    nearer to the target. Same rows, same result.
    """
    spark = docs.sparkSession
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("h"))
    if quality is not None:
        rows = rows.join(quality.groupBy("doc_id").agg(F.max("weight").alias("weight")), "doc_id", "left")
    else:
        rows = rows.withColumn("weight", F.lit(1.0))
    u = (F.pmod(F.xxhash64("doc_id", "h", F.lit(seed)), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    rows = written(rows.withColumn("key", -F.log(u) / F.greatest(F.coalesce("weight", F.lit(1.0)), F.lit(1e-6))), "mix")
    sizes = written(targets(rows.groupBy("source").agg(F.sum("size").cast("long").alias("source_size")), weights, share, max_epochs), "targets")
    plan = sizes.withColumn("epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long"))
    plan = plan.withColumn("left", F.col("target") - F.col("epochs") * F.col("source_size"))
    # keys lie in (0, inf); 1 - exp(-key) deals them evenly for weight 1 and in order for any weight
    even = 1 - F.exp(-F.col("key"))
    bin1 = F.floor(even * BINS)
    bin2 = F.floor((even * BINS - F.floor(even * BINS)) * BINS)
    same = lambda a, b: a.eqNullSafe(b)
    p = plan.select(F.col("source").alias("_s"), "left")
    b1 = _upto(rows, "left", bin1, ["source"])
    cut1 = written(b1.join(p, same(b1["source"], p["_s"])).where("_start < left and _end >= left").select("_s", F.col("_bin").alias("b1"), (F.col("left") - F.col("_start")).alias("left1")), "bins")
    in1 = written(rows.withColumn("_b1", bin1).join(cut1, same(F.col("source"), F.col("_s")) & (F.col("_b1") == F.col("b1"))).drop("_s"), "bin")
    b2 = _upto(in1, "left1", bin2, ["source"])
    c1 = cut1.select("_s", "left1")
    cut2 = written(b2.join(c1, same(b2["source"], c1["_s"])).where("_start < left1 and _end >= left1").select("_s", F.col("_bin").alias("b2"), (F.col("left1") - F.col("_start")).alias("left2")), "bins")
    in2 = in1.withColumn("_b2", bin2).join(cut2, same(F.col("source"), F.col("_s")) & (F.col("_b2") == F.col("b2"))).drop("_s")
    w = Window.partitionBy("source").orderBy("key", "doc_id", "h")
    run = F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, 0))
    last = in2.withColumn("_end", run).select("source", "key", "doc_id", "h", "size", "_end", "left2")
    # the limit key: the last one taken, ordered by (key, doc_id, h); nothing of the bin may be taken
    limit = last.where(F.col("_end") - F.col("size") / 2 <= F.col("left2")).groupBy("source").agg(F.max(F.struct("key", "doc_id", "h")).alias("limit"))
    full = cut1.join(cut2.select(F.col("_s").alias("_t"), "b2"), same(F.col("_s"), F.col("_t")), "left").drop("_t")
    full = full.join(limit.select(F.col("source").alias("_t"), "limit"), same(F.col("_s"), F.col("_t")), "left").drop("_t").withColumnRenamed("_s", "_p")
    plan = written(plan.join(full, same(plan["source"], full["_p"]), "left").drop("_p").withColumnRenamed("source", "_s"), "plan")
    # a document is in the fractional part if its bin, or its place in the last bin, is before the end
    me = F.struct("key", "doc_id", "h")
    before = (bin1 < F.col("b1")) | ((bin1 == F.col("b1")) & ((bin2 < F.col("b2")) | ((bin2 == F.col("b2")) & F.coalesce(me <= F.col("limit"), F.lit(False)))))
    took = F.when(F.col("left") <= 0, F.lit(0)).otherwise(F.when(F.coalesce(before, F.lit(False)) & (F.col("size") > 0), F.lit(1)).otherwise(F.lit(0)))
    chosen = _per_source(rows, plan).select("doc_id", "h", "source", "size", "source_size", "target", "epochs", took.cast("long").alias("extra"))
    return chosen


def _per_source(rows: DataFrame, plan: DataFrame) -> DataFrame:
    """rows joined with one plan row per source. The plan is broadcast when it has few rows (checked), else shuffled."""
    few = plan.limit(MAX_SOURCES + 1).count() <= MAX_SOURCES
    return rows.join(F.broadcast(plan) if few else plan, rows["source"].eqNullSafe(plan["_s"])).drop("_s")


MAX_SOURCES = 100_000


def labelled_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality weights of labelled documents: 2 for good ones, 1/2 for bad ones; others weigh 1."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return labels.select("doc_id", F.when(F.col("quality") == 1, 2.0).when(F.col("quality") == 0, 0.5).otherwise(1.0).alias("weight"))


def op1_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text", "source")
    chosen = mix(docs, labelled_weights(spark, sf_dir))
    return chosen.select("doc_id", "size", "source_size", "target", (F.col("size") * (F.col("epochs") + F.col("extra"))).alias("taken"), "source", "epochs", "extra")


def mixed_documents(docs: DataFrame, quality: DataFrame | None = None, **how: object) -> DataFrame:
    """The mix itself: docs' columns, each row as often as it is taken.

    docs is keyed by (doc_id, hash of its text); rows equal in both are the same document, taken alike.
    """
    chosen = mix(docs, quality, **how).select(F.col("doc_id").alias("_d"), F.col("h").alias("_h"), (F.col("epochs") + F.col("extra")).cast("int").alias("_times")).dropDuplicates(["_d", "_h"])
    both = slim(docs, ["doc_id", "text"]).withColumn("_k", F.xxhash64("text")).join(chosen, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("_k") == F.col("_h")))
    return both.where("_times > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).transform(widened, docs)
