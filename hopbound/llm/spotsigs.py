"""SpotSigs fingerprints on DataFrame functions alone.

A signature is a run of common words and the content words that follow it; a document's fingerprint is the
set of its signatures, each hashed to 32 bits. Sets are compared by Jaccard likeness: lengths too far
apart are pruned, and only sets that share one of their rarest signatures meet.
"""

from __future__ import annotations

import json
import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, written

# Frequent function words of English, German, French and Spanish.
COMMON = (
    "a an and are as at be by for from he in is it of on or that the this to was were which with "
    "auf das dem den der des die ein eine für im ist mit nicht sich sie und von zu "
    "au avec ce dans de des du en est et il la le les ne par pas pour que qui sur un une "
    "como con del el los las no para por se su una y"
).split()
CHAIN = 2


def _anchor_pattern() -> str:
    """Common words at a word's place, told apart by their first letter first."""
    by: dict[str, list[str]] = {}
    for w in sorted(set(COMMON), key=lambda w: (w[0], -len(w), w)):
        by.setdefault(w[0], []).append(w[1:])
    return "(?<![^ ])(" + "|".join(f"{a}(?:{'|'.join(rest)})" for a, rest in by.items()) + ") "


def _words(text: Column) -> Column:
    """Lower-case words as a list, the common words before a content word glued to it by _."""
    plain = F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " ")
    return F.split(F.trim(F.regexp_replace(plain, _anchor_pattern(), "$1_")), " ")


def with_signatures(df: DataFrame, text: str, out: str) -> DataFrame:
    """df plus out: the sorted distinct signature hashes of column text. A text without anchors has the hashes of its words."""
    df = df.withColumn("_w", _words(F.col(text)))

    def signature(w: Column, i: Column) -> Column:
        rest = [F.coalesce(F.substring_index(F.get("_w", i + k), "_", -1), F.lit("")) for k in range(1, CHAIN)]
        return F.when(F.contains(w, F.lit("_")), F.hash(w, *rest))

    found = F.array_sort(F.array_distinct(F.filter(F.transform("_w", signature), lambda s: s.isNotNull())))
    df = df.withColumn("_s", found)
    return df.withColumn(out, F.when(F.size("_s") > 0, F.col("_s")).otherwise(F.array_sort(F.array_distinct(F.transform("_w", lambda w: F.hash(w)))))).drop("_w", "_s")


def as_text(sigs: Column) -> Column:
    return F.array_join(F.transform(sigs, lambda s: F.lower(F.lpad(F.hex(s.cast("long").bitwiseAND(F.lit(0xFFFFFFFF))), 8, "0"))), "")


def likeness(a: Column, b: Column) -> Column:
    common = F.size(F.array_intersect(a, b))
    return common / (F.size(a) + F.size(b) - common)


ROWS_PER_BUCKET = 1000
MAX_CELLS = 1 << 20


def with_next(df: DataFrame, carry: list[str]) -> DataFrame:
    """df plus next_<c> for c in carry: the next row's value by descending doc_id, the first row's after the last.

    Ids are cut into buckets of about ROWS_PER_BUCKET rows by a histogram of equal id ranges, whose
    size is bounded; each bucket also gets the first row of the bucket below it, so no task orders all rows.
    Ties are put in order of the text's hash; null ids come last.
    """
    ids = df.select("doc_id")
    lo, hi, n = ids.agg(F.min("doc_id"), F.max("doc_id"), F.count(F.lit(1))).first()
    if not n:
        return df.select("*", *[F.col(c).alias(f"next_{c}") for c in carry])
    lo, hi = (0, 0) if lo is None else (lo, hi)
    cells = min(MAX_CELLS, max(1, 4 * n // ROWS_PER_BUCKET), hi - lo + 1)
    cell = F.coalesce(F.floor((F.col("doc_id") - F.lit(lo)).cast("decimal(38,0)") * cells / (hi - lo + 1)).cast("int"), F.lit(0))
    found = sorted(ids.groupBy(cell.alias("cell")).agg(F.count(F.lit(1)).alias("n"), F.max("doc_id").alias("head")).collect())
    bucket_of, heads, rows = [0] * cells, [], 0
    for c, m, head in found:  # at most MAX_CELLS numbers
        if not heads or rows + m > ROWS_PER_BUCKET:
            heads.append(None)
            rows = 0
        rows += m
        heads[-1] = head
        bucket_of[c] = len(heads) - 1
    array = lambda xs, kind: F.from_json(F.lit(json.dumps(xs)), f"array<{kind}>")
    k = len(heads)
    placed = df.withColumn("_b", F.get(array(bucket_of, "int"), cell))
    head = F.col("doc_id").eqNullSafe(F.get(array(heads, "long"), F.col("_b")))
    own = F.struct(F.col("_b").alias("b"), F.lit(0).alias("after"))
    below = F.struct(F.pmod(F.col("_b") + 1, F.lit(k)).alias("b"), F.lit(1).alias("after"))
    dealt = placed.withColumn("_at", F.explode(F.when(head, F.array(own, below)).otherwise(F.array(own))))
    dealt = dealt.select("*", F.col("_at.b").alias("_bucket"), F.col("_at.after").alias("_after")).drop("_b", "_at")
    w = Window.partitionBy("_bucket").orderBy("_after", F.col("doc_id").desc_nulls_last(), "_h")
    led = dealt.select("*", *[F.lead(c).over(w).alias(f"next_{c}") for c in carry])
    return led.where("_after = 0").drop("_bucket", "_after")


def op5_spotsigs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of all documents and of their edited texts. Null texts are empty; empty texts have the empty text's fingerprint."""
    docs = documents(spark, sf_dir).select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("_h", F.xxhash64("text"))
    led = with_next(with_signatures(docs, "text", "sigs"), ["text", "sigs"])
    n = F.char_length("text")
    third = F.floor(n / 3).cast("int")
    cut = led.select("doc_id", n.cast("long").alias("n_chars"), F.concat(F.substr("text", F.lit(1), n - third), F.substr("next_text", F.lit(1), third)).alias("edited"), "sigs", "next_sigs")
    both = with_signatures(cut, "edited", "edited_sigs")
    return both.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        as_text(F.col("sigs")).alias("fingerprint"),
        as_text(F.col("edited_sigs")).alias("edited_fingerprint"),
        likeness(F.col("sigs"), F.col("edited_sigs")).alias("near_edited"),
        likeness(F.col("sigs"), F.col("next_sigs")).alias("near_next"),
    )


def similar(docs: DataFrame, least: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """(members, pairs): doc_id and class_id of every document, and pairs of classes (a < b, likeness) of at least `least`.

    docs has doc_id and text; other columns are ignored. A class is an equal fingerprint, named by its least
    doc_id, so copies are not expanded into pairs. Signatures are ranked by how many classes have them; a
    set of n signatures is entered under its n - ceil(least * n) + 1 rarest ones only. Entries are
    partitioned by set length, in classes whose bounds grow by 1 / least, and meet only in their own and the two neighbouring
    classes, where the shorter set has at least `least` (above 0) times the longer one's length.
    """
    sets = written(with_signatures(docs.select("doc_id", "text"), "text", "sigs").select("doc_id", "sigs"), "sigs")
    classes = written(sets.groupBy("sigs").agg(F.min("doc_id").alias("class_id")), "classes")
    members = sets.join(classes, "sigs").select("doc_id", "class_id")
    each = classes.select("class_id", F.explode("sigs").alias("sig"))
    df = each.groupBy("sig").agg(F.count(F.lit(1)).alias("n"))
    ranked = each.join(df, "sig").groupBy("class_id").agg(F.sort_array(F.collect_list(F.struct("n", "sig"))).alias("order"))
    size = F.size("order")
    entries = ranked.select("class_id", size.alias("size"), F.explode(F.slice("order", 1, size - F.ceil(F.lit(least) * size).cast("int") + 1)).alias("e")).select("class_id", "size", "e.sig")
    part = F.floor(F.log("size") / math.log(1.001 / least))  # a little wider than 1 / least, so that rounding parts no pair by two classes
    b = entries.select(F.col("class_id").alias("b"), F.col("size").alias("nb"), "sig", part.alias("part"))
    a = entries.select(F.col("class_id").alias("a"), F.col("size").alias("na"), "sig", F.explode(F.array(part - 1, part, part + 1)).alias("part"))
    fits = (F.col("a") < F.col("b")) & (F.least("na", "nb") >= least * F.greatest("na", "nb"))
    met = a.join(b, ["sig", "part"]).where(fits).select("a", "b").distinct()
    s = classes.select("class_id", "sigs")
    full = met.join(s.select(F.col("class_id").alias("a"), F.col("sigs").alias("sa")), "a").join(s.select(F.col("class_id").alias("b"), F.col("sigs").alias("sb")), "b")
    return members, full.select("a", "b", likeness(F.col("sa"), F.col("sb")).alias("likeness")).where(F.col("likeness") >= least)
