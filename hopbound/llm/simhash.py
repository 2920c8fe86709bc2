"""SimHash near-duplicates by multi-index hashing.

64-bit fingerprints of word shingles; documents whose fingerprints differ in few bits are linked. Equal
fingerprints collapse first. Then every distinct fingerprint looks up small Hamming balls in the tables
of its segments: by the pigeonhole principle two fingerprints within r bits agree, up to a small
radius, in one of its segments. Matches are verified over all 64 bits. Where a table entry is crowded,
pairs are not enumerated: its members meet at the midpoints of their balls instead, which loses
no link (two fingerprints within r bits have a common point within r/2 of both) and takes rows in
proportion to the members.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, documents, give_back, slim, widened, written

# Segments as (low bit, width, radius): two fingerprints within 4 bits agree up to the radius in one of them. If the first
# segments differ by more than their radii, too few differences are left for the last.
SEGMENTS = ((0, 22, 1), (22, 21, 1), (43, 21, 0))
WIDE_SEGMENTS = ((0, 32, 2), (32, 32, 1))
MANY = 1 << 27  # distinct fingerprints from which the wide segments keep table entries short
CROWDED = 200  # distinct fingerprints of a table entry beyond which midpoints are used


def fingerprint(text: str | None, shingle: int = 4) -> int:
    """Bit set if set in over half of the XXH64 (seed 42) of the word shingles, repeats counted; no words: 0."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[:-1]))[:n].tolist()
    stops = (ends[min(shingle, len(words)) - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(joined[a:b], 42) for a, b in zip(starts, stops)), np.uint64, n)
    ones = np.zeros(64, np.int64)
    for k in range(0, n, 1 << 16):
        ones += np.unpackbits(h[k : k + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """(doc_id, fp): fp a signed 64-bit integer with the fingerprint's bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t.as_py(), shingle) for t in b.column("text")), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fp.view(np.int64))], ["doc_id", "fp"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, fp long")


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def _balls(low: int, width: int, radius: int) -> list[int]:
    """All masks of up to radius (2 at most) bits among `width` bits from `low`, as signed 64-bit integers."""
    masks = [0]
    for i in range(low, low + width if radius else low):
        masks.append(1 << i)
        masks += [1 << i | 1 << j for j in range(low, i)] if radius > 1 else []
    return [_signed(m) for m in masks]


def links(fps: DataFrame, bits: int = 4) -> DataFrame:
    """(a, b): links that join the same distinct fingerprints (column fp) as all pairs within `bits` (0, 2 or 4) would."""
    if bits not in (0, 2, 4):
        raise ValueError("bits must be 0, 2 or 4: an odd distance has no common midpoint")
    segments = SEGMENTS if fps.limit(MANY).count() < MANY else WIDE_SEGMENTS
    whole = [_signed(((1 << width) - 1) << low) for low, width, _ in segments]
    table = F.explode(F.array(*[F.struct(F.lit(s).alias("seg"), F.col("fp").bitwiseAND(F.lit(m)).alias("val")) for s, m in enumerate(whole)]))

    def ball_of(s: int) -> Column:
        own = F.col("fp").bitwiseAND(F.lit(whole[s]))
        near = F.array(*[F.lit(x).cast("long") for x in _balls(*segments[s])])
        return F.transform(near, lambda x: F.struct(F.lit(s).alias("seg"), own.bitwiseXOR(x).alias("val")))

    ball = F.explode(F.flatten(F.array(*[ball_of(s) for s in range(len(segments))])))
    entries = fps.select("fp", table.alias("e")).select("fp", "e.seg", "e.val")
    probes = fps.select("fp", ball.alias("e")).select("fp", "e.seg", "e.val")
    counts = entries.groupBy("seg", "val").agg(F.count("*").alias("n"))
    crowded = written(counts.where(F.col("n") > CROWDED).select("seg", "val"), "crowded")
    # members of crowded entries meet at midpoints; all others are paired in their entries
    sparse = entries.join(crowded, ["seg", "val"], "left_anti")
    pairs = probes.withColumnRenamed("fp", "a").join(sparse.withColumnRenamed("fp", "b"), ["seg", "val"]).where((F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= bits)).select("a", "b")
    reach = bits // 2
    dense = probes.join(crowded, ["seg", "val"], "left_semi").select("fp").distinct()
    met = _meet(dense, reach)
    return pairs.distinct().unionByName(met)


def _meet(fps: DataFrame, radius: int) -> DataFrame:
    """(a, b) links through common points of the balls of this radius: each fingerprint with the least one at each point."""
    masks = np.array(_balls(0, 64, radius), np.int64)

    def points(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for k in range(0, len(batch), 256):
                fp = batch["fp"].to_numpy(np.int64)[k : k + 256]
                at = (fp[:, None] ^ masks[None, :]).ravel()
                yield pd.DataFrame({"point": at, "fp": np.repeat(fp, len(masks))})

    hubs = fps.mapInPandas(points, "point long, fp long")
    least = hubs.groupBy("point").agg(F.min("fp").alias("b"), F.max("fp").alias("top")).where("b < top").select("point", "b")
    return hubs.join(least, "point").where("fp <> b").select(F.col("fp").alias("a"), "b").distinct()


def _components(fps: DataFrame, bits: int) -> DataFrame:
    """(_fp, component) of the distinct fingerprints of fps; a component is named by one of its fingerprints."""
    reps = fps.select("fp").distinct()
    comp = components(links(reps, bits))
    return reps.join(comp, reps["fp"] == comp["node"], "left").select(F.col("fp").alias("_fp"), F.coalesce("component", "fp").alias("component"))


def near_duplicates(docs: DataFrame, bits: int = 4, shingle: int = 4) -> DataFrame:
    """(doc_id, fp, component_id): one row per row of docs.

    docs has doc_id and text; other columns are ignored. Null and empty texts have fingerprint 0, linked like
    any other. Repeated rows are all returned. component_id is the least doc_id reachable, null only if
    all ids there are null. No rows give no rows.
    """
    fps = written(fingerprints(docs, shingle), "fingerprints")
    named = _components(fps, bits)
    first = fps.groupBy("fp").agg(F.min("doc_id").alias("first")).join(named, F.col("fp") == F.col("_fp")).groupBy("component").agg(F.min("first").alias("component_id"))
    of = named.join(first, "component").select("_fp", "component_id")
    return fps.join(of, fps["fp"] == of["_fp"]).select("doc_id", "fp", "component_id")


def one_each(docs: DataFrame, bits: int = 4, shingle: int = 4) -> DataFrame:
    """The row with the least doc_id (null last, then by hash of the text) of each group of near duplicates, all columns of docs."""
    keyed = slim(docs, ["doc_id", "text"]).withColumn("_h", F.xxhash64("text"))
    fps = written(fingerprints(docs, shingle), "fingerprints")
    return widened(_least_rows(keyed, fps, _components(fps, bits)), docs)


def _least_rows(keyed: DataFrame, fps: DataFrame, named: DataFrame) -> DataFrame:
    """The row of keyed with the least doc_id of each component; fps has doc_id and fp, named has _fp and component."""
    at = fps.groupBy("fp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id")).alias("first"))
    first = at.join(named, F.col("fp") == F.col("_fp")).groupBy("component").agg(F.min("first").alias("first")).select("component", "first.doc_id")
    kept = first.select(F.col("doc_id").alias("_d"), F.lit(True).alias("_kept")).distinct()
    return _first_of(keyed.join(kept, F.col("doc_id").eqNullSafe(F.col("_d"))).drop("_d", "_kept"))


def _first_of(rows: DataFrame) -> DataFrame:
    """One row of each doc_id, the one with the least text hash."""
    rest = [c for c in rows.columns if c not in ("doc_id", "_h")]
    return rows.groupBy("doc_id").agg(F.min_by(F.struct(*rest), "_h").alias("_r")).select("doc_id", "_r.*")


# Tables for Jaccard 0.8: a pair there meets in one of BANDS tables of ROWS least hashes with probability 1 - (1 - 0.8 ** 5) ** 24 > 0.9999.
# 64-bit fingerprints of such a pair differ in 10 bits on average and in 17 now and then, which no bit tables of reasonable number cover.
BANDS, ROWS = 24, 5
_XOR, _TIMES = np.random.default_rng(20240301).integers(0, 1 << 64, (2, BANDS * ROWS, 1), dtype=np.uint64)
_TIMES = _TIMES | np.uint64(1)
ALIKE, ALIKE_SHINGLE = 0.8, 5
SLICE = 256  # texts whose sets a worker makes at a time
FIRST_TABLES = 3  # tables that are measured by one link a set
BUCKET = 8  # sets of a table entry up to which its pairs are rows
HUB_SETS, HUB_ROUNDS = 8192, 12  # sets beyond which an entry goes through rounds of hubs first, and how many
BLOCK_SETS, BLOCK_SHINGLES = 512, 4_000_000  # of a block
MAX_BROADCAST_ROWS = 1_000_000


def shingle_set(text: str | None, shingle: int = ALIKE_SHINGLE) -> np.ndarray:
    """Sorted distinct XXH64 (seed 42) of the word shingles; texts of fewer words are one shingle; no words: none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - shingle + 1)
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[:-1]))[:n].tolist()
    stops = (ends[min(shingle, len(words)) - 1 :] - 1).tolist()
    return np.unique(np.fromiter((digest(joined[a:b], 42) for a, b in zip(starts, stops)), np.uint64, n))


def band_keys(hashes: np.ndarray) -> list[int]:
    """Signed 64-bit key of a set in each of the BANDS tables; the empty set has none."""
    if not len(hashes):
        return []
    least = np.full(BANDS * ROWS, (1 << 64) - 1, np.uint64)
    for k in range(0, len(hashes), 4096):
        np.minimum(least, ((hashes[None, k : k + 4096] ^ _XOR) * _TIMES).min(axis=1), out=least)
    raw = least.tobytes()
    return [_signed(xxhash.xxh64_intdigest(raw[8 * ROWS * i : 8 * ROWS * (i + 1)], i)) for i in range(BANDS)]


def _sets(keyed: DataFrame, shingle: int, whole: bool) -> DataFrame:
    """Of rows (doc_id, k, text): (doc_id, k, sid, fp, keys), or with `whole` (sid, shingles); sid names a set of shingles, fp is the SimHash of the text."""
    kind = keyed.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):  # a worker holds the sets of few texts at a time
                b = batch.slice(at, SLICE)
                texts = [t.as_py() for t in b.column("text")]
                sets = [shingle_set(t, shingle) for t in texts]
                sid = pa.array([_signed(xxhash.xxh64_intdigest(h.tobytes(), 0)) for h in sets], pa.int64())
                if whole:
                    yield pa.RecordBatch.from_arrays([sid, pa.array([h.view(np.int64) for h in sets], pa.list_(pa.int64()))], ["sid", "shingles"])
                else:
                    fp = np.fromiter((fingerprint(t, shingle) for t in texts), np.uint64, len(texts)).view(np.int64)
                    yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("k"), sid, pa.array(fp), pa.array([band_keys(h) for h in sets], pa.list_(pa.int64()))], ["doc_id", "k", "sid", "fp", "keys"])
        give_back()

    return keyed.mapInArrow(run, "sid long, shingles array<long>" if whole else f"doc_id {kind}, k long, sid long, fp long, keys array<long>")


def _likeness(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """pairs (a, b) with `like`, the exact Jaccard similarity of their sets."""
    one = pairs.join(sets.select(F.col("sid").alias("a"), F.col("shingles").alias("_x")), "a")
    two = one.join(sets.select(F.col("sid").alias("b"), F.col("shingles").alias("_y")), "b")
    both = F.size(F.array_intersect("_x", "_y"))
    return two.withColumn("like", both / (F.size("_x") + F.size("_y") - both)).select("a", "b", "like")


def _alike(pairs: DataFrame, sets: DataFrame, alike: float) -> DataFrame:
    return written(_likeness(pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), sets).where(F.col("like") >= alike).select("a", "b"), "alike")


def _to_hubs(entries: DataFrame) -> DataFrame:
    """entries with `hub`, the least set of their key, without the hubs' own rows."""
    return entries.join(entries.groupBy("key").agg(F.min("sid").alias("hub")), "key").where("sid <> hub")


def _among(shingles: list[np.ndarray], names: np.ndarray, parts: np.ndarray, alike: float) -> list[tuple[int, int]]:
    """Links that join the sets of a block as all its pairs of at least `alike` of different parts do; at most one fewer than there are sets."""
    n = len(shingles)
    size = np.array([len(x) for x in shingles], np.int64)
    _, column, times = np.unique(np.concatenate(shingles), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(n), size)
    shared = times[column] > 1
    row, column = row[shared], np.unique(column[shared], return_inverse=True)[1]
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    both = np.zeros((n, n), np.float32)  # counts below 2^24 are exact
    for k in range(0, int(column[-1]) + 1 if len(column) else 0, 4096):
        own = slice(*np.searchsorted(column, [k, k + 4096]))
        m = np.zeros((n, 4096), np.float32)
        m[row[own], column[own] - k] = 1
        both += m @ m.T
    both = both.astype(np.float64)
    like = both / np.maximum(size[:, None] + size[None, :] - both, 1)
    up = {c: c for c in parts.tolist()}

    def root(c: int) -> int:
        while up[c] != c:
            up[c] = up[up[c]]
            c = up[c]
        return c

    out = []
    for i, j in zip(*np.nonzero(np.triu(like >= alike, 1))):
        x, y = root(int(parts[i])), root(int(parts[j]))
        if x != y:
            up[x] = y
            out.append((int(max(names[i], names[j])), int(min(names[i], names[j]))))
    return out


def _bounded(few: DataFrame) -> DataFrame:
    """A written table to be broadcast if its rows are at most MAX_BROADCAST_ROWS, so that rows joined to it by a hot key stay where they are."""
    return F.broadcast(few) if few.limit(MAX_BROADCAST_ROWS + 1).count() <= MAX_BROADCAST_ROWS else few


def block_links(entries: DataFrame, sets: DataFrame, alike: float) -> DataFrame:
    """(a, b): links that join the sets of every entry (key, sid, c: the component so far) as all its pairs of at least `alike` do.

    An entry's sets are dealt to blocks of about BLOCK_SETS sets and BLOCK_SHINGLES shingles, and every two blocks meet in a task of their own,
    which compares them by matrix products and returns no more links than it has sets. Pairs are never rows.
    """
    size = entries.join(sets.select("sid", F.size("shingles").alias("_n")), "sid")
    blocks = size.groupBy("key").agg(F.ceil(F.greatest(F.count(F.lit(1)) / BLOCK_SETS, F.sum("_n") / BLOCK_SHINGLES)).cast("int").alias("_blocks"))
    own = entries.join(_bounded(written(blocks, "blocks")), "key").withColumn("_own", F.pmod(F.xxhash64("sid"), F.col("_blocks")).cast("int"))
    dealt = own.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
    rows = dealt.select("key", F.least("_own", "_other").alias("i"), F.greatest("_own", "_other").alias("j"), "sid", "c").join(sets, "sid")

    def run(part: pa.Table) -> pa.Table:
        shingles = [np.asarray(x.values, np.int64) for x in part.column("shingles")]
        found = _among(shingles, part.column("sid").to_numpy(), part.column("c").to_numpy(), alike)
        return pa.table([pa.array([x for x, _ in found], pa.int64()), pa.array([y for _, y in found], pa.int64())], ["a", "b"])

    return rows.select("key", "i", "j", "sid", "c", "shingles").groupBy("key", "i", "j").applyInArrow(run, "a long, b long")


def alike_links(found: DataFrame, near: DataFrame, sets: DataFrame, alike: float = ALIKE) -> DataFrame:
    """(a, b): links that join the same sets as all pairs do that are in near or share a table entry and have a Jaccard similarity of at least `alike`.

    found has sid, tab (number of the table) and key (rows distinct), near a and b, sets sid and shingles. Pairs of sets that are
    joined already need no measuring: so the first tables and near are measured by one link a set, and of all tables
    only entries of more than one component go on: small ones pair by pair, others block by block. Of an entry of very many sets, all its sets
    are first measured against one of them, the hub, for HUB_ROUNDS rounds. Those alike to it are joined through it; the others go on without
    the hub, and with those of its neighbours that, by the triangle inequality of the Jaccard distance, can be alike to one of them.
    """
    stars = _to_hubs(found.where(F.col("tab") < FIRST_TABLES).select("key", "sid")).select(F.col("sid").alias("a"), F.col("hub").alias("b"))
    joined = _alike(near.unionByName(stars), sets, alike)
    comp = components(joined)
    named = found.select("key", "sid").join(comp.withColumnRenamed("node", "sid"), "sid", "left").select("key", "sid", F.coalesce("component", "sid").alias("c"))
    mixed = named.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("key")
    cur = written(named.join(mixed, "key"), "entries")
    rest = cur.limit(0)
    for _ in range(HUB_ROUNDS):
        large = written(cur.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HUB_SETS).select("key"), "large")
        if not large.limit(1).count():
            break
        rest = rest.unionByName(cur.join(large, "key", "left_anti"))
        rows = written(_to_hubs(cur.join(large, "key", "left_semi")), "members")
        like = written(_likeness(rows.select(F.col("sid").alias("a"), F.col("hub").alias("b")).distinct(), sets), "likeness")
        joined = joined.unionByName(like.where(F.col("like") >= alike).select("a", "b"))
        rows = rows.join(like.select(F.col("a").alias("sid"), F.col("b").alias("hub"), (1 - F.col("like")).alias("far")), ["sid", "hub"])
        least = rows.where(F.col("far") > 1 - alike + 1e-12).groupBy("key").agg(F.min("far").alias("least"))
        cur = written(rows.join(least, "key").where(F.col("far") >= F.col("least") - (1 - alike) - 1e-9).select("key", "sid", "c"), "entries")
    rest = rest.unionByName(cur)
    many = written(rest.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > BUCKET).select("key"), "many")
    many = _bounded(many)
    few = rest.join(many, "key", "left_anti")
    one, two = (few.select("key", F.col("sid").alias(x), F.col("c").alias(f"_{x}")) for x in "ab")
    pairs = one.join(two, "key").where("a < b AND _a <> _b").select("a", "b")
    blocks = written(block_links(rest.join(many, "key", "left_semi"), sets, alike), "alike")
    return joined.unionByName(_alike(pairs, sets, alike)).unionByName(blocks)


def one_each_alike(docs: DataFrame, alike: float = ALIKE, shingle: int = ALIKE_SHINGLE, bits: int = 4) -> DataFrame:
    """As one_each, of groups of documents whose sets of word shingles have a Jaccard similarity of at least `alike`.

    Candidates are pairs of near fingerprints and pairs that share one of BANDS tables of least hashes; each is measured exactly.
    """
    keyed = slim(docs, ["doc_id", "text"]).withColumn("_h", F.xxhash64("text"))
    named = keyed.select("doc_id", F.xxhash64("doc_id", "text").alias("k"), "text")
    found = written(_sets(named, shingle, False), "sets")
    once = found.groupBy("sid").agg(F.min_by(F.struct("k", "fp", "keys"), "k").alias("r")).select("sid", "r.*")
    once = written(once, "reps")
    entries = once.select("sid", F.posexplode("keys").alias("tab", "key"))
    shared = entries.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("key")
    entries = written(entries.join(shared, "key"), "entries")
    # fingerprints: equal ones are linked to the least set of theirs, near ones through those
    of_fp = once.groupBy("fp").agg(F.min("sid").alias("first"))
    same = once.join(of_fp, "fp").where("sid <> first").select(F.col("sid").alias("a"), F.col("first").alias("b"))
    ends = links(once.select("fp").distinct(), bits)
    for c in ("a", "b"):
        ends = ends.join(of_fp.select(F.col("fp").alias(c), F.col("first").alias(f"_{c}")), c)
    near = written(same.unionByName(ends.select(F.col("_a").alias("a"), F.col("_b").alias("b"))), "near")
    needed = entries.select("sid").unionByName(near.select(F.col("a").alias("sid"))).unionByName(near.select(F.col("b").alias("sid"))).distinct()
    ks = written(once.join(needed, "sid").select("k"), "needed")
    sets = written(_sets(named.join(_bounded(ks), "k", "left_semi").select("doc_id", "k", "text"), shingle, True).dropDuplicates(["sid"]), "shingles")
    comp = components(alike_links(entries, near, sets, alike))
    sids = once.select("sid")
    groups = sids.join(comp, sids["sid"] == comp["node"], "left").select(F.col("sid").alias("_fp"), F.coalesce("component", "sid").alias("component"))
    return widened(_least_rows(keyed, found.select("doc_id", F.col("sid").alias("fp")), groups), docs)


def op7_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(documents(spark, sf_dir).select("doc_id", "text"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
