"""Quality classifier: an interpolated modified Kneser-Ney n-gram model of trusted text.

N-grams are over characters as they are, ORDER at a time: they find scrambled, shouted and decorated text in any script. Their counts
grow with the corpus and stay on the cluster. Documents are cut into shards of at most SHARD_CHARS characters; a shard sends its
different n-grams, each once, to be joined with the sharded counts, and gets their log probabilities back by a join on its
number, under which its documents already lie. So what moves is n-grams per shard, not per document, no
n-gram is a hot key beyond one row a shard, and nothing is broadcast. Thresholds are quantiles of the trusted documents of each language.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import bucketed, documents, give_back, slim, widened, written

ORDER = 4
QUANTILE = 0.99
START = "\x02"  # stands ORDER - 1 times before every text
CODE_POINTS = 0x110000  # characters there may be: the uniform distribution below the unigrams
SHARD_CHARS = 32 << 20  # characters of a shard; a longer text is a shard of its own
CHUNK_CHARS = 1 << 19  # characters that are looked at together
MAX_BROADCAST_LABELS = 1_000_000
MAX_LANGUAGES = 10_000
MODELS = ("all", "even", "odd")  # models of all trusted texts and of either half of them
_TIMES = np.random.default_rng(20240307).integers(0, 1 << 64, 16, dtype=np.uint64) | np.uint64(1)


def _characters(texts: list[str | None], order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(characters of all texts, each behind order - 1 times START; length of each text; key of the n-gram that ends at each of their own characters).

    A key is a 64-bit hash, unique within a shard but for a chance of some 10^-5 for a shard of 2^25 different n-grams. U+0000 is read as U+FFFD.
    """
    pad = START * (order - 1)
    whole = "".join(pad + (t or "") for t in texts).replace("\0", "�")
    points = np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32)
    n = np.fromiter((len(t or "") for t in texts), np.int64, len(texts))
    width = len(points) - order + 1
    key = np.zeros(max(width, 0), np.uint64)
    for k in range(order):
        key += points[k : k + width] * _TIMES[k]
    # n-grams of order - 1 starts and a text's own characters begin where the text's block begins
    begin = np.cumsum(n + order - 1) - n - (order - 1)
    own = np.repeat(begin - (np.cumsum(n) - n), n) + np.arange(n.sum())
    return points, n, key[own].view(np.int64) if len(own) else np.zeros(0, np.int64)


def _chunks(texts: list[str | None], chars: int) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about so many characters."""
    begin, size = 0, 0
    for k, t in enumerate(texts):
        size += len(t or "")
        if size >= chars:
            yield begin, k + 1
            begin, size = k + 1, 0
    if begin < len(texts):
        yield begin, len(texts)


class _Grams:
    """The different n-grams of a shard with their counts in the two halves of the trusted texts."""

    def __init__(self, order: int):
        self.order = order
        self.keys, self.grams, self.n = np.zeros(0, np.int64), np.zeros((0, order), np.uint32), np.zeros((0, 2), np.int64)
        self.new: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.pending = 0

    def add(self, texts: list[str | None], fold: np.ndarray) -> None:
        points, n, key = _characters(texts, self.order)
        code, keys = pd.factorize(key)
        first = np.empty(len(keys), np.int64)
        first[code[::-1]] = np.arange(len(key))[::-1]
        of = np.repeat(np.arange(len(n)), n)
        at = first + (of[first] + 1) * (self.order - 1) if len(first) else first  # place of the last character among points
        grams = points[at[:, None] + np.arange(1 - self.order, 1)]
        counts = np.stack([np.bincount(code[np.repeat(fold == f, n)], minlength=len(keys)) for f in (0, 1)], axis=1)
        self.new.append((keys, grams, counts))
        self.pending += len(keys)
        if self.pending > max(1 << 18, len(self.keys)):
            self.merge()

    def merge(self) -> None:
        keys = np.concatenate([self.keys, *(x[0] for x in self.new)])
        code, self.keys = pd.factorize(keys)
        first = np.empty(len(self.keys), np.int64)
        first[code[::-1]] = np.arange(len(keys))[::-1]
        self.grams = np.concatenate([self.grams, *(x[1] for x in self.new)])[first]
        counts = np.concatenate([self.n, *(x[2] for x in self.new)])
        self.n = np.stack([np.bincount(code, weights=counts[:, f], minlength=len(self.keys)).astype(np.int64) for f in (0, 1)], axis=1)
        self.new, self.pending = [], 0

    def rows(self) -> Iterator[tuple[list[str], list[int], list[int]]]:
        """Blocks of n-grams in order of their characters, which packs them well."""
        self.merge()
        order = np.lexsort(self.grams.T[::-1])
        for k in range(0, len(order), 1 << 16):
            part = order[k : k + (1 << 16)]
            yield _strings(self.grams[part]), self.n[part, 0].tolist(), self.n[part, 1].tolist()


def _strings(grams: np.ndarray) -> list[str]:
    return np.ascontiguousarray(grams).view(f"<U{grams.shape[1]}").ravel().tolist()


def _packed(batch: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _nullable(kind: pa.DataType) -> pa.DataType:
    """The type with all fields nullable, as schemas written in text are."""
    if pa.types.is_struct(kind):
        return pa.struct([pa.field(f.name, _nullable(f.type)) for f in kind])
    if pa.types.is_map(kind):
        return pa.map_(_nullable(kind.key_type), _nullable(kind.item_type))
    if pa.types.is_list(kind):
        return pa.list_(pa.field(kind.value_field.name, _nullable(kind.value_type)))
    return kind


def _unpacked(data: bytes) -> pa.Table:
    rows = pa.ipc.open_stream(data).read_all()
    return rows.cast(pa.schema([pa.field(f.name, _nullable(f.type)) for f in rows.schema]))


def shards(docs: DataFrame, order: int = ORDER, shard_chars: int = SHARD_CHARS, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """docs (column text, and _fold: 0 or 1 in trusted rows) cut into shards: (shard, first, rows, grams, even, odd), a table bucketed by shard.

    A row has either rows, documents from the place `first` of the shard on, compressed, or grams, n-grams of the shard with their counts in trusted texts of fold 0 and 1.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, first, size, seen = TaskContext.get().partitionId() << 32, 0, 0, _Grams(order)

        def block(rows=None, grams=(None, None, None)) -> pa.RecordBatch:
            columns = [pa.array([shard]), pa.array([first]), pa.array([rows], pa.binary()), pa.array([grams[0]], pa.list_(pa.string())), *(pa.array([x], pa.list_(pa.int64())) for x in grams[1:])]
            return pa.RecordBatch.from_arrays(columns, ["shard", "first", "rows", "grams", "even", "odd"])

        for whole in batches:
            texts = whole.column("text").to_pylist()
            fold = whole.column("_fold").fill_null(-1).to_numpy()
            for begin, end in _chunks(texts, chunk_chars):
                n = sum(len(t or "") for t in texts[begin:end])
                if size and size + n > shard_chars:
                    for g in seen.rows():
                        yield block(grams=g)
                    shard, first, size, seen = shard + 1, 0, 0, _Grams(order)
                seen.add(texts[begin:end], fold[begin:end])
                yield block(rows=_packed(whole.slice(begin, end - begin)))
                first, size = first + end - begin, size + n
        for g in seen.rows():
            yield block(grams=g)
        del seen
        give_back()

    return bucketed(docs.mapInArrow(run, "shard long, first long, rows binary, grams array<string>, even array<long>, odd array<long>"), "shard", "shards")


def gram_counts(cut: DataFrame) -> DataFrame:
    """(gram, all, even, odd) of every n-gram of the shards: its counts in trusted texts, 0 where only other texts have it."""
    each = cut.where("grams is not null").select(F.inline(F.arrays_zip(F.col("grams").alias("gram"), "even", "odd")))
    return written(each.groupBy("gram").agg(F.sum(F.col("even") + F.col("odd")).alias("all"), F.sum("even").alias("even"), F.sum("odd").alias("odd")), "grams")


def _discounts(n: list[int]) -> list[float]:
    """What is taken off a count of 1, 2, and 3 or more, from the numbers of n-grams with counts 1 to 4."""
    n = [max(1, x) for x in n]
    y = n[0] / (n[0] + 2 * n[1])
    return [min(k * 1.0, max(0.05, k - (k + 1) * y * n[k] / n[k - 1])) for k in (1, 2, 3)]


def probabilities(counts: DataFrame, order: int = ORDER) -> DataFrame:
    """(gram, all, even, odd): of every n-gram of counts, the probability of its last character after the others, in each model.

    From the unigrams up, every order is joined with the order below it by the n-gram without its first character. Lower
    orders count the different characters before an n-gram. A context that a model has not seen leaves all to the order below.
    """
    levels = {order: counts}
    for k in range(order - 1, 0, -1):
        longer = levels[k + 1]
        levels[k] = written(longer.groupBy(F.right("gram", F.lit(k)).alias("gram")).agg(*[F.sum((F.col(m) > 0).cast("long")).alias(m) for m in MODELS]), "grams")
    below: DataFrame | None = None
    for k in range(1, order + 1):
        level = levels[k]
        met = level.agg(*[F.count_if(F.col(m) == c).alias(f"{m}{c}") for m in MODELS for c in (1, 2, 3, 4)]).first()
        # a context has at most as many rows as there are characters
        context = Window.partitionBy(F.left("gram", F.lit(k - 1))) if k > 1 else None
        if below is not None:
            level = level.withColumn("_s", F.right("gram", F.lit(k - 1))).join(below.select(F.col("gram").alias("_s"), *[F.col(m).alias(f"_{m}") for m in MODELS]), "_s")
        taken = {m: _taken(F.col(m), _discounts([met[f"{m}{c}"] for c in (1, 2, 3, 4)])) for m in MODELS}
        if context is None:
            sums = level.agg(*[F.sum(m).alias(m) for m in MODELS], *[F.sum(taken[m]).alias(f"{m}_off") for m in MODELS]).first()
        out = []
        for m in MODELS:
            total, off = (F.sum(m).over(context), F.sum(taken[m]).over(context)) if context is not None else (F.lit(sums[m] or 0), F.lit(sums[f"{m}_off"] or 0.0))
            lower = F.col(f"_{m}") if below is not None else F.lit(1.0 / CODE_POINTS)
            out.append(F.when(total > 0, (F.col(m) - taken[m] + off * lower) / total).otherwise(lower).alias(m))
        below = written(level.select("gram", *out), "probabilities")
    return below


def _taken(c: Column, discounts: list[float]) -> Column:
    return F.when(c == 1, F.lit(discounts[0])).when(c == 2, F.lit(discounts[1])).when(c > 2, F.lit(discounts[2])).otherwise(F.lit(0.0))


def perplexities(cut: DataFrame, known: DataFrame, order: int = ORDER) -> DataFrame:
    """(shard, place, lang, fold, n_symbols, perplexity, crossed) of every document of the shards: crossed is the perplexity by the other half's model, for trusted documents."""
    logs = known.select("gram", *[F.log(m).cast("float").alias(m) for m in MODELS])
    named = cut.where("grams is not null").select(F.col("shard").alias("of"), F.explode("grams").alias("gram")).join(logs, "gram")
    rows = cut.where("rows is not null").select("shard", "first", "rows")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        # the grams' keys are computed as those of the documents are, each gram behind nothing
        blocks = [np.array(right.column("gram").slice(k, 1 << 16).to_pylist(), f"<U{order}") for k in range(0, right.num_rows, 1 << 16)]
        grams = np.concatenate([np.zeros(0, f"<U{order}"), *blocks])
        points = grams.view(np.uint32).reshape(-1, order)
        key = np.zeros(len(points), np.uint64)
        for k in range(order):
            key += points[:, k] * _TIMES[k]
        index = pd.Index(key.view(np.int64))
        logp = [right.column(m).to_numpy() for m in MODELS]
        out = []
        for shard, first, data in zip(*(left.column(c).to_pylist() for c in ("shard", "first", "rows"))):
            docs = _unpacked(data)
            _, n, keys = _characters(docs.column("text").to_pylist(), order)
            fold = docs.column("_fold").fill_null(-1).to_numpy()
            code, distinct = pd.factorize(keys)
            at = index.get_indexer(distinct)
            if (at < 0).any():
                raise ValueError("an n-gram of the shard has no probability")
            of = np.repeat(np.arange(len(n)), n)
            total = [np.bincount(of, weights=p[at][code], minlength=len(n)) for p in logp]
            mean = [np.exp(-t / np.maximum(n, 1)) for t in total]
            crossed = np.where(fold == 0, mean[2], mean[1])
            out.append(pa.table({"shard": np.full(len(n), shard), "place": first + np.arange(len(n)), "lang": docs.column("lang"), "fold": pa.array(fold, mask=fold < 0, type=pa.int32()), "n_symbols": n, "perplexity": mean[0], "crossed": pa.array(crossed, mask=fold < 0)}))
        del blocks, grams, points, key, index, logp
        give_back()
        return pa.concat_tables(out) if out else SCORED.empty_table()

    text = "shard long, place long, lang string, fold int, n_symbols long, perplexity double, crossed double"
    return written(rows.groupBy("shard").cogroup(named.groupBy("of")).applyInArrow(run, text), "perplexity")


SCORED = pa.schema([("shard", pa.int64()), ("place", pa.int64()), ("lang", pa.string()), ("fold", pa.int32()), ("n_symbols", pa.int64()), ("perplexity", pa.float64()), ("crossed", pa.float64())])


def _judged(docs: DataFrame, trusted: DataFrame, quantile: float) -> tuple[DataFrame, DataFrame]:
    """(shards of docs; shard, place, n_symbols, perplexity, threshold, keep of every row of docs)."""
    ids = trusted.select("doc_id").where(F.col("doc_id").isNotNull()).distinct().withColumn("_trusted", F.lit(True))
    few = ids.limit(MAX_BROADCAST_LABELS + 1).count() <= MAX_BROADCAST_LABELS
    fold = F.when(F.col("_trusted"), F.pmod(F.xxhash64("text"), F.lit(2)).cast("int"))
    cut = shards(docs.join(F.broadcast(ids) if few else ids, "doc_id", "left").withColumn("_fold", fold).drop("_trusted"))
    scored = perplexities(cut, probabilities(gram_counts(cut)))
    at = F.percentile_approx("crossed", quantile, 10000)
    overall = scored.where("fold is not null").agg(at).first()[0]
    by_lang = scored.where("fold is not null").groupBy(F.col("lang").alias("_l")).agg(at.alias("threshold"))
    few = by_lang.limit(MAX_LANGUAGES + 1).count() <= MAX_LANGUAGES
    named = scored.join(F.broadcast(by_lang) if few else by_lang, F.col("lang").eqNullSafe(F.col("_l")), "left")
    threshold = F.coalesce("threshold", F.lit(float("inf") if overall is None else overall))
    return cut, named.select("shard", "place", "n_symbols", "perplexity", threshold.alias("threshold"), (F.col("perplexity") <= threshold).alias("keep"))


def _with_rows(cut: DataFrame, judged: DataFrame, schema: str, make) -> DataFrame:
    """make(documents of a block, their judgements in the same order) for every block of every shard."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        right = right.sort_by("place")
        out = [make(docs := _unpacked(data), right.slice(first, docs.num_rows)) for first, data in zip(left.column("first").to_pylist(), left.column("rows").to_pylist())]
        give_back()
        return pa.concat_tables(out)

    return cut.where("rows is not null").select("shard", "first", "rows").groupBy("shard").cogroup(judged.groupBy("shard")).applyInArrow(run, schema)


def classify(docs: DataFrame, trusted: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """One row per row of docs: doc_id, lang, n_symbols, perplexity, threshold, keep.

    docs has doc_id, text, lang; other columns are ignored; trusted has the doc_ids of trusted documents. Null texts
    are empty; empty texts have perplexity 1 and are kept; a null language is one of its own; languages without trusted
    documents use the quantile of all; without any trusted documents all are kept. Repeated rows are all
    returned. No rows give no rows. Trusted ids are broadcast up to MAX_BROADCAST_LABELS, else joined by shuffle. Either half of the
    trusted texts (copies in one half) is judged by the model of the other for the thresholds, as new text would be.
    """
    cut, judged = _judged(docs.select("doc_id", "text", "lang"), trusted, quantile)
    names = ["n_symbols", "perplexity", "threshold", "keep"]
    kind = docs.schema["doc_id"].dataType.simpleString()
    make = lambda rows, told: pa.table([rows.column("doc_id"), rows.column("lang"), *(told.column(c) for c in names)], ["doc_id", "lang", *names])
    return _with_rows(cut, judged.select("shard", "place", *names), f"doc_id {kind}, lang string, n_symbols long, perplexity double, threshold double, keep boolean", make)


def accepted(docs: DataFrame, trusted: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """The rows of docs, all columns, that classify keeps."""
    narrow = slim(docs, ["doc_id", "text", "lang"])
    cut, judged = _judged(narrow, trusted, quantile)
    names = narrow.columns
    make = lambda rows, told: rows.filter(told.column("keep")).select(names)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in narrow.schema)
    return widened(_with_rows(cut, judged.select("shard", "place", "keep"), schema, make), docs)


def trusted_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet").where("quality = 1").select("doc_id")


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = classify(documents(spark, sf_dir).select("doc_id", "text", "lang"), trusted_ids(spark, sf_dir))
    return found.select("doc_id", "lang", "n_symbols", "perplexity", "threshold", "keep")
