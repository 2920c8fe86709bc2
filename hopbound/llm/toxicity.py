"""Toxic spans by a linear-chain conditional random field, and document scores from its marginals.

Two states per word, one chain per sentence, of whatever length. The
emission of a word is a sum of weights of its features: the word itself and its first letters. Only
document labels exist, so words are labelled first: a word of a toxic document counts as toxic if one of its
features is found in toxic documents far more often than chance allows. The field is then fitted
to these labels, and forward-backward marginals over whole texts give spans and document scores.
Training uses all sentences of a bounded sample of labelled rows (TOXIC_ROWS and CLEAN_ROWS, of TRAIN_CHARS characters together), scoring all text.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents

TOXIC_ROWS, CLEAN_ROWS = 2000, 4000
TRAIN_CHARS = 64 << 20  # characters of the rows that are fitted to, whole texts only
BLOCK = 128  # words of a chain that one pass of the recursion covers; states are carried from block to block
PREFIXES = (3, 4, 5, 6, 7)
TOKEN = re.compile(r"\w+|[.!?\n]+")
CACHED_WORDS = 300_000
MIN_SHARE = 0.5  # least share of toxic documents among those with a feature
CHANCE = 1e-8  # how likely a feature's count in toxic documents may be by chance


def features(word: str) -> list[str]:
    return [word, *(f"{n}:{word[:n]}" for n in PREFIXES if len(word) > n)]


def tokens(text: str) -> list[str]:
    """Words as they stand, and runs of sentence ends, in order. Words are lower-cased one by one later, which keeps offsets true."""
    return TOKEN.findall(text)


def _is_end(token: str) -> bool:
    return token[0] in ".!?\n"


def chains(rows: list[list[str]], emit) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(emissions, chain starts, chain lengths, words per row) of token rows."""
    e: list[float] = []
    cuts: list[int] = [0]
    per_row = np.zeros(len(rows), np.int64)
    for k, row in enumerate(rows):
        before = len(e)
        for t in row:
            x = emit(t)
            if x is None:
                if cuts[-1] != len(e):
                    cuts.append(len(e))
            else:
                e.append(x)
        per_row[k] = len(e) - before
        if cuts[-1] != len(e):
            cuts.append(len(e))
    at = np.array(cuts, np.int64)
    return np.array(e), at[:-1], np.diff(at), per_row


def _carried(one: np.ndarray, t: np.ndarray, begin: np.ndarray, size: np.ndarray, place: np.ndarray, n_blocks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every block, in order within its chain: (probability of state 1 of the word before it, backward message from behind it, as the share of state 1).

    The words of a block together are a 2x2 matrix; the matrices of all blocks are multiplied out at once, then states go from block to block.
    """
    before, behind = np.full(len(begin), 0.5), np.full(len(begin), 0.5)
    long = np.repeat(n_blocks, n_blocks) > 1
    if not long.any():
        return before, behind
    at = np.flatnonzero(long)
    m = np.broadcast_to(np.eye(2), (len(at), 2, 2)).copy()
    for k in range(int(size[at].max())):
        on = np.flatnonzero(size[at] > k)
        x = m[on] @ t if k else m[on]
        x[:, :, 1] *= one[begin[at[on]] + k][:, None]
        m[on] = x / x.sum(axis=(1, 2), keepdims=True)
    row = np.full(len(begin), -1)
    row[at] = np.arange(len(at))
    last = np.cumsum(n_blocks) - 1  # of each chain
    for j in range(1, int(n_blocks.max())):
        b = (last - n_blocks + 1 + j)[n_blocks > j]  # blocks that are the j-th of their chain
        q = before[b - 1]
        v = np.stack([1 - q, q], axis=1)[:, None, :] @ t if j > 1 else np.ones((len(b), 1, 2))
        v = (v @ m[row[b - 1]])[:, 0]
        before[b] = v[:, 1] / v.sum(axis=1)
        b = (last - j)[n_blocks > j]  # the same from the end
        q = behind[b + 1]
        v = (t @ (m[row[b + 1]] @ np.stack([1 - q, q], axis=1)[:, :, None]))[:, :, 0]
        behind[b] = v[:, 1] / v.sum(axis=1)
    return before, behind


def marginals(emission: np.ndarray, starts: np.ndarray, lengths: np.ndarray, log_t: np.ndarray, weight: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, float]:
    """(probability of state 1 per word, expected transitions 2x2, log partition) of all chains at once; the sums count each chain `weight` times."""
    t = np.exp(log_t)
    one = np.exp(np.clip(emission, -30, 30))
    n_blocks = -(-lengths // BLOCK)
    chain = np.repeat(np.arange(len(lengths)), n_blocks)
    place = np.arange(len(chain)) - np.repeat(np.cumsum(n_blocks) - n_blocks, n_blocks)
    begin = starts[chain] + place * BLOCK
    size = np.minimum(BLOCK, lengths[chain] - place * BLOCK)
    before, behind = _carried(one, t, begin, size, place, n_blocks)
    w = np.ones(len(chain)) if weight is None else weight[chain].astype(float)
    order = np.argsort(-size, kind="stable")
    begin, size, w, before, behind, first = begin[order], size[order], w[order], before[order], behind[order], place[order] == 0
    a1 = np.zeros(len(emission))
    longest = int(size[0]) if len(size) else 0
    active = [int(np.searchsorted(-size, -k, side="left")) for k in range(longest)]  # blocks longer than k
    logz = 0.0
    prev = before
    for k in range(longest):
        n = active[k]
        i = begin[:n] + k
        q = prev[:n]
        p0 = (1 - q) * t[0, 0] + q * t[1, 0]
        p1 = (1 - q) * t[0, 1] + q * t[1, 1]
        if k == 0:
            p0, p1 = np.where(first, 1.0, p0), np.where(first, 1.0, p1)
        p1 = p1 * one[i]
        z = p0 + p1
        logz += float((w[:n] * np.log(z)).sum())
        prev = p1 / z
        a1[i] = prev
    out, pairs = np.zeros(len(emission)), np.zeros((2, 2))
    b0, b1 = 1 - behind, behind.copy()
    for k in range(longest - 1, -1, -1):
        n = active[k]
        i = begin[:n] + k
        q = a1[i]
        x1 = q * b1[:n]
        out[i] = x1 / (x1 + (1 - q) * b0[:n])
        inner = np.ones(n, bool) if k else ~first
        f = np.where(inner, a1[i - 1], 0.0)
        e1 = one[i] * b1[:n]
        j = [[(1 - f) * t[0, 0] * b0[:n], (1 - f) * t[0, 1] * e1], [f * t[1, 0] * b0[:n], f * t[1, 1] * e1]]
        z = j[0][0] + j[0][1] + j[1][0] + j[1][1]
        for r in (0, 1):
            for c in (0, 1):
                pairs[r, c] += float((w[:n] * j[r][c] / z)[inner].sum())
        n0, n1 = t[0, 0] * b0[:n] + t[0, 1] * e1, t[1, 0] * b0[:n] + t[1, 1] * e1
        b0[:n], b1[:n] = n0 / (n0 + n1), n1 / (n0 + n1)
    return out, pairs, logz


@dataclass
class ToxicityModel:
    bias: float = -6.0
    weights: dict[str, float] = field(default_factory=dict)
    log_t: np.ndarray = field(default_factory=lambda: np.zeros((2, 2)))
    slope: float = 1.0
    shift: float = 0.0
    known: dict[str, float | None] = field(default_factory=dict)

    def emission(self, token: str) -> float | None:
        """None for a sentence end."""
        try:
            return self.known[token]
        except KeyError:
            if len(self.known) > CACHED_WORDS:
                self.known.clear()
            w = self.weights
            x = None if _is_end(token) else self.bias + sum(w[f] for f in features(token.lower()) if f in w)
            self.known[token] = x
            return x

    def evidence(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(evidence per text, word probabilities, words per text); evidence is -log of the chance that no word is toxic."""
        e, starts, lengths, per_row = chains([tokens(t) for t in texts], self.emission)
        p, _, _ = marginals(e, starts, lengths, self.log_t)
        ends = np.cumsum(per_row)
        total = np.concatenate(([0.0], np.cumsum(-np.log1p(-np.minimum(p, 1 - 1e-9)))))
        return np.maximum(total[ends] - total[ends - per_row], 0), p, per_row

    def score(self, evidence: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * np.log(evidence + 1e-4) + self.shift, -30, 30)))


class _Numbered:
    """Texts as arrays of word numbers (-1 at sentence ends), and the numbered features of every word."""

    def __init__(self, texts: list[str]):
        number: dict[str, int] = {}
        self.rows = [np.fromiter((-1 if _is_end(w) else number.setdefault(w.lower(), len(number)) for w in tokens(t)), np.int32) for t in texts]
        names: dict[str, int] = {}
        self.of_word = np.full((len(number), 1 + len(PREFIXES)), -1, np.int32)
        for w, k in number.items():
            for j, f in enumerate(features(w)):
                self.of_word[k, j] = names.setdefault(f, len(names))
        self.names = list(names)

    def document_counts(self, which: np.ndarray) -> np.ndarray:
        """Of each feature, how many of the texts flagged in `which` have it."""
        n = np.zeros(len(self.names) + 1, np.int32)
        for row, use in zip(self.rows, which):
            if use:
                n[np.unique(self.of_word[np.unique(row[row >= 0])])] += 1
        return n[:-1]  # the last is of no feature


def _signal(texts: _Numbered, toxic: np.ndarray) -> np.ndarray:
    """Flags of features in toxic texts far more often than the share of toxic texts makes likely (Chernoff bound)."""
    n, m = texts.document_counts(toxic), texts.document_counts(np.ones(len(toxic), bool))
    share = toxic.mean()
    x = n / np.maximum(m, 1)
    with np.errstate(divide="ignore", invalid="ignore"):
        kl = x * np.log(x / share) + np.where(x < 1, (1 - x) * np.log((1 - x) / (1 - share)), 0.0)
    return (x > max(MIN_SHARE, share)) & (n >= 5) & (m * np.nan_to_num(kl) > -np.log(CHANCE))


def _gradient(w: np.ndarray, t: np.ndarray, at: np.ndarray, feat: np.ndarray, seen: np.ndarray, true_t: np.ndarray, starts: np.ndarray, lengths: np.ndarray, times: np.ndarray, per_word: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of the log likelihood, less 0.05 times the squares of the feature weights (not the bias) and of the transitions; feat[k] is a feature of word at[k]."""
    p, pairs, _ = marginals(np.bincount(at, weights=w[feat], minlength=len(per_word)), starts, lengths, t, times)
    return seen - np.bincount(feat, weights=(p * per_word)[at], minlength=len(w)) - 0.1 * w * (np.arange(len(w)) > 0), true_t - pairs - 0.1 * t


def fit(texts: list[str], toxic: list[int], prior: float, rounds: int = 60) -> ToxicityModel:
    """The field fitted to the labelled texts, and its document calibration; prior is the share of toxic documents at large."""
    model = ToxicityModel()
    y = np.array(toxic, bool)
    if y.all() or not y.any():
        model.shift, model.slope = float(np.log(max(prior, 1e-6) / max(1 - prior, 1e-6))) if len(y) else -4.0, 0.0
        return model
    data = _Numbered(texts)
    signal = _signal(data, y)
    if not signal.any():
        model.shift, model.slope = float(np.log(max(prior, 1e-6) / max(1 - prior, 1e-6))), 0.0
        return model
    names = [data.names[f] for f in np.flatnonzero(signal)]
    column = np.zeros(len(signal) + 1, np.int32)  # 0: no signal
    column[:-1][signal] = np.arange(1, len(names) + 1)
    of_word = column[data.of_word]  # signal features of each word, 0 where none
    told = of_word.any(axis=1)
    # sentences with a signal word one by one; the others, whose words all have the bias alone, by length
    use: list[tuple[np.ndarray, bool]] = []
    plain: dict[int, int] = {}
    none = np.zeros(0, np.int64)
    for row, v in zip(data.rows, y):
        for s in np.split(row, np.flatnonzero(row < 0)):
            s = s[s >= 0]
            if len(s) and told[s].any():
                use.append((s, v))
            elif len(s):
                plain[len(s)] = plain.get(len(s), 0) + 1
    lengths = np.array([*(len(s) for s, _ in use), *plain], np.int64)
    times = np.array([*(1 for _ in use), *plain.values()], np.int64)
    starts = np.cumsum(lengths) - lengths
    words = np.concatenate([none, *(s for s, _ in use), np.full(sum(plain), -1)])
    n = len(words)
    per_word = np.repeat(times, lengths)
    label = np.zeros(n)
    own = sum(len(s) for s, _ in use)
    label[:own] = told[words[:own]] & np.repeat([v for _, v in use], lengths[: len(use)]) if use else 0
    found = np.zeros((n, of_word.shape[1]), np.int32)
    found[:own] = of_word[words[:own]]
    at, where = np.nonzero(found)
    at, feat = np.r_[np.arange(n), at], np.r_[np.zeros(n, np.int64), found[at, where]]  # feature 0: bias
    w, t = np.zeros(len(names) + 1), np.zeros((2, 2))
    w[0] = -3.0
    seen = np.bincount(feat, weights=label[at], minlength=len(w))
    inner = np.ones(n, bool)
    inner[starts] = False
    true_t = np.zeros((2, 2))
    np.add.at(true_t, (label[:-1][inner[1:]].astype(int), label[1:][inner[1:]].astype(int)), per_word[1:][inner[1:]])
    mw, vw, mt, vt = np.zeros_like(w), np.zeros_like(w), np.zeros_like(t), np.zeros_like(t)
    for k in range(1, rounds + 1):
        gw, gt = _gradient(w, t, at, feat, seen, true_t, starts, lengths, times, per_word)
        mw, vw = 0.9 * mw + 0.1 * gw, 0.99 * vw + 0.01 * gw**2
        mt, vt = 0.9 * mt + 0.1 * gt, 0.99 * vt + 0.01 * gt**2
        w += 0.3 * (mw / (1 - 0.9**k)) / (np.sqrt(vw / (1 - 0.99**k)) + 1e-8)
        t += 0.1 * (mt / (1 - 0.9**k)) / (np.sqrt(vt / (1 - 0.99**k)) + 1e-8)
    model.bias, model.log_t = float(w[0]), t
    model.weights = {f: float(w[k]) for k, f in enumerate(names, 1)}
    ev = np.concatenate([model.evidence(texts[k : k + 200])[0] for k in range(0, len(texts), 200)])
    model.known.clear()
    x = np.log(ev + 1e-4)
    share = y.mean()
    weight = np.where(y == 1, prior / share, (1 - prior) / (1 - share))
    a, b = 1.0, 0.0
    for _ in range(200):  # weighted logistic regression by Newton steps, slightly held to a slope of 1
        q = 1 / (1 + np.exp(-np.clip(a * x + b, -30, 30)))
        r, h = weight * (y - q), weight * q * (1 - q) + 1e-9
        g = np.array([(r * x).sum() - 0.5 * (a - 1), r.sum() - 0.01 * b])
        m = np.array([[(h * x * x).sum() + 0.5, (h * x).sum()], [(h * x).sum(), h.sum() + 0.01]])
        d = np.linalg.solve(m, g)
        a, b = a + np.clip(d[0], -1, 1), b + np.clip(d[1], -1, 1)
    model.slope, model.shift = float(max(a, 0.1)), float(b)
    return model


def train(docs: DataFrame, labels: DataFrame, toxic_rows: int = TOXIC_ROWS, clean_rows: int = CLEAN_ROWS, chars: int = TRAIN_CHARS) -> ToxicityModel:
    """Fit on at most toxic_rows + clean_rows labelled documents, taken by hash, as far as their texts have `chars` characters together.

    labels has doc_id and toxic, ties resolved to toxic. Of several rows of a doc_id the text with the least hash counts.
    """
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    prior = known.agg(F.avg("toxic")).first()[0]
    if prior is None:
        return ToxicityModel(slope=0.0, shift=-4.0)
    pick = [known.where(F.col("toxic") == v).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n) for v, n in ((1, toxic_rows), (0, clean_rows))]
    chosen = pick[0].unionByName(pick[1])
    text = F.coalesce("text", F.lit(""))
    found = docs.select("doc_id", text.alias("text")).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min_by("text", F.struct(F.xxhash64("text"), "text")).alias("text"))
    room = Window.orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, 0)  # toxic_rows + clean_rows rows at most
    found = found.withColumn("_chars", F.sum(F.char_length("text")).over(room)).where(F.col("_chars") <= chars)
    rows = found.select("doc_id", "text", "toxic").collect()
    rows.sort(key=lambda r: r["doc_id"])
    return fit([r["text"] for r in rows], [r["toxic"] for r in rows], float(prior))


def score(docs: DataFrame, model: ToxicityModel, spans_from: float = 0.5) -> DataFrame:
    """(doc_id, score, spans): spans (start, end in code points, probability) of words likely toxic.

    docs has doc_id and text; other columns are ignored. Null texts are empty; empty texts get the score of no
    evidence; repeated rows are all scored; no rows give no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = sent.value
        for b in batches:
            for at in range(0, len(b), 512):
                part = b.iloc[at : at + 512]
                texts = [t or "" for t in part["text"]]
                ev, p, n = m.evidence(texts)
                ends, found = np.cumsum(n), []
                hot = p >= spans_from
                for k, text in enumerate(texts):
                    own = slice(ends[k] - n[k], ends[k])
                    if hot[own].any():
                        at_word = [x.span() for x in TOKEN.finditer(text) if not _is_end(x.group())]
                        q = p[own]
                        found.append([{"start": s, "end": e, "probability": float(v)} for (s, e), v in zip(at_word, q) if v >= spans_from])
                    else:
                        found.append([])
                yield pd.DataFrame({"doc_id": part["doc_id"].to_numpy(), "score": m.score(ev), "spans": found})

    return docs.select("doc_id", "text").mapInPandas(run, f"doc_id {kind}, score double, spans array<struct<start:int,end:int,probability:double>>")


def held_out():
    """Rows whose labels are never used for training."""
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) == 1


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic").where(~held_out())
    scored = score(docs, train(docs, labels))
    return scored.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"), F.transform("spans", lambda s: F.concat_ws(":", s["start"], s["end"])).alias("spans")).withColumn("spans", F.array_join("spans", ","))
