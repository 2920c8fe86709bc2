"""Best-fit packing of token sequences through the configuration linear program.

Documents are tokenised and cut into pieces of at most `capacity` tokens. Only the histogram of piece
lengths (at most `capacity` numbers, whatever the corpus) reaches the driver. There the configuration
program, least number of sequences whose contents cover the histogram, is solved by multiplicative weights: lengths
that are covered less than others keep more weight, and a knapsack dynamic program prices the best content of a
sequence. The fractional solution is rounded down to whole sequences, solved again for what is left,
and best fit places the rounding's remainder. Pieces find their places by their rank among equal lengths,
which is counted per task and summed over tasks, so no length is gathered anywhere.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, give_back, written

CAPACITY = 2048
END = 0
ROUNDS, PASSES = 80, 2  # rounds of pricing; solutions that are rounded one after the other
CACHE_BYTES = 48 << 20  # words and their ids that a Python worker keeps
SEPARATOR = "\u2764"
SPECIAL = "<|"


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordTokenizer:
    """Ids of texts, word by word through a cache of at most CACHE_BYTES.

    The tokenizer lower-cases, and never joins characters across white space, nor a letter with the mark after it; so
    a text's ids are those of its lower-case words, a full stop or comma after them apart. New words are encoded many at a time
    with SEPARATOR between them, whose id no other word has. The cache is three arrays, not a dictionary of objects.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.separator = self._direct([SEPARATOR])[0]
        self._forget()

    def _forget(self) -> None:
        self.words = pa.array([""], pa.string())
        self.ids = np.zeros(0, np.uint32)
        self.first = np.zeros(2, np.int64)  # where the ids of each word begin, and their end

    def _direct(self, words: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]

    def _learn(self, new: list[str]) -> None:
        odd = [w for w in new if SPECIAL in w or SEPARATOR in w or len(self.separator) != 1]
        plain = [w for w in new if not (SPECIAL in w or SEPARATOR in w)] if len(self.separator) == 1 else []
        found = self._direct(odd) if odd else []
        sizes = [np.fromiter(map(len, found), np.int64, len(found))]
        for k in range(0, len(plain), 65536):
            groups = [plain[i : min(i + 256, len(plain), k + 65536)] for i in range(k, min(k + 65536, len(plain)), 256)]
            for ids in self._direct([f" {SEPARATOR} ".join(g) for g in groups]):
                cut = np.flatnonzero(ids == self.separator[0])
                sizes.append(np.diff(np.r_[-1, cut, len(ids)]) - 1)
                found.append(np.delete(ids, cut))
        self.words = pa.concat_arrays([self.words, pa.array([*odd, *plain], pa.string())])
        self.ids = np.concatenate([self.ids, *found])
        self.first = np.r_[self.first, self.first[-1] + np.cumsum(np.concatenate(sizes))]

    def _places(self, words: pa.Array) -> np.ndarray:
        """Place of every word in the cache; unknown ones are learned."""
        at = pc.index_in(words, value_set=self.words)
        if at.null_count:
            if self.words.nbytes + self.ids.nbytes + self.first.nbytes > CACHE_BYTES:
                self._forget()
                return self._places(words)
            self._learn(words.filter(at.is_null()).to_pylist())
            at = pc.index_in(words, value_set=self.words)
        return at.to_numpy().astype(np.int64)

    def encode(self, texts: pa.Array, end: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, each with `end` after it; where each text ends). Null texts are empty."""
        texts = pc.fill_null(texts, "")
        plain = pc.invert(pc.match_substring_regex(texts, f"[^\\x00-\\x{{FF}}]|{re.escape(SPECIAL)}"))  # in Latin-1 lower case goes letter by letter
        easy = pc.replace_substring_regex(pc.utf8_lower(texts), r"(\pL)([.,])([ \n])", r"\1 \2\3")
        lists = pc.ascii_split_whitespace(pc.if_else(plain, easy, texts))
        coded = lists.flatten().dictionary_encode()
        place = self._places(coded.dictionary.cast(pa.string()))
        # the ids of the cache, and behind them the one of the end
        known = np.append(self.ids, np.uint32(end))
        first, size = np.append(self.first[place], len(known) - 1), np.append(self.first[place + 1] - self.first[place], 1)
        stops = lists.offsets.to_numpy()[1:] - lists.offsets.to_numpy()[0]
        at = np.insert(coded.indices.to_numpy().astype(np.int64), stops, len(place))
        n = size[at]
        ends = np.cumsum(n)
        where = np.arange(ends[-1] if len(ends) else 0) + np.repeat(first[at] - ends + n, n)
        return known[where], ends[stops + np.arange(len(stops))]


@cache
def _tokenizer(path: str) -> WordTokenizer:
    return WordTokenizer(path)


def _ranks(length: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """Each row's place among the rows of its length so far; seen counts on."""
    order = np.argsort(length, kind="stable")
    ordered = length[order]
    starts = np.flatnonzero(np.r_[True, ordered[1:] != ordered[:-1]]) if len(ordered) else np.zeros(0, np.int64)
    n = np.diff(np.r_[starts, len(ordered)])
    out = np.empty(len(length), np.int64)
    out[order] = np.arange(len(ordered)) - np.repeat(starts, n) + np.repeat(seen[ordered[starts]], n)
    seen[ordered[starts]] += n
    return out


def pieces(docs: DataFrame, capacity: int = CAPACITY, tokenizer_path: str | None = None) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids (binary, little-endian unsigned 32-bit), ids_crc32, shard, rank.

    A document is its ids and then END; null texts are empty. shard is the task that made the row and rank
    its place among the shard's pieces of that length, so (shard, length, rank) names the row once it is written.
    """
    path = tokenizer_path or default_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, seen = TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        for whole in batches:
            for k in range(0, whole.num_rows, 1000):
                b = whole.slice(k, 1000)
                ids, ends = _tokenizer(path).encode(b.column("text"), END)
                begins = np.r_[0, ends[:-1]]
                n = -(-(ends - begins) // capacity)
                doc = np.repeat(np.arange(len(ends)), n)
                piece = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
                start = piece * capacity
                offsets = np.r_[begins[doc] + start, len(ids)]
                length = np.diff(offsets)
                raw = memoryview(ids).cast("B")
                cut = (offsets * 4).tolist()
                crc = np.fromiter((zlib.crc32(raw[x:y]) for x, y in zip(cut, cut[1:])), np.int64, len(doc))
                data = pa.Array.from_buffers(pa.binary(), len(doc), [None, pa.py_buffer((offsets * 4).astype(np.int32)), pa.py_buffer(ids)])
                columns = [b.column("doc_id").take(pa.array(doc)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), data, pa.array(crc), pa.array(np.full(len(doc), shard, np.int32)), pa.array(_ranks(length, seen))]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "piece", "start", "length", "ids", "ids_crc32", "shard", "rank"])
        give_back()

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, piece int, start long, length long, ids binary, ids_crc32 long, shard int, rank long")


def knapsack(lengths: np.ndarray, prices: np.ndarray, capacity: int) -> tuple[np.ndarray, list[int]]:
    """By dynamic programming, for every room up to capacity: the most that lengths (ascending, repeats allowed) in it are worth, and the last of them (0: none)."""
    worth, last = np.zeros(capacity + 1), [0] * (capacity + 1)
    fits = np.searchsorted(lengths, np.arange(capacity + 1), side="right")
    for room in range(1, capacity + 1):
        best, m = worth[room - 1], fits[room]
        if m:
            v = worth[room - lengths[:m]] + prices[:m]
            k = int(v.argmax())
            if v[k] > best:
                best, last[room] = v[k], int(lengths[k])
        worth[room] = best
    return worth, last


def content(last: list[int], room: int) -> list[int]:
    """The lengths that knapsack chose for a room."""
    out = []
    while room > 0:
        if last[room]:
            out.append(last[room])
        room -= last[room] or 1
    return out


def cover(counts: np.ndarray, rounds: int = ROUNDS, rate: float = 1.0, least: float = 0.01) -> dict[tuple[int, ...], float]:
    """A fractional solution of the configuration program: contents of sequences, and how often each is used.

    In every round a knapsack over the prices gives, for each length still uncovered, the content worth most that has it; contents
    are used until one of their lengths is covered, and the weights of the lengths used fall by the factor exp(-rate * share covered). A price is the share
    of a sequence that the length fills, which is the dual value where full sequences are possible, plus less than a token's worth
    of its weight, which tells full sequences apart: long and lagging lengths come first. Ends when less than the share `least` of all tokens is uncovered.
    """
    top = len(counts) - 1
    rest = counts.astype(float).tolist()
    rest[0] = 0.0
    tokens = sum(n * length for length, n in enumerate(rest))
    share, weight = np.arange(top + 1) / top, np.ones(top + 1)
    used: dict[tuple[int, ...], float] = {}
    for _ in range(rounds):
        there = np.array([length for length in range(1, top + 1) if rest[length] > 1e-9], np.int64)
        if not len(there) or sum(rest[length] * length for length in there.tolist()) < least * tokens:
            break
        _, last = knapsack(there, share[there] + 0.9 / top * share[there] ** 2 * weight[there], top)
        before, moved = np.array(rest), False
        for full in (True, False):  # contents with room left only when no full one is to be had
            for length in there[::-1].tolist():
                if rest[length] <= 1e-9:
                    continue
                config = (length, *content(last, top - length))
                if full and sum(config) < top:
                    continue
                each: dict[int, int] = {}
                for x in config:
                    each[x] = each.get(x, 0) + 1
                step = min(rest[x] / n for x, n in each.items())
                if step > 1e-9:
                    for x, n in each.items():
                        rest[x] -= n * step
                    used[config] = used.get(config, 0.0) + step
                    moved = True
            if moved:
                break
        if not moved:
            break
        weight *= np.exp(-rate * (before - np.array(rest)) / np.maximum(counts, 1))
    return used


def rounded(counts: np.ndarray, passes: int = PASSES) -> tuple[list[tuple[list[int], int]], np.ndarray]:
    """(content, times) of the whole multiplicities of the fractional solution, again for what they leave; and the counts left in the end."""
    left = counts.astype(np.int64).copy()
    left[0] = 0
    out: list[tuple[list[int], int]] = []
    for _ in range(passes):
        whole = [(list(config), int(times + 1e-6)) for config, times in cover(left).items() if times + 1e-6 >= 1]
        for config, times in whole:
            np.subtract.at(left, config, times)
        out += whole
        if not whole:
            break
    return out, left


def plan(counts: np.ndarray) -> list[tuple[list[int], int]]:
    """(content, times): whole sequences that hold every piece exactly once. counts[l]: pieces of length l.

    The rounded solution of the configuration program, its remainder by best fit; or best fit alone if that takes fewer sequences.
    """
    whole, left = rounded(counts)
    solved, plain = whole + best_fit(left), best_fit(counts)
    size = lambda configs: sum(times for _, times in configs)
    return solved if size(solved) <= size(plain) else plain


def best_fit(counts: np.ndarray) -> list[tuple[list[int], int]]:
    """Best fit, longest first, over a histogram; groups of equal sequences move together."""
    top = len(counts) - 1
    free: list[list[tuple[tuple[int, ...], int]]] = [[] for _ in range(top + 1)]
    rooms = np.zeros(top + 1, bool)
    for length in range(top, 0, -1):
        n = int(counts[length])
        while n:
            at = np.flatnonzero(rooms[length:])
            if at.size:
                room = length + int(at[0])
                content, times = free[room].pop()
                take = min(n, times)
                if take < times:
                    free[room].append((content, times - take))
                rooms[room] = bool(free[room])
            else:
                room, content, take = top, (), -(-n // (top // length))
                take = min(take, n)
            free[room - length].append(((*content, length), take))
            rooms[room - length] = room - length > 0
            n -= take
    return [(list(c), t) for group in free for c, t in group]


def _places(configs: list[tuple[list[int], int]], top: int) -> tuple[np.ndarray, ...]:
    """Runs of ranks of each length, sorted by (length, first rank): length, first rank, first sequence, offset; and where a length starts."""
    runs, done, base = [], np.zeros(top + 1, np.int64), 0
    for content, times in configs:
        at = 0
        for length in content:
            runs.append((length, done[length], base, at))
            done[length] += times
            at += length
        base += times
    table = np.array(sorted(runs), np.int64).reshape(-1, 4)
    return table[:, 0], table[:, 1], table[:, 2], table[:, 3], np.searchsorted(table[:, 0], np.arange(top + 2))


def assign(cut: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """cut's pieces (a written table) with sequence_id and offset instead of ids. The plan's size is bounded by its configurations."""
    counts = np.zeros(capacity + 1, np.int64)
    by_shard = written(cut.groupBy("shard", "length").agg(F.count("*").alias("n")), "lengths")
    for r in by_shard.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most `capacity` rows
        counts[r["length"]] = r["n"]
    _, first, base, offset, starts = _places(plan(counts), capacity)
    w = Window.partitionBy("length").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    before = by_shard.select("shard", "length", F.coalesce(F.sum("n").over(w), F.lit(0)).cast("long").alias("before"))
    ranked = cut.drop("ids").join(before.hint("merge"), ["shard", "length"])  # the table grows with the tasks: never broadcast
    kind = cut.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            length, rank = b["length"].to_numpy(np.int64), (b["rank"] + b["before"]).to_numpy(np.int64)
            row = np.empty(len(b), np.int64)
            for x in np.unique(length):
                own = length == x
                row[own] = starts[x] + np.searchsorted(first[starts[x] : starts[x + 1]], rank[own], side="right") - 1
            yield b[["doc_id", "piece", "start", "length", "ids_crc32", "shard", "rank"]].assign(sequence_id=base[row] + rank - first[row], offset=offset[row])

    return ranked.mapInPandas(run, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, shard int, rank long, sequence_id long, offset long")


def pack(docs: DataFrame, capacity: int = CAPACITY, tokenizer_path: str | None = None) -> tuple[DataFrame, DataFrame]:
    """(pieces with ids, their places): the places have sequence_id and offset, gapless from 0 in each sequence.

    docs has doc_id and text; other columns are ignored; null and empty texts make a piece of END alone;
    repeated rows are packed each; no rows give no rows.
    """
    cut = written(pieces(docs, capacity, tokenizer_path), "pieces")
    return cut, assign(cut, capacity)


def sequences(cut: DataFrame, places: DataFrame) -> DataFrame:
    """(sequence_id, ids): the packed sequences themselves, each at most `capacity` ids."""
    both = cut.select("shard", "length", "rank", "ids").join(places.select("shard", "length", "rank", "sequence_id", "offset"), ["shard", "length", "rank"])
    parts = both.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("parts"))
    return parts.select("sequence_id", F.aggregate("parts", F.lit(b""), lambda a, x: F.concat(a, x["ids"])).alias("ids"))


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, places = pack(documents(spark, sf_dir).select("doc_id", "text"))
    return places.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
