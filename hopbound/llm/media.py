"""Media columns stored as content-defined chunks.

A payload is kept losslessly as 8-bit samples in a WAV file. The file is cut where a rolling gear hash of its
bytes says so, chunks are named by their digests, and a Spark join on digests leaves one copy of each
in the store. A media is its ordered chunk list; reading it back joins the list with the store, puts the chunks in order
and verifies the digest of the whole before anything is computed from it.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bucketed, documents, written

UNIT, PAD = 192, b" "
RATE = 8000
MIN_CHUNK, MASK_BITS, MAX_CHUNK = 128, 8, 4096  # well below a document and a passage, so that documents with a common passage share chunks
MASK = ((1 << MASK_BITS) - 1) << (32 - MASK_BITS)
SAMPLE_ROWS, SAMPLE_BYTES, DICTIONARY_BYTES, LEVEL = 4000, 8192, 400 << 10, 12
STORE_PARTS, READ_PARTS = 2, 3  # shares of the chunks and of the media that are in shuffle files at a time
GEAR = np.random.default_rng(20240229).integers(0, 1 << 32, 256, dtype=np.uint32)


def payload_of(text: str | None) -> tuple[bytes, int]:
    """(UTF-8 text filled with spaces to a positive multiple of UNIT, its own length)."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + PAD * ((-len(raw)) % UNIT or (UNIT if not raw else 0)), len(raw)


def wav(samples: bytes, rate: int = RATE) -> bytes:
    """8-bit mono PCM; the payload length is even, so no fill byte is needed."""
    return b"RIFF" + struct.pack("<I", 36 + len(samples)) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, rate, rate, 1, 8) + b"data" + struct.pack("<I", len(samples)) + samples


def samples_of(media: bytes) -> bytes:
    """The data chunk of a WAV file."""
    at = 12
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"data":
            return media[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    raise ValueError("no data chunk")


def cuts(data: bytes) -> list[int]:
    """Ends of the chunks of data. The gear hash at a byte depends on the 32 bytes up to it, so cuts move with content."""
    n = len(data)
    if n <= MIN_CHUNK:
        return [n]
    h = GEAR[np.frombuffer(data, np.uint8)]
    for k in (1, 2, 4, 8, 16):  # h over 2k bytes from two h over k bytes
        h[k:] = h[k:] + (h[:-k] << np.uint32(k))
    found = np.flatnonzero((h & np.uint32(MASK)) == 0) + 1
    out, last = [], 0
    for c in [*found.tolist(), n]:
        while c - last > MAX_CHUNK:
            last += MAX_CHUNK
            out.append(last)
        if c - last >= MIN_CHUNK and c < n:
            out.append(c)
            last = c
    if last < n:
        out.append(n)
    return out


def features(samples: bytes) -> str:
    """Mean, deviation, zero crossings about the middle, and the shares of 8 level bands of the samples."""
    x = np.frombuffer(samples, np.uint8).astype(np.int32)
    side = x >= 128
    bands = np.bincount(x >> 5, minlength=8)
    return f"{x.mean():.4f};{x.std():.4f};{int((side[1:] != side[:-1]).sum())};" + ",".join(f"{b / len(x):.4f}" for b in bands)


def _named(data: bytes) -> bytes:
    """Digest that names a chunk: 128 bits of SHA-256."""
    return hashlib.sha256(data).digest()[:16]


def train_dictionary(docs: DataFrame) -> bytes:
    """A compression dictionary from at most SAMPLE_ROWS texts; empty if they are too few. It changes sizes only."""
    texts = [r["text"].encode("utf-8", "surrogatepass")[:SAMPLE_BYTES] for r in docs.where(F.length("text") > 0).select("text").limit(SAMPLE_ROWS).collect()]
    if sum(map(len, texts)) < 20 * DICTIONARY_BYTES:
        return b""
    return zstandard.train_dictionary(DICTIONARY_BYTES, texts).as_bytes()


def _dictionary(data: bytes) -> dict:
    return {"dict_data": zstandard.ZstdCompressionDict(data)} if data else {}


def _split(text: str | None) -> tuple[bytes, bytes, int, list[bytes]]:
    """(digest of the media, media, length of the text, chunks)."""
    payload, n = payload_of(text)
    media = wav(payload)
    ends = cuts(media)
    return hashlib.sha256(media).digest(), media, n, [media[x:y] for x, y in zip([0, *ends], ends)]


def manifests(docs: DataFrame) -> DataFrame:
    """doc_id, media (digest), n_bytes, media_bytes, chunks (digests in order) of every row of docs."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for d, text in zip(b["doc_id"], b["text"]):
                name, media, n, pieces = _split(text)
                rows.append((d, name, n, len(media), [_named(p) for p in pieces]))
            yield pd.DataFrame(rows, columns=["doc_id", "media", "n_bytes", "media_bytes", "chunks"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInPandas(run, f"doc_id {kind}, media binary, n_bytes long, media_bytes long, chunks array<binary>")


def chunk_rows(docs: DataFrame, dictionary: bytes = b"", part: int = 0, parts: int = 1) -> DataFrame:
    """(digest, packed): the compressed chunks of docs whose digests fall into a part, each once a task at most."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        squeeze, met, whole = zstandard.ZstdCompressor(level=LEVEL, **_dictionary(dictionary)), set(), set()
        for b in batches:
            rows = []
            for text in b["text"]:
                name, _, _, pieces = _split(text)
                if name in whole:
                    continue
                whole.add(name)
                for p in pieces:
                    digest = _named(p)
                    if digest[0] % parts == part and digest not in met:
                        met.add(digest)
                        rows.append((digest, squeeze.compress(p)))
            yield pd.DataFrame(rows, columns=["digest", "packed"])

    return docs.select("text").mapInPandas(run, "digest binary, packed binary")


def store(docs: DataFrame) -> tuple[DataFrame, DataFrame, bytes]:
    """(manifests, chunk store, compression dictionary) of docs, the tables written; the store holds every digest once."""
    listed, chunks, dictionary = _stored(docs)
    return listed, reduce(DataFrame.unionByName, chunks), dictionary


def _stored(docs: DataFrame) -> tuple[DataFrame, list[DataFrame], bytes]:
    """As store, but the tables that make up the store.

    The store holds every digest once, in a table for each of STORE_PARTS parts of the digests. The tables are bucketed by digest, so readers do not shuffle
    them, and are written one after the other, so that no more than a part of all chunks is in shuffle files at a time.
    """
    spark = docs.sparkSession
    listed = written(manifests(docs), "manifests")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dictionary = train_dictionary(docs)
    chunks = []
    for part in range(STORE_PARTS):
        chunks.append(bucketed(chunk_rows(docs, dictionary, part, STORE_PARTS).repartition(n, "digest").dropDuplicates(["digest"]), "digest", "chunks"))
    return listed, chunks, dictionary


def read_back(listed: DataFrame, chunks: DataFrame | list[DataFrame], dictionary: bytes = b"") -> DataFrame:
    """(media, payload_bytes, payload_sha256, tail_crc32, feature) of every distinct media, from the chunks in their listed order.

    Media are read in READ_PARTS parts, one after the other, for the same reason as in store. A media whose bytes do not have its digest raises an error.
    """
    chunks = [chunks] if isinstance(chunks, DataFrame) else chunks
    found = None
    for part in range(READ_PARTS):
        own = listed.where(F.pmod(F.xxhash64("media"), F.lit(READ_PARTS)) == part)
        one = written(_read_part(own, chunks, dictionary), "found")
        found = one if found is None else found.unionByName(one)
    return found


def _read_part(listed: DataFrame, chunks: list[DataFrame], dictionary: bytes) -> DataFrame:
    each = listed.groupBy("media").agg(F.first("chunks").alias("chunks"))
    refs = each.select("media", F.size("chunks").alias("n"), F.posexplode("chunks").alias("pos", "digest"))
    met = None
    for part, table in enumerate(chunks):
        # the first byte of a digest says which table has it
        of = refs.where(F.conv(F.hex(F.substring("digest", 1, 1)), 16, 10).cast("int") % len(chunks) == part)
        one = of.join(table, "digest").select("media", "n", "pos", "packed")
        met = one if met is None else met.unionByName(one)
    ordered = met.repartition("media").sortWithinPartitions("media", "pos")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor(**_dictionary(dictionary))
        parts: list[bytes] = []
        for b in batches:
            rows = []
            for name, n, pos, packed in zip(*(b.column(c).to_pylist() for c in ("media", "n", "pos", "packed"))):
                if pos != len(parts):
                    raise ValueError("a chunk list is out of order")
                parts.append(unpack.decompress(packed))
                if len(parts) == n:
                    media, parts = b"".join(parts), []
                    if hashlib.sha256(media).digest() != name:
                        raise ValueError("a stored media is damaged")
                    samples = samples_of(media)
                    rows.append((name, len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-16:]), features(samples)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.string()))], ["media", "payload_bytes", "payload_sha256", "tail_crc32", "feature"])

    return ordered.mapInArrow(run, "media binary, payload_bytes long, payload_sha256 string, tail_crc32 long, feature string")


def stored_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media_bytes, media_sha256 and what read_back finds, one row per row of docs.

    docs has doc_id and text; other columns are ignored. Null texts are empty (one unit of spaces);
    repeated rows are all returned; no rows give no rows.
    """
    listed, chunks, dictionary = _stored(docs)
    found = read_back(listed, chunks, dictionary)
    return listed.drop("chunks").join(found, "media").withColumn("media_sha256", F.lower(F.hex("media"))).drop("media")


def op3_media_chunking(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = stored_media(documents(spark, sf_dir).select("doc_id", "text"))
    return found.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")
