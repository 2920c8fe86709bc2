"""The pipeline's stages on a small corpus, each against what it must keep or change."""

import random
import re

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from hopbound.llm import queries
from hopbound.llm.packing import default_tokenizer

DOC = "doc_id bigint, text string, lang string, source string, n_chars bigint"
WORDS = "the of and to in stone river carry bright green lamp window seven house paper quiet".split()


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    r = random.Random(3)
    texts = [" ".join(r.choice(WORDS) for _ in range(60)) for _ in range(150)]
    texts += texts[:10] + [t + " paper" for t in texts[10:20]]
    texts += ["".join(r.choice("qxzj#!%vkw ") for _ in range(400)) for _ in range(15)]
    texts += [f"{' '.join(r.choice(WORDS) for _ in range(50))} write to me{i}@mail.com please" for i in range(10)]
    rows = [(i, t, "en", f"s{i % 3}", len(t)) for i, t in enumerate(texts)]
    at = str(tmp_path_factory.mktemp("corpus"))
    spark.createDataFrame(rows, DOC).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(120)], "doc_id bigint, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    return at, {r[0]: r for r in rows}


def test_stages(spark, corpus):
    at, rows = corpus
    docs = spark.read.parquet(f"{at}/documents.parquet")
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.written(stage(spark, docs, at), name)
        seen[name] = docs.collect()
        if name != "best_fit_packing":
            assert docs.columns == DOC.replace(",", "").split()[::2]
    good = {r.doc_id for r in seen["quality_classifier"]}
    assert not good & set(range(170, 185)) and len(good) > 150
    one = {r.doc_id for r in seen["simhash_near_dedup"]}
    assert one <= good and not any(i in one and i - 150 in one for i in range(150, 160))
    clean = {r.doc_id: r.text for r in seen["pii_sanitisation"]}
    assert set(clean) == one and not any("@" in t for t in clean.values())
    assert all(t == rows[i][1] for i, t in clean.items() if i < 185)
    sizes, taken = {}, {}
    for r in seen["pii_sanitisation"]:
        sizes[r.source] = sizes.get(r.source, 0) + len(r.text.split())
    for r in seen["source_mixing"]:
        assert r.text == clean[r.doc_id]
        taken[r.source] = taken.get(r.source, 0) + len(r.text.split())
    total = sum(sizes.values())
    assert abs(sum(taken.values()) - 1.5 * total) <= 3 * 60 and all(taken[s] <= 2 * sizes[s] for s in sizes)
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(default_tokenizer())
    want = sum(len(tok.encode(r.text, add_special_tokens=False).ids) + 1 for r in seen["source_mixing"])
    assert sum(r.length for r in seen["best_fit_packing"]) == want


def test_run_gives_the_last_stage(spark, corpus):
    assert corpus_pipeline.run(spark, corpus[0]).columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    assert corpus_pipeline.ORACLE_SQL is None


def test_ten_queries_are_registered():
    assert sorted(int(re.match(r"op(\d+)_", q)[1]) for q in queries.QUERIES) == list(range(1, 11))
    assert set(queries.ORACLES) <= set(queries.QUERIES)


def test_queries_on_empty_tables(spark, tmp_path):
    at = str(tmp_path)
    spark.createDataFrame([], DOC).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([], "doc_id bigint, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    spark.createDataFrame([], "page_id bigint, url string").write.parquet(f"{at}/pages.parquet")
    spark.createDataFrame([], "conv_id bigint, turn bigint, role string, text string").write.parquet(f"{at}/conversations.parquet")
    for name, q in queries.QUERIES.items():
        assert q(spark, at).count() == (1 if name.startswith("op9") else 0), name
    assert corpus_pipeline.run(spark, at).agg(F.count(F.lit(1))).first()[0] == 0
