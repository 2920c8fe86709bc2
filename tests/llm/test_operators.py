"""Each operator against brute force or an exact round trip, on small fixtures with nulls, ties, repeats and clashing names."""

import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from hopbound.llm import chat, common, media, mixing, packing, pii, quality, simhash, spotsigs, toxicity, urls

DOC = "doc_id bigint, text string, lang string, source string, n_chars bigint"
CLASH = "_h string, h string, base string, terms string, list string, keep boolean, threshold int, weight int, _k int, _times int, _rest int, label string, size int"
WORDS = "the of and to in stone river carry bright green lamp window seven house paper quiet".split()


def prose(seed, n):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) for _ in range(n))


def docs_of(spark, texts, **more):
    rows = [(i if more.get("ids") is None else more["ids"][i], t, "en", f"src{i % 3}" if i % 5 else None, None if t is None else len(t)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOC)


AWKWARD = [None, "", " ", "\n\n", "a", "a", "É" * 30000, "x" * 50000, "ab " * 9000, "日本語 текст 🙂 \x1c\x1d", "\\", "<|endoftext|> a"]


@pytest.fixture(scope="module")
def awkward(spark):
    return docs_of(spark, AWKWARD + [prose(i, 80) for i in range(20)], ids=[*range(12), None, 5, 5, -3, *range(50, 66)])


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


def wide(df):
    """df with extra columns that have the operators' own names."""
    for c in CLASH.split(", "):
        name, kind = c.split()
        df = df.withColumn(name, F.lit(1).cast(kind))
    return df


# --- mixing --------------------------------------------------------------------------------------------


def filled(sizes, weights, share, cap):
    """Targets by repeated resharing."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, open_, out = share * sum(sizes.values()), set(names), {}
    while open_:
        unit = left / sum(w[s] for s in open_)
        over = {s for s in open_ if unit * w[s] > cap * sizes[s]}
        if not over:
            out |= {s: unit * w[s] for s in open_}
            break
        for s in over:
            out[s] = cap * sizes[s]
            left -= out[s]
        open_ -= over
    return out


def test_mixing_meets_targets(spark):
    docs = docs_of(spark, [prose(i, 5 + (i * 37) % 60) for i in range(400)])
    rows = mixing.mix(docs).collect()
    sizes = {}
    for r in rows:
        sizes[r.source] = sizes.get(r.source, 0) + r["size"]
    want = filled(sizes, (3, 1, 2), 1.5, 2)
    took = {}
    for r in rows:
        assert r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-6
        assert 0 <= r.epochs + r.extra <= 2
        took[r.source] = took.get(r.source, 0) + r["size"] * (r.epochs + r.extra)
    for s, t in took.items():
        assert abs(t - want[s]) <= 32
    again = {(r.doc_id, r.epochs, r.extra) for r in mixing.mix(docs.repartition(7)).collect()}
    assert again == {(r.doc_id, r.epochs, r.extra) for r in rows}


def test_mixing_prefers_better_documents(spark):
    docs = docs_of(spark, [prose(i, 20) for i in range(600)])
    good = spark.createDataFrame([(i, 8.0 if i % 2 else 0.25) for i in range(600)], "doc_id bigint, weight double")
    rows = mixing.mix(docs, good, weights=(1,), share=0.5).collect()
    assert sum(r.extra for r in rows if r.doc_id % 2) > 3 * sum(r.extra for r in rows if not r.doc_id % 2)


def test_mixing_takes_what_ordered_keys_and_prefix_sums_give(spark):
    docs = docs_of(spark, [prose(i, (i * 37) % 60) for i in range(900)])
    weights = {i: (0.25, 1.0, 8.0)[i % 3] for i in range(0, 900, 2)}
    quality = spark.createDataFrame(list(weights.items()), "doc_id bigint, weight double")
    draw = F.pmod(F.xxhash64("doc_id", F.xxhash64("text"), F.lit(7)), F.lit(1 << 52))
    drawn = {r[0]: (r[1] + 0.5) / (1 << 52) for r in docs.select("doc_id", draw).collect()}
    by = {}
    for r in mixing.mix(docs, quality, share=1.3, seed=7).collect():
        by.setdefault(r.source, []).append(r)
    parts = 0
    for rows in by.values():
        total = sum(r["size"] for r in rows)
        epochs, left = divmod(rows[0].target, total)
        done = 0
        for r in sorted(rows, key=lambda r: -math.log(drawn[r.doc_id]) / weights.get(r.doc_id, 1.0)):
            inside = r["size"] > 0 and left > 0 and done + r["size"] / 2 <= left
            assert (r.epochs, r.extra) == (epochs, int(inside))
            done += r["size"]
            parts += r.extra
    assert parts


def test_mixing_awkward(spark, awkward, none):
    assert mixing.mix(none).count() == 0 and mixing.mixed_documents(none).count() == 0
    assert mixing.mix(awkward).count() == awkward.count()
    out = mixing.mixed_documents(wide(awkward))
    assert out.columns == wide(awkward).columns and out.count() > 0
    same = docs_of(spark, ["one two three"] * 40, ids=[1] * 40)
    assert mixing.mix(same).count() == 40


# --- packing --------------------------------------------------------------------------------------------


def test_packing_is_whole_and_close_to_the_bound(spark):
    from tokenizers import Tokenizer

    texts = [prose(i, 1 + (i * 61) % 700) for i in range(150)] + AWKWARD
    docs = docs_of(spark, texts)
    cut, places = packing.pack(docs, capacity=512)
    tok = Tokenizer.from_file(packing.default_tokenizer())
    rows = sorted((tuple(r) for r in places.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset").collect()))
    ids = {i: [*tok.encode(t or "", add_special_tokens=False).ids, 0] for i, t in enumerate(texts)}
    want = []
    for i, x in ids.items():
        for k, s in enumerate(range(0, len(x), 512)):
            part = x[s : s + 512]
            want.append((i, k, s, len(part), zlib.crc32(np.array(part, "<u4").tobytes())))
    assert [r[:5] for r in rows] == sorted(want)
    by = {}
    for r in rows:
        by.setdefault(r[5], []).append((r[6], r[3]))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 512
    assert len(by) <= -(-sum(map(len, ids.values())) // 512) + 2
    joined = {r.sequence_id: bytes(r.ids) for r in packing.sequences(cut, places).collect()}
    assert sum(map(len, joined.values())) == 4 * sum(map(len, ids.values()))


def check_plan(counts, plan):
    held = np.zeros(len(counts), int)
    for content, times in plan:
        assert sum(content) < len(counts) and times > 0
        np.add.at(held, content, times)
    assert (held[1:] == counts[1:]).all()
    return sum(t for _, t in plan)


@pytest.mark.parametrize("seed", range(4))
def test_plans_come_from_the_configuration_program(seed):
    r = np.random.default_rng(seed)
    lengths = np.minimum(256, r.geometric(0.02, 20000))
    counts = np.bincount(lengths, minlength=257)
    whole, left = packing.rounded(counts)
    n = check_plan(counts, packing.plan(counts))
    assert n <= check_plan(counts, packing.best_fit(counts)) and n <= -(-lengths.sum() // 256) + 1
    assert sum(t for _, t in whole) >= 0.95 * n and (left >= 0).all()
    used = packing.cover(counts)
    covered = np.zeros(257)
    for config, times in used.items():
        np.add.at(covered, list(config), times)
    assert (covered <= counts + 1e-6).all() and (covered * np.arange(257)).sum() > 0.98 * lengths.sum()


def fewest(lengths, top):
    """Least number of sequences, by trying all places of the pieces, longest first."""
    lengths = sorted(lengths, reverse=True)
    best = [len(lengths)]

    def place(i, rooms):
        if len(rooms) >= best[0]:
            return
        if i == len(lengths):
            best[0] = len(rooms)
            return
        for j in range(len(rooms)):
            if rooms[j] >= lengths[i] and rooms[j] not in rooms[:j]:
                place(i + 1, [*rooms[:j], rooms[j] - lengths[i], *rooms[j + 1 :]])
        place(i + 1, [*rooms, top - lengths[i]])

    place(0, [])
    return best[0]


@pytest.mark.parametrize("seed", range(12))
def test_plans_of_small_histograms_are_the_fewest(seed):
    r = np.random.default_rng(seed)
    top = 20
    counts = np.bincount(r.integers(1, top + 1, 11), minlength=top + 1)
    n = check_plan(counts, packing.plan(counts))
    assert n == fewest(np.repeat(np.arange(top + 1), counts).tolist(), top)


def test_knapsack_is_exact():
    r = np.random.default_rng(3)
    for _ in range(20):
        lengths, p = np.array([1, 2, 3, 5, 7, 8, 11]), r.random(7)
        worth, last = packing.knapsack(lengths, p, 12)
        best = [0.0] * 13
        for c in range(1, 13):
            best[c] = max(best[c - 1], *(best[c - k] + v for k, v in zip(lengths, p) if k <= c))
            inside = packing.content(last, c)
            assert sum(inside) <= c and abs(sum(dict(zip(lengths.tolist(), p))[k] for k in inside) - best[c]) < 1e-9
        assert np.allclose(worth, best)


def test_word_cache_forgets_and_stays_exact(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(packing, "CACHE_BYTES", 2000)
    tok = packing.WordTokenizer(packing.default_tokenizer())
    for k in range(4):
        texts = [prose(i + 50 * k, 60) + f" word{i * k} ❤ x<|y|>" for i in range(20)] + AWKWARD
        ids, ends = tok.encode(pa.array(texts), 0)
        want = [[*tok.tokenizer.encode(t or "", add_special_tokens=False).ids, 0] for t in texts]
        assert ids.tolist() == sum(want, []) and ends.tolist() == np.cumsum([len(w) for w in want]).tolist()


def test_packing_awkward(awkward, none):
    assert packing.pack(none)[1].count() == 0
    assert packing.pack(wide(awkward))[1].select("doc_id", "piece").count() >= awkward.count()


# --- media --------------------------------------------------------------------------------------------------


def test_media_round_trip(spark, awkward, none):
    texts = {r.doc_id: r.text for r in awkward.collect()}
    got = media.stored_media(wide(awkward)).collect()
    assert len(got) == awkward.count()
    for r in got:
        raw = None if r.doc_id in (5, None) else (texts[r.doc_id] or "").encode()
        if raw is not None:
            full = raw + b" " * ((-len(raw)) % 192 or (0 if raw else 192))
            assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-16:]))
            assert r.media_sha256 == hashlib.sha256(media.wav(full)).hexdigest() and r.media_bytes == len(full) + 44
    assert media.stored_media(none).count() == 0


def test_chunks_move_with_content_and_are_stored_once(spark):
    r = random.Random(1)
    body = bytes(r.randrange(32, 127) for _ in range(200_000))
    a, b = media.cuts(body), media.cuts(b"new front " + body)
    assert a[-1] == len(body) and len(a) > 5
    pieces = lambda data, ends: [data[x:y] for x, y in zip([0, *ends], ends)]
    assert b"".join(pieces(body, a)) == body
    assert len(set(pieces(body, a)) & set(pieces(b"new front " + body, b))) >= len(a) - 2
    text = body.decode()
    listed, store, words = media.store(docs_of(spark, [text, text, "front " * 40 + text]))
    assert store.count() == store.select("digest").distinct().count() < listed.select(F.sum(F.size("chunks"))).first()[0]
    with pytest.raises(Exception, match="damaged|size|rror"):
        media.read_back(listed.withColumn("media", F.reverse("media")), store, words).collect()


def test_documents_with_a_common_passage_share_chunks():
    texts = []
    passage = prose(77, 250)
    for i in range(4):
        r = random.Random(i)
        own = [" ".join(f"w{r.randrange(10**6)}" for _ in range(150)) for _ in range(2)]
        texts.append(f"{own[0]} {passage} {own[1]}")
    files = [media.wav(media.payload_of(t)[0]) for t in texts]
    pieces = [{f[x:y] for x, y in zip([0, *media.cuts(f)], media.cuts(f))} for f in files]
    assert all(len(p) >= 4 for p in pieces) and len(passage) < 2000
    assert set.intersection(*pieces)


# --- urls -------------------------------------------------------------------------------------------------------


def test_url_rules_and_list(spark):
    rows = ["https://Shop.Example.COM/en/1", "http://example.com/en/71?q", "http://x.example.net/de/80", "ftp://a.net/de/1#f", "x://a.org/es/", "http://notcom/en/1", "no scheme", None, "http://b.org/q/1.html?utm_source=feed", "https://www.b.org/q/1/", "http://b.org/q/1", "http://e.com", "a://b://c/d"]
    pages = spark.createDataFrame(list(enumerate(rows)), "page_id bigint, url string").withColumn("block", F.lit(1)).withColumn("canon", F.lit("x"))
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(pages, pages.where("url like '%utm_source=feed%'"), urls.RULES).collect()}
    assert got[0] == ("shop.example.com", "/en/1", "com/en/", "block")
    assert got[1] == ("example.com", "/en/71", "example.com/en/7", "allow")
    assert got[2][2:] == ("example.net/de/8", "block") and got[3][2:] == ("net/de/", "allow") and got[4][2:] == ("org/es/", "block")
    assert got[5][2:] == (None, "allow") and got[6] == ("", "", None, "allow") and got[7] == ("", "", None, "allow")
    assert got[8][3] == got[9][3] == got[10][3] == "block" and got[11][:2] == ("e.com", "") and got[12][:2] == ("b:", "//c/d")
    none = pages.where("page_id < 0")
    assert urls.judge(none, none, urls.RULES).count() == 0 and urls.judge(pages, none, urls.RULES).count() == len(rows)


def test_bloom_filter_has_no_false_negatives(spark):
    keys = spark.range(3000).select(F.concat(F.lit("k"), "id").alias("key"))
    asked = spark.range(6000).select(F.concat(F.lit("k"), "id").alias("key"))
    blocks, n = urls.bloom_blocks(keys, "key", 3000)
    assert blocks.count() <= n
    got = urls.listed(asked, "key", keys).where("_listed")
    assert got.count() == 3000 and got.where("cast(substring(key, 2) as int) >= 3000").count() == 0


# --- spotsigs ------------------------------------------------------------------------------------------------------


def sigs(text):
    """Signature strings of a text, in the operator's terms."""
    plain = re.sub(r"[^\w]|_", " ", text.lower()).split()
    out, run = [], []
    content = [(w, i) for i, w in enumerate(plain) if w not in spotsigs.COMMON]
    for n, (w, i) in enumerate(content):
        start = content[n - 1][1] + 1 if n else 0
        run = plain[start:i]
        if run:
            out.append(("_".join([*run, w]), content[n + 1][0] if n + 1 < len(content) else ""))
    return set(out)


def test_spotsigs_likeness_is_jaccard(spark):
    texts = [prose(i, 200) for i in range(12)]
    texts += [texts[0] + " the zebra runs", texts[1]]
    docs = docs_of(spark, texts)
    rows = {r.doc_id: r.sigs for r in spotsigs.with_signatures(docs, "text", "sigs").collect()}
    for a in range(14):
        for b in range(a):
            x, y = sigs(texts[a]), sigs(texts[b])
            if plainly(texts[a]) and plainly(texts[b]):
                want = len(x & y) / len(x | y)
                got = len(set(rows[a]) & set(rows[b])) / len(set(rows[a]) | set(rows[b]))
                assert abs(want - got) < 1e-9
    members, pairs = spotsigs.similar(docs, 0.8)
    classes = {r.doc_id: r.class_id for r in members.collect()}
    assert classes[13] == classes[1] == 1
    want = {(a, b) for a in set(classes.values()) for b in set(classes.values()) if a < b and len(set(rows[a]) & set(rows[b])) / len(set(rows[a]) | set(rows[b])) >= 0.8}
    assert {(r.a, r.b) for r in pairs.collect()} == want and want


def plainly(text):
    return text.split()[-1] not in spotsigs.COMMON


def test_next_document_and_edits(spark, awkward, none, monkeypatch):
    monkeypatch.setattr(spotsigs, "ROWS_PER_BUCKET", 4)
    df = spark.createDataFrame([(i * i % 101, f"t{i}") for i in range(50)], "doc_id bigint, text string").dropDuplicates(["doc_id"]).withColumn("_h", F.xxhash64("text"))
    rows = {r.doc_id: (r.text, r.next_text) for r in spotsigs.with_next(df, ["text"]).collect()}
    order = sorted(rows, reverse=True)
    for i, d in enumerate(order):
        assert rows[d][1] == rows[order[(i + 1) % len(order)]][0]
    keyed = awkward.select("doc_id", "text").withColumn("_h", F.xxhash64("text"))
    assert spotsigs.with_next(keyed, ["text"]).count() == awkward.count()
    assert spotsigs.with_next(none.select("doc_id", "text").withColumn("_h", F.lit(0)), ["text"]).count() == 0


def test_spotsigs_query_edits_and_likenesses(spark, tmp_path):
    texts = [prose(i, 40 + 7 * i) for i in range(9)] + [None, "", "ab", "a é 𝄞 z", prose(3, 61)]
    ids = [(7 * i) % 31 for i in range(len(texts))]
    rows = [(d, t, "en", "s") for d, t in zip(ids, texts)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    found = {r.doc_id: r for r in spotsigs.op5_spotsigs(spark, str(tmp_path)).collect()}
    order = sorted(zip(ids, ((t or "") for t in texts)), reverse=True)
    edited = {d: t[: len(t) - len(t) // 3] + order[(i + 1) % len(order)][1][: len(t) // 3] for i, (d, t) in enumerate(order)}
    both = spark.createDataFrame([(d, t) for d, t in order] + [(1000 + d, t) for d, t in edited.items()], "doc_id bigint, text string")
    sets = {r.doc_id: set(r.sigs) for r in spotsigs.with_signatures(both, "text", "sigs").collect()}
    alike = lambda a, b: len(sets[a] & sets[b]) / len(sets[a] | sets[b])
    assert len(found) == len(order)
    for i, (d, t) in enumerate(order):
        assert found[d].n_chars == len(t)
        assert found[d].edited_sha256 == hashlib.sha256(edited[d].encode()).hexdigest()
        assert abs(found[d].near_edited - alike(d, 1000 + d)) < 1e-12
        assert abs(found[d].near_next - alike(d, order[(i + 1) % len(order)][0])) < 1e-12


@pytest.mark.parametrize("least", [0.5, 0.8, 1.0])
def test_spotsigs_length_partitions_lose_no_pair(spark, least):
    base = prose(5, 300).split()
    texts = [" ".join(base[:n]) for n in range(12, 300, 9)]
    docs = docs_of(spark, texts)
    sets = {r.doc_id: set(r.sigs) for r in spotsigs.with_signatures(docs, "text", "sigs").collect()}
    members, pairs = spotsigs.similar(docs, least)
    names = sorted({r.class_id for r in members.collect()})
    want = {(a, b) for a in names for b in names if a < b and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= least}
    assert {(r.a, r.b) for r in pairs.collect()} == want


# --- pii ---------------------------------------------------------------------------------------------------------------


def luhn(s):
    return sum(int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4) for i, c in enumerate(reversed(s))) % 10 == 0


def entities(x):
    digits = lambda m: re.sub("[^0-9]", "", m)
    kinds = (
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(q) <= 255 for q in m.split("."))),
        ("card", r"[0-9]([\x20-]?[0-9])+", lambda m: 13 <= len(digits(m)) <= 19 and luhn(digits(m))),
        ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(digits(m)) <= 15),
    )
    return [(k, m.start(), m.end()) for k, rx, ok in kinds for m in re.finditer(rx, x) if ok(m.group())]


PII = [
    "é🙂 mail a.b@c.de, x@y.z_q@r.st a@b @c.d e@f..g h@i.j.k-", "1.2.3.4.5.6.7.8 999.1.1.1 10.0.0.256 001.002.003.255 1.2.3", "4111 1111 1111 1111 4111-1111-1111-1111 41111111111111112 5 6  7 8-9",
    "4111111111111111 4111111111111111", "+1 (976) 555-9693 4123094741088840 +49.30.123456 +1-2 ++12345678901 +1 (((", "0" * 40, "9 " * 3000, "a" * 20000 + "@", "a.b@" * 2000 + "c.d", "1." * 4000, "+1" + " 1" * 4000, "٣٤٥ @", None, "",
]


def test_base_entities_are_those_of_the_patterns(spark, awkward):
    r = random.Random(7)
    texts = PII + ["".join(r.choice("0123456789 .-+()@ab") for _ in range(300)) for _ in range(300)]
    got = {x.doc_id: x.base for x in pii.personal_data(docs_of(spark, texts)).collect()}
    for i, t in enumerate(texts):
        assert [(s.kind, s.start, s.end) for s in got[i]] == entities(t or ""), t
        assert all((t or "")[s.start : s.end] == s.value for s in got[i])


def levels_of(kind, value):
    digits = re.sub("[^0-9]", "", value)
    value = value.lower()
    part = {"email": value.split("@")[-1], "ip": ".".join(value.split(".")[:3]), "card": digits[:6], "phone": digits[:3]}[kind]
    return {(0, f"{kind}:{value}"), (1, f"{kind}:{part}"), (2, kind), (3, "")}


def brute_disclosures(texts, least):
    """Of every term, the largest discounted PMI over IC."""
    import math

    words = [set(re.findall(r"[^\W_]+", t.lower())) for t in texts]
    base = [entities(t) for t in texts]
    n = len(texts)
    out = {}
    keys = [set().union(*[levels_of(k, t[a:b]) for k, a, b in e]) if e else set() for t, e in zip(texts, base)]
    clear = []
    for t, e in zip(texts, base):
        for k, a, b in e:
            t = t.replace(t[a:b], " ") if t[a:b] in t else t
        clear.append(set(re.findall(r"[^\W_]+", t.lower())))
    first = {}
    for i, t in enumerate(texts):
        first.setdefault(t, i)
    for key in set().union(*keys):
        of = [i for i in range(n) if key in keys[i]]
        for term in set().union(*(clear[i] for i in of)):
            if len(term) < 2 or term.isdigit():
                continue
            n_te, n_t, n_e = sum(term in clear[i] for i in of), sum(term in w for w in words), len(of)
            distinct = sum(term in clear[i] and first[texts[i]] == i for i in of)
            ic = math.log(n / n_e)
            rarer = min(n_t, n_e)
            d = distinct / (distinct + 1) * rarer / (rarer + 1) * math.log(n_te * n / (n_t * n_e)) / ic if ic > 0 else 0
            out[term] = max(out.get(term, 0), min(1, max(0, d)))
    return {t: d for t, d in out.items() if d >= least}


def pii_texts():
    texts = [f"Report {prose(i, 30)} call Zorblax at zorb@mail.com now {prose(i + 99, 20)}" for i in range(8)] + [prose(i + 500, 60) for i in range(60)] + ["again Zorblax without mail"]
    texts += [f"{prose(i + 700, 20)} person{i}@corp.org {prose(i, 9)} Quux desk" for i in range(30)] + ["desk " + prose(i, 5) for i in range(40)] + [f"{prose(i, 4)} 10.0.0.{i} ping" for i in range(12)]
    return texts + [texts[3]] * 9


def test_disclosures_equal_brute_force(spark):
    texts = pii_texts()
    docs = docs_of(spark, texts)
    keyed = docs.select(F.col("doc_id").alias("_r"), "text")
    found = pii.with_entities(docs.select(F.xxhash64("text").alias("_h"), "text")).where(F.size("base") > 0).select("_h", "base", pii._outside(F.col("text"), F.col("base")).alias("_words"))
    n_t = keyed.select(F.explode(F.array_distinct(pii._words(F.col("text")))).alias("term")).groupBy(F.xxhash64("term").alias("t")).agg(F.count("*").alias("n_t"))
    for least in (0.3, 0.5, 0.7):
        got = {r.term: r.disclosure for r in pii.term_disclosures(len(texts), n_t, found, least).collect()}
        want = brute_disclosures(texts, least)
        # terms of fewer texts than the threshold can be reached with are left out early, and could not have reached it
        assert got.keys() == want.keys() and all(abs(got[t] - want[t]) < 1e-6 for t in want) and "zorblax" in want


def test_terms_that_disclose_are_found_and_replaced(spark, none, awkward):
    texts = pii_texts()
    docs = docs_of(spark, texts)
    told = brute_disclosures(texts, pii.GENERALISE)
    found = {r.doc_id: r for r in pii.personal_data(docs).collect()}
    for i, t in enumerate(texts):
        assert {x.value.lower() for x in found[i].terms} == {w for w in re.findall(r"[^\W_]+", t.lower()) if w in told} - {w for k, a, b in entities(t) for w in re.findall(r"[^\W_]+", t[a:b].lower()) if w in told and t.lower().count(w) == 1}
        assert all(t[x.start : x.end] == x.value for x in found[i].terms)
    assert "Zorblax" in {t.value for t in found[0].terms} and [t.value for t in found[68].terms] == ["Zorblax"] and not any(found[i].terms for i in range(8, 68))
    # quux is in some of the documents of desk, which is in others too: its broader term
    broader = {x.term: x.broader for r in found.values() for x in r.list or []}
    assert broader["quux"] == "desk"
    clean = {r.doc_id: r for r in pii.sanitised(wide(docs)).collect()}
    assert "zorb@mail.com" not in clean[0].text and "Zorblax" not in clean[0].text and "<EMAIL>" in clean[0].text
    assert "Quux" not in clean[70].text and clean[70].text.count("desk") == 1 + (told["quux"] < pii.REMOVE)
    assert clean[30].text == texts[30] and clean[0].n_chars == len(clean[0].text)
    assert pii.sanitised(none).count() == 0 and pii.personal_data(none).count() == 0
    assert pii.sanitised(wide(awkward)).columns == wide(awkward).columns
    both = pii.personal_data(wide(awkward))
    assert {"base_in", "list_in", "terms_in", "h", "_h", "label"} <= set(both.columns) and both.count() == awkward.count()


@pytest.mark.parametrize("few, bucket, share", [(True, 2000, 0.3), (True, 3, 0.3), (False, 3, 0.3), (False, 2000, 0.01)])
def test_broader_terms_equal_brute_force_and_shuffle_little(spark, monkeypatch, few, bucket, share):
    monkeypatch.setattr(pii, "TERM_DOCS", bucket)
    monkeypatch.setattr(common, "CLEANUP", "spark.hopbound.none")  # to see all shuffle files
    monkeypatch.setattr(pii, "SHORTER", share)  # 0.01: too few to hold every candidate, so that all are taken
    r = random.Random(11)
    texts = [" ".join(r.choice("abcdefg") + str(r.randint(0, 9) ** 2) + "x" for _ in range(r.choice((3, 8, 30, 60)))) for _ in range(60)] + [" ".join(f"u{i}v{j}" for j in range(3000)) for i in range(25)]
    told = ["tell" + str(i) for i in range(8)]
    texts = [t + "".join(f" {x}" + f" wide{i // 2}" * (r.random() < 0.95) for i, x in enumerate(told) if r.random() < 0.25) for t in texts]
    words = [set(re.findall(r"[^\W_]+", t.lower())) for t in texts]
    n_of = lambda w: sum(w in x for x in words)
    want = {}
    for t in told:
        of = [x for x in words if t in x]
        fits = [(n_of(w), w) for w in set.union(*of) - set(told) if not w.isdigit() and sum(w in x for x in of) >= pii.SUBSUMES * len(of) and len(of) < n_of(w) <= len(texts) / 2]
        if fits:
            want[t] = min(fits)[1]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(0, texts[0])] * 3, "_r long, text string")
    held = spark.createDataFrame([(i, t, len(texts[i])) for i, x in enumerate(words) for t in sorted(x & set(told))], "_r long, term string, size int")
    n_t = rows.distinct().select(F.explode(F.array_distinct(pii._words(F.col("text")))).alias("term")).groupBy(F.xxhash64("term").alias("t")).agg(F.count("*").alias("n_t")).where("n_t > 1").localCheckpoint()
    before = shuffle_bytes(spark)
    got = {x.term: x.broader for x in pii.broader_terms(len(texts), n_t, spark.createDataFrame([(t,) for t in told], "term string"), held, rows, few, few).collect()}
    assert got == want and len(want) > 3
    if share == 0.3 and few:  # the long texts, which are most of all, are not shuffled
        assert shuffle_bytes(spark) - before < 0.1 * sum(map(len, texts))


def test_copies_of_one_text_disclose_nothing(spark):
    texts = pii_texts()
    copies = docs_of(spark, [texts[0]] * 20 + texts[8:40])
    assert not any(r.terms for r in pii.personal_data(copies).collect())


# --- simhash -------------------------------------------------------------------------------------------------------------


def plain_fingerprint(text):
    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    hs = [xxhash.xxh64_intdigest(" ".join(words[i : i + 4]).encode(), 42) for i in range(max(1, len(words) - 3))]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))


def linked(fps, ids):
    """Least id reachable by brute force."""
    up = list(range(len(fps)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 4:
                up[root(i)] = root(j)
    return [min((ids[j] for j in range(len(fps)) if root(j) == root(i) and ids[j] is not None), default=None) for i in range(len(fps))]


def test_fingerprints(spark, awkward):
    for r in simhash.fingerprints(wide(awkward)).join(awkward, "doc_id").where("doc_id <> 5").collect():
        assert r.fp % (1 << 64) == plain_fingerprint(r.text)


@pytest.mark.parametrize(("crowded", "many"), [(200, 1 << 27), (2, 1 << 27), (200, 1), (1, 1)])
def test_components_equal_brute_force(spark, monkeypatch, crowded, many):
    monkeypatch.setattr(simhash, "CROWDED", crowded)
    monkeypatch.setattr(simhash, "MANY", many)
    r = random.Random(5)
    base = [r.getrandbits(64) for _ in range(12)]
    fps = []
    for b in base:
        x = b
        for _ in range(10):
            for _ in range(r.randint(1, 4)):
                x ^= 1 << r.randrange(64)
            fps.append(x)
    fps = list(dict.fromkeys(fps))
    signed = [x - (1 << 64) if x >> 63 else x for x in fps]
    df = spark.createDataFrame([(x,) for x in signed], "fp bigint")
    comp = {r.node: r.component for r in common.components(simhash.links(df)).collect()}
    want = linked(fps, signed)
    assert all(comp.get(x, x) == w for x, w in zip(signed, want))


def test_near_duplicates(spark, awkward, none):
    texts = [prose(i, 120) for i in range(30)]
    texts += [t + " paper" for t in texts[:10]] + texts[10:20]
    docs = docs_of(spark, texts, ids=[100 - i for i in range(50)])
    fps = [plain_fingerprint(t) for t in texts]
    want = dict(zip([100 - i for i in range(50)], linked(fps, [100 - i for i in range(50)])))
    assert {r.doc_id: r.component_id for r in simhash.near_duplicates(docs).collect()} == want
    kept = simhash.one_each(wide(docs))
    assert {r.doc_id for r in kept.collect()} == set(want.values()) and kept.columns == wide(docs).columns
    assert simhash.near_duplicates(none).count() == 0 and simhash.one_each(none).count() == 0
    assert simhash.near_duplicates(awkward).count() == awkward.count()
    assert simhash.one_each(docs_of(spark, ["a b c"] * 3, ids=[None] * 3)).count() == 1


def five_words(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


@pytest.mark.parametrize(("bucket", "block", "hubs"), [(8, 512, 8192), (2, 10, 20)])
def test_one_of_all_alike(spark, awkward, none, monkeypatch, bucket, block, hubs):
    monkeypatch.setattr(simhash, "BUCKET", bucket)
    monkeypatch.setattr(simhash, "BLOCK_SETS", block)
    monkeypatch.setattr(simhash, "HUB_SETS", hubs)
    r = random.Random(11)
    base = [" ".join(f"w{r.randrange(3000)}" for _ in range(200)) for _ in range(40)]
    texts = list(base)
    for t in base:
        for edits in (1, 2, 3, 4, 6, 8):  # similarities from 0.95 to about 0.65
            w = t.split()
            for at in r.sample(range(5, 195), edits):
                w[at] = f"new{r.randrange(1000)}"
            texts.append(" ".join(w))
    texts += [base[0] + f" tail{i}" for i in range(60)]
    sets = [five_words(t) for t in texts]
    like = lambda i, j: len(sets[i] & sets[j]) / len(sets[i] | sets[j])
    up = list(range(len(texts)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            if like(i, j) >= 0.8:
                up[max(root(i), root(j))] = min(root(i), root(j))
    want = {root(i) for i in range(len(texts))}
    assert 0.8 <= min(like(i, (i - 40) // 6) for i in range(40, 280) if like(i, (i - 40) // 6) >= 0.8) < 0.85 and len(want) > 45
    docs = docs_of(spark, texts)
    kept = simhash.one_each_alike(wide(docs))
    assert {x.doc_id for x in kept.collect()} == want and kept.columns == wide(docs).columns
    assert len(want) < simhash.one_each(docs).count()
    assert simhash.one_each_alike(none).count() == 0 and simhash.one_each_alike(awkward).count() > 20
    assert simhash.one_each_alike(docs_of(spark, ["a b c"] * 3, ids=[None] * 3)).count() == 1


def test_star_components_on_chains(spark):
    r = random.Random(2)
    edges = [(i, i + 1) for i in range(0, 60) if i % 20 != 19] + [(200, 199), (7, 7)]
    r.shuffle(edges)
    got = {x.node: x.component for x in common.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert all(got[i] == i // 20 * 20 for i in range(60)) and got[200] == 199


# --- toxicity -----------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("block", [128, 1, 2, 3])
def test_marginals_equal_enumeration(monkeypatch, block):
    r = np.random.default_rng(0)
    lengths = np.array([3, 1, 4, 2])
    starts = np.cumsum(lengths) - lengths
    e, t = r.normal(size=10), r.normal(size=(2, 2))
    monkeypatch.setattr(toxicity, "BLOCK", block)
    p, pairs, logz = toxicity.marginals(e, starts, lengths, t)
    twice = toxicity.marginals(np.r_[e, e], np.r_[starts, starts + 10], np.r_[lengths, lengths], t)
    again = toxicity.marginals(e, starts, lengths, t, np.array([2, 2, 2, 2]))
    assert np.allclose(twice[1], again[1]) and np.isclose(twice[2], again[2])
    total, want_pairs = 0.0, np.zeros((2, 2))
    for s, n in zip(starts, lengths):
        z, m = 0.0, np.zeros(n)
        pr = np.zeros((2, 2))
        for code in range(1 << n):
            y = [code >> i & 1 for i in range(n)]
            w = np.exp(sum(e[s + i] for i in range(n) if y[i]) + sum(t[y[i], y[i + 1]] for i in range(n - 1)))
            z += w
            m += w * np.array(y)
            for i in range(n - 1):
                pr[y[i], y[i + 1]] += w
        assert np.allclose(p[s : s + n], m / z)
        total += np.log(z)
        want_pairs += pr / z
    assert np.allclose(logz, total) and np.allclose(pairs, want_pairs)


def test_gradient_is_that_of_the_likelihood():
    r = np.random.default_rng(4)
    lengths, times = np.array([5, 2, 3]), np.array([1, 3, 2])
    starts, n = np.cumsum(lengths) - lengths, 10
    y = r.integers(0, 2, n)
    per_word = np.repeat(times, lengths)
    at, feat = np.r_[np.arange(n), [0, 3, 3, 7]], np.r_[np.zeros(n, int), [1, 1, 2, 2]]
    seen = np.bincount(feat, weights=(y * per_word)[at], minlength=3)
    true_t = np.zeros((2, 2))
    for s, m, c in zip(starts, lengths, times):
        for i in range(s, s + m - 1):
            true_t[y[i], y[i + 1]] += c
    w, t = r.normal(size=3), r.normal(size=(2, 2))

    def value(w, t):
        e = np.bincount(at, weights=w[feat], minlength=n)
        return (e * y * per_word).sum() + (true_t * t).sum() - toxicity.marginals(e, starts, lengths, t, times)[2] - 0.05 * (w[1:] ** 2).sum() - 0.05 * (t**2).sum()

    gw, gt = toxicity._gradient(w, t, at, feat, seen, true_t, starts, lengths, times, per_word)
    for k in range(3):
        d = np.eye(3)[k] * 1e-5
        assert np.isclose((value(w + d, t) - value(w - d, t)) / 2e-5, gw[k], atol=1e-5)
    for k in range(4):
        d = np.eye(4)[k].reshape(2, 2) * 1e-5
        assert np.isclose((value(w, t + d) - value(w, t - d)) / 2e-5, gt.ravel()[k], atol=1e-5)


def test_words_are_labelled_by_counts_beyond_chance():
    texts = [f"good word{i} " + ("vile " if i < 40 else "") + ("rare " if i in (0, 1, 2) else "") + ("half " if i % 2 else "") for i in range(200)]
    y = np.arange(200) < 50
    data = toxicity._Numbered(texts)
    flagged = {n for n, s in zip(data.names, toxicity._signal(data, y)) if s}
    assert {"vile", "3:vil"} <= flagged and not flagged & {"good", "half", "rare", "3:goo"}
    n = data.document_counts(y)
    assert n[data.names.index("vile")] == 40 and n[data.names.index("half")] == 25


def labelled(spark, n=600):
    r = random.Random(9)
    texts, y = [], []
    for i in range(n):
        w = prose(i, 60).split()
        bad = i % 4 == 0
        for _ in range(4 if bad else 0):
            w.insert(r.randrange(len(w)), r.choice(["scoundrel", "villain", "wretchish", "wretchful"]))
        texts.append(" ".join(w) + ".")
        y.append(int(bad))
    return docs_of(spark, texts), spark.createDataFrame(list(enumerate(y)), "doc_id bigint, toxic int")


def test_toxicity_on_held_out_rows(spark, awkward, none):
    docs, labels = labelled(spark)
    model = toxicity.train(docs, labels.where(~toxicity.held_out()))
    rows = toxicity.score(wide(docs), model).join(labels, "doc_id").where(toxicity.held_out()).collect()
    assert len(rows) > 100 and all((r.score >= 0.7) == bool(r.toxic) for r in rows)
    text = {r.doc_id: r.text for r in docs.collect()}
    for r in rows:
        found = {text[r.doc_id][s.start : s.end] for s in r.spans}
        assert found <= {"scoundrel", "villain", "wretchish", "wretchful"} and bool(found) == bool(r.toxic)
    scores = toxicity.score(awkward, model)
    assert scores.count() == awkward.count() and scores.where("score < 0 or score > 1 or score is null").count() == 0
    assert toxicity.score(none, model).count() == 0
    blank = toxicity.train(docs, labels.where("doc_id < 0"))
    assert toxicity.score(docs, blank).where("score >= 0.7").count() == 0
    one_kind = toxicity.train(docs, labels.where("toxic = 0"))
    assert toxicity.score(docs, one_kind).where("score >= 0.7").count() == 0


def test_offsets_hold_where_lower_case_is_longer(spark):
    docs, labels = labelled(spark)
    model = toxicity.train(docs, labels)
    odd = docs_of(spark, ["İİ good word VILLAIN here", "İ" * 50 + ". scoundrel"])
    spans = {r.doc_id: r.spans for r in toxicity.score(odd, model).collect()}
    assert [(s.start, s.end) for s in spans[0]] == [(13, 20)] and [(s.start, s.end) for s in spans[1]] == [(52, 61)]


def test_training_is_stable_among_repeated_ids(spark):
    docs, labels = labelled(spark, 200)
    doubled = docs.unionByName(docs.withColumn("text", F.lit("nothing to see")))
    a, b = (toxicity.train(x, labels, chars=9000) for x in (doubled, doubled.repartition(5)))
    assert a.weights == b.weights and a.shift == b.shift


def test_words_past_the_first_chain_of_a_sentence_are_learned(spark):
    texts = []
    for i in range(300):
        w = prose(i, 220).split()
        if i % 4 == 0:
            w[130:130] = ["scoundrel"] * 2
        texts.append(" ".join(w))
    docs, labels = docs_of(spark, texts), spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(300)], "doc_id bigint, toxic int")
    scores = {r.doc_id: r.score for r in toxicity.score(docs, toxicity.train(docs, labels)).collect()}
    assert all((scores[i] >= 0.7) == (i % 4 == 0) for i in range(300))


# --- chat ------------------------------------------------------------------------------------------------------------------------


def test_chat_round_trip(spark):
    nasty = ["<turn user>", "</turn>\n", "&lt;<also>&amp;", chat.PROBE, "", None, "é🙂\n", "x" * 30000, "\\<"]
    rows = [(c, t, ["user", "assistant", "assistant", None, "a<b>&"][(c * t + t) % 5], nasty[(c + t) % len(nasty)]) for c in range(20) for t in range(1 + c % 9)]
    rows += [(3, 1, "user", "tie"), (3, 1, "user", "tie"), (None, 0, "user", "of none")]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumn("turns", F.lit(1)).withColumn("pieces", F.lit(2))
    made = chat.format_chat(df)
    for r in chat.read_back(made).collect():
        want = sorted(((t, ro or "", x or "") for c, t, ro, x in rows if c == r.conv_id))
        assert [(x.role, x.text) for x in r.turns] == [w[1:] for w in want]
        assert r.loss_text == "".join(w[2] for w in want if w[1] == "assistant")
        assert r.formatted.count(chat.CLOSE) == 1 + sum(a[1] != b[1] for a, b in zip(want, want[1:]))
    assert chat.format_chat(df.where("turn > 99")).count() == 0


# --- quality ------------------------------------------------------------------------------------------------------------------------


def kneser_ney(texts, order):
    """P(character after its context) by the definition, from dictionaries; contexts are padded with starts."""
    from collections import Counter

    pad = quality.START * (order - 1)
    levels = {order: Counter(x[i : i + order] for x in (pad + t for t in texts) for i in range(len(x) - order + 1))}
    for k in range(order - 1, 0, -1):
        levels[k] = Counter(g[1:] for g in levels[k + 1])
    off = {}
    for k, c in levels.items():
        n = [max(1, sum(v == j for v in c.values())) for j in (1, 2, 3, 4)]
        y = n[0] / (n[0] + 2 * n[1])
        d = [0, *(min(j, max(0.05, j - (j + 1) * y * n[j] / n[j - 1])) for j in (1, 2, 3))]
        off[k] = lambda v, d=d: d[min(v, 3)]

    def p(gram):
        k = len(gram)
        if not k:
            return 1 / quality.CODE_POINTS
        after = [v for g, v in levels[k].items() if g[:-1] == gram[:-1]]
        if not after:
            return p(gram[1:])
        v = levels[k].get(gram, 0)
        return (v - off[k](v) + sum(off[k](x) for x in after) * p(gram[1:])) / sum(after)

    return p


def test_probabilities_and_perplexities_equal_brute_force(spark):
    r = random.Random(3)
    texts = ["".join(r.choice("ab c.é") for _ in range(r.randrange(1, 25))) for _ in range(14)] + [None, "", "zab", "a\0b", "日本 ab"]
    docs = docs_of(spark, texts)
    fold = [None if i >= 10 else i % 2 for i in range(len(texts))]
    folded = docs.join(spark.createDataFrame(list(enumerate(fold)), "doc_id bigint, _fold int"), "doc_id").repartition(2)
    cut = quality.shards(folded.select("doc_id", "text", "lang", "_fold"), shard_chars=60, chunk_chars=30)
    assert cut.select("shard").distinct().count() > 2
    known = quality.probabilities(quality.gram_counts(cut))
    of = {m: kneser_ney([t for t, f in zip(texts, fold) if f in fs], quality.ORDER) for m, fs in (("all", (0, 1)), ("even", (0,)), ("odd", (1,)))}
    rows = known.collect()
    assert len(rows) == len({(quality.START * 3 + t.replace("\0", "�"))[i : i + 4] for t in texts if t for i in range(len(t))})
    for row in rows:
        for m in of:
            assert abs(row[m] - of[m](row.gram)) < 1e-9 * max(1, row[m]), (row, m)

    def perplexity(t, p):
        t = (t or "").replace("\0", "�")
        x = quality.START * 3 + t
        return np.exp(-sum(np.log(p(x[i : i + 4])) for i in range(len(t))) / max(1, len(t)))

    trusted = docs.where("doc_id < 10").select("doc_id")
    got = {r.doc_id: r for r in quality.classify(docs, trusted, 0.5).collect()}
    for i, t in enumerate(texts):
        assert abs(got[i].perplexity - perplexity(t, of["all"])) < 1e-4 * got[i].perplexity and got[i].n_symbols == len(t or "")
    halves = docs.where("doc_id < 10").select("doc_id", F.pmod(F.xxhash64("text"), F.lit(2)).alias("f")).collect()
    half = {r.doc_id: r.f for r in halves}
    by = [kneser_ney([texts[i] for i in half if half[i] != f], quality.ORDER) for f in (0, 1)]
    crossed = sorted(perplexity(texts[i], by[half[i]]) for i in half)
    assert abs(got[0].threshold - crossed[4]) < 1e-4 * crossed[4]
    assert all(r.keep == (r.perplexity <= r.threshold) for r in got.values())


def test_kneser_ney_sums_to_one():
    p = kneser_ney(["the stone and the river and the lamp in the house " * 3], 4)
    seen = sorted(set("the stone and the river and the lamp in the house "))
    for context in ("", "the", " an", "xyz", "\x02\x02t"):
        rest = quality.CODE_POINTS - len(seen)
        assert abs(sum(p(context + c) for c in seen) + rest * p(context + "Ω") - 1) < 1e-9


def test_quality_keeps_clean_and_drops_junk(spark, awkward, none):
    texts = [prose(i, 80) for i in range(200)] + ["".join(random.Random(i).choice("qxzj#!%vkw ") for _ in range(400)) for i in range(20)]
    docs = docs_of(spark, texts)
    trusted = spark.range(100).select(F.col("id").alias("doc_id"))
    rows = quality.classify(docs, trusted).collect()
    assert sum(r.keep for r in rows if r.doc_id < 200) >= 190 and not any(r.keep for r in rows if r.doc_id >= 200)
    kept = quality.accepted(wide(docs), trusted)
    assert {r.doc_id for r in kept.collect()} == {r.doc_id for r in rows if r.keep} and kept.columns == wide(docs).columns
    assert quality.classify(docs, trusted.where("doc_id < 0")).where("keep").count() == docs.count()
    assert quality.classify(none, trusted).count() == 0
    assert quality.classify(awkward, trusted).count() == awkward.count()


def test_clean_deletes_what_was_written(spark):
    df = common.written(spark.range(3))
    assert df.count() == 3
    common.clean(spark)
    assert not common._WRITTEN
    with pytest.raises(Exception, match="PATH_NOT_FOUND|not exist|FILE_NOT_EXIST"):
        spark.read.parquet(df.inputFiles()[0]).count()


def test_media_are_stored_and_read_in_parts(spark, monkeypatch):
    texts = [f"text {i} " * 300 for i in range(12)]
    tables, parts = [], []
    bucketed, read = media.bucketed, media._read_part
    monkeypatch.setattr(media, "bucketed", lambda *a: tables.append(bucketed(*a)) or tables[-1])
    monkeypatch.setattr(media, "_read_part", lambda *a: parts.append(1) or read(*a))
    got = {r.doc_id: r.payload_sha256 for r in media.stored_media(docs_of(spark, texts)).collect()}
    assert sorted(got.values()) == sorted(hashlib.sha256(media.payload_of(t)[0]).hexdigest() for t in texts)
    digests = [{bytes(r.digest) for r in t.collect()} for t in tables]
    assert len(digests) == media.STORE_PARTS > 1 and all(digests) and not set.intersection(*digests) and len(parts) == media.READ_PARTS


def shuffle_files(spark):
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {n for i in range(files.size()) if (n := files.apply(i).getName()).startswith("shuffle_")}


def shuffle_bytes(spark):
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return sum(f.length() for i in range(files.size()) if (f := files.apply(i)).getName().startswith("shuffle_") and f.getName().endswith(".data"))


def test_tables_leave_no_shuffle_files(spark):
    before, setting = shuffle_files(spark), spark.conf.get(common.CLEANUP, None)
    for write in (lambda df: common.written(df), lambda df: common.bucketed(df, "k", "left")):
        df = spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count()
        table = write(df)
        assert not shuffle_files(spark) - before
        assert table.count() == df.count() == 7  # which leave theirs until they are collected
        before |= shuffle_files(spark)
    assert spark.conf.get(common.CLEANUP, None) == setting


def test_media_parts_meet_no_shuffle_files_of_each_other(spark, monkeypatch):
    met, before, read = [], shuffle_files(spark), media._read_part
    monkeypatch.setattr(media, "_read_part", lambda *a: met.append(shuffle_files(spark) - before) or read(*a))
    media.stored_media(docs_of(spark, [f"text {i} " * 300 for i in range(12)]))
    assert len(met) == media.READ_PARTS and not any(met)
