"""Information-theoretic sanitisation on DataFrame functions alone.

Base entities (emails, IPv4 addresses, card and phone numbers) are found by patterns. Then the corpus
says which terms give an entity away, a part of one, a kind, or that something protected is there: a term in the same document discloses it to the degree
PMI(term; entity) / IC(entity), that is log(n(t,e) N / (n(t) n(e))) / log(N / n(e)) over documents, discounted for small counts.
Terms that reach the threshold are generalised wherever they occur, to the most specific term of the corpus that subsumes them; those that
disclose most are removed.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, slim, widened, written

KINDS = ("email", "ip", "card", "phone")
# The contract's patterns, each begun only where a leftmost match can begin, so that long runs take linear time.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][ -])[0-9](?:[ -]?[0-9]){12,18}(?![ -]?[0-9])",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
GUARDS = {"email": "@", "ip": ".", "card": None, "phone": "+"}
SPANS = "array<struct<kind:string,start:long,end:long,value:string,before:string,after:string>>"
WORD = r"[\p{L}\p{N}]+"
GENERALISE, REMOVE = 0.7, 0.9  # disclosure from which a term is replaced by a broader one, and removed
SUBSUMES = 0.8  # share of a term's documents in which a broader term is
SHORTER, TERM_DOCS = 0.3, 2000  # share of a term's documents, beyond 1 - SUBSUMES, whose words are brought together; those a task counts
MAX_BROADCAST_TERMS = 100_000  # words, some 10 MB
MAX_BROADCAST_LISTS = 200_000  # numbers of documents with terms


def _valid(kind: str, m: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    digits = F.regexp_replace(m, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: F.regexp_like(p, F.lit(r"^0*(25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])$")))
    if kind == "phone":
        return F.char_length(digits).between(9, 15)
    # Luhn: from the right, every second digit doubled, less 9 beyond 9
    each = F.transform(F.split(F.reverse(digits), ""), lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise((d.cast("int") * 2) % 10 + F.floor(d.cast("int") * 2 / 10).cast("int")))
    return F.char_length(digits).between(13, 19) & (F.aggregate(each, F.lit(0), lambda a, d: a + F.coalesce(d, F.lit(0))) % 10 == 0)


def _found(text: Column, pattern: Column, kind: str) -> Column:
    """Array of (kind, start, end, value, before, after) of all matches in order; offsets in code points, end exclusive."""
    parts, values = F.split(text, pattern, -1), F.regexp_extract_all(text, pattern, F.lit(0))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(SPANS).alias("out"))
    pairs = F.transform(values, lambda v, i: F.struct(v.alias("v"), F.get(parts, i).alias("p"), F.get(parts, i + 1).alias("q")))

    def step(a: Column, x: Column) -> Column:
        begin = a["at"] + F.char_length(x["p"])
        end = begin + F.char_length(x["v"])
        one = F.struct(F.lit(kind).alias("kind"), begin.alias("start"), end.alias("end"), x["v"].alias("value"), F.right(x["p"], F.lit(120)).alias("before"), F.left(x["q"], F.lit(120)).alias("after"))
        return F.struct(end.alias("at"), F.array_append(a["out"], one).alias("out"))

    return F.aggregate(pairs, start, step, lambda a: a["out"])


def with_entities(df: DataFrame) -> DataFrame:
    """df (column text) plus `base`: the valid base entities in order of kind, then start."""
    for k in KINDS:
        likely = F.regexp_like("text", F.lit(PATTERNS[k]))
        likely = F.contains("text", F.lit(GUARDS[k])) & likely if GUARDS[k] else likely
        df = df.withColumn(f"_{k}", F.when(likely, _checked(k)).otherwise(F.array().cast(SPANS)))
    return df.withColumn("base", F.concat(*[f"_{k}" for k in KINDS])).drop(*[f"_{k}" for k in KINDS])


def _checked(kind: str) -> Column:
    return F.filter(_found(F.col("text"), F.lit(PATTERNS[kind]), kind), lambda m: _valid(kind, m["value"]))


LEVELS = 4


def _levels(e: Column) -> list[Column]:
    """Keys of an entity: its value, the part of it that others share, its kind, and that it is protected at all."""
    value, digits = F.lower(e["value"]), F.regexp_replace(e["value"], "[^0-9]", "")
    part = F.when(e["kind"] == "email", F.substring_index(value, "@", -1)).when(e["kind"] == "ip", F.substring_index(value, ".", 3)).when(e["kind"] == "card", F.left(digits, F.lit(6))).otherwise(F.left(digits, F.lit(3)))
    return [F.concat_ws(":", e["kind"], value), F.concat_ws(":", e["kind"], part), e["kind"], F.lit("")]


def _words(c: Column) -> Column:
    return F.regexp_extract_all(F.lower(c), F.lit(WORD), F.lit(0))


def _outside(text: Column, base: Column) -> Column:
    """The distinct words of text outside its base entities."""
    return F.array_distinct(_words(F.aggregate(base, text, lambda t, e: F.replace(t, e["value"], F.lit(" ")))))


def entities_of(found: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(texts: _h, _words, copies; entities: _h, copies, entity, level) of the distinct texts that hold entities; found has _h, base and _words of every row that does."""
    texts = found.groupBy("_h").agg(F.first("base").alias("base"), F.first("_words").alias("_words"), F.count(F.lit(1)).alias("copies"))
    keys = F.array_distinct(F.flatten(F.transform("base", lambda e: F.array(*[F.struct(F.lit(i).alias("level"), key.alias("entity")) for i, key in enumerate(_levels(e))]))))
    return texts.select("_h", "_words", "copies"), texts.select("_h", "copies", F.inline(keys))


def term_disclosures(n_docs: int, n_t: DataFrame, found: DataFrame, generalise: float = GENERALISE) -> DataFrame:
    """(term, disclosure) of the terms that give some entity away to the degree `generalise` at least.

    n_t has t (hash of a term) and n_t, the documents that have it; found is as for entities_of. A term meets an entity where it is anywhere in the same document
    outside base spans. disclosure is the largest, over entities, of discount * PMI(term; entity) / IC(entity), cut to 0 to 1, of
    counts over all documents. The discount smooths small counts: x / (x + 1) for the distinct texts in which they meet, times the same
    for the rarer of the two; so copies of one text prove nothing, and what meets in fewer than generalise / (1 - generalise) texts cannot reach the threshold and is left out early.
    """
    least = max(1, math.ceil(generalise / (1 - generalise) - 1e-9)) if generalise < 1 else 1 << 40
    texts, each = entities_of(found)
    n_e = written(each.groupBy("level", "entity").agg(F.sum("copies").alias("n_e"), F.count(F.lit(1)).alias("texts")).where(F.col("texts") >= least).select("level", "entity", "n_e"), "counted")
    # values and parts are joined by shuffle; of kinds and the whole there are len(KINDS) + 1 at most
    fine = each.where("level < 2").join(n_e.where("level < 2"), ["level", "entity"])
    broad = each.where("level >= 2").join(F.broadcast(n_e.where("level >= 2")), ["level", "entity"])
    near = fine.unionByName(broad).join(texts.select("_h", "_words"), "_h").select("level", "entity", "n_e", "copies", F.explode("_words").alias("term"))
    near = near.where(~F.regexp_like("term", F.lit("^[0-9]+$")) & (F.char_length("term") > 1))
    joint = near.groupBy("level", "entity", "n_e", "term").agg(F.count(F.lit(1)).alias("texts"), F.sum("copies").alias("n_te")).where(F.col("texts") >= least)
    joint = written(joint.withColumn("t", F.xxhash64("term")), "joint").join(n_t, "t")
    pmi = F.log(F.col("n_te") * n_docs / (F.col("n_t") * F.col("n_e")))
    ic = F.log(F.lit(n_docs) / F.col("n_e"))
    rarer = F.least("n_t", "n_e")
    discount = F.col("texts") / (F.col("texts") + 1) * rarer / (rarer + 1)
    told = joint.withColumn("disclosure", F.when(ic > 0, F.greatest(F.lit(0.0), F.least(F.lit(1.0), discount * pmi / ic))).otherwise(F.lit(0.0)))
    return written(told.groupBy("term").agg(F.round(F.max("disclosure"), 9).alias("disclosure")).where(F.col("disclosure") >= generalise), "terms")


def broader_terms(n_docs: int, n_t: DataFrame, told: DataFrame, held: DataFrame, texts: DataFrame, few: bool = False, few_ids: bool = False) -> DataFrame:
    """(term, broader): for each told term, the most specific term of the corpus that subsumes it; no row where there is none.

    held has _r, term and size: the documents' told terms, each once, and the documents' sizes; texts has _r and text of all documents, repeated rows allowed.
    `few` and `few_ids` say that the told terms and the documents that have some can be broadcast. A term subsumes another if it is in SUBSUMES of
    the other's documents at least, in more documents than the other, not told itself, and in at most half of all documents, beyond which a term says nothing.

    What is in SUBSUMES of a term's documents is in some of any larger share of them than the rest. So only the words of a term's shorter documents are brought together
    and counted, by term or buckets of TERM_DOCS or so; the words that can still subsume it are then counted in all its documents, where those are.
    """
    small = F.broadcast if few else lambda df: df
    of = held.groupBy("term").agg(F.count(F.lit(1)).alias("n"), F.percentile_approx("size", SHORTER, 10_000).alias("most"))
    of = held.join(small(of), "term").groupBy("term", "n", "most").agg(F.count_if(F.col("size") <= F.col("most")).alias("s"), F.max("size").alias("longest"))
    enough = F.col("s") > F.col("n") - SUBSUMES * F.col("n") + 1e-6  # always, as long as percentiles are good
    of = written(of.select("term", "n", F.when(enough, F.col("most")).otherwise(F.col("longest")).alias("most"), F.when(enough, F.col("s")).otherwise(F.col("n")).alias("s")), "counted")

    def words_of(lists: DataFrame) -> DataFrame:
        return texts.join(F.broadcast(lists) if few_ids else lists, "_r").select("_r", "own", F.array_distinct(_words(F.col("text"))).alias("words")).select("_r", F.inline("own"), "words")

    shorter = held.join(small(of), "term").where("size <= most").withColumn("bucket", F.pmod(F.xxhash64("_r"), F.ceil(F.col("s") / TERM_DOCS)))
    each = words_of(shorter.groupBy("_r").agg(F.collect_list(F.struct("term", "n", "s", "bucket")).alias("own"))).repartition("term", "bucket").dropDuplicates(["term", "bucket", "n", "s", "_r"])
    near = each.select("term", "bucket", "n", "s", F.explode("words").alias("wide")).where("wide <> term").groupBy("term", "bucket", "n", "s", "wide").agg(F.count(F.lit(1)).alias("both"))
    can = F.col("both") >= SUBSUMES * F.col("n") - (F.col("n") - F.col("s")) - 1e-6
    # what is in one bucket is counted in full
    near = near.where((F.col("s") > TERM_DOCS) | can).where(~F.regexp_like("wide", F.lit("^[0-9]+$"))).groupBy("term", "n", "s", "wide").agg(F.sum("both").alias("both")).where(can)
    likely = near.join(told.select(F.col("term").alias("wide")), "wide", "left_anti").withColumn("t", F.xxhash64("wide")).join(n_t, "t")
    likely = written(likely.where((F.col("n_t") > F.col("n")) & (F.col("n_t") * 2 <= n_docs)).select("term", "n", "wide", "n_t"), "likely")

    wides = likely.groupBy("term").agg(F.collect_list("wide").alias("wides"))
    whole = held.join(small(wides), "term")
    # many terms' words go with the documents' terms, so that no text is shuffled for each of its terms
    if few:
        all_of = words_of(whole.groupBy("_r").agg(F.collect_list(F.struct("term")).alias("own"))).join(F.broadcast(wides), "term")
    else:
        all_of = words_of(whole.groupBy("_r").agg(F.collect_list(F.struct("term", "wides")).alias("own")))
    met = all_of.select("_r", "term", F.explode(F.array_intersect("wides", "words")).alias("wide")).groupBy("term", "wide").agg(F.count_distinct("_r").alias("both"))
    fits = met.join(likely, ["term", "wide"]).where(F.col("both") >= SUBSUMES * F.col("n"))
    return fits.groupBy("term").agg(F.min_by("wide", F.struct("n_t", "wide")).alias("broader"))


def disclosing_terms(keyed: DataFrame, found: DataFrame, generalise: float = GENERALISE) -> DataFrame:
    """(_r, list): for each document (keyed: _r, text) that has some, its terms that give an entity away, with their disclosure and broader term (null: none)."""
    n_docs = keyed.count()
    words = keyed.select("_r", F.char_length("text").alias("size"), F.explode(F.array_distinct(_words(F.col("text")))).alias("term"))
    # counted over all words before any join, so that frequent terms are one row per task
    n_t = written(words.groupBy(F.xxhash64("term").alias("t")).agg(F.count(F.lit(1)).alias("n_t")), "terms")
    told = term_disclosures(n_docs, n_t, found, generalise)
    few = told.limit(MAX_BROADCAST_TERMS + 1).count() <= MAX_BROADCAST_TERMS
    small = F.broadcast(told) if few else told
    listed = written(words.join(small, "term"), "listed")
    held = listed.select("_r", "term", "size").distinct()
    ids = held.select("_r").distinct()
    few_ids = ids.limit(MAX_BROADCAST_LISTS + 1).count() <= MAX_BROADCAST_LISTS
    broader = written(broader_terms(n_docs, n_t, told, held, keyed, few, few_ids), "broader")
    whole = told.join(broader, "term", "left").select("term", "disclosure", "broader")
    each = held.join(F.broadcast(whole) if few else whole, "term")
    return written(each.groupBy("_r").agg(F.sort_array(F.collect_set(F.struct("term", "disclosure", "broader"))).alias("list")), "lists")


OURS = ("base", "terms", "list")


def personal_data(docs: DataFrame, generalise: float = GENERALISE) -> DataFrame:
    """docs with base, terms and list: the spans of personal data in each row's text, and its listed terms (term, disclosure, broader).

    docs has doc_id and text; other columns are kept, those named base, terms or list as base_in, terms_in and list_in. Null texts are empty; repeated rows are all
    returned; no rows give no rows. Terms inside base spans are left out.
    """
    df = _with_terms(slim(docs, ["doc_id", "text"]), generalise)
    others = [F.col("_rest").getField(c).alias(f"{c}_in" if c in OURS else c) for c in docs.columns if c not in ("doc_id", "text")]
    return df.select("doc_id", "text", *others, *OURS)


def _with_terms(narrow: DataFrame, generalise: float) -> DataFrame:
    """narrow (doc_id, text, _rest) with base, terms and list."""
    keyed = narrow.withColumn("text", F.coalesce("text", F.lit(""))).withColumn("_h", F.xxhash64("text")).withColumn("_r", F.xxhash64("doc_id", "_h"))
    found = written(with_entities(keyed.select("_h", "text")).where(F.size("base") > 0).select("_h", "base", _outside(F.col("text"), F.col("base")).alias("_words")), "entities")
    lists = disclosing_terms(keyed.select("_r", "text"), found, generalise)
    size = lists.agg(F.coalesce(F.sum(F.size("list")), F.lit(0))).first()[0]
    named = with_entities(keyed).join(F.broadcast(lists) if size <= MAX_BROADCAST_TERMS else lists, "_r", "left")
    pattern = F.concat(F.lit(r"(?iu)(?<![\p{L}\p{N}])(?:"), F.array_join(F.transform("list", lambda x: x["term"]), "|"), F.lit(r")(?![\p{L}\p{N}])"))
    named = named.withColumn("_p", pattern).withColumn("_t", F.when(F.col("list").isNotNull(), _found(F.col("text"), F.col("_p"), "term")).otherwise(F.array().cast(SPANS)))
    clear = F.filter("_t", lambda t: ~F.exists("base", lambda e: (e["start"] < t["end"]) & (t["start"] < e["end"])))
    return named.withColumn("terms", clear).drop("_p", "_t", "_h", "_r")


def sanitised(docs: DataFrame, generalise: float = GENERALISE, remove: float = REMOVE) -> DataFrame:
    """docs with its personal data replaced in text: base entities by their kind in angle brackets, terms by the broader term of the corpus (without one, by <TERM>), terms that disclose to the degree `remove` by nothing.

    Spans that overlap are replaced as one. n_chars, where docs has it, is counted anew. Otherwise as personal_data, whatever the columns are named.
    """
    df = _with_terms(slim(docs, ["doc_id", "text"]), generalise)
    known = F.map_from_arrays(F.transform("list", lambda x: x["term"]), F.transform("list", lambda x: F.when(x["disclosure"] >= remove, "").otherwise(F.coalesce(x["broader"], F.lit("<TERM>")))))
    df = df.withColumn("_known", F.when(F.col("list").isNotNull(), known))
    label = lambda s: F.when(s["kind"] == "term", F.coalesce(F.try_element_at("_known", F.lower(s["value"])), F.lit("<TERM>"))).otherwise(F.concat(F.lit("<"), F.upper(s["kind"]), F.lit(">")))
    df = df.withColumn("_o", F.array_sort(F.transform(F.concat("base", "terms"), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), label(s).alias("label")))))

    def step(a: Column, s: Column) -> Column:
        kept = F.concat(a["out"], F.substr(F.col("text"), (a["at"] + 1).cast("int"), (s["start"] - a["at"]).cast("int")), s["label"])
        apart = s["start"] >= a["at"]
        return F.struct(F.greatest(a["at"], s["end"]).alias("at"), F.when(apart, kept).otherwise(a["out"]).alias("out"))

    begin = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out"))
    clean = F.aggregate("_o", begin, step, lambda a: F.concat(a["out"], F.substr(F.col("text"), (a["at"] + 1).cast("int"), F.char_length("text"))))
    df = df.withColumn("text", F.when(F.size("_o") > 0, clean).otherwise(F.col("text")))
    counted = {"n_chars": F.char_length("text").cast(docs.schema["n_chars"].dataType)} if "n_chars" in docs.columns else {}
    return widened(df.drop(*OURS, "_known", "_o"), docs, **counted)


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op6_pii_sanitisation(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = personal_data(documents(spark, sf_dir).select("doc_id", "text"))
    counts = [_count(k) for k in KINDS]
    terms = F.size("terms").cast("long")
    return found.select("doc_id", *counts, F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.concat("base", "terms")).alias("spans"), terms.alias("n_term"), (F.size("base") + terms).alias("n_spans"))


def _count(kind: str) -> Column:
    return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
