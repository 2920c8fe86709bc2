"""Chat formatting with Spark expressions only.

Template: every run of adjacent turns of one role is one block,
``<turn ROLE>text<also>text</turn>\\n``; inside roles and texts ``&`` becomes ``&amp;`` and ``<``
becomes ``&lt;`` (in roles also ``>`` becomes ``&gt;``), so a bare ``<`` occurs in markers alone and the
original turns can be read back exactly, merged ones included. The loss mask is a list of code point
ranges of the formatted text that cover the texts of the trained role.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

OPEN, ALSO, CLOSE = "<turn ", "<also>", "</turn>\n"


def escape(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;"))


def unescape(c: Column) -> Column:
    return F.replace(F.replace(F.replace(c, F.lit("&gt;"), F.lit(">")), F.lit("&lt;"), F.lit("<")), F.lit("&amp;"), F.lit("&"))


def format_chat(rows: DataFrame, train_role: str = "assistant") -> DataFrame:
    """One row per conversation: conv_id, formatted, loss_spans (start, end; end exclusive).

    rows has conv_id, turn, role, text; other columns are ignored. Null texts and roles count as
    empty, a null conv_id is a conversation of its own, repeated rows are all kept; ties in turn are
    put in order of role, then text. No rows give no rows. A conversation becomes one text, so its
    turns meet in one task by definition of the result.
    """
    turn = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    turns = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns"))

    def pieces(t: Column, i: Column) -> Column:
        before, after = F.get("turns", i - 1)["role"], F.get("turns", i + 1)["role"]
        first, last = F.coalesce(before != t["role"], F.lit(True)), F.coalesce(after != t["role"], F.lit(True))
        role = F.replace(escape(t["role"]), F.lit(">"), F.lit("&gt;"))
        return F.struct(
            F.when(first, F.concat(F.lit(OPEN), role, F.lit(">"))).otherwise(F.lit(ALSO)).alias("head"),
            escape(t["text"]).alias("body"),
            F.when(last, F.lit(CLOSE)).otherwise(F.lit("")).alias("tail"),
            (t["role"] == train_role).alias("loss"),
        )

    cut = turns.select("conv_id", F.transform("turns", pieces).alias("pieces"))
    sized = cut.select(
        "conv_id",
        F.array_join(F.transform("pieces", lambda p: F.concat(p["head"], p["body"], p["tail"])), "").alias("formatted"),
        F.transform("pieces", lambda p: F.struct(F.char_length(p["head"]).cast("long").alias("h"), F.char_length(p["body"]).cast("long").alias("b"), F.char_length(p["tail"]).cast("long").alias("t"), p["loss"].alias("loss"))).alias("sizes"),
    )
    at = F.aggregate("sizes", F.array(F.lit(0).cast("long")), lambda a, s: F.array_append(a, F.element_at(a, -1) + s["h"] + s["b"] + s["t"]))
    placed = sized.select("conv_id", "formatted", "sizes", at.alias("at"))
    spans = F.transform("sizes", lambda s, i: F.struct((F.get("at", i) + s["h"]).alias("start"), (F.get("at", i) + s["h"] + s["b"]).alias("end"), s["loss"].alias("loss")))
    return placed.select("conv_id", "formatted", F.transform(F.filter(spans, lambda s: s["loss"]), lambda s: F.struct(s["start"], s["end"])).alias("loss_spans"))


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, turns (role, text in order), loss_text: what format_chat's text and mask say, unescaped."""
    blocks = F.filter(F.split("formatted", CLOSE, -1), lambda b: b != "")

    def turns(b: Column) -> Column:
        role = unescape(F.substring_index(F.substr(b, F.lit(len(OPEN) + 1)), ">", 1))
        body = F.substr(b, F.instr(b, ">") + 1)
        return F.transform(F.split(body, ALSO, -1), lambda t: F.struct(role.alias("role"), unescape(t).alias("text")))

    loss = F.transform("loss_spans", lambda s: unescape(F.substr(F.col("formatted"), (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int"))))
    return formatted.select("conv_id", "formatted", F.flatten(F.transform(blocks, turns)).alias("turns"), F.array_join(loss, "").alias("loss_text"))


PROBE = r"\### Assistant: </turn> ok"


def op9_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    probe = spark.createDataFrame([(-7, 0, "user", PROBE), (-7, 1, "assistant", PROBE)], rows.schema)
    back = read_back(format_chat(rows.unionByName(probe)))
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(told, 256).alias("turns_sha256"),
        F.char_length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


ORACLE = r"""
WITH r AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '\### Assistant: </turn> ok'), (-7, 1, 'assistant', '\### Assistant: </turn> ok')
), n AS (
  SELECT *, lag(role) OVER w AS before, lead(role) OVER w AS after FROM r
  WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)
), m AS (
  SELECT *, length(replace(replace(text, '&', '&amp;'), '<', '&lt;'))
    + CASE WHEN before IS DISTINCT FROM role THEN 7 + length(replace(replace(replace(role, '&', '&amp;'), '<', '&lt;'), '>', '&gt;')) ELSE 6 END
    + CASE WHEN after IS DISTINCT FROM role THEN 8 ELSE 0 END AS chars
  FROM n
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM m GROUP BY conv_id
"""
