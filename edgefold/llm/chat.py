"""Chat formatting in Spark expressions alone.

A conversation's rows are collected as structs, sorted, and folded by one array aggregation that merges adjacent turns
of a role into one block; a mark between parts keeps each turn apart. Layout of a block:

    ### role:<newline>part</part><newline>part</turn><newline>

Texts and roles are escaped so that none of the marks can occur in them: a backslash is doubled, `</` becomes `<\\/`, `##`
becomes `#\\#`, and in roles a newline gets a backslash before it. Dropping each backslash and keeping what follows it
undoes all of these. The loss mask is a list of byte spans of the formatted text (start, length), one for each part
of a role that is trained on.

Defined cases: a null text or role is empty; turns with equal numbers are ordered by role and text, and nulls come
first; rows with a null conversation id form one conversation; an empty table gives no rows; columns other than
conv_id, turn, role and text are ignored. The formatted text of a conversation is one value, as its reader needs it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm.shared import table

TRAINED_ROLE = "assistant"
PART_END, TURN_END = "</part>\n", "</turn>\n"


def escape(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    out = F.replace(out, F.lit("</"), F.lit("<\\/"))
    return F.replace(out, F.lit("##"), F.lit("#\\#"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("\\\n"))


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def format_conversations(rows: DataFrame, *, trained_role: str = TRAINED_ROLE) -> DataFrame:
    """conv_id, formatted, loss_spans (array of byte start and length)."""
    turn = F.struct(
        F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )
    sorted_turns = rows.select("conv_id", turn.alias("t")).groupBy("conv_id").agg(F.array_sort(F.collect_list("t")).alias("turns"))
    marked = sorted_turns.select(
        "conv_id",
        F.transform(
            "turns", lambda t: F.struct(t["role"].alias("role"), escape_role(t["role"]).alias("shown"), escape(t["text"]).alias("text"))
        ).alias("turns"),
    )

    def add(state: Column, t: Column) -> Column:
        fresh = state["role"].isNull() | (state["role"] != t["role"])
        head = F.when(state["role"].isNull(), F.lit("")).when(fresh, F.lit(TURN_END)).otherwise(F.lit(PART_END))
        head = F.concat(head, F.when(fresh, F.concat(F.lit("### "), t["shown"], F.lit(":\n"))).otherwise(F.lit("")))
        begins = state["at"] + F.octet_length(head)
        length = F.octet_length(t["text"]).cast("long")
        span = F.struct(begins.cast("long").alias("start"), length.alias("length"))
        spans = F.when(t["role"] == trained_role, F.array_append(state["spans"], span)).otherwise(state["spans"])
        pieces = F.concat(state["pieces"], F.array(head, t["text"]))
        return F.struct(pieces.alias("pieces"), spans.alias("spans"), (begins + length).cast("long").alias("at"), t["role"].alias("role"))

    empty = F.struct(
        F.array().cast("array<string>").alias("pieces"),
        F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"),
        F.lit(0).cast("long").alias("at"),
        F.lit(None).cast("string").alias("role"),
    )
    folded = marked.select("conv_id", F.explode(F.array(F.aggregate("turns", empty, add))).alias("s"))
    text = F.concat(F.array_join("s.pieces", ""), F.lit(TURN_END))
    # explode of one element keeps the folded value from being worked out anew for each use
    return folded.select("conv_id", F.explode(F.array(F.struct(text.alias("formatted"), F.col("s.spans").alias("loss_spans")))).alias("o")).select(
        "conv_id", "o.formatted", "o.loss_spans"
    )


def read_turns(formatted: Column) -> Column:
    """Array of (role, text) in order, from the formatted text alone."""
    blocks = F.filter(F.split(formatted, TURN_END), lambda b: b != "")

    def turns(block: Column) -> Column:
        role = unescape(F.regexp_extract(block, r"(?s)\A### (.*?):\n", 1))
        body = F.regexp_replace(block, r"(?s)\A### .*?:\n", "")
        return F.transform(F.split(body, PART_END), lambda x: F.struct(role.alias("role"), unescape(x).alias("text")))

    return F.flatten(F.transform(blocks, turns))


def read_trained(formatted_bytes: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped, in order."""
    cut = F.transform(spans, lambda s: F.decode(F.substring(formatted_bytes, (s["start"] + 1).cast("int"), s["length"].cast("int")), "UTF-8"))
    return F.array_join(F.transform(cut, unescape), "")


def op10_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    said = "\\### Assistant: </turn> ok"
    extra = spark.sql("SELECT -7L AS conv_id, t.turn, t.role, '' AS text FROM VALUES (0L, 'user'), (1L, 'assistant') AS t(turn, role)")
    extra = extra.withColumn("text", F.lit(said))
    out = format_conversations(rows.unionByName(extra))
    seen = F.struct(
        F.col("formatted"), F.encode("formatted", "UTF-8").alias("raw"), F.col("loss_spans"), read_turns(F.col("formatted")).alias("turns")
    )
    read = out.select("conv_id", F.explode(F.array(seen)).alias("r"))
    trained = read_trained(F.col("r.raw"), F.col("r.loss_spans"))
    shown = F.array_join(F.transform("r.turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id",
        F.size("r.turns").cast("long").alias("n_turns"),
        F.sha2(shown, 256).alias("turns_sha256"),
        F.length(trained).cast("long").alias("loss_chars"),
        F.sha2(trained, 256).alias("loss_sha256"),
        F.length("r.formatted").cast("long").alias("formatted_chars"),
    )


OP10_SQL = r"""
WITH spoken AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), marked AS (
  SELECT conv_id, turn, role, text,
    length(replace(replace(replace(text, '\', '\\'), '</', '<\/'), '##', '#\#')) AS shown,
    length(replace(replace(replace(replace(role, '\', '\\'), '</', '<\/'), '##', '#\#'), chr(10), '\' || chr(10))) AS shown_role,
    lag(role) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS earlier
  FROM spoken
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum(shown + 8 + CASE WHEN earlier IS NULL OR earlier <> role THEN shown_role + 6 ELSE 0 END)::BIGINT AS formatted_chars
FROM marked GROUP BY conv_id
"""
