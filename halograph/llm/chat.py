"""Chat formatting by prefix-target expansion, in DataFrame functions only.

Turns are written through a template whose control strings are escaped, reversibly, where they occur inside roles or texts. Every
assistant turn becomes an example of its own: all preceding turns are its context and only its own text is trainable. A context is a
prefix of its conversation's formatted text, so an example refers to that prefix by its end instead of repeating it: written out, the
contexts of a conversation of n turns would hold n squared turns. expand() writes them out where that is wanted.

Turns are ordered by turn, then role, then text; null comes first. Null text and null role count as empty; repeated rows are repeated
turns; conversations without an assistant turn are formatted and have no example; an empty table gives an empty result. Positions in
long conversations come from sums over blocks of turns, so that no task needs a whole conversation to format it or to make its examples.
Only the query's digests do: a hash of all turns is a hash of one string, so there a conversation is one row, of at most 2 GB.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialise

OPEN, AFTER_ROLE, CLOSE = "### ", ": ", " </turn>\n"
TRAINABLE = "assistant"
#: turns whose positions are summed together
STRETCH = 512

# What is escaped, in the order of escaping. Escaped text holds no "#" and no "<", so no control string.
ESCAPES = (("\\", "\\b"), ("#", "\\h"), ("<", "\\l"))
ROLE_ESCAPES = (*ESCAPES, (":", "\\c"))


def escape(text: Column, table: tuple[tuple[str, str], ...] = ESCAPES) -> Column:
    for raw, written in table:
        text = F.replace(text, F.lit(raw), F.lit(written))
    return text


def unescape(text: Column, table: tuple[tuple[str, str], ...] = ESCAPES) -> Column:
    for raw, written in reversed(table):
        text = F.replace(text, F.lit(written), F.lit(raw))
    return text


def format_turns(conversations: DataFrame) -> DataFrame:
    """One row per turn: conv_id, position, start (characters of the conversation before it), piece (its formatted text), is_target,
    body_start and body_end (its own text, as characters of the conversation)."""
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    head = F.concat(F.lit(OPEN), escape(role, ROLE_ESCAPES), F.lit(AFTER_ROLE))
    rows = conversations.select(
        "conv_id", F.col("turn").cast("long").alias("turn"), role.alias("role"), text.alias("text"),
        F.coalesce(F.floor(F.col("turn") / STRETCH), F.lit(-1)).cast("long").alias("stretch"),
    ).withColumns({"head": head, "body": escape(F.col("text"))})
    rows = rows.withColumn("piece", F.concat("head", "body", F.lit(CLOSE)))
    inside = Window.partitionBy("conv_id", "stretch").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumns({
        "start": F.coalesce(F.sum(F.length("piece").cast("long")).over(inside), F.lit(0)),
        "position": F.count("piece").over(inside),
    })
    totals = rows.groupBy("conv_id", "stretch").agg(F.sum(F.length("piece").cast("long")).alias("chars"), F.count("*").alias("turns"))
    earlier = Window.partitionBy("conv_id").orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(
        F.col("conv_id").alias("c"), F.col("stretch").alias("s"),
        F.coalesce(F.sum("chars").over(earlier), F.lit(0)).alias("chars"), F.coalesce(F.sum("turns").over(earlier), F.lit(0)).alias("turns"),
    )
    joined = rows.join(totals, F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("stretch") == F.col("s")))
    start = F.col("start") + F.col("chars")
    return joined.select(
        "conv_id", (F.col("position") + F.col("turns")).alias("position"), start.alias("start"), "piece", (F.col("role") == TRAINABLE).alias("is_target"),
        (start + F.length("head")).alias("body_start"), (start + F.length("head") + F.length("body")).alias("body_end"),
    )


def examples(formatted: DataFrame) -> DataFrame:
    """One row per assistant turn: its context is the conversation's first context_end characters, of which none is trainable, and the
    characters from target_start to target_end are."""
    return formatted.where("is_target").select(
        "conv_id", F.col("position").alias("example"), F.col("start").alias("context_end"), F.col("body_start").alias("target_start"),
        F.col("body_end").alias("target_end"), F.substring("piece", F.col("body_start") - F.col("start") + 1, F.col("body_end") - F.col("body_start")).alias("target"),
    )


def expand(formatted: DataFrame) -> DataFrame:
    """The examples with their contexts written out: conv_id, example, context, target (with its closing mark), mask (ranges)."""
    e = examples(formatted).drop("target")
    parts = e.join(formatted.select("conv_id", "position", "piece"), "conv_id").where("position <= example")
    ordered = parts.groupBy("conv_id", "example", "context_end", "target_start", "target_end").agg(F.sort_array(F.collect_list(F.struct("position", "piece"))).alias("p"))
    pieces = F.transform("p", lambda x: x["piece"])
    return ordered.select(
        "conv_id", "example", F.array_join(F.slice(pieces, 1, F.size("p") - 1), "").alias("context"), F.element_at(pieces, -1).alias("target"),
        F.array(F.struct(F.col("target_start").alias("start"), F.col("target_end").alias("end"))).alias("mask"),
    )


def parse(formatted_text: Column) -> Column:
    """The turns of a formatted conversation as structs (role, text)."""
    marked = F.split(formatted_text, F.lit(CLOSE), -1)

    def turn(piece: Column) -> Column:
        cut = F.split(piece, AFTER_ROLE, 2)
        return F.struct(
            unescape(F.substring(F.get(cut, F.lit(0)), len(OPEN) + 1, 1 << 30), ROLE_ESCAPES).alias("role"), unescape(F.get(cut, F.lit(1))).alias("text")
        )

    return F.transform(F.filter(marked, lambda p: p != ""), turn)


def op9_chat_prefix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    extra = spark.sql(r"SELECT -7L AS conv_id, turn, role, r'\### Assistant: </turn> ok' AS text FROM VALUES (0L, 'user'), (1L, 'assistant') AS t(turn, role)")
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", F.col("turn").cast("long").alias("turn"), "role", "text").unionByName(extra)
    formatted = materialise(format_turns(rows), "formatted")
    made = materialise(examples(formatted).drop("target"), "examples")
    # what follows knows only the two outputs: formatted pieces of conversations, and examples with the ranges that are trainable
    got = formatted.select("conv_id", "position", "start", "piece").join(
        made.select(F.col("conv_id").alias("c"), "example", "target_start", "target_end"), F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("position") == F.col("example")), "left"
    )
    masked = F.substring("piece", F.col("target_start") - F.col("start") + 1, F.col("target_end") - F.col("target_start"))
    whole = got.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("position", "piece", masked.alias("loss")))).alias("p"), F.count("example").alias("n_examples"))
    text = F.array_join(F.transform("p", lambda x: x["piece"]), "")
    loss = unescape(F.array_join(F.transform("p", lambda x: F.coalesce(x["loss"], F.lit(""))), ""))
    back = whole.select("conv_id", parse(text).alias("turns"), loss.alias("loss"), F.length(text).cast("long").alias("formatted_chars"), "n_examples")
    lines = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(lines, 256).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars", "n_examples",
    )


ORACLE_OP9 = r"""
WITH c AS (
  SELECT conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, t.turn, t.role, '\### Assistant: </turn> ok' FROM (VALUES (0, 'user'), (1, 'assistant')) AS t(turn, role)
), g AS (
  SELECT conv_id, count(*) AS n_turns,
    string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS whole,
    coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, text) FILTER (role = 'assistant'), '') AS loss,
    sum(15 + 2 * (length(role) + length(text)) - length(regexp_replace(role, '[\\#<:]', '', 'g')) - length(regexp_replace(text, '[\\#<]', '', 'g'))) AS formatted,
    count(*) FILTER (role = 'assistant') AS n_examples
  FROM c GROUP BY conv_id
)
SELECT conv_id, n_turns, sha256(whole) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars, sha256(loss) AS loss_sha256,
  CAST(formatted AS BIGINT) AS formatted_chars, n_examples
FROM g
"""
