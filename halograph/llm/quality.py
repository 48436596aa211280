"""Quality rules: a table of thresholds that is compiled into one Spark projection, without user functions.

Null text counts as empty, so it has no words, fails the base rule and isn't kept. An empty table gives an empty result. Rows are
judged one by one: repeated rows and repeated ids each keep their own verdict. Nothing is shuffled, whatever the skew.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let, unused

WORD = r"[^\x20\x09-\x0D]+"
SYMBOLS = "[#*$%&|<>]"
WINDOW = 5

# Frequent function words of English, German, French and Spanish.
STOP_WORDS = (
    "the of and to in a is that for it as was with be by on not he i this are or his from at which "
    "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine "
    "de la le et les des en un du une que est pour qui dans par sur au avec "
    "el los y del se las por con no su para como más pero sus"
).split()


@dataclass(frozen=True)
class Rule:
    """A document fails where it has at least from_words words and its measure lies outside [least, most]."""

    name: str
    measure: str
    least: float | None = None
    most: float | None = None
    from_words: int = 0


#: The method's own thresholds; the base rule on length and repeats comes before them.
RULES = (
    Rule("mean_word_length", "word_chars / n_words", least=2.0, most=14.0, from_words=10),
    Rule("symbol_ratio", "n_symbols / n_words", most=0.5, from_words=10),
    Rule("duplicate_line_ratio", "n_dup_lines / n_lines", most=0.45, from_words=10),
    Rule("stop_word_ratio", "n_stop_words / n_words", least=0.01, from_words=60),
)


def _repeat_words(words: Column) -> Column:
    """Number of words that lie in a window of five words found twice or more in the text."""
    hashes = F.transform(
        F.sequence(F.lit(0), F.size(words) - WINDOW), lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(WINDOW)])
    )

    def covered(h: Column) -> Column:
        ranked = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("x"), i.alias("i"))))
        places = let(
            ranked,
            lambda s: F.sort_array(
                F.transform(
                    F.filter(s, lambda e, i: (e["x"] == F.get(s, i - 1)["x"]) | (e["x"] == F.get(s, i + 1)["x"])),
                    lambda e: e["i"],
                )
            ),
        )
        total = let(
            places,
            lambda p: F.aggregate(
                F.transform(p, lambda at, i: F.coalesce(F.least(F.get(p, i + 1) - at, F.lit(WINDOW)), F.lit(WINDOW))),
                F.lit(0).cast("long"),
                lambda a, b: a + b,
            ),
        )
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(total)

    return F.when(F.size(words) < WINDOW, F.lit(0).cast("long")).otherwise(let(hashes, covered))


def measures(text: Column) -> Column:
    """All measures of one text as a struct; each is computed once."""
    whole = F.coalesce(text, F.lit(""))
    words = F.regexp_extract_all(whole, F.lit(WORD), F.lit(0))
    lines = F.filter(F.split(whole, "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))

    def of(w: Column) -> Column:
        return F.struct(
            F.size(w).cast("long").alias("n_words"),
            F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
            (F.length(whole) - F.length(F.regexp_replace(whole, SYMBOLS, ""))).cast("long").alias("n_symbols"),
            _repeat_words(w).alias("n_repeat_words"),
            F.size(F.filter(w, lambda x: F.lower(x).isin(*STOP_WORDS))).cast("long").alias("n_stop_words"),
            let(
                lines,
                lambda x: F.struct(
                    F.size(x).cast("long").alias("n_lines"),
                    (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
                ),
            ).alias("line"),
        )

    return let(words, of)


def compile_rules(rules: tuple[Rule, ...], column: dict[str, Column]) -> Column:
    """The rules as one boolean expression: true where none fails."""

    def passes(rule: Rule) -> Column:
        top, _, bottom = rule.measure.partition(" / ")
        value = F.try_divide(column[top], column[bottom]) if bottom else column[top]
        tests = [value >= F.lit(rule.least)] * (rule.least is not None) + [value <= F.lit(rule.most)] * (rule.most is not None)
        ok = reduce(lambda a, b: a & b, tests)
        return (column["n_words"] < F.lit(rule.from_words)) | F.coalesce(ok, F.lit(True))

    return reduce(lambda a, b: a & b, [passes(r) for r in rules], F.lit(True))


def score(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text", name: str = "quality") -> DataFrame:
    """The input's columns and a struct called `name` with every measure, base_failed and kept. A column of that name is replaced."""
    got = docs.withColumn(name, measures(docs[text]))
    q = F.col(name)
    column = {n: q[n] for n in ("n_words", "word_chars", "n_symbols", "n_repeat_words", "n_stop_words")}
    column |= {n: q["line"][n] for n in ("n_lines", "n_dup_lines")}
    failed = (column["n_words"] < 10) | (100 * column["n_repeat_words"] > 20 * column["n_words"])
    return got.withColumn(
        name,
        F.struct(*[c.alias(n) for n, c in column.items()], failed.alias("base_failed"), (~failed & compile_rules(rules, column)).alias("kept")),
    )


def keep(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows that pass, with the columns of the input, whatever their names."""
    name = unused(docs, "quality")
    return score(docs, rules, name=name).where(F.col(name)["kept"]).select(*docs.columns)


def op4_quality_rules(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    q = F.col("quality")
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
    return score(docs).select("doc_id", *[q[n].alias(n) for n in names])


_STOP_SQL = ", ".join(f"'{w}'" for w in dict.fromkeys(STOP_WORDS))
ORACLE_OP4 = rf"""
WITH w AS (
  SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents
), win AS (
  SELECT doc_id, unnest(range(1, len(words) - 3)) AS pos, words FROM w WHERE len(words) >= 5
), marked AS (
  SELECT doc_id, pos, count(*) OVER (PARTITION BY doc_id, array_to_string(words[pos:pos + 4], ' ')) AS n FROM win
), gaps AS (
  SELECT doc_id, least(5, coalesce(lead(pos) OVER (PARTITION BY doc_id ORDER BY pos) - pos, 5)) AS c FROM marked WHERE n > 1
), rep AS (
  SELECT doc_id, sum(c) AS n FROM gaps GROUP BY doc_id
), m AS (
  SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(length(array_to_string(words, '')) AS BIGINT) AS word_chars,
    CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
    CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words,
    len(list_filter(words, lambda x: lower(x) IN ({_STOP_SQL}))) AS n_stop,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines
  FROM w LEFT JOIN rep USING (doc_id)
), f AS (
  SELECT *, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
    n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND word_chars / n_words BETWEEN 2.0 AND 14.0 AND n_symbols / n_words <= 0.5
    AND n_dup_lines / len(lines) <= 0.45 AND (n_words < 60 OR n_stop / n_words >= 0.01) AS kept
FROM f
"""
