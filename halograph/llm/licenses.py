"""License scans, in DataFrame functions only: sparse TF-IDF cosine to templates, then inheritance from the nearest ancestor directory.

Headers are passages of a whole text that hold a license cue, wherever they stand: sentences of its lines and, where a sentence is long,
windows of it. Each distinct passage is scored once, by joining its tokens with the templates' weights. License files are scored whole as
well, as vectors of all their tokens, against whole license texts: a document is one where its file name says so or where license passages
make up a good part of its words. A document's own license is the best of its passages and, for a license file, of the whole; a
directory's license is that of its best license file. A document without a license of its own takes it from the nearest ancestor
directory that has one: distinct directories are exploded into their ancestors and joined with the licensed ones by path, and documents
join the outcome by directory, in salted parts.

Inverse document frequencies count all distinct passages of the table. A word that no template has weighs as if it stood in one of them;
in a window, whose ends are arbitrary, such words don't count, but more of the template must be there. Null text has no passage; a null
path has no directory and so inherits nothing. Ties go to the higher score, then to the template that stands first. Repeated rows
each get their result; an empty table gives an empty one; other columns of the input are left out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialise
from .license_texts import FILES, TEMPLATES

#: cosine from which a passage counts as its template, and a window of a longer sentence, which also needs so many of the template's words
SIMILAR, SIMILAR_WINDOW, WINDOW_WORDS = 0.6, 0.75, 4
#: words from which a sentence is cut into windows, and the windows: (words, from one to the next)
LONG, WINDOWS = 24, ((10, 2), (40, 8))
#: share of a document's words that stand in license lines, from which it is a license file
FILE_SHARE = 0.3
SALTS = 16
#: distinct license files up to which their hashes are sent to all tasks, 64 bytes each; more are joined by a shuffle
FEW_FILES = 200_000

CUE = (
    r"(?i)licen[cs]|copyright|permission|redistribut|\bcc[ -]by\b|\bcc0\b|public domain|warrant(?:y|ies)\b|unencumbered"
)
FILE_NAME = r"(?i)(?:^|/)(?:licen[cs]e|copying|notice)(?:\.[a-z]+)?$"


def tokens(text: Column) -> Column:
    """Lower-case words and version numbers."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"[a-z]+[0-9]*|[0-9]+(?:\.[0-9]+)*"), F.lit(0))


def templates(spark: SparkSession, rows: tuple[tuple[str, str], ...] = TEMPLATES) -> DataFrame:
    quoted = lambda t: "'" + t.replace("\\", "\\\\").replace("'", "\\'") + "'"
    values = ", ".join(f"({i}, {quoted(n)}, {quoted(t)})" for i, (n, t) in enumerate(rows))
    return spark.sql(f"SELECT * FROM VALUES {values} AS t(template, license, text)")


def passages(docs: DataFrame, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(id, at, line, cut, words) for every passage with a cue, of whole texts: at is the line's number, line the passage, cut whether it
    is a window, words how many it adds to the document's license words."""
    rows = docs.where(docs[text].rlike(CUE)).select(F.col(id_col).alias("id"), F.posexplode(F.split(docs[text], "\r?\n")).alias("at", "whole")).where(F.col("whole").rlike(CUE))
    rows = rows.select("id", "at", F.explode(F.split("whole", r"(?<=[.;!?])\s+(?=[\p{Lu}(\"'])")).alias("sentence")).where(F.col("sentence").rlike(CUE))
    rows = rows.withColumn("w", F.regexp_extract_all("sentence", F.lit(r"\S+"), F.lit(0)))
    whole = F.array(F.struct(F.col("sentence").alias("line"), F.lit(False).alias("cut"), F.size("w").alias("words")))

    def windows(n: int, step: int):
        starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.size("w") - n), F.lit(step))
        made = F.transform(starts, lambda i: F.struct(F.array_join(F.slice("w", i + 1, n), " ").alias("line"), F.lit(True).alias("cut"), F.lit(step).alias("words")))
        return F.filter(made, lambda x: x["line"].rlike(CUE))

    cut = F.when(F.size("w") > LONG, F.concat(*[windows(n, step) for n, step in WINDOWS])).otherwise(F.filter(whole, lambda x: F.lit(False)))
    return rows.select("id", "at", F.inline(F.concat(whole, cut)))


def weights(units: DataFrame, shelf: DataFrame, n: int) -> DataFrame:
    """(term, idf) of the templates' words over the distinct passages: at most as many rows as the templates have words."""
    vocabulary = shelf.select(F.explode("terms").alias("term")).distinct()
    known = units.select(F.explode(F.array_distinct("terms")).alias("term")).join(F.broadcast(vocabulary), "term")
    df = known.groupBy("term").agg(F.count("*").alias("df"))
    return vocabulary.join(df, "term", "left").select("term", (F.log(F.lit(float(n)) / (1 + F.coalesce("df", F.lit(0)))) + 1).alias("idf"))


def scored(units: DataFrame, key: str, shelf: DataFrame, weight: DataFrame, n: int) -> DataFrame:
    """(key, license, score, within, shared) of the best template for each unit of (key, terms): score is the cosine; within the one that
    leaves out words that no template has; shared the template's words that are there."""
    rare = F.log(F.lit(float(n) / 2)) + 1

    def vectors(frame: DataFrame, *keys: str) -> DataFrame:
        tf = frame.select(*keys, F.explode("terms").alias("term")).groupBy(*keys, "term").agg(F.count("*").alias("tf"))
        return tf.join(F.broadcast(weight), "term", "left").withColumn("w", (1 + F.log("tf")) * F.coalesce("idf", rare)).select(*keys, "term", "w", F.col("idf").isNotNull().alias("known"))

    norm = Window.partitionBy("template")
    right = vectors(shelf, "template", "license")
    right = right.withColumn("unit", F.col("w") / F.sqrt(F.sum(F.col("w") * F.col("w")).over(norm))).select("template", "license", "term", "unit")
    left = vectors(units, key)
    square = F.col("w") * F.col("w")
    lengths = left.groupBy(key).agg(F.sqrt(F.sum(square)).alias("length"), F.sqrt(F.sum(F.when(F.col("known"), square).otherwise(0.0))).alias("inner"))
    dots = left.join(F.broadcast(right), "term").groupBy(key, "template", "license").agg(F.sum(F.col("w") * F.col("unit")).alias("dot"), F.count("*").alias("shared"))
    every = dots.join(lengths, key).withColumns({"score": F.round(F.col("dot") / F.col("length"), 6), "within": F.round(F.col("dot") / F.col("inner"), 6)})
    best = every.groupBy(key).agg(F.max(F.struct("score", (-F.col("template")).alias("t"), "license", "within", "shared")).alias("b"))
    return best.select(key, "b.license", "b.score", "b.within", "b.shared")


def _shelf(spark: SparkSession, rows: tuple[tuple[str, str], ...]) -> DataFrame:
    return templates(spark, rows).withColumn("terms", tokens(F.col("text")))


def cosines(lines: DataFrame) -> DataFrame:
    """(line, license, score, within, shared) of the best template for each distinct passage of column `line`."""
    spark = lines.sparkSession
    units = materialise(lines.select("line").distinct().withColumn("terms", tokens(F.col("line"))), "lines")
    shelf = _shelf(spark, TEMPLATES)
    n = units.count() + len(TEMPLATES)
    return scored(units, "line", shelf, materialise(weights(units, shelf, n), "idf"), n)


def file_cosines(files: DataFrame, lines: DataFrame) -> DataFrame:
    """(sha, license, score, ...) of the best whole license text for each distinct text of (sha, text). Frequencies count the passages."""
    spark = files.sparkSession
    shelf = _shelf(spark, FILES)
    units = materialise(lines.select("line").distinct().withColumn("terms", tokens(F.col("line"))), "lines")
    n = units.count() + len(FILES)
    whole = files.groupBy("sha").agg(F.first("text").alias("text")).select("sha", tokens(F.col("text")).alias("terms"))
    return scored(whole, "sha", shelf, materialise(weights(units, shelf, n), "idf"), n)


def parent(path: Column) -> Column:
    """The directory of a path, "" at the top; null for null."""
    return F.when(path.contains("/"), F.regexp_replace(path, "/[^/]*$", "")).otherwise(F.when(path.isNotNull(), F.lit("")))


def ancestors(directory: Column) -> Column:
    """A directory and all above it, as structs (depth, dir)."""
    parts = F.split(directory, "/")
    named = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.struct(k.alias("depth"), F.array_join(F.slice(parts, F.lit(1), k), "/").alias("dir")))
    top = F.array(F.struct(F.lit(0).alias("depth"), F.lit("").alias("dir")))
    return F.when(directory == "", top).otherwise(F.concat(top, named))


def scan(docs: DataFrame, path: Column, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """id, path, n_license_lines, own_license, own_score, is_license_file, license, inherited_from (the directory, where inherited)."""
    tagged = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"), path.alias("path"))
    lines = materialise(passages(tagged, "text", "id").distinct(), "found")  # of repeated rows one counts
    best = cosines(lines).where(f"score >= {SIMILAR} OR within >= {SIMILAR_WINDOW} AND shared >= {WINDOW_WORDS}")
    best = materialise(best, "scored")
    good = lines.join(best, "line").where(f"IF(cut, within >= {SIMILAR_WINDOW} AND shared >= {WINDOW_WORDS}, score >= {SIMILAR})")
    value = F.when(F.col("cut"), F.col("within")).otherwise(F.col("score"))
    per_line = good.groupBy("id", "at").agg(F.max(F.struct(value.alias("score"), "license")).alias("b"), F.sum(F.when(~F.col("cut"), F.col("words")).otherwise(0)).alias("full"), F.sum(F.when(F.col("cut"), F.col("words")).otherwise(0)).alias("part"))
    per_doc = per_line.groupBy("id").agg(F.max("b").alias("b"), F.sum(F.greatest("full", "part")).alias("license_words"), F.count("*").alias("n_lines"))
    per_doc = materialise(per_doc, "per-doc")
    narrow = tagged.select("id", "path", F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"\S+"), F.lit(0))).alias("n_words"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("sha"))
    named = F.coalesce(F.col("path").rlike(FILE_NAME), F.lit(False))
    joined = narrow.join(per_doc, "id", "left").withColumn("is_file", named | F.coalesce(F.col("license_words") >= FILE_SHARE * F.col("n_words"), F.lit(False)))
    joined = materialise(joined, "joined")
    files = materialise(joined.where("is_file").select("sha").distinct(), "files")
    files = F.broadcast(files) if files.count() <= FEW_FILES else files  # so only license files' texts are exchanged
    texts = tagged.select(F.sha2(F.coalesce("text", F.lit("")), 256).alias("sha"), "text").join(files, "sha", "left_semi")
    whole = file_cosines(texts, lines).where(F.col("score") >= SIMILAR).select("sha", F.struct("score", "license").alias("f"))
    both = joined.join(whole, "sha", "left").withColumn("b", F.when(F.col("is_file"), F.greatest("b", "f")).otherwise(F.col("b")))
    own = both.select(
        "id", "path", parent(F.col("path")).alias("dir"), F.coalesce("n_lines", F.lit(0)).alias("n_license_lines"), F.col("b.license").alias("own_license"), F.col("b.score").alias("own_score"),
        (F.col("b").isNotNull() & F.col("is_file")).alias("is_license_file"),
    )
    own = materialise(own, "own")
    licensed = own.where("is_license_file").groupBy("dir").agg(F.max(F.struct("own_score", "own_license")).alias("b")).select("dir", F.col("b.own_license").alias("license"))
    above = own.groupBy("dir").count().where("dir IS NOT NULL").select(F.col("dir").alias("leaf"), F.explode(ancestors(F.col("dir"))).alias("a"))
    above = above.select("leaf", F.col("a.depth").alias("depth"), F.col("a.dir").alias("dir"))
    nearest = above.join(licensed, "dir").groupBy("leaf").agg(F.max(F.struct("depth", "license", "dir")).alias("b"))
    nearest = nearest.select(F.col("leaf").alias("dir"), F.col("b.license").alias("given"), F.col("b.dir").alias("giver"), F.explode(F.array(*map(F.lit, range(SALTS)))).alias("salt"))
    salted = own.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int"))
    return salted.join(nearest, ["dir", "salt"], "left").select(
        "id", "path", "n_license_lines", "own_license", "own_score", "is_license_file", F.coalesce("own_license", "given").alias("license"),
        F.when(F.col("own_license").isNull(), F.col("giver")).alias("inherited_from"),
    )


#: documents of the table lie in directories source / language / hundred
DOCUMENT_PATH = "concat(source, '/', lang, '/', CAST(doc_id DIV 100 AS STRING), '/', CAST(doc_id AS STRING), '.txt')"


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source", "lang")
    return scan(docs, F.expr(DOCUMENT_PATH)).withColumnRenamed("id", "doc_id")
