"""Two-pass external shuffle into shards.

The first pass scatters rows uniformly into memory-sized buckets by seeded hashes: the shard comes from rendezvous hashing of the id, so
one more shard takes rows only into itself (law `key`), and a second hash deals a shard's rows over its buckets. The second pass reads one
bucket at a time, puts it in Fisher-Yates order under a seed of its own, and writes it. A row's slot is the size of its shard's earlier
buckets plus its place in its own.

The bucket's hash takes the id, the text's checksum and the row's number in the table, so repeated ids and even repeated rows, which the
law keeps in one shard, are spread over its buckets. Row numbers are those of a table's files, which a task that runs again reads alike;
what comes out of other operators is staged first. Null text has size 16 and the checksum of nothing. A null id is an id of its own. An
empty table gives an empty result. A row's columns travel together in one struct, so no name of theirs can clash with the operator's.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import ship_package
from .common import fresh_path, materialise

SHARDS = 40
SEED = 7
BUCKET_BYTES = 16 << 20


def rendezvous(key: Column, shards: int, seed: int = SEED) -> Column:
    """The shard whose hash with the key is the largest."""
    weighed = F.transform(F.sequence(F.lit(0), F.lit(shards - 1)), lambda s: F.struct(F.xxhash64(key, s, F.lit(seed)), s.alias("s")))
    return F.array_max(weighed)["s"]


def _fisher_yates(seed: int):
    def run(bucket: pa.Table) -> pa.Table:
        n = bucket.num_rows
        order = np.lexsort([bucket.column(c).to_numpy() for c in ("number", "tie", "key")])  # the same start, whatever order the network gave
        rng = np.random.Generator(np.random.PCG64([seed, bucket.column("bucket")[0].as_py()]))
        rng.shuffle(order)  # numpy's shuffle is Fisher and Yates's
        out = bucket.select(["row", "shard", "grown", "bucket"]).take(pa.array(order))
        return out.append_column("place", pa.array(np.arange(n, dtype=np.int64)))

    return run


def _read_from_files(df: DataFrame) -> bool:
    """Whether rows come from files with nothing but projections and filters on the way, so that their numbers are the same in every run."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    nodes = {re.sub(r"^[ :+|-]*", "", line).split(" ")[0].split("[")[0] for line in plan.splitlines() if line.strip()}
    return nodes <= {"Project", "Filter", "Relation"}


def shuffle(docs: DataFrame, path: str, shards: int = SHARDS, seed: int = SEED, key: str = "doc_id", text: str = "text", bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """Write docs in shuffled order as Parquet under path, partitioned by shard. Returns what was written: row (a struct of the input's
    columns), shard, grown (the shard with one more), bucket, and place in the bucket; slots() adds the slot."""
    spark = docs.sparkSession
    ship_package(spark)
    docs = docs if _read_from_files(docs) else materialise(docs, "numbered")
    size = F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 16
    total = docs.agg(F.sum(size)).first()[0] or 0
    per_shard = max(1, math.ceil(total / shards / bucket_bytes))
    ahead = docs.select(
        F.struct(*[docs[c] for c in docs.columns]).alias("row"), F.xxhash64(docs[key], F.lit(seed)).alias("key"), F.crc32(F.coalesce(docs[text], F.lit(""))).alias("tie"),
        rendezvous(docs[key], shards, seed).cast("int").alias("shard"), rendezvous(docs[key], shards + 1, seed).cast("int").alias("grown"),
        F.monotonically_increasing_id().alias("number"),
    )
    bucket = F.col("shard") * per_shard + F.pmod(F.xxhash64("key", "tie", "number", F.lit(seed + 1)), F.lit(per_shard))
    ahead = ahead.withColumn("bucket", bucket.cast("int"))
    kind = ahead.select("row", "shard", "grown", "bucket", F.lit(0).cast("long").alias("place")).schema
    done = ahead.groupBy("bucket").applyInArrow(_fisher_yates(seed), kind)
    done.write.partitionBy("shard").parquet(path)
    return spark.read.schema(kind).parquet(path)


#: buckets up to which their first slots are sent to all tasks, 16 bytes each; more are joined by a shuffle
FEW_BUCKETS = 500_000


def slots(written: DataFrame) -> DataFrame:
    """The written rows with `slot`. Only counts of buckets travel, so select the columns that are wanted first."""
    counts = written.groupBy("shard", "bucket").agg(F.count("*").alias("n"))
    counts = materialise(counts, "buckets")
    earlier = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("bucket", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"))
    base = F.broadcast(base) if counts.count() <= FEW_BUCKETS else base
    return written.join(base, "bucket").withColumn("slot", F.col("base") + F.col("place")).drop("base")


def op7_two_pass_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = shuffle(docs, fresh_path(spark, "shards"))
    text = F.col("row.text")
    narrow = rows.select(
        F.col("row.doc_id").alias("doc_id"), (F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 16).alias("size"),
        F.crc32(F.coalesce(text, F.lit(""))).alias("text_crc32"), F.lit("key").alias("law"), "shard", "bucket", "place", F.col("grown").alias("grown_shard"),
    )
    return slots(narrow).select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")
