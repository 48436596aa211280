"""Helpers shared by the operators for training-data pipelines: shared storage, bounded look-ups, lambda bindings."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..session import fresh_path, shared_dir, stage  # noqa: F401 - for the operators

def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read again: cuts lineage, and outlives a lost executor."""
    return stage(df, f"llm-{name}")


def observed(df: DataFrame, name: str, **measures: Column) -> tuple[DataFrame, dict]:
    """materialise(), with measures of all rows that are taken while they are written, in no job of their own."""
    got = Observation()
    out = materialise(df.observe(got, *[c.alias(n) for n, c in measures.items()]), name)
    return out, got.get


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind value once and use it many times in body. A plain column used inside a lambda is computed again for every element."""
    return F.transform(F.array(value), body)[0]


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def need(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, so that further columns of the input can't clash with an operator's own."""
    return df.select(*[df[n] for n in names])


def unused(df: DataFrame, name: str) -> str:
    """The name, with underscores until no column of df has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


BLOCK = 256


def prefix_sums(lengths: Column) -> Column:
    """For an array of ints, the sums of what stands before each element."""
    return prefixes(lengths, lambda a, b: a + b)


def prefixes(values: Column, add: Callable[[Column, Column], Column]) -> Column:
    """For an array of ints, what stands before each element, added up from 0. Done in blocks, so long arrays stay close to linear."""

    def of(step: Column) -> Column:
        n_blocks = F.ceil(F.size(step) / BLOCK).cast("int")
        sums = F.transform(F.sequence(F.lit(0), n_blocks - 1), lambda k: F.aggregate(F.slice(step, k * BLOCK + 1, BLOCK), F.lit(0), add))
        bases = let(sums, lambda s: F.transform(s, lambda _, k: F.aggregate(F.slice(s, F.lit(1), k), F.lit(0), add)))
        block = lambda i: F.floor(i / BLOCK).cast("int")
        return let(
            bases,
            lambda base: F.transform(step, lambda _, i: add(F.get(base, block(i)), F.aggregate(F.slice(step, block(i) * BLOCK + 1, i % BLOCK), F.lit(0), add))),
        )

    return F.when(F.size(values) > 0, let(values, of)).otherwise(F.array().cast("array<int>"))
