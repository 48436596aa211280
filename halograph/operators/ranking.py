"""Running sums over long groups without one task for a group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import stage

#: rows up to which a group's order is found by one window
ONE_TASK = 1_000_000


def running(df: DataFrame, group: str, order: list[tuple[str, bool]], **sums: Column) -> DataFrame:
    """df with running sums (their row included) over each group in the order of columns (name, whether it falls), which must be total.

    Few rows go through one window for each group. More are range-sorted over the cluster first: a window then covers no more than a
    group's rows in one range, and what stands before comes from sums of (range, group), of which there are no more than ranges and groups."""
    sort = [F.desc(name) if falls else F.asc(name) for name, falls in order]
    upto = (Window.unboundedPreceding, 0)
    values = {f"_{k}": v for k, v in sums.items()}
    if df.count() <= ONE_TASK:
        w = Window.partitionBy(group).orderBy(*sort).rowsBetween(*upto)
        return df.withColumns(values).withColumns({k: F.sum(f"_{k}").over(w) for k in sums}).drop(*values)
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = stage(df.withColumns(values).repartitionByRange(n, F.col(group), *sort).withColumn("_range", F.spark_partition_id()), "ranged")
    totals = ranged.groupBy(group, "_range").agg(*[F.sum(f"_{k}").alias(f"_t{k}") for k in sums])
    earlier = Window.partitionBy(group).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    base = totals.select(group, "_range", *[F.coalesce(F.sum(f"_t{k}").over(earlier), F.lit(0)).alias(f"_b{k}") for k in sums])
    inside = Window.partitionBy(group, "_range").orderBy(*sort).rowsBetween(*upto)
    got = ranged.withColumns({k: F.sum(f"_{k}").over(inside) for k in sums}).join(base, [group, "_range"])
    return got.withColumns({k: F.col(k) + F.col(f"_b{k}") for k in sums}).select(*df.columns, *sums)
