"""Labels that depend on a vertex and on its neighbours, so that rows of other ranks matter."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import dyadic


def planted(edges: DataFrame, features: DataFrame, width: int = 16, classes: int = 6, weight: float = 8.0) -> DataFrame:
    """(vid, label): the class with the largest score of the own row plus weight times that of the neighbours' mean row."""
    mean = edges.join(features.withColumnRenamed("vid", "src"), "src").groupBy(F.col("dst").alias("vid")).agg(F.array(*[F.avg(F.get("x", F.lit(k))) for k in range(width)]).alias("m"))
    scores = [
        sum((F.get("x", F.lit(k)) * dyadic(k, c, 3) + weight * F.get("m", F.lit(k)) * dyadic(k, c, 11) for k in range(width)), F.lit(0.0)) for c in range(classes)
    ]
    both = features.join(mean, "vid")
    ranked = F.array(*scores)
    return both.select("vid", F.expr("0").alias("z"), ranked.alias("s")).select("vid", (F.array_position("s", F.array_max("s")) - 1).cast("int").alias("label"))
