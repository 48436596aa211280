"""Reproducible draws. Every random choice is a hash of what it is about, so a task that is run again draws the same.

md5 over text is what other engines can repeat. fast=True takes Spark's 64-bit hash over the values themselves, which costs a fraction of
it and stays inside generated code: the choice for large graphs."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

RANGE = 1 << 32


def _columns(parts) -> list[Column]:
    return [p if isinstance(p, Column) else F.lit(p) for p in parts]


def digest(*parts, fast: bool = False) -> Column:
    """Something to order by: md5 of the parts, joined by bars, or a 64-bit hash."""
    if fast:
        return F.xxhash64(*_columns(parts))
    return F.md5(F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]))


def draw(*parts, fast: bool = False) -> Column:
    """A whole number below RANGE."""
    if fast:
        return F.shiftrightunsigned(F.xxhash64(*_columns(parts)), 32)
    return F.conv(F.substring(digest(*parts), 1, 8), 16, 10).cast("long")


def uniform(*parts, fast: bool = False) -> Column:
    """A double inside (0, 1)."""
    return (draw(*parts, fast=fast) + F.lit(0.5)) / F.lit(float(RANGE))


def below(share: float, *parts) -> Column:
    """True for about that share of draws; whole numbers are compared, so engines agree at the edge."""
    return draw(*parts) < F.lit(int(share * RANGE))


def race(weight: Column, *parts, fast: bool = False) -> Column:
    """Exponential race: the smallest keys are a sample without replacement, with probabilities in proportion to the weights."""
    return -F.log(uniform(*parts, fast=fast)) / weight
