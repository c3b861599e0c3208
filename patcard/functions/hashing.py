"""Sampling keys that any engine can recompute: md5 over plain integers, so that a sample is a value, not an accident of a run."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def portable_key(*parts: Column | int | str) -> Column:
    """md5 of the parts joined by bars; sorting by it is a random order that depends on nothing else."""
    return F.md5(F.concat_ws("|", *[(p if isinstance(p, Column) else F.lit(p)).cast("string") for p in parts]))


def portable_int(*parts: Column | int | str) -> Column:
    """60 random bits as a number, from the same digest."""
    return F.conv(F.substring(portable_key(*parts), 1, 15), 16, 10).cast("long")


def hash01(*parts: Column | int | str) -> Column:
    """A uniform number in [0, 1)."""
    return portable_int(*parts) / F.lit(float(1 << 60))


def branch_size(n: Column, k: int | None, adaptive: bool = True) -> Column:
    """How many of n candidates to follow at branching factor 1/k: ceil(n / k) in whole numbers.

    adaptive: all of up to four, and four at least beyond. k None: one, a walk without branches.
    """
    if k is None:
        return F.lit(1).cast("long")
    t = F.expr("1L") * F.floor((n + F.lit(k - 1)) / F.lit(k))
    t = t.cast("long")
    return F.when(n <= 4, n).otherwise(F.greatest(F.lit(4).cast("long"), t)) if adaptive else t
