"""Uniform draws out of large relations without gathering or sorting them in one place.

Rows are numbered once, within hash buckets, and a draw is an equi-join on the number. A sample
without replacement of t out of n takes one row out of each of t neighbouring ranges of numbers:
every row has the same chance up to the ranges' rounding, the weight of a row is its range's size,
and no two draws meet, so nothing has to be ranked or compared.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patcard.functions.hashing import portable_int

#: Buckets in which rows are numbered; their sizes are the only thing that is summed in one place.
BUCKETS = 4096


def numbered(rows: DataFrame, *cols: str, tag: str = "a") -> DataFrame:
    """Distinct rows with a number idx from 0 on: numbers within hash buckets, moved up by the sizes of the buckets before (BUCKETS rows)."""
    cols = cols or tuple(rows.columns)
    dealt = rows.withColumn("bk", F.pmod(portable_int(F.lit(tag), *[F.col(c) for c in cols]), F.lit(BUCKETS)))
    sizes = dealt.groupBy("bk").agg(F.count("*").alias("m"))
    before = sizes.select("bk", F.coalesce(F.sum("m").over(Window.orderBy("bk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("up"))
    within = dealt.withColumn("rn", F.row_number().over(Window.partitionBy("bk").orderBy(*cols)) - 1)
    return within.join(F.broadcast(before), "bk").select(*rows.columns, (F.col("up") + F.col("rn")).cast("long").alias("idx"))


def sized(callers: DataFrame, pool: DataFrame) -> DataFrame:
    """Callers with __m, the number of rows of the pool (one row, broadcast); none if the pool is empty."""
    return callers.crossJoin(F.broadcast(pool.agg(F.count("*").alias("__m")))).where("__m > 0")


def draw_ranges(callers: DataFrame, t: Column, *key: Column) -> DataFrame:
    """For each caller (with __m) t numbers below __m in column idx, one out of each of t equal ranges, and __share, the size of the number's range."""
    each = callers.withColumn("__t", t).withColumn("__j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__t") - 1)))
    lo, hi = F.expr("(__j * __m) div __t"), F.expr("((__j + 1) * __m) div __t")
    each = each.withColumn("__lo", lo).withColumn("__share", hi - F.col("__lo"))
    return each.withColumn("idx", F.col("__lo") + F.pmod(portable_int(*key, F.col("__j")), F.col("__share"))).drop("__t", "__j", "__lo")


def picked(callers: DataFrame, rows: DataFrame, *cols: str, tag: str = "a") -> DataFrame:
    """callers.join(numbered(rows, ...), "idx") for few callers: only those buckets that hold a number asked for are numbered, so the rows are looked at, not moved."""
    cols = cols or tuple(rows.columns)
    dealt = rows.withColumn("bk", F.pmod(portable_int(F.lit(tag), *[F.col(c) for c in cols]), F.lit(BUCKETS)))
    sizes = dealt.groupBy("bk").agg(F.count("*").alias("m"))
    before = sizes.select("bk", "m", F.coalesce(F.sum("m").over(Window.orderBy("bk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("up"))
    asked = callers.join(F.broadcast(before), (F.col("idx") >= F.col("up")) & (F.col("idx") < F.col("up") + F.col("m"))).withColumn("rn", (F.col("idx") - F.col("up")).cast("int")).drop("m", "up")
    within = dealt.join(F.broadcast(asked.select("bk").distinct()), "bk").withColumn("rn", (F.row_number().over(Window.partitionBy("bk").orderBy(*cols)) - 1))
    return asked.join(within, ["bk", "rn"]).drop("bk", "rn")
