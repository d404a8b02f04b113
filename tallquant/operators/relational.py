"""Relational operators around the engine that Spark has no single call for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, time: str, value: str, out: str, seconds: int = 86_400) -> DataFrame:
    """For each left row the latest right value at or before it, by one union and a running last.

    The running last stays within a bin of ``seconds``, so a hot key is dealt by
    time; what a bin starts with is the last value of the bins before it, one row
    a key and bin.  No pairs are formed.
    """
    bin_of = F.floor(F.unix_timestamp(F.col(time).cast("timestamp")) / seconds)
    l = left.select(by, time, F.lit(1).alias("_side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("_v"), F.struct(*left.columns).alias("_row"))  # noqa: E741
    r = right.select(by, time, F.lit(0).alias("_side"), F.col(value).alias("_v"), F.lit(None).cast(l.schema["_row"].dataType).alias("_row"))
    both = l.union(r).withColumn("_bin", bin_of)
    here = Window.partitionBy(by, "_bin").orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    inside = both.withColumn("_here", F.last("_v", ignorenulls=True).over(here)).where("_side = 1")
    ends = both.groupBy(by, "_bin").agg(F.max_by("_v", F.when(F.col("_v").isNotNull(), F.col(time))).alias("_end"))
    before = Window.partitionBy(by).orderBy("_bin").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select(F.col(by).alias("_by"), F.col("_bin").alias("_at"), F.last("_end", ignorenulls=True).over(before).alias("_carried"))
    rows = inside.join(carried, F.col(by).eqNullSafe(F.col("_by")) & F.col("_bin").eqNullSafe(F.col("_at")), "left")
    return rows.select("_row.*", F.coalesce("_here", "_carried").alias(out))


def range_join(rows: DataFrame, value: str, bands: DataFrame, low: str, high: str) -> DataFrame:
    """Rows with the band [low, high) that holds their value; the bands are a parameter table and broadcast."""
    return rows.join(F.broadcast(bands), (F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


def interval_join(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of one key whose right time lies within ``seconds`` after the left one.

    Time is cut into bins of that length, so a right row meets two bins of its
    key and not the whole key.
    """
    bin_of = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds)
    l = left.withColumn("_bin", bin_of(left_time))  # noqa: E741
    r = right.withColumn("_b", bin_of(right_time)).withColumn("_bin", F.explode(F.array(F.col("_b"), F.col("_b") - 1))).drop("_b")
    near = (F.col(right_time) >= F.col(left_time)) & (F.col(right_time) <= F.col(left_time) + F.make_interval(secs=F.lit(seconds)))
    return l.join(r, [by, "_bin"]).where(near).drop("_bin")


def salted_sum(rows: DataFrame, key: str, value: Column, salts: int = 16) -> DataFrame:
    """Sum by key in two levels: a giant key is dealt over ``salts`` partitions first."""
    salted = rows.select(key, value.alias("_v"), F.pmod(F.xxhash64("row_id"), F.lit(salts)).alias("_salt"))
    return salted.groupBy(key, "_salt").agg(F.sum("_v").alias("_v"), F.count("*").alias("_n")).groupBy(key).agg(F.sum("_v").alias("total"), F.sum("_n").alias("n"))


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Equi-join with a hot key on the big side: its rows are salted, the small side repeated for each salt."""
    b = big.withColumn("_salt", F.pmod(F.xxhash64("row_id"), F.lit(salts)))
    s = small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return b.join(s, [key, "_salt"]).drop("_salt")


def top_per_group(rows: DataFrame, by: str, order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; the rank filter is pushed below the shuffle by the optimizer."""
    return rows.withColumn("_k", F.row_number().over(Window.partitionBy(by).orderBy(*order))).where(F.col("_k") <= k).drop("_k")
