"""Timestamp arrays of documents and their workload matrix."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

GRAINS = ("year", "quarter", "month", "day", "hour")


def stamp_number(ts: Column, grain: str) -> Column:
    """A timestamp as INT: years, or quarters, months, days or hours since 1970."""
    if grain == "year":
        return F.year(ts)
    if grain == "quarter":
        return ((F.year(ts) - 1970) * 4 + F.quarter(ts) - 1).cast("int")
    if grain == "month":
        return ((F.year(ts) - 1970) * 12 + F.month(ts) - 1).cast("int")
    if grain == "day":
        return F.datediff(ts, F.lit("1970-01-01").cast("date"))
    if grain == "hour":
        return (F.datediff(ts, F.lit("1970-01-01").cast("date")) * 24 + F.hour(ts)).cast("int")
    raise ValueError(f"grain is one of {', '.join(GRAINS)}")


def stamp_arrays(dated: DataFrame, row: str, ts: str, grain: str = "month", slots: int = 16, policy: str = "repeat") -> DataFrame:
    """row_id, stamps.

    "repeat": the earliest stamp of a row, ``slots`` times. "proportional": all stamps of a row in shares that make
    ``slots``, by largest remainder, ties to the earlier stamp. "raw": all stamps, as many as there are.
    """
    base = dated.filter(F.col(ts).isNotNull()).select(F.col(row).cast("bigint").alias("row_id"), stamp_number(F.col(ts), grain).alias("stamp"))
    if policy == "repeat":
        return base.groupBy("row_id").agg(F.min("stamp").alias("s")).select("row_id", F.array_repeat("s", slots).alias("stamps"))
    counts = base.groupBy("row_id", "stamp").agg(F.count(F.lit(1)).alias("c"))
    if policy == "raw":
        shares = counts.select("row_id", "stamp", F.col("c").cast("int").alias("k"))
    elif policy == "proportional":
        own = Window.partitionBy("row_id")
        total = F.sum("c").over(own)
        split = counts.select("row_id", "stamp", F.floor(F.col("c") * slots / total).cast("int").alias("q"), (F.col("c") * slots % total).alias("r"))
        left = F.lit(slots) - F.sum("q").over(own)
        at = F.row_number().over(own.orderBy(F.desc("r"), "stamp"))
        shares = split.select("row_id", "stamp", (F.col("q") + F.when(at <= left, 1).otherwise(0)).cast("int").alias("k"))
    else:
        raise ValueError("policy is repeat, proportional or raw")
    runs = F.transform(F.array_sort(F.collect_list(F.struct("stamp", "k"))), lambda x: F.array_repeat(x.stamp, x.k))
    return shares.groupBy("row_id").agg(F.flatten(runs).alias("stamps"))


def stamp_workload(arrays: DataFrame) -> DataFrame:
    """row_id, col_id (the stamp), n."""
    return arrays.select("row_id", F.explode("stamps").alias("s")).groupBy("row_id", F.col("s").cast("bigint").alias("col_id")).agg(F.count(F.lit(1)).alias("n"))
