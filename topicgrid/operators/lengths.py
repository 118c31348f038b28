"""Row and column lengths, their extremes and their order."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from topicgrid.functions.rng import key
from topicgrid.sources.shared import stored

BUCKET_BITS = 12  # of ids, counted apart for each length
RANGE = 262_144  # items that a task sorts where ranks are written


def lengths(matrix: DataFrame, axis: str) -> DataFrame:
    """id, len. Reads two of the three columns; partial sums make a hot column one row a task."""
    return matrix.groupBy(F.col(f"{axis}_id").alias("id")).agg(F.sum("n").alias("len"))


def extremes(lens: DataFrame, k: int, longest: bool = True) -> DataFrame:
    """The k longest or shortest, ties by id; a top-k per task, merged."""
    return lens.orderBy(F.desc("len") if longest else F.asc("len"), "id").limit(k)


def with_bucket(df: DataFrame, column: str, name: str = "bucket") -> DataFrame:
    """``df`` with a bucket that follows the order of a BIGINT column: its leading bits within the range that occurs, 4,097 buckets at most.

    So dense ids and hashes are both cut into many even buckets. The range is one row, joined to all.
    """
    span = df.agg(F.min(column).alias("lo"), F.max(column).alias("hi"))
    width = F.log2(F.col("hi").cast("double") - F.col("lo").cast("double") + 1)
    span = span.select("lo", F.greatest(F.lit(0), F.ceil(width).cast("int") - BUCKET_BITS).alias("shift"))
    return df.crossJoin(F.broadcast(span)).withColumn(name, F.expr(f"shiftright({column}, shift) - shiftright(lo, shift)")).drop("lo", "shift")


def rank_desc(lens: DataFrame, tie: str = "id", seed: int = 7, mode: str = "two_level", axis: str = "row") -> DataFrame:
    """id, len, rank (1 = longest), size (items), total (tokens).

    Ties go by id or by a seeded hash, then by id. "window" sorts in one task. "two_level" counts items by length and tie bucket,
    adds up over the distinct lengths (of which N tokens allow at most the square root of 2 N) and ranks inside each
    bucket, so no task holds more than a bucket.
    """
    order = F.col("id") if tie == "id" else key(seed, axis, "tie", 0, F.col("id"))
    keyed = lens.withColumn("tie", order)
    if mode == "window":
        every = Window.partitionBy()
        rank = F.row_number().over(Window.orderBy(F.desc("len"), "tie", "id"))
        return keyed.select("id", "len", rank.cast("bigint").alias("rank"), F.count(F.lit(1)).over(every).alias("size"), F.sum("len").over(every).alias("total"))
    if mode != "two_level":
        raise ValueError("mode is window or two_level")
    # a hash of 48 bits needs no look at its range
    keyed = with_bucket(keyed, "tie") if tie == "id" else keyed.withColumn("bucket", F.shiftrightunsigned("tie", 48 - BUCKET_BITS))
    small = keyed.groupBy("len", "bucket").agg(F.count(F.lit(1)).alias("c"))
    by_len = small.groupBy("len").agg(F.sum("c").alias("c"))
    before = Window.orderBy(F.desc("len")).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    above = by_len.select("len", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("above"), F.sum("c").over(every).alias("size"), F.sum(F.col("c") * F.col("len")).over(every).alias("total"))
    inside = Window.partitionBy("len").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = small.select("len", "bucket", F.coalesce(F.sum("c").over(inside), F.lit(0)).alias("base")).join(above, "len")
    rank = F.row_number().over(Window.partitionBy("len", "bucket").orderBy("tie", "id"))
    return keyed.withColumn("inner", rank).join(base, ["len", "bucket"]).select("id", "len", (F.col("above") + F.col("base") + F.col("inner")).cast("bigint").alias("rank"), "size", "total")


def rank_stored(lens: DataFrame) -> DataFrame:
    """``rank_desc`` with ties by id, written.

    Lengths are written, dealt out by ranges of (length, id) and numbered within each; what is counted of the ranges tells the rest. That is a few
    short plans with neither windows nor joins, so the driver plans, compiles and keeps account of far less.
    """
    lens = stored(lens.select("id", "len"), "lengths")
    every = lens.agg(F.count(F.lit(1)).alias("size"), F.sum("len").alias("total"))
    kind, all_ = every.schema["total"].dataType, every.first()
    order = (F.desc("len"), F.asc("id"))
    dealt = lens.repartitionByRange(max(1, -(-all_["size"] // RANGE)), *order).sortWithinPartitions(*order)
    placed = stored(dealt.select("id", "len", F.monotonically_increasing_id().alias("at")), "placed")  # the range, then 33 bits for the place in it
    counts = {r.range: r.c for r in placed.groupBy(F.shiftright("at", 33).alias("range")).agg(F.count(F.lit(1)).alias("c")).collect()}
    before = [0]
    for k in range(max(counts, default=0)):
        before.append(before[-1] + counts.get(k, 0))
    above = F.array(*(F.lit(x).cast("bigint") for x in before))[F.shiftright("at", 33).cast("int")]
    rank = above + F.col("at").bitwiseAND(F.lit((1 << 33) - 1)) + 1
    whole = placed.filter("id IS NOT NULL AND len IS NOT NULL")  # what has no id or length takes a rank that nothing shows
    return whole.select("id", "len", rank.alias("rank"), F.lit(all_["size"]).cast("bigint").alias("size"), F.lit(all_.total).cast(kind).alias("total"))
