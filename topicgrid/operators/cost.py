"""Block, epoch and total cost, and the load-balancing ratio."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BROADCAST_GROUPS = 4_000_000


def diagonal(m: Column, n: Column, groups: int) -> Column:
    return F.pmod(n - m, F.lit(groups)).cast("int")


def grid(spark, groups: int) -> DataFrame:
    """m, n of all blocks: P * P rows from a range."""
    return spark.range(groups * groups).select((F.col("id") / groups).cast("int").alias("m"), (F.col("id") % groups).cast("int").alias("n"))


def block_costs(matrix: DataFrame, row_groups: DataFrame, col_groups: DataFrame, groups: int, how: str | None = None) -> DataFrame:
    """m, n, diag, cost of all P * P blocks, absent ones 0.

    ``how`` forces a join strategy ("broadcast", "merge", "shuffle_hash") on both sides; without it the sizes that Spark
    knows decide, again at run time. Costs are summed map-side: a task sends P * P rows at most.
    """
    rows = row_groups.select(F.col("id").alias("row_id"), F.col("grp").alias("m"))
    cols = col_groups.select(F.col("id").alias("col_id"), F.col("grp").alias("n"))
    if how:
        rows, cols = rows.hint(how), cols.hint(how)
    cells = matrix.withColumnRenamed("n", "tokens").join(cols, "col_id").join(rows, "row_id")
    sums = cells.groupBy("m", "n").agg(F.sum("tokens").alias("cost"))
    full = grid(matrix.sparkSession, groups).join(sums, ["m", "n"], "left")
    return full.select("m", "n", diagonal(F.col("m"), F.col("n"), groups).alias("diag"), F.coalesce("cost", F.lit(0)).alias("cost"))


def epoch_costs(blocks: DataFrame) -> DataFrame:
    """diag, cost: an epoch takes as long as its heaviest block."""
    return blocks.groupBy("diag").agg(F.max("cost").alias("cost"))


def eta(blocks: DataFrame, groups: int) -> DataFrame:
    """One row: tokens, total_cost, optimum, eta, speedup. Without tokens eta is null."""
    per = blocks.groupBy("diag").agg(F.max("cost").alias("c"), F.sum("cost").alias("s"))
    out = per.agg(F.sum("s").alias("tokens"), F.sum("c").alias("total_cost"))
    out = out.withColumn("optimum", F.col("tokens").cast("double") / groups)
    return out.withColumn("eta", F.expr("try_divide(optimum, total_cost)")).withColumn("speedup", F.col("eta") * groups)


def idle(blocks: DataFrame) -> DataFrame:
    """m, n, diag, cost, idle: how long each block's process waits for the heaviest of its epoch."""
    heaviest = F.max("cost").over(Window.partitionBy("diag"))
    return blocks.withColumn("idle", heaviest - F.col("cost"))


def eta_ceiling(row_lens: DataFrame, col_lens: DataFrame, groups: int) -> DataFrame:
    """tokens, longest_row, longest_col, ceiling: no grouping can do better than N / P over the longest row or column."""
    r = row_lens.agg(F.sum("len").alias("tokens"), F.max("len").alias("longest_row"))
    out = r.crossJoin(col_lens.agg(F.max("len").alias("longest_col")))  # one row each
    share = F.col("tokens").cast("double") / groups
    return out.withColumn("ceiling", F.least(F.lit(1.0), share / F.greatest("longest_row", "longest_col")))


def group_ceiling(row_groups: DataFrame, col_groups: DataFrame, groups: int) -> DataFrame:
    """ceiling of a given grouping: each group meets every diagonal once, so C is at least its heaviest group."""
    r = row_groups.groupBy("grp").agg(F.sum("len").alias("s")).agg(F.sum("s").alias("tokens"), F.max("s").alias("row_max"))
    c = col_groups.groupBy("grp").agg(F.sum("len").alias("s")).agg(F.max("s").alias("col_max"))
    return r.crossJoin(c).withColumn("ceiling", F.col("tokens").cast("double") / groups / F.greatest("row_max", "col_max"))


def group_skew(groups_of: DataFrame, groups: int) -> DataFrame:
    """One row: min, max, mean and deviation of the groups' tokens, and how many are empty."""
    sums = groups_of.groupBy("grp").agg(F.sum("len").alias("s"))
    full = groups_of.sparkSession.range(groups).select(F.col("id").cast("int").alias("grp")).join(sums, "grp", "left").withColumn("s", F.coalesce("s", F.lit(0)))
    return full.agg(F.min("s").alias("min_tokens"), F.max("s").alias("max_tokens"), F.avg("s").alias("mean_tokens"), F.round(F.stddev_pop("s"), 6).alias("sd_tokens"), F.count_if(F.col("s") == 0).alias("empty"))


def memory_model(documents: int, words: int, topics: int, groups: int, bytes_each: int = 8) -> dict[str, int]:
    """Bytes of counts: the diagonal scheme has one copy of each matrix, replication one of topic-word counts a process."""
    theta, phi = documents * topics * bytes_each, words * topics * bytes_each
    return {"diagonal": theta + phi, "replica": theta + groups * phi}


def barriers(groups: int) -> dict[str, int]:
    """Synchronisations an iteration."""
    return {"diagonal": groups, "replica": 1}
