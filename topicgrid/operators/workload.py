"""Workload matrices in coordinate form: row_id, col_id, n > 0."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.schema import whole_numbers


def workload(counts: DataFrame, vocab: DataFrame, how: str | None = None) -> DataFrame:
    """Cells of words in the vocabulary. ``how`` names a join strategy; without it the optimiser chooses by size."""
    side = vocab.select("word", F.col("word_id").alias("col_id"))
    side = side.hint(how) if how else side
    return counts.join(side, "word").select("row_id", "col_id", F.col("n").cast("bigint").alias("n"))


def basket_workload(lineitem: DataFrame, orders: DataFrame | None = None, row: str = "o_custkey", col: str = "l_partkey", weight: str | None = "l_quantity") -> DataFrame:
    """Row = buyer or order, column = item, n = sum of ``weight``, or the number of lines without one."""
    facts = lineitem.join(orders.select("o_orderkey", *({row} & set(orders.columns))), F.col("l_orderkey") == F.col("o_orderkey")) if orders is not None else lineitem
    n = F.sum(whole_numbers(weight)) if weight else F.count(F.lit(1))
    return facts.groupBy(F.col(row).cast("bigint").alias("row_id"), F.col(col).cast("bigint").alias("col_id")).agg(n.cast("bigint").alias("n"))


def merged_workload(words: DataFrame, stamps: DataFrame, shift: int) -> DataFrame:
    """Words and stamps in one matrix, with kind; stamp ids are moved above ``shift``, at least the largest word id."""
    return words.select("row_id", "col_id", "n", F.lit("word").alias("kind")).unionByName(stamps.select("row_id", (F.col("col_id") + shift).alias("col_id"), "n", F.lit("stamp").alias("kind")))


def corpus_stats(matrix: DataFrame, stamps: DataFrame | None = None, approximate: bool = False) -> DataFrame:
    """One row: documents, words, tokens, cells; with stamps also how many differ, the first and the last."""
    distinct = F.approx_count_distinct if approximate else F.count_distinct
    out = matrix.agg(distinct("row_id").alias("documents"), distinct("col_id").alias("words"), F.sum("n").alias("tokens"), F.count(F.lit(1)).alias("cells"))
    if stamps is None:
        return out
    times = stamps.agg(distinct("col_id").alias("timestamps"), F.min("col_id").alias("first_stamp"), F.max("col_id").alias("last_stamp"))
    return out.crossJoin(times)  # one row each


def decorrelated(matrix: DataFrame, seed: int) -> DataFrame:
    """Row and column lengths kept, who uses which column redealt at random over all tokens (an ablation).

    Tokens get their columns back in the order of a random key, by ranks of both sides from counts of hash buckets.
    """
    from topicgrid.functions.rng import key
    from topicgrid.operators.permute import ranked_by_hash

    name = F.concat_ws("/", F.col("row_id").cast("string"), F.col("col_id").cast("string"), F.col("i").cast("string"))
    spread = matrix.select("row_id", "col_id", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("i")).withColumn("id", name)
    spread = spread.crossJoin(F.broadcast(matrix.agg(F.sum("n").alias("size")))).withColumn("all", F.lit(0))  # one row: the tokens
    dealt = lambda axis: ranked_by_hash(spread.withColumn("k", key(seed, axis, "redeal", 0, F.col("id"))), ["all"], "k").select(f"{axis}_id", "pos")
    return dealt("row").join(dealt("col"), "pos").groupBy("row_id", "col_id").agg(F.count(F.lit(1)).alias("n"))
