"""Topic assignments, counts, estimates and training perplexity, in Catalyst expressions.

Counts are arrays of length K. Topics are 0 .. K - 1.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from topicgrid.functions.rng import key


def init_topics(matrix: DataFrame, topics: int, seed: int = 7, axis: str = "word") -> DataFrame:
    """row_id, col_id, n, z: a topic for each of a cell's tokens, uniform by hash of (row, column, occurrence)."""
    cell = F.concat_ws("/", F.col("row_id").cast("string"), F.col("col_id").cast("string"))
    draw = lambda i: (key(seed, axis, "topic", 0, F.concat_ws("/", cell, i.cast("string"))) % topics).cast("int")
    return matrix.select("row_id", "col_id", "n", F.transform(F.sequence(F.lit(1), F.col("n").cast("int")), draw).alias("z"))


def topic_counts(assigned: DataFrame, by: str, topics: int) -> DataFrame:
    """``by``, c: how many tokens of each topic a row or a column has. Summed by topic map-side, so a hot column is K rows a task."""
    per = assigned.select(by, F.explode("z").alias("k")).groupBy(by, "k").agg(F.count(F.lit(1)).alias("t"))
    return per.groupBy(by).agg(F.map_from_entries(F.collect_list(F.struct("k", "t"))).alias("m")).select(by, _dense("m", topics).alias("c"))


def _dense(m: str, topics: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(topics - 1)), lambda k: F.coalesce(F.try_element_at(F.col(m), k), F.lit(0).cast("bigint")))


def sparse_counts(assigned: DataFrame, by: str) -> DataFrame:
    """``by``, c: the same as a map from topic to count, without zeros; for large K."""
    per = assigned.select(by, F.explode("z").alias("k")).groupBy(by, "k").agg(F.count(F.lit(1)).alias("t"))
    return per.groupBy(by).agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("k", "t")))).alias("c"))


def add_arrays(by: list[str], counts: DataFrame, topics: int) -> DataFrame:
    """Sums of count arrays, element by element; K plain sums, combined map-side."""
    sums = counts.groupBy(*by).agg(*(F.sum(F.element_at("c", k + 1)).alias(f"c{k}") for k in range(topics)))
    return sums.select(*by, F.array(*(f"c{k}" for k in range(topics))).alias("c"))


def topic_totals(counts: DataFrame, topics: int) -> DataFrame:
    """One row, c: tokens of each topic over all rows or columns."""
    return add_arrays([], counts, topics)


def theta(counts: DataFrame, topics: int, alpha: float) -> DataFrame:
    """row_id, p: smoothed topic shares of each document."""
    total = F.aggregate("c", F.lit(0).cast("bigint"), lambda a, x: a + x)
    return counts.select("row_id", F.transform("c", lambda x: (x + alpha) / (total + topics * alpha)).alias("p"))


def phi(counts: DataFrame, totals: DataFrame, size: int, beta: float, by: str = "col_id") -> DataFrame:
    """``by``, p: smoothed probability of the word (or stamp) in each topic. ``totals`` is one row of K numbers, broadcast."""
    held = counts.crossJoin(F.broadcast(totals.select(F.col("c").alias("t"))))
    return held.select(by, F.zip_with("c", "t", lambda x, t: (x + beta) / (t + size * beta)).alias("p"))


def perplexity(matrix: DataFrame, theta_: DataFrame, phi_: DataFrame) -> DataFrame:
    """One row, tokens and perplexity: exp of minus the mean log likelihood of the word tokens, cells weighted by n."""
    rows = theta_.select("row_id", F.col("p").alias("t"))
    cols = phi_.select("col_id", F.col("p").alias("f"))
    like = F.aggregate(F.zip_with("t", "f", lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x)
    cells = matrix.join(rows, "row_id").join(cols, "col_id").select("n", (F.log(like) * F.col("n")).alias("ll"))
    return cells.agg(F.sum("n").alias("tokens"), F.sum("ll").alias("ll")).select("tokens", F.exp(-F.col("ll") / F.col("tokens")).alias("perplexity"))


def model_perplexity(matrix: DataFrame, theta_counts: DataFrame, phi_counts: DataFrame, topics: int, alpha: float, beta: float) -> DataFrame:
    words = phi_counts.count()
    return perplexity(matrix, theta(theta_counts, topics, alpha), phi(phi_counts, topic_totals(phi_counts, topics), words, beta))


def top_words(phi_: DataFrame, k: int, by: str = "col_id") -> DataFrame:
    """topic, rank, id, p (rounded to 9 places), ties by id; a top-k per task before the shuffle."""
    long = phi_.select(F.posexplode("p").alias("topic", "p"), F.col(by).alias("id"))
    best = Window.partitionBy("topic").orderBy(F.desc("p"), "id")
    return long.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("topic", "rank", "id", F.round("p", 9).alias("p"))


def topic_timeline(pi: DataFrame) -> DataFrame:
    """stamp, topic, p: how each topic is spread over the stamps."""
    return pi.select(F.col("col_id").alias("stamp"), F.posexplode("p").alias("topic", "p"))


def dominant_topic(theta_: DataFrame) -> DataFrame:
    """row_id, topic, p: the largest share of each document, ties to the smaller topic."""
    best = F.array_max(F.transform("p", lambda p, k: F.struct(p.alias("p"), (-k).alias("k"))))
    return theta_.select("row_id", (-best.k).cast("int").alias("topic"), best.p.alias("p"))
