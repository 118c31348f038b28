"""Sinks: the block store of a grid, groups, tables bucketed for joins, and model exports."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_grid(matrix: DataFrame, row_groups: DataFrame, col_groups: DataFrame, groups: int, path: str) -> None:
    """Cells by diagonal and row group: one file a block, sorted by column, so an epoch reads 1 / P of the tokens."""
    rows = row_groups.select(F.col("id").alias("row_id"), F.col("grp").alias("m"))
    cols = col_groups.select(F.col("id").alias("col_id"), F.col("grp").alias("b"))
    cells = matrix.join(cols, "col_id").join(rows, "row_id").withColumn("diag", F.pmod(F.col("b") - F.col("m"), F.lit(groups)).cast("int"))
    placed = cells.repartitionById(groups, F.col("m")).sortWithinPartitions("diag", "col_id", "row_id")
    placed.write.mode("overwrite").partitionBy("diag").parquet(path)


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int) -> None:
    """A table bucketed by an id, so that later joins on it don't shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def write_groups(row_groups: DataFrame, col_groups: DataFrame, path: str) -> None:
    both = row_groups.select("id", "grp", F.lit("row").alias("axis")).unionByName(col_groups.select("id", "grp", F.lit("col").alias("axis")))
    both.write.mode("overwrite").partitionBy("axis").parquet(path)


def write_model(theta: DataFrame, phi: DataFrame, path: str, kind: str = "parquet") -> None:
    theta.write.mode("overwrite").format(kind).save(f"{path}/theta")
    phi.write.mode("overwrite").format(kind).save(f"{path}/phi")
