"""Schemas of the frames that operators exchange, and the checks made where frames come in."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructField, StructType

WORKLOAD = StructType([StructField("row_id", LongType()), StructField("col_id", LongType()), StructField("n", LongType())])
LENGTHS = StructType([StructField("id", LongType()), StructField("len", LongType())])
GROUPS = StructType([StructField("id", LongType()), StructField("grp", IntegerType())])
BLOCKS = StructType([StructField("m", IntegerType()), StructField("n", IntegerType()), StructField("diag", IntegerType()), StructField("cost", LongType())])
VOCAB = StructType([StructField("word_id", LongType()), StructField("word", StringType()), StructField("df", LongType()), StructField("cf", LongType())])
STAMPS = StructType([StructField("row_id", LongType()), StructField("stamps", ArrayType(IntegerType()))])


class WorkloadError(ValueError):
    """A frame that isn't a workload matrix."""


def require_columns(df: DataFrame, *names: str) -> DataFrame:
    if missing := [c for c in names if c not in df.columns]:
        raise WorkloadError(f"missing columns: {', '.join(missing)}; there are {', '.join(df.columns)}")
    return df


def check_workload(workload: DataFrame) -> DataFrame:
    """Raise unless the frame has cells, all with ids and positive counts, each once. One pass and one shuffle."""
    require_columns(workload, "row_id", "col_id", "n")
    bad = workload.agg(
        F.count(F.lit(1)).alias("cells"),
        F.count_if(F.col("row_id").isNull() | F.col("col_id").isNull()).alias("null ids"),
        F.count_if(F.col("n").isNull() | (F.col("n") <= 0)).alias("counts not above 0"),
    ).first()
    if not bad["cells"]:
        raise WorkloadError("the workload is empty")
    for what in ("null ids", "counts not above 0"):
        if bad[what]:
            raise WorkloadError(f"{bad[what]} cells with {what}")
    if not workload.groupBy("row_id", "col_id").count().filter("count > 1").isEmpty():
        raise WorkloadError("a cell occurs more than once")
    return workload


def whole_numbers(column):
    """A double as BIGINT; fails where it is no whole number."""
    exact = F.col(column).cast("bigint") if isinstance(column, str) else column.cast("bigint")
    original = F.col(column) if isinstance(column, str) else column
    return F.when(original.isNull() | (exact == original), exact).otherwise(F.raise_error(F.lit("a count is no whole number")).cast("bigint"))
