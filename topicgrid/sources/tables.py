"""Sources: Parquet tables, bag-of-words coordinate text, CSV, JSON lines and ORC."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topicgrid.schema import WORKLOAD, check_workload


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_coordinates(spark: SparkSession, path: str, sep: str = " ", header_lines: int = 0, check: bool = True) -> DataFrame:
    """A workload from lines "row column count". Leading lines of totals, with fewer fields, are dropped by their shape."""
    raw = spark.read.schema("row_id long, col_id long, n long").option("sep", sep).option("mode", "PERMISSIVE").csv(path)
    out = raw.filter(F.col("n").isNotNull()) if header_lines else raw
    return check_workload(out) if check else out


def write_coordinates(matrix: DataFrame, path: str, sep: str = " ") -> None:
    matrix.select("row_id", "col_id", "n").write.mode("overwrite").option("sep", sep).csv(path)


def read_workload(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """A workload in Parquet, ORC, JSON lines or CSV with a header."""
    reader = spark.read.schema(WORKLOAD)
    if kind == "csv":
        reader = reader.option("header", True)
    if kind not in ("parquet", "orc", "json", "csv"):
        raise ValueError("kind is parquet, orc, json or csv")
    return reader.format(kind).load(path)
