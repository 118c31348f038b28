"""The corpus pipeline: from ``documents`` to packed training sequences, one operator a stage.

Each stage works on all that the one before kept. Null and empty texts pass the filters only if the quality
network accepts them; texts that line dedup empties stay as empty documents. Sizes and copies are those of the mix, so the
last stage packs a document as often as the mix takes it. Columns beside those of ``documents`` pass through under any names; rows
that repeat are rows each; empty tables give empty ones at every stage.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from topicgrid.llm.common import Passing, Scratch, read, small_enough
from topicgrid.llm.line_dedup import line_dedup
from topicgrid.llm.mixing import mixed_documents
from topicgrid.llm.near_dedup import BROADCAST_IDS, near_dedup
from topicgrid.llm.packing import pack_documents
from topicgrid.llm.quality import score_quality, train_quality


def named(docs: DataFrame, *roles: str) -> tuple[Passing, DataFrame]:
    """``docs`` with the columns of these roles called so, and all others by names that clash with nothing."""
    own = Passing.of(docs, roles)
    at = {k: role for role, k in own.at.items()}
    return own, own.frame.toDF(*(at.get(k, c) for k, c in enumerate(own.frame.columns)))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; null and empty texts share one score, very long texts are scored whole."""
    net = train_quality(docs, read(spark, sf_dir, "labels"))
    own, docs = named(docs, "text")
    return score_quality(docs, net).filter("predicted = 1").select(*docs.columns).toDF(*own.names)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of a line that 10 documents or more have, only the first document keeps it, once. Null texts become empty."""
    own, docs = named(docs, "doc_id", "text", "n_chars")
    out = line_dedup(docs, min_docs=10, min_points=1, keep="first")
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns).toDF(*own.names)


def with_row_keys(scratch: Scratch, docs: DataFrame) -> DataFrame:
    """``docs`` with row: the doc_id, or for each row without one a number of its own above all doc_ids.

    These are numbered by a hash of all columns, so which of several copies stays doesn't depend on where they lie.
    """
    with_id = docs.filter("doc_id IS NOT NULL").withColumn("row", F.col("doc_id").cast("long"))
    bare = docs.filter("doc_id IS NULL")
    if bare.isEmpty():
        return with_id
    order = (F.xxhash64(*docs.columns), F.rand(7))  # equal rows may lie in several tasks
    dealt = bare.withColumns({"h": order[0], "r": order[1]}).repartitionByRange("h", "r").sortWithinPartitions("h", "r")
    bare = scratch.table(dealt.drop("h", "r").withColumn("at", F.monotonically_increasing_id()), "bare")
    task = F.shiftright("at", 33)
    first, starts = (docs.agg(F.max(F.col("doc_id").cast("long"))).first()[0] or 0) + 1, {}
    for r in sorted(bare.groupBy(task.alias("task")).count().collect()):
        starts[r[0]], first = first, first + r[1]
    start = F.element_at(F.create_map(*(F.lit(x).cast("bigint") for kv in starts.items() for x in kv)), task)
    return with_id.unionByName(bare.withColumn("row", start + F.col("at") - F.shiftleft(task, 33)).drop("at"))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one with the smallest doc_id; one without only where none has one.

    Texts without words, null ones too, are near to nothing and stay. Of rows that share the doc_id that stays the least by text does.
    """
    scratch = Scratch(spark, "pipeline-near")
    own, docs = named(docs, "doc_id", "text")
    columns = docs.columns
    docs = with_row_keys(scratch, docs)
    found = scratch.table(near_dedup(docs.select(F.col("row").alias("doc_id"), "text")).withColumnRenamed("doc_id", "row"), "found")
    gone = found.filter(~F.col("kept")).select("row").distinct()
    if small_enough(gone, BROADCAST_IDS):
        gone = F.broadcast(gone)
    left = docs.join(gone, "row", "left_anti")
    twice = found.filter("kept").groupBy("row").count().filter("count > 1").select("row")
    if not twice.isEmpty():  # rows that share the id that stays: the least by text
        order = Window.partitionBy("row").orderBy("text", *[c for c in columns if c not in ("doc_id", "text")])
        one = left.join(twice, "row").withColumn("at", F.row_number().over(order)).filter("at = 1").select(*left.columns)
        left = left.join(twice, "row", "left_anti").select(*left.columns).unionByName(one)
    return left.select(*columns).toDF(*own.names)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources in the proportions 5, 2, 1, repeating, each at most 3 times; a row for each copy taken. Null texts have no words."""
    own, docs = named(docs, "doc_id", "text", "source")
    return mixed_documents(docs, weights=(5, 2, 1), cap=3).select(*docs.columns).toDF(*own.names)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces and their places in sequences of 2,048 tokens; null texts are a token each, only longer ones than a sequence are cut."""
    return pack_documents(docs, with_ids=False).select("doc_id", "row_no", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", quality),
    ("line_dedup", lines),
    ("near_dedup", near_copies),
    ("mixing", mixture),
    ("packing", packing),
]

#: A trained network, hashes of shingles and a tokenizer are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each is written as Parquet and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = read(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = scratch.table(stage(spark, docs, sf_dir), f"{k}_{name}")
        if k > 1:
            scratch.drop(f"{k - 2}_{STAGES[k - 2][0]}")
    return docs
