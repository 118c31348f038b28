"""Exact dedup with a heavy-hitter split.

Each text is hashed once. Misra-Gries summaries of every task name the digests that may be frequent; these are
counted exactly, and the winners of the frequent ones go to every task as a broadcast of at most ``counters``
rows, so their copies are settled map-side and never meet in one task. All other digests shuffle as usual, pre-aggregated.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.llm.common import WHITE, Scratch, picked, texts, tidy


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, row_no (unique), digest (SHA-256 of the text without white space), n_points (of the whole text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = TaskContext.get().partitionId() << 33
        for batch in batches:
            raw = texts(batch.column(1))
            sha = [hashlib.sha256(t.translate(None, WHITE)).digest() for t in raw]
            points = [len(t) if t.isascii() else len(t.decode()) for t in raw]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.arange(at, at + len(raw))), pa.array(sha, pa.binary()), pa.array(points, pa.int64())], names=["doc_id", "row_no", "digest", "n_points"])
            at += len(raw)

    slim = picked(docs, doc_id=id_col, text=text_col)
    return slim.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), "doc_id bigint, row_no bigint, digest binary, n_points bigint")


def misra_gries(items: Iterator, k: int) -> dict:
    """At most k counters; what occurs more than n / (k + 1) times among n items is among them."""
    held: dict = {}
    for x in items:
        if x in held:
            held[x] += 1
        elif len(held) < k:
            held[x] = 1
        else:
            held = {y: c - 1 for y, c in held.items() if c > 1}
    return held


def frequent(hashed: DataFrame, counters: int) -> DataFrame:
    """digest: at most ``counters`` candidates, among them all that make up over 2 / counters of the rows.

    Each task sends its counters; a digest with more than n / (counters + 1) of a task's rows is in that task's
    summary, and lower bounds add up over tasks.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = misra_gries((d for b in batches for d in b.column(0).to_pylist()), counters)
        pairs = [(d, c) for d, c in held.items() if c > 1]
        yield pa.RecordBatch.from_pydict({"digest": pa.array([d for d, _ in pairs], pa.binary()), "n": pa.array([c for _, c in pairs], pa.int64())})

    found = hashed.select("digest").mapInArrow(tidy(run), "digest binary, n bigint")
    return found.groupBy("digest").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "digest").limit(counters).select("digest")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", counters: int = 256) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256 (hex), n_points.

    Texts are equal when identical without ``[\\x20\\x09-\\x0D]``; null counts as empty, so null, empty and blank
    texts are one group. Of a group the row with most code points stays, then the smallest doc_id; a null doc_id
    comes after all others, and of rows that tie in both exactly one stays. ``keep_id`` is null only if all ids of the
    winning length are. Empty tables give empty results; other columns are not read.
    """
    scratch = Scratch(docs.sparkSession, "exact")
    hashed = scratch.table(digests(docs, id_col, text_col), "hashed")
    order = F.struct("n_points", (-F.col("doc_id")).alias("less"), (-F.col("row_no")).alias("first"))
    gathered = [F.max(order).alias("top"), F.count(F.lit(1)).alias("group_size")]
    heavy = scratch.table(frequent(hashed, counters), "heavy")
    winners = scratch.table(hashed.join(F.broadcast(heavy), "digest").groupBy("digest").agg(*gathered), "winners")
    settled = hashed.join(F.broadcast(winners), "digest")
    rest = hashed.join(F.broadcast(heavy), "digest", "left_anti")
    light = rest.join(rest.groupBy("digest").agg(*gathered).hint("merge"), "digest")
    return settled.unionByName(light).select("doc_id", (-F.col("top.less")).alias("keep_id"), "group_size", (F.col("row_no") == -F.col("top.first")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), "n_points")
