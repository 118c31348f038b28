"""Online workloads: event streams into cells, stamps and groups."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from topicgrid.operators.cut import prefix_tokens
from topicgrid.operators.lengths import rank_desc
from topicgrid.sources.shared import stored

def event_stream(spark: SparkSession, path: str, schema: StructType, files_per_trigger: int = 1) -> DataFrame:
    """Events from a folder of Parquet files as they come."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def with_time(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Events with ts as a timestamp and a watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def online_workload(events: DataFrame) -> DataFrame:
    """row_id (user), col (event type), n; for update or complete mode, and for a batch alike."""
    return events.groupBy(F.col("user_id").cast("bigint").alias("row_id"), F.col("event_type").alias("col")).agg(F.count(F.lit(1)).alias("n"))


def window_stamps(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """row_id, stamp (seconds at the window's start), n: tumbling, or sliding with ``slide``, windows as timestamps of users."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(F.col("user_id").cast("bigint").alias("row_id"), w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("row_id", F.unix_timestamp("w.start").alias("stamp"), "n")


def session_stamps(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """row_id, stamp (seconds at the session's start), n."""
    s = F.session_window("ts", gap)
    return events.groupBy(F.col("user_id").cast("bigint").alias("row_id"), s.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("row_id", F.unix_timestamp("w.start").alias("stamp"), "n")


def without_repeats(events: DataFrame) -> DataFrame:
    """Each event_id once within the watermark (a stream) or at all (a batch)."""
    return events.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def placed_online(events: DataFrame, groups: int) -> DataFrame:
    """row_id, grp, n: users are dealt to groups by hash, and keep their totals in state; update mode.

    A user's group never changes, so blocks that were written stay valid. Loads are not looked at: a skewed stream stays uneven, which
    ``Placement`` avoids.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        grp = ((int(key[0]) * 0x9E3779B97F4A7C15) & (2**64 - 1)) >> 32
        yield pd.DataFrame({"row_id": [key[0]], "grp": [grp * groups >> 32], "n": [n]})

    keyed = events.select(F.col("user_id").cast("bigint").alias("row_id"))
    return keyed.groupBy("row_id").applyInPandasWithState(update, "row_id bigint, grp int, n bigint", "n bigint", "update", GroupStateTimeout.NoTimeout)


class Placement:
    """Rows that keep their group, new ones in the lightest groups: a foreachBatch sink.

    Of a micro-batch's new rows, in order of falling length, each group gets a run of about as many tokens as it lacks to the level at which all
    groups would stand; the driver sees P loads, never rows. Rows and their tokens go to ``path`` under the batch's number, so a batch
    that is repeated overwrites itself.
    """

    def __init__(self, spark: SparkSession, path: str, groups: int):
        self.spark, self.path, self.groups = spark, path, groups

    def rows(self, before: int | None = None) -> DataFrame:
        """row_id, grp, n of all batches, or of those before one."""
        try:
            seen = self.spark.read.parquet(self.path)
        except AnalysisException:  # nothing has been placed yet
            return self.spark.createDataFrame([], "row_id bigint, grp int, n bigint")
        seen = seen if before is None else seen.filter(F.col("batch") < before)
        return seen.groupBy("row_id").agg(F.min("grp").alias("grp"), F.sum("n").alias("n"))

    def loads(self, before: int | None = None) -> list[int]:
        held = {r.grp: int(r.s) for r in self.rows(before).groupBy("grp").agg(F.sum("n").alias("s")).collect()}
        return [held.get(g, 0) for g in range(self.groups)]

    @staticmethod
    def shares(loads: list[int], tokens: int) -> list[float]:
        """How many of ``tokens`` each group gets so that the lightest are lifted to one level."""
        order = sorted(range(len(loads)), key=lambda g: (loads[g], g))
        out, level, left = [0.0] * len(loads), 0.0, float(tokens)
        for k in range(1, len(order) + 1):
            level = (left + sum(loads[g] for g in order[:k])) / k
            if k == len(order) or level <= loads[order[k]]:
                for g in order[:k]:
                    out[g] = level - loads[g]
                break
        return out

    def place(self, batch: DataFrame, number: int) -> None:
        """``batch``: row_id, n, a row each."""
        known = self.rows(number)
        old = batch.join(known.select("row_id", "grp"), "row_id").select("row_id", "grp", "n")
        new = stored(batch.join(known, "row_id", "left_anti"), "placing")
        loads = self.loads(number)
        for r in old.groupBy("grp").agg(F.sum("n").alias("s")).collect():
            loads[r.grp] += int(r.s)
        ends = [0.0]
        for share in self.shares(loads, int(new.agg(F.sum("n")).first()[0] or 0)):
            ends.append(ends[-1] + share)
        # the run in which the middle of a row falls
        placed = prefix_tokens(rank_desc(new.select(F.col("row_id").alias("id"), F.col("n").alias("len"))).withColumn("pos", F.col("rank")))
        edges = F.array(*(F.lit(float(e)) for e in ends[1:-1])) if self.groups > 1 else F.array().cast("array<double>")
        grp = F.size(F.filter(edges, lambda e: e <= F.col("before") + F.col("len") / 2)).cast("int")
        both = old.unionByName(placed.select(F.col("id").alias("row_id"), grp.alias("grp"), F.col("len").alias("n")))
        both.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{self.path}/part={number:08d}")

    def run(self, events: DataFrame, checkpoint: str) -> StreamingQuery:
        """Place the users of all files there are now, then stop; called again it goes on from the checkpoint."""
        users = lambda b: b.groupBy(F.col("user_id").cast("bigint").alias("row_id")).agg(F.count(F.lit(1)).alias("n"))
        return events.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(lambda b, e: self.place(users(b.filter("user_id IS NOT NULL")), e)).start()

    def drift(self) -> DataFrame:
        """batch, heaviest, mean, balance (mean over heaviest) after each micro-batch: how even the groups stay."""
        seen = self.spark.read.parquet(self.path).groupBy("batch", "grp").agg(F.sum("n").alias("n"))
        every = seen.select("batch").distinct().crossJoin(self.spark.range(self.groups).select(F.col("id").cast("int").alias("grp")))  # batches by P
        upto = Window.partitionBy("grp").orderBy("batch")
        run = every.join(seen, ["batch", "grp"], "left").withColumn("load", F.sum(F.coalesce("n", F.lit(0))).over(upto))
        return run.groupBy("batch").agg(F.max("load").alias("heaviest"), F.avg("load").alias("mean")).withColumn("balance", F.col("mean") / F.col("heaviest"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that came after the watermark and were left out, over all progress that the query still holds."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in json.loads(p.json if hasattr(p, "json") else json.dumps(p)).get("stateOperators", []))


def merge_cells(batch: DataFrame, epoch: int, path: str) -> None:
    """foreachBatch sink: the cells that a micro-batch changed, under its number; ``latest_cells`` reads the newest of each. A repeated batch overwrites itself."""
    batch.withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{path}/batch={epoch:08d}")


def latest_cells(spark: SparkSession, path: str) -> DataFrame:
    keys = ("row_id", "col")
    return spark.read.parquet(path).groupBy(*keys).agg(F.max_by("n", "epoch").alias("n"))


def run_workload(events: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """Keep a workload of all files there are now, then stop; called again it goes on from the checkpoint."""
    return online_workload(events).writeStream.outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(lambda b, e: merge_cells(b, e, path)).start()
