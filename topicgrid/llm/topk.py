"""Exact top-k inner products by an impact-ordered, score-at-a-time index.

The index of a block of vectors has a posting list for every dimension, cut into segments by quantised value. A
query gives each segment an impact: what its bound adds to the least that its dimension gives anyone, quantised to
``IMPACTS`` levels. Segments are processed level by level from the highest; every posting read adds its impact to its
vector's accumulator. After each level the accumulators and the level bound all scores from above; vectors whose bound
lies below the k-th best exact score so far are out for good. Processing stops only when that proof leaves few, or when all
postings are read; what is left, and nothing else, is rescored exactly.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from topicgrid.llm.common import Scratch, picked, tidy

LEVELS = 16  # segments of a posting list
IMPACTS = 24
FEW = 16  # processing ends when a proof leaves one row in so many
BLOCK_ROWS = 16_384
QUERY_ROWS = 20_000  # in one broadcast, and on the driver
SAFE = 2.0**52


def quantised(arr: pa.Array) -> tuple[np.ndarray, list[np.ndarray]]:
    """Rows that take part, and floor(256 * x) of their components; null or non-finite ones leave a row out."""
    rows, out = [], []
    for k, v in enumerate(arr):
        x = v.values
        if x is None or x.null_count:
            continue
        x = x.to_numpy(zero_copy_only=False).astype(np.float64)
        if np.isfinite(x).all():
            rows.append(k)
            out.append(np.floor(256 * x))
    return np.array(rows, np.int64), out


def stacked(vectors: list[np.ndarray], dims: int) -> np.ndarray:
    """As one array; shorter vectors end in zeros."""
    out = np.zeros((len(vectors), dims))
    for k, v in enumerate(vectors):
        out[k, : len(v)] = v
    return out


class ImpactIndex:
    """Posting segments of a block: in each dimension ``LEVELS`` ranges of value, from low to high."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids, self.v = ids[order], vectors[order]
        n, self.dims = self.v.shape
        self.postings = np.ascontiguousarray(np.argsort(self.v, axis=0, kind="stable").T.astype(np.int32))
        self.cuts = np.unique(np.linspace(0, n, min(LEVELS, n) + 1).astype(np.int64))
        by_value = np.take_along_axis(self.v.T, self.postings.astype(np.int64), 1)
        self.low, self.high = by_value[:, self.cuts[:-1]], by_value[:, self.cuts[1:] - 1]
        self.largest = float(np.abs(self.v).max(initial=0))
        self.flat = self.postings.ravel()
        sizes = np.diff(self.cuts)
        self.size = np.tile(sizes, self.dims)
        self.start = (np.arange(self.dims)[:, None] * n + self.cuts[:-1]).ravel()

    def postings_of(self, segments: np.ndarray) -> np.ndarray:
        return np.concatenate([self.flat[a : a + n] for a, n in zip(self.start[segments].tolist(), self.size[segments].tolist(), strict=True)])

    def search(self, q: np.ndarray, own: int, k: int, floor: float) -> tuple[np.ndarray, np.ndarray, int, int]:
        """Ids and scores of rows that may be among the k best; none that scores ``floor`` or more is missed. With them
        how many rows were rescored and how many postings read."""
        n = len(self.ids)
        if self.largest * np.abs(q).max(initial=0) * self.dims >= SAFE:  # doubles would not be exact
            wide = [min(max(sum(int(a) * int(b) for a, b in zip(v, q, strict=True)), -(2**63)), 2**63 - 1) for v in self.v]
            rows = np.array(sorted((r for r in range(n) if self.ids[r] != own), key=lambda r: (-wide[r], self.ids[r]))[:k], np.int64)
            return self.ids[rows], np.array([wide[r] for r in rows], np.int64), n, 0
        up = q[:, None] * np.where((q >= 0)[:, None], self.high, self.low)
        least = up.min(axis=1)
        impact = (up - least[:, None]).ravel()
        step = max(impact.max(initial=0) / IMPACTS, 1e-9)
        level = np.ceil(impact / step).astype(np.int64)
        base = float(least.sum())
        gained, read = np.zeros(n), np.zeros(n, np.int64)
        alive = np.flatnonzero(self.ids != own)
        exact = np.full(n, np.nan)
        threshold, seen = floor, 0
        order = np.argsort(-level, kind="stable")
        ends = np.searchsorted(-level[order], -np.arange(IMPACTS, 0, -1), side="right")  # level 0 adds nothing
        for at, (a, b) in enumerate(zip(np.concatenate([[0], ends[:-1]]).tolist(), ends.tolist(), strict=True)):
            if len(alive) <= max(4 * k, n // FEW):  # proven: all others are out; these cost less to rescore than to read on
                break
            if a == b:
                continue
            segments = order[a:b]
            rows = self.postings_of(segments)
            seen += len(rows)
            gained += np.bincount(rows, np.repeat(impact[segments], self.size[segments]), minlength=n)
            read += np.bincount(rows, minlength=n)
            bound = base + gained[alive] + (self.dims - read[alive]) * (step * (IMPACTS - 1 - at))
            # a few of the most promising get their exact scores, which lifts the threshold
            first = alive[np.argpartition(-bound, 2 * k)[: 2 * k]]
            first = first[np.isnan(exact[first])]
            exact[first] = self.v[first] @ q
            known = exact[~np.isnan(exact)]
            if len(known) >= k:
                threshold = max(threshold, float(np.partition(known, -k)[-k]))
            alive = alive[bound >= threshold - 0.5]  # scores are whole numbers; bounds carry rounding errors far below a half
        todo = alive[np.isnan(exact[alive])]
        exact[todo] = self.v[todo] @ q
        alive = alive[exact[alive] >= threshold]
        best = alive[np.lexsort((self.ids[alive], -exact[alive]))[:k]]
        return self.ids[best], exact[best].astype(np.int64), int((~np.isnan(exact)).sum()), seen


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", query_rows: int = QUERY_ROWS) -> DataFrame:
    """query_id, rank (from 1), id, score, for each row of ``queries`` (same columns), against all rows of ``vectors``.

    Scores are integer inner products of floor(256 * x); ties go to the smaller id. Null vectors and ids, and
    vectors with null or non-finite components, take no part; shorter vectors count as ending in zeros. Rows with the query's own id are no
    candidates of it; rows that repeat an id are candidates each, and queries each. A query with fewer candidates than k gets all; empty tables
    give empty results. Other columns aren't read. Products beyond 64 bits saturate.

    The driver holds and broadcasts about ``query_rows`` queries at a time, one after the other; candidates lie in blocks of ``BLOCK_ROWS``,
    and a task sends at most k rows a query. What each round of queries finds is written to the shared folder.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "topk")
    slim = lambda df: picked(df, id=id_col, v=vector_col).select(F.col("id").cast("long").alias("id"), F.col("v").cast("array<double>").alias("v")).filter("id IS NOT NULL AND v IS NOT NULL")
    asked = slim(queries)
    rounds = max(1, -(-asked.count() // query_rows))
    dealt = slim(vectors)
    n = dealt.count()
    dealt = scratch.table(dealt.repartition(max(1, -(-n // BLOCK_ROWS))), "vectors")
    if rounds > 1:
        asked = scratch.table(asked.withColumn("round", F.pmod(F.xxhash64("id"), F.lit(rounds)).cast("int")).repartition("round"), "queries")
    found = None
    for c in range(rounds):
        mine = asked.filter(F.col("round") == c).select("id", "v") if rounds > 1 else asked
        done = _search(dealt, mine.toArrow(), c, k)
        if rounds > 1:
            done = scratch.table(done, f"round{c}")
        found = done if found is None else found.unionByName(done)
    best = Window.partitionBy("round", "number").orderBy(F.desc("score"), "id")
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "id", "score")


def _search(dealt: DataFrame, asked: pa.Table, number: int, k: int) -> DataFrame:
    asked = asked.sort_by("id").combine_chunks()
    rows, vectors = quantised(asked.column("v").combine_chunks() if asked.num_rows else pa.array([], pa.list_(pa.float64())))
    ids = asked.column("id").to_numpy()[rows] if asked.num_rows else np.empty(0, np.int64)
    sent = dealt.sparkSession.sparkContext.broadcast((ids, stacked(vectors, max((len(v) for v in vectors), default=0))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, qs = sent.value
        best: list[list[tuple[int, int]]] = [[] for _ in own]

        def search(ids: list[np.ndarray], vs: list[np.ndarray]) -> None:
            dims = max(qs.shape[1], max((len(v) for v in vs), default=0))
            index = ImpactIndex(np.concatenate(ids), stacked(vs, dims))
            for j, (i, q) in enumerate(zip(own.tolist(), qs, strict=True)):
                floor = -best[j][k - 1][0] if len(best[j]) >= k else -np.inf
                got, score, *_ = index.search(np.pad(q, (0, dims - len(q))), i, k, floor)
                best[j] = sorted([*best[j], *zip((-score).tolist(), got.tolist(), strict=True)])[:k]

        held_ids: list[np.ndarray] = []
        held: list[np.ndarray] = []
        for batch in batches:
            r, v = quantised(batch.column(1))
            held_ids.append(batch.column(0).to_numpy()[r])
            held += v
            if len(held) >= BLOCK_ROWS:
                search(held_ids, held)
                held_ids, held = [], []
        if held:
            search(held_ids, held)
        flat = [(number, j, int(own[j]), i, -s) for j, b in enumerate(best) for s, i in b]
        kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array([f[c] for f in flat], t) for c, t in enumerate(kinds)], names=["round", "number", "query_id", "id", "score"])

    return dealt.mapInArrow(tidy(run), "round int, number int, query_id bigint, id bigint, score bigint")
