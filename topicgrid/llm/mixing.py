"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

Each source's documents are permuted by hash and cut into blocks by the hash's leading bits. A source with target T and
size S gets a quota of blocks: whole passes over all of them, and of one more pass as many as come nearest to T. The
vector of quotas is split down a binary tree over the output shards, each time multivariate-hypergeometrically, so the
quotas add up exactly. A shard draws as many of a source's permuted blocks as the tree gives it, from where the shard before it stopped;
what a document contributes is the number of draws that hit its block. Shards order their documents by a second hash.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.llm.common import Passing, Scratch, blocks, picked, tidy, utf8_view

HALF_BITS = 10  # a source has 2 ** 20 blocks; where its quota ends is found in two steps of 2 ** 10 numbers
BLOCKS = 1 << 2 * HALF_BITS
SHARD_WORDS = 20_000_000
MOST_DRAWN = 10**9  # blocks that one multivariate-hypergeometric draw can handle
IS_WHITE = np.zeros(256, bool)
IS_WHITE[[9, 10, 11, 12, 13, 32]] = True


def word_counts(arr: pa.Array) -> np.ndarray:
    """Words ``[^\\x20\\x09-\\x0D]+`` of each row; null: none."""
    data, off = utf8_view(arr)
    n = len(off) - 1
    if not len(data):
        return np.zeros(n, np.int64)
    white = IS_WHITE[data]
    begins = ~white
    begins[1:] &= white[:-1]
    full = off[:-1] < off[1:]
    begins[off[:-1][full]] = ~white[off[:-1][full]]
    total = np.concatenate([[0], np.cumsum(begins, dtype=np.int64)])
    return total[off[1:]] - total[off[:-1]]


def water_fill(sizes: dict, weights: dict, cap: int = 3) -> dict:
    """Targets that share the total of all sizes by weight, none above ``cap`` times its source's size.

    Exact fractions; a source that reaches its cap gets just that, and the rest is shared among the others, until none is above.
    """
    left, open_ = Fraction(sum(sizes.values())), {s for s in sizes if sizes[s]}
    out = {s: Fraction(0) for s in sizes}
    while open_:
        whole = sum(weights[s] for s in open_)
        over = {s for s in open_ if left * weights[s] / whole > cap * sizes[s]}
        if not over:
            out |= {s: left * weights[s] / whole for s in open_}
            break
        for s in over:
            out[s] = Fraction(cap * sizes[s])
            left -= out[s]
        open_ -= over
    return out


def in_order(sources) -> list:
    """By code point, null last."""
    return sorted((s for s in sources if s is not None), key=lambda s: [ord(c) for c in s]) + [None] * (None in set(sources))


def drawn(have: np.ndarray, draw: int, g: np.random.Generator) -> np.ndarray:
    """``draw`` blocks out of ``have``, without replacement. Beyond a thousand million blocks, where numpy can't, each source
    gets its share, rounded so that the sum is right."""
    if not draw:
        return np.zeros_like(have)
    total = int(have.sum())
    if total < MOST_DRAWN:
        return g.multivariate_hypergeometric(have, draw, method="marginals")
    ends = [int(c) * draw // total for c in np.cumsum(have)]
    return np.diff([0, *ends]).astype(np.int64)


def split_quotas(quotas: list[int], shards: int, seed: int) -> np.ndarray:
    """shards x sources: how many blocks of each source a shard gets; columns add up to the quotas.

    A node over several shards gives its left half a multivariate-hypergeometric draw of the share that its
    number of shards asks for, and its right half the rest.
    """
    out = np.zeros((shards, len(quotas)), np.int64)

    def descend(lo: int, hi: int, have: np.ndarray) -> None:
        if hi - lo == 1:
            out[lo] = have
            return
        mid = (lo + hi) // 2
        draw = int(have.sum()) * (mid - lo) // (hi - lo)
        left = drawn(have, draw, np.random.default_rng([seed, lo, hi]))
        descend(lo, mid, left)
        descend(mid, hi, have - left)

    descend(0, shards, np.array(quotas, np.int64))
    return out


class MixPlan:
    """What each document's copies and shards follow from: a few numbers a source and a shard, made on the driver."""

    def __init__(self, sizes: dict, targets: dict, quota: dict, shards: int, seed: int):
        self.sizes, self.targets, self.quota, self.shards, self.seed = sizes, targets, quota, shards, seed
        self.order = in_order(sizes)
        self.tree = split_quotas([quota[s] for s in self.order], shards, seed) if self.order else np.zeros((shards, 0), np.int64)
        #: of each source where each shard's draws end, in blocks
        self.ends = {s: np.cumsum(self.tree[:, k]) for k, s in enumerate(self.order)}

    def shards_of(self, source, block: int) -> list[int]:
        """The shard of each draw that hits this block. Every pass has an order of its own, the last one that of the blocks."""
        ends = self.ends[source]
        whole = self.quota[source] // BLOCKS
        at = [j * BLOCKS + ((block * (2 * (self.seed + 97 * j) + 1) + 31 * j) & (BLOCKS - 1)) for j in range(whole)]
        at.append(whole * BLOCKS + block)
        return [int(x) for x in np.searchsorted(ends, at, side="right") if x < len(ends)]


def block_of(ids: list, sizes: np.ndarray) -> list[int]:
    """Blocks of documents: the leading bits of an MD5 of doc_id and size, which other engines have as well."""
    return [int.from_bytes(hashlib.md5(f"{i}:{n}".encode()).digest()[:3]) >> (24 - 2 * HALF_BITS) for i, n in zip(ids, sizes.tolist(), strict=True)]


def measure(docs: DataFrame, text_col: str, source_col: str) -> DataFrame:
    """doc_id, source, size (words), block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "text"):
            n = word_counts(batch.column(2))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n), pa.array(block_of(batch.column(0).to_pylist(), n), pa.int32())], names=["doc_id", "source", "size", "block"])

    slim = picked(docs, doc_id="doc_id", source=source_col, text=text_col)
    return slim.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), "doc_id bigint, source string, size bigint, block int")


def plan_mix(measured: DataFrame, weights=(5, 2, 1), cap: int = 3, shards: int | None = None, seed: int = 11) -> MixPlan:
    """Targets and quotas of a measured corpus.

    The driver gets one row a source, then for sources whose quota isn't a whole number of passes 1,024 rows each (the words
    of runs of 1,024 blocks) and 1,024 more for the blocks of the run where the target falls: never a row a document. The number of sources
    is taken to be moderate; nothing else here grows with the data. A source's taken words miss its target by at most half the words of one
    block, which holds a millionth of its documents.
    """
    sizes = {r.source: int(r.n or 0) for r in measured.groupBy("source").agg(F.sum("size").alias("n")).collect()}
    order = in_order(sizes)
    shards = shards or max(16, -(-sum(sizes.values()) // SHARD_WORDS))
    targets = water_fill(sizes, {s: weights[k % len(weights)] for k, s in enumerate(order)}, cap)
    quota = {s: BLOCKS * int(targets[s] // sizes[s]) if sizes[s] else 0 for s in order}
    want = {s: targets[s] - quota[s] // BLOCKS * sizes[s] for s in order}
    number = {s: k for k, s in enumerate(order)}
    spark = measured.sparkSession
    prefix = {s: 0 for s in order if want[s] > 0}  # leading bits of the block where the quota ends
    for level in range(2):
        if not prefix:
            break
        looked = spark.createDataFrame([(s, number[s], p) for s, p in prefix.items()], "s string, k int, prefix int")
        run = F.shiftright("block", HALF_BITS)
        part = run if not level else F.col("block").bitwiseAND(F.lit((1 << HALF_BITS) - 1))
        mine = F.col("source").eqNullSafe(F.col("s")) & ((run == F.col("prefix")) if level else F.lit(True))
        rows = measured.filter("size > 0").join(F.broadcast(looked), mine).groupBy("k", part.alias("part")).agg(F.sum("size").alias("n")).collect()
        by: dict = {k: [] for k in (number[s] for s in prefix)}
        for r in rows:
            by[r.k].append((r.part, int(r.n)))
        for s in prefix:
            stop = 1 << HALF_BITS
            for p, n in sorted(by[number[s]]):
                if n > (2 if level else 1) * want[s]:  # the last block is in if at least half of it is wanted
                    stop = p
                    break
                want[s] -= n
            prefix[s] = (prefix[s] << HALF_BITS) + stop
        if not level:  # a quota that takes all runs is settled
            for s in [s for s, p in prefix.items() if p == 1 << HALF_BITS]:
                quota[s] += BLOCKS
                del prefix[s]
    for s, p in prefix.items():
        quota[s] += p
    return MixPlan(sizes, targets, quota, shards, seed)


def mix_rows(measured: DataFrame, plan: MixPlan) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken, shards (one a copy)."""
    held = measured.sparkSession.sparkContext.broadcast(plan)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = held.value
        for batch in batches:
            src = batch.column(1).to_pylist()
            where = [p.shards_of(s, x) for s, x in zip(src, batch.column(3).to_pylist(), strict=True)]
            n = np.array([len(w) for w in where], np.int64)
            size = batch.column(2).to_numpy()
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array([p.sizes[s] for s in src], pa.int64()), pa.array([float(p.targets[s]) for s in src], pa.float64()), pa.array(n), pa.array(n * size), pa.array(where, pa.list_(pa.int32()))], names=["doc_id", "source", "size", "source_size", "target", "copies", "taken", "shards"])

    return measured.mapInArrow(tidy(run), "doc_id bigint, source string, size bigint, source_size bigint, target double, copies bigint, taken bigint, shards array<int>")


def mix(docs: DataFrame, text_col: str = "text", source_col: str = "source", weights=(5, 2, 1), cap: int = 3, shards: int | None = None, seed: int = 11) -> DataFrame:
    """One row per row of ``docs``: doc_id, source, size, source_size, target, copies, taken, shards.

    Sources in code-point order, null last, weigh ``weights`` in turn. Null texts have size 0. Texts without words get as many
    copies as any of their block. Rows that repeat one doc_id and size are taken alike. A corpus without words takes nothing, an empty one gives
    an empty result. Reruns agree, since all follows from hashes of doc_id and size. Very long texts count as any other. Only three
    columns are read; others may have any names.
    """
    measured = Scratch(docs.sparkSession, "mix").table(measure(docs, text_col, source_col), "measured")
    return mix_rows(measured, plan_mix(measured, weights, cap, shards, seed))


def mixed_documents(docs: DataFrame, text_col: str = "text", source_col: str = "source", weights=(5, 2, 1), cap: int = 3, shards: int | None = None, seed: int = 11) -> DataFrame:
    """The mix itself: a row of ``docs`` for each copy taken, with mix_shard and mix_rank; each shard is one partition, in order of rank.

    Null, repeated and very long texts are as in ``mix``. Columns named like the two added ones, in any case, are replaced.
    """
    measured = Scratch(docs.sparkSession, "mixed").table(measure(docs, text_col, source_col), "measured")
    plan = plan_mix(measured, weights, cap, shards, seed)
    held = docs.sparkSession.sparkContext.broadcast(plan)
    own = Passing.of(docs, ["doc_id", source_col, text_col], ("mix_shard", "mix_rank"))
    at_id, at_source, at_text = own.at.values()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = held.value
        for batch in blocks(batches, at_text):
            n = word_counts(batch.column(at_text))
            ids = batch.column(at_id).to_pylist()
            where = [p.shards_of(s, x) for s, x in zip(batch.column(at_source).to_pylist(), block_of(ids, n), strict=True)]
            take = np.repeat(np.arange(len(ids)), [len(w) for w in where])
            rank = [xxhash.xxh3_64_intdigest(f"{i}:{x}:{j}".encode(), seed + 1) >> 1 for i, x, w in zip(ids, n.tolist(), where, strict=True) for j in range(len(w))]
            cols = [c.take(pa.array(take)) for c in batch.columns]
            yield pa.RecordBatch.from_arrays([*cols, pa.array([k for w in where for k in w], pa.int32()), pa.array(rank, pa.int64())], names=[*batch.schema.names, "mix_shard", "mix_rank"])

    done = own.frame.mapInArrow(tidy(run), own.schema.add("mix_shard", "integer").add("mix_rank", "long"))
    return own.returned(done.repartitionById(plan.shards, F.col("mix_shard")).sortWithinPartitions("mix_shard", "mix_rank"))
