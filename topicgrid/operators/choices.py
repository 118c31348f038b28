"""Groups of many orders at once, and the costs of all of them from one pass over the matrix.

A choice is a method, a number of groups and, of random methods, a trial. Nothing is exploded by trial: items carry one number a
choice. In each choice's order an item falls into one of about ``BUCKETS`` buckets; tokens by bucket, which are a matter of
parameters and not of data, tell the group of every bucket that no boundary falls into. Only the items of the buckets that have one (a share of about
``groups / BUCKETS``) are sorted, to find the first item of each group. Cells then meet the groups of their rows and columns in tasks that hold
a bucket of rows and a bucket of columns, so groups are copied once for each bucket of the other axis instead of once a cell; cells travel
many in a record.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from topicgrid.functions.digests import Keys
from topicgrid.sources.shared import remove, shared_folder

BUCKETS = 4096
BLOCK = 65_536  # items a task orders at once
HELD = 48 << 20  # bytes of groups that a task holds of each axis, or a little more where ids are few
PACKED = 512  # cells that travel as one record; Arrow takes 10,000 records at once
CLOSED = ("interleave", "mirror", "mirror_alternate", "sorted")


@dataclass(frozen=True)
class Choice:
    method: str
    groups: int
    trial: int = 0


def position(method: str, k: np.ndarray, d: int) -> np.ndarray:
    """``positions`` in numpy."""
    q = d + 1 - k
    if method == "interleave":
        return np.where(2 * k <= d + 1, 2 * k - 1, 2 * q)
    if method == "mirror":
        return np.where(((k % 2 == 0) & (2 * k < d)) | ((q % 2 == 0) & (2 * q < d)), q, k)
    if method == "mirror_alternate":
        return np.where(2 * k <= d + 1, np.where(k % 2 == 1, k, d + 2 - k), np.where(q % 2 == 1, q + 1, d + 1 - q))
    return k


def _bits(groups: int) -> int:
    return max(0, (BUCKETS // groups).bit_length() - 1)


class Order:
    """Where the items of a block stand: a bucket, and a number within it; items alike in both go by id."""

    def __init__(self, ids: np.ndarray, rank: np.ndarray, size: int, seed: int, axis: str):
        self.ids, self.rank, self.size, self.seed, self.axis, self.keys = ids, rank, size, seed, axis, Keys(ids)

    def slots(self, c: Choice) -> np.ndarray:
        """Of whole runs in order of rank: the place each item is dealt to in its run, from 0."""
        k = self.keys.of(self.seed, self.axis, "deal", c.trial)
        order = np.lexsort((self.ids, k, (self.rank - 1) // c.groups))
        out = np.empty(len(k), np.int64)
        out[order] = (self.rank - 1) % c.groups  # runs are whole, so the n-th of a run stands where rank has the n-th
        return out

    def buckets(self, c: Choice) -> np.ndarray:
        if c.method == "stratified":
            return self.slots(c) << _bits(c.groups) | self.fine(c) >> 48 - _bits(c.groups)
        if c.method == "plain_shuffle":
            return self.fine(c) >> 48 - _bits(1)
        return (position(c.method, self.rank, self.size) - 1) * BUCKETS // self.size

    def fine(self, c: Choice) -> np.ndarray:
        if c.method in ("stratified", "plain_shuffle"):
            return self.keys.of(self.seed, self.axis, "order" if c.method == "stratified" else "plain", c.trial)
        return position(c.method, self.rank, self.size)


def _array(column: pa.Array, kind: str, width: int) -> np.ndarray:
    """A BINARY column of equal lengths as a matrix."""
    return np.frombuffer(b"".join(column.to_pylist()), kind).reshape(-1, width)


def _binary(x: np.ndarray) -> pa.Array:
    x = np.ascontiguousarray(x)
    return pa.array([r.tobytes() for r in x], pa.binary())


class Axis:
    """Groups of rows or of columns in all choices: ``frame()`` has id and a byte (two, if groups are many) a choice."""

    def __init__(self, ranked: DataFrame, choices: Sequence[Choice], seed: int, axis: str, rule: str):
        self.spark, self.choices, self.seed, self.axis, self.rule = ranked.sparkSession, tuple(choices), seed, axis, rule
        self.kind = "<u1" if max(c.groups for c in choices) <= 256 else "<u2"
        first = ranked.select("size", "total").first()
        self.size, self.total = (int(first.size), int(first.total or 0)) if first else (0, 0)
        self.path = shared_folder(self.spark, f"choices-{axis}")
        self.wide = max(_bits_needed(c) for c in choices)
        run = math.lcm(*(c.groups for c in choices if c.method == "stratified"))
        width = run * -(-BLOCK // run)
        blocks = max(1, -(-self.size // width))
        dealt = ranked.select("id", "len", "rank", F.expr(f"cast((rank - 1) div {width} as int)").alias("block")).repartitionById(blocks, F.col("block")).select("id", "len", "rank")
        dealt.mapInArrow(self._place(), "id bigint, len bigint, rank bigint, at binary").write.parquet(self.path)
        self.placed = self.spark.read.schema("id bigint, len bigint, rank bigint, at binary").parquet(self.path)
        self._find_bounds()

    def _place(self):
        choices, size, seed, axis = self.choices, self.size, self.seed, self.axis

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            whole = [b for b in batches if b.num_rows]
            if not whole:
                return
            ids, n, rank = (np.concatenate([b.column(k).to_numpy() for b in whole]) for k in range(3))
            order = np.argsort(rank, kind="stable")
            ids, n, rank = ids[order], n[order], rank[order]
            o = Order(ids, rank, size, seed, axis)
            at = np.empty((len(ids), len(choices)), "<u2")
            for k, c in enumerate(choices):
                at[:, k] = o.buckets(c)
            for a in range(0, len(ids), 8192):
                yield pa.RecordBatch.from_arrays([pa.array(ids[a : a + 8192]), pa.array(n[a : a + 8192]), pa.array(rank[a : a + 8192]), _binary(at[a : a + 8192])], names=["id", "len", "rank", "at"])

        return run

    def _find_bounds(self) -> None:
        """``base``: the group of each choice's bucket where it begins; ``bounds``: bucket, number and id of the first item of each later group in it."""
        s, wide, count = len(self.choices), self.wide, self.rule == "count"

        def add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = np.zeros(s * wide, np.int64)
            for b in batches:
                if b.num_rows:
                    at = _array(b.column(1), "<u2", s) + np.arange(s) * wide
                    held += _sums(at, np.ones(b.num_rows, np.int64) if count else b.column(0).to_numpy(), s * wide)
            k = np.flatnonzero(held)
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(held[k])], names=["k", "n"])

        found = self.placed.select("len", "at").mapInArrow(add_up, "k bigint, n bigint").groupBy("k").agg(F.sum("n").alias("n")).toArrow()
        sums = np.zeros(s * wide, np.int64)
        sums[found.column("k").to_numpy()] = found.column("n").to_numpy()
        sums = sums.reshape(s, wide)
        ends = np.cumsum(sums, axis=1)
        total, doubled = self.size if count else self.total, 1 if self.rule == "midpoint" else 0
        groups = [c.groups for c in self.choices]
        exact = [[_group(2 * int(x), g, total) for x in row] if total * 4 * g >= 1 << 62 else np.minimum(g - 1, 2 * row * g // max(1, 2 * total)) for row, g in zip(ends - sums, groups, strict=True)]
        last = [[_group(2 * int(x), g, total) for x in row] if total * 4 * g >= 1 << 62 else np.minimum(g - 1, 2 * row * g // max(1, 2 * total)) for row, g in zip(ends, groups, strict=True)]
        self.base = np.array(exact, np.int64).reshape(s, wide)
        open_ = (self.base != np.array(last, np.int64).reshape(s, wide)) & (sums > 0)
        self.open = open_
        at = np.argwhere(open_)
        self.bounds: list[list[tuple[int, int, int, int]]] = [[] for _ in range(s)]
        if not len(at):
            return
        before = ends - sums
        starts = self.spark.createDataFrame([(int(k), int(b), int(before[k, b]), groups[k]) for k, b in at], "k int, bucket int, start bigint, groups int")
        some = self.placed.select("id", "len", "rank", "at").mapInArrow(self._pick(), "k int, bucket int, fine bigint, id bigint, len bigint")
        if count:
            some = some.withColumn("len", F.lit(1).cast("bigint"))
        inside = Window.partitionBy("k", "bucket").orderBy("fine", "id").rowsBetween(Window.unboundedPreceding, -1)
        summed = some.withColumn("inner", F.coalesce(F.sum("len").over(inside), F.lit(0))).join(F.broadcast(starts), ["k", "bucket"])
        value = (2 * (F.col("start") + F.col("inner")) + doubled * F.col("len")).cast("decimal(38,0)")
        grp = F.least(F.col("groups") - 1, F.floor(value * F.col("groups") / F.lit(2 * total).cast("decimal(38,0)")).cast("int"))
        if total * 4 * max(groups) < 1 << 62:
            grp = F.least(F.col("groups") - 1, F.expr(f"(2 * (start + inner) + {doubled} * len) * groups div {2 * total}").cast("int"))
        for r in summed.withColumn("grp", grp).groupBy("k", "bucket", "grp").agg(F.min(F.struct("fine", "id")).alias("first")).collect():  # at most P a choice
            self.bounds[r.k].append((r.bucket, r.first.fine, r.first.id, r.grp))

    def _pick(self):
        choices, size, seed, axis, open_ = self.choices, self.size, self.seed, self.axis, self.open

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                ids, n, rank = (b.column(k).to_numpy() for k in range(3))
                at = _array(b.column(3), "<u2", len(choices))
                for k, c in enumerate(choices):
                    some = np.flatnonzero(open_[k][at[:, k]])
                    if len(some):
                        fine = Order(ids[some], rank[some], size, seed, axis).fine(c)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), k, np.int32)), pa.array(at[some, k].astype(np.int32)), pa.array(fine), pa.array(ids[some]), pa.array(n[some])], names=["k", "bucket", "fine", "id", "len"])

        return run

    def frame(self) -> DataFrame:
        """id, grps."""
        choices, size, seed, axis, kind = self.choices, self.size, self.seed, self.axis, self.kind
        sent = self.spark.sparkContext.broadcast((self.base.astype(kind), self.open, self.bounds))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            base, open_, bounds = sent.value
            for b in batches:
                if not b.num_rows:
                    continue
                ids, rank = b.column(0).to_numpy(), b.column(1).to_numpy()
                at = _array(b.column(2), "<u2", len(choices))
                out = np.empty(at.shape, kind)
                for k, c in enumerate(choices):
                    out[:, k] = base[k][at[:, k]]
                    some = np.flatnonzero(open_[k][at[:, k]])
                    if not len(some):
                        continue
                    fine, i, bucket = Order(ids[some], rank[some], size, seed, axis).fine(c), ids[some], at[some, k]
                    own = np.zeros(len(some), kind)
                    for x, f, first, g in bounds[k]:
                        own = np.where((bucket == x) & ((fine > f) | ((fine == f) & (i >= first))), np.maximum(own, g), own)
                    out[some, k] = own
                yield pa.RecordBatch.from_arrays([b.column(0), _binary(out)], names=["id", "grps"])

        return self.placed.select("id", "rank", "at").mapInArrow(run, "id bigint, grps binary")

    def done(self) -> None:
        remove(self.spark, self.path)


def _bits_needed(c: Choice) -> int:
    """How many buckets a choice has."""
    return c.groups << _bits(c.groups) if c.method == "stratified" else BUCKETS


def _group(doubled: int, groups: int, total: int) -> int:
    return min(groups - 1, doubled * groups // max(1, 2 * total))


def _sums(at: np.ndarray, n: np.ndarray, size: int) -> np.ndarray:
    """Sums of n by place; each row of ``at`` has the places of one n. Doubles add whole numbers below 2 ** 53 exactly."""
    if float(np.abs(n).astype(np.float64).sum()) < 2.0**52:
        return np.bincount(at.ravel(), np.repeat(n.astype(np.float64), at.shape[1]), size).astype(np.int64)
    out = np.zeros(size, np.int64)
    np.add.at(out, at.ravel(), np.repeat(n, at.shape[1]))
    return out


def _narrow(x: np.ndarray) -> list[bytes]:
    """int64 as the least and what is above it, in 1, 2, 4 or 8 bytes each; the first byte says in how many."""
    least = x.min()
    above = x.astype(np.uint64) - np.uint64(least.astype(np.uint64))
    width = next(w for w in (1, 2, 4, 8) if w == 8 or int(above.max()) < 1 << 8 * w)
    return [bytes([width]), least.tobytes(), above.astype(f"<u{width}").tobytes()]


def _widen(data: memoryview, at: int, count: int) -> tuple[np.ndarray, int]:
    """What ``_narrow`` took, and where it ends."""
    width, least = data[at], np.frombuffer(data, "<i8", 1, at + 1)
    end = at + 9 + width * count
    return (np.frombuffer(data, f"<u{width}", count, at + 9).astype(np.uint64) + least.astype(np.uint64)).astype(np.int64), end


def _pack(batches: Iterator[pa.RecordBatch], together: int = 1 << 19) -> Iterator[pa.RecordBatch]:
    """task and up to ``PACKED`` of its cells, by column and row, from task, row_id, col_id, n."""
    held, size = [], 0

    def packs() -> Iterator[pa.RecordBatch]:
        task, row, col, n = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in range(4))
        order = np.lexsort((row, col, task))
        task, row, col, n = task[order], row[order], col[order], n[order]
        starts = [x for a, z in _runs(task) for x in range(a, z, PACKED)]
        data = []
        for a, z in zip(starts, [*starts[1:], len(task)], strict=True):
            data.append(b"".join([(z - a).to_bytes(4, "little"), *_narrow(row[a:z]), *_narrow(np.diff(col[a:z], prepend=col[a])), col[a].tobytes(), *_narrow(n[a:z])]))
        for a in range(0, len(data), 512):
            yield pa.RecordBatch.from_arrays([pa.array(task[starts[a : a + 512]]), pa.array(data[a : a + 512], pa.binary())], names=["task", "grps"])

    for b in batches:
        if b.num_rows:
            held.append(b)
            size += b.num_rows
        if size >= together:
            yield from packs()
            held, size = [], 0
    if size:
        yield from packs()


def _runs(x: np.ndarray) -> list[tuple[int, int]]:
    start = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])).tolist()
    return list(zip(start, [*start[1:], len(x)], strict=True))


def _unpack(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """row_id, col_id, n of packed cells, some 16,384 at a time."""
    held, size = [], 0
    for pack in column:
        data = memoryview(pack.as_buffer())
        count = int.from_bytes(data[:4], "little")
        row, at = _widen(data, 4, count)
        step, at = _widen(data, at, count)
        col = np.frombuffer(data, "<i8", 1, at) + np.cumsum(step)
        n, _ = _widen(data, at + 8, count)
        held.append((row, col, n))
        size += count
        if size >= 16_384:
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
            held, size = [], 0
    if held:
        yield tuple(np.concatenate(x) for x in zip(*held, strict=True))


def choice_costs(matrix: DataFrame, choices: Sequence[Choice], ranked: tuple[DataFrame, DataFrame], seed: int = 7, rule: str = "midpoint") -> DataFrame:
    """choice (its place in ``choices``), m, n, cost of the blocks that have cells; written, so that it is made once."""
    spark, choices = matrix.sparkSession, tuple(choices)
    s = len(choices)
    axes = [Axis(r, choices, seed, axis, rule) for r, axis in zip(ranked, ("row", "col"), strict=True)]
    parts = [max(4, -(-a.size * s * np.dtype(a.kind).itemsize // HELD)) for a in axes]
    frames = []
    for k, (a, mine, other) in enumerate(zip(axes, parts, reversed(parts), strict=True)):
        own = F.pmod(F.xxhash64("id"), F.lit(mine))
        copies = F.explode(F.sequence(F.lit(0), F.lit(other - 1))).alias("copy")
        task = own * parts[1] + F.col("copy") if k == 0 else F.col("copy") * parts[1] + own
        frames.append(a.frame().select("id", "grps", copies).select(task.cast("int").alias("task"), F.lit(k).alias("kind"), "id", "grps"))
    typed = matrix.select(*(F.col(c).cast("bigint").alias(c) for c in ("row_id", "col_id", "n")))
    task = F.pmod(F.xxhash64("row_id"), F.lit(parts[0])) * parts[1] + F.pmod(F.xxhash64("col_id"), F.lit(parts[1]))
    packed = typed.select(task.cast("int").alias("task"), "row_id", "col_id", "n").mapInArrow(_pack, "task int, grps binary")
    cells = packed.select("task", F.lit(2).alias("kind"), F.lit(None).cast("bigint").alias("id"), "grps")
    wide = np.array([c.groups for c in choices])
    offset = np.concatenate([[0], np.cumsum(wide**2)])
    narrow = np.dtype("<u2") if wide.max() <= 256 else np.dtype("<u4")
    kinds = [a.kind for a in axes]

    def add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, got, tables = np.zeros(offset[-1], np.int64), ([], []), None
        for b in batches:
            kind = b.column(0).to_numpy()
            for k in (0, 1):
                if len(some := np.flatnonzero(kind == k)):
                    part = b.take(pa.array(some))
                    got[k].append((part.column(1).to_numpy(), _array(part.column(2), kinds[k], s)))
            if not len(some := np.flatnonzero(kind == 2)):
                continue
            if tables is None:  # kinds come in order
                tables = []
                for x in got:
                    ids = np.concatenate([i for i, _ in x])
                    order = np.argsort(ids)
                    tables.append((ids[order], np.concatenate([g for _, g in x])[order]))
                    x.clear()
            for row, col, n in _unpack(b.column(2).take(pa.array(some))):
                at = None
                for k, of in ((0, row), (1, col)):
                    ids, grps = tables[k]
                    g = grps[np.searchsorted(ids, of)]
                    at = np.multiply(g, wide.astype(narrow), dtype=narrow) if at is None else at + g
                held += _sums(at + offset[:-1], n, len(held))
        k = np.flatnonzero(held)
        choice = np.searchsorted(offset, k, side="right") - 1
        m, n = np.divmod(k - offset[choice], wide[choice])
        yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int32)) for x in (choice, m, n)] + [pa.array(held[k])], names=["choice", "m", "n", "cost"])

    together = frames[0].unionByName(frames[1]).unionByName(cells).repartitionById(parts[0] * parts[1], F.col("task")).sortWithinPartitions("kind")
    sums = together.select("kind", "id", "grps").mapInArrow(add_up, "choice int, m int, n int, cost bigint").groupBy("choice", "m", "n").agg(F.sum("cost").alias("cost"))
    path = shared_folder(spark, "costs")
    sums.write.parquet(path)
    for a in axes:
        a.done()
    return spark.read.schema("choice int, m int, n int, cost bigint").parquet(path)


def choice_etas(matrix: DataFrame, choices: Sequence[Choice], ranked: tuple[DataFrame, DataFrame], seed: int = 7, rule: str = "midpoint") -> DataFrame:
    """choice, method, groups, trial, tokens, total_cost, eta; null where there are no tokens."""
    spark = matrix.sparkSession
    per = choice_costs(matrix, choices, ranked, seed, rule).join(F.broadcast(_listed(spark, choices)), "choice").groupBy("choice", F.pmod(F.col("n") - F.col("m"), F.col("groups")).alias("diag")).agg(F.max("cost").alias("c"), F.sum("cost").alias("s"))
    out = per.groupBy("choice").agg(F.sum("s").alias("tokens"), F.sum("c").alias("total_cost"))
    every = _listed(spark, choices).join(out, "choice", "left").withColumns({c: F.coalesce(c, F.lit(0)) for c in ("tokens", "total_cost")})
    return every.withColumn("eta", F.expr("try_divide(cast(tokens as double) / groups, total_cost)"))


def _listed(spark, choices: Sequence[Choice]) -> DataFrame:
    return spark.createDataFrame([(k, c.method, c.groups, c.trial) for k, c in enumerate(choices)], "choice int, method string, groups int, trial int")
