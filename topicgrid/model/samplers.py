"""The samplers: diagonal (for a plain and for a stamped model), serial, replicating, and one frozen sweep.

The state lies on shared storage in parts: the cells of each diagonal apart ("z" words, "y" stamps), the counts of documents
("t"), words ("p") and stamps ("q"). Epoch l reads and rewrites the cells of diagonal l and the counts, no other cells, so an
iteration writes each token once whatever P is. A task of epoch l gets the rows of document group m and of column group
(m + l) mod P, and no other task of that epoch has any of them. Rows are placed with ``repartitionById``, anew before every
epoch, since reading back forgets a placement. A lost executor costs one epoch at most, and a task that runs again draws
the same numbers.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topicgrid.model.counts import init_topics, model_perplexity, topic_counts
from topicgrid.model import native
from topicgrid.model.kernel import KERNELS, WIDE, Sweep, stream
from topicgrid.sources.shared import located, remove, shared_folder

STATE = "kind string, g int, h int, a bigint, b bigint, v array<int>"
ROW = "g int, h int, a bigint, b bigint, v array<int>"
LAYOUTS = ("independent", "shared_rows", "merged")
IN_ONE = 64_000_000  # tokens up to which a serial fit makes all its sweeps in one task


@dataclass(frozen=True)
class Priors:
    """Topics and priors; the published settings are 256, 0.5, 0.1, 0.1."""

    topics: int = 256
    alpha: float = 0.5
    beta: float = 0.1
    gamma: float = 0.1


@dataclass
class Fit:
    """What a sampler leaves: theta counts, phi counts, pi counts (or none), perplexity by iteration, and all cells (kind, row_id, col_id, z)."""

    theta: DataFrame
    phi: DataFrame
    pi: DataFrame | None
    history: list[float]
    cells: DataFrame


@dataclass(frozen=True)
class Part:
    """One matrix of the model: its cells, its columns, its prior, how many columns it has and which phase its draws are of."""

    cell: str
    col: str
    prior: float
    size: int
    phase: int


@dataclass
class GridStore:
    """The parts of the state as folders; what an epoch has replaced is removed."""

    spark: SparkSession
    root: str
    groups: int
    topics: int
    cells: dict[tuple[str, int], str] = field(default_factory=dict)
    counts: dict[str, str] = field(default_factory=dict)
    totals: dict[str, np.ndarray] = field(default_factory=dict)
    epochs: int = 0

    def exists(self, path: str) -> bool:
        fs, where = located(self.spark, path)
        return fs.exists(where)

    def read(self, kind: str, path: str | None) -> DataFrame:
        df = self.spark.read.schema(ROW).parquet(path) if path else self.spark.createDataFrame([], ROW)
        return df.select(F.lit(kind).alias("kind"), "g", "h", "a", "b", "v")

    def diagonal(self, kind: str, diag: int) -> DataFrame:
        return self.read(kind, self.cells.get((kind, diag)))

    def all_cells(self, kind: str) -> DataFrame:
        out = None
        for (k, _), path in sorted(self.cells.items()):
            if k == kind:
                out = self.read(kind, path) if out is None else out.unionByName(self.read(kind, path))
        return self.read(kind, None) if out is None else out

    def lay_out(self, cells: DataFrame, kind: str) -> None:
        """Cells by diagonal, a file for each document group."""
        path = f"{self.root}/layout-{kind}"
        placed = cells.withColumn("diag", F.pmod(F.col("h") - F.col("g"), F.lit(self.groups)).cast("int")).select("g", "h", "a", "b", "v", "diag")
        placed = placed.repartitionById(self.groups, F.col("g")) if self.groups > 1 else placed
        placed.write.partitionBy("diag").parquet(path)
        for d in range(self.groups):
            if self.exists(f"{path}/diag={d}"):
                self.cells[kind, d] = f"{path}/diag={d}"

    def put_counts(self, kind: str, df: DataFrame) -> None:
        path = f"{self.root}/first-{kind}"
        df.select("g", "h", "a", "b", "v").write.parquet(path)
        self.counts[kind] = path

    def close(self, done: DataFrame, diag: int, parts: tuple[Part, ...], kinds: tuple[str, ...]) -> None:
        """Write an epoch, point to what it made, add up the tasks' changes of the topic totals, and drop what it replaced."""
        self.epochs += 1
        path = f"{self.root}/epoch-{self.epochs}"
        done.write.partitionBy("kind").parquet(path)
        old = []
        for part in parts:
            if (part.cell, diag) in self.cells:
                old.append(self.cells[part.cell, diag])
                self.cells[part.cell, diag] = f"{path}/kind={part.cell}"
            change = f"{path}/kind=total-{part.cell}"
            if self.exists(change):
                for r in self.spark.read.schema(ROW).parquet(change).collect():  # a row of K numbers a task
                    self.totals[part.cell] = self.totals[part.cell] + np.array(r.v)
        for kind in kinds:
            if self.exists(f"{path}/kind={kind}"):
                old.append(self.counts[kind])
                self.counts[kind] = f"{path}/kind={kind}"
        for x in old:
            remove(self.spark, x)


def place_cells(matrix: DataFrame, row_groups: DataFrame | None, col_groups: DataFrame | None, kind: str, topics: int, seed: int) -> DataFrame:
    """Cells with their groups and first topics."""
    cells = init_topics(matrix.select("row_id", "col_id", "n"), topics, seed, "word" if kind == "z" else "stamp")
    if row_groups is None:  # one group
        cells = cells.withColumns({"g": F.lit(0), "h": F.lit(0)})
    else:
        rows = row_groups.select(F.col("id").alias("row_id"), F.col("grp").alias("g"))
        cols = col_groups.select(F.col("id").alias("col_id"), F.col("grp").alias("h"))
        cells = cells.join(rows, "row_id").join(cols, "col_id")
    return cells.select(F.lit(kind).alias("kind"), "g", "h", F.col("row_id").alias("a"), F.col("col_id").alias("b"), F.col("z").alias("v"))


def _counts(cells: DataFrame, axis: str, kind: str, topics: int) -> DataFrame:
    id_, grp = ("a", "g") if axis == "row" else ("b", "h")
    c = topic_counts(cells.select(F.col(id_).alias("id"), F.col("v").alias("z")), "id", topics)
    where = cells.select(F.col(id_).alias("id"), F.col(grp).alias("g")).distinct()
    return c.join(where, "id").select(F.lit(kind).alias("kind"), "g", F.lit(0).alias("h"), F.col("id").alias("a"), F.lit(0).cast("bigint").alias("b"), F.transform("c", lambda x: x.cast("int")).alias("v"))


def dense(column: pa.ChunkedArray, width: int) -> np.ndarray:
    return column.combine_chunks().flatten().to_numpy().astype(np.int64).reshape(-1, width)


def lookup(ids: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Where each wanted id is among ``ids``, which has each once."""
    order = np.argsort(ids)
    return order[np.searchsorted(ids, wanted, sorter=order)]


def lists(values: np.ndarray, lengths: np.ndarray | int) -> pa.Array:
    values = values.ravel()
    ends = np.arange(0, len(values) + 1, lengths) if isinstance(lengths, int) else np.concatenate([[0], np.cumsum(lengths)])
    return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(values.astype(np.int32)))


def _with(table: pa.Table, values: pa.Array) -> pa.Table:
    return table.set_column(table.schema.get_field_index("v"), "v", values)


class Block:
    """What a task has of its epoch: counts of documents and, for each part, its cells and the counts of its columns."""

    def __init__(self, docs: pa.Table, topics: int):
        self.docs, self.topics = docs, topics
        self.ids = docs.column("a").to_numpy()
        self.theta = dense(docs.column("v"), topics) if len(docs) else np.zeros((0, topics), np.int64)

    def resample(self, cells: pa.Table, cols: pa.Table, totals: np.ndarray, part: Part, alpha: float, kernel: str, rng: np.random.Generator) -> tuple[pa.Table, pa.Table, np.ndarray]:
        """Cells and columns as they are after one sweep, and the change of the topic totals."""
        cells = cells.sort_by([("a", "ascending"), ("b", "ascending")]).combine_chunks()
        phi, own = dense(cols.column("v"), self.topics), totals.copy()
        n = pc.list_value_length(cells.column("v").combine_chunks()).to_numpy()
        rows = np.repeat(lookup(self.ids, cells.column("a").to_numpy()), n)
        at = np.repeat(lookup(cols.column("a").to_numpy(), cells.column("b").to_numpy()), n)
        z = cells.column("v").combine_chunks().flatten().to_numpy().astype(np.int64)
        KERNELS[kernel](rows, at, z, self.theta, phi, own, alpha, part.prior, part.size, rng.random(len(z)))
        return _with(cells, lists(z, n)), _with(cols, lists(phi, self.topics)), own - totals

    def documents(self) -> pa.Table:
        return _with(self.docs, lists(self.theta, self.topics)) if len(self.docs) else self.docs


def _of(table: pa.Table, kind: str) -> pa.Table:
    return table.filter(pc.equal(table.column("kind"), kind))


def _whole(batches: Iterator[pa.RecordBatch]) -> pa.Table | None:
    some = [b for b in batches if b.num_rows]
    return pa.Table.from_batches(some) if some else None


COLUMNS = ["kind", "g", "h", "a", "b", "v"]
ARROW_STATE = pa.schema([("kind", pa.string()), ("g", pa.int32()), ("h", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("v", pa.list_(pa.int32()))])


MANY = 65_536  # rows of counts in a batch


def _batches(*tables: pa.Table) -> Iterator[pa.RecordBatch]:
    for table in tables:
        yield from table.cast(ARROW_STATE).combine_chunks().to_batches()


def _epoch(store: GridStore, diag: int, parts: tuple[Part, ...], priors: Priors, seed: int, iteration: int, row_group: str, kernel: str) -> None:
    """One epoch: the cells of the diagonal of each part, documents "t" and the parts' columns in, the same out.

    ``row_group``: where document rows keep their group for these parts: in g, or, with independent partitions, in h.
    """
    groups, topics, alpha = store.groups, store.topics, priors.alpha
    sent = store.spark.sparkContext.broadcast({p.cell: store.totals[p.cell] for p in parts})
    frames = [store.read("t", store.counts["t"]).withColumn("task", F.col(row_group))]
    for p in parts:
        frames.append(store.diagonal(p.cell, diag).withColumn("task", F.col("g")))
        frames.append(store.read(p.col, store.counts[p.col]).withColumn("task", F.pmod(F.col("g") - diag, F.lit(groups)).cast("int")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = _whole(batches)
        if whole is None:
            return
        m = pc.unique(whole.column("task")).to_pylist()
        assert len(m) == 1, "a task got the blocks of two groups"
        whole = whole.select(COLUMNS)
        block, out = Block(_of(whole, "t"), topics), []
        for p in parts:
            cells, cols = _of(whole, p.cell), _of(whole, p.col)
            if len(cells):
                cells, cols, change = block.resample(cells, cols, sent.value[p.cell], p, alpha, kernel, stream(seed, iteration, p.phase, diag, m[0]))
                one = {"kind": [f"total-{p.cell}"], "g": [m[0]], "h": [0], "a": [0], "b": [0], "v": [change.tolist()]}
                out.append(pa.table(one, schema=ARROW_STATE))
            out += [cells, cols]
        yield from _batches(block.documents(), *out)

    def run_sorted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Token by token: counts come first, then cells in the order they are drawn in, and pass through batch by batch."""
        part, counts, state, m = parts[0], [], None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            here = pc.unique(table.column("task")).to_pylist()
            assert len(here) == 1 and m in (None, here[0]), "a task got the blocks of two groups"
            m, table = here[0], table.select(COLUMNS)
            cells = _of(table, part.cell)
            if len(cells) < len(table):
                counts.append(table.filter(pc.not_equal(table.column("kind"), part.cell)))
            if not len(cells):
                continue
            if state is None:
                whole = pa.concat_tables(counts)
                block, cols = Block(_of(whole, "t"), topics), _of(whole, part.col)
                col_ids, phi, own = cols.column("a").to_numpy(), dense(cols.column("v"), topics), sent.value[part.cell].copy()
                state, rng = Sweep(block.theta, phi, own, alpha, part.prior, part.size), stream(seed, iteration, part.phase, diag, m)
                counts = []
            n = pc.list_value_length(cells.column("v").combine_chunks()).to_numpy()
            # both sorted
            rows = np.repeat(np.searchsorted(block.ids, cells.column("a").to_numpy()), n)
            at = np.repeat(np.searchsorted(col_ids, cells.column("b").to_numpy()), n)
            z = cells.column("v").combine_chunks().flatten().to_numpy().astype(np.int64)
            state.draw(rows, at, z, rng.random(len(z)))
            yield from _batches(_with(cells, lists(z, n)))
        if state is not None:
            state.close()
            change = (own - sent.value[part.cell]).tolist()
            yield from _batches(pa.table({"kind": [f"total-{part.cell}"], "g": [m], "h": [0], "a": [0], "b": [0], "v": [change]}, schema=ARROW_STATE))
            yield from _batches(block.documents(), _with(cols, lists(phi, topics)))
        elif counts:
            yield from _batches(pa.concat_tables(counts))

    dealt = _union(frames).repartitionById(groups, F.col("task"))
    if kernel == "loop" and len(parts) == 1:
        done = dealt.sortWithinPartitions(F.when(F.col("kind") == parts[0].cell, 1).otherwise(0), "a", "b").mapInArrow(run_sorted, STATE)
    else:
        done = dealt.mapInArrow(run, STATE)
    store.close(done, diag, parts, ("t", *(p.col for p in parts)))


def _ring(store: GridStore, phases: list[tuple[tuple[Part, ...], str]], priors: Priors, seed: int, iteration: int, kernel: str) -> None:
    """A whole iteration in one barrier stage: tasks keep their documents and cells, slabs of columns go round.

    Slabs pass through the shared folder, changes of topic totals through the barrier. All P tasks must run at once, and document
    groups must be the same for all parts.
    """
    groups, topics = store.groups, store.topics
    if store.spark.sparkContext.defaultParallelism < groups:
        raise ValueError(f"a ring of {groups} needs as many slots, there are {store.spark.sparkContext.defaultParallelism}")
    parts = tuple(p for some, _ in phases for p in some)
    sent = store.spark.sparkContext.broadcast({p.cell: store.totals[p.cell] for p in parts})
    frames = [store.read("t", store.counts["t"])]
    for p in parts:
        frames += [store.all_cells(p.cell), store.read(p.col, store.counts[p.col])]
    folder = f"{store.root}/ring-{iteration}"
    fs, where = located(store.spark, folder)
    fs.mkdirs(where)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import feather
        from pyarrow.fs import FileSystem
        from pyspark import BarrierTaskContext

        context = BarrierTaskContext.get()
        m = context.partitionId()
        files, root = FileSystem.from_uri(folder)
        whole = _whole(batches)
        whole = (whole if whole is not None else pa.table({c: [] for c in COLUMNS}, schema=ARROW_STATE)).select(COLUMNS).cast(ARROW_STATE)
        block, totals = Block(_of(whole, "t"), topics), {c: t.copy() for c, t in sent.value.items()}
        cells, slab = {p.cell: _of(whole, p.cell) for p in parts}, {p.col: _of(whole, p.col) for p in parts}
        for diag in range(groups):
            n = (m + diag) % groups
            for some, _ in phases:
                changes = {}
                for p in some:
                    here = pc.equal(cells[p.cell].column("h"), n)
                    mine, others = cells[p.cell].filter(here), cells[p.cell].filter(pc.invert(here))
                    if len(mine):
                        mine, slab[p.col], changes[p.cell] = block.resample(mine, slab[p.col], totals[p.cell], p, priors.alpha, kernel, stream(seed, iteration, p.phase, diag, m))
                        cells[p.cell] = pa.concat_tables([mine, others])
                raw = b"".join(changes.get(p.cell, np.zeros(topics, np.int64)).tobytes() for p in some)
                for other in context.allGather(base64.b64encode(raw).decode()):
                    for p, change in zip(some, np.frombuffer(base64.b64decode(other), np.int64).reshape(len(some), topics), strict=True):
                        totals[p.cell] += change
            for p in parts:
                with files.open_output_stream(f"{root}/{diag}-{p.col}-{n}") as f:
                    feather.write_feather(slab[p.col], f, compression="zstd")
            context.barrier()
            for p in parts:
                with files.open_input_file(f"{root}/{diag}-{p.col}-{(n + 1) % groups}") as f:
                    slab[p.col] = feather.read_table(f).cast(ARROW_STATE)
        if m == 0:
            end = {"kind": [f"total-{p.cell}" for p in parts], "g": [0] * len(parts), "h": [0] * len(parts), "a": [0] * len(parts), "b": [0] * len(parts), "v": [(totals[p.cell] - sent.value[p.cell]).tolist() for p in parts]}
            yield from _batches(pa.table(end, schema=ARROW_STATE))
        yield from _batches(block.documents(), *cells.values(), *slab.values())

    # slab n starts with task n, which also keeps document group n
    done = _union(frames).withColumn("task", F.col("g")).repartitionById(groups, F.col("task")).mapInArrow(run, STATE, barrier=True)
    store.epochs += 1
    path = f"{store.root}/epoch-{store.epochs}"
    marked = done.withColumn("diag", F.when(F.col("kind").isin([p.cell for p in parts]), F.pmod(F.col("h") - F.col("g"), F.lit(groups))).otherwise(0))
    marked.write.partitionBy("kind", "diag").parquet(path)
    old = {*store.cells.values(), *store.counts.values()}
    for key in list(store.cells):
        if key[0] in [p.cell for p in parts]:
            store.cells[key] = f"{path}/kind={key[0]}/diag={key[1]}"
    for kind in ("t", *(p.col for p in parts)):
        store.counts[kind] = f"{path}/kind={kind}/diag=0"
    for p in parts:
        for r in store.spark.read.schema(ROW).parquet(f"{path}/kind=total-{p.cell}/diag=0").collect():
            store.totals[p.cell] = store.totals[p.cell] + np.array(r.v)
    for x in (*old, folder):
        remove(store.spark, x)


def in_one(store: GridStore, part: Part, priors: Priors) -> bool:
    """Whether a fit of one block can stay in a process beside one task."""
    tokens = int(store.totals[part.cell].sum())
    return 0 < tokens <= IN_ONE and native.usable(_rows(store, "t"), [part.size], [tokens], priors.topics) and native.compiled(store.spark, priors.topics) is not None


def _sweeps(store: GridStore, part: Part, priors: Priors, seed: int, iterations: int, tolerance: float, track: bool) -> list[float]:
    """All iterations of one block, token by token, in one task: state in, state out, and the perplexity after each. Draws are those of ``_epoch``."""
    code, topics, tokens = native.compiled(store.spark, priors.topics), priors.topics, int(store.totals[part.cell].sum())
    start = store.totals[part.cell].copy()
    documents = _rows(store, "t")
    frames = [store.read("t", store.counts["t"]), store.diagonal(part.cell, 0), store.read(part.col, store.counts[part.col])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, held, fit = [], [], None
        batches = (b for b in batches if b.num_rows)
        if (first := next(batches, None)) is None:
            return
        with native.Fit(code, topics, documents, priors.alpha, native.memory_mb(documents, [(tokens, part.size)], topics, 1, 0)) as fit:
            fit.add_part(0, part.size, tokens, 1, part.prior)
            row_ids = col_ids = None
            for batch in chain([first], batches):
                table = pa.Table.from_batches([batch]).select(COLUMNS)
                cells = _of(table, part.cell)
                if len(cells) < len(table):  # counts come first, sorted by id
                    counts.append(table.filter(pc.not_equal(table.column("kind"), part.cell)).drop_columns(["v"]))
                if not len(cells):
                    continue
                if row_ids is None:
                    whole = pa.concat_tables(counts)
                    docs, cols = _of(whole, "t"), _of(whole, part.col)
                    row_ids, col_ids = docs.column("a").to_numpy(), cols.column("a").to_numpy()
                n = pc.list_value_length(cells.column("v").combine_chunks()).to_numpy()
                a = np.searchsorted(row_ids, cells.column("a").to_numpy()).astype(np.int32)
                b = np.searchsorted(col_ids, cells.column("b").to_numpy()).astype(np.int32)
                fit.add_tokens(0, np.repeat(a, n), np.repeat(b, n), cells.column("v").combine_chunks().flatten().to_numpy())
                held.append((a, b, n.astype(np.int32)))
            fit.deal(0, np.zeros(documents, np.int32), np.zeros(part.size, np.int32), 1)
            history = [fit.perplexity()] if track else []
            for it in range(iterations):
                fit.sweep(0, 0, WIDE, False, False, stream(seed, it, part.phase, 0, 0))
                fit.close(0)
                if track:
                    history.append(fit.perplexity())
                    if tolerance and converged(history, tolerance):
                        break
            z, theta, phi, end = fit.z(0), fit.theta(), fit.phi(0), fit.totals(0)
        one = lambda kind, a, b, v: pa.table({"kind": [kind] * len(a), "g": [0] * len(a), "h": [0] * len(a), "a": a, "b": b, "v": v}, schema=ARROW_STATE)
        yield from _batches(one(f"total-{part.cell}", [0], [0], [(end - start).tolist()]))
        if history:  # the bits of each number
            yield from _batches(one("history", range(len(history)), np.array(history).view(np.int64), [[]] * len(history)))
        for table, values in ((docs, theta), (cols, phi)):
            for at in range(0, len(table), MANY):
                some = table.slice(at, MANY)
                yield from _batches(some.append_column("v", lists(values[at : at + MANY], topics)))
        at = 0
        for a, b, n in held:
            some = {"kind": pa.array([part.cell] * len(a)), "g": np.zeros(len(a), np.int32), "h": np.zeros(len(a), np.int32), "a": row_ids[a], "b": col_ids[b], "v": lists(z[at : at + (size := int(n.sum()))], n)}
            at += size
            yield from _batches(pa.table(some))

    dealt = _union(frames).repartitionById(1, F.lit(0))
    done = dealt.sortWithinPartitions(F.when(F.col("kind") == part.cell, 1).otherwise(0), "a", "b").mapInArrow(run, STATE)
    store.close(done, 0, (part,), ("t", part.col))
    if not track:
        return []
    found = store.spark.read.schema(ROW).parquet(f"{store.root}/epoch-{store.epochs}/kind=history").select("a", "b").collect()
    return np.array([r.b for r in sorted(found)], np.int64).view(np.float64).tolist()


def converged(history: list[float], tolerance: float) -> bool:
    """Whether the last iteration changed perplexity by less than that share."""
    return len(history) > 1 and abs(history[-1] - history[-2]) < tolerance * history[-2]


def fit_diagonal(matrix: DataFrame, row_groups: DataFrame, col_groups: DataFrame, groups: int, priors: Priors, iterations: int = 200, seed: int = 7, tolerance: float = 0.0, track: bool = True, execution: str = "staged", kernel: str = "waves") -> Fit:
    """Plain model: P epochs an iteration, the P blocks of an epoch in parallel on one copy of the counts.

    ``execution``: "staged" runs a job an epoch; "ring" an iteration in one barrier stage of P tasks. Both draw the same. ``kernel``:
    "waves" draws tokens that share no row or column in one step, "loop" one token at a time.
    """
    return fit_parts(matrix, None, (row_groups, col_groups), None, groups, priors, iterations, seed, tolerance, track, "shared_rows", execution, kernel)


def fit_diagonal_stamped(matrix: DataFrame, stamps: DataFrame, parts, stamp_parts, groups: int, priors: Priors, iterations: int = 200, seed: int = 7, layout: str = "independent", tolerance: float = 0.0, track: bool = True, execution: str = "staged", kernel: str = "waves") -> Fit:
    """Stamped model: in each epoch a diagonal of words, then the same diagonal of stamps.

    ``layout``: "independent" has row groups of their own for the stamps, so documents change task between the two
    phases; "shared_rows" uses the words' row groups for both; "merged" cuts words and stamps as one matrix and draws
    both in one phase an epoch, each with its own prior and totals (``parts`` and ``stamp_parts`` aren't read).
    """
    return fit_parts(matrix, stamps, parts, stamp_parts, groups, priors, iterations, seed, tolerance, track, layout, execution, kernel)


def fit_parts(matrix, stamps, parts, stamp_parts, groups, priors, iterations, seed, tolerance, track, layout, execution, kernel) -> Fit:
    if layout not in LAYOUTS or kernel not in KERNELS or execution not in ("staged", "ring"):
        raise ValueError(f"layout is one of {LAYOUTS}, kernel of {tuple(KERNELS)}, execution staged or ring")
    if execution == "ring" and stamps is not None and layout == "independent":
        raise ValueError("a ring keeps documents in place: lay out with shared rows, or merged")
    store = open_store(matrix, stamps, parts, stamp_parts, groups, priors, seed, layout)
    spec = [Part("z", "p", priors.beta, _rows(store, "p"), 0)]
    if stamps is not None:
        spec.append(Part("y", "q", priors.gamma, _rows(store, "q"), 1))
    phases = [(tuple(spec), "g")] if layout == "merged" else [((p,), "h" if p.cell == "y" else "g") for p in spec]
    if execution == "staged" and kernel == "loop" and groups == 1 and len(spec) == 1 and iterations > 0 and in_one(store, spec[0], priors):
        return finished(store, _sweeps(store, spec[0], priors, seed, iterations, tolerance, track), False)
    history = [_perplexity(matrix, store, priors)] if track else []
    for it in range(iterations):
        if execution == "ring":
            _ring(store, phases, priors, seed, it, kernel)
        else:
            for diag in range(groups):
                for some, row_group in phases:
                    if any((p.cell, diag) in store.cells for p in some):
                        _epoch(store, diag, some, priors, seed, it, row_group, kernel)
        if track:
            history.append(_perplexity(matrix, store, priors))
            if tolerance and converged(history, tolerance):
                break
    return finished(store, history, stamps is not None)


def merged_parts(matrix: DataFrame, stamps: DataFrame, groups: int, method: str = "interleave"):
    """Row groups, and column groups of words and of stamps, from one partition of words and stamps as one matrix."""
    from topicgrid.operators.trials import partition
    from topicgrid.operators.workload import merged_workload

    high = matrix.agg(F.max("col_id").alias("m")).first().m or 0
    low = stamps.agg(F.min("col_id").alias("m")).first().m or 0
    shift = high - min(low, 0) + 1
    both = merged_workload(matrix.select("row_id", "col_id", "n"), stamps.select("row_id", "col_id", "n"), shift)
    p = partition(both.select("row_id", "col_id", "n"), method, groups)
    stamp_cols = p.cols.filter(F.col("id") >= shift + low).withColumn("id", F.col("id") - shift)
    return p.rows, p.cols.filter(F.col("id") < shift + low), stamp_cols


def open_store(matrix, stamps, parts, stamp_parts, groups: int, priors: Priors, seed: int, layout: str) -> GridStore:
    """The state laid out, with first topics, counts and totals."""
    spark, k = matrix.sparkSession, priors.topics
    store = GridStore(spark, shared_folder(spark, "sampler"), groups, k)
    if layout == "merged" and stamps is not None:
        rows, word_cols, stamp_cols = merged_parts(matrix, stamps, groups)
        parts, stamp_parts = (rows, word_cols), (rows, stamp_cols)
    store.lay_out(place_cells(matrix, *parts, "z", k, seed), "z")
    words = store.all_cells("z")
    store.put_counts("p", _counts(words, "col", "p", k))
    docs = _counts(words, "row", "t", k).withColumn("h", F.col("g"))
    if stamps is not None:
        r = stamp_parts[0] if layout == "independent" else parts[0]
        store.lay_out(place_cells(stamps, r, stamp_parts[1], "y", k, seed), "y")
        slots = store.all_cells("y")
        store.put_counts("q", _counts(slots, "col", "q", k))
        # a document counts its words and its stamps; its group among the stamps goes to h
        both = docs.select("a", "g", "v").join(_counts(slots, "row", "t", k).select("a", F.col("g").alias("h"), F.col("v").alias("w")), "a", "full")
        empty = F.array_repeat(F.lit(0), k)
        other = F.pmod("a", F.lit(groups)).cast("int") if layout == "independent" else None
        g, h = (F.coalesce("g", other), F.coalesce("h", other)) if layout == "independent" else (F.coalesce("g", "h"), F.coalesce("g", "h"))
        docs = both.select(g.alias("g"), h.alias("h"), "a", F.lit(0).cast("bigint").alias("b"), F.zip_with(F.coalesce("v", empty), F.coalesce("w", empty), lambda x, y: x + y).alias("v"))
    store.put_counts("t", docs)
    for cell, col in (("z", "p"), ("y", "q")):
        if col in store.counts:
            sums = store.read(col, store.counts[col]).agg(*(F.sum(F.get("v", F.lit(i))).alias(f"c{i}") for i in range(k))).first()
            store.totals[cell] = np.array([int(x or 0) for x in sums], np.int64)
    return store


def _rows(store: GridStore, kind: str) -> int:
    return store.read(kind, store.counts[kind]).count()


def _as_counts(store: GridStore, kind: str, name: str) -> DataFrame:
    return store.read(kind, store.counts[kind]).select(F.col("a").alias(name), F.transform("v", lambda x: x.cast("bigint")).alias("c"))


def finished(store: GridStore, history: list[float], stamped: bool) -> Fit:
    cells = store.all_cells("z").unionByName(store.all_cells("y")) if stamped else store.all_cells("z")
    cells = cells.select("kind", F.col("a").alias("row_id"), F.col("b").alias("col_id"), F.col("v").alias("z"))
    return Fit(_as_counts(store, "t", "row_id"), _as_counts(store, "p", "col_id"), _as_counts(store, "q", "col_id") if stamped else None, history, cells)


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def _perplexity(matrix: DataFrame, store: GridStore, priors: Priors) -> float:
    row = model_perplexity(matrix.select("row_id", "col_id", "n"), _as_counts(store, "t", "row_id"), _as_counts(store, "p", "col_id"), priors.topics, priors.alpha, priors.beta).first()
    return float(row.perplexity)


def fit_serial(matrix: DataFrame, priors: Priors, iterations: int = 200, seed: int = 7, tolerance: float = 0.0, track: bool = True, kernel: str = "loop") -> Fit:
    """The baseline without parallelism: one block, token by token; all iterations in one task for up to ``IN_ONE`` tokens, else a job each."""
    return fit_diagonal(matrix, None, None, 1, priors, iterations, seed, tolerance, track, kernel=kernel)


def fit_serial_stamped(matrix: DataFrame, stamps: DataFrame, priors: Priors, iterations: int = 200, seed: int = 7, tolerance: float = 0.0, track: bool = True, kernel: str = "loop") -> Fit:
    """The stamped model without parallelism: all words, then all stamps, in each iteration."""
    return fit_diagonal_stamped(matrix, stamps, (None, None), (None, None), 1, priors, iterations, seed, "independent", tolerance, track, kernel=kernel)


def fit_replica(matrix: DataFrame, row_groups: DataFrame, groups: int, priors: Priors, iterations: int = 200, seed: int = 7, track: bool = True, kernel: str = "waves") -> Fit:
    """The copy-and-merge baseline: documents are cut, every process has its own copy of all topic-word counts, and the
    changes of all copies are added up after each iteration. Memory for counts grows with P."""
    spark, k = matrix.sparkSession, priors.topics
    cols = matrix.select(F.col("col_id").alias("id"), F.lit(0).alias("grp")).distinct()
    store = open_store(matrix, None, (row_groups, cols), None, groups, priors, seed, "shared_rows")
    part = Part("z", "p", priors.beta, _rows(store, "p"), 2)
    history = [_perplexity(matrix, store, priors)] if track else []
    for it in range(iterations):
        totals = spark.sparkContext.broadcast(store.totals["z"])
        copies = store.read("p", store.counts["p"]).withColumn("task", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
        mine = store.all_cells("z").unionByName(store.read("t", store.counts["t"])).withColumn("task", F.col("g"))

        def run(batches: Iterator[pa.RecordBatch], it=it, totals=totals) -> Iterator[pa.RecordBatch]:
            whole = _whole(batches)
            if whole is None:
                return
            m = whole.column("task")[0].as_py()
            whole = whole.select(COLUMNS)
            block, cells, copy = Block(_of(whole, "t"), k), _of(whole, "z"), _of(whole, "p")
            if len(cells):
                cells, after, change = block.resample(cells, copy, totals.value, part, priors.alpha, kernel, stream(seed, it, 2, 0, m))
                moved = dense(after.column("v"), k) - dense(copy.column("v"), k)
                some = np.flatnonzero(moved.any(axis=1))
                changed = _with(after.take(pa.array(some)), lists(moved[some], k))
                one = {"kind": ["total-z"], "g": [m], "h": [0], "a": [0], "b": [0], "v": [change.tolist()]}
                yield from _batches(pa.table(one, schema=ARROW_STATE), changed.set_column(0, "kind", pa.array(["change"] * len(some), pa.string())), cells)
            yield from _batches(block.documents())

        done = mine.unionByName(copies).repartitionById(groups, F.col("task")).mapInArrow(run, STATE)
        store.epochs += 1
        path = f"{store.root}/epoch-{store.epochs}"
        done.write.partitionBy("kind").parquet(path)
        before = store.read("p", store.counts["p"])
        changed = before.unionByName(store.read("p", f"{path}/kind=change")) if store.exists(f"{path}/kind=change") else before
        sums = changed.groupBy("a").agg(*(F.sum(F.get("v", F.lit(i))).cast("int").alias(f"c{i}") for i in range(k)))
        merged = sums.select(F.lit(0).alias("g"), F.lit(0).alias("h"), "a", F.lit(0).cast("bigint").alias("b"), F.array(*(f"c{i}" for i in range(k))).alias("v"))
        merged.write.parquet(f"{path}/merged")
        for r in store.spark.read.schema(ROW).parquet(f"{path}/kind=total-z").collect():
            store.totals["z"] = store.totals["z"] + np.array(r.v)
        old = {*store.cells.values(), *store.counts.values()}
        store.cells = {("z", 0): f"{path}/kind=z"}
        store.counts = {"t": f"{path}/kind=t", "p": f"{path}/merged"}
        for x in (*old, f"{path}/kind=change"):
            remove(spark, x)
        if track:
            history.append(_perplexity(matrix, store, priors))
    return finished(store, history, False)


def frozen_sweep(assigned: DataFrame, topics: int, alpha: float, beta: float, seed: int = 7) -> DataFrame:
    """row_id, col_id, i, z: every token redrawn once from the counts as they are, its own token excluded.

    All Catalyst: joins and array expressions, no loop over tokens; an approximation that lets all tokens move at once. Weights are
    rounded to 9 places, so any engine draws the same.
    """
    from topicgrid.functions.rng import key
    from topicgrid.model.counts import topic_totals

    t = topic_counts(assigned, "row_id", topics).select("row_id", F.col("c").alias("t"))
    p = topic_counts(assigned, "col_id", topics)
    size = p.agg(F.count(F.lit(1)).alias("w"))
    total = topic_totals(p, topics).select(F.col("c").alias("s")).crossJoin(size)  # one row each
    held = assigned.join(t, "row_id").join(p.select("col_id", F.col("c").alias("p")), "col_id").crossJoin(F.broadcast(total))
    tokens = held.select("row_id", "col_id", "t", "p", "s", "w", F.posexplode("z").alias("i", "old"))
    own = lambda k: F.when(k == F.col("old"), 1).otherwise(0)
    weight = F.transform(F.sequence(F.lit(0), F.lit(topics - 1)), lambda k: F.round((F.get("t", k) - own(k) + alpha) * (F.get("p", k) - own(k) + beta) / (F.get("s", k) - own(k) + F.col("w") * beta), 9))
    cell = F.concat_ws("/", F.col("row_id").cast("string"), F.col("col_id").cast("string"), F.col("i").cast("string"))
    u = key(seed, "word", "frozen", 0, cell).cast("double") / float(1 << 48)
    drawn = tokens.withColumn("weight", weight).withColumn("mass", F.aggregate("weight", F.lit(0.0), lambda a, x: a + x)).withColumn("cut", u * F.col("mass"))
    # how many running sums lie at or below the cut
    step = F.aggregate("weight", F.struct(F.lit(0.0).alias("a"), F.lit(0).alias("k")), lambda s, x: F.struct((s.a + x).alias("a"), (s.k + F.when(s.a + x <= F.col("cut"), 1).otherwise(0)).alias("k")))
    return drawn.select("row_id", "col_id", "i", F.least(step.k, F.lit(topics - 1)).alias("z"))
