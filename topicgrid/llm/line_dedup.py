"""Line dedup with two Bloom filters.

The first pass marks each line's hash in a once-seen and, if it comes again, in a twice-seen filter. Tasks send
only the positions they would set, and position ranges are merged in parallel: a bit that two tasks set for
once-seen is set for twice-seen too, so a line of two documents is never missed. The second pass shuffles only
lines that the twice-seen filter has, whole, counted map-side, for exact confirmation and to choose the first
occurrence. The third pass rewrites the documents.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from topicgrid.llm.common import WHITE, Passing, Scratch, picked, shuffle_width, texts, tidy

SEGMENT = 22  # bits of a position within a segment
LIST_BYTES = 64 << 20  # of repeated keys, with what a dictionary takes for each


def keys_of(text: bytes) -> list[bytes]:
    """The keys of a text's lines: A-Z lower-cased, white space stripped at both ends."""
    return [x.strip(WHITE) for x in text.lower().split(b"\n")]


def positions(h: np.ndarray, bits: int) -> np.ndarray:
    """Two positions a hash in a filter of 2 ** bits, from its lower and upper half."""
    mask = np.uint64((1 << bits) - 1)
    return np.concatenate([h & mask, (h >> np.uint64(64 - bits)) & mask])


def _spread(pos: np.ndarray, kind: int) -> Iterator[tuple[int, int, bytes]]:
    pos = np.unique(pos)
    pack = zstandard.ZstdCompressor(level=1)
    seg = pos >> np.uint64(SEGMENT)
    cuts = np.flatnonzero(np.diff(seg)) + 1
    for part in np.split(pos, cuts):
        if len(part):
            low = (part & np.uint64((1 << SEGMENT) - 1)).astype(np.uint32)
            yield int(part[0] >> np.uint64(SEGMENT)), kind, pack.compress(np.diff(low, prepend=np.uint32(0)).tobytes())


class Filter:
    """A Bloom filter's bits; they travel compressed and are unpacked once a worker."""

    def __init__(self, packed_bits: np.ndarray):
        self.blob = zstandard.compress(packed_bits.tobytes(), 1)
        self.unpacked: np.ndarray | None = None

    def __getstate__(self) -> dict:
        return {"blob": self.blob, "unpacked": None}

    def bytes(self) -> np.ndarray:
        if self.unpacked is None:
            self.unpacked = np.frombuffer(zstandard.decompress(self.blob), np.uint8)
        return self.unpacked


def twice_seen(items: DataFrame, task, bits: int) -> Filter:
    """The twice-seen filter. ``task(batches)`` yields arrays of hashes, each once per document."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        once = np.empty(0, np.uint64)
        twice = np.empty(0, np.uint64)
        held: list[np.ndarray] = []

        def fold() -> None:
            nonlocal once, twice
            h, n = np.unique(np.concatenate([once, *held]), return_counts=True)
            twice = np.union1d(twice, h[n > 1])
            once = h
            held.clear()

        out: list[tuple[int, int, bytes]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            nonlocal once, twice, size
            fold()
            rows = [*_spread(positions(once, bits), 1), *_spread(positions(twice, bits), 2)]
            once = twice = np.empty(0, np.uint64)
            size = 0
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.binary())], names=["seg", "kind", "bits"])

        for h in task(batches):
            held.append(h)
            size += len(h)
            if size > 4_000_000:  # bounds the memory of a task, whatever its share
                yield flush()
        if size:
            yield flush()
        out.clear()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one: dict[int, np.ndarray] = {}
        two: dict[int, np.ndarray] = defaultdict(lambda: np.zeros(1 << SEGMENT, bool))
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            for seg, kind, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                low = np.cumsum(np.frombuffer(unpack.decompress(raw), np.uint32), dtype=np.uint32)
                if kind == 2:
                    two[seg][low] = True
                elif seg not in one:
                    one[seg] = np.zeros(1 << SEGMENT, bool)
                    one[seg][low] = True
                else:
                    two[seg][low[one[seg][low]]] = True
                    one[seg][low] = True
        done = [(s, x) for s, x in two.items() if x.any()]
        yield pa.RecordBatch.from_arrays([pa.array([s for s, _ in done], pa.int32()), pa.array([zstandard.compress(np.packbits(x).tobytes(), 1) for _, x in done], pa.binary())], names=["seg", "bits"])

    width = max(1, 1 << max(0, bits - SEGMENT))
    marked = items.mapInArrow(tidy(mark), "seg int, kind int, bits binary")
    merged = marked.repartition(min(width, 2 * shuffle_width(items.sparkSession)), "seg").mapInArrow(tidy(merge), "seg int, bits binary")
    out = np.zeros(max(1, (1 << bits) >> 3), np.uint8)
    for r in merged.toLocalIterator():
        part = np.frombuffer(zstandard.decompress(bytes(r.bits)), np.uint8)
        at = r.seg << (SEGMENT - 3)
        n = min(len(part), len(out) - at)
        out[at : at + n] = part[:n]
    return Filter(out)


def probe(held: Filter, h: np.ndarray, bits: int) -> np.ndarray:
    """Whether the filter has both positions of each hash."""
    pos, bitmap = positions(h, bits), held.bytes()
    hit = (bitmap[(pos >> np.uint64(3)).astype(np.int64)] >> (7 - (pos & np.uint64(7))).astype(np.uint8)) & 1
    return (hit[: len(h)] & hit[len(h) :]).astype(bool)


def filter_bits(n_bytes: int, per_item: int, least: int = 16, most: int = 30) -> int:
    """log2 of a filter's size: 16 bits for each ``per_item`` bytes of input, 128 MB at most.

    Beyond that the filter fills up: more lines shuffle, the result stays exact.
    """
    return min(most, max(least, int(16 * max(1, n_bytes // per_item) - 1).bit_length()))


def repeated_lines(docs: DataFrame, text_col: str = "text", min_docs: int = 2, min_points: int = 1) -> DataFrame:
    """key (binary), n_docs, first_id: keys of ``min_points`` code points or more in ``min_docs`` documents or more.

    ``docs`` needs doc_id. A row is a document, also where ids repeat.
    """
    spark = docs.sparkSession
    docs, text_col = picked(docs, doc_id="doc_id", text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), "text"
    n_bytes = docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    bits = filter_bits(n_bytes, 64)

    def long_enough(k: bytes) -> bool:
        return len(k) >= min_points and (min_points <= 1 or len(k.decode()) >= min_points)

    def hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            held: list[int] = []
            for t in texts(batch.column(0)):
                held += [xxhash.xxh3_64_intdigest(k) for k in set(keys_of(t)) if long_enough(k)]
            yield np.array(held, np.uint64)

    bitmap = spark.sparkContext.broadcast(twice_seen(docs.select("text"), hashes, bits))

    def suspects(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[bytes, list] = {}
        size = 0

        def flush() -> pa.RecordBatch:
            nonlocal size
            out = pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array([v[0] for v in seen.values()], pa.int64()), pa.array([v[1] for v in seen.values()], pa.int64())], names=["key", "n_docs", "first_id"])
            seen.clear()
            size = 0
            return out

        for batch in batches:
            ids = batch.column(0).to_pylist()
            of, keys = [], []
            for i, t in zip(ids, texts(batch.column(1)), strict=True):
                own = [k for k in set(keys_of(t)) if long_enough(k)]
                keys += own
                of += [i] * len(own)
            if not keys:
                continue
            hit = probe(bitmap.value, np.fromiter((xxhash.xxh3_64_intdigest(k) for k in keys), np.uint64, len(keys)), bits)
            for j in np.flatnonzero(hit):
                k, i = keys[j], of[j]
                if (v := seen.get(k)) is None:
                    seen[k] = [1, i]
                    size += len(k) + 200
                else:
                    v[0] += 1
                    if i is not None and (v[1] is None or i < v[1]):
                        v[1] = i
            if size > 64 << 20:
                yield flush()
        yield flush()

    found = docs.mapInArrow(tidy(suspects), "key binary, n_docs bigint, first_id bigint")
    return found.groupBy("key").agg(F.sum("n_docs").alias("n_docs"), F.min("first_id").alias("first_id")).filter(F.col("n_docs") >= min_docs)


def _rewrite(ids: list, raw: list[bytes], drop, keep: str) -> tuple[list[int], list[int], list[str]]:
    """Lines, dropped lines and what is left of each text; ``drop(i, keys)`` gives a key's first document, or nothing."""
    lines, gone, left = [], [], []
    for i, t in zip(ids, raw, strict=True):
        keys = keys_of(t)
        known = drop(i, keys)
        if not known:
            lines.append(len(keys))
            gone.append(0)
            left.append(t)
            continue
        kept, mine = [], set()
        for line, k in zip(t.split(b"\n"), keys, strict=True):
            if k not in known:
                kept.append(line)
            elif keep == "first" and known[k] == i and k not in mine:
                mine.add(k)
                kept.append(line)
        lines.append(len(keys))
        gone.append(len(keys) - len(kept))
        left.append(b"\n".join(kept))
    return lines, gone, [x.decode() for x in left]


def line_dedup(docs: DataFrame, text_col: str = "text", min_docs: int = 2, min_points: int = 1, keep: str = "first", list_bytes: int = LIST_BYTES) -> DataFrame:
    """``docs`` with text rewritten, and n_lines, n_dropped.

    Texts split at ``\\n``; a null or empty text is one empty line. Keys found in ``min_docs`` rows or more lose
    their lines: all of them with ``keep="none"``, all but the first in the row with the smallest doc_id with
    ``keep="first"`` (rows that share that doc_id each keep one; where all ids are null none is kept). A document that loses nothing keeps its
    text byte by byte, and null becomes empty; an empty table gives an empty one. Other columns pass through; columns of the names n_lines and
    n_dropped, in any case, are replaced. The list of repeated keys goes to every task if it takes at most ``list_bytes`` there; else it is
    joined by key.
    """
    assert keep in ("first", "none")
    spark = docs.sparkSession
    scratch = Scratch(spark, "lines")
    rep = scratch.table(repeated_lines(docs, text_col, min_docs, min_points), "repeated")
    passing = Passing.of(docs, [text_col, "doc_id"], ("n_lines", "n_dropped"))
    at_text, at_id = passing.at[text_col], passing.at["doc_id"]
    schema = passing.schema.add("n_lines", "long").add("n_dropped", "long")
    schema.fields[at_text].dataType = StringType()
    names = passing.frame.columns

    def rebuilt(batch: pa.RecordBatch, own: list, drop) -> pa.RecordBatch:
        n, d, left = _rewrite(own, texts(batch.column(at_text)), drop, keep)
        cols = list(batch.columns[: len(names)])
        cols[at_text] = pa.array(left, pa.string())
        return pa.RecordBatch.from_arrays([*cols, pa.array(n, pa.int64()), pa.array(d, pa.int64())], names=[*names, "n_lines", "n_dropped"])

    if (rep.agg(F.sum(F.octet_length("key") + 200)).first()[0] or 0) <= list_bytes:
        table = spark.sparkContext.broadcast({bytes(r.key): r.first_id for r in rep.select("key", "first_id").toLocalIterator()})

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            listed = table.value
            for batch in batches:
                yield rebuilt(batch, batch.column(at_id).to_pylist(), lambda i, keys: {k: listed[k] for k in keys if k in listed})

        return passing.returned(passing.frame.mapInArrow(tidy(run), schema))

    def occurrences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, t in zip(batch.column(0).to_pylist(), texts(batch.column(1)), strict=True):
                own = list(set(keys_of(t)))
                mark = xxhash.xxh3_128_digest(t)
                yield pa.RecordBatch.from_arrays([pa.array([i] * len(own), pa.int64()), pa.array([mark] * len(own), pa.binary()), pa.array(own, pa.binary())], names=["id", "mark", "key"])

    def with_mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([xxhash.xxh3_128_digest(t) for t in texts(batch.column(at_text))], pa.binary())], names=[*names, "own_mark"])

    slim = passing.frame.select(passing.col("doc_id").cast("long").alias("id"), passing.col(text_col).cast("string").alias("text"))
    held = slim.mapInArrow(tidy(occurrences), "id bigint, mark binary, key binary").distinct()
    lists = held.join(rep.hint("merge"), "key").groupBy("id", "mark").agg(F.collect_list(F.struct("key", "first_id")).alias("listed"))
    marked = passing.frame.mapInArrow(tidy(with_mark), passing.schema.add("own_mark", "binary"))
    joined = marked.join(lists.hint("merge"), passing.col("doc_id").eqNullSafe(F.col("id")) & (F.col("own_mark") == F.col("mark")), "left").select(*names, "listed")

    def run_joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            listed = iter(batch.column(len(names)).to_pylist())
            yield rebuilt(batch, batch.column(at_id).to_pylist(), lambda i, keys: {bytes(x["key"]): x["first_id"] for x in next(listed) or ()})

    return passing.returned(joined.mapInArrow(tidy(run_joined), schema))
