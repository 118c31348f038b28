"""Suffix-array dedup: every byte that lies in a 50-byte string which also starts in an earlier document goes.

The suffix array is sparse. Each 50-byte window is filed under its anchor, the place in it where the hash of 24
bytes is least; equal windows have equal anchors, so only suffixes at anchors, one in fourteen bytes, need sorting. A
twice-seen filter drops anchors that one document alone has, and whole copies of an earlier text are settled by their SHA-256.
The rest is range-partitioned by sampled splitters on the suffixes' leading 8-byte tokens (a token that fills several
ranges is spread over them by its next tokens, so that equal suffixes always meet: the two sides of a boundary have nothing to
compare), sorted in each bucket by multikey quicksort, and the windows of suffixes that agree at their anchor are
compared whole, byte by byte. What is equal takes the smallest doc_id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.llm.common import Passing, Scratch, blocks, mix64, shuffle_width, small_enough, tidy, unplaced, utf8_view
from topicgrid.llm.line_dedup import filter_bits, probe, twice_seen

MATCH, SEED = 50, 24
REACH = MATCH - SEED + 1  # anchors to choose from in a window
LONGEST = 1 << 17  # bytes laid out at once
PLACE_BITS = 20
PACK_ROWS = 96 << 10  # bytes of text for each bucket, up to 16 MB, whose runs are packed together
MOST_PACKED = 16 << 20
COPY_ROWS = 500_000  # copied texts in a broadcast
SMALL = 1 << 15  # suffixes that are sorted at once
STEP = 1 << 20  # windows compared at once
LIST_BYTES, LIST_ROWS = 32 << 20, 400_000
LAST = np.iinfo(np.int64).max  # stands for a null doc_id
_C = mix64(np.arange(1, 17, dtype=np.uint64) << np.uint64(7)) | np.uint64(1)
U = np.uint64


def words_at(data: np.ndarray, at: np.ndarray | slice) -> np.ndarray:
    """The 8 bytes from each place, as a little-endian number. ``data`` ends in 8 bytes of padding at least."""
    view = np.ndarray((len(data) - 7,), "<u8", data, strides=(1,))
    return view[at]


class Anchored:
    """Runs of windows of a block that share an anchor."""

    def __init__(self, data: np.ndarray, off: np.ndarray):
        n = len(data)
        self.data = np.concatenate([data, np.zeros(96, np.uint8)])
        self.row = self.begin = self.end = self.anchor = np.empty(0, np.int64)
        self.hash = np.empty(0, np.uint64)
        size = np.diff(off)
        if n < MATCH or size.max(initial=0) < MATCH:
            return
        with np.errstate(over="ignore"):
            h = words_at(self.data, slice(0, n)) * _C[0]
            h += words_at(self.data, slice(8, n + 8)) * _C[1]
            h += words_at(self.data, slice(16, n + 16)) * _C[2]
        h = mix64(h)
        # the place in the low bits: of equal hashes the left one is least
        low = U((1 << PLACE_BITS) - 1)
        least = (h & ~low) | np.arange(n, dtype=np.uint64)
        for d in (1, 2, 4, 8, REACH - 16):
            least = np.minimum(least[d:], least[:-d])
        place = (least & low).astype(np.int32)
        windows = n - MATCH + 1
        place = place[:windows]
        valid = np.zeros(windows + 1, bool)
        for a, b in zip(off[:-1][size >= MATCH].tolist(), off[1:][size >= MATCH].tolist(), strict=True):
            valid[a : b - MATCH + 1] = True
        first = valid[:-1].copy()
        first[1:] &= ~valid[:-2] | (place[1:] != place[:-1])
        self.begin = np.flatnonzero(first)
        last = valid[:-1].copy()
        last[:-1] &= ~valid[1:-1] | (place[1:] != place[:-1])
        self.end = np.flatnonzero(last) + MATCH
        self.anchor = place[self.begin].astype(np.int64)
        self.hash = h[self.anchor]
        self.row = np.searchsorted(off, self.begin, side="right") - 1

    def contents(self) -> np.ndarray:
        """A hash of the bytes of each run and of its anchor's place."""
        last = self.end - 8
        with np.errstate(over="ignore"):
            h = ((self.end - self.begin) << 8 | (self.anchor - self.begin)).astype(np.uint64) * _C[15]
            for t in range(10):
                h = h + mix64(words_at(self.data, np.minimum(self.begin + 8 * t, last))) * _C[t]
        return mix64(h)


def laid_out(batch: pa.RecordBatch, text: str) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Bytes, bounds, row and place in its document of each part: very long documents in parts that overlap by a window less a byte."""
    data, off = utf8_view(batch.column(text))
    size = np.diff(off)
    if size.max(initial=0) <= 2 * LONGEST:
        yield data, off, np.arange(len(size)), np.zeros(len(size), np.int64)
        return
    for k, n in enumerate(size.tolist()):
        for at in range(0, max(1, n - MATCH + 1), LONGEST):
            part = data[off[k] + at : min(off[k + 1], off[k] + at + LONGEST + MATCH - 1)]
            yield part, np.array([0, len(part)]), np.array([k]), np.array([at])


def multikey_sort(tokens: list[np.ndarray], small: int = SMALL) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows by their token strings, and whether each begins a group of equal ones.

    Three-way quicksort on one token at a time, for all segments at once: each is split by a pivot, the median of three, into what is
    less, equal and greater; equal rows go on to their next token. Segments of at most ``small`` rows are sorted directly.
    """
    n = len(tokens[0])
    order, key = np.arange(n), np.stack(tokens)
    begin, size, depth = np.zeros(1, np.int64), np.array([n]), np.zeros(1, np.int64)
    rest: list[tuple[np.ndarray, np.ndarray]] = []
    while True:
        large = size > small
        rest.append((begin[~large], size[~large]))
        begin, size, depth = begin[large], size[large], depth[large]
        if not len(begin):
            break
        at = _ragged(begin, size)
        seg = np.repeat(np.arange(len(begin)), size)
        rows = order[at]
        value = key[depth[seg], rows]
        three = np.sort(key[depth, order[np.stack([begin, begin + size // 2, begin + size - 1])]], axis=0)
        pivot = three[1][seg]
        less, equal = value < pivot, value == pivot
        n_less, n_equal = (np.bincount(seg, m, len(begin)).astype(np.int64) for m in (less, equal))
        first = np.concatenate([[0], np.cumsum(size)[:-1]])
        rank = lambda m: (c := np.cumsum(m) - m) - c[first][seg]
        to = np.where(less, rank(less), np.where(equal, n_less[seg] + rank(equal), (n_less + n_equal)[seg] + rank(~less & ~equal)))
        order[begin[seg] + to] = rows
        parts = (n_less, n_equal, size - n_less - n_equal)
        begin = np.concatenate([begin, begin + n_less, begin + n_less + n_equal])
        depth = np.concatenate([depth, depth + 1, depth])
        size = np.concatenate(parts)
        go = (size > 0) & (depth < len(tokens))
        begin, size, depth = begin[go], size[go], depth[go]
    begin, size = (np.concatenate(x) for x in zip(*rest, strict=True))
    for a, m in zip(begin.tolist(), size.tolist(), strict=True):
        order[a : a + m] = _sorted_directly(tokens, order[a : a + m])
    first = np.ones(n, bool)
    first[1:] = np.logical_or.reduce([t[order[1:]] != t[order[:-1]] for t in tokens])
    return order, first


def _sorted_directly(tokens: list[np.ndarray], rows: np.ndarray) -> np.ndarray:
    """A short segment: by one token, then what ties by the next."""
    rows = rows[np.argsort(tokens[0][rows])]
    tied = np.concatenate([[False], tokens[0][rows[1:]] == tokens[0][rows[:-1]]])
    for t in tokens[1:]:
        group = np.cumsum(~tied)
        at = np.flatnonzero(tied | np.append(tied[1:], False))
        if not len(at):
            break
        some = rows[at]
        rows[at] = some = some[np.lexsort((t[some], group[at]))]
        tied[at[1:]] &= t[some[1:]] == t[some[:-1]]
    return rows


class Splitters:
    """Ranges of leading tokens of about equal share; a token that fills several is spread over them by what follows it."""

    def __init__(self, sample: np.ndarray, ranges: int):
        sample = np.sort(sample)
        cuts = sample[np.linspace(0, len(sample) - 1, ranges + 1).astype(np.int64)[1:-1]] if len(sample) and ranges > 1 else np.empty(0, np.uint64)
        self.cuts = cuts

    def bucket(self, lead: np.ndarray, rest: np.ndarray) -> np.ndarray:
        lo = np.searchsorted(self.cuts, lead, side="left")
        hi = np.searchsorted(self.cuts, lead, side="right")
        return (lo + (rest % (hi - lo + 1).astype(np.uint64)).astype(np.int64)).astype(np.int32)


def _gather(data: np.ndarray, begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    return data[_ragged(begin, size)]


#: Columns of a pack and their types: of documents, of runs, of the documents that hold them.
COLUMNS = (("id", "<i8"), ("mark", "<i8"), ("anchor", "u1"), ("size", "u1"), ("held", "<u4"), ("content", "u1"), ("doc", "<u4"), ("start", "<i8"))


def pack(columns: dict[str, np.ndarray]) -> bytes:
    raw = [np.ascontiguousarray(columns[name].astype(kind)).tobytes() for name, kind in COLUMNS]
    head = np.array([len(r) for r in raw], "<i8").tobytes()
    return zstandard.compress(head + b"".join(raw), 3)


def unpack(blob: bytes) -> dict[str, np.ndarray]:
    raw = zstandard.decompress(blob)
    size = np.frombuffer(raw, "<i8", len(COLUMNS))
    ends = 8 * len(COLUMNS) + np.cumsum(size)
    return {name: np.frombuffer(raw[e - n : e], kind) for (name, kind), n, e in zip(COLUMNS, size.tolist(), ends.tolist(), strict=True)}


class Held:
    """Suspect runs of some blocks, until they are packed by bucket."""

    def __init__(self):
        self.clear()

    def clear(self) -> None:
        self.size, self.parts, self.ids, self.marks, self.docs = 0, [], [], [], 0

    def add(self, runs: Anchored, hit: np.ndarray, ids: np.ndarray, marks: np.ndarray, first: np.ndarray) -> None:
        """``ids``, ``marks`` and ``first`` (place of its first byte, less its place here) of each document of a block."""
        row, begin, end, anchor = runs.row[hit], runs.begin[hit], runs.end[hit], runs.anchor[hit]
        lead = words_at(runs.data, anchor).byteswap()
        self.parts.append((runs.contents()[hit], lead, runs.hash[hit], anchor - begin, end - begin, self.docs + row, begin + first[row], _gather(runs.data, begin, end - begin)))
        self.ids.append(ids)
        self.marks.append(marks)
        self.docs += len(ids)

    def packs(self, splitters: Splitters) -> Iterator[tuple[int, bytes]]:
        """Bucket and pack; equal runs are one row with all documents that hold them."""
        if not self.parts:
            return
        content, lead, seed, anchor, size, doc_of, starts, raw = (np.concatenate(c) for c in zip(*self.parts, strict=True))
        ids, marks = np.concatenate(self.ids), np.concatenate(self.marks)
        self.clear()
        at = np.cumsum(size) - size
        order = np.argsort(content, kind="stable")
        heads = np.concatenate([[True], content[order[1:]] != content[order[:-1]]])
        padded = np.concatenate([raw, np.zeros(8, np.uint8)])
        words = lambda rows, t: words_at(padded, at[rows] + np.minimum(8 * t, size[rows] - 8))
        head_of = order[np.maximum.accumulate(np.where(heads, np.arange(len(order)), 0))]
        same = (size[order] == size[head_of]) & (anchor[order] == anchor[head_of])
        for t in range(10):
            same &= words(order, t) == words(head_of, t)
        if not same.all():  # different runs of one hash: sort by the bytes
            every = np.arange(len(order))
            columns = [*(words(every, t) for t in range(10)), size, anchor]
            order = np.lexsort(columns)
            heads = np.concatenate([[True], np.logical_or.reduce([c[order[1:]] != c[order[:-1]] for c in columns])])
        first = np.flatnonzero(heads)
        held = np.diff(np.append(first, len(order)))
        rep = order[first]
        bucket = splitters.bucket(lead[rep], seed[rep])
        by = np.lexsort((rep, bucket))  # in a bucket by place, which packs better
        cuts = np.flatnonzero(np.concatenate([[True], np.diff(bucket[by]) != 0, [True]]))
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            g = by[a:b]
            occ = order[_ragged(first[g], held[g])]
            used, doc = np.unique(doc_of[occ], return_inverse=True)
            r = rep[g]
            yield int(bucket[g[0]]), pack({"id": ids[used], "mark": marks[used], "anchor": anchor[r], "size": size[r], "held": held[g], "content": _gather(raw, at[r], size[r]), "doc": doc, "start": starts[occ]})


SUSPECT = "bucket int, pack binary"


def _suspects(bitmap, bits: int, splitters: Splitters | None, ranges: int = 1):
    """Runs whose anchor two documents seem to have, packed by bucket; without splitters only their leading tokens."""

    packed = min(MOST_PACKED, ranges * PACK_ROWS)

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = Held()

        def flush() -> pa.RecordBatch:
            rows = list(held.packs(splitters))
            return pa.RecordBatch.from_arrays([pa.array([b for b, _ in rows], pa.int32()), pa.array([p for _, p in rows], pa.binary())], names=["bucket", "pack"])

        for batch in blocks(batches, "text", LONGEST):
            ids, marks = (batch.column(c).to_numpy() for c in ("doc_id", "mark"))
            for data, off, rows, base in laid_out(batch, "text"):
                runs = Anchored(data, off)
                if not len(runs.begin):
                    continue
                hit = probe(bitmap.value, runs.hash, bits)
                if splitters is None:
                    lead = words_at(runs.data, runs.anchor[hit]).byteswap()
                    yield pa.RecordBatch.from_arrays([pa.array((lead ^ U(1 << 63)).view(np.int64))], names=["lead"])
                    continue
                held.add(runs, hit, ids[rows], marks[rows], base - off[:-1])
                held.size += len(data)
                if held.size >= packed:
                    yield flush()
        if splitters is not None:
            yield flush()

    return emit


def _ragged(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin[k], begin[k] + 1, ... of each row, one after the other."""
    off = np.concatenate([[0], np.cumsum(size)])
    return np.repeat(begin - off[:-1], size) + np.arange(off[-1])


def _slices(weight: np.ndarray, most: int) -> Iterator[slice]:
    """Consecutive rows of at most that weight together, one row at least."""
    ends = np.cumsum(weight)
    at = 0
    while at < len(weight):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, side="right")))
        yield slice(at, to)
        at = to


def equal_windows(data: np.ndarray, begin: np.ndarray, relative: np.ndarray, value: np.ndarray) -> np.ndarray:
    """For each window the least value of all windows equal to it."""
    loads = [words_at(data, begin + t) for t in (0, 8, 16, 24, 32, 40, MATCH - 8)]
    with np.errstate(over="ignore"):
        key = relative.astype(np.uint64) * _C[15]
        for t, w in enumerate(loads):
            key = key + mix64(w) * _C[t]
    order = np.argsort(key)
    same = lambda o: np.logical_and.reduce([w[o[1:]] == w[o[:-1]] for w in loads])
    equal = same(order)
    if (~equal & (key[order[1:]] == key[order[:-1]])).any():  # different windows of one hash: sort by the bytes
        order = np.lexsort(loads)
        equal = same(order)
    first = np.flatnonzero(np.concatenate([[True], ~equal]))
    least = np.minimum.reduceat(value[order], first)
    out = np.empty(len(value), value.dtype)
    out[order] = np.repeat(least, np.diff(np.append(first, len(order))))
    return out


def _joined(packs: Iterator[dict[str, np.ndarray]]) -> dict[str, np.ndarray]:
    """All packs of a bucket in one, documents numbered through."""
    parts: dict[str, list[np.ndarray]] = {name: [] for name, _ in COLUMNS}
    docs = 0
    for p in packs:
        for name, _ in COLUMNS:
            parts[name].append(p[name].astype(np.int64) + docs if name == "doc" else p[name])
        docs += len(p["id"])
    return {name: np.concatenate(x) if x else np.empty(0, np.int64) for name, x in parts.items()}


def _bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Spans to remove, packed by document: what a bucket's windows have in common with an earlier document."""
    whole = _joined(unpack(blob) for b in batches for blob in b.column("pack").to_pylist())
    if not len(whole["size"]):
        return
    data = np.concatenate([whole["content"], np.zeros(96, np.uint8)])
    size, anchor = whole["size"].astype(np.int64), whole["anchor"].astype(np.int64)
    at = np.cumsum(size) - size
    held = whole["held"].astype(np.int64)
    loff = np.concatenate([[0], np.cumsum(held)])
    docs = whole["id"][whole["doc"]]
    starts = whole["start"]
    least, most = np.minimum.reduceat(docs, loff[:-1]), np.maximum.reduceat(docs, loff[:-1])
    order, first = multikey_sort([words_at(data, at + anchor + 8 * t).byteswap() for t in range(SEED // 8)])
    heads = np.flatnonzero(first)
    rows_in = np.diff(np.append(heads, len(order)))
    group_least = np.minimum.reduceat(least[order], heads)
    alone = np.maximum.reduceat(most[order], heads) == group_least  # an anchor of one document
    # groups whose runs are all the same go as a whole, without a look at their windows
    head_of = np.repeat(order[heads], rows_in)
    same = (size[order] == size[head_of]) & (anchor[order] == anchor[head_of])
    last = size[order] - 8
    for t in range(10):
        step = np.minimum(8 * t, last)
        same &= words_at(data, at[order] + step) == words_at(data, at[head_of] + np.minimum(8 * t, size[head_of] - 8))
    uniform = np.logical_and.reduceat(same, heads) & ~alone
    out: list[tuple[np.ndarray, ...]] = []
    rows = order[np.repeat(uniform, rows_in)]
    if len(rows):
        o = _ragged(loff[rows], held[rows])
        gone = docs[o] > np.repeat(np.repeat(group_least[uniform], rows_in[uniform]), held[rows])
        long = np.repeat(size[rows], held[rows])[gone]
        o = o[gone]
        out.append((whole["doc"][o], starts[o], starts[o] + long))
    mixed = ~uniform & ~alone
    order, rows_in = order[np.repeat(mixed, rows_in)], rows_in[mixed]
    out += _window_spans(data, at, anchor, size, held, loff, docs, whole["doc"], starts, least, order, rows_in)
    if out:
        doc, a, b = (np.concatenate(c) for c in zip(*out, strict=True))
        if len(doc):
            yield _packed(whole["id"][doc], whole["mark"][doc], a, b)


def _window_spans(data, at, anchor, size, held, loff, docs, doc, starts, least, order, rows_in) -> Iterator[tuple[np.ndarray, ...]]:
    """Spans of groups whose runs differ: every window is compared with those of the same anchor."""
    group_end = np.cumsum(rows_in)
    n_windows = size - MATCH + 1
    per_group = np.add.reduceat(n_windows[order], group_end - rows_in) if len(order) else np.empty(0, np.int64)
    for part in _slices(per_group, STEP):
        rows = order[group_end[part.start] - rows_in[part.start] : group_end[part.stop - 1]]
        nw = n_windows[rows]
        woff = np.concatenate([[0], np.cumsum(nw)])
        begin = _ragged(at[rows], nw)
        relative = np.repeat(anchor[rows] + at[rows], nw) - begin
        least_of = equal_windows(data, begin, relative, np.repeat(least[rows], nw))
        occ, of = _ragged(loff[rows], held[rows]), np.repeat(np.arange(len(rows)), held[rows])
        for some in _slices(nw[of], 2 * STEP):
            o, r = occ[some], of[some]
            window = _ragged(woff[r], nw[r])
            gone = np.repeat(docs[o], nw[r]) > least_of[window]
            begins = np.zeros(len(gone), bool)
            begins[np.concatenate([[0], np.cumsum(nw[r])[:-1]])] = True
            ends = np.append(begins[1:], True)
            a = np.flatnonzero(gone & (begins | ~np.concatenate([[False], gone[:-1]])))
            b = np.flatnonzero(gone & (ends | ~np.append(gone[1:], False)))
            which = np.repeat(np.arange(len(o)), nw[r])[a]
            shift = starts[o[which]] - woff[r[which]]
            yield doc[o[which]], window[a] + shift, window[b] + shift + MATCH


def merged(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of spans [a, b) sorted by a."""
    reach = np.maximum.accumulate(b)
    first = np.concatenate([[True], a[1:] > reach[:-1]])
    heads = np.flatnonzero(first)
    return a[heads], reach[np.append(heads[1:] - 1, len(a) - 1)]


def _packed(d: np.ndarray, m: np.ndarray, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    order = np.lexsort((a, m, d))
    d, m, a, b = d[order], m[order], a[order], b[order]
    heads = np.flatnonzero(np.concatenate([[True], (d[1:] != d[:-1]) | (m[1:] != m[:-1])]))
    spans = []
    for x, y in zip(heads.tolist(), np.append(heads[1:], len(d)).tolist(), strict=True):
        spans.append(np.stack(merged(a[x:y], b[x:y]), 1).astype("<i8").tobytes())
    return pa.RecordBatch.from_arrays([pa.array(d[heads]), pa.array(m[heads]), pa.array(spans, pa.binary())], names=["doc_id", "mark", "spans"])


def _merge_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        spans = []
        for parts in batch.column(2).to_pylist():
            x = np.frombuffer(b"".join(parts), "<i8").reshape(-1, 2)
            x = x[np.argsort(x[:, 0], kind="stable")]
            spans.append(np.stack(merged(x[:, 0], x[:, 1]), 1).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(spans, pa.binary())], names=["doc_id", "mark", "spans"])


def repeated_spans(docs: DataFrame) -> DataFrame:
    """doc_id, mark, spans (pairs of 64-bit bounds, merged) of documents that lose bytes. ``docs``: doc_id, mark, text, no nulls."""
    spark = docs.sparkSession
    n_bytes = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = filter_bits(n_bytes, 14, most=29)

    def anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in blocks(batches, "text", LONGEST):
            for data, off, _, _ in laid_out(batch, "text"):
                yield Anchored(data, off).hash

    bitmap = spark.sparkContext.broadcast(twice_seen(docs.select("text"), anchors, bits))
    few = F.pmod(F.xxhash64("doc_id", "mark"), F.lit(max(1, min(256, n_bytes >> 22)))) == 0  # for the splitters only
    sample = docs.filter(few).mapInArrow(tidy(_suspects(bitmap, bits, None)), "lead bigint").orderBy(F.xxhash64("lead")).limit(20_000)
    lead = np.array([r.lead for r in sample.collect()], np.int64).view(np.uint64) ^ U(1 << 63)
    ranges = max(shuffle_width(spark), n_bytes // (24 << 20))
    found = docs.mapInArrow(tidy(_suspects(bitmap, bits, Splitters(lead, ranges), ranges)), SUSPECT)
    spans = found.repartitionById(ranges, F.col("bucket")).mapInArrow(tidy(_bucket), "doc_id bigint, mark bigint, spans binary")
    return spans.groupBy("doc_id", "mark").agg(F.collect_list("spans").alias("spans")).mapInArrow(tidy(_merge_lists), "doc_id bigint, mark bigint, spans binary")


def _with_copies(own: Passing, text, key, scratch: Scratch, copy_rows: int) -> DataFrame:
    """The passing columns with key (doc_id, or the largest number), mark (a hash of the text) and copy: whether an earlier document has just this text."""
    named = own.frame.withColumns({"key": key, "mark": F.xxhash64(text), "sha": F.unhex(F.sha2(text.cast("binary"), 256))})
    copies = named.groupBy("mark", "sha").agg(F.min("key").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    copies = scratch.table(copies, "copies", few=True)
    few = small_enough(copies, copy_rows)
    if few:
        found = named.join(F.broadcast(copies), ["mark", "sha"], "left")
    else:  # hot texts can be split, since the smaller side is placed anew
        found = named.join(unplaced(copies, "mark").hint("merge"), ["mark", "sha"], "left")
    found = found.select(*own.frame.columns, "key", "mark", F.coalesce(F.col("first") < F.col("key"), F.lit(False)).alias("copy"))
    return found if few else scratch.table(found, "marked")


def suffix_dedup(docs: DataFrame, text_col: str = "text", list_bytes: int = LIST_BYTES, copy_rows: int = COPY_ROWS) -> DataFrame:
    """``docs`` with kept (binary: what is left of the UTF-8 bytes), n_bytes, n_removed, n_spans.

    A byte goes if a 50-byte string that covers it also starts in a row with a smaller doc_id; rows that share a
    doc_id don't remove from each other, a null doc_id counts as larger than all others. Null texts are empty; texts
    under 50 bytes stay; very long ones are read in overlapping parts; an empty table gives an empty one. Columns named like the new ones, in
    any case, are replaced, others pass through. The spans are broadcast if they take at most ``list_bytes``, else joined by document; copied
    texts are broadcast up to ``copy_rows``, else joined.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "suffix")
    added = ("kept", "n_bytes", "n_removed", "n_spans")
    own = Passing.of(docs, [text_col, "doc_id"], added)
    names, at_text = own.frame.columns, own.at[text_col]
    text = F.coalesce(own.col(text_col).cast("string"), F.lit(""))
    # whole copies of an earlier document go as they are: they need no suffixes, and neither are they a source of their own
    marked = _with_copies(own, text, F.coalesce(own.col("doc_id").cast("long"), F.lit(int(LAST))), scratch, copy_rows)
    slim = marked.filter(~F.col("copy")).select(F.col("key").alias("doc_id"), "mark", text.alias("text"))
    spans = scratch.table(repeated_spans(slim), "spans", few=True)
    stat = spans.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.octet_length("spans")), F.lit(0)).alias("b")).first()
    schema = own.schema.add("kept", "binary").add("n_bytes", "long").add("n_removed", "long").add("n_spans", "long")

    def rebuilt(batch: pa.RecordBatch, found: list) -> pa.RecordBatch:
        data, off = utf8_view(batch.column(at_text))
        kept, gone, n_spans = [], [], []
        for k, (s, copy) in enumerate(zip(found, batch.column("copy").to_pylist(), strict=True)):
            t = data[off[k] : off[k + 1]]
            if copy and len(t) >= MATCH:
                kept.append(b"")
                gone.append(len(t))
                n_spans.append(1)
                continue
            if s is None:
                kept.append(t.tobytes())
                gone.append(0)
                n_spans.append(0)
                continue
            x = np.frombuffer(s, "<i8").reshape(-1, 2)
            left = np.ones(len(t), bool)
            for a, b in x.tolist():
                left[a:b] = False
            kept.append(t[left].tobytes())
            gone.append(int((x[:, 1] - x[:, 0]).sum()))
            n_spans.append(len(x))
        return pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(kept, pa.binary()), pa.array(np.diff(off)), pa.array(gone, pa.int64()), pa.array(n_spans, pa.int64())], names=[*names, *added])

    if stat.b <= list_bytes and stat.n <= LIST_ROWS:
        listed = spark.sparkContext.broadcast({(r.doc_id, r.mark): bytes(r.spans) for r in spans.toLocalIterator()})

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ids, marks = (batch.column(c).to_pylist() for c in ("key", "mark"))
                yield rebuilt(batch, [listed.value.get(k) for k in zip(ids, marks, strict=True)])

        return own.returned(marked.mapInArrow(tidy(run), schema))

    def run_joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield rebuilt(batch, batch.column("spans").to_pylist())

    right = spans.select(F.col("doc_id").alias("key"), "mark", "spans")
    return own.returned(marked.join(right.hint("merge"), ["key", "mark"], "left").select(*names, "copy", "spans").mapInArrow(tidy(run_joined), schema))
