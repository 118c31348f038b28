"""Cells of texts by word: what a block of documents has of a word travels as one record, so words are written, moved and compared once a block.

A block ends where a document does. A record's cells are numbers of the least width that holds them: the document's distance from the
block's least id, and how often the word occurs in it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 1 << 21  # tokens of a block, or one document's where that has more
SOME = 1 << 17  # cells of a batch
CELLS = [np.dtype([("row", r), ("n", n)]) for r in ("<u2", "<u4", "<u8") for n in ("<u1", "<u8")]
SCHEMA = "word string, df bigint, cf bigint, base bigint, kind int, cells binary"


def postings(counts: DataFrame) -> DataFrame:
    """word, df, cf, base, kind, cells from row_id, word (tokens) or row_id, word, n (counts); a word has a record a block.

    Row ids aren't null. Of tokens those of a row lie together, in one task; of counts a row and word occur once.
    """
    return counts.mapInArrow(_pack, SCHEMA)


def cells(records: DataFrame) -> DataFrame:
    """row_id, col_id, n of records with col_id."""
    return records.select("col_id", "base", "kind", "cells").mapInArrow(_unpack, "row_id bigint, col_id bigint, n bigint")


def _pack(batches: Iterator[pa.RecordBatch], block: int = BLOCK) -> Iterator[pa.RecordBatch]:
    held, size, full = [], 0, block
    for b in batches:
        if b.num_rows:
            held.append(b)
            size += b.num_rows
        if size < full:
            continue
        whole = pa.Table.from_batches(held)
        ids = whole.column(0).to_numpy()
        end = int(np.max(np.flatnonzero(ids != ids[-1]), initial=-1)) + 1
        if end:
            yield from _records(whole.slice(0, end))
            held = whole.take(pa.array(np.arange(end, size))).to_batches()
            size, full = size - end, block
        full = max(block, 2 * size)  # a long document isn't looked through at each batch
    if held:
        yield from _records(pa.Table.from_batches(held))


def _records(block: pa.Table) -> Iterator[pa.RecordBatch]:
    words = block.column(1).dictionary_encode().combine_chunks()
    words = words.chunk(0) if isinstance(words, pa.ChunkedArray) else words
    ids = block.column(0).to_numpy()
    start = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
    rows, row = np.unique(ids[start], return_inverse=True)
    key = words.indices.to_numpy().astype(np.int64)
    key *= len(rows)
    key += np.repeat(row, np.diff(start, append=len(ids)))
    if block.num_columns > 2:
        order = np.argsort(key, kind="stable")
        key, n = key[order], block.column(2).to_numpy()[order]
    else:
        key.sort()
        first = np.flatnonzero(np.diff(key, prepend=-1))
        n, key = np.diff(first, append=len(key)), key[first]
    word, row = np.divmod(key, len(rows))
    start = np.flatnonzero(np.diff(word, prepend=-1))
    df, cf, wide = np.diff(start, append=len(word)), np.add.reduceat(n, start), np.maximum.reduceat(n, start) > 255
    away = rows.astype(np.uint64)[row] - rows[:1].astype(np.uint64)
    span = int(rows[-1]) - int(rows[0])
    for some, kind in ((~wide, 0), (wide, 1)):
        if not some.any():
            continue
        kind += 0 if span < 1 << 16 else 2 if span < 1 << 32 else 4
        own = np.repeat(some, df)
        data = np.empty(int(own.sum()), CELLS[kind])
        data["row"], data["n"] = away[own], n[own]
        for a, z in _stretches(df[some], SOME):
            count, at = df[some][a:z], int(df[some][:a].sum())
            offsets = np.concatenate([[0], np.cumsum(count)]) * data.itemsize
            part = data[at : at + int(count.sum())]
            packed = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(count), [None, pa.py_buffer(offsets), pa.py_buffer(part)]).cast(pa.binary())
            columns = [words.dictionary.take(pa.array(word[start[some][a:z]])), pa.array(count), pa.array(cf[some][a:z]), pa.array(np.full(len(count), rows[0])), pa.array(np.full(len(count), kind, np.int32)), packed]
            yield pa.RecordBatch.from_arrays(columns, names=["word", "df", "cf", "base", "kind", "cells"])


def _stretches(count: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Bounds of stretches of items with about ``most`` in all."""
    part = np.cumsum(count) // most
    start = np.flatnonzero(np.diff(part, prepend=-1))
    return list(zip(start.tolist(), [*start[1:].tolist(), len(count)], strict=True))


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        kinds = b.column(2).to_numpy()
        for kind in np.unique(kinds):
            part = b.take(pa.array(np.flatnonzero(kinds == kind)))
            col, base, packed = part.column(0).to_numpy(), part.column(1).to_numpy().astype(np.uint64), part.column(3).cast(pa.large_binary())
            offsets = np.frombuffer(packed.buffers()[1], "<i8")[packed.offset : packed.offset + len(packed) + 1]
            data = np.frombuffer(packed.buffers()[2], np.uint8)[offsets[0] : offsets[-1]].view(CELLS[kind])
            count = np.diff(offsets) // data.itemsize
            at = 0
            for a, z in _stretches(count, SOME):
                here = data[at : at + int(count[a:z].sum())]
                at += len(here)
                row = (np.repeat(base[a:z], count[a:z]) + here["row"].astype(np.uint64)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(row), pa.array(np.repeat(col[a:z], count[a:z])), pa.array(here["n"].astype(np.int64))], names=["row_id", "col_id", "n"])


def words(records: DataFrame) -> DataFrame:
    """word, df, cf of all records."""
    return records.groupBy("word").agg(F.sum("df").alias("df"), F.sum("cf").alias("cf"))
