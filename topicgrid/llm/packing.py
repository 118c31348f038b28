"""Best-fit packing planned on a histogram of lengths.

Texts are tokenised and only pieces longer than a sequence are cut. The plan works on counts: for each length, from
the longest, best-fit puts that many equal pieces into the open sequences with least room, whole groups of equal
sequences at a time, so planning takes a few thousand steps for any number of documents. Pieces are then ranked
within their length and take the slot of their rank.
"""

from __future__ import annotations

import base64
import bisect
import functools
import json
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from topicgrid.llm.common import Scratch, blocks, picked, tidy

SEQUENCE = 2048


class Encoder:
    """ids of a public byte-level tokenizer, by name or by the path of its json file.

    The ids are those of ``tokenizers``; where the same vocabulary lies beside it as ranks, ``tiktoken`` makes
    them, several times faster, save for texts that hold a special token's string.
    """

    def __init__(self, tokenizer: str = "byte_bpe_50k.json"):
        import public_tokenizers
        import tiktoken

        self.path = tokenizer if "/" in tokenizer else public_tokenizers.path(tokenizer)
        text = open(self.path, encoding="utf-8").read()
        added = text.find('"added_tokens"')
        self.special = [t["content"] for t in json.JSONDecoder().raw_decode(text, text.index("[", added))[0]] if added >= 0 else []
        try:
            lines = open(self.path.removesuffix(".json") + ".tiktoken").read().splitlines()
        except OSError:
            self.fast = None
        else:
            ranks = {base64.b64decode(a): int(b) for a, b in map(str.split, lines)}
            self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    @functools.cached_property
    def whole(self):
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def ids(self, text: str) -> np.ndarray:
        if self.fast is None or any(s in text for s in self.special):
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, np.uint32)
        return np.array(self.fast.encode_ordinary(text), np.uint32)


@functools.lru_cache(maxsize=1)
def encoder(tokenizer: str) -> Encoder:
    """One for all tasks of a worker."""
    return Encoder(tokenizer)


def token_pieces(docs: DataFrame, text_col: str = "text", tokenizer: str = "byte_bpe_50k.json", most: int = SEQUENCE, end: int = 0) -> DataFrame:
    """doc_id, row_no, piece, start, length, ids (little-endian 32-bit words).

    A document is its ids and ``end``; null counts as empty. Only what is longer than ``most`` is cut, so that all pieces but the first have
    ``most`` ids. Rows that repeat are packed each on its own.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        row = TaskContext.get().partitionId() << 33
        for batch in blocks(batches, "text", 1 << 20):
            out: list[list] = [[], [], [], [], [], []]
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.append(enc.ids(t or ""), np.uint32(end)).astype("<u4")
                cuts = [0, *range(len(ids) % most or most, len(ids) + 1, most)] if len(ids) > most else [0, len(ids)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                    for col, v in zip(out, (i, row, k, a, b - a, ids[a:b].tobytes()), strict=True):
                        col.append(v)
                row += 1
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, kinds, strict=True)], names=["doc_id", "row_no", "piece", "start", "length", "ids"])

    slim = picked(docs, doc_id="doc_id", text=text_col)
    return slim.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), "doc_id bigint, row_no bigint, piece int, start bigint, length bigint, ids binary")


class Plan:
    """Slots by (length, rank): runs of equal pieces laid over runs of equal sequences."""

    def __init__(self, histogram: dict[int, int], most: int = SEQUENCE):
        self.most, self.sequences = most, 0
        rows: list[tuple[int, int, int, int, int]] = []  # length, first rank, first sequence, pieces in each, offset
        open_: dict[int, list[tuple[int, int]]] = defaultdict(list)  # by room: first sequence, how many
        rooms: list[int] = []

        def keep(room: int, first: int, n: int) -> None:
            if n and room:
                if not open_[room]:
                    bisect.insort(rooms, room)
                open_[room].append((first, n))

        for length in sorted(histogram, reverse=True):
            left, rank = histogram[length], 0
            while left:
                at = bisect.bisect_left(rooms, length)
                if at < len(rooms):
                    room = rooms[at]
                    first, n = open_[room].pop()
                    if not open_[room]:
                        del rooms[at]
                else:
                    room, first, n = most, self.sequences, -(-left // (most // length))
                    self.sequences += n
                each = room // length
                full = min(n, left // each)
                if full:
                    rows.append((length, rank, first, each, most - room))
                    keep(room - each * length, first, full)
                    rank += full * each
                    left -= full * each
                if full < n and left:  # fewer are left than fit into one more
                    rows.append((length, rank, first + full, left, most - room))
                    keep(room - left * length, first + full, 1)
                    rank += left
                    left = 0
                    full += 1
                keep(room, first + full, n - full)
        rows.sort()
        self.table = np.array(rows, np.int64).reshape(-1, 5)
        self.key = (self.table[:, 0] << 44) + self.table[:, 1]

    def slots(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        row = self.table[np.searchsorted(self.key, (length << 44) + rank, side="right") - 1]
        within, each = rank - row[:, 1], row[:, 3]
        return row[:, 2] + within // each, row[:, 4] + within % each * length


def ranked_within_length(pieces: DataFrame, bucket_rows: int = 500_000) -> DataFrame:
    """``pieces`` with rank (from 0) within their length: a count by hash bucket, its running sum, and a rank inside each bucket."""
    n = pieces.count()
    dealt = pieces.withColumn("bucket", F.pmod(F.xxhash64("row_no", "piece"), F.lit(max(64, n // bucket_rows))).cast("int"))
    counts = dealt.groupBy("length", "bucket").count()
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("length", "bucket", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("length", "bucket").orderBy("row_no", "piece")
    return dealt.withColumn("inside", F.row_number().over(inside)).join(base, ["length", "bucket"]).withColumn("rank", F.col("base") + F.col("inside") - 1).drop("bucket", "base", "inside")


def pack(pieces: DataFrame, most: int = SEQUENCE) -> DataFrame:
    """``pieces`` (row_no, piece, length, written already) with sequence_id and offset.

    Lengths lie between 1 and ``most``; the histogram on the driver has at most that many rows.
    """
    plan = Plan({r.length: r["count"] for r in pieces.groupBy("length").count().collect()}, most)
    held = pieces.sparkSession.sparkContext.broadcast(plan)
    ranked = ranked_within_length(pieces)
    names = [c for c in ranked.columns if c != "rank"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seq, off = held.value.slots(batch.column("length").to_numpy(), batch.column("rank").to_numpy())
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(seq), pa.array(off)], names=[*names, "sequence_id", "offset"])

    return ranked.mapInArrow(tidy(run), StructType([ranked.schema[c] for c in names]).add("sequence_id", "long").add("offset", "long"))


def pack_documents(docs: DataFrame, text_col: str = "text", tokenizer: str = "byte_bpe_50k.json", most: int = SEQUENCE, with_ids: bool = True) -> DataFrame:
    """doc_id, row_no, piece, start, length, ids (unless left out), ids_crc32, sequence_id, offset. An empty table packs to nothing."""
    pieces = token_pieces(docs, text_col, tokenizer, most).withColumn("ids_crc32", F.crc32("ids"))
    held = Scratch(docs.sparkSession, "pack").table(pieces if with_ids else pieces.drop("ids"), "pieces")
    if not with_ids:
        return pack(held, most)
    return pack(held.drop("ids"), most).join(held.select("row_no", "piece", "ids"), ["row_no", "piece"])


def sequences(packed: DataFrame) -> DataFrame:
    """sequence_id, ids: the sequences themselves, from packed pieces with ids; none is longer than planned."""
    inner = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(inner.alias("parts")).select("sequence_id", F.expr("aggregate(parts, cast('' as binary), (a, x) -> concat(a, x.ids))").alias("ids"))
