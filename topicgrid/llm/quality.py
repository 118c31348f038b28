"""Quality classifier: a byte-level convolutional network in numpy.

A document's bytes are covered whole by chunks of 256 bytes that overlap by half. Learned filters of six bytes run
over each chunk and are max-pooled. A hidden layer turns each chunk's values into features, these are max-pooled over
all chunks, and an output unit combines them into one probability. Filters run over a bounded stretch of bytes at a
time, so a text of any length takes its own size and about one byte more for each of its bytes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.llm.common import Passing, blocks, held_out, picked, tidy, utf8_view

CELL = 128  # a chunk is two neighbouring cells
WIDTH = 6
STRETCH = 2048  # cells that filters run over at once
LEARNED_BYTES = 96 << 20  # of labelled text that the driver may hold
PIECES = 16  # that a long labelled text is learned from


class Laid:
    """Documents laid out in cells: zero-padded so that no filter sees two documents."""

    def __init__(self, data: np.ndarray, off: np.ndarray):
        size = np.diff(off)
        self.cells = -(-(size + WIDTH) // CELL)
        self.first = np.concatenate([[0], np.cumsum(self.cells)])
        self.bytes = np.zeros(int(self.first[-1]) * CELL + WIDTH, np.uint8)
        for k, n in enumerate(size.tolist()):
            at = int(self.first[k]) * CELL
            self.bytes[at : at + n] = data[off[k] : off[k + 1]]
        self.n = int(self.first[-1]) * CELL
        # the chunk that starts with a cell; a document's last cell stands alone if it is the only one
        self.next = np.arange(1, int(self.first[-1]) + 1)
        self.last = self.first[1:] - 1
        self.next[self.last] = self.last


class ByteConvNet:
    """Weights: tables (WIDTH, 256, filters) of one-hot byte filters; hidden (filters, units) and bias; output and bias."""

    def __init__(self, filters: int = 12, units: int = 12, seed: int = 5):
        g = np.random.default_rng(seed)
        self.tables = g.normal(0, 0.3, (WIDTH, 256, filters)).astype(np.float32)
        self.hidden = g.normal(0, 0.4, (filters, units)).astype(np.float32)
        self.bias = np.zeros(units, np.float32)
        self.out = g.normal(0, 0.4, units).astype(np.float32)
        self.base = np.zeros(1, np.float32)

    def pairs(self) -> np.ndarray:
        """Tables of byte pairs: (WIDTH / 2, filters, 65536)."""
        pair = self.tables[0::2, :, None, :] + self.tables[1::2, None, :, :]
        return np.ascontiguousarray(pair.reshape(WIDTH // 2, 65536, -1).transpose(0, 2, 1))

    def singles(self) -> np.ndarray:
        """Tables of bytes: (WIDTH, filters, 256)."""
        return np.ascontiguousarray(self.tables.transpose(0, 2, 1))

    @staticmethod
    def strongest(laid: Laid, tables: np.ndarray, places: bool = False) -> tuple[np.ndarray, np.ndarray | None]:
        """Each filter's largest response in each cell and, if asked, where in the cell it is. ``tables``: of pairs or of bytes."""
        step = WIDTH // len(tables)
        top = np.empty((laid.n // CELL, tables.shape[1]), np.float32)
        place = np.empty(top.shape, np.int64) if places else None
        for at in range(0, laid.n, STRETCH * CELL):
            to = min(laid.n, at + STRETCH * CELL)
            b = laid.bytes[at : to + WIDTH].astype(np.intp)
            seen = b if step == 1 else b[:-1] * 256 + b[1:]
            rows = slice(at // CELL, to // CELL)
            last = laid.last[(laid.last >= rows.start) & (laid.last < rows.stop)] - rows.start
            for f in range(tables.shape[1]):
                r = np.take(tables[0, f], seen[: to - at])
                for j in range(1, len(tables)):
                    r += np.take(tables[j, f], seen[step * j : step * j + to - at])
                r = r.reshape(-1, CELL)
                r[last, CELL - WIDTH + 1 :] = -np.inf  # these would look into the next document
                if place is None:
                    top[rows, f] = r.max(axis=1)
                else:
                    k = r.argmax(axis=1)
                    place[rows, f], top[rows, f] = k, np.take_along_axis(r, k[:, None], 1)[:, 0]
        return top, place

    def probabilities(self, data: np.ndarray, off: np.ndarray, pair: np.ndarray | None = None) -> np.ndarray:
        """The score of each document; an empty one has one chunk of padding. ``pair``: ``pairs()``, if made already."""
        if len(off) < 2:
            return np.zeros(0)
        laid = Laid(data, off)
        cell, _ = self.strongest(laid, self.pairs() if pair is None else pair)
        h = np.maximum(np.maximum(cell, cell[laid.next]) @ self.hidden + self.bias, 0)
        z = np.maximum.reduceat(h, laid.first[:-1], axis=0).astype(np.float64) @ self.out + self.base[0]
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))

    def fit(self, texts: list[bytes], labels: np.ndarray, epochs: int = 6, rate: float = 0.02, batch: int = 24, seed: int = 9) -> ByteConvNet:
        """Adam on the log loss; the max-pools pass gradients to the byte positions that won."""
        g = np.random.default_rng(seed)
        params = [self.tables, self.hidden, self.bias, self.out, self.base]
        m, v, step = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
        weight = np.where(labels == 1, 1.0, max(1.0, (labels == 1).sum() / max(1, (labels == 0).sum()) / 2))
        for _ in range(epochs):
            order = g.permutation(len(texts))
            for at in range(0, len(order), batch):
                pick = order[at : at + batch]
                raw = [texts[k] for k in pick]
                off = np.concatenate([[0], np.cumsum([len(t) for t in raw])])
                grads = self.gradients(Laid(np.frombuffer(b"".join(raw), np.uint8), off), labels[pick], weight[pick])
                step += 1
                for p, d, a, b in zip(params, grads, m, v, strict=True):
                    a += 0.1 * (d - a)
                    b += 0.001 * (d * d - b)
                    p -= rate * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.999**step)) + 1e-8)
        return self

    def gradients(self, laid: Laid, labels: np.ndarray, weight: np.ndarray) -> list[np.ndarray]:
        cell, best = self.strongest(laid, self.singles(), places=True)
        x = np.maximum(cell, cell[laid.next])
        h = x @ self.hidden + self.bias
        docs, units = len(labels), h.shape[1]
        won = np.stack([laid.first[k] + h[laid.first[k] : laid.first[k + 1]].argmax(axis=0) for k in range(docs)])
        pooled = np.maximum(np.take_along_axis(h, won, 0), 0)
        p = 1 / (1 + np.exp(-np.clip(pooled @ self.out + self.base[0], -40, 40)))
        dz = ((p - labels) * weight / docs).astype(np.float32)
        dh = dz[:, None] * self.out * (pooled > 0)
        d_hidden, d_tables = np.zeros_like(self.hidden), np.zeros_like(self.tables)
        for u in range(units):
            rows = won[:, u]
            d_hidden[:, u] = x[rows].T @ dh[:, u]
            dx = dh[:, u, None] * self.hidden[:, u]
            a, b = cell[rows], cell[laid.next[rows]]
            from_cell = np.where(a >= b, rows[:, None], laid.next[rows][:, None])
            place = from_cell * CELL + np.take_along_axis(best, from_cell, 0)
            f = np.broadcast_to(np.arange(place.shape[1]), place.shape)
            for k in range(WIDTH):
                np.add.at(d_tables[k], (laid.bytes[place + k], f), dx)
        return [d_tables, d_hidden, dh.sum(0), pooled.T @ dz, np.array([dz.sum()], np.float32)]


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, most: int, most_bytes: int = LEARNED_BYTES) -> tuple[list[bytes], np.ndarray]:
    """At most ``most`` labelled texts of the training folds, chosen by a hash of doc_id; null counts as empty.

    A text longer than ``most_bytes / most`` is learned from by sixteen pieces that are spread evenly from its first byte to
    its last, so the driver holds ``most_bytes`` at most. Both bounds hold for learning only; scoring has neither. Of contradicting
    labels of a doc_id the smaller counts; rows that share a doc_id are all learned from.
    """
    labels = picked(labels, doc_id="doc_id", y=label)
    given = labels.select("doc_id", F.col("y").cast("int").alias("y")).filter(F.col("y").isin(0, 1) & ~held_out())
    pick = given.orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(most).groupBy("doc_id").agg(F.min("y").alias("y"))
    raw = picked(docs, doc_id="doc_id", text="text").select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary").alias("raw"))
    each = max(1, most_bytes // most // PIECES)
    step = (F.octet_length("raw") - each).cast("double") / (PIECES - 1)
    spread = F.transform(F.sequence(F.lit(0), F.lit(PIECES - 1)), lambda k: F.substring(F.col("raw"), (F.floor(k * step) + 1).cast("int"), F.lit(each)))
    pieces = F.aggregate(spread, F.lit(b""), lambda a, x: F.concat(a, x))
    text = F.when(F.octet_length("raw") <= each * PIECES, F.col("raw")).otherwise(pieces)
    found = raw.join(F.broadcast(pick), "doc_id").select("doc_id", text.alias("text"), "y")  # pick has ``most`` rows at most
    rows = sorted(((r.doc_id, bytes(r.text), r.y) for r in found.collect()), key=lambda r: (r[0], r[1]))
    return [t for _, t, _ in rows], np.array([y for *_, y in rows], np.int64)


def train_quality(docs: DataFrame, labels: DataFrame, most: int = 3000, epochs: int = 6) -> ByteConvNet:
    """A network fitted to labels.quality. Without labelled rows it stays at its random start."""
    t, y = labelled_sample(docs, labels, "quality", most)
    net = ByteConvNet()
    return net.fit(t, y, epochs) if len(t) else net


def score_quality(docs: DataFrame, net: ByteConvNet, text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """``docs`` with score (probability of quality 1) and predicted (1 where it is at least ``threshold``).

    Whole texts are scored; null counts as empty, and both get the score of one chunk of zeros. Rows that repeat get equal
    scores, an empty table gives an empty one. Very long texts are laid out whole, but filters see a stretch at a time. Columns named
    score or predicted, in any case, are replaced, all others pass through.
    """
    own = Passing.of(docs, [text_col], ("score", "predicted"))
    at, held = own.at[text_col], docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pair = held.value.pairs()
        for batch in blocks(batches, at, 1 << 20):
            p = held.value.probabilities(*utf8_view(batch.column(at)), pair)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p), pa.array((p >= threshold).astype(np.int32))], names=[*batch.schema.names, "score", "predicted"])

    return own.returned(own.frame.mapInArrow(tidy(run), own.schema.add("score", "double").add("predicted", "integer")))
