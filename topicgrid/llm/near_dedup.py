"""MinHash near-dedup: universal hash minima, banding, signature and exact verification, connected components.

Documents with the same shingle set are one class from the start. The classes' signatures are cut into bands; a
twice-seen filter drops band keys that only one class has, so only shared ones shuffle. For documents in shared
buckets the number of shingles that any other such document may have is found; it bounds the similarity of every
pair they are in, so heavily edited copies drop out without being compared. In each bucket the document with the
smallest share of own shingles is compared with all others; what that leaves apart is compared across
components, block by block. Links are confirmed on full sets, components found by large-star and small-star.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.llm.common import Scratch, blocks, mix64, picked, release, small_enough, tidy, unplaced, utf8_view
from topicgrid.llm.components import components
from topicgrid.llm.line_dedup import filter_bits, probe, twice_seen
from topicgrid.llm.mixing import IS_WHITE

HASHES, ROWS = 128, 4  # 32 bands of 4: a pair at 0.75 shares no band in one case of 200,000
BROADCAST_IDS = 500_000
CHUNK_LEAST, CHUNK_MOST, CHUNK_SHINGLES = 64, 16_384, 2_000_000  # documents and shingles of a block's side
CARD_ROWS = 2_000  # texts that one task looks through
PART = 1 << 20  # bytes of text that are hashed at once
LEAST_AGREEMENT = 66  # of 128; at similarity 0.75 six standard deviations below what is expected

_G = np.random.default_rng(20_061)
_A = (_G.integers(0, 2**32, HASHES, dtype=np.uint64) | 1).astype(np.uint32)
_B = _G.integers(0, 2**32, HASHES, dtype=np.uint64).astype(np.uint32)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
BYTE = mix64(np.arange(1, 257, dtype=np.uint64) << np.uint64(20))
_PLACE = np.array([mix64(np.array([k + 1], np.uint64))[0] | np.uint64(1) for k in range(64)], np.uint64)


class Shingler:
    """Sorted distinct 64-bit hashes of texts' word shingles, whole blocks of texts at a time.

    A word's hash comes from prefix sums of byte values times powers of an odd number, divided by the power at the word's
    place; words over 256 bytes, where such sums are weak, are hashed on their own. Long texts are read in parts.
    """

    BASE = 0x9E3779B97F4A7C15
    powers = inverse = np.ones(1, np.uint64)

    def __init__(self, words: int = 5):
        self.words = words

    @classmethod
    def _powers(cls, n: int) -> None:
        if len(cls.powers) <= n:
            with np.errstate(over="ignore"):
                for name, base in (("powers", cls.BASE), ("inverse", pow(cls.BASE, -1, 1 << 64))):
                    x = np.full(n + 1, base, np.uint64)
                    x[0] = 1
                    setattr(cls, name, np.cumprod(x))

    def word_hashes(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hash of each word, and how many words each text has."""
        low = LOWER[data]
        black = np.concatenate([[False], ~IS_WHITE[low], [False]])
        before = black[:-2].copy()
        after = black[2:].copy()
        inner = off[1:-1]
        inner = inner[(inner > 0) & (inner < len(data))]
        before[inner] = False
        after[inner - 1] = False
        begin = np.flatnonzero(black[1:-1] & ~before)
        end = np.flatnonzero(black[1:-1] & ~after) + 1
        self._powers(max(1 << 20, len(data)))
        with np.errstate(over="ignore"):
            sums = np.concatenate([[np.uint64(0)], np.cumsum(BYTE[low] * self.powers[: len(low)], dtype=np.uint64)])
            h = (sums[end] - sums[begin]) * self.inverse[begin] + (end - begin).astype(np.uint64) * _PLACE[60]
        h = mix64(h)
        for k in np.flatnonzero(end - begin > 256):
            h[k] = xxhash.xxh3_64_intdigest(low[begin[k] : end[k]].tobytes())
        return h, np.diff(np.searchsorted(begin, off))

    def shingled(self, h: np.ndarray) -> np.ndarray:
        """A hash of each run of ``words`` words."""
        m = max(0, len(h) - self.words + 1)
        with np.errstate(over="ignore"):
            s = np.zeros(m, np.uint64)
            for k in range(self.words):
                s += h[k : k + m] * _PLACE[k]
        return mix64(s)

    def short(self, h: np.ndarray) -> np.ndarray:
        """The one hash of a text of fewer words than a shingle, or none."""
        if not len(h):
            return np.empty(0, np.uint64)
        with np.errstate(over="ignore"):
            return mix64((h * _PLACE[20 : 20 + len(h)]).sum(keepdims=True) + np.uint64(len(h)))

    def sets(self, data: np.ndarray, off: np.ndarray) -> Iterator[np.ndarray]:
        h, counts = self.word_hashes(data, off)
        s, at = self.shingled(h), 0
        for n in counts.tolist():
            yield np.unique(s[at : at + n - self.words + 1]) if n >= self.words else self.short(h[at : at + n])
            at += n

    def long_set(self, data: np.ndarray) -> np.ndarray:
        """The set of one long text, from parts that end at white space; memory is that of a part and of the set."""
        found, carry = np.empty(0, np.uint64), np.empty(0, np.uint64)
        fresh: list[np.ndarray] = []
        seen = 0
        for h in self._parts(data):
            seen += len(h)
            h = np.concatenate([carry, h])
            fresh.append(np.unique(self.shingled(h)))
            if sum(map(len, fresh)) > max(PART, len(found)):
                found, fresh = np.unique(np.concatenate([found, *fresh])), []
            carry = h[max(0, len(h) - self.words + 1) :]
        return np.unique(np.concatenate([found, *fresh])) if seen >= self.words else self.short(carry)

    def _parts(self, data: np.ndarray) -> Iterator[np.ndarray]:
        at, n = 0, len(data)
        while at < n:
            to = min(n, at + PART)
            if to < n:
                white = np.flatnonzero(IS_WHITE[data[at:to]])
                if len(white):
                    to = at + int(white[-1]) + 1
                else:  # a word that is longer than a part
                    while to < n and not len(white := np.flatnonzero(IS_WHITE[data[to : to + PART]])):
                        to = min(n, to + PART)
                    to = to + int(white[0]) if to < n else n
                    yield np.array([xxhash.xxh3_64_intdigest(LOWER[data[at:to]].tobytes())], np.uint64)
                    at = to
                    continue
            yield self.word_hashes(data[at:to], np.array([0, to - at]))[0]
            at = to

    def column(self, batch: pa.RecordBatch, name: str) -> Iterator[np.ndarray]:
        for part in blocks(iter([batch]), name, PART):
            data, off = utf8_view(part.column(name))
            if len(off) == 2 and len(data) > 2 * PART:
                yield self.long_set(data)
            else:
                yield from self.sets(data, off)

    def __call__(self, text: bytes) -> np.ndarray:
        data = np.frombuffer(text, np.uint8)
        return self.long_set(data) if len(data) > 2 * PART else next(self.sets(data, np.array([0, len(text)])))


def minima(shingles: np.ndarray) -> np.ndarray:
    """16 bits of each of the minima of the universal hashes a * x + b."""
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    low = np.full(HASHES, 0xFFFFFFFF, np.uint32)
    with np.errstate(over="ignore"):
        for at in range(0, len(x), 4096):
            part = x[at : at + 4096]
            np.minimum(low, (part[None, :] * _A[:, None] + _B[:, None]).min(axis=1), out=low)
        low = (low ^ (low >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    return (low >> np.uint32(16)).astype("<u2")


def band_keys(signatures: np.ndarray) -> np.ndarray:
    """One 64-bit key a band, of rows of signatures."""
    bands = np.ascontiguousarray(signatures).view("<u8")
    return mix64(bands ^ mix64(np.arange(1, bands.shape[1] + 1, dtype=np.uint64))[None, :])


def _slim(docs: DataFrame, text_col: str) -> DataFrame:
    return picked(docs, doc_id="doc_id", text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def signatures(docs: DataFrame, text_col: str = "text", words: int = 5) -> DataFrame:
    """doc_id, n_shingles, set_key (null for an empty set), sig."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler(words)
        for batch in batches:
            n, keys, sigs = [], [], []
            for s in shingle.column(batch, "text"):
                n.append(len(s))
                keys.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                sigs.append(minima(s).tobytes() if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(keys, pa.binary()), pa.array(sigs, pa.binary())], names=["doc_id", "n_shingles", "set_key", "sig"])

    return _slim(docs, text_col).mapInArrow(tidy(run), "doc_id bigint, n_shingles bigint, set_key binary, sig binary")


def _sig_rows(arr: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(arr.to_pylist()), "<u2").reshape(len(arr), HASHES)


def shared_bands(classes: DataFrame) -> DataFrame:
    """key, rep: bands that at least two classes seem to have."""
    spark = classes.sparkSession
    bits = filter_bits(classes.count() * (HASHES // ROWS), 1, most=29)

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for b in batches:
            if b.num_rows:
                yield band_keys(_sig_rows(b.column(0))).ravel()

    bitmap = spark.sparkContext.broadcast(twice_seen(classes.select("sig"), keys, bits))

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            k = band_keys(_sig_rows(b.column(1)))
            rep = np.repeat(b.column(0).to_numpy(), k.shape[1])
            k = k.ravel()
            hit = probe(bitmap.value, k, bits)
            yield pa.RecordBatch.from_arrays([pa.array(k[hit].view(np.int64)), pa.array(rep[hit])], names=["key", "rep"])

    return classes.select("rep", "sig").mapInArrow(tidy(emit), "key bigint, rep bigint")


def with_shared_counts(cards: DataFrame, words: int) -> tuple[DataFrame, object, int]:
    """rep, n, shared: how many of a text's shingles another text of ``cards`` has, never too few; with the filter that tells and its bits."""
    spark = cards.sparkSession
    n_bytes = cards.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = filter_bits(n_bytes, 12, most=29)

    def hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        shingle = Shingler(words)
        for b in batches:
            yield from shingle.column(b, "text")

    bitmap = spark.sparkContext.broadcast(twice_seen(cards.select("text"), hashes, bits))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler(words)
        for b in batches:
            n, shared = [], []
            for s in shingle.column(b, "text"):
                n.append(len(s))
                shared.append(int(probe(bitmap.value, s, bits).sum()) if len(s) else 0)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(shared, pa.int64())], names=["rep", "n", "shared"])

    found = cards.select("rep", "text").mapInArrow(tidy(count), "rep bigint, n bigint, shared bigint")
    # rows that repeat a doc_id with other texts: the widest bound of them
    return found.groupBy("rep").agg(F.min("n").alias("n"), F.max("shared").alias("shared")), bitmap, bits


def possible(a: str, b: str, percent: int):
    """Whether two documents may be linked, by their sizes and by how many shingles they share with anyone."""
    most = F.least(f"{a}.shared", f"{b}.shared", f"{a}.n", f"{b}.n")
    return most * 100 >= (F.col(f"{a}.n") + F.col(f"{b}.n") - most) * percent


def verified(pairs: DataFrame, cards: DataFrame, words: int, percent: int) -> DataFrame:
    """Of pairs a, b those whose signatures agree enough and whose full sets have the similarity."""
    left = cards.select(F.col("rep").alias("a"), F.col("text").alias("text_a"), F.col("sig").alias("sig_a"))
    right = cards.select(F.col("rep").alias("b"), F.col("text").alias("text_b"), F.col("sig").alias("sig_b"))
    rows = pairs.join(right.hint("merge"), "b").join(left.hint("merge"), "a").select("a", "b", "sig_a", "sig_b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle, last = Shingler(words), (None, None)
        for batch in batches:
            if not batch.num_rows:
                continue
            agree = (_sig_rows(batch.column(2)) == _sig_rows(batch.column(3))).sum(axis=1)
            out_a, out_b = [], []
            for k in np.flatnonzero(agree >= LEAST_AGREEMENT).tolist():
                own = batch.column(4)[k].as_py() or ""
                if last[0] != own:
                    last = (own, shingle(own.encode()))
                x, y = last[1], shingle((batch.column(5)[k].as_py() or "").encode())
                both = len(np.intersect1d(x, y, assume_unique=True))
                if 100 * both >= percent * (len(x) + len(y) - both):
                    out_a.append(batch.column(0)[k].as_py())
                    out_b.append(batch.column(1)[k].as_py())
            yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["a", "b"])

    return rows.mapInArrow(tidy(run), "a bigint, b bigint").distinct()


def near_dedup(docs: DataFrame, text_col: str = "text", words: int = 5, percent: int = 75) -> DataFrame:
    """doc_id, n_shingles, component_id, kept, for each row of ``docs``.

    Sets are compared case-folded for A-Z. Texts without words, and nulls, have an empty set and link with nothing;
    with fewer words than a shingle the whole sequence is one. Links need 100 * intersection >= percent * union.
    Rows that share a doc_id are one node. Rows without doc_id are judged by their exact set only: they get its
    smallest doc_id, else null, and are kept only where no other row has that set's id. Very long texts are read in parts; an empty table
    gives an empty result. Other columns aren't read and may have any names.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "near")
    sigs = scratch.table(signatures(docs, text_col, words), "sigs")
    own = F.col("doc_id").isNotNull() & F.col("set_key").isNotNull()
    classes = scratch.table(sigs.filter(own).groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.min_by("sig", "doc_id").alias("sig")), "classes")
    edges = scratch.table(_links(spark, scratch, docs, text_col, classes, words, percent), "links", few=True)
    found = components(edges, "near-components")
    # rows that repeat an id with other sets are one node, whichever class they are in
    named = classes.select("set_key", "rep").join(found.withColumnRenamed("node", "rep").hint("merge"), "rep", "left").select("set_key", F.coalesce("component", "rep").alias("component"))
    out = sigs.select("doc_id", "n_shingles", "set_key").join(named.hint("merge"), "set_key", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"), F.coalesce(F.col("doc_id") == F.coalesce("component", "doc_id"), F.col("component").isNull()).alias("kept"))


def _links(spark, scratch: Scratch, docs: DataFrame, text_col: str, classes: DataFrame, words: int, percent: int) -> DataFrame:
    bands = scratch.table(shared_bands(classes), "suspects")
    real = bands.groupBy("key").agg(F.count(F.lit(1)).alias("k")).filter("k > 1").select("key")
    bands = scratch.table(bands.join(unplaced(real, "key").hint("merge"), "key"), "bands", few=True)
    needed = scratch.table(bands.select("rep").distinct(), "needed", few=True)
    n_needed = needed.count()
    ids = F.broadcast(needed) if n_needed <= BROADCAST_IDS else needed
    # as many parts as there is work: texts are looked through several times, which takes longer than reading them
    width = max(4 * spark.sparkContext.defaultParallelism, n_needed // CARD_ROWS)
    texts = _slim(docs, text_col).withColumnRenamed("doc_id", "rep").join(ids, "rep").repartition(width, "rep")
    cards = texts.join(classes.select("rep", "sig").join(ids, "rep").repartition(width, "rep").hint("merge"), "rep")
    cards = scratch.table(cards.dropDuplicates(["rep", "text", "sig"]) if _repeats(classes) else cards, "cards")
    facts, bitmap, bits = with_shared_counts(cards, words)
    facts = scratch.table(facts, "facts", few=True)
    # a document that can't be linked with one of its own size or smaller ends here
    alone = F.col("shared") * 100 < F.col("n") * percent
    held = scratch.table(bands.join(facts.filter(~alone).hint("merge"), "rep").select("key", "rep", "n", "shared"), "held", few=True)

    head = held.groupBy("key").agg(F.max(F.struct((F.col("shared") / F.col("n")).alias("share"), (-F.col("rep")).alias("less"), "n", "shared")).alias("h"))
    head = head.select(F.col("key"), (-F.col("h.less")).alias("rep"), F.col("h.n").alias("n"), F.col("h.shared").alias("shared"))
    star = held.alias("x").join(unplaced(head, "key").alias("h").hint("merge"), (F.col("x.key") == F.col("h.key")) & (F.col("x.rep") != F.col("h.rep")) & possible("x", "h", percent))
    pairs = star.select(F.col("h.rep").alias("a"), F.col("x.rep").alias("b")).distinct()
    first = scratch.table(verified(pairs, cards, words, percent), "first", few=True)

    return first.unionByName(_apart(scratch, held, first, cards, facts, bitmap, bits, words, percent))


def _apart(scratch: Scratch, held: DataFrame, first: DataFrame, cards: DataFrame, facts: DataFrame, bitmap, bits: int, words: int, percent: int) -> DataFrame:
    """Links between documents of one bucket that the stars left in different components.

    Buckets that hold several components are gathered into clusters. Of a cluster, the documents outside its largest
    component are compared with all others, exactly and block by block: each task gets two chunks and returns links that join
    components, at most one a document, so no pair that fails is ever written. Texts move once, to be turned into sets; to the
    tasks go only those shingles of a set that another document has. A document is in 32 blocks at most, until a
    cluster has more than 32 chunks of two million shingles.
    """
    comp = components(first, "near-first").withColumnRenamed("node", "rep")
    placed = scratch.table(held.select("key", "rep").join(comp.hint("merge"), "rep", "left").withColumn("component", F.coalesce("component", "rep")), "placed", few=True)
    mixed = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.min("rep").alias("head")).filter("lo <> hi").select("key", "head")
    touching = placed.join(unplaced(mixed, "key").hint("merge"), "key").select(F.col("head").alias("a"), F.col("rep").alias("b"))
    cluster = components(touching, "near-clusters").select(F.col("node").alias("rep"), F.col("component").alias("cluster"))
    own = placed.select("rep", "component").distinct()
    members = scratch.table(cluster.join(own.hint("merge"), "rep").join(facts.select("rep", "n").hint("merge"), "rep"), "members", few=True)
    sizes = members.groupBy("cluster", "component").agg(F.count(F.lit(1)).alias("c"), F.sum("n").alias("s"))
    top = F.max(F.struct("c", (-F.col("component")).alias("less"), "s")).alias("top")
    stat = sizes.groupBy("cluster").agg(top, F.sum("c").alias("c"), F.sum("s").alias("s"))
    chunk = F.least(F.lit(CHUNK_MOST), F.greatest(F.lit(CHUNK_LEAST), F.col("c") / 32))
    chunks = lambda c, s: F.greatest(F.ceil(c / chunk), F.ceil(s / CHUNK_SHINGLES)).cast("int")
    stat = stat.select("cluster", (-F.col("top.less")).alias("main"), chunks(F.col("c") - F.col("top.c"), F.col("s") - F.col("top.s")).alias("k_out"), chunks(F.col("top.c"), F.col("top.s")).alias("k_main"))
    dealt = members.join(unplaced(stat, "cluster").hint("merge"), "cluster").withColumn("out", F.col("component") != F.col("main"))
    dealt = dealt.withColumn("own", F.pmod(F.xxhash64("rep"), F.when(F.col("out"), F.col("k_out")).otherwise(F.col("k_main"))).cast("int"))
    each = lambda k, f: F.transform(F.sequence(F.lit(0), F.col(k) - 1), f)
    task = lambda kind, i, j: F.struct(F.lit(kind).alias("kind"), i.cast("int").alias("i"), j.cast("int").alias("j"))
    inside = each("k_out", lambda j: task(0, F.least("own", j), F.greatest("own", j)))
    against = each("k_main", lambda j: task(1, F.col("own"), j))
    tasks = F.when(F.col("out"), F.concat(inside, against)).otherwise(each("k_out", lambda i: task(1, i, F.col("own"))))
    with_text = dealt.select("rep", "component", "cluster", "out", "own", tasks.alias("tasks")).join(cards.select("rep", "text").hint("merge"), "rep")

    def shared_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler(words)
        for b in batches:
            n, sets = [], []
            for s in shingle.column(b, "text"):
                n.append(len(s))
                sets.append(s[probe(bitmap.value, s, bits)].tobytes() if len(s) else b"")
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(n, pa.int64()), pa.array(sets, pa.binary())], names=[*b.schema.names[:-1], "n", "shared_set"])

    with_sets = with_text.mapInArrow(tidy(shared_sets), with_text.drop("text").schema.add("n", "long").add("shared_set", "binary"))
    rows = with_sets.withColumn("task", F.explode("tasks")).select("cluster", "task.kind", "task.i", "task.j", "rep", "component", "out", "own", "n", "shared_set")

    def compare(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        sets = [np.frombuffer(x, np.uint64) for x in table.column("shared_set").to_pylist()]
        kind, i, j = (table.column(c)[0].as_py() for c in ("kind", "i", "j"))
        rep, component, out, chunk_of, n = (table.column(c).to_numpy() for c in ("rep", "component", "out", "own", "n"))
        left, right = (out, ~out) if kind else (chunk_of == i, chunk_of == j)
        links = linked(sets, n, np.flatnonzero(left), np.flatnonzero(right), component, percent)
        release()
        return pa.table({"a": pa.array([int(rep[x]) for x, _ in links], pa.int64()), "b": pa.array([int(rep[y]) for _, y in links], pa.int64())})

    return rows.groupBy("cluster", "kind", "i", "j").applyInArrow(compare, "a bigint, b bigint").distinct()


def linked(sets: list[np.ndarray], size: np.ndarray, left: np.ndarray, right: np.ndarray, component: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Links of rows ``left`` with rows ``right`` that join components not joined before, by exact intersections.

    ``sets`` may lack shingles that no other row has; ``size`` is that of the whole sets. The right side is filed by shingle.
    """
    if not len(left) or not len(right):
        return []
    shingles = np.concatenate([sets[r] for r in right])
    owner = np.repeat(np.arange(len(right)), [len(sets[r]) for r in right])
    order = np.argsort(shingles, kind="stable")
    shingles, owner = shingles[order], owner[order]
    parent: dict[int, int] = {}

    def root(c: int) -> int:
        while (up := parent.get(c, c)) != c:
            c = up
        return c

    found = []
    for x in left.tolist():
        a, b = np.searchsorted(shingles, sets[x], side="left"), np.searchsorted(shingles, sets[x], side="right")
        n = b - a
        places = np.repeat(a - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum()) if len(n) else np.empty(0, np.int64)
        both = np.bincount(owner[places], minlength=len(right))
        for k in np.flatnonzero((both > 0) & (100 * both >= percent * (size[x] + size[right] - both)) & (component[right] != component[x])):
            y = int(right[k])
            c, d = root(int(component[x])), root(int(component[y]))
            if c != d:
                parent[max(c, d)] = min(c, d)
                found.append((x, y))
    return found


def _repeats(classes: DataFrame) -> bool:
    """Whether one doc_id stands for several sets."""
    n = classes.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("rep").alias("d")).first()
    return n.n != n.d
