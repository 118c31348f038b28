"""Each operator against a brute-force version, on given tables and on hand-made hard cases."""

import collections
import hashlib
import itertools
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from topicgrid.llm import mixing, near_dedup as near, packing, quality, suffix_dedup, topk, toxicity, url_filter
from topicgrid.llm.components import components
from topicgrid.llm.exact_dedup import exact_dedup, misra_gries
from topicgrid.llm.line_dedup import line_dedup
from topicgrid.llm.near_dedup import near_dedup

WS = re.compile(r"[\x20\x09-\x0D]+")
LONG = "word%d " * 1 + " ".join(f"token{i % 977}x{i}" for i in range(9000))
HARD = [
    (1, "Alpha beta\n\n gamma \nshared line here", "a"),
    (2, "alpha BETA\ngamma\nShared Line here  ", "a"),
    (2, "alpha BETA\ngamma\nShared Line here  ", "b"),
    (3, None, "b"),
    (4, "", None),
    (5, " \t\n\x0b\x0c\r ", "null"),
    (6, LONG, "é"),
    (7, LONG, "é"),
    (8, LONG + " tail of its own", None),
    (9, "ß é İ " * 40, "c"),
    (10, "ß é İ " * 40 + "x", "c"),
    (11, "one two three", "c"),
    (12, "ONE\ttwo  three", "c"),
    (13, "one two three four five six seven eight nine ten eleven twelve thirteen fourteen", "c"),
    (14, "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen", "c"),
    (None, "alpha BETA\ngamma\nShared Line here  ", "a"),
]


#: Names that operators use or add, some in another case.
CLASHING = ("score", "Predicted", "n_lines", "N_Dropped", "digest", "key", "len", "KEPT", "n", "bucket", "mark", "mark__", "key__", "second__", "copy", "first", "first__", "listed", "id", "own_mark", "MIX_shard", "mix_rank", "block", "size", "c0", "C1", "rep", "row", "at", "h", "r", "n_matches", "N_BYTES", "sha", "spans")


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame(HARD, "doc_id bigint, text string, source string").withColumns({c: F.lit("clash") for c in CLASHING})


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], "doc_id bigint, text string, source string")


@pytest.fixture(scope="module")
def given(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def rows(df):
    return df.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), *(["source"] if "source" in df.columns else [])).collect()


def lower(s):
    return s.translate({c: c + 32 for c in range(65, 91)})


@pytest.mark.parametrize("table", ["hard", "given", "empty"])
@pytest.mark.parametrize("keep", ["first", "none"])
@pytest.mark.parametrize("list_bytes", [1 << 26, -1])
def test_lines(request, table, keep, list_bytes):
    df = request.getfixturevalue(table)
    out = line_dedup(df, min_docs=2, keep=keep, list_bytes=list_bytes)
    assert out.columns == [c for c in df.columns if c.lower() not in ("n_lines", "n_dropped")] + ["n_lines", "n_dropped"]
    found = out.select("doc_id", "text", "n_lines", "n_dropped").collect()
    docs = rows(df)
    keyed = [[lower(x).strip(" \t\n\x0b\x0c\r") for x in r.text.split("\n")] for r in docs]
    n, first = collections.Counter(), {}
    for r, ks in zip(docs, keyed, strict=True):
        for k in {k for k in ks if k}:
            n[k] += 1
            if r.doc_id is not None:
                first[k] = min(first.get(k, r.doc_id), r.doc_id)
    want = []
    for r, ks in zip(docs, keyed, strict=True):
        left, mine = [], set()
        for x, k in zip(r.text.split("\n"), ks, strict=True):
            if n[k] < 2:
                left.append(x)
            elif keep == "first" and r.doc_id is not None and first[k] == r.doc_id and k not in mine:
                mine.add(k)
                left.append(x)
        want.append((r.doc_id, "\n".join(left), len(ks), len(ks) - len(left)))
    if keep == "first":  # where only rows without id have a line none keeps it
        want = [w for w in want if w[0] is not None]
        found = [f for f in found if f.doc_id is not None]
    assert collections.Counter(map(tuple, found)) == collections.Counter(want)


@pytest.mark.parametrize("table", ["hard", "given", "empty"])
@pytest.mark.parametrize("counters", [1, 256])
def test_exact(request, table, counters):
    df = request.getfixturevalue(table)
    found = exact_dedup(df, counters=counters).collect()
    groups = collections.defaultdict(list)
    for r in rows(df):
        groups[WS.sub("", r.text)].append((r.doc_id, len(r.text)))
    want = collections.Counter()
    for norm, members in groups.items():
        keep = min(members, key=lambda m: (-m[1], m[0] is None, m[0] or 0))[0]
        sha = hashlib.sha256(norm.encode()).hexdigest()
        want.update((i, keep, len(members), sha) for i, _ in members)
    assert collections.Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in found) == want
    kept = collections.Counter(r.text_sha256 for r in found if r.kept)
    assert set(kept.values()) <= {1} and len(kept) == len(groups)


def test_misra_gries_keeps_what_is_frequent():
    items = ["a"] * 40 + [str(i) for i in range(50)] + ["b"] * 30
    assert {"a", "b"} <= set(misra_gries(iter(items), 4))


def brute_near(docs, percent=75, words=5):
    sets = {}
    for r in docs:
        if r.doc_id is None:
            continue
        w = [x for x in WS.split(lower(r.text)) if x]
        s = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
        sets.setdefault(r.doc_id, []).append(s)
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        for x, y in itertools.product(sets[a], sets[b]):
            both = len(x & y)
            if x and y and 100 * both >= percent * (len(x) + len(y) - both):
                c, d = root(a), root(b)
                up[max(c, d)] = min(c, d)
    return {i: root(i) for i in sets}, sets


@pytest.mark.parametrize("table", ["hard", "given", "empty"])
def test_near(request, table):
    df = request.getfixturevalue(table)
    want, sets = brute_near(rows(df))
    for r in near_dedup(df).collect():
        if r.doc_id is not None:
            assert (r.component_id, r.kept) == (want[r.doc_id], want[r.doc_id] == r.doc_id), r
            assert r.n_shingles in {len(s) for s in sets[r.doc_id]}


def test_near_chains_and_edits(spark):
    """Chains of edits, where ends are linked only through the middle, and a group edited at random."""
    g = np.random.default_rng(2)
    base = [f"w{i}" for i in range(160)]
    docs, i = [], 0
    for step in range(30):
        docs.append((i, " ".join(base[step:] + [f"x{k}" for k in range(step)])))
        i += 1
    for _ in range(120):
        w = list(base)
        for _ in range(int(g.integers(0, 9))):
            del w[int(g.integers(0, len(w)))]
        docs.append((i, " ".join(w)))
        i += 1
    df = spark.createDataFrame(docs, "doc_id bigint, text string")
    want, _ = brute_near(df.collect())
    assert {r.doc_id: r.component_id for r in near_dedup(df).collect()} == want


def test_components(spark):
    g = np.random.default_rng(4)
    edges = [(int(a), int(b)) for a, b in g.integers(0, 300, (220, 2))] + [(k, k + 1) for k in range(1000, 1080)]
    found = {r.node: r.component for r in components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    up = {}

    def root(x):
        up.setdefault(x, x)
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        if a != b:
            c, d = root(a), root(b)
            up[max(c, d)] = min(c, d)
    assert found == {x: root(x) for x in up}


def brute_suffix(docs, n=50):
    first = {}
    for i, t in docs:
        for s in range(len(t) - n + 1):
            w = t[s : s + n]
            first[w] = min(first.get(w, i), i)
    out = []
    for i, t in docs:
        gone = bytearray(len(t))
        for s in range(len(t) - n + 1):
            if first[t[s : s + n]] < i:
                gone[s : s + n] = b"\1" * n
        spans = sum(1 for k, g in enumerate(gone) if g and (k == 0 or not gone[k - 1]))
        out.append((i, len(t), sum(gone), spans, bytes(c for c, g in zip(t, gone, strict=True) if not g)))
    return collections.Counter(out)


@pytest.mark.parametrize("table", ["hard", "given", "empty"])
@pytest.mark.parametrize(("list_bytes", "copy_rows"), [(1 << 25, 10**6), (-1, 0)])
def test_suffix(request, table, list_bytes, copy_rows):
    df = request.getfixturevalue(table)
    last = suffix_dedup.LAST
    docs = [(last if r.doc_id is None else r.doc_id, r.text.encode()) for r in rows(df)]
    out = suffix_dedup.suffix_dedup(df, list_bytes=list_bytes, copy_rows=copy_rows)
    added = ["kept", "n_bytes", "n_removed", "n_spans"]
    assert out.columns == [c for c in df.columns if c.lower() not in added] + added
    found = out.collect()
    assert collections.Counter((last if r.doc_id is None else r.doc_id, r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in found) == brute_suffix(docs)


def test_suffix_repetitive_texts(spark):
    """Texts of one letter, periods that differ by a byte, shared passages of just 49, 50 and 51 bytes, and parts longer than a block."""
    g = np.random.default_rng(8)
    letters = lambda n: bytes(g.integers(97, 123, n, dtype=np.uint8)).decode()
    p = letters(51)
    big = letters(400_000)
    docs = [(1, "a" * 300), (2, "a" * 49), (3, "b" + "a" * 60 + "b"), (4, "ab" * 90), (5, "abc" * 40 + "ab" * 40), (6, letters(30) + p[:49] + letters(9)), (7, letters(3) + p + letters(70)), (8, p[1:]), (9, letters(5) + p[:50]), (10, big), (11, letters(77) + big[100_000:300_000]), (0, "é" * 100), (12, "x" + "é" * 60)]
    df = spark.createDataFrame(docs, "doc_id bigint, text string")
    found = suffix_dedup.suffix_dedup(df).collect()
    assert collections.Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in found) == brute_suffix([(i, t.encode()) for i, t in docs])


def test_multikey_sort():
    g = np.random.default_rng(1)
    for n, high, small in ((500, 3, 1), (500, 3, 50), (2000, 40, 8), (1, 2, 1), (3000, 2**63, 100)):
        cols = [g.integers(0, high, n, dtype=np.uint64) for _ in range(4)]
        order, first = suffix_dedup.multikey_sort(cols, small)
        keys = list(zip(*(c.tolist() for c in cols), strict=True))
        assert [keys[k] for k in order] == sorted(keys) and first.sum() == len(set(keys))


def test_ranges_keep_equal_suffixes_together():
    """Nothing needs comparing across a boundary: suffixes of one anchor share a bucket, also where a token fills many ranges."""
    g = np.random.default_rng(4)
    lead = np.concatenate([g.integers(0, 50, 4000, dtype=np.uint64), np.full(3000, 7, np.uint64)])
    rest = g.integers(0, 30, len(lead), dtype=np.uint64)
    s = suffix_dedup.Splitters(lead, 40)
    where = collections.defaultdict(set)
    for a, r, b in zip(lead.tolist(), rest.tolist(), s.bucket(lead, rest).tolist(), strict=True):
        where[a, r].add(b)
    assert all(len(b) == 1 for b in where.values())
    hot = {b for (a, _), bs in where.items() if a == 7 for b in bs}
    assert len(hot) > 5 and max(max(b) for b in where.values()) < 40


def test_runs_of_one_hash_are_told_apart(monkeypatch):
    """Runs are merged by their bytes: with a hash that is the same for all, the outcome is the same."""
    g = np.random.default_rng(6)
    raw = [bytes(g.integers(97, 100, 300, dtype=np.uint8)) for _ in range(6)]
    raw += raw[:3]
    off = np.concatenate([[0], np.cumsum([len(t) for t in raw])])

    def packed():
        runs = suffix_dedup.Anchored(np.frombuffer(b"".join(raw), np.uint8), off)
        held = suffix_dedup.Held()
        held.add(runs, np.ones(len(runs.begin), bool), np.arange(9), np.zeros(9, np.int64), -off[:-1])
        out = set()
        for bucket, blob in held.packs(suffix_dedup.Splitters(np.arange(100, dtype=np.uint64), 1)):
            p = suffix_dedup.unpack(blob)
            at, occ = np.cumsum(p["size"]) - p["size"], np.cumsum(p["held"]) - p["held"]
            for k in range(len(p["size"])):
                docs = tuple(sorted(zip(p["id"][p["doc"][occ[k] : occ[k] + p["held"][k]]].tolist(), p["start"][occ[k] : occ[k] + p["held"][k]].tolist(), strict=True)))
                out.add((bucket, p["content"][at[k] : at[k] + p["size"][k]].tobytes(), int(p["anchor"][k]), docs))
        return out

    want = packed()
    monkeypatch.setattr(suffix_dedup.Anchored, "contents", lambda self: np.zeros(len(self.begin), np.uint64))
    assert packed() == want and any(len(d) > 1 for *_, d in want)


def test_mixing(spark, hard, given, empty):
    for df in (hard, given, empty):
        for shards in (None, 5):
            found = mixing.mix(df, shards=shards).collect()
            sizes = collections.Counter()
            want = collections.Counter()
            for r in rows(df):
                n = len([x for x in WS.split(r.text) if x])
                sizes[r.source] += n
                want[r.doc_id, n] += 1
            assert collections.Counter((r.doc_id, r.size) for r in found) == want
            order = sorted(s for s in sizes if s is not None) + [None] * (None in sizes)
            targets = brute_targets(sizes, order)
            taken = collections.Counter()
            for r in found:
                assert r.source_size == sizes[r.source] and r.target == pytest.approx(targets[r.source], abs=1e-6)
                assert r.taken == r.copies * r.size == len(r.shards) * r.size and r.copies <= 3
                taken[r.source] += r.taken
            largest = max((r.size for r in found), default=0)
            for s in sizes:
                assert abs(targets[s] - taken[s]) <= 2 * largest
            again = mixing.mix(df.repartition(3), shards=shards).collect()
            assert collections.Counter(map(str, again)) == collections.Counter(map(str, found))
            copies = mixing.mixed_documents(df, shards=shards)
            assert copies.columns == [c for c in df.columns if c.lower() not in ("mix_shard", "mix_rank")] + ["mix_shard", "mix_rank"]
            assert collections.Counter((r.doc_id, r.mix_shard) for r in copies.collect()) == collections.Counter((r.doc_id, s) for r in found for s in r.shards)


def brute_targets(sizes, order, weights=(5, 2, 1), cap=3):
    """Pour the total in small steps of the level, each source's share by weight until it is full."""
    total, w = sum(sizes.values()), {s: weights[k % 3] for k, s in enumerate(order)}
    lo, hi = 0.0, float(cap * total + 1)
    for _ in range(200):
        level = (lo + hi) / 2
        lo, hi = (level, hi) if sum(min(cap * sizes[s], w[s] * level) for s in order) < total else (lo, level)
    return {s: min(cap * sizes[s], w[s] * hi) for s in order}


def test_shards_draw_what_the_tree_gives():
    """Copies are the draws: each shard takes just its quota of each source's blocks, and no block twice in a pass."""
    sizes = {"a": 1000, "b": 500, None: 10}
    quota = {"a": mixing.BLOCKS // 3, "b": 2 * mixing.BLOCKS + 5, None: 3 * mixing.BLOCKS}
    plan = mixing.MixPlan(sizes, dict.fromkeys(sizes, 0), quota, 7, 3)
    assert plan.tree.sum(axis=0).tolist() == [quota[s] for s in plan.order]
    some = np.random.default_rng(1).choice(mixing.BLOCKS, 3000, replace=False).tolist()
    for s in sizes:
        n = [len(plan.shards_of(s, b)) for b in some]
        whole, rest = divmod(quota[s], mixing.BLOCKS)
        assert n == [whole + (b < rest) for b in some]
    drawn = collections.Counter(x for b in some for x in plan.shards_of("b", b))
    share = plan.tree[:, 1] / quota["b"]
    assert all(abs(drawn[k] - 6000 * share[k]) < 5 * (6000 * share[k]) ** 0.5 for k in range(7))


def test_water_fill_and_tree():
    t = mixing.water_fill({"a": 10, "b": 1000, "c": 100}, {"a": 5, "b": 2, "c": 1})
    assert t == {"a": 30, "b": 780, "c": 300} and all(t[s] <= 3 * n for s, n in {"a": 10, "b": 1000, "c": 100}.items())
    tree = mixing.split_quotas([4096, 100, 7], 13, 3)
    assert tree.sum(axis=0).tolist() == [4096, 100, 7] and tree.min() >= 0
    huge = mixing.split_quotas([3 << 30, 5, 1 << 29], 9, 3)  # beyond what one draw can handle
    assert huge.sum(axis=0).tolist() == [3 << 30, 5, 1 << 29] and huge.min() >= 0
    assert np.ptp(tree.sum(axis=1)) <= 13


def test_packing(spark, hard, given, empty):
    from tokenizers import Tokenizer
    import public_tokenizers

    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    special = spark.createDataFrame([(1, "a <|endoftext|> b"), (2, " " * 5000), (3, "a" * 3000)], "doc_id bigint, text string")
    for df in (hard, given, empty, special):
        found = packing.pack_documents(df).collect()
        want = collections.Counter()
        for i, t in df.select("doc_id", "text").collect():
            ids = [*whole.encode(t or "", add_special_tokens=False).ids, 0]
            want[i, zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
        docs = collections.defaultdict(list)
        for r in found:
            docs[r.row_no].append(r)
            assert r.ids_crc32 == zlib.crc32(bytes(r.ids)) and len(r.ids) == 4 * r.length
        got = collections.Counter()
        for parts in docs.values():
            parts.sort(key=lambda r: r.piece)
            assert [p.start for p in parts] == [sum(q.length for q in parts[:k]) for k in range(len(parts))]
            assert all(p.length == 2048 for p in parts[1:]) and 1 <= parts[0].length <= 2048
            got[parts[0].doc_id, zlib.crc32(b"".join(bytes(p.ids) for p in parts))] += 1
        assert got == want
        seqs = collections.defaultdict(list)
        for r in found:
            seqs[r.sequence_id].append((r.offset, r.length))
        for s in seqs.values():
            s.sort()
            assert [o for o, _ in s] == [sum(n for _, n in s[:k]) for k in range(len(s))] and sum(n for _, n in s) <= 2048
        total = sum(r.length for r in found)
        assert len(seqs) <= -(-total // 2048) * 11 / 9 + 1
        if found:
            made = packing.sequences(packing.pack_documents(df)).collect()
            assert sum(len(r.ids) for r in made) == 4 * total and len(made) == len(seqs)


def test_plan_is_best_fit():
    g = np.random.default_rng(3)
    hist = collections.Counter(int(x) for x in g.integers(1, 101, 700))
    plan = packing.Plan(dict(hist), 100)
    bins = []
    for n in sorted(hist.elements(), reverse=True):
        fit = [b for b in bins if b[0] >= n]
        if fit:
            min(fit)[0] -= n
        else:
            bins.append([100 - n])
    assert plan.sequences == len(bins)


def test_topk(spark, sf):
    hardv = [(i, [float(x) for x in np.random.default_rng(i).normal(0, 0.4, 8)]) for i in range(300)]
    hardv += [(300 + k, [0.5] * 8) for k in range(40)] + [(350, [0.5] * 8), (400, None), (401, [1.0, None] + [0.0] * 6), (402, [float("nan")] * 8), (403, [float("inf")] * 8), (450, [1.0, 2.0]), (None, [0.1] * 8), (500, [1e6] * 8), (550, [-1e6] * 8), (600, [])]
    made = spark.createDataFrame(hardv, "vec_id bigint, embedding array<double>")
    given = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding")
    for df in (made, given, given.limit(0), made.filter("vec_id < 3")):
        q = df.filter("vec_id % 50 = 0")
        found = collections.defaultdict(list)
        for r in topk.top_k(df.withColumns({"ID": F.lit(1), "v": F.lit(2)}), q.withColumns({"ID": F.lit(1), "v": F.lit(2)}), 5).collect():
            found[r.query_id].append((r.rank, r.id, r.score))
        rounds = topk.top_k(df, q, 5, query_rows=3)
        assert collections.Counter((r.query_id, r.rank, r.id, r.score) for r in rounds.collect()) == collections.Counter((i, *x) for i, v in found.items() for x in v)
        vs = {}
        for i, v in df.collect():
            if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v):
                vs[i] = [int(np.floor(256 * x)) for x in v]
        want = {}
        for i in (r.vec_id for r in q.collect() if r.vec_id in vs):
            s = sorted((-sum(a * b for a, b in zip(vs[i], v, strict=False)), j) for j, v in vs.items() if j != i)[:5]
            if s:
                want[i] = [(k + 1, j, -x) for k, (x, j) in enumerate(s)]
        assert {i: sorted(v) for i, v in found.items()} == want


def test_topk_prunes_and_stays_exact():
    """Clustered vectors: the proof stops the reading early. Scattered ones: all is read, and few rows are rescored."""
    g = np.random.default_rng(5)
    centres = g.normal(0, 60, (20, 32))
    clustered = np.floor(centres[g.integers(0, 20, 4000)] + g.normal(0, 8, (4000, 32)))
    for v, most_read, most_rescored in ((clustered, 0.75, 0.1), (np.floor(g.normal(0, 60, (4000, 32))), 1.0, 0.2)):
        index = topk.ImpactIndex(np.arange(4000), v)
        rescored = read = 0
        for j in range(40):
            ids, score, n, seen = index.search(v[j], j, 5, -np.inf)
            rescored, read = rescored + n, read + seen
            all_ = sorted((-int(v[j] @ v[k]), k) for k in range(4000) if k != j)[:5]
            assert list(zip((-score).tolist(), ids.tolist(), strict=True)) == all_
        assert read <= 40 * v.size * most_read and rescored < 40 * 4000 * most_rescored


def test_urls(spark, sf):
    made = [(1, "https://a.example.com/en/7x?q#f"), (2, "HTTP://WWW.EXAMPLE.COM/en/1"), (3, None), (4, "no scheme"), (5, "x://"), (6, "https://com/en/"), (7, "https://xcom/en/"), (8, "ftp://x.net/de"), (9, "ftp://x.net/de/"), (10, "https://example.net?x=/de/8"), (11, "s://example.net/de/8"), (12, "s://cheap-pills.io/"), (12, "s://cheap-pills.io/"), (13, "a://b://c.com/en/"), (14, "s://x.org:80/es/"), (15, "s://É.org/es/#")]
    df = spark.createDataFrame(made, "page_id bigint, url string").withColumn("host", F.lit("clash"))
    rules = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("block", "net", "/de/"), ("allow", "example.net", "/de/8"), ("block", "org", "/es/")]
    for t in (df, spark.read.parquet(f"{sf}/pages.parquet"), df.limit(0)):
        found = url_filter.filter_urls(t).collect()
        want = collections.Counter()
        for i, u in t.select("page_id", "url").collect():
            rest = u.split("://", 1)[1] if u and "://" in u else ""
            host = re.split("[/?#]", rest)[0]
            path = re.split("[?#]", rest[len(host) :])[0]
            host = lower(host)
            fit = [(len(h + p), h + p, v) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
            bad = any(x in host.split(".") for x in ("cheap-pills", "spam-farm", "casino", "free-money", "adult", "xxx", "porn", "viagra"))
            rule, verdict = max(fit)[1:] if fit else (None, "block" if bad else "allow")
            want[i, host, path, rule, verdict] += 1
        assert collections.Counter((r.page_id, r.host, r.path, r.rule, r.verdict) for r in found) == want
        assert all(r.n_run <= 4 for r in found)


def test_listed_rules_are_those_of_the_contract(spark):
    urls = ["http://a.com/en/1", "http://example.com/en/7x", "http://a.net/de/8", "http://w.example.net/de/81", "http://example.net/de/9", "http://b.org/es/", "http://b.org/en/"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    got = [(r.rule, r.verdict) for r in url_filter.filter_urls(df).orderBy("page_id").collect()]
    assert got == [("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("net/de/", "allow"), ("org/es/", "block"), (None, "allow")]


def test_rarest_token_decides():
    r = url_filter.RuleIndex([url_filter.Rule("x", "block", r".*rare.*common", ("common", "rare")), url_filter.Rule("y", "block", ".*", ())], {"common": 10, "rare": 1})
    assert r.candidates("a.common.b", "/") == [1] and r.candidates("rare", "/") == [0, 1]


def auc(score, y):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(score))
    values = np.asarray(score)[order]
    for v in np.unique(values):
        at = np.flatnonzero(values == v)
        rank[order[at]] = at.mean() + 1
    n1 = (y == 1).sum()
    return (rank[y == 1].sum() - n1 * (n1 + 1) / 2) / (n1 * (len(y) - n1))


@pytest.mark.parametrize(("label", "least"), [("quality", 0.95), ("toxic", 0.8)])
def test_classifiers_on_held_out_rows(spark, label, least):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    if label == "quality":
        scored = quality.score_quality(docs, quality.train_quality(docs, labels))
    else:
        scored = toxicity.score_toxicity(docs, toxicity.train_toxicity(docs, labels))
    held = scored.join(labels.select("doc_id", F.col(label).alias("y")), "doc_id").filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0).select("score", "y").toPandas()
    assert auc(held.score.to_numpy(), held.y.to_numpy()) > least


def test_classifiers_on_hard_rows(spark, hard, empty):
    labels = spark.createDataFrame([(1, 1, 0), (6, 0, 1), (None, 1, 1), (99, 0, 0)], "doc_id bigint, quality int, toxic int").withColumns({c: F.lit(1) for c in ("y", "text", "raw")})
    for df in (hard, empty):
        for lab in (labels, labels.limit(0)):
            a = quality.score_quality(df, quality.train_quality(df, lab, epochs=1)).collect()
            b = toxicity.score_toxicity(df, toxicity.train_toxicity(df, lab)).collect()
            for out in (a, b):
                assert len(out) == df.count() and all(0 <= r.score <= 1 and r.predicted in (0, 1) for r in out)
            assert all(r.source in {x[2] for x in HARD} for r in a)


def test_grammar_reads_clauses():
    g = toxicity.ToxicityGrammar()
    m = g.lexicon.matcher()
    score = lambda t: g.score(g.lexicon.features(t, m))
    assert score("you are an idiot.") > score("an idiot.") > score("said an idiot.") > score("hello there.")
    assert score("you are not an idiot.") < score("you are an idiot.")
    assert score("no. you idiot") == score("you idiot")
    assert g.lexicon.features("idiotic and Scummy words", m) is None
    assert score("idiot.") == score("hello.") and score("kill time") == score("hello.")  # a lone word; a threat to nobody
    assert score("kill you") == score("you kill") > 0.5 and score("idiot, that is what you are") == score("you are an idiot")
    assert score("“hello”, you idiot") == score("hello, you idiot") > score("“hello, you idiot”")
    assert score('she wrote "go. you idiot! go" today') < score('she wrote. "go" you idiot')


def brute_clauses(kinds):
    """What each clause is, by looking at the whole sequence instead of running machines: (target, insult, threat) or nothing."""
    T = toxicity
    out, begin = [], 0
    for end in [k for k, c in enumerate(kinds) if c in (T.END, T.BREAK)]:
        line = max((k + 1 for k in range(begin) if kinds[k] == T.BREAK), default=0)
        found = {T.INSULT: [], T.THREAT: []}
        for k in range(begin, end):
            if kinds[k] not in found:
                continue
            quoted = False
            for c in kinds[line:k]:
                quoted = not quoted if c == T.QUOTE else quoted and c != T.CLOSE
            before = [c for c in kinds[begin:k] if c not in (T.QUOTE, T.CLOSE)]
            found[kinds[k]].append((T.NEG in before[-3:]) * T.NEGATED | (quoted or T.REPORT in before) * T.REPORTED)
        words = [c for c in kinds[begin:end] if c not in (T.QUOTE, T.CLOSE)]
        insult, threat = (min(f) + 1 if f else 0 for f in (found[T.INSULT], found[T.THREAT]))
        out.append((int(T.TARGET in words), insult, threat) if len(words) > 1 and (insult or threat) else None)
        begin = end + 1
    return out


def test_machine_against_brute_force():
    g = np.random.default_rng(11)
    for _ in range(3000):
        kinds = [*g.choice(10, int(g.integers(1, 25)), p=[0.2, 0.14, 0.14, 0.08, 0.1, 0.08, 0.08, 0.04, 0.1, 0.04]).tolist(), toxicity.BREAK]
        state, got = 0, []
        for c in kinds:
            state, match = toxicity.ROWS[state][(c, 0)]
            if c in (toxicity.END, toxicity.BREAK):
                got.append(None if match is None else toxicity.parts_of(match))
            else:
                assert match is None
        assert got == brute_clauses(kinds), kinds


def test_network_against_brute_force():
    """Filters byte by byte, pools and layers as loops."""
    g = np.random.default_rng(3)
    net = quality.ByteConvNet(filters=3, units=4, seed=2)
    net.out[:] = g.normal(0, 1, 4)
    texts = [b"", b"a", bytes(g.integers(0, 256, 121, dtype=np.uint8)), bytes(g.integers(0, 256, 122, dtype=np.uint8)), bytes(g.integers(32, 126, 700, dtype=np.uint8))]
    off = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    found = net.probabilities(np.frombuffer(b"".join(texts), np.uint8), off)
    for t, p in zip(texts, found, strict=True):
        cells = -(-(len(t) + quality.WIDTH) // quality.CELL)
        padded = t + bytes(cells * quality.CELL + quality.WIDTH - len(t))
        top = np.full((cells, 3), -np.inf)
        for at in range(cells * quality.CELL - quality.WIDTH + 1):
            r = sum(net.tables[j, padded[at + j]] for j in range(quality.WIDTH))
            top[at // quality.CELL] = np.maximum(top[at // quality.CELL], r)
        pooled = np.full(4, -np.inf)
        for c in range(cells):
            x = np.maximum(top[c], top[min(c + 1, cells - 1)])
            pooled = np.maximum(pooled, np.maximum(x @ net.hidden + net.bias, 0))
        assert p == pytest.approx(1 / (1 + np.exp(-(pooled @ net.out + net.base[0]))), rel=1e-4)


def test_very_long_texts(monkeypatch):
    """64 MB in one text: scored and shingled in bounded stretches; parts change nothing."""
    g = np.random.default_rng(7)
    words = np.array([b"%x" % x for x in range(4096)])
    text = b" ".join(words[g.integers(0, 4096, 15_000_000)].tolist())
    data = np.frombuffer(text, np.uint8)
    assert len(data) > 50 << 20
    net = quality.ByteConvNet()
    p = net.probabilities(data, np.array([0, len(data)]))
    assert 0 <= p[0] <= 1
    shingle = near.Shingler()
    s = shingle.long_set(data)
    assert len(s) > 14_000_000 and len(near.Shingler.powers) <= (1 << 20) + 1
    some = text[:300_000] + b"\t" + b"Q" * 90_000 + b" " + text[300_000:400_000] + b"\n"
    whole = next(shingle.sets(np.frombuffer(some, np.uint8), np.array([0, len(some)])))
    for part in (5_000, 1 << 16):
        monkeypatch.setattr(near, "PART", part)
        assert np.array_equal(shingle.long_set(np.frombuffer(some, np.uint8)), whole)
        assert np.array_equal(shingle.long_set(np.frombuffer(b" one  two\n", np.uint8)), shingle(b"ONE two"))


def test_long_labelled_texts_are_learned_from_in_pieces(spark):
    rows = [(k, "x" * 100_000 + f"<{k}>" if k % 2 else None) for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(40)], "doc_id bigint, quality int")
    texts, y = quality.labelled_sample(docs, labels, "quality", 50, 50 * 1600)
    assert len(texts) == len(y) > 20 and {len(t) for t in texts} == {0, 1600}
    assert all(t.endswith(b">") for t, k in zip(texts, y, strict=True) if k) and all(t == b"" for t, k in zip(texts, y, strict=True) if not k)


def test_columns_that_differ_in_case(spark):
    """A second doc_id or text in another case is a column like any other."""
    df = spark.createDataFrame([(1, "a b c d e f", "x"), (2, "A b c d e f", "y")], "doc_id bigint, text string, source string")
    df = df.select("*", F.lit(9).alias("DOC_ID"), F.lit("other").alias("Text"), F.lit("z").alias("SOURCE"))
    assert [r.component_id for r in near_dedup(df).orderBy("doc_id").collect()] == [1, 1]
    assert {r.keep_id for r in exact_dedup(df).collect()} == {1, 2}
    assert mixing.mix(df).count() == 2 and packing.pack_documents(df).count() == 2
    assert suffix_dedup.suffix_dedup(df).count() == 2 and line_dedup(df).count() == 2
    assert mixing.mixed_documents(df).count() > 0


def test_network_covers_the_whole_text():
    net = quality.ByteConvNet()
    a, b = b"x" * 5000, b"x" * 5000 + b" %%% $$$ !!!"
    p = net.probabilities(np.frombuffer(a + b + b"", np.uint8), np.array([0, len(a), len(a) + len(b), len(a) + len(b)]))
    one = net.probabilities(np.frombuffer(b, np.uint8), np.array([0, len(b)]))
    assert len(p) == 3 and p[0] != p[1] and np.isclose(p[1], one[0])
