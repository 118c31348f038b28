"""Worked examples, list machines, brute force, invariants and edge cases of partitioning."""

import hashlib
import itertools
import math

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from topicgrid.functions import positions
from topicgrid.functions.digests import Keys
from topicgrid.functions.sql import register
from topicgrid.functions.stem import stem
from topicgrid.operators import choices, cost, cut, lengths, permute, postings, tokens, trials, workload
from topicgrid.operators.choices import Axis, Choice
from topicgrid.plans import corpora
from topicgrid.plans.corpora import basket
from topicgrid.plans.queries import QUERIES
from topicgrid.schema import WorkloadError, check_workload, whole_numbers
from topicgrid.sources.tables import read_coordinates, read_workload, write_coordinates


def matrix(spark, cells):
    return spark.createDataFrame([tuple(map(int, c)) for c in cells], "row_id bigint, col_id bigint, n bigint")


def ranks(spark, d):
    return spark.range(1, d + 1).select(F.col("id"), F.col("id").alias("k"), F.lit(d).cast("bigint").alias("d"))


def order_of(spark, d, form):
    rows = ranks(spark, d).select("k", form(F.col("k"), F.col("d")).alias("p")).collect()
    return [r.k for r in sorted(rows, key=lambda r: r.p)]


@pytest.mark.parametrize(
    ("form", "d", "want"),
    [
        (positions.interleave, 7, [1, 7, 2, 6, 3, 5, 4]),
        (positions.interleave, 8, [1, 8, 2, 7, 3, 6, 4, 5]),
        (positions.mirror_swap, 8, [1, 7, 3, 4, 5, 6, 2, 8]),
        (positions.mirror_swap, 9, [1, 8, 3, 6, 5, 4, 7, 2, 9]),
        (positions.mirror_swap, 10, [1, 9, 3, 7, 5, 6, 4, 8, 2, 10]),
        (positions.mirror_alternate, 8, [1, 8, 3, 6, 5, 4, 7, 2]),
    ],
)
def test_worked_orders(spark, form, d, want):
    assert order_of(spark, d, form) == want


def test_closed_forms_equal_list_machines(spark):
    """Moves on lists, as described, for all sizes up to 60 in one query."""
    sizes = spark.range(1, 61).select(F.col("id").alias("d"), F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("id"))).alias("k"))
    k, d = F.col("k"), F.col("d")
    rows = sizes.select("d", "k", positions.interleave(k, d).alias("i"), positions.mirror_swap(k, d).alias("s"), positions.mirror_alternate(k, d).alias("a")).collect()
    by = {}
    for r in rows:
        by.setdefault(r.d, []).append(r)
    for size, rs in by.items():
        get = lambda name: [r.k for r in sorted(rs, key=lambda r: r[name])]  # noqa: E731, B023
        left = list(range(1, size + 1))
        woven = []
        while left:
            woven.append(left.pop(0))
            if left:
                woven.append(left.pop())
        assert get("i") == woven
        swapped = list(range(1, size + 1))
        for at in range(2, size + 1, 2):
            if 2 * at < size:
                swapped[at - 1], swapped[size - at] = swapped[size - at], swapped[at - 1]
        assert get("s") == swapped
        left, front, back = list(range(1, size + 1)), [], []
        while left:
            for side, flip in ((front, False), (back, True)):
                pair = [left.pop(0)] if left else []
                pair += [left.pop()] if left else []
                side.extend(pair) if not flip else back.__setitem__(slice(0, 0), pair[::-1])
        assert get("a") == front + back


def grid_frame(spark, g):
    return spark.createDataFrame([(m, n, (n - m) % len(g), g[m][n]) for m in range(len(g)) for n in range(len(g))], "m int, n int, diag int, cost bigint")


@pytest.mark.parametrize(("g", "epochs", "eta"), [([[5, 3], [2, 6]], [6, 3], 8 / 9), ([[4, 1, 2], [3, 5, 1], [2, 2, 4]], [5, 2, 3], 0.8)])
def test_worked_grids(spark, g, epochs, eta):
    b = grid_frame(spark, g)
    assert [r.cost for r in cost.epoch_costs(b).orderBy("diag").collect()] == epochs
    r = cost.eta(b, len(g)).first()
    assert r.total_cost == sum(epochs) and math.isclose(r.eta, eta) and math.isclose(r.speedup, eta * len(g))
    idle = cost.idle(b).agg(F.sum("idle")).first()[0]
    assert idle == len(g) * r.total_cost - r.tokens


@pytest.fixture(scope="module")
def small(spark):
    g = np.random.default_rng(3)
    cells = {(int(a), int(b)): int(n) for a, b, n in zip(g.integers(0, 40, 400), g.zipf(1.6, 400) % 50, g.integers(1, 30, 400), strict=True)}
    return matrix(spark, [(a, b, n) for (a, b), n in cells.items()]).cache()


@pytest.mark.parametrize("method", permute.METHODS)
@pytest.mark.parametrize("groups", [1, 3, 7])
def test_invariants(spark, small, method, groups):
    p = trials.partition(small, method, groups)
    for axis, part in (("row", p.rows), ("col", p.cols)):
        ids = small.select(f"{axis}_id").distinct().count()
        assert part.count() == part.select("id").distinct().count() == part.select("pos").distinct().count() == ids
        assert part.agg(F.min("pos"), F.max("pos")).first() == (1, ids)
        assert part.filter((F.col("grp") < 0) | (F.col("grp") >= groups)).isEmpty()
        firsts = [r.first_pos for r in cut.group_bounds(part).orderBy("grp").collect()]
        assert firsts == sorted(firsts)
    b = cost.block_costs(small, p.rows, p.cols, groups)
    r = cost.eta(b, groups).first()
    total = small.agg(F.sum("n")).first()[0]
    assert b.count() == groups * groups and r.tokens == total and 1 / groups - 1e-12 <= r.eta <= 1 + 1e-12
    assert r.eta <= cost.group_ceiling(p.rows, p.cols, groups).first().ceiling + 1e-12
    assert r.eta <= cost.eta_ceiling(lengths.lengths(small, "row"), lengths.lengths(small, "col"), groups).first().ceiling + 1e-12
    if groups == 1:
        assert r.eta == 1


def test_flat_matrix_is_always_balanced(spark):
    flat = matrix(spark, itertools.product(range(12), range(12), [1]))
    for p in (1, 2, 3, 4, 6, 12):
        for method in ("interleave", "mirror", "mirror_alternate", "stratified"):
            assert trials.eta_of(flat, method, p).first().eta == 1


def test_edge_cases(spark):
    one = matrix(spark, [(1, 1, 5)])
    assert trials.eta_of(one, "interleave", 1).first().eta == 1
    r = trials.eta_of(one, "interleave", 2).first()
    assert (r.total_cost, r.eta) == (5, 0.5)
    assert cost.group_skew(trials.partition(one, "mirror", 2).rows, 2).first().empty == 1
    wide = matrix(spark, itertools.product(range(3), range(3), [2]))
    assert 1 / 5 <= trials.eta_of(wide, "interleave", 5).first().eta <= 1
    giant = matrix(spark, [(0, c, 90) for c in range(10)] + [(r, r % 10, 10) for r in range(1, 11)])
    assert trials.eta_of(giant, "mirror", 4).first().eta <= cost.eta_ceiling(lengths.lengths(giant, "row"), lengths.lengths(giant, "col"), 4).first().ceiling


@pytest.mark.parametrize("bad", [[], [(1, 1, 0)], [(1, 1, -2)], [(1, 1, 2), (1, 1, 3)]])
def test_bad_workloads(spark, bad):
    with pytest.raises(WorkloadError):
        check_workload(matrix(spark, bad))


def test_null_ids_and_fractions(spark):
    with pytest.raises(WorkloadError):
        check_workload(spark.createDataFrame([(None, 1, 2)], "row_id bigint, col_id bigint, n bigint"))
    with pytest.raises(Exception, match="whole number"):
        spark.createDataFrame([(1.5,)], "x double").select(whole_numbers("x")).collect()


@pytest.mark.parametrize("tie", ["id", "hash"])
@pytest.mark.parametrize("axis", ["row", "col"])
def test_ranks_agree(spark, small, axis, tie):
    lens = lengths.lengths(small, axis)
    a, b = (lengths.rank_desc(lens, tie, mode=m, axis=axis).orderBy("id").collect() for m in ("window", "two_level"))
    assert a == b
    wide = lens.withColumn("id", F.col("id") * 1000)
    assert lengths.rank_desc(wide, tie, mode="two_level").select("rank").distinct().count() == wide.count()


@pytest.mark.parametrize("held", [3, 1 << 18])
def test_written_ranks_agree(spark, small, monkeypatch, held):
    """The ranks of ``rank_desc`` with size and total, in one range or in many, with ties, wide ids, nulls and nothing at all."""
    monkeypatch.setattr(lengths, "RANGE", held)
    odd = spark.createDataFrame([(2**62, 5), (-(2**62), 5), (None, 5), (7, None), (3, 9), (4, 1), (None, None)], "id bigint, len bigint")
    for lens in (lengths.lengths(small, "row"), lengths.lengths(small, "col"), odd, odd.filter("id IS NULL"), odd.limit(0)):
        want, got = lengths.rank_desc(lens), lengths.rank_stored(lens)
        assert got.columns == want.columns and got.dtypes == want.dtypes
        assert got.orderBy("rank").collect() == want.orderBy("rank").collect()


def test_comparison_reads_the_matrix_once_an_axis_and_once_for_costs(spark, small, tmp_path):
    """What the driver plans and keeps account of grows with every further pass; ranking used to make six an axis here."""

    def seen(batches):
        for b in batches:
            with open(tmp_path / "seen", "a") as f:
                f.write(f"{b.num_rows}\n")
            yield b

    told = small.mapInArrow(seen, small.schema)
    want = {tuple(r) for r in trials.compare(small, ("mirror", "stratified"), (1, 3), 2).collect()}
    assert {tuple(r) for r in trials.compare(told, ("mirror", "stratified"), (1, 3), 2).collect()} == want
    assert sum(map(int, (tmp_path / "seen").read_text().split())) == 3 * small.count()


def test_hashed_ids_fall_into_even_buckets(spark):
    """However ids are spread, buckets follow their order and are few; ranks agree with a sort."""
    for ids in (F.xxhash64("id"), F.col("id") + (1 << 40), F.col("id") * 1_000_003 - (1 << 50)):
        lens = spark.range(20_000).select(ids.alias("id"), F.lit(1).cast("bigint").alias("len"))
        sizes = lengths.with_bucket(lens, "id").groupBy("bucket").count().agg(F.max("count"), F.count(F.lit(1))).first()
        assert sizes[1] <= 4097 and sizes[0] <= 40
        a, b = (lengths.rank_desc(lens, mode=m).orderBy("id").collect() for m in ("window", "two_level"))
        assert a == b
        order = [r.id for r in permute.identity(lengths.rank_desc(lens)).orderBy("pos").collect()]
        assert order == sorted(order)


def test_vocabulary_ids_follow_the_words(spark):
    words = ["a", "ab", "abc", "abcd", "abcdefg", "abcdefgh", "abcdefghi", "abcdeg", "b", "é", "éa", "z", "aé", "ab c"] + [f"prefix{k}" for k in range(300)]
    counts = spark.createDataFrame([(1, w, 2) for w in words] + [(2, "a", 1)], "row_id bigint, word string, n bigint")
    found = {r.word: (r.word_id, r.df, r.cf) for r in tokens.vocabulary(counts).collect()}
    assert {w: found[w][0] for w in words} == {w: k + 1 for k, w in enumerate(sorted(words, key=lambda w: w.encode()))}
    assert found["a"][1:] == (2, 3) and tokens.hash_collisions(tokens.vocabulary(counts, ids="hash")).isEmpty()


def test_moving_means_meet_at_slabs(spark, small):
    placed = permute.interleave(lengths.rank_desc(lengths.lengths(small, "row")))
    whole, parts = (permute.moving(placed, 3, slab=s).orderBy("pos").collect() for s in (10**6, 4))
    assert whole == parts


def test_cuts_agree(spark, small):
    ranked = lengths.rank_desc(lengths.lengths(small, "row"))
    placed = permute.interleave(ranked)
    for p in (1, 2, 5, 9, 60):
        plain = cut.cut(placed, p, mode="window").select("id", "pos", "grp").orderBy("id").collect()
        assert plain == cut.cut(placed, p).select("id", "pos", "grp").orderBy("id").collect()
        assert plain == cut.cut_by_histogram(ranked, p).select("id", "pos", "grp").orderBy("id").collect()
    small_slabs = cut.prefix_tokens(placed, slab=3).orderBy("pos").collect()
    assert [r.before for r in small_slabs] == list(itertools.accumulate([0] + [r.len for r in small_slabs]))[:-1]


def test_bottleneck_is_optimal(spark):
    g = np.random.default_rng(9)
    for _ in range(4):
        lens = g.integers(1, 30, 9)
        placed = spark.createDataFrame([(i, int(x), i + 1) for i, x in enumerate(lens)], "id bigint, len bigint, pos bigint")
        got = max(r.tokens for r in cut.group_bounds(cut.cut_bottleneck(placed, 3)).collect())
        best = min(max(lens[:a].sum(), lens[a:b].sum(), lens[b:].sum()) for a in range(1, 9) for b in range(a, 9))
        assert got == best


@pytest.mark.parametrize("held", [3, 5, 16])
def test_bottleneck_is_optimal_beyond_what_the_driver_holds(spark, held):
    g = np.random.default_rng(held)
    lens = g.integers(1, 30, 60)
    lens[g.integers(0, 60, 3)] = 400  # giants among small neighbours
    placed = spark.createDataFrame([(i, int(x), i + 1) for i, x in enumerate(lens)], "id bigint, len bigint, pos bigint")
    ends = [0, *np.cumsum(lens).tolist()]
    best = [e for e in ends]  # least maximum of the first k items in one group, then in one more each time
    for _ in range(4):
        best = [min(max(best[a], ends[b] - ends[a]) for a in range(b + 1)) for b in range(61)]
    few = cut.cut_bottleneck(placed, 5, held).orderBy("pos").collect()
    assert max(sum(r.len for r in few if r.grp == k) for k in range(5)) == best[-1]
    assert few == cut.cut_bottleneck(placed, 5).orderBy("pos").collect()


def test_brute_force_bound(spark):
    """No method beats the best of all groupings of a tiny matrix."""
    g = np.random.default_rng(1)
    m = g.integers(0, 9, (5, 4))
    cells = [(i, j, m[i, j]) for i in range(5) for j in range(4) if m[i, j]]
    best = 0.0
    for rg in itertools.product(range(2), repeat=5):
        for cg in itertools.product(range(2), repeat=4):
            b = np.zeros((2, 2))
            for i, j, n in cells:
                b[rg[i], cg[j]] += n
            best = max(best, m.sum() / 2 / (max(b[0, 0], b[1, 1]) + max(b[0, 1], b[1, 0])))
    for method in ("interleave", "mirror", "mirror_alternate", "stratified", "plain_shuffle"):
        assert trials.eta_of(matrix(spark, cells), method, 2).first().eta <= best + 1e-12


def test_stratified_deals_each_run_over_all_slots(spark):
    lens = spark.range(1, 38).select(F.col("id"), (100 - F.col("id")).alias("len"))
    placed = permute.stratified(lengths.rank_desc(lens), 5, trials=3)
    rows = placed.collect()
    for t in range(3):
        own = sorted((r.pos, r["rank"]) for r in rows if r.trial == t)
        slots = [8, 8, 7, 7, 7]  # the short last run fills the first slots
        at = 0
        for n in slots:
            runs = [(k - 1) // 5 for _, k in own[at : at + n]]
            assert sorted(runs) == list(range(8))[:n] if n == 8 else sorted(runs) == list(range(7))
            at += n
    again = permute.stratified(lengths.rank_desc(lens.repartition(13)), 5, trials=3)
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again.select(placed.columns).collect()))


def test_reflection_keeps_what_it_should(spark, small):
    r = lengths.rank_desc(lengths.lengths(small, "row"))
    p = permute.interleave(r)
    twice = permute.reflect(permute.reflect(p))
    assert p.select("id", "pos").orderBy("id").collect() == twice.select("id", "pos").orderBy("id").collect()


def test_trials_in_one_pass_equal_single_trials(spark, small):
    for method in permute.RANDOM:
        one = {r.trial: r.eta for r in trials.trial_etas(small, method, 4, 3).collect()}
        for t in range(3):
            assert math.isclose(one[t], trials.eta_of(small, method, 4, trial=t).first().eta)
        best = trials.best_of(small, method, 4, 3).first()
        assert best.eta == max(one.values()) and one[best.trial] == best.eta


def test_orders_of_many_trials_make_no_rows(spark, small):
    """One row an item whatever the number of trials, with the groups that each order alone gives, for both rules of tokens and for counts."""
    ids = np.array([0, 7, -3, 2**62, 123_456])
    assert Keys(ids).of(7, "row", "deal", 12).tolist() == [int(hashlib.md5(f"7:12:row:deal:{i}".encode()).hexdigest()[:12], 16) for i in ids.tolist()]
    ranked = trials.ranked_axes(small)[1]
    choices = [Choice(m, p, t) for m, p, t in (("stratified", 3, 0), ("stratified", 5, 4), ("plain_shuffle", 60, 2), ("mirror", 7, 0), ("interleave", 1, 0), ("mirror_alternate", 4, 0), ("sorted", 4, 0))]
    for rule in cut.RULES:
        got = {r.id: list(r.grps) for r in Axis(ranked, choices, 7, "col", rule).frame().collect()}
        assert len(got) == ranked.count()
        for k, c in enumerate(choices):
            alone = cut.cut(permute.place(ranked, c.method, c.groups, 7, "col", 1, c.trial).drop("trial"), c.groups, rule)
            assert {r.id: r.grp for r in alone.collect()} == {i: g[k] for i, g in got.items()}


def test_comparison_plan_does_not_grow(spark, small):
    plans = [trials.compare(small, ("mirror", "plain_shuffle"), sizes, 2)._jdf.queryExecution().executedPlan().toString().count("Exchange") for sizes in ((1,), (1, 2, 3))]
    assert plans[0] == plans[1]


def test_texts_are_counted_where_they_are_read(spark):
    """The matrix that plain counting gives, for any ids, with a record for each word and block of documents instead of one for each cell."""
    texts = ["b a a c", "", None, "C a d", "e " * 300 + "a", "f"]
    for ids in ((1, 2, 3, 4, 5, 6), (-(2**62), 9, 10, 2**62, 5, 70_000), (1, 1, 3, 4, 4, 6), (1, None, 3, None, 5, None)):
        docs = spark.createDataFrame(list(zip(ids, texts, strict=True)), "doc_id bigint, text string").coalesce(1)
        counts = tokens.word_counts(tokens.tokens(docs))
        for prune in ((), (2,), (1, 2)):
            want = sorted(map(str, workload.workload(counts, tokens.vocabulary(counts, *prune)).collect()))
            assert sorted(map(str, corpora.text_matrix(docs, *prune).collect())) == want
        if None not in ids:
            got = postings.postings(tokens.tokens(docs) if len(set(ids)) == 6 else counts.coalesce(1))
            assert got.count() == got.select("word").distinct().count() == 6


def test_blocks_end_where_documents_do():
    ids, words = np.repeat([5, 6, 2**61, 8], [7, 900, 3, 40]), np.array(["a", "b", "c"])[np.arange(950) % 3]
    parts = [pa.RecordBatch.from_arrays([pa.array(ids[a : a + 10]), pa.array(words[a : a + 10].tolist())], names=["row_id", "word"]) for a in range(0, 950, 10)]
    cells = []
    for b in postings._pack(iter(parts), 30):
        numbered = pa.RecordBatch.from_arrays([pa.array([ord(w) for w in b.column(0).to_pylist()]), *(b.column(k) for k in (3, 4, 5))], names=["col_id", "base", "kind", "cells"])
        cells += [x for o in postings._unpack(iter([numbered])) for x in zip(*(o.column(k).to_pylist() for k in range(3)), strict=True)]
    assert len({x[:2] for x in cells}) == len(cells) == 12 and sum(x[2] for x in cells) == 950


def test_cells_travel_many_in_a_record():
    rng = np.random.default_rng(3)
    task, row, col, n = rng.integers(0, 3, 5000).astype(np.int32), rng.integers(-(2**62), 2**62, 5000), rng.integers(0, 50, 5000), rng.integers(1, 300, 5000)
    row[:2], col[:2], n[0] = (-(2**63), 2**63 - 1), (2**63 - 1, -(2**63)), 2**50
    parts = [pa.RecordBatch.from_arrays([pa.array(x[a : a + 700]) for x in (task, row, col, n)], names=["task", "row_id", "col_id", "n"]) for a in range(0, 5000, 700)]
    out = [(b.column(0)[k].as_py(), b.column(1).slice(k, 1)) for b in choices._pack(iter(parts)) for k in range(b.num_rows)]
    assert len(out) <= 5000 // choices.PACKED + 3
    got = [(t, *x) for t, pack in out for r, c, m in choices._unpack(pack) for x in zip(r.tolist(), c.tolist(), m.tolist(), strict=True)]
    assert sorted(got) == sorted(zip(task.tolist(), row.tolist(), col.tolist(), n.tolist(), strict=True))


def test_advise_stops_early(spark, small):
    easy = trials.advise(small, 2, 0.5, 20).first()
    assert easy.reached and easy.tried == 2 and easy.method in ("interleave", "mirror")
    hard = trials.advise(small, 7, 0.9999, 6, 3).first()
    assert hard.tried <= 8 and hard.eta <= hard.ceiling + 1e-12


def test_advised_trial_can_be_made_again(spark, small):
    """Also one from a later round of trials."""
    a = trials.advise(small, 5, 1.0, 4, 2, seed=9).first()
    assert math.isclose(a.eta, trials.eta_of(small, a.method, 5, seed=9, trial=a.trial).first().eta), a
    late = trials.trial_groups(trials.ranked_axes(small)[0], "stratified", 4, 2, 9, "row", first=3)
    one = trials.partition(small, "stratified", 4, seed=9, trial=4).rows
    assert {r.id: r.grps[1] for r in late.collect()} == {r.id: r.grp for r in one.collect()}


def test_models_of_memory_and_barriers():
    m = cost.memory_model(10, 20, 4, 3)
    assert m == {"diagonal": 960, "replica": 320 + 3 * 640} and cost.barriers(7) == {"diagonal": 7, "replica": 1}


def test_memory_follows_the_tables(spark, sf, tmp_path):
    rows = QUERIES["memory_and_barriers"](spark, sf).orderBy("groups").collect()
    m = basket(spark, sf)
    theta, phi = (m.select(c).distinct().count() * 256 * 8 for c in ("row_id", "col_id"))
    assert [(r.groups, r.diagonal_bytes, r.replica_bytes) for r in rows] == [(p, theta + phi, theta + p * phi) for p in (1, 2, 4, 10, 30)]


def test_sql_functions(spark):
    register(spark)
    assert [r.p for r in spark.sql("SELECT interleave_pos(id, 7) AS p FROM range(1, 8)").collect()] == [1, 3, 5, 7, 6, 4, 2]
    assert [r.p for r in spark.sql("SELECT mirror_pos(id, 8) AS p FROM range(1, 9)").collect()] == [1, 7, 3, 4, 5, 6, 2, 8]
    assert spark.sql("SELECT diag_of(3, 1, 4), cut_group(10, 4, 100, 10)").first() == (2, 1)
    assert [r["rank"] for r in spark.sql("SELECT * FROM grid_positions(8, 'interleave')").collect()] == [1, 8, 2, 7, 3, 6, 4, 5]
    spark.createDataFrame([(0, 0, 4), (0, 1, 1), (0, 2, 2), (1, 0, 3), (1, 1, 5), (1, 2, 1), (2, 0, 2), (2, 1, 2), (2, 2, 4)], "m int, n int, cost bigint").createOrReplaceTempView("grid3")
    r = spark.sql("SELECT * FROM balance_table(TABLE(grid3) WITH SINGLE PARTITION, 3)").first()
    assert (r.tokens, r.total_cost, r.optimum, r.eta, r.heaviest_diag) == (24, 10, 8.0, 0.8, 0)
    assert spark.sql("SELECT m, evenness(cost) AS e FROM grid3 GROUP BY m ORDER BY m").first().e == pytest.approx(7 / 12)


def test_coordinates_and_formats(spark, small, tmp_path):
    write_coordinates(small, f"file://{tmp_path}/c")
    assert read_coordinates(spark, f"file://{tmp_path}/c").exceptAll(small).isEmpty()
    for kind in ("parquet", "orc", "json"):
        small.write.format(kind).save(f"file://{tmp_path}/{kind}")
        assert read_workload(spark, f"file://{tmp_path}/{kind}", kind).exceptAll(small).isEmpty()


@pytest.mark.parametrize(("word", "want"), [("nationally", "nation"), ("sitting", "sit"), ("the", "the"), ("matrix", "matric"), ("hopping", "hop"), ("relational", "rel")])
def test_stems(word, want):
    assert stem(word) == want


def test_sinks(spark, small, tmp_path):
    """Groups, models, bucketed tables, CSV and approximate statistics."""
    from topicgrid.operators.workload import corpus_stats
    from topicgrid.sources import sinks

    p = trials.partition(small, "mirror", 3)
    sinks.write_groups(p.rows, p.cols, f"file://{tmp_path}/groups")
    back = spark.read.parquet(f"file://{tmp_path}/groups")
    assert back.filter("axis = 'row'").select("id", "grp").exceptAll(p.rows.select("id", "grp")).isEmpty()
    sinks.write_model(p.rows, p.cols, f"file://{tmp_path}/model", "json")
    assert spark.read.json(f"file://{tmp_path}/model/phi").count() == p.cols.count()
    small.write.option("header", True).csv(f"file://{tmp_path}/csv")
    assert read_workload(spark, f"file://{tmp_path}/csv", "csv").exceptAll(small).isEmpty()
    exact, near = corpus_stats(small).first(), corpus_stats(small, approximate=True).first()
    assert exact.tokens == near.tokens and abs(near.words - exact.words) <= 0.1 * exact.words
    sinks.write_bucketed(small, "bucketed_cells", "row_id", 4)
    t = spark.table("bucketed_cells")
    assert t.exceptAll(small).isEmpty()
    spark.sql("DROP TABLE bucketed_cells")


def test_golden_value(spark):
    from topicgrid.plans.corpora import basket

    r = trials.eta_of(basket(spark, "/root/testdata/sf0.01"), "interleave", 10).first()
    assert (r.tokens, r.total_cost, round(r.eta, 6)) == (1_524_135, 162_517, 0.937831)


def test_plans(spark, sf):
    """Only a histogram of lengths meets in one task; lengths read two columns; the diagonal's store prunes."""
    from topicgrid.plans.corpora import basket
    from topicgrid.sources.sinks import write_grid

    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    placed = permute.interleave(lengths.rank_desc(lengths.lengths(basket(spark, sf), "row")))
    text = plan(placed)
    assert "SinglePartition" in text  # of the lengths, below an aggregate of them
    for part in text.split("SinglePartition")[1:]:
        assert "HashAggregate(keys=[len" in part.split("Exchange hashpartitioning(len")[0] or "Window" in part or "HashAggregate(keys=[], functions=[partial_min" in part.split("Exchange")[0]
    import tempfile

    m = basket(spark, sf)
    p = trials.partition(m, "interleave", 3)
    path = f"file://{tempfile.mkdtemp()}/grid"
    write_grid(m, p.rows, p.cols, 3, path)
    back = spark.read.parquet(path)
    assert back.count() == m.count() and "PartitionFilters: [isnotnull(diag" in plan(back.filter("diag = 1"))
    files = back.filter("diag = 1").select(F.input_file_name().alias("f"), "m").distinct()
    assert files.count() == files.select("f").distinct().count() == files.select("m").distinct().count()
