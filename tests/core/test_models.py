"""Samplers: the kernel against exact distributions and a naive loop, schedules against a naive engine, conservation, placement and quality."""

import itertools
from collections import Counter, defaultdict
from math import gamma

import numpy as np
import pytest
from pyspark.sql import functions as F

from topicgrid.model import counts as C
from topicgrid.model import samplers as S
from topicgrid.model.kernel import KERNELS, stream, sweep, sweep_plain, sweep_waves, wave_numbers
from topicgrid.model.study import Setting, apart, fits, study, study_packed
from topicgrid.operators.trials import partition
from topicgrid.plans import corpora as K
from topicgrid.plans.queries import QUERIES

PRIORS = S.Priors(6)


@pytest.fixture(scope="module")
def corpus(spark, sf):
    return K.basket(spark, sf, weight=None).filter("row_id < 40").coalesce(1).cache()


@pytest.fixture(scope="module")
def stamps(spark, sf):
    return K.stamp_matrix(spark, sf).filter("row_id < 40").coalesce(1).cache()


def total(df, name="c"):
    return df.select(F.aggregate(name, F.lit(0).cast("bigint"), lambda a, x: a + x).alias("s")).agg(F.sum("s")).first()[0]


def tables(rows, cols, z, k):
    theta, phi = np.zeros((rows.max() + 1, k), np.int64), np.zeros((cols.max() + 1, k), np.int64)
    for r, c, t in zip(rows, cols, z, strict=True):
        theta[r, t] += 1
        phi[c, t] += 1
    return theta, phi, phi.sum(axis=0)


def exact_posterior(rows, cols, k, alpha, beta, size):
    """Probability of every assignment, from the joint of words and topics with both distributions integrated out."""
    weight = {}
    for z in itertools.product(range(k), repeat=len(rows)):
        theta, phi, totals = tables(rows, cols, z, k)
        w = np.prod([gamma(c + alpha) for c in theta.ravel()]) * np.prod([gamma(c + beta) for c in phi.ravel()])
        weight[z] = w / np.prod([gamma(t + size * beta) for t in totals])
    mass = sum(weight.values())
    return {z: w / mass for z, w in weight.items()}


@pytest.mark.parametrize("kernel", ["loop", "waves"])
def test_kernel_samples_the_posterior(kernel):
    """Long chains on five tokens visit each assignment as often as the exact posterior says. In waves topic totals stand still for tokens drawn
    together, so these chains may be off a little; token by token they are not."""
    rows, cols, k, alpha, beta, size = np.array([0, 0, 0, 1, 1]), np.array([0, 1, 0, 0, 2]), 2, 0.7, 0.4, 3
    want = exact_posterior(rows, cols, k, alpha, beta, size)
    g, z, seen, n = np.random.default_rng(5), np.zeros(5, np.int64), Counter(), 30_000
    theta, phi, totals = tables(rows, cols, z, k)
    for _ in range(n):
        KERNELS[kernel](rows, cols, z, theta, phi, totals, alpha, beta, size, g.random(5))
        seen[tuple(z.tolist())] += 1
    far = sum(abs(seen[x] / n - p) for x, p in want.items()) / 2
    assert far < (0.02 if kernel == "loop" else 0.06), far


@pytest.mark.parametrize("hot", [False, True])
def test_waves_share_nothing(hot):
    g = np.random.default_rng(2)
    rows = np.sort(g.integers(0, 300, 20_000))
    cols = g.integers(0, 400, 20_000) if not hot else np.minimum(g.geometric(0.2, 20_000), 400)
    w = wave_numbers(rows, cols)
    assert np.array_equal(w, wave_numbers(rows, cols))
    for k in range(w.max() + 1):
        at = np.flatnonzero(w == k)
        assert len(at) and len(np.unique(rows[at])) == len(np.unique(cols[at])) == len(at)
    assert hot or (w < 0).sum() < 200
    assert wave_numbers(rows[:0], cols[:0]).size == 0 and wave_numbers(rows[:1], cols[:1]).tolist() == [0]


def naive_sweep(rows, cols, z, theta, phi, totals, alpha, beta, size, u, waves):
    """Plain Python: waves in order, totals as they were when a wave began; then the rest, one at a time."""
    for k in [*range(max(waves, default=-1) + 1), -1]:
        before = None if k < 0 else list(totals)
        for t in [i for i, w in enumerate(waves) if w == k]:
            d, w = theta[rows[t]], phi[cols[t]]
            d[z[t]] -= 1
            w[z[t]] -= 1
            totals[z[t]] -= 1
            seen = list(totals) if before is None else [x - (j == z[t]) for j, x in enumerate(before)]
            weights = [(a + alpha) * (b + beta) / (s + size * beta) for a, b, s in zip(d, w, seen, strict=True)]
            cut, run, new = u[t] * sum(weights), 0.0, 0
            for new, x in enumerate(weights):  # noqa: B007
                run += x
                if run > cut:
                    break
            z[t] = new
            d[new] += 1
            w[new] += 1
            totals[new] += 1


@pytest.mark.parametrize("kernel", ["loop", "waves"])
def test_kernel_against_a_naive_loop(kernel):
    g = np.random.default_rng(8)
    rows, cols, z = np.sort(g.integers(0, 20, 400)), np.minimum(g.geometric(0.15, 400), 30), g.integers(0, 5, 400)
    u = g.random(400)
    waves = wave_numbers(rows, cols) if kernel == "waves" else np.full(400, -1)
    mine, (theta, phi, totals) = z.copy(), tables(rows, cols, z, 5)
    KERNELS[kernel](rows, cols, mine, theta, phi, totals, 0.5, 0.1, 31, u)
    naive = z.tolist()
    th, ph, to = (x.tolist() for x in tables(rows, cols, z, 5))
    naive_sweep(rows.tolist(), cols.tolist(), naive, th, ph, to, 0.5, 0.1, 31, u.tolist(), waves.tolist())
    assert mine.tolist() == naive and theta.tolist() == th and phi.tolist() == ph and totals.tolist() == to


def naive_fit(parts, groups, priors, iterations, seed, kernel):
    """The diagonal schedule on dictionaries: epochs, phases, blocks; totals as they were when the epoch began."""
    theta, tokens = defaultdict(lambda: np.zeros(priors.topics, np.int64)), []
    for cells, row_of, col_of, prior in parts:
        phi = defaultdict(lambda: np.zeros(priors.topics, np.int64))
        flat = [[a, b, t, row_of[a], col_of[b]] for a, b, z in sorted(cells) for t in z]
        for a, b, t, *_ in flat:
            theta[a][t] += 1
            phi[b][t] += 1
        tokens.append((flat, phi, prior))
    for it in range(iterations):
        for diag in range(groups):
            for phase, (flat, phi, prior) in enumerate(tokens):
                start = sum(phi.values())
                after = start.copy()
                for m in range(groups):
                    block = [x for x in flat if x[3] == m and x[4] == (m + diag) % groups]
                    if not block:
                        continue
                    rows, cols = sorted({x[0] for x in block}), sorted({x[1] for x in block})
                    r, c = np.array([rows.index(x[0]) for x in block]), np.array([cols.index(x[1]) for x in block])
                    z = [int(x[2]) for x in block]
                    waves = wave_numbers(r, c).tolist() if kernel == "waves" else [-1] * len(z)
                    own = start.tolist()
                    naive_sweep(r.tolist(), c.tolist(), z, [theta[x] for x in rows], [phi[x] for x in cols], own, priors.alpha, prior, len(phi), stream(seed, it, phase, diag, m).random(len(z)).tolist(), waves)
                    for x, new in zip(block, z, strict=True):
                        x[2] = new
                    after = after + np.array(own) - start
                assert (sum(phi.values()) == after).all()
    return {a: v.tolist() for a, v in theta.items()}


def arrays(df, by="row_id"):
    return {r[by]: list(r.c) for r in df.collect()}


@pytest.mark.parametrize(("groups", "kernel"), [(1, "loop"), (2, "waves")])
def test_engine_equals_a_naive_one(spark, corpus, stamps, groups, kernel):
    a, b = partition(corpus, "mirror", groups), partition(stamps, "interleave", groups)
    priors = S.Priors(6, gamma=0.3)
    parts = []
    for m, p, axis, prior in ((corpus, a, "word", 0.1), (stamps, b, "stamp", 0.3)):
        cells = [(r.row_id, r.col_id, r.z) for r in C.init_topics(m, 6, 7, axis).collect()]
        parts.append((cells, {r.id: r.grp for r in p.rows.collect()}, {r.id: r.grp for r in p.cols.collect()}, prior))
    fit = S.fit_diagonal_stamped(corpus, stamps, (a.rows, a.cols), (b.rows, b.cols), groups, priors, groups, track=False, kernel=kernel)
    assert arrays(fit.theta) == naive_fit(parts, groups, priors, groups, 7, kernel)
    n, s = (m.agg(F.sum("n")).first()[0] for m in (corpus, stamps))
    assert (total(fit.theta), total(fit.phi), total(fit.pi)) == (n + s, n, s)


@pytest.mark.parametrize("layout", ["plain", "shared_rows", "merged"])
def test_ring_equals_staged(spark, corpus, stamps, layout):
    a, b = partition(corpus, "mirror", 3), partition(stamps, "mirror", 3)
    fits = []
    for execution in ("staged", "ring"):
        if layout == "plain":
            fits.append(S.fit_diagonal(corpus, a.rows, a.cols, 3, PRIORS, 2, track=False, execution=execution))
        else:
            fits.append(S.fit_diagonal_stamped(corpus, stamps, (a.rows, a.cols), (b.rows, b.cols), 3, PRIORS, 1, track=False, layout=layout, execution=execution))
    assert arrays(fits[0].theta) == arrays(fits[1].theta) and arrays(fits[0].phi, "col_id") == arrays(fits[1].phi, "col_id")
    n, s = (m.agg(F.sum("n")).first()[0] for m in (corpus, stamps))
    assert total(fits[1].theta) == n + (layout != "plain") * s
    assert layout == "plain" or total(fits[0].pi) == total(fits[1].pi) == s


def test_ring_needs_slots(spark, corpus):
    p = partition(corpus, "mirror", 20)
    with pytest.raises(ValueError, match="slots"):
        S.fit_diagonal(corpus, p.rows, p.cols, 20, PRIORS, 1, execution="ring")


@pytest.mark.parametrize("groups", [2, 3])
def test_an_iteration_writes_each_token_once(spark, corpus, groups):
    """Whatever P is: an epoch reads and writes the cells of its own diagonal only."""
    p = partition(corpus, "mirror", groups)
    store = S.open_store(corpus, None, (p.rows, p.cols), None, groups, PRIORS, 7, "shared_rows")
    part, n, written = S.Part("z", "p", 0.1, 200, 0), corpus.agg(F.sum("n")).first()[0], 0
    for diag in range(groups):
        before = dict(store.cells)
        S._epoch(store, diag, (part,), PRIORS, 7, 0, "g", "waves")
        assert {k for k in before if before[k] != store.cells[k]} == {("z", diag)}
        written += store.diagonal("z", diag).agg(F.sum(F.size("v"))).first()[0]
        assert store.diagonal("z", diag).filter(F.pmod(F.col("h") - F.col("g"), F.lit(groups)) != diag).isEmpty()
    assert written == n


def test_diagonal_conserves_and_improves(spark, corpus, groups=2):
    p = partition(corpus, "mirror", groups)
    fit = S.fit_diagonal(corpus, p.rows, p.cols, groups, PRIORS, 3)
    n = corpus.agg(F.sum("n")).first()[0]
    assert total(fit.theta) == total(fit.phi) == n
    for by, kept in (("row_id", fit.theta), ("col_id", fit.phi)):
        assert arrays(C.topic_counts(fit.cells.filter("kind = 'z'"), by, 6), by) == arrays(kept, by)
    assert fit.history[-1] < fit.history[0]


def test_study_equals_the_grid(spark, corpus, stamps):
    """Fits in one task draw what the grid draws: diagonal, serial, stamped, replicating."""
    a, b = partition(corpus, "mirror", 2), partition(stamps, "mirror", 2)
    settings = [Setting("diagonal", 2), Setting("serial", 1, kernel="loop")]
    found = study(corpus, stamps, settings, PRIORS, 1).collect()
    stamped = S.fit_diagonal_stamped(corpus, stamps, (a.rows, a.cols), (b.rows, b.cols), 2, PRIORS, 1)
    serial = S.fit_serial_stamped(corpus, stamps, PRIORS, 1)
    for name, fit in (("diagonal", stamped), ("serial", serial)):
        assert [r.perplexity for r in sorted((r for r in found if r.sampler == name), key=lambda r: r.iteration)] == pytest.approx(fit.history)
    plain = study(corpus, None, [Setting("replica", 2)], PRIORS, 2).orderBy("iteration").collect()
    want = S.fit_replica(corpus, partition(corpus, "mirror", 2).rows, 2, PRIORS, 2)
    assert [r.perplexity for r in plain] == pytest.approx(want.history)


def test_parallel_is_about_as_good(spark, corpus, stamps):
    """Means over three seeds of serial and diagonal lie within 2 percent; groups of 1 to 10."""
    seeds = (1, 2, 3)
    settings = [Setting("serial", 1, s, kernel="loop") for s in seeds] + [Setting("diagonal", p, s) for p in (1, 2, 4, 10) for s in seeds]
    end = study(corpus, stamps, settings, PRIORS, 15).filter("iteration = 15").groupBy("sampler", "groups").agg(F.avg("perplexity").alias("p")).collect()
    serial = next(r.p for r in end if r.sampler == "serial")
    assert len(end) == 5 and all(abs(r.p - serial) < 0.02 * serial for r in end), end


def test_fits_have_no_bound(spark, corpus, stamps):
    """Above what tasks hold in memory the grid gives the same."""
    settings = [Setting("serial", 1, 3, kernel="loop"), Setting("diagonal", 1, 3), Setting("diagonal", 2, 3)]
    a, b = (fits(corpus, stamps, settings, PRIORS, 1, m).orderBy("sampler", "groups", "iteration").collect() for m in (10**7, 1))
    assert [(r.sampler, r.groups, r.iteration, r.tokens) for r in a] == [(r.sampler, r.groups, r.iteration, r.tokens) for r in b]
    assert [r.perplexity for r in a] == pytest.approx([r.perplexity for r in b])


@pytest.mark.parametrize("topics", [1, 8, 64, 65])
def test_unrolled_sweep_equals_the_plain_one(topics):
    rng = np.random.default_rng(topics)
    rows, cols, z0 = rng.integers(0, 40, 20_000), rng.integers(0, 31, 20_000), rng.integers(0, topics, 20_000)
    ended = []
    for f in (sweep_plain, sweep):
        z, theta, phi = z0.copy(), np.zeros((40, topics), np.int64), np.zeros((31, topics), np.int64)
        np.add.at(theta, (rows, z), 1)
        np.add.at(phi, (cols, z), 1)
        totals = phi.sum(axis=0)
        f(rows, cols, z, theta, phi, totals, 0.5, 0.1, 31, np.random.default_rng(9).random(len(z)))
        ended.append((z, theta, phi, totals))
    assert all(np.array_equal(x, y) for x, y in zip(*ended, strict=True))


def test_serial_lda_makes_all_sweeps(spark, sf):
    """As many as the serial sampler makes by itself, which are the published 200."""
    found = QUERIES["serial_lda"](spark, sf).orderBy("iteration").collect()
    assert [r.iteration for r in found] == list(range(201)) and found[-1].perplexity < found[1].perplexity


def test_sweeps_in_one_task_equal_jobs(spark, corpus, monkeypatch):
    """All iterations of a serial fit in one task draw what a job an iteration draws."""
    assert S.native.compiled(spark, 6) and S.native.java()
    together = S.fit_serial(corpus, PRIORS, 3)
    monkeypatch.setattr(S, "IN_ONE", 0)
    apart = S.fit_serial(corpus, PRIORS, 3)
    assert together.history == pytest.approx(apart.history, rel=1e-12) and len(together.history) == 4
    for a, b, by in ((together.theta, apart.theta, "row_id"), (together.phi, apart.phi, "col_id")):
        assert arrays(a, by) == arrays(b, by)
    assert together.cells.exceptAll(apart.cells).isEmpty() and together.cells.count() == apart.cells.count()


def test_packed_study_equals_the_other(spark, corpus, stamps):
    """Fits in processes beside their tasks draw what those in Python draw, for every sampler, kernel and P."""
    settings = [Setting("serial", 1, 3, kernel="loop"), *(Setting("diagonal", p, s) for p in (1, 3) for s in (3, 4)), Setting("diagonal", 2, 3, "stratified", "loop")]
    replicas = [Setting("replica", p, 4, kernel=k) for p, k in ((1, "waves"), (3, "waves"), (2, "loop"))]
    n, k = (m.agg(F.sum("n")).first()[0] for m in (corpus, stamps))
    for some, extra, sizes in ((settings, stamps, [n, k]), ([*settings, *replicas], None, [n])):
        a, b = (x.orderBy("sampler", "method", "groups", "seed", "iteration").collect() for x in (study(corpus, extra, some, PRIORS, 2), study_packed(corpus, extra, some, PRIORS, 2, sizes, range(3))))
        assert [r[:5] + (r.tokens,) for r in a] == [r[:5] + (r.tokens,) for r in b] and len(a) == 3 * len(some)
        assert [r.perplexity for r in a] == pytest.approx([r.perplexity for r in b], rel=1e-12)


def test_fits_lie_in_tasks_of_their_own(spark, tmp_path):
    """As Spark 4.1 unites frames of one partition each, all fits would run in one task."""
    one = [spark.range(3).coalesce(1) for _ in range(4)]
    together = one[0].union(one[1]).union(one[2]).union(one[3])
    assert len(apart(together).inputFiles()) == 4


def test_study_has_a_bound(spark, corpus):
    with pytest.raises(ValueError, match="at most"):
        study(corpus.withColumn("n", F.col("n") * 10**7), None, [Setting("serial")], PRIORS, 1)


def test_replica_conserves(spark, corpus):
    p = partition(corpus, "mirror", 2)
    fit = S.fit_replica(corpus, p.rows, 2, PRIORS, 2)
    n = corpus.agg(F.sum("n")).first()[0]
    assert total(fit.theta) == total(fit.phi) == n and fit.history[-1] < fit.history[0]
    assert arrays(C.topic_counts(fit.cells, "col_id", 6), "col_id") == arrays(fit.phi, "col_id")


def test_one_topic_is_the_unigram(spark, corpus):
    fit = S.fit_serial(corpus, S.Priors(1), 1)
    w = [r.c for r in corpus.groupBy("col_id").agg(F.sum("n").alias("c")).collect()]
    n = sum(w)
    want = np.exp(-sum(c * np.log((c + 0.1) / (n + len(w) * 0.1)) for c in w) / n)
    assert np.isclose(fit.history[-1], want) and np.isclose(fit.history[0], want)


def test_convergence_rule():
    assert not S.converged([10.0], 0.1) and S.converged([10.0, 9.99], 0.01) and not S.converged([10.0, 9.0], 0.01)


def test_frozen_sweep_redraws_every_token(spark, corpus):
    z = C.init_topics(corpus, 4, 7)
    out = S.frozen_sweep(z, 4, 0.5, 0.1)
    assert out.count() == corpus.agg(F.sum("n")).first()[0] and out.filter("z < 0 OR z > 3").isEmpty()


def test_sparse_counts_equal_dense(spark, corpus):
    z = C.init_topics(corpus, 5, 7)
    dense = {r.row_id: {k: c for k, c in enumerate(r.c) if c} for r in C.topic_counts(z, "row_id", 5).collect()}
    assert dense == {r.row_id: dict(r.c) for r in C.sparse_counts(z, "row_id").collect()}


def test_block_tasks_see_one_group(spark):
    """The placement that samplers rely on: one group a task, also after reading back."""
    df = spark.range(1000).select((F.col("id") % 4).cast("int").alias("task"))

    def seen(it):
        import pandas as pd

        b = pd.concat(list(it))
        yield pd.DataFrame({"k": [b["task"].nunique() if len(b) else 0], "n": [len(b)]})

    out = df.repartitionById(4, F.col("task")).mapInPandas(seen, "k int, n int").collect()
    assert sorted(r.n for r in out if r.n) == [250] * 4 and all(r.k <= 1 for r in out)
