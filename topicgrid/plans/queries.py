"""One query for each method, variant, baseline, measure, workload and operator, with its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from topicgrid.functions.rng import key
from topicgrid.functions.stem import stemmed_vocabulary
from topicgrid.model import counts as C
from topicgrid.model import samplers as S
from topicgrid.model.study import Setting, fits
from topicgrid.operators import cost, cut, lengths, permute, stamps, tokens, trials, workload
from topicgrid.plans import corpora as K
from topicgrid.plans import oracles as O
from topicgrid.sources.shared import stored
from topicgrid.sources.tables import table
from topicgrid.streaming import online

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
SIZES = (1, 2, 4, 10, 30)
P = 4


def query(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql is not None:
            ORACLES[name or f.__name__] = sql
        return f

    return add


# Corpus to workload matrix


@query(f"WITH {O.TOKENS} SELECT row_id, count(*) AS n FROM tok GROUP BY 1")
def tokens_count(spark, sf):
    return tokens.tokens(table(spark, sf, "documents")).groupBy("row_id").agg(F.count(F.lit(1)).alias("n"))


STOP = ("the", "of", "and", "to", "in", "der", "die", "das", "le", "la", "de", "et", "que", "el", "en")


@query(f"WITH {O.TOKENS} SELECT word, count(*) AS n FROM tok WHERE word NOT IN {STOP} GROUP BY 1")
def stopword_filtered(spark, sf):
    return tokens.drop_stopwords(tokens.tokens(table(spark, sf, "documents")), STOP).groupBy("word").agg(F.count(F.lit(1)).alias("n"))


@query()
def stemmed_vocab(spark, sf):
    return stemmed_vocabulary(tokens.vocabulary(K.doc_counts(spark, sf)))


@query(f"WITH {O.VOCAB} SELECT word_id, word, df, cf FROM v")
def vocab_stats(spark, sf):
    return tokens.vocabulary(K.doc_counts(spark, sf))


@query(f"WITH {O.DOCS} SELECT row_id, col_id, n FROM r")
def workload_docs(spark, sf):
    return K.docs(spark, sf)


@query(f"WITH {O.PRUNED} SELECT row_id, col_id, n FROM r")
def workload_docs_pruned(spark, sf):
    return K.docs_pruned(spark, sf)


@query(f"WITH {O.BASKET} SELECT row_id, col_id, n FROM r")
def workload_basket(spark, sf):
    return K.basket(spark, sf)


@query("SELECT l_orderkey AS row_id, l_partkey AS col_id, sum(l_quantity::BIGINT)::BIGINT AS n FROM lineitem GROUP BY 1, 2")
def workload_order_basket(spark, sf):
    return K.order_basket(spark, sf)


@query(f"WITH {O.TIMES} SELECT row_id, col_id, n FROM r")
def workload_basket_time(spark, sf):
    return K.basket_time(spark, sf)


@query("SELECT user_id AS row_id, event_type || '/' || coalesce(json_extract_string(props, '$.k'), '') AS col, count(*) AS n FROM events WHERE user_id IS NOT NULL GROUP BY 1, 2")
def workload_clicks(spark, sf):
    e = table(spark, sf, "events").filter("user_id IS NOT NULL")
    col = F.concat_ws("/", "event_type", F.coalesce(F.get_json_object("props", "$.k"), F.lit("")))
    return e.groupBy(F.col("user_id").alias("row_id"), col.alias("col")).agg(F.count(F.lit(1)).alias("n"))


M = O.MONTHS.format("o_orderdate")
BUYERS = f"d AS (SELECT o_custkey AS row_id, {M} AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"
PROPORTIONAL = (
    BUYERS + ", c AS (SELECT row_id, s, count(*) AS c FROM d GROUP BY 1, 2), "
    "q AS (SELECT row_id, s, c * 16 // sum(c) OVER w AS q, c * 16 % sum(c) OVER w AS rest FROM c WINDOW w AS (PARTITION BY row_id)), "
    "k AS (SELECT row_id, s, (q + (row_number() OVER (PARTITION BY row_id ORDER BY rest DESC, s) <= 16 - sum(q) OVER (PARTITION BY row_id))::INT)::BIGINT AS k FROM q)"
)


@query(f"WITH {BUYERS} SELECT row_id, array_to_string(list_resize([]::BIGINT[], 16, min(s)), ',') AS stamps FROM d GROUP BY 1")
def stamps_repeat(spark, sf):
    return K.customer_stamps(spark, sf, "repeat").select("row_id", F.concat_ws(",", F.transform("stamps", lambda s: s.cast("string"))).alias("stamps"))


@query(f"WITH {PROPORTIONAL} SELECT row_id, string_agg(s, ',' ORDER BY s) AS stamps FROM (SELECT row_id, s, unnest(range(k)) FROM k) GROUP BY 1")
def stamps_proportional(spark, sf):
    return K.customer_stamps(spark, sf, "proportional").select("row_id", F.concat_ws(",", F.transform("stamps", lambda s: s.cast("string"))).alias("stamps"))


@query(f"WITH {BUYERS} SELECT row_id, string_agg(s, ',' ORDER BY s) AS stamps FROM d GROUP BY 1")
def stamps_raw(spark, sf):
    return K.customer_stamps(spark, sf, "raw").select("row_id", F.concat_ws(",", F.transform("stamps", lambda s: s.cast("string"))).alias("stamps"))


@query(f"WITH {PROPORTIONAL} SELECT row_id, s AS col_id, k AS n FROM k WHERE k > 0")
def workload_stamps(spark, sf):
    return K.stamp_matrix(spark, sf)


SHIFT = 10_000_000
MERGED = f"{O.BASKET.replace('r AS', 'w AS', 1)}, {PROPORTIONAL}, r AS (SELECT row_id, col_id, n, 'word' AS kind FROM w UNION ALL SELECT row_id, s + {SHIFT}, k, 'stamp' FROM k WHERE k > 0)"


def _merged(spark, sf):
    return workload.merged_workload(K.basket(spark, sf), K.stamp_matrix(spark, sf), SHIFT)


@query(f"WITH {MERGED} SELECT row_id, col_id, n, kind FROM r")
def workload_merged(spark, sf):
    return _merged(spark, sf)


STATS = "count(DISTINCT row_id) AS documents, count(DISTINCT col_id) AS words, sum(n)::BIGINT AS tokens, count(*) AS cells"


@query(f"WITH {O.DOCS} SELECT {STATS} FROM r")
def corpus_stats_docs(spark, sf):
    return workload.corpus_stats(K.docs(spark, sf))


@query(f"WITH {O.BASKET}, {PROPORTIONAL} SELECT * FROM (SELECT {STATS} FROM r), (SELECT count(DISTINCT s) AS timestamps, min(s) AS first_stamp, max(s) AS last_stamp FROM k WHERE k > 0)")
def corpus_stats_basket(spark, sf):
    return workload.corpus_stats(K.basket(spark, sf), K.stamp_matrix(spark, sf))


@query(f"WITH {O.DOCS}, d AS (SELECT doc_id FROM documents WHERE lang = 'en') SELECT count(DISTINCT row_id) AS documents, count(DISTINCT word) AS words, sum(n)::BIGINT AS tokens FROM wc JOIN d ON d.doc_id = wc.row_id")
def docs_english_workload(spark, sf):
    english = table(spark, sf, "documents").filter("lang = 'en'").select("doc_id", "text")
    return tokens.word_counts(tokens.tokens(english)).agg(F.count_distinct("row_id").alias("documents"), F.count_distinct("word").alias("words"), F.sum("n").alias("tokens"))


# Lengths and ranks


def _lens(axis, corpus=K.basket):
    return lambda spark, sf: lengths.lengths(corpus(spark, sf), axis)


for _axis, _t in (("row", "rl"), ("col", "cl")):
    query(f"WITH {O.BASKET}, {O.LENS} SELECT id, len FROM {_t}", f"{_axis}_lengths")(_lens(_axis))
    query(f"WITH {O.DOCS}, {O.LENS} SELECT id, len FROM {_t}", f"{_axis}_lengths_docs")(_lens(_axis, K.docs))


@query(f"WITH {O.BASKET}, {O.LENS} SELECT id, len FROM cl ORDER BY len DESC, id LIMIT 10")
def longest_columns(spark, sf):
    return lengths.extremes(_lens("col")(spark, sf), 10)


@query(f"WITH {O.BASKET}, {O.LENS} SELECT id, len FROM rl ORDER BY len, id LIMIT 10")
def shortest_rows(spark, sf):
    return lengths.extremes(_lens("row")(spark, sf), 10, longest=False)


def _ranked(axis, mode="two_level", corpus=K.basket, tie="id"):
    return lambda spark, sf: lengths.rank_desc(_lens(axis, corpus)(spark, sf), tie, O.SEED, mode, axis)


RANK_SQL = f"WITH {O.BASKET}, {O.RANKS} SELECT id, len, rank, size, total FROM rr"
query(RANK_SQL, "rank_rows")(_ranked("row"))
query(RANK_SQL, "rank_rows_window")(_ranked("row", "window"))
query(f"WITH {O.DOCS}, {O.RANKS} SELECT id, len, rank, size, total FROM cr", "rank_cols_docs")(_ranked("col", corpus=K.docs))
query(
    f"WITH {O.BASKET}, {O.LENS} SELECT id, len, row_number() OVER (ORDER BY len DESC, {O.key('row', 'tie', chr(39) + '0' + chr(39))}, id) AS rank, count(*) OVER () AS size, (sum(len) OVER ())::BIGINT AS total FROM rl",
    "rank_rows_hash_ties",
)(_ranked("row", tie="hash"))


@query(f"WITH {O.BASKET}, {O.LENS} SELECT quantile_disc(len, [0.1, 0.5, 0.9])[1] AS p10, quantile_disc(len, [0.1, 0.5, 0.9])[2] AS p50, quantile_disc(len, [0.1, 0.5, 0.9])[3] AS p90, min(len) AS lo, max(len) AS hi FROM rl")
def length_quantiles(spark, sf):
    at = lambda q: F.expr(f"cast(percentile_disc({q}) WITHIN GROUP (ORDER BY len) AS BIGINT)")
    return _lens("row")(spark, sf).agg(at(0.1).alias("p10"), at(0.5).alias("p50"), at(0.9).alias("p90"), F.min("len").alias("lo"), F.max("len").alias("hi"))


# Orders


def _placed(axis, method, groups=P, n=1):
    return lambda spark, sf: permute.place(_ranked(axis)(spark, sf), method, groups, O.SEED, axis, n).select("trial", "id", "rank", "pos")


for _method, _name in (("interleave", "interleave"), ("mirror", "mirror"), ("mirror_alternate", "mirror_alt"), ("identity", "identity"), ("sorted", "sorted"), ("stratified", "stratified"), ("plain_shuffle", "plain")):
    for _axis in ("row", "col"):
        _a = _axis[0]
        query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed(_a, _method, P)} SELECT trial, id, rank, pos FROM {_a}p", f"{_name}_{_axis}s")(_placed(_axis, _method))


@query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)} SELECT id, (size + 1 - pos)::BIGINT AS pos FROM rp")
def reflect_rows(spark, sf):
    return permute.reflect(permute.interleave(_ranked("row")(spark, sf))).select("id", "pos")


EVEN = "SELECT ((pos - 1) * 8 // size)::INT AS rng, count(*) AS items, avg(len) AS mean_len, min(len) AS min_len, max(len) AS max_len, count(*) FILTER (WHERE rank * 2 <= size) AS long_items FROM rp GROUP BY 1"
for _method in ("interleave", "mirror", "stratified"):
    query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', _method, P)} {EVEN}", f"evenness_{_method}")(lambda spark, sf, m=_method: permute.evenness(permute.place(_ranked("row")(spark, sf), m, P, O.SEED), 8))


@query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)} SELECT id, pos, round(avg(len) OVER (ORDER BY pos ROWS BETWEEN 5 PRECEDING AND 5 FOLLOWING), 6) AS moving, len - lag(len) OVER (ORDER BY pos) AS step FROM rp")
def evenness_moving(spark, sf):
    return permute.moving(permute.interleave(_ranked("row")(spark, sf)), 5, slab=256)


# Cuts


def _rows_cut(rule):
    return lambda spark, sf: cut.cut(permute.interleave(_ranked("row")(spark, sf)), P, rule).select("id", "pos", "grp")


for _rule in cut.RULES:
    query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)}, {O.cut('r', P, _rule)} SELECT id, pos, grp FROM rg", f"cut_rows_{_rule}")(_rows_cut(_rule))

query(ORACLES["cut_rows_midpoint"], "cut_rows_histogram")(lambda spark, sf: cut.cut_by_histogram(_ranked("row")(spark, sf), P).select("id", "pos", "grp"))


@query(f"WITH RECURSIVE {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)}, {O.bottleneck(P)}")
def cut_rows_bottleneck(spark, sf):
    return cut.group_bounds(cut.cut_bottleneck(permute.interleave(_ranked("row")(spark, sf)), P))


@query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)}, {O.cut('r', P)} SELECT grp, min(pos) AS first_pos, max(pos) AS last_pos, count(*) AS items, sum(len)::BIGINT AS tokens FROM rg GROUP BY 1")
def group_bounds(spark, sf):
    return cut.group_bounds(cut.cut(permute.interleave(_ranked("row")(spark, sf)), P))


@query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)} SELECT id, pos, coalesce(sum(len) OVER (ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before FROM rp")
def prefix_tokens(spark, sf):
    return cut.prefix_tokens(permute.interleave(_ranked("row")(spark, sf)), slab=256).select("id", "pos", "before")


@query(f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)}, {O.cut('r', P)} SELECT id, pos, grp FROM rg")
def range_cut(spark, sf):
    """Groups again, by joining positions with the bounds of the groups (P rows)."""
    p = permute.interleave(_ranked("row")(spark, sf))
    bounds = cut.group_bounds(cut.cut(p, P)).select("grp", "first_pos", "last_pos")
    return p.join(F.broadcast(bounds), F.col("pos").between(F.col("first_pos"), F.col("last_pos"))).select("id", "pos", "grp")


# Costs


def _blocks(spark, sf, corpus=K.basket, method="interleave", groups=P, how=None, **kw):
    matrix = corpus(spark, sf)
    p = trials.partition(matrix, method, groups, O.SEED, **kw)
    return cost.block_costs(matrix, p.rows, p.cols, groups, how), p


BLOCKS = f"WITH {O.grouped(O.BASKET, 'interleave', P)}, {O.blocks(P)}"


@query(f"{BLOCKS} SELECT m, n, diag, cost FROM b")
def block_costs_interleave(spark, sf):
    return _blocks(spark, sf)[0]


for _how in ("merge", "shuffle_hash"):
    query(ORACLES["block_costs_interleave"], f"block_costs_{_how}")(lambda spark, sf, h=_how: _blocks(spark, sf, how=h)[0])


@query(f"{BLOCKS} SELECT diag, max(cost) AS cost FROM b GROUP BY 1")
def epoch_costs_interleave(spark, sf):
    return cost.epoch_costs(_blocks(spark, sf)[0])


for _method, _name in (("interleave", "interleave"), ("mirror", "mirror"), ("mirror_alternate", "mirror_alt"), ("stratified", "stratified"), ("plain_shuffle", "plain")):
    for _p in (2, 4, 10, 30):
        query(O.eta(O.BASKET, _method, _p), f"eta_{_name}_p{_p}")(lambda spark, sf, m=_method, p=_p: trials.eta_of(K.basket(spark, sf), m, p, seed=O.SEED))

for _corpus, _sql, _name in ((K.docs, O.DOCS, "docs"), (K.docs_pruned, O.PRUNED, "docs_pruned"), (K.basket_time, O.TIMES, "basket_time")):
    for _method in ("interleave", "mirror"):
        query(O.eta(_sql, _method, 10), f"eta_{_name}_{_method}_p10")(lambda spark, sf, c=_corpus, m=_method: trials.eta_of(c(spark, sf), m, 10))

query(O.eta(O.BASKET, "sorted", 10), "sorted_eta")(lambda spark, sf: trials.eta_of(K.basket(spark, sf), "sorted", 10))
query(O.eta(O.BASKET, "identity", 10), "identity_eta")(lambda spark, sf: trials.eta_of(K.basket(spark, sf), "identity", 10))
query(O.eta(O.BASKET, "interleave", 10, "start"), "eta_cut_start_p10")(lambda spark, sf: trials.eta_of(K.basket(spark, sf), "interleave", 10, rule="start"))
query(O.eta(O.BASKET, "interleave", 10, "count"), "eta_cut_count_p10")(lambda spark, sf: trials.eta_of(K.basket(spark, sf), "interleave", 10, rule="count"))

for _method, _name in (("stratified", "stratified"), ("plain_shuffle", "plain")):
    query(O.best(O.BASKET, _method, 10), f"{_name}_best")(lambda spark, sf, m=_method: trials.best_of(K.basket(spark, sf), m, 10, O.TRIALS, O.SEED))
    query(O.best(O.PRUNED, _method, 10), f"{_name}_best_docs_pruned")(lambda spark, sf, m=_method: trials.best_of(K.docs_pruned(spark, sf), m, 10, O.TRIALS, O.SEED))

TABLE = (("interleave", 1), ("mirror", 1), ("stratified", O.TRIALS), ("plain_shuffle", O.TRIALS))


def _table_sql(corpus, sizes):
    return " UNION ALL ".join(f"SELECT '{m}' AS method, {p} AS groups, {O.eta_value(corpus, m, p, t)} AS eta" for m, t in TABLE for p in sizes)


PUBLISHED = (1, 10, 30, 60)
#: The published table of the ratio by method and P, for each corpus; random methods take the best of five trials here, of 100 in ``bench.py --full``.
for _corpus, _sql, _name in (
    (lambda spark, sf: stored(K.basket(spark, sf), "basket"), O.BASKET, "balance_table"),
    (K.docs, O.DOCS, "balance_table_docs"),
    (K.docs_pruned, O.PRUNED, "balance_table_docs_pruned"),
    (lambda spark, sf: K.docs_stopped(spark, sf, STOP), O.STOPPED.replace("{0}", str(STOP)), "balance_table_docs_stopped"),
):
    query(_table_sql(_sql, PUBLISHED), _name)(lambda spark, sf, c=_corpus: trials.compare(c(spark, sf), tuple(m for m, _ in TABLE), PUBLISHED, O.TRIALS, O.SEED))


@query()
def balance_table_docs_stemmed(spark, sf):
    """The corpus without stop words and with stems: the two deterministic methods, which need one run."""
    return trials.compare(K.docs_stemmed(spark, sf), ("interleave", "mirror"), PUBLISHED, O.TRIALS, O.SEED)


@query(" UNION ALL ".join(f"SELECT '{m}' AS method, {p} AS groups, {O.eta_value(O.BASKET, m, p)} * {p} AS speedup" for m in ("interleave", "mirror") for p in (2, 4, 10)))
def speedup_table(spark, sf):
    return trials.compare(K.basket(spark, sf), ("interleave", "mirror"), (2, 4, 10)).select("method", "groups", (F.col("eta") * F.col("groups")).alias("speedup"))


@query(f"{BLOCKS} SELECT m, sum(mx - cost)::BIGINT AS idle FROM (SELECT m, cost, max(cost) OVER (PARTITION BY diag) AS mx FROM b) GROUP BY 1")
def idle_by_group(spark, sf):
    return cost.idle(_blocks(spark, sf)[0]).groupBy("m").agg(F.sum("idle").alias("idle"))


for _corpus, _sql, _name in ((K.basket, O.BASKET, "eta_ceiling"), (K.docs, O.DOCS, "eta_ceiling_docs")):
    query(
        f"WITH {_sql}, {O.LENS} SELECT tokens, longest_row, longest_col, least(1.0::DOUBLE, tokens::DOUBLE / 30 / greatest(longest_row, longest_col)) AS ceiling FROM (SELECT sum(len)::BIGINT AS tokens, max(len) AS longest_row FROM rl), (SELECT max(len) AS longest_col FROM cl)",
        _name,
    )(lambda spark, sf, c=_corpus: cost.eta_ceiling(_lens("row", c)(spark, sf), _lens("col", c)(spark, sf), 30))


@query(
    f"WITH {O.grouped(O.BASKET, 'interleave', P)}, a AS (SELECT grp, sum(len)::BIGINT AS s FROM rg GROUP BY 1), c AS (SELECT grp, sum(len)::BIGINT AS s FROM cg GROUP BY 1) "
    f"SELECT tokens, row_max, col_max, tokens::DOUBLE / {P} / greatest(row_max, col_max) AS ceiling FROM (SELECT sum(s)::BIGINT AS tokens, max(s) AS row_max FROM a), (SELECT max(s) AS col_max FROM c)"
)
def group_ceiling(spark, sf):
    p = _blocks(spark, sf)[1]
    return cost.group_ceiling(p.rows, p.cols, P)


@query(
    f"WITH {O.grouped(O.BASKET, 'interleave', 10)}, s AS (SELECT g.grp, coalesce(sum(len), 0)::BIGINT AS s FROM (SELECT unnest(range(10))::INT AS grp) g LEFT JOIN rg USING (grp) GROUP BY 1) "
    "SELECT min(s) AS min_tokens, max(s) AS max_tokens, avg(s) AS mean_tokens, round(stddev_pop(s), 6) AS sd_tokens, count(*) FILTER (WHERE s = 0) AS empty FROM s"
)
def group_skew_interleave(spark, sf):
    return cost.group_skew(trials.partition(K.basket(spark, sf), "interleave", 10).rows, 10)


@query()
def advise_docs(spark, sf):
    return trials.advise(K.docs_pruned(spark, sf), 10, 0.95, 20)


@query(
    f"WITH {O.BASKET}, d AS (SELECT count(DISTINCT row_id) * 2048 AS theta, count(DISTINCT col_id) * 2048 AS phi FROM r) "
    f"SELECT p::INT AS groups, (theta + phi)::BIGINT AS diagonal_bytes, (theta + p * phi)::BIGINT AS replica_bytes, p::INT AS diagonal_barriers, 1 AS replica_barriers FROM d, (SELECT unnest({list(SIZES)}) AS p)"
)
def memory_and_barriers(spark, sf):
    """What counts of 256 topics take for the customers and parts of the given tables."""
    lines = table(spark, sf, "lineitem").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    documents, words = (lines.select(c).dropna().distinct().count() for c in ("o_custkey", "l_partkey"))
    rows = [(p, *cost.memory_model(documents, words, 256, p).values(), *cost.barriers(p).values()) for p in SIZES]
    return spark.createDataFrame(rows, "groups int, diagonal_bytes bigint, replica_bytes bigint, diagonal_barriers int, replica_barriers int")


# The stamped corpus


SHARED = f"{O.grouped(O.BASKET, 'interleave', P)}, {PROPORTIONAL}, r2 AS (SELECT row_id, s AS col_id, k AS n FROM k WHERE k > 0)"


def _stamp_cols(sql):
    """The stamps' columns ranked, placed and cut on their own, rows as given."""
    return (
        sql + ", l2 AS (SELECT col_id AS id, sum(n)::BIGINT AS len FROM r2 GROUP BY 1), k2 AS (SELECT id, len, row_number() OVER (ORDER BY len DESC, id) AS rank, count(*) OVER () AS size, (sum(len) OVER ())::BIGINT AS total FROM l2), "
        "p2 AS (SELECT *, row_number() OVER (ORDER BY least(rank, size + 1 - rank), rank) AS pos FROM k2), "
        f"c2 AS (SELECT id, least({P - 1}, (2 * coalesce(sum(len) OVER (ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT + len) * {P} // (2 * total))::INT AS grp FROM p2), "
        f"b AS (SELECT i.m, j.n, ((j.n - i.m + {P}) % {P})::INT AS diag, coalesce(sum(x.n), 0)::BIGINT AS cost FROM (SELECT unnest(range({P}))::INT AS m) i CROSS JOIN (SELECT unnest(range({P}))::INT AS n) j "
        "LEFT JOIN (SELECT rg.grp AS m, c2.grp AS g, r2.n FROM r2 JOIN rg ON rg.id = r2.row_id JOIN c2 ON c2.id = r2.col_id) x ON x.m = i.m AND x.g = j.n GROUP BY 1, 2, 3)"
    )


@query(f"WITH {_stamp_cols(SHARED)} {O.ETA.format(p=P)}")
def shared_rows_eta(spark, sf):
    """Stamps on the words' row groups, only their columns cut anew."""
    words = trials.partition(K.basket(spark, sf), "interleave", P)
    s = K.stamp_matrix(spark, sf)
    own = trials.partition(s, "interleave", P)
    return cost.eta(cost.block_costs(s, words.rows, own.cols, P), P)


INDEPENDENT = f"{PROPORTIONAL}, r AS (SELECT row_id, s AS col_id, k AS n FROM k WHERE k > 0)"
query(O.eta(INDEPENDENT, "interleave", P), "independent_stamps_eta")(lambda spark, sf: trials.eta_of(K.stamp_matrix(spark, sf), "interleave", P))
query(O.eta(MERGED.replace(", kind", ""), "interleave", P), "merged_eta")(lambda spark, sf: trials.eta_of(_merged(spark, sf).drop("kind"), "interleave", P))
for _method, _name in (("stratified", "stratified"), ("plain_shuffle", "plain")):
    query(O.best(O.TIMES, _method, 10), f"{_name}_best_basket_time")(lambda spark, sf, m=_method: trials.best_of(K.basket_time(spark, sf), m, 10, O.TRIALS, O.SEED))


#: The published numbers of trials: 100 for documents by words, 200 for documents by timestamps.
query(O.best(O.BASKET, "stratified", 10, 100), "stratified_best_of_100")(lambda spark, sf: trials.best_of(stored(K.basket(spark, sf), "basket"), "stratified", 10, 100, O.SEED))
query(O.best(O.TIMES, "stratified", 10, 200), "stratified_best_of_200_basket_time")(lambda spark, sf: trials.best_of(stored(K.basket_time(spark, sf), "times"), "stratified", 10, 200, O.SEED))
for _method in ("interleave", "mirror"):
    query(O.eta(O.YEARS, _method, 10), f"eta_order_years_{_method}_p10")(lambda spark, sf, m=_method: trials.eta_of(K.order_years(spark, sf), m, 10))
    query(O.eta(O.ORDERS, _method, 10), f"eta_order_basket_{_method}_p10")(lambda spark, sf, m=_method: trials.eta_of(K.order_basket(spark, sf), m, 10))
query(O.best(O.YEARS, "stratified", 10), "stratified_best_order_years")(lambda spark, sf: trials.best_of(K.order_years(spark, sf), "stratified", 10, O.TRIALS, O.SEED))


# Samplers, counts and quality


T, ALPHA, BETA, GAMMA = O.TOPICS, O.ALPHA, O.BETA, O.GAMMA
Z = f"WITH {O.LINES}, {O.topics()}"


def _lines(spark, sf):
    return K.basket(spark, sf, weight=None)


def _first(spark, sf):
    return C.init_topics(_lines(spark, sf), T, O.SEED)


def _array_rows(df: DataFrame, by: str) -> DataFrame:
    return df.select(by, F.posexplode("c").alias("k", "c")).select(by, "k", "c")


@query(f"{Z} SELECT k, count(*) AS c FROM z GROUP BY 1")
def init_topic_counts(spark, sf):
    return _first(spark, sf).select(F.explode("z").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("c"))


@query(f"{Z} SELECT row_id, k, c FROM {O.dense('row_id')}")
def theta_counts0(spark, sf):
    return _array_rows(C.topic_counts(_first(spark, sf), "row_id", T), "row_id")


@query(f"{Z} SELECT col_id, k, c FROM {O.dense('col_id')}")
def phi_counts0(spark, sf):
    return _array_rows(C.topic_counts(_first(spark, sf), "col_id", T), "col_id")


ZS = f"WITH {INDEPENDENT}, {O.topics('stamp')}"


def _first_stamps(spark, sf):
    return C.init_topics(K.stamp_matrix(spark, sf), T, O.SEED, "stamp")


@query(f"{ZS} SELECT col_id, k, c FROM {O.dense('col_id')}")
def pi_counts0(spark, sf):
    return _array_rows(C.topic_counts(_first_stamps(spark, sf), "col_id", T), "col_id")


@query(f"{Z} SELECT row_id, map_from_entries(list((k, c) ORDER BY k))::VARCHAR AS c FROM (SELECT row_id, k, count(*) AS c FROM z GROUP BY 1, 2) GROUP BY 1")
def sparse_counts(spark, sf):
    entries = F.transform(F.map_entries("c"), lambda e: F.concat_ws("=", e.key.cast("string"), e.value.cast("string")))
    return C.sparse_counts(_first(spark, sf), "row_id").select("row_id", F.concat(F.lit("{"), F.concat_ws(", ", entries), F.lit("}")).alias("c"))


THETA = f"th AS (SELECT row_id, k, (c + {ALPHA}) / (sum(c) OVER (PARTITION BY row_id) + {T} * {ALPHA}) AS p FROM {O.dense('row_id')})"
PHI = f"ph AS (SELECT col_id, k, (c + {BETA}) / (sum(c) OVER (PARTITION BY k) + (SELECT count(DISTINCT col_id) FROM z) * {BETA}) AS p FROM {O.dense('col_id')})"
PI = PHI.replace(str(BETA), str(GAMMA))


def _theta0(spark, sf):
    return C.theta(C.topic_counts(_first(spark, sf), "row_id", T), T, ALPHA)


def _phi_of(assigned, prior):
    c = C.topic_counts(assigned, "col_id", T)
    return C.phi(c, C.topic_totals(c, T), c.count(), prior)


def _long(df, by):
    return df.select(by, F.posexplode("p").alias("k", "p")).select(by, "k", F.round("p", 9).alias("p"))


query(f"{Z}, {THETA} SELECT row_id, k, round(p, 9) AS p FROM th", "theta0")(lambda spark, sf: _long(_theta0(spark, sf), "row_id"))
query(f"{Z}, {PHI} SELECT col_id, k, round(p, 9) AS p FROM ph", "phi0")(lambda spark, sf: _long(_phi_of(_first(spark, sf), BETA), "col_id"))
query(f"{ZS}, {PI} SELECT col_id, k, round(p, 9) AS p FROM ph", "pi0")(lambda spark, sf: _long(_phi_of(_first_stamps(spark, sf), GAMMA), "col_id"))


@query(f"{Z}, {THETA}, {PHI} SELECT sum(n)::BIGINT AS tokens, round(exp(-sum(n * ln(l)) / sum(n)), 6) AS perplexity FROM (SELECT r.row_id, r.col_id, r.n, sum(th.p * ph.p) AS l FROM r JOIN th ON th.row_id = r.row_id JOIN ph ON ph.col_id = r.col_id AND ph.k = th.k GROUP BY 1, 2, 3)")
def perplexity_init(spark, sf):
    return C.perplexity(_lines(spark, sf), _theta0(spark, sf), _phi_of(_first(spark, sf), BETA)).select("tokens", F.round("perplexity", 6).alias("perplexity"))


@query(f"WITH {O.LINES}, w AS (SELECT col_id, sum(n) AS c FROM r GROUP BY 1) SELECT sum(c)::BIGINT AS tokens, round(exp(-sum(c * ln((c + {BETA}) / ((SELECT sum(n) FROM r) + (SELECT count(*) FROM w) * {BETA}))) / sum(c)), 6) AS perplexity FROM w")
def perplexity_k1(spark, sf):
    """With one topic the model is the smoothed unigram."""
    m = _lines(spark, sf)
    z = C.init_topics(m, 1, O.SEED)
    out = C.model_perplexity(m, C.topic_counts(z, "row_id", 1), C.topic_counts(z, "col_id", 1), 1, ALPHA, BETA)
    return out.select("tokens", F.round("perplexity", 6).alias("perplexity"))


@query(f"{Z}, {PHI} SELECT k AS topic, rank::INT AS rank, col_id AS id, round(p, 9) AS p FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY p DESC, col_id) AS rank FROM ph) WHERE rank <= 10")
def top_words0(spark, sf):
    return C.top_words(_phi_of(_first(spark, sf), BETA), 10)


@query(f"{ZS}, {PI} SELECT col_id AS stamp, k AS topic, round(p, 9) AS p FROM ph")
def topic_timeline0(spark, sf):
    return C.topic_timeline(_phi_of(_first_stamps(spark, sf), GAMMA)).select("stamp", "topic", F.round("p", 9).alias("p"))


@query(f"{Z}, {THETA} SELECT row_id, k AS topic, round(p, 9) AS p FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY p DESC, k) AS a FROM th) WHERE a = 1")
def dominant_topic0(spark, sf):
    return C.dominant_topic(_theta0(spark, sf)).select("row_id", "topic", F.round("p", 9).alias("p"))


FROZEN = (
    f"{Z}, t AS (SELECT row_id, list(c ORDER BY k) AS t FROM {O.dense('row_id')} GROUP BY 1), p AS (SELECT col_id, list(c ORDER BY k) AS p FROM {O.dense('col_id')} GROUP BY 1), s AS (SELECT list(c ORDER BY k) AS s FROM (SELECT k, count(*) AS c FROM z GROUP BY 1)), w AS (SELECT count(*) AS w FROM p), "
    f"g AS (SELECT z.row_id, z.col_id, z.i, x.k, round((t[x.k + 1] - (x.k = z.k)::INT + {ALPHA}) * (p[x.k + 1] - (x.k = z.k)::INT + {BETA}) / (s[x.k + 1] - (x.k = z.k)::INT + w * {BETA}), 9) AS wt "
    f"FROM z JOIN t USING (row_id) JOIN p USING (col_id), s, w, (SELECT unnest(range({T}))::INT AS k) x), "
    "c AS (SELECT *, sum(wt) OVER (PARTITION BY row_id, col_id, i ORDER BY k) AS run, sum(wt) OVER (PARTITION BY row_id, col_id, i) AS mass FROM g) "
    f"SELECT row_id, col_id, (i - 1)::INT AS i, least({T - 1}, count(*) FILTER (WHERE run <= {O.key('word', 'frozen', chr(39) + '0' + chr(39), 'row_id || ' + chr(39) + '/' + chr(39) + ' || col_id || ' + chr(39) + '/' + chr(39) + ' || (i - 1)')}::DOUBLE / 281474976710656 * mass))::INT AS z FROM c GROUP BY 1, 2, 3"
)


@query(FROZEN)
def frozen_sweep(spark, sf):
    return S.frozen_sweep(_first(spark, sf), T, ALPHA, BETA, O.SEED)


def _history(spark, fit: S.Fit) -> DataFrame:
    return spark.createDataFrame([(k, round(p, 6)) for k, p in enumerate(fit.history)], "iteration int, perplexity double")


PRIORS = S.Priors(8, ALPHA, BETA, GAMMA)


@query()
def serial_lda(spark, sf):
    return _history(spark, S.fit_serial(stored(_lines(spark, sf), "lines"), PRIORS))


@query()
def diagonal_lda(spark, sf):
    m = _lines(spark, sf)
    p = trials.partition(m, "mirror", 2)
    return _history(spark, S.fit_diagonal(m, p.rows, p.cols, 2, PRIORS, 2))


@query()
def replica_lda(spark, sf):
    m = _lines(spark, sf)
    return _history(spark, S.fit_replica(m, trials.partition(m, "mirror", 2).rows, 2, PRIORS, 2))


@query()
def serial_stamped(spark, sf):
    return _history(spark, S.fit_serial_stamped(stored(_lines(spark, sf), "lines"), stored(K.stamp_matrix(spark, sf), "stamps"), PRIORS, 1))


def _stamped(layout):
    def f(spark, sf):
        m, s = _lines(spark, sf), K.stamp_matrix(spark, sf)
        a, b = trials.partition(m, "mirror", 2), trials.partition(s, "mirror", 2)
        return _history(spark, S.fit_diagonal_stamped(m, s, (a.rows, a.cols), (b.rows, b.cols), 2, PRIORS, 1, layout=layout))

    return f


query(name="diagonal_stamped")(_stamped("independent"))
query(name="diagonal_stamped_shared_rows")(_stamped("shared_rows"))
query(name="diagonal_stamped_merged")(_stamped("merged"))


def _quality(spark, sf, iterations):
    """Serial against diagonal at the published P and below, three seeds, the stamped model of customers, parts and months."""
    seeds = (1, 2, 3)
    settings = [Setting("serial", 1, s, kernel="loop") for s in seeds] + [Setting("diagonal", p, s) for p in (1, 2, 4, 10, 30) for s in seeds]
    return fits(stored(_lines(spark, sf), "lines"), stored(K.stamp_matrix(spark, sf), "stamps"), settings, PRIORS, iterations, wanted=(iterations,))


@query()
def quality_table(spark, sf):
    """Mean perplexity over the seeds after equal iterations, and how far it is from that of the serial sampler."""
    end = _quality(spark, sf, 8).groupBy("sampler", "groups").agg(F.avg("perplexity").alias("p"), F.min("perplexity").alias("lo"), F.max("perplexity").alias("hi"))
    serial = end.filter("sampler = 'serial'").select(F.col("p").alias("s"))
    gap = F.round(F.col("p") / F.col("s") - 1, 6).alias("gap")
    return end.crossJoin(F.broadcast(serial)).select("sampler", "groups", F.round("p", 4).alias("perplexity"), F.round("lo", 4).alias("lowest"), F.round("hi", 4).alias("highest"), gap)


@query(f"WITH {O.LINES} SELECT s.sampler, s.p::INT AS groups, k::INT AS seed, (SELECT sum(n) FROM r)::BIGINT AS tokens FROM (VALUES ('serial', 1), ('diagonal', 1), ('diagonal', 2), ('diagonal', 4), ('diagonal', 10), ('diagonal', 30)) s(sampler, p), (SELECT unnest([1, 2, 3]) AS k)")
def quality_tokens(spark, sf):
    """Whatever the sampler, no token is lost: the word counts of each fit add up to the corpus."""
    return _quality(spark, sf, 1).select("sampler", "groups", "seed", "tokens")


@query()
def quality_table_docs(spark, sf):
    """The plain model on documents: serial, diagonal and replicating, equal iterations."""
    settings = [Setting("serial", 1, 7, kernel="loop"), *(Setting(s, p, 7) for s in ("diagonal", "replica") for p in (4, 10))]
    return fits(K.docs_pruned(spark, sf), None, settings, PRIORS, 4).select("sampler", "groups", "iteration", F.round("perplexity", 4).alias("perplexity"), "tokens")


def _fitted(spark, sf):
    """The stamped model fitted on the grid, words and stamps on shared rows."""
    m, s = stored(_lines(spark, sf), "lines"), stored(K.stamp_matrix(spark, sf), "stamps")
    a, b = trials.partition(m, "mirror", 2), trials.partition(s, "mirror", 2)
    return S.fit_diagonal_stamped(m, s, (a.rows, a.cols), (b.rows, b.cols), 2, PRIORS, 3, layout="shared_rows", track=False)


@query()
def fitted_top_words(spark, sf):
    fit = _fitted(spark, sf)
    return C.top_words(C.phi(fit.phi, C.topic_totals(fit.phi, 8), fit.phi.count(), BETA), 10)


@query()
def fitted_timeline(spark, sf):
    """How each topic of the fitted model is spread over the months."""
    fit = _fitted(spark, sf)
    return C.topic_timeline(C.phi(fit.pi, C.topic_totals(fit.pi, 8), fit.pi.count(), GAMMA)).select("stamp", "topic", F.round("p", 9).alias("p"))


@query(f"WITH {O.LINES}, {PROPORTIONAL} SELECT (SELECT sum(n) FROM r)::BIGINT AS words, (SELECT sum(k) FROM k)::BIGINT AS stamps, (SELECT sum(n) FROM r)::BIGINT + (SELECT sum(k) FROM k)::BIGINT AS document_tokens")
def fitted_totals(spark, sf):
    """What the counts of a fitted model add up to: words, stamps, and both together for documents."""
    fit = _fitted(spark, sf)
    total = lambda df, name: df.agg(F.sum(F.aggregate("c", F.lit(0).cast("bigint"), lambda a, x: a + x)).alias(name))
    return total(fit.phi, "words").crossJoin(total(fit.pi, "stamps")).crossJoin(total(fit.theta, "document_tokens"))  # one row each


# The relational surface around the methods


@query(f"WITH {O.VOCAB} SELECT count(*) AS cells, sum(n)::BIGINT AS tokens FROM wc WHERE word IN (SELECT word FROM v WHERE df >= 5)")
def semi_vocab(spark, sf):
    c = K.doc_counts(spark, sf)
    return c.join(tokens.vocabulary(c, 5).select("word"), "word", "left_semi").agg(F.count(F.lit(1)).alias("cells"), F.sum("n").alias("tokens"))


@query(f"WITH {O.VOCAB} SELECT count(*) AS cells, sum(n)::BIGINT AS tokens FROM wc WHERE word NOT IN (SELECT word FROM v WHERE df >= 5)")
def anti_vocab(spark, sf):
    c = K.doc_counts(spark, sf)
    return c.join(tokens.vocabulary(c, 5).select("word"), "word", "left_anti").agg(F.count(F.lit(1)).alias("cells"), F.sum("n").alias("tokens"))


@query(f"WITH {O.BASKET} SELECT p_partkey AS id, coalesce(sum(n), 0)::BIGINT AS len FROM part LEFT JOIN r ON r.col_id = p_partkey GROUP BY 1 HAVING coalesce(sum(n), 0) < 300")
def zero_columns(spark, sf):
    lens = _lens("col")(spark, sf)
    parts = table(spark, sf, "part").select(F.col("p_partkey").alias("id"))
    return parts.join(lens, "id", "left").select("id", F.coalesce("len", F.lit(0)).alias("len")).filter("len < 300")


@query(
    f"WITH {O.BASKET}, {O.RANKS}, {O.placed('r', 'interleave', P)}, {O.cut('r', P)}, a AS (SELECT id, grp FROM rg WHERE grp < 3), {O.placed('c', 'mirror', P).replace('cp AS', 'mp AS').replace('FROM cr', 'FROM rr')}, {O.cut('m', P)}, b AS (SELECT id, grp FROM mg WHERE grp > 0) "
    "SELECT coalesce(a.id, b.id) AS id, a.grp AS first_grp, b.grp AS second_grp FROM a FULL JOIN b ON a.id = b.id WHERE a.grp IS DISTINCT FROM b.grp"
)
def grouping_diff(spark, sf):
    r = _ranked("row")(spark, sf)
    a = cut.cut(permute.interleave(r), P).filter("grp < 3").select("id", F.col("grp").alias("first_grp"))
    b = cut.cut(permute.mirror(r), P).filter("grp > 0").select("id", F.col("grp").alias("second_grp"))
    return a.join(b, "id", "full").filter(~F.col("first_grp").eqNullSafe(F.col("second_grp")))


@query("SELECT event_id, any_value(user_id) AS user_id, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS o_orderkey FROM events LEFT JOIN orders ON o_custkey = user_id AND o_orderdate <= ts WHERE user_id IS NOT NULL GROUP BY event_id")
def asof_stamp(spark, sf):
    """Each event with its user's last order at or before it, ties to the larger key, by a union and a running last value."""
    none = F.lit(None).cast("bigint")
    e = table(spark, sf, "events").filter("user_id IS NOT NULL").select("user_id", F.col("ts").alias("at"), "event_id", none.alias("o_orderkey"))
    o = table(spark, sf, "orders").select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("at"), none.alias("event_id"), "o_orderkey")
    w = Window.partitionBy("user_id").orderBy("at", F.col("event_id").asc_nulls_first(), "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    both = e.unionByName(o).withColumn("last", F.last("o_orderkey", ignorenulls=True).over(w))
    return both.filter("event_id IS NOT NULL").select("event_id", "user_id", F.col("last").alias("o_orderkey"))


@query("SELECT o_custkey AS row_id, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey AND l_shipdate >= o_orderdate AND l_shipdate < o_orderdate + INTERVAL 30 DAY GROUP BY 1")
def interval_ship(spark, sf):
    o, li = table(spark, sf, "orders"), table(spark, sf, "lineitem")
    near = (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") >= F.col("o_orderdate")) & (F.col("l_shipdate") < F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS"))
    return o.join(li, near).groupBy(F.col("o_custkey").alias("row_id")).agg(F.count(F.lit(1)).alias("n"))


@query(f"{BLOCKS} SELECT m, n, sum(cost)::BIGINT AS cost FROM b GROUP BY CUBE (m, n)")
def block_cube(spark, sf):
    return _blocks(spark, sf)[0].cube("m", "n").agg(F.sum("cost").alias("cost"))


@query(f"{BLOCKS} SELECT diag, m, sum(cost)::BIGINT AS cost FROM b GROUP BY ROLLUP (diag, m)")
def block_rollup(spark, sf):
    return _blocks(spark, sf)[0].rollup("diag", "m").agg(F.sum("cost").alias("cost"))


@query(f"{BLOCKS} SELECT m, " + ", ".join(f"sum(cost) FILTER (WHERE n = {j})::BIGINT AS n{j}" for j in range(P)) + " FROM b GROUP BY 1")
def block_grid(spark, sf):
    grid = _blocks(spark, sf)[0].groupBy("m").pivot("n", list(range(P))).agg(F.sum("cost"))
    return grid.select("m", *(F.col(str(j)).alias(f"n{j}") for j in range(P)))


@query(f"WITH {O.BASKET}, {O.LENS} SELECT id, dense_rank() OVER (ORDER BY len DESC)::INT AS dense, ntile(7) OVER (ORDER BY len DESC, id)::INT AS tile, round(percent_rank() OVER (ORDER BY len DESC), 9) AS share FROM cl")
def rank_functions(spark, sf):
    """From ranks and one row a distinct length, so no window runs over all items."""
    ranked = _ranked("col")(spark, sf)
    first = ranked.groupBy("len").agg(F.min("rank").alias("first"))
    first = first.withColumn("dense", F.row_number().over(Window.orderBy(F.desc("len"))))
    wide, rest = F.floor(F.col("size") / 7), F.col("size") % 7  # the first tiles have one more
    tile = F.when(F.col("rank") <= rest * (wide + 1), F.ceil(F.col("rank") / (wide + 1))).otherwise(rest + F.ceil((F.col("rank") - rest * (wide + 1)) / wide))
    share = F.round((F.col("first") - 1) / (F.col("size") - 1), 9)
    return ranked.join(first, "len").select("id", "dense", tile.cast("int").alias("tile"), share.alias("share"))


HALVES = f"WITH {O.TOKENS}, a AS (SELECT word FROM tok WHERE row_id % 2 = 0), b AS (SELECT word FROM tok WHERE row_id % 2 = 1)"
for _op, _sql in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):

    def _sets(spark, sf, op=_op):
        t = tokens.tokens(table(spark, sf, "documents"))
        a, b = t.filter("row_id % 2 = 0").select("word"), t.filter("row_id % 2 = 1").select("word")
        return {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.subtract(b)}[op]

    query(f"{HALVES} SELECT word FROM a {_sql} SELECT word FROM b", f"vocab_{_op}")(_sets)


@query(f"SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, {M}::INT AS m, date_diff('day', DATE '1970-01-01', o_orderdate::DATE)::INT AS d, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first_day FROM orders")
def date_functions(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", stamps.stamp_number(d, "year").alias("y"), F.quarter(d).alias("q"), stamps.stamp_number(d, "month").alias("m"), stamps.stamp_number(d, "day").alias("d"), F.date_format(F.trunc(d.cast("date"), "month"), "yyyy-MM-dd").alias("first_day"))


@query(f"WITH {PROPORTIONAL}, a AS (SELECT row_id, list(s ORDER BY s) AS l FROM (SELECT row_id, s, unnest(range(k)) FROM k) GROUP BY 1) SELECT row_id, len(l)::INT AS slots, l[1]::INT AS first, l[-1]::INT AS last, len(list_distinct(l))::INT AS kinds, list_sum(l[1:4])::BIGINT AS early FROM a")
def array_functions(spark, sf):
    s = F.col("stamps")
    total = F.aggregate(F.slice(s, 1, 4), F.lit(0).cast("bigint"), lambda a, x: a + x)
    return K.customer_stamps(spark, sf).select("row_id", F.size(s).alias("slots"), F.element_at(s, 1).alias("first"), F.element_at(s, -1).alias("last"), F.size(F.array_distinct(s)).alias("kinds"), total.alias("early"))


@query("SELECT event_type, json_extract_string(props, '$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1, 2")
def json_props(spark, sf):
    return table(spark, sf, "events").groupBy("event_type", F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("n"))


SAMPLE = f"f AS ({O.BASKET[6:-1]}), r AS (SELECT * FROM f WHERE {O.key('row', 'sample', chr(39) + '0' + chr(39), 'row_id')} % 4 = 0)"


@query(O.eta(SAMPLE, "interleave", P))
def eta_sample(spark, sf):
    """The same measure on a quarter of the rows, chosen by hash: a cheap look before trials."""
    m = K.basket(spark, sf)
    return trials.eta_of(m.filter(key(O.SEED, "row", "sample", 0, F.col("row_id")) % 4 == 0), "interleave", P)


REDEAL = "(SELECT {0}_id, row_number() OVER (ORDER BY {1}, row_id || '/' || col_id || '/' || i) AS spot FROM tk)"
REDEALT = (
    O.LINES.replace("r AS", "f AS", 1) + ", tk AS (SELECT row_id, col_id, unnest(range(1, n + 1)) AS i FROM f), r AS (SELECT row_id, col_id, count(*) AS n FROM "
    + " JOIN ".join(REDEAL.format(a, O.key(a, "redeal", "'0'", "row_id || '/' || col_id || '/' || i")) for a in ("row", "col")) + " USING (spot) GROUP BY 1, 2)"
)


@query(O.eta(REDEALT, "interleave", 10))
def decorrelated_eta(spark, sf):
    """An ablation: lengths kept, who uses what redealt."""
    return trials.eta_of(stored(workload.decorrelated(_lines(spark, sf), O.SEED), "redealt"), "interleave", 10)


# Streams, as batches


def _events(spark, sf):
    return table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).filter("user_id IS NOT NULL")


query("SELECT user_id AS row_id, event_type AS col, count(*) AS n FROM events WHERE user_id IS NOT NULL GROUP BY 1, 2", "online_workload")(lambda spark, sf: online.online_workload(_events(spark, sf)))
query("SELECT user_id AS row_id, epoch(date_trunc('day', ts))::BIGINT AS stamp, count(*) AS n FROM events WHERE user_id IS NOT NULL GROUP BY 1, 2", "tumbling_stamps")(lambda spark, sf: online.window_stamps(_events(spark, sf), "1 day"))
query(
    "SELECT user_id AS row_id, (epoch(ts)::BIGINT // 21600 - i) * 21600 AS stamp, count(*) AS n FROM (SELECT user_id, date_trunc('second', ts) AS ts FROM events WHERE user_id IS NOT NULL), (SELECT unnest(range(4)) AS i) GROUP BY 1, 2",
    "sliding_stamps",
)(lambda spark, sf: online.window_stamps(_events(spark, sf), "1 day", "6 hours"))
query(
    "WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events WHERE user_id IS NOT NULL WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
    "s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id AS row_id, floor(epoch(min(ts)))::BIGINT AS stamp, count(*) AS n FROM s GROUP BY user_id, k",
    "session_stamps",
)(lambda spark, sf: online.session_stamps(_events(spark, sf), "6 hours"))


@query("SELECT count(DISTINCT event_id) AS n FROM events WHERE user_id IS NOT NULL")
def events_without_repeats(spark, sf):
    e = _events(spark, sf)
    return online.without_repeats(e.unionByName(e)).agg(F.count(F.lit(1)).alias("n"))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """tokens, total cost, optimum, eta and speedup of the interleaved 4 x 4 grid of the basket corpus."""
    return QUERIES["eta_interleave_p4"](spark, sf)
