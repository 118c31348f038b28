"""DuckDB SQL for the queries, written from the definitions and not from the engine."""

from __future__ import annotations

SEED = 7
TRIALS = 5

BASKET = "r AS (SELECT o_custkey AS row_id, l_partkey AS col_id, sum(l_quantity::BIGINT)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)"
LINES = BASKET.replace("sum(l_quantity::BIGINT)::BIGINT", "count(*)")
TOKENS = r"tok AS (SELECT doc_id AS row_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM documents)"
COUNTS = TOKENS + ", wc AS (SELECT row_id, word, count(*) AS n FROM tok GROUP BY 1, 2)"
VOCAB = COUNTS + ", v AS (SELECT row_number() OVER (ORDER BY word) AS word_id, word, count(*) AS df, sum(n)::BIGINT AS cf FROM wc GROUP BY word)"
DOCS = VOCAB + ", r AS (SELECT row_id, word_id AS col_id, n FROM wc JOIN v USING (word))"
PRUNED = COUNTS + ", v AS (SELECT row_number() OVER (ORDER BY word) AS word_id, word FROM wc GROUP BY word HAVING count(*) >= 2 AND count(*) <= 0.1 * (SELECT count(*) FROM documents)), r AS (SELECT row_id, word_id AS col_id, n FROM wc JOIN v USING (word))"
MONTHS = "((year({0}) - 1970) * 12 + month({0}) - 1)::BIGINT"
TIMES = f"r AS (SELECT o_custkey AS row_id, {MONTHS.format('o_orderdate')} AS col_id, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)"
LENS = "rl AS (SELECT row_id AS id, sum(n)::BIGINT AS len FROM r GROUP BY 1), cl AS (SELECT col_id AS id, sum(n)::BIGINT AS len FROM r GROUP BY 1)"
RANKS = LENS + ", " + ", ".join(f"{a}r AS (SELECT id, len, row_number() OVER (ORDER BY len DESC, id) AS rank, count(*) OVER () AS size, (sum(len) OVER ())::BIGINT AS total FROM {a}l)" for a in "rc")
AXES = {"r": "row", "c": "col"}


STOPPED = COUNTS.replace("SELECT row_id, word, count(*) AS n FROM tok GROUP", "SELECT row_id, word, count(*) AS n FROM tok WHERE word NOT IN {0} GROUP") + ", v AS (SELECT row_number() OVER (ORDER BY word) AS word_id, word FROM wc GROUP BY word), r AS (SELECT row_id, word_id AS col_id, n FROM wc JOIN v USING (word))"
YEARS = "r AS (SELECT o_orderkey AS row_id, year(o_orderdate)::BIGINT AS col_id, 16::BIGINT AS n FROM orders)"
ORDERS = "r AS (SELECT l_orderkey AS row_id, l_partkey AS col_id, sum(l_quantity::BIGINT)::BIGINT AS n FROM lineitem GROUP BY 1, 2)"


def bottleneck(groups: int) -> str:
    """Group bounds of the least possible maximum: the maximum by bisection, each step filling all groups from the left."""
    fill = "0::BIGINT"
    for _ in range(groups):
        fill = f"(SELECT coalesce(max(e), 0) FROM pre WHERE e <= {fill} + mid)"
    cuts, at = [], "0::BIGINT"
    for _ in range(groups):
        at = f"(SELECT max(e) FROM pre WHERE e <= {at} + (SELECT hi FROM m))"
        cuts.append(at)
    grp = " + ".join(f"(e > {c})::INT" for c in cuts[:-1])
    return (
        "pre AS (SELECT pos, len, (sum(len) OVER (ORDER BY pos))::BIGINT AS e FROM rp), "
        "s AS (SELECT 0 AS k, max(len)::BIGINT - 1 AS lo, sum(len)::BIGINT AS hi FROM rp UNION ALL "
        f"SELECT k + 1, CASE WHEN ok THEN lo ELSE mid END, CASE WHEN ok THEN mid ELSE hi END FROM (SELECT k, lo, hi, mid, {fill} >= (SELECT max(e) FROM pre) AS ok FROM (SELECT *, (lo + hi) // 2 AS mid FROM s WHERE hi - lo > 1))), "
        "m AS (SELECT hi FROM s ORDER BY k DESC LIMIT 1) "
        f"SELECT grp, min(pos) AS first_pos, max(pos) AS last_pos, count(*) AS items, sum(len)::BIGINT AS tokens FROM (SELECT pos, len, ({grp})::INT AS grp FROM pre) GROUP BY 1"
    )


def key(axis: str, stage: str, trial: str, id_: str = "id") -> str:
    return f"('0x' || substr(md5('{SEED}:' || {trial} || ':{axis}:{stage}:' || {id_}), 1, 12))::BIGINT"


def placed(axis: str, method: str, groups: int, trials: int = 1) -> str:
    """CTE {axis}p: trial, id, len, rank, size, total, pos."""
    name, src = f"{axis}p", f"{axis}r"
    q = "(size + 1 - rank)"
    fixed = {
        "interleave": f"row_number() OVER (ORDER BY least(rank, {q}), rank)",
        "mirror": f"CASE WHEN least(rank, {q}) % 2 = 0 AND 2 * least(rank, {q}) < size THEN {q} ELSE rank END",
        "mirror_alternate": f"CASE WHEN least(rank, {q}) % 2 = 1 THEN least(rank, {q}) + (rank > {q})::INT ELSE size + 2 - least(rank, {q}) - (rank > {q})::INT END",
        "sorted": "rank",
        "identity": "row_number() OVER (ORDER BY id)",
    }
    if method in fixed:
        return f"{name} AS (SELECT 0 AS trial, *, ({fixed[method]})::BIGINT AS pos FROM {src})"
    every = f"(SELECT t.trial, x.* FROM {src} x, (SELECT unnest(range({trials}))::INT AS trial) t)"
    ax = AXES[axis]
    if method == "plain_shuffle":
        return f"{name} AS (SELECT *, row_number() OVER (PARTITION BY trial ORDER BY {key(ax, 'plain', 'trial')}, id) AS pos FROM {every})"
    dealt = f"(SELECT *, row_number() OVER (PARTITION BY trial, (rank - 1) // {groups} ORDER BY {key(ax, 'deal', 'trial')}, id) AS slot FROM {every})"
    return f"{name} AS (SELECT * EXCLUDE (slot), row_number() OVER (PARTITION BY trial ORDER BY slot, {key(ax, 'order', 'trial')}, id) AS pos FROM {dealt})"


def cut(axis: str, groups: int, rule: str = "midpoint") -> str:
    """CTE {axis}g: trial, id, len, pos, grp."""
    g = {"midpoint": f"(2 * x + len) * {groups} // (2 * total)", "start": f"x * {groups} // total", "count": f"(pos - 1) * {groups} // size"}[rule]
    x = "coalesce(sum(len) OVER (PARTITION BY trial ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT"
    return f"{axis}g AS (SELECT trial, id, len, pos, size, least({groups - 1}, {g})::INT AS grp FROM (SELECT *, {x} AS x FROM {axis}p))"


def grouped(corpus: str, method: str, groups: int, rule: str = "midpoint", trials: int = 1) -> str:
    return ", ".join([corpus, RANKS, *(placed(a, method, groups, trials) for a in "rc"), *(cut(a, groups, rule) for a in "rc")])


def blocks(groups: int, trials: int = 1) -> str:
    """CTE b: trial, m, n, diag, cost."""
    return (
        f"sums AS (SELECT rg.trial, rg.grp AS m, cg.grp AS n, sum(r.n)::BIGINT AS cost FROM r JOIN rg ON rg.id = r.row_id JOIN cg ON cg.id = r.col_id AND cg.trial = rg.trial GROUP BY 1, 2, 3), "
        f"b AS (SELECT t.trial, i.m, j.n, ((j.n - i.m + {groups}) % {groups})::INT AS diag, coalesce(cost, 0)::BIGINT AS cost "
        f"FROM (SELECT unnest(range({trials}))::INT AS trial) t CROSS JOIN (SELECT unnest(range({groups}))::INT AS m) i CROSS JOIN (SELECT unnest(range({groups}))::INT AS n) j LEFT JOIN sums ON sums.trial = t.trial AND sums.m = i.m AND sums.n = j.n)"
    )


ETA = "SELECT sum(s)::BIGINT AS tokens, sum(c)::BIGINT AS total_cost, sum(s)::BIGINT::DOUBLE / {p} AS optimum, sum(s)::BIGINT::DOUBLE / {p} / sum(c)::BIGINT AS eta, sum(s)::BIGINT::DOUBLE / {p} / sum(c)::BIGINT * {p} AS speedup FROM (SELECT diag, max(cost) AS c, sum(cost) AS s FROM b GROUP BY diag)"


def eta(corpus: str, method: str, groups: int, rule: str = "midpoint") -> str:
    return f"WITH {grouped(corpus, method, groups, rule)}, {blocks(groups)} {ETA.format(p=groups)}"


def eta_value(corpus: str, method: str, groups: int, trials: int = 1) -> str:
    """One value: the eta, or the best of several trials."""
    return f"(WITH {grouped(corpus, method, groups, trials=trials)}, {blocks(groups, trials)} SELECT max(e) FROM (SELECT trial, sum(s)::BIGINT::DOUBLE / {groups} / sum(c)::BIGINT AS e FROM (SELECT trial, diag, max(cost) AS c, sum(cost) AS s FROM b GROUP BY 1, 2) GROUP BY trial))"


def best(corpus: str, method: str, groups: int, trials: int = TRIALS) -> str:
    return (
        f"WITH {grouped(corpus, method, groups, trials=trials)}, {blocks(groups, trials)}, "
        f"e AS (SELECT trial, sum(c)::BIGINT AS total_cost, sum(s)::BIGINT::DOUBLE / {groups} / sum(c)::BIGINT AS eta FROM (SELECT trial, diag, max(cost) AS c, sum(cost) AS s FROM b GROUP BY 1, 2) GROUP BY trial) "
        "SELECT (SELECT trial FROM e ORDER BY eta DESC, trial LIMIT 1) AS trial, max(eta) AS eta, round(avg(eta), 9) AS mean_eta, min(total_cost) AS total_cost FROM e"
    )


TOPICS = 4
ALPHA, BETA, GAMMA = 0.5, 0.1, 0.1


def topics(axis: str = "word", src: str = "r", out: str = "z") -> str:
    """CTE: one row a token with its first topic k."""
    k = f"({key(axis, 'topic', chr(39) + '0' + chr(39), 'row_id' + ' || ' + chr(39) + '/' + chr(39) + ' || col_id || ' + chr(39) + '/' + chr(39) + ' || i')} % {TOPICS})::INT"
    return f"{out} AS (SELECT row_id, col_id, i, {k} AS k FROM (SELECT row_id, col_id, unnest(range(1, n + 1)) AS i FROM {src}))"


def dense(by: str, src: str = "z") -> str:
    """id, k, c for every topic, zeros too."""
    return f"(SELECT a.{by}, t.k, count({src}.k) AS c FROM (SELECT DISTINCT {by} FROM {src}) a CROSS JOIN (SELECT unnest(range({TOPICS}))::INT AS k) t LEFT JOIN {src} ON {src}.{by} = a.{by} AND {src}.k = t.k GROUP BY 1, 2)"
