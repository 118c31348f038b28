"""The queries of the training-data operators, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topicgrid.llm.common import held_out, read
from topicgrid.llm.exact_dedup import exact_dedup
from topicgrid.llm.line_dedup import line_dedup
from topicgrid.llm.mixing import mix
from topicgrid.llm.near_dedup import near_dedup
from topicgrid.llm.packing import pack_documents
from topicgrid.llm.quality import score_quality, train_quality
from topicgrid.llm.suffix_dedup import suffix_dedup
from topicgrid.llm.topk import top_k
from topicgrid.llm.toxicity import score_toxicity, train_toxicity
from topicgrid.llm.url_filter import filter_urls


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines found in 10 documents or more lose all their copies."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    out = line_dedup(docs, min_docs=10, min_points=1, keep="none")
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


OP1_SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(l) AS line, generate_subscripts(l, 1) AS pos
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)),
keyed AS (
  SELECT doc_id, line, pos, translate(regexp_replace(regexp_replace(line, '^[\x20\x09-\x0D]+', ''), '[\x20\x09-\x0D]+$', ''),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM lines),
frequent AS (SELECT key FROM keyed WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT doc_id) >= 10)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(f.key))::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE f.key IS NULL), '')) AS kept_sha256
FROM keyed LEFT JOIN frequent f USING (key) GROUP BY doc_id
"""


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    net = train_quality(docs, read(spark, sf_dir, "labels"))
    return score_quality(docs, net).select("doc_id", held_out().alias("held_out"), "score", "predicted")


def op3_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = read(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return top_k(vectors, vectors.filter(F.col("vec_id") % 50 == 0), 5).select("query_id", "rank", F.col("id").alias("vec_id"), "score")


OP3_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS q FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda z: z[1] * z[2]))::BIGINT AS score
  FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id),
r AS (SELECT query_id, vec_id, score, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 5
"""


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each document gives to the mix: the draws of all shards that hit it, times its words."""
    out = mix(read(spark, sf_dir, "documents"), weights=(5, 2, 1), cap=3)
    return out.select("doc_id", "size", "source_size", "target", "taken")


#: Sources in order of how soon they reach three times their size; the first that doesn't sets the level of all that follow. A source's
#: quota of blocks ends before the block of which less than half the words would be wanted.
OP4_SQL = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS n, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS w FROM d GROUP BY source),
o AS (SELECT *, sum(n) OVER () - 3 * coalesce(sum(n) OVER (ORDER BY n::DOUBLE / w, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS spare,
  sum(w) OVER (ORDER BY n::DOUBLE / w, source ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS whole FROM s WHERE n > 0),
f AS (SELECT *, spare * w > 3 * n * whole AS full_ FROM o),
l AS (SELECT arg_max(spare, whole) FILTER (WHERE NOT full_) AS spare, max(whole) FILTER (WHERE NOT full_) AS whole FROM f),
t AS (SELECT f.source, f.n, CASE WHEN full_ THEN 3 * f.n ELSE l.spare * f.w END::HUGEINT AS num, CASE WHEN full_ THEN 1 ELSE l.whole END::HUGEINT AS den FROM f, l),
b AS (SELECT d.source, ('0x' || substr(md5(doc_id || ':' || size), 1, 5))::BIGINT AS block, sum(size) AS n FROM d GROUP BY 1, 2),
c AS (SELECT source, block, 2 * sum(n) OVER (PARTITION BY source ORDER BY block) - n AS twice FROM b)
SELECT d.doc_id, d.size, coalesce(t.n, 0)::BIGINT AS source_size, coalesce(t.num::DOUBLE / t.den, 0)::DOUBLE AS target,
  (d.size * CASE WHEN t.n IS NULL THEN 0 ELSE t.num // (t.den * t.n) + ((2 * (t.num // (t.den * t.n)) * t.n + c.twice) * t.den <= 2 * t.num)::INT END)::BIGINT AS taken
FROM d JOIN c ON c.source IS NOT DISTINCT FROM d.source AND c.block = ('0x' || substr(md5(d.doc_id || ':' || d.size), 1, 5))::BIGINT
LEFT JOIN t ON t.source IS NOT DISTINCT FROM d.source
"""


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(read(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


OP5_SQL = r"""
WITH t AS (SELECT doc_id, length(coalesce(text, '')) AS n, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm FROM documents),
w AS (SELECT *, first_value(doc_id) OVER (PARTITION BY norm ORDER BY n DESC, doc_id) AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size FROM t)
SELECT doc_id, keep_id, group_size::BIGINT AS group_size, doc_id = keep_id AS kept, sha256(norm) AS text_sha256 FROM w
"""


def op6_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup(read(spark, sf_dir, "documents"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = pack_documents(read(spark, sf_dir, "documents"), with_ids=False)
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    grammar = train_toxicity(docs, read(spark, sf_dir, "labels"))
    return score_toxicity(docs, grammar).select("doc_id", held_out().alias("held_out"), "score", "predicted", "n_matches")


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(read(spark, sf_dir, "pages").select("page_id", "url")).select("page_id", "host", "path", "rule", "verdict")


OP9_SQL = r"""
WITH rest AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS r FROM pages),
h AS (SELECT page_id, r, regexp_extract(r, '^[^/?#]*') AS raw FROM rest),
u AS (SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(substr(r, length(raw) + 1), '^[^?#]*') AS path FROM h),
rules(verdict, rh, rp) AS (VALUES ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('block', 'net', '/de/'), ('allow', 'example.net', '/de/8'), ('block', 'org', '/es/')),
fit AS (
  SELECT page_id, arg_max(rh || rp, length(rh || rp)) AS rule, arg_max(verdict, length(rh || rp)) AS verdict
  FROM u JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY page_id)
SELECT page_id, host, path, rule, coalesce(fit.verdict, CASE WHEN len(list_intersect(string_split(host, '.'),
  ['cheap-pills', 'spam-farm', 'casino', 'free-money', 'adult', 'xxx', 'porn', 'viagra'])) > 0 THEN 'block' ELSE 'allow' END) AS verdict
FROM u LEFT JOIN fit USING (page_id)
"""


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_dedup(read(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_line_dedup": op1_line_dedup,
    "op2_quality": op2_quality,
    "op3_topk_search": op3_topk_search,
    "op4_mixing": op4_mixing,
    "op5_exact_dedup": op5_exact_dedup,
    "op6_near_dedup": op6_near_dedup,
    "op7_packing": op7_packing,
    "op8_toxicity": op8_toxicity,
    "op9_url_filter": op9_url_filter,
    "op10_suffix_dedup": op10_suffix_dedup,
}
ORACLES: dict[str, str] = {
    "op1_line_dedup": OP1_SQL,
    "op3_topk_search": OP3_SQL,
    "op4_mixing": OP4_SQL,
    "op5_exact_dedup": OP5_SQL,
    "op9_url_filter": OP9_SQL,
}
