"""The pipeline's stages against brute force, each on its own input."""

import collections
import os

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests.llm.test_operators import brute_near, lower


@pytest.fixture(scope="module")
def stages(spark, sf, tmp_path_factory):
    docs, out = spark.read.parquet(f"{sf}/documents.parquet"), []
    for k, (name, f) in enumerate(corpus_pipeline.STAGES):
        path = f"file://{tmp_path_factory.mktemp('stage')}/{k}"
        f(spark, docs, sf).write.parquet(path)
        out.append((name, docs, spark.read.parquet(path)))
        docs = out[-1][2]
    return out


def test_columns(stages):
    for _, before, after in stages[:-1]:
        assert after.columns == before.columns == ["doc_id", "text", "lang", "source", "n_chars"]


def test_quality_keeps_good_documents(stages, spark, sf):
    _, before, after = stages[0]
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    good = before.join(labels.filter("quality = 1"), "doc_id").count()
    assert after.join(labels.filter("quality = 1"), "doc_id").count() >= 0.95 * good
    assert after.count() < before.count()


def test_lines(stages):
    _, before, after = stages[1]
    n, first = collections.Counter(), {}
    docs = before.orderBy("doc_id").collect()
    keys = lambda t: [lower(x).strip(" \t\n\x0b\x0c\r") for x in t.split("\n")]
    for r in docs:
        for k in {k for k in keys(r.text) if k}:
            n[k] += 1
            first.setdefault(k, r.doc_id)
    want = {}
    for r in docs:
        left, mine = [], set()
        for x, k in zip(r.text.split("\n"), keys(r.text), strict=True):
            if n[k] < 10 or (first[k] == r.doc_id and k not in mine):
                mine.add(k)
                left.append(x)
        want[r.doc_id] = "\n".join(left)
    assert {r.doc_id: r.text for r in after.collect()} == want
    assert after.filter(F.col("n_chars") != F.length("text")).isEmpty()


def test_near(stages):
    _, before, after = stages[2]
    want, _ = brute_near(before.collect())
    assert {r.doc_id for r in after.collect()} == set(want.values())


def test_near_takes_rows_without_id(spark):
    """Whichever rows lack an id, as many groups stay as there are, and none without an id where one has it."""
    text = lambda k: " ".join(f"w{k}x{i}" for i in range(60))
    near = lambda k: text(k).replace(f"w{k}x59", "other")
    rows = [(None, text(0))] * 3 + [(None, text(1)), (None, near(1))] + [(7, text(2)), (None, text(2)), (None, near(2))]
    rows += [(9, near(3)), (8, text(3)), (None, text(4)), (None, None), (None, None), (None, "")]
    docs = spark.createDataFrame([(i, t, "en", s % 2, 0) for s, (i, t) in enumerate(rows)], "doc_id bigint, text string, lang string, source int, n_chars bigint")
    found = corpus_pipeline.near_copies(spark, docs.repartition(3), "")
    assert found.columns == docs.columns
    kept = [(r.doc_id, r.text) for r in found.collect()]
    groups = collections.Counter((t or "").split("x")[0] for _, t in kept)
    assert groups == {"w0": 1, "w1": 1, "w2": 1, "w3": 1, "w4": 1, "": 3}
    assert {i for i, _ in kept} == {None, 7, 8}
    again = corpus_pipeline.near_copies(spark, docs.orderBy(F.desc("text")).repartition(5), "").collect()
    assert collections.Counter(map(tuple, again)) == collections.Counter(map(tuple, found.collect()))


def test_mixing_and_packing(stages):
    _, before, after = stages[3]
    sizes = {r.source: r.n for r in before.groupBy("source").agg(F.sum(F.size(F.expr(r"regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+', 0)"))).alias("n")).collect()}
    taken = {r.source: r.n for r in after.groupBy("source").agg(F.sum(F.size(F.expr(r"regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+', 0)"))).alias("n")).collect()}
    assert 0.8 * sum(sizes.values()) <= sum(taken.values()) <= sum(sizes.values())
    assert all(taken.get(s, 0) <= 3 * n for s, n in sizes.items())
    _, before, after = stages[4]
    assert after.select("row_no").distinct().count() == before.count()
    assert after.groupBy("sequence_id").agg(F.sum("length").alias("n")).filter("n > 2048").isEmpty()


def test_stages_take_anything(spark, sf):
    """Nulls in every column, empty texts, repeated rows, clashing names and an empty table, at every stage."""
    rows = [(1, "alpha beta gamma delta epsilon zeta", "en", "a", 5), (1, "alpha beta gamma delta epsilon zeta", "en", "a", 5), (2, None, None, None, None), (None, "", None, "b", 0), (None, None, None, None, None), (3, "word " * 9000, "de", "b", 45000)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    more = docs.withColumns({c: F.lit("clash") for c in ("Score", "predicted", "n_lines", "row", "at", "h", "r", "c0", "MIX_SHARD", "kept", "piece", "row_no", "mark", "key")})
    for df in (docs, more, more.limit(0)):
        for name, f in corpus_pipeline.STAGES:
            out = f(spark, df, sf)
            n = out.count()
            if name != "packing":
                assert out.columns == df.columns
            if df is not docs and df is not more:
                assert n == 0
            elif name == "line_dedup":
                assert n == 6
            elif name == "near_dedup":  # the two rows of doc_id 1 are one group; the others are near to nothing
                assert n == 5
            elif name == "packing":
                assert out.select("row_no").distinct().count() == 6


def test_run_agrees(stages, spark, sf):
    found = corpus_pipeline.run(spark, sf)
    cols = ["doc_id", "piece", "start", "length", "ids_crc32"]
    assert collections.Counter(map(tuple, found.select(cols).collect())) == collections.Counter(map(tuple, stages[-1][2].select(cols).collect()))


def test_no_machine_local_folder_where_one_is_named(spark):
    from types import SimpleNamespace

    from topicgrid.llm.common import Scratch, shared_root

    named = SimpleNamespace(conf=SimpleNamespace(get=lambda key, default=None: "hdfs://shared/ck/" if key == "spark.checkpoint.dir" else default))
    assert shared_root(named) == "hdfs://shared/ck"
    s = Scratch(spark, "named")
    assert s.root.startswith(f"{shared_root(spark)}/topicgrid-named-")
    assert s.table(spark.range(3).toDF("x"), "t").count() == 3
    folder = s.root.removeprefix("file://")
    assert os.listdir(folder) == ["t"]
    s.drop("t")
    assert os.listdir(folder) == []
