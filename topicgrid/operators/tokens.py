"""Tokens, stop words and vocabularies."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PATTERN = r"\p{L}+"
LEADS = (2, 4, 7)  # characters by which a vocabulary is counted


def tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", pattern: str = PATTERN, lower: bool = True) -> DataFrame:
    """row_id, word: one row a token. Null texts have none."""
    text = F.lower(text_col) if lower else F.col(text_col)
    return docs.select(F.col(id_col).cast("bigint").alias("row_id"), F.explode(F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).alias("word"))


def word_counts(toks: DataFrame) -> DataFrame:
    """row_id, word, n: the only shuffle of tokens; combined map-side, so a hot word costs a row a task and document."""
    return toks.groupBy("row_id", "word").agg(F.count(F.lit(1)).alias("n"))


def default_stopwords(*languages: str) -> list[str]:
    from pyspark.ml.feature import StopWordsRemover

    return sorted({w for lang in languages for w in StopWordsRemover.loadDefaultStopWords(lang)})


def drop_stopwords(toks: DataFrame, words: Sequence[str] | DataFrame) -> DataFrame:
    """Without the listed words: a broadcast anti join for a list, which is a parameter; a frame is joined as it comes."""
    if isinstance(words, DataFrame):
        return toks.join(words.select("word"), "word", "left_anti").select(*toks.columns)
    listed = toks.sparkSession.createDataFrame([(w,) for w in words], "word string")
    return toks.join(F.broadcast(listed), "word", "left_anti").select(*toks.columns)


def vocabulary(counts: DataFrame, min_df: int = 1, max_df: float | int | None = None, n_docs: int | None = None, max_size: int | None = None, ids: str = "dense") -> DataFrame:
    """word_id, word, df, cf from ``word_counts``.

    ``max_df``: a number of documents, or a share of ``n_docs`` where below 1. ``max_size`` keeps the words of highest df.
    Ids: "dense", 1.. in order of the words, counted by their first 2, 4 and 7 characters and ranked among those that share all seven, so
    no task sorts much of the vocabulary; or "hash", 64 bits, stable when words are added (``hash_collisions`` checks it).
    """
    return numbered(pruned(counts.groupBy("word").agg(F.count(F.lit(1)).alias("df"), F.sum("n").alias("cf")), min_df, max_df, n_docs, max_size), ids)


def pruned(found: DataFrame, min_df: int = 1, max_df: float | int | None = None, n_docs: int | None = None, max_size: int | None = None) -> DataFrame:
    """The words of word, df, cf that ``vocabulary`` keeps."""
    found = found.filter(F.col("df") >= min_df)
    if max_df is not None:
        found = found.filter(F.col("df") <= F.lit(max_df * n_docs if max_df < 1 else max_df))
    if max_size is not None:
        found = found.orderBy(F.desc("df"), "word").limit(max_size)
    return found


def numbered(found: DataFrame, ids: str = "dense") -> DataFrame:
    """word_id, word, df, cf of word, df, cf; it reads them several times."""
    if ids == "hash":
        return found.select(F.xxhash64("word").alias("word_id"), "word", "df", "cf")
    found = found.withColumns({f"p{k}": F.substring("word", 1, k) for k in LEADS})
    base, above = found.groupBy(*(f"p{k}" for k in LEADS)).agg(F.count(F.lit(1)).alias("c")), None
    for depth, k in enumerate(LEADS):  # words before each lead among those of the next shorter one, and before that
        outer = [f"p{j}" for j in LEADS[:depth]]
        before = Window.partitionBy(*outer[-1:]).orderBy(f"p{k}").rowsBetween(Window.unboundedPreceding, -1)
        here = base.groupBy(*outer, f"p{k}").agg(F.sum("c").alias("c")) if k != LEADS[-1] else base
        here = here.select(*outer, f"p{k}", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("b"))
        above = here if above is None else here.join(above.withColumnRenamed("b", "a"), outer).select(*outer, f"p{k}", (F.col("a") + F.col("b")).alias("b"))
    last = f"p{LEADS[-1]}"
    inside = F.row_number().over(Window.partitionBy(last).orderBy("word"))
    return found.withColumn("inside", inside).join(above.select(last, "b"), last).select((F.col("b") + F.col("inside")).cast("bigint").alias("word_id"), "word", "df", "cf")


def hash_collisions(vocab: DataFrame) -> DataFrame:
    """word_id, k of ids that several words share."""
    return vocab.groupBy("word_id").agg(F.count(F.lit(1)).alias("k")).filter("k > 1")
