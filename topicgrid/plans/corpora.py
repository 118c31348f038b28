"""The corpora of the experiments, from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topicgrid.functions.stem import stemmed_counts
from topicgrid.operators.postings import cells, postings, words as words_of
from topicgrid.operators.stamps import stamp_arrays, stamp_number, stamp_workload
from topicgrid.operators.tokens import default_stopwords, drop_stopwords, numbered, pruned, tokens, vocabulary, word_counts
from topicgrid.operators.workload import basket_workload, workload
from topicgrid.sources.shared import stored
from topicgrid.sources.tables import table


def doc_counts(spark: SparkSession, sf: str) -> DataFrame:
    return word_counts(tokens(table(spark, sf, "documents")))


def word_matrix(counts: DataFrame, *prune) -> DataFrame:
    """Row = document, column = word. Counts and matrix are written once each: texts are read once, and what reads the matrix often reads ids."""
    counts = stored(counts, "counts")
    return stored(workload(counts, vocabulary(counts, *prune)), "matrix")


def text_matrix(documents: DataFrame, *prune) -> DataFrame:
    """``word_matrix`` of texts. Where each document is one row its tokens are counted where they are read, and words travel once a block of documents."""
    toks = tokens(documents)
    row = F.col("doc_id").cast("bigint")
    rows = documents.groupBy(row.alias("row_id")).agg(F.count(F.lit(1)).alias("k")).agg(F.max("k").alias("most"), F.count_if(F.col("row_id").isNull()).alias("unnamed")).first()
    if rows.unnamed:
        return word_matrix(word_counts(toks), *prune)
    records = stored(postings(word_counts(toks) if (rows.most or 0) > 1 else toks), "postings")
    found = stored(pruned(words_of(records), *prune), "words")
    side = stored(numbered(found).select("word", F.col("word_id").alias("col_id")), "ids")
    return stored(cells(records.join(side, "word")), "matrix")


def docs(spark: SparkSession, sf: str) -> DataFrame:
    """Row = document, column = word, n = occurrences."""
    return text_matrix(table(spark, sf, "documents"))


def docs_pruned(spark: SparkSession, sf: str) -> DataFrame:
    """Only words that 2 documents have, and at most a tenth of all."""
    documents = table(spark, sf, "documents")
    return text_matrix(documents, 2, 0.1, documents.count())


def docs_stopped(spark: SparkSession, sf: str, words=None) -> DataFrame:
    """Without stop words; by default those that Spark lists for the four languages of the documents."""
    words = default_stopwords("english", "french", "german", "spanish") if words is None else words
    return word_matrix(word_counts(drop_stopwords(tokens(table(spark, sf, "documents")), words)))


def docs_stemmed(spark: SparkSession, sf: str, words=None) -> DataFrame:
    """The same with words reduced to their stems."""
    words = default_stopwords("english", "french", "german", "spanish") if words is None else words
    counts = stored(word_counts(drop_stopwords(tokens(table(spark, sf, "documents")), words)), "words")
    return word_matrix(stemmed_counts(counts, counts.select("word").distinct()))


def basket(spark: SparkSession, sf: str, weight: str | None = "l_quantity") -> DataFrame:
    """Row = customer, column = part, n = units bought, or order lines."""
    return basket_workload(table(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_quantity"), table(spark, sf, "orders").select("o_orderkey", "o_custkey"), weight=weight)


def order_basket(spark: SparkSession, sf: str) -> DataFrame:
    """Row = order, column = part."""
    return basket_workload(table(spark, sf, "lineitem"), None, "l_orderkey")


def basket_time(spark: SparkSession, sf: str) -> DataFrame:
    """Row = customer, column = month of order, n = order lines."""
    lines = table(spark, sf, "lineitem").select("l_orderkey").join(table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return lines.groupBy(F.col("o_custkey").alias("row_id"), stamp_number(F.col("o_orderdate"), "month").cast("bigint").alias("col_id")).agg(F.count(F.lit(1)).alias("n"))


def order_dates(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "orders").select("o_custkey", "o_orderdate")


def customer_stamps(spark: SparkSession, sf: str, policy: str = "proportional", slots: int = 16) -> DataFrame:
    """Month stamps of customers that have lines."""
    buyers = table(spark, sf, "lineitem").select("l_orderkey").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return stamp_arrays(buyers, "o_custkey", "o_orderdate", "month", slots, policy)


def stamp_matrix(spark: SparkSession, sf: str, policy: str = "proportional") -> DataFrame:
    return stamp_workload(customer_stamps(spark, sf, policy))


def order_years(spark: SparkSession, sf: str, slots: int = 16) -> DataFrame:
    """Row = order, column = its year, as often as a stamp array has slots: a document with one date."""
    o = table(spark, sf, "orders").select("o_orderkey", "o_orderdate")
    return stamp_workload(stamp_arrays(o, "o_orderkey", "o_orderdate", "year", slots, "repeat"))


def clicks(spark: SparkSession, sf: str) -> DataFrame:
    """Row = user, column = event type and property (by hash), n = events."""
    e = table(spark, sf, "events").filter(F.col("user_id").isNotNull())
    col = F.xxhash64("event_type", F.get_json_object("props", "$.k"))
    return e.groupBy(F.col("user_id").cast("bigint").alias("row_id"), col.alias("col_id")).agg(F.count(F.lit(1)).alias("n"))


CORPORA = {"docs": docs, "docs_pruned": docs_pruned, "docs_stopped": docs_stopped, "docs_stemmed": docs_stemmed, "order_years": order_years, "basket": basket, "order_basket": order_basket, "basket_time": basket_time, "clicks": clicks}
