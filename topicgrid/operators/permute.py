"""Orders of rows or columns: the three methods, their variants and the baseline."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from topicgrid.functions import positions
from topicgrid.functions.rng import key
from topicgrid.operators.lengths import with_bucket

CLOSED = {
    "interleave": positions.interleave,
    "mirror": positions.mirror_swap,
    "mirror_alternate": positions.mirror_alternate,
    "sorted": lambda k, d: k,
}
RANDOM = ("stratified", "plain_shuffle")
METHODS = (*CLOSED, "identity", *RANDOM)


def closed_form(ranked: DataFrame, method: str) -> DataFrame:
    """``ranked`` with pos: a projection, no shuffle."""
    return ranked.withColumn("pos", CLOSED[method](F.col("rank"), F.col("size")).cast("bigint"))


def interleave(ranked: DataFrame) -> DataFrame:
    return closed_form(ranked, "interleave")


def mirror(ranked: DataFrame, form: str = "swap") -> DataFrame:
    """``form``: "swap" trades every second item of the front half with its mirror; "alternate" fills both ends in turn."""
    return closed_form(ranked, {"swap": "mirror", "alternate": "mirror_alternate"}[form])


def identity(ranked: DataFrame) -> DataFrame:
    """Natural order by id: counts by bucket of ids, and ranks inside each."""
    dealt = with_bucket(ranked, "id", "part")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a bucket
    base = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("c")).select("part", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("base"))
    inner = F.row_number().over(Window.partitionBy("part").orderBy("id"))
    return dealt.withColumn("inner", inner).join(base, "part").withColumn("pos", (F.col("base") + F.col("inner")).cast("bigint")).drop("part", "inner", "base")


def _in_trials(ranked: DataFrame, trials: int, first: int) -> DataFrame:
    return ranked.withColumn("trial", F.explode(F.sequence(F.lit(first), F.lit(first + trials - 1))))


def stratified(ranked: DataFrame, groups: int, seed: int = 7, axis: str = "row", trials: int = 1, first: int = 0) -> DataFrame:
    """Each run of ``groups`` neighbours by length is dealt out at random, one item to each sublist; sublists are shuffled and joined.

    One frame for all trials, with trial and pos. A last short run fills the first slots. Windows are partitioned by (trial, run) and by
    (trial, slot, hash bucket), so the largest partition is a bucket of a sublist.
    """
    run = F.floor((F.col("rank") - 1) / groups)
    dealt = _in_trials(ranked, trials, first).withColumn("run", run).withColumn("k1", key(seed, axis, "deal", F.col("trial"), F.col("id")))
    slot = F.row_number().over(Window.partitionBy("trial", "run").orderBy("k1", "id"))
    dealt = dealt.withColumn("slot", slot.cast("int")).withColumn("k2", key(seed, axis, "order", F.col("trial"), F.col("id")))
    return ranked_by_hash(dealt, ["trial", "slot"], "k2").drop("run", "k1", "k2", "slot")


def plain_shuffle(ranked: DataFrame, seed: int = 7, axis: str = "row", trials: int = 1, first: int = 0) -> DataFrame:
    """The baseline: a uniformly random order in each trial."""
    keyed = _in_trials(ranked, trials, first).withColumn("k", key(seed, axis, "plain", F.col("trial"), F.col("id")))
    return ranked_by_hash(keyed, ["trial"], "k").drop("k")


def ranked_by_hash(df: DataFrame, by: list[str], k: str) -> DataFrame:
    """pos: rank in the order (by[1:], k, id) within by[0], from counts of hash buckets and ranks inside each.

    The column size says how many buckets: 256 at least, a million at most, each of about 65,536 items.
    """
    bits = "least(20, greatest(8, cast(ceil(log2(size / 65536D)) AS INT)))"
    df = df.withColumn("part", F.expr(f"cast(shiftrightunsigned({k}, 48 - {bits}) AS INT)"))
    small = df.groupBy(*by, "part").agg(F.count(F.lit(1)).alias("c"))
    order = Window.partitionBy(by[0]).orderBy(*by[1:], "part").rowsBetween(Window.unboundedPreceding, -1)
    base = small.select(*by, "part", F.coalesce(F.sum("c").over(order), F.lit(0)).alias("base"))
    inner = F.row_number().over(Window.partitionBy(*by, "part").orderBy(k, "id"))
    return df.withColumn("inner", inner).join(base, [*by, "part"]).withColumn("pos", (F.col("base") + F.col("inner")).cast("bigint")).drop("part", "inner", "base")


def reflect(placed: DataFrame) -> DataFrame:
    """The same list from its end."""
    return placed.withColumn("pos", positions.reflected(F.col("pos"), F.col("size")))


def place(ranked: DataFrame, method: str, groups: int, seed: int = 7, axis: str = "row", trials: int = 1, first: int = 0) -> DataFrame:
    """``ranked`` with pos, and trial (constant for methods that aren't random)."""
    if method == "stratified":
        return stratified(ranked, groups, seed, axis, trials, first)
    if method == "plain_shuffle":
        return plain_shuffle(ranked, seed, axis, trials, first)
    done = identity(ranked) if method == "identity" else closed_form(ranked, method)
    return done.withColumn("trial", F.lit(0))


def evenness(placed: DataFrame, ranges: int) -> DataFrame:
    """rng, items, mean_len, min_len, max_len, long_items (of the longer half by rank): how alike the ranges of a list are."""
    rng = F.floor((F.col("pos") - 1) * ranges / F.col("size")).cast("int")
    return placed.groupBy(rng.alias("rng")).agg(
        F.count(F.lit(1)).alias("items"),
        F.avg("len").alias("mean_len"),
        F.min("len").alias("min_len"),
        F.max("len").alias("max_len"),
        F.count_if(F.col("rank") * 2 <= F.col("size")).alias("long_items"),
    )


def moving(placed: DataFrame, reach: int, slab: int = 65_536) -> DataFrame:
    """id, pos, moving (mean length from ``reach`` positions before to as many after), step (length less that of the position before).

    Windows run inside slabs of positions; rows near a slab's ends are lent to the next one.
    """
    own = F.floor((F.col("pos") - 1) / slab)
    near = F.array_distinct(F.array(*(F.greatest(F.lit(0), F.floor((F.col("pos") - 1 + d) / slab)) for d in (0, -reach, reach))))
    lent = placed.select("id", "len", "pos", own.alias("home"), F.explode(near).alias("slab"))
    order = Window.partitionBy("slab").orderBy("pos")
    seen = lent.withColumns({"moving": F.avg("len").over(order.rowsBetween(-reach, reach)), "step": F.col("len") - F.lag("len").over(order)})
    return seen.filter("home = slab").select("id", "pos", F.round("moving", 6).alias("moving"), "step")
