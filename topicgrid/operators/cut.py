"""Cuts of an ordered list into P consecutive groups of about equal token counts."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SLAB = 65_536
RULES = ("midpoint", "start", "count")
_EXACT = 1 << 62


def _group(rule: str, before: Column, length: Column, pos: Column, groups: int, total: Column, size: Column) -> Column:
    """Integers throughout; the product is taken in DECIMAL(38) where BIGINT might not hold it."""
    if rule == "count":
        return F.least(F.lit(groups - 1), F.expr(f"(pos - 1) * {groups} div size")).cast("int")
    doubled = 2 * before + length if rule == "midpoint" else 2 * before
    wide = F.floor(doubled.cast("decimal(38,0)") * groups / (2 * total).cast("decimal(38,0)"))
    narrow = ((doubled * groups - (doubled * groups) % (2 * total)) / (2 * total)).cast("bigint")
    return F.least(F.lit(groups - 1), F.when(total < F.lit(_EXACT // (4 * groups)), narrow).otherwise(wide.cast("bigint"))).cast("int")


def prefix_tokens(placed: DataFrame, by: tuple[str, ...] = (), mode: str = "two_level", slab: int = SLAB) -> DataFrame:
    """``placed`` with before: the tokens of all items at earlier positions.

    "window" is one running sum (in one task for each value of ``by``). "two_level" sums slabs of positions, adds up over the slabs
    and runs inside each, so tasks hold a slab at most.
    """
    running = Window.partitionBy(*by).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    if mode == "window":
        return placed.withColumn("before", F.coalesce(F.sum("len").over(running), F.lit(0)))
    keyed = placed.withColumn("slab", F.floor((F.col("pos") - 1) / slab).cast("bigint"))
    sums = keyed.groupBy(*by, "slab").agg(F.sum("len").alias("s"))
    over = Window.partitionBy(*by).orderBy("slab").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select(*by, "slab", F.coalesce(F.sum("s").over(over), F.lit(0)).alias("base"))
    inside = Window.partitionBy(*by, "slab").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    inner = keyed.withColumn("inner", F.coalesce(F.sum("len").over(inside), F.lit(0)))
    return inner.join(base, [*by, "slab"]).withColumn("before", F.col("base") + F.col("inner")).drop("slab", "base", "inner")


def cut(placed: DataFrame, groups: int, rule: str = "midpoint", by: tuple[str, ...] = (), mode: str = "two_level") -> DataFrame:
    """id, len, pos, grp (0 .. groups - 1), and ``by``.

    "midpoint": the slab of N / P tokens in which an item's middle falls; "start": that of its first token; "count":
    equal numbers of items. A group is empty where one item outweighs it, or where there are fewer items than groups.
    """
    if rule not in RULES:
        raise ValueError(f"rule is one of {', '.join(RULES)}")
    summed = placed.withColumn("before", F.lit(0)) if rule == "count" else prefix_tokens(placed, by, mode)
    cols = [F.col(c) for c in ("before", "len", "pos")]
    return summed.select(*by, "id", "len", "pos", _group(rule, *cols, groups, F.col("total"), F.col("size")).alias("grp"))


def cut_sizes(placed: DataFrame, sizes: tuple[int, ...], mode: str = "two_level") -> DataFrame:
    """id and, for each P of ``sizes``, g<P>: the groups that ``cut`` makes by the midpoint rule, from one prefix sum."""
    summed = prefix_tokens(placed, (), mode)
    cols = [F.col(c) for c in ("before", "len", "pos")]
    return summed.select("id", *(_group("midpoint", *cols, p, F.col("total"), F.col("size")).alias(f"g{p}") for p in sizes))


def cut_by_histogram(ranked: DataFrame, groups: int, method: str = "interleave") -> DataFrame:
    """The midpoint cut of ``interleave`` without any prefix shuffle of the items.

    Length is a step function of rank, so the P - 1 boundaries follow from the histogram of lengths alone (at most
    the square root of 2 N rows, on the driver); items then find their group by comparing their position.
    """
    from topicgrid.operators.permute import closed_form

    if method != "interleave":
        raise ValueError("only interleave has prefix sums in closed form")
    hist = sorted(((r.len, r.c) for r in ranked.groupBy("len").agg(F.count(F.lit(1)).alias("c")).collect()), reverse=True)
    value = np.array([v for v, _ in hist], dtype=object)
    ends = np.cumsum([c for _, c in hist])
    tokens = [0, *np.cumsum([v * c for v, c in hist]).tolist()]
    size, total = int(ends[-1]), int(tokens[-1])

    def top(k: int) -> int:
        """Tokens of the k longest."""
        j = int(np.searchsorted(ends, k, side="left"))
        return int(tokens[j]) + (k - (int(ends[j - 1]) if j else 0)) * int(value[j]) if k else 0

    def length(rank: int) -> int:
        return int(value[int(np.searchsorted(ends, rank, side="left"))])

    def before(pos: int) -> int:
        longs, shorts = pos // 2, (pos - 1) // 2
        return top(longs) + total - top(size - shorts)

    rank_at = lambda pos: (pos + 1) // 2 if pos % 2 else size + 1 - pos // 2

    def group_at(pos: int) -> int:
        return min(groups - 1, (2 * before(pos) + length(rank_at(pos))) * groups // (2 * total))

    bounds = []
    for g in range(1, groups):
        lo, hi = 1, size + 1
        while lo < hi:
            mid = (lo + hi) // 2
            if group_at(mid) >= g:
                hi = mid
            else:
                lo = mid + 1
        bounds.append(lo)
    edges = F.array(*(F.lit(b).cast("bigint") for b in bounds)) if bounds else F.array().cast("array<bigint>")
    return closed_form(ranked, method).select("id", "len", "pos", F.size(F.filter(edges, lambda b: b <= F.col("pos"))).cast("int").alias("grp"))


def _knots(ends: DataFrame, width: int, ranges: list[tuple[int, int]]) -> np.ndarray:
    """The least and the largest end in each bucket of ``width`` tokens, of the ends in ``ranges``; two columns, ascending."""
    starts = F.array(*(F.lit(a).cast("bigint") for a, _ in ranges))
    stops = F.array(*(F.lit(b).cast("bigint") for _, b in ranges))
    dealt = ends.withColumn("r", F.size(F.filter(starts, lambda a: a <= F.col("end")))).filter("r > 0").filter(F.get(stops, F.col("r") - 1) >= F.col("end"))
    found = dealt.groupBy("r", F.expr(f"end div {width}").alias("k")).agg(F.min("end").alias("lo"), F.max("end").alias("hi")).select("lo", "hi").toArrow()
    knots = np.column_stack([found.column(c).to_numpy().astype(np.int64) for c in ("lo", "hi")])
    return knots[np.argsort(knots[:, 0])]


def _fill(knots: np.ndarray, most: int, groups: int, high: bool) -> list[int]:
    """Tokens up to the end of each group if groups are filled up to ``most``: at most (``high``) or at least, as far as the knots tell."""
    flat, cuts, base = knots.ravel(), [], 0
    for _ in range(groups):
        at = int(np.searchsorted(flat, base + most, side="right"))
        inside = at % 2 == 1  # between the two ends of a bucket, where others may be
        base = base + most if high and inside else int(flat[at - 1]) if at else base
        cuts.append(base)
    return cuts


def bottleneck_ends(placed: DataFrame, groups: int, most_items: int = 2_000_000) -> list[int]:
    """Tokens up to the end of each group but the last one, for the least possible maximum; groups are filled from the left.

    The driver holds prefix sums by buckets of tokens, about ``most_items`` at most. They bracket the maximum and each boundary; the
    buckets in which a boundary may fall are read again in finer ones until the brackets are closed, so the outcome doesn't depend on
    ``most_items``. A heavy item never blurs its neighbours, since buckets are of tokens.
    """
    ends = prefix_tokens(placed).select((F.col("before") + F.col("len")).alias("end"))
    seen = placed.agg(F.sum("len").alias("total"), F.max("len").alias("longest"), F.count(F.lit(1)).alias("n")).first()
    if not seen.n or not seen.total:
        return []
    total = int(seen.total)
    width = 1 if seen.n <= most_items else -(-total // most_items)
    knots = _knots(ends, width, [(0, total)])
    least, enough = max(int(seen.longest), -(-total // groups)), total
    while True:
        found = []
        for high, lo, hi in ((True, least, enough), (False, least, enough)):
            while lo < hi:
                mid = (lo + hi) // 2
                lo, hi = (lo, mid) if _fill(knots, mid, groups, high)[-1] >= total else (mid + 1, hi)
            found.append(lo)
        least, enough = found
        low, high = _fill(knots, least, groups, False), _fill(knots, enough, groups, True)
        if low == high:
            return low[:-1]
        open_ = knots[:, 0] < knots[:, 1]
        ranges: list[tuple[int, int]] = []
        for a, b in zip(low, high, strict=True):
            k = np.flatnonzero(open_ & (knots[:, 1] > a) & (knots[:, 0] <= b))
            if not len(k):
                continue
            first, last = int(knots[k[0], 0]), int(knots[k[-1], 1])
            if ranges and first <= ranges[-1][1]:
                first, last = ranges[-1][0], max(last, ranges.pop()[1])
            ranges.append((first, last))
        inner = np.zeros(len(knots), bool)
        for a, b in ranges:
            inner |= (knots[:, 0] >= a) & (knots[:, 1] <= b)
        width = max(1, min(width // 2, -(-sum(b - a + 1 for a, b in ranges) // most_items)))
        knots = np.concatenate([knots[~inner], _knots(ends, width, ranges)])
        knots = knots[np.argsort(knots[:, 0])]


def cut_bottleneck(placed: DataFrame, groups: int, most_items: int = 2_000_000) -> DataFrame:
    """Contiguous groups whose heaviest is as light as can be, at every size (``bottleneck_ends``)."""
    bounds = bottleneck_ends(placed, groups, most_items)
    cuts = F.array(*(F.lit(b).cast("bigint") for b in bounds)) if bounds else F.array().cast("array<bigint>")
    end = F.col("before") + F.col("len")
    return prefix_tokens(placed).select("id", "len", "pos", F.size(F.filter(cuts, lambda b: b < end)).cast("int").alias("grp"))


def group_bounds(groups: DataFrame) -> DataFrame:
    """grp, first_pos, last_pos, items, tokens of the groups that have items."""
    return groups.groupBy("grp").agg(F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"), F.count(F.lit(1)).alias("items"), F.sum("len").alias("tokens"))
