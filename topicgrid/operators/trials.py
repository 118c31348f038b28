"""Many random groupings evaluated in one pass over the matrix, and the best of them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from topicgrid.operators.choices import Choice, choice_etas
from topicgrid.operators.cost import block_costs, epoch_costs, eta
from topicgrid.operators.cut import cut
from topicgrid.operators.lengths import lengths, rank_desc, rank_stored
from topicgrid.operators.permute import RANDOM, place


@dataclass
class Partition:
    """Row and column groups of one method (id, len, pos, grp) and, of a random one, the trial."""

    rows: DataFrame
    cols: DataFrame
    groups: int
    method: str
    trial: int = 0


def ranked_axes(matrix: DataFrame, tie: str = "id", seed: int = 7, mode: str = "two_level") -> tuple[DataFrame, DataFrame]:
    return tuple(rank_desc(lengths(matrix, axis), tie, seed, mode, axis) for axis in ("row", "col"))


def stored_axes(matrix: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The ranked axes, written: orders are made from them more than once."""
    return tuple(rank_stored(lengths(matrix, axis)) for axis in ("row", "col"))


def partition(matrix: DataFrame, method: str, groups: int, seed: int = 7, rule: str = "midpoint", trial: int = 0, tie: str = "id", mode: str = "two_level", ranked: tuple[DataFrame, DataFrame] | None = None) -> Partition:
    """Groups by one method (of a random one: of that trial). ``ranked``: the ranked axes, if made already."""
    made = []
    for axis, items in zip(("row", "col"), ranked or ranked_axes(matrix, tie, seed, mode), strict=True):
        placed = place(items, method, groups, seed, axis, 1, trial)
        made.append(cut(placed.drop("trial"), groups, rule, mode=mode))
    return Partition(*made, groups, method, trial)


def eta_of(matrix: DataFrame, method: str, groups: int, **how) -> DataFrame:
    p = partition(matrix, method, groups, **how)
    return eta(block_costs(matrix, p.rows, p.cols, groups), groups)


def trial_groups(ranked: DataFrame, method: str, groups: int, trials: int, seed: int, axis: str, rule: str = "midpoint", first: int = 0) -> DataFrame:
    """id, grps: the group of each item in each of ``trials`` trials from ``first`` on, as an array in order of trials."""
    placed = place(ranked, method, groups, seed, axis, trials, first)
    done = cut(placed, groups, rule, by=("trial",))
    listed = F.transform(F.array_sort(F.collect_list(F.struct("trial", "grp"))), lambda x: x.grp)
    return done.groupBy("id").agg(listed.alias("grps"))


def trial_etas(matrix: DataFrame, method: str, groups: int, trials: int, seed: int = 7, rule: str = "midpoint", ranked: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """trial, tokens, total_cost, eta."""
    assert method in RANDOM
    choices = [Choice(method, groups, t) for t in range(trials)]
    return choice_etas(matrix, choices, ranked or stored_axes(matrix), seed, rule).select("trial", "tokens", "total_cost", "eta")


def best_of(matrix: DataFrame, method: str, groups: int, trials: int, seed: int = 7, rule: str = "midpoint", ranked: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """One row: the trial with the highest eta (ties: the first), its eta, and the mean over all."""
    return trial_etas(matrix, method, groups, trials, seed, rule, ranked).agg(
        F.max_by("trial", F.struct("eta", (-F.col("trial")).alias("t"))).alias("trial"),
        F.max("eta").alias("eta"),
        F.round(F.avg("eta"), 9).alias("mean_eta"),
        F.min("total_cost").alias("total_cost"),
    )


def compare(matrix: DataFrame, methods: tuple[str, ...], sizes: tuple[int, ...], trials: int = 5, seed: int = 7) -> DataFrame:
    """method, groups, eta: the comparison table. Ranks are made once, and one pass over the matrix serves all methods, sizes and trials."""
    choices = [Choice(m, p, t) for m in methods for p in sizes for t in range(trials if m in RANDOM else 1)]
    return choice_etas(matrix, choices, stored_axes(matrix), seed).groupBy("method", "groups").agg(F.max("eta").alias("eta"))


def advise(matrix: DataFrame, groups: int, target: float, trials: int = 100, step: int = 10, seed: int = 7) -> DataFrame:
    """What to use: method, trial, eta, tried, ceiling, reached.

    The ceiling comes first: where it lies below the target nothing can reach it. Then the deterministic methods, and only if
    these fall short rounds of ``step`` stratified trials until the target or ``trials`` is reached. ``partition`` with the
    method, seed and trial makes the grouping that has this eta.
    """
    from topicgrid.operators.cost import eta_ceiling

    ceiling = eta_ceiling(lengths(matrix, "row"), lengths(matrix, "col"), groups).first().ceiling
    best, tried = ("", 0, 0.0), 0
    for method in ("interleave", "mirror"):
        e = eta_of(matrix, method, groups).first().eta or 0.0
        tried += 1
        best = max(best, (method, 0, e), key=lambda x: x[2])
    done, ranked = 0, stored_axes(matrix) if best[2] < min(target, ceiling) and trials else None
    while best[2] < min(target, ceiling) and done < trials:
        n = min(step, trials - done)
        for r in choice_etas(matrix, [Choice("stratified", groups, done + t) for t in range(n)], ranked, seed).orderBy("trial").collect():
            best = max(best, ("stratified", r.trial, r.eta or 0.0), key=lambda x: x[2])
        tried += n
        done += n
    spark = matrix.sparkSession
    return spark.createDataFrame([(*best, tried, ceiling, best[2] >= target)], "method string, trial int, eta double, tried int, ceiling double, reached boolean")


__all__ = ["Partition", "advise", "best_of", "compare", "epoch_costs", "eta_of", "partition", "ranked_axes", "trial_etas", "trial_groups"]
