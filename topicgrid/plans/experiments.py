"""The published experiments for the bench: balance and times at the published P and numbers of trials; learning with K = 16 and 20 sweeps; speedups."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topicgrid.model.samplers import Priors, fit_diagonal
from topicgrid.model.study import Setting, study
from topicgrid.operators import cost, lengths, trials
from topicgrid.plans import corpora as K

SIZES = (1, 10, 30, 60)


def seconds(make) -> tuple[float, object]:
    began = time.perf_counter()
    got = make()
    return round(time.perf_counter() - began, 3), got


def balance(matrix: DataFrame, sizes=SIZES, n_trials: int = 100, seed: int = 7) -> list[dict]:
    """eta of the methods and the baseline with its ceiling, and how long each partitioner took."""
    matrix = matrix.persist()
    out = []
    for p in sizes:
        row: dict = {"P": p, "ceiling": cost.eta_ceiling(lengths.lengths(matrix, "row"), lengths.lengths(matrix, "col"), p).first().ceiling}
        for m in ("interleave", "mirror", "mirror_alternate"):
            t, r = seconds(lambda m=m, p=p: trials.eta_of(matrix, m, p).first())
            row[m], row[f"{m}_s"] = round(r.eta, 4), t
        for m in ("stratified", "plain_shuffle"):
            t, r = seconds(lambda m=m, p=p: trials.best_of(matrix, m, p, n_trials, seed).first())
            row[m], row[f"{m}_mean"], row[f"{m}_s"] = round(r.eta, 4), round(r.mean_eta, 4), t
        row["speedup"] = {m: round(row[m] * p, 2) for m in ("interleave", "mirror", "stratified", "plain_shuffle")}
        out.append(row)
    matrix.unpersist()
    return out


def learning(spark: SparkSession, sf: str, priors: Priors, iterations: int, sizes=(2, 4, 10, 30), seeds=(1, 2, 3)) -> list[dict]:
    """Perplexity after equal iterations: serial against diagonal, the stamped model of customers, parts and months; a task for each fit."""
    settings = [Setting("serial", 1, s, kernel="loop") for s in seeds] + [Setting("diagonal", p, s) for p in sizes for s in seeds]
    end = study(K.basket(spark, sf, weight=None), K.stamp_matrix(spark, sf), settings, priors, iterations).filter(F.col("iteration").isin(0, iterations)).collect()
    out = []
    for sampler, p in [("serial", 1), *(("diagonal", p) for p in sizes)]:
        mine = [r.perplexity for r in end if (r.sampler, r.groups, r.iteration) == (sampler, p, iterations)]
        out.append({"sampler": sampler, "P": p, "perplexity": round(sum(mine) / len(mine), 3), "lowest": round(min(mine), 3), "highest": round(max(mine), 3)})
    for row in out:
        row["gap"] = round(row["perplexity"] / out[0]["perplexity"] - 1, 5)
    return out


def speedups(spark: SparkSession, matrix: DataFrame, priors: Priors, sizes=(1, 2, 4), method: str = "mirror", kernel: str = "loop") -> list[dict]:
    """Seconds an iteration of the plain model takes in a ring of P tasks, next to what eta * P predicts.

    The difference between fits of three iterations and of one leaves out what is done once.
    """
    matrix, out = matrix.persist(), []
    matrix.count()
    for p in sizes:
        g = trials.partition(matrix, method, p)
        rows, cols = g.rows.persist(), g.cols.persist()
        e = cost.eta(cost.block_costs(matrix, rows, cols, p), p).first().eta
        took = []
        for n in (1, 1, 3):
            t, _ = seconds(lambda n=n, p=p, rows=rows, cols=cols: fit_diagonal(matrix, rows, cols, p, priors, n, track=False, execution="ring", kernel=kernel))
            took.append(t)
        out.append({"P": p, "eta": round(e, 4), "predicted": round(e * p, 3), "iteration_s": round((took[2] - took[1]) / 2, 3)})
    for row in out:
        row["measured"] = round(out[0]["iteration_s"] / row["iteration_s"], 3)
    matrix.unpersist()
    return out


def report(spark: SparkSession, sf: str, n_trials: int = 100, iterations: int = 20, corpora=("docs", "docs_pruned", "docs_stopped", "basket", "basket_time", "order_years")) -> dict:
    """Everything over the tables that are given; learning with K = 16 and ``iterations`` sweeps."""
    out: dict = {"sf": sf}
    for name in corpora:
        matrix = K.CORPORA[name](spark, sf)
        out[name] = balance(matrix, n_trials=200 if name in ("basket_time", "order_years") else n_trials)
        out[f"{name}_stats"] = matrix.agg(F.count_distinct("row_id"), F.count_distinct("col_id"), F.sum("n")).first().asDict()
    out["speedups"] = speedups(spark, K.basket(spark, sf, weight=None), Priors(16))
    out["learning"] = learning(spark, sf, Priors(16), iterations)
    return out
