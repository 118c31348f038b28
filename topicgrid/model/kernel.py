"""The sampling kernel: collapsed Gibbs over one block, in numpy, token by token or in waves.

A wave is a set of tokens of which no two share a row or a column: the grid's idea once more, inside a block. All tokens of
a wave are drawn in one step. What they share are the topic totals, which stand still during a wave, as those of other
blocks do during an epoch.
"""

from __future__ import annotations

from bisect import bisect_right
from functools import cache
from struct import Struct

import numpy as np

THIN = 400  # a wave with less than one token in so many that were looked at isn't worth looking for
LOOK = 16_384  # tokens among which waves are looked for at once
UNROLLED = 64  # topics up to which a token is drawn without numpy
WIDE = 2048  # tokens drawn in one step


def sweep_plain(rows: np.ndarray, cols: np.ndarray, z: np.ndarray, theta: np.ndarray, phi: np.ndarray, totals: np.ndarray, alpha: float, beta: float, size: int, u: np.ndarray) -> None:
    """Resample each token in turn, in place; ``u``: a uniform number for each.

    ``rows`` and ``cols`` index ``theta`` (documents x K) and ``phi`` (words or stamps x K). A token leaves the
    counts, its topic is drawn with weight (theta + alpha) * (phi + beta) / (totals + size * beta), and it comes back.
    """
    scale = size * beta
    for t in range(len(z)):
        d, w, k = theta[rows[t]], phi[cols[t]], z[t]
        d[k] -= 1
        w[k] -= 1
        totals[k] -= 1
        c = np.cumsum((d + alpha) * (w + beta) / (totals + scale))
        k = int(np.searchsorted(c, u[t] * c[-1], side="right"))
        k = min(k, len(c) - 1)
        z[t] = k
        d[k] += 1
        w[k] += 1
        totals[k] += 1


@cache
def _unrolled(topics: int):
    """``sweep_plain`` over a piece of tokens with one variable a topic, so a token costs no call of numpy: the same operations on the same doubles in the same order."""
    every = range(topics)
    name = lambda x: ", ".join(f"{x}{k}" for k in every)
    running = "\n".join(f"        c{k} = {f'c{k - 1} + ' if k else ''}({'d%d' % k} + alpha) * (w{k} + beta) / s{k}" for k in every)
    code = f"""
def run(rows, cols, z, us, theta, phi, totals, alpha, beta, scale):
    read, width = Struct("{topics}d").unpack_from, {topics * 8}
    {name("s")}, = scaled = [x + scale for x in totals]
    for t, (r, w, k, u) in enumerate(zip(rows, cols, z, us)):
        i, j = r * {topics}, w * {topics}
        theta[i + k] -= 1.0
        phi[j + k] -= 1.0
        totals[k] -= 1.0
        scaled[k] = totals[k] + scale
        {name("s")}, = scaled
        {name("d")}, = read(theta, r * width)
        {name("w")}, = read(phi, w * width)
{running}
        k = bisect_right(({name("c")},), u * c{topics - 1})
        if k == {topics}:
            k = {topics - 1}
        z[t] = k
        theta[i + k] += 1.0
        phi[j + k] += 1.0
        totals[k] += 1.0
        scaled[k] = totals[k] + scale
"""
    made: dict = {"Struct": Struct, "bisect_right": bisect_right}
    exec(code, made)  # of a number only
    return made["run"]


class Sweep:
    """``sweep_plain`` in pieces of tokens, with equal results to the bit; with few topics several times faster. ``close`` brings counts and totals up to date."""

    def __init__(self, theta: np.ndarray, phi: np.ndarray, totals: np.ndarray, alpha: float, beta: float, size: int):
        self.counts, self.how, self.topics = (theta, phi, totals), (alpha, beta, size), len(totals)
        self.fast = self.topics <= UNROLLED
        if self.fast:  # whole numbers, exact in doubles
            self.held = (theta.astype(np.float64), phi.astype(np.float64), totals.astype(np.float64).tolist())

    def draw(self, rows: np.ndarray, cols: np.ndarray, z: np.ndarray, u: np.ndarray) -> None:
        alpha, beta, size = self.how
        if not self.fast:
            sweep_plain(rows, cols, z, *self.counts, alpha, beta, size, u)
            return
        theta, phi, totals = self.held
        views = [memoryview(x).cast("B").cast("d") if x.size else x for x in (theta, phi)]
        for at in range(0, len(z), LOOK):
            some = z[at : at + LOOK].tolist()
            _unrolled(self.topics)(rows[at : at + LOOK].tolist(), cols[at : at + LOOK].tolist(), some, u[at : at + LOOK].tolist(), *views, totals, alpha, beta, size * beta)
            z[at : at + LOOK] = some

    def close(self) -> None:
        if self.fast:
            for x, y in zip(self.counts, self.held, strict=True):
                x[...] = y


def sweep(rows: np.ndarray, cols: np.ndarray, z: np.ndarray, theta: np.ndarray, phi: np.ndarray, totals: np.ndarray, alpha: float, beta: float, size: int, u: np.ndarray) -> None:
    """The same in one piece."""
    if len(z) * 500 < len(theta) + len(phi):  # copying the counts would take longer
        sweep_plain(rows, cols, z, theta, phi, totals, alpha, beta, size, u)
        return
    s = Sweep(theta, phi, totals, alpha, beta, size)
    s.draw(rows, cols, z, u)
    s.close()


def wave_numbers(rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """The wave of each token; -1: none, since those left share few rows or columns that have very many tokens.

    In each round every row offers its first token that is left, and every column takes the first that it is offered. Tokens come in
    an order shuffled by their number alone, so the same block always gets the same waves.
    """
    n = len(rows)
    wave = np.full(n, -1, np.int32)
    if not n:
        return wave
    order = np.random.default_rng(n).permutation(n)
    by_row, by_col = np.empty(rows.max() + 1, np.int64), np.empty(cols.max() + 1, np.int64)
    k = 0
    for at in range(0, n, LOOK):
        left = order[at : at + LOOK]
        while len(left):
            by_row[rows[left[::-1]]] = left[::-1]  # the last write is the first token
            offered = left[by_row[rows[left]] == left]
            by_col[cols[offered[::-1]]] = offered[::-1]
            taken = offered[by_col[cols[offered]] == offered]
            if len(taken) * THIN < len(left) or (len(taken) < 4 and len(left) > 4):
                break
            wave[taken] = k
            left = left[wave[left] < 0]
            k += 1
    return wave


def sweep_waves(rows: np.ndarray, cols: np.ndarray, z: np.ndarray, theta: np.ndarray, phi: np.ndarray, totals: np.ndarray, alpha: float, beta: float, size: int, u: np.ndarray, waves: np.ndarray | None = None) -> None:
    """The same, wave by wave; tokens without a wave come last, one by one."""
    waves = wave_numbers(rows, cols) if waves is None else waves
    order = np.argsort(waves, kind="stable")
    cuts = np.searchsorted(waves[order], np.arange(0, waves.max(initial=-1) + 2))
    for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
        for at in range(a, b, WIDE):
            draw(order[at : min(b, at + WIDE)], rows, cols, z, theta, phi, totals, alpha, beta, size, u)
    rest = np.sort(order[: cuts[0]])
    if len(rest):
        left = z[rest]
        sweep(rows[rest], cols[rest], left, theta, phi, totals, alpha, beta, size, u[rest])
        z[rest] = left


def draw(some: np.ndarray, rows: np.ndarray, cols: np.ndarray, z: np.ndarray, theta: np.ndarray, phi: np.ndarray, totals: np.ndarray, alpha: float, beta: float, size: int, u: np.ndarray) -> None:
    """One step: tokens that share no row and no column."""
    d, w, k = rows[some], cols[some], z[some]
    each = np.arange(len(some))
    left, right = theta[d] + alpha, phi[w] + beta
    left[each, k] -= 1
    right[each, k] -= 1
    down = np.broadcast_to(totals + size * beta, left.shape).copy()
    down[each, k] -= 1
    left *= right
    left /= down
    c = np.cumsum(left, axis=1)
    new = np.minimum((c <= (u[some] * c[:, -1])[:, None]).sum(axis=1), c.shape[1] - 1)
    theta[d, k] -= 1
    phi[w, k] -= 1
    theta[d, new] += 1
    phi[w, new] += 1
    totals += np.bincount(new, minlength=len(totals)) - np.bincount(k, minlength=len(totals))
    z[some] = new


KERNELS = {"loop": sweep, "waves": sweep_waves}


def stream(seed: int, iteration: int, phase: int, diag: int, m: int) -> np.random.Generator:
    """Draws that depend on nothing but their place, so a task that runs again repeats them."""
    return np.random.default_rng([seed, iteration, phase, diag, m])
