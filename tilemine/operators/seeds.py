"""Seeding of two-way splits for many nodes at once, and of k centroids.

``axis``: the halves about the mean of the dimension with the largest variance.
``farthest``: the smallest id and the row farthest from it.
``random``: the two rows with the smallest hash of (seed, code, id).
``dsquare``: one random row, the next ones drawn with probability in proportion to squared distance.
``parallel``: rounds that each draw rows independently, a row with a chance of OVERSAMPLING x k times its share of the cost; then every
candidate is weighted by the rows nearest to it, and weighted draws and means among the candidates give k.  A round is two passes, however
many rows it draws.
A split by ``dsquare`` or ``parallel`` looks one level ahead, as the best two groups may split badly: the candidates (those of TRIALS draws of AHEAD
rows, or of the rounds) give AHEAD centres, the least cost of TRIALS reductions, and these are put into the two groups of the least cost.
All are functions of (seed, node code), so every growing schedule gives the same tree.
"""

from __future__ import annotations

import itertools
import zlib

import numpy as np
from pyspark.sql import DataFrame

from tilemine.operators.passes import Split, best, bests, costs, draw, nearest, sums

#: Expected candidates of a round for each centre wanted, and rounds.
OVERSAMPLING, ROUNDS = 2, 4
#: Centres that a split is made from, and trials to find them.
AHEAD, TRIALS = 4, 8
INITS = ("axis", "farthest", "random", "dsquare", "parallel")


def uniform(code: str, ids: np.ndarray, seed: int, draw: int = 0) -> np.ndarray:
    """A number in (0, 1) for each id."""
    with np.errstate(over="ignore"):
        z = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(zlib.crc32(f"{seed}/{draw}/{code}".encode()) * 2654435761 % 2**64)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            z = (z ^ (z >> np.uint64(shift))) * np.uint64(factor)
        z ^= z >> np.uint64(31)
    return (z >> np.uint64(11)).astype(float) / 2**53 + 2.0**-54


def bisector(y0: np.ndarray, y1: np.ndarray) -> Split:
    """w, b with w.x > b exactly where x is nearer to y1."""
    return y1 - y0, float((y1 @ y1 - y0 @ y0) / 2)


def axis_split(n: int, s: np.ndarray, ss: np.ndarray) -> Split:
    d = int(np.argmax(n * ss - s * s))
    w = np.zeros(len(s))
    w[d] = 1.0
    return w, float(s[d] / n)


class _ById:
    def __call__(self, code, ids, x):
        return ids.astype(float)


class _Far:
    def __init__(self, first):
        self.first = first

    def __call__(self, code, ids, x):
        return -((x - self.first[code]) ** 2).sum(1)


class _Random:
    def __init__(self, seed, but=None):
        self.seed, self.but = seed, but or {}

    def __call__(self, code, ids, x):
        u = uniform(code, ids, self.seed)
        return np.where(np.isin(ids, self.but.get(code, [])), 2.0, u)


class _Race:
    def __init__(self, centres, seed, draw):
        self.centres, self.seed, self.draw = centres, seed, draw

    def __call__(self, code, ids, x):
        d = np.min([((x - c) ** 2).sum(1) for c in self.centres[code]], axis=0)
        with np.errstate(divide="ignore"):
            return np.where(d > 0, -np.log(uniform(code, ids, self.seed, self.draw)) / np.where(d > 0, d, 1), np.inf)


def centres(labelled: DataFrame, codes: set[str], init: str, seed: int, k: int = 2) -> dict[str, list[np.ndarray]]:
    """k starting centroids for each code by one of the row-based methods."""
    if init == "farthest":
        first = {c: [v] for c, (_, v, _) in best(labelled, _ById(), codes).items()}
        for _ in range(k - 1):
            found = best(labelled, _FarAll(first), codes)
            first = {c: [*first[c], found[c][1]] for c in first}
        return first
    taken: dict[str, list[int]] = {}
    out: dict[str, list[np.ndarray]] = {}
    for code, (i, v, _) in best(labelled, _Random(seed), codes).items():
        taken[code], out[code] = [i], [v]
    if init == "random":
        for _ in range(k - 1):
            for code, (i, v, score) in best(labelled, _Random(seed, taken), codes).items():
                if score < 2:
                    taken[code].append(i)
                    out[code].append(v)
        return out
    if init == "dsquare":
        for turn in range(1, k):
            for code, (_, v, score) in best(labelled, _Race(out, seed, turn), codes).items():
                if np.isfinite(score):
                    out[code].append(v)
        return out
    return oversampled({c: v[0] for c, v in out.items()}, lambda now: costs(labelled, now), lambda chosen, codes: draw(labelled, chosen, codes), k, seed)


class _Chance:
    """Takes a row with probability wanted x its squared distance / the cost."""

    def __init__(self, centres, cost, wanted, seed, turn):
        self.centres, self.cost, self.wanted, self.seed, self.turn = centres, cost, wanted, seed, turn

    def __call__(self, code, ids, x):
        return uniform(code, ids, self.seed, 1000 + self.turn) < self.wanted * nearest(x, np.array(self.centres[code]))[1] / self.cost[code]


def oversampled(first: dict[str, np.ndarray], cost_of, draw_of, k: int, seed: int, rounds: int = ROUNDS) -> dict[str, list[np.ndarray]]:
    """k centres for each code from over-sampled candidates; ``cost_of`` and ``draw_of`` go over the rows, wherever they are."""
    candidates = rounds_of(first, cost_of, draw_of, k, seed, rounds)
    weights = {c: n for c, (_, n) in cost_of(candidates).items()}
    return {c: weighted_reduction(np.array(v), weights[c].astype(float), k, c, seed) for c, v in candidates.items()}


def rounds_of(first: dict[str, np.ndarray], cost_of, draw_of, k: int, seed: int, rounds: int = ROUNDS) -> dict[str, list[np.ndarray]]:
    """The candidates of each code: the first one and those drawn in the rounds."""
    candidates = {c: [v] for c, v in first.items()}
    for turn in range(rounds):
        cost = {c: phi for c, (phi, _) in cost_of(candidates).items() if phi > 0}
        if not cost:
            break
        for code, rows in draw_of(_Chance({c: candidates[c] for c in cost}, cost, OVERSAMPLING * k, seed, turn), set(cost)).items():
            candidates[code] += [v for _, v in rows]
    return candidates


class _Trials:
    """Scores of several trials at once: the next row by squared distance from those that each trial has, any row for the first."""

    def __init__(self, drawn: dict[str, list[list[np.ndarray]]], seed: int, turn: int):
        self.drawn, self.seed, self.turn = drawn, seed, turn

    def __call__(self, code, ids, x):
        out = np.empty((TRIALS, len(x)))
        for trial, has in enumerate(self.drawn[code]):
            out[trial] = -np.log(uniform(code, ids, self.seed, AHEAD * trial + self.turn))
            if has:
                d = nearest(x, np.array(has))[1]
                out[trial] = np.where(d > 0, out[trial] / np.where(d > 0, d, 1), np.inf)
        return out


def trials_of(codes: set[str], bests_of, seed: int) -> dict[str, list[np.ndarray]]:
    """The candidates of each code: AHEAD rows of each trial; ``bests_of`` goes over the rows, wherever they are."""
    drawn: dict[str, list[list[np.ndarray]]] = {c: [[] for _ in range(TRIALS)] for c in codes}
    for turn in range(AHEAD):
        for (code, trial), (_, v, score) in bests_of(_Trials(drawn, seed, turn), codes).items():
            if np.isfinite(score):
                drawn[code][trial].append(v)
    return {c: [v for has in trials for v in has] for c, trials in drawn.items()}


def looking_ahead(codes: set[str], init: str, seed: int, first_of, bests_of, cost_of, draw_of) -> dict[str, list[np.ndarray]]:
    """Two centres for each code (one if its rows give no more) by ``dsquare`` or ``parallel``; the functions go over the rows."""
    found = trials_of(codes, bests_of, seed) if init == "dsquare" else rounds_of(first_of(codes), cost_of, draw_of, AHEAD, seed)
    weights = {c: n.astype(float) for c, (_, n) in cost_of(found).items()}
    return {c: grouped(np.array(v), weights[c], c, seed) for c, v in found.items()}


def grouped(points: np.ndarray, weights: np.ndarray, code: str, seed: int) -> list[np.ndarray]:
    """Two means of weighted points: AHEAD centres, the best of TRIALS reductions, in the two groups of the least cost; sides differ by one at most."""
    tries = [np.array(weighted_reduction(points, weights, AHEAD, code, seed + trial)) for trial in range(TRIALS)]
    centres = min(tries, key=lambda c: float(weights @ nearest(points, c)[1]))
    n = np.bincount(nearest(points, centres)[0], weights, len(centres))
    sides = [list(side) for side in itertools.combinations(range(len(centres)), (len(centres) + 1) // 2)]
    if len(centres) < 2:
        return list(centres)
    means, least = [], np.inf
    for side in sides:
        both = [np.isin(np.arange(len(centres)), side) == inside for inside in (True, False)]
        if min(n[s].sum() for s in both) > 0:
            pair = [n[s] @ centres[s] / n[s].sum() for s in both]
            cost = sum(float(n[s] @ ((centres[s] - m) ** 2).sum(1)) for s, m in zip(both, pair))
            if cost < least:
                means, least = pair, cost
    return means or list(centres[:1])


def weighted_reduction(points: np.ndarray, weights: np.ndarray, k: int, code: str, seed: int, steps: int = 5) -> list[np.ndarray]:
    """k of weighted points: drawn by weight times squared distance, then moved to weighted means a few times."""
    random = np.random.default_rng(zlib.crc32(f"{seed}/{code}".encode()))
    chosen = [points[int(weights.argmax())]]
    while len(chosen) < k:
        worth = weights * nearest(points, np.array(chosen))[1]
        if not worth.sum() > 0:
            break
        chosen.append(points[int(random.choice(len(points), p=worth / worth.sum()))])
    centres = np.array(chosen)
    for _ in range(steps):
        near = nearest(points, centres)[0]
        total = np.bincount(near, weights, len(centres))
        if not total.all():
            break
        centres = np.array([(points[near == i] * weights[near == i, None]).sum(0) / total[i] for i in range(len(centres))])
    return list(centres)


class _FarAll:
    def __init__(self, chosen):
        self.chosen = chosen

    def __call__(self, code, ids, x):
        return -np.min([((x - c) ** 2).sum(1) for c in self.chosen[code]], axis=0)


def first_splits(labelled: DataFrame, stats: dict[str, dict], init: str, seed: int) -> dict[str, Split]:
    """A first split of each node of ``stats`` (code -> n, s, ss).  Nodes whose rows are all equal have none."""
    codes = {c for c, v in stats.items() if (v["n"] * v["ss"] - v["s"] ** 2).max(initial=0) > 1e-9 * max(1.0, v["ss"].max(initial=0))}
    if init == "axis" or not codes:
        return {c: axis_split(stats[c]["n"], stats[c]["s"], stats[c]["ss"]) for c in codes}
    if init in ("dsquare", "parallel"):
        found = looking_ahead(
            codes, init, seed, lambda codes: {c: v for c, (_, v, _) in best(labelled, _Random(seed), codes).items()}, lambda score, codes: bests(labelled, score, codes), lambda now: costs(labelled, now), lambda chosen, codes: draw(labelled, chosen, codes)
        )
    else:
        found = centres(labelled, codes, init, seed)
    out = {c: bisector(*v[:2]) for c, v in found.items() if len(v) > 1 and (v[0] != v[1]).any()}
    # a draw may give one point only: the row farthest from it makes the other
    return out | farthest_split(labelled, {c: v[0] for c, v in found.items() if c not in out})


def centroids_of(parts: dict[tuple[str, int], dict], code: str) -> list[np.ndarray] | None:
    """Means of a node's two children, None if one of them is empty."""
    both = [parts.get((code, c)) for c in (0, 1)]
    return None if None in both else [p["s"] / p["n"] for p in both]


def farthest_split(labelled: DataFrame, centre: dict[str, np.ndarray]) -> dict[str, Split]:
    """For nodes whose split left a side empty: the row farthest from the mean against the mean."""
    found = best(labelled, _Far(centre), set(centre)) if centre else {}
    return {c: bisector(centre[c], v) for c, (_, v, s) in found.items() if s < 0}


__all__ = ["INITS", "axis_split", "bisector", "centres", "centroids_of", "farthest_split", "first_splits", "oversampled", "sums", "uniform", "weighted_reduction"]
