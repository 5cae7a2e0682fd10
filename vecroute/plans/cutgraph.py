"""Balanced cuts of the routing graph's bottom layer into parts with few crossing edges.

Multilevel: vertices are matched along heavy edges and merged until few are left,
parts are grown on the small graph, and boundary moves improve the cut at every
level on the way back. The graph has one vertex per centre, so this runs on the
driver; with two levels of centres, per branch.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Adjacency = list[dict[int, float]]


def symmetric(links: np.ndarray) -> Adjacency:
    """Undirected weights from a padded neighbour matrix: 1 per direction."""
    out: Adjacency = [{} for _ in range(links.shape[0])]
    for u, row in enumerate(links.tolist()):
        for v in row:
            if v >= 0 and v != u:
                out[u][v] = out[u].get(v, 0) + 1
                out[v][u] = out[v].get(u, 0) + 1
    return out


def cut_size(adjacency: Adjacency, part: np.ndarray) -> float:
    return sum(w for u, near in enumerate(adjacency) for v, w in near.items() if u < v and part[u] != part[v])


def _coarsen(adjacency: Adjacency, weight: np.ndarray, limit: float, rng: np.random.Generator) -> tuple[Adjacency, np.ndarray, np.ndarray]:
    mate = np.full(len(adjacency), -1)
    for u in rng.permutation(len(adjacency)).tolist():
        if mate[u] >= 0:
            continue
        best, pick = -1.0, u
        for v, w in adjacency[u].items():
            if mate[v] < 0 and v != u and weight[u] + weight[v] <= limit:
                s = w / max(weight[u] * weight[v], 1e-9)
                if s > best or s == best and v < pick:
                    best, pick = s, v
        mate[u], mate[pick] = pick, u
    first = np.minimum(np.arange(len(adjacency)), mate)
    heads, up = np.unique(first, return_inverse=True)
    merged: Adjacency = [{} for _ in range(heads.size)]
    for u, near in enumerate(adjacency):
        mine = merged[up[u]]
        for v, w in near.items():
            if up[v] != up[u]:
                mine[up[v]] = mine.get(up[v], 0) + w
    return merged, np.bincount(up, weights=weight), up


def _grow(adjacency: Adjacency, weight: np.ndarray, w: int, rng: np.random.Generator) -> np.ndarray:
    n = len(adjacency)
    part, load = np.full(n, -1), np.zeros(w)
    pull = np.zeros((n, w))
    seeds = [int(rng.integers(n))]
    hop = np.full(n, np.inf)
    while len(seeds) < min(w, n):
        wave, d = [seeds[-1]], 0
        seen = {seeds[-1]}
        while wave:
            for u in wave:
                hop[u] = min(hop[u], d)
            wave = [v for v in {v for u in wave for v in adjacency[u]} if v not in seen]
            seen.update(wave)
            d += 1
        far = np.where(np.isinf(hop), 1e9, hop)
        far[seeds] = -1
        seeds.append(int(far.argmax()))

    def put(u: int, p: int) -> None:
        part[u] = p
        load[p] += weight[u]
        for v, e in adjacency[u].items():
            pull[v, p] += e

    for p, s in enumerate(seeds):
        put(s, p)
    for _ in range(n - len(seeds)):
        p = int(load.argmin())
        free = np.flatnonzero(part < 0)
        gain = pull[free, p] - 0.5 * (pull[free].sum(axis=1) - pull[free, p])
        gain = np.where(pull[free, p] > 0, gain, gain - 1e6)
        put(int(free[gain.argmax()]), p)
    return part


def _refine(adjacency: Adjacency, weight: np.ndarray, part: np.ndarray, w: int, most: float, passes: int = 6) -> np.ndarray:
    load = np.bincount(part, weights=weight, minlength=w)
    members = np.bincount(part, minlength=w)
    for _ in range(passes):
        moved = 0
        for u in range(len(adjacency)):
            p = part[u]
            if members[p] <= 1:
                continue
            pull: dict[int, float] = {}
            for v, e in adjacency[u].items():
                pull[part[v]] = pull.get(part[v], 0) + e
            here, best, to = pull.get(p, 0), 0.0, -1
            over = load[p] > most
            options = set(pull) | ({int(load.argmin())} if over else set())
            for q in options - {p}:
                if load[q] + weight[u] > most and not (over and load[q] + weight[u] < load[p]):
                    continue
                gain = pull.get(q, 0) - here + (1e-6 if load[q] + weight[u] < load[p] else 0) + (1e3 if over else 0)
                if gain > best or gain == best and to >= 0 and load[q] < load[to]:
                    best, to = gain, q
            if to >= 0:
                part[u] = to
                load[p] -= weight[u]
                load[to] += weight[u]
                members[p] -= 1
                members[to] += 1
                moved += 1
        if not moved:
            break
    return part


def _fill_empty(part: np.ndarray, weight: np.ndarray, w: int) -> np.ndarray:
    for p in range(w):
        if not (part == p).any():
            load = np.bincount(part, weights=weight, minlength=w)
            count = np.bincount(part, minlength=w)
            load[count < 2] = -1
            rich = np.flatnonzero(part == load.argmax())
            if rich.size < 2:
                break
            half, total = rich[np.argsort(-weight[rich], kind="stable")], 0.0
            for u in half[: rich.size // 2]:
                if total + weight[u] <= weight[rich].sum() / 2 or total == 0:
                    part[u] = p
                    total += weight[u]
    return part


def partition(adjacency: Adjacency, weight: np.ndarray, w: int, imbalance: float = 0.05, seed: int = 42, starts: int = 4) -> np.ndarray:
    """Part of each vertex; every part non-empty if there are vertices enough."""
    n = len(adjacency)
    if n <= w:
        return np.arange(n)
    weight = np.asarray(weight, np.float64) + 1e-9
    rng = np.random.default_rng(seed)
    ideal = weight.sum() / w
    most = max(ideal * (1 + imbalance), weight.max())
    levels, ups = [(adjacency, weight)], []
    while len(levels[-1][0]) > max(20 * w, 40):
        small, heavier, up = _coarsen(*levels[-1], ideal / 4, rng)
        if len(small) > 0.95 * len(levels[-1][0]):
            break
        levels.append((small, heavier))
        ups.append(up)
    best, least = None, np.inf
    for _ in range(starts):
        trial = _refine(*levels[-1], _grow(*levels[-1], w, rng), w, most)
        load = np.bincount(trial, weights=levels[-1][1], minlength=w).max()
        cost = cut_size(levels[-1][0], trial) * (1 + max(0.0, load / most - 1) * 10)
        if cost < least:
            best, least = trial.copy(), cost
    part = best
    for (near, heavy), up in zip(levels[-2::-1], ups[::-1], strict=True):
        part = _refine(near, heavy, part[up], w, most)
    return _refine(adjacency, weight, _fill_empty(part, weight, w), w, most, 2)


def modulo(ids: np.ndarray, w: int, step: int = 1) -> np.ndarray:
    return (ids // step) % w


def random(n: int, w: int, seed: int = 42) -> np.ndarray:
    """A balanced random split."""
    return np.random.default_rng(seed).permutation(np.arange(n) % w)


def coarse_kmeans(matrix: np.ndarray, w: int, seed: int = 42, iters: int = 10) -> np.ndarray:
    """Centres grouped by k-means of the centres; balance is left to chance."""
    rng = np.random.default_rng(seed)
    c = matrix[rng.choice(len(matrix), min(w, len(matrix)), replace=False)].copy()
    for _ in range(iters):
        at = (2 * matrix @ c.T - (c * c).sum(axis=1)).argmax(axis=1)
        for j in np.unique(at):
            c[j] = matrix[at == j].mean(axis=0)
    return at


def label_prop(edges: DataFrame, labels: DataFrame, rounds: int = 3) -> DataFrame:
    """Parts by label propagation in joins: ``node, sub_id`` from ``a, b, weight`` and a first labelling.

    Each round a node takes the label of most incident weight, ties to the smaller.
    """
    both = edges.select("a", "b", "weight").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "weight"))
    for _ in range(rounds):
        votes = both.join(labels.select(F.col("node").alias("b"), "sub_id"), "b").groupBy("a", "sub_id").agg(F.sum("weight").alias("v"))
        won = votes.groupBy("a").agg(F.max(F.struct("v", (-F.col("sub_id")).alias("n"))).alias("m")).select(F.col("a").alias("node"), (-F.col("m.n")).cast("int").alias("won"))
        labels = labels.join(won, "node", "left").select("node", F.coalesce("won", "sub_id").alias("sub_id"))
    return labels
