"""Layered proximity graphs in numpy, for one part at a time.

A graph keeps, per layer, a padded neighbour matrix over the nodes of that layer.
Searches run many queries in lockstep: each step expands the best open vertex of
every live query, scores all their unseen neighbours at once and keeps the best
``l``. As only the best ``l`` are ever kept, a query ends when none of them is open.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass, field

import numpy as np

from vecroute.functions.kernels import best_pairs, nearest_rows, prepared, rank_matrix, scores_at


def draw_level(ids: np.ndarray, seed: int, degree: int) -> np.ndarray:
    """Top layer of each item by the exponential law, from a hash of (seed, id)."""
    with np.errstate(over="ignore"):
        z = ids.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x9E3779B97F4A7C15) & (2**64 - 1))
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        z ^= z >> np.uint64(31)
    u = ((z >> np.uint64(11)).astype(np.float64) + 0.5) / 2**53
    return np.floor(-np.log(u) / math.log(degree)).astype(np.int64)


@dataclass
class Layer:
    nodes: np.ndarray  # positions of the layer's nodes, ascending
    links: np.ndarray  # padded with -1; rows follow ``nodes``, entries are positions
    row_of: np.ndarray = field(repr=False, default=None)

    def __post_init__(self) -> None:
        if self.row_of is None:
            self.row_of = np.full(int(self.nodes.max(initial=-1)) + 1, -1, np.int64)
            self.row_of[self.nodes] = np.arange(self.nodes.size)


@dataclass
class Graph:
    ids: np.ndarray
    x: np.ndarray  # prepared vectors
    metric: str
    layers: list[Layer]
    entry: int
    degree: int
    degree0: int

    @property
    def n(self) -> int:
        return self.ids.size


@dataclass
class Stats:
    hops: np.ndarray
    evals: np.ndarray


def _walk(graph: Graph, layer: Layer, q: np.ndarray, start: np.ndarray, width: int, stats: Stats, max_evals: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Best ``width`` vertices (positions, rank values) per query on one layer, best first."""
    live, n_q = np.arange(q.shape[0]), q.shape[0]
    x, norms = graph.x, (graph.x**2).sum(axis=1) if graph.metric == "l2" else None

    def value(rows: np.ndarray, at: np.ndarray) -> np.ndarray:
        g = np.einsum("ij,ij->i", q[rows], x[at])
        return 2 * g - norms[at] if norms is not None else g

    seen = np.zeros((n_q, graph.n + 1), bool)
    beam = np.full((n_q, width), -1, np.int64)
    worth = np.full((n_q, width), -np.inf)
    open_ = np.zeros((n_q, width), bool)
    m = min(start.shape[1], width)
    first = value(np.repeat(live, start.shape[1]), np.maximum(start, 0).reshape(-1)).reshape(start.shape)
    first[start < 0] = -np.inf
    order = np.argsort(-first, axis=1, kind="stable")[:, :m]
    beam[:, :m], worth[:, :m] = np.take_along_axis(start, order, 1), np.take_along_axis(first, order, 1)
    open_[:, :m] = (beam[:, :m] >= 0) & np.isfinite(worth[:, :m])
    seen[np.arange(n_q)[:, None], start] = True
    seen[:, -1] = True
    stats.evals[live] += (start >= 0).sum(axis=1)
    while live.size:
        at = open_[live].argmax(axis=1)  # the beam is in order, so the first open vertex is the best
        going = open_[live, at]
        if max_evals is not None:
            going &= stats.evals[live] < max_evals
        live, at = live[going], at[going]
        if not live.size:
            break
        open_[live, at] = False
        stats.hops[live] += 1
        near = layer.links[layer.row_of[beam[live, at]]]
        fresh = ~seen[live[:, None], near]
        if max_evals is not None:
            fresh &= np.cumsum(fresh, axis=1) <= (max_evals - stats.evals[live])[:, None]
        pair, column = np.nonzero(fresh)
        at, rows = near[pair, column], live[pair]
        seen[rows, at] = True
        stats.evals[live] += fresh.sum(axis=1)
        gain = value(rows, at)
        enters = ~(gain <= worth[rows, -1])  # what is no better than a full beam's last stays out
        if not enters.any():
            continue
        at, gain, (rows, row) = at[enters], gain[enters], np.unique(rows[enters], return_inverse=True)
        place = width + np.arange(row.size) - np.searchsorted(row, row, "left")
        shape = (rows.size, int(place.max()) + 1)
        all_at, all_worth, all_open = np.full(shape, -1, np.int64), np.full(shape, -np.inf), np.zeros(shape, bool)
        all_at[:, :width], all_worth[:, :width], all_open[:, :width] = beam[rows], worth[rows], open_[rows]
        all_at[row, place], all_worth[row, place], all_open[row, place] = at, gain, np.isfinite(gain)
        best = np.argsort(-all_worth, axis=1, kind="stable")[:, :width]
        beam[rows], worth[rows], open_[rows] = np.take_along_axis(all_at, best, 1), np.take_along_axis(all_worth, best, 1), np.take_along_axis(all_open, best, 1)
    return beam, worth


def _whole_walk(graph: Graph, q: np.ndarray, start: np.ndarray, k: int, stats: Stats) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query positions, ids, scores) of the best ``k`` where the beam holds all vertices.

    Such a walk expands every vertex it can reach, in whatever order, so queries share the
    waves. It sets out from the graph's entry too: ``repair`` makes all reachable from
    there, not from every vertex that the upper layers lead to.
    """
    metric = "ip" if graph.metric == "cosine" else graph.metric  # vectors are prepared
    found = []
    whole = reachable(graph)
    groups = [(whole, np.arange(len(q)))] if whole.all() else [(reachable(graph, [graph.entry, int(v)]), np.flatnonzero(start == v)) for v in np.unique(start)]
    for hit, rows in groups:
        row, ids, scores = best_pairs(q[rows], graph.x[hit], graph.ids[hit], k, metric)
        found.append((rows[row], ids, scores))
        stats.hops[rows] += int(hit.sum())
        stats.evals[rows] += int(hit.sum())
    row, ids, scores = (np.concatenate(c) for c in zip(*found, strict=True))
    order = np.argsort(row, kind="stable")
    return row[order], ids[order], scores[order]


def search(graph: Graph, queries: np.ndarray, k: int, l: int = 100, max_evals: int | None = None, block: int = 256) -> tuple[np.ndarray, np.ndarray, Stats]:  # noqa: E741
    """(ids, scores, stats): the best ``k`` found per query, padded with -1 and -inf.

    ``l`` is the beam on the bottom layer, at least ``k``; 1 gives the greedy walk.
    ``max_evals`` caps the similarities computed per query.
    """
    q = prepared(np.atleast_2d(queries), graph.metric)
    total = Stats(np.zeros(q.shape[0], np.int64), np.zeros(q.shape[0], np.int64))
    out_ids, out_scores = np.full((q.shape[0], k), -1, np.int64), np.full((q.shape[0], k), -np.inf)
    if graph.n == 0:
        return out_ids, out_scores, total
    width = min(max(l, k), graph.n)
    for s in range(0, q.shape[0], block):
        part = q[s : s + block]
        stats = Stats(total.hops[s : s + block], total.evals[s : s + block])
        at = np.full((part.shape[0], 1), graph.entry)
        for layer in reversed(graph.layers[1:]):
            at, _ = _walk(graph, layer, part, at, 1, stats, max_evals)
        if width == graph.n and max_evals is None:
            row, ids, scores = _whole_walk(graph, part, at[:, 0], k, stats)
            place = np.arange(row.size) - np.searchsorted(row, row, "left")
            out_ids[s + row, place], out_scores[s + row, place] = ids, scores
            continue
        found, _ = _walk(graph, graph.layers[0], part, at, width, stats, max_evals)
        scores = scores_at(part, graph.x[np.maximum(found, 0)], graph.metric)
        scores[found < 0] = -np.inf
        ids = np.where(found >= 0, graph.ids[np.maximum(found, 0)], np.iinfo(np.int64).max)
        order = np.lexsort((ids, -scores), axis=1)[:, :k]
        m = order.shape[1]
        out_ids[s : s + block, :m] = np.take_along_axis(np.where(found >= 0, ids, -1), order, 1)
        out_scores[s : s + block, :m] = np.take_along_axis(scores, order, 1)
    return out_ids, out_scores, total


def _diverse(x: np.ndarray, metric: str, worth: np.ndarray, candidates: np.ndarray, degree: int) -> np.ndarray:
    """Of candidates (best first), those nearer to the base than to any kept one; topped up in order."""
    if candidates.size <= degree:
        return candidates
    between = rank_matrix(x[candidates], x[candidates], metric)
    if metric == "l2":
        between -= (x[candidates] ** 2).sum(axis=1)[:, None]
    kept: list[int] = []
    closest = np.full(candidates.size, -np.inf)  # to any kept one
    columns, values = np.ascontiguousarray(between.T), worth.tolist()
    for i in range(candidates.size):
        if len(kept) == degree:
            break
        if not kept or values[i] > closest[i]:
            kept.append(i)
            np.maximum(closest, columns[i], out=closest)
    if len(kept) < degree:
        chosen = set(kept)
        kept += [i for i in range(candidates.size) if i not in chosen][: degree - len(kept)]
    return candidates[np.array(kept, np.int64)]


class _Builder:
    """Item-at-a-time insertion, with adjacency as Python lists."""

    def __init__(self, x: np.ndarray, metric: str, degree: int, degree0: int, l: int, select: str, reverse_edges: bool, carry: str):  # noqa: E741
        self.x, self.metric, self.degree, self.degree0, self.l = x, metric, degree, degree0, l
        self.select, self.reverse_edges, self.carry = select, reverse_edges, carry
        self.links: list[dict[int, list[int]]] = []
        self.entry = -1
        self.square = (x * x).sum(axis=1)

    def worth(self, base: int, at: list[int]) -> np.ndarray:
        at = np.array(at, np.int64)
        g = self.x.take(at, axis=0) @ self.x[base]
        return 2 * g - self.square.take(at) - self.square[base] if self.metric == "l2" else g

    def near(self, layer: int, base: int, start: list[int], width: int) -> list[tuple[float, int]]:
        """Best ``width`` (value, vertex) found from ``start``, best first."""
        values = self.worth(base, start)
        seen = set(start)
        waiting = [(-v, s) for v, s in zip(values.tolist(), start, strict=True)]
        kept = [(v, -s) for v, s in zip(values.tolist(), start, strict=True)]
        heapq.heapify(waiting)
        heapq.heapify(kept)
        while waiting:
            v, at = heapq.heappop(waiting)
            if len(kept) >= width and -v < kept[0][0]:
                break
            fresh = [u for u in self.links[layer][at] if u not in seen]
            if not fresh:
                continue
            seen.update(fresh)
            values = self.worth(base, fresh)
            if len(kept) >= width:  # the bound only rises, so the rest cannot enter
                better = np.flatnonzero(values > kept[0][0]).tolist()
                values, fresh = values[better], [fresh[i] for i in better]
            for w, u in zip(values.tolist(), fresh, strict=True):
                if len(kept) < width:
                    heapq.heappush(kept, (w, -u))
                elif w > kept[0][0]:
                    heapq.heapreplace(kept, (w, -u))
                else:
                    continue
                heapq.heappush(waiting, (-w, u))
        return sorted(((w, -u) for w, u in kept), key=lambda p: (-p[0], p[1]))

    def choose(self, found: list[tuple[float, int]], degree: int) -> list[int]:
        if self.select == "nearest":
            return [u for _, u in found[:degree]]
        at = np.array([u for _, u in found], np.int64)
        return _diverse(self.x, self.metric, np.array([w for w, _ in found]), at, degree).tolist()

    def insert(self, node: int, level: int) -> None:
        top = len(self.links) - 1
        while len(self.links) <= level:
            self.links.append({})
        for t in range(level + 1):
            self.links[t][node] = []
        if self.entry < 0:
            self.entry = node
            return
        start = [self.entry]
        for t in range(top, level, -1):
            start = [self.near(t, node, start, 1)[0][1]]
        for t in range(min(level, top), -1, -1):
            found = self.near(t, node, start, self.l)
            limit = self.degree0 if t == 0 else self.degree
            self.links[t][node] = self.choose(found, self.degree)
            if self.reverse_edges:
                for u in self.links[t][node]:
                    mine = self.links[t][u]
                    mine.append(node)
                    if len(mine) > limit:
                        values = self.worth(u, mine)
                        order = np.lexsort((mine, -values))
                        self.links[t][u] = self.choose([(float(values[i]), mine[i]) for i in order], limit)
            start = [found[0][1]] if self.carry == "best" else [u for _, u in found]
        if level > top:
            self.entry = node


def _pack(ids, x, metric, links, entry, degree, degree0) -> Graph:
    layers = []
    for t, adjacency in enumerate(links):
        nodes = np.array(sorted(adjacency), np.int64)
        width = degree0 if t == 0 else degree
        matrix = np.full((nodes.size, width), -1, np.int64)
        for i, u in enumerate(nodes.tolist()):
            row = adjacency[u][:width]
            matrix[i, : len(row)] = row
        layers.append(Layer(nodes, matrix))
    return Graph(ids, x, metric, layers, entry, degree, degree0)


def _ordered(ids: np.ndarray, x: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(ids, kind="stable")
    return np.asarray(ids, np.int64)[order], prepared(np.atleast_2d(x)[order] if len(ids) else np.zeros((0, 1)), metric)


def build(ids: np.ndarray, x: np.ndarray, metric: str = "l2", degree: int = 16, degree0: int = 32, l: int = 100, seed: int = 42, select: str = "heuristic", reverse_edges: bool = True, carry: str = "best", mend: bool = True) -> Graph:  # noqa: E741
    """A graph by insertion in id order; the same for the same items and seed."""
    ids, x = _ordered(ids, x, metric)
    b = _Builder(x, metric, degree, degree0, l, select, reverse_edges, carry)
    for node, level in enumerate(draw_level(ids, seed, degree).tolist()):
        b.insert(node, level)
    graph = _pack(ids, x, metric, b.links or [{}], b.entry, degree, degree0)
    return repair(graph) if mend and reverse_edges else graph


def _diverse_rows(x: np.ndarray, metric: str, worth: np.ndarray, candidates: np.ndarray, degree: int) -> np.ndarray:
    """``_diverse`` for many bases at once; rows of candidates (best first), -1 for none."""
    c = x[np.maximum(candidates, 0)]
    size, own = (c * c).sum(axis=2) if metric == "l2" else None, np.arange(len(c))
    kept, out = np.zeros(candidates.shape, bool), candidates < 0  # out: none, kept, or nearer to a kept one
    for _ in range(degree):
        at = out[own].argmin(axis=1)  # the first that is left
        left = ~out[own, at]
        own, at = own[left], at[left]
        if not own.size:
            break
        kept[own, at] = True
        between = np.einsum("rid,rd->ri", c[own], c[own, at])
        if size is not None:
            between = 2 * between - size[own] - size[own, at][:, None]
        blocked = ~(worth[own] > between)
        blocked[np.arange(own.size), at] = True
        out[own] |= blocked
    order = np.argsort(np.where(candidates < 0, 2, np.where(kept, 0, 1)).astype(np.int8), axis=1, kind="stable")[:, :degree]
    return np.take_along_axis(candidates, order, 1)


def build_bulk(ids: np.ndarray, x: np.ndarray, metric: str = "l2", degree: int = 16, degree0: int = 32, seed: int = 42, block: int = 1024, near0: tuple[np.ndarray, np.ndarray] | None = None) -> Graph:
    """The same kind of graph from blocked exact neighbours per layer: matrix products in place of walks.

    Half of a node's links go to diverse near neighbours, the other half is filled with
    the nearest of those that link to it. ``near0`` is what ``nearest_rows`` gives for the
    prepared items in id order, ``2 * degree0`` of each or all, where it is known.
    """
    ids, x = _ordered(ids, x, metric)
    level = draw_level(ids, seed, degree)
    square = (x * x).sum(axis=1)
    layers: list[Layer] = []
    for t in range(int(level.max(initial=0)) + 1):
        nodes = np.flatnonzero(level >= t)
        n, width = nodes.size, degree0 if t == 0 else degree
        half, pool = width // 2, min(2 * width, nodes.size - 1)
        near = x[nodes]
        chosen = np.full((n, half), -1, np.int64)
        part, value = nearest_rows(near, max(0, pool), metric) if t or near0 is None else near0
        for s in range(0, n if pool > 0 else 0, block):
            worth = value[s : s + block] - (square[nodes[s : s + block]][:, None] if metric == "l2" else 0)
            found = _diverse_rows(near, metric, worth, part[s : s + block], half)
            chosen[s : s + block, : found.shape[1]] = found
        links = np.full((n, width), -1, np.int64)
        links[:, :half] = chosen
        source, column = np.nonzero(chosen >= 0)
        target = chosen[source, column]
        if target.size:
            fresh = ~(chosen[target] == source[:, None]).any(axis=1)
            source, target = source[fresh], target[fresh]
            gain = np.concatenate([np.einsum("ij,ij->i", near[target[i : i + 65536]], near[source[i : i + 65536]]) for i in range(0, target.size, 65536)]) if target.size else np.zeros(0)
            if metric == "l2":
                gain = 2 * gain - square[nodes[source]]
            order = np.lexsort((source, -gain, target))
            source, target = source[order], target[order]
            place = np.arange(target.size) - np.searchsorted(target, target, "left") + half
            room = place < width
            links[target[room], place[room]] = source[room]
        links = np.where(links >= 0, nodes[np.maximum(links, 0)], -1)
        order = np.argsort(links < 0, axis=1, kind="stable")
        layers.append(Layer(nodes, np.take_along_axis(links, order, 1)))
    top = np.flatnonzero(level == level.max(initial=0))
    graph = Graph(ids, x, metric, layers, int(top[0]) if top.size else -1, degree, degree0)
    return repair(graph)


def reachable(graph: Graph, start: list[int] | None = None) -> np.ndarray:
    """Vertices of the bottom layer that a walk from the entry can reach."""
    hit = np.zeros(graph.n, bool)
    if graph.n == 0:
        return hit
    wave = np.array(start if start is not None else [graph.entry], np.int64)
    hit[wave] = True
    while wave.size:
        nxt = np.unique(graph.layers[0].links[wave])
        nxt = nxt[nxt >= 0]
        wave = nxt[~hit[nxt]]
        hit[wave] = True
    return hit


def repair(graph: Graph) -> Graph:
    """Links every bottom-layer vertex that cannot be reached from its nearest reachable one with room."""
    links = graph.layers[0].links
    hit = reachable(graph)
    while not hit.all():
        lost = np.flatnonzero(~hit)
        inside = np.flatnonzero(hit)
        room = (links[inside] < 0).any(axis=1)
        if room.any():
            inside = inside[room]
            orphan = int(lost[0])
            g = rank_matrix(graph.x[orphan][None, :], graph.x[inside], graph.metric)[0]
            host = int(inside[np.lexsort((inside, -g))[0]])
            links[host, int(np.argmax(links[host] < 0))] = orphan
        else:  # every reachable vertex is full: widen the matrix
            links = np.concatenate([links, np.full((links.shape[0], 1), -1, np.int64)], axis=1)
            graph.layers[0] = Layer(graph.layers[0].nodes, links)
            continue
        wave = np.array([orphan])
        hit[orphan] = True
        while wave.size:
            nxt = np.unique(links[wave])
            nxt = nxt[nxt >= 0]
            wave = nxt[~hit[nxt]]
            hit[wave] = True
    return graph


def to_row(graph: Graph) -> dict:
    """A graph as plain columns: ids, vectors as bytes, and the layers' links flattened."""
    return {
        "entry": graph.entry, "metric": graph.metric, "degree": graph.degree, "degree0": graph.degree0, "n": graph.n, "d": int(graph.x.shape[1]) if graph.n else 0,
        "item_ids": graph.ids.tolist(), "vectors": graph.x.astype("<f8").tobytes(),
        "levels": [{"layer": t, "width": int(y.links.shape[1]), "nodes": y.nodes.astype(np.int32).tolist(), "targets": y.links.astype(np.int32).reshape(-1).tolist()} for t, y in enumerate(graph.layers)],
    }


def from_row(row: dict) -> Graph:
    n = row["n"]
    x = np.frombuffer(row["vectors"], "<f8").reshape(n, -1) if n else np.zeros((0, 1))
    layers = [Layer(np.array(y["nodes"], np.int64), np.array(y["targets"], np.int64).reshape(-1, y["width"])) for y in sorted(row["levels"], key=lambda y: y["layer"])]
    return Graph(np.array(row["item_ids"], np.int64), x, row["metric"], layers, row["entry"], row["degree"], row["degree0"])


ROW_DDL = "entry int, metric string, degree int, degree0 int, n int, d int, item_ids array<bigint>, vectors binary, levels array<struct<layer: int, width: int, nodes: array<int>, targets: array<int>>>"
