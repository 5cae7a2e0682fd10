"""Dense scoring in numpy: one definition of each similarity for all kernels."""

from __future__ import annotations

import numpy as np


def unit(x: np.ndarray) -> np.ndarray:
    x = np.asarray(x, np.float64)
    n = np.sqrt((x * x).sum(axis=-1, keepdims=True))
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


def prepared(x: np.ndarray, metric: str) -> np.ndarray:
    """Items or queries as the walk sees them: cosine is inner product of unit vectors."""
    return unit(x) if metric == "cosine" else np.ascontiguousarray(x, np.float64)


def rank_matrix(q: np.ndarray, x: np.ndarray, metric: str, square: np.ndarray | None = None) -> np.ndarray:
    """Values that rank as the similarity does; one matrix product. ``square`` holds the squared lengths of ``x`` where they are known."""
    g = q @ x.T
    if metric == "l2":
        g *= 2
        g -= (x * x).sum(axis=1) if square is None else square
    return g


def least_of_best(g: np.ndarray, k: int) -> np.ndarray:
    """At most the ``k``-th best value of each row, and near it.

    Of columns folded onto one another only the best counts, so fewer values are ranked.
    """
    if k == 1:
        return g.max(axis=1)
    fold = max(1, min(8, g.shape[1] // max(1, 4 * k)))
    width = g.shape[1] // fold
    heads = g[:, :width].copy()
    for j in range(1, fold):
        np.maximum(heads, g[:, j * width : (j + 1) * width], out=heads)
    heads.partition(width - k, axis=1)
    return heads[:, width - k]


def score_matrix(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """Similarities of every query to every item."""
    if metric == "l2":
        d = (q * q).sum(axis=1)[:, None] - rank_matrix(q, x, "l2")
        return -np.sqrt(np.maximum(d, 0))
    q, x = prepared(q, metric), prepared(x, metric)
    return q @ x.T


def scores_at(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """Similarities of prepared q[i] to prepared x[i, :], by differences; exact to rounding."""
    if metric == "l2":
        d = x - q[:, None, :]
        return -np.sqrt(np.einsum("ijk,ijk->ij", d, d))
    return np.einsum("ik,ijk->ij", q, x)


def _scores_of(q: np.ndarray, x: np.ndarray, row: np.ndarray, col: np.ndarray, metric: str) -> np.ndarray:
    """Similarities of prepared q[row] to prepared x[col] by differences, so that equal vectors tie exactly."""
    s = np.empty(row.size)
    for at in range(0, row.size, 1 << 16):
        a, b = q[row[at : at + (1 << 16)]], x[col[at : at + (1 << 16)]]
        s[at : at + (1 << 16)] = -np.sqrt(np.einsum("ij,ij->i", b - a, b - a)) if metric == "l2" else np.einsum("ij,ij->i", a, b)
    return s


def pair_scores(q: np.ndarray, x: np.ndarray, row: np.ndarray, col: np.ndarray, metric: str) -> np.ndarray:
    """Similarities of q[row] to x[col]."""
    return _scores_of(prepared(q, metric), prepared(x, metric), row, col, metric)


#: Values of a block of queries and items that are ranked at a time: what stays in a cache.
CELLS = 1 << 20


def best_pairs(q: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, metric: str, skip: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query positions, ids, scores) of the best ``k`` items of each query, best first, ties to the smaller id.

    A matrix product finds candidates, with room for its rounding; they are scored
    again by differences, so equal vectors tie exactly. ``skip`` marks pairs to leave out.
    """
    q, x = prepared(q, metric), prepared(x, metric)
    k = min(k, x.shape[0])
    if not k or not len(q):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    square = (x * x).sum(axis=1) if metric == "l2" else None
    step, found = max(1, CELLS // len(x)), []
    for at in range(0, len(q), step):
        part = q[at : at + step]
        g = rank_matrix(part, x, metric, square)
        if skip is not None:
            g[skip[at : at + step]] = -np.inf
        least = least_of_best(g, k)
        room = 1e-9 * (1 + np.abs(np.where(np.isfinite(least), least, 0)) + ((part * part).sum(axis=1) if metric == "l2" else 0))
        row, col = np.divmod(np.flatnonzero(g >= (least - room)[:, None]), len(x))
        sound = np.isfinite(g[row, col])
        found.append((row[sound] + at, col[sound]))
    row, col = (np.concatenate(c) for c in zip(*found, strict=True))
    s = _scores_of(q, x, row, col, metric)
    order = np.lexsort((ids[col], -s, row))
    row, col, s = row[order], col[order], s[order]
    keep = np.arange(row.size) - np.searchsorted(row, row, "left") < k
    return row[keep], ids[col[keep]], s[keep]


def best_columns(q: np.ndarray, x: np.ndarray, k: int, metric: str, width: int = 8192) -> np.ndarray:
    """Positions in ``x`` of the best ``k`` of each query, best first, ties to the smaller position; padded with -1."""
    found = [best_pairs(q, x[a : a + width], np.arange(a, min(a + width, len(x))), k, metric) for a in range(0, len(x), width)]
    out = np.full((len(q), min(k, len(x))), -1, np.int64)
    if found:
        row, col, s = (np.concatenate(c) for c in zip(*found, strict=True))
        order = np.lexsort((col, -s, row))
        row, col = row[order], col[order]
        place = np.arange(row.size) - np.searchsorted(row, row, "left")
        best = place < k
        out[row[best], place[best]] = col[best]
    return out


def nearest_rows(x: np.ndarray, k: int, metric: str, block: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """(positions, values of ``rank_matrix``) of the ``k`` best other rows of each prepared row, best first, ties to the smaller position.

    Blocks are small enough to stay in a core's cache; only what reaches ``least_of_best`` is sorted.
    """
    n = len(x)
    at, worth = np.zeros((n, k), np.int64), np.zeros((n, k))
    for s in range(0, n if k > 0 else 0, block):
        g = rank_matrix(x[s : s + block], x, metric)
        np.fill_diagonal(g[:, s:], -np.inf)
        least = least_of_best(g, k)
        row, col = np.divmod(np.flatnonzero(~(g < least[:, None])), n)
        place = np.arange(row.size) - np.searchsorted(row, row, "left")
        found = np.zeros((len(g), int(place.max()) + 1), np.int64)
        value = np.full(found.shape, -np.inf)
        found[row, place], value[row, place] = col, g[row, col]
        order = np.argsort(-value, axis=1, kind="stable")[:, :k]
        at[s : s + block], worth[s : s + block] = np.take_along_axis(found, order, 1), np.take_along_axis(value, order, 1)
    return at, worth


def pairs_from(q: np.ndarray, x: np.ndarray, ids: np.ndarray, least: float, metric: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query positions, ids, scores) of all pairs whose similarity is ``least`` or more.

    A matrix product finds candidates, with room for its rounding; they are scored
    again by differences.
    """
    q, x = prepared(q, metric), prepared(x, metric)
    if not len(q) or not len(x) or (metric == "l2" and least > 0):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    squares = (q * q).sum(axis=1) if metric == "l2" else np.zeros(len(q))
    bound = squares - least * least if metric == "l2" else np.full(len(q), float(least))
    room = 1e-9 * (1 + np.abs(bound) + squares + (q * q).sum(axis=1) ** 0.5 * (x * x).sum(axis=1).max() ** 0.5)
    row, col = np.nonzero(rank_matrix(q, x, metric) >= (bound - room)[:, None])
    s = _scores_of(q, x, row, col, metric)
    keep = s >= least
    return row[keep], ids[col[keep]], s[keep]


def top_k(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, scores) of the best k per row, ties to the smaller id; rows may be shorter than k wide."""
    k = min(k, scores.shape[1])
    order = np.lexsort((np.broadcast_to(ids, scores.shape), -scores), axis=1)[:, :k]
    return np.take_along_axis(np.broadcast_to(ids, scores.shape), order, 1), np.take_along_axis(scores, order, 1)
