"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics of the whole text are cut into quantile bins; trees grow level by level
from histograms of the logistic loss's gradients, all of a level's nodes at once.
A fitted model is five flat arrays over the nodes of all trees, and scoring walks
every (row, tree) pair one level per numpy step.

The model is fitted on the driver from at most ``SAMPLE`` labelled rows, the first
by a seeded hash; everything else covers all rows. Scores never see labels, ids,
languages or sources.

Defined cases: null text scores as empty text; without labels of both kinds the
score is the share of label 1 (0.5 without any); labels of unknown value are left
out; equal ids are scored row by row; an empty table gives no rows; extra columns
are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecroute.llm.ranks import seeded_key
from vecroute.llm.words import duplicate_lines, repeated_window_words, words_of

SAMPLE = 20_000
THRESHOLD = 0.3
SEED = 4

FEATURES = (
    "log_words", "chars_per_word", "word_length_spread", "upper_share", "digit_share", "symbol_per_word", "exclaim_per_word", "bar_per_word", "comma_per_word", "stop_per_word",
    "other_ascii_per_word", "wide_share", "lines_per_word", "duplicate_line_share", "repeat_word_share", "distinct_share", "top_word_share", "short_word_share", "byte_entropy", "letter_share",
)

_CLASS = np.zeros(256, np.int64)
_CLASS[65:91] = 1
_CLASS[97:123] = 2
_CLASS[48:58] = 3
for _c in b"#*$%&<>@^~=+_\\/":
    _CLASS[_c] = 4
_CLASS[ord("!")], _CLASS[ord("|")], _CLASS[ord(",")], _CLASS[ord(".")] = 5, 6, 7, 8
_CLASS[33:127] = np.where(_CLASS[33:127] == 0, 9, _CLASS[33:127])
_CLASS[128:] = 10


def statistics(text: str | None) -> np.ndarray:
    """FEATURES of one whole text; zeros for an empty one."""
    text = text or ""
    out = np.zeros(len(FEATURES))
    words = words_of(text)
    n = len(words)
    if not n:
        return out
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    counts = np.bincount(raw, minlength=256)
    kinds = np.bincount(_CLASS, weights=counts, minlength=11)
    lengths = np.fromiter(map(len, words), np.int64, n)
    tally: dict[bytes, int] = {}
    for w in words:
        tally[w] = tally.get(w, 0) + 1
    p = counts[counts > 0] / raw.size
    letters = kinds[1] + kinds[2]
    lines = text.count("\n") + 1
    solid = float(lengths.sum())
    out[:] = (
        np.log1p(n), lengths.mean(), lengths.std(), kinds[1] / max(1.0, letters), kinds[3] / solid, kinds[4] / n, kinds[5] / n, kinds[6] / n, kinds[7] / n, kinds[8] / n,
        kinds[9] / n, kinds[10] / solid, lines / n, duplicate_lines(text) / lines, repeated_window_words(words) / n, len(tally) / n, max(tally.values()) / n, float((lengths <= 3).mean()), -(p * np.log2(p)).sum(), letters / solid,
    )
    return out


@dataclass(frozen=True)
class Model:
    """All trees in flat arrays; a leaf points to itself."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    roots: np.ndarray
    depth: int
    base: float

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(x.shape[0], self.base)
        for at in range(0, x.shape[0], 2048):
            part = x[at : at + 2048]
            node = np.broadcast_to(self.roots, (part.shape[0], self.roots.size))
            rows = np.arange(part.shape[0])[:, None]
            for _ in range(self.depth):
                go_left = part[rows, self.feature[node]] <= self.threshold[node]
                node = np.where(go_left, self.left[node], self.right[node])
            out[at : at + 2048] += self.value[node].sum(axis=1)
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 64, leaf_rows: int = 10, ridge: float = 1.0) -> Model:
    """Boosted trees for labels 0 and 1."""
    n, n_features = x.shape if x.ndim == 2 else (0, len(FEATURES))
    mean = float(y.mean()) if n else 0.5
    base = float(np.log(np.clip(mean, 1e-6, 1 - 1e-6) / (1 - np.clip(mean, 1e-6, 1 - 1e-6))))
    feature, threshold, left, right, value, roots = [], [], [], [], [], []
    if n and 0 < mean < 1:
        edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for f in range(n_features)]
        binned = np.stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)], axis=1)
        margin = np.full(n, base)
        for _ in range(trees):
            prob = 1 / (1 + np.exp(-margin))
            grad, hess = prob - y, np.maximum(prob * (1 - prob), 1e-9)
            first = len(feature)
            roots.append(first)
            node = np.full(n, first)
            feature.append(0), threshold.append(0.0), left.append(first), right.append(first), value.append(-grad.sum() / (hess.sum() + ridge) * rate)
            level = [first]
            for _ in range(depth):
                if not level:
                    break
                place = np.full(len(feature), -1)
                place[level] = np.arange(len(level))
                at = place[node]
                live = at >= 0
                best = np.zeros(len(level))
                choice: list[tuple | None] = [None] * len(level)
                for f in range(n_features):
                    key = at[live] * bins + binned[live, f]
                    shape = (len(level), bins)
                    size = len(level) * bins
                    g = np.bincount(key, grad[live], size).reshape(shape).cumsum(axis=1)
                    h = np.bincount(key, hess[live], size).reshape(shape).cumsum(axis=1)
                    c = np.bincount(key, minlength=size).reshape(shape).cumsum(axis=1)
                    gt, ht, ct = g[:, -1:], h[:, -1:], c[:, -1:]
                    gain = g**2 / (h + ridge) + (gt - g) ** 2 / (ht - h + ridge) - gt**2 / (ht + ridge)
                    gain[(c < leaf_rows) | (ct - c < leaf_rows)] = 0
                    gain[:, len(edges[f]) :] = 0
                    top = gain.argmax(axis=1)
                    for i, b in enumerate(top):
                        if gain[i, b] > best[i] + 1e-9:
                            best[i] = gain[i, b]
                            choice[i] = (f, int(b), g[i, b], h[i, b], gt[i, 0] - g[i, b], ht[i, 0] - h[i, b])
                nxt = []
                for i, parent in enumerate(level):
                    if choice[i] is None:
                        continue
                    f, b, gl, hl, gr, hr = choice[i]
                    a = len(feature)
                    for gs, hs in ((gl, hl), (gr, hr)):
                        k = len(feature)
                        feature.append(0), threshold.append(0.0), left.append(k), right.append(k), value.append(-gs / (hs + ridge) * rate)
                    feature[parent], threshold[parent], left[parent], right[parent] = f, float(edges[f][b]), a, a + 1
                    mine = node == parent
                    node[mine] = np.where(binned[mine, f] <= b, a, a + 1)
                    nxt += [a, a + 1]
                level = nxt
            margin += np.asarray(value)[node]
    if not roots:
        feature, threshold, left, right, value, roots = [0], [0.0], [0], [0], [0.0], [0]
    return Model(np.array(feature), np.array(threshold), np.array(left), np.array(right), np.array(value), np.array(roots), depth, base)


def auc(score: np.ndarray, y: np.ndarray) -> float:
    """Share of (label 1, label 0) pairs in the right order, ties by half."""
    _, inverse, counts = np.unique(score, return_inverse=True, return_counts=True)
    rank = (np.cumsum(counts) - (counts - 1) / 2)[inverse]
    ones = int((y == 1).sum())
    return float((rank[y == 1].sum() - ones * (ones + 1) / 2) / max(1, ones * (y.size - ones)))


def held_out(doc_id: Column) -> Column:
    """Rows whose labels are never learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def statistics_column(text: Column) -> Column:
    def run(texts: pa.Array) -> pa.Array:
        return pa.array([statistics(t.as_py()) for t in texts], pa.list_(pa.float64()))

    return F.arrow_udf(run, "array<double>")(text.cast("string"))


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, seed: int = SEED) -> Model:
    """A model of ``labels.quality`` from at most ``sample`` labelled rows outside the held-out fold."""
    usable = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id")))
    drawn = usable.select("doc_id", F.col("quality").cast("double").alias("y"), seeded_key(seed, F.col("doc_id")).alias("draw")).orderBy("draw", "doc_id", "y").limit(sample)
    joined = docs.select("doc_id", "text").join(F.broadcast(drawn), "doc_id")
    rows = joined.select(statistics_column(F.col("text")).alias("x"), "y", "draw", "doc_id").orderBy("draw", "doc_id", "y").limit(sample).select("x", "y").toArrow()
    x = np.array(rows.column("x").to_pylist()).reshape(-1, len(FEATURES))
    return fit(x, rows.column("y").to_numpy())


def score(text: Column, model: Model) -> Column:
    """Probability of label 1 for a text column."""

    def run(texts: pa.Array) -> pa.Array:
        x = np.array([statistics(t.as_py()) for t in texts]).reshape(-1, len(FEATURES))
        return pa.array(model.score(x))

    return F.arrow_udf(run, "double")(text.cast("string"))


def classify(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, threshold: float = THRESHOLD) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every row."""
    model = train(docs, labels, sample)
    scored = docs.select("doc_id", score(F.col("text"), model).alias("score"))
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
