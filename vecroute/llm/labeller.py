"""Main-text extraction by a recurrent block labeller.

A page is cut into leaf blocks at block-level tags. Each block becomes a vector of
its hashed tag path (tags, classes and ids of its ancestors, plain inline markup apart), hashed words and a few
shares; a bidirectional LSTM in numpy reads the page's whole sequence of blocks and
labels each as main text or not, so a block is judged in the light of the rest of
the page.

The network is trained on the driver from generated pages: articles and
surroundings (menus, headers, footers, sidebars, notices, adverts, forms, reader
comments) in many markup habits, part of them without telling names, all from one
seed. Nothing is learned from the table, so its size plays no part.

Defined cases: null and empty html give the empty text; unclosed or stray tags follow
the usual implied-end rules; an unclosed script or style hides the rest of the page,
other raw elements without an end tag are skipped as tags; a page is read once, so
its cost grows in proportion to its length; a page without main text gives the empty text; equal ids
and repeated rows are treated row by row; an empty table gives no rows; extra columns
are ignored.
"""

from __future__ import annotations

import functools
import html as html_module
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: How HTML elements behave.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style template noscript iframe textarea svg".split())
#: Of these the rest of the page is content if no end tag follows; a start tag of the others is then skipped alone.
RAW_TO_END = frozenset("script style".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q s samp small span strike strong sub sup time tt u var wbr br img".split())
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "tbody": {"thead", "tbody", "tr", "td", "th"}}
#: An implied end tag does not reach beyond these.
SCOPE = frozenset("table ul ol dl select div article section main aside nav header footer form body html".split())

#: Elements nested deeper add no step to a path, as in browsers; their text counts.
DEEPEST = 512

_START = re.compile(r"<(?=[!?a-zA-Z]|/[a-zA-Z])")
_COMMENT = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+(?:>|\Z)", re.S)
_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>")
#: The same where a quote has no partner.
_LOOSE_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>")
_NAMED = re.compile(r"""(?<![\w-])(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
_PARTS = re.compile(r"[a-z]+")

PATH_SLOTS, WORD_SLOTS, SHARES = 512, 128, 8
WIDTH = PATH_SLOTS + WORD_SLOTS + SHARES


@functools.lru_cache(maxsize=32)
def _end_of(tag: str) -> re.Pattern:
    return re.compile(rf"</{re.escape(tag)}(?=[\s/>])", re.I)


@dataclass
class Block:
    path: tuple[str, ...]
    text: str
    link_share: float


def blocks_of(page: str | None) -> list[Block]:
    """Leaf blocks of a page in order, white space collapsed, empty ones left out."""
    page = page or ""
    stack: list[tuple[str, str]] = []
    out: list[Block] = []
    parts: list[str] = []
    linked = 0
    path: tuple[str, ...] = ()
    in_link = 0

    def add(chunk: str) -> None:
        nonlocal linked, path
        if chunk:
            if not parts:
                path = tuple(f"{t} {names}" if names else t for t, names in stack if names or t not in INLINE)
            parts.append(html_module.unescape(chunk) if "&" in chunk else chunk)
            if in_link:
                linked += len(chunk)

    def flush() -> None:
        nonlocal linked, in_link
        if parts:
            raw = "".join(parts)
            text = " ".join(raw.split())
            if text:
                out.append(Block(path, text, min(1.0, linked / max(1, len(raw)))))
            parts.clear()
        linked = 0

    def pop_to(k: int) -> None:
        nonlocal in_link
        in_link -= sum(t == "a" for t, _ in stack[k:])
        del stack[k:]

    at, last = 0, page.rfind(">")
    tags, endless = _TAG, set()
    while True:
        start = _START.search(page, at)
        # After the last closing bracket there is no tag, but a comment may be open.
        if start is None or (start.start() > last and page[start.start() + 1] not in "!?"):
            add(page[at:])
            break
        add(page[at : start.start()])
        m = _COMMENT.match(page, start.start())
        if m:
            at = m.end()
            if m[0].startswith("<![CDATA["):
                add(m[0][9:].removesuffix("]]>"))
            continue
        m = tags.match(page, start.start())
        if m is None:
            # A quote without a partner: from here on quotes protect nothing, so that no text is read twice.
            tags = _LOOSE_TAG
            m = tags.match(page, start.start())
        at = m.end()
        tag = m[2].lower()
        if tag == "br":
            add(" ")
            continue
        block_level = tag not in INLINE
        if block_level:
            flush()
        if m[1]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    pop_to(k)
                    break
            continue
        attributes = m[3]
        if tag in RAW:
            if not attributes.rstrip().endswith("/") and tag not in endless:
                end = _end_of(tag).search(page, at)
                if end:
                    at = page.find(">", end.end()) + 1 or len(page)
                elif tag in RAW_TO_END:
                    at = len(page)
                else:
                    endless.add(tag)
            continue
        if tag in VOID:
            continue
        if block_level:
            closing = CLOSES.get(tag, {"p"})
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] in closing:
                    pop_to(k)
                    break
                if stack[k][0] in SCOPE:
                    break
        names = " ".join(p for found in _NAMED.findall(attributes) for p in _PARTS.findall("".join(found).lower())) if attributes else ""
        if len(stack) < DEEPEST:
            stack.append((tag, names))
        else:
            continue
        in_link += tag == "a"
    flush()
    return out


def _slot(token: str, slots: int) -> int:
    return zlib.crc32(token.encode("utf-8", "surrogatepass")) % slots


@functools.lru_cache(maxsize=4096)
def _path_vector(path: tuple[str, ...]) -> np.ndarray:
    v = np.zeros(PATH_SLOTS, np.float32)
    for depth, step in enumerate(reversed(path)):
        tag, *names = step.split(" ")
        weight = 1.0 if depth < 2 else 0.6
        if tag not in ("html", "body", "div", "span"):
            v[_slot(f"t:{tag}", PATH_SLOTS)] += weight
        for name in names:
            v[_slot(f"n:{name}", PATH_SLOTS)] += weight
    return np.minimum(v, 2)


def vectors(blocks: list[Block]) -> np.ndarray:
    """One row per block."""
    out = np.zeros((len(blocks), WIDTH), np.float32)
    for i, b in enumerate(blocks):
        out[i, :PATH_SLOTS] = _path_vector(b.path)
        words = b.text.lower().encode("utf-8", "surrogatepass").split()
        hashed = np.bincount([zlib.crc32(w.strip(b".,;:!?()")) % WORD_SLOTS for w in words], minlength=WORD_SLOTS)
        out[i, PATH_SLOTS : PATH_SLOTS + WORD_SLOTS] = hashed / np.sqrt((hashed * hashed).sum())
        stops = sum(map(b.text.count, ".,;:!?。、，！？"))
        n = len(b.text)
        out[i, -SHARES:] = (min(1.5, np.log1p(len(words)) / 5), min(1.5, np.log1p(n) / 8), b.link_share, min(1.0, stops / len(words)), min(1.0, 20 * stops / n), i / max(1, len(blocks) - 1), float(b.text[-1] in ".!?。！？"), float(len(words) > 12 or n > 80))
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Lstm:
    """One direction; gates in the order input, forget, output, candidate."""

    @staticmethod
    def init(rng: np.random.Generator, width: int, hidden: int, kind: type = np.float64) -> dict[str, np.ndarray]:
        bias = np.zeros(4 * hidden, kind)
        bias[hidden : 2 * hidden] = 1
        return {"x": (rng.standard_normal((width, 4 * hidden)) * (1 / width) ** 0.5).astype(kind), "h": (rng.standard_normal((hidden, 4 * hidden)) * (1 / hidden) ** 0.5).astype(kind), "b": bias}

    @staticmethod
    def forward(p: dict[str, np.ndarray], x: np.ndarray, mask: np.ndarray, keep: bool = False):
        """x: steps, pages, width. Masked steps pass the state on."""
        steps, pages, _ = x.shape
        hidden = p["h"].shape[0]
        kind = p["h"].dtype
        h, c = np.zeros((pages, hidden), kind), np.zeros((pages, hidden), kind)
        out, saved = np.empty((steps, pages, hidden), kind), []
        fed = x @ p["x"] + p["b"]
        for t in range(steps):
            z = fed[t] + h @ p["h"]
            gates = _sigmoid(z[:, : 3 * hidden])
            i, f, o = gates[:, :hidden], gates[:, hidden : 2 * hidden], gates[:, 2 * hidden :]
            g = np.tanh(z[:, 3 * hidden :])
            m = mask[t][:, None]
            c_new = np.where(m, f * c + i * g, c)
            tanh_c = np.tanh(c_new)
            h_new = np.where(m, o * tanh_c, h)
            if keep:
                saved.append((h, c, i, f, o, g, tanh_c))
            h, c = h_new, c_new
            out[t] = h
        return out, saved

    @staticmethod
    def backward(p: dict[str, np.ndarray], x: np.ndarray, mask: np.ndarray, saved: list, d_out: np.ndarray) -> dict[str, np.ndarray]:
        steps, pages, _ = x.shape
        hidden = p["h"].shape[0]
        kind = p["h"].dtype
        d_fed = np.zeros((steps, pages, 4 * hidden), kind)
        d_h, d_c, d_hh = np.zeros((pages, hidden), kind), np.zeros((pages, hidden), kind), np.zeros_like(p["h"])
        for t in range(steps - 1, -1, -1):
            h, c, i, f, o, g, tanh_c = saved[t]
            m = mask[t][:, None]
            d_h = d_h + d_out[t]
            live = d_h * m
            dc = d_c + live * o * (1 - tanh_c**2)
            z = np.concatenate([dc * g * i * (1 - i), dc * c * f * (1 - f), live * tanh_c * o * (1 - o), dc * i * (1 - g**2)], axis=1) * m
            d_fed[t] = z
            d_hh += h.T @ z
            d_h = np.where(m, z @ p["h"].T, d_h)
            d_c = np.where(m, dc * f, d_c)
        flat = d_fed.reshape(-1, 4 * hidden)
        return {"x": x.reshape(-1, x.shape[2]).T @ flat, "h": d_hh, "b": flat.sum(axis=0)}


def _padded(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    steps = max(p.shape[0] for p in pages)
    x, mask = np.zeros((steps, len(pages), WIDTH), np.float32), np.zeros((steps, len(pages)), bool)
    for k, p in enumerate(pages):
        x[: p.shape[0], k], mask[: p.shape[0], k] = p, True
    return x, mask


@dataclass
class Labeller:
    """A bidirectional LSTM with a linear read-out."""

    forward: dict[str, np.ndarray]
    backward: dict[str, np.ndarray]
    read_out: dict[str, np.ndarray]

    @staticmethod
    def _hidden(params, x, mask, keep=False):
        a, saved_a = Lstm.forward(params[0], x, mask, keep)
        b, saved_b = Lstm.forward(params[1], x[::-1], mask[::-1], keep)
        return np.concatenate([a, b[::-1]], axis=2), saved_a, saved_b

    def probabilities(self, pages: list[np.ndarray]) -> list[np.ndarray]:
        """Probability of main text for each block of each page."""
        out: list[np.ndarray] = [np.zeros(0)] * len(pages)
        order = sorted((k for k, p in enumerate(pages) if p.shape[0]), key=lambda k: pages[k].shape[0])
        at = 0
        while at < len(order):
            longest = pages[order[min(at + 127, len(order) - 1)]].shape[0]
            some = order[at : at + max(1, min(128, 40_000 // longest))]
            x, mask = _padded([pages[k] for k in some])
            hidden, _, _ = self._hidden((self.forward, self.backward), x, mask)
            p = _sigmoid(hidden @ self.read_out["w"] + self.read_out["b"])
            for j, k in enumerate(some):
                out[k] = p[: pages[k].shape[0], j]
            at += len(some)
        return out


def train(pages: list[tuple[np.ndarray, np.ndarray]], hidden: int = 24, rounds: int = 4, batch: int = 32, rate: float = 0.02, wordless: float = 0.3, seed: int = 5) -> Labeller:
    """Adam on the mean cross-entropy of the blocks, with a rate that falls to nothing."""
    rng = np.random.default_rng(seed)
    params = [Lstm.init(rng, WIDTH, hidden, np.float32), Lstm.init(rng, WIDTH, hidden, np.float32), {"w": (rng.standard_normal(2 * hidden) * 0.1).astype(np.float32), "b": np.zeros(1, np.float32)}]
    first = [{k: np.zeros_like(v) for k, v in p.items()} for p in params]
    second = [{k: np.zeros_like(v) for k, v in p.items()} for p in params]
    step = 0
    for _ in range(rounds):
        order = sorted(rng.permutation(len(pages)).tolist(), key=lambda k: pages[k][0].shape[0] // 8)
        starts = rng.permutation(np.arange(0, len(order), batch))
        for s in starts:
            some = [pages[k] for k in order[s : s + batch]]
            x, mask = _padded([p for p, _ in some])
            # Pages without words, so that tags and order suffice.
            x[:, rng.random(len(some)) < wordless, PATH_SLOTS : PATH_SLOTS + WORD_SLOTS] = 0
            y = np.zeros(mask.shape, np.float32)
            for k, (_, labels) in enumerate(some):
                y[: labels.size, k] = labels
            h, saved_a, saved_b = Labeller._hidden(params, x, mask, keep=True)
            d = (_sigmoid(h @ params[2]["w"] + params[2]["b"]) - y) * mask / np.float32(mask.sum())
            d_h = d[:, :, None] * params[2]["w"]
            n = params[0]["h"].shape[0]
            grads = [
                Lstm.backward(params[0], x, mask, saved_a, d_h[:, :, :n]),
                Lstm.backward(params[1], x[::-1], mask[::-1], saved_b, d_h[::-1, :, n:]),
                {"w": np.einsum("tp,tph->h", d, h), "b": np.array([d.sum()])},
            ]
            step += 1
            now = rate * (1 - (step - 1) / (rounds * len(starts)))
            for p, g, m1, m2 in zip(params, grads, first, second, strict=True):
                for k in p:
                    m1[k] = 0.9 * m1[k] + 0.1 * g[k]
                    m2[k] = 0.999 * m2[k] + 0.001 * g[k] ** 2
                    p[k] -= now * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.999**step)) + 1e-8)
    return Labeller(*params)


@functools.lru_cache(maxsize=2)
def trained(n_pages: int = 4000, seed: int = 5) -> Labeller:
    """The production model; the same wherever it is trained."""
    from vecroute.llm.page_maker import make_page

    rng = np.random.default_rng(seed)
    pages = []
    for _ in range(n_pages):
        blocks, labels = labelled_blocks(make_page(rng))
        if blocks:
            pages.append((vectors(blocks), labels))
    return train(pages, seed=seed)


def labelled_blocks(pieces: list[tuple[str, bool]]) -> tuple[list[Block], np.ndarray]:
    """Blocks of a generated page with their labels; main text is marked inside the page by a control character."""
    page = "".join(piece.replace(">", ">\x02") if main else piece for piece, main in pieces)
    blocks = blocks_of(page)
    labels = np.array([float("\x02" in b.text) for b in blocks])
    clean, kept = [], []
    for b, y in zip(blocks, labels, strict=True):
        text = " ".join(b.text.replace("\x02", "").split())
        if text:
            clean.append(Block(b.path, text, b.link_share))
            kept.append(y)
    return clean, np.array(kept)


def main_texts(pages: list[str | None], model: Labeller, threshold: float = 0.45) -> list[str]:
    cut = [blocks_of(p) for p in pages]
    scores = model.probabilities([vectors(b) for b in cut])
    return ["\n\n".join(b.text for b, p in zip(blocks, scored, strict=True) if p >= threshold) for blocks, scored in zip(cut, scores, strict=True)]


def extract(pages: DataFrame, model: Labeller | None = None) -> DataFrame:
    """``page_id, url, text, n_chars`` of every row."""
    shared = pages.sparkSession.sparkContext.broadcast(model or trained())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                texts = main_texts(batch.column(2).to_pylist(), shared.value)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    kinds = {c: pages.schema[c].dataType.simpleString() for c in ("page_id", "url")}
    return pages.select("page_id", "url", F.col("html").cast("string").alias("html")).mapInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long")
