"""Hierarchical multi-length packing.

Documents are tokenised and routed to context-size tiers (powers of two). What is
longer than the largest window is cut into full windows; the rest goes to the
smallest tier that holds it. Tiers are packed from the largest down: a piece opens
a window, its gap is filled with the longest pieces of the shorter tiers that fit,
and what then remains is filled by cutting the shortest piece left. Windows of a
tier are dealt to step groups of equal token budget so that the groups' attention
cost (sum of squared piece lengths) is even.

Packing needs no exchange: each partition packs its own rows in rounds of bounded
size and carries what fills no window into the next round. At its end the rest is
packed into ever smaller powers of two, so no sequence is padded.

Defined cases: null text counts as empty and gives the end token alone; rows with
equal ids are packed as separate documents; an empty table gives no rows; extra
columns are ignored. Tokens are those of the ``tokenizers`` file of the vocabulary:
the rank vocabulary's encoding, with the file's added tokens found in the text as
their own ids.
"""

from __future__ import annotations

import functools
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.llm.fertility import rank_encoding, vocabulary_path

WINDOW = 2048
TIERS = (256, 512, 1024, 2048)
END_ID = 1
ROUND_TOKENS = 1 << 21
STEP_TOKENS = 1 << 15

SCHEMA = "start long, length long, token_ids binary, doc_tokens long, sequence_id long, offset long, tier int, sequence_tokens int, step_group long"


class Pool:
    """Pieces by length, with the non-empty lengths in one bit set."""

    def __init__(self, window: int):
        self.by_length: list[list] = [[] for _ in range(window + 1)]
        self.mask = 0
        self.tokens = 0

    def add(self, piece) -> None:
        n = piece[2]
        self.by_length[n].append(piece)
        self.mask |= 1 << n
        self.tokens += n

    def _take(self, n: int):
        stack = self.by_length[n]
        piece = stack.pop()
        if not stack:
            self.mask ^= 1 << n
        self.tokens -= n
        return piece

    def longest(self, at_most: int):
        """The longest piece of at most so many tokens, if any."""
        n = (self.mask & ((1 << (at_most + 1)) - 1)).bit_length() - 1
        return self._take(n) if n > 0 else None

    def cut(self, size: int):
        """The first ``size`` tokens of the shortest longer piece, if any."""
        above = self.mask >> (size + 1)
        if not above:
            return None
        doc, start, n = self._take(size + (above & -above).bit_length())
        self.add((doc, start + size, n - size))
        return doc, start, size


def fill(pool: Pool, size: int) -> list:
    """Pieces for one window of ``size`` tokens; full if the pool holds as many."""
    pieces, gap = [], size
    while gap:
        piece = pool.longest(gap) or pool.cut(gap)
        if piece is None:
            break
        pieces.append(piece)
        gap -= piece[2]
    return pieces


def pack_pool(pool: Pool, tiers: tuple[int, ...], last: bool) -> list[tuple[int, list]]:
    """(tier, pieces) of each window packed; without ``last`` only full windows."""
    windows = []
    for k in range(len(tiers) - 1, -1, -1):
        size, floor = tiers[k], tiers[k - 1] if k else 0
        while pool.tokens >= size and (pool.mask >> (floor + 1)):
            windows.append((size, fill(pool, size)))
    if last:
        while pool.tokens:
            size = 1 << (min(pool.tokens, tiers[-1]).bit_length() - 1)
            windows.append((size, fill(pool, size)))
    return windows


def step_groups(windows: list[tuple[int, list]], step_tokens: int) -> list[int]:
    """A step group for each window: by tier, dealt to and fro in order of cost."""
    groups, base = [0] * len(windows), 0
    by_tier: dict[int, list[int]] = {}
    for i, (tier, _) in enumerate(windows):
        by_tier.setdefault(tier, []).append(i)
    for tier, members in sorted(by_tier.items()):
        n = -(-len(members) * tier // step_tokens)
        members.sort(key=lambda i: -sum(p[2] ** 2 for p in windows[i][1]))
        for rank, i in enumerate(members):
            lap, at = divmod(rank, n)
            groups[i] = base + (n - 1 - at if lap % 2 else at)
        base += n
    return groups


@functools.lru_cache(maxsize=4)
def added_tokens(path: str) -> tuple[tuple[str, int], ...]:
    """Added tokens of the ``tokenizers`` file beside a rank file."""
    with open(path.removesuffix(".tiktoken") + ".json", encoding="utf-8") as f:
        return tuple((t["content"], t["id"]) for t in json.load(f)["added_tokens"])


def _encode(texts: list[str | None], path: str) -> Iterator[np.ndarray]:
    encoding = rank_encoding(path, added_tokens(path))
    for text in texts:
        yield np.append(np.asarray(encoding.encode_to_numpy(text or "", allowed_special="all")), END_ID).astype("<u4")


class _Packer:
    def __init__(self, id_type: pa.DataType, tiers: tuple[int, ...], step_tokens: int, part: int):
        self.tiers, self.step_tokens, self.id_type = tiers, step_tokens, id_type
        self.next_sequence = self.next_group = part << 40
        self.reset()

    def reset(self) -> None:
        self.pool, self.full, self.docs, self.held = Pool(self.tiers[-1]), [], [], 0

    def add(self, doc_id, ids: np.ndarray) -> None:
        top, at = self.tiers[-1], len(self.docs)
        self.docs.append((doc_id, ids, 0))
        whole = ids.size // top * top
        self.full += [(top, [(at, s, top)]) for s in range(0, whole, top)]
        if ids.size > whole:
            self.pool.add((at, whole, ids.size - whole))
        self.held += ids.size

    def flush(self, last: bool) -> pa.RecordBatch:
        windows = self.full + pack_pool(self.pool, self.tiers, last)
        groups = step_groups(windows, self.step_tokens)
        rows = []
        for (tier, pieces), group in zip(windows, groups, strict=True):
            offset, used = 0, sum(p[2] for p in pieces)
            for at, start, n in pieces:
                doc_id, ids, total = self.docs[at]
                rows.append((doc_id, start, n, ids[start : start + n].tobytes(), total or ids.size, self.next_sequence, offset, tier, used, self.next_group + group))
                offset += n
            self.next_sequence += 1
        self.next_group += max(groups, default=-1) + 1
        types = [self.id_type, pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()]
        names = ["doc_id", "start", "length", "token_ids", "doc_tokens", "sequence_id", "offset", "tier", "sequence_tokens", "step_group"]
        columns = zip(*rows, strict=True) if rows else [()] * len(names)
        out = pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, types, strict=True)], names)
        left = [p for stack in self.pool.by_length for p in stack]
        docs = self.docs
        self.reset()
        places: dict[int, int] = {}
        for at, start, n in left:
            if at not in places:
                places[at] = len(self.docs)
                self.docs.append(docs[at])
            self.pool.add((places[at], start, n))
        return out


def pack(docs: DataFrame, vocabulary: str = "byte_bpe_50k.tiktoken", tiers: tuple[int, ...] = TIERS, round_tokens: int = ROUND_TOKENS, step_tokens: int = STEP_TOKENS) -> DataFrame:
    """One row per piece: where it lies in its document and in which sequence, with its token ids.

    ``token_ids`` holds little-endian unsigned 32-bit ids. ``tier`` is the size of
    the sequence's window, always a power of two and here always full.
    """
    if any(t & (t - 1) for t in tiers) or list(tiers) != sorted(set(tiers)):
        raise ValueError("tiers are rising powers of two")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        path, packer, part = vocabulary_path(vocabulary), None, TaskContext.get().partitionId()
        for batch in batches:
            packer = packer or _Packer(batch.schema.field(0).type, tiers, step_tokens, part)
            for at in range(0, batch.num_rows, 256):
                piece = batch.slice(at, 256)
                texts = piece.column(1).to_pylist()
                for doc_id, ids in zip(piece.column(0).to_pylist(), _encode(texts, path), strict=True):
                    packer.add(doc_id, ids)
                    if packer.held >= round_tokens:
                        yield packer.flush(last=False)
        if packer:
            yield packer.flush(last=True)

    id_type = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(run, f"doc_id {id_type}, {SCHEMA}")


def packing_measures(pieces: DataFrame) -> DataFrame:
    """Per tier: sequences, tokens, padding, pieces a sequence, and cost balance of the step groups."""
    window = max(TIERS)
    power = F.expr("sequence_tokens & (sequence_tokens - 1)") == 0
    sequences = pieces.groupBy("sequence_id", "tier", "step_group").agg(
        F.max("sequence_tokens").alias("used"), F.max(F.when(power, F.col("sequence_tokens")).otherwise(window)).alias("padded"), F.count(F.lit(1)).alias("pieces"), F.sum(F.col("length") * F.col("length")).alias("cost")
    )
    steps = sequences.groupBy("tier", "step_group").agg(F.count(F.lit(1)).alias("sequences"), F.sum("used").alias("used"), F.sum("padded").alias("padded"), F.sum("pieces").alias("pieces"), F.sum("cost").alias("cost"))
    return steps.groupBy("tier").agg(
        F.sum("sequences").alias("sequences"), F.sum("used").alias("tokens"), (1 - F.sum("used") / F.sum("padded")).alias("padding"),
        (F.sum("pieces") / F.sum("sequences")).alias("pieces_per_sequence"), (F.max("cost") / F.avg("cost")).alias("step_cost_peak"),
    )
