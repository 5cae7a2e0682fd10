"""Quality rules by tokeniser fertility.

Public vocabularies are fitted to ordinary text, so text unlike it is cut into
shorter tokens, falls back to bytes, or repeats few tokens. Each text is measured
with two byte-level vocabularies and one with byte fallback:

* ``chars_per_token`` under an English-centred and a many-language vocabulary,
* ``byte_share``: share of the text's bytes that the third vocabulary can only
  write as byte tokens,
* ``entropy``: bits per token of the text's own token distribution,
* ``top_share``: share of its commonest token (two to the power of minus the
  min-entropy).

A text is kept if every measure lies inside the band of its language; a language
without a band uses the band of the text's main script. Bands widen with the
inverse root of the token count, and fertility is not judged below ``MIN_TOKENS``
tokens, where it is mostly noise.

Defined cases: null and empty text have no words and fail the base rules; a null or
unknown language falls back to the script; repeated rows are measured alike; extra
columns are ignored. The measures need one pass, no shuffle and no state.
"""

from __future__ import annotations

import base64
import functools
import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecroute.llm.words import duplicate_lines, repeated_window_words, symbol_count, words_of

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
MIN_TOKENS = 64
#: Characters per token by which a band is wider for a text of one token; it falls with the root of the count.
NOISE = 1.2
#: Upper end of the fertility bands in the Latin script: natural prose reaches 5.5 characters per token, and more in dense registers.
WIDE = 8.0


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@functools.lru_cache(maxsize=4)
def rank_encoding(path: str, added: tuple[tuple[str, int], ...] = ()):
    """A byte-level vocabulary from its rank file, and tokens added to it."""
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding(path, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=dict(added))


@functools.lru_cache(maxsize=2)
def piece_characters(path: str) -> frozenset[str]:
    """Characters that the byte-fallback vocabulary can write as themselves."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = (model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i)))
    return frozenset(p for p in pieces if len(p) == 1) | {" "}


@dataclass(frozen=True)
class Band:
    """Open ranges inside which a text's measures must lie."""

    main: tuple[float, float]
    multi: tuple[float, float]
    entropy_low: float
    byte_share_high: float
    top_share_high: float


@dataclass(frozen=True)
class Rules:
    """Parameters of the rules.

    Lower ends of the language bands were read off clean labelled texts; natural
    prose, with its longer tokens, lies above them. The upper end is ``WIDE``.
    """

    languages: tuple[tuple[str, Band], ...]
    scripts: tuple[tuple[str, Band], ...]
    other: Band
    main: str = "byte_bpe_50k.tiktoken"
    multi: str = "byte_bpe_multi_50k.tiktoken"
    pieces: str = "piece_bpe_32k.model"


#: Bands by language, then by script for texts of no listed language.
DEFAULT = Rules(
    languages=(
        ("de", Band((2.20, WIDE), (2.47, WIDE), 5.55, 0.06, 0.10)),
        ("en", Band((2.44, WIDE), (2.40, WIDE), 5.45, 0.06, 0.10)),
        ("es", Band((1.90, WIDE), (2.22, WIDE), 5.40, 0.06, 0.10)),
        ("fr", Band((1.99, WIDE), (2.13, WIDE), 5.40, 0.06, 0.10)),
    ),
    # An English-centred vocabulary writes other scripts in pieces of characters: fewer characters per token, and one lead byte may be a fifth of all tokens.
    scripts=(("LATIN", Band((0.9, WIDE), (1.5, WIDE), 5.0, 0.08, 0.12)), ("CYRILLIC", Band((0.4, 4.5), (1.2, 5.5), 4.3, 0.10, 0.20)), ("GREEK", Band((0.4, 4.5), (0.8, 5.0), 4.3, 0.15, 0.20))),
    other=Band((0.2, 6.0), (0.2, 6.0), 3.5, 0.9, 0.30),
)

MEASURE_FIELDS = [("n_words", pa.int64()), ("word_chars", pa.int64()), ("n_symbols", pa.int64()), ("n_dup_lines", pa.int64()), ("n_repeat_words", pa.int64()), ("base_failed", pa.bool_()), ("kept", pa.bool_()), ("n_tokens", pa.int64()), ("chars_per_token", pa.float64()), ("chars_per_token_multi", pa.float64()), ("byte_share", pa.float64()), ("token_entropy", pa.float64()), ("top_share", pa.float64()), ("band", pa.string())]
MEASURE_DDL = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_tokens long, chars_per_token double, chars_per_token_multi double, byte_share double, token_entropy double, top_share double, band string"


def script_of(text: str) -> str:
    """Script of most letters, from the first word of their Unicode names."""
    if text.isascii():
        return "LATIN"
    letters: dict[str, int] = {}
    for ch in set(text):
        if ch.isalpha():
            name = unicodedata.name(ch, "OTHER").split(" ", 1)[0]
            letters[name] = letters.get(name, 0) + text.count(ch)
    return max(sorted(letters), key=letters.get) if letters else "OTHER"


def token_entropy(ids: np.ndarray) -> tuple[float, float]:
    """Bits per token, and the share of the commonest one."""
    if ids.size == 0:
        return 0.0, 0.0
    counts = np.bincount(ids)
    p = counts[counts > 0] / ids.size
    return float(-(p * np.log2(p)).sum()) + 0.0, float(p.max())


def byte_share(text: str, plain: frozenset[str]) -> float:
    """Share of the UTF-8 bytes in characters that only byte tokens can write.

    White space is left out, as the vocabulary's own normaliser rewrites it.
    """
    if text.isascii() and plain.issuperset(map(chr, range(33, 127))):
        odd = sum(text.count(c) for c in map(chr, (*range(9), *range(14, 32), 127)))
        return odd / max(1, len(text))
    size = len(text.encode("utf-8", "surrogatepass"))
    missing = [c for c in set(text) if c not in plain and not c.isspace()]
    return sum(text.count(c) * len(c.encode("utf-8", "surrogatepass")) for c in missing) / max(1, size)


def measure_one(text: str | None, lang: str | None, rules: Rules = DEFAULT) -> tuple:
    """All measures and the verdict of one text; the order of MEASURE_FIELDS."""
    text = text or ""
    words = words_of(text)
    n = len(words)
    word_chars = len(text) - sum(map(text.count, " \t\n\v\f\r"))
    repeated = repeated_window_words(words)
    failed = n < MIN_WORDS or 100 * repeated > MAX_REPEAT_PERCENT * n
    main = np.asarray(rank_encoding(vocabulary_path(rules.main)).encode_to_numpy(text))
    multi = np.asarray(rank_encoding(vocabulary_path(rules.multi)).encode_to_numpy(text))
    cpt, cptm = len(text) / max(1, main.size), len(text) / max(1, multi.size)
    fallback = byte_share(text, piece_characters(vocabulary_path(rules.pieces)))
    entropy, top = token_entropy(main)
    known = dict(rules.languages)
    if lang in known:
        name, band = lang, known[lang]
    else:
        name = script_of(text)
        band = dict(rules.scripts).get(name, rules.other)
    slack = NOISE / max(1, main.size) ** 0.5
    fits = lambda x, b: b[0] - slack < x < b[1] + slack
    inside = main.size < MIN_TOKENS or (fits(cpt, band.main) and fits(cptm, band.multi) and entropy > band.entropy_low - slack and fallback < band.byte_share_high and top < band.top_share_high + slack / 4)
    return n, word_chars, symbol_count(text), duplicate_lines(text), repeated, failed, inside and not failed, int(main.size), cpt, cptm, fallback, entropy, top, name


def _measures(texts: pa.Array, langs: pa.Array, rules: Rules) -> pa.StructArray:
    rows = [measure_one(t, g, rules) for t, g in zip(texts.to_pylist(), langs.to_pylist(), strict=True)]
    columns = zip(*rows, strict=True) if rows else [[] for _ in MEASURE_FIELDS]
    return pa.StructArray.from_arrays([pa.array(c, t) for c, (_, t) in zip(columns, MEASURE_FIELDS, strict=True)], [n for n, _ in MEASURE_FIELDS])


def measure(text: Column, lang: Column, rules: Rules = DEFAULT) -> Column:
    """Struct column of MEASURE_DDL for a text column and its language."""

    def run(texts: pa.Array, langs: pa.Array) -> pa.Array:
        return _measures(texts, langs, rules)

    return F.arrow_udf(run, MEASURE_DDL)(text.cast("string"), lang.cast("string"))


def kept(text: Column, lang: Column, rules: Rules = DEFAULT) -> Column:
    """Boolean column: the verdict alone."""

    def run(texts: pa.Array, langs: pa.Array) -> pa.Array:
        return _measures(texts, langs, rules).field("kept")

    return F.arrow_udf(run, "boolean")(text.cast("string"), lang.cast("string"))


def fertility_rules(docs: DataFrame, rules: Rules = DEFAULT) -> DataFrame:
    """``doc_id``, the base statistics, the fertility measures and the verdict of every row."""
    measured = docs.select("doc_id", measure(F.col("text"), F.col("lang"), rules).alias("m"))
    return measured.select("doc_id", "m.*")


def fit_bands(docs: DataFrame, rules: Rules = DEFAULT, low: float = 0.002, high: float = 0.998, slack: float = 0.03) -> DataFrame:
    """Bands by language from a set of texts taken as clean: quantiles, widened by ``slack``."""
    m = fertility_rules(docs, rules).where(~F.col("base_failed") & (F.col("n_tokens") >= MIN_TOKENS))
    edge = lambda c, q, f: (F.percentile_approx(c, F.lit(q), F.lit(10000)) * f)
    return m.groupBy("band").agg(
        edge("chars_per_token", low, 1 - slack).alias("main_low"), edge("chars_per_token", high, 1 + slack).alias("main_high"),
        edge("chars_per_token_multi", low, 1 - slack).alias("multi_low"), edge("chars_per_token_multi", high, 1 + slack).alias("multi_high"),
        edge("token_entropy", low, 1 - slack).alias("entropy_low"), edge("byte_share", high, 1 + slack).alias("byte_share_high"), edge("top_share", high, 1 + slack).alias("top_share_high"), F.count(F.lit(1)).alias("n"),
    )
