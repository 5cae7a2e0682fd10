"""Text primitives shared by the text operators: one definition of a word."""

from __future__ import annotations

import numpy as np

#: The symbols that the base statistics count.
SYMBOLS = "#*$%&|<>"


def words_of(text: str) -> list[bytes]:
    """Maximal runs of anything but space and U+0009..U+000D, as UTF-8.

    ``bytes.split()`` splits at exactly these six ASCII characters, while
    ``str.split()`` would also split at other Unicode spaces.
    """
    return text.encode("utf-8", "surrogatepass").split()


def repeated_window_words(words: list[bytes], width: int = 3) -> int:
    """Words inside a ``width``-word window that the text holds at least twice."""
    n = len(words)
    if n <= width:
        return 0
    index = dict.fromkeys(words)
    if len(index) == n:
        return 0
    for i, w in enumerate(index):
        index[w] = i
    ids = np.fromiter(map(index.__getitem__, words), np.int64, n)
    code = ids[: n - width + 1].copy()
    for k in range(1, width):
        if code.size and len(index) >= 1 << 31:
            raise ValueError("too many different words in one text")
        code = code * len(index) + ids[k : n - width + 1 + k]
        if k < width - 1 or len(index) ** width >= 1 << 62:
            code = np.unique(code, return_inverse=True)[1].astype(np.int64)
    order = np.argsort(code, kind="stable")
    same = code[order][1:] == code[order][:-1]
    hit = np.zeros(n + 1, np.int64)
    twice = np.zeros(code.size, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    start = np.flatnonzero(twice)
    np.add.at(hit, start, 1)
    np.add.at(hit, start + width, -1)
    return int(np.count_nonzero(np.cumsum(hit[:n])))


def duplicate_lines(text: str) -> int:
    """Lines that hold a word and equal an earlier line."""
    if "\n" not in text:
        return 0
    lines = text.split("\n")
    if len(set(lines)) == len(lines):
        return 0
    seen: set[str] = set()
    n = 0
    for line in lines:
        if line in seen:
            n += bool(line.strip(" \t\n\v\f\r"))
        else:
            seen.add(line)
    return n


def symbol_count(text: str) -> int:
    return sum(map(text.count, SYMBOLS))
