"""Exact scan or routed search, from sizes alone."""

from __future__ import annotations

from dataclasses import dataclass

#: Multiply-adds per second and core of a blocked scan, and of a walk's scattered scoring.
SCAN_RATE, WALK_RATE = 4e9, 2e8
#: What routing and two exchanges cost whatever the size.
ROUTED_FIXED_S = 0.5


@dataclass(frozen=True)
class Cost:
    scan_s: float
    routed_s: float


def cost(n: int, d: int, queries: int, parts: int = 5, evals: int = 1500) -> Cost:
    return Cost(n * d * queries / SCAN_RATE, ROUTED_FIXED_S + queries * parts * evals * d / WALK_RATE)


def choose(n: int, d: int, queries: int, selectivity: float = 1.0, parts: int = 5) -> str:
    """``scan`` if scoring all that a filter leaves is cheaper than walking, else ``routed``."""
    c = cost(max(1, int(n * selectivity)), d, queries, parts)
    return "scan" if c.scan_s <= c.routed_s else "routed"


def over_fetch(k: int, selectivity: float, slack: float = 1.5) -> int:
    """Answers to ask for so that about ``k`` survive a filter applied afterwards."""
    return max(k, int(k / max(selectivity, 1e-6) * slack) + 1)


def parts_for(n: int, d: int, part_bytes: int = 140 << 20) -> int:
    """Parts so that vectors and links of one fit a task."""
    return max(1, -(-n * (4 * d + 320) // part_bytes))
