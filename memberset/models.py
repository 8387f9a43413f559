"""Closed forms: sizes, expected loads and false-positive rates."""

from __future__ import annotations

from math import comb, exp, floor, log

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from .geometry import LINE_BITS


def classic_load(n: int, k: int, m: int) -> float:
    return 1 - (1 - 1 / m) ** (n * k)


def classic_fpr(n: int, k: int, m: int) -> float:
    return classic_load(n, k, m) ** k


def overload(gamma: float, k: int) -> float:
    """FPR of a classic filter with gamma times the keys it was sized for, over 2^-k."""
    return (1 - 2.0**-gamma) ** k * 2.0**k


def distinct_candidates(choices: int, lines: int) -> list[float]:
    """Chances that a key's candidates are 1, 2, ... different lines of a shard."""
    chance = [1.0] + [0.0] * (choices - 1)
    for _ in range(choices - 1):
        grown = [0.0] * choices
        for i, p in enumerate(chance):
            grown[i] += p * (i + 1) / lines
            if i + 1 < choices:
                grown[i + 1] += p * (1 - (i + 1) / lines)
        chance = grown
    return chance


def choice_fpr(line_fpr: float, choices: int, lines: int | None = None) -> float:
    """FPR with several candidate lines; in small shards candidates may coincide."""
    if lines:
        return sum(w * (1 - (1 - line_fpr) ** i) for i, w in enumerate(distinct_candidates(choices, lines), 1))
    return 1 - (1 - line_fpr) ** choices


def collision(k: int, bits: int = LINE_BITS) -> float:
    """Chance that k independent addresses of a line are not all different."""
    p = 1.0
    for i in range(k):
        p *= 1 - i / bits
    return 1 - p


def max_line_load(k: int, choices: int) -> int:
    """Most ones a line may have so that its part of the FPR stays within 2^-k / choices."""
    return floor(LINE_BITS * (2.0**-k / choices) ** (1 / k))


def linelocal_fpr(k: int, rel_size: float) -> float:
    """Expected FPR of a line-local filter: Poisson keys per line, exact occupancy of the line's bits."""
    mean = LINE_BITS * log(2) / (k * rel_size)
    occupied, weight, out = np.zeros(LINE_BITS + 1), exp(-mean), 0.0
    occupied[0] = 1.0
    share, j, n = (np.arange(LINE_BITS + 1) / LINE_BITS), np.arange(LINE_BITS + 1), 0
    while n < mean + 12 * mean**0.5 + 12:
        out += weight * float(occupied @ share**k)
        for _ in range(k):
            moved = occupied * (1 - share)
            occupied = occupied * share
            occupied[1:] += moved[:-1]
        n += 1
        weight *= mean / n
    return out


def linelocal_fpr_of(k: int, held: dict[int, int]) -> float:
    """Expected FPR of a line-local filter with so many lines (values) of so many keys (names), exact occupancy of the line's bits."""
    occupied, share, out = np.zeros(LINE_BITS + 1), np.arange(LINE_BITS + 1) / LINE_BITS, 0.0
    occupied[0] = 1.0
    for n in range(max(held) + 1):
        out += held.get(n, 0) * float(occupied @ share**k)
        for _ in range(k):
            moved = occupied * (1 - share)
            occupied = occupied * share
            occupied[1:] += moved[:-1]
    return out / sum(held.values())


def required_linelocal(k: int) -> float:
    low, high = 0.9, 2.0
    while high - low > 1e-4:
        middle = (low + high) / 2
        low, high = (middle, high) if linelocal_fpr(k, middle) > 2.0**-k else (low, middle)
    return high


# Published lower bounds of space overhead, as (factor, additive share of 1/k).
RIVALS = {"cuckoo": (1.053, 3.0), "quotient": (1.053, 2.125), "vector_quotient": (1.0753, 2.914)}
# Published overhead factors at k = 10.
AT_TEN = {"classic": 1.443, "linelocal": 1.565, "choice2": 1.456, "cuckoo": 2.73, "quotient": 2.55, "vector_quotient": 2.77}
# Lines touched, least and most, by insertion and by lookup; "k" the count of bits, None: unbounded or not told.
LINES = {
    "classic": ("k", "k", "k", "k"),
    "linelocal": (1, 1, 1, 1),
    "choice2": (2, 2, 1, 2),
    "cuckoo": (1, None, 2, 2),
    "quotient": (None, None, None, None),
    "vector_quotient": (2, 2, 2, 2),
}


def rival_overhead(name: str, k: int) -> tuple[float, float]:
    """(best, worst): slots come in powers of two, so the worst case is twice the bound."""
    factor, share = RIVALS[name]
    best = factor * (1 + share / k)
    return best, 2 * best


def overview(spark: SparkSession, top: int = 30) -> DataFrame:
    """Filter types side by side, for k up to ``top``: overhead (null where no closed form is known; then the published value
    at k = 10 stands alone), ranges of the lines touched, and whether an overloaded filter degrades smoothly."""
    rows = []
    for name, touched in LINES.items():
        for k in range(1, top + 1):
            best, worst = rival_overhead(name, k) if name in RIVALS else (1 / log(2),) * 2 if name == "classic" else (None, None)
            at_ten = AT_TEN[name] if k == 10 else None
            rows.append((name, k, best and round(best, 11), worst and round(worst, 11), at_ten, *(float(k) if t == "k" else t and float(t) for t in touched), name not in RIVALS))
    ends = ", ".join(f"{what}_{end} double" for what in ("insert", "lookup") for end in ("low", "high"))
    return spark.createDataFrame(rows, f"filter string, k int, best double, worst double, published_c10 double, {ends}, smooth boolean")


def line_fpr(ones: np.ndarray, k: int, bits: str = "random") -> np.ndarray:
    """Chance that a fresh footprint lies within a line of that many ones."""
    if bits == "distinct":
        table = np.array([comb(j, k) / comb(LINE_BITS, k) for j in range(LINE_BITS + 1)])
        return table[ones]
    return (ones / LINE_BITS) ** k
