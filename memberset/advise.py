"""Which filter for which target."""

from __future__ import annotations


def advise(k: int, memory_bound: bool = True, smallest: bool = False) -> tuple[str, int]:
    """(kind, choices) for a target of 2^-k.

    Up to k = 3 the classic filter; line-local while k is at most 7 or memory does not matter; beyond, two
    choices; three where the size counts most.
    """
    if k <= 3:
        return "classic", 1
    if k <= 7 or not memory_bound:
        return "linelocal", 1
    return "choice", 3 if smallest else 2
