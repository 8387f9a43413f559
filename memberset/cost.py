"""Cost of writing a key into a candidate line, from j (ones of the line afterwards) and a (ones added).

Costs are integers (2^32 steps), so that every engine orders them alike; ties go to the first candidate.
The exponential form is the recommended one, the others are there for comparison.
"""

from __future__ import annotations

from dataclasses import asdict, dataclass

import numpy as np

STEP = 1 << 32
GOLDEN = (1 + 5**0.5) / 2


@dataclass(frozen=True)
class Cost:
    def of_total(self, j: np.ndarray, k: int) -> np.ndarray:
        return np.zeros(len(j))

    def of_added(self, a: np.ndarray, k: int) -> np.ndarray:
        return np.zeros(len(a))

    def tables(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Quantised costs by j (0..512) and by a (0..64)."""
        j, a = np.arange(513.0), np.arange(65.0)
        return np.rint(STEP * self.of_total(j, k)).astype(np.int64), np.rint(STEP * self.of_added(a, k)).astype(np.int64)

    def to_dict(self) -> dict:
        return {"form": type(self).__name__, **asdict(self)}


@dataclass(frozen=True)
class ExpCost(Cost):
    """beta^(j / knee) + weight a / k"""

    beta: float = GOLDEN
    knee: float = 128.0
    weight: float = 1.0

    def of_total(self, j, k):
        return self.beta ** (j / self.knee)

    def of_added(self, a, k):
        return self.weight * a / k


@dataclass(frozen=True)
class TotalCost(Cost):
    """j alone"""

    def of_total(self, j, k):
        return j / 512


@dataclass(frozen=True)
class AddedCost(Cost):
    """a alone"""

    def of_added(self, a, k):
        return a / k


@dataclass(frozen=True)
class LinearCost(Cost):
    """j / 512 + weight a / k"""

    weight: float = 1.0

    def of_total(self, j, k):
        return j / 512

    def of_added(self, a, k):
        return self.weight * a / k


@dataclass(frozen=True)
class PowerCost(Cost):
    """(j / 512)^power + weight a / k"""

    power: float = 2.0
    weight: float = 0.2

    def of_total(self, j, k):
        return (j / 512) ** self.power

    def of_added(self, a, k):
        return self.weight * a / k


FORMS = {c.__name__: c for c in (ExpCost, TotalCost, AddedCost, LinearCost, PowerCost)}


def cost_from_dict(raw: dict) -> Cost:
    return FORMS[raw["form"]](**{k: v for k, v in raw.items() if k != "form"})
