"""Filter parameters and sizing."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, field

from .cost import Cost, ExpCost, cost_from_dict

LINE_BITS, WORDS = 512, 8
GOLDEN = (1 + 5**0.5) / 2


@dataclass(frozen=True)
class FilterSpec:
    """One filter. ``lines`` is per shard; ``classic`` filters use the same bits without line locality.

    kind: classic | linelocal | choice; choices: candidate lines per key (1 for the others);
    bits: random | distinct | sliced; premix: scramble keys first (for dense ids); width: bits of the keys (2 q for q-grams),
    which the hash forms of even moduli look at where keys are not scrambled; capacity: keys it is sized for (0: not told).
    """

    kind: str = "choice"
    k: int = 10
    choices: int = 2
    shards: int = 1
    lines: int = 64
    bits: str = "random"
    seed: int = 1
    premix: bool = True
    cost: Cost = field(default_factory=ExpCost)
    capacity: int = 0
    width: int = 64

    def __post_init__(self):
        if self.kind not in ("classic", "linelocal", "choice") or self.bits not in ("random", "distinct", "sliced"):
            raise ValueError(f"unknown kind or bits: {self.kind}, {self.bits}")
        if not 2 <= self.width <= 64:
            raise ValueError("width in 2..64")
        if not 1 <= self.k <= 64 or self.choices < 1 or self.lines < 1 or self.shards < 1:
            raise ValueError("k in 1..64, choices, lines and shards from 1")
        if self.kind != "choice" and self.choices != 1:
            object.__setattr__(self, "choices", 1)

    @property
    def u(self) -> int:
        return 64 if self.premix else self.width

    @property
    def m(self) -> int:
        return self.shards * self.lines * LINE_BITS

    @property
    def bytes(self) -> int:
        return self.m // 8

    def overhead(self, n: int) -> float:
        return self.m / (n * self.k)

    def relative_size(self, n: int) -> float:
        return self.overhead(n) * math.log(2)

    def to_json(self) -> str:
        return json.dumps(asdict(self) | {"cost": self.cost.to_dict()})

    @staticmethod
    def from_json(text: str) -> FilterSpec:
        raw = json.loads(text)
        return FilterSpec(**raw | {"cost": cost_from_dict(raw["cost"])})


def lines_for(n: int, k: int, rel_size: float = 1.0) -> int:
    """Lines for n keys: n k / ln 2 bits times the relative size."""
    return max(1, math.ceil(n * k * rel_size / (math.log(2) * LINE_BITS)))


def plan_spec(n: int, k: int, kind: str = "choice", choices: int = 2, rel_size: float = 1.0, shard_lines: int = 1 << 20, shards: int | None = None, **rest) -> FilterSpec:
    """Spec for n keys; shards of about ``shard_lines`` lines (64 MiB), or as many as asked for."""
    total = lines_for(max(1, n), k, rel_size)
    shards = shards or max(1, math.ceil(total / shard_lines))
    return FilterSpec(kind=kind, k=k, choices=choices, shards=shards, lines=math.ceil(total / shards), capacity=n, **rest)
