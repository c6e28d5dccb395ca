"""Parameters of the sketches and the constants that follow from them."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass, replace

#: Largest 31-bit prime: keys are below it, so hash products stay below 2^62.
P31 = 2147483647
#: Coins are 28-bit numbers.
COIN = 1 << 28


@dataclass(frozen=True)
class Params:
    """eps: budget; m: row width; k: rows; theta: share of frequency on the heavy path; r: share of clients in phase 1;
    k_pool: hash functions of pooled local hashing; g_rule: exp_plus_one or exp; flip: full or half (Hadamard)."""

    eps: float = 4.0
    m: int = 64
    k: int = 8
    theta: float = 0.5
    r: float = 0.1
    k_pool: int = 16
    g_rule: str = "exp_plus_one"
    flip: str = "full"
    seed: int = 7

    def __post_init__(self):
        if self.eps <= 0 or self.m < 2 or self.k < 1 or not 0 < self.theta < 1 or not 0 < self.r < 1:
            raise ValueError(f"out of range: {self}")

    def but(self, **changes) -> Params:
        return replace(self, **changes)

    @property
    def q(self) -> float:
        """Chance that a bit of a one-hot report is flipped."""
        return 1 / (math.exp(self.eps / 2) + 1)

    @property
    def c(self) -> float:
        return (math.exp(self.eps / 2) + 1) / (math.exp(self.eps / 2) - 1)

    @property
    def hadamard_q(self) -> float:
        return 1 / (math.exp(self.eps if self.flip == "full" else self.eps / 2) + 1)

    @property
    def hadamard_c(self) -> float:
        return 1 / (1 - 2 * self.hadamard_q)

    @property
    def g(self) -> int:
        """Range of the small hashes of local hashing."""
        return max(2, round(math.exp(self.eps)) + (self.g_rule == "exp_plus_one"))

    @property
    def keep(self) -> float:
        """Chance that local hashing reports the true hash."""
        return math.exp(self.eps) / (math.exp(self.eps) + self.g - 1)

    def hashes(self, n: int | None = None, family: str = "h") -> list[tuple[int, int]]:
        """(a, b) of the affine hash functions modulo P31, from md5 of the seed and the function's number."""
        take = lambda tag, j: int(hashlib.md5(f"{family}|{tag}|{self.seed}|{j}".encode()).hexdigest()[:15], 16)
        return [(1 + take("a", j) % (P31 - 1), take("b", j) % P31) for j in range(n or self.k)]


def threshold(p: float) -> int:
    """A coin below it has chance p."""
    return math.floor(p * COIN)


SMALL = Params()
COLLISION = Params(m=256, k=16, k_pool=128)
ZIPF = Params(m=1024, k=64, k_pool=128)
SENSOR = Params(m=512, k=32, theta=0.4, k_pool=128)
