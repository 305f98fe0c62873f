"""Sizes of a code and of its embedding into the next powers of two."""

from __future__ import annotations

from dataclasses import dataclass
from math import gcd, lcm


def is_power_of_two(x: int) -> bool:
    return x > 0 and x & (x - 1) == 0


def next_power_of_two(x: int) -> int:
    return 1 << max(0, x - 1).bit_length()


def primes_below(limit: int) -> list[int]:
    sieve = bytearray([1]) * limit
    sieve[:2] = b"\0\0"
    for p in range(2, int(limit**0.5) + 1):
        if sieve[p]:
            sieve[p * p :: p] = bytes(len(range(p * p, limit, p)))
    return [p for p in range(limit) if sieve[p]]


def coprime_step(k: int) -> int:
    """The smallest odd prime that does not divide k (odd, so it shares no factor with a power of two either)."""
    for p in primes_below(1000):
        if p > 2 and k % p:
            return p
    raise ValueError("k is a multiple of every prime tried")


@dataclass(frozen=True)
class CodeParams:
    """n lanes, k shards, weight t. Power-of-two codes need 2 <= t <= k/2 and n <= 2k."""

    n: int
    k: int
    t: int

    def validate(self) -> CodeParams:
        if not (is_power_of_two(self.k) and is_power_of_two(self.t)):
            raise ValueError(f"k={self.k} and t={self.t} must be powers of two")
        if not 2 <= self.t <= self.k // 2:
            raise ValueError(f"t={self.t} must lie between 2 and k/2={self.k // 2}: beyond, two lanes would have one ray")
        if not 0 < self.n <= 2 * self.k:
            raise ValueError(f"n={self.n} must lie between 1 and 2k={2 * self.k}")
        return self

    def shards_of(self, lane: int) -> list[int]:
        return [self.theta(lane, q) for q in range(self.t)]

    def theta(self, lane: int, q: int) -> int:
        return ((lane % self.k) // self.t * self.t + (self.t // 2 if lane >= self.k else 0) + q) % self.k

    def sign(self, lane: int, q: int) -> int:
        return 1 - 2 * ((lane % self.t & q).bit_count() % 2)

    def group_signs(self, lane: int) -> list[int]:
        """The sign of each output group in the lane's message: that of the coefficient whose index is the group modulo t."""
        by = {self.theta(lane, q) % self.t: self.sign(lane, q) for q in range(self.t)}
        return [by[g] for g in range(self.t)]


@dataclass(frozen=True)
class Embedding:
    """n lanes and k tasks as a window on a code of rows x cols on the torus, moved by step rows and one column each wave."""

    n: int
    k: int
    t: int
    rows: int
    cols: int
    step: int

    @property
    def period(self) -> int:
        """Waves until rows, columns and tasks come round together."""
        return lcm(self.rows // gcd(self.rows, self.step), self.cols, self.k)


def embed_parameters(n: int, k: int, t: int, step: int | None = None) -> Embedding:
    """The next powers of two; t must fit into the code that they give (2 <= t <= cols/2). More than 2*cols rows repeat."""
    rows, cols = next_power_of_two(n), next_power_of_two(k)
    CodeParams(min(rows, 2 * cols), cols, t).validate()
    return Embedding(n, k, t, rows, cols, step or coprime_step(k))
