"""The rivals that recover the sum exactly from any k of n lanes: cyclic windows and fractional repetition."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.operators.lanes import Scheme


@dataclass(frozen=True)
class ExactCode:
    n: int
    k: int
    matrix: np.ndarray

    @property
    def weight(self) -> int:
        return self.n - self.k + 1

    def scheme(self) -> Scheme:
        encode = tuple((i, j, 0, 0, float(self.matrix[i, j])) for i in range(self.n) for j in range(self.n) if self.matrix[i, j])
        return Scheme("exact_cyclic", self.n, self.n, 1, 1, encode, tuple((i, 0, 0, 1.0) for i in range(self.n)), 1.0)

    def solve(self, arrived: list[int], tolerance: float = 1e-7) -> np.ndarray:
        """Coefficients of the arrived messages whose sum is the whole gradient; refuses if they cannot give it."""
        part = self.matrix[arrived]
        coef, *_ = np.linalg.lstsq(part.T, np.ones(self.n), rcond=None)
        if np.abs(part.T @ coef - 1).max() > tolerance * max(1.0, np.abs(coef).max()):
            raise ValueError(f"{len(arrived)} messages of {self.n} lanes do not give the sum; {self.k} are needed")
        return coef


@dataclass(frozen=True)
class RepetitionCode:
    """Groups of n-k+1 lanes with the same shards: the first message of every group makes the sum, and any k lanes hold one."""

    n: int
    k: int

    @property
    def weight(self) -> int:
        return self.n - self.k + 1

    def scheme(self) -> Scheme:
        return repetition_scheme(self.n, self.k)

    def solve(self, arrived: list[int]) -> np.ndarray:
        """1 for the first arrived lane of each group, 0 for others; refuses if a group is missing."""
        groups = [lane // self.weight for lane in arrived]
        if len(set(groups)) < self.n // self.weight:
            raise ValueError(f"{len(arrived)} messages of {self.n} lanes do not give the sum; {self.k} are needed")
        return np.array([float(groups.index(g) == i) for i, g in enumerate(groups)])


def exact_cyclic(n: int, k: int, seed: int = 0, most_trials: int = 50) -> ExactCode:
    """Lane i holds the n-k+1 shards from i on. Windows are solved against a random matrix whose rows sum to nothing;
    badly conditioned draws are thrown again."""
    s = n - k
    if not 0 <= s < n:
        raise ValueError("k must lie between 1 and n")
    if s == 0:
        return ExactCode(n, k, np.eye(n))
    rng, best = np.random.default_rng(seed), None
    for _ in range(most_trials):
        h = rng.standard_normal((s, n))
        h[:, -1] = -h[:, :-1].sum(axis=1)
        b, worst = np.zeros((n, n)), 0.0
        for i in range(n):
            at = [(i + j) % n for j in range(s + 1)]
            b[i, at[0]] = 1
            b[i, at[1:]] = np.linalg.solve(h[:, at[1:]], -h[:, at[0]])
            worst = max(worst, np.abs(b[i]).max())
        if best is None or worst < best[0]:
            best = (worst, b)
        if worst < 100:
            break
    return ExactCode(n, k, best[1])


def repetition_scheme(n: int, k: int) -> Scheme:
    """Groups of n-k+1 lanes hold the same shards; the first of a group is enough. n-k+1 must divide n."""
    r = n - k + 1
    if n % r:
        raise ValueError("n-k+1 must divide n")
    encode = tuple((i, i // r * r + j, 0, 0, 1.0) for i in range(n) for j in range(r))
    return Scheme("exact_repetition", n, n, 1, 1, encode, tuple((i, 0, 0, 1.0) for i in range(n)), 1.0)


def repetition_picks(arrivals: DataFrame, n: int, k: int) -> DataFrame:
    """lane, arrive_at of the first message of every repetition group."""
    r = n - k + 1
    first = F.expr(f"row_number() OVER (PARTITION BY lane div {r} ORDER BY arrive_at, lane)")
    return arrivals.withColumn("_r", first).where("_r = 1").drop("_r")


def cyclic_table(spark: SparkSession, code: ExactCode) -> DataFrame:
    """lane, theta, coef."""
    return spark.createDataFrame([(i, j, float(code.matrix[i, j])) for i in range(code.n) for j in range(code.n) if code.matrix[i, j]], "lane int, theta int, coef double")
