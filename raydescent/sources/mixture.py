"""Random normal mixtures made on the executors: the synthetic data of the experiments, the same in any engine.

Component c of m components stands at sep times character row c+1 of the sign table over sqrt(width); its class is
c mod v. The normal numbers come from uniform hashes by the Box-Muller formula.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from raydescent.operators.codes import hash_step, parity_sign
from raydescent.operators.layout import assign_shards, uniform
from raydescent.plans.params import next_power_of_two


def component_of(key: Column, components: int) -> Column:
    return (hash_step(hash_step(key + 7_919), 16807) % components).cast("int")


def normal_number(key: Column, j: Column, u: int, seed: int) -> Column:
    """The j-th of u normal numbers of a row."""
    base = (key * u + j) * 2 + seed * 1_000_003
    return F.sqrt(-2 * F.log(uniform(base + 1))) * F.cos(2 * F.lit(3.141592653589793) * uniform(hash_step(base + 2, 69621)))


def gaussian_mixture(spark: SparkSession, rows: int, u: int, v: int, components: int, sep: float = 2.0, seed: int = 1, k: int = 4) -> DataFrame:
    """row_key, x, y, part_id, split. Rows are made where they are used; nothing is stored."""
    width = next_power_of_two(max(u, components + 1))
    key = F.col("row_key")
    df = spark.range(rows).select(F.col("id").alias("row_key")).withColumn("component", component_of(key, components))

    def coordinate(j):
        centre = parity_sign(F.col("component") + 1, j) * (sep / float(width) ** 0.5)
        return centre + normal_number(key, j, u, seed)

    x = F.transform(F.sequence(F.lit(0), F.lit(u - 1)), coordinate)
    return assign_shards(df.select("row_key", x.alias("x"), (F.col("component") % v).cast("double").alias("y")), "row_key", k)


class _Part(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.u, self.v = (int(options.get(o, d)) for o, d in (("rows", 1000), ("u", 8), ("v", 4)))
        self.components, self.sep, self.seed = int(options.get("components", 8)), float(options.get("sep", 2.0)), int(options.get("seed", 1))
        self.parts = int(options.get("partitions", 4))

    def partitions(self):
        edges = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(edges[:-1], edges[1:])]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        step = lambda x, f=48271: x % 2147483647 * f % 2147483647
        width = next_power_of_two(max(self.u, self.components + 1))
        j = np.arange(self.u)
        for at in range(partition.lo, partition.hi, 10_000):
            key = np.arange(at, min(at + 10_000, partition.hi), dtype=np.int64)
            comp = step(step(key + 7_919), 16807) % self.components
            base = (key[:, None] * self.u + j) * 2 + self.seed * 1_000_003
            r, a = (step(base + 1) + 0.5) / 2147483647.0, (step(step(base + 2, 69621)) + 0.5) / 2147483647.0
            sign = 1 - 2 * (np.bitwise_count((comp[:, None] + 1) & j) % 2).astype(int)
            x = sign * (self.sep / width**0.5) + np.sqrt(-2 * np.log(r)) * np.cos(2 * np.pi * a)
            yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(list(x), pa.list_(pa.float64())), pa.array((comp % self.v).astype(float))], ["row_key", "x", "y"])


class MixtureSource(DataSource):
    """spark.read.format("mixture") with options rows, u, v, components, sep, seed, partitions."""

    @classmethod
    def name(cls) -> str:
        return "mixture"

    def schema(self) -> str:
        return "row_key long, x array<double>, y double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register_mixture(spark: SparkSession) -> None:
    spark.dataSource.register(MixtureSource)
