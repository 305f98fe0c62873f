"""Who holds which data and which derivatives: allocation as relations over one stored copy."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from raydescent.operators.codes import hash_step


def shard_of(key: Column, k: int) -> Column:
    """The shard of a non-negative key: random for any order of load, the same in every run."""
    return (hash_step(hash_step(key.cast("long")), 69621) % k).cast("int")


def split_of(key: Column) -> Column:
    """test, valid or train by a hash of its own, so that no shard is all test."""
    h = hash_step(hash_step(hash_step(key.cast("long")), 69621)) % 5
    return F.when(h == 0, "test").when(h == 1, "valid").otherwise("train")


def uniform(key: Column) -> Column:
    """A number in (0, 1) from a key."""
    return (hash_step(key) + 0.5) / 2147483647.0


def assign_shards(df: DataFrame, key: str, k: int) -> DataFrame:
    """df with part_id and split."""
    return df.withColumn("part_id", shard_of(F.col(key), k)).withColumn("split", split_of(F.col(key)))


def rows_by_shard(df: DataFrame, key: Column, k: int) -> DataFrame:
    """part_id, rows: how many rows of a table each of k shards holds; rows without a key are in none."""
    return df.select(shard_of(key, k).alias("part_id")).where("part_id IS NOT NULL").groupBy("part_id").agg(F.count("*").alias("rows"))


def allocate_shards(code: DataFrame) -> DataFrame:
    """lane, part_id: a lane reads the shards under its non-zeros."""
    return code.select("lane", F.col("theta").alias("part_id")).distinct()


def allocate_gradient(code: DataFrame, t: int) -> DataFrame:
    """lane, theta, group, block, sign: derivative theta is output group theta mod t on data block theta div t."""
    return code.select("lane", "theta", (F.col("theta") % t).cast("int").alias("group"), F.expr(f"theta div {t}").cast("int").alias("block"), "sign")


def pad_units(v: int, t: int) -> tuple[int, int]:
    """Units per group and padded units when v outputs are dealt to t groups."""
    per = -(-v // t)
    return per, per * t - v


def allocate_network(code: DataFrame, outputs: list[int], t: int, split: str = "flat") -> DataFrame:
    """lane, layer, group, block, first_unit, units, sign for a network whose layers have these numbers of outputs.

    'flat' cuts every layer into t groups with the same signs. 'nested' cuts the layer q steps before the output into
    t^(q+1) groups whose sign is the product of the signs of the group's digits to base t.
    """
    base = allocate_gradient(code, t)
    parts = []
    for layer, v in enumerate(outputs):
        depth = 1 if split == "flat" else len(outputs) - layer
        rows = base.withColumn("layer", F.lit(layer))
        for _ in range(depth - 1):
            finer = base.select(F.col("lane").alias("_l"), F.col("group").alias("_g"), F.col("sign").alias("_s"))
            rows = rows.join(finer, F.col("lane") == F.col("_l")).withColumn("group", F.col("group") * t + F.col("_g")).withColumn("sign", F.col("sign") * F.col("_s")).drop("_l", "_g", "_s")
        per = -(-v // t**depth)
        units = F.greatest(F.lit(0), F.least(F.lit(per), F.lit(v) - F.col("group") * per))
        parts.append(rows.select("lane", "layer", "group", "block", (F.col("group") * per).cast("int").alias("first_unit"), units.cast("int").alias("units"), F.col("sign").cast("int").alias("sign")))
    out = parts[0]
    for more in parts[1:]:
        out = out.union(more)
    return out
