"""Sizes that are not powers of two: a window of real lanes and tasks slides over a larger code on a torus."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.operators.codes import projective_code
from raydescent.plans.params import Embedding, embed_parameters, primes_below


def coprime_steps(spark: SparkSession, sizes: list[int]) -> DataFrame:
    """k, step: the smallest odd prime that does not divide k, as a relation."""
    primes = spark.createDataFrame([(p,) for p in primes_below(100) if p > 2], "p int")
    asked = spark.createDataFrame([(k,) for k in sizes], "k int")
    return asked.join(F.broadcast(primes), F.col("k") % F.col("p") != 0).groupBy("k").agg(F.min("p").alias("step"))


def windows(spark: SparkSession, e: Embedding, waves: int) -> DataFrame:
    """wave, lane, slot, task, code_row, code_col for every place of the window in every wave."""
    ids = spark.range(waves * e.n * e.k)
    cells = ids.select(F.expr(f"id div {e.n * e.k}").cast("int").alias("wave"), F.expr(f"id div {e.k} % {e.n}").cast("int").alias("lane"), (F.col("id") % e.k).cast("int").alias("slot"))
    moved = F.col("slot") + F.col("wave")
    row = (F.col("lane") + F.col("wave") * e.step) % e.rows
    return cells.select("wave", "lane", "slot", (moved % e.k).cast("int").alias("task"), row.cast("int").alias("code_row"), (moved % e.cols).cast("int").alias("code_col"))


def wave_schedule(spark: SparkSession, n: int, k: int, t: int, waves: int, step: int | None = None) -> DataFrame:
    """wave, lane, code_row, slot, code_col, task, sign: what each lane works on in each wave (non-zeros only)."""
    e = embed_parameters(n, k, t, step)
    lanes = min(e.rows, 2 * e.cols)
    code = projective_code(spark, e.cols, t, n=lanes).select(F.col("lane").alias("_lane"), F.col("theta").alias("_theta"), "sign")
    met = (F.col("code_row") % lanes == F.col("_lane")) & (F.col("code_col") == F.col("_theta"))
    return windows(spark, e, waves).join(F.broadcast(code), met).select("wave", "lane", "code_row", "slot", "code_col", "task", "sign")


def wave_coverage(spark: SparkSession, n: int, k: int, t: int, step: int | None = None) -> DataFrame:
    """period, pairs_hit, pairs_total: how many (row, task) pairs the first lane reaches in one period."""
    e = embed_parameters(n, k, t, step)
    lead = windows(spark, Embedding(1, e.k, e.t, e.rows, e.cols, e.step), e.period).where("slot = 0")
    hit = lead.select("code_row", "task").distinct().agg(F.count("*").alias("pairs_hit"))
    return hit.select(F.lit(e.period).cast("long").alias("period"), "pairs_hit", F.lit(e.rows * e.k).cast("long").alias("pairs_total"))


def idle_lanes(spark: SparkSession, n: int, k: int, t: int, step: int | None = None) -> DataFrame:
    """wave, lane of one period whose window holds no non-zero."""
    e = embed_parameters(n, k, t, step)
    busy = wave_schedule(spark, n, k, t, e.period, step).select("wave", "lane").distinct()
    return windows(spark, e, e.period).select("wave", "lane").distinct().join(busy, ["wave", "lane"], "left_anti")
