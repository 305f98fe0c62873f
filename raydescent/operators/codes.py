"""Codes as relations: sign tables, the sparse projective code, and the codes it is compared with.

A code is a table (lane, theta, sign or coef, scale): one row per non-zero. It grows with the number of lanes, never with
the data, and is made on the executors from ranges.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.plans.params import CodeParams, is_power_of_two


def parity_sign(a: Column, b: Column) -> Column:
    """+1 or -1: the character value of two bit strings."""
    return (1 - 2 * (F.bit_count(a.bitwiseAND(b)) % 2)).cast("int")


def sign_table(spark: SparkSession, t: int) -> DataFrame:
    """alpha, beta, sign for all pairs of bit strings of log2(t) bits."""
    if not is_power_of_two(t):
        raise ValueError("t must be a power of two")
    pairs = spark.range(t * t).select((F.col("id") / t).cast("int").alias("alpha"), (F.col("id") % t).cast("int").alias("beta"))
    return pairs.withColumn("sign", parity_sign(F.col("alpha"), F.col("beta")))


def sign_table_kron(spark: SparkSession, t: int) -> DataFrame:
    """The same table by doubling: the table of 2m is the Kronecker product of those of 2 and m."""
    out = spark.range(1).select(F.lit(0).alias("alpha"), F.lit(0).alias("beta"), F.lit(1).alias("sign"))
    cells = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.lit(-1 if i and j else 1).alias("s")) for i in (0, 1) for j in (0, 1)]))
    m = 1
    while m < t:
        out = out.select("*", cells.alias("c")).select((F.col("c.i") * m + F.col("alpha")).alias("alpha"), (F.col("c.j") * m + F.col("beta")).alias("beta"), (F.col("sign") * F.col("c.s")).alias("sign"))
        m *= 2
    return out


def row_sign_table(counts: DataFrame, t: int) -> DataFrame:
    """alpha, beta, sign, signed_rows: the signs that a block's t lanes give the rows of each shard of a table, and the rows under their sign.

    counts: part_id (below t), rows. A shard without rows has no signs.
    """
    if not is_power_of_two(t):
        raise ValueError("t must be a power of two")
    cells = counts.select(F.explode(F.sequence(F.lit(0), F.lit(t - 1))).alias("alpha"), F.col("part_id").alias("beta"), "rows")
    return cells.withColumn("sign", parity_sign(F.col("alpha"), F.col("beta"))).select("alpha", "beta", "sign", (F.col("sign") * F.col("rows")).alias("signed_rows"))


def row_sign_table_kron(counts: DataFrame, t: int) -> DataFrame:
    """The same table by doubling: a bit of the shard turns the sign of the lanes that have the bit too."""
    if not is_power_of_two(t):
        raise ValueError("t must be a power of two")
    out = counts.select(F.lit(0).alias("alpha"), F.col("part_id").alias("beta"), "rows", F.lit(1).alias("sign"))
    m = 1
    while m < t:
        factor = F.when((F.col("i") == 1) & (F.col("beta").bitwiseAND(F.lit(m)) != 0), -1).otherwise(1)
        out = out.withColumn("i", F.explode(F.array(F.lit(0), F.lit(1)))).select((F.col("i") * m + F.col("alpha")).alias("alpha"), "beta", "rows", (F.col("sign") * factor).alias("sign"))
        m *= 2
    return out.select("alpha", "beta", "sign", (F.col("sign") * F.col("rows")).alias("signed_rows"))


def hadamard_report(table: DataFrame, other: DataFrame | None = None) -> DataFrame:
    """alpha_a <= alpha_b, product: inner products of the rows of a sign table; a Hadamard table has zeros off the diagonal.

    With another table, of signed sums, alpha_b counts its rows: the signs undo those that the sums were made with.
    """
    a, b = table.toDF("alpha_a", "beta", "sa"), (table if other is None else other).toDF("alpha_b", "beta", "sb")
    return a.join(b, "beta").where("alpha_a <= alpha_b").groupBy("alpha_a", "alpha_b").agg(F.sum(F.col("sa") * F.col("sb")).alias("product"))


def identity_parity_code(spark: SparkSession) -> DataFrame:
    """The code of two derivatives: each of them, their sum and their difference."""
    half = 0.5**0.5
    rows = [(0, 0, 1, 1.0), (1, 1, 1, 1.0), (2, 0, 1, half), (2, 1, 1, half), (3, 0, 1, half), (3, 1, -1, half)]
    return spark.createDataFrame(rows, "lane int, theta int, sign int, scale double")


def projective_code(spark: SparkSession, k: int, t: int, n: int | None = None, scaling: str = "unit") -> DataFrame:
    """lane, theta, sign, scale of the sparse code with n (2k if not given) lanes, k shards and weight t.

    The first k lanes hold sign tables in blocks, the others the same shifted cyclically by half a block. scaling 'unit'
    has rows of length 1, 'sign' leaves the constant to the step size.
    """
    p = CodeParams(2 * k if n is None else n, k, t).validate()
    cells = spark.range(p.n * t).select((F.col("id") / t).cast("int").alias("lane"), (F.col("id") % t).cast("int").alias("q"))
    shift = F.when(F.col("lane") >= k, t // 2).otherwise(0)
    block = F.expr(f"(lane % {k}) div {t}") * t
    theta = ((block + shift + F.col("q")) % k).cast("int")
    scale = F.lit(t**-0.5 if scaling == "unit" else 1.0)
    return cells.select("lane", theta.alias("theta"), parity_sign(F.col("lane") % t, F.col("q")).alias("sign"), scale.alias("scale"))


def parity_parts(spark: SparkSession, t: int) -> DataFrame:
    """side (L or R), row, col, sign: the halves of the sign table that a parity block puts on two neighbouring column blocks."""
    half = t // 2
    side = F.when(F.col("beta") < half, "L").otherwise("R")
    return sign_table(spark, t).select(side.alias("side"), F.col("alpha").alias("row"), (F.col("beta") % half).cast("int").alias("col"), "sign")


def replication_code(spark: SparkSession, k: int, r: int) -> DataFrame:
    """r lanes for each task, nothing else: rays repeat, so the least angle is 0."""
    return spark.range(k * r).select(F.col("id").cast("int").alias("lane"), (F.col("id") % k).cast("int").alias("theta"), F.lit(1).alias("sign"), F.lit(1.0).alias("scale"))


def mds_code(spark: SparkSession, n: int, k: int) -> DataFrame:
    """lane, theta, coef: a dense real Vandermonde code on Chebyshev nodes; any k lanes give everything."""
    cells = spark.range(n * k).select((F.col("id") / k).cast("int").alias("lane"), (F.col("id") % k).cast("int").alias("theta"))
    node = F.cos((2 * F.col("lane") + 1) * (3.141592653589793 / (2 * n)))
    return cells.select("lane", "theta", F.pow(node, F.col("theta")).alias("coef"))


def hash_step(key: Column, factor: int = 48271) -> Column:
    """One step of a multiplicative generator modulo a prime; stays far below 64 bits."""
    return (key % 2147483647) * factor % 2147483647


def random_sign_code(spark: SparkSession, n: int, k: int, t: int, seed: int = 1) -> DataFrame:
    """For contrast: t hash-chosen places of a random sign in every lane."""
    cells = spark.range(n * k).select((F.col("id") / k).cast("int").alias("lane"), (F.col("id") % k).cast("int").alias("theta"), F.col("id"))
    h = hash_step(hash_step(F.col("id") + 1 + seed * 1_000_003), 69621)
    cells = cells.withColumn("h", h)
    rank = F.expr("row_number() OVER (PARTITION BY lane ORDER BY h, theta)")
    return cells.withColumn("r", rank).where(F.col("r") <= t).select("lane", "theta", (1 - 2 * F.expr("h div 7 % 2")).cast("int").alias("sign"), F.lit(t**-0.5).alias("scale"))
