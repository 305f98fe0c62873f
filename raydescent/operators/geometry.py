"""How good a code is: weights, angles between rays, information, recoverable subsets. Inner products stay whole numbers."""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.operators.codes import projective_code
from raydescent.plans.params import CodeParams


def weights_of(code: DataFrame, axis: str = "lane") -> DataFrame:
    """lane (or theta), weight: non-zeros per row or column."""
    return code.groupBy(axis).agg(F.count("*").alias("weight"))


def weight_distribution(code: DataFrame, axis: str = "lane") -> DataFrame:
    """weight, how_many: the weight enumerator of the rows or columns."""
    return weights_of(code, axis).groupBy("weight").agg(F.count("*").alias("how_many"))


def replication_factor(code: DataFrame) -> DataFrame:
    """copies, shards, factor: stored shard copies over shards."""
    pairs = code.select("lane", "theta").distinct()
    return pairs.agg(F.count("*").alias("copies"), F.countDistinct("theta").alias("shards")).withColumn("factor", F.col("copies") / F.col("shards"))


def frame_operator(code: DataFrame) -> DataFrame:
    """theta_a, theta_b, product: entries of the code's transpose times itself, in units of scale squared (non-zeros only)."""
    a, b = code.select("lane", F.col("theta").alias("theta_a"), F.col("sign").alias("sa")), code.select("lane", F.col("theta").alias("theta_b"), F.col("sign").alias("sb"))
    return a.join(b, "lane").groupBy("theta_a", "theta_b").agg(F.sum(F.col("sa") * F.col("sb")).alias("product")).where("product <> 0")


def pair_angles(code: DataFrame, t: int) -> DataFrame:
    """lane_a < lane_b, product, angle: pairs that share a column; all others are at right angles and are only counted.

    A column has 2t lanes, so that this is k times 4t squared rows before the sum, not the square of the lanes.
    """
    a, b = code.select("theta", F.col("lane").alias("lane_a"), F.col("sign").alias("sa")), code.select("theta", F.col("lane").alias("lane_b"), F.col("sign").alias("sb"))
    met = a.join(b, "theta").where("lane_a < lane_b").groupBy("lane_a", "lane_b").agg(F.sum(F.col("sa") * F.col("sb")).alias("product"))
    return met.withColumn("angle", F.acos(F.least(F.lit(1.0), F.abs("product") / float(t))))


def angle_profile(code: DataFrame, n: int, t: int) -> DataFrame:
    """product (absolute), angle, pairs: how many pairs of the n lanes stand at each angle."""
    met = pair_angles(code, t).groupBy(F.abs("product").cast("long").alias("product")).agg(F.count("*").alias("pairs"))
    rest = met.agg((F.lit(n * (n - 1) // 2) - F.coalesce(F.sum("pairs"), F.lit(0))).alias("pairs")).select(F.lit(0).cast("long").alias("product"), "pairs")
    all_ = met.union(rest).groupBy("product").agg(F.sum("pairs").alias("pairs")).where("pairs > 0")
    return all_.select("product", F.acos(F.col("product") / float(t)).alias("angle"), "pairs")


def row_angle_profile(code: DataFrame, counts: DataFrame, n: int) -> DataFrame:
    """product (absolute), angle (six digits), pairs: how many pairs of the n lanes stand at each angle over a table's rows.

    A lane is its vector over the rows: its sign on the rows of its shards, 0 elsewhere. counts (part_id, rows) is read
    once, whatever the number of lanes. Uneven shards turn the rays; a lane without rows is at right angles to all.
    """
    held = code.join(counts, code["theta"] == counts["part_id"]).select("lane", "theta", "sign", "rows")
    held = held.withColumn("length", F.sum("rows").over(Window.partitionBy("lane")))
    shards = held.groupBy("theta", "rows").agg(F.collect_list(F.struct("lane", "sign", "length")).alias("held"))
    pairs = shards.select("rows", F.explode("held").alias("a"), "held").select("rows", "a", F.explode("held").alias("b")).where("a.lane < b.lane")
    met = pairs.groupBy(F.col("a.lane").alias("lane_a"), F.col("b.lane").alias("lane_b"), F.col("a.length").alias("la"), F.col("b.length").alias("lb")).agg(F.abs(F.sum(F.col("a.sign") * F.col("b.sign") * F.col("rows"))).alias("product"))
    right = F.struct(F.lit(0).cast("long").alias("product"), F.round(F.lit(math.pi / 2), 6).alias("angle"))
    cosine = F.least(F.lit(1.0), F.col("product") / (F.sqrt("la") * F.sqrt("lb")))
    at = F.when(F.col("product") == 0, right).otherwise(F.struct("product", F.round(F.acos(cosine), 6).alias("angle")))
    # all pairs count as at right angles, and each that meets moves to its own angle: nothing is read twice for the rest
    moved = met.select(F.explode(F.array(F.struct(at.alias("at"), F.lit(1).alias("pairs")), F.struct(right.alias("at"), F.lit(-1).alias("pairs")))).alias("m")).select("m.at", F.col("m.pairs").cast("long").alias("pairs"))
    every = code.sparkSession.range(1).select(right.alias("at"), F.lit(n * (n - 1) // 2).cast("long").alias("pairs"))
    return moved.union(every).groupBy("at").agg(F.sum("pairs").alias("pairs")).where("pairs > 0").select("at.product", "at.angle", "pairs")


def neighbour_counts(code: DataFrame, t: int) -> DataFrame:
    """lane, neighbours: lanes at the code's closest angle (half the weight in common)."""
    close = pair_angles(code, t).where(F.abs("product") * 2 == t)
    ends = close.select(F.col("lane_a").alias("lane")).union(close.select("lane_b"))
    return ends.groupBy("lane").agg(F.count("*").alias("neighbours"))


def optimality_gap(code: DataFrame, n: int, t: int) -> DataFrame:
    """least_angle, abs_gap and rel_gap to the right angle, fraction_of_ideal."""
    least = angle_profile(code, n, t).agg(F.min("angle").alias("least_angle"))
    ideal = math.pi / 2
    return least.select("least_angle", (ideal - F.col("least_angle")).alias("abs_gap"), ((ideal - F.col("least_angle")) / ideal).alias("rel_gap"), (F.col("least_angle") / ideal).alias("fraction_of_ideal"))


def welch_bound(n: int, k: int) -> float:
    """No n rays of k dimensions have a largest cosine below this."""
    return math.sqrt((n - k) / (k * (n - 1))) if n > k else 0.0


def pair_information(code: DataFrame, n: int, t: int) -> DataFrame:
    """product, pairs, nats: mutual information of two lanes' values for independent normal derivatives."""
    share = F.col("product") / float(t)
    return angle_profile(code, n, t).where(F.col("product") < t).select("product", "pairs", (-0.5 * F.log(1 - share * share)).alias("nats"))


def dense(params: CodeParams, scaling: str = "unit") -> np.ndarray:
    """The generator matrix of a power-of-two code (driver; for checks of small codes)."""
    out = np.zeros((params.n, params.k))
    for lane in range(params.n):
        for q in range(params.t):
            out[lane, params.theta(lane, q)] = params.sign(lane, q)
    return out / (math.sqrt(params.t) if scaling == "unit" else 1.0)


def subset_report(spark: SparkSession, params: CodeParams, sizes: list[int] | None = None) -> DataFrame:
    """size, subsets, full_rank, sum_recoverable, mean_entropy over all lane subsets of the sizes asked (codes of up to about 16 lanes).

    mean_entropy: mean of half the logarithm of the Gram determinant, over the subsets where it is not singular.
    """
    matrix = dense(params)
    wanted = spark.createDataFrame([(m, list(s)) for m in sizes or range(1, params.n + 1) for s in combinations(range(params.n), m)], "size int, lanes array<int>")

    def judge(batches):
        for pdf in batches:
            rank, ones, entropy = [], [], []
            for lanes in pdf["lanes"]:
                part = matrix[list(lanes)]
                r = np.linalg.matrix_rank(part)
                rank.append(bool(r == params.k))
                ones.append(bool(np.linalg.matrix_rank(np.vstack([part, np.ones(params.k)])) == r))
                gram = np.linalg.det(part @ part.T)
                entropy.append(0.5 * math.log(gram) if gram > 1e-9 else None)
            yield pdf.assign(full=rank, ones=ones, entropy=entropy)[["size", "full", "ones", "entropy"]]

    judged = wanted.repartition(8).mapInPandas(judge, "size int, full boolean, ones boolean, entropy double")
    return judged.groupBy("size").agg(F.count("*").alias("subsets"), F.sum(F.col("full").cast("long")).alias("full_rank"), F.sum(F.col("ones").cast("long")).alias("sum_recoverable"), F.avg("entropy").alias("mean_entropy"))


def code_sweep(spark: SparkSession, sizes: list[tuple[int, int, int]]) -> DataFrame:
    """n, k, t, least_angle, largest_cosine, welch, neighbours, closest pairs for several codes."""
    out = None
    for n, k, t in sizes:
        code = projective_code(spark, k, t, n=n)
        prof = angle_profile(code, n, t).agg(F.min("angle").alias("least_angle"), F.max(F.col("product") / float(t)).alias("largest_cosine"), F.max(F.struct("product", "pairs")).alias("m"))
        row = prof.select(F.lit(n).alias("n"), F.lit(k).alias("k"), F.lit(t).alias("t"), "least_angle", "largest_cosine", F.lit(welch_bound(n, k)).alias("welch"), F.col("m.pairs").alias("closest_pairs"))
        out = row if out is None else out.union(row)
    return out


def degenerate_pair(spark: SparkSession, steps: int = 16, lipschitz: float = 1.0) -> DataFrame:
    """eps, first, second: two directions that are almost one line both report almost nothing far from an optimum.

    The gradient is (L, -L); the first direction (1, 1)/sqrt 2 sees 0, the second, turned by eps, sees -sqrt 2 L sin eps.
    """
    eps = (F.col("id") + 1) * (math.pi / 2 / steps)
    return spark.range(steps).select(eps.alias("eps"), F.lit(0.0).alias("first"), (-math.sqrt(2) * lipschitz * F.sin(eps)).alias("second"))
