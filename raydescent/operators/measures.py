"""Costs and outcomes of runs as relations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def cost_table(spark: SparkSession, sizes: list[tuple[int, int, int]], parameters: int) -> DataFrame:
    """scheme, n, k, t, weight, encode_mults, floats_per_message, decode_adds, decode_mults, copies (of each shard), asynchronous, compresses.

    The exact scheme takes n lanes of which any k must do; its solve is counted as k^2.38 multiplications.
    """
    given = spark.createDataFrame(sizes, "n int, k int, t int")
    n, k, t, p = F.col("n"), F.col("k"), F.col("t"), F.lit(parameters)
    whole = lambda c: c.cast("long")

    def scheme(name: str, weight: Column, encode: Column, sent: Column, adds: Column, mults: Column, copies: Column, asynchronous: bool, compresses: bool) -> DataFrame:
        return given.select(F.lit(name).alias("scheme"), "n", "k", "t", whole(weight).alias("weight"), whole(encode).alias("encode_mults"), whole(sent).alias("floats_per_message"), whole(adds).alias("decode_adds"), mults.cast("double").alias("decode_mults"), copies.cast("double").alias("copies"), F.lit(asynchronous).alias("asynchronous"), F.lit(compresses).alias("compresses"))

    coded = scheme("coded", t, F.lit(0), F.ceil(p / t), t, F.lit(0), n * t / k, True, True)
    exact = scheme("exact", n - k + 1, n * k, p, F.lit(0), F.pow(k, F.lit(2.38)), (n - k + 1).cast("double"), False, False)
    uncoded = scheme("uncoded", t, F.lit(0), p, F.lit(1), F.lit(0), n * t / k, True, False)
    return coded.union(exact).union(uncoded)


def communication_rollup(costs: DataFrame) -> DataFrame:
    """scheme, n, floats: numbers sent by all lanes once, summed by scheme and size and by scheme."""
    return costs.rollup("scheme", "n").agg(F.sum(F.col("floats_per_message") * F.col("n")).cast("long").alias("floats"))


def gradient_error(decoded: DataFrame, exact: DataFrame, factor: float = 1.0) -> DataFrame:
    """relative_error (of decoded times factor) and cosine to exact; both are group, pos, and delta or value."""
    a = decoded.select("group", "pos", (F.col("delta") * factor).alias("a"))
    b = exact.select("group", "pos", F.col("value").alias("b"))
    met = a.join(b, ["group", "pos"], "full").select(F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("b", F.lit(0.0)).alias("b"))
    s = met.agg(F.sum((F.col("a") - F.col("b")) ** 2).alias("d"), F.sum(F.col("a") * F.col("b")).alias("ab"), F.sum(F.col("a") ** 2).alias("aa"), F.sum(F.col("b") ** 2).alias("bb"))
    return s.select(F.sqrt(F.col("d") / F.col("bb")).alias("relative_error"), (F.col("ab") / F.sqrt(F.col("aa") * F.col("bb"))).alias("cosine"))


def time_to_target(curve: DataFrame, target: float) -> DataFrame:
    """run_id, scheme, update_no, virtual_time, floats_sent of the first point at or below the target test loss; null if never reached."""
    hit = F.col("test_loss") <= target
    first = lambda c: F.min(F.when(hit, F.col(c))).alias(c)  # noqa: E731  all of them grow along a run
    return curve.groupBy("run_id", "scheme").agg(first("update_no"), first("virtual_time"), first("floats_sent"))


def overfit_points(curve: DataFrame) -> DataFrame:
    """run_id, update_no, test_loss, overfits: points above the least test loss so far while the train loss still falls."""
    along = Window.partitionBy("run_id").orderBy("update_no")
    least = F.min("test_loss").over(along.rowsBetween(Window.unboundedPreceding, 0))
    falls = F.col("train_loss") < F.lag("train_loss").over(along)
    return curve.select("run_id", "update_no", "test_loss", ((F.col("test_loss") > least) & F.coalesce(falls, F.lit(False))).alias("overfits"))


def smoothed(curve: DataFrame, points: int = 5) -> DataFrame:
    """curve with the moving average of the test loss over the last points."""
    along = Window.partitionBy("run_id").orderBy("update_no").rowsBetween(1 - points, 0)
    return curve.withColumn("test_loss_smooth", F.avg("test_loss").over(along))


def read_as_of(messages: DataFrame, published: DataFrame, width: float = 3600.0) -> DataFrame:
    """messages (lane, started_at) with the newest version (version, published_at) at or before their start; null before the first.

    A version holds from its publication to the next. These spans are laid out on bins of width seconds, so that messages
    meet them by an equal bin and a comparison, and no message sees all publications.
    """
    last = messages.agg(F.max("started_at")).first()[0]
    until = F.lead("published_at").over(Window.orderBy("published_at", "version"))  # of publications: one row an update
    spans = published.select("version", "published_at", until.alias("until")).where(F.col("until").isNull() | (F.col("until") > F.col("published_at")))
    floor = lambda c: F.floor(c / width)
    end = floor(F.least(F.coalesce("until", F.lit(last)), F.lit(last)))
    spans = spans.where(F.col("published_at") <= F.lit(last)).withColumn("_bin", F.explode(F.sequence(floor(F.col("published_at")), end)))
    met = (floor(F.col("started_at")) == F.col("_bin")) & (F.col("started_at") >= F.col("published_at")) & (F.col("until").isNull() | (F.col("started_at") < F.col("until")))
    return messages.join(spans, met, "left").select(*messages.columns, F.col("version").alias("read_version"))
