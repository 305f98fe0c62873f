"""Readers and writers: pruned table scans, other file formats, shard layout, weights and metrics."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from raydescent.operators.layout import assign_shards


def load_table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A Parquet table, with only the columns asked."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_any(spark: SparkSession, path: str, fmt: str, schema: StructType | str) -> DataFrame:
    """json, csv, orc, parquet or text with a given schema; nothing is inferred."""
    reader = spark.read.format(fmt)
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.load(path) if fmt == "text" else reader.schema(schema).load(path)


def write_shards(examples: DataFrame, path: str, key: str = "row_key", files_per_shard: int = 1) -> None:
    """One stored copy, a folder per shard, so that an update reads only the shards of its lanes (partition pruning).

    files_per_shard spreads every shard over that many tasks and files.
    """
    salt = F.pmod(F.xxhash64(key), F.lit(files_per_shard))
    examples.repartition("part_id", salt).sortWithinPartitions(key).write.partitionBy("part_id").parquet(path)


def read_shards(spark: SparkSession, path: str, shards: list[int] | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return df if shards is None else df.where(F.col("part_id").isin(shards))


def write_bucketed(examples: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed by shard, whose later joins and sums by part_id need no shuffle."""
    examples.write.bucketBy(buckets, "part_id").sortBy("row_key").saveAsTable(name)


def save_weights(spark: SparkSession, weights: list[np.ndarray], path: str, run_id: str, version: int) -> None:
    """Weights as rows under path/run/version; a version's folder is complete or absent (the commit of the write)."""
    rows = [(layer, out, w[out].tolist()) for layer, w in enumerate(weights) for out in range(len(w))]
    spark.createDataFrame(rows, "layer int, out_unit int, values array<double>").coalesce(1).write.parquet(f"{path}/run_id={run_id}/version={version}")


def load_weights(spark: SparkSession, path: str, run_id: str, version: int | None = None) -> tuple[int, list[np.ndarray]]:
    """The weights of a version, or of the newest one. They are as large as the model, which the driver holds anyway."""
    df = spark.read.option("basePath", path).parquet(f"{path}/run_id={run_id}")
    if version is None:
        version = df.agg(F.max("version")).first()[0]
    rows = df.where(F.col("version") == version).orderBy("layer", "out_unit").collect()
    return version, [np.array([r["values"] for r in rows if r["layer"] == layer]) for layer in sorted({r["layer"] for r in rows})]


def long_weights(spark: SparkSession, weights: list[np.ndarray], version: int = 0) -> DataFrame:
    """version, layer, out_unit, in_unit, w: weights for SQL."""
    rows = [(version, layer, o, i, float(w[o, i])) for layer, w in enumerate(weights) for o in range(w.shape[0]) for i in range(w.shape[1])]
    return spark.createDataFrame(rows, "version long, layer int, out_unit int, in_unit int, w double")


def examples_from(df: DataFrame, key: str, x, y, k: int, *carried: str) -> DataFrame:
    """row_key, part_id, split, x array<double>, y double from column expressions; columns carried on stand after them."""
    rows = df.select(F.col(key).cast("long").alias("row_key"), x.cast("array<double>").alias("x"), y.cast("double").alias("y"), *carried)
    return assign_shards(rows, "row_key", k)
