"""Shared plumbing of the training-text operators: shared storage, skew-safe lookups, text splitting."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.session import shared_folder

#: A key that holds more than this share of all rows is joined by broadcast; so there are at most 1/HOT_SHARE such keys.
HOT_SHARE = 1 / 1024

#: Rows of a short table that is sent to all executors at most; a longer one is joined by a shuffle.
BROADCAST_ROWS = 1_000_000

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ASCII_LOWER = bytes.maketrans(UPPER.encode(), LOWER.encode())


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Application to the folders that cut() has written in it, in order.
_WRITTEN: dict[str, list[str]] = {}


def _written(spark: SparkSession) -> list[str]:
    return _WRITTEN.setdefault(spark.sparkContext.applicationId, [])


def new_folder(spark: SparkSession, label: str) -> str:
    """A folder of its own in the shared one, to be removed like the tables that cut() writes."""
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    _written(spark).append(path)
    return path


def cut(df: DataFrame, label: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it again: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = new_folder(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def checked_broadcast(df: DataFrame, label: str) -> DataFrame:
    """df as a written table, to be broadcast if it has no more than BROADCAST_ROWS rows; else Spark joins it by a shuffle."""
    held = cut(df, label)
    return F.broadcast(held) if held.count() <= BROADCAST_ROWS else held


def drop_cut(df: DataFrame) -> None:
    """Remove what cut() wrote, once nothing reads it any more."""
    for path in {os.path.dirname(f) for f in df.inputFiles()}:
        _remove(df.sparkSession, path)


def cuts(spark: SparkSession) -> list[str]:
    """The folders that cut() has written in this application, in order."""
    return list(_written(spark))


def clear_cuts(spark: SparkSession, paths: list[str]) -> None:
    """Remove written tables whose readers have all been written themselves."""
    for path in paths:
        _remove(spark, path)
        if path in _written(spark):
            _written(spark).remove(path)


@contextmanager
def owned_cuts(spark: SparkSession) -> Iterator[None]:
    """Tables that operators write for themselves within are removed at the end; what is made of them must be stored before."""
    before = set(cuts(spark))
    try:
        yield
    finally:
        clear_cuts(spark, [path for path in cuts(spark) if path not in before])


def _remove(spark: SparkSession, name: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(name)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only, on the JVM. lower() does the same wherever ASCII is concerned, but for the two
    other characters whose lower case holds ASCII letters; only texts that hold them take the slow translate()."""
    odd = text.contains("İ") | text.contains("K")
    return F.when(odd, F.translate(text, UPPER, LOWER)).otherwise(F.lower(text))


def spare(taken: Iterable[str], *names: str) -> list[str]:
    """names, each with as many underscores in front as it takes to differ from all that are taken (in any case)."""
    used, out = {c.lower() for c in taken}, []
    for name in names:
        while name.lower() in used:
            name = "_" + name
        used.add(name.lower())
        out.append(name)
    return out


def skew_safe_lookup(rows: DataFrame, facts: DataFrame, key: str, weight: str, total: int) -> DataFrame:
    """Left join rows with facts (one row per key; weight: how many of the total rows hold the key).

    Keys with more than HOT_SHARE of all rows are at most 1/HOT_SHARE, so they are broadcast; all others are
    shuffled, and of a hot key nothing is shuffled to one place, as its rows go by a hash of the row. (Not by a running
    number: a task that is run again may see its rows in another order, and would deal them anew.)
    Null keys find nothing. The columns of facts besides key must not be in rows.
    """
    cols = [c for c in facts.columns if c != key]
    hk, hot_, ck, cold_, jk, found = spare([*rows.columns, *facts.columns], "_hk", "_hot", "_ck", "_cold", "_jk", "_f")
    hot_from = max(total * HOT_SHARE, 1000)
    hot = facts.where(F.col(weight) > hot_from).select(F.col(key).alias(hk), F.struct(*cols).alias(hot_))
    cold = facts.where(F.col(weight) <= hot_from).select(F.col(key).cast("string").alias(ck), F.struct(*cols).alias(cold_))
    hashable = [F.col(f"`{f.name}`") for f in rows.schema if not any(x in f.dataType.simpleString() for x in ("map<", "variant"))]
    scatter = F.concat(F.lit("\u0000"), F.xxhash64(*hashable).cast("string"))
    out = rows.join(F.broadcast(hot), F.col(key) == F.col(hk), "left")
    out = out.withColumn(jk, F.when(F.col(hot_).isNull() & F.col(key).isNotNull(), F.col(key).cast("string")).otherwise(scatter))
    out = out.join(cold, F.col(jk) == F.col(ck), "left").withColumn(found, F.coalesce(hot_, cold_))
    return out.select(*[F.col(f"`{c}`") for c in rows.columns], *[F.col(found)[c].alias(c) for c in cols])


def sorted_groups(batches, keys: list[str], least_rows: int = 1) -> Iterator[pa.Table]:
    """Tables of whole groups (rows that agree in keys) from batches that are sorted by them, as the batches stream past:
    as many groups in a table as it takes to have least_rows rows. What is held is a table and a batch."""
    now, held, rows = None, [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy() for k in keys]
        new = np.zeros(batch.num_rows, bool)
        for c in columns:
            new[1:] |= c[1:] != c[:-1]
        new[0] = tuple(c[0] for c in columns) != now
        now = tuple(c[-1] for c in columns)
        at = 0
        for edge in np.flatnonzero(new).tolist():
            if rows + edge - at >= least_rows and rows + edge > at:
                if edge > at:
                    held.append(batch.slice(at, edge - at))
                yield pa.Table.from_batches(held)
                held, rows, at = [], 0, edge
        held.append(batch.slice(at))
        rows += batch.num_rows - at
    if held:
        yield pa.Table.from_batches(held)


def grouped(rows: DataFrame, *keys: str, within: tuple = ()) -> DataFrame:
    """rows dealt and sorted by keys (then by within), for sorted_groups."""
    return rows.repartition(*keys).sortWithinPartitions(*keys, *within)
