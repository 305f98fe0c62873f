"""Gradients by shard: one pass over the examples for all weight versions that an update needs.

Every Arrow batch is multiplied in numpy and added into one array per (version, shard) of the task, so that a task hands
on a row per version, shard and group. Small blocks are added up by the JVM, element by element with partial aggregation;
large ones as slices of an array, which stream past sorted, in two steps over salted keys. Neither a reducer nor the
driver ever holds the rows of all tasks of a shard.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from raydescent.plans.models import GroupLayout, gradients, losses

Kernel = Callable[..., list[np.ndarray]]
BLOCK_SCHEMA = "version long, part_id int, group int, first int, values array<double>, n_rows long"
#: Numbers in one row at most, so that rows of large models stay small.
SLICE = 8192
#: Blocks of more numbers are added up as slices.
LONG_BLOCK = 65_536
#: Parts of a slice's rows that are added up apart before they are added together.
SALTS = 64


def _matrix(column: pa.ChunkedArray | pa.Array, width: int) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return np.asarray(flat, np.float64).reshape(-1, width)


def shard_blocks(examples: DataFrame, weights: dict[int, list[np.ndarray]], wanted: dict[int, list[int]], layout: GroupLayout, kernel: Kernel = gradients) -> DataFrame:
    """Partial gradient blocks: version, part_id, group, first, values, n_rows; a row per task, and not yet added up.

    wanted: the versions whose gradient each shard owes. Rows of other shards are filtered at the scan (partition
    pruning, if the examples are stored by part_id). Rows with a null x or y are left out.
    """
    held = examples.sparkSession.sparkContext.broadcast((weights, wanted))

    def run(batches):
        versions, owed = held.value
        for (version, shard), (g, n) in task_sums(batches, versions, owed, layout, kernel).items():
            for group in range(layout.t):
                firsts = list(range(0, g.shape[1], SLICE))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([version] * len(firsts), pa.int64()), pa.array([shard] * len(firsts), pa.int32()), pa.array([group] * len(firsts), pa.int32()), pa.array(firsts, pa.int32()), pa.array([g[group, f : f + SLICE] for f in firsts], pa.list_(pa.float64())), pa.array([n] * len(firsts), pa.int64())],
                    ["version", "part_id", "group", "first", "values", "n_rows"],
                )

    return owed_rows(examples, wanted).mapInArrow(run, BLOCK_SCHEMA)


def owed_rows(examples: DataFrame, wanted: dict[int, list[int]]) -> DataFrame:
    rows = examples.where(F.col("part_id").isin(sorted(wanted)) & F.col("x").isNotNull() & F.col("y").isNotNull())
    return rows.select("part_id", "x", F.col("y").cast("double").alias("y"))


def task_sums(batches, versions: dict, owed: dict[int, list[int]], layout: GroupLayout, kernel: Kernel) -> dict[tuple[int, int], tuple[np.ndarray, int]]:
    """(version, shard) to (groups x block gradient sum, rows) over a task's batches."""
    sums: dict[tuple[int, int], tuple[np.ndarray, int]] = {}
    for batch in batches:
        if not batch.num_rows:
            continue
        part = batch.column("part_id").to_numpy()
        x, y = _matrix(batch.column("x"), layout.spec.inputs), batch.column("y").to_numpy(zero_copy_only=False)
        order = np.argsort(part, kind="stable")
        part, x, y = part[order], x[order], y[order]
        edges = np.r_[np.flatnonzero(np.r_[True, part[1:] != part[:-1]]), len(part)]
        for lo, hi in zip(edges[:-1], edges[1:]):
            shard = int(part[lo])
            for version in owed.get(shard, ()):
                g = layout.split(kernel(layout.spec, versions[version], x[lo:hi], y[lo:hi]))
                had, n = sums.get((version, shard), (0.0, 0))
                sums[version, shard] = (had + g, n + int(hi - lo))
    return sums


def coded_sums(examples: DataFrame, versions: dict[int, list[np.ndarray]], asked: list[tuple[int, int]], encode: list[tuple[int, int, int, int, float]], slots: int, layout: GroupLayout, kernel: Kernel = gradients, sent: list | None = None) -> DataFrame:
    """lane, version, slot, first, values: messages of the (lane, version) asked, encoded in the tasks that have the gradients.

    As encoding is linear, a task sends its part of each message (a block a lane) instead of its part of each shard's
    gradient (t blocks a shard and version), and the parts are added up on the way. The broadcast weights are appended to
    sent, so that the caller can let go of them. values are slices from first on; of one number where blocks are small.
    """
    lanes: dict[int, list] = {}
    for lane, part, group, slot, coef in encode:
        lanes.setdefault(lane, []).append((part, group, slot, coef))
    wanted: dict[int, list[int]] = {}
    for lane, version in asked:
        for part, *_ in lanes.get(lane, ()):
            if version not in wanted.setdefault(part, []):
                wanted[part].append(version)
    held = examples.sparkSession.sparkContext.broadcast((versions, wanted, lanes, asked))
    if sent is not None:
        sent.append(held)

    def run(batches):
        weights, owed, rows, some = held.value
        sums = task_sums(batches, weights, owed, layout, kernel)
        for lane, version in some:
            message = np.zeros((slots, layout.block))
            for part, group, slot, coef in rows.get(lane, ()):
                if (version, part) in sums:
                    message[slot] += coef * sums[version, part][0][group]
            for slot in range(slots):
                firsts = list(range(0, layout.block, SLICE))
                kinds = (pa.int32(), pa.int64(), pa.int32())
                keys = [pa.array([v] * len(firsts), k) for v, k in zip((lane, version, slot), kinds)]
                yield pa.RecordBatch.from_arrays([*keys, pa.array(firsts, pa.int32()), pa.array([message[slot, f : f + SLICE] for f in firsts], pa.list_(pa.float64()))], ["lane", "version", "slot", "first", "values"])

    blocks = owed_rows(examples, wanted).mapInArrow(run, "lane int, version long, slot int, first int, values array<double>")
    keys = ["lane", "version", "slot"]
    if layout.block > LONG_BLOCK:
        return summed_slices(blocks, keys)
    return summed(blocks, keys).select(*keys, F.col("pos").alias("first"), F.array("value").alias("values"))


def summed_slices(blocks: DataFrame, keys: list[str]) -> DataFrame:
    """keys, first, values: slices added up by array, first in salted parts, then together. A task holds a slice at a time."""
    names = [*keys, "first"]
    types = {f.name: f.dataType.simpleString() for f in blocks.schema}
    made = ", ".join(f"{n} {types[n]}" for n in names) + ", values array<double>"
    kinds = [pa.int32() if types[n] == "int" else pa.int64() for n in names]

    def run(batches):
        now, total = None, None
        for batch in batches:
            for *key, values in zip(*(batch.column(c).to_pylist() for c in names), batch.column("values")):
                x = values.values.to_numpy()
                if key != now:
                    if now is not None:
                        yield row(now, total)
                    now, total = key, x.copy()
                else:
                    total += x
        if now is not None:
            yield row(now, total)

    def row(key, total):
        return pa.RecordBatch.from_arrays([*(pa.array([v], k) for v, k in zip(key, kinds)), pa.array([total], pa.list_(pa.float64()))], [*names, "values"])

    rows = blocks.select(*names, "values")
    salted = rows.withColumn("_salt", F.pmod(F.spark_partition_id(), F.lit(SALTS)))
    part = salted.repartition(*names, "_salt").sortWithinPartitions(*names, "_salt").select(*names, "values")
    return part.mapInArrow(run, made).repartition(*names).sortWithinPartitions(*names).mapInArrow(run, made)


def summed(blocks: DataFrame, keys: list[str]) -> DataFrame:
    """blocks added up element by element over keys: keys..., pos, value. (n_rows is not carried.)"""
    cells = blocks.select(*keys, "first", F.posexplode("values").alias("_p", "_v"))
    return cells.groupBy(*keys, (F.col("first") + F.col("_p")).alias("pos")).agg(F.sum("_v").alias("value"))


def shard_gradients(examples: DataFrame, weights: dict[int, list[np.ndarray]], wanted: dict[int, list[int]], layout: GroupLayout, kernel: Kernel = gradients) -> DataFrame:
    """version, part_id, group, pos, value."""
    return summed(shard_blocks(examples, weights, wanted, layout, kernel), ["version", "part_id", "group"])


def evaluate(examples: DataFrame, versions: dict[int, list[np.ndarray]], spec, by: str | None = None, sent: list | None = None) -> DataFrame:
    """version (and by), n_rows, loss, error: means over the examples, of several versions in one scan. The broadcast weights
    are appended to sent."""
    held = examples.sparkSession.sparkContext.broadcast(versions)
    if sent is not None:
        sent.append(held)
    keys = [by] if by else []

    def run(batches):
        sums: dict[tuple, list[float]] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = _matrix(batch.column("x"), spec.inputs), batch.column("y").to_numpy(zero_copy_only=False)
            label = np.array(batch.column(by).to_pylist(), dtype=object) if by else np.full(len(y), "", object)
            for version, w in held.value.items():
                loss, wrong = losses(spec, w, x, y)
                for key in set(label.tolist()):
                    at = label == key
                    s = sums.setdefault((version, key), [0, 0.0, 0.0])
                    s[0] += int(at.sum())
                    s[1] += float(loss[at].sum())
                    s[2] += float(wrong[at].sum())
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in sums], pa.int64()), pa.array([str(k[1]) for k in sums]), *[pa.array([s[i] for s in sums.values()]) for i in range(3)]], ["version", "label", "n", "l", "e"])

    rows = examples.where(F.col("x").isNotNull() & F.col("y").isNotNull()).select("x", F.col("y").cast("double").alias("y"), *keys)
    part = rows.mapInArrow(run, "version long, label string, n long, l double, e double")
    total = part.groupBy("version", "label").agg(F.sum("n").alias("n_rows"), (F.sum("l") / F.sum("n")).alias("loss"), (F.sum("e") / F.sum("n")).alias("error"))
    return total.withColumnRenamed("label", by) if by else total.drop("label")
