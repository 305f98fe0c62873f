"""Schemes as two relations: what a lane sums into its message, and how the master takes a message apart.

encode (lane, part_id, group, slot, coef): the message's slot is the sum of coef times the gradient group on the shard.
decode (lane, slot, group, coef): what the message adds to each gradient group. With signs only, encoding and decoding
are additions; constants are left to the step size.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.plans.params import CodeParams, Embedding


@dataclass(frozen=True)
class Scheme:
    """name; n lanes; k shards; t groups of parameters; encode and decode rows; slots in a message.

    rows_share: the part of all examples that a message speaks for, when shards are of equal size; a master that
    averages messages divides by it.
    """

    name: str
    n: int
    k: int
    t: int
    slots: int
    encode: tuple[tuple[int, int, int, int, float], ...]
    decode: tuple[tuple[int, int, int, float], ...]
    rows_share: float

    def shards_of(self, lane: int) -> list[int]:
        return sorted({r[1] for r in self.encode if r[0] == lane})

    @property
    def load(self) -> float:
        """How many n-ths of all rows the busiest lane handles."""
        held: dict[int, set[int]] = {}
        for lane, shard, *_ in self.encode:
            held.setdefault(lane, set()).add(shard)
        return self.n / self.k * max(map(len, held.values()))

    def encode_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(list(self.encode), "lane int, part_id int, group int, slot int, coef double")

    def decode_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(list(self.decode), "lane int, slot int, group int, coef double")


def coded_scheme(p: CodeParams, mode: str = "support", scaling: str = "sign") -> Scheme:
    """The sparse projective scheme. mode 'support': all groups on the lane's t shards; 'pure': each derivative on its own block of t shards."""
    p.validate()
    scale = 1.0 if scaling == "sign" else p.t**-0.5
    encode, decode = [], []
    for lane in range(p.n):
        signs = p.group_signs(lane)
        for q in range(p.t):
            theta = p.theta(lane, q)
            if mode == "support":
                encode += [(lane, theta, g, 0, scale * signs[g]) for g in range(p.t)]
            else:
                block = theta // p.t * p.t
                encode += [(lane, shard, theta % p.t, 0, scale * p.sign(lane, q)) for shard in range(block, block + p.t)]
        decode += [(lane, 0, g, scale * signs[g]) for g in range(p.t)]
    return Scheme(f"coded_{mode}_{scaling}", p.n, p.k, p.t, 1, tuple(encode), tuple(decode), p.t / p.k)


def rotated_scheme(e: Embedding, wave: int) -> Scheme:
    """The scheme of one wave on the torus; lanes without a task send nothing and have no rows."""
    lanes = min(e.rows, 2 * e.cols)
    code = CodeParams(lanes, e.cols, e.t).validate()
    encode, decode = [], []
    for lane in range(e.n):
        row = (lane + wave * e.step) % e.rows % lanes
        signs = code.group_signs(row)
        on = {code.theta(row, q) for q in range(e.t)}
        tasks = sorted({(slot + wave) % e.k for slot in range(e.k) if (slot + wave) % e.cols in on})
        encode += [(lane, task, g, 0, float(signs[g])) for task in tasks for g in range(e.t)]
        decode += [(lane, 0, g, float(signs[g])) for g in range(e.t) if tasks]
    return Scheme(f"coded_wave_{wave}", e.n, e.k, e.t, 1, tuple(encode), tuple(decode), e.t / e.cols)


def uncoded_scheme(p: CodeParams) -> Scheme:
    """The same shards at the same lanes, sent whole: the rival without a code."""
    encode = tuple((lane, p.theta(lane, q), 0, 0, 1.0) for lane in range(p.n) for q in range(p.t))
    return Scheme("uncoded", p.n, p.k, 1, 1, encode, tuple((lane, 0, 0, 1.0) for lane in range(p.n)), p.t / p.k)


def synchronous_scheme(n: int) -> Scheme:
    """A shard for every lane; the master needs them all."""
    return Scheme("synchronous", n, n, 1, 1, tuple((i, i, 0, 0, 1.0) for i in range(n)), tuple((i, 0, 0, 1.0) for i in range(n)), 1 / n)


def nested_scheme(p: CodeParams, layers: int) -> Scheme:
    """The code on a network cut by repeated splitting: the layer q steps before the output has t^(q+1) groups, whose sign is
    the product of the signs of the group's digits to base t. A message has a slot per layer; groups are numbered through
    all layers (see NestedLayout). Groups whose digits are permutations of each other have one sign in every lane, so that
    their derivatives arrive mixed: more is saved, and less can be told apart, than with a flat cut."""
    p.validate()
    encode, decode, first = [], [], 0
    for layer in range(layers):
        depth = layers - layer
        for lane in range(p.n):
            signs = p.group_signs(lane)
            for group in range(p.t**depth):
                sign = float(np.prod([signs[group // p.t**d % p.t] for d in range(depth)]))
                encode += [(lane, shard, first + group, layer, sign) for shard in p.shards_of(lane)]
                decode.append((lane, layer, first + group, sign))
        first += p.t**depth
    return Scheme("coded_nested", p.n, p.k, first, layers, tuple(encode), tuple(decode), p.t / p.k)


def ray_scheme(name: str, rows: list[tuple[int, int, float]], k: int, t: int) -> Scheme:
    """Messages by any code (lane, theta, coef) on derivatives theta = group theta mod t on the t shards of block theta div t.
    Rows are brought to the squared length t, that of a row of t signs."""
    n = 1 + max(r[0] for r in rows)
    length = [sum(c * c for lane, _, c in rows if lane == i) for i in range(n)]
    scaled = [(lane, theta, coef * (t / length[lane]) ** 0.5) for lane, theta, coef in rows]
    encode = [(lane, shard, theta % t, 0, c) for lane, theta, c in scaled for shard in range(theta // t * t, theta // t * t + t)]
    return Scheme(name, n, k, t, 1, tuple(encode), tuple((lane, 0, theta % t, c) for lane, theta, c in scaled), t / k)


def repeated_scheme(k: int, r: int) -> Scheme:
    """r lanes for each shard."""
    return Scheme("replication", k * r, k, 1, 1, tuple((i, i % k, 0, 0, 1.0) for i in range(k * r)), tuple((i, 0, 0, 1.0) for i in range(k * r)), 1 / k)


def lane_messages(cells: DataFrame, encode: DataFrame, read: DataFrame | None = None) -> DataFrame:
    """lane, version, slot, pos, value: messages from shard gradients (version, part_id, group, pos, value).

    read (lane, version): the version that each lane has worked on; without it every lane answers for every version.
    Gradients are made once per shard and version; that t lanes use them costs a broadcast join, not t scans.
    """
    table = encode if read is None else encode.join(read, "lane")
    keys = ["part_id", "group"] + (["version"] if read is not None else [])
    met = cells.join(F.broadcast(table), keys)
    return met.groupBy("lane", "version", "slot", "pos").agg(F.sum(F.col("coef") * F.col("value")).alias("value"))


def decode_messages(messages: DataFrame, decode: DataFrame) -> DataFrame:
    """group, pos, delta: the sum over the messages of what each adds to the groups."""
    met = messages.join(F.broadcast(decode), ["lane", "slot"])
    return met.groupBy("group", "pos").agg(F.sum(F.col("coef") * F.col("value")).alias("delta"))


def apply_message(total: np.ndarray, payload: np.ndarray, decode: list[tuple[int, int, float]]) -> None:
    """Add one message (slots x block) to total (groups x block) in place: decoding at arrival, without a solve."""
    for slot, group, coef in decode:
        if coef == 1.0:
            total[group] += payload[slot]
        elif coef == -1.0:
            total[group] -= payload[slot]
        else:
            total[group] += coef * payload[slot]
