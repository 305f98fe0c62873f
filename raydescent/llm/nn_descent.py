"""Near-duplicate vectors by NN-descent.

Equal vectors are one node. Lists of neighbours start from blocks of random projections (rows whose signs agree on some
random directions; all pairs of a bounded block are multiplied). Rounds of NN-descent then send every node's list and
the nodes that list it to one place, multiply them with each other, and keep what improves a list. A list that is full
of neighbours above the threshold is saturated and may be twice as long from the next round on. Links found in any
block or round give the components. As lists are bounded, the links of a component are then counted exactly, by blocked
products within the component, of which only one number a vector comes out; cells of a large component around pivots
whose angles keep all their members apart are not multiplied.

Rows go to a task sorted by block, so that a task holds some blocks at a time, however many it has.

Cosines are in double precision from the stored components throughout. audit_recall() compares the outcome for a set of
query vectors with all rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.llm.bit_planes import spanning
from raydescent.llm.common import checked_broadcast, cut, drop_cut, grouped, skew_safe_lookup, sorted_groups
from raydescent.llm.components import connected_components

BLOCK = 1024
#: Rows that a projection bucket has on average.
BUCKET_ROWS = 512
#: Rows of blocks that a task takes up at once.
PORTION_ROWS = 8192
#: A projection bucket above this share of all rows is dealt to several blocks by Spark; there are at most tables / share of them.
HOT_BUCKET = 1 / 16384
#: Rows of one component in a part of it: a 64th of all rows in components, within these bounds.
LEAST_PART, PART_ROWS = 256, 20_000
#: Pivots of all large components together, and of one.
PIVOTS, COMPONENT_PIVOTS = 8192, 1024
_NO_ID = (1 << 63) - 1


def raw_vectors(rows: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """id, raw (components as little-endian doubles, or floats if stored as floats), null where a vector cannot link."""
    single = rows.schema[vector_col].dataType.simpleString() == "array<float>"
    kind = np.dtype("<f4" if single else "<f8")

    def run(batches):
        for batch in batches:
            v = batch.column("v")
            off, values = v.offsets.to_numpy().astype(np.int64), v.values
            flat = np.asarray((values.fill_null(np.nan) if values.null_count else values).to_numpy(zero_copy_only=False), kind)[off[0] : off[-1]]
            off -= off[0]
            odd, any_ = (np.r_[0, np.cumsum(x)] for x in (~np.isfinite(flat), flat != 0))
            good = np.asarray(v.is_valid()) & (odd[off[1:]] == odd[off[:-1]]) & (any_[off[1:]] > any_[off[:-1]])
            bits, ends = pa.array(good).buffers()[1], pa.py_buffer((off * kind.itemsize).astype("<i4"))
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.Array.from_buffers(pa.binary(), len(good), [bits, ends, pa.py_buffer(np.ascontiguousarray(flat))])], ["id", "raw"])

    wanted = rows.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<float>" if single else "array<double>").alias("v"))
    return wanted.mapInArrow(run, "id long, raw binary")


def _units(raw: list[bytes], kind: str) -> np.ndarray:
    x = np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1).astype(np.float64)
    x /= np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _edges(a, b, c):
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.float64())], ["node", "near", "cos"])


_EDGE = "node long, near long, cos double"


def _runs(*keys: np.ndarray) -> np.ndarray:
    """Edges of the runs of equal keys in sorted columns."""
    new = np.zeros(len(keys[0]), bool)
    new[:1] = True
    for k in keys:
        new[1:] |= k[1:] != k[:-1]
    return np.r_[np.flatnonzero(new), len(new)]


def block_bits(n: int) -> int:
    return max(0, round(math.log2(max(n, 1) / BUCKET_ROWS)))


def block_tables(bits: int, threshold: float, miss: float = 0.02) -> int:
    """How many tables it takes that a pair at the threshold shares no bucket with a chance of miss at most. It agrees on the
    sign of one random direction with 1 - angle/pi, so that tables grow as a root of the number of rows."""
    meet = (1 - math.acos(min(threshold, 1.0)) / math.pi) ** bits
    return 1 if meet == 1 else max(4, math.ceil(math.log(miss) / math.log1p(-meet)))


def block_neighbours(nodes: DataFrame, n: int, kind: str, threshold: float, tables: int | None = None, keep: int = 4, seed: int = 7, bits: int | None = None) -> DataFrame:
    """First neighbours from random-projection blocks: each row's best in its block, and links that span the block's classes.

    bits: directions that make a bucket, block_bits(n) unless given; tables: block_tables(bits) unless given.
    """
    bits = block_bits(n) if bits is None else bits
    tables = tables or block_tables(bits, threshold)

    def key(batches):
        for batch in batches:
            raw = batch.column("raw").to_pylist()
            for width in sorted({len(r) for r in raw}):
                at = [i for i, r in enumerate(raw) if len(r) == width]
                x = _units([raw[i] for i in at], kind)
                for number in range(tables):
                    planes = np.random.default_rng((seed, number)).standard_normal((x.shape[1], bits))
                    code = ((x @ planes > 0) @ (1 << np.arange(bits))) if bits else np.zeros(len(at), np.int64)
                    bucket = (code.astype(np.int64) * tables + number) * 65_536 + width // np.dtype(kind).itemsize % 65_536
                    yield pa.RecordBatch.from_arrays([pa.array(bucket), batch.column("node").take(pa.array(at)), batch.column("raw").take(pa.array(at))], ["bucket", "node", "raw"])

    keyed = nodes.select("node", "raw").mapInArrow(key, "bucket long, node long, raw binary")
    sizes = keyed.groupBy("bucket").agg(F.count("*").alias("_n")).where(F.col("_n") > max(4 * BLOCK, n * HOT_BUCKET))
    large = checked_broadcast(sizes.select(F.col("bucket").alias("_b"), F.ceil(F.col("_n") / BLOCK).cast("int").alias("_parts")), "large")
    rows = keyed.join(large, F.col("bucket") == F.col("_b"), "left")
    rows = rows.withColumn("part", F.pmod(F.xxhash64("node", "bucket"), F.coalesce("_parts", F.lit(1))).cast("int"))

    def multiply(batches):
        for t in sorted_groups(batches, ["bucket", "part"], PORTION_ROWS):
            bucket, part, node = (t.column(c).to_numpy() for c in ("bucket", "part", "node"))
            raw = t.column("raw").to_pylist()
            edges = _runs(bucket, part)
            for lo, hi in zip(edges[:-1], edges[1:]):
                for at in np.array_split(np.arange(lo, hi), -(-(hi - lo) // (2 * BLOCK))):  # a bucket's blocks are of random members
                    if len(at) < 2:
                        continue
                    x = _units(raw[at[0] : at[-1] + 1], kind)
                    c = x @ x.T
                    np.fill_diagonal(c, -2)
                    k = min(keep, len(at) - 1)
                    best = np.argpartition(-c, k - 1, axis=1)[:, :k]
                    own = np.repeat(np.arange(len(at)), k)
                    near = best.ravel()
                    i, j = np.nonzero(np.triu(c >= threshold, 1))
                    if len(i):
                        _, tie = spanning(np.arange(len(at)), i, j, np.zeros(len(i), np.int8))
                        own, near = np.r_[own, j[tie]], np.r_[near, i[tie]]
                    yield _edges(node[at[own]], node[at[near]], c[own, near])

    return grouped(rows.select("bucket", "part", "node", "raw"), "bucket", "part", within=(F.xxhash64("node"),)).mapInArrow(multiply, _EDGE)


def top_lists(candidates: DataFrame, sizes: DataFrame | None, k: int) -> DataFrame:
    """The nearest of each node: k of them, or as many as sizes (node, k) says. First by salted parts, then together."""
    rows = candidates.groupBy("node", "near").agg(F.max("cos").alias("cos"), F.min("old").alias("old"))
    if sizes is None:
        rows = rows.withColumn("k", F.lit(k))
    else:
        rows = rows.join(sizes.select(F.col("node").alias("_n"), "k"), F.col("node") == F.col("_n"), "left").drop("_n").withColumn("k", F.coalesce("k", F.lit(k)))
    rows = rows.withColumn("_salt", F.pmod(F.xxhash64("near"), F.lit(32)))
    by = [F.desc("cos"), F.col("near")]
    rows = rows.withColumn("_r", F.row_number().over(Window.partitionBy("node", "_salt").orderBy(*by))).where("_r <= k")
    rows = rows.withColumn("_r", F.row_number().over(Window.partitionBy("node").orderBy(*by))).where("_r <= k")
    return rows.select("node", "near", "cos", "old", "k")


def improve(lists: DataFrame, state: DataFrame, nodes: DataFrame, k: int, kind: str, threshold: float = 0.9) -> DataFrame:
    """One round: what the members of each list, and of the nodes that list one node, can add to each other's lists; and
    links that span the classes of what has met, whether or not a list has room for them."""
    back = lists.select(F.col("near").alias("at"), F.col("node").alias("member"), "old")
    back = back.withColumn("_salt", F.pmod(F.xxhash64("member"), F.lit(32)))
    back = back.withColumn("_r", F.row_number().over(Window.partitionBy("at", "_salt").orderBy(F.xxhash64("member")))).where(F.col("_r") <= k)
    back = back.withColumn("_r", F.row_number().over(Window.partitionBy("at").orderBy(F.xxhash64("member")))).where(F.col("_r") <= k)
    met = lists.select(F.col("node").alias("at"), F.col("near").alias("member"), "old").union(back.select("at", "member", "old"))
    met = met.groupBy("at", "member").agg(F.min("old").alias("old"))
    info = nodes.select("node", "raw").join(state, "node").select(F.col("node").alias("member"), "raw", "tau")
    gathered = grouped(met.join(info, "member").select("at", "member", "old", "raw", "tau"), "at")

    def joins(t: pa.Table):
        at, member, old, tau = (t.column(c).to_numpy(zero_copy_only=False) for c in ("at", "member", "old", "tau"))
        raw = t.column("raw").to_pylist()
        edges = _runs(at)
        out: list[list[np.ndarray]] = [[], [], []]
        ties: list[list[np.ndarray]] = [[], [], []]
        held = 0
        for lo, hi in zip(edges[:-1], edges[1:]):
            rows = np.arange(lo, hi)
            fresh = ~old[rows].astype(bool)
            if len(rows) < 2 or not fresh.any():
                continue
            x = _units([raw[i] for i in rows], kind)
            c = x @ x.T
            new = fresh[:, None] | fresh[None, :]
            i, j = np.nonzero(np.triu((c >= threshold) & new, 1))
            if len(i):
                _, tie = spanning(np.arange(len(rows)), i, j, np.zeros(len(i), np.int8))
                i, j = i[tie], j[tie]
                for o, v in zip(ties, (member[rows[i]], member[rows[j]], c[i, j])):
                    o.append(v)
            better = (c > tau[rows][:, None] + 1e-12) & new
            np.fill_diagonal(better, False)
            i, j = np.nonzero(better)
            for o, v in zip(out, (member[rows[i]], member[rows[j]], c[i, j])):
                o.append(v)
            held += len(i)
            if held > 200_000:
                yield _best(out, k)
                out, held = [[], [], []], 0
        if held:
            yield _best(out, k)
        if ties[0]:
            yield _edges(*(np.concatenate(o) for o in ties))

    def multiply(batches):
        for t in sorted_groups(batches, ["at"], PORTION_ROWS):
            yield from joins(t)

    return gathered.mapInArrow(multiply, _EDGE)


def _best(out: list[list[np.ndarray]], k: int) -> pa.RecordBatch:
    """Of a portion of candidates each node's 4k best, each once: no list of this node will take more."""
    a, b, c = (np.concatenate(o) for o in out)
    order = np.lexsort((b, -c, a))
    a, b, c = a[order], b[order], c[order]
    once = np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])]
    a, b, c = a[once], b[once], c[once]
    starts = np.flatnonzero(np.r_[True, a[1:] != a[:-1]])
    rank = np.arange(len(a)) - np.repeat(starts, np.diff(np.r_[starts, len(a)]))
    keep = rank < 4 * k
    return _edges(a[keep], b[keep], c[keep])


def list_state(lists: DataFrame, threshold: float, k: int) -> DataFrame:
    """node, k (length allowed), tau (what a neighbour must exceed). Saturated lists may double, up to 4 k."""
    s = lists.groupBy("node").agg(F.count("*").alias("n"), F.min("cos").alias("low"), F.max("k").alias("k0"))
    saturated = (F.col("n") >= F.col("k0")) & (F.col("low") >= threshold)
    s = s.withColumn("k", F.when(saturated, F.least(F.col("k0") * 2, F.lit(4 * k))).otherwise(F.col("k0")).cast("int"))
    return s.select("node", "k", F.when(F.col("n") < F.col("k"), -2.0).otherwise(F.col("low")).alias("tau"))


def descend(nodes: DataFrame, n: int, kind: str, threshold: float, k: int = 10, rounds: int = 5, least_change: float = 0.001, **init) -> DataFrame:
    """Links (a, b) at or above threshold that any block or round has found; enough to span what they connect.

    Rounds end when less than this part of all entries changes, or, from the third on, when as few rows get a new link.
    """
    first = cut(block_neighbours(nodes, n, kind, threshold, **init), "blocks")
    links = [cut(first.where(F.col("cos") >= threshold).select(F.greatest("node", "near").alias("a"), F.least("node", "near").alias("b")).distinct(), "links")]
    lists = cut(top_lists(first.withColumn("old", F.lit(False)), None, k), "lists")
    drop_cut(first)
    for number in range(rounds):
        state = cut(list_state(lists, threshold, k), "state")
        found = cut(improve(lists, state, nodes, k, kind, threshold), "found")
        links.append(found.where(F.col("cos") >= threshold).select(F.greatest("node", "near").alias("a"), F.least("node", "near").alias("b")).distinct())
        candidates = lists.select("node", "near", "cos", F.lit(True).alias("old")).union(found.select("node", "near", "cos", F.lit(False).alias("old")))
        # a neighbour that was there already counts as old even if found again
        flagged = candidates.groupBy("node", "near").agg(F.max("cos").alias("cos"), F.max("old").alias("old"))
        newer = cut(top_lists(flagged, state, k), "lists")
        drop_cut(lists)
        lists = newer
        fresh = lists.where(~F.col("old")).agg(F.count("*").alias("n"), F.count_if(F.col("cos") >= threshold).alias("links")).first()
        if fresh["n"] < least_change * n * k or (number > 1 and fresh["links"] < least_change * n):
            break
    out = links[0]
    for more in links[1:]:
        out = out.union(more)
    return out


def _pivots(large: DataFrame, members: DataFrame, part: int, kind: str) -> dict[int, np.ndarray]:
    """Some members of each large component (component, _n), two for each part it will have, as unit rows: at most PIVOTS in all.
    Components that would have less than two at that limit have none."""
    whole = large.agg(F.sum(F.least(F.lit(COMPONENT_PIVOTS), F.ceil(2 * F.col("_n") / part)))).first()[0] or 0
    wanted = F.least(F.lit(COMPONENT_PIVOTS), F.ceil(2 * F.col("_n") / part)) * min(1.0, PIVOTS / max(whole, 1))
    some = members.join(large, "component").where((wanted >= 2) & (F.pmod(F.xxhash64("node"), F.col("_n")) < F.floor(wanted)))
    out: dict[int, list[bytes]] = {}
    for r in some.select("component", "node", "raw").orderBy(F.xxhash64("node")).limit(2 * PIVOTS).collect():  # about PIVOTS; fewer pivots only prune less
        out.setdefault(r["component"], []).append(bytes(r["raw"]))
    return {c: _units(raw, kind) for c, raw in out.items() if len(raw) > 1}


def _near_cells(cells: list, pivots: dict[int, np.ndarray], part: int, threshold: float) -> list[tuple[int, int, int, int, int]]:
    """(component, cell, its parts, cell it can have links with, that one's parts), by the angles between pivots and of members."""
    by: dict[int, list] = {}
    for r in cells:
        by.setdefault(r["component"], []).append(r)
    out = []
    for component, rows in by.items():
        cell, parts = (np.array(x) for x in zip(*((r["cell"], -(-r["n"] // part)) for r in rows)))
        wide = np.array([r["wide"] for r in rows])
        p = pivots[component][cell]
        apart = np.arccos(np.clip(p @ p.T, -1, 1)) - wide[:, None] - wide[None, :]
        i, j = np.nonzero((apart <= math.acos(threshold) + 1e-6) | np.eye(len(cell), dtype=bool))
        out += zip([component] * len(i), cell[i].tolist(), parts[i].tolist(), cell[j].tolist(), parts[j].tolist())
    return out


def count_links(members: DataFrame, kind: str, threshold: float) -> DataFrame:
    """members (component, node, members, raw; a written table) to node, linked: how many rows of other nodes it links with, exactly.

    A component of more than a part is cut into cells, each member going to its nearest pivot. A pair of cells is
    multiplied unless the angle between the pivots exceeds that of the threshold by more than both cells are wide. Cells
    are cut into parts, and a task takes two parts, so that none holds a whole large component.
    """
    spark = members.sparkSession
    counts = members.groupBy("component").agg(F.count("*").alias("_n"))
    part = min(max(members.count() // 64, LEAST_PART), PART_ROWS)
    large = checked_broadcast(counts.where(F.col("_n") > part), "large")
    marked = members.join(large.withColumnRenamed("component", "_c"), F.col("component") == F.col("_c"), "left").drop("_c")
    whole = lambda c: c.cast("int")
    key = ("component", "p", "q", "x", "y")
    small = marked.where("_n IS NULL").select("component", *[F.lit(v).alias(c) for v, c in ((-1, "p"), (-1, "q"), (0, "x"), (0, "y"), (0, "side"))], "node", "members", "raw")
    pivots = _pivots(large, members, part, kind)
    held = spark.sparkContext.broadcast(pivots)

    def assign(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            component, raw = batch.column("component").to_numpy(), batch.column("raw").to_pylist()
            cell, angle = np.full(len(raw), -1, np.int32), np.zeros(len(raw))
            for c in np.unique(component).tolist():
                p = held.value.get(c)
                rows = np.flatnonzero(component == c) if p is not None else ()
                for at in range(0, len(rows), BLOCK):
                    some = rows[at : at + BLOCK]
                    dots = _units([raw[i] for i in some], kind) @ p.T
                    cell[some] = dots.argmax(axis=1)
                    angle[some] = np.arccos(np.clip(dots.max(axis=1), -1, 1))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("component", "node", "members", "raw", "_n")), pa.array(cell), pa.array(angle)], ["component", "node", "members", "raw", "_n", "cell", "angle"])

    if large.isEmpty():
        dealt = small
    else:
        celled = marked.where("_n IS NOT NULL").select("component", "node", "members", "raw", "_n").mapInArrow(assign, "component long, node long, members long, raw binary, _n long, cell int, angle double")
        celled = cut(celled, "cells")
        seen = celled.where("cell >= 0").groupBy("component", "cell").agg(F.count("*").alias("n"), F.max("angle").alias("wide")).collect()  # as many as there are pivots
        near = spark.createDataFrame(_near_cells(seen, pivots, part, threshold), "_c long, _cell int, own int, other int, others int")
        uncut = F.ceil(F.col("_n") / part)
        plain = large.where(~F.col("component").isin(list(pivots))).select(F.col("component").alias("_c"), F.lit(-1).alias("_cell"), whole(uncut).alias("own"), F.lit(-1).alias("other"), whole(uncut).alias("others"))
        near = checked_broadcast(near.union(plain), "near")
        rows = celled.join(near, (F.col("component") == F.col("_c")) & (F.col("cell") == F.col("_cell")))
        rows = rows.withColumn("_i", whole(F.pmod(F.xxhash64("node"), F.col("own")))).withColumn("_j", F.explode(F.sequence(F.lit(0), F.col("others") - 1)))
        first = (F.col("cell") < F.col("other")) | ((F.col("cell") == F.col("other")) & (F.col("_i") <= F.col("_j")))
        either = lambda a, b, name: F.when(first, F.col(a)).otherwise(F.col(b)).alias(name)
        dealt = small.union(rows.select("component", either("cell", "other", "p"), either("other", "cell", "q"), either("_i", "_j", "x"), either("_j", "_i", "y"), F.when(first, 0).otherwise(1).alias("side"), "node", "members", "raw"))

    def counted(t: pa.Table, lo: int, hi: int, same: bool):
        side, node, many = (t.column(c).to_numpy()[lo:hi] for c in ("side", "node", "members"))
        raw = t.column("raw")[lo:hi].to_pylist()
        rows = np.arange(hi - lo)
        left, right = (rows, rows) if same else (rows[side == 0], rows[side == 1])
        for a, b in ((left, right),) if same else ((left, right), (right, left)):
            total = np.zeros(len(a), np.int64)
            for p in range(0, len(a), 2 * BLOCK):
                u = _units([raw[i] for i in a[p : p + 2 * BLOCK]], kind)
                for q in range(0, len(b) if len(a) else 0, 2 * BLOCK):
                    v = _units([raw[i] for i in b[q : q + 2 * BLOCK]], kind)
                    met = u @ v.T >= threshold
                    if same and p == q:
                        np.fill_diagonal(met, False)
                    total[p : p + 2 * BLOCK] += met @ many[b[q : q + 2 * BLOCK]]
            yield pa.RecordBatch.from_arrays([pa.array(node[a]), pa.array(total)], ["node", "linked"])

    def run(batches):
        for t in sorted_groups(batches, list(key), PORTION_ROWS):
            columns = [t.column(c).to_numpy() for c in key]
            _, p, q, x, y = columns
            edges = _runs(*columns)
            for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist()):
                yield from counted(t, lo, hi, bool(p[lo] == q[lo] and x[lo] == y[lo]))

    found = grouped(dealt, *key).mapInArrow(run, "node long, linked long")
    return found.groupBy("node").agg(F.sum("linked").alias("linked"))


def vector_components(rows: DataFrame, threshold: float = 0.9, id_col: str = "vec_id", vector_col: str = "embedding", **search) -> DataFrame:
    """id, n_links, component_id, kept for every row.

    Vectors that are null, empty or zero, or hold null or non-finite components, link with nothing; vectors of different
    lengths do not link. Equal vectors link with each other. Rows that share an id are rows of their own, and
    a null id is larger than any other. threshold must be positive.
    """
    single = rows.schema[vector_col].dataType.simpleString() == "array<float>"
    kind = "<f4" if single else "<f8"
    raw = cut(raw_vectors(rows, id_col, vector_col), "vectors").withColumn("_key", F.sha2("raw", 256))
    nodes = raw.where("raw IS NOT NULL").groupBy("_key").agg(F.min(F.coalesce("id", F.lit(_NO_ID))).alias("node"), F.count("*").alias("members"), F.any_value("raw").alias("raw"))
    # rows that share an id may stand for several vectors: number them apart, below all ids
    nodes = cut(nodes.withColumn("_same", F.row_number().over(Window.partitionBy("node").orderBy("_key"))), "nodes")
    clash = nodes.where("_same > 1")
    if not clash.isEmpty():
        nodes = cut(nodes.withColumn("name", F.col("node")).withColumn("node", F.when(F.col("_same") > 1, -1 - F.abs(F.xxhash64("_key"))).otherwise(F.col("node"))), "nodes")
    else:
        nodes = nodes.withColumn("name", F.col("node"))
    n = nodes.count()
    links = descend(nodes, n, kind, threshold, **search)
    found = connected_components(links)
    joined = nodes.join(found.withColumnRenamed("node", "_n"), F.col("node") == F.col("_n"), "left").withColumn("component", F.coalesce("component", "node")).drop("_n")
    joined = cut(joined, "classes")
    least = joined.groupBy("component").agg(F.min("name").alias("component_id"), F.count("*").alias("_size"))
    named = cut(skew_safe_lookup(joined, least, "component", "_size", n), "classes")
    counted = count_links(cut(named.where("_size > 1").select("component", "node", "members", "raw"), "members"), kind, threshold)
    facts = named.join(counted.withColumnRenamed("node", "_n"), F.col("node") == F.col("_n"), "left")
    facts = cut(facts.select("_key", "component_id", "members", (F.col("members") - 1 + F.coalesce("linked", F.lit(0))).alias("n_links")), "facts")
    total = facts.agg(F.sum("members")).first()[0] or 0
    out = skew_safe_lookup(raw.select(F.col("id").alias(id_col), "_key"), facts, "_key", "members", total)
    component = F.coalesce("component_id", F.col(id_col))
    out = out.withColumn("component_id", F.when(component != _NO_ID, component))
    return out.select(id_col, F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), "component_id", F.col(id_col).eqNullSafe(F.col("component_id")).alias("kept"))


def audit_recall(rows: DataFrame, result: DataFrame, threshold: float = 0.9, every: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """One row: queries, true_links, found_links, recall. Queries are the rows whose id is divisible by every, against all rows.

    The queries are written once and read by each task in portions, all other rows stream past them.
    """
    single = rows.schema[vector_col].dataType.simpleString() == "array<float>"
    kind = "<f4" if single else "<f8"
    raw = cut(raw_vectors(rows, id_col, vector_col).where("raw IS NOT NULL"), "audit")
    queries = raw.where(F.col("id") % every == 0)
    parts, slices = 1 + queries.count() // PART_ROWS, 16 + raw.count() // (4 * PART_ROWS)
    asked = queries.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")).withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1)))).withColumn("asks", F.lit(True))
    shown = raw.withColumn("id", F.coalesce("id", F.lit(-1))).withColumn("slice", F.pmod(F.xxhash64("id", "raw"), F.lit(slices)).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).withColumn("asks", F.lit(False))

    def run(batches):
        for t in sorted_groups(batches, ["part", "slice"]):
            asks, id_ = (t.column(c).to_numpy(zero_copy_only=False) for c in ("asks", "id"))
            raw_ = t.column("raw").to_pylist()
            widths = np.array([len(x) for x in raw_])
            for w in np.unique(widths):
                here = np.flatnonzero(widths == w)
                q, r = here[asks[here].astype(bool)], here[~asks[here].astype(bool)]
                if not len(q) or not len(r):
                    continue
                u, total = _units([raw_[i] for i in q], kind), np.zeros(len(q), np.int64)
                for p in range(0, len(r), BLOCK):
                    total += (u @ _units([raw_[i] for i in r[p : p + BLOCK]], kind).T >= threshold).sum(axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(id_[q]), pa.array(total)], ["id", "n"])

    met = grouped(asked.unionByName(shown), "part", "slice").mapInArrow(run, "id long, n long")
    truth = met.groupBy("id").agg((F.sum("n") - 1).alias("n"))
    both = truth.join(result.select(F.col(id_col).alias("id"), "n_links"), "id")
    return both.agg(F.count("*").alias("queries"), F.sum("n").alias("true_links"), F.sum("n_links").alias("found_links"), F.coalesce(F.sum(F.least("n", "n_links")) / F.sum("n"), F.lit(1.0)).alias("recall"))


def audited_components(rows: DataFrame, threshold: float = 0.9, least_recall: float = 0.9, attempts: int = 3, id_col: str = "vec_id", vector_col: str = "embedding", **search) -> tuple[DataFrame, float]:
    """vector_components of rows and its recall by audit_recall; below least_recall the search is repeated with twice as many tables."""
    tables = search.pop("tables", None) or block_tables(block_bits(rows.count()), threshold)
    for attempt in range(attempts):
        result = cut(vector_components(rows, threshold, id_col, vector_col, tables=tables << attempt, **search), "audited")
        recall = audit_recall(rows, result, threshold, id_col=id_col, vector_col=vector_col).first()["recall"]
        if recall >= least_recall:
            break
    return result, recall
