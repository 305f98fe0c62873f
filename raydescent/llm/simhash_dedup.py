"""SimHash fingerprints of word shingles, compared bit-sliced (see bit_planes).

Equal fingerprints are one class from the start, so copies of any number are one row. Classes meet in tables keyed by
some of the bits. For an exact radius r the bits are cut into blocks and a table is kept for each choice of all but r of
them: two fingerprints within r bits agree in at least one table. Wide fingerprints instead have bands, whose chance to
find a pair is known from its similarity. What they connect are families; within a family all pairs are then verified on
their shingles, as the nearest fingerprints need not be those of the most similar texts.

A bucket above a size is dealt out as pairs of its parts, so that no task holds a whole large bucket; the comparisons are
all made. A task hands on a spanning forest of the links it finds, so that what leaves a bucket is as long as the bucket, not
as its pairs. Large families are dealt out likewise.
"""

from __future__ import annotations

import hashlib
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from raydescent.llm.bit_planes import close_pairs, distances, spanning
from raydescent.llm.common import ASCII_LOWER, checked_broadcast, cut, grouped, skew_safe_lookup, sorted_groups, spare
from raydescent.llm.components import connected_components

#: Rows of one bucket that are compared in one task; larger buckets are split into pairs of parts.
BUCKET_ROWS = 20_000
PORTION_ROWS = 20_000
#: Rows and shingles of one family that are verified in one task at most; larger families, and those that hold much of all
#: rows in families (a 32nd of them, if that is LEAST_FAMILY rows), are split into pairs of parts.
LEAST_FAMILY, FAMILY_ROWS = 256, 20_000
FAMILY_SHINGLES = 2_000_000
_BLOCK = 512
_COLUMNS = 1 << 14
#: Nodes from here on stand for fingerprints of which no row has an id.
_NO_ID = 1 << 62
_STEP = 1 << 15


def shingle_hashes(text: str | None, size: int) -> np.ndarray:
    """XXH64 (seed 42) of every shingle of the whole text, repeats included; fewer words are one shingle, no words none."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(ASCII_LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    if len(words) < size:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), 42)], np.uint64)
    parts = zip(*(words[i : len(words) - size + 1 + i] for i in range(size)))
    return np.fromiter((xxhash.xxh64_intdigest(p, 42) for p in map(b" ".join, parts)), np.uint64, len(words) - size + 1)


def widened(h: np.ndarray, word: int) -> np.ndarray:
    """The word-th 64 bits that a shingle's hash stands for; the first are the hash itself."""
    if word == 0:
        return h
    x = h + np.uint64(word * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def fingerprint(h: np.ndarray, bits: int = 64) -> bytes:
    """A bit is 1 if it is set in more than half of the hashes; no hashes: zero."""
    out = []
    for word in range(bits // 64):
        total = np.zeros(64, np.int64)
        for at in range(0, len(h), _STEP):
            step = widened(h[at : at + _STEP], word).astype(">u8").view(np.uint8).reshape(-1, 8)
            total += np.unpackbits(step, axis=1).sum(axis=0, dtype=np.int32)
        out.append(np.packbits(2 * total > len(h)).tobytes())
    return b"".join(out)


def fingerprints(docs: DataFrame, shingle: int = 3, bits: int = 64, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, print (bits/8 bytes) for every row of docs; null text is empty."""

    def run(batches):
        for batch in batches:
            made = [fingerprint(shingle_hashes(t, shingle), bits) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(made, pa.binary())], ["id", "print"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id long, print binary")


def exact_tables(bits: int, radius: int, blocks: int) -> list[list[int]]:
    """Bit positions of the key of each table: every choice of blocks - radius of the blocks."""
    edges = [bits * i // blocks for i in range(blocks + 1)]
    return [[p for b in chosen for p in range(edges[b], edges[b + 1])] for chosen in combinations(range(blocks), blocks - radius)]


def band_tables(bits: int, band: int) -> list[list[int]]:
    return [list(range(i, i + band)) for i in range(0, bits - band + 1, band)]


def _keyed(nodes: DataFrame, tables: list[list[int]]) -> DataFrame:
    """bucket, node, print for each table; the bucket is the table's number and the key's bits."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            raw = batch.column("print").to_pylist()
            bits = np.unpackbits(np.frombuffer(b"".join(raw), np.uint8).reshape(len(raw), -1), axis=1)
            for number, places in enumerate(tables):
                key = np.full(len(raw), number, np.uint64)
                for p in places:
                    key = (key << np.uint64(1)) | bits[:, p]
                yield pa.RecordBatch.from_arrays([pa.array(key.astype(np.int64)), batch.column("node"), batch.column("print")], ["bucket", "node", "print"])

    return nodes.select("node", "print").mapInArrow(run, "bucket long, node long, print binary")


def _dealt(keyed: DataFrame) -> DataFrame:
    """bucket, part pair (x <= y) and side for each row. A bucket of up to BUCKET_ROWS has the one pair (0, 0)."""
    sizes = keyed.groupBy("bucket").agg(F.count("*").alias("_n")).where(F.col("_n") > BUCKET_ROWS)
    large = checked_broadcast(sizes.select(F.col("bucket").alias("_b"), F.ceil(F.col("_n") / BUCKET_ROWS).cast("int").alias("_parts")), "large")
    rows = keyed.join(large, F.col("bucket") == F.col("_b"), "left").withColumn("_parts", F.coalesce("_parts", F.lit(1)))
    rows = rows.withColumn("_own", F.pmod(F.xxhash64("node"), F.col("_parts")).cast("int"))
    rows = rows.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1)))
    return rows.select("bucket", F.least("_own", "_other").alias("x"), F.greatest("_own", "_other").alias("y"), (F.col("_own") > F.col("_other")).cast("int").alias("side"), "node", "print")


def _portion(group, node, prints, cross, radius: int):
    label = np.arange(len(node))
    for i, j in close_pairs(prints, group, radius, cross):
        label, at = spanning(label, i, j, distances(prints, i, j))
        a, b = node[i[at]], node[j[at]]
        yield pa.RecordBatch.from_arrays([pa.array(np.maximum(a, b)), pa.array(np.minimum(a, b))], ["a", "b"])


def close_links(nodes: DataFrame, tables: list[list[int]], radius: int) -> DataFrame:
    """a, b (node numbers): links within radius bits that span the classes of every bucket."""
    dealt = grouped(_dealt(_keyed(nodes, tables)), "bucket", "x", "y", within=("node",))

    def run(batches):
        for t in sorted_groups(batches, ["bucket", "x", "y"], PORTION_ROWS):  # whole buckets, of few rows at a time
            bucket, x, y, side, node = (t.column(c).to_numpy() for c in ("bucket", "x", "y", "side", "node"))
            new = np.r_[True, (bucket[1:] != bucket[:-1]) | (x[1:] != x[:-1]) | (y[1:] != y[:-1])]
            size = np.diff(np.r_[np.flatnonzero(new), len(new)])
            keep = np.flatnonzero(np.repeat(size > 1, size))  # most buckets have a single row
            if not len(keep):
                continue
            prints = np.frombuffer(b"".join(t.column("print").take(pa.array(keep)).to_pylist()), np.uint8).reshape(len(keep), -1)
            cross = np.where(x == y, -1 - np.arange(len(x)), side)[keep]
            yield from _portion(np.cumsum(new)[keep], node[keep], prints, cross, radius)

    return dealt.mapInArrow(run, "a long, b long")


def _classes(prints: DataFrame) -> DataFrame:
    """print, node (smallest id, or a number above all ids), members."""
    own = F.lit(_NO_ID) + F.shiftrightunsigned(F.xxhash64("print"), 2)
    return prints.groupBy("print").agg(F.min("id").alias("node"), F.count("*").alias("members")).withColumn("node", F.coalesce("node", own))


def _digest(shingles: np.ndarray) -> bytes:
    """What stands for a set of shingles (sorted, each once)."""
    return hashlib.sha256(shingles.tobytes()).digest()


def simhash_components(docs: DataFrame, shingle: int = 3, radius: int = 3, blocks: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, fingerprint (16 hexadecimal digits), component_id (smallest id reachable over links of radius bits or fewer).

    Every row of docs is there. Texts without words have fingerprint zero and link like any other. Null ids belong to
    the component of their fingerprint; a component of null ids alone has a null component_id. Rows that share an id are
    one node. Ids must be below 2^62.
    """
    prints = cut(fingerprints(docs, shingle, 64, id_col, text_col), "prints")
    nodes = cut(_classes(prints), "nodes")
    links = close_links(nodes, exact_tables(64, radius, blocks), radius)
    found = connected_components(links)
    named = nodes.join(found.withColumnRenamed("node", "_n"), F.col("node") == F.col("_n"), "left")
    facts = cut(named.select(F.hex("print").alias("fingerprint"), F.coalesce("component", "node").alias("component_id"), "members"), "classes")
    total = nodes.agg(F.sum("members")).first()[0] or 0
    rows = prints.select(F.col("id").alias(id_col), F.hex("print").alias("fingerprint"))
    out = skew_safe_lookup(rows, facts, "fingerprint", "members", total)
    component = F.when(F.col("component_id") < _NO_ID, F.col("component_id"))
    return out.select(id_col, F.lower("fingerprint").alias("fingerprint"), component.alias("component_id"))


def _shared(col: np.ndarray, start: np.ndarray, size: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """How many shingles each of the rows a shares with each of b; the row r has the numbers col[start[r] : start[r] + size[r]]."""

    def entries(rows):
        n = size[rows]
        c = col[np.repeat(start[rows] - np.cumsum(n) + n, n) + np.arange(n.sum())]
        order = np.argsort(c, kind="stable")
        return c[order], np.repeat(np.arange(len(rows)), n)[order]

    (ca, ra), (cb, rb) = entries(a), entries(b)
    both = np.intersect1d(ca, cb)
    out = np.zeros((len(a), len(b)), np.float32)  # whole numbers below 2^24
    for at in range(0, len(both), _COLUMNS):
        some = both[at : at + _COLUMNS]
        sides = []
        for c, r, rows in ((ca, ra, a), (cb, rb, b)):
            lo, hi = np.searchsorted(c, some[0]), np.searchsorted(c, some[-1], "right")
            place = np.searchsorted(some, c[lo:hi])
            hit = some[place] == c[lo:hi]
            x = np.zeros((len(rows), len(some)), np.float32)
            x[r[lo:hi][hit], place[hit]] = 1
            sides.append(x)
        out += sides[0] @ sides[1].T
    return out.astype(np.float64)


def similarity(both: np.ndarray, a: np.ndarray, b: np.ndarray, cosine: bool) -> np.ndarray:
    """Of sets with so many members, and both in common: the cosine, or the part of their union that is common (Jaccard)."""
    return both / np.sqrt(a * b) if cosine else both / (a + b - both)


def _family_links(sets: list[np.ndarray], side: np.ndarray | None, least: float, cosine: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs (i, j) of similarity least or more, and it, that span all such pairs; of different sides only, if side is given.

    Pairs whose rows are connected already are not compared, nor are blocks whose sizes alone keep them apart.
    """
    whole = np.array([len(x) for x in sets])
    row = np.repeat(np.arange(len(sets)), whole)
    _, col, many = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    keep = many[col] > 1
    size = np.bincount(row[keep], minlength=len(sets))
    col, start = col[keep], np.cumsum(size) - size
    by_size = np.argsort(whole, kind="stable")
    cut_up = lambda rows: [rows[i : i + _BLOCK] for i in range(0, len(rows), _BLOCK)]
    if side is None:
        blocks = cut_up(by_size)
        met = [(blocks[i], blocks[i + d]) for d in range(len(blocks)) for i in range(len(blocks) - d)]
    else:
        met = [(p, q) for p in cut_up(by_size[side[by_size] == 0]) for q in cut_up(by_size[side[by_size] == 1])]
    label = np.arange(len(sets))
    found: list[list[np.ndarray]] = [[], [], []]
    for p, q in met:
        if max(whole[p[0]], whole[q[0]]) * (least * least if cosine else least) > min(whole[p[-1]], whole[q[-1]]) + 1e-6:
            continue
        names, n = np.unique(np.r_[label[p], label[q]], return_counts=True)
        most = names[n.argmax()]
        one, rest = p[label[p] == most], p[label[p] != most]
        other = q[label[q] != most]
        for a, b in ((rest, q), (one, other)):
            if not len(a) or not len(b):
                continue
            both = _shared(col, start, size, a, b)
            share = similarity(both, whole[a][:, None].astype(float), whole[b][None, :].astype(float), cosine)
            i, j = np.nonzero((share >= least) & (label[a][:, None] != label[b][None, :]))
            if len(i):
                label, tie = spanning(label, a[i], b[j], np.zeros(len(i), np.int8))
                for o, v in zip(found, (a[i][tie], b[j][tie], share[i, j][tie])):
                    o.append(v)
    return tuple(np.concatenate(o) if o else np.zeros(0, k) for o, k in zip(found, (np.int64, np.int64, float)))


def family_links(members: DataFrame, texts: DataFrame, shingle: int, least: float, cosine: bool) -> DataFrame:
    """a, b, similarity: links that span all pairs of similarity least or more within each family.

    members: component, node, digest, shingles (their number), a written table; texts: id, text, of which those of members are read. A
    family is worked off in tasks of two parts each, so that none holds a whole large one.
    """
    part = min(max(members.count() // 32, LEAST_FAMILY), FAMILY_ROWS)
    sizes = members.groupBy("component").agg(F.greatest(F.ceil(F.count("*") / part), F.ceil(F.sum("shingles") / FAMILY_SHINGLES)).cast("int").alias("_parts"))
    large = checked_broadcast(sizes.where("_parts > 1").withColumnRenamed("component", "_c"), "large")
    wanted = members.join(large, F.col("component") == F.col("_c"), "left")
    wanted = wanted.select(F.col("node").alias("id"), "digest", "component", F.coalesce("_parts", F.lit(1)).alias("parts"))

    def sets(batches):
        for batch in batches:
            made = [np.unique(shingle_hashes(t, shingle)) for t in batch.column("text").to_pylist()]
            own = pa.array([_digest(m) == d for m, d in zip(made, batch.column("digest").to_pylist())], pa.bool_())  # an id may stand for several texts
            rows = pa.RecordBatch.from_arrays([batch.column("id"), batch.column("digest"), batch.column("component"), batch.column("parts"), pa.array([m.tobytes() for m in made], pa.binary())], ["node", "digest", "component", "parts", "set"])
            yield rows.filter(own)

    rows = texts.join(wanted, "id").mapInArrow(sets, "node long, digest binary, component long, parts int, set binary")
    rows = rows.withColumn("_own", F.pmod(F.xxhash64("digest"), F.col("parts")).cast("int"))
    rows = rows.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    dealt = rows.select("component", F.least("_own", "_other").alias("x"), F.greatest("_own", "_other").alias("y"), (F.col("_own") > F.col("_other")).cast("int").alias("side"), "node", "set")

    def verify(batches):
        for t in sorted_groups(batches, ["component", "x", "y"]):
            node, side = t.column("node").to_numpy(), t.column("side").to_numpy()
            held = [np.frombuffer(v, np.uint64) for v in t.column("set").to_pylist()]
            i, j, share = _family_links(held, None if t.column("x")[0] == t.column("y")[0] else side, least, cosine)
            a, b = node[i], node[j]
            yield pa.RecordBatch.from_arrays([pa.array(np.maximum(a, b)), pa.array(np.minimum(a, b)), pa.array(share)], ["a", "b", "similarity"])

    return grouped(dealt, "component", "x", "y").mapInArrow(verify, "a long, b long, similarity double")


def similar_pairs(docs: DataFrame, shingle: int = 5, least: float = 0.8, cosine: bool = True, bits: int = 512, band: int = 11, radius: int = 128, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """Classes of equal shingle sets (digest, print, shingles, node, members) of docs and verified links (a, b, similarity)
    between documents, enough to span what they connect.

    Texts without words are in no class. Equal sets are linked at once; sets with one fingerprint are compared like any others.
    Bands of wide fingerprints connect families, within which all pairs are verified on the whole texts: the cosine of
    their shingle sets, which is what fingerprints estimate, or (cosine=False) their Jaccard similarity, is at least
    least. Sets of cosine 0.8 (of equal size: Jaccard 0.67) differ in 20.5 of 100 bits on average: with 46 bands of 11 bits
    a pair is missed by all bands with a chance of 2 in 100, and lies beyond 128 of 512 bits with 0.6 in 100; it is still
    found if others connect it. Closer pairs are missed more seldom: at a cosine of 0.85 with 0.2 in 100.
    """

    def mark(batches):
        for batch in batches:
            rows = []
            for i, t in zip(batch.column("id").to_pylist(), batch.column("text").to_pylist()):
                h = np.unique(shingle_hashes(t, shingle))  # what is asked for is the similarity of sets: repeats do not count
                if len(h):
                    rows.append((i, _digest(h), fingerprint(h, bits), len(h)))
            columns = zip(*rows) if rows else ((), (), (), ())
            kinds = (pa.int64(), pa.binary(), pa.binary(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], ["id", "digest", "print", "shingles"])

    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).where("id IS NOT NULL")
    marks = cut(texts.mapInArrow(mark, "id long, digest binary, print binary, shingles long"), "prints")
    nodes = marks.groupBy("digest").agg(F.min_by("print", "id").alias("print"), F.first("shingles").alias("shingles"), F.min("id").alias("node"), F.count("*").alias("members"))
    nodes = cut(nodes, "nodes")
    facts = nodes.where("members > 1").select(F.hex("digest").alias("_digest"), F.col("node").alias("b"), "members")
    total = nodes.agg(F.sum("members")).first()[0] or 0
    equal = skew_safe_lookup(marks.select(F.col("id").alias("a"), F.hex("digest").alias("_digest")), facts, "_digest", "members", total).where("a <> b")
    families = connected_components(close_links(nodes, band_tables(bits, band), radius))
    members = cut(nodes.join(families, "node").select("component", "node", "digest", "shingles"), "families")
    links = family_links(members, texts, shingle, least, cosine)
    return nodes, links.union(equal.select("a", "b", F.lit(1.0)))


def near_dedup(docs: DataFrame, shingle: int = 5, least: float = 0.8, cosine: bool = True, id_col: str = "doc_id", text_col: str = "text", **search) -> DataFrame:
    """docs without those that are linked, directly or through others, to a document of smaller id; columns as in docs.
    Documents are linked by the cosine (or the Jaccard similarity) of their sets of word shingles; search: see similar_pairs.

    Texts without any words, rows with a null id and documents that share no shingles with others stay. Rows that share an
    id go or stay together. An empty table gives no rows.
    """
    named = docs.where(F.col(id_col).isNotNull())
    _, links = similar_pairs(named, shingle, least, cosine, id_col=id_col, text_col=text_col, **search)
    found = connected_components(cut(links.select("a", "b"), "similar"))
    (name,) = spare(docs.columns, "_gone")
    gone = found.where("node <> component").select(F.col("node").alias(name))
    return docs.join(gone, F.col(id_col).cast("long") == F.col(name), "left_anti")
