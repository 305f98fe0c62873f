"""Exact de-duplication by owners in Patricia tries.

Texts go to partitions by length and content hash. There every full byte string is inserted into a compressed radix
trie whose terminal nodes hold the smallest identifier and how many rows had the string; a trie over its memory budget
moves its largest subtree to a local spill file, which is worked off afterwards with the same budget.

A text is first merged in a trie of its input partition, so one group of copies sends at most a row per input task,
however large it is. The tries compare whole strings. The owners come back to the documents by SHA-256 digest and length
through skew_safe_lookup; two strings of one length under one digest would be mistaken for each other there.
"""

from __future__ import annotations

import hashlib
import pickle
import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from raydescent.llm.common import cut, skew_safe_lookup, spare

_NODE_COST = 220


def common_prefix(a: bytes, b: bytes) -> int:
    lo, hi = 0, min(len(a), len(b))
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[:mid] == b[:mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


class _Node:
    __slots__ = ("label", "kids", "owner", "count", "ties", "spill")

    def __init__(self, label: bytes, owner=None, count: int = 0, ties: int = 0):
        self.label, self.kids, self.owner, self.count, self.ties, self.spill = label, {}, owner, count, ties, None


class PatriciaTrie:
    """Byte strings to (smallest identifier, rows, rows that have it). budget: bytes held in memory; beyond it subtrees go to files."""

    def __init__(self, budget: int = 256 << 20):
        self.root, self.budget, self.held = _Node(b""), budget, 0

    def insert(self, key: bytes, owner, count: int = 1, ties: int = 1) -> None:
        node, at = self.root, 0
        while True:
            if node.spill is not None:
                pickle.dump((key, owner, count, ties), node.spill)
                return
            if at == len(key):
                if not node.count or owner < node.owner:
                    node.owner, node.ties = owner, 0
                node.count += count
                node.ties += ties if owner == node.owner else 0
                return
            kid = node.kids.get(key[at])
            if kid is None:
                node.kids[key[at]] = _Node(key[at:], owner, count, ties)
                self.held += len(key) - at + _NODE_COST
                if self.held > self.budget:
                    self._spill()
                return
            if not key.startswith(kid.label, at):
                n = common_prefix(kid.label, key[at : at + len(kid.label)])
                upper = _Node(kid.label[:n])
                kid.label = kid.label[n:]
                upper.kids[kid.label[0]] = kid
                node.kids[upper.label[0]] = kid = upper
                self.held += _NODE_COST
            node, at = kid, at + len(kid.label)

    def _size(self, node: _Node) -> int:
        total, stack = 0, [node]
        while stack:
            x = stack.pop()
            total += len(x.label) + _NODE_COST
            stack += x.kids.values()
        return total

    def _spill(self) -> None:
        """Move the largest subtrees below the topmost branching to files, down to half the budget. The node of a moved
        subtree keeps the first byte of its label and passes on whatever comes there later. A trie of one string has no
        branching and stays."""
        path, node = b"", self.root
        while len(node.kids) == 1 and not node.count and node.spill is None:
            (node,) = node.kids.values()
            path += node.label
        sizes = sorted(((self._size(x), first) for first, x in node.kids.items() if x.spill is None), reverse=True)
        for size, first in sizes:
            if self.held <= self.budget // 2:
                break
            self._move(node.kids[first], path)
            self.held -= size - 1 - _NODE_COST

    def _move(self, victim: _Node, path: bytes) -> None:
        out = tempfile.TemporaryFile(prefix="trie-")
        stack = [(victim, path + victim.label)]
        while stack:
            x, key = stack.pop()
            if x.spill is not None:
                x.spill.seek(0)
                for item in _unpickle(x.spill):
                    pickle.dump(item, out)
                x.spill.close()
            if x.count:
                pickle.dump((key, x.owner, x.count, x.ties), out)
            stack += [(y, key + y.label) for y in x.kids.values()]
        victim.label, victim.kids, victim.owner, victim.count, victim.ties, victim.spill = victim.label[:1], {}, None, 0, 0, out

    def items(self) -> Iterator[tuple[bytes, object, int, int]]:
        """Each string once. Spilled subtrees follow one by one, in tries of the same budget."""
        stack, spilled = [(self.root, b"")], []
        while stack:
            node, key = stack.pop()
            if node.count:
                yield key, node.owner, node.count, node.ties
            if node.spill is not None:
                spilled.append(node.spill)
            stack += [(y, key + y.label) for y in node.kids.values()]
        self.root, self.held = _Node(b""), 0
        for f in spilled:
            f.seek(0)
            sub = PatriciaTrie(self.budget)
            for item in _unpickle(f):
                sub.insert(*item)
            f.close()
            yield from sub.items()


def _unpickle(f) -> Iterator[tuple]:
    while True:
        try:
            yield pickle.load(f)
        except EOFError:
            return


def normal_form(text: Column) -> Column:
    """Null is empty; each run of ASCII white space is one space."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), "[\\x20\\x09-\\x0D]+", " ")


_OWNER_SCHEMA = "digest string, body binary, owner long, members long, ties long"


def _merge(batches, budget: int, bodies: bool):
    trie = PatriciaTrie(budget)
    for batch in batches:
        body = batch.column("body").to_pylist()
        owner = [(i is None, i or 0) for i in batch.column("owner").to_pylist()]  # a null id is larger than any other
        more = [batch.column(c).to_pylist() if c in batch.schema.names else [1] * len(body) for c in ("members", "ties")]
        for item in zip(body, owner, *more):
            trie.insert(*item)
        if bodies and trie.held > budget // 2:  # a first merge may end early: the second one sums up
            yield from _rows(trie, bodies)
            trie = PatriciaTrie(budget)
    yield from _rows(trie, bodies)


def _rows(trie: PatriciaTrie, bodies: bool):
    held, size = [], 0
    for key, owner, count, ties in trie.items():
        digest = f"{hashlib.sha256(key).hexdigest()}:{len(key)}"
        held.append((digest, key if bodies else None, None if owner[0] else owner[1], count, ties))
        size += len(key) + 100
        if size > 8 << 20:
            yield _batch(held)
            held, size = [], 0
    yield _batch(held)


def _batch(rows):
    cols = list(zip(*rows)) or [[]] * 5
    kinds = (pa.string(), pa.binary(), pa.int64(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["digest", "body", "owner", "members", "ties"])


def owners(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", budget: int = 192 << 20) -> DataFrame:
    """One row per different normalised text: digest (SHA-256 and length in bytes), owner (smallest id), members, ties
    (rows that have the owner's id)."""
    texts = docs.select(F.col(id_col).cast("long").alias("owner"), F.encode(normal_form(F.col(text_col)), "UTF-8").alias("body"))
    local = texts.mapInArrow(lambda b: _merge(b, budget, True), _OWNER_SCHEMA)
    dealt = local.repartition(F.length("body"), F.xxhash64("body"))
    return dealt.mapInArrow(lambda b: _merge(b, budget, False), _OWNER_SCHEMA).select("digest", "owner", "members", "ties")


NAMES = ("keep_id", "group_size", "kept", "text_sha256")


def _assigned(docs: DataFrame, id_col: str, text_col: str, names: list[str]) -> tuple[DataFrame, DataFrame]:
    """docs with new columns of these names (those of NAMES, then how many rows have the text and the owner's id), and
    the table of owners."""
    keep_id, size, kept, sha, ties = names
    (key,) = spare([*docs.columns, *names], "_key")
    found = cut(owners(docs, id_col, text_col), "owners")
    found = found.select(F.col("digest").alias(key), F.col("owner").alias(keep_id), F.col("members").alias(size), F.col("ties").alias(ties))
    total = found.agg(F.sum(size)).first()[0] or 0
    body = F.encode(normal_form(F.col(text_col)), "UTF-8")
    rows = docs.withColumn(key, F.concat_ws(":", F.sha2(body, 256), F.octet_length(body)))
    joined = skew_safe_lookup(rows, found, key, size, total)
    joined = joined.withColumn(kept, F.col(id_col).cast("long").eqNullSafe(F.col(keep_id))).withColumn(sha, F.substring_index(key, ":", 1))
    return joined.drop(key), found


def assign_owners(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with keep_id, group_size, kept and text_sha256.

    Null text counts as empty; an empty table gives no rows. The row with the smallest id is kept; a null id is larger
    than any other. Rows that repeat both the text and its smallest id are all marked kept, as nothing tells them apart.
    Columns of those four names in docs are replaced.
    """
    (ties,) = spare([*docs.columns, *NAMES], "_ties")
    return _assigned(docs.drop(*NAMES), id_col, text_col, [*NAMES, ties])[0].drop(ties)


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each different text, the one with the smallest id (any one of rows that repeat both); columns as in
    docs, whatever their names."""
    names = spare(docs.columns, *NAMES, "_ties")
    joined, found = _assigned(docs, id_col, text_col, names)
    _, _, kept_col, sha, ties = names
    kept = joined.where(kept_col)
    if not found.where(F.col(ties) > 1).isEmpty():
        kept = kept.where(F.col(ties) == 1).unionByName(kept.where(F.col(ties) > 1).dropDuplicates([sha]))
    return kept.select(*[F.col(f"`{c}`") for c in docs.columns])
