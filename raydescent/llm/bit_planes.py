"""Many Hamming distances at once over vertically stored bits.

Rows are taken in blocks of 64. Of a block, plane p is one machine word that holds bit p of all its rows. A query is
compared with a whole block by exclusive-or of its own bit with the plane; the differing bits are added up for the 64
rows together in counters that are themselves bit slices, three planes at a time through a carry-save adder. The
counters start so that they overflow just when a distance exceeds the radius; an overflow marks the row for good, and a
block whose rows are all marked is abandoned with the rest of its planes unread.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

TASKS = 1 << 16
CHECK_EVERY = 9
ALL = np.uint64(0xFFFFFFFFFFFFFFFF)


def unpacked(prints: np.ndarray) -> np.ndarray:
    """rows x bytes to rows x bits, the most significant first."""
    return np.unpackbits(prints, axis=1)


def planes_of(bits: np.ndarray) -> np.ndarray:
    """rows x bits (0/1) to bits x blocks words; row r of a block is bit r."""
    rows, width = bits.shape
    blocks = -(-rows // 64)
    padded = np.zeros((blocks * 64, width), np.uint8)
    padded[:rows] = bits
    turned = np.packbits(padded.reshape(blocks, 64, width).transpose(2, 0, 1), axis=2, bitorder="little")
    return np.ascontiguousarray(turned).view(np.uint64).reshape(width, blocks)


def _add(counters: list[np.ndarray], x: np.ndarray, level: int, dead: np.ndarray) -> None:
    for k in range(level, len(counters)):
        counters[k], x = counters[k] ^ x, counters[k] & x
    np.bitwise_or(dead, x, out=dead)


def survivors(planes: np.ndarray, bits: np.ndarray, query: np.ndarray, block: np.ndarray, lanes: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Of tasks (query row, block, lanes wanted): the pairs of task number and lane whose distance is at most radius."""
    slices = max(1, radius.bit_length())
    start = (1 << slices) - 1 - radius
    task = np.arange(len(query))
    dead = ~lanes
    counters = [np.full(len(query), ALL if start >> k & 1 else 0, np.uint64) for k in range(slices)]
    width = planes.shape[0]
    for at in range(0, width, 3):
        d = [planes[p][block] ^ (np.uint64(0) - bits[p][query].astype(np.uint64)) for p in range(at, min(at + 3, width))]
        if len(d) == 3:
            half = d[0] ^ d[1]
            carry = (d[0] & d[1]) | (half & d[2])
            _add(counters, half ^ d[2], 0, dead)
            _add(counters, carry, 1, dead)
        else:
            for x in d:
                _add(counters, x, 0, dead)
        if (at // 3) % (CHECK_EVERY // 3) == CHECK_EVERY // 3 - 1:
            live = np.flatnonzero(dead != ALL)
            if len(live) < 0.8 * len(task):
                task, query, block, dead = task[live], query[live], block[live], dead[live]
                counters = [c[live] for c in counters]
                if not len(task):
                    break
    lanes_left = np.unpackbits((~dead).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    t, lane = np.nonzero(lanes_left)
    return task[t], lane


def close_pairs(prints: np.ndarray, group: np.ndarray, radius: int, cross: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (i, j), i < j, of rows of one group (rows are sorted by group) within radius bits, in bounded portions.

    cross: rows of two sides; then only pairs of different sides count.
    """
    n = len(group)
    if n < 2:
        return
    ends = np.flatnonzero(np.r_[group[1:] != group[:-1], True]) + 1
    end = np.repeat(ends, np.diff(np.r_[0, ends]))
    rows = np.arange(n)
    wide = unpacked(prints)
    planes, bits = planes_of(wide), np.ascontiguousarray(wide.T)
    first, last = (rows + 1) // 64, (end - 1) // 64
    many = np.where(end - rows > 1, last - first + 1, 0)
    upto = np.cumsum(many)
    at = 0
    while at < n:
        stop = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + TASKS)))
        q = np.repeat(rows[at:stop], many[at:stop])
        if len(q):
            step = np.arange(len(q)) - np.repeat(upto[at:stop] - many[at:stop] - (upto[at - 1] if at else 0), many[at:stop])
            b = first[q] + step
            low = np.clip(q + 1 - 64 * b, 0, 63).astype(np.uint64)
            high = np.clip(end[q] - 64 * b, 1, 64).astype(np.uint64)
            lanes = (ALL << low) & (ALL >> (np.uint64(64) - high))
            t, lane = survivors(planes, bits, q, b, lanes, radius)
            i, j = q[t], 64 * b[t] + lane
            if cross is not None:
                keep = cross[i] != cross[j]
                i, j = i[keep], j[keep]
            if len(i):
                yield i, j
        at = stop


def distances(prints: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    return np.bitwise_count(prints[i] ^ prints[j]).sum(axis=1, dtype=np.int32)


def join_labels(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Labels (smallest row of each class) after the classes of i and j have become one, pair by pair."""
    while len(i):
        a, b = label[i], label[j]
        open_ = a != b
        if not open_.any():
            break
        i, j, a, b = i[open_], j[open_], a[open_], b[open_]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    return label


def spanning(label: np.ndarray, i: np.ndarray, j: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Labels after the pairs, and places of pairs that span them, the nearest first."""
    picked = []
    for level in np.unique(d):
        at = np.flatnonzero(d == level)
        while True:
            a, b = label[i[at]], label[j[at]]
            apart = a != b
            if not apart.any():
                break
            at, a, b = at[apart], a[apart], b[apart]
            _, first = np.unique(np.maximum(a, b), return_index=True)  # one pair for each class that joins a smaller one
            picked.append(at[first])
            label = join_labels(label, i[at[first]], j[at[first]])
    return label, np.concatenate(picked) if picked else np.zeros(0, np.int64)
