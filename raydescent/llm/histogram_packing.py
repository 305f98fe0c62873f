"""Best-fit packing planned over a histogram of lengths.

The driver sees only how many pieces there are of each length (at most as many numbers as a sequence has tokens). Best
fit decreasing is run over these counts: all pieces of one length are placed at once into the open sequences with the
least room that holds them, and sequences with one history are one group, a range of numbers. Its steps are slots
"pieces from rank r of length L, m of them, start at this offset of sequences from s on". Pieces take them by joining on
their rank within their length. The rank is exact and distributed: pieces of a length are dealt to parts by a hash,
ranked within their part, and the parts of a length are added up, so that a length with a third of all pieces is spread.
"""

from __future__ import annotations

import json
import math
import os
import re
import zlib
from bisect import bisect_left, insort
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.llm.bpe_automaton import latin_class, read_vocabulary
from raydescent.llm.common import BROADCAST_ROWS, cut

#: Characters below U+0180 keep to that range when lower-cased, but for U+0130, and are their own normal form.
_SLOW = re.compile("[^\u0000-\u012f\u0131-\u017f]")


def rank_parts(n: int) -> int:
    """In how many parts n pieces of one length are ranked: a quarter of the root, so that neither the rows of a part nor
    the parts of a length are many."""
    return 1 + math.isqrt(n) // 4


def plan_slots(histogram: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, pieces, first sequence, offset) of every step of best fit decreasing over the counts."""
    rooms: list[int] = []  # sorted, those with groups
    groups: dict[int, list[tuple[int, int]]] = {}  # room left -> (first sequence, how many)
    slots, opened = [], 0

    def leave(room: int, first: int, many: int) -> None:
        if room:
            if room not in groups:
                groups[room] = []
                insort(rooms, room)
            groups[room].append((first, many))

    for length in sorted(histogram, reverse=True):
        if not 0 < length <= capacity:
            raise ValueError(f"a piece of {length} tokens does not fit into {capacity}")
        rank, todo = 0, histogram[length]
        while todo:
            at = bisect_left(rooms, length)
            if at < len(rooms):
                room = rooms[at]
                first, many = groups[room].pop()
                if not groups[room]:
                    del groups[room], rooms[at]
            else:  # nothing has room: as many new sequences as it takes
                room, first, many = capacity, opened, -(-todo // (capacity // length))
                opened += many
            # a sequence just filled is the best fit for the next piece: one is filled up before the next is touched
            each = room // length
            full, rest = divmod(todo, each)
            if full >= many:
                full, rest = many, 0
            for layer in range(each):
                here = full + (layer < rest)
                if here:
                    slots.append((length, rank, here, first, capacity - room + layer * length))
                    rank += here
            todo -= full * each + rest
            if full:
                leave(room - each * length, first, full)
            if rest:
                leave(room - rest * length, first + full, 1)
            if many > full + (rest > 0):
                leave(room, first + full + (rest > 0), many - full - (rest > 0))
    return slots


class WordBpe:
    """Ids of the library for lower-casing word vocabularies, remembered by word where a text is of Latin letters only.

    Other texts and those that may hold a special token go through the library whole.
    """

    def __init__(self, source: str, most_words: int = 500_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core, and the batches are small
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_str(source)
        self.library.no_truncation()
        self.library.no_padding()
        spec = json.loads(source)  # for words that are already lower-cased and split: without those steps
        spec |= {"normalizer": None, "added_tokens": [], "pre_tokenizer": spec["pre_tokenizer"] | {"pretokenizers": spec["pre_tokenizer"]["pretokenizers"][1:]}}
        self.bare = Tokenizer.from_str(json.dumps(spec))
        letters, numbers, space = latin_class("L"), latin_class("N"), "\\t\\n\\x0b\\x0c\\r\\x20\\x85\\xa0"
        self.rule = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{letters}]+|[{numbers}]|[^{space}{letters}{numbers}]+")
        self.words: dict[str, bytes] = {}
        self.most = most_words

    def encode(self, text: str) -> bytes:
        if _SLOW.search(text) or "<|" in text:
            return b"".join(i.to_bytes(4, "little") for i in self.library.encode(text, add_special_tokens=False).ids)
        words, known = self.rule.findall(text.lower()), self.words
        fresh = [w for w in set(words) if w not in known]
        if fresh:
            if len(known) + len(fresh) > self.most:
                known.clear()
                fresh = list(set(words))
            made = self.bare.encode(fresh, is_pretokenized=True, add_special_tokens=False)
            ids, edges = np.array(made.ids, "<u4").tobytes(), np.searchsorted(made.word_ids, np.arange(len(fresh) + 1)) * 4
            for w, a, b in zip(fresh, edges[:-1].tolist(), edges[1:].tolist()):
                known[w] = ids[a:b]
        return b"".join(map(known.__getitem__, words))


@lru_cache(maxsize=2)
def _word_bpe(source: str) -> WordBpe:
    return WordBpe(source)


def cut_pieces(docs: DataFrame, vocabulary: str, capacity: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of the ids of each text, with end_id after them: _row, id, piece, start, length, ids_crc32.

    Only what is longer than capacity is cut, into pieces of capacity and a last one. Null and empty texts are end_id alone.
    """
    held = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary))
    end = end_id.to_bytes(4, "little")

    def run(batches):
        bpe = _word_bpe(held.value)
        for batch in (b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)):
            out = []
            for row, doc, text in zip(*(batch.column(c).to_pylist() for c in ("_row", "id", "text"))):
                ids = bpe.encode(text or "") + end
                for piece, at in enumerate(range(0, len(ids) // 4, capacity)):
                    part = ids[4 * at : 4 * (at + capacity)]
                    out.append((row, doc, piece, at, len(part) // 4, zlib.crc32(part)))
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            cols = list(zip(*out)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["_row", "id", "piece", "start", "length", "ids_crc32"])

    rows = docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "_row long, id long, piece int, start long, length long, ids_crc32 long")


def pack_lengths(pieces: DataFrame, capacity: int = 4096) -> DataFrame:
    """pieces (any rows with _row, piece and length, 1 to capacity) with sequence_id and offset; gapless from 0 in each sequence.

    pieces is read twice and must give the same rows both times, as a written table does. Pieces of equal length are
    interchangeable; they are ranked by (part of the hash, _row, piece).
    """
    spark = pieces.sparkSession
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most capacity rows
    slots = plan_slots(counts, capacity)
    widths = {x: max(1, counts[x] // n) for x, n in Counter(x[0] for x in slots).items()}
    per_length = spark.createDataFrame([(x, rank_parts(n), widths[x]) for x, n in counts.items()], "_wl long, _parts int, _width long")
    dealt = pieces.join(F.broadcast(per_length), F.col("length") == F.col("_wl"))  # at most capacity rows
    dealt = dealt.withColumn("_part", F.pmod(F.xxhash64("_row", "piece"), F.col("_parts")).cast("int"))
    sizes = dealt.groupBy("length", "_part").agg(F.count("*").alias("_n"))
    before = Window.partitionBy("length").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    bases = sizes.select(F.col("length").alias("_l"), F.col("_part").alias("_p"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    own = Window.partitionBy("length", "_part").orderBy("_row", "piece")
    ranked = dealt.withColumn("_rank", F.row_number().over(own) - 1)
    ranked = ranked.join(bases, (F.col("length") == F.col("_l")) & (F.col("_part") == F.col("_p"))).withColumn("_rank", F.col("_rank") + F.col("_base"))
    # The plan is as long as best fit has steps: that depends on the lengths that occur, and hardly on how many pieces there
    # are; it is broadcast if it is short enough. Ranks of a length go by stretches of equal width, so that a piece meets
    # the few slots of its stretch alone.
    cells = [(s[0], b, *s[1:]) for s in slots for b in range(s[1] // widths[s[0]], (s[1] + s[2] - 1) // widths[s[0]] + 1)]
    plan = spark.createDataFrame(cells, "_len long, _stretch long, _from long, _many long, _first long, offset long")
    plan = F.broadcast(plan) if len(cells) <= BROADCAST_ROWS else plan
    ranked = ranked.withColumn("_at", F.floor(F.col("_rank") / F.col("_width")))
    met = (F.col("length") == F.col("_len")) & (F.col("_at") == F.col("_stretch"))
    taken = ranked.join(plan, met & (F.col("_rank") >= F.col("_from")) & (F.col("_rank") < F.col("_from") + F.col("_many")))
    return taken.select(*pieces.columns, (F.col("_first") + F.col("_rank") - F.col("_from")).alias("sequence_id"), "offset")


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, piece, start, length, ids_crc32, sequence_id, offset of every piece; an empty table gives no rows.

    Rows that share an id are packed each by itself.
    """
    pieces = cut(cut_pieces(docs, vocabulary, capacity, end_id, id_col, text_col), "pieces")
    return pack_lengths(pieces, capacity).drop("_row").withColumnRenamed("id", id_col)


def write_sequences(docs: DataFrame, packed: DataFrame, vocabulary: str, path: str, capacity: int = 4096, end_id: int = 1) -> None:
    """The packed sequences themselves as Parquet at path: sequence_id, ids array<int>. docs: doc_id (unique), text."""
    held = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary))
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator):
        bpe = _word_bpe(held.value)
        for batch in batches:
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                ids = bpe.encode(text or "") + end
                cuts = [ids[i : i + 4 * capacity] for i in range(0, len(ids), 4 * capacity)]
                lists = pa.array([np.frombuffer(c, "<u4").astype(np.int32) for c in cuts], pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([pa.array([doc] * len(cuts), pa.int64()), pa.array(range(len(cuts)), pa.int32()), lists], ["doc_id", "piece", "ids"])

    bodies = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, piece int, ids array<int>")
    placed = packed.select("doc_id", "piece", "sequence_id", "offset").join(bodies, ["doc_id", "piece"])
    joined = placed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("p"))  # at most capacity tokens
    joined.select("sequence_id", F.flatten(F.col("p.ids")).alias("ids")).write.parquet(path)
