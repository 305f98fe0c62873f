"""Stupid-backoff scores from n-gram counts of the whole corpus, computed as relations.

Texts become ids of a public vocabulary; single ids are counted in a table of the vocabulary's size. Longer n-grams are
exploded and counted once per chunk of documents (some millions of ids that stand together), so that a frequent n-gram
sends a row per chunk and not per place. The rows go by hash of the n-gram to its partition of the count table, where the
chunks' counts are added up, a bucket at a time; each chunk gets back the totals of its own n-grams, joins them to its places
and sums the logarithms per document. Between the steps n-grams travel as packed columns (sorted keys by byte planes): a
row per n-gram would not fit the disk that the job may use. A key is the n-gram's ids as one number, of 64 bits or, for
longer n-grams, of 128, so that different n-grams never share one.

score(w) = count(h w) / count(h) for the longest history h whose n-gram is counted least times at least, times alpha
for each word of history given up; a single id has count / total. In a corpus that is scored by itself a text vouches for
itself: n-grams that nothing else has are counted by it. So each text is also scored by the counts of all other texts.
"""

from __future__ import annotations

import json
import os
import unicodedata
from codecs import charmap_decode
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from raydescent.llm.bpe_automaton import LATIN_END, byte_symbols, read_vocabulary
from raydescent.llm.common import cut, sorted_groups

CHUNK_TOKENS = 4_000_000
BUCKET_TOKENS = 4_000_000
#: Documents in one row of the token table.
ROW_DOCS = 200


def pack(values: np.ndarray) -> bytes:
    """Unsigned 64-bit numbers (or wide keys) as byte planes: planes of leading zeros and of sorted keys compress to little."""
    flat = values if values.dtype == WIDE else values.astype("<u8")
    return np.ascontiguousarray(flat.view(np.uint8).reshape(-1, flat.itemsize).T).tobytes()


def unpack(planes: bytes, kind: np.dtype = np.dtype("<u8")) -> np.ndarray:
    flat = np.frombuffer(planes, np.uint8).reshape(kind.itemsize, -1)
    return np.ascontiguousarray(flat.T).view(kind).reshape(-1)


#: Keys of 128 bits, as the bytes of a big-endian number: they sort and compare like it.
WIDE = np.dtype("S16")


def key_kind(order: int, base: int) -> np.dtype:
    if base**order >= 1 << 128:
        raise ValueError("n-grams of this order do not fit into 128 bits")
    return np.dtype("<u8") if base**order < 1 << 63 else WIDE


def mix(keys: np.ndarray) -> np.ndarray:
    if keys.dtype == WIDE:
        both = keys.view("<u8").reshape(-1, 2)
        keys = both[:, 0] * np.uint64(0x9E3779B97F4A7C15) ^ both[:, 1]
    x = (keys ^ (keys >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    return x ^ (x >> np.uint64(27))


#: Classes of the splitting rule for what UTF-8 writes in one byte or two: other, letter, number, white space. Only those below LATIN_END are used.
_LETTER, _NUMBER, _SPACE = 1, 2, 3
_KINDS = np.array([_SPACE if c in (*range(9, 14), 0x20, 0x85, 0xA0) else {"L": _LETTER, "N": _NUMBER}.get(unicodedata.category(chr(c))[0], 0) for c in range(0x800)], np.uint8)


def word_starts(raw: np.ndarray, texts: np.ndarray) -> np.ndarray:
    """Where the words of the byte-level splitting rule begin in raw, the UTF-8 of texts that stand one after the other and
    begin at texts. Right for texts of characters below LATIN_END.

    Words are runs of letters, of numbers or of others, with a space in front if there is one. White space before a word is cut
    before its last character, and a word's quote begins one of 's 't 're 've 'm 'll 'd where it is followed so.
    """
    n = len(raw)
    padded = np.r_[raw, np.zeros(3, np.uint8)]
    text = np.zeros(n + 3, bool)
    text[texts], text[n:] = True, True
    kind = _KINDS[raw]
    lead = np.flatnonzero(raw >= 0xC2)
    kind[lead] = kind[lead + 1] = _KINDS[(raw[lead] & 0x1F).astype(np.int64) << 6 | raw[lead + 1] & 0x3F]
    start = text.copy()
    start[1:n] |= kind[1:] != kind[:-1]
    space = kind == _SPACE
    word = np.flatnonzero(space[:-1] & ~space[1:] & ~text[1:n]) + 1
    before = raw[word - 1]
    start[word - 1 - (before >= 0x80)] = True
    start[word[before == 0x20]] = False
    quote = np.flatnonzero(raw == 0x27)
    quote = quote[start[quote]]
    one, two = padded[quote + 1], padded[quote + 2]
    short = np.isin(one, np.frombuffer(b"stmd", np.uint8)) & ~text[quote + 1]
    long = ((one == 0x6C) & (two == 0x6C) | np.isin(one, np.frombuffer(b"rv", np.uint8)) & (two == 0x65)) & ~text[quote + 1] & ~text[quote + 2]
    start[quote[short | long] + 1] = False
    start[quote[short] + 2] = start[quote[long] + 3] = True
    return np.flatnonzero(start[:n])


#: Bytes of text that are split at once, so that the arrays for it are bounded but for a longer text.
AT_ONCE = 4_000_000
#: Masks of the first 0 to 8 bytes of a little-endian number.
_FIRST = np.array([(1 << 8 * i) - 1 for i in range(9)], np.uint64)


class WordIds(dict):
    """Ids of a byte-level vocabulary file (its JSON text), remembered by word; emptied when full.

    Words come from word_starts, a batch of texts at once, and from the library for texts with characters beyond; the library
    merges them. Special tokens count as text. Short words are first looked for in arrays, all at once: a slot for each hash
    holds the whole spelling (15 bytes and how many there are), so that no word is taken for another, and its ids.
    """

    def __init__(self, source: str, most: int = 400_000, slots: int = 1 << 18):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core, and words come one by one
        from tokenizers import Tokenizer

        library = Tokenizer.from_str(json.dumps(json.loads(source) | {"added_tokens": [], "post_processor": None}))
        self.merged, self.split = library.model.tokenize, library.pre_tokenizer.pre_tokenize_str
        self.codes, size = byte_symbols(), vocabulary_size(source)
        self.symbols = "".join(sorted(self.codes, key=self.codes.get))
        self.kind = np.dtype("<u2" if size <= 65_536 else "<u4")
        self.wire = [i.to_bytes(self.kind.itemsize, "little") for i in range(size)]
        self.most = most
        self.slot_head, self.slot_tail = np.zeros(slots, np.uint64), np.zeros(slots, np.uint64)
        self.slot_many, self.slot_ids = np.zeros(slots, np.int64), np.zeros((slots, 8), self.kind)

    def __missing__(self, word: bytes) -> bytes:
        if len(self) >= self.most:
            self.clear()
        wire = self.wire
        made = b"".join([wire[t.id] for t in self.merged(charmap_decode(word, "strict", self.symbols)[0])])
        if len(word) <= 64:
            self[word] = made
        return made

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts (null has none), one text after the other, and how many each has."""
        texts = texts.cast(pa.large_string()).fill_null("")
        edges = np.frombuffer(texts.buffers()[1], "<i8")[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
        if edges[0] == edges[-1]:
            return np.zeros(0, self.kind), np.zeros(len(texts), np.int64)
        if len(texts) > 1 and edges[-1] - edges[0] > AT_ONCE:
            halves = [self.encode(x) for x in (texts[: len(texts) // 2], texts[len(texts) // 2 :])]
            return tuple(np.concatenate(x) for x in zip(*halves))
        data = texts.buffers()[2][int(edges[0]) : int(edges[-1])].to_pybytes()
        raw, edges = np.frombuffer(data, np.uint8), edges - edges[0]
        beyond = np.flatnonzero(raw >= (0xC0 | LATIN_END >> 6))
        beyond = beyond[(raw[beyond] > (0xC0 | LATIN_END >> 6)) | ((raw[beyond + 1] & 0x3F) >= (LATIN_END & 0x3F))]
        if len(beyond):
            return self._with_library(texts, np.unique(np.searchsorted(edges, beyond, "right") - 1))
        starts = word_starts(raw, edges[:-1])
        flat, many = self._looked_up(data, starts, np.diff(np.r_[starts, len(raw)]))
        return flat, np.diff(np.r_[0, np.cumsum(many)][np.searchsorted(starts, edges)])

    def _with_library(self, texts: pa.Array, odd: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        left = np.ones(len(texts), bool)
        left[odd] = False
        flat, sizes = self.encode(texts.filter(pa.array(left)))
        parts = np.split(flat, np.cumsum(sizes))  # the last is empty
        for i in odd.tolist():  # ascending: what stands before is in place
            words = [bytes(map(self.codes.__getitem__, w)) for w, _ in self.split(texts[i].as_py())]
            parts.insert(i, np.frombuffer(b"".join(map(self.__getitem__, words)), self.kind))
        return np.concatenate(parts), np.array([len(x) for x in parts[:-1]], np.int64)

    def _looked_up(self, data: bytes, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all words, one word after the other, and how many each has."""
        eight = np.ndarray(len(data) + 8, "<u8", data + bytes(16), strides=(1,))
        head = eight[starts] & _FIRST[np.minimum(sizes, 8)]
        tail = eight[np.minimum(starts + 8, len(data))] & _FIRST[np.clip(sizes - 8, 0, 7)] | sizes.astype(np.uint64) << np.uint64(56)
        slot = (mix(head * np.uint64(0x9E3779B97F4A7C15) ^ tail) % np.uint64(len(self.slot_many))).astype(np.int64)
        fits = sizes <= 15
        hit = (self.slot_head[slot] == head) & (self.slot_tail[slot] == tail) & fits
        miss = np.flatnonzero(~hit)
        made = list(map(self.__getitem__, map(data.__getitem__, map(slice, starts[miss].tolist(), (starts + sizes)[miss].tolist()))))
        many = self.slot_many[slot]
        many[miss] = np.fromiter(map(len, made), np.int64, len(made)) // self.kind.itemsize
        begin = np.cumsum(many) - many
        out, fresh = np.empty(int(many.sum()), self.kind), np.frombuffer(b"".join(made), self.kind)
        hit, cells = np.flatnonzero(hit), np.arange(8)
        full = cells < many[hit][:, None]
        out[(begin[hit][:, None] + cells)[full]] = self.slot_ids[slot[hit]][full]
        before = np.cumsum(many[miss]) - many[miss]
        out[np.repeat(begin[miss] - before, many[miss]) + np.arange(len(fresh))] = fresh
        keep = np.flatnonzero(fits[miss] & (many[miss] <= 8))
        to, first = np.unique(slot[miss[keep]], return_index=True)
        keep, held = keep[first], miss[keep[first]]
        self.slot_head[to], self.slot_tail[to], self.slot_many[to] = head[held], tail[held], many[held]
        if len(fresh):
            self.slot_ids[to] = fresh[np.minimum(before[keep][:, None] + cells, len(fresh) - 1)]
        return out, many


def vocabulary_size(source: str) -> int:
    return max(json.loads(source)["model"]["vocab"].values()) + 1


@lru_cache(maxsize=2)
def _word_ids(source: str) -> WordIds:
    return WordIds(source)


def token_table(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """chunk, ids, sizes, n_tokens, tokens: rows of some documents that stand together, with all their ids compressed
    (null text has none). Chunks are of rows that follow each other."""
    held = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary))

    def run(batches):
        bpe, chunk, size = _word_ids(held.value), TaskContext.get().partitionId() << 32, 0
        squeeze = zstandard.ZstdCompressor(3)
        for batch in batches:
            for at in range(0, batch.num_rows, ROW_DOCS):
                part = batch.slice(at, ROW_DOCS)
                flat, n = bpe.encode(part.column("text"))
                body = squeeze.compress(flat.tobytes())
                kinds = (pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int64(), pa.binary())
                row = (chunk, part.column("id").to_pylist(), n.tolist(), len(flat), body)
                yield pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, kinds)], ["chunk", "ids", "sizes", "n_tokens", "tokens"])
                size += len(flat)
                if size > CHUNK_TOKENS:
                    chunk, size = chunk + 1, 0

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "chunk long, ids array<long>, sizes array<long>, n_tokens long, tokens binary")


def expanded(body: bytes, n: int) -> np.ndarray:
    """All ids of a row in one array; the width follows from the bytes."""
    raw = zstandard.ZstdDecompressor().decompress(body)
    return np.frombuffer(raw, "<u2" if n and len(raw) == 2 * n else "<u4").astype(np.uint64)


def gram_keys(ids: np.ndarray, sizes: np.ndarray, order: int, base: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all n-grams that end at each place and stay in its document, and which places have one."""
    place = np.arange(len(ids)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    ends = np.flatnonzero(place >= order - 1)

    def number(first: int, last: int) -> np.ndarray:
        out = np.zeros(len(ends), np.uint64)
        for back in range(first, last, -1):
            out = out * np.uint64(base) + ids[ends - back]
        return out

    if key_kind(order, base) != WIDE:
        return number(order - 1, -1), ends
    half = order // 2
    return np.column_stack([number(order - 1, half - 1), number(half - 1, -1)]).astype(">u8").view(WIDE).reshape(-1), ends


def _rows(batches):
    """(chunk, ids, sizes) of every row."""
    for batch in batches:
        for chunk, body, sizes, n in zip(*(batch.column(c).to_pylist() for c in ("chunk", "tokens", "sizes", "n_tokens"))):
            yield chunk, expanded(body, n), np.array(sizes, np.int64)


def _counted(parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Different keys, sorted, and how often each occurs."""
    keys = np.concatenate(parts)
    parts.clear()
    keys.sort()
    first = np.flatnonzero(np.r_[len(keys) > 0, keys[1:] != keys[:-1]])
    return keys[first], np.diff(np.r_[first, len(keys)])


def chunk_counts(table: DataFrame, orders: range, base: int, buckets: int) -> DataFrame:
    """bucket, chunk, gram_order, keys, counts: each chunk's different n-grams, dealt by hash."""

    def emit(chunk, parts):
        for order in orders:
            keys, counts = _counted(parts[order])
            to = (mix(keys) % np.uint64(buckets)).astype(np.int64)
            by = np.argsort(to, kind="stable")  # keys stay sorted within a bucket
            keys, counts, to = keys[by], counts[by], to[by]
            edges = np.r_[np.flatnonzero(np.r_[True, to[1:] != to[:-1]]), len(to)] if len(to) else np.zeros(1, np.int64)
            spans = list(zip(edges[:-1], edges[1:]))
            for at in range(0, len(spans), 64):
                some = spans[at : at + 64]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([int(to[a]) for a, _ in some], pa.int64()), pa.array([chunk] * len(some), pa.int64()), pa.array([order] * len(some), pa.int32()), pa.array([pack(keys[a:b]) for a, b in some], pa.binary()), pa.array([pack(counts[a:b]) for a, b in some], pa.binary())],
                    ["bucket", "chunk", "gram_order", "keys", "counts"],
                )

    def run(batches):
        now, parts = None, {order: [] for order in orders}
        for chunk, ids, sizes in _rows(batches):
            if now is not None and chunk != now:
                yield from emit(now, parts)
            now = chunk
            for order in orders:
                parts[order].append(gram_keys(ids, sizes, order, base)[0])
        if now is not None:
            yield from emit(now, parts)

    return table.select("chunk", "sizes", "n_tokens", "tokens").mapInArrow(run, "bucket long, chunk long, gram_order int, keys binary, counts binary")


def corpus_totals(counts: DataFrame, least: int, buckets: int, base: int) -> DataFrame:
    """chunk, gram_order, keys, totals: the corpus counts of each chunk's n-grams, where they are least at least.

    The rows come sorted by bucket and order, and a bucket's are added up as they stream past.
    """

    def run(batches):
        for t in sorted_groups(batches, ["bucket", "gram_order"]):
            chunk, order = t.column("chunk").to_pylist(), t.column("gram_order")[0].as_py()
            own = [unpack(k, key_kind(order, base)) for k in t.column("keys").to_pylist()]
            many = np.concatenate([unpack(n) for n in t.column("counts").to_pylist()]).astype(np.float64)
            del t
            _, at = np.unique(np.concatenate(own), return_inverse=True)
            total = np.bincount(at, weights=many)[at].astype(np.int64)
            del at, many
            stops = np.cumsum([len(x) for x in own])
            for c, x, stop in zip(chunk, own, stops):
                n = total[stop - len(x) : stop]
                known = n >= least
                if known.any():
                    yield pa.RecordBatch.from_arrays([pa.array([c], pa.int64()), pa.array([order], pa.int32()), pa.array([pack(x[known])], pa.binary()), pa.array([pack(n[known])], pa.binary())], ["chunk", "gram_order", "keys", "totals"])

    dealt = counts.repartition(buckets, "bucket").sortWithinPartitions("bucket", "gram_order")
    return dealt.mapInArrow(run, "chunk long, gram_order int, keys binary, totals binary")


def counts_of(keys: np.ndarray, doc: np.ndarray, base: int, known: np.ndarray, totals: np.ndarray, unknown: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """For each place, the total of its key (below base; unknown where there is none) and how often the key occurs in the
    place's own document. doc ascends. One sort serves both: known keys are asked for once each, in order."""
    if not len(keys):
        return np.zeros(0), np.zeros(0)
    bits = int(doc[-1]).bit_length()
    if base << bits < 1 << 63:
        cells = keys << np.uint64(bits) | doc.astype(np.uint64)
        by = np.argsort(cells)
        cells = cells[by]
        asked = cells >> np.uint64(bits)
        new, other = (np.r_[True, x[1:] != x[:-1]] for x in (asked, cells))
    else:
        by = np.argsort(keys, kind="stable")
        asked, of = keys[by], doc[by]
        new = np.r_[True, asked[1:] != asked[:-1]]
        other = new | np.r_[True, of[1:] != of[:-1]]
    first = np.flatnonzero(new)
    total = np.full(len(first), float(unknown))
    if len(known):
        at = np.minimum(np.searchsorted(known, asked[first]), len(known) - 1)
        total = np.where(known[at] == asked[first], totals[at], total)
    counts, own = np.empty(len(keys)), np.empty(len(keys))
    counts[by] = np.repeat(total, np.diff(np.r_[first, len(keys)]))
    runs = np.diff(np.r_[np.flatnonzero(other), len(keys)])
    own[by] = np.repeat(runs, runs)
    return counts, own


def place_scores(ids: np.ndarray, sizes: np.ndarray, single: np.ndarray, total: int, tables: dict[int, tuple[np.ndarray, np.ndarray]], top: int, base: int, alpha: float, unknown: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """log of the stupid-backoff score of every place, by all texts and by all others; an n-gram that is not in the tables
    was counted unknown times. An id that no other text has counts there as if it had been seen once."""
    flat, doc = ids.astype(np.int64), np.repeat(np.arange(len(sizes)), sizes)
    history = single[flat]
    score = np.log(single / total, where=single > 0, out=np.zeros(len(single)))[flat]
    before = history - counts_of(ids, doc, base, ids[:0], history[:0])[1]
    other = np.log(np.maximum(before, 1) / np.maximum(total - sizes[doc], 1))
    for order in range(2, top + 1):
        keys, ends = gram_keys(ids, sizes, order, base)
        counts, own = counts_of(keys, doc[ends], base**order, *tables.get(order, (keys[:0], np.zeros(0))), unknown)
        others = np.maximum(counts - own, 0)
        for out, n, had in ((score, counts, history), (other, others, before)):
            seen = n > 0
            less = out[ends] + np.log(alpha)  # one more word of history given up, unless this order is known
            out[ends] = np.log(np.divide(n, had[ends - 1], where=seen, out=np.ones(len(n))), where=seen, out=less)
        history, before = np.zeros(len(ids)), np.zeros(len(ids))
        history[ends], before[ends] = counts, others
    return score, other


def backoff_scores(docs: DataFrame, vocabulary: str, top: int = 3, least: int = 1, alpha: float = 0.4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_tokens, log_score (sum over the places), mean_log_score (null without ids) of every row of docs, and
    others_log_score and mean_others_log_score by the counts of all other rows.

    Null and empty texts have no ids and log_score 0. Rows with one id are scored each by itself. top: longest n-gram
    (as long as 128 bits hold it: 8 for vocabularies of up to 65,536); with least above 1, n-grams counted less often are
    given up, single ids never. An n-gram of a text that is counted once in the corpus has no need to come back to its
    chunk: with least = 1 what does not come back counts 1.
    """
    spark = docs.sparkSession
    table = cut(token_table(docs, vocabulary, id_col, text_col), "tokens")
    base = vocabulary_size(read_vocabulary(vocabulary))
    key_kind(top, base)

    def singles(batches):
        _word_ids.cache_clear()  # the table is written: the worker has no more words to remember
        sums = np.zeros(base, np.int64)
        for _, ids, _ in _rows(batches):
            sums += np.bincount(ids.astype(np.int64), minlength=base)
        at = np.flatnonzero(sums)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(sums[at], pa.int64())], ["token", "n"])

    single = np.zeros(base)
    counted = table.select("chunk", "sizes", "n_tokens", "tokens").mapInArrow(singles, "token long, n long")
    for r in counted.groupBy("token").agg(F.sum("n").alias("n")).collect():  # as many as the vocabulary has at most
        single[r["token"]] = r["n"]
    total = int(single.sum())
    held = spark.sparkContext.broadcast(single)
    buckets = 1 + total // BUCKET_TOKENS
    found = corpus_totals(chunk_counts(table, range(2, top + 1), base, buckets), max(least, 2), buckets, base)

    def score(left: pa.Table, right: pa.Table) -> pa.Table:
        tables = {}
        orders = right.column("gram_order").to_numpy()
        keys, totals = right.column("keys").to_pylist(), right.column("totals").to_pylist()
        for order in np.unique(orders):
            rows = np.flatnonzero(orders == order)
            k, n = np.concatenate([unpack(keys[i], key_kind(int(order), base)) for i in rows]), np.concatenate([unpack(totals[i]) for i in rows])
            k, first = np.unique(k, return_index=True)  # a chunk read in two parts has asked twice
            tables[int(order)] = (k, n[first])
        del keys, totals
        docs_, many, out = [], [], []
        for row, (_, ids, sizes) in zip(left.column("ids").to_pylist(), _rows(left.to_batches())):
            sums, full = np.zeros((2, len(sizes))), np.flatnonzero(sizes)
            if len(full):
                for i, places in enumerate(place_scores(ids, sizes, held.value, total, tables, top, base, alpha, int(least < 2))):
                    sums[i, full] = np.add.reduceat(places, (np.cumsum(sizes) - sizes)[full])
            docs_ += row
            many.append(sizes)
            out.append(sums)
        n, sums = (np.concatenate(many), np.concatenate(out, axis=1)) if many else (np.zeros(0), np.zeros((2, 0)))
        return pa.table({"id": pa.array(docs_, pa.int64()), "n_tokens": pa.array(n, pa.int64()), "log_score": pa.array(sums[0]), "others_log_score": pa.array(sums[1])})

    scored = table.groupBy("chunk").cogroup(found.groupBy("chunk")).applyInArrow(score, "id long, n_tokens long, log_score double, others_log_score double")
    mean = lambda c: F.when(F.col("n_tokens") > 0, F.col(c) / F.col("n_tokens")).alias(f"mean_{c}")
    return scored.select(F.col("id").alias(id_col), "n_tokens", "log_score", mean("log_score"), "others_log_score", mean("others_log_score"))
