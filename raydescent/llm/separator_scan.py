"""Token counts from flat token files by a scan for end-of-document identifiers.

A flat file is ids one after the other, an end id after each document, and no index. It is read in blocks; each block is
searched for the end id as one vectorised comparison and leaves a short row: how many ids, where the ends are. Documents
run across blocks, so a prefix scan over these rows (first within chunks of blocks, then over the chunks) gives every
block its place in the file, the last end before it and the number of documents before it.
"""

from __future__ import annotations

import re
import uuid
from itertools import count

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.llm.bpe_automaton import sent
from raydescent.llm.common import cut

BLOCK_TOKENS = 1 << 16
CHUNK_BLOCKS = 1024
#: Bytes of a file that one row of the reading plan stands for, about.
RANGE_BYTES = 16 << 20
RECEIPT_DOCS = 1024


def opened(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path as Spark writes it, and the path in it."""
    if path.startswith("file:") or "://" not in path:
        return fs.LocalFileSystem(), re.sub("^file:/*", "/", path)
    return fs.FileSystem.from_uri(path)


def flat_files(spark: SparkSession, path: str, width: int = 2, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """Blocks (stream, block, payload) of the flat files at path, ids of width bytes.

    Spark lists the files and their sizes; ranges of them, of any file size, are then dealt to tasks, which open the
    file at the range's offset. A compressed file (.zst) is one range and streams through its task. A file that does not
    hold whole ids ends the run with an error; an empty one has no blocks.
    """
    step = block_tokens * width
    span = max(1, RANGE_BYTES // step) * step
    files = spark.read.format("binaryFile").load(path).select("path", "length").where("length > 0")
    last = F.when(F.col("path").endswith(".zst"), 0).otherwise(F.col("length") - 1)
    ranges = files.select("path", "length", F.explode(F.sequence(F.lit(0).cast("long"), last, F.lit(span).cast("long"))).alias("first"))
    many = files.agg(F.sum(1 + F.floor(last / span))).first()[0] or 1

    def block(name, number, body):
        if len(body) % width:
            raise ValueError(f"{name} does not hold whole ids of {width} bytes")
        return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([number], pa.int64()), pa.array([body], pa.binary())], ["stream", "block", "payload"])

    def run(batches):
        for batch in batches:
            for name, length, first in zip(*(batch.column(c).to_pylist() for c in ("path", "length", "first"))):
                store, place = opened(name)
                if name.endswith(".zst"):
                    with store.open_input_stream(place) as f:
                        for number in count():
                            body = f.read(step)
                            while 0 < len(body) < step and (more := f.read(step - len(body))):
                                body += more
                            if not body:
                                break
                            yield block(name, number, body)
                    continue
                with store.open_input_file(place) as f:
                    f.seek(first)
                    for at in range(first, min(first + span, length), step):
                        body = f.read(min(step, length - at))
                        if len(body) != min(step, length - at):
                            raise OSError(f"{name} has become shorter")
                        yield block(name, at // step, body)

    return ranges.repartition(int(many)).mapInArrow(run, "stream string, block long, payload binary")


def write_flat(docs: DataFrame, vocabulary: str, end_id: int, folder: str, compress: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write the texts of docs as flat files (.bin, or .bin.zst) into folder, one per input partition, and return (stream,
    number, id): which row is the number-th document of which file. Ids have 16 bits, or 32 if the vocabulary is larger. Special tokens in a
    text are ordinary text, so that no text holds the end id; null is empty.

    A task that is run again writes another file; only the files that the returned (written) table names are whole.
    """
    held = sent(docs.sparkSession, vocabulary, True)
    width = id_width(max(len(held.value.labels), end_id + 1))
    end = np.array([end_id], f"<u{width}").tobytes()

    def row(name, first, ids):
        kinds = (pa.string(), pa.int64(), pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip((name, first, ids), kinds)], ["stream", "first", "ids"])

    def run(batches):
        bpe, name, out, number, receipt = held.value, f"{uuid.uuid4().hex}.bin{'.zst' if compress else ''}", None, 0, []
        for batch in batches:
            for doc, text in zip(batch.column("id").to_pylist(), batch.column("text").to_pylist()):
                if out is None:
                    store, place = opened(folder)
                    store.create_dir(place, recursive=True)
                    out = store.open_output_stream(f"{place}/{name}")
                out.write(np.frombuffer(bpe.encode(text or ""), "<u4").astype(f"<u{width}").tobytes() + end)
                receipt.append(doc)
                number += 1
                if len(receipt) == RECEIPT_DOCS:
                    yield row(name, number - len(receipt), receipt)
                    receipt = []
        if out is not None:
            out.close()
        if receipt:
            yield row(name, number - len(receipt), receipt)

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    receipts = cut(rows.mapInArrow(run, "stream string, first long, ids array<long>"), "receipts")
    return receipts.select("stream", "first", F.posexplode("ids").alias("_i", "id")).select("stream", (F.col("first") + F.col("_i")).alias("number"), "id")


def id_width(vocabulary_size: int) -> int:
    return 2 if vocabulary_size <= 65_536 else 4


def scan_blocks(blocks: DataFrame, end_id: int, width: int = 2) -> DataFrame:
    """stream, block, n_tokens, ends (places of the end id in the block)."""

    def run(batches):
        for batch in batches:
            n, ends = [], []
            for payload in batch.column("payload").to_pylist():
                ids = np.frombuffer(payload or b"", f"<u{width}")
                n.append(len(ids))
                ends.append(np.flatnonzero(ids == end_id))
            yield pa.RecordBatch.from_arrays([batch.column("stream"), batch.column("block"), pa.array(n, pa.int64()), pa.array(ends, pa.list_(pa.int64()))], ["stream", "block", "n_tokens", "ends"])

    return blocks.select("stream", "block", "payload").mapInArrow(run, "stream string, block long, n_tokens long, ends array<long>")


def stitch(scanned: DataFrame) -> DataFrame:
    """scanned with at (place of the block in its stream), prior (place of the last end before it, -1 if none) and
    documents (ends before it). scanned is read twice and must be a written table."""
    rows = scanned.withColumn("_chunk", F.floor(F.col("block") / CHUNK_BLOCKS)).withColumn("_ends", F.size("ends").cast("long"))
    inside = Window.partitionBy("stream", "_chunk").orderBy("block")
    before = inside.rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_at", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))
    rows = rows.withColumn("_last", F.when(F.col("_ends") > 0, F.col("_at") + F.element_at("ends", -1)))
    rows = rows.withColumn("_prior", F.max("_last").over(before)).withColumn("_docs", F.coalesce(F.sum("_ends").over(before), F.lit(0)))
    chunks = rows.groupBy("stream", "_chunk").agg(F.sum("n_tokens").alias("n"), F.sum("_ends").alias("e"), F.max("_last").alias("l"))
    over = Window.partitionBy("stream").orderBy("_chunk").rowsBetween(Window.unboundedPreceding, -1)
    chunks = chunks.withColumn("_base", F.coalesce(F.sum("n").over(over), F.lit(0))).withColumn("_base_docs", F.coalesce(F.sum("e").over(over), F.lit(0)))
    chunks = chunks.withColumn("_base_prior", F.max(F.col("l") + F.col("_base")).over(over))
    chunks = chunks.select(F.col("stream").alias("_s"), F.col("_chunk").alias("_c"), "_base", "_base_docs", "_base_prior")
    met = rows.join(chunks, (F.col("stream") == F.col("_s")) & (F.col("_chunk") == F.col("_c")))
    prior = F.coalesce(F.col("_prior") + F.col("_base"), F.col("_base_prior"), F.lit(-1))
    return met.select(*scanned.columns, (F.col("_at") + F.col("_base")).alias("at"), prior.alias("prior"), (F.col("_docs") + F.col("_base_docs")).alias("documents"))


def document_lengths(scanned: DataFrame) -> DataFrame:
    """One row per document: stream, number (from 0), start, n_tokens (without the end id), ended.

    Ids after a stream's last end are a last document with ended false; an empty stream has no documents.
    """
    rows = stitch(scanned)
    places = F.transform("ends", lambda e: e + F.col("at"))
    froms = F.concat(F.array("prior"), places)
    zipped = F.arrays_zip(places.alias("stop"), froms.alias("from"))
    ended = rows.where(F.size("ends") > 0).select("stream", "documents", F.posexplode(zipped).alias("_i", "_d")).where("_d.stop IS NOT NULL")
    start = F.col("_d.from") + 1
    out = ended.select("stream", (F.col("documents") + F.col("_i")).alias("number"), start.alias("start"), (F.col("_d.stop") - start).alias("n_tokens"), F.lit(True).alias("ended"))
    total = rows.groupBy("stream").agg(F.max(F.col("at") + F.col("n_tokens")).alias("n"), F.max(F.when(F.size("ends") > 0, F.col("at") + F.element_at("ends", -1))).alias("last"), F.max(F.col("documents") + F.size("ends")).alias("number"))
    after = F.coalesce("last", F.lit(-1)) + 1
    tail = total.where(F.col("n") > after).select("stream", "number", after.alias("start"), (F.col("n") - after).alias("n_tokens"), F.lit(False).alias("ended"))
    return out.union(tail)


def count_tokens(blocks: DataFrame, end_id: int, width: int = 2) -> DataFrame:
    """document_lengths of blocks (stream, block, payload): the payloads are read once, what follows is short."""
    return document_lengths(cut(scan_blocks(blocks, end_id, width), "scan"))
