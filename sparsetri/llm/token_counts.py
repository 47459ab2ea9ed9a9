"""Token counts of flat, unindexed token files by a scan for separators.

A token file is nothing but ids, with an end-of-document id after each document.  It is cut into blocks of fixed size that any
task can scan alone: one vectorised comparison finds the separators, and what lies between two of them is a whole document.
A document that crosses blocks is stitched from block summaries: a prefix scan over (separators, ids since the last separator)
tells every block how many documents ended before it and how many ids of an open document it inherits.

Defined results: an empty file has no documents.  Ids after the last separator are a document without end and are
reported with ended = false.  Bytes that do not fill an id are an error.  A null text is an empty document, with a count of 0.
Repeated rows are documents of their own, and a null doc_id is noted as it is.  Only doc_id and text are read, so other columns may have any
name; an empty table makes no file.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import text_groups
from .common import arrow_rows, attempt_name, filesystem, new_folder, parts_for, stored, write_atomically
from .token_store import encoder

FILES_DDL = "file string, bytes long, doc_ids array<long>"


def write_flat_files(docs: DataFrame, tokenizer_path: str, end_id: int, width: int = 2, file_bytes: int = 16 << 20) -> DataFrame:
    """Flat files of all texts: (file, bytes, doc_ids in file order), stored.  The ids of documents are the writer's own
    note of what it wrote; nothing in the scan needs them."""
    folder = new_folder(docs.sparkSession, "flat")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, partition = encoder(tokenizer_path), TaskContext.get().partitionId()
        end, keys, held, size = np.array([end_id], f"<u{width}").tobytes(), [], [], 0

        def publish() -> pa.RecordBatch:
            uri = write_atomically(folder, attempt_name("flat", partition) + ".bin", iter(held))
            return pa.RecordBatch.from_arrays([pa.array([uri]), pa.array([size]), pa.array([keys], pa.list_(pa.int64()))], names=["file", "bytes", "doc_ids"])

        for batch in batches:
            ids = batch.column(0).to_pylist()
            for start, texts in text_groups(batch, 1):
                for key, raw in zip(ids[start:], own.encode(texts)):
                    if width != own.dtype.itemsize:
                        raw = np.frombuffer(raw, own.dtype).astype(f"<u{width}").tobytes()
                    keys.append(key), held.append(raw), held.append(end)
                    size += len(raw) + width
                    if size >= file_bytes:
                        yield publish()
                        keys, held, size = [], [], 0
        if keys:
            yield publish()

    return stored(docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text")).mapInArrow(run, FILES_DDL), "flat-files")


def blocks(files: DataFrame, block_bytes: int = 4 << 20) -> DataFrame:
    """(file, block, low, high): every file cut at multiples of block_bytes."""
    starts = F.sequence(F.lit(0).cast("long"), F.greatest(F.col("bytes") - 1, F.lit(0)), F.lit(block_bytes).cast("long"))
    cut = files.where("bytes > 0").select("file", "bytes", F.posexplode(starts).alias("block", "low"))
    return cut.select("file", F.col("block").cast("long").alias("block"), "low", F.least("bytes", F.col("low") + block_bytes).alias("high"))


SCAN = pa.schema([("file", pa.string()), ("block", pa.int64()), ("ids", pa.int64()), ("head", pa.int64()), ("tail", pa.int64()), ("inner", pa.list_(pa.int64()))])
SCAN_DDL = "file string, block long, ids long, head long, tail long, inner array<long>"


def scan_block(ids: np.ndarray, end_id: int) -> tuple[int | None, int, list[int]]:
    """(ids before the first separator or None, ids after the last, lengths between)."""
    at = np.flatnonzero(ids == end_id)
    if not len(at):
        return None, len(ids), []
    return int(at[0]), len(ids) - int(at[-1]) - 1, (np.diff(at) - 1).tolist()


def scan(blocked: DataFrame, end_id: int, width: int = 2) -> DataFrame:
    """One row per block; head is null where it has no separator."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(SCAN)
        for batch in batches:
            for file, block, low, high in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                fs, path = filesystem(file)
                with fs.open_input_file(path) as f:
                    raw = f.read_at(high - low, low)
                if len(raw) != high - low or len(raw) % width:
                    raise ValueError(f"{file}: {high} is no whole number of ids")
                head, tail, inner = scan_block(np.frombuffer(raw, f"<u{width}"), end_id)
                if (full := add((file, block, len(raw) // width, head, tail, inner), 64 + 8 * len(inner))) is not None:
                    yield full
        yield from rest()

    parts = parts_for(blocked.select((F.col("high") - F.col("low")).alias("bytes")), "bytes", 64 << 20)
    return blocked.repartition(parts, F.xxhash64("file", "block")).mapInArrow(run, SCAN_DDL)


def stitch(scanned: DataFrame) -> DataFrame:
    """(file, place, n_tokens, ended): the documents of every file in order."""
    order = Window.partitionBy("file").orderBy("block")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    ends = F.when(F.col("head").isNotNull(), F.size("inner") + 1).otherwise(0)
    # the open document's ids so far: all ids of blocks since the last one with a separator, and that one's tail
    summed = scanned.withColumns({"places": F.coalesce(F.sum(ends).over(before), F.lit(0)), "all": F.coalesce(F.sum("ids").over(before), F.lit(0))})
    summed = summed.withColumn("mark", F.coalesce(F.max(F.when(F.col("head").isNotNull(), F.col("all") + F.col("ids") - F.col("tail"))).over(before), F.lit(0)))
    carried = F.col("all") - F.col("mark")
    last = F.lead("block").over(order).isNull()
    whole = F.concat(F.array(carried + F.col("head")), F.col("inner"))
    ended = summed.where(F.col("head").isNotNull()).select("file", "places", F.posexplode(whole).alias("nth", "n_tokens")).select("file", (F.col("places") + F.col("nth")).cast("long").alias("place"), F.col("n_tokens").cast("long").alias("n_tokens"), F.lit(True).alias("ended"))
    rest = F.when(F.col("head").isNull(), carried + F.col("ids")).otherwise(F.col("tail"))
    open_ = summed.withColumns({"last": last, "rest": rest}).where("last and rest > 0").select("file", (F.col("places") + ends).cast("long").alias("place"), F.col("rest").cast("long").alias("n_tokens"), F.lit(False).alias("ended"))
    return ended.unionByName(open_)


def token_counts(files: DataFrame, end_id: int, width: int = 2, block_bytes: int = 4 << 20) -> DataFrame:
    """Counts of every document of the flat files in `files` (file, bytes)."""
    return stitch(stored(scan(blocks(files, block_bytes), end_id, width), "flat-scan"))
