"""WARC archives with an index that is written first and read by coalesced byte ranges.

Each task writes archives of gzip members, one per record, and an index row for every record: file, offset, length, URL,
digest.  Readers take index rows only, sort them by place, join neighbouring byte ranges into one read and inflate the
members they asked for.  Payloads that occur more than once are written once: the record of the largest page_id is the
response, the others are revisits that name it.

Archive names hold a token of their task attempt, and index rows name the archive they were written with: a task that runs
again after a lost executor writes other files and lists those.

Defined results: null html is an empty payload.  Rows with a null page_id are written and indexed but refer to nothing and
are referred to by nothing.  Rows that share page_id and payload are all responses if that page_id is the largest.  A null url is
an empty target.  Extra columns are not read.  A payload of any length is one record.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from functools import partial

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_rows, attempt_name, filesystem, new_folder, parts_for, stored, write_atomically

INDEX = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64())])
INDEX_DDL = "page_id long, url string, digest string, record_type string, refers_to long, file string, offset long, length long"
RECORD = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("digest", pa.string()), ("payload", pa.binary())])
RECORD_DDL = "page_id long, url string, record_type string, refers_to long, digest string, payload binary"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: One date for all records, so that equal input makes equal archives.
DATE = "2000-01-01T00:00:00Z"


def _one_line(value: str) -> str:
    return value.replace("\r", "%0D").replace("\n", "%0A")


def record_bytes(page_id: int | None, url: str, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC/1.1 record as a gzip member."""
    ident = "none" if page_id is None else str(page_id)
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{ident}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {_one_line(url)}", f"WARC-Payload-Digest: sha1:{digest}"]
    if refers_to is not None:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n" + (payload if refers_to is None else b"")
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    packer = zlib.compressobj(3, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n") + packer.flush()


def parse_record(member: bytes) -> tuple[dict[str, str], bytes]:
    """(WARC headers in lower case, payload)."""
    raw = zlib.decompress(member, 31)
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    headers = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    body = rest[: int(headers["content-length"])]
    if len(body) != int(headers["content-length"]) or rest[len(body) :] != b"\r\n\r\n":
        raise ValueError("record is cut short")
    return headers, body.partition(b"\r\n\r\n")[2]


def _page(urn: str) -> int | None:
    number = urn.removeprefix("<urn:page:").removesuffix(">")
    return None if number == "none" else int(number)


def _write(folder: str, max_bytes: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Archives are filled in memory up to max_bytes and then published: the bound of a task's memory."""
    held, waiting, size = [], [], 0
    partition = TaskContext.get().partitionId()

    def publish() -> pa.RecordBatch:
        nonlocal size
        uri = write_atomically(folder, attempt_name("pages", partition) + ".warc.gz", iter(held))
        columns = list(zip(*waiting, strict=True))
        columns.insert(5, [uri] * len(waiting))
        out = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, INDEX, strict=True)], schema=INDEX)
        held.clear(), waiting.clear()
        size = 0
        return out

    for batch in batches:
        for page_id, url, html, digest, refers_to in zip(*(batch.column(i) for i in range(5)), strict=True):
            page_id, url, digest, refers_to = page_id.as_py(), url.as_py() or "", digest.as_py(), refers_to.as_py()
            member = record_bytes(page_id, url, (html.as_py() or "").encode(), digest, refers_to)
            waiting.append((page_id, url, digest, "response" if refers_to is None else "revisit", refers_to, size, len(member)))
            held.append(member)
            size += len(member)
            if size >= max_bytes:
                yield publish()
    if waiting:
        yield publish()


def write_archives(pages: DataFrame, min_revisit_bytes: int = 1000, max_bytes: int = 64 << 20) -> DataFrame:
    """Writes every page and returns the stored index."""
    html = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    named = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.sha1(html).alias("digest"), F.octet_length(html).alias("bytes"))
    repeated = (
        named.where((F.col("bytes") >= min_revisit_bytes) & F.col("page_id").isNotNull()).groupBy(F.col("digest").alias("d"), F.col("bytes").alias("b"))
        .agg(F.max("page_id").alias("keeper"), F.min("page_id").alias("least")).where(F.col("least") < F.col("keeper")).select("d", "b", "keeper")
    )
    # ids and digests look for their response; html meets the answer by page, so that a page copied very often is no hot key of whole pages
    copies = named.select("page_id", "digest", "bytes").where(F.col("bytes") >= min_revisit_bytes).join(repeated, (F.col("digest") == F.col("d")) & (F.col("bytes") == F.col("b")))
    refers = copies.where(F.col("page_id") != F.col("keeper")).select(F.col("page_id").alias("p"), "d", F.col("keeper").alias("refers_to")).distinct()
    placed = named.join(refers, (F.col("page_id") == F.col("p")) & (F.col("digest") == F.col("d")), "left").select("page_id", "url", "html", "digest", "refers_to")
    folder = new_folder(pages.sparkSession, "warc")
    return stored(placed.mapInArrow(partial(_write, folder, max_bytes), INDEX_DDL), "warc-index")


def coalesce_ranges(places: list[tuple[int, int]], gap: int = 64 << 10, most: int = 8 << 20) -> list[tuple[int, int, list[int]]]:
    """places: (offset, length) in order.  (start, end, members): one read each; a gap of up to `gap` bytes is read along."""
    out: list[tuple[int, int, list[int]]] = []
    for i, (offset, length) in enumerate(places):
        if out and offset - out[-1][1] <= gap and offset + length - out[-1][0] <= most:
            start, end, members = out[-1]
            members.append(i)
            out[-1] = (start, max(end, offset + length), members)
        else:
            out.append((offset, offset + length, [i]))
    return out


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    add, rest = arrow_rows(RECORD)
    open_uri, source = None, None
    for batch in batches:
        files, offsets, lengths = (batch.column(i).to_pylist() for i in range(3))
        start = 0
        while start < len(files):
            stop = start
            while stop < len(files) and files[stop] == files[start]:
                stop += 1
            if files[start] != open_uri:
                open_uri = files[start]
                fs, path = filesystem(open_uri)
                source = fs.open_input_file(path)
            for low, high, members in coalesce_ranges(list(zip(offsets[start:stop], lengths[start:stop], strict=True))):
                block = source.read_at(high - low, low)
                for i in members:
                    at = offsets[start + i] - low
                    headers, payload = parse_record(block[at : at + lengths[start + i]])
                    kind = headers["warc-type"]
                    digest = headers["warc-payload-digest"].removeprefix("sha1:")
                    if kind == "response" and hashlib.sha1(payload).hexdigest() != digest:
                        raise ValueError(f"{open_uri} at {offsets[start + i]}: payload and digest differ")
                    refers = _page(headers["warc-refers-to"]) if kind == "revisit" else None
                    row = (_page(headers["warc-record-id"]), headers["warc-target-uri"], kind, refers, digest, payload if kind == "response" else None)
                    if (full := add(row, 200 + len(payload))) is not None:
                        yield full
            start = stop
    yield from rest()


def read_records(index: DataFrame) -> DataFrame:
    """The records that `index` (any selection of index rows) lists, with payloads; a revisit's payload is null.

    The rows are dealt out by place, so that each task reads runs of neighbouring records, however large one archive is; the number
    of tasks follows the bytes to read, not the short index rows."""
    return index.select("file", "offset", "length").repartitionByRange(parts_for(index, "length", 32 << 20), "file", "offset").sortWithinPartitions("file", "offset").mapInArrow(_read, RECORD_DDL)


def resolve_revisits(records: DataFrame) -> DataFrame:
    """records with `payload_bytes` of the full payload: revisits get it from the response they name.

    A column own_bytes, where payloads were measured already, serves in their place."""
    sized = records if "own_bytes" in records.columns else records.withColumn("own_bytes", F.octet_length("payload").cast("long")).drop("payload")
    responses = sized.where("record_type = 'response' and page_id is not null").groupBy(F.col("page_id").alias("p"), F.col("digest").alias("d")).agg(F.max("own_bytes").alias("named_bytes"))
    joined = sized.join(responses, (F.col("refers_to") == F.col("p")) & (F.col("digest") == F.col("d")), "left")
    return joined.select("page_id", "url", "record_type", "refers_to", "digest", F.coalesce("own_bytes", "named_bytes").alias("payload_bytes"))
