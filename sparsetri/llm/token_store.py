"""Token-id files with a minimal perfect hash index.

Documents are range-partitioned by id, encoded and appended to raw payloads of 16-bit (or, for large vocabularies, 32-bit)
ids; beside every payload lies an index: a hash-and-displace function that sends the shard's n keys to n different slots, and per slot a
64-bit fingerprint, the offset and the length.  A lookup is one displacement, one slot, one fingerprint comparison and one read.
The manifest has a row for each shard; running sums over it give each document's place in the whole.

File names hold a token of the task attempt, and the manifest lists what its own attempt wrote, so re-run tasks do no harm.

Defined results: a null text is an empty one and still gets its end id.  Null ids come first.  Rows that share an id are kept all; the
n-th of them in a shard has the key (id, n).  Lookups of ids that were never stored are answered by the fingerprint: absent.
Strings of special tokens are ordinary text.  Only the named columns are read; an empty table makes no shard.
"""

from __future__ import annotations

import os
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import text_groups
from .common import arrow_rows, attempt_name, claim_cache, filesystem, new_folder, parts_for, stored, write_atomically

MAGIC = b"STIX0001"
NULL_KEY = np.uint64(0xD1B54A32D192ED03)


#: Texts of ASCII without apostrophes and control characters and of Latin letters: in them the vocabulary's rules keep runs of marks apart from letters and
#: digits, and lower each letter by itself, so both can be done before words are numbered.
PLAIN = "^[\\t-\\r -&(-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u024f]*$"
MARKS = r"([!-&(-/:-@\[-`{-~]+)"


BETWEEN = "\x01"


class WordEncoder:
    """Encodes with the tokenizers library, each distinct blank-separated word once: the vocabulary's own rules drop white
    space and never join across it, so a text's ids are its words' ids in a row.  Arrow splits and numbers the words, Python sees
    each distinct word of a group of texts once, and ids are gathered by number.

    The memo is emptied when full, so a worker's memory has a bound.  Ids come as little-endian bytes."""

    def __init__(self, path: str, memo_words: int = 300_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.memo: dict[str, bytes] = {}
        self.memo_words = memo_words

    def _one(self, word: str) -> bytes:
        return np.array(self.tokenizer.encode(word, add_special_tokens=False).ids, self.dtype).tobytes()

    def _learn(self, fresh: list[str]) -> None:
        """Many words in one call, with a control character between them, whose id nothing else has."""
        mark = self.tokenizer.encode(BETWEEN, add_special_tokens=False).ids
        joint = [w for w in fresh if BETWEEN not in w] if len(mark) == 1 else []
        chunks = [joint[k : k + 500] for k in range(0, len(joint), 500)]
        width = self.dtype.itemsize
        for words, e in zip(chunks, self.tokenizer.encode_batch_fast([f" {BETWEEN} ".join(c) for c in chunks], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, self.dtype)
            cuts = np.flatnonzero(ids == mark[0])
            if len(cuts) == len(words) - 1:
                raw, ends = ids.tobytes(), [*cuts.tolist(), len(ids)]
                start = 0
                for word, end in zip(words, ends, strict=True):
                    self.memo[word] = raw[start * width : end * width]
                    start = end + 1
        for word in fresh:
            if word not in self.memo:
                self.memo[word] = self._one(word)

    def encode(self, texts: list[str]) -> Iterator[bytes]:
        if len(self.memo) > self.memo_words:
            self.memo = {}
        raw = pa.array(texts, pa.large_string())
        plain = pc.match_substring_regex(raw, PLAIN)
        if pc.any(plain).as_py():
            eased = pc.replace_substring_regex(pc.utf8_lower(pc.if_else(plain, raw, "")), MARKS, r" \1 ")
            raw = pc.if_else(plain, eased, raw)
        words = pc.ascii_split_whitespace(raw)
        numbered = words.values.dictionary_encode()
        distinct, which = numbered.dictionary.to_pylist(), numbered.indices.to_numpy()
        if fresh := [w for w in distinct if w not in self.memo]:
            self._learn(fresh)
        held = [self.memo[w] for w in distinct]
        pa.default_memory_pool().release_unused()
        lens = np.fromiter(map(len, held), np.int64, len(held)) // self.dtype.itemsize
        flat = np.frombuffer(b"".join(held), self.dtype)
        shift = (np.cumsum(lens) - lens)[which]
        lens = lens[which]
        ends = np.concatenate([[0], np.cumsum(lens)])
        shift -= ends[:-1]
        cuts = words.offsets.to_numpy()
        for low, high in zip(cuts, cuts[1:], strict=False):
            yield flat[np.repeat(shift[low:high], lens[low:high]) + np.arange(ends[low], ends[high])].tobytes()


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    claim_cache("words", _encoders.clear)
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def key_hashes(keys: np.ndarray, nulls: np.ndarray, nth: np.ndarray, seed: int) -> np.ndarray:
    base = np.where(nulls, NULL_KEY, keys.astype(np.int64).view(np.uint64))
    return _mixed(_mixed(base + np.uint64(seed)) + nth.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def _slots(h: np.ndarray, d: np.ndarray, n: int) -> np.ndarray:
    return (_mixed(h + (d.astype(np.uint64) + np.uint64(1)) * np.uint64(0xA24BAED4963EE407)) % np.uint64(n)).astype(np.int64)


def build_mph(h: np.ndarray, per_bucket: float = 3.0) -> np.ndarray:
    """Displacements of distinct hashes: buckets are placed from large to small, all buckets of one size trying together;
    buckets of one key take the slots that are left, written as -slot-1."""
    n = len(h)
    m = max(1, int(n / per_bucket))
    bucket = (h % np.uint64(m)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    sizes = np.bincount(bucket, minlength=m)
    firsts = np.cumsum(sizes) - sizes
    disp, taken = np.zeros(m, np.int32), np.zeros(n, bool)
    for size in range(int(sizes.max(initial=0)), 1, -1):
        waiting = np.flatnonzero(sizes == size)
        if not len(waiting):
            continue
        members = h[order[firsts[waiting][:, None] + np.arange(size)]]
        d, claim = np.zeros(len(waiting), np.int64), np.empty(n, np.int64)
        while len(waiting):
            slots = _slots(members, np.broadcast_to(d[:, None], members.shape), n)
            ordered = np.sort(slots, axis=1)
            ok = ~taken[slots].any(axis=1) & (ordered[:, 1:] != ordered[:, :-1]).all(axis=1)
            rows = np.flatnonzero(ok)
            claim[slots[rows]] = rows[:, None]
            ok[rows] = (claim[slots[rows]] == rows[:, None]).all(axis=1)
            taken[slots[ok]] = True
            disp[waiting[ok]] = d[ok]
            waiting, members, d = waiting[~ok], members[~ok], d[~ok] + 1
            if len(d) and d.max() > 1 << 22:
                raise ValueError("no displacement: equal hashes")
    disp[np.flatnonzero(sizes == 1)] = -np.flatnonzero(~taken)[: int((sizes == 1).sum())] - 1
    return disp


def mph_slots(h: np.ndarray, disp: np.ndarray, n: int) -> np.ndarray:
    d = disp[(h % np.uint64(len(disp))).astype(np.int64)].astype(np.int64)
    return np.where(d < 0, -d - 1, _slots(h, np.maximum(d, 0), n))


ENTRY = np.dtype([("fingerprint", "<u8"), ("offset", "<u8"), ("length", "<u4")])


class ShardIndex:
    """n keys, in stored order, with displacements and one entry a slot."""

    def __init__(self, width: int, seed: int, keys: np.ndarray, nulls: np.ndarray, nth: np.ndarray, disp: np.ndarray, entries: np.ndarray):
        self.width, self.seed, self.keys, self.nulls, self.nth, self.disp, self.entries = width, seed, keys, nulls, nth, disp, entries

    @classmethod
    def build(cls, width: int, keys: list[int | None], lengths: np.ndarray) -> ShardIndex:
        nulls = np.array([k is None for k in keys], bool)
        plain = np.array([0 if k is None else k for k in keys], np.int64)
        nth, seen = np.zeros(len(keys), np.uint32), {}
        if len(set(keys)) < len(keys):
            for i, k in enumerate(keys):
                nth[i] = seen[k] = seen.get(k, -1) + 1
        seed = 0
        while len(np.unique(h := key_hashes(plain, nulls, nth, seed))) < len(keys):
            seed += 1  # two keys with one hash: all keys are hashed anew
        disp = build_mph(h)
        entries = np.zeros(len(keys), ENTRY)
        slot = mph_slots(h, disp, len(keys))
        entries["fingerprint"][slot] = _mixed(h ^ np.uint64(0x5851F42D4C957F2D))
        entries["offset"][slot] = (np.cumsum(lengths) - lengths) * width
        entries["length"][slot] = lengths
        return cls(width, seed, plain, nulls, nth, disp, entries)

    def to_bytes(self) -> bytes:
        n = len(self.keys)
        return b"".join([MAGIC, struct.pack("<IIQQ", self.width, self.seed, n, len(self.disp)), self.keys.astype("<i8").tobytes(), self.nulls.tobytes(), self.nth.astype("<u4").tobytes(), self.disp.astype("<i4").tobytes(), self.entries.tobytes()])

    @classmethod
    def from_bytes(cls, raw: bytes) -> ShardIndex:
        if raw[:8] != MAGIC:
            raise ValueError("not an index")
        width, seed, n, m = struct.unpack_from("<IIQQ", raw, 8)
        at, parts = 32, []
        for kind, count in (("<i8", n), ("?", n), ("<u4", n), ("<i4", m), (ENTRY, n)):
            parts.append(np.frombuffer(raw, kind, count, at))
            at += parts[-1].nbytes
        return cls(width, seed, *parts)

    @classmethod
    def find_one(cls, f, key: int, null: bool, nth: int) -> tuple[int, int, int] | None:
        """(width, offset, length) of one key from an open index file: head, one displacement and one entry are read, whatever its size."""
        head = f.read_at(32, 0)
        if head[:8] != MAGIC:
            raise ValueError("not an index")
        width, seed, n, m = struct.unpack_from("<IIQQ", head, 8)
        if not n:
            return None
        h = key_hashes(np.array([key], np.int64), np.array([null]), np.array([nth]), seed)
        at = 32 + n * (8 + 1 + 4)
        d = np.frombuffer(f.read_at(4, at + 4 * int(h[0] % np.uint64(m))), "<i4").astype(np.int64)
        slot = -int(d[0]) - 1 if d[0] < 0 else int(_slots(h, d, n)[0])
        e = np.frombuffer(f.read_at(ENTRY.itemsize, at + 4 * m + ENTRY.itemsize * slot), ENTRY)[0]
        return (width, int(e["offset"]), int(e["length"])) if e["fingerprint"] == _mixed(h ^ np.uint64(0x5851F42D4C957F2D))[0] else None

    def find(self, keys: np.ndarray, nulls: np.ndarray, nth: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(present, offset, length) of each key, in constant time each."""
        if not len(self.keys):
            return np.zeros(len(keys), bool), np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        h = key_hashes(keys, nulls, nth, self.seed)
        e = self.entries[mph_slots(h, self.disp, len(self.keys))]
        return e["fingerprint"] == _mixed(h ^ np.uint64(0x5851F42D4C957F2D)), e["offset"].astype(np.int64), e["length"].astype(np.int64)


MANIFEST = pa.schema([("partition", pa.int64()), ("part", pa.int64()), ("payload", pa.string()), ("index", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64()), ("least", pa.int64()), ("largest", pa.int64())])
MANIFEST_DDL = "partition long, part long, payload string, index string, n_docs long, n_ids long, least long, largest long"


def write_shards(docs: DataFrame, tokenizer_path: str, end_id: int = 1, shard_bytes: int = 32 << 20) -> DataFrame:
    """Writes all documents' ids in ascending order of doc_id; returns the stored manifest.  A task holds one shard's payload."""
    folder = new_folder(docs.sparkSession, "tokens")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, partition, part = encoder(tokenizer_path), TaskContext.get().partitionId(), 0
        end = np.array([end_id], own.dtype).tobytes()
        keys, lengths, payload, size = [], [], [], 0

        def publish() -> pa.RecordBatch:
            name = attempt_name("shard", partition)
            index = ShardIndex.build(own.dtype.itemsize, keys, np.array(lengths, np.int64))
            ids = write_atomically(folder, f"{name}.ids", iter(payload))
            row = (partition, part, ids, write_atomically(folder, f"{name}.idx", iter([index.to_bytes()])), len(keys), sum(lengths), keys[0], keys[-1])
            return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(row, MANIFEST, strict=True)], schema=MANIFEST)

        for batch in batches:
            ids = batch.column(0).to_pylist()
            for start, texts in text_groups(batch, 1, 3 << 20):
                for key, raw in zip(ids[start:], own.encode(texts)):
                    keys.append(key), lengths.append(len(raw) // own.dtype.itemsize + 1), payload.append(raw + end)
                    size += len(raw) + own.dtype.itemsize
                    if size >= shard_bytes:
                        yield publish()
                        keys, lengths, payload, size, part = [], [], [], 0, part + 1
        if keys:
            yield publish()

    narrow = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"))
    ordered = narrow.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    return stored(ordered.mapInArrow(run, MANIFEST_DDL), "tokens-manifest")


STORED = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])


def read_shards(manifest: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every stored document, each fetched through its shard's index."""
    # the manifest has one short row per shard, so its running sum is small work
    before = F.coalesce(F.sum("n_ids").over(Window.orderBy("partition", "part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = manifest.select("payload", "index", before.cast("long").alias("base"), F.xxhash64("payload").alias("spread"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(STORED)
        for batch in batches:
            for payload, index, base in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                fs, path = filesystem(index)
                with fs.open_input_file(path) as f:
                    own = ShardIndex.from_bytes(f.read())
                found, offsets, lengths = own.find(own.keys, own.nulls, own.nth)
                if not found.all():
                    raise ValueError(f"{index}: a key is not found")
                fs, path = filesystem(payload)
                with fs.open_input_file(path) as f:
                    for i in range(len(own.keys)):
                        raw = f.read_at(int(lengths[i]) * own.width, int(offsets[i]))
                        ids = np.frombuffer(raw, f"<u{own.width}").astype("<u4")
                        row = (None if own.nulls[i] else int(own.keys[i]), base + int(offsets[i]) // own.width, len(ids), zlib.crc32(ids.tobytes()))
                        if (full := add(row)) is not None:
                            yield full
        yield from rest()

    # shards are some megabytes each: tasks are counted by ids, as the manifest's own rows are too short to tell
    return placed.repartition(parts_for(manifest, "n_ids", 32 << 20), "spread").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def lookup(manifest_rows: list, doc_id: int | None, nth: int = 0) -> np.ndarray | None:
    """The ids of the n-th document with this id by keyed access: three short reads of an index and one of its payload.  manifest_rows are
    the manifest's rows of shards that may hold the id; shards are in order of ids, so that their least and largest leave one or, at a
    border, two.  Where an id goes on in a next shard, its documents there are counted on."""
    for row in sorted(manifest_rows, key=lambda r: (r["partition"], r["part"])):
        if doc_id is not None and (row["largest"] is None or not ((row["least"] is None or row["least"] <= doc_id) and doc_id <= row["largest"])):
            continue
        fs, path = filesystem(row["index"])
        with fs.open_input_file(path) as f:
            one = lambda k, f=f: ShardIndex.find_one(f, doc_id or 0, doc_id is None, k)
            found, here = one(nth), 0
            while not found and one(here):
                here += 1
        if found:
            width, offset, length = found
            fs, path = filesystem(row["payload"])
            with fs.open_input_file(path) as f:
                return np.frombuffer(f.read_at(length * width, offset), f"<u{width}")
        nth -= here
    return None
