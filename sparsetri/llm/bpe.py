"""Byte-level BPE on padded numpy matrices.

Texts are split by a pattern; the distinct pieces of a batch that are no token themselves are put, as byte ids, into matrices whose rows
have about the same length.  In every round each row looks up the ranks of its neighbouring pairs in a hash table and merges the
leftmost pair of least rank; finished rows leave the matrix.  Pieces met before keep their ids in a bounded memo.

Rows wider than `WIDE` keep the least rank of each block of entries, so that a round costs a block and not the whole width.

Defined results: a null text is an empty one, which has no ids.  Special tokens' strings are ordinary text.  A null doc_id stays null and
an empty table gives an empty one.  Repeated rows repeat; only doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex

from .common import arrow_rows, claim_cache

WIDE, BLOCK = 1024, 256
NONE = np.int32(2**31 - 1)


def load_ranks(path: str) -> list[bytes]:
    """Token bytes by rank, from a file of base64 tokens and ranks."""
    with open(path, "rb") as f:
        pairs = [line.split() for line in f if line.strip()]
    tokens = [b""] * (max(int(r) for _, r in pairs) + 1)
    for token, rank in pairs:
        tokens[int(rank)] = base64.b64decode(token)
    return tokens


class PairTable:
    """Open addressing in two arrays: key left<<32|right to the merged token's rank."""

    def __init__(self, tokens: list[bytes]):
        rank = {t: i for i, t in enumerate(tokens) if t}
        pairs = [(rank[t[:k]], rank[t[k:]], r) for t, r in rank.items() for k in range(1, len(t)) if t[:k] in rank and t[k:] in rank]
        left, right, value = (np.array(x, np.int64) for x in zip(*pairs, strict=True)) if pairs else [np.empty(0, np.int64)] * 3
        keys = left << 32 | right
        self.bits = max(4, int(np.ceil(np.log2(len(keys) * 2 + 1))))
        self.keys, self.values = np.full(1 << self.bits, -1, np.int64), np.full(1 << self.bits, NONE, np.int32)
        slot, waiting, self.probes = self._slot(keys), np.arange(len(keys)), 0
        while len(waiting):
            self.probes += 1
            free = self.keys[slot[waiting]] < 0
            self.keys[slot[waiting[free]]] = keys[waiting[free]]  # of several on one free slot the last stays
            mine = self.keys[slot[waiting]] == keys[waiting]
            self.values[slot[waiting[mine]]] = value[waiting[mine]]
            waiting = waiting[~mine]
            slot[waiting] = (slot[waiting] + 1) & (1 << self.bits) - 1

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of the merged pairs, NONE where there is none; a negative id is padding."""
        keys = left.astype(np.int64) << 32 | right.astype(np.int64)
        flat = np.where((left < 0) | (right < 0), np.int64(-2), keys).ravel()
        out = np.full(len(flat), NONE, np.int32)
        open_ = np.flatnonzero(flat >= 0)
        slot = self._slot(flat[open_])
        for _ in range(self.probes):
            held = self.keys[slot]
            hit = held == flat[open_]
            out[open_[hit]] = self.values[slot[hit]]
            on = ~hit & (held >= 0)
            open_, slot = open_[on], (slot[on] + 1) & (1 << self.bits) - 1
            if not len(open_):
                break
        return out.reshape(keys.shape)


class Codec:
    """Encodes and decodes with one rank file."""

    def __init__(self, path: str, pattern: str, memo_pieces: int = 300_000):
        self.tokens = load_ranks(path)
        self.rank = {t: i for i, t in enumerate(self.tokens) if t}
        self.pairs = PairTable(self.tokens)
        self.byte_ids = np.array([self.rank[bytes([b])] for b in range(256)], np.int32)
        self.split = regex.compile(pattern).findall
        self.words = [str(i) for i in range(len(self.tokens))]
        self.memo_pieces = memo_pieces
        self._forget()

    def _forget(self) -> None:
        self.memo: dict[str, int] = {}
        self.flat, self.starts, self.lens = np.empty(0, np.int32), np.empty(0, np.int64), np.empty(0, np.int64)

    def _merge_matrix(self, m: np.ndarray, places: np.ndarray, out: list) -> None:
        """m: rows of ids, padded with -1 at the right; out[place] gets each row's ids."""
        ranks = self.pairs.ranks(m[:, :-1], m[:, 1:])
        while len(m):
            at = ranks.argmin(axis=1)  # the first of equal ranks is the leftmost
            rows = np.arange(len(m))
            least = ranks[rows, at]
            if (done := least == NONE).any():
                for row, place in zip(m[done], places[done], strict=True):
                    out[place] = row[row >= 0]
                m, ranks, places, at, least = m[~done], ranks[~done], places[~done], at[~done], least[~done]
                rows = np.arange(len(m))
                if not len(m):
                    return
            m[rows, at] = least
            # compaction: everything right of the merged pair moves one to the left, and the matrix loses a column
            column = np.arange(m.shape[1] - 1)
            m = np.take_along_axis(m, column + (column > at[:, None]), axis=1)
            if m.shape[1] == 1:
                for row, place in zip(m, places, strict=True):
                    out[place] = row
                return
            pair = np.arange(m.shape[1] - 1)
            ranks = np.take_along_axis(ranks, pair + (pair >= at[:, None]), axis=1)
            for side in (at - 1, at):
                ok = (side >= 0) & (side < m.shape[1] - 1)
                ranks[rows[ok], side[ok]] = self.pairs.ranks(m[rows[ok], side[ok]], m[rows[ok], side[ok] + 1])

    def _merge_wide(self, m: np.ndarray, places: np.ndarray, out: list) -> None:
        """The same rounds for wide rows: ranks stand in blocks with a least rank each, so a round looks at one block a row and leaves dead
        entries behind, which compaction takes out when half of a row may be dead.  m is as wide as a power of two above BLOCK."""
        while len(m):
            n, width = m.shape
            if width <= 2 * BLOCK:
                self._merge_matrix(m, places, out)
                return
            rows, side = np.arange(n), np.arange(width)
            ranks = np.full((n, width), NONE, np.int32)
            ranks[:, :-1] = self.pairs.ranks(m[:, :-1], m[:, 1:])
            least = ranks.reshape(n, -1, BLOCK).min(axis=2)
            before, after, live = np.tile(side - 1, (n, 1)), np.tile(side + 1, (n, 1)), m >= 0
            for _ in range(width // 2):
                block = least.argmin(axis=1)
                open_ = least[rows, block] != NONE
                if not open_.any():
                    break
                r, block = rows[open_], block[open_]
                at = block * BLOCK + ranks.reshape(n, -1, BLOCK)[r, block].argmin(axis=1)
                gone, new = after[r, at], ranks[r, at]
                m[r, at], live[r, gone], ranks[r, gone] = new, False, NONE
                follow = after[r, gone]
                after[r, at] = follow
                some = follow < width
                before[r[some], follow[some]] = at[some]
                right = np.where(some, m[r, np.minimum(follow, width - 1)], -1)
                ranks[r, at] = self.pairs.ranks(new, right)
                lead = before[r, at]
                some = lead >= 0
                ranks[r[some], lead[some]] = self.pairs.ranks(m[r[some], lead[some]], new[some])
                for rr, place in ((r, at), (r, gone), (r[some], lead[some])):
                    least[rr, place // BLOCK] = ranks.reshape(n, -1, BLOCK)[rr, place // BLOCK].min(axis=1)
            done = (least == NONE).all(axis=1)
            for row, ok, place in zip(m[done], live[done], places[done], strict=True):
                out[place] = row[ok]
            left = np.flatnonzero(~done)
            counts = live[left].sum(axis=1)
            packed = np.full((len(left), max(2 * BLOCK, 1 << int(counts.max(initial=1) - 1).bit_length())), -1, np.int32)
            for k, i in enumerate(left.tolist()):
                packed[k, : counts[k]] = m[i][live[i]]
            m, places = packed, places[left]

    def encode_pieces(self, pieces: list[bytes]) -> list[np.ndarray]:
        out: list = [None] * len(pieces)
        buckets: dict[int, list[int]] = {}
        for i, p in enumerate(pieces):
            if (whole := self.rank.get(p)) is not None:
                out[i] = np.array([whole], np.int32)
            else:
                buckets.setdefault(len(p) if len(p) <= 16 else 1 << (len(p) - 1).bit_length(), []).append(i)
        for width, members in buckets.items():
            step = max(1, (1 << 20) // width)
            for start in range(0, len(members), step):
                part = np.array(members[start : start + step])
                raw = np.frombuffer(b"".join(pieces[i].ljust(width, b"\0") for i in part), np.uint8).reshape(-1, width)
                lens = np.array([len(pieces[i]) for i in part])
                merge = self._merge_wide if width > WIDE else self._merge_matrix
                merge(np.where(np.arange(width) < lens[:, None], self.byte_ids[raw], np.int32(-1)), part, out)
        return out

    def encode(self, texts: list[str]) -> Iterator[np.ndarray]:
        """Ids of each text; the distinct new pieces of all texts are merged together."""
        if len(self.memo) > self.memo_pieces:
            self._forget()
        split = [self.split(t) for t in texts]
        fresh = list({p for pieces in split for p in pieces} - self.memo.keys())
        if fresh:
            found = self.encode_pieces([p.encode() for p in fresh])
            self.memo.update(zip(fresh, range(len(self.memo), len(self.memo) + len(fresh)), strict=True))
            lens = np.fromiter(map(len, found), np.int64, len(found))
            self.starts = np.concatenate([self.starts, len(self.flat) + np.cumsum(lens) - lens])
            self.lens = np.concatenate([self.lens, lens])
            self.flat = np.concatenate([self.flat, *found])
        for pieces in split:
            which = np.fromiter(map(self.memo.__getitem__, pieces), np.int64, len(pieces))
            lens = self.lens[which]
            ends = np.cumsum(lens)
            total = int(ends[-1]) if len(ends) else 0
            yield self.flat[np.repeat(self.starts[which] - (ends - lens), lens) + np.arange(total)]

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids.tolist()))

    def decimal(self, ids: np.ndarray) -> str:
        return " ".join(map(self.words.__getitem__, ids.tolist()))


def text_groups(batch: pa.RecordBatch, column: int, chars: int = 2 << 20) -> Iterator[tuple[int, list[str]]]:
    """Runs of rows with about `chars` characters, so that memory does not depend on the size of a batch."""
    texts, held, start = [], 0, 0
    for i, x in enumerate(batch.column(column)):
        texts.append(x.as_py() or "")
        held += len(texts[-1])
        if held >= chars:
            yield start, texts
            texts, held, start = [], 0, i + 1
    if texts:
        yield start, texts


_codecs: dict[tuple[str, str], Codec] = {}


def codec(path: str, pattern: str) -> Codec:
    """One for each worker process."""
    claim_cache("bpe", _codecs.clear)
    if (path, pattern) not in _codecs:
        _codecs[path, pattern] = Codec(path, pattern)
    return _codecs[path, pattern]


ENCODED = pa.schema([("doc_id", pa.int64()), ("ids", pa.binary())])
ROUND_TRIP = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])


def _encoding(path: str, pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(ENCODED)
        own = codec(path, pattern)
        for batch in batches:
            keys = batch.column(0).to_pylist()
            for start, texts in text_groups(batch, 1):
                for key, ids in zip(keys[start:], own.encode(texts)):
                    if (full := add((key, ids.astype("<i4").tobytes()), 4 * len(ids))) is not None:
                        yield full
        yield from rest()

    return run


def _decoding(path: str, pattern: str):
    import hashlib

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(ROUND_TRIP)
        own = codec(path, pattern)
        for batch in batches:
            for key, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.frombuffer(raw.as_py(), "<i4")
                row = (key, len(ids), hashlib.sha256(own.decimal(ids).encode()).hexdigest(), hashlib.sha256(own.decode(ids)).hexdigest())
                if (full := add(row, 200)) is not None:
                    yield full
        yield from rest()

    return run


ROUND_TRIP_DDL = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def _keyed_texts(docs):
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"))


def encode_documents(docs, path: str, pattern: str):
    """(doc_id, ids): ids as little-endian 32-bit integers."""
    return _keyed_texts(docs).mapInArrow(_encoding(path, pattern), "doc_id long, ids binary")


def decode_documents(encoded, path: str, pattern: str):
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of what encode_documents gave, from the ids alone."""
    return encoded.select("doc_id", "ids").mapInArrow(_decoding(path, pattern), ROUND_TRIP_DDL)


def round_trip_documents(docs, path: str, pattern: str):
    """decode_documents(encode_documents(docs)) in one worker a task: both ends share a codec, and ids need not pass through the JVM."""
    encoding, decoding = _encoding(path, pattern), _decoding(path, pattern)
    return _keyed_texts(docs).mapInArrow(lambda batches: decoding(encoding(batches)), ROUND_TRIP_DDL)
