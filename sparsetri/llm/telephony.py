"""Telephony audio as media columns.

WAV files with 8-bit mu-law or A-law samples, or blocks of IMA ADPCM, are parsed from a binary column; companded samples
are expanded by 256-entry lookup tables, ADPCM blocks are decoded together (one numpy step for the same nibble of every
block), and 16-bit PCM is resampled and can be stored as a column.  Tables of media go through Parquet.

Defined results: a null payload is an empty one.  Media that are null or no readable WAV give null PCM and an
`error` text, and digests of their bytes alone; so do cut chunks, a rate of 0 and unknown codecs.  Equal media give equal results, so
repeated rows repeat.  A null key stays null, an empty table gives an empty one, and only the named columns are read, so other columns may
have any name.  Whole payloads are decoded; work is linear in their length.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import arrow_rows, stored

PCM, ALAW, MULAW, IMA = 1, 6, 7, 17


def mulaw_table() -> np.ndarray:
    """Sign, 3-bit exponent and 4-bit mantissa of the inverted code, with the bias of 132 taken off."""
    code = ~np.arange(256) & 0xFF
    size = ((((code & 15) << 3) + 132) << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    """Even bits are inverted; the lowest segment is linear, the others have a hidden leading bit."""
    code = np.arange(256) ^ 0x55
    segment, mantissa = (code >> 4) & 7, ((code & 15) << 4) + 8
    size = np.where(segment == 0, mantissa, (mantissa + 256) << np.maximum(segment - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


def ima_steps() -> np.ndarray:
    """The 89 quantiser steps of IMA ADPCM.  Fixed values."""
    return np.array([
        7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143,
        157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552,
        1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487,
        12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
    ])


MULAW_TO_PCM, ALAW_TO_PCM, IMA_STEPS = mulaw_table(), alaw_table(), ima_steps()
#: How a nibble moves the step index.  Fixed values.
IMA_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8])


def ima_tables() -> tuple[np.ndarray, np.ndarray]:
    """By step index and nibble: the change of the sample, and the next step index."""
    code, step = np.arange(16), IMA_STEPS[:, None]
    change = (step >> 3) + (step >> 2) * (code & 1) + (step >> 1) * (code >> 1 & 1) + step * (code >> 2 & 1)
    following = np.clip(np.arange(len(IMA_STEPS))[:, None] + IMA_MOVES[code & 7], 0, len(IMA_STEPS) - 1)
    return np.where(code & 8, -change, change).ravel(), following.ravel()


IMA_CHANGES, IMA_NEXT = ima_tables()


def decode_ima(data: bytes, block: int) -> np.ndarray:
    """Mono IMA ADPCM: blocks of `block` bytes with a 4-byte head (first sample, step index).  All blocks advance together, in parts that
    bound the memory."""
    whole = len(data) // block
    out = []
    step = max(1, HELD // block) * block
    for part in (*(data[k : min(k + step, whole * block)] for k in range(0, whole * block, step)), data[whole * block :]):
        width = block if part and len(part) % block == 0 else len(part)
        if width < 4:
            continue
        blocks = np.frombuffer(part, np.uint8).reshape(-1, width)
        value = blocks[:, :2].copy().view("<i2")[:, 0].astype(np.int64)
        index = np.minimum(blocks[:, 2], 88).astype(np.int64)
        nibbles = np.stack([blocks[:, 4:] & 15, blocks[:, 4:] >> 4], axis=2).reshape(len(blocks), -1)
        pcm = np.empty((nibbles.shape[1] + 1, len(blocks)), np.int16)
        pcm[0] = value
        for k, code in enumerate(np.ascontiguousarray(nibbles.T)):
            place = index * 16 + code
            value = np.clip(value + IMA_CHANGES[place], -32768, 32767)
            index = IMA_NEXT[place]
            pcm[k + 1] = value
        out.append(pcm.T.ravel())
    return np.concatenate(out) if out else np.empty(0, np.int16)


def wav(samples: bytes, codec: int, rate: int = 8000, bits: int = 8, block: int = 1) -> bytes:
    """A mono WAV file; formats other than PCM get the extension field and the fact chunk they need."""
    extra = b"" if codec == PCM else struct.pack("<H", 0)
    fmt = struct.pack("<HHIIHH", codec, 1, rate, rate * block, block, bits) + extra
    fact = b"" if codec == PCM else b"fact" + struct.pack("<II", 4, len(samples))
    body = b"WAVEfmt " + struct.pack("<I", len(fmt)) + fmt + fact + b"data" + struct.pack("<I", len(samples)) + samples + b"\0" * (len(samples) % 2)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def parse_wav(media: bytes) -> tuple[int, int, int, bytes]:
    """(codec, rate, block, sample bytes); chunks may stand in any order."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("no RIFF/WAVE head")
    at, fmt, data = 12, None, None
    while at + 8 <= len(media) and data is None:
        kind, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if kind == b"fmt " and size >= 16:
            if at + 24 > len(media):
                raise ValueError("fmt chunk is cut short")
            fmt = struct.unpack_from("<HHIIHH", media, at + 8)
        elif kind == b"data":
            if at + 8 + size > len(media):
                raise ValueError("data chunk is cut short")
            data = media[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    if fmt is None or data is None:
        raise ValueError("no fmt or data chunk")
    if fmt[1] != 1:
        raise ValueError(f"{fmt[1]} channels")
    if not fmt[2]:
        raise ValueError("rate 0")
    return fmt[0], fmt[2], fmt[4], data


def expand(codec: int, block: int, data: bytes) -> np.ndarray:
    """16-bit samples."""
    if codec == MULAW:
        return MULAW_TO_PCM[np.frombuffer(data, np.uint8)]
    if codec == ALAW:
        return ALAW_TO_PCM[np.frombuffer(data, np.uint8)]
    if codec == IMA:
        return decode_ima(data, max(block, 5))
    if codec == PCM:
        return np.frombuffer(data[: len(data) // 2 * 2], "<i2")
    raise ValueError(f"codec {codec}")


def resample(pcm: np.ndarray, rate: int, to: int) -> np.ndarray:
    """Linear interpolation in integers, so that every machine gets the same samples."""
    if rate == to or not len(pcm):
        return pcm
    at = np.arange(-(-len(pcm) * to // rate), dtype=np.int64) * rate
    low, part = at // to, at % to
    high = np.minimum(low + 1, len(pcm) - 1)
    return ((pcm[low].astype(np.int64) * (to - part) + pcm[high].astype(np.int64) * part) // to).astype(np.int16)


def _scale(table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A law's levels in ascending order, and by any 16-bit sample the place of its level, or -1; negative samples index from the end."""
    levels = np.unique(table)
    places = np.full(1 << 16, -1, np.int16)
    places[levels] = np.arange(len(levels))
    return levels, places


#: By the number that a code of PCM has for them.
SCALES = {1: _scale(MULAW_TO_PCM), 2: _scale(ALAW_TO_PCM)}


def code_pcm(pcm: np.ndarray) -> bytes:
    """Any 16-bit samples without loss, behind a byte that says how: every other one, and those between as what they differ from the mean of their
    neighbours.  Where they differ nowhere, as in sound of twice its first rate, a flag stands for them.  Every other sample takes a byte, its place on a
    law's scale, where all of them are on it, and two otherwise, for what it differs from the one before."""
    even, odd = pcm[::2], pcm[1::2]
    rest = (odd.astype(np.int32) - _between(even, len(odd))).astype("<i2")  # wraps around, and back
    for scale, (_, places) in SCALES.items():
        if len(even) and (at := places[even]).min() >= 0:
            own = at.astype(np.uint8)
            break
    else:
        scale, own = 0, np.diff(even, prepend=np.int16(0)).astype("<i2")  # wraps around as well
    return bytes([scale << 2 | 2 * bool(rest.any()) | len(pcm) % 2]) + own.tobytes() + (rest.tobytes() if rest.any() else b"")


def _between(even: np.ndarray, n: int) -> np.ndarray:
    """Means of neighbours, rounded down; the last has itself for a neighbour."""
    wide = even.astype(np.int32)
    return ((wide + np.r_[wide[1:], wide[-1:]]) >> 1)[:n]


def decode_pcm(coded: bytes) -> np.ndarray:
    """The samples that code_pcm() was given."""
    scale, differs, odd = coded[0] >> 2, coded[0] & 2, coded[0] & 1
    width = 1 if scale else 2
    n = (len(coded) - 1 + 2 * odd) // (width + 2) if differs else (len(coded) - 1) // width
    own, rest = coded[1 : 1 + width * n], np.frombuffer(coded[1 + width * n :], "<i2")
    even = SCALES[scale][0][np.frombuffer(own, np.uint8)] if scale else np.cumsum(np.frombuffer(own, "<i2"), dtype=np.int16)
    pcm = np.empty(2 * n - odd, "<i2")
    pcm[::2] = even
    pcm[1::2] = (_between(even, n - odd) + (rest if differs else 0)).astype("<i2")
    return pcm


def features(pcm: np.ndarray) -> dict[str, int]:
    """Peak, mean power, zero crossings: integers only."""
    wide = pcm.astype(np.int64)
    if not len(wide):
        return {"samples": 0, "peak": 0, "power": 0, "crossings": 0}
    return {"samples": len(wide), "peak": int(np.abs(wide).max()), "power": int((wide * wide).sum() // len(wide)), "crossings": int(np.count_nonzero((wide[1:] < 0) != (wide[:-1] < 0)))}


UNIT = 64
#: An ADPCM block of ours: a head of first sample and step index, both 0, and one unit of payload as nibbles.
HEAD, BLOCK = 4, 4 + UNIT
#: Blocks of ADPCM that are decoded together, and bytes of media that are held for that.
HELD = 4 << 20
MEDIA = pa.schema([("key", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.binary())])
DECODED = pa.schema([("key", pa.int64()), ("n_bytes", pa.int64()), ("codec", pa.int64()), ("rate", pa.int64()), ("payload", pa.binary()), ("pcm", pa.binary()), ("error", pa.string())])
STORED_PCM = pa.schema([("key", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("codec", pa.int64()), ("rate", pa.int64()), ("coded", pa.binary()), ("error", pa.string())])
STORED_PCM_DDL = "key long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, codec long, rate long, coded binary, error string"
#: Media and sound are stored for good, so they take a dearer compression, over more bytes at once than Parquet's 1 MB.
LEVEL, PAGE = 9, 4 << 20


def dealt_codec(payload: bytes) -> int:
    """A codec by content, so that equal payloads have equal media: an eighth ADPCM, whose media are larger, three eighths A-law, the rest mu-law."""
    kind = zlib.crc32(payload) % 8
    return IMA if kind == 0 else ALAW if kind < 4 else MULAW


def media_of(payload: bytes, codec: int | None) -> bytes:
    """The payload, whole units, as one WAV file: companded samples are its bytes, ADPCM blocks hold a unit of it behind each head."""
    codec = dealt_codec(payload) if codec is None else codec
    if codec != IMA:
        return wav(payload, codec)
    blocks = np.zeros((len(payload) // UNIT, BLOCK), np.uint8)
    blocks[:, HEAD:] = np.frombuffer(payload, np.uint8).reshape(-1, UNIT)
    return wav(blocks.tobytes(), IMA, bits=4, block=BLOCK)


def payload_of(codec: int, block: int, data: bytes) -> bytes:
    """What carries the sound: all bytes of companded samples, and of ADPCM the nibbles without the heads."""
    if codec != IMA:
        return data
    block = max(block, HEAD + 1)
    whole = len(data) // block * block
    return np.frombuffer(data[:whole], np.uint8).reshape(-1, block)[:, HEAD:].tobytes() + data[whole + HEAD :]


def _media(codec: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(MEDIA)
        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = (text.as_py() or "").encode()
                payload = own.ljust(max(UNIT, -(-len(own) // UNIT) * UNIT), b"\0")
                if (full := add((key, len(own), media_of(payload, codec)), len(payload))) is not None:
                    yield full
        yield from rest()

    return run


def _expanded(parsed: list[tuple[int, int, int, bytes] | None]) -> list[np.ndarray | None]:
    """16-bit samples of each file; the ADPCM blocks of all files with one block size are decoded together."""
    out: list[np.ndarray | None] = [None] * len(parsed)
    alike: dict[int, list[int]] = {}
    for i, p in enumerate(parsed):
        if p and p[0] == IMA and p[3] and len(p[3]) % max(p[2], HEAD + 1) == 0:
            alike.setdefault(max(p[2], HEAD + 1), []).append(i)
        elif p:
            out[i] = expand(p[0], p[2], p[3])
    for block, members in alike.items():
        pcm = decode_ima(b"".join(parsed[i][3] for i in members), block)
        ends = np.cumsum([len(parsed[i][3]) // block * (1 + 2 * (block - HEAD)) for i in members])
        for i, part in zip(members, np.split(pcm, ends[:-1]), strict=True):
            out[i] = part
    return out


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple[int | None, int | None, bytes]]]:
    """Rows with some megabytes of media, whatever the size of a batch."""
    rows, held = [], 0
    for batch in batches:
        for key, n, media in zip(*(batch.column(i) for i in range(3)), strict=True):
            rows.append((key.as_py(), n.as_py(), media.as_py() or b""))
            held += len(rows[-1][2])
            if held >= HELD:
                yield rows
                rows, held = [], 0
    if rows:
        yield rows


def _read(media: bytes) -> tuple[tuple[int, int, int, bytes] | None, str | None]:
    try:
        codec, rate, block, data = parse_wav(media)
        if codec not in (PCM, ALAW, MULAW, IMA):
            raise ValueError(f"codec {codec}")
        return (codec, rate, block, data), None
    except ValueError as e:
        return None, str(e)


def _sound(batches: Iterator[pa.RecordBatch], to: int) -> Iterator[tuple]:
    """(key, n_bytes, media, parsed or None, resampled PCM bytes or None, error or None) of every row."""
    for rows in _groups(batches):
        parsed, errors = zip(*(_read(media) for _, _, media in rows), strict=True)
        for (key, n, media), p, pcm, error in zip(rows, parsed, _expanded(list(parsed)), errors, strict=True):
            yield key, n, media, p, None if p is None else resample(pcm, p[1], to).astype("<i2").tobytes(), error


def _decoded(to: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(DECODED)
        for key, n, _, p, pcm, error in _sound(batches, to):
            row = (key, n, None, None, None, None, error) if p is None else (key, n, p[0], p[1], payload_of(p[0], p[2], p[3]), pcm, None)
            if (full := add(row, 64 + len(row[4] or b"") + len(row[5] or b""))) is not None:
                yield full
        yield from rest()

    return run


def _stored_pcm(to: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        add, rest = arrow_rows(STORED_PCM)
        for key, n, media, p, pcm, error in _sound(batches, to):
            held = (len(media), hashlib.sha256(media).hexdigest())
            if p is None:
                row = (key, n, None, None, None, *held, None, None, None, error)
            else:
                payload = payload_of(p[0], p[2], p[3])
                row = (key, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-UNIT:]), *held, p[0], p[1], code_pcm(np.frombuffer(pcm, "<i2")), None)
            if (full := add(row, 400 + len(pcm or b""))) is not None:
                yield full
        yield from rest()

    return run


def feature_text(codec: int | None, rate: int | None, to: int, pcm: bytes | None) -> str | None:
    if pcm is None:
        return None
    return f"codec={codec};rate={rate}>{to};" + ";".join(f"{k}={v}" for k, v in features(np.frombuffer(pcm, "<i2")).items()) + f";pcm_crc32={zlib.crc32(pcm)}"


def _digest(to: int):
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "error"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [feature_text(c, r, to, decode_pcm(x.as_py()).tobytes() if x.is_valid else None) for c, r, x in zip(batch.column(8).to_pylist(), batch.column(9).to_pylist(), batch.column(10), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:8], pa.array(found, pa.string())], names=[*names, "feature"])

    return run


def store_media(docs: DataFrame, key: str = "doc_id", text: str = "text", codec: int | None = None) -> DataFrame:
    """Each text's bytes, padded to whole units, as the samples of one WAV file: (key, n_bytes, media), in a Parquet table.

    Without a codec, payloads are dealt over mu-law, A-law and ADPCM by their content."""
    return stored(docs.select(docs[key].cast("long").alias("key"), docs[text].alias("text")).mapInArrow(_media(codec), "key long, n_bytes long, media binary"), "media", LEVEL, PAGE)


def decode_media(media: DataFrame, to: int = 16000) -> DataFrame:
    """(key, n_bytes, codec, rate, payload, pcm, error): samples as stored, and resampled 16-bit PCM."""
    return media.select("key", "n_bytes", "media").mapInArrow(_decoded(to), "key long, n_bytes long, codec long, rate long, payload binary, pcm binary, error string")


def store_pcm(media: DataFrame, to: int = 16000) -> DataFrame:
    """Per row of media what its bytes hold, and the resampled PCM, all of it and without loss (code_pcm), as a column of a Parquet table."""
    return stored(media.select("key", "n_bytes", "media").mapInArrow(_stored_pcm(to), STORED_PCM_DDL), "pcm", LEVEL, PAGE)


def media_digest(media: DataFrame, to: int = 16000) -> DataFrame:
    """Per row of store_media() its digests and features of the resampled sound, which is stored and read back for them."""
    rows = store_pcm(media, to).select("key", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "error", "codec", "rate", "coded")
    return rows.mapInArrow(_digest(to), "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, error string, feature string")
