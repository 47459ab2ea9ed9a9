"""Operators against brute force and exact round trips, on small fixtures and the smallest tables."""

import hashlib
import random
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import public_tokenizers as pt
import pyarrow.parquet as pq
import pytest

from sparsetri.llm import bpe, common, components, line_dedup, minhash, mixing, nn_descent, quality, telephony, token_counts, token_store, warc
from sparsetri.llm import queries as q

DOCS = "doc_id long, text string, lang string, source string, n_chars long, lines string, size long, h string, key string"


def frame(spark, rows):
    """Rows of (doc_id, text, source) with extra columns whose names clash with inner ones."""
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "x", 5, "h", "k") for i, t, s in rows], DOCS)


def awkward():
    rnd = random.Random(3)
    word = lambda: "".join(rnd.choice("abcdeABÉß0!") for _ in range(rnd.randint(1, 7)))
    base = [" ".join(word() for _ in range(60)) for _ in range(12)]
    shared = ["  This Line Is Shared By Many Documents And Long Enough\t", "a short shared line", "this line is shared by many documents and long enough"]
    rows = []
    for i in range(60):
        t = base[i % 12]
        if i % 3 == 1:
            t = t.replace(" ", "  ", 1) + " tail%d" % i
        if i % 4 == 0:
            t = "\n".join([t, rnd.choice(shared), shared[1], "end"])
        rows.append((i, t, ["s1", "s2", None, "é", "s1"][i % 5]))
    rows += [(100, None, "s1"), (101, "", None), (102, " \n\t ", "s3"), (103, "x" * 5000, "s1"), (104, "Ünï😀\x00\x1c", "s2"), (None, "no id", "s1"), (None, None, None)]
    rows += [(105, "w " * 30_000, "s3"), (106, "one two three", "s1"), (107, "One  two THREE", "s1"), rows[5], rows[5]]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return frame(spark, awkward()).repartition(5).cache()


def empty(spark):
    return frame(spark, [(1, "x", "s")]).where("doc_id < 0")


def test_empty_tables(spark):
    none = empty(spark)
    assert line_dedup.dedup_lines(none).count() == 0
    assert mixing.mix(none).count() == 0 and mixing.take(none).count() == 0
    assert minhash.near_duplicates(none).count() == 0 and minhash.keep_one(none).count() == 0
    assert telephony.media_digest(telephony.store_media(none)).count() == 0
    assert token_store.read_shards(token_store.write_shards(none, q.WORD_BPE)).count() == 0
    assert token_counts.token_counts(token_counts.write_flat_files(none, q.WORD_BPE, 49407), 49407).count() == 0
    assert bpe.decode_documents(bpe.encode_documents(none, q.BYTE_BPE, pt.PATTERN), q.BYTE_BPE, pt.PATTERN).count() == 0
    labels = spark.createDataFrame([], "doc_id long, quality int")
    assert quality.score(none, quality.fit(none, labels)).count() == 0
    assert warc.read_records(warc.write_archives(spark.createDataFrame([], "page_id long, url string, html string"))).count() == 0
    assert nn_descent.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_op1_counts(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(q.WORD_BPE)
    files = token_counts.write_flat_files(docs, q.WORD_BPE, 49407, file_bytes=3000)
    for block in (2, 64, 1 << 20):
        got = token_counts.token_counts(files.select("file", "bytes"), 49407, block_bytes=block)
        rows = {(r.file, r.place): r for r in got.collect()}
        want = Counter((i, len(t.encode(x or "", add_special_tokens=False).ids)) for i, x, _ in awkward())
        have = Counter((d, rows[f.file, k].n_tokens) for f in files.collect() for k, d in enumerate(f.doc_ids))
        assert have == want and len(rows) == len(awkward()) and all(r.ended for r in rows.values())


def test_op1_unended_and_odd_files(spark, tmp_path):
    np.array([5, 6, 9, 9, 1, 2, 3], "<u2").tofile(tmp_path / "a.bin")
    files = spark.createDataFrame([(f"file://{tmp_path}/a.bin", 14)], "file string, bytes long")
    got = [(r.place, r.n_tokens, r.ended) for r in token_counts.token_counts(files, 9, block_bytes=4).orderBy("place").collect()]
    assert got == [(0, 2, True), (1, 0, True), (2, 3, False)]
    with pytest.raises(Exception, match="whole number"):
        token_counts.token_counts(files.withColumn("bytes", files.bytes - 1), 9).collect()


def _ima(raw, block):
    """Sample by sample."""
    out = []
    for start in range(0, len(raw), block):
        b = raw[start : start + block]
        value, index = int.from_bytes(b[:2], "little", signed=True), b[2]
        out.append(value)
        for byte in b[4:]:
            for code in (byte & 15, byte >> 4):
                step = int(telephony.IMA_STEPS[index])
                change = (step >> 3) + (step >> 2) * (code & 1) + (step >> 1) * (code >> 1 & 1) + step * (code >> 2 & 1)
                value = max(-32768, min(32767, value - change if code & 8 else value + change))
                index = max(0, min(88, index + [-1, -1, -1, -1, 2, 4, 6, 8][code & 7]))
                out.append(value)
    return out


def _companded(byte, codec):
    """One sample by the rules of the two laws."""
    if codec == 7:
        code = byte ^ 0xFF
        size = (((code & 15) * 8 + 132) << (code >> 4 & 7)) - 132
        return -size if code & 128 else size
    code = byte ^ 0x55
    segment, size = code >> 4 & 7, (code & 15) * 16 + 8
    size = size if segment == 0 else (size + 256) << (segment - 1)
    return size if code & 128 else -size


@pytest.mark.parametrize("to", [4000, 16000])
def test_op2_round_trip(docs, to):
    got = telephony.media_digest(telephony.store_media(docs), to).collect()
    want, codecs = Counter(), Counter()
    for i, t, _ in awkward():
        own = (t or "").encode()
        padded = own + b"\0" * (-len(own) % 64 if own else 64)
        codec = telephony.dealt_codec(padded)
        codecs[codec] += 1
        if codec == 17:
            data = b"".join(b"\0" * 4 + padded[k : k + 64] for k in range(0, len(padded), 64))
            pcm = _ima(data, 68)
            fmt = (17, 1, 8000, 8000 * 68, 68, 4, 0)
        else:
            data, pcm, fmt = padded, [_companded(b, codec) for b in padded], (codec, 1, 8000, 8000, 1, 8, 0)
        body = b"WAVEfmt " + struct.pack("<I", 18) + struct.pack("<HHIIHHH", *fmt) + b"fact" + struct.pack("<II", 4, len(data)) + b"data" + struct.pack("<I", len(data)) + data
        media = b"RIFF" + struct.pack("<I", len(body)) + body
        wide = []
        for k in range(-(-len(pcm) * to // 8000)):
            low, part = divmod(k * 8000, to)
            wide.append((pcm[low] * (to - part) + pcm[min(low + 1, len(pcm) - 1)] * part) // to)
        crossings = sum((a < 0) != (b < 0) for a, b in zip(wide, wide[1:], strict=False))
        raw = struct.pack(f"<{len(wide)}h", *wide)
        feature = f"codec={codec};rate=8000>{to};samples={len(wide)};peak={max(map(abs, wide))};power={sum(x * x for x in wide) // len(wide)};crossings={crossings};pcm_crc32={zlib.crc32(raw)}"
        want[i, len(own), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature, None] += 1
    assert len(codecs) == 3
    assert Counter((r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32, r.media_bytes, r.media_sha256, r.feature, r.error) for r in got) == want


def test_op2_errors_are_rows(spark):
    good = telephony.wav(b"\x10\x20", telephony.ALAW)
    bad = [None, b"", b"RIFF", good[:12] + b"fmt " + struct.pack("<I", 18) + b"\1\0", good[:30], good[:-1], telephony.wav(b"ab", telephony.ALAW, rate=0), telephony.wav(b"ab", 99), b"RIFFxxxxWAVEdata\xff\xff\xff\xff"]
    rows = [(k, 0, m) for k, m in enumerate(bad)] + [(None, None, good), (50, 2, telephony.wav(b"", telephony.IMA, block=68)), (51, 3, telephony.wav(b"\0" * 71, telephony.IMA, block=68))]
    media = spark.createDataFrame(rows, "key long, n_bytes long, media binary").withColumn("pcm", q.F.lit(1))
    got = {r.doc_id: r for r in telephony.media_digest(media).collect()}
    assert len(got) == len(rows) and all(got[k].error and got[k].feature is None and got[k].payload_sha256 is None for k in range(len(bad)))
    assert all(got[k].media_sha256 == hashlib.sha256(m or b"").hexdigest() for k, m in enumerate(bad))
    assert got[None].error is None and "codec=6" in got[None].feature and got[50].payload_bytes == 0 and got[51].payload_bytes == 64
    assert {r.key for r in telephony.decode_media(media).where("error is null").collect()} == {None, 50, 51}


def test_op2_codecs(spark):
    assert telephony.MULAW_TO_PCM[0] == -32124 and telephony.MULAW_TO_PCM[0xFF] == 0 and telephony.MULAW_TO_PCM[0x80] == 32124
    assert telephony.ALAW_TO_PCM[0xD5] == 8 and telephony.ALAW_TO_PCM[0x55] == -8 and telephony.ALAW_TO_PCM[0x2A] == -32256
    rng = np.random.default_rng(1)
    data = rng.integers(0, 256, 36 * 5 + 20, np.uint8)
    data[2::36] = 40
    raw = data.tobytes()
    out = _ima(raw, 36)
    assert telephony.decode_ima(raw, 36).tolist() == out
    media = spark.createDataFrame([(1, 1, telephony.wav(raw, telephony.IMA, 8000, 4, 36)), (2, 0, None), (3, 0, b"RIFFxxxxWAVEdata"), (4, 2, telephony.wav(b"\x10\x20", telephony.ALAW))], "key long, n_bytes long, media binary")
    rows = {r.key: r for r in telephony.decode_media(media).collect()}
    assert rows[1].payload == b"".join(raw[k + 4 : k + 36] for k in range(0, len(raw), 36)) and len(rows[1].pcm) == 4 * len(out) and rows[2].error and rows[3].error and rows[4].codec == 6


def test_op3_brute_force(docs):
    import string

    lower = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
    rows = awkward()
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(lower)
    held = defaultdict(set)
    for i, t, _ in rows:
        if i is not None:
            for x in (t or "").split("\n"):
                held[key(x)].add(i)
    bad = {k: max(v) for k, v in held.items() if len(k) >= 40 and len(v) >= 5}
    assert bad
    want = Counter()
    for i, t, _ in rows:
        lines = (t or "").split("\n")
        keep = [x for x in lines if i is None or key(x) not in bad or bad[key(x)] == i]
        want[i, len(lines), len(lines) - len(keep), "\n".join(keep)] += 1
    for got in (line_dedup.dedup_lines(docs, most_sent=0), line_dedup.dedup_lines(docs)):
        assert Counter((r.doc_id, r.line_dedup.n_lines, r.line_dedup.n_dropped, r.text) for r in got.collect()) == want
    assert Counter((r.doc_id, r.line_dedup.n_lines, r.line_dedup.n_dropped, r.text) for r in got.collect()) == want
    assert got.columns == [*docs.columns, "line_dedup"]


def test_op4_learns(spark):
    got = {r.doc_id: r for r in q.op4_quality_classifier(spark, "/root/testdata/sf0.1").collect()}
    labels = pq.read_table("/root/testdata/sf0.1/labels.parquet").to_pylist()
    out = [x for x in labels if zlib.crc32(str(x["doc_id"]).encode()) % 4 == 2]
    assert all(got[x["doc_id"]].held_out for x in out)
    assert np.mean([got[x["doc_id"]].predicted == x["quality"] for x in out]) > 0.97
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got.values())


def test_op3_hot_line_is_split(spark):
    """Where common lines are joined, a line of most documents is dealt to several tasks."""
    settings = {"spark.sql.adaptive.skewJoin.skewedPartitionThresholdInBytes": "4k", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "4k", "spark.sql.adaptive.skewJoin.skewedPartitionFactor": "1.5", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {k: spark.conf.get(k) for k in settings}
    rows = spark.range(4000).select(q.F.col("id").alias("doc_id"), q.F.concat(q.F.lit("a line that nearly every document of this table holds\n"), q.F.repeat(q.F.md5(q.F.col("id").cast("string")), 2)).alias("text")).repartition(16)
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        lined = rows.select("doc_id", q.F.xxhash64("text").alias("__row"), q.F.split("text", "\n").alias("__lines"))
        lost = line_dedup.over_common_lines(lined, most_sent=0)
        assert lost.count() == 3999
        out = lost.collect()
        assert len(out) == 3999 and "SortMergeJoin(skew=true)" in lost._jdf.queryExecution().executedPlan().toString()
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def _features(text):
    """Distinct hashed byte n-grams, one at a time."""
    raw, out = (text or "").encode(), set()
    shapes = bytes(97 if 97 <= c <= 122 or c >= 128 else 65 if 65 <= c <= 90 else 57 if 48 <= c <= 57 else c for c in raw)
    for kind, data, n in ((1, raw, 3), (2, shapes, 5)):
        for at in range(len(data) - n + 1):
            code = kind
            for c in data[at : at + n]:
                code = (code * 257 + c) % 2**64
            out.add(code * 0x9E3779B97F4A7C15 % 2**64 >> 46)
    return out


def test_op4_brute_force(docs):
    """Features and ratios by sets and counts, and the optimality conditions of the hinge-loss dual."""
    rnd = random.Random(9)
    texts = [t for _, t, _ in awkward()] + [" ".join(rnd.choice(("fine good prose words " if k % 2 else "CLICK $$$ 99 now ").split()) for _ in range(30)) for k in range(60)]
    make = quality.Indicators()
    rows = [make.of(t) for t in texts if len(t or "") < 3000]
    assert [set(x.tolist()) for x in rows] == [_features(t) for t in texts if len(t or "") < 3000]
    rows = rows[-60:]
    y = np.arange(60) % 2
    ratios = quality.log_count_ratios(rows, y)
    counts = [Counter(f for x, label in zip(rows, y, strict=True) if label == c for f in x.tolist()) for c in (0, 1)]
    for f in {*counts[0], *counts[1], 5}:
        assert abs(ratios[f] - np.log(((counts[1][f] + 1) / 32) / ((counts[0][f] + 1) / 32))) < 1e-12
    values = [ratios[x] / np.sqrt((ratios[x] ** 2).sum() or 1.0) for x in rows]
    sign, c = np.where(y == 1, 1.0, -1.0), np.full(60, 0.05)
    w, bias = quality.dual_coordinate_descent(rows, values, sign, c, epochs=500)
    dense = np.zeros((60, quality.SIZE + 1))
    for i, (x, v) in enumerate(zip(rows, values, strict=True)):
        dense[i, x], dense[i, -1] = v, 1
    margin = sign * (dense @ np.append(w, bias))
    # a plain projected gradient on the dual gives the best value there is; what coordinate descent found has to reach it
    signed = dense * sign[:, None]
    gram, alpha = signed @ signed.T, np.zeros(60)
    for _ in range(20_000):
        alpha = np.clip(alpha + (1 - gram @ alpha) / np.linalg.norm(gram, 2), 0, c)
    best = alpha.sum() - alpha @ gram @ alpha / 2
    assert 0 <= (w @ w + bias * bias) / 2 + (c * np.maximum(0, 1 - margin)).sum() - best + 1e-9 < 2e-3


def test_op4_ties_and_bounds(spark):
    rows = [(k % 30, "good words here" if k % 2 else "BAD 11", "s") for k in range(60)] + [(None, "good words here", "s")]
    labels = spark.createDataFrame([(k, k % 2) for k in range(30)], "doc_id long, quality int")
    docs = frame(spark, rows)
    model = quality.fit(docs, labels)
    by = defaultdict(set)
    for r in quality.score(docs, model).collect():
        by[r.text].add(r.score)
    assert all(len(x) == 1 for x in by.values()) and min(by["good words here"]) > min(by["BAD 11"])
    small = quality.fit(docs, labels, max_fit_features=60)
    assert np.count_nonzero(small.ratios) <= np.count_nonzero(model.ratios)
    assert [r.h for r in spark.createDataFrame([(None,), (4,)], "doc_id long").select(quality.held_out().alias("h")).collect()][0] is False


def test_heap_over_half_is_collected():
    from unittest.mock import MagicMock

    for total, calls in ((400, 1), (300, 0)):
        session = MagicMock()
        runtime = session.sparkContext._jvm.java.lang.Runtime.getRuntime()
        runtime.totalMemory.return_value, runtime.maxMemory.return_value = total, 750
        common.ease_driver(session)
        assert runtime.gc.call_count == calls


def test_op4_fits_in_a_task(spark, monkeypatch):
    """The driver gets the model and no features, and the model is that of the rows in the sample's order."""
    docs = frame(spark, [(k, f"good words number {k} of {k * k}" if k % 2 else f"BAD {k} $$ {k * 7}", "s") for k in range(300)])
    labels = spark.createDataFrame([(k, k % 2) for k in range(300)], "doc_id long, quality int")
    make = quality.Indicators()
    ordered = docs.selectExpr("xxhash64('fit', doc_id) as place", "doc_id", "text").orderBy("place").collect()
    wanted = quality.fit_rows([make.of(r.text) for r in ordered], np.array([r.doc_id % 2 for r in ordered]))

    def on_the_driver(*_):
        raise AssertionError("fitted on the driver")

    monkeypatch.setattr(quality, "fit_rows", on_the_driver)
    got = quality.fit(docs, labels)
    assert np.array_equal(got.weights, wanted.weights) and np.array_equal(got.ratios, wanted.ratios) and np.count_nonzero(got.ratios)
    assert (got.bias, got.slope, got.offset) == (wanted.bias, wanted.slope, wanted.offset)
    values = quality.UnitRows([make.of("some text"), make.of("")], got.ratios)
    assert abs(np.linalg.norm(values[0]) - 1) < 1e-12 and len(values[1]) == 0


def test_op4_odd_inputs(spark, docs):
    labels = spark.createDataFrame([(1, None), (None, 1), (2, 1), (3, 7)], "doc_id long, quality int")
    model = quality.fit(docs, labels)
    scores = {r.score for r in quality.score(docs.withColumn("score", docs.n_chars), model).collect()}
    assert len(scores) == 1 and 0.5 < scores.pop() < 1


def test_op5_archives(spark):
    big = "<p>" + "é" * 600
    rows = [(1, "http://a", big), (2, "u\r\nWARC-Type: x", big), (3, None, "small"), (4, "b", "small"), (5, "c", None), (None, "d", big), (9, "e", big), (9, "e", big), (7, "f", "y" * 300_000)]
    index = warc.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", q.F.lit("clash")).repartition(3), max_bytes=500)
    got = warc.resolve_revisits(warc.read_records(index)).collect()
    sha = lambda t: hashlib.sha1((t or "").encode()).hexdigest()
    want = Counter((i, len((t or "").encode()), sha(t), *(("revisit", 9) if t == big and i in (1, 2) else ("response", None))) for i, _, t in rows)
    assert Counter((r.page_id, r.payload_bytes, r.digest, r.record_type, r.refers_to) for r in got) == want
    one = warc.read_records(index.where("page_id = 7")).collect()
    assert len(one) == 1 and one[0].payload.decode() == "y" * 300_000
    assert warc.coalesce_ranges([(0, 10), (10, 5), (100, 5), (10**6, 3)], gap=90) == [(0, 105, [0, 1, 2]), (10**6, 10**6 + 3, [3])]


def _links(vectors, labels, threshold=0.93):
    n = {}
    for i, v in vectors.items():
        n[i] = {j for j, w in vectors.items() if j != i and labels[i] == labels[j] and labels[i] is not None and v @ w / np.sqrt((v @ v) * (w @ w)) >= threshold}
    return n


def _components(ids, links):
    name = {i: i for i in ids}
    changed = True
    while changed:
        changed = False
        for i in ids:
            least = min([name[i], *(name[j] for j in links[i])])
            changed |= least != name[i]
            name[i] = least
    return name


def test_op6_brute_force(spark):
    rng = np.random.default_rng(2)
    vectors, labels = {}, {}
    for c in range(40):
        centre = rng.standard_normal(16)
        for _ in range([1, 2, 5, 90][c % 4]):
            i = len(vectors)
            vectors[i] = (centre + rng.standard_normal(16) * 0.08).astype(np.float32).astype(float)
            labels[i] = c % 3
    vectors[len(vectors)] = vectors[3]
    labels[len(labels)] = labels[3]
    links = _links(vectors, labels)
    want = _components(list(vectors), links)
    rows = [(i, v.tolist(), labels[i]) for i, v in vectors.items()]
    odd = [(9001, None, 1), (9002, [0.0] * 16, 1), (9003, [float("nan")] * 16, 1), (9004, [], 1), (9005, [None, 1.0], 1), (9006, vectors[0].tolist(), None), (None, vectors[0].tolist(), 0), (9007, [1e38] * 3, 1)]
    df = spark.createDataFrame(rows + odd + [rows[7]], "vec_id long, embedding array<float>, label int").withColumn("unit", q.F.lit(1))
    got = nn_descent.near_vectors(df).collect()
    assert len(got) == len(rows) + len(odd) + 1
    by = {r.vec_id: r for r in got}
    assert {i: by[i].n_links for i in vectors} == {i: len(links[i]) for i in vectors}
    assert {i: by[i].component_id for i in vectors} == want
    assert all(by[i].n_links == 0 and by[i].component_id == i and by[i].kept for i, _, _ in odd if i is not None) and by[None].kept


def test_op6_recall_on_table(spark):
    """The table's vectors and planted neighbours of every tenth, most of them just above the threshold."""
    t = pq.read_table("/root/testdata/sf0.1/embeddings.parquet").to_pylist()
    rng = np.random.default_rng(4)
    rows = [(x["vec_id"], x["embedding"], x["label"]) for x in t]
    for k, x in enumerate(t[::10]):
        v = np.array(x["embedding"], float)
        noise = rng.standard_normal(len(v))
        v = v / np.sqrt(v @ v) + noise / np.sqrt(noise @ noise) * rng.uniform(0.2, 0.38)
        rows.append((100_000 + k, v.astype(np.float32).tolist(), x["label"]))
    links = _links({i: np.array(v, float) for i, v, _ in rows}, {i: label for i, _, label in rows})
    got = {r.vec_id: r.n_links for r in nn_descent.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")).collect()}
    whole = sum(map(len, links.values()))
    assert whole > 300 and sum(got.values()) >= 0.99 * whole and all(got[i] <= len(x) for i, x in links.items())


def test_op6_saturated_groups(spark):
    """Two dense groups: every vector has far more than a list's length of nearer neighbours, and weaker links join the groups."""
    rng = np.random.default_rng(6)
    centres = np.zeros((2, 32))
    centres[0, 0], centres[1, :2] = 1, (0.92, np.sqrt(1 - 0.92**2))
    vectors = {}
    for i in range(300):
        noise = rng.standard_normal(32)
        v = centres[i % 2] + 0.1 * noise / np.sqrt(noise @ noise)
        vectors[i] = (v / np.sqrt(v @ v)).astype(np.float32).astype(float)
    links = _links(vectors, dict.fromkeys(vectors, 0))
    cross = {i: sum((i - j) % 2 for j in x) for i, x in links.items()}
    assert sum(cross.values()) > 20 and all(len(x) - cross[i] > 100 for i, x in links.items())
    nearest = {i: sorted(links[i], key=lambda j, v=v: -(v @ vectors[j]))[: nn_descent.K] for i, v in vectors.items()}
    assert all((i - j) % 2 == 0 for i, x in nearest.items() for j in x)
    got = nn_descent.near_vectors(spark.createDataFrame([(i, v.tolist(), 0) for i, v in vectors.items()], "vec_id long, embedding array<float>, label int")).collect()
    assert {r.vec_id: r.n_links for r in got} == {i: len(x) for i, x in links.items()} and {r.component_id for r in got} == {0}


def test_op6_enlarged_lists(spark):
    """A list that is full of links takes more of them, and stops at something that is none."""
    rng = np.random.default_rng(7)
    centre = rng.standard_normal((3, 24))
    sizes, vectors = (20, 5, 90), []
    for c, n in zip(centre, sizes, strict=True):
        vectors += [c + 0.05 * rng.standard_normal(24) for _ in range(n)]
    df = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>, label int")
    nodes = nn_descent.units(df).withColumnRenamed("vec_id", "node")
    lists = nn_descent.shortened(nn_descent.leaf_lists(nodes, 0), nn_descent.K)
    for _ in range(2):
        lists = nn_descent.descend(nodes, lists)
    got = Counter(r.v for r in nn_descent.enlarged(nodes, lists, 0.93).where("cos >= 0.93").collect())
    links = _links(dict(enumerate(vectors)), dict.fromkeys(range(len(vectors)), 0))
    assert all(got[i] == len(links[i]) for i in range(25)) and all(got[i] == nn_descent.MOST for i in range(25, 115))


def test_op6_rare_links(spark):
    """One label of random vectors; few have a partner, just above the threshold."""
    rng = np.random.default_rng(8)
    x = rng.standard_normal((20_000, 64))
    x /= np.sqrt((x * x).sum(axis=1))[:, None]
    for k in range(300):
        side = rng.standard_normal(64)
        side -= side @ x[k] * x[k]
        cos = rng.uniform(0.931, 0.95)
        x[10_000 + k] = cos * x[k] + np.sqrt(1 - cos**2) * side / np.sqrt(side @ side)
    got = nn_descent.near_vectors(spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(len(x)), "embedding": x.tolist(), "label": 0}))).where("n_links > 0").collect()
    assert sum(r.n_links for r in got) >= 0.999 * 600


def test_op7_is_tiktoken(docs):
    import tiktoken

    ranks = {t: i for i, t in enumerate(bpe.load_ranks(q.BYTE_BPE))}
    e = tiktoken.Encoding("own", pat_str=pt.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = bpe.decode_documents(bpe.encode_documents(docs, q.BYTE_BPE, pt.PATTERN), q.BYTE_BPE, pt.PATTERN).collect()
    want = Counter()
    for i, t, _ in awkward():
        ids = e.encode_ordinary(t or "")
        want[i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    assert Counter(tuple(r) for r in got) == want


def test_op7_long_pieces_and_random_text():
    import tiktoken

    c = bpe.Codec(q.BYTE_BPE, pt.PATTERN)
    e = tiktoken.Encoding("own", pat_str=pt.PATTERN, mergeable_ranks=c.rank, special_tokens={})
    rnd = random.Random(5)
    texts = ["the" * 900, "ab" * 700, "é" * 800] + ["".join(rnd.choice("abcdefé 'strelv\n\t0１!") for _ in range(rnd.randint(0, 60))) for _ in range(500)]
    for t, ids in zip(texts, c.encode(texts), strict=True):
        assert ids.tolist() == e.encode_ordinary(t)
        assert c.decode(ids) == t.encode()


def test_op8_targets_and_cut(docs):
    import re

    got = mixing.mix(docs).collect()
    rows = awkward()
    assert len(got) == len(rows)
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    per = Counter()
    for _, t, s in rows:
        per[s] += size(t)
    order = sorted((s for s in per if s is not None), key=lambda s: s.encode()) + [None] * (None in per)
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    target, open_, left = dict.fromkeys(order, 0.0), set(order), 1.5 * sum(per.values())
    while open_:  # the rule as stated: share out by weight, cap, share the excess again
        level = left / sum(weight[s] for s in open_)
        over = {s for s in open_ if weight[s] * level > 2 * per[s]}
        if not over:
            target |= {s: weight[s] * level for s in open_}
            break
        for s in over:
            target[s] = 2.0 * per[s]
            left -= target[s]
        open_ -= over
    assert {(r.source_size, round(r.target, 6)) for r in got} == {(per[s], round(target[s], 6)) for s in order}
    taken = Counter()
    for r in got:
        taken[round(r.target, 6)] += r.size * r.copies
        assert r.copies <= 2
    biggest = max(size(t) for _, t, _ in rows)
    assert all(abs(n - t) <= biggest for t, n in taken.items())
    again = Counter((r.doc_id, r.row_hash, r.copies) for r in mixing.mix(docs.repartition(3)).collect())
    assert again == Counter((r.doc_id, r.row_hash, r.copies) for r in got)
    out = mixing.take(docs)
    assert out.columns == docs.columns and out.count() == sum(r.copies for r in got)


def test_op9_store(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(q.WORD_BPE)
    t.encode_special_tokens = True
    manifest = token_store.write_shards(docs, q.WORD_BPE, shard_bytes=2000)
    got = sorted((tuple(r) for r in token_store.read_shards(manifest).collect()), key=lambda r: r[1])
    ids = {}
    for i, x, _ in awkward():
        ids.setdefault(i, []).append(np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4"))
    assert Counter((i, n, crc) for i, _, n, crc in got) == Counter((i, len(a), zlib.crc32(a.tobytes())) for i, v in ids.items() for a in v)
    assert [r[0] is not None for r in got] == sorted(r[0] is not None for r in got)
    keys = [r[0] for r in got if r[0] is not None]
    assert keys == sorted(keys) and [r[1] for r in got] == np.cumsum([0, *(r[2] for r in got)])[:-1].tolist()
    rows = [r.asDict() for r in manifest.collect()]
    assert len(rows) > 3
    for key in (7, 103, 106):
        assert token_store.lookup(rows, key).astype("<u4").tolist() == ids[key][0].tolist()
    assert token_store.lookup(rows, 55555) is None
    nulls = sorted(a.tolist() for a in ids[None])
    assert sorted(token_store.lookup(rows, None, k).astype("<u4").tolist() for k in range(2)) == nulls and token_store.lookup(rows, None, 2) is None
    same = sorted(a.tolist() for a in ids[5])
    assert len(same) == 3 and sorted(token_store.lookup(rows, 5, k).astype("<u4").tolist() for k in range(3)) == same and token_store.lookup(rows, 5, 3) is None


def test_op9_words_are_the_library(spark):
    """Every Latin letter between marks, and random text: easing plain texts changes no id."""
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(q.WORD_BPE)
    t.encode_special_tokens = True
    own = token_store.WordEncoder(q.WORD_BPE, memo_words=50)
    rnd = random.Random(6)
    texts = [f"{m}{chr(c)}{chr(c)}x{m}, A{chr(c)}" for c in range(1, 0x300) for m in ("", "$$", "'")]
    pool = [*"abcXYZÉßσΣİ0٣'`.!?<|>_-\u0301\u00a0\u2003\t\n ", "'s", "'LL", "<|endoftext|>", "ﬁ", "Å"]
    texts += ["".join(rnd.choice(pool) for _ in range(rnd.randint(0, 40))) for _ in range(2000)]
    for start in range(0, len(texts), 100):
        some = texts[start : start + 100]
        for x, raw in zip(some, own.encode(some), strict=True):
            assert np.frombuffer(raw, own.dtype).tolist() == t.encode(x, add_special_tokens=False).ids, x


def test_op9_minimal_perfect_hash():
    for n in (1, 2, 7, 1000, 20_000):
        h = token_store.key_hashes(np.arange(n) * 3, np.zeros(n, bool), np.zeros(n, np.uint32), 0)
        slots = token_store.mph_slots(h, token_store.build_mph(h), n)
        assert sorted(slots.tolist()) == list(range(n))


def _similar(rows, width, percent):
    import string

    lower = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
    sets = {}
    for i, t in rows:
        words = [w for w in "".join(" " if c in "\t\n\x0b\x0c\r" else c for c in (t or "").translate(lower)).split(" ") if w]
        n = min(width, len(words))
        sets[i] = {tuple(words[k : k + n]) for k in range(len(words) - n + 1)} if words else set()
    links = {i: {j for j, b in sets.items() if i != j and a and b and 100 * len(a & b) >= percent * len(a | b)} for i, a in sets.items()}
    return sets, links


@pytest.mark.parametrize("width", [4, 5])
def test_op10_brute_force(spark, docs, width):
    rows = {i: t for i, t, _ in awkward() if i is not None}
    sets, links = _similar(rows.items(), width, 80)
    want = _components(list(rows), links)
    got = minhash.near_duplicates(docs, width).collect()
    assert len(got) == len(awkward())
    for r in got:
        if r.doc_id is None:
            assert r.component_id is None and r.kept
        else:
            assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), want[r.doc_id], want[r.doc_id] == r.doc_id)


def test_op10_table(spark, sf):
    t = pq.read_table(f"{sf}/documents.parquet").to_pylist()
    sets, links = _similar([(x["doc_id"], x["text"]) for x in t], 4, 80)
    want = _components(list(sets), links)
    assert sum(i != c for i, c in want.items()) > 5
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in q.op10_minhash(spark, sf).collect()} == {i: (len(sets[i]), want[i]) for i in sets}


def test_op10_groups_across_components(spark):
    """A chain of versions: neighbours link, ends do not, so buckets hold several components after the first step."""
    rnd = random.Random(8)
    words = [f"w{rnd.randrange(10**6)}" for _ in range(300)]
    rows = []
    for k in range(25):
        rows.append((k, " ".join(words)))
        words = words[:]
        for _ in range(4):
            words[rnd.randrange(300)] = f"v{rnd.randrange(10**6)}"
    rnd.shuffle(rows)
    rows = [(k, t, "s") for k, (_, t) in enumerate(rows)]
    sets, links = _similar([(i, t) for i, t, _ in rows], 4, 80)
    want = _components(list(sets), links)
    got = minhash.near_duplicates(frame(spark, rows), 4).collect()
    assert {r.doc_id: r.component_id for r in got} == want


def test_op10_blocks_of_a_hot_half(spark, monkeypatch):
    """The same links when a half's classes are dealt to many blocks."""
    monkeypatch.setattr(minhash, "BLOCK", 3)
    test_op10_groups_across_components(spark)


def test_repeated_ids_with_other_texts(spark):
    rows = [(1, "a b c d e f g h i j", "s"), (1, "k l m n o p q r s t", "s"), (2, "a b c d e f g h i j", "s"), (3, "k l m n o p q r s t", "s")]
    got = minhash.near_duplicates(frame(spark, rows), 4).collect()
    assert sorted(r.component_id for r in got) in ([1, 1, 1, 3], [1, 1, 2, 1], [1, 1, 1, 2])


def test_components_of_chains_and_stars(spark):
    edges = [(k, k + 1) for k in range(200)] + [(1000, 1000 + k) for k in range(1, 300)] + [(5, 5)]
    got = {r.id: r.component for r in components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(201)} | {1000 + k: 1000 for k in range(300)}


def test_op10_parity_cells_never_exclude_a_link():
    rnd = np.random.default_rng(4)
    for n in (1, 30, 300, 5000):
        for changed in {0, 1, n // 10, n // 3}:
            pool = rnd.integers(0, 2**63, n + changed, np.uint64)
            a, b = pool[:n], pool[changed : n + changed]
            cells = sum(bin(x ^ y).count("1") for x, y in zip(*((minhash.parities(s).astype(object) & (2**64 - 1)).tolist() for s in (a, b)), strict=True))
            assert cells <= len(set(a.tolist()) ^ set(b.tolist()))
            assert cells >= min(changed, 60) and cells % 2 == 0


def test_query_keeps_all_samples(spark, sf):
    """The stored sound has two samples for each of the media's, none left out."""
    from sparsetri.llm import queries

    rows = queries.op2_telephony_media(spark, sf).select("payload_bytes", "feature").collect()
    assert rows
    for r in rows:
        found = dict(x.split("=") for x in r.feature.split(";"))
        held = r.payload_bytes if found["codec"] != "17" else r.payload_bytes // 64 * 129
        assert found["rate"] == "8000>16000" and int(found["samples"]) == 2 * held


def test_op2_stored_pcm_has_every_sample():
    """Any sound comes back from its code, and sound of twice its first rate takes no more than that first rate does."""
    rnd = np.random.default_rng(7)
    for n in (0, 1, 2, 3, 4, 5, 1000, 1001):
        raw = rnd.integers(-(2**15), 2**15, n).astype(np.int16)
        for pcm in (raw, telephony.resample(raw, 8000, 16000), telephony.resample(raw, 8000, 16000)[:-1], telephony.resample(raw, 8000, 11025), np.sort(raw)):
            assert telephony.decode_pcm(telephony.code_pcm(pcm)).tolist() == pcm.tolist()
        assert len(telephony.code_pcm(telephony.resample(raw, 8000, 16000))) == 1 + 2 * n


def test_op2_companded_sound_takes_a_byte_a_sample():
    """Sound on a law's scale comes back from a byte for every other sample, whatever lies between; other sound from differences that wrap around."""
    rnd = np.random.default_rng(11)
    text = np.frombuffer(b"A line of prose, as payloads are.\n" * 40, np.uint8)
    for table in (telephony.MULAW_TO_PCM, telephony.ALAW_TO_PCM):
        for codes in (np.arange(256), rnd.integers(0, 256, 999), text, text[:1]):
            raw = table[codes]
            for pcm in (raw, telephony.resample(raw, 8000, 16000), telephony.resample(raw, 8000, 16000)[:-1]):
                assert telephony.decode_pcm(telephony.code_pcm(pcm)).tolist() == pcm.tolist()
            assert len(telephony.code_pcm(telephony.resample(raw, 8000, 16000))) == 1 + len(raw)
            off = telephony.resample(raw, 8000, 16000).copy()
            off[-2] = 1  # on neither scale
            assert telephony.decode_pcm(telephony.code_pcm(off)).tolist() == off.tolist() and len(telephony.code_pcm(off)) > 2 * len(raw)
    steps = np.array([-32768, 32767, -32768, 1, 32767, 0, -1], np.int16)
    for pcm in (steps, steps[:-1], np.repeat(steps, 2), telephony.decode_ima(b"\0\0\0\0" + text.tobytes(), 4 + len(text))):
        assert telephony.decode_pcm(telephony.code_pcm(pcm)).tolist() == pcm.tolist()
