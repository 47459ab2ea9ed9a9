"""Each stage on its predecessor's rows, against brute force where it is a decision of its own."""

import hashlib

import public_tokenizers

import corpus_pipeline
from sparsetri.llm import bpe, mixing, quality
from sparsetri.llm.common import stored, table
from sparsetri.llm.queries import BYTE_BPE
from tests.llm.test_operators import _components, _similar


def test_stages(spark, sf):
    docs = table(spark, sf, "documents")
    names = docs.columns
    for step, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = {r.doc_id: r for r in docs.collect()}
        docs_in = docs
        docs = stored(stage(spark, docs, sf), name)
        after = docs.collect()
        if step < 4:
            assert docs.columns == names
        if name == "quality_classifier":
            model = quality.fit(docs_in, table(spark, sf, "labels").where(~quality.held_out()))
            assert {r.doc_id for r in after} == {r.doc_id for r in quality.score(docs_in, model).where("score >= 0.7").collect()}
        if name == "line_dedup":
            assert len(after) == len(before) and all(r.n_chars == len(r.text) for r in after)
        if name == "minhash_near_dedup":
            sets, links = _similar([(i, r.text) for i, r in before.items()], 5, 80)
            parts = _components(list(sets), links)
            assert {r.doc_id for r in after} == {i for i, c in parts.items() if i == c}
        if name == "mix_sources":
            copies = {r.doc_id: r.copies for r in mixing.mix(docs_in).collect()}
            assert sorted(r.doc_id for r in after) == sorted(i for i, n in copies.items() for _ in range(n))
        if name == "byte_bpe":
            assert {(r.doc_id, r.decoded_sha256) for r in after} == {(i, hashlib.sha256(r.text.encode()).hexdigest()) for i, r in before.items()}


def _stepwise(spark, docs, sf):
    for name, stage in corpus_pipeline.STAGES:
        docs = stored(stage(spark, docs, sf), name)
    return docs


def test_run_is_the_stages(spark, sf):
    a = sorted(map(tuple, corpus_pipeline.run(spark, sf).collect()))
    assert a == sorted(map(tuple, _stepwise(spark, table(spark, sf, "documents"), sf).collect())) and a


def test_byte_bpe_takes_one_worker_a_task(spark, sf):
    """Encoding and decoding share a worker and its codec, with the rows of both in turn."""
    docs = table(spark, sf, "documents")
    out = dict(corpus_pipeline.STAGES)["byte_bpe"](spark, docs, sf)
    assert str(out._jdf.queryExecution().executedPlan()).count("MapInArrow") == 1
    apart = bpe.decode_documents(bpe.encode_documents(docs, BYTE_BPE, public_tokenizers.PATTERN), BYTE_BPE, public_tokenizers.PATTERN)
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, apart.collect()))


def test_odd_rows(spark, sf):
    """Null ids and texts, empty and long texts, repeated rows and ties go through all stages; so does an empty table."""
    good = [r.text for r in quality.score(table(spark, sf, "documents"), quality.fit(table(spark, sf, "documents"), table(spark, sf, "labels"))).where("score > 0.9 and lang = 'en'").orderBy("doc_id").limit(5).collect()]
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (None, good[0], "en", "s", 5), (None, None, None, None, None), (3, good[1], "en", None, 5), (3, good[1], "en", None, 5)]
    rows += [(4, good[1], "en", "s", 5), (5, "\n".join(good * 200), "en", "s", 5), (6, good[2], "en", "t", 5), (7, good[2], "en", "t", 5), (8, " \n\t ", "en", "t", 5)]
    schema = table(spark, sf, "documents").schema
    docs = spark.createDataFrame(rows, schema)
    got = _stepwise(spark, docs, sf).collect()
    kept = {r.doc_id for r in quality.score(docs, quality.fit(docs, table(spark, sf, "labels").where(~quality.held_out()))).where("score >= 0.7").collect()}
    assert {r.doc_id for r in got} <= kept and 7 not in {r.doc_id for r in got}
    known = {hashlib.sha256((t or "").encode()).hexdigest() for _, t, *_ in rows}
    assert all(r.decoded_sha256 in known for r in got if r.doc_id != 5)
    assert _stepwise(spark, docs.where("doc_id > 100"), sf).count() == 0
