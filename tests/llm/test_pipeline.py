"""The pipeline against its stages' operators, brute force, and odd documents."""

import hashlib

import numpy as np
import public_tokenizers

import corpus_pipeline
from bandloom.llm import decontaminate, langid, toxicity
from bandloom.runtime import table

from .test_operators_llm import slow_components, slow_fingerprint


def test_pipeline_equals_brute_force(spark, sf):
    from tokenizers import Tokenizer

    docs = {r.doc_id: r.text for r in table(spark, sf, "documents").collect()}
    speaks = langid.fit(table(spark, sf, "documents"))
    docs = {i: t for i, t in docs.items() if (p := speaks.predict(t))[0] != "und" and not p[2]}
    toxic = toxicity.fit(table(spark, sf, "documents"), table(spark, sf, "labels"))
    docs = {i: t for i, t in docs.items() if toxic.score(t) < 0.7}
    part = slow_components({i: slow_fingerprint(t) for i, t in docs.items()})
    docs = {i: t for i, t in docs.items() if part[i] == i}
    (seeds,) = decontaminate.seed_blocks(table(spark, sf, "benchmark"))
    docs = {i: t for i, t in docs.items() if not seeds.matches([t])[0]}
    lib = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = set()
    for i, t in docs.items():
        ids = lib.encode(t, add_special_tokens=False).ids
        want.add((i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()))
    got = [tuple(r) for r in corpus_pipeline.run(spark, sf).collect()]
    assert len(got) == len(want) and set(got) == want


def test_stages_keep_columns_and_take_odd_documents(spark, sf):
    rows = [(1, None), (2, ""), (3, "Der die und das ist nicht mit einer Stadt"), (3, "Der die und das ist nicht mit einer Stadt"), (None, "the and of to in is that"), (4, "the and of " * 5000)]
    odd = spark.createDataFrame([(i, t, None, None, None, 0.1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, score double")
    for docs in (odd, odd.limit(0)):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, sf)
            assert out.columns == docs.columns, name
            assert out.where("score <> 0.1").count() == 0
            docs = out
        assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_stage_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "toxicity", "simhash_near_dedup", "benchmark_decontamination", "bpe"]
    assert corpus_pipeline.ORACLE_SQL is None
