"""The pipeline's stages against brute force."""

import zlib

import corpus_pipeline as cp
import numpy as np
import pytest

from langpath.llm import common

from .test_operators import base_spans, components_of, edited, ids_of, prose, table

BENCH = prose(40)


@pytest.fixture(scope="module")
def sf_dir(spark, tmp_path_factory):
    root = str(tmp_path_factory.mktemp("sf"))
    a, b = prose(150), prose(90)
    texts = [a, edited(a, 1), b, edited(b, 60), prose(100) + " " + BENCH, "too short", None, prose(60) + ' token = "abcdefgh12345678" ' + prose(20), " ".join(["the same words again"] * 50), prose(1500)]
    rows = [(i * 3, t, "en", "s", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{root}/documents.parquet")
    spark.createDataFrame([(1, BENCH)], "item_id long, text string").write.parquet(f"{root}/benchmark.parquet")
    return root


def test_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    left = dict(table(docs))
    kept = {d: t for d, t in left.items() if len(t.split()) >= 20 and "the same words" not in t}
    first = {d for d, _, c in components_of(sorted(kept.items()), 5) if c == d}
    clean = {d: t for d, t in kept.items() if d in first and BENCH not in t}
    want = [set(kept), first, set(clean), set(clean)]
    for (name, stage), ids in zip(cp.STAGES[:-1], want, strict=True):
        out = common.cut(stage(spark, docs, sf_dir), name)
        assert out.columns == docs.columns, name
        assert {r["doc_id"] for r in out.collect()} == ids, name
        docs = out
    for d, t in table(docs):
        spans = base_spans(clean[d])
        assert (t == clean[d]) == (not spans) and not base_spans(t)
    assert all(r["n_chars"] == len(r["text"]) for r in docs.collect())
    pieces = cp.STAGES[-1][1](spark, docs, sf_dir).collect()
    for d, t in table(docs):
        x, at = ids_of(t), 0
        for r in sorted((r for r in pieces if r["doc_id"] == d), key=lambda r: r["start"]):
            assert r["start"] == at and r["ids_crc32"] == zlib.crc32(x[at : at + r["length"]]) and np.array_equal(r["ids"], x[at : at + r["length"]])
            at += r["length"]
        assert at == len(x)


def test_run_is_the_stages(spark, sf_dir):
    rows = cp.run(spark, sf_dir).select("doc_id", "start", "length").collect()
    assert [n for n, _ in cp.STAGES] == ["quality_rules", "near_duplicates", "decontamination", "secret_redaction", "packing"]
    assert {r["doc_id"] for r in rows} == {0, 6, 9, 21, 27}
