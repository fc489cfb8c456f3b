"""Every operator on columns whose names clash with its own and on very long texts."""

import random

import pytest

from stagefilter.llm.langid import ByteConv, accepted, identify
from stagefilter.llm.mixing import mix_sources, mixed_documents
from stagefilter.llm.packing import pack
from stagefilter.llm.pii import personal_data
from stagefilter.llm.quality import quality_rules
from stagefilter.llm.secrets import find_secrets

NAMES = ["doc_id", "text", "lang", "source", "n_chars", "size", "bucket", "w", "c", "lines", "base", "spans", "taken", "whole", "_own_text", "h", "a.b"]


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(3)
    prose = " ".join(rng.choice(("the", "and", "of", "house", "river", "stood")) for _ in range(20_000))
    marks = " ".join(f"{rng.getrandbits(160):040x} a{i}@b.org 10.0.0.{i % 250} token={rng.getrandbits(60):x}zz" for i in range(500))
    one = "x" * 300_000
    texts = [prose, marks, one, None, "", "a short text with some words in it, nothing else at all"]
    rows = [(i, t, "en" if i % 2 else "fr", f"s{i % 2}", len(t or ""), *range(12)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, NAMES)


def test_row_operators(docs):
    small = ByteConv(sample=50)
    for run in (lambda d: identify(d, small), find_secrets, mix_sources, personal_data, quality_rules):
        rows = run(docs).collect()
        assert sorted(r.doc_id for r in rows) == [0, 1, 2, 3, 4, 5]
    found = {r.doc_id: r for r in find_secrets(docs).collect()}
    assert found[1].n_hex == 500 and found[1].n_assign == 500 and found[0].n_hex == 0
    people = {r.doc_id: r for r in personal_data(docs).collect()}
    assert people[1].n_email == 500 and people[1].n_ip == 500


def test_stages_keep_columns(docs):
    out = accepted(docs, 0.0, ByteConv(sample=50))
    assert out.columns == NAMES and out.count() <= 6
    mixed = mixed_documents(docs)
    assert mixed.columns == NAMES and all(r["a.b"] == 11 and r["bucket"] == 1 for r in mixed.collect())


def test_packing(docs):
    rows = pack(docs).collect()
    assert sum(r.length for r in rows) == sum(r.doc_tokens for r in rows if r.start == 0) and {r.doc_id for r in rows} == {0, 1, 2, 3, 4, 5}
