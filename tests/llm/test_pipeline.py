import sys
from collections import Counter, defaultdict
from pathlib import Path

sys.path.insert(0, str(Path(__file__).parent))

import corpus_pipeline
from test_jaccard import plain_classes
from test_linededup import plain_removed_growing

SF = "/root/testdata/sf0.001"


def test_stages_one_by_one_against_plain_versions(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "line_dedup", "jaccard_join", "mixing", "packing"]
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        given = {r.doc_id: r.text or "" for r in docs.collect()} if name != "packing" else None
        out = stage(spark, docs, SF)
        if name != "packing":
            assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        out.write.parquet(f"{tmp_path}/{i}")
        out = spark.read.parquet(f"{tmp_path}/{i}")
        rows = out.collect()
        if name == "language_id":
            assert {r.doc_id for r in rows} == {d for d, t in given.items() if any(c.isalpha() for c in t)}
        if name == "line_dedup":
            gone = plain_removed_growing(given)
            assert {r.doc_id: r.text for r in rows} == {d: "\n".join(x for k, x in enumerate(t.split("\n")) if (d, k) not in gone) for d, t in given.items()}
            assert all(r.n_chars == len(r.text) for r in rows if r.text != given[r.doc_id])
        if name == "jaccard_join":
            want = plain_classes(given, 5, 80)
            assert {r.doc_id for r in rows} == {d for d, (_, c) in want.items() if c == d}
        if name == "mixing":
            assert set(given) >= {r.doc_id for r in rows} and max(Counter(r.doc_id for r in rows).values()) <= 2
            assert all(r.text == given[r.doc_id] or given[r.doc_id].split()[: len(r.text.split())] == r.text.split() for r in rows)
        if name == "packing":
            tokens = defaultdict(set)
            assert sum(r.length for r in rows) == sum(r.doc_tokens for r in rows if r.start == 0)
            for r in rows:
                tokens[r.sequence_id].add((r.offset, r.length))
            for pieces in tokens.values():
                at = 0
                for a, n in sorted(pieces):
                    assert a == at
                    at += n
                assert at <= 2048
            last = rows
        docs = out
    # run() gives what the stages gave: the same documents, as often, with the same tokens
    ran = corpus_pipeline.run(spark, SF)
    assert ran.columns == ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    whole = lambda rs: Counter((r.doc_id, r.doc_tokens) for r in rs if r.start == 0)
    assert whole(ran.collect()) == whole(last) and whole(last)


def test_exact_copies_leave_one_document(spark):
    text = "A first line of the text that is copied.\nAnd then a second one that is different."
    other = "Something else entirely stands in this document, and it stays."
    rows = [(1, text), (2, text), (3, text), (4, other)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    stages = dict(corpus_pipeline.STAGES)
    for name in ("line_dedup", "jaccard_join", "mixing"):
        docs = stages[name](spark, docs, SF)
    assert {r.doc_id for r in docs.collect()} == {1, 4}
