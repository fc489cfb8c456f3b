import zlib

from stagefilter.llm.langid import ByteConv, accepted, identify, windows_of

SF = "/root/testdata/sf0.01"


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    truth = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    rows = identify(docs).collect()
    assert len(rows) == len(truth)
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1
    out = [r for r in rows if r.held_out]
    assert sum(r.lang_pred == truth[r.doc_id] for r in out) >= 0.97 * len(out)
    kept = accepted(docs)
    assert kept.columns == docs.columns and kept.count() >= 0.995 * docs.count()


def test_labels_of_held_out_rows_are_never_read(spark):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    spoilt = docs.withColumn("lang", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, "xx").otherwise(F.col("lang")))
    assert sorted(map(tuple, identify(docs).collect())) == sorted(map(tuple, identify(spoilt).collect()))


def test_odd_rows(spark, odd_docs, no_docs):
    rows = {r.doc_id: r for r in identify(odd_docs).collect()}
    assert len(rows) == odd_docs.count()
    for i in (0, 1, 2):
        assert (rows[i].lang_pred, rows[i].score) == ("und", 0.0)
    assert identify(no_docs).count() == 0
    unlabelled = odd_docs.withColumn("lang", odd_docs.lang.substr(9, 1)).filter("false").unionByName(odd_docs.selectExpr("doc_id", "text", "cast(null as string) lang", "source", "n_chars", "note"))
    assert {r.lang_pred for r in identify(unlabelled).collect()} == {"und"}


def test_windows_cover_every_byte_group():
    cfg = ByteConv(length=16)
    for n in range(1, 80):
        text = bytes(range(1, n + 1))
        groups = {w[i : i + 4].tobytes() for w in windows_of(text, cfg) for i in range(13)}
        assert all(text[i : i + 4] in groups for i in range(n - 3))
