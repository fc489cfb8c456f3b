import hashlib
import random

import numpy as np

from stagefilter.llm.substring import Substrings, first_holders, minimizers, substring_dedup

SF = "/root/testdata/sf0.01"


def plain(texts, n=50):
    first, out = {}, {}
    data = {d: (t or "").encode() for d, t in texts.items()}
    for d in sorted(data):
        b = data[d]
        gone = bytearray(len(b))
        mine = {b[i : i + n] for i in range(len(b) - n + 1)}
        for i in range(len(b) - n + 1):
            if b[i : i + n] in first:
                gone[i : i + n] = b"\x01" * n
        for g in mine:
            first.setdefault(g, d)
        kept = bytes(c for c, x in zip(b, gone, strict=True) if not x)
        spans = sum(x and (i == 0 or not gone[i - 1]) for i, x in enumerate(gone))
        out[d] = (len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest())
    return out


def check(df, cfg=Substrings()):
    want = plain({r.doc_id: r.text for r in df.select("doc_id", "text").collect()}, cfg.length)
    got = {r.doc_id: tuple(r)[1:] for r in substring_dedup(df, cfg).collect()}
    assert got == want


def test_documents(spark, odd_docs, no_docs):
    check(spark.read.parquet(f"{SF}/documents.parquet"))
    check(odd_docs)
    assert substring_dedup(no_docs).count() == 0


def test_random_texts(spark):
    rng = random.Random(9)
    for alphabet, block in (("ab", 50), ("abcdé ", 7)):
        pool = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(5, 90))) for _ in range(20)]
        texts = [(i, "".join(rng.choice(pool) for _ in range(rng.randrange(6)))) for i in range(80)]
        df = spark.createDataFrame(texts, "doc_id long, text string").repartition(4)
        check(df, Substrings(length=20, gram=8, block=block, chunk=64))


def test_column_index_orders_all_suffixes():
    rng = random.Random(1)
    for _ in range(30):
        strings = list({bytes(rng.choice(b"abc") for _ in range(rng.randrange(1, 30))) for _ in range(12)})
        first = np.array([rng.randrange(100) for _ in strings])
        got = first_holders(strings, first, 5)
        for s, low in zip(strings, got, strict=True):
            want = [min(f for t, f in zip(strings, first, strict=True) if s[i : i + 5] in t) for i in range(len(s) - 4)]
            assert list(low) == want


def test_minimizers_do_not_depend_on_chunks():
    rng = random.Random(2)
    text = bytes(rng.choice(b"abcd") for _ in range(3000))
    whole, parts = minimizers(text, Substrings()), minimizers(text, Substrings(chunk=257))
    assert all((a == b).all() for a, b in zip(whole, parts, strict=True))


def test_crowded_sides_and_shared_passages(spark):
    """Long shared phrases between texts that differ around them, with blocks so small that their sides are taken apart."""
    rng = random.Random(3)
    phrase, other = "we agree to all terms of this license " * 2, "and nothing else was said about it at all"
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    texts = []
    for i in range(120):
        lead, tail = [word() for _ in range(8)], [word() for _ in range(8)]
        texts.append((i, " ".join([*lead[: rng.randrange(1, 8)], phrase[: rng.randrange(45, len(phrase))], *tail, other[rng.randrange(0, 12) :], *lead])))
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    for block in (1, 4, 40_000):
        check(df, Substrings(block=block, crowd=block, bundle=2_000, bucket=200))


def test_long_texts_repeated_ids_and_clashing_columns(spark):
    rng = random.Random(4)
    long = " ".join(f"{rng.randrange(10**6)}" for _ in range(60_000))
    rows = [(1, long, 0, 0, "x"), (2, long[7:90_000] + "é\U0001f600", 0, 0, "x"), (2, "short", 1, 1, "y"), (3, "é" * 400, 0, 0, "z"), (4, "é" * 99, 0, 0, "z"), (None, long[:500], 0, 0, "z")]
    df = spark.createDataFrame(rows, "doc_id long, text string, chunk long, doc long, blob string")
    got = [tuple(r) for r in substring_dedup(df, Substrings(chunk=10_000, bundle=50_000)).collect()]
    want = plain({1: long, 2: rows[1][1], 3: rows[3][1], 4: rows[4][1]})
    want = [(d, *x) for d, x in want.items()] + [(2, *plain({0: "short"})[0]), (None, *plain({0: long[:500]})[0])]
    assert sorted(got, key=str) == sorted(want, key=str)
