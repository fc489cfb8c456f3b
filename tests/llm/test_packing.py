import random
import zlib
from collections import defaultdict

import numpy as np

from stagefilter.llm.packing import Packing, WordIds, combinations, nnls, pack, tokenizer_path

SF = "/root/testdata/sf0.01"


def test_word_ids_equal_the_tokenizer():
    from tokenizers import Tokenizer

    whole, fast = Tokenizer.from_file(tokenizer_path()), WordIds(tokenizer_path(), 500)
    rng = random.Random(1)
    plain = [chr(c) for c in [9, 10, 13, *range(32, 127), *range(0xA1, 0x17F)]]
    odd = [*plain, "\x1c", "\x85", " ", "Σ", "İ", "K", "́", "\U0001f600", "<|endoftext|>", "中", "٠"]
    for alphabet in (plain, odd):
        for _ in range(3000):
            t = "".join(rng.choice(alphabet) for _ in range(rng.randrange(40)))
            assert list(np.frombuffer(fast(t), "<u4")) == whole.encode(t, add_special_tokens=False).ids, repr(t)


def test_nnls_against_enumeration():
    rng = np.random.default_rng(0)
    for _ in range(20):
        a, b = rng.random((6, 4)), rng.random(6)
        best = np.inf
        for mask in range(16):
            at = [j for j in range(4) if mask >> j & 1]
            z = np.linalg.lstsq(a[:, at], b, rcond=None)[0] if at else np.zeros(0)
            if (z >= 0).all():
                best = min(best, np.linalg.norm(a[:, at] @ z - b))
        assert abs(np.linalg.norm(a @ nnls(a, b) - b) - best) < 1e-8
    assert (combinations(np.array([1, 2, 3, 4]), 4, 3).T @ [1, 2, 3, 4] <= 4).all()


def test_pack_round_trip(spark, odd_docs, no_docs):
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(tokenizer_path())
    docs = spark.read.parquet(f"{SF}/documents.parquet").repartition(3, "doc_id")
    for df in (docs, odd_docs):
        texts = {r.doc_id: r.text or "" for r in df.select("doc_id", "text").collect()}
        pieces, sequences = defaultdict(list), defaultdict(list)
        for r in pack(df, Packing(block=300)).collect():
            pieces[r.doc_id].append(r)
            sequences[r.sequence_id].append(r)
        assert set(pieces) == set(texts)
        for d, rows in pieces.items():
            ids = np.asarray([*whole.encode(texts[d], add_special_tokens=False).ids, 1], "<u4")
            at = 0
            for r in sorted(rows, key=lambda r: r.start):
                assert r.start == at and r.doc_tokens == len(ids) and r.length > 0
                assert r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
                at += r.length
            assert at == len(ids)
        padding = used = 0
        for rows in sequences.values():
            at = 0
            for r in sorted(rows, key=lambda r: r.offset):
                assert r.offset == at
                at += r.length
            assert at <= 2048
            used += at
            padding += 0 if at & (at - 1) == 0 else 2048 - at
        assert padding <= 0.01 * used
    assert pack(no_docs).count() == 0
