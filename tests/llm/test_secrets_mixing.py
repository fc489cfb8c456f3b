import hashlib
import random
import re
from collections import defaultdict

import pytest

from stagefilter.llm.mixing import Mix, mix_sources, mixed_documents
from stagefilter.llm.secrets import find_secrets

SF = "/root/testdata/sf0.01"
ASSIGN = re.compile(r"""((?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy]))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")


def plain_spans(text):
    out = [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    out += [("access", m.start(), m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    out += [("hex", m.start(), m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 32]
    order = ("assign", "access", "hex")
    return sorted(out, key=lambda x: (x[1], order.index(x[0])))


def test_secrets_match_plain_patterns(spark, odd_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for df in (docs, odd_docs):
        texts = {r.doc_id: r.text or "" for r in df.select("doc_id", "text").collect()}
        rows = find_secrets(df).collect()
        assert len(rows) == len(texts)
        for r in rows:
            want = plain_spans(texts[r.doc_id])
            said = [f"{k}:{a}:{b}" for k, a, b in want]
            assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(k == x for k, _, _ in want) for x in ("assign", "access", "hex"))
            assert r.base_sha256 == hashlib.sha256(",".join(said).encode()).hexdigest(), (r, said)
            assert [s for s in r.spans.split(",") if s and not s.startswith("random")] == said


def test_battery_flags_random_tokens_only(spark, no_docs):
    rng = random.Random(3)
    alphabet = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    hits = ["see " + "".join(rng.choice(alphabet) for _ in range(40)) + " end" for _ in range(40)]
    misses = [f"see aaaa1111aaaa1111aaaa1111aaaa{i % 10} end" for i in range(40)] + ["plain words only, averyveryveryverylongwordindeed"] * 5
    df = spark.createDataFrame([(i, t) for i, t in enumerate(hits + misses)], "doc_id long, text string")
    spans = {r.doc_id: r.spans for r in find_secrets(df).collect()}
    assert sum("random" in spans[i] for i in range(40)) >= 35
    assert not any("random" in spans[i] for i in range(40, 85))
    assert find_secrets(no_docs).count() == 0


def plain_targets(sizes, cfg):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: cfg.weights[i % len(cfg.weights)] for i, s in enumerate(names)}
    total, capped = cfg.total * sum(sizes.values()), set()
    while True:
        free = [s for s in names if s not in capped]
        rest = total - sum(cfg.epochs * sizes[s] for s in capped)
        share = {s: rest * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > cfg.epochs * sizes[s]}
        if not over:
            return {s: share.get(s, cfg.epochs * sizes[s]) for s in names}
        capped |= over


def test_mixing(spark, odd_docs, no_docs):
    cfg = Mix()
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for df in (docs, odd_docs):
        given = {r.doc_id: r for r in df.collect()}
        rows = mix_sources(df).collect()
        assert sorted(r.doc_id for r in rows) == sorted(given)
        sizes, taken = defaultdict(int), defaultdict(int)
        for r in rows:
            assert r.size == len(re.findall(r"[^\x20\x09-\x0D]+", given[r.doc_id].text or ""))
            assert 0 <= r.taken <= 2 * r.size
            sizes[given[r.doc_id].source] += r.size
            taken[given[r.doc_id].source] += r.taken
        want = plain_targets(sizes, cfg)
        for r in rows:
            s = given[r.doc_id].source
            assert r.source_size == sizes[s] and r.target == pytest.approx(want[s], rel=1e-9)
        n = defaultdict(int)
        for r in rows:
            n[given[r.doc_id].source] += 1
        assert all(abs(taken[s] - want[s]) <= max(3, 2 * n[s] ** 0.5) for s in sizes)
        assert sorted(map(tuple, rows)) == sorted(map(tuple, mix_sources(df).collect()))
        mixed = mixed_documents(df)
        assert mixed.columns == df.columns
        words = mixed.select("text").collect()
        assert sum(len(re.findall(r"[^\x20\x09-\x0D]+", r.text or "")) for r in words) == sum(taken.values())
    assert mix_sources(no_docs).count() == 0 and mixed_documents(no_docs).count() == 0


def test_a_fraction_keeps_the_white_space(spark):
    text = "  first line\there\n\n second  line,\u00e9 \U0001f600 end\nthird line  \n"
    docs = spark.createDataFrame([(i, text, "s", len(text)) for i in range(5)], "doc_id long, text string, source string, n_chars long")
    parts = set()
    for total in (0.3, 0.45, 0.7, 1.25):
        for r in mixed_documents(docs, Mix(total=total, buckets=1)).collect():
            assert text.startswith(r.text) and r.n_chars == len(r.text)
            assert r.text == text or not r.text[-1].isspace()
            parts.add(r.text)
    assert any("\n\n second  line" in x for x in parts - {text})
