import hashlib
import re
from collections import Counter

from stagefilter.llm.pii import BASE_KINDS, luhn, mod97, personal_data, spans
from stagefilter.llm.quality import LineRules, kept_lines, quality_rules

SF = "/root/testdata/sf0.01"

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def plain_spans(text):
    out = []
    for kind, pattern in PLAIN.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {
                "email": lambda: True,
                "ip": lambda: all(int(p) <= 255 for p in m[0].split(".")),  # noqa: B023
                "card": lambda: 13 <= len(digits) <= 19 and luhn(digits),  # noqa: B023
                "phone": lambda: 9 <= len(digits) <= 15,  # noqa: B023
            }[kind]()
            if ok:
                out.append((kind, m.start(), m.end()))
    return out


def plain_quality(text):
    text = text or ""
    ws = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = [tuple(ws[i : i + 5]) for i in range(len(ws) - 4)]
    count = Counter(grams)
    marked = {i + k for i, g in enumerate(grams) if count[g] > 1 for k in range(5)}
    return len(ws), sum(map(len, ws)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(marked)


def check_pii(rows, texts):
    for r in rows:
        want = plain_spans(texts[r.doc_id] or "")
        said = ",".join(f"{k}:{a}:{b}" for k, a, b in want)
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == b for k, _, _ in want) for b in BASE_KINDS]
        assert r.base_sha256 == hashlib.sha256(said.encode()).hexdigest()
        assert r.spans.startswith(said)


def test_pii_matches_plain_patterns(spark, odd_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for df in (docs, odd_docs):
        texts = {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}
        rows = personal_data(df).collect()
        assert len(rows) == len(texts)
        check_pii(rows, texts)


def test_pii_random_strings():
    import random

    rng = random.Random(5)
    for _ in range(4000):
        t = "".join(rng.choice("0123456789..-- @a+(b") for _ in range(rng.randrange(60)))
        assert [s for s in spans(t) if s[0] in BASE_KINDS] == plain_spans(t), t


def test_pii_added_kinds():
    assert mod97("DE89 3704 0044 0532 0130 00")
    assert any(k == "iban" for k, _, _ in spans("bank DE89370400440532013000 ok"))
    assert not any(k == "iban" for k, _, _ in spans("bank DE89370400440532013001 ok"))


def test_account_numbers_in_prose():
    de, gb = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32"
    for number in (de, gb, "DE89 3704 0044 0532 0130 00"):
        for after in ("", ".", " Please pay", " The", " 7 days", " 12", " BIC COBADEFF", " OR CASH", " A", " AND THEN SOME MORE WORDS IN UPPER CASE"):
            t = f"IBAN {number}{after}"
            assert [t[a:b] for k, a, b in spans(t) if k == "iban"] == [number], t
    t = f"REF AB12 {de} and {gb} Thanks"
    assert [t[a:b] for k, a, b in spans(t) if k == "iban"] == [de, gb]
    # unknown country, no end of a word inside, and a wrong digit
    assert [s for s in spans(f"{de}x {de[:-1]}1 Please") if s[0] == "iban"] == []
    assert any(k == "iban" for k, _, _ in spans("MT84MALT011000012345MTLCAST001S Please"))


def test_quality_matches_plain_counts(spark, odd_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for df in (docs, odd_docs):
        texts = {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}
        rows = quality_rules(df).collect()
        assert len(rows) == len(texts)
        for r in rows:
            want = plain_quality(texts[r.doc_id])
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, (r, want)
            assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0])
            assert not (r.base_failed and r.kept)


def test_quality_line_rules(spark, no_docs):
    assert quality_rules(no_docs).count() == 0
    good = "This is a full and proper sentence that ends well and says enough.\n"
    df = spark.createDataFrame([(1, good + "home | about | us | help"), (2, "A | b | c | d | e | f | g | h | i | j | k"), (3, good)], "doc_id long, text string")
    kept = {r.doc_id: r.kept for r in quality_rules(df).collect()}
    assert kept == {1: True, 2: False, 3: True}
    # doubled spaces make no words: three words without an end
    spaced = spark.createDataFrame([(1, good + "three   spaced    words"), (2, good + "four  words   stand here")], "doc_id long, text string")
    assert {r.doc_id: r.lost_share > 0 for r in quality_rules(spaced).collect()} == {1: True, 2: False}
    lines = df.select(kept_lines(df.text, LineRules()).alias("x")).first().x
    assert lines == [good.strip()]
