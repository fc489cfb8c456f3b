"""What remains of a text after its failing lines: given out, counted and judged as a text of its own."""

import re
from collections import Counter

import __spark_entry__ as entry
from stagefilter.llm.quality import LineRules, kept_lines, quality_rules

SF = "/root/testdata/sf0.01"
RULES = LineRules()
BLANK = "\x20\t\n\x0b\x0c\r"
GOOD = "This is a full and proper sentence that ends well and says enough."


def plain_fails(line):
    n = len([w for w in line.split(" ") if w])
    return (
        (line[-1] not in ".!?:;,…\"'”’»)]" and n < RULES.short_words)
        or sum(c in "!?" for c in line) > n * RULES.shouting
        or sum(c in "|»•>" for c in line) >= RULES.separators
        or (any(p in line.lower() for p in RULES.boilerplate) and n <= RULES.boilerplate_words)
    )


def plain_rest(text):
    """The remaining text, and the characters of all lines and of those that go."""
    lines = [(x, re.sub("[\t\x0b\x0c\r]", " ", x).strip(" ")) for x in (text or "").split("\n") if x.strip(BLANK)]
    return "\n".join(x for x, t in lines if not plain_fails(t)), sum(len(t) for _, t in lines), sum(len(t) for _, t in lines if plain_fails(t))


def plain_counts(text):
    ws = re.findall(r"[^\x20\x09-\x0D]+", text)
    grams = [tuple(ws[i : i + 5]) for i in range(len(ws) - 4)]
    count = Counter(grams)
    return len(ws), len({i + k for i, g in enumerate(grams) if count[g] > 1 for k in range(5)})


ODD = [
    GOOD + "\n\tthree\x0bodd  words\r\n" + GOOD.upper() + "\r\n", "a\tb\x0cc\n\x0b\r\nclick here", "really?! yes!! no!?\n" + GOOD, "a|b|c|d|e are bars\n" + GOOD + " a » b",
    "Lorem Ipsum is not kept.\nCLICK HERE " + "but this line is longer than thirty words, " * 5 + "so it stays.", "\n".join([GOOD, "x", GOOD, "y", GOOD]), "one two three four five one two three four five.", "a b c d\x85e f g h",
]


def test_rest_matches_plain_rules(spark, odd_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    odd = spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string")
    for df in (docs, odd_docs.select("doc_id", "text"), odd):
        texts = {r.doc_id: r.text for r in df.collect()}
        rows = quality_rules(df).collect()
        assert len(rows) == len(texts)
        for r in rows:
            rest, whole, lost = plain_rest(texts[r.doc_id])
            assert r.rest == rest and r.lost_share == (lost / whole if whole else 0.0), (r, rest)
            n, repeat = plain_counts(rest)
            assert (r.n_words, r.n_repeat_words) == plain_counts(texts[r.doc_id] or "")
            assert (r.n_rest_words, r.n_rest_repeat_words, r.rest_failed) == (n, repeat, n < 10 or 100 * repeat > 20 * n), r
        lines = {r.doc_id: r.x for r in df.select("doc_id", kept_lines(df.text, RULES).alias("x")).collect()}
        assert all("\n".join(lines[r.doc_id]) == r.rest for r in rows)


def test_rest_is_judged_as_a_text(spark):
    """Nine words and a menu pass as a whole, with half of the text lost at most; what remains is too short."""
    df = spark.createDataFrame([(1, "These nine remaining words alone are too few altogether.\nhome | about | us | help"), (2, f"{GOOD}\nmenu")], "doc_id long, text string")
    rows = {r.doc_id: r for r in quality_rules(df).collect()}
    assert rows[1].kept and not rows[1].base_failed and rows[1].rest_failed and rows[1].n_rest_words == 9
    assert rows[2].kept and not rows[2].rest_failed and rows[2].rest == GOOD


def test_query_has_the_columns_of_its_sql(spark):
    names = "doc_id n_words word_chars n_symbols n_dup_lines n_repeat_words base_failed kept lost_share".split()
    assert entry.queries()["op9_quality_rules"](spark, SF).columns == names
