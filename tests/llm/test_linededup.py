import random
import re

from pyspark.sql import functions as F

from stagefilter.llm.linededup import GROWING, LineJoin, line_classes, line_components, line_keys, line_links, places, signature, signatures_close, within_edits, without_repeated_lines

SF = "/root/testdata/sf0.01"


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def edited(rng, t, n, alphabet):
    t = list(t)
    for _ in range(n):
        k, at = rng.randrange(3), rng.randrange(len(t) + 1)
        if k == 0:
            t.insert(at, rng.choice(alphabet))
        elif t and at < len(t):
            if k == 1:
                del t[at]
            else:
                t[at] = rng.choice(alphabet)
    return "".join(t)


def test_banded_distance(spark):
    rng = random.Random(6)
    pairs = []
    for _ in range(1500):
        a = "".join(rng.choice("abé") for _ in range(rng.randrange(14)))
        pairs.append((a, edited(rng, a, rng.randrange(5), "abé")))
    df = spark.createDataFrame(pairs, "a string, b string")
    for k in (1, 2, 3):
        rows = df.select("a", "b", within_edits(F.col("a"), F.col("b"), k).alias("ok"), signatures_close(signature(F.col("a")), signature(F.col("b")), k).alias("near")).collect()
        for r in rows:
            want = edit_distance(r.a, r.b) <= k
            assert r.ok == want, (k, r)
            assert r.near or not want


def test_join_finds_every_link(spark):
    rng = random.Random(8)
    lines = set()
    for _ in range(25):
        base = "".join(rng.choice("etano xy") for _ in range(rng.randrange(20, 40)))
        lines |= {edited(rng, base, rng.randrange(4), "etano xy") for _ in range(8)}
    lines = sorted(x for x in lines if len(x) >= 20)
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    for k in (1, 2):
        of = {r.id: r.line for r in df.select(F.xxhash64("line").alias("id"), "line").collect()}
        got = {frozenset((of[r.a], of[r.b])) for r in line_links(df, LineJoin(edits=k)).collect()}
        want = {frozenset((a, b)) for i, a in enumerate(lines) for b in lines[i + 1 :] if abs(len(a) - len(b)) <= k and edit_distance(a, b) <= k}
        assert got == want and want


def plain_removed(texts, cfg=LineJoin()):
    """(doc, line number) of removed lines by comparing all distinct lines."""
    rows = [(d, i, x) for d, t in sorted(texts.items()) for i, x in enumerate((t or "").split("\n")) if re.search(r"[^\x20\x09-\x0D]", x)]
    distinct = sorted({x for _, _, x in rows})
    root = {x: x for x in distinct}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    by_length = {}
    for x in distinct:
        by_length.setdefault(len(x), []).append(x)
    for x in distinct:
        for n in range(len(x), len(x) + cfg.edits + 1):
            for y in by_length.get(n, ()) if len(x) >= cfg.least else ():
                # a quick bound: common head and tail must cover all but the edits
                h = next((i for i, (p, q) in enumerate(zip(x, y, strict=False)) if p != q), len(x))
                t = next((i for i, (p, q) in enumerate(zip(x[::-1], y[::-1], strict=False)) if p != q), len(x))
                if h + t >= len(y) - cfg.edits and x != y:
                    root[find(x)] = find(y)
    seen, out = set(), set()
    for d, i, x in rows:
        c = find(x)
        if c in seen:
            out.add((d, i))
        seen.add(c)
    return out


def test_removed_lines(spark, odd_docs, no_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for df in (docs, odd_docs):
        texts = {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}
        want = plain_removed(texts)
        rows = line_classes(df).collect()
        assert {(r.doc_id, r.line_no) for r in rows if r.removed} == want
        assert len(rows) == sum(bool(re.search(r"[^\x20\x09-\x0D]", x)) for t in texts.values() for x in (t or "").split("\n"))
        out = without_repeated_lines(df)
        assert out.columns == df.columns
        got = {r.doc_id: r.text for r in out.collect()}
        assert set(got) == set(texts)
        for d, t in texts.items():
            kept = "\n".join(x for i, x in enumerate((t or "").split("\n")) if (d, i) not in want)
            assert (got[d] or "") == kept
    assert line_classes(no_docs).count() == 0 and without_repeated_lines(no_docs).count() == 0


def symbol_edits(a, b, most):
    """Edit distance of two lists, or most + 1 if it is greater."""
    if abs(len(a) - len(b)) > most:
        return most + 1
    while a and b and a[0] == b[0]:
        a, b = a[1:], b[1:]
    while a and b and a[-1] == b[-1]:
        a, b = a[:-1], b[:-1]
    return min(most + 1, edit_distance(a, b))


def linked(a, b, cfg):
    """By the definition: characters if both are short, words if both are long."""
    wa, wb = a.split(" "), b.split(" ")
    grow = lambda n, per: min(cfg.most, max(cfg.edits, n // per))
    by_chars = max(len(wa), len(wb)) < cfg.long + cfg.most and symbol_edits(list(a), list(b), cfg.most) <= grow(min(len(a), len(b)), cfg.per_chars)
    return by_chars or min(len(wa), len(wb)) >= cfg.long and symbol_edits(wa, wb, cfg.most) <= grow(min(len(wa), len(wb)), cfg.per_words)


def classes(lines, pairs):
    root = {x: x for x in lines}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        root[find(a)] = find(b)
    out = {}
    for x in lines:
        out.setdefault(find(x), set()).add(x)
    return {frozenset(c) for c in out.values() if len(c) > 1}


def check_links(spark, lines):
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    of = {r.id: r.line for r in df.select(F.xxhash64("line").alias("id"), "line").collect()}
    want = {frozenset((a, b)) for i, a in enumerate(lines) for b in lines[i + 1 :] if linked(a, b, GROWING)}
    got = [frozenset((of[r.a], of[r.b])) for r in line_links(df, GROWING).collect()]
    assert set(got) == want and len(got) == len(want)
    found = {}
    for r in line_components(df, GROWING).collect():
        found.setdefault(r.component, set()).add(of[r.node])
    assert {frozenset(c) for c in found.values()} == classes(lines, want)
    return want


def test_threshold_grows_with_the_line(spark):
    rng = random.Random(11)
    words = ["".join(rng.choice("etanoüxy") for _ in range(rng.randrange(2, 8))) for _ in range(60)]
    lines = {"ten chars.", "ten chart.", "x" * 300, "x" * 299 + "y"}
    for _ in range(25):
        base = " ".join(rng.choice(words) for _ in range(rng.randrange(4, 90)))
        lines |= {edited(rng, base, rng.randrange(6), "etano xü") for _ in range(6)}
        # a word replaced, one removed, one added in a long line
        w = base.split(" ")
        lines |= {base.replace(w[1], "otherwise", 1), " ".join(w[:2] + w[3:]), " ".join([*w[:-1], "addition", w[-1]])}
    want = check_links(spark, sorted(x for x in lines if len(x) >= GROWING.least))
    assert any(edit_distance(*p) > 4 for p in want)


def test_lines_around_the_change_of_symbols(spark):
    """Lines of about `long` words, alike but for words, spaces and characters."""
    rng = random.Random(5)
    lines = set()
    for _ in range(12):
        w = ["".join(rng.choice("etano") for _ in range(rng.randrange(1, 7))) for _ in range(rng.randrange(17, 26))]
        base = " ".join(w)
        lines |= {base, base.replace(" ", "", 1), base.replace(w[5], w[5] + "x y", 1), " ".join(w[1:]), edited(rng, base, 2, "et ")}
    assert check_links(spark, sorted(lines))


def test_registered_query_removes_a_long_line_with_one_word_replaced(spark, tmp_path):
    from stagefilter.llm.queries import op10_line_dedup

    line = "The committee met in the old town hall on Monday evening to talk about the new bridge over the river and its likely cost."
    spark.createDataFrame([(1, line), (2, line.replace("Monday", "Friday"))], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert {r.doc_id: r.removed for r in op10_line_dedup(spark, str(tmp_path)).collect()} == {1: False, 2: True}


def growing_pairs(lines):
    """All linked pairs of distinct lines by the definition; pairs whose symbols differ too much are passed over."""
    most, known = GROWING.most, []
    for x in lines:
        w = x.split(" ")
        known.append((x, len(x), set(x), len(w), set(w)))
    out = set()
    for i, (a, n, chars, m, words) in enumerate(known):
        for b, k, other, o, more in known[i + 1 :]:
            near = max(m, o) < GROWING.long + most and abs(n - k) <= most and len(chars ^ other) <= 2 * most
            near = near or min(m, o) >= GROWING.long and abs(m - o) <= most and len(words ^ more) <= 2 * most
            if near and linked(a, b, GROWING):
                out.add(frozenset((a, b)))
    return out


def plain_removed_growing(texts):
    """(doc, line number) of removed lines by the definition of GROWING."""
    rows = [(d, i, x) for d, t in sorted(texts.items()) for i, x in enumerate((t or "").split("\n")) if re.search(r"[^\x20\x09-\x0D]", x)]
    distinct = sorted({x for _, _, x in rows})
    of = {x: c for c in classes(distinct, growing_pairs([x for x in distinct if len(x) >= GROWING.least])) for x in c}
    seen, out = set(), set()
    for d, i, x in rows:
        c = of.get(x, x)
        if c in seen:
            out.add((d, i))
        seen.add(c)
    return out


def test_growing_threshold_on_documents(spark):
    """All pairs of distinct lines by the definition."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    lines = sorted({x for r in docs.select("text").collect() for x in (r.text or "").split("\n") if GROWING.least <= len(x) <= 1500}, key=len)
    want = growing_pairs(lines)
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    of = {r.id: r.line for r in df.select(F.xxhash64("line").alias("id"), "line").collect()}
    got = {frozenset((of[r.a], of[r.b])) for r in line_links(df, GROWING).collect()}
    assert got == want and any(edit_distance(*p) > 1 for p in want)


def test_a_family_of_near_copies_is_one_class(spark):
    """Links between all members are implied by few; the rows compared stay in proportion to the family."""
    base = " ".join(f"word{i}" for i in range(45))
    family = [f"{base} ending{i}" for i in range(600)]
    docs = spark.createDataFrame([(i, x) for i, x in enumerate(family)], "doc_id long, text string")
    rows = line_classes(docs, GROWING).collect()
    assert len(rows) == 600 and {r.class_doc for r in rows} == {0} and sum(not r.removed for r in rows) == 1


def test_clashing_columns_and_long_texts(spark):
    names = ["doc_id", "text", "version", "line_no", "gone", "id", "key", "d", "class_id", "kept", "_doc", "a.b"]
    long = "\n".join([*("a long text of many lines " * 20 for _ in range(3)), " ".join(f"w{i}" for i in range(60_000)), "x" * 200_000])
    rows = [(1, long, *range(10)), (2, long + "\nanother ending", *range(10)), (3, None, *range(10))]
    df = spark.createDataFrame(rows, names)
    out = without_repeated_lines(df, GROWING)
    assert out.columns == names
    got = {r[0]: r for r in out.collect()}
    assert got[2][1] == "another ending" and got[2][2:] == tuple(range(10)) and got[3][1] is None
    assert got[1][1].count("\n") == 2


def test_places_are_those_of_the_line_s_own_thresholds(spark):
    """Lines get the places of thresholds they can have, not the places of all; no key is lost by that."""
    df = spark.createDataFrame([("x" * n,) for n in range(8, 120)] + [(" ".join(["w"] * n),) for n in range(20, 90)], "line string")
    want = 0
    for r in df.collect():
        n_words = len(r.line.split(" "))
        for by_words in [False] * (n_words < 20) + [False, True] * (20 <= n_words < 23) + [True] * (n_words >= 23):
            n = n_words if by_words else len(r.line)
            threshold = lambda l: min(3, max(1, l // (20 if by_words else 25)))  # noqa: B023, E731, E741
            for k, s, i, m, _ in places(GROWING):
                length = n - s
                if length <= 0 or threshold(length) != k:
                    continue
                sizes = [length // (k + 1) + (j > k + 1 - length % (k + 1)) for j in range(1, k + 2)]
                start = 1 + sum(sizes[: i - 1]) + m
                want += start >= 1 and start + sizes[i - 1] - 1 <= n
    keys = line_keys(df, GROWING)
    assert keys.count() == want
    plan = keys._jdf.queryExecution().optimizedPlan().toString()
    assert "CASE WHEN" in plan.split("Generate")[1]


def test_keys_are_narrow_and_tell_the_symbols(spark):
    """Three columns are shuffled; a line compared both ways has keys of both kinds, a short one those of characters."""
    lines = ["a short line of text", " ".join(f"w{i}" for i in range(21)), " ".join(f"w{i}" for i in range(40))]
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    keys = line_keys(df, GROWING)
    assert keys.columns == ["id", "key", "filed"]
    of = {r.id: r.line for r in df.select(F.xxhash64("line").alias("id"), "line").collect()}
    kinds = {x: {r.key & 1 for r in keys.collect() if of[r.id] == x} for x in lines}
    assert [kinds[x] for x in lines] == [{0}, {0, 1}, {1}]


def test_keys_of_words_are_made_by_plain_functions(spark):
    """No lambda, which is interpreted word by word; symbols are what single spaces separate, and runs of equal words have equal keys."""
    words = [f"wörd{i}" for i in range(41)]
    lines = [" ".join(words), " ".join([*words[:40], "other"]), " ".join(f"x{i}" for i in range(41)), " " + "  ".join(f"y{i}" for i in range(20)) + " "]
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    keys = line_keys(df, GROWING)
    assert "lambda" not in keys._jdf.queryExecution().optimizedPlan().toString()
    of = {r.id: r.line for r in df.select(F.xxhash64("line").alias("id"), "line").collect()}
    held = {x: {r.key for r in keys.collect() if of[r.id] == x and r.filed} for x in lines}
    # thresholds are 2 (40 or 41 words, the last with empty ones): three segments each
    assert [len(held[x]) for x in lines] == [3, 3, 3, 3]
    # one word at the end is another: two of the three segments are shared, and none with different words
    assert len(held[lines[0]] & held[lines[1]]) == 2 and not held[lines[0]] & held[lines[2]]
