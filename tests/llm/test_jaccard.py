import random
import re

from stagefilter.llm.components import components
from stagefilter.llm.jaccard import JaccardJoin, jaccard_classes, one_per_class, prefix_length

SF = "/root/testdata/sf0.01"


def plain_classes(texts, n=3, percent=90):
    sets = {}
    for d, t in texts.items():
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or ""))
        ws = re.findall(r"[^\x20\x09-\x0D]+", low)
        sets[d] = {tuple(ws[i : i + n]) for i in range(max(1, len(ws) - n + 1))} if ws else set()
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and min(len(x), len(y)) * 100 >= percent * max(len(x), len(y)):
                both = len(x & y)
                if 100 * both >= percent * (len(x) + len(y) - both):
                    u, v = find(a), find(b)
                    root[max(u, v)] = min(u, v)
    return {d: (len(sets[d]), find(d)) for d in ids}


def test_classes_match_all_pairs(spark, odd_docs, no_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for df in (docs, odd_docs):
        want = plain_classes({r.doc_id: r.text for r in df.select("doc_id", "text").collect()})
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_classes(df).collect()}
        assert got == want
    assert jaccard_classes(no_docs).count() == 0
    kept = one_per_class(docs)
    assert kept.columns == docs.columns and kept.count() < docs.count()


def test_families_of_near_copies(spark):
    rng = random.Random(4)
    vocabulary = [f"w{i}" for i in range(300)]
    texts, k = {}, 0
    for _ in range(6):
        base = [rng.choice(vocabulary) for _ in range(rng.randrange(20, 120))]
        for _ in range(25):
            t = list(base)
            for _ in range(rng.randrange(4)):
                t[rng.randrange(len(t))] = rng.choice(vocabulary)
            texts[k] = " ".join(t)
            k += 1
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    for percent in (80, 90):
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_classes(df, JaccardJoin(percent=percent, local=2)).collect()}
        assert got == plain_classes(texts, 3, percent)


def test_a_thousand_near_copies_of_long_texts(spark):
    """Families over a small vocabulary, so that sets share n-grams across families."""
    rng = random.Random(9)
    vocabulary = [f"w{i}" for i in range(40)]
    texts = {}
    for k in range(5):
        base = [rng.choice(vocabulary) for _ in range(rng.randrange(60, 260))]
        for i in range(200):
            t = list(base)
            for _ in range(rng.randrange(3)):
                t[rng.randrange(len(t))] = rng.choice(vocabulary)
            texts[5 * i + k] = " ".join(t)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_classes(df).collect()}
    assert got == plain_classes(texts)


def test_clashing_columns_and_long_texts(spark):
    names = ["doc_id", "text", "d", "_first", "size", "gram", "a.b", "component_id"]
    long = " ".join(f"w{i * i % 9973}" for i in range(80_000))
    df = spark.createDataFrame([(4, long, *range(6)), (2, long + " end", *range(6)), (7, None, *range(6))], names)
    out = one_per_class(df)
    assert out.columns == names and {r[0]: r[2:] for r in out.collect()} == {2: tuple(range(6)), 7: tuple(range(6))}


def test_components(spark):
    rng = random.Random(2)
    links = [(i, i + 1) for i in range(0, 60)] + [(rng.randrange(100, 400), rng.randrange(100, 400)) for _ in range(200)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        u, v = find(a), find(b)
        root[max(u, v)] = min(u, v)
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: find(x) for x in root if find(x) != x}
    assert prefix_length(10, 90) == 2


def test_few_links_take_one_job_and_many_the_stars(spark):
    rng = random.Random(3)
    # a long chain in random order, stars both ways and a ring
    chain = rng.sample(range(1000, 3000), 400)
    links = list(zip(chain, chain[1:], strict=False)) + [(5, i) for i in range(10, 60)] + [(900, i) for i in range(100, 160)] + [(200 + i, 200 + (i + 1) % 9) for i in range(9)] + [(7, 7)]
    rng.shuffle(links)
    df, tracker = spark.createDataFrame(links, "a long, b long"), spark.sparkContext.statusTracker()

    def run(few: int) -> tuple[dict, int]:
        spark.sparkContext.setJobGroup(group := f"components-{few}", "")
        got = {r.node: r.component for r in components(df, few=few).collect()}
        jobs = len(tracker.getJobIdsForGroup(group))
        spark.sparkContext.setJobGroup("", "")
        return got, jobs

    few, many = run(len(links)), run(0)
    assert few[0] == many[0]
    assert few[1] <= 8 < many[1]
    assert components(df.filter("a = b")).count() == 0
