import math

import numpy as np

from stagefilter.llm.ann import CollisionIndex, nearest

SF = "/root/testdata/sf0.01"


def brute(ids, x, qids, q, k):
    out = {}
    n = np.sqrt((x * x).sum(1))
    for i, v in zip(qids, q, strict=True):
        s = (x * v).sum(1) / (n * math.sqrt((v * v).sum()))
        order = [j for j in np.lexsort((ids, -s)) if ids[j] != i][:k]
        out[i] = [(int(ids[j]), float(s[j])) for j in order]
    return out


def test_recall_and_scores(spark):
    e = spark.read.parquet(f"{SF}/embeddings.parquet")
    rows = e.collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], float)
    got = nearest(e, e.filter("vec_id % 50 = 0"), 5).collect()
    want = brute(ids, x, ids[ids % 50 == 0], x[ids % 50 == 0], 5)
    score = {(r.query_id, r.vec_id): r.score for r in got}
    assert len(got) == 5 * len(want)
    hit = sum((q, v) in score for q, best in want.items() for v, _ in best)
    assert hit >= 0.95 * 5 * len(want)
    for r in got:
        a, b = x[ids == r.query_id][0], x[ids == r.vec_id][0]
        assert abs(r.score - a @ b / np.linalg.norm(a) / np.linalg.norm(b)) < 1e-12
    for q in want:
        mine = sorted((r for r in got if r.query_id == q), key=lambda r: r.rank)
        assert [r.rank for r in mine] == [1, 2, 3, 4, 5]
        assert all((-a.score, a.vec_id) <= (-b.score, b.vec_id) for a, b in zip(mine, mine[1:], strict=False))


def test_odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (50, [2.0, 0.0]), (1, [1.0, 1.0]), (2, [1.0, 1.0]), (3, None), (4, [0.0, 0.0]), (5, [nan, 1.0]), (100, [inf, 1.0]), (6, [1.0, None]), (7, []), (8, [1.0, 0.0, 0.0]), (None, [1.0, 2.0])]
    df = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<float>, score string")
    got = {(r.query_id, r.rank): r.vec_id for r in nearest(df, df.filter("vec_id % 50 = 0"), 5).collect()}
    assert got == {(0, 1): 50, (0, 2): 1, (0, 3): 2, (50, 1): 0, (50, 2): 1, (50, 3): 2}
    assert nearest(df.limit(0), df.limit(0)).count() == 0


def test_threshold_follows_the_miss_rate():
    assert CollisionIndex(miss=0.01).threshold < CollisionIndex(miss=0.2).threshold < CollisionIndex().projections
