import numpy as np
import pytest

from bundlegraph.llm.neighbours import nearest


def brute(rows, ask, k):
    ok = [(i, np.array(v, float)) for i, v in rows if i is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v) and len(v) == 4]
    out = set()
    for q, qv in ok:
        if ask(q):
            near = sorted((-float(sum(a * b for a, b in zip(qv, v))), i) for i, v in ok if i != q)[:k]
            out |= {(q, n + 1, i) for n, (_, i) in enumerate(near)}
    return out


@pytest.mark.parametrize("recall", [0.999999, 0.3])
def test_small_tables_come_back_exact(spark, recall):
    rng = np.random.default_rng(2)
    rows = [(i, rng.integers(-3, 4, 4).astype(float).tolist()) for i in range(120)]
    rows += [(200 + i, [1.0, 2.0, 0.0, 1.0]) for i in range(40)]  # one vector many times
    rows += [(300, None), (301, [0.0] * 4), (302, [1.0, None, 0.0, 0.0]), (303, [float("nan")] * 4), (304, [1.0, float("inf"), 0.0, 0.0]), (None, [1.0] * 4), (305, [1.0, 2.0]), (306, [-90.0, 1.0, 0.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("*", "1 AS score", "2 AS id")
    got = nearest(df, "vec_id", "embedding", lambda i: i % 20 == 0, k=20, recall=recall).collect()
    want = brute(rows, lambda i: i % 20 == 0, 20)
    have = {(r.query_id, r["rank"], r.vec_id) for r in got}
    assert len(got) == len(have) == len(want)
    scores = dict((i, np.array(v)) for i, v in rows if i is not None and v and None not in v and len(v) == 4)
    for r in got:
        assert r.score == float(sum(a * b for a, b in zip(scores[r.query_id], scores[r.vec_id])))
    assert len(have & want) / len(want) > (0.99 if recall > 0.9 else 0.5)


def test_fewer_rows_than_k_and_none(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5]), (2, [0.0, -1.0])], "vec_id long, embedding array<float>")
    got = nearest(df, "vec_id", "embedding", lambda i: i == 0, k=20).orderBy("rank").collect()
    assert [(r.vec_id, r.score) for r in got] == [(1, 0.5), (2, 0.0)]
    assert nearest(df.limit(0), "vec_id", "embedding", lambda i: i == 0).count() == 0


def test_recall_at_sixty_four_dimensions(spark):
    rng = np.random.default_rng(4)
    centres = rng.normal(size=(40, 64))
    x = np.concatenate([centres[rng.integers(0, 40, 2500)] + 0.7 * rng.normal(size=(2500, 64)), rng.normal(size=(1500, 64))])
    x[100:400] = x[100]  # one vector that many rows have
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got: dict[int, set[int]] = {}
    for r in nearest(df, "vec_id", "embedding", lambda i: i % 20 == 0, k=20).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = 0
    for q in range(0, 4000, 20):
        score = x @ x[q]
        score[q] = -np.inf
        best = sorted(range(4000), key=lambda i: (-score[i], i))[:20]
        hits += len(got[q] & set(best))
    assert hits / (200 * 20) >= 0.9
