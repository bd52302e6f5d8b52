import math

import numpy as np

from certsel.llm.ann import IndexSettings, nearest
from certsel.llm.topk import Bucket, top_products


def rows_of(spark, sf):
    return spark.read.parquet(f"{sf}/embeddings.parquet")


def test_top_products_match_brute_force(spark, sf):
    df = rows_of(spark, sf)
    data = df.orderBy("vec_id").select("vec_id", "embedding").collect()
    ids, v = np.array([r.vec_id for r in data]), np.floor(np.array([r.embedding for r in data]) * 256)
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in top_products(df).collect()}
    want = {}
    for i in np.flatnonzero(ids % 50 == 0):
        s = v @ v[i]
        best = [j for j in np.lexsort((ids, -s)) if j != i][:5]
        want |= {(int(ids[i]), k + 1): (int(ids[j]), int(s[j])) for k, j in enumerate(best)}
    assert got == want


def test_pruning_by_length_and_coordinate_is_exact():
    rng = np.random.default_rng(2)
    v = np.floor(rng.normal(size=(400, 6)) * rng.lognormal(size=(400, 1)) * 100)
    b = Bucket(np.arange(400), v)
    for q in np.floor(rng.normal(size=(60, 6)) * 50):
        s = b.v @ q
        for bar in (*np.quantile(s, [0.2, 0.9, 0.99, 1.0]), 0.0, -5.0, s.max() + 1):
            got = b.candidates(q, float(np.sqrt(q @ q)), float(bar))
            picked = set() if got is None else set(np.arange(400)[got])
            assert picked >= set(np.flatnonzero(s >= bar))
    one_way = np.zeros(6)
    one_way[2] = 50.0
    assert len(b.candidates(one_way, 50.0, 0.9 * 50 * b.length[0])) < 400


def edge_frame(spark):
    rows = [(0, [1.0, 2.0]), (100, [1.0, 2.0]), (7, [1.0, 2.0]), (8, [1.0, 2.0]), (8, [1.0, 2.0]), (9, [0.0, 0.0]), (10, None), (11, [1.0, None]), (12, [float("nan"), 1.0]),
            (13, [math.inf, 1.0]), (None, [1.0, 1.0]), (14, []), (15, [1.0, 2.0, 3.0]), (200, [5.0, 5.0, 5.0])]
    return spark.createDataFrame([(i, v, 1.0) for i, v in rows], "vec_id long, embedding array<double>, score double")


def test_edge_vectors(spark):
    df = edge_frame(spark)
    got = [(r.query_id, r["rank"], r.vec_id) for r in top_products(df, every=100).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 7), (0, 2, 8), (0, 3, 8), (0, 4, 100), (0, 5, 9), (100, 1, 0), (100, 2, 7), (100, 3, 8), (100, 4, 8), (100, 5, 9), (200, 1, 15)]
    got = [(r.query_id, r["rank"], r.vec_id) for r in nearest(df).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 7), (0, 2, 8), (0, 3, 8), (0, 4, 100), (100, 1, 0), (100, 2, 7), (100, 3, 8), (100, 4, 8), (200, 1, 15)]
    assert top_products(df.limit(0)).count() == 0 and nearest(df.limit(0)).count() == 0


def test_nearest_recall_and_scores(spark):
    df = rows_of(spark, "/root/testdata/sf0.1")
    data = df.orderBy("vec_id").select("vec_id", "embedding").collect()
    ids, v = np.array([r.vec_id for r in data]), np.array([r.embedding for r in data], dtype=np.float64)
    got = {}
    for r in nearest(df).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = (r.vec_id, r.score)
    hit = total = 0
    at = {int(i): k for k, i in enumerate(ids)}
    for i in np.flatnonzero(ids % 100 == 0):
        d = np.sqrt(((v - v[i]) ** 2).sum(axis=1))
        want = [int(ids[j]) for j in np.lexsort((ids, d)) if j != i][:10]
        mine = got[int(ids[i])]
        assert sorted(mine) == list(range(1, 11))
        assert all(abs(mine[k][1] - d[at[mine[k][0]]]) < 1e-12 for k in mine) and [mine[k][1] for k in sorted(mine)] == sorted(x[1] for x in mine.values())
        hit += len(set(want) & {x[0] for x in mine.values()})
        total += 10
    assert hit / total >= 0.9


def test_probing_all_lists_and_reranking_all_rows_is_exact(spark, sf):
    df = rows_of(spark, sf)
    data = df.orderBy("vec_id").select("vec_id", "embedding").collect()
    ids, v = np.array([r.vec_id for r in data]), np.array([r.embedding for r in data], dtype=np.float64)
    got = {(r.query_id, r["rank"]): r.vec_id for r in nearest(df, s=IndexSettings(lists=8, probes=8, codes=16, rerank=10_000)).collect()}
    for i in np.flatnonzero(ids % 100 == 0):
        d = np.sqrt(((v - v[i]) ** 2).sum(axis=1))
        assert [got[(int(ids[i]), k)] for k in range(1, 11)] == [int(ids[j]) for j in np.lexsort((ids, d)) if j != i][:10]
