import numpy as np

from certsel.llm.ann import nearest


def test_close_copies_and_outliers_are_found(spark):
    """More near copies than are reranked, rows far from every centroid and rows of very different lengths: the answer is exact."""
    rng = np.random.default_rng(8)
    centre = rng.normal(size=(1, 16))
    v = np.concatenate([centre + 1e-4 * rng.normal(size=(1500, 16)), rng.normal(size=(6000, 16)), rng.normal(size=(300, 16)) * rng.lognormal(0, 3, size=(300, 1)), np.full((1, 16), 1e30)])
    v = v[rng.permutation(len(v))]
    df = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(v)], "vec_id long, embedding array<double>").repartition(4)
    got = {(r.query_id, r["rank"]): r.vec_id for r in nearest(df).collect()}
    for i in range(0, len(v), 100):
        with np.errstate(over="ignore"):
            d = np.sqrt(((v - v[i]) ** 2).sum(axis=1))
        assert [got[i, k] for k in range(1, 11)] == [int(j) for j in np.lexsort((np.arange(len(v)), d)) if j != i][:10]
