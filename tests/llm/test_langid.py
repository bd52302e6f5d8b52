import zlib

import numpy as np

from certsel.llm import langid


def test_gradients_match_differences():
    rng = np.random.default_rng(0)
    net = langid.ByteGru(["a", "b", "c"], 3, 1)
    net.p = {k: v.astype(np.float64) * 0.5 for k, v in net.p.items()}
    x, y = rng.integers(97, 105, (7, 4)), np.array([0, 1, 2, 1])
    x[5:, 2] = 256
    _, g = net.gradients(x, y)
    for k, at in (("Ef", (99, 0)), ("Ef", (100, 4)), ("Eb", (101, 7)), ("Uf", (1, 2)), ("Ub", (0, 5)), ("Vf", (2, 1)), ("Vb", (1, 1)), ("W", (4, 1)), ("c", (2,))):
        old = net.p[k][at]
        net.p[k][at] = old + 1e-2
        up = net.gradients(x, y)[0]
        net.p[k][at] = old - 1e-2
        down = net.gradients(x, y)[0]
        net.p[k][at] = old
        assert abs((up - down) / 2e-2 - g[k][at]) < 2e-3 + 0.05 * abs(g[k][at]), (k, at)


def test_held_out_accuracy_and_edges(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.train(docs)
    rows = langid.predict(docs, model).collect()
    want = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    assert len(rows) == len(want)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r.score <= 1 for r in rows)
    held = [r.lang_pred == want[r.doc_id] for r in rows if r.held_out]
    assert sum(held) / len(held) > 0.97
    odd = spark.createDataFrame([(1, None, None), (2, "", "en"), (3, "123 !!", "en"), (None, "the thing and of the", None), (5, "the of and " * 20000, "x")], "doc_id long, text string, lang_pred string")
    got = {r.doc_id: r for r in langid.predict(odd, model).collect()}
    assert [got[k].lang_pred for k in (1, 2, 3)] == ["und"] * 3 and not got[None].held_out and got[5].score > 0.5
    assert {r.lang_pred for r in langid.predict(odd, None).collect()} == {"und"}
    assert langid.train(docs.limit(0)) is None and langid.predict(docs.limit(0), model).count() == 0
    kept = langid.keep_determined(odd, model)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} == {None, 5}
