import duckdb
import pytest

from certsel.llm import mixing


def fill(sizes, weights, budget, cap):
    """Clamp what is above its cap and share the rest anew, until nothing is."""
    total, done = budget * sum(sizes.values()), {}
    while True:
        open_ = [s for s in sizes if s not in done]
        left = total - sum(done.values())
        share = {s: left * weights[s] / sum(weights[x] for x in open_) for s in open_} if open_ else {}
        above = [s for s in open_ if share[s] > cap * sizes[s]]
        if not above:
            return done | share
        done |= {s: cap * sizes[s] for s in above}


def test_targets_by_repeated_clamping(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = mixing.allocate(docs).collect()
    sizes = {r.source: r.source_size for r in rows}
    weights = {s: (3, 1, 2)[k % 3] for k, s in enumerate(sorted(sizes, key=lambda s: s.encode()))}
    want = fill(sizes, weights, 1.5, 2)
    assert {r.source: pytest.approx(r.target, rel=1e-9) for r in rows} == want
    for s in sizes:
        assert abs(sum(r.taken for r in rows if r.source == s) - want[s]) <= 1
    assert all(0 <= r.taken <= 2 * r.size for r in rows)
    assert sorted(rows) == sorted(mixing.allocate(docs.repartition(7)).collect())


def test_sql(spark, sf):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{sf}/documents.parquet'")
    got = sorted(tuple(r) for r in mixing.allocate(spark.read.parquet(f"{sf}/documents.parquet")).collect())
    assert got == sorted(con.execute(mixing.SQL).fetchall())


def test_edges(spark):
    rows = [(1, None, None, 0), (2, "", "a", 0), (3, "x y z", "a", 0), (3, "x y z", "a", 0), (None, "p q", None, 0), (5, "w " * 3000, "Z", 0), (6, "\x85 \xa0", "é", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, target int")
    out = mixing.allocate(docs).collect()
    assert sorted((r.doc_id or 0, r.size) for r in out) == [(0, 2), (1, 0), (2, 0), (3, 3), (3, 3), (5, 3000), (6, 2)]
    assert all(r.taken <= 2 * r.size for r in out)
    assert mixing.allocate(docs.limit(0)).count() == 0
    assert {r.target for r in mixing.allocate(docs.where("doc_id < 3")).collect()} == {0.0}
    mixed = mixing.mixed(docs)
    assert mixed.columns == docs.columns
    words = {r.doc_id: r.taken for r in out if r.doc_id in (5,)}
    assert mixed.where("doc_id = 5").count() == round(words[5] / 3000)
