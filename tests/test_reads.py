import duckdb
from certsel.plans.queries import QUERIES, SQL


def test_small_answers_come_from_the_events(spark):
    """Both match their SQL, and their plans scan the table."""
    sf, con = "/root/testdata/sf0.01", duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    for name in ("answer_nothing", "grid_candidates"):
        got = QUERIES[name](spark, sf)
        assert "Scan parquet" in got._jdf.queryExecution().executedPlan().toString()
        assert sorted(map(tuple, got.collect())) == sorted(con.execute(SQL[name]).fetchall())
