"""Surrounding operators that users of a selection need: joins on labels, as-of thresholds, top-k, windows, sessions, set operations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from certsel.sources.tables import load


def as_of(left: DataFrame, right: DataFrame, by: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """Each left row with the latest right value at or before its time: one union, one sort per key, no range join."""
    a = left.withColumn("ts__", F.col(left_ts)).withColumn("side__", F.lit(1)).withColumn("v__", F.lit(None).cast(right.schema[value].dataType))
    b = right.select(by, F.col(right_ts).alias("ts__"), F.lit(0).alias("side__"), F.col(value).alias("v__"))
    w = Window.partitionBy(by).orderBy("ts__", "side__").rowsBetween(Window.unboundedPreceding, 0)
    u = a.unionByName(b, allowMissingColumns=True).withColumn("as_of", F.last("v__", ignorenulls=True).over(w))
    return u.where("side__ = 1").select(*left.columns, "as_of")


def interval_join(points: DataFrame, intervals: DataFrame, at: str, low: str, high: str, width: float) -> DataFrame:
    """Points within [low, high): both sides meet on strips of `width`, then the bounds are tested."""
    i = intervals.withColumn("strip__", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    p = points.withColumn("strip__", F.floor(F.col(at) / width))
    return p.join(i, "strip__").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("strip__")


def labelled_docs(spark, sf_dir):
    return load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_semi").select("doc_id", "lang", "source")


def unlabelled_docs(spark, sf_dir):
    return load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_anti").select("doc_id", "lang", "source")


def as_of_threshold(spark, sf_dir):
    """The last purchase above 200 before each error-free event of a user."""
    e = load(spark, sf_dir, "events")
    cal = e.where("event_type = 'purchase' and value > 200").groupBy("user_id", "ts").agg(F.max("value").alias("bar"))
    return as_of(e.select("event_id", "user_id", "ts"), cal, "user_id", "ts", "ts", "bar").select("event_id", F.col("as_of").alias("bar"))


def topk_scores(spark, sf_dir, k: int = 50):
    e = load(spark, sf_dir, "events")
    return e.orderBy(F.desc("value"), "event_id").limit(k).select("event_id", "value")


def daily_counts(spark, sf_dir):
    w = Window.partitionBy("event_type").orderBy("day").rowsBetween(-6, 0)
    d = load(spark, sf_dir, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type").agg(F.count("*").alias("n"))
    return d.select("day", "event_type", "n", F.sum("n").over(w).alias("week"))


def sessions(spark, sf_dir, gap_minutes: int = 60):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, sf_dir, "events").withColumn("before", F.lag("ts").over(w))
    new = (F.col("before").isNull() | (F.col("ts") > F.col("before") + F.expr(f"interval {gap_minutes} minutes"))).cast("int")
    s = e.withColumn("session", F.sum(new).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return s.groupBy("user_id", "session").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


def union_answers(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.where("value > 200").select("event_id").unionByName(e.where("event_type = 'purchase' and value <= 200 and value > 150").select("event_id"))


def range_join_bands(spark, sf_dir):
    """Events by value band, through the strip join."""
    bands = spark.range(0, 10).select(F.col("id").alias("band"), (F.col("id") * 37.5).alias("low"), ((F.col("id") + 1) * 37.5).alias("high"))
    j = interval_join(load(spark, sf_dir, "events").select("event_id", "value"), bands, "value", "low", "high", 25.0)
    return j.select("event_id", "band")


def json_props(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k")).groupBy("event_type").agg(F.sum("k").alias("k_sum"), F.count("k").alias("n"))


def rollup_lines(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


def grouping_lines(spark, sf_dir):
    """Chosen groupings in one pass, told apart by their grouping number."""
    load(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus", "l_quantity").createOrReplaceTempView("certsel_lines")
    return spark.sql("""SELECT l_returnflag, l_linestatus, CAST(grouping_id() AS INT) AS level, count(*) AS n, round(sum(l_quantity), 2) AS qty
        FROM certsel_lines GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())""")


def ranked_events(spark, sf_dir):
    """Rank and quarter of each event within its type, by value."""
    w = Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
    return load(spark, sf_dir, "events").select("event_id", F.rank().over(w).alias("place"), F.ntile(4).over(w).alias("quarter"))


def approximate_users(spark, sf_dir):
    """Whether sketches are within their promised errors of the exact distinct count and median."""
    a = load(spark, sf_dir, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("u"), F.countDistinct("user_id").alias("v"),
                                          F.percentile_approx("value", 0.5, 1000).alias("m"), F.avg((F.col("value") > 0).cast("int")).alias("z"),
                                          F.expr("percentile(value, 0.49)").alias("low"), F.expr("percentile(value, 0.51)").alias("high"))
    return a.select(F.col("v").alias("users"), (F.abs(F.col("u") - F.col("v")) <= 0.08 * F.col("v")).alias("count_near"), F.col("m").between(F.col("low"), F.col("high")).alias("median_near"))


QUERIES = {
    "grouping_lines": (grouping_lines, """SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag, l_linestatus) AS INTEGER) AS level, count(*) AS n, round(sum(l_quantity), 2) AS qty
        FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())"""),
    "ranked_events": (ranked_events, """SELECT event_id, CAST(rank() OVER w AS INTEGER) AS place, CAST(ntile(4) OVER w AS INTEGER) AS quarter FROM events WINDOW w AS (PARTITION BY event_type ORDER BY value DESC, event_id)"""),
    "approximate_users": (approximate_users, "SELECT count(DISTINCT user_id) AS users, true AS count_near, true AS median_near FROM events"),
    "join_labels_semi": (labelled_docs, "SELECT doc_id, lang, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)"),
    "join_unlabelled_anti": (unlabelled_docs, "SELECT doc_id, lang, source FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL)"),
    "asof_threshold": (as_of_threshold, """SELECT event_id, bar FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS bar FROM events
        WHERE event_type = 'purchase' AND value > 200 GROUP BY user_id, ts) c ON e.user_id = c.user_id AND e.ts >= c.ts"""),
    "topk_scores": (topk_scores, "SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 50"),
    "window_daily_counts": (daily_counts, """SELECT day, event_type, n, sum(n) OVER (PARTITION BY event_type ORDER BY day ROWS 6 PRECEDING)::BIGINT AS week
        FROM (SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2)"""),
    "session_events": (sessions, """SELECT user_id, session, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS session
        FROM (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts > lag(ts) OVER w + INTERVAL 60 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))) GROUP BY 1, 2"""),
    "setop_union_answers": (union_answers, "SELECT event_id FROM events WHERE value > 200 UNION ALL SELECT event_id FROM events WHERE event_type = 'purchase' AND value <= 200 AND value > 150"),
    "range_join_bands": (range_join_bands, "SELECT event_id, band FROM events JOIN (SELECT range AS band, range * 37.5 AS low, (range + 1) * 37.5 AS high FROM range(10)) ON value >= low AND value < high"),
    "json_props": (json_props, "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k_sum, count(props->>'$.k') AS n FROM events GROUP BY 1"),
    "rollup_lines": (rollup_lines, "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
}
