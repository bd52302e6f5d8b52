"""Hand-worked fixtures F-A to F-H."""

import math

import pytest
from pyspark.sql import functions as F

from certsel.operators import estimators, measures, sampling, thresholds
from certsel.spec import NOTHING, SelectionSpec, tail

F_A = [(.95, 1), (.90, 1), (.80, 0), (.70, 1), (.60, 0), (.50, 1), (.40, 0), (.30, 0), (.20, 1), (.10, 0)]


def sample(spark, rows, r=1.0):
    made = [(0, k, round(a * 1e6), int(y), 1, round((x[0] if x else r) * 1e6)) for k, (a, y, *x) in enumerate(rows)]
    return spark.createDataFrame(made, "trial int, key long, score_u long, y int, mult long, r_u long")


def tau(df):
    return df.first()["tau_u"] / 1e6


def spec(**kw):
    return SelectionSpec(**({"budget": 1000} | kw))


def test_curves(spark):
    s = sample(spark, F_A)
    c = {r.score_u / 1e6: r for r in estimators.curves(s).collect()}
    assert [c[a].cum_pos / c[a].total_pos for a, _ in F_A] == pytest.approx([.2, .4, .4, .6, .6, .8, .8, .8, 1, 1])
    p = {r.score_u / 1e6: r.precision for r in estimators.precision_curve(s).collect()}
    assert [p[a] for a, _ in F_A] == pytest.approx([1, 1, .6667, .75, .6, .6667, .5714, .5, .5556, .5], abs=5e-5)


@pytest.mark.parametrize("g,want", [(.8, .5), (.75, .5), (.9, .2)])
def test_raw_recall(spark, g, want):
    assert tau(thresholds.raw_recall(sample(spark, F_A), g)) == want


def test_raw_precision_is_not_a_first_crossing(spark):
    assert tau(thresholds.raw_precision(sample(spark, F_A), .75)) == .7


def test_clamped_goal(spark):
    r = thresholds.bound_recall(sample(spark, F_A), spec(target=.8, delta=.1, overflow="sample_min")).first()
    assert tail(.05) == pytest.approx(2.447747, abs=1e-6)
    assert (r.tau_u, r.target_u) == (200_000, 1_000_000)
    guarded = thresholds.bound_recall(sample(spark, F_A), spec(target=.8, delta=.1, overflow="guarded")).first()
    assert guarded.tau_u == 0  # .8^5 is above .1: five positives are not enough


@pytest.mark.parametrize("above,below,goal", [(360, 40, .945430), (90, 10, .987510)])
def test_inflated_goal(spark, above, below, goal):
    rows = [(.9, 1)] * above + [(.5, 1)] * below + [(.1, 0)] * (1000 - above - below)
    r = thresholds.bound_recall(sample(spark, rows), spec(target=.9)).first()
    assert r.target_u == pytest.approx(goal * 1e6, abs=1)


def test_precision_bound_numbers(spark):
    for hits, k, want in ((97, 100, .914190), (197, 200, .956951), (290, 300, .932874)):
        c = estimators.precision_stats(estimators.curves(sample(spark, [(.5, i < hits) for i in range(k)]))).first()
        assert c.p - c.sd / math.sqrt(k) * tail(.05 / 10) == pytest.approx(want, abs=1e-6)


def test_precision_grid(spark):
    rows = [(.9, i >= 3) for i in range(100)] + [(.8, 1)] * 100 + [(.7, i >= 7) for i in range(100)] + [(.1, 0)] * 700
    assert tau(thresholds.bound_precision(sample(spark, rows), spec(goal="precision", target=.93), .05 / 10)) == .7
    assert thresholds.bound_precision(sample(spark, rows), spec(goal="precision", target=.99), .005).first().tau_u == NOTHING


def test_weights(spark):
    u = spark.createDataFrame([(k, round(a * 1e6)) for k, a in enumerate((1, .25, 0, 0))], "key long, score_u long")
    w = [r.w_u for r in sampling.weights(u).orderBy("key").collect()]
    assert [x / sum(w) for x in w] == pytest.approx([.625, .325, .025, .025], abs=1e-8)
    assert [sum(w) / (4 * x) for x in w] == pytest.approx([.4, .769231, 10, 10], abs=1e-6)
    flat = sampling.weights(u, exponent=0.0).select("w_u").distinct().collect()
    assert len(flat) == 1 and len(sampling.weights(u, mix=1.0).select("w_u").distinct().collect()) == 1
    zero = sampling.weights(u.withColumn("score_u", F.lit(0).cast("long"))).select("w_u").distinct().collect()
    assert [r.w_u for r in zero] == [1_000_000_000]


def test_weighted_estimates(spark):
    s = sample(spark, [(.9, 1, .5), (.8, 1, .5), (.7, 0, 1), (.2, 1, 4), (.1, 0, 4)])
    c = {r.score_u: r for r in estimators.precision_stats(estimators.curves(s)).collect()}
    assert [c[a].cum_pos / c[a].total_pos for a in (900_000, 800_000, 200_000)] == pytest.approx([.1, .2, 1])
    assert c[700_000].p == pytest.approx(.5) and c[200_000].p == pytest.approx(.8333, abs=1e-4)
    plain = {r.score_u: r.precision for r in estimators.precision_curve(estimators.unweighted(s)).collect()}
    assert plain[700_000] == pytest.approx(.6667, abs=1e-4)


def test_variance_parts(spark):
    u = spark.createDataFrame([(k, round(a * 1e6)) for k, a in enumerate((1, .25, 0, 0))], "key long, score_u long")
    r = measures.variance_parts(u).first()
    assert tuple(r) == pytest.approx((.3125, .15625, .140625, .171875, .015625), abs=1e-6)


def test_rank_floor(spark):
    u = spark.range(1000).select(F.col("id").alias("key"), (F.col("id") * 1000).alias("score_u"))
    ranks = spark.createDataFrame([(0, 40), (1, 1200), (2, 1000)], "trial int, rank long")
    assert {r.trial: r.floor for r in thresholds.rank_floor(u, ranks).collect()} == {0: 960_000, 1: 0, 2: 0}


def test_no_positive_and_all_positive(spark):
    none, every = sample(spark, [(.9, 0)] * 200), sample(spark, [(.9, 1)] * 200)
    s = spec(goal="precision", budget=200)
    assert thresholds.raw_recall(none, .9).first().tau_u == 0 and thresholds.bound_recall(none, spec()).first().tau_u == 0
    assert thresholds.raw_precision(none, .9).first().tau_u == NOTHING and thresholds.bound_precision(none, s, .01).first().tau_u == NOTHING
    assert thresholds.bound_recall(every, spec()).first().tau_u == 900_000 and thresholds.bound_precision(every, s, .01).first().tau_u == 900_000
