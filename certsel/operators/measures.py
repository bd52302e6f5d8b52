"""Accuracy, calibration, variance and cost measures.  Most are read off the score histogram (score_u, n, n_pos)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from certsel.spec import GRID


def histogram(truth: DataFrame) -> DataFrame:
    """Lossless for every question about cut-offs: at most a million rows, whatever the universe's size."""
    return truth.groupBy("score_u").agg(F.count("*").alias("n"), F.sum("y").alias("n_pos"))


def achieved(hist: DataFrame, tau: DataFrame, labelled: DataFrame) -> DataFrame:
    """(trial, tau_u, size, hits, matches, precision, recall) of each trial's answer, without a pass over the universe."""
    total = hist.agg(F.sum("n_pos").alias("matches"))
    above = hist.join(F.broadcast(tau.select("trial", "tau_u")), F.col("score_u") >= F.col("tau_u")).groupBy("trial").agg(
        F.sum("n").alias("above"), F.sum("n_pos").alias("above_pos"))
    extra = labelled.where("y = 1").join(F.broadcast(tau.select("trial", "tau_u")), "trial").where("score_u < tau_u").groupBy("trial").agg(
        F.countDistinct("key").alias("extra"))
    j = tau.select("trial", "tau_u").join(above, "trial", "left").join(extra, "trial", "left").crossJoin(F.broadcast(total))  # one row
    zero = lambda c: F.coalesce(c, F.lit(0))
    j = j.select("trial", "tau_u", (zero("above") + zero("extra")).alias("size"), (zero("above_pos") + zero("extra")).alias("hits"), "matches")
    return j.withColumn("precision", F.when(F.col("size") > 0, F.col("hits") / F.col("size")).otherwise(1.0)).withColumn(
        "recall", F.when(F.col("matches") > 0, F.col("hits") / F.col("matches")).otherwise(1.0))


def answer_metrics(answer: DataFrame, truth: DataFrame) -> DataFrame:
    """size, hits, precision and recall of an answer held against the whole universe's labels."""
    j = truth.select("key", "y").join(answer.select("key", F.lit(1).alias("got")), "key", "left")
    a = j.agg(F.count("got").alias("size"), F.sum(F.when(F.col("got") == 1, F.col("y")).otherwise(0)).alias("hits"), F.sum("y").alias("matches"))
    return a.select("size", "hits", "matches", F.round(F.when(F.col("size") > 0, F.col("hits") / F.col("size")).otherwise(1.0), 6).alias("precision"),
                    F.round(F.when(F.col("matches") > 0, F.col("hits") / F.col("matches")).otherwise(1.0), 6).alias("recall"))


def failure_rate(trials: DataFrame, goal: str, target, by: tuple = ()) -> DataFrame:
    """Share of trials below the target, and the mean of the other measure (quality)."""
    other = "precision" if goal == "recall" else "recall"
    failed = F.col(goal) < (target if isinstance(target, Column) else F.lit(target))
    return trials.groupBy(*by).agg(F.count("*").alias("n_trials"), F.sum(failed.cast("int")).cast("long").alias("n_failed"),
                                   F.round(F.avg(failed.cast("int")), 6).alias("failure_rate"), F.round(F.avg(other), 6).alias("quality"),
                                   F.round(F.avg("size"), 6).alias("mean_size"))


def boxplot(trials: DataFrame, column: str) -> DataFrame:
    """Quartiles, extremes and whiskers (the outermost values within 1.5 interquartile ranges of the box)."""
    q = trials.agg(*[F.expr(f"percentile({column}, {p})").alias(n) for n, p in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))])
    j = trials.crossJoin(F.broadcast(q))  # one row
    inside = (F.col(column) >= F.col("q1") - 1.5 * (F.col("q3") - F.col("q1"))) & (F.col(column) <= F.col("q3") + 1.5 * (F.col("q3") - F.col("q1")))
    a = j.agg(F.min(column).alias("least"), F.max("q1").alias("q1"), F.max("median").alias("median"), F.max("q3").alias("q3"), F.max(column).alias("most"),
              F.min(F.when(inside, F.col(column))).alias("low_whisker"), F.max(F.when(inside, F.col(column))).alias("high_whisker"))
    return a.select(*[F.round(c, 6).alias(c) for c in a.columns])


def calibration(truth: DataFrame, buckets: int = 10) -> DataFrame:
    """Match rate per score bucket; the last bucket holds score 1 too."""
    b = F.least(F.lit(buckets - 1), F.floor(F.col("score_u") * buckets / F.lit(GRID))).cast("long")
    return truth.groupBy(b.alias("bucket")).agg(F.count("*").alias("n"), F.round(F.avg("y"), 6).alias("rate"))


def is_monotone(cal: DataFrame) -> DataFrame:
    """Whether the match rate never falls from bucket to bucket."""
    w = Window.orderBy("bucket")
    return cal.withColumn("before", F.lag("rate").over(w)).agg(F.coalesce(F.min((F.col("rate") >= F.coalesce("before", F.lit(0.0))).cast("int")), F.lit(1)).alias("monotone"))


def variance_parts(universe: DataFrame) -> DataFrame:
    """First variance part of uniform, linear and square-root weighted estimators for calibrated scores, and their gaps."""
    a = F.col("score_u") / F.lit(float(GRID))
    m = universe.agg(F.avg(a).alias("m"), F.avg(F.sqrt(a)).alias("r"), F.avg((a > 0).cast("double")).alias("z"))
    u, lin, root = F.col("m"), F.col("z") * F.col("m"), F.col("r") * F.col("r")
    return m.select(*[F.round(c, 6).alias(n) for n, c in (("uniform_v", u), ("linear_v", lin), ("root_v", root), ("uniform_gap", u - root), ("linear_gap", lin - root))])


def sharpness(universe: DataFrame) -> DataFrame:
    return universe.agg(F.round(F.stddev_pop(F.col("score_u") / F.lit(float(GRID))), 6).alias("score_sd"), F.count("*").alias("n"))


def positive_rate(truth: DataFrame) -> DataFrame:
    return truth.agg(F.count("*").alias("n"), F.sum("y").cast("long").alias("matches"), F.round(F.avg("y"), 6).alias("rate"))


def cost(n: int, budget: int, proxy_per_second: float, sampling_seconds: float = 0.09, label_price: float = 0.08, hour_price: float = 3.06) -> dict[str, float]:
    """Money for sampling, proxy, oracle, their total, and labelling everything."""
    parts = {"sampling": sampling_seconds / 3600 * hour_price, "proxy": n / proxy_per_second / 3600 * hour_price, "oracle": budget * label_price}
    total = sum(parts.values())
    return parts | {"total": total, "exhaustive": n * label_price, "gain": n * label_price / total if total else float("inf")}


def cost_columns(n: Column, budget: int, proxy_per_second: float, sampling_seconds: float = 0.09, label_price: float = 0.08, hour_price: float = 3.06) -> list[Column]:
    """The parts of cost() over a column of table sizes, rounded."""
    sampling, oracle = F.lit(sampling_seconds / 3600 * hour_price), F.lit(budget * label_price)
    proxy = n / F.lit(proxy_per_second) / F.lit(3600) * F.lit(hour_price)
    total, every = sampling + proxy + oracle, n * F.lit(label_price)
    return [F.round(c, d).alias(x) for x, c, d in (("sampling", sampling, 6), ("proxy", proxy, 6), ("oracle", oracle, 6), ("total", total, 6), ("exhaustive", every, 6), ("gain", every / total, 4))]


def gain_factor(rates: DataFrame, base: str, ours: str) -> DataFrame:
    """(target, base_quality, quality, gain): by how much one method's mean quality exceeds another's at equal targets; null where the base has none."""
    a, b = (rates.where(F.col("method") == m).select("target", F.col("quality").alias(q)) for m, q in ((base, "base_quality"), (ours, "quality")))
    return a.join(b, "target").withColumn("gain", F.when(F.col("base_quality") > 0, F.round(F.col("quality") / F.col("base_quality"), 4)))


def calibration_of_sample(sample: DataFrame, buckets: int = 10) -> DataFrame:
    """calibration() as a weighted sample estimates it: reweighted matches over reweighted draws of each bucket."""
    b = F.least(F.lit(buckets - 1), F.floor(F.col("score_u") * buckets / F.lit(GRID))).cast("long")
    c = F.col("mult") * F.col("r_u")
    return sample.groupBy(b.alias("bucket")).agg(F.sum("mult").alias("draws"), F.round(F.sum(c * F.col("y")).cast("double") / F.sum(c), 6).alias("rate"))


def noise_share(universe: DataFrame, noise: tuple[float, ...]) -> DataFrame:
    """(noise, percent): proxy noise as a percentage of the scores' own spread."""
    sd = universe.agg(F.stddev_pop(F.col("score_u") / F.lit(float(GRID))).alias("sd"))
    return sd.select(F.explode(F.array(*[F.lit(s) for s in noise])).alias("noise"), "sd").select("noise", F.round(100 * F.col("noise") / F.col("sd"), 4).alias("percent"))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Keys in one answer alone, with the side they are on."""
    j = a.select("key", F.lit(1).alias("in_a")).join(b.select("key", F.lit(1).alias("in_b")), "key", "full")
    return j.where("in_a is null or in_b is null").select("key", F.when(F.col("in_a") == 1, "first").otherwise("second").alias("side"))
