"""Recall and precision curves of labelled samples, plain and reweighted.  All sums are of integers and so exact."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

_BIG = "decimal(38,0)"


def by_score(sample: DataFrame) -> DataFrame:
    """One row per trial and score: draws, weight, positive weight and their squares' sums."""
    c = F.col("mult") * F.col("r_u")
    return sample.groupBy("trial", "score_u").agg(
        F.sum("mult").alias("d"), F.sum(c).alias("c"), F.sum(c * F.col("y")).alias("cy"),
        F.sum((c * F.col("r_u")).cast(_BIG)).alias("c2"), F.sum((c * F.col("r_u") * F.col("y")).cast(_BIG)).alias("cy2"))


def curves(sample: DataFrame) -> DataFrame:
    """Running sums from the top score down, ties together: k draws, cum_all, cum_pos, their squares, and total_pos."""
    w = Window.partitionBy("trial").orderBy(F.desc("score_u")).rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy("trial")
    return by_score(sample).select(
        "trial", "score_u", "d", F.sum("d").over(w).alias("k"), F.sum("c").over(w).alias("cum_all"), F.sum("cy").over(w).alias("cum_pos"),
        F.sum("c2").over(w).alias("sq_all"), F.sum("cy2").over(w).alias("sq_pos"), F.sum("cy").over(every).alias("total_pos"), F.sum("d").over(every).alias("draws"))


def recall_curve(sample: DataFrame) -> DataFrame:
    """(trial, score_u, cum_pos, cum_all): recall at a cut is cum_pos over its last value."""
    return curves(sample).select("trial", "score_u", F.col("cum_pos").cast("long").alias("cum_pos"), F.col("cum_all").cast("long").alias("cum_all"))


def precision_curve(sample: DataFrame) -> DataFrame:
    """(trial, score_u, precision): positives over the draws kept, not over the whole sample."""
    return curves(sample).select("trial", "score_u", (F.col("cum_pos") / F.col("cum_all")).alias("precision"))


def importance_mean(sample: DataFrame, column: str = "y") -> DataFrame:
    """(trial, mean): the weighted mean of a column, an unbiased estimate of its mean over the universe."""
    v = F.col("mult") * F.col("r_u") * F.col(column)
    return sample.groupBy("trial").agg((F.sum(v) / F.sum("mult") / F.lit(1e6)).alias("mean"))


def precision_stats(curve: DataFrame) -> DataFrame:
    """curve with p (ratio estimate) and sd of its linearised residuals over the k draws kept."""
    p = F.col("cum_pos").cast("double") / F.col("cum_all").cast("double")
    c = curve.withColumn("p", p)
    sq = F.col("sq_pos").cast("double") * (1.0 - F.col("p") - F.col("p")) + F.col("sq_all").cast("double") * F.col("p") * F.col("p")
    mean_r = F.col("cum_all").cast("double") / F.col("k").cast("double")
    var = F.when(F.col("k") > 1, F.greatest(F.lit(0.0), sq / (mean_r * mean_r) / (F.col("k") - 1).cast("double"))).otherwise(F.lit(0.0))
    return c.withColumn("sd", F.sqrt(var))


def unweighted(sample: DataFrame) -> DataFrame:
    """The sample with equal factors: what a plain mean sees."""
    return sample.withColumn("r_u", F.lit(1_000_000).cast("long"))
