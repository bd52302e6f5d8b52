"""Cut-offs from labelled samples.  Each function gives (trial, tau_u, target_u, n_labels, flag); target_u is the goal after inflation.

flag tells what a user should know of a run: "no_match" (none was drawn, so everything is returned), "few_matches" (too few for the
bounds), "clamped" (the lower bound was under zero, but matches were enough), "none_passed" (no cut met a precision goal),
"unguaranteed", or "".
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from certsel.functions import bounds
from certsel.operators import sampling
from certsel.operators.estimators import curves, precision_stats, unweighted
from certsel.spec import NOTHING, SelectionSpec, tail

#: Bootstrap replicates, or as many as resolve the quantile if that is more.
REPLICATES = 400


def _result(sample: DataFrame, tau: DataFrame, default: int, target, missing: str, flag: str = "") -> DataFrame:
    """One row for every trial of the sample, with the default where no cut was found."""
    labels = sample.groupBy("trial").agg(F.count("*").alias("n_labels"))
    j = labels.join(tau, "trial", "left")
    asked = F.round(_goal(target) * F.lit(1e6))
    goal = F.coalesce("target_u", asked) if "target_u" in tau.columns else asked
    own = F.col("flag") if "flag" in tau.columns else F.lit(flag)
    return j.select("trial", F.coalesce("tau_u", F.lit(default)).cast("long").alias("tau_u"), goal.cast("long").alias("target_u"), "n_labels",
                    F.when(F.col("tau_u").isNull(), missing).otherwise(own).alias("flag"))


def _goal(target) -> Column:
    """A target is a number, or a column over trial where trials have targets of their own."""
    return target if isinstance(target, Column) else F.lit(float(target))


def _cut(curve: DataFrame, goal) -> DataFrame:
    """Highest score whose running positive weight reaches the goal's share of the total."""
    reached = F.col("cum_pos").cast("double") >= goal * F.col("total_pos").cast("double")
    return curve.where(reached & (F.col("total_pos") > 0)).groupBy("trial").agg(F.max("score_u").alias("tau_u"))


def raw_recall(sample: DataFrame, target) -> DataFrame:
    """No guarantee: the highest cut with enough sample recall; everything where no positive was drawn."""
    return _result(sample, _cut(curves(sample), _goal(target)), 0, target, "no_match", "unguaranteed")


def raw_precision(sample: DataFrame, target) -> DataFrame:
    """No guarantee: the lowest cut with enough sample precision, which need not be the first one met."""
    ok = F.col("cum_pos").cast("double") >= _goal(target) * F.col("cum_all").cast("double")
    return _result(sample, curves(sample).where(ok).groupBy("trial").agg(F.min("score_u").alias("tau_u")), NOTHING, target, "none_passed", "unguaranteed")


def _halves(sample: DataFrame, first: DataFrame) -> DataFrame:
    """Per trial, of the draws' positive values above and below the first cut: sums, squares and number of draws."""
    j = sample.join(F.broadcast(first.withColumnRenamed("tau_u", "t0")), "trial")
    v, v2 = F.col("mult") * F.col("r_u") * F.col("y"), (F.col("mult") * F.col("r_u") * F.col("r_u") * F.col("y")).cast("decimal(38,0)")
    up = F.col("score_u") >= F.col("t0")
    return j.groupBy("trial").agg(F.sum("mult").cast("double").alias("s"), F.sum(F.when(up, v).otherwise(0)).cast("double").alias("a1"),
                                  F.sum(F.when(up, v2).otherwise(F.lit(0).cast("decimal(38,0)"))).cast("double").alias("a2"),
                                  F.sum(F.when(up, 0).otherwise(v)).cast("double").alias("b1"),
                                  F.sum(F.when(up, F.lit(0).cast("decimal(38,0)")).otherwise(v2)).cast("double").alias("b2"))


def bound_recall(sample: DataFrame, spec: SelectionSpec, r_max: float = 1.0, target=None) -> DataFrame:
    """Guaranteed: the goal is inflated by an upper bound of the mass above the first cut and a lower one of the mass below.

    A lower bound under zero counts as zero: the goal is then 1 and the cut is the lowest sampled match.  That is safe only if
    enough matches were drawn to have met one below the best cut: target to the power of their number has to be delta at
    most.  Matches count by weight, as the number of equally weighted ones that tell as much: their mass squared over the
    sum of their squares, since the matches a weighted sample misses are those it seldom draws.  Where they are too few everything is returned (overflow='guarded'); with 'sample_min' the
    cut stays, and the run is flagged.
    """
    curve, g, half = curves(sample), _goal(spec.target if target is None else target), spec.delta / 2
    first = _cut(curve, g)
    h = _halves(sample, first)
    mean = lambda x: F.col(f"{x}1") / F.col("s")
    sd = lambda x: F.sqrt(F.greatest(F.lit(0.0), (F.col(f"{x}2") - F.col(f"{x}1") * F.col(f"{x}1") / F.col("s")) / (F.col("s") - 1.0)))
    if spec.bound in ("normal", "student"):
        scale = tail(half) if spec.bound == "normal" else bounds.student_quantile(1 - half, max(1, spec.budget - 1))
        top, bottom = (mean(x) + sign * sd(x) / F.sqrt("s") * F.lit(scale) for x, sign in (("a", 1), ("b", -1)))
    elif spec.bound == "hoeffding":
        wide = F.lit(1e6 * r_max * math.sqrt(math.log(1 / half) / 2)) / F.sqrt("s")
        top, bottom = mean("a") + wide, mean("b") - wide
    elif spec.bound == "bootstrap":
        h = h.join(_bootstrap_halves(sample, first, half, spec.seed), "trial")
        top, bottom = F.col("top"), F.col("bottom")
    else:
        return _bound_recall_in_python(sample, spec)
    bottom = F.greatest(F.lit(0.0), bottom)
    enough = F.pow(g, (F.col("a1") + F.col("b1")) * (F.col("a1") + F.col("b1")) / (F.col("a2") + F.col("b2"))) <= spec.delta
    goal = h.select("trial", F.least(F.lit(1.0), top / (top + bottom)).alias("goal"), (bottom <= 0).alias("over"), enough.alias("enough"))
    second = _cut(curve.join(F.broadcast(goal), "trial"), F.col("goal")).join(goal, "trial")  # one row a trial
    weak = F.col("over") & ~F.col("enough")
    tau = F.when(weak, 0).otherwise(F.col("tau_u")) if spec.overflow == "guarded" else F.col("tau_u")
    flag = F.when(weak, "few_matches").when(F.col("over"), "clamped").otherwise("")
    tau = second.select("trial", tau.alias("tau_u"), F.round(F.col("goal") * F.lit(1e6)).cast("long").alias("target_u"), flag.alias("flag"))
    return _result(sample, tau, 0, g, "no_match")


def poisson_one() -> list[float]:
    """Distribution function of a Poisson count of mean 1, as far as it differs from 1."""
    total, out = 0.0, []
    while total < 1 - 1e-15 and len(out) < 20:
        total += math.exp(-1) / math.factorial(len(out))
        out.append(total)
    return out


def _replicated(sample: DataFrame, replicates: int, seed: int) -> DataFrame:
    """The sample's draws, once for each bootstrap replicate they are in: m is a draw's hashed Poisson count."""
    from certsel.functions.draws import hashed, unit

    rows = sample.withColumn("draw", F.explode(F.sequence(F.lit(1), F.col("mult").cast("int")))).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(replicates - 1))))
    u = unit(hashed(F.concat_ws("/", F.col("key").cast("string"), F.col("trial").cast("string"), F.col("draw").cast("string")), F.col("rep") + seed, "boot"))
    rows = rows.withColumn("u", u)
    return rows.withColumn("m", sum(((F.col("u") > c).cast("long") for c in poisson_one()), F.lit(0).cast("long"))).where("m > 0")


def replicates_for(share: float) -> int:
    return max(REPLICATES, math.ceil(2 / share))


def _bootstrap_halves(sample: DataFrame, first: DataFrame, share: float, seed: int) -> DataFrame:
    """(trial, top, bottom): percentiles of the resampled means of the positive mass above and below the first cut."""
    j = _replicated(sample, replicates_for(share), seed).join(F.broadcast(first.withColumnRenamed("tau_u", "t0")), "trial")  # one row a trial
    v = F.col("m") * F.col("r_u") * F.col("y")
    up = F.col("score_u") >= F.col("t0")
    means = j.groupBy("trial", "rep").agg((F.sum(F.when(up, v).otherwise(0)) / F.sum("m")).alias("above"), (F.sum(F.when(up, 0).otherwise(v)) / F.sum("m")).alias("below"))
    return means.groupBy("trial").agg(F.expr(f"percentile(above, {1 - share!r})").alias("top"), F.expr(f"percentile(below, {share!r})").alias("bottom"))


def _bound_recall_in_python(sample: DataFrame, spec: SelectionSpec) -> DataFrame:
    """Exact binomial bounds: each trial's sample, which the budget bounds, is one group."""

    def one(p: pd.DataFrame) -> pd.DataFrame:
        trial, s = int(p.trial.iloc[0]), int(p.mult.sum())
        v = np.repeat((p.r_u * p.y).to_numpy() / 1e6, p.mult)
        score, hit = np.repeat(p.score_u.to_numpy(), p.mult), np.repeat(p.y.to_numpy(), p.mult)
        out = {"trial": trial, "tau_u": 0, "target_u": round(spec.target * 1e6), "flag": "no_match"}

        def cut(goal: float) -> int:
            best = 0
            for x in np.unique(score[hit == 1]):
                if v[score >= x].sum() >= goal * v.sum() * (1 - 1e-12):
                    best = max(best, int(x))
            return best

        if v.sum() > 0:
            up = score >= cut(spec.target)
            top = bounds.clopper_pearson(int(hit[up].sum()), s, spec.delta / 2)[1]
            bottom = bounds.clopper_pearson(int(hit[~up].sum()), s, spec.delta / 2)[0]
            goal = min(1.0, top / (top + bottom)) if top + bottom > 0 else 1.0
            weak = bottom <= 0 and spec.target ** int(hit.sum()) > spec.delta
            flag = "few_matches" if weak else "clamped" if bottom <= 0 else ""
            out |= {"tau_u": 0 if weak and spec.overflow == "guarded" else cut(goal), "target_u": round(goal * 1e6), "flag": flag}
        return pd.DataFrame([out])

    found = sample.select("trial", "score_u", "y", "mult", "r_u").groupBy("trial").applyInPandas(one, "trial int, tau_u long, target_u long, flag string")
    return _result(sample, found, 0, spec.target, "no_match")


def bound_precision(sample: DataFrame, spec: SelectionSpec, share: float, r_max: float = 1.0, target=None) -> DataFrame:
    """Guaranteed: every `step` draws from the top give a candidate; the lowest one whose lower bound exceeds the target is taken.

    A candidate keeps all draws at or above its score, so ties make it keep more.  `share` is the failure probability of one test.
    """
    g = _goal(spec.target if target is None else target)
    c = precision_stats(curves(sample))
    before = F.col("k") - F.col("d")
    c = c.where(F.floor(F.col("k") / F.lit(spec.step)) > F.floor(before / F.lit(spec.step)))
    if spec.bound in ("clopper_pearson", "student"):
        kind, quant = spec.bound, share

        @F.pandas_udf("double")
        def low(p: pd.Series, sd: pd.Series, k: pd.Series) -> pd.Series:
            if kind == "clopper_pearson":
                return pd.Series([bounds.clopper_pearson(round(a * n), int(n), quant)[0] for a, n in zip(p, k)])
            return pd.Series([bounds.student(a, b, int(n), quant)[0] for a, b, n in zip(p, sd, k)])

        bound = low(F.col("p"), F.col("sd"), F.col("k").cast("long"))
    elif spec.bound == "bootstrap":
        c, bound = c.join(_bootstrap_ratios(sample, share, spec.seed), ["trial", "score_u"]), F.col("low")
    elif spec.bound == "hoeffding":
        bound = F.col("p") - F.lit(r_max * math.sqrt(math.log(1 / share) / 2)) / F.sqrt(F.col("k").cast("double"))
    else:
        bound = F.col("p") - F.col("sd") / F.sqrt(F.col("k").cast("double")) * F.lit(tail(share))
    ok = c.where(bound > g)
    return _result(sample, ok.groupBy("trial").agg(F.min("score_u").alias("tau_u")), NOTHING, g, "none_passed")


def _bootstrap_ratios(sample: DataFrame, share: float, seed: int) -> DataFrame:
    """(trial, score_u, low): the percentile of the resampled precision at each score."""
    r = _replicated(sample, replicates_for(share), seed)
    c = F.col("m") * F.col("r_u")
    at = r.groupBy("trial", "rep", "score_u").agg(F.sum(c).alias("c"), F.sum(c * F.col("y")).alias("cy"))
    every = sample.select("trial", "score_u").distinct().crossJoin(F.broadcast(sample.sparkSession.range(replicates_for(share)).select(F.col("id").cast("int").alias("rep"))))
    w = Window.partitionBy("trial", "rep").orderBy(F.desc("score_u")).rowsBetween(Window.unboundedPreceding, 0)
    down = every.join(at, ["trial", "rep", "score_u"], "left").select("trial", "rep", "score_u", F.sum("c").over(w).alias("c"), F.sum("cy").over(w).alias("cy"))
    ratio = down.select("trial", "score_u", F.coalesce(F.col("cy") / F.col("c"), F.lit(0.0)).alias("p"))
    return ratio.groupBy("trial", "score_u").agg(F.expr(f"percentile(p, {share!r})").alias("low"))


def tests_of(spec: SelectionSpec, present: int) -> int:
    return spec.grid_tests if spec.union_terms == "budget" else max(1, math.ceil(present / spec.step))


def match_bound(sample: DataFrame, n: DataFrame, spec: SelectionSpec, target=None) -> DataFrame:
    """(trial, n_match, rank): an upper bound of the number of matches, and the rank from the top that holds them at the target."""
    v, v2 = F.col("mult") * F.col("r_u") * F.col("y"), (F.col("mult") * F.col("r_u") * F.col("r_u") * F.col("y")).cast("decimal(38,0)")
    m = sample.groupBy("trial").agg(F.sum("mult").cast("double").alias("s"), F.sum(v).cast("double").alias("a1"), F.sum(v2).cast("double").alias("a2"))
    m = m.crossJoin(F.broadcast(n))  # one row
    mean = F.col("a1") / F.col("s") / F.lit(1e6)
    sd = F.sqrt(F.greatest(F.lit(0.0), (F.col("a2") - F.col("a1") * F.col("a1") / F.col("s")) / (F.col("s") - 1.0))) / F.lit(1e6)
    scale = tail(spec.delta / 2) if spec.bound == "normal" else bounds.student_quantile(1 - spec.delta / 2, max(1, spec.budget // 2 - 1))
    upper = mean + sd / F.sqrt("s") * F.lit(scale)
    n_match = F.least(F.col("n").cast("double"), F.col("n") * upper)
    return m.select("trial", n_match.alias("n_match"), F.ceil(n_match / _goal(spec.target if target is None else target)).cast("long").alias("rank"))


def rank_floor(universe: DataFrame, ranks: DataFrame, hist: DataFrame | None = None) -> DataFrame:
    """(trial, floor): the score of the record at the rank from the top; 0 beyond the universe.  From the score histogram, without a sort of records."""
    hist = universe.groupBy("score_u").agg(F.count("*").alias("c")) if hist is None else hist
    down = hist.withColumn("cum", F.sum("c").over(Window.orderBy(F.desc("score_u")).rowsBetween(Window.unboundedPreceding, 0)))
    total = hist.agg(F.sum("c").alias("all_n"))
    r = ranks.crossJoin(F.broadcast(total))  # one row
    j = down.join(F.broadcast(r), F.col("cum") >= F.col("rank"))  # one row a trial
    found = j.where("rank < all_n").groupBy("trial").agg(F.max("score_u").alias("floor"))
    return ranks.join(found, "trial", "left").select("trial", F.coalesce("floor", F.lit(0)).cast("long").alias("floor"))


def twostage_precision(universe: DataFrame, label, spec: SelectionSpec, trials: int = 1, hist: DataFrame | None = None,
                       one: DataFrame | None = None, target=None, cycle: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Half of the budget bounds the number of matches; the other half tests cut-offs among as many top records as can hold them.

    Returns the cut-offs and all labelled rows of both halves.  hist and one (the labelled first half) are made if not given.
    Trials `cycle` apart, which differ in their targets, draw by the same random numbers.
    """
    half, target = spec.budget // 2, spec.target if target is None else target
    hist = sampling.histogram(universe) if hist is None else hist
    one = first_half(universe, label, spec, trials, hist) if one is None else one
    n = hist.agg(F.sum("c").alias("n"))
    found = rank_floor(universe, match_bound(one, n, spec, target), hist).collect()  # one row a trial: stage 2 is planned from it
    floors = universe.sparkSession.createDataFrame(found, "trial int, floor long").coalesce(1)
    region = universe.where(F.col("score_u") >= min((r.floor for r in found), default=0))
    two = label(sampling.weighted_cdf(region, half, trials, spec.seed, spec.exponent, spec.mix, floors, "stage2", hist, cycle))
    used = two if spec.stage2_weighting == "ratio" else unweighted(two)
    tau = bound_precision(used, spec, spec.delta / (2 * tests_of(spec, half)), target=target)
    both = one.select("trial", "key", "score_u", "y").union(two.select("trial", "key", "score_u", "y")).distinct()
    labels = both.groupBy("trial").agg(F.count("*").alias("n_labels"))
    tau = labels.join(tau.drop("n_labels"), "trial", "left").select("trial", F.coalesce("tau_u", F.lit(NOTHING)).cast("long").alias("tau_u"),
                                                                    F.round(_goal(target) * F.lit(1e6)).cast("long").alias("target_u"), "n_labels",
                                                                    F.coalesce("flag", F.lit("none_passed")).alias("flag"))
    return tau, both


def first_half(universe: DataFrame, label, spec: SelectionSpec, trials: int, hist: DataFrame) -> DataFrame:
    """The labelled draws of the first stage, which do not depend on the target."""
    return label(sampling.weighted_cdf(universe, spec.budget // 2, trials, spec.seed, spec.exponent, spec.mix, stream="stage1", hist=hist))
