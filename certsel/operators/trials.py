"""Repeated runs with ground truth: all trials of a method are one plan."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certsel.operators import measures, runner
from certsel.sources.staging import staged
from certsel.spec import SelectionSpec


def trial_metrics(base: DataFrame, oracle, truth: DataFrame, spec: SelectionSpec, trials: int, hist: DataFrame | None = None) -> DataFrame:
    """(trial, tau_u, size, hits, matches, precision, recall) of each trial."""
    tau, labelled = runner.estimate(base, oracle, spec, trials)
    return measures.achieved(measures.histogram(truth) if hist is None else hist, tau, labelled)


def compare(truth: DataFrame, specs: dict[str, SelectionSpec], trials: int) -> DataFrame:
    """(method, target, n_trials, n_failed, failure_rate, quality, mean_size) per named specification.

    truth is (key, score_u, y) of the whole universe.  It is written once as a scored table that all methods read; its
    labels stand in for the oracle, which is still asked for sampled keys only.  Specifications that draw alike share a sample.
    """
    scored = staged(truth.select("key", "score_u", "y"), "scored")
    hist = staged(measures.histogram(scored), "histogram")
    runs = runner.Labelling(scored, lambda df: df, trials, scored.select("key", "score_u"))
    alike: dict[SelectionSpec, list[str]] = {}
    for name, s in specs.items():
        alike.setdefault(s.but(target=0.5), []).append(name)
    rows = [part for spec, names in alike.items() for part in _rates(runs, hist, spec, {n: specs[n].target for n in names})]
    return reduce(DataFrame.unionByName, rows)


def _rates(runs: runner.Labelling, hist: DataFrame, spec: SelectionSpec, targets: dict[str, float]) -> list[DataFrame]:
    """Failure rates of one way to select at several targets: one plan."""
    if len(targets) == 1 or spec.bound == "clopper_pearson":
        return [measures.failure_rate(measures.achieved(hist, *runs.estimate(spec.but(target=g))), spec.goal, g).select(
            F.lit(name).alias("method"), F.lit(g).alias("target"), "*") for name, g in targets.items()]
    tau, labelled, target = runs.sweep(spec, list(targets.values()))
    m = measures.achieved(hist, tau, labelled).withColumn("target", target)
    name = F.element_at(F.array(*[F.lit(n) for n in targets]), F.floor(F.col("trial") / runs.trials).cast("int") + 1)
    rates = measures.failure_rate(m.withColumn("method", name), spec.goal, F.col("target"), ("method", "target"))
    return [rates]


def drift(fit_truth: DataFrame, truth: DataFrame, spec: SelectionSpec, trials: int, name: str) -> DataFrame:
    """(dataset, goal, target, frozen, refit, frozen_gap): what a cut fitted elsewhere achieves here, by how much it misses the target, and
    what estimating anew achieves on average.  One row always: an empty side gives null."""
    truth = staged(truth.select("key", "score_u", "y"), "scored")
    hist = staged(measures.histogram(truth), "histogram")
    tau = runner.frozen_cut(fit_truth, spec.goal, spec.target)
    none = truth.limit(0).select(F.lit(0).alias("trial"), "key", "score_u", "y")
    frozen = measures.achieved(hist, tau, none).agg(F.max(spec.goal).alias("frozen"))
    ours = trial_metrics(truth, lambda df: df, truth, spec, trials, hist).agg(F.avg(spec.goal).alias("refit"))
    j = frozen.crossJoin(F.broadcast(ours))  # one row each
    return j.select(F.lit(name).alias("dataset"), F.lit(spec.goal).alias("goal"), F.lit(spec.target).alias("target"), F.round("frozen", 6).alias("frozen"),
                    F.round("refit", 6).alias("refit"), F.round(F.lit(spec.target) - F.col("frozen"), 6).alias("frozen_gap"))
