"""From a specification to an answer: sample, label, estimate the cut, return labelled matches and everything above it.

Lazy mode keeps the cut as a one-row table, so the whole selection is one plan.  Staged mode runs sample, labels and cut as
actions and puts the cut into the plan as a literal, so that a saved scored table is read from the cut up only.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from certsel.operators import sampling, thresholds
from certsel.sources.staging import staged
from certsel.spec import NOTHING, SelectionSpec


@dataclass
class Selection:
    """rows: the answer; sample: labelled rows (trial, key, score_u, y); cut: (trial, tau_u, target_u, n_labels, flag), lazy mode's report."""

    rows: DataFrame
    tau_u: int | None
    sample: DataFrame
    report: dict = field(default_factory=dict)
    cut: DataFrame | None = None


class Labelling:
    """Samples of one universe, each drawn and labelled once, however many targets, bounds and trials use it."""

    def __init__(self, base: DataFrame, oracle, trials: int = 1, universe: DataFrame | None = None):
        self.base, self.oracle, self.trials = base, oracle, trials
        # Scores are made once, whatever the proxy costs: all later passes read (key, score) alone.
        self.universe = staged(base.select("key", "score_u"), "universe") if universe is None else universe
        self.hist = sampling.histogram(self.universe)
        self.made: dict[tuple, DataFrame] = {}

    def label(self, sample: DataFrame) -> DataFrame:
        return sampling.label(sample, self.base, self.oracle)

    def sample(self, spec: SelectionSpec) -> DataFrame:
        """The labelled draws of spec (the first half of them for two stages)."""
        own = (spec.exponent, spec.mix) if spec.is_weighted else ()
        name = (spec.method == "twostage", spec.is_weighted, spec.budget, spec.seed, spec.draws, *own)
        if name not in self.made:
            self.made[name] = self._draw(spec)
        return self.made[name]

    def _draw(self, spec: SelectionSpec) -> DataFrame:
        if spec.method == "twostage":
            return thresholds.first_half(self.universe, self.label, spec, self.trials, self.hist)
        if spec.is_weighted:
            if spec.draws == "poisson" and self.trials == 1:
                return self.label(sampling.weighted_poisson(self.universe, spec.budget, spec.seed, spec.exponent, spec.mix))
            return self.label(sampling.weighted_cdf(self.universe, spec.budget, self.trials, spec.seed, spec.exponent, spec.mix, hist=self.hist))
        if spec.draws == "iid":
            return self.label(sampling.uniform_iid(self.universe, spec.budget, self.trials, spec.seed, self.hist))
        return self.label(sampling.uniform_distinct(self.universe, spec.budget, self.trials, spec.seed))

    def estimate(self, spec: SelectionSpec) -> tuple[DataFrame, DataFrame]:
        """(cut-offs, labelled rows) of the independent runs; labelled rows are trial, key, score_u, y."""
        if spec.method in ("exhaustive", "everything", "nothing"):
            raise ValueError(f"{spec.method} draws no sample")
        return self._estimate(spec, self.sample(spec), spec.target, self.trials)

    def sweep(self, spec: SelectionSpec, targets: list[float]) -> tuple[DataFrame, DataFrame, Column]:
        """estimate() for many targets in one plan: the runs of the k-th target are trials k * trials and on; also gives the target of a trial."""
        numbers = self.sample(spec).sparkSession.range(len(targets)).select(F.col("id").cast("int").alias("target_no"))
        s = self.sample(spec).crossJoin(F.broadcast(numbers)).withColumn("trial", F.col("trial") + F.col("target_no") * self.trials).drop("target_no")
        target = F.element_at(F.array(*[F.lit(float(g)) for g in targets]), F.floor(F.col("trial") / self.trials).cast("int") + 1)
        return *self._estimate(spec, s, target, self.trials * len(targets)), target

    def _estimate(self, spec: SelectionSpec, s: DataFrame, target, trials: int) -> tuple[DataFrame, DataFrame]:
        if spec.method == "twostage":
            return thresholds.twostage_precision(self.universe, self.label, spec, trials, self.hist, s, target, self.trials)
        r_max = (1 / spec.mix if spec.mix else 1e6) if spec.is_weighted else 1.0
        if spec.method == "uniform_raw":
            tau = (thresholds.raw_recall if spec.goal == "recall" else thresholds.raw_precision)(s, target)
        elif spec.goal == "recall":
            tau = thresholds.bound_recall(s, spec, r_max, target)
        else:
            tau = thresholds.bound_precision(s, spec, spec.delta / thresholds.tests_of(spec, spec.budget), r_max, target)
        return tau, s.select("trial", "key", "score_u", "y")


def estimate(base: DataFrame, oracle, spec: SelectionSpec, trials: int = 1) -> tuple[DataFrame, DataFrame]:
    """(cut-offs, labelled rows) of `trials` independent runs of one specification."""
    return Labelling(base, oracle, trials).estimate(spec)


def answer(base: DataFrame, tau: DataFrame, labelled: DataFrame, drop_known_negatives: bool = False) -> DataFrame:
    """Rows of base at or above the cut of trial 0, or sampled as matches; one pass, and the two parts never overlap."""
    known = labelled.where("trial = 0").select(F.col("key").alias("k"), F.col("y").alias("known_y"))
    cut = tau.where("trial = 0").select("tau_u")
    j = base.crossJoin(F.broadcast(cut)).join(F.broadcast(known), F.col("key") == F.col("k"), "left")  # one row
    keep = (F.col("score_u") >= F.col("tau_u")) | (F.coalesce("known_y", F.lit(0)) == 1)
    if drop_known_negatives:
        keep = keep & ~(F.coalesce("known_y", F.lit(1)) == 0)
    return j.where(keep).select(*base.columns)


def _all_labelled(base: DataFrame, oracle) -> Selection:
    """Every row's label is bought once and written; the answer is the matches."""
    known = staged(oracle(base).select("key", "score_u", F.coalesce("y", F.lit(0)).cast("int").alias("y")), "labels")
    rows = base.join(known.where("y = 1").select("key"), "key", "left_semi").select(*base.columns)
    return Selection(rows, None, known.select(F.lit(0).alias("trial"), "key", "score_u", "y"), {"method": "exhaustive", "flags": []})


def _fits(base: DataFrame, spec: SelectionSpec) -> bool:
    return base.select("key").limit(spec.budget + 1).count() <= spec.budget


def run(base: DataFrame, oracle, spec: SelectionSpec) -> Selection:
    """Lazy mode.  A universe no larger than the budget, and method exhaustive, are labelled whole; cut holds the flags of other runs."""
    if spec.method == "everything":
        return Selection(base, 0, base.limit(0))
    if spec.method == "nothing":
        return Selection(base.where(F.col("score_u") >= NOTHING), NOTHING, base.limit(0))
    if spec.method == "exhaustive" or _fits(base, spec):
        return _all_labelled(base, oracle)
    tau, labelled = estimate(base, oracle, spec)
    return Selection(answer(base, tau, labelled, spec.drop_known_negatives), None, labelled, cut=tau)


def run_staged(base: DataFrame, oracle, spec: SelectionSpec, ledger_dir: str) -> Selection:
    """Staged mode.  The labelled sample is written to ledger_dir, so its oracle calls are made once whatever fails later."""
    spark = base.sparkSession
    if _fits(base, spec):
        return _all_labelled(base, oracle)
    tau, labelled = estimate(base, oracle, spec)
    labelled.join(tau.select("trial", "tau_u", "target_u", "flag"), "trial").write.mode("overwrite").parquet(ledger_dir)
    bought = spark.read.parquet(ledger_dir)
    first = bought.select("tau_u", "target_u", "flag").first()
    tau_u = int(first["tau_u"]) if first else (0 if spec.goal == "recall" else NOTHING)
    matches = bought.where("y = 1").select(F.col("key").alias("k")).distinct()
    above = base.where(F.col("score_u") >= tau_u)
    below = base.where(F.col("score_u") < tau_u).join(F.broadcast(matches), F.col("key") == F.col("k"), "left_semi")
    if spec.drop_known_negatives:
        wrong = bought.where("y = 0").select(F.col("key").alias("k")).distinct()
        above = above.join(F.broadcast(wrong), F.col("key") == F.col("k"), "left_anti")
    counts = bought.agg(F.countDistinct("key").alias("n"), F.countDistinct(F.when(F.col("y") == 1, F.col("key"))).alias("m")).first()
    flags = [x for x in (first["flag"] if first else "", "few_positives" if counts["m"] < 10 else "", "small_budget" if spec.budget <= 100 else "") if x]
    report = {"method": spec.method, "goal": spec.goal, "target": spec.target, "delta": spec.delta, "budget": spec.budget, "tau_u": tau_u,
              "inflated_target_u": int(first["target_u"]) if first else None, "distinct_labels": counts["n"], "sampled_matches": counts["m"], "flags": flags}
    return Selection(above.unionByName(below), tau_u, bought, report)


def select_both(base: DataFrame, oracle, spec: SelectionSpec) -> DataFrame:
    """Both goals at once: a recall-goal answer whose every row is then labelled.  Labels used are as many as rows, without bound."""
    picked = run(base, oracle, spec.but(goal="recall", method="weighted"))
    return oracle(picked.rows).where("y = 1").select(*base.columns)


def signal_only(base: DataFrame, cut_u: int) -> DataFrame:
    """A filter on the cheap signal alone, without labels or guarantee."""
    return base.where(F.col("score_u") >= cut_u)


def blend(*scores, how: str = "mean"):
    """Several proxies as one: their mean or their maximum."""
    return F.greatest(*scores) if how == "max" else sum(scores[1:], scores[0]) / len(scores)


def frozen_cut(fit: DataFrame, goal: str, target: float) -> DataFrame:
    """(trial, tau_u) from a universe whose every label is known: (key, score_u, y)."""
    s = fit.select(F.lit(0).alias("trial"), "key", "score_u", "y", F.lit(1).cast("long").alias("mult"), F.lit(1_000_000).cast("long").alias("r_u"))
    return (thresholds.raw_recall if goal == "recall" else thresholds.raw_precision)(s, target).select("trial", "tau_u")
