"""All queries of the engine with their DuckDB twins: scores, samples, curves, cut-offs, answers, measures, experiments."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certsel.operators import callbacks, estimators, measures, runner, sampling, thresholds, trials
from certsel.plans import sqlfront
from certsel.plans.twins import UNIVERSE, Twin, leak_sql, synth_sql
from certsel.sources import workloads
from certsel.sources.workloads import ALL, Workload
from certsel.spec import SelectionSpec
from certsel.streaming import refit

TRIALS = 5
FULL_TRIALS = 100
#: Ship years run from 1995 to 2001: the control case of drift fits on those before.
SPLIT_YEAR = 1998
TRIAL_WORKLOADS = ("net", "rare", "bulk", "pii", "junk", "beta_1.0", "beta_2.0")
EVERY_WORKLOAD = (*ALL, "beta_1.0", "beta_2.0")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def register(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


def _synth(alpha: float, beta: float, noise: float = 0.0) -> tuple[Workload, str]:
    return workloads.synthetic(alpha, beta, 0, noise), synth_sql(alpha, beta, 0, noise)


def _w(name: str) -> tuple[Workload, str]:
    return _synth(0.01, float(name[5:])) if name.startswith("beta_") else (ALL[name], UNIVERSE[name])


def _spec(w: Workload, **kw) -> SelectionSpec:
    return SelectionSpec(**({"budget": w.budget, "step": w.step} | kw))


def _sampled(w: Workload, pick, *args, **kw):
    def run(spark, sf_dir):
        base = w.scored(spark, sf_dir)
        return sampling.label(pick(base.select("key", "score_u"), *args, **kw), base, w.oracle)

    return run


# scores
def _scores():
    out = ("key", "score_u", "y")
    for name in ("pii", "tox", "junk", "junk_ascii", "audit", "leak", "rare", "net", "bulk", "chat", "vec", "page"):
        w, u = _w(name)
        register(f"score_{name}", lambda s, d, w=w: w.truth(s, d), f"SELECT key, score_u, y FROM ({u})")
    weak = workloads._make_leak(2)
    register("score_leak_weak", lambda s, d: weak.truth(s, d), f"SELECT key, score_u, y FROM ({leak_sql(2)})")
    for name, (a, b, noise) in {"synth_beta_1": (0.01, 1.0, 0.0), "synth_beta_2": (0.01, 2.0, 0.0), "synth_beta_half": (0.01, 0.5, 0.0), "synth_noise": (0.01, 2.0, 0.02)}.items():
        w, u = _synth(a, b, noise)
        register(name, lambda s, d, w=w: w.truth(s, d).select(*out), f"SELECT key, score_u, y FROM ({u})")


_SAMPLE = "SELECT trial, key, score_u, y, mult, r_u FROM"


def _samples():
    w, u = _w("net")
    cols = ("trial", "key", "score_u", "y", "mult", "r_u")
    pick = lambda f, *a, **k: lambda s, d: _sampled(w, f, *a, **k)(s, d).select(*cols)
    t = Twin(u)
    register("sample_uniform_distinct", pick(sampling.uniform_distinct, w.budget, 2), t.done(f"{_SAMPLE} {t.uniform_distinct(w.budget, 2)}"))
    t = Twin(u)
    register("sample_uniform_iid", pick(sampling.uniform_iid, w.budget), t.done(f"{_SAMPLE} {t.weighted_cdf(w.budget, exponent=0.0, mix=1.0, stream='iid')}"))
    for name, p in (("sqrt", 0.5), ("linear", 1.0)):
        t = Twin(u)
        register(f"sample_weighted_{name}", pick(sampling.weighted_cdf, w.budget, 2, exponent=p), t.done(f"{_SAMPLE} {t.weighted_cdf(w.budget, 2, exponent=p)}"))
        t = Twin(u)
        register(f"weights_{name}", lambda s, d, p=p: sampling.weights(w.scored(s, d).select("key", "score_u"), p).select("key", "p_u", "w_u"),
                 t.done(f"SELECT key, p_u, w_u FROM {t.weights('u', p)}"))
    sweep = [0.0, 0.25, 0.5, 0.75, 1.0]
    t = Twin(u)
    register("weights_exponent_sweep", lambda s, d: reduce(DataFrame.union, [sampling.weights(w.scored(s, d).select("key", "score_u"), p).agg(
        F.lit(p).alias("exponent"), F.sum("w_u").alias("w_total"), F.max("w_u").alias("w_most")) for p in sweep]),
        t.done(" UNION ALL ".join(f"SELECT {p!r}::DOUBLE AS exponent, sum(w_u)::BIGINT AS w_total, max(w_u) AS w_most FROM {t.weights('u', p)}" for p in sweep)))
    t = Twin(u)
    register("sample_poisson", pick(sampling.weighted_poisson, w.budget), t.done(f"{_SAMPLE} {t.poisson(w.budget)}"))
    t = Twin(u)
    s = _spec(w, goal="precision", method="twostage")
    tau, both = t.twostage(s)
    register("sample_stage2_region", lambda sp, d: runner.estimate(w.scored(sp, d), w.oracle, s)[1].select("trial", "key", "score_u", "y"), t.done(f"SELECT trial, key, score_u, y FROM {both}"))


def _curves():
    w, u = _w("net")
    uni = _sampled(w, sampling.uniform_distinct, w.budget)
    wei = _sampled(w, sampling.weighted_cdf, w.budget)
    for suffix, run, pick in (("", uni, lambda t: t.uniform_distinct(w.budget)), ("_weighted", wei, lambda t: t.weighted_cdf(w.budget))):
        t = Twin(u)
        register(f"curve_recall{suffix}", lambda s, d, run=run: estimators.recall_curve(run(s, d)), t.done(f"SELECT trial, score_u, cum_pos, cum_all FROM {t.curves(pick(t))}"))
        t = Twin(u)
        register(f"curve_precision{suffix}", lambda s, d, run=run: estimators.precision_curve(run(s, d)).withColumn("precision", F.round("precision", 6)),
                 t.done(f"SELECT trial, score_u, round(cum_pos / cum_all, 6) AS precision FROM {t.curves(pick(t))}"))
    t = Twin(u)
    smp = t.weighted_cdf(w.budget)
    register("importance_mean_vs_true", lambda s, d: estimators.importance_mean(wei(s, d)).select(F.round("mean", 6).alias("estimate")).crossJoin(
        w.truth(s, d).agg(F.round(F.avg("y"), 6).alias("true_mean"))), t.done(
        f"SELECT round(sum(mult * r_u * y) / sum(mult) / 1000000, 6) AS estimate, (SELECT round(avg(y), 6) FROM u) AS true_mean FROM {smp} GROUP BY trial"))


TAU_SPECS: dict[str, tuple[str, dict]] = {
    "tau_raw_recall": ("net", {"goal": "recall", "method": "uniform_raw"}),
    "tau_raw_precision": ("net", {"goal": "precision", "method": "uniform_raw"}),
    "tau_uniform_recall": ("net", {"goal": "recall", "method": "uniform"}),
    "tau_uniform_iid_recall": ("rare", {"goal": "recall", "method": "uniform", "draws": "iid"}),
    "tau_uniform_precision": ("chat", {"goal": "precision", "method": "uniform", "target": 0.75}),
    "tau_weighted_recall": ("net", {"goal": "recall", "method": "weighted"}),
    "tau_linear_recall": ("net", {"goal": "recall", "method": "weighted", "exponent": 1.0}),
    "tau_weighted_recall_rare": ("rare", {"goal": "recall", "method": "weighted"}),
    "tau_onestage_precision": ("net", {"goal": "precision", "method": "onestage", "target": 0.75}),
    "tau_twostage_precision": ("net", {"goal": "precision", "method": "twostage", "target": 0.75}),
    "tau_twostage_plain": ("net", {"goal": "precision", "method": "twostage", "target": 0.75, "stage2_weighting": "plain"}),
    "tau_twostage_actual_terms": ("bulk", {"goal": "precision", "method": "twostage", "target": 0.75, "union_terms": "actual"}),
    "tau_bound_hoeffding": ("net", {"goal": "recall", "method": "uniform", "bound": "hoeffding"}),
    "tau_bound_bootstrap": ("chat", {"goal": "recall", "method": "uniform", "bound": "bootstrap"}),
    "tau_bound_bootstrap_weighted": ("rare", {"bound": "bootstrap"}),
    "tau_bound_bootstrap_precision": ("chat", {"goal": "precision", "method": "uniform", "bound": "bootstrap", "target": 0.75}),
    "tau_printed_overflow": ("rare", {"overflow": "sample_min"}),
    "tau_bound_clopper": ("chat", {"goal": "recall", "method": "uniform", "bound": "clopper_pearson"}),
    "tau_bound_clopper_precision": ("chat", {"goal": "precision", "method": "uniform", "bound": "clopper_pearson", "target": 0.75}),
    "tau_bound_student": ("chat", {"goal": "precision", "method": "uniform", "bound": "student", "target": 0.75}),
}


def _taus():
    for name, (wn, kw) in TAU_SPECS.items():
        w, u = _w(wn)
        s = _spec(w, **kw)
        t = Twin(u)
        sql = None if s.bound not in ("normal", "hoeffding", "bootstrap") else t.done(f"SELECT trial, tau_u, target_u, n_labels, flag FROM {t.estimate(s, TRIALS)[0]}")
        register(name, lambda sp, d, w=w, s=s: runner.estimate(w.scored(sp, d), w.oracle, s, TRIALS)[0], sql)
    w, u = _w("beta_2")
    for name, field, values in (("tau_mix_sweep", "mix", (0.1, 0.3, 0.5)), ("tau_step_sweep", "step", (100, 300, 500))):
        goal = {"goal": "recall", "method": "weighted"} if field == "mix" else {"goal": "precision", "method": "onestage", "target": 0.75}
        specs = [_spec(w, **goal, **{field: v}) for v in values]
        t = Twin(u)
        register(name, lambda sp, d, w=w, specs=specs, field=field: reduce(DataFrame.union, [runner.estimate(w.scored(sp, d), w.oracle, s, 2)[0].select(
            F.lit(float(getattr(s, field))).alias("value"), "trial", "tau_u", "target_u") for s in specs]),
            t.done(" UNION ALL ".join(f"SELECT {float(getattr(s, field))!r}::DOUBLE AS value, trial, tau_u, target_u FROM {t.estimate(s, 2)[0]}" for s in specs)))


ANSWERS: dict[str, tuple[str, dict]] = {
    "answer_pii_recall": ("pii", {}), "answer_pii_precision": ("pii", {"goal": "precision", "method": "twostage", "target": 0.75}),
    "answer_net_recall": ("net", {}), "answer_net_precision": ("net", {"goal": "precision", "method": "twostage"}), "answer_rare_recall": ("rare", {}),
    "answer_bulk_recall": ("bulk", {}), "answer_tox_recall": ("tox", {}), "answer_junk_recall": ("junk", {}), "answer_audit_recall": ("audit", {}),
    "answer_leak_recall": ("leak", {}), "answer_vec_recall": ("vec", {}), "answer_chat_precision": ("chat", {"goal": "precision", "method": "uniform", "target": 0.75}),
    "answer_page_recall": ("page", {}), "answer_drop_negatives": ("net", {"drop_known_negatives": True}),
}


def _answers():
    for name, (wn, kw) in ANSWERS.items():
        w, u = _w(wn)
        s = _spec(w, **kw)
        t = Twin(u)
        register(name, lambda sp, d, w=w, s=s: runner.run(w.scored(sp, d), w.oracle, s).rows.select("key", "score_u"), t.done(t.answer(s)))
    w, u = _w("rare")
    t = Twin(u)
    register("answer_joint", lambda sp, d: runner.select_both(w.scored(sp, d), w.oracle, _spec(w)).select("key", "score_u"),
             t.done(f"SELECT a.key, a.score_u FROM ({t.answer(_spec(w))}) a JOIN u ON a.key = u.key WHERE u.y = 1"))
    register("answer_exhaustive", lambda sp, d: runner.run(w.scored(sp, d), w.oracle, _spec(w, method="exhaustive")).rows.select("key", "score_u"), f"SELECT key, score_u FROM ({u}) WHERE y = 1")
    register("answer_everything", lambda sp, d: runner.run(w.scored(sp, d), w.oracle, _spec(w, method="everything")).rows.select("key", "score_u"), f"SELECT key, score_u FROM ({u})")
    register("answer_nothing", lambda sp, d: runner.run(w.scored(sp, d), w.oracle, _spec(w, method="nothing")).rows.select("key", "score_u"), f"SELECT key, score_u FROM ({u}) WHERE false")
    register("answer_signal_only", lambda sp, d: runner.signal_only(w.scored(sp, d), 500_000).select("key", "score_u"), f"SELECT key, score_u FROM ({u}) WHERE score_u >= 500000")
    statement = ("SELECT * FROM certified_select(source => 'rare', goal => 'recall', level => 95, confidence => 95, labels => 1000)")
    t = Twin(u)
    register("answer_sql_surface", lambda sp, d: sqlfront.execute(sp, statement, d).select("key", "score_u"), t.done(t.answer(_spec(w, target=0.95, delta=0.05, budget=1000))))
    t = Twin(u)
    a, b = _spec(w), _spec(w, method="uniform")
    both = lambda sp, d: [runner.run(w.scored(sp, d), w.oracle, s).rows for s in (a, b)]
    register("answer_diff", lambda sp, d: measures.diff(*both(sp, d)), t.done(
        f"SELECT coalesce(a.key, b.key) AS key, CASE WHEN b.key IS NULL THEN 'first' ELSE 'second' END AS side FROM ({t.answer(a)}) a FULL JOIN ({t.answer(b)}) b ON a.key = b.key WHERE a.key IS NULL OR b.key IS NULL"))
    t = Twin(u)
    register("setop_common_answers", lambda sp, d: (lambda x: x[0].select("key").intersect(x[1].select("key")))(both(sp, d)),
             t.done(f"SELECT key FROM ({t.answer(a)}) INTERSECT SELECT key FROM ({t.answer(b)})"))
    t = Twin(u)
    register("setop_extra_answers", lambda sp, d: (lambda x: x[1].select("key").exceptAll(x[0].select("key")))(both(sp, d)),
             t.done(f"SELECT key FROM ({t.answer(b)}) EXCEPT ALL SELECT key FROM ({t.answer(a)})"))
    t = Twin(u)
    register("proxy_blend", lambda sp, d: _blended(sp, d), "SELECT p.key, CAST((p.score_u + l.score_u) // 2 AS BIGINT) AS mean_u, greatest(p.score_u, l.score_u) AS most_u FROM "
             f"({UNIVERSE['pii']}) p JOIN ({UNIVERSE['leak']}) l ON p.key = l.key")


def _blended(spark, sf_dir):
    p, l = ALL["pii"].scored(spark, sf_dir).select("key", "score_u"), ALL["leak"].scored(spark, sf_dir).select("key", F.col("score_u").alias("other"))
    j = p.join(l, "key")
    return j.select("key", F.floor(runner.blend(F.col("score_u"), F.col("other"))).cast("long").alias("mean_u"), runner.blend(F.col("score_u"), F.col("other"), how="max").alias("most_u"))


def _measures():
    w, u = _w("net")
    truth = w.truth
    s = _spec(w)
    t = Twin(u)
    six = "CASE WHEN size > 0 THEN round(hits / size, 6) ELSE 1.0 END AS precision, CASE WHEN matches > 0 THEN round(hits / matches, 6) ELSE 1.0 END AS recall"
    ans = t.add(t.answer(s))
    register("achieved_metrics", lambda sp, d: measures.answer_metrics(runner.run(w.scored(sp, d), w.oracle, s).rows, truth(sp, d)), t.done(
        f"SELECT size, hits, matches, {six} FROM (SELECT (SELECT count(*) FROM {ans}) AS size, (SELECT sum(y)::BIGINT FROM u WHERE key IN (SELECT key FROM {ans})) AS hits, (SELECT sum(y)::BIGINT FROM u) AS matches)"))
    raw = _spec(w, method="uniform_raw")
    t = Twin(u)
    register("failure_rate", lambda sp, d: trials.compare(truth(sp, d), {"unguaranteed": raw, "guaranteed": s}, TRIALS),
             t.done(t.failure("unguaranteed", raw, TRIALS) + " UNION ALL " + t.failure("guaranteed", s, TRIALS)))
    t = Twin(u)
    m = t.add(f"SELECT precision AS v FROM {t.achieved(*t.estimate(raw.but(goal='recall'), TRIALS))}")
    q = t.add(f"SELECT quantile_cont(v, 0.25) AS q1, quantile_cont(v, 0.5) AS median, quantile_cont(v, 0.75) AS q3 FROM {m}")
    inside = "v >= q1 - 1.5 * (q3 - q1) AND v <= q3 + 1.5 * (q3 - q1)"
    register("boxplot", lambda sp, d: measures.boxplot(trials.trial_metrics(w.scored(sp, d), w.oracle, truth(sp, d), raw, TRIALS), "precision"), t.done(
        f"SELECT round(min(v), 6) AS least, round(max(q1), 6) AS q1, round(max(median), 6) AS median, round(max(q3), 6) AS q3, round(max(v), 6) AS most, round(min(CASE WHEN {inside} THEN v END), 6) AS low_whisker, "
        f"round(max(CASE WHEN {inside} THEN v END), 6) AS high_whisker FROM {m}, {q}"))
    v = "SELECT avg(score_u / 1000000.0::DOUBLE) AS m, avg(sqrt(score_u / 1000000.0::DOUBLE)) AS r, avg((score_u > 0)::INTEGER) AS z FROM"
    for name in EVERY_WORKLOAD:
        wn, un = _w(name)
        key = name.replace(".0", "")
        register(f"calibration_{key}", lambda sp, d, wn=wn: measures.calibration(wn.truth(sp, d)), f"SELECT CAST(least(9, floor(score_u * 10 / 1000000::DOUBLE)) AS BIGINT) AS bucket, count(*) AS n, round(avg(y), 6) AS rate FROM ({un}) GROUP BY 1")
        register(f"variance_gain_{key}", lambda sp, d, wn=wn: measures.variance_parts(wn.scored(sp, d)),
                 f"SELECT round(m, 6) AS uniform_v, round(z * m, 6) AS linear_v, round(r * r, 6) AS root_v, round(m - r * r, 6) AS uniform_gap, round(z * m - r * r, 6) AS linear_gap FROM ({v} ({un}))")
        register(f"sharpness_{key}", lambda sp, d, wn=wn: measures.sharpness(wn.scored(sp, d)), f"SELECT round(stddev_pop(score_u / 1000000::DOUBLE), 6) AS score_sd, count(*) AS n FROM ({un})")
        register(f"positive_rate_{key}", lambda sp, d, wn=wn: measures.positive_rate(wn.truth(sp, d)), f"SELECT count(*) AS n, sum(y)::BIGINT AS matches, round(avg(y), 6) AS rate FROM ({un})")
    register("calibration_monotone", lambda sp, d: measures.is_monotone(measures.calibration(truth(sp, d))),
             f"WITH c AS (SELECT CAST(least(9, floor(score_u * 10 / 1000000::DOUBLE)) AS BIGINT) AS bucket, round(avg(y), 6) AS rate FROM ({u}) GROUP BY 1) SELECT coalesce(min((rate >= b)::INTEGER), 1) AS monotone FROM (SELECT rate, coalesce(lag(rate) OVER (ORDER BY bucket), 0) AS b FROM c)")
    register("frontier_histogram", lambda sp, d: measures.histogram(truth(sp, d)), f"SELECT score_u, count(*) AS n, sum(y)::BIGINT AS n_pos FROM ({u}) GROUP BY score_u")
    p, up = _w("pii")
    sp_ = _spec(p)
    t = Twin(up)
    a = t.add(t.answer(sp_))
    register("cube_metrics_by_lang_source", lambda sp, d: _cube(sp, d, p, sp_), t.done(
        f"SELECT lang, source, count(*) AS size, sum(y)::BIGINT AS hits FROM {a} a JOIN (SELECT u.key, y, lang, source FROM u JOIN documents ON key = doc_id) USING (key) GROUP BY CUBE (lang, source)"))
    # cost: prices and rates as published; sizes are those of the workloads
    one = lambda name, wn, b: (f"SELECT '{name}' AS dataset, n, {cost_sql('n', b)} FROM (SELECT count(*) AS n FROM ({_w(wn)[1]}))")
    register("cost_breakdown", lambda sp, d: _costs(sp, d), " UNION ALL ".join(one(wn.replace(".0", ""), wn, _w(wn)[0].budget) for wn in EVERY_WORKLOAD))


def cost_sql(n: str, budget: int) -> str:
    parts = f"(0.09::DOUBLE / 3600 * 3.06::DOUBLE), ({n} / 1000.0::DOUBLE / 3600 * 3.06::DOUBLE), ({budget} * 0.08::DOUBLE)"
    a, b, c = parts.split(", ")
    return (f"round({a}, 6) AS sampling, round({b}, 6) AS proxy, round({c}, 6) AS oracle, round({a} + {b} + {c}, 6) AS total, round({n} * 0.08::DOUBLE, 6) AS exhaustive, "
            f"round({n} * 0.08::DOUBLE / ({a} + {b} + {c}), 4) AS gain")


def _costs(spark, sf_dir):
    parts = []
    for wn in EVERY_WORKLOAD:
        w = _w(wn)[0]
        n = w.scored(spark, sf_dir).agg(F.count("*").alias("n"))
        parts.append(n.select(F.lit(wn.replace(".0", "")).alias("dataset"), "n", *measures.cost_columns(F.col("n"), w.budget, 1000.0)))
    return reduce(DataFrame.union, parts)


def _cube(spark, sf_dir, w, s):
    base = w.scored(spark, sf_dir)
    rows = w.oracle(runner.run(base, w.oracle, s).rows)
    return rows.cube("lang", "source").agg(F.count("*").alias("size"), F.sum("y").alias("hits"))


# experiments, few trials each
def _compare(name: str, wn: str, specs: dict[str, SelectionSpec], n: int = 3):
    w, u = _w(wn)
    t = Twin(u)
    register(name, lambda sp, d: trials.compare(w.truth(sp, d), specs, n), t.done(" UNION ALL ".join(t.failure(k, s, n) for k, s in specs.items())))


def _experiments():
    for wn in TRIAL_WORKLOADS:
        w, key = _w(wn)[0], wn.replace(".0", "")
        for x, goal, method in (("x1_precision_trials", "precision", "twostage"), ("x2_recall_trials", "recall", "weighted")):
            _compare(f"{x}_{key}", wn, {"unguaranteed": _spec(w, goal=goal, method="uniform_raw"), "guaranteed": _spec(w, goal=goal, method=method)}, FULL_TRIALS)
    for wn in EVERY_WORKLOAD:
        w, key = _w(wn)[0], wn.replace(".0", "")
        _compare(f"x4_precision_sweep_{key}", wn, {f"{m} {g}": _spec(w, goal="precision", method=m, target=g) for g in (0.75, 0.8, 0.9, 0.95, 0.99) for m in ("uniform", "onestage", "twostage")}, 2)
        _compare(f"x5_recall_sweep_{key}", wn, {f"{m} {g}": _spec(w, target=g, method="uniform" if m == "uniform" else "weighted", exponent=1.0 if m == "linear" else 0.5)
                                              for g in (0.5, 0.6, 0.7, 0.75, 0.8, 0.9, 0.95) for m in ("uniform", "linear", "sqrt")}, 2)
    for sigma in (0.01, 0.02, 0.03, 0.04):
        w, u = _synth(0.01, 2.0, sigma)
        specs = {f"{m} {g}": _spec(w, goal=g, target=t, method=m) for g, t, ms in (("precision", 0.95, ("uniform", "twostage")), ("recall", 0.9, ("uniform", "weighted"))) for m in ms}
        t = Twin(u)
        register(f"x6_noise_{int(sigma * 100)}", lambda sp, d, w=w, specs=specs: trials.compare(w.truth(sp, d), specs, 2), t.done(" UNION ALL ".join(t.failure(k, s, 2) for k, s in specs.items())))
    for beta in (0.125, 0.25, 0.5, 1.0, 2.0):
        w, u = _synth(0.01, beta)
        _compare(f"x7_imbalance_{str(beta).replace('.', '_')}", f"beta_{beta}", {f"{m} {g}": _spec(w, goal=g, target=t, method=m) for g, t, ms in (
            ("precision", 0.95, ("uniform", "twostage")), ("recall", 0.9, ("uniform", "weighted"))) for m in ms}, 2)
    w = _w("beta_2.0")[0]
    _compare("x8_step", "beta_2.0", {f"step {m}": _spec(w, goal="precision", method="twostage", step=m) for m in (100, 200, 300, 400, 500)}, 2)
    _compare("x8_mix", "beta_2.0", {f"mix {m}": _spec(w, mix=m) for m in (0.1, 0.2, 0.3, 0.4, 0.5)}, 2)
    _compare("x9_exponent", "beta_2.0", {f"exponent {p}": _spec(w, exponent=p) for p in (0.0, 0.25, 0.5, 0.75, 1.0)}, 2)
    w1 = _w("beta_1.0")[0]
    _compare("x10_bounds", "beta_1.0", {f"{m} {b}": _spec(w1, method=m, bound=b) for b in ("normal", "hoeffding", "bootstrap") for m in ("uniform", "weighted")}, 2)
    other = {"uniform clopper_pearson": _spec(w1, method="uniform", bound="clopper_pearson"), "uniform student": _spec(w1, method="uniform", bound="student"), "weighted student": _spec(w1, bound="student")}
    register("x10_bounds_sampled", lambda sp, d: trials.compare(w1.truth(sp, d), other, 2))
    _compare("x14_use_case_rare", "rare", {"rare recall 90": _spec(ALL["rare"])}, TRIALS)
    _compare("x14_use_case_audit", "audit", {"audit recall 90": _spec(ALL["audit"])}, TRIALS)
    _compare("x14_use_case_discovery", "pii", {"recall 90": _spec(ALL["pii"]), "precision 75": _spec(ALL["pii"], goal="precision", method="twostage", target=0.75)}, TRIALS)
    _compare("x14_example_statement", "net", {"recall 95": _spec(ALL["net"], target=0.95, budget=10_000)}, 2)


def _drift_sql(fit: str, apply: str, s: SelectionSpec, n: int, name: str) -> str:
    t = Twin(apply)
    f = t.add(fit, "fit_u")
    sample = t.add(f"SELECT 0 AS trial, key, score_u, y, 1::BIGINT AS mult, 1000000::BIGINT AS r_u FROM {f}")
    tau = (t.raw_recall if s.goal == "recall" else t.raw_precision)(sample, s.target)
    none = t.add("SELECT 0 AS trial, key, score_u, y FROM u WHERE false")
    return t.done(f"SELECT '{name}' AS dataset, '{s.goal}' AS goal, {s.target!r}::DOUBLE AS target, round(raw, 6) AS frozen, refit, round({s.target!r}::DOUBLE - raw, 6) AS frozen_gap FROM "
                  f"(SELECT (SELECT {s.goal} FROM {t.achieved(tau, none)}) AS raw, (SELECT round(avg({s.goal}), 6) FROM {t.achieved(*t.estimate(s, n))}) AS refit)")


def _drifts():
    j, uj = ALL["junk_ascii"], UNIVERSE["junk_ascii"]
    lang = lambda en: lambda sp, d: j.scored(sp, d).where(F.col("lang") == "en" if en else F.col("lang") != "en")
    net, un = ALL["net"], UNIVERSE["net"]
    year = lambda old: lambda sp, d: net.scored(sp, d).where((F.year("l_shipdate") < SPLIT_YEAR) == old)
    b1, u1 = _synth(0.01, 1.0)
    b2, u2 = _synth(0.01, 2.0)
    for goal, method in (("recall", "weighted"), ("precision", "twostage")):
        cases = {
            "lang": (j, lang(True), lang(False), f"SELECT key, score_u, y FROM ({uj}) WHERE lang = 'en'", f"SELECT key, score_u, y FROM ({uj}) WHERE lang <> 'en'", _spec(j, goal=goal, method=method, target=0.95, budget=120)),
            "years": (net, year(True), year(False), f"SELECT key, score_u, y FROM ({un}) WHERE part < {SPLIT_YEAR}", f"SELECT key, score_u, y FROM ({un}) WHERE part >= {SPLIT_YEAR}", _spec(net, goal=goal, method=method, target=0.95)),
            "synth": (b2, b1.scored, b2.scored, u1, u2, _spec(b2, goal=goal, method=method, target=0.95)),
        }
        for name, (w, fit, apply, fs, as_, s) in cases.items():
            fit_oracle = b1.oracle if name == "synth" else w.oracle
            register(f"x3_drift_{name}_{goal}", lambda sp, d, w=w, fit=fit, apply=apply, s=s, name=name, fo=fit_oracle: trials.drift(
                fo(fit(sp, d)), w.oracle(apply(sp, d)), s, 3, name), _drift_sql(fs, as_, s, 3, name))


def _coverage():
    """Measures and user hooks beside the experiments."""
    for wn in ("net", "rare", "beta_2.0"):
        w, u = _w(wn)
        key = wn.replace(".0", "")
        t = Twin(u)
        for goal, base, ours in (("recall", "uniform", "weighted"), ("precision", "uniform", "twostage")):
            a, b = _spec(w, goal=goal, method=base), _spec(w, goal=goal, method=ours)
            t = Twin(u)
            parts = f"({t.failure('base', a, TRIALS)}) a, ({t.failure('ours', b, TRIALS)}) b"
            register(f"gain_factor_{goal}_{key}", lambda sp, d, w=w, a=a, b=b: measures.gain_factor(trials.compare(w.truth(sp, d), {"base": a, "ours": b}, TRIALS), "base", "ours"),
                     t.done(f"SELECT a.target, a.quality AS base_quality, b.quality AS quality, CASE WHEN a.quality > 0 THEN round(b.quality / a.quality, 4) END AS gain FROM {parts}"))
        t = Twin(u)
        smp = t.weighted_cdf(w.budget)
        register(f"calibration_weighted_{key}", lambda sp, d, w=w: measures.calibration_of_sample(_sampled(w, sampling.weighted_cdf, w.budget)(sp, d)), t.done(
            f"SELECT CAST(least(9, floor(score_u * 10 / 1000000::DOUBLE)) AS BIGINT) AS bucket, sum(mult)::BIGINT AS draws, round(sum(mult * r_u * y)::DOUBLE / sum(mult * r_u), 6) AS rate FROM {smp} GROUP BY 1"))
    w, u = _w("beta_2.0")
    noise = (0.01, 0.02, 0.03, 0.04)
    register("noise_share", lambda sp, d: measures.noise_share(w.scored(sp, d), noise), " UNION ALL ".join(
        f"SELECT {s!r}::DOUBLE AS noise, round(100 * {s!r}::DOUBLE / stddev_pop(score_u / 1000000::DOUBLE), 4) AS percent FROM ({u})" for s in noise))
    r, ur = _w("rare")
    t = Twin(ur)
    register("answer_callback_ledger", lambda sp, d: callbacks.replay(sp, d, _spec(r)), t.done(
        f"SELECT key, score_u, true AS same_again, (SELECT count(DISTINCT key) FROM {t.estimate(_spec(r))[1]}) AS calls, 0::BIGINT AS calls_again FROM ({t.answer(_spec(r))})"))
    t = Twin(ur)
    register("grid_candidates", lambda sp, d: callbacks.grid(sp, d, 1000, 100), t.done(
        f"SELECT CAST(k // 100 AS INTEGER) AS candidate, CAST(k AS INTEGER) AS draws, score_u FROM (SELECT score_u, row_number() OVER (ORDER BY score_u DESC, key) AS k FROM {t.uniform_distinct(1000)}) WHERE k % 100 = 0"))
    register("stream_sliding", lambda sp, d: refit.replay_counts(sp, d, refit.sliding_counts), "SELECT strftime(start, '%Y-%m-%d') AS start, event_type, count(*) AS n FROM "
             "(SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS start FROM events) GROUP BY 1, 2")
    register("stream_sessions", lambda sp, d: refit.replay_counts(sp, d, refit.session_counts, "user_id"), """SELECT strftime(min(ts), '%Y-%m-%d') AS start, user_id, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session
 FROM (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))) GROUP BY user_id, session""")
    register("stream_running_matches", lambda sp, d: refit.replay_running(sp, d), "SELECT event_type, count(*) AS n, max(value) AS most FROM events GROUP BY event_type")
    register("current_cut", lambda sp, d: refit.apply_current(r.scored(sp, d), sp.createDataFrame([(1, 900_000), (2, 700_000)], "fitted_at int, tau_u long")).select("key", "score_u"),
             f"SELECT key, score_u FROM ({ur}) WHERE score_u >= 700000")


def _surrounding():
    from certsel.operators import relational as rel

    for name, (run, sql) in rel.QUERIES.items():
        register(name, run, sql)
    register("stream_refit", lambda sp, d: refit.replay(sp, d))


for _part in (_scores, _samples, _curves, _taus, _answers, _measures, _experiments, _drifts, _coverage, _surrounding):
    _part()
