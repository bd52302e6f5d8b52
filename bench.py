"""Headline runs at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from certsel.operators import costs, measures, runner, trials  # noqa: E402
from certsel.session import local_session  # noqa: E402
from certsel.sources import workloads  # noqa: E402
from certsel.spec import SelectionSpec  # noqa: E402

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
TRIALS = int(os.environ.get("BENCH_TRIALS", "100"))
RUNS = {
    "net_recall_90": (workloads.ALL["net"], SelectionSpec(budget=10_000)),
    "net_precision_90": (workloads.ALL["net"], SelectionSpec(goal="precision", method="twostage", budget=10_000)),
    "synth_1_recall_90": (workloads.synthetic(0.01, 1.0), SelectionSpec(budget=10_000)),
    "synth_2_precision_90": (workloads.synthetic(0.01, 2.0), SelectionSpec(goal="precision", method="twostage", budget=10_000)),
    "pii_recall_90": (workloads.ALL["pii"], SelectionSpec(budget=1_000)),
}
#: Trials on one labelled universe: unguaranteed, uniform with bounds (the base of gain factors) and weighted.
TRIAL_RUNS = {
    "net_recall": ("net_recall_90", {"unguaranteed": {"method": "uniform_raw"}, "uniform": {"method": "uniform"}, "guaranteed": {}}),
    "net_precision": ("net_precision_90", {"unguaranteed": {"method": "uniform_raw"}, "uniform": {"method": "uniform"}, "guaranteed": {}}),
    "synth_1_recall": ("synth_1_recall_90", {"uniform": {"method": "uniform"}, "linear": {"exponent": 1.0}, "guaranteed": {}}),
}


def main() -> None:
    spark = local_session()
    seconds, detail = {}, {}
    for name, (w, spec) in RUNS.items():
        with costs.taken(spark) as t:
            picked = runner.run(w.scored(spark, SF), w.oracle, spec)
            m = measures.answer_metrics(picked.rows, w.truth(spark, SF)).first()
            labels = picked.sample.select("key").distinct().count()
        flag = picked.cut.first()["flag"] if picked.cut is not None else "exhaustive"
        seconds[name] = t.seconds
        detail[name] = {"rows": m["size"], "precision": m["precision"], "recall": m["recall"], "labels": labels, "flag": flag, "rows_read": t.rows_read, "shuffle_mb": round(t.shuffle_bytes / 1e6, 1)}
    for name, (of, methods) in TRIAL_RUNS.items() if TRIALS else ():
        w, spec = RUNS[of]
        with costs.taken(spark) as t:
            rates = {r["method"]: r for r in trials.compare(w.truth(spark, SF), {k: spec.but(**kw) for k, kw in methods.items()}, TRIALS).collect()}
        seconds[f"trials_{name}"] = t.seconds
        base = rates["uniform"]["quality"]
        for k, r in rates.items():
            detail[f"trials_{name}_{k}"] = {"trials": r["n_trials"], "failure_rate": r["failure_rate"], "quality": r["quality"], "gain": round(r["quality"] / base, 3) if base else None}
    print(json.dumps({"metric": "total seconds of headline runs", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "detail": detail, "sf": os.path.basename(SF)}))


if __name__ == "__main__":
    main()
