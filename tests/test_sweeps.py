from certsel.plans import queries as q


def test_targets_and_workloads_of_the_survey():
    for wn in (*q.ALL, "beta_1", "beta_2"):
        for x in ("x4_precision_sweep", "x5_recall_sweep", "calibration", "variance_gain"):
            assert f"{x}_{wn}" in q.QUERIES
        for x, targets in (("x4_precision_sweep", "0.75 0.8 0.9 0.95 0.99"), ("x5_recall_sweep", "0.5 0.6 0.7 0.75 0.8 0.9 0.95")):
            assert all(f"'uniform {g}'" in q.SQL[f"{x}_{wn}"] for g in targets.split())
    for wn in ("pii", "rare", "net", "bulk", "junk", "beta_1", "beta_2"):
        assert f"x1_precision_trials_{wn}" in q.QUERIES and f"x2_recall_trials_{wn}" in q.QUERIES
    assert q.FULL_TRIALS == 100
