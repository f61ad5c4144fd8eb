"""The registered experiments use the method's own settings."""

from dpsynth.experiments import grid
from dpsynth.queries import mechanism_queries as mq
from dpsynth.synth import AdaptiveConfig


def test_experiments_use_the_default_capacity(spark, monkeypatch):
    assert mq.CFG.cap_mb == AdaptiveConfig().cap_mb == 80.0
    seen = []
    monkeypatch.setattr(grid, "synthesize_from", lambda store, w, rho, name, cfg: seen.append(cfg.cap_mb) or 1 / 0)
    try:
        grid.bound_experiment(spark, "/root/testdata/sf0.001", "F7")
    except ZeroDivisionError:
        pass
    assert seen == [80.0]


def test_whole_grids_are_registered(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(grid, "run_grid", lambda spark, sf_dir, *a: seen.append(a))
    for w in ("all3", "target", "skewed", "all2", "ablation"):
        for t in ("F1", "F2", "F3", "F4", "F5", "F6"):
            mq.QUERIES[f"x_{w}_{t}"][0](spark, "")
            names, workloads, epsilons, mechanisms, trials, cfg = seen.pop()
            assert (names, workloads, len(epsilons), trials) == ([t], ["all3" if w == "ablation" else w], 9, 5)
            assert set(mq.ABLATIONS if w == "ablation" else mq.MECHANISMS) <= set(mechanisms) and cfg == mq.CFG
    assert "x_bounds_F1" in mq.QUERIES
