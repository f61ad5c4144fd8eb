"""python -m dpsynth: synthesize a fixture, or run a grid of experiments."""

from __future__ import annotations

import argparse


def main() -> None:
    p = argparse.ArgumentParser(prog="dpsynth", description=__doc__)
    p.add_argument("command", choices=["synthesize", "grid", "summary"])
    p.add_argument("--data", required=True, help="folder of the given tables")
    p.add_argument("--fixture", nargs="+", default=["F7"])
    p.add_argument("--workload", nargs="+", default=["all3"], choices=["all3", "all2", "target", "skewed"])
    p.add_argument("--mechanism", nargs="+", default=["adaptive"])
    p.add_argument("--epsilon", nargs="+", type=float, default=[1.0])
    p.add_argument("--trials", type=int, default=1)
    p.add_argument("--cap-mb", type=float, default=80.0)
    p.add_argument("--whole", action="store_true", help="grid: all nine budgets, every mechanism and ablation, five trials")
    p.add_argument("--folder", help="grid: shared folder of results; runs found there are not made again")
    p.add_argument("--out", help="folder for the synthetic records, which must not exist")
    a = p.parse_args()

    from pyspark.sql import SparkSession

    from dpsynth import encode, fixtures, synth
    from dpsynth.experiments import grid
    from dpsynth.privacy.accountant import ApproxDP
    from dpsynth.sources.tables import write_as

    spark = SparkSession.builder.appName("dpsynth").getOrCreate()
    cfg = synth.AdaptiveConfig(cap_mb=a.cap_mb)
    if a.command == "summary":
        grid.fixture_summary(spark, a.data, a.fixture).show(truncate=False)
    elif a.command == "grid":
        epsilons, mechanisms, trials = (grid.EPSILONS, [*synth.MECHANISMS, "gen_mix_query", *synth.ABLATIONS], 5) if a.whole else (a.epsilon, a.mechanism, a.trials)
        grid.run_grid(spark, a.data, a.fixture, a.workload, epsilons, mechanisms, trials, cfg, a.folder).show(1000, truncate=False)
    else:
        codes, spec = fixtures.load(spark, a.data, a.fixture[0])
        w = grid.workload_of(spec, a.workload[0], grid.target_of(a.fixture[0], spec))
        r = synth.synthesize(codes, spec, w, ApproxDP(a.epsilon[0]), a.mechanism[0], cfg)
        records = encode.decode(r.generate(spark), spec)
        if a.out:
            write_as(records, a.out)
        else:
            records.show()
        print(r.stats)


if __name__ == "__main__":
    main()
