"""Headline queries, timed: one JSON line on stdout.

BENCH_SF_DIR (default /root/testdata/sf0.1) and BENCH_CPUS (default 8) choose input and cores.
Every figure is the best of two runs after a warm-up of the session.
"""

import json
import os
import sys
import time

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession

    from dpsynth import fixtures, synth
    from dpsynth import workload as wl
    from dpsynth.operators import marginals as mg
    from dpsynth.privacy.accountant import ApproxDP

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    noop = lambda df: df.write.format("noop").mode("overwrite").save()

    def f1(k: int):
        codes, spec = fixtures.load(spark, SF, "F1")
        return codes, spec, wl.all_kway(spec, k).closure()

    def store() -> None:
        codes, spec, sets = f1(3)
        s = mg.MarginalStore.build(codes, spec, sets)
        s.dense((0,))
        s.close()

    def pairs() -> None:
        codes, spec, sets = f1(2)
        noop(mg.marginals(codes, spec, sets))

    def inline() -> None:
        codes, spec, sets = f1(1)
        noop(mg.marginals(codes, spec, sets, "inline"))

    def adaptive() -> None:
        codes, spec = fixtures.load(spark, SF, "F2")
        noop(synth.synthesize(codes, spec, wl.all_kway(spec, 3), ApproxDP(10.0), "adaptive", synth.AdaptiveConfig(seed=0, cap_mb=2.0)).generate(spark))

    def independent() -> None:
        codes, spec = fixtures.load(spark, SF, "F1")
        noop(synth.synthesize(codes, spec, wl.all_kway(spec, 1), ApproxDP(10.0), "independent", synth.AdaptiveConfig(seed=0)).generate(spark))

    runs = {"encode_F1": lambda: noop(fixtures.load(spark, SF, "F1")[0]), "marginals_F1_all2": pairs, "marginals_inline_F1_all1": inline, "store_F1_all3": store, "independent_F1": independent, "adaptive_F2_all3": adaptive}
    try:
        from dpsynth.llm import registry

        runs |= {name: (lambda q=run: noop(q(spark, SF))) for name, (run, _) in registry.REGISTERED.items()}
    except ImportError:
        pass
    noop(fixtures.load(spark, SF, "F7")[0])
    took = {}
    for name, run in runs.items():
        best = None
        for _ in range(2):
            began = time.perf_counter()
            run()
            now = time.perf_counter() - began
            best = now if best is None else min(best, now)
        took[name] = round(best, 3)
        print(name, took[name], file=sys.stderr)
    lines = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF.rsplit("sf", 1)[-1], "store_rows_per_s": round(lines / took["store_F1_all3"])}))


if __name__ == "__main__":
    main()
