"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: prints one JSON line. Each time is the mean of
three runs after one that warms up; rates are multiplications a second."""

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
SF, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession

    from rowproduct import multiply
    from rowproduct.operators import baselines, graphs
    from rowproduct.plans.work import total_work
    from rowproduct.sources import builders as b
    from rowproduct.sources.synth import synth
    from rowproduct.study import timed

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "20g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    held = {}

    def matrix(name):
        if name not in held:
            m = synth(spark, *name) if isinstance(name, tuple) else b.BUILDERS[name](spark, SF)
            held[name] = m.with_df(m.df.persist())
            held[name].df.count()
        return held[name]

    def square(name, **o):
        m = matrix(name)
        return lambda: multiply(m, m, **o).df

    follow, dense = "part_follow", "supplier_follow"
    plans = {
        "square_part_follow_local": (follow, square(follow, lowering="rowlocal")),
        "square_part_follow_joinagg": (follow, square(follow, lowering="joinagg")),
        "square_part_follow_rowfetch": (follow, square(follow, lowering="rowfetch")),
        "square_part_follow_sortagg": (follow, square(follow, accumulator="sortagg", order="sorted", lowering="rowlocal")),
        "square_part_follow_plain": (follow, lambda m=matrix(follow): baselines.plain(m, m)),
        "square_part_follow_plain_sorted": (follow, lambda m=matrix(follow): baselines.plain(m, m, "sorted")),
        "square_supplier_follow": (dense, square(dense)),
        "square_user_next": ("user_next", square("user_next")),
    }
    for kind, scale, ef in (("uniform", 12, 4), ("uniform", 12, 16), ("skewed", 12, 4), ("skewed", 12, 16)):
        plans[f"square_{kind}_{scale}_{ef}"] = ((scale, ef, kind), square((scale, ef, kind)))
        plans[f"square_{kind}_{scale}_{ef}_sorted"] = ((scale, ef, kind), square((scale, ef, kind), order="sorted"))
    took, rates = {}, {}
    for name, (m, make) in plans.items():
        took[name] = round(timed(make, 3), 3)
        rates[name] = round(total_work(matrix(m), matrix(m)) / took[name])
    bigram = matrix("term_bigram")
    took["tall_skinny_terms_64"] = round(timed(lambda: graphs.tall_skinny(bigram, 64).df, 3), 3)
    sym = matrix("follow_sym")
    took["triangles_follow_sym"] = round(timed(lambda: graphs.triangle_count(sym), 3), 3)
    t = time.perf_counter()
    graphs.msbfs(matrix(follow), list(range(16)), 3).count()
    took["msbfs_16_sources_3_levels"] = round(time.perf_counter() - t, 3)
    gains = [took[f"square_{k}_12_{e}_sorted"] / took[f"square_{k}_12_{e}"] for k in ("uniform", "skewed") for e in (4, 16)]
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF.rsplit("sf", 1)[-1], "cpus": int(CPUS),
                      "multiplications_per_sec": rates, "sorted_over_unsorted_harmonic_mean": round(len(gains) / sum(1 / g for g in gains), 3)}))


if __name__ == "__main__":
    main()
