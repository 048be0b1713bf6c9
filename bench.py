"""Headline queries on one machine; prints one JSON line."""

import json
import os
import sys
import time
from pathlib import Path

ROOT = str(Path(__file__).resolve().parent)
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
HEADLINE = ("cover_greedy_c1", "cover_from_sample_c1", "cover_sketch_cells_c1t", "l0_per_column_c1t", "targeted_exact_f1_u0", "general_exact_onehot_f1", "general_exact_f2", "general_rowhash_f1_1250", "general_sketch_cells_f1", "complement_exact_p2", "op_agg_cube_pairs")
RATES = (0.1, 0.2, 0.4, 0.6)


def main() -> None:
    from pyspark.sql import SparkSession

    from turnstile_cover.operators import fingerprint, targeted
    from turnstile_cover.plans import workloads
    from turnstile_cover.queries import QUERIES

    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "7g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    QUERIES["cover_greedy_c4"](spark, SF).collect()  # warm-up
    took, more = {}, {}

    def clock(name, run):
        t = time.perf_counter()
        out = run()
        took[name] = round(time.perf_counter() - t, 3)
        return out

    for name in HEADLINE:
        clock(name, lambda n=name: QUERIES[n](spark, SF).write.format("noop").mode("overwrite").save())
    # targeted, one run each: the same targets and code at every rate and at rate 1, the exact method
    for name, rates, targets in (("F1", RATES, 400), ("F2", (0.1,), 200)):
        for r in clock(f"targeted_times_{name}", lambda x=name, y=rates, z=targets: workloads.targeted_times(spark, SF, x, list(y), 7, z).collect()):
            label = "exact" if r["rate"] == 1.0 else r["rate"]
            more[f"targeted_{name}_ms_a_target_{label}"] = round(1000 * r["seconds_a_target"], 3)
            more[f"targeted_{name}_build_seconds_{label}"] = round(r["build_seconds"], 3)
            if r["rate"] < 1:
                more[f"targeted_{name}_speedup_{label}"] = round(r["speedup"], 2)
                more[f"targeted_{name}_speedup_with_build_{label}"] = round(r["speedup_with_build"], 2)
    users = workloads.WIDE["F1"](spark, SF)
    codes = clock("code_f1", users.codes)
    n = codes.df.count()
    one = clock("targeted_exact_one_user", lambda: targeted.exact(users, 0, 7, codes=codes).collect())
    more["targeted_separated_exact_pct"] = round(100 * one[-1]["total"] / (n - 1), 3) if one else None
    # general: exact once, then samples; seeds 1 to 10
    for name, sizes, k in (("F1", [300, 600, 900, 1250], 20), ("F2", [0.022, 0.073, 0.163], 10)):
        w = workloads.WIDE[name](spark, SF)
        c = codes if name == "F1" else clock("code_f2", w.codes)
        n = c.df.count()
        sizes = [s if s > 1 else round(s * n) for s in sizes]
        exact = clock(f"general_exact_{name}_k{k}", lambda: fingerprint.greedy_onehot(w, k, n, c).collect())
        for rows in sizes:
            runs = clock(f"general_{name}_rows_{rows}", lambda r=rows: fingerprint.sweep_rowhash(c, k, [r], 1, n).collect())
            picks = [(p["a"], p["v"]) for p in runs[0]["picks"]]
            ours = {r["k"]: r["separated"] for r in fingerprint.prefix_pairs(c, [(0, picks)]).collect()}
            more[f"general_{name}_ratio_{rows}"] = round(min(ours[r["round"]] / r["total"] for r in exact), 4)
            more[f"general_{name}_speedup_{rows}"] = round(took[f"general_exact_{name}_k{k}"] / took[f"general_{name}_rows_{rows}"], 1)
    print(json.dumps({"metric": "headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF, "cpus": CPUS, "measures": more}))


if __name__ == "__main__":
    main()
