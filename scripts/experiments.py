"""The published experiments at chosen size, as Markdown beside the published figures: experiments.py [REPS]"""

import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

import numpy as np
from compare import session
from pyspark.sql import functions as F

from evencube.operators import covering, designs, discrepancy, fitted, latin, strata
from evencube.workloads import experiments as e

#: Published spreads (plate: standard deviation; hundred: three integrands).
PLATE = {"srs": 1.041e-3, "lhs": 8.005e-5, "radinv": 1.194e-4, "power_lattice_latin": 1.279e-4, "padded_grid:2^3": 1.340e-4, "padded_grid:2^2.1^2": 1.207e-4, "padded_grid:4.1^2": 2.942e-4, "padded_grid_latin:2^3": 7.156e-5, "padded_grid_latin:2^2.1^2": 7.362e-5, "padded_grid_latin:4.1^2": 6.139e-5, "bsplit": 5.210e-4, "bsplit_cog": 6.102e-5, "bsplit_match": 5.71e-5}
HUNDRED = {
    "srs": (8.795, 232.97, 2955.7),
    "lhs": (6.696, 232.92, 238.17),
    "radinv": (6.529, 188.87, 781.42),
    "power_lattice_latin": (4.217, 185.5, 316.92),
    "padded_grid:2^50": (4.821, 225.29, 401.57),
    "padded_grid:4^25": (4.656, 227.34, 963.67),
    "padded_grid_latin:2^50": (4.861, 225.63, 231.19),
    "padded_grid_latin:4^25": (3.842, 226.73, 231.72),
    "bsplit": (8.767, 232.95, 2820.8),
    "bsplit_cog": (6.785, 222.47, 228.0),
    "bsplit_match:cog": (6.874, 232.47, 237.83),
    "padded_bsplit_cog:2^50": (4.878, 227.61, 233.37),
    "padded_bsplit_cog:4^25": (4.944, 230.40, 235.59),
    "padded_bsplit_match:2^50": (4.802, 230.33, 236.49),
    "padded_bsplit_match:4^25": (3.984, 227.87, 232.21),
}
CONTEST = {2: (822, 96, 102), 3: (610, 96, 314), 4: (800, 94, 126), 5: (698, 120, 202), 6: (720, 167, 133), 7: (712, 271, 37), 8: (517, 466, 37), 9: (136, 807, 77), 10: (142, 778, 100)}


#: Sizes that run times are compared over, and what is timed at each.
GROWTH = (1000, 2000, 4000, 8000)
RUNS = {
    "two-way splits, n = 6": lambda c: strata.bsplit_np(c, 6),
    "centre order, n = 2": lambda c: latin.latin_np(*strata.bsplit_np(c, 2), "cog", 1),
    "perfect matching, n = 2": lambda c: latin.latin_np(*strata.bsplit_np(c, 2), "random_greedy", 1),
    "upper bound by own strata, n = 6": lambda c: covering.upper_np(designs.srs_np(c, 6, 1), *strata.bsplit_np(c, 6)),
    "fitted partition, n = 6": lambda c: fitted.fitted_upper_np(designs.srs_np(c, 6, 1), 1, 1),
    "discrepancy by pairs, n = 6": lambda c: discrepancy.discrepancy_np(designs.srs_np(c, 6, 1)),
    "lower bound, ten probes a point, n = 6": lambda c: covering.lower_np(designs.srs_np(c, 6, 1), 10 * c, 1),
    "pick by splitting, 20 points a pick, n = 2": lambda c: fitted.pick_np(designs.srs_np(20 * c, 2, 1), c),
}


def timed(title: str, make) -> list:
    began = time.time()
    rows = make()
    print(f"\n### {title} ({time.time() - began:.0f} s)\n", flush=True)
    return rows


def main(reps: int) -> None:
    spark = session()
    spark.sparkContext.setLogLevel("ERROR")
    rows = timed(f"Plate, {reps} replications", lambda: e.integration_spread(spark, "plate", reps).collect())
    print("design | mean | spread | published\n-|-|-|-")
    for r in sorted(rows, key=lambda r: list(PLATE).index(r.method)):
        print(f"{r.method} | {r['mean']:.6f} | {r.sd:.3e} | {PLATE[r.method]:.3e}")
    few = max(20, reps // 4)
    rows = timed(f"Hundred dimensions, {few} replications", lambda: e.integration_spread(spark, "hundred", few).collect())
    got = {(r.method, r.integrand): r.sd for r in rows}
    print("design | Rosenbrock | double sum N(0,1) | double sum N(1,1) | published\n-|-|-|-|-")
    for m, want in HUNDRED.items():
        print(m, "|", " | ".join(f"{got[m, i]:.4g}" for i in ("rosenbrock", "double_sum_0", "double_sum_1")), "|", " / ".join(map(str, want)))
    rows = timed("Even-preferring rule, sizes 4 to 1024, upper bounds", lambda: e.rule_table(spark, tuple(CONTEST), range(4, 1025), exact_dims=0).orderBy("dims").collect())
    print("n | with, ties, without | published\n-|-|-")
    for r in rows:
        print(f"{r.dims} | {r.wins}, {r.ties}, {r.losses} | {', '.join(map(str, CONTEST[r.dims]))}")
    rows = timed("Exact radius, n = 2 and 3, every 17th size to 1024", lambda: e.rule_table(spark, (2, 3), range(4, 1025, 17), exact_dims=3).orderBy("dims").collect())
    print("; ".join(f"n={r.dims}: with, ties, without {r.wins}, {r.ties}, {r.losses}" for r in rows))
    for n, step in ((2, 9), (3, 51)):
        rows = timed(f"Upper bound over exact radius, n = {n}, every {step}th size", lambda n=n, step=step: covering.bound_tightness(e.radius_bounds(spark, (n,), range(4, 1025, step)).withColumnRenamed("dims", "n")).collect())
        print("; ".join(f"n={r.n}: exact within 1e-9 for {r.tight:.0%}, to the last bit for {r.equal:.0%}, mean ratio {r.mean_ratio:.3f}" for r in rows))
    rows = timed("Measures, 100 points, 25 replications", lambda: e.measure_table(spark, 100, (2, 5, 10), 25).orderBy("n", "discrepancy").collect())
    print("n | design | discrepancy | radius or its bound | front\n-|-|-|-|-")
    for r in rows:
        print(f"{r.n} | {r.method} | {r.discrepancy:.3e} | {r.radius:.4f} | {'yes' if r.front else ''}")
    print("\n### Run time against the number of points\n\nmethod | " + " | ".join(map(str, GROWTH)) + " | power\n-|-|-|-|-|-")
    for name, run in RUNS.items():
        took = []
        for count in GROWTH:
            began = time.time()
            run(count)
            took.append(time.time() - began)
        print(name, "|", " | ".join(f"{t:.3f}" for t in took), "|", f"{np.polyfit(np.log(GROWTH), np.log(took), 1)[0]:.2f}")
    rows = timed("Best of 50 n points, mean gap", lambda: e.optimum_gap_rows(spark, (2, 4, 8, 16), max(20, reps // 5), candidates=200).groupBy("n", "objective").pivot("method").agg(F.avg("gap")).orderBy("objective", "n").collect())
    for r in rows:
        d = r.asDict()
        print(d.pop("objective"), d.pop("n"), {k: f"{v:.4g}" for k, v in d.items()})


if __name__ == "__main__":
    main(int(sys.argv[1]) if len(sys.argv) > 1 else 1000)
