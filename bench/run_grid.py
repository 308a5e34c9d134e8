"""The experiments whole: python bench/run_grid.py FOLDER [experiment ...] [--names emb10,role3] [--sizes 10,25,50,100] [--methods ...]
[--expansions 3].

Writes FOLDER/EXPERIMENT.csv as soon as an experiment (of a workload, for the main comparison) is done. BENCH_SF_DIR and BENCH_CPUS
as in bench.py.
"""

from __future__ import annotations

import csv
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
from pyspark.sql import SparkSession  # noqa: E402

from vecboost.plans import experiments as E  # noqa: E402


def main() -> None:
    args, given = sys.argv[1:], {"names": "emb10,letter26,role3,cover7,cover7_oblique,hand10", "sizes": "10,25,50,100", "methods": ",".join(E.METHODS), "expansions": "3"}
    while any(a.startswith("--") for a in args):
        k = next(i for i, a in enumerate(args) if a.startswith("--"))
        given[args[k][2:]] = args[k + 1]
        del args[k : k + 2]
    out, names, sizes = args[0], given["names"].split(","), tuple(map(int, given["sizes"].split(",")))
    most = max(sizes)
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    every = {
        **{f"main_{n}": lambda s, n=n: E.main_comparison(s, sf, (n,), given["methods"].split(","), sizes, expansions=int(given["expansions"])) for n in names},
        **{f"convergence_{n}": lambda s, n=n: E.convergence(s, sf, n, n_trees=most) for n in names},
        "grid_swapped": lambda s: E.grid_swapped(s, sf, n_trees=most),
        "full_vs_diag": lambda s: E.hessian_costs(s, sf, names),
        "layer_ablation": lambda s: E.layer_ablation(s, sf, names[0], n_trees=min(25, most)),
        "refresh": lambda s: E.refresh(s, sf, names[0], most),
        "class_counts": lambda s: E.class_counts(s, sf, names, 4),
        "rows_per_layer": lambda s: E.quotas(s, sf, n_trees=10),
        "significance": lambda s: E.significance(s, sf, names[0]),
        "presets": lambda s: E.preset_scores(s, sf, names),
        "null_controls": lambda s: E.null_controls(s, sf),
    }
    wanted = args[1:] or list(every)
    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    spark.sparkContext.environment["PYTHONPATH"] = sys.path[0]
    os.makedirs(out, exist_ok=True)
    for name in [n for w in wanted for n in every if n == w or n.startswith(w + "_") and w in ("main", "convergence")]:
        began = time.time()
        d = every[name](spark)
        with open(f"{out}/{name}.csv", "w", newline="") as f:
            w = csv.writer(f)
            w.writerow(d.columns)
            w.writerows(d.collect())
        print(name, round(time.time() - began, 1), flush=True)


if __name__ == "__main__":
    main()
