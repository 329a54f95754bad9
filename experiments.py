"""Run the accuracy experiments with many orders and print Markdown tables.

    python experiments.py [sf_dir] [seeds] [graph ...]
"""

import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

SPACES = (0.02, 0.04, 0.10, 0.16)
DEPTHS = (2, 3, 5, 10, 15, 20)


def main(sf: str = "/root/testdata/sf0.01", seeds: str = "20", *graphs: str) -> None:
    from pyspark.sql import functions as F

    from clustercost.plans.methods import sweep
    from clustercost.session import local_session
    from clustercost.sources.graphs import nodes_and_pairs

    spark = local_session(8)
    names = [f"x{i}" for i in range(int(seeds))]
    for g in graphs or ("emb", "page", "part"):
        ids, pairs = nodes_and_pairs(spark, sf, g)
        for title, rows, by in (("space", [(s, 15, f) for f in SPACES for s in names], "space"), ("depth", [(s, k, 0.04) for k in DEPTHS for s in names], "k")):
            began = time.time()
            methods = ("budgeted", "compact", "pair_sampling", "prior_pivot", "prior_sparse_dense") if title == "space" else ("budgeted", "compact")
            found = sweep(spark, ids, pairs, rows, methods)
            error = (F.col("value") - F.col("best")) / F.nullif(F.col("best"), F.lit(0))
            out = found.groupBy(by, "method").agg(F.round(100 * F.avg(error), 1).alias("e"), F.round(100 * F.stddev_samp(error), 1).alias("s"), F.round(100 * F.stddev_samp("value") / F.avg("value"), 1).alias("v")).orderBy(by, "method").collect()
            print(f"\n{g}, {title}, {seeds} orders, {time.time() - began:.0f} s\n\n| {by} | method | mean error % | SD of error % | SD / mean % |\n|---|---|---|---|---|")
            for r in out:
                print(f"| {r[0]} | {r[1]} | {r[2]} | {r[3]} | {r[4]} |", flush=True)


if __name__ == "__main__":
    main(*sys.argv[1:])
