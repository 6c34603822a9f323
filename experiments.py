"""Runs the experiment workloads at more repetitions and writes their tables as Markdown.

    python experiments.py [--sf DIR] [--reps N] [--out EXPERIMENTS.md] [--cores C]
"""

import argparse
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def markdown(df, order: list[str]) -> str:
    rows = df.orderBy(*order).collect()
    show = lambda v: f"{v:.4g}" if isinstance(v, float) else str(v)
    head = "| " + " | ".join(df.columns) + " |\n|" + "-|" * len(df.columns) + "\n"
    return head + "".join("| " + " | ".join(show(v) for v in r) + " |\n" for r in rows)


def main() -> None:
    parser = argparse.ArgumentParser()
    parser.add_argument("--sf", default="/root/testdata/sf0.1")
    parser.add_argument("--reps", type=int, default=200)
    parser.add_argument("--out", default="EXPERIMENTS.md")
    parser.add_argument("--cores", default="8")
    parser.add_argument("--large", action="store_true", help="20,000 items: squared error and subpopulation bounds only")
    own = parser.parse_args()

    from pyspark.sql import SparkSession

    from subweight.plans import metrics, workloads

    spark = SparkSession.builder.master(f"local[{own.cores}]").config("spark.sql.shuffle.partitions", own.cores).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    r = own.reps
    runs = [
        ("Error of the total weight", lambda: workloads.run_total_error(spark, own.sf, r, (4, 40, 100)), ["wt", "k", "method"]),
        ("Bounds on the total weight, 95 % each side", lambda: workloads.run_total_bounds(spark, own.sf, r, (10, 40, 100), more=True), ["wt", "k", "method"]),
        ("Rate inside the 90 % interval, over k", lambda: workloads.run_in_bounds(spark, own.sf, r, (10, 20, 40, 100)), ["wt", "method"]),
        ("Squared error against group size", lambda: workloads.run_partition_error(spark, own.sf, r // 2, (4, 40), (1, 10, 100, 1000), n=1000, baselines=True), ["wt", "k", "g", "method"]),
        ("Settings of the chain", lambda: workloads.run_chain_settings(spark, own.sf, r // 8, 100, gs=(1, 100, 1000), n=1000), ["wt", "g", "method"]),
        ("Bounds on all groups of 200 of 1,000", lambda: workloads.run_subpop_bounds(spark, own.sf, r // 2, draws=200), ["wt", "method"]),
        ("Bounds on all groups of 500 of 1,000", lambda: workloads.run_subpop_bounds(spark, own.sf, r // 2, g=500, draws=200), ["wt", "method"]),
    ]
    if own.large:
        runs = [
            ("Squared error against group size, 20,000 items", lambda: workloads.run_partition_error(spark, own.sf, r, (4, 40, 500), (1, 100, 5000, 20000), ("exp_rc", "priority_rc", "subset", "subset_chain"), 20_000), ["wt", "k", "g", "method"]),
            ("Settings of the chain, 20,000 items, k = 500", lambda: workloads.run_chain_settings(spark, own.sf, r, 500, gs=(1, 5000, 20000), n=20_000), ["wt", "g", "method"]),
            ("Bounds on all groups of 4,000 of 20,000", lambda: workloads.run_subpop_bounds(spark, own.sf, r, (40,), 4000, 20_000, (1.2, 2.0), 200), ["wt", "method"]),
        ]
    with open(own.out, "a" if own.large else "w") as out:
        if not own.large:
            out.write(f"# Experiments\n\n{os.path.basename(os.path.normpath(own.sf))}, 1,000 orders as base table, {r} repetitions (fewer where said). Written by experiments.py.\n")
        theory = {k: metrics.with_replacement_theory(k)["mean_abs_rel_error"] for k in (40, 100)}
        note = f"\n{r} repetitions from here on.\n" if own.large else f"\nClosed form of the with-replacement error: {', '.join(f'k={k}: {v:.3f}' for k, v in theory.items())}.\n"
        out.write(note)
        for title, run, order in runs:
            began = time.time()
            out.write(f"\n## {title}\n\n{markdown(run(), order)}")
            out.flush()
            print(title, round(time.time() - began, 1), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
