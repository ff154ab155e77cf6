"""Run the experiment queries and print their tables: python experiments.py [sf_dir] [query ...]."""

from __future__ import annotations

import os
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

TABLES = (
    ("study_w1", "Attribute ranking, a task per nation: tau by path, factual profile, with grounded scores"),
    ("study_w2", "Nations by their customers' orders: tau by path, factual profile, with grounded scores"),
    ("study_w3", "Passages, LIMIT 10, reasoning profile: nDCG@10 with 80% interval, calls, dollars per query"),
    ("study_w4", "Passages for half a question, LIMIT 10, reasoning profile"),
    ("study_w5b", "Reviews, criterion reversed, LIMIT 10, reasoning profile"),
    ("study_w6", "Few relevant among many, LIMIT 10, reasoning profile"),
    ("study_w7", "Shared pool of continuations, LIMIT 10, reasoning profile"),
    ("floors_w5b", "Input order and random order on the reviews"),
    ("spread_w3", "Spread over queries by path"),
    ("log_fit_w4", "Quality against the log of dollars over static paths"),
    ("main_table_w4", "Three best static paths and the best of each policy, three tiers"),
    ("budget_sweep_w3", "Both policies over rising budgets: passages"),
    ("budget_sweep_w4", "Both policies over rising budgets: passages for half a question"),
    ("budget_sweep_w5b", "Both policies over rising budgets: reviews"),
    ("budget_sweep_w6", "Both policies over rising budgets: few relevant among many"),
    ("budget_sweep_w7", "Both policies over rising budgets: shared pool"),
    ("pareto_w4", "Points that no cheaper one reaches"),
    ("dips_w4", "How often quality falls as the budget rises, six budgets"),
    ("call_ratios_w3", "Calls of full sorts, relative"),
    ("latency_w4", "Sequential depth and simulated seconds, LIMIT 10, N = 100"),
    ("cost_error_w3", "Mean absolute error of cost estimates from 20 items, in percent"),
    ("cost_error_w4", "The same on passages for half a question, three tiers"),
    ("cost_error_w6", "The same on few relevant among many"),
    ("cost_error_w7", "The same on the shared pool"),
    ("judge_ablation_w4", "Share of tasks that match or beat the best static path, ranker of the small tier, by judge and budget"),
    ("sample_size_w4", "Quality and probe spend by sample size"),
    ("inquiry_accuracy", "Inquiry accuracy"),
    ("proxy_ndcg_w14", "Light ranker over vectors"),
)


def show(value) -> str:
    return f"{value:.4g}" if isinstance(value, float) else str(value)


def main() -> None:
    from pyspark.sql import SparkSession

    from semrank.queries import QUERIES

    sf_dir, only = (sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"), set(sys.argv[2:])
    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name, title in TABLES:
        if only and name not in only:
            continue
        df = QUERIES[name](spark, sf_dir)
        rows = sorted(tuple(show(v) for v in r) for r in df.collect())
        print(f"\n### {title} (`{name}`)\n\n| " + " | ".join(df.columns) + " |\n|" + "-|" * len(df.columns))
        for r in rows:
            print("| " + " | ".join(r) + " |")
        sys.stdout.flush()


if __name__ == "__main__":
    main()
