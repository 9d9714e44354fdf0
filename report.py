"""Run experiment tables with several seeds and print them as Markdown: python report.py [sf_dir] [workload ...]"""

from __future__ import annotations

import os
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


def main(folder: str, names: list[str]) -> None:
    from pyspark.sql import SparkSession

    from lakeadapt.workloads.experiments import seed_variance

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in names:
        rows = seed_variance(spark, folder, name).orderBy("transfer", "budget", "method").collect()
        print(f"\n## {name}\n\n| transfer | budget | method | labels | SW F1 | MA F1 | OOD | judge calls |\n|---|---|---|---|---|---|---|---|")
        for r in rows:
            sd = lambda a, b: f"{r[a]:.3f} ({r[b] or 0:.3f})" if r[a] is not None else "refused"  # noqa: B023, E731
            print(f"| {r['transfer']} | {r['budget']} | {r['method']} | {r['n_labels']:.0f} | {sd('sw_f1', 'sw_sd')} | {sd('ma_f1', 'ma_sd')} | {r['ood']:.3f} | {r['judge_calls']:.0f} |", flush=True)


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01", sys.argv[2:] or ["W1", "W2", "W5", "W11", "W12"])
