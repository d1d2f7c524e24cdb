"""Run the experiments and print their summaries as Markdown tables: python experiments.py SF_DIR [OUT] [--full].

--full takes the three seeds and the wider grids; without it one seed is used. Times are this machine's and only costs.
"""

from __future__ import annotations

import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def table(rows: list[dict], columns: list[str]) -> str:
    show = lambda v: f"{v:.4g}" if isinstance(v, float) else str(v)
    return "\n".join(["| " + " | ".join(columns) + " |", "|" + "---|" * len(columns), *("| " + " | ".join(show(r.get(c, "")) for c in columns) + " |" for r in rows)])


def summary(frame, keep: str, by: list[str]) -> list[dict]:
    """Means over seeds, and half widths of their 95 % intervals where there are three."""
    from pyspark.sql import functions as F

    from annspark.functions import stats

    agg = stats.summarise(frame.where(keep), by)
    return [r.asDict() for r in agg.withColumn("half", F.round("half", 4)).withColumn("mean", F.round("mean", 4)).orderBy(*by).collect()]


def main() -> None:
    from pyspark.sql import SparkSession

    from annspark.plans import workloads as w

    args = [a for a in sys.argv[1:] if not a.startswith("--")]
    sf_dir, out, full = args[0], args[1] if len(args) > 1 else None, "--full" in sys.argv
    seeds = w.SEEDS if full else (42,)
    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    end = "metric IN ('recall', 'delta_pp')"
    plans = [
        ("w01 equal memory: stage 1 alone against one bit less and refinement", lambda: w.w01_matched_memory(spark, sf_dir), "metric <> 'x'", ["dataset", "regime", "method", "metric"]),
        ("w02 flat against partitioned", lambda: w.w02_amplification(spark, sf_dir), "true", ["dataset", "method", "metric"]),
        ("w03 second stage of the flat quantizer", lambda: w.w03_flat_stage2(spark, sf_dir), "true", ["dataset", "regime", "method"]),
        ("w04 ceiling of the learned index", lambda: w.w04_learned_ceiling(spark, sf_dir), "true", ["dataset", "regime", "metric"]),
        ("w05 recall by probes", lambda: w.w05_probes(spark, sf_dir), "true", ["dataset", "regime"]),
        ("w06 small stream", lambda: w.w06_streaming_small(spark, sf_dir, "D(96)" if full else "A(2.5)", seeds=seeds, m=96 if full else 64, bits=5, n=8), "metric = 'recall' AND batch IN (0, 4, 8)", ["regime", "method", "batch"]),
        ("w07 cells", lambda: w.w07_nine_cells(spark, sf_dir) if full else w.w07_nine_cells(spark, sf_dir, (96,), ("sub", "bit"), seeds, 4, True), f"{end} AND batch IN (-1, 0, {9 if full else 4})", ["dataset", "regime", "method", "metric", "batch"]),
        ("w08 orders", lambda: w.w08_orders(spark, sf_dir, seeds=seeds), "metric = 'recall' AND batch IN (0, 3)", ["regime", "method", "batch"]),
        ("w09 bias and capacity", lambda: w.w09_bias_capacity(spark, sf_dir, seeds=seeds), "true", ["method", "metric"]),
        ("w10 encoder swap", lambda: w.w10_encoder_swap(spark, sf_dir, seeds=seeds), "metric IN ('recall', 'cosine', 'initial')", ["regime", "method", "metric"]),
        ("w11 rotation stress", lambda: w.w11_rotation_stress(spark, sf_dir, seeds=seeds), "metric IN ('recall', 'initial')", ["regime", "method", "metric"]),
        ("w12 refresh period", lambda: w.w12_refresh_sweep(spark, sf_dir), "true", ["regime", "metric"]),
        ("w13 cost of freshness", lambda: w.w13_freshness(spark, sf_dir), "metric IN ('rows_reencoded', 'recall_on_front') OR batch = 4", ["method", "regime", "metric"]),
        ("w14 static comparison", lambda: w.w14_static(spark, sf_dir), "true", ["method", "metric"]),
        ("w15 bits or re-rank", lambda: w.w15_bits_or_rerank(spark, sf_dir), "true", ["dataset", "method", "metric"]),
        ("w16 bounds", lambda: w.w16_bounds(spark, sf_dir), "true", ["method", "metric", "regime"]),
        ("w17 generations", lambda: w.w17_generation_loss(spark, sf_dir), "true", ["method", "metric", "batch"]),
        ("w18 error by insert batch", lambda: w.w18_flat_error(spark, sf_dir), "true", ["metric", "batch"]),
        ("w19 accounting", lambda: w.w19_accounting(spark, sf_dir), "true", ["dataset", "metric"]),
    ]
    parts = [f"# Experiments on {sf_dir}\n\nSeeds: {', '.join(map(str, seeds))}. Made by `python experiments.py {' '.join(sys.argv[1:])}`; recall is of 10 neighbours."]
    for title, run, keep, by in plans:
        t = time.time()
        frame = run().persist()
        rows = summary(frame, keep, by)
        frame.unpersist()
        spark.catalog.clearCache()
        parts.append(f"## {title}\n\n" + table(rows, [*by, "mean", *(["half"] if len(seeds) > 1 else [])]) + f"\n\n{time.time() - t:.0f} s")
        print(title, f"{time.time() - t:.0f} s", flush=True)
    text = "\n\n".join(parts) + "\n"
    if out:
        with open(out, "w") as f:
            f.write(text)
    else:
        print(text)
    spark.stop()


if __name__ == "__main__":
    main()
