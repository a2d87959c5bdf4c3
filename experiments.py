"""The experiments as tables on standard output: accuracy, scalability, ablation times.

    python experiments.py accuracy /root/testdata/sf0.01
    python experiments.py scalability 0.01 3          # share of the full sizes, repeats
    python experiments.py ablation /root/testdata/sf0.01
"""

from __future__ import annotations

import os
import sys
import tempfile

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join(filter(None, [ROOT, os.environ.get("PYTHONPATH", "")]))


def accuracy(spark, sf_dir: str, view: str = "brand", width: int = 250, sigma: int = 14) -> None:
    """Best F1 of every method's grid against the exact answer, with Jaccard and temporal precision where there are intervals."""
    from pyspark.sql import functions as F

    from localfreq.operators import metrics
    from localfreq.plans import baselines, grid
    from localfreq.registry.accuracy import _LOCAL_AXES, _SURPLUS_AXES, _two
    from localfreq.session import checkpointed
    from localfreq.sources.tables import order_ranks, transactions
    from localfreq.workloads import reference

    tx = checkpointed(transactions(spark, sf_dir, view))
    ref, (occ, t_max) = checkpointed(reference(spark, sf_dir, view, width, sigma)), _two(spark, sf_dir, view)
    occ = checkpointed(occ)
    ordinals = order_ranks(spark, sf_dir).select("t", F.col("t").alias("ord"))
    rows = {
        "frequent": metrics.score(baselines.mine_frequent(tx, sigma, k_max=2).where("len = 2"), ref, intervals=False),
        "periodic": grid.best(grid.grid_periodic(occ, ref, t_max, sigma, 900), ["max_per"]),
        "partial-periodic": grid.best(grid.grid_partial(occ, ref, t_max, sigma, 120), ["max_per", "min_pr"]),
        "gap-local": grid.best(grid.grid_gap_local(occ, ref, ordinals, *_LOCAL_AXES)[1], ["local_sup", "max_gap", "min_dur"]),
        "surplus-local": grid.best(grid.grid_surplus_local(occ, ref, *_SURPLUS_AXES)[1], ["max_per", "min_dur", "max_so_per"]),
        "recurring": grid.best(grid.grid_recurring(occ, ref, sigma, 250), ["max_per"]),
        "span": metrics.interval_scores(baselines.span_intervals(occ, ref), ref),
    }
    for name, df in rows.items():
        print(view, width, sigma, name, df.first().asDict(), flush=True)


def scalability(spark, share: float, repeats: int) -> None:
    """Mean seconds, patterns and peak memory for 45 sizes, at a share of 1 to 2 million transactions."""
    from localfreq.plans import cost, sharded, synth

    folder, rows = spark.conf.get("spark.checkpoint.dir"), []
    for t in (1.0, 1.25, 1.5, 1.75, 2.0):
        for i in (10_000, 15_000, 20_000):
            for b in (5, 10, 15):
                n, path = int(t * 1e6 * share), f"{folder}/synth-{t}-{i}-{b}"
                # stretches and occurrences keep their sizes; fewer patterns fit into fewer transactions
                synth.generate(spark, n, i, b, patterns=max(1, min(50, n // 6_000)), occurrences=100, duration=10_000).write.mode("overwrite").parquet(path)
                make = lambda path=path: sharded.mine_dense_sharded(spark.read.parquet(path), 1000, 10, shard_width=20_000)
                took = cost.timed(make, repeats)
                patterns = make().select("pattern").distinct().count()
                rows.append((n, i, b, took, patterns))
                print({"T": n, "I": i, "B": b, "s": round(took, 3), "patterns": patterns, "tx_per_s": round(n / took), **cost.peak_memory_mb(spark)}, flush=True)
    table = spark.createDataFrame([(float(n), float(i), float(b), s) for n, i, b, s, _ in rows], "T double, I double, B double, s double")
    for x in "TIB":
        print(x, cost.growth(table, x, "s").first().asDict())


def ablation(spark, sf_dir: str) -> None:
    """Seconds of each strategy: every position, the ranges' positions, stride-skip, window expressions, shards."""
    from localfreq.operators import detect
    from localfreq.operators.candidates import candidate_ranges
    from localfreq.operators.kernels import scan_by_pattern
    from localfreq.plans import cost, sharded
    from localfreq.registry.accuracy import _two
    from localfreq.sources.tables import occurrences, transactions
    from localfreq.workloads import SETTINGS

    for name in ("A1", "A2", "A3"):
        for view, width, sigma in SETTINGS[name]:
            occ, t_max = _two(spark, sf_dir, view)
            occ = occ.persist()
            tx = transactions(spark, sf_dir, view).persist()
            singles = detect.dense_intervals(occurrences(spark, sf_dir, view)[0], width, sigma, t_max=t_max)
            ranges = candidate_ranges(occ.select("pattern").distinct(), singles, width, 2).persist()  # the common ranges of the items
            plans = {
                "every": lambda: scan_by_pattern(occ, width, sigma, t_max=t_max, kernel="every"),
                "every_ranges": lambda: scan_by_pattern(occ, width, sigma, t_max=t_max, kernel="every", ranges=ranges),
                "skip_ranges": lambda: scan_by_pattern(occ, width, sigma, t_max=t_max, kernel="skip", ranges=ranges),
                "window_expressions": lambda: detect.dense_runs(occ, width, sigma, t_max=t_max),
                "sharded_miner": lambda: sharded.mine_dense_sharded(tx, width, sigma, shard_width=8 * width, k_max=2),
            }
            print({"view": view, "W": width, "sigma": sigma, **{k: round(cost.timed(f, 2), 3) for k, f in plans.items()}}, flush=True)
            for df in (occ, tx, ranges):
                df.unpersist()


def main() -> None:
    from localfreq.session import build

    what, *rest = sys.argv[1:]
    with tempfile.TemporaryDirectory() as folder:
        spark = build("local[*]", **{"spark.sql.shuffle.partitions": "8", "spark.driver.memory": "12g", "spark.ui.showConsoleProgress": "false", "spark.checkpoint.dir": folder})
        spark.sparkContext.setLogLevel("ERROR")
        if what == "scalability":
            scalability(spark, float(rest[0]), int(rest[1]))
        else:
            {"accuracy": accuracy, "ablation": ablation}[what](spark, rest[0])


if __name__ == "__main__":
    main()
