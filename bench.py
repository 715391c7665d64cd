"""Times the headline workloads and prints one JSON line.

Beside the total it reports, per feature set and variant of the ablation, training and classifying seconds, passes, stop reason, samples
shown per second, moves of every pass, quantization error and the ratio of times to the standard variant; passes until the error is within a hundredth of the standard
variant's last; fingerprints over repeated runs; and the highest correlations of a pair of regimes.

After a warm-up run, variants take turns, each round in another order, and the median of a variant's times counts: none pays for what runs first.
"""

from __future__ import annotations

import json
import os
import statistics
import time
from collections import defaultdict
from dataclasses import replace

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
PASSES = int(os.environ.get("BENCH_PASSES", "3"))
ROUNDS = {"docs": 3, "cells": 3, "lines": 1}


def main() -> None:
    from topomap.config import MapConfig
    from topomap.functions import measures, regimes
    from topomap.operators import baselines
    from topomap.operators.train import fit_map
    from topomap.plans import catalogue
    from topomap.sources import workloads
    from topomap.sources.io import load, run_to_nowhere

    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    report: dict[str, dict] = {}
    began = time.perf_counter()

    def clock(name, action):
        t = time.perf_counter()
        out = action()
        seconds[name] = round(time.perf_counter() - t, 3)
        return out

    sets = {"docs": (catalogue.docs_v, ["doc_id"]), "cells": (catalogue.cells_v, ["l_suppkey", "period"]), "lines": (workloads.lines, workloads.LINE_KEY)}
    prepared = {}
    for name, (build, key) in sets.items():
        df = build(spark, SF).select(*key, "features").cache()
        clock(f"build_{name}", df.count)
        prepared[name] = df
    for name, df in prepared.items():
        key, n, passes = sets[name][1], df.count(), PASSES if name != "lines" else 1
        settings = {v: baselines.variant(MapConfig(4, 3, max_passes=passes), v) for v in baselines.VARIANTS}
        models, train, classify = {}, defaultdict(list), defaultdict(list)
        run_to_nowhere(fit_map(df.limit(2000), settings["standard"], key=key).classify(df))
        names = list(settings)
        for turn in range(ROUNDS[name]):
            for v in names[turn:] + names[:turn]:
                t = time.perf_counter()
                models[v] = fit_map(df, settings[v], key=key)
                train[v].append(time.perf_counter() - t)
                t = time.perf_counter()
                run_to_nowhere(models[v].classify(df))
                classify[v].append(time.perf_counter() - t)
        for v, model in models.items():
            seconds[f"train_{name}_{v}"], seconds[f"classify_{name}_{v}"] = (round(statistics.median(x[v]), 3) for x in (train, classify))
            shown = sum(h["seconds"] for h in model.history)
            report[f"{name}/{v}"] = {
                "samples": n, "passes": len(model.history), "stop": model.stop_reason, "moves": [h["moves"] for h in model.history], "samples_per_second_of_a_pass": round(n * len(model.history) / shown),
                "quantization_error": round(measures.quantization_error(model.classify(df)).first()[0], 6), "seconds": round(seconds[f"train_{name}_{v}"] + seconds[f"classify_{name}_{v}"], 3),
            }
        for v in models:
            report[f"{name}/{v}"]["ratio_to_standard"] = round(report[f"{name}/{v}"]["seconds"] / report[f"{name}/standard"]["seconds"], 3)
    errors = {}
    stages = {f"{v}/{p}": replace(baselines.variant(MapConfig(4, 3), v), max_passes=p, stop="max") for v in baselines.VARIANTS for p in (1, 2, 3, 4)}
    for run, model in baselines.fit_many(prepared["docs"], stages, key=["doc_id"]).items():
        errors[run] = measures.quantization_error(model.classify(prepared["docs"])).first()[0]
    goal = 1.01 * errors["standard/4"]
    report["passes_to_error_docs"] = {v: next((p for p in (1, 2, 3, 4) if errors[f"{v}/{p}"] <= goal), None) for v in baselines.VARIANTS} | {"goal": round(goal, 6)}
    docs = prepared["docs"]
    cfg = MapConfig(4, 3, max_passes=PASSES)
    report["fingerprints"] = {
        "reproducible, three layouts": len({fit_map(d, cfg, key=["doc_id"]).fingerprint for d in (docs, docs.repartition(16), docs.coalesce(1))}),
        "standard, three seeds": len({m.fingerprint for m in baselines.standard_runs(docs, cfg, [1, 2, 3], key=["doc_id"]).values()}),
    }
    won = fit_map(docs, cfg, key=["doc_id"]).classify(docs).join(load(spark, SF, "documents", "doc_id", "source"), "doc_id")
    report["highest_correlations"] = {
        "histograms": regimes.regime_correlation(regimes.regime_centroids(won, 42)).agg(F.max("histogram_corr")).first()[0],
        "maps": regimes.rfo_correlation(regimes.rfo_map(won, "source", 12), "source").agg(F.max("map_corr")).first()[0],
    }
    for name in ("dense_index_lineitem", "histogram_events", "winners_gradient_line", "rfo_map_nation", "regime_transitions_cells", "kmeans_3round_docs", "batch_map_3round_docs", "stream_classify_events"):
        clock(name, lambda: run_to_nowhere(catalogue.queries()[name](spark, SF)))
    print(json.dumps({"metric": "headline workloads", "value": round(time.perf_counter() - began, 3), "unit": "sec", "queries": seconds, "sf": SF, "report": report}))


if __name__ == "__main__":
    main()
