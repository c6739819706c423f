"""Headline joins with and without the bitmap filter; prints one JSON line.

Preparation (reading, ordering, encoding, sketches) is excluded from the join times and reported beside them. The two
forms of a join take turns, and the mean of two runs counts.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ["PYTHONPATH"] = os.pathsep.join([os.path.dirname(os.path.abspath(__file__)), os.environ.get("PYTHONPATH", "")])

from setsim.functions.bitmap import BitmapSpec  # noqa: E402
from setsim.functions.spec import SimSpec  # noqa: E402
from setsim.operators.joins import join_collections  # noqa: E402
from setsim.operators.order import prepare  # noqa: E402
from setsim.plans import experiments, metrics  # noqa: E402
from setsim.sources.workloads import WORKLOADS  # noqa: E402

METHODS = {"PFX-L": ("prefix_length", {}), "PFX-LP": ("prefix_positional", {}), "GRP": ("grouped_prefix", {}), "ELL": ("ell_prefix", {"ell": 2})}
#: workload, thresholds, bitmap width
SERIES = (("order_parts", ("0.5", "0.8", "0.95"), 64), ("user_evt_dow", ("0.8",), 64), ("emb_pos", ("0.5", "0.8"), 64), ("doc_words", ("0.8",), 512), ("page_words", ("0.8",), 512))


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries: dict[str, float] = {}
    rows, ratios, prepared = [], {}, {}
    for workload, thresholds, b in SERIES:
        began = time.perf_counter()
        c = prepare(WORKLOADS[workload](spark, sf))
        for t in thresholds:
            c.sketch(BitmapSpec("auto", b).resolved(SimSpec.of("jaccard", t)))
        prepared[workload] = round(time.perf_counter() - began, 3)
        join_collections(c, None, SimSpec.of("jaccard", "0.95"), "prefix_length").count()  # compiles, touches files
        for t in thresholds:
            spec = SimSpec.of("jaccard", t)
            for label, (method, options) in METHODS.items():
                if workload in ("doc_words", "page_words") and label == "ELL" or workload in ("user_evt_dow", "emb_pos") and label == "GRP":
                    continue
                joined = lambda bits: join_collections(c, None, spec, method, bitmap=bits, **options)  # noqa: B023, E731
                took = experiments.interleaved({"orig": lambda: joined(None), "hbf": lambda: joined(BitmapSpec("auto", b))}, 2)  # noqa: B023
                for form, sec in took.items():
                    queries[f"{workload}_{t}_{label}_{form}"] = round(sec, 3)
                rows.append((workload, label, t, took["orig"], took["hbf"]))
            r = metrics.prune_ratio(c, spec, BitmapSpec("auto", b)).first()
            ratios[f"{workload}_{t}"] = {"candidates": r.candidates, "pruned": r.pruned, "ratio": r.ratio}
    widths = block_series(spark, sf)
    runs = spark.createDataFrame(rows, "input string, method string, threshold string, cost_orig double, cost_hbf double")
    means = {f"{r.method or r.input or 'all'}_{r.threshold or 'all'}": round(r.mean_improvement, 1) for r in metrics.mean_improvement(runs).collect()}
    share = metrics.share_improved(runs).first()
    totals = {r.method: {"orig": round(r.orig, 3), "hbf": round(r.hbf, 3), "saved_percent": round(r.saved, 1)} for r in metrics.totals(runs).collect()}
    wins = {f"{r.method}_{r.form}": [r.wins_in_form, r.wins_overall] for r in metrics.wins(runs).collect()}
    out = {
        "metric": "similarity joins with and without bitmap filter", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": sf, "mean_improvement_percent": means["all_all"], "mean_improvement_by": means,
        "runs_improved": share.runs_improved, "inputs_improved": share.inputs_improved, "totals": totals, "wins_in_form_and_overall": wins, "pruning": ratios, "block_widths": widths, "preparation_sec": prepared,
    }
    print(json.dumps(out))


def block_series(spark: SparkSession, sf: str, names=("user_evt_dow",), thresholds=("0.5", "0.75"), widths=(64, 256, 1024)) -> dict:
    """All-pairs joins by width: the best one and its gain over the best unfiltered prefix join."""
    inputs = {w: prepare(WORKLOADS[w](spark, sf)) for w in names}
    found = experiments.block_widths(spark, inputs, thresholds, widths).collect()
    return {f"{r.input}_{r.threshold}": {"b": r.b, "seconds": round(r.seconds, 3), "baseline": round(r.baseline, 3), "speedup": round(r.speedup, 2)} for r in found}


if __name__ == "__main__":
    main()
