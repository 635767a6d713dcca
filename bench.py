"""Headline runs: six methods on four graphs (web, near copies, road, social), timed as label tables that are fully computed (graph building excluded,
and one run on a toy graph before, so that no method pays for the start of the JVM's and Python's workers).

Prints one JSON line. BENCH_SF_DIR, BENCH_CPUS and BENCH_REPEATS (runs per method and graph, the mean counts) are read.
``python bench.py slots`` (or scans, sketches, folds, pickless, tune) prints an ablation as JSON instead.
"""

from __future__ import annotations

import json
import math
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = ":".join([HERE, *filter(None, [os.environ.get("PYTHONPATH")])])

from pyspark.sql import SparkSession  # noqa: E402

from labelsketch.operators import baselines, metrics  # noqa: E402
from labelsketch.operators.builders import BUILDERS, toy  # noqa: E402
from labelsketch.operators.graph import graph_stats  # noqa: E402
from labelsketch.operators.propagate import LPConfig, PickLess, label_propagation, tune  # noqa: E402
from labelsketch.operators.selectors import Exact, HeavyHitter, MajorityVote  # noqa: E402
from labelsketch.store import written  # noqa: E402

GRAPHS = ("weblink", "shared_line", "order_path", "copurchase")
METHODS = {
    "mg8": lambda e: label_propagation(e, LPConfig(HeavyHitter())),
    "vote": lambda e: label_propagation(e, LPConfig(MajorityVote())),
    "exact": lambda e: label_propagation(e, LPConfig(Exact())),
    "baseline_a": baselines.baseline_parallel_lp,
    "baseline_b": baselines.baseline_thread_map_lp,
    "baseline_c": baselines.baseline_vertex_map_lp,
}
ABLATIONS = {
    "slots": {f"k{k}": LPConfig(HeavyHitter(k=k)) for k in (2, 4, 8, 16, 32)},
    "scans": {s: LPConfig(HeavyHitter(scan=s)) for s in ("single", "double")},
    "sketches": {s: LPConfig(HeavyHitter(consolidation=s)) for s in ("partial", "shared")},
    "folds": {s: LPConfig(HeavyHitter(engine=s)) for s in ("expr", "arrow")},
    "pickless": {str(p): LPConfig(HeavyHitter(), PickLess(p)) for p in (None, 1, 2, 4, 8, 16)} | {"first": LPConfig(HeavyHitter(), PickLess(first_only=True))},
}


def timed(run, edges, repeats: int) -> tuple[float, object]:
    total, found = 0.0, None
    for _ in range(repeats):
        began = time.time()
        found = run(edges)
        found.labels.write.format("noop").mode("overwrite").save()
        total += time.time() - began
    return total / repeats, found


def geometric(values: list[float]) -> float:
    return round(math.exp(sum(map(math.log, values)) / len(values)), 3)


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus, repeats = os.environ.get("BENCH_CPUS", "8"), int(os.environ.get("BENCH_REPEATS", "1"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    what = sys.argv[1] if len(sys.argv) > 1 else "compare"
    runs = METHODS if what == "compare" else {k: (lambda e, c=c: label_propagation(e, c)) for k, c in ABLATIONS.get(what, {}).items()}
    queries, rows, sets = {}, [], {}
    timed(METHODS["mg8"], toy(spark, "clique_ring"), 1)
    for name in GRAPHS:
        began = time.time()
        edges = written(BUILDERS[name](spark, sf_dir), name)
        queries[f"build_{name}"] = round(time.time() - began, 3)
        stats = graph_stats(edges).first()
        if what == "tune":
            def cost(p):
                return timed(lambda e: label_propagation(e, LPConfig(HeavyHitter(), hub_degree=p["hub_degree"], hub_chunks=p["hub_chunks"])), edges, 1)[0]  # noqa: B023
            best, seconds = tune({"hub_degree": [128, 64, 256], "hub_chunks": [32, 8]}, cost, 1)
            rows.append({"graph": name, **best, "seconds": round(seconds, 2)})
            continue
        if not sets.get(name):
            sets[name] = {r["method"]: r["bytes"] for r in metrics.working_set_bytes(graph_stats(edges)).collect()}
        for method, run in runs.items():
            moved = metrics.shuffled_bytes(spark)
            seconds, found = timed(run, edges, repeats)
            moved = (metrics.shuffled_bytes(spark) - moved) // repeats
            q = metrics.modularity(edges, found.labels).first()
            queries[f"{method}_{name}"] = round(seconds, 3)
            print(f"{method} {name}: {seconds:.1f} s, {len(found.history)} iterations, modularity {q['q']:.4f}, {moved} bytes shuffled", file=sys.stderr, flush=True)
            rows.append({"method": method, "graph": name, "seconds": round(seconds, 3), "iterations": len(found.history), "modularity": round(q["q"], 4), "communities": q["communities"], "shuffle_bytes": moved, "edges_per_second": round(stats["m_edges"] * len(found.history) / seconds)})
        rows.append({"graph": name, "working_set_bytes": sets[name]})
    out = {"metric": f"label_propagation_{what}", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), "rows": rows}
    if what == "compare":
        at = {(r["method"], r["graph"]): r for r in rows if "method" in r}
        out["ratios"] = {
            **{f"seconds_{m}_over_mg8": geometric([at[m, g]["seconds"] / at["mg8", g]["seconds"] for g in GRAPHS]) for m in METHODS if m != "mg8"},
            **{f"modularity_loss_percent_mg8_to_{m}": round(sum(100 * (1 - at["mg8", g]["modularity"] / at[m, g]["modularity"]) for g in GRAPHS if at[m, g]["modularity"] > 0.01) / max(1, sum(at[m, g]["modularity"] > 0.01 for g in GRAPHS)), 2) for m in METHODS if m != "mg8"},
            **{f"modularity_mg8_minus_{m}": round(sum(at["mg8", g]["modularity"] - at[m, g]["modularity"] for g in GRAPHS) / len(GRAPHS), 4) for m in METHODS if m != "mg8"},
            "working_set_thread_map_over_mg8": geometric([sets[g]["thread_map"] / sets[g]["mg"] for g in GRAPHS]), "working_set_vertex_map_over_mg8": geometric([sets[g]["vertex_map"] / sets[g]["mg"] for g in GRAPHS]),
        }
    print(json.dumps(out))
    spark.stop()


if __name__ == "__main__":
    main()
