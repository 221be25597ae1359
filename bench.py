"""Headline runs at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one line of JSON.

Each method runs on each experiment graph with the edges already written, as the reference
measures methods and not readers. Beside the graphs of the given tables stands a generated one
of a million edges in many uneven components. ``queries`` holds the median seconds of $BENCH_RUNS
runs of the contracting methods (three by default) and one run of the others; ``phases``,
``relative`` (median over the fastest method of the graph), ``decay`` (edges at the start of a
phase over those of the next, main method), ``sent`` (rows through exchanges for each edge) and
``status`` stand beside it. A run that outgrows its pair bound or $BENCH_TIMEOUT seconds is
marked ``x`` and counts its time so far.
"""

from __future__ import annotations

import json
import os
import sys
import threading
import time
from pathlib import Path
from statistics import median

sys.path.insert(0, str(Path(__file__).parent))

from pyspark.sql import SparkSession  # noqa: E402

from ccspark.plans.runner import CONTRACTING, TooLarge, connected_components  # noqa: E402
from ccspark.plans.store import Scratch  # noqa: E402
from ccspark.sources.generators import forest_mix  # noqa: E402
from ccspark.sources.workloads import WORKLOADS  # noqa: E402

METHODS = ("two_hop", "forest", "rewire_merge", "star_alternation", "min_hub")
GRAPHS = ("purchase", "copart", "pagelink", "embedsim", "docline", "generated")
#: The reference finishes at tens of millions of edges out of 1e8 to 1e12: here one edge in a thousand of each graph.
FINISH_SHARE = 1000
GENERATED = 600_000


def timed(spark, run, limit: float):
    """(result or None, seconds, status): jobs are cancelled at the limit."""
    timer = threading.Timer(limit, spark.sparkContext.cancelAllJobs)
    timer.start()
    began = time.time()
    try:
        return run(), time.time() - began, "ok"
    except TooLarge:
        return None, time.time() - began, "x"
    except Exception as e:
        if "cancel" not in str(e).lower():
            raise
        return None, time.time() - began, "x"
    finally:
        timer.cancel()


def main() -> None:
    sf, cpus, runs, limit = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8"), int(os.environ.get("BENCH_RUNS", "3")), float(os.environ.get("BENCH_TIMEOUT", "40"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", os.environ.get("BENCH_PARTITIONS", "8"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries, phases, relative, decay, sent, status = {}, {}, {}, {}, {}, {}
    began = time.time()
    for graph in GRAPHS:
        scratch = Scratch(spark, f"bench-{graph}")
        source = forest_mix(spark, GENERATED, seed=1) if graph == "generated" else WORKLOADS[graph].build(spark, sf)[0]
        edges, n = scratch.counted(source, "edges")
        if graph == GRAPHS[0]:
            connected_components(edges, finish_edges=0)  # compiles what all runs share
        for method in METHODS:
            options = {"finish_edges": n // FINISH_SHARE, "lookup": method == "forest"} if method in CONTRACTING else {}
            if method == "star_alternation":
                options["lookup"] = True
            name, took = f"{method}__{graph}", []
            for _ in range(runs if method in CONTRACTING else 1):
                result, seconds, status[name] = timed(spark, lambda e=edges, m=method, o=options: connected_components(e, method=m, max_pairs=20_000_000, **o), limit)
                took.append(seconds)
                if result is None:
                    break
                phases[name] = result.phases
                sent[name] = round(sum(s.records_sent for s in result.phase_stats) / n, 2)
                if method == "two_hop":
                    sizes = [s.edges_in for s in result.phase_stats]
                    decay[graph] = [round(a / b, 1) for a, b in zip(sizes, sizes[1:], strict=False)] or [f"{n} edges in one phase"]
                result.scratch.drop()
            queries[name] = round(median(took), 3)
        own = {m: queries[f"{m}__{graph}"] for m in METHODS if status[f"{m}__{graph}"] == "ok"}
        relative[graph] = {m: round(own[m] / min(own.values()), 2) if m in own else "x" for m in METHODS}
        scratch.drop()
    total = round(sum(queries.values()), 3)
    print(json.dumps({"metric": "total_seconds_components", "value": total, "unit": "sec", "queries": queries, "sf": Path(sf).name, "phases": phases, "relative": relative, "decay": decay, "sent": sent, "status": status, "wall": round(time.time() - began, 1)}))
    spark.stop()


if __name__ == "__main__":
    main()
