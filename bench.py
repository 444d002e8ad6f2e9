"""Headline timings: one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 8), BENCH_RUNS (default 1; the
published protocol is 5), BENCH_MAIN_RUNS (runs of the rows in MAIN, default 2), BENCH_BUDGET_S (seconds
after which a run is stopped and marked OOT, default 90), BENCH_TOTAL_S (seconds after which no more rows begin, default 330;
rows left out are listed in status), BENCH_PLANTED (nodes of the planted graphs; the
published 50,000 is the default), BENCH_ONLY (comma-separated names).  A run holds the scan, the shuffles and the write of its result; the
score of its labels is worked out after it, outside of the time.
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronocluster import catalog, plans, quality
from chronocluster.generators import planted_edges, preset
from chronocluster.session import cut
from chronocluster.supra import auto_omega, couple, supra_graph, supra_size
from chronocluster.temporal import TemporalGraph
from chronocluster.workloads import WORKLOADS

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
RUNS = int(os.environ.get("BENCH_RUNS", "1"))
MAIN_RUNS = int(os.environ.get("BENCH_MAIN_RUNS", "2"))
BUDGET = float(os.environ.get("BENCH_BUDGET_S", "90"))
TOTAL = float(os.environ.get("BENCH_TOTAL_S", "330"))
ONLY = [x for x in os.environ.get("BENCH_ONLY", "").split(",") if x]
PLANTED = int(os.environ.get("BENCH_PLANTED", "50000"))


#: The rows that are run several times, for a spread.
MAIN = ("leiden_supra_trade_region_year_thinned", "leiden_multislice_trade_region_year_thinned")

#: The rows that come first, so that each kind of method is measured before BENCH_TOTAL_S.
FIRST = (
    *MAIN,
    "leiden_supra_docwords_arrival",
    "leiden_multislice_docwords_arrival",
    "baseline_sequential_trade_region_year_thinned",
    "spectral_deformed_nation",
    "independent_snapshots_cosupp_day",
    "leiden_sbm_base",
    "leiden_windowed_trade",
    "properties_copart_quarter",
    "supra_contact_hour",
    "couple_contact_5min",
    "multislice_modularity",
)


def session() -> SparkSession:
    builder = SparkSession.builder.master(f"local[{CPUS}]").appName("bench")
    for k, v in {"spark.sql.shuffle.partitions": CPUS, "spark.driver.memory": "8g", "spark.sql.session.timeZone": "UTC", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false"}.items():
        builder = builder.config(k, v)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def stop_late(spark: SparkSession, group: str, done: threading.Event) -> None:
    """Cancel the jobs of a group once its time is over, and those that follow, until it is done."""
    wait = BUDGET
    while not done.wait(wait):
        spark.sparkContext.cancelJobGroup(group)
        wait = 0.5


def costs(spark: SparkSession, group: str) -> dict[str, float]:
    """Jobs (trips to the driver), stages and MB shuffled of a job group, from the engine's own counters."""
    tracker, store = spark.sparkContext.statusTracker(), spark.sparkContext._jsc.sc().statusStore()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds}
    moved = 0
    for s in stages:
        try:
            moved += store.lastStageAttempt(s).shuffleWriteBytes()
        except Exception:  # a stage that was skipped has no record
            continue
    return {"jobs": len(jobs), "stages": len(stages), "shuffle_mb": round(moved / 1e6, 1)}


def main() -> None:
    spark = session()
    methods: dict[str, Callable[[], DataFrame]] = {}

    def on(name: str) -> TemporalGraph:
        return TemporalGraph(WORKLOADS[name].build(spark, SF), WORKLOADS[name].directed)

    scored: dict[str, tuple[str, DataFrame]] = {}

    def leiden(row: str, name: str, method: Callable[[TemporalGraph], DataFrame]) -> None:
        def labelled() -> DataFrame:
            labels = cut(method(on(name)), "labels")
            scored[row] = (name, labels)
            return labels

        methods[row] = labelled

    for name in ("trade_region_year_thinned", "docwords_arrival", "nation_trade_year", "docwords_static", "contact_5min", "copart_quarter_thinned", "vec_knn_static"):
        leiden(f"leiden_supra_{name}", name, lambda g: plans.leiden(g, "auto", null="global"))
        leiden(f"leiden_multislice_{name}", name, lambda g: plans.leiden(g, "auto"))
    for name in ("trade_region_year_thinned", "docwords_arrival"):
        leiden(f"baseline_sequential_{name}", name, lambda g: plans.baseline_multislice_sequential(g, "auto"))
    leiden("leiden_windowed_trade", "trade_region_year_thinned", lambda g: plans.windowed(g, 3, 2, "auto"))
    leiden("leiden_distributed_trade_region_year_thinned", "trade_region_year_thinned", lambda g: plans.leiden(g, "auto", backend_name="distributed"))
    methods["independent_snapshots_cosupp_day"] = lambda: plans.independent_snapshots(on("cosupp_day"))
    methods["spectral_deformed_nation"] = lambda: plans.spectral_clustering(on("nation_trade_year_thinned"), 5, omega=200.0)
    methods["spectral_multislice_nation"] = lambda: plans.spectral_clustering(on("nation_trade_year_thinned"), 5, "modularity", omega=200.0)
    for name in ("base", "nodes", "edges", "snapshots"):
        methods[f"leiden_sbm_{name}"] = lambda n=name: plans.leiden(TemporalGraph(planted_edges(spark, preset(n, PLANTED))), 4.0, null="global", backend_name="kernel")
    for name in ("copart_quarter", "contact_hour", "contact_5min"):
        methods[f"properties_{name}"] = lambda n=name: catalog.QUERIES[f"properties_{n}"](spark, SF)
        methods[f"supra_{name}"] = lambda n=name: supra_size(supra_graph(on(n)))
    methods["couple_contact_5min"] = lambda: couple(on("contact_5min").nodes)

    def multislice() -> DataFrame:
        tg = on("copart_quarter").stored()
        return quality.multislice_modularity(tg, catalog.rule_labels(tg.nodes))

    methods["multislice_modularity"] = multislice
    methods = {**{name: methods[name] for name in FIRST}, **methods}
    run(spark.range(10).groupBy(F.col("id") % 2).count())
    seconds, spread, status, counters = {}, {}, {}, {}
    started = time.time()
    for name, make in methods.items():
        if ONLY and name not in ONLY:
            continue
        if time.time() - started > TOTAL:
            status[name] = "not begun: BENCH_TOTAL_S"
            continue
        took = []
        spark.sparkContext.setJobGroup(name, name)
        for _ in range(MAIN_RUNS if name in MAIN else RUNS):
            began, done = time.time(), threading.Event()
            threading.Thread(target=stop_late, args=(spark, name, done), daemon=True).start()
            try:
                run(make())
            except Exception as problem:  # a method that fails or is stopped is reported, not hidden
                status[name] = "OOT" if time.time() - began >= BUDGET else f"{type(problem).__name__}: {str(problem)[:120]}"
                break
            finally:
                done.set()
            took.append(time.time() - began)
        print(name, [round(t, 1) for t in took], status.get(name, ""), file=sys.stderr, flush=True)
        counters[name] = costs(spark, name)
        if took:
            seconds[name], spread[name] = round(statistics.mean(took), 3), round(statistics.stdev(took), 3) if len(took) > 1 else 0.0
    spark.sparkContext.setJobGroup("scores", "scores")
    scores = {}
    for name in ("trade_region_year_thinned", "docwords_arrival"):
        tg = on(name).stored()
        omega = auto_omega(tg.edges)
        for row in (r for r, (n, _) in scored.items() if n == name and r in seconds):
            scores[row] = round(quality.multislice_modularity(tg, scored[row][1], omega=omega).first().q_ms, 5)
    ratio = lambda a, b: round(seconds[a] / seconds[b], 2) if a in seconds and b in seconds else None
    more = {
        **{f"sequential_over_supra_{x}": ratio(f"baseline_sequential_{x}", f"leiden_supra_{x}") for x in ("trade_region_year_thinned", "docwords_arrival")},
        **{f"doubling_{x}": ratio(f"leiden_sbm_{x}", "leiden_sbm_base") for x in ("nodes", "edges", "snapshots")},
    }
    print(json.dumps({"metric": "sum of mean seconds of the headline methods", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sd": spread, "runs": RUNS, "main_runs": MAIN_RUNS, "q_ms": scores, "ratios": more, "status": status, "costs": counters, "sf": SF, "cpus": int(CPUS)}))
    spark.stop()


if __name__ == "__main__":
    main()
