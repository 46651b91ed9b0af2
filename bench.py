"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

The shared graphs are built once, as a user would keep them; each query then
counts its triangles by another method.  `setup` is the time that this takes.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import DataFrame, SparkSession

from tricell.costs.measured import spark_cost
from tricell.model import MemoryModel
from tricell.operators import baselines, canonical, cells, recursive, steered
from tricell.plans import choose
from tricell.sources import graphs
from tricell.tables import stored


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g"))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session()
    times: dict[str, float] = {}
    counts: dict[str, int] = {}
    moved: dict[str, dict] = {}

    def run(name: str, build) -> None:
        began = time.time()
        counts[name], cost = spark_cost(spark, lambda: build().count())
        times[name] = round(time.time() - began, 3)
        moved[name] = {"shuffle_records": cost.shuffle_records, "shuffle_mb": round(cost.shuffle_bytes / 1e6, 1), "spilled_mb": round(cost.spilled_bytes / 1e6, 1), "tasks": cost.tasks}
        print(name, times[name], counts[name], file=sys.stderr, flush=True)

    began = time.time()
    ranked: dict[str, tuple[DataFrame, int]] = {}
    for g in ("copurchase", "cps", "cbt", "hub"):
        r = stored(canonical.orient(canonical.canonical_edges(graphs.GRAPHS[g](spark, sf_dir)), keep_degrees=True), g)
        ranked[g] = (r, r.count())
    setup = round(time.time() - began, 3)
    for g in ("copurchase", "cps"):
        r, n = ranked[g]
        e = r.select("lo", "hi")
        run(f"{g}_naive", lambda e=e: baselines.naive_triangles(e))
        run(f"{g}_sort_wedge", lambda e=e: baselines.sort_wedge_triangles(e))
        for c in (2, 4):
            mm = MemoryModel.for_colours(n, c)
            run(f"{g}_cells_c{c}", lambda r=r, n=n, mm=mm: cells.enumerate_cells(r, mm, edges=n))
        run(f"{g}_planned_c4", lambda r=r, n=n: choose.enumerate_planned(r, MemoryModel.for_colours(n, 4)))
    for g in ("cbt", "hub"):
        r, n = ranked[g]
        e = r.select("lo", "hi")
        for c in (4, 16):
            mm = MemoryModel.for_colours(n, c)
            run(f"{g}_cells_c{c}", lambda r=r, n=n, mm=mm: cells.enumerate_cells(r, mm, edges=n))
        run(f"{g}_base_scan_c2", lambda e=e, n=n: baselines.base_scan_triangles(e, MemoryModel.for_colours(n, 2)))
        run(f"{g}_recursive", lambda r=r, n=n: recursive.enumerate_recursive(r, base_size=1 << 14))
    r, n = ranked["cbt"]
    deg = canonical.degrees(r.select("lo", "hi"))
    run("cbt_steered_c4", lambda: steered.enumerate_steered(r, deg, MemoryModel.for_colours(n, 4), edges=n))
    for g in ranked:
        own = {v for k, v in counts.items() if k.startswith(f"{g}_")}
        if len(own) > 1:
            raise SystemExit(f"methods disagree on {g}: {own}")
    print(json.dumps({"metric": "triangle_methods_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1], "setup": setup, "triangles": counts, "moved": moved}))


if __name__ == "__main__":
    main()
