"""Headline timings: series and maps through anchors against full scans, by size; build time, storage and reads.

Raw cells and anchor tables are written once and read from Parquet in every timed run; results go to the noop
sink. Prints one JSON line. Environment: BENCH_SF_DIR, BENCH_CPUS, BENCH_ROWS (rows of the field's plane, all if it
is not given). BENCH_ROWS at several values is the sweep over sizes, BENCH_CPUS=1 the single server.
"""

from __future__ import annotations

import json
import os
import shutil
import sys
import tempfile
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession

from boxsum.functions.measure import price, scaling, speedup, timed
from boxsum.operators import baseline, query
from boxsum.operators.build import AnchorStore, points
from boxsum.plans.box import plan_box
from boxsum.sources import io
from boxsum.sources.grids import G1, dense_field
from boxsum.workloads.cases import all_subsets

RATE = 4.032  # dollars an hour of the machine that the published numbers come from
SERVICES = [("r",), ("c",), ("t",), ("r", "c")]


def size_of(path: str) -> int:
    return sum(p.stat().st_size for p in Path(path.removeprefix("file://")).rglob("*.parquet"))


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus, rows = os.environ.get("BENCH_CPUS", "4"), int(os.environ.get("BENCH_ROWS", "0"))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    root = tempfile.mkdtemp(prefix="boxsum-bench-")
    took: dict[str, float] = {}
    facts: dict[str, object] = {}
    try:
        grid = dense_field(rows or None)
        spec = grid.sized(spark, sf)
        rows = spec["r"].n
        began = time.perf_counter()
        io.write_cells(grid.cells(spark, sf, spec), spec, f"{root}/field/cells", max(8, rows // 100))
        took["write_cells"] = time.perf_counter() - began
        cells = spark.read.parquet(f"{root}/field/cells")
        stores = {}
        for stride in (1, 2, 4):
            began = time.perf_counter()
            io.write_store(AnchorStore.build(cells, spec, SERVICES, stride), f"{root}/field{stride}", with_cells=False)
            took[f"build_stride_{stride}"] = time.perf_counter() - began
            stores[stride] = io.read_store(spark, f"{root}/field{stride}", cells)
            facts[f"supplement_points_stride_{stride}"] = round(sum(points(spec, s) for s in stores[stride].specs.values()) / spec.cells, 5)
            facts[f"supplement_bytes_stride_{stride}"] = round(size_of(f"{root}/field{stride}") / size_of(f"{root}/field/cells"), 5)
        store, timings = stores[2], []
        for service, over in (("series", "rc"), ("map", "t")):
            for k in (80, 240, 400, 560, 720):
                box = {"t": (0, k)}
                fast = took[f"{service}_{k}_anchors"] = timed(lambda: query.box_average(store, box, over))  # noqa: B023
                brute = took[f"{service}_{k}_scan"] = timed(lambda: baseline.scan_average(cells, spec, box, over), 2)  # noqa: B023
                timings += [(service + "_anchors", k, fast), (service + "_scan", k, brute)]
                plan = plan_box(spec, store.specs, box, over)
                facts[f"{service}_{k}"] = {"speedup": round(speedup(brute, fast)[0], 2), "rows_read": plan.reads(), "cells_scanned": rows * 64 * k}
        whole, off = {}, {"r": (13, rows - 13), "c": (5, 59), "t": (31, 700)}
        for stride in (1, 2, 4):
            for service, over in (("series", "rc"), ("map", "t")):
                for mode in ("floor", "nearest", "best"):
                    took[f"{service}_unaligned_stride_{stride}_{mode}"] = timed(lambda: query.box_average(stores[stride], off, over, mode), 2)  # noqa: B023
                    whole[f"{service}_stride_{stride}_{mode}"] = plan_box(spec, stores[stride].specs, off, over, mode).reads()
        facts["unaligned_rows_read"] = whole
        took["series_unaligned_scan"] = timed(lambda: baseline.scan_average(cells, spec, off, "rc"), 2)
        took["map_unaligned_scan"] = timed(lambda: baseline.scan_average(cells, spec, off, "t"), 2)
        ship = AnchorStore.build(G1.cells(spark, sf), G1.spec, all_subsets("yx") + [("t",)])
        began = time.perf_counter()
        io.write_store(ship, f"{root}/ship")
        took["ship_build"] = time.perf_counter() - began
        ship = io.read_store(spark, f"{root}/ship")
        baseline.build_full_prefix(ship.cells, G1.spec, "yx").write.parquet(f"{root}/ship_full")
        full = spark.read.parquet(f"{root}/ship_full")
        region = {"y": (7, 33), "x": (2, 9)}
        took["ship_series_anchors"] = timed(lambda: query.area_series(ship, region))
        took["ship_series_scan"] = timed(lambda: baseline.scan_average(ship.cells, G1.spec, region, "yx"))
        took["ship_series_full_cumulation"] = timed(lambda: baseline.full_prefix_average(full, G1.spec, region, "yx"))
        took["ship_map_anchors"] = timed(lambda: query.time_map(ship, {"t": (0, 2400)}))
        took["ship_map_scan"] = timed(lambda: baseline.scan_average(ship.cells, G1.spec, {"t": (0, 2400)}, "t"))
        facts["slopes"] = {r["method"]: [round(r["slope"], 7), round(r["intercept"], 4)] for r in scaling(spark.createDataFrame(timings, "method string, slices int, seconds double")).collect()}
        facts["dollars_per_100000_series"] = round(price(took["series_720_anchors"], RATE, 100_000), 2)
        facts["cells"] = spec.cells
    finally:
        spark.stop()
        shutil.rmtree(root, ignore_errors=True)
    headline = sum(v for k, v in took.items() if k.endswith("_anchors"))
    print(json.dumps({"metric": "series_and_maps_through_anchors", "value": round(headline, 3), "unit": "sec", "queries": {k: round(v, 4) for k, v in took.items()}, "facts": facts, "sf": sf, "cpus": cpus}))


if __name__ == "__main__":
    main()
