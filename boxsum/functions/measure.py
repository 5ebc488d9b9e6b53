"""Measures of accuracy, storage, reads, headroom, time and price."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.operators import query
from boxsum.operators.build import AnchorStore, points
from boxsum.plans.box import BoxPlan


def nrmsd(brute: DataFrame, fast: DataFrame, keys: list[str], value: str = "avg", by: Iterable[str] = ()) -> DataFrame:
    """(by, unmatched, n, nrmsd, max_abs, max_rel): differences of two results over all points, for each value of some keys; null where the range is 0."""
    a = brute.select(*keys, F.col(value).alias("a"), F.lit(1).alias("in_a"))
    b = fast.select(*keys, F.col(value).alias("b"), F.lit(1).alias("in_b"))
    both = a.join(b, keys, "full")
    off = F.abs(F.col("a") - F.col("b"))
    spread = F.max("a") - F.min("a")
    return both.groupBy(*by).agg(
        F.sum((F.col("in_a").isNull() | F.col("in_b").isNull()).cast("long")).alias("unmatched"), F.count("*").alias("n"),
        F.when(spread > 0, F.sqrt(F.avg(off * off)) / spread).alias("nrmsd"), F.max(off).alias("max_abs"), F.max(F.try_divide(off, F.abs("a"))).alias("max_rel"),
    )


def overhead(store: AnchorStore) -> DataFrame:
    """(subset, points, fraction): rows of each table on a grid without empty cells, against the cells."""
    rows = [("_".join(s), points(store.grid, spec), points(store.grid, spec) / store.grid.cells) for s, spec in store.specs.items()]
    return store.cells.sparkSession.createDataFrame(rows, "subset string, points long, fraction double")


def headroom(table: DataFrame, measure: str = "sx") -> DataFrame:
    """(largest, share): the largest absolute sum, and what share of a bigint's range it takes."""
    return table.agg(F.max(F.abs(measure)).alias("largest"), (F.max(F.abs(measure)).cast("double") / (2.0**63 - 1)).alias("share"))


def reads_row(plan: BoxPlan) -> tuple[int, int, int, int]:
    """(scans, anchor rows, gap cells, all) of a plan."""
    roles = plan.by_role()
    return len(plan.scans), roles["anchor"], roles["gap"], plan.reads()


def touched(store: AnchorStore, plan: BoxPlan) -> DataFrame:
    """(tiles, found, anchor_rows, anchor_rows_found, touched, touched_found): tiles of cells and rows of anchor tables that a plan expects to read, and those that its scans find."""
    tile = F.struct(*(F.floor(F.col(a.name) / a.tile).alias(a.name) for a in store.grid.axes))
    of_cells = lambda t: query.scan_rows(store, t).select(tile.alias("tile"), F.lit(None).cast("int").alias("anchor"))
    of_anchors = lambda t: query.scan_rows(store, t).select(F.lit(None).alias("tile"), F.lit(1).alias("anchor"))
    found = union((of_anchors if t.subset else of_cells)(t) for t in plan.scans).agg(F.countDistinct("tile").alias("found"), F.count("anchor").alias("anchor_rows_found"))
    tiles, rows = (F.lit(n).cast("long") for n in (plan.tiles(store.grid), plan.by_role()["anchor"]))
    return found.select(tiles.alias("tiles"), "found", rows.alias("anchor_rows"), "anchor_rows_found", (tiles + rows).alias("touched"), (F.col("found") + F.col("anchor_rows_found")).alias("touched_found"))


def timed(run: Callable[[], DataFrame], repeat: int = 3, warm: bool = True) -> float:
    """Median seconds to compute every row of a result."""
    took = []
    for k in range(repeat + warm):
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if k >= warm:
            took.append(time.perf_counter() - began)
    return sorted(took)[len(took) // 2]


def speedup(brute_s: float, fast_s: float) -> tuple[float, float]:
    """The ratio, and its decimal logarithm."""
    return brute_s / fast_s, math.log10(brute_s / fast_s)


def price(seconds: float, per_hour: float, requests: int = 1) -> float:
    return seconds / 3600 * per_hour * requests


def scaling(timings: DataFrame) -> DataFrame:
    """(method, slope, intercept): seconds against slices, by least squares."""
    return timings.groupBy("method").agg(F.regr_slope("seconds", "slices").alias("slope"), F.regr_intercept("seconds", "slices").alias("intercept"))


def union(frames: Iterable[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
