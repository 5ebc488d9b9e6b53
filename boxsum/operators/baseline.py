"""What the anchors are compared with: full scans, sums at every cell, tile totals, and cached results."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxsum.operators.build import running
from boxsum.operators.query import divided
from boxsum.plans.box import Range, plan_box
from boxsum.plans.spec import GridSpec


def _inside(box: Mapping[str, Range]):
    return reduce(lambda x, y: x & y, ((F.col(a) >= lo) & (F.col(a) < hi) for a, (lo, hi) in box.items()), F.lit(True))


def scan_average(cells: DataFrame, grid: GridSpec, box: Mapping[str, Range], average_over: Iterable[str], divisor: str = "cells") -> DataFrame:
    """(kept axes, s, n, avg) by reading every cell of the box."""
    plan = plan_box(grid, {}, box, average_over)
    measures = {"cells": ["sx", "n"], "weight": ["swx", "sw", "n"], "present": ["sx", "p", "n"]}[divisor]
    sums = cells.where(_inside(box)).groupBy(*plan.kept).agg(*(F.sum(m).alias(m) for m in measures))
    return divided(sums, plan.kept, plan.extent, divisor)


def scan_sums(cells: DataFrame, grid: GridSpec, axis: str, ranges: Iterable[Range], average_over: Iterable[str], measures: Iterable[str] = ("sx", "n")) -> DataFrame:
    """(kept axes, lo, hi, extent, measures) of several ranges of one axis, by reading every cell once.

    A kept axis gives its points to all ranges that they are in. An averaged one is first summed between each two
    neighbouring ends of the ranges, and each range is the sum of its parts.
    """
    ranges, measures = list(ranges), list(measures)
    plans = {r: plan_box(grid, {}, {axis: r}, average_over) for r in ranges}
    kept, ends = [*plans[ranges[0]].kept], sorted({e for r in ranges for e in r})
    split = axis not in kept
    part = reduce(lambda x, y: x + y, ((F.col(axis) >= e).cast("int") for e in ends))
    sums = cells.groupBy(*kept, *([part.alias("__part")] if split else [])).agg(*(F.sum(m).alias(m) for m in measures))
    inside = lambda lo, hi: F.col("__part").between(ends.index(lo) + 1, ends.index(hi)) if split else (F.col(axis) >= lo) & (F.col(axis) < hi)
    each = F.array(*(F.when(inside(*r), F.struct(F.lit(r[0]).alias("lo"), F.lit(r[1]).alias("hi"), F.lit(plans[r].extent).cast("long").alias("extent"))) for r in ranges))
    rows = sums.select(*kept, *measures, F.inline(F.filter(each, lambda x: x.isNotNull())))
    if not split:
        return rows.select(*kept, "lo", "hi", "extent", *measures)
    return rows.groupBy(*kept, "lo", "hi", "extent").agg(*(F.sum(m).alias(m) for m in measures))


def densify(cells: DataFrame, grid: GridSpec) -> DataFrame:
    """A row for every cell of the grid; measures of missing ones are 0."""
    spark = cells.sparkSession
    lines = [spark.range(a.n).select(F.col("id").cast("int").alias(a.name)) for a in grid.axes]
    full = reduce(lambda x, y: x.crossJoin(y), lines)  # the axes' lengths multiply to the grid's, which is what is wanted
    return full.join(cells, list(grid.names), "left").select(*grid.names, *(F.coalesce(m, F.lit(0)).alias(m) for m in grid.measures))


def build_full_prefix(cells: DataFrame, grid: GridSpec, over: Iterable[str]) -> DataFrame:
    """Cumulative sums at every cell along the given axes, over the densified grid: one row a cell."""
    rows = densify(cells, grid)
    for a in grid.order(over):
        w = Window.partitionBy(*(b for b in grid.names if b != a)).orderBy(a).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        rows = rows.select(*grid.names, *(F.sum(m).over(w).alias(m) for m in grid.measures))
    return rows


def full_prefix_average(prefix: DataFrame, grid: GridSpec, box: Mapping[str, Range], average_over: Iterable[str]) -> DataFrame:
    """(kept axes, s, n, avg) from 2^k reads a kept point of sums at every cell."""
    plan = plan_box(grid, {}, box, average_over)
    rows, sign = prefix, F.lit(1)
    for a in plan.averaged:
        lo, hi = box.get(a, (0, grid[a].n))
        rows = rows.where(F.col(a).isin([i for i in (lo - 1, hi - 1) if i >= 0]))
        sign = sign * F.when(F.col(a) == hi - 1, 1).otherwise(-1)
    kept = {a: box[a] for a in plan.kept if a in box}
    sums = rows.where(_inside(kept)).groupBy(*plan.kept).agg(*(F.sum(F.col(m) * sign).alias(m) for m in ("sx", "n"))).where("n > 0")
    return divided(sums, plan.kept, plan.extent)


def tile_total_average(cells: DataFrame, grid: GridSpec, box: Mapping[str, Range], average_over: Iterable[str], totals: DataFrame | None = None) -> DataFrame:
    """(kept axes, s, n, avg) from totals of covered tiles, not cumulated, and the cells around them."""
    plan = plan_box(grid, {}, box, average_over)
    tiles = {a: F.floor(F.col(a) / grid[a].tile).cast("int") for a in plan.averaged}
    if totals is None:
        totals = cells.groupBy(*(t.alias(f"tile_{a}") for a, t in tiles.items()), *plan.kept).agg(F.sum("sx").alias("sx"), F.sum("n").alias("n"))
    full = {a: (-(-box.get(a, (0, grid[a].n))[0] // grid[a].tile), box.get(a, (0, grid[a].n))[1] // grid[a].tile) for a in plan.averaged}
    core = {a: (lo * grid[a].tile, hi * grid[a].tile) for a, (lo, hi) in full.items()}
    kept = {a: box[a] for a in plan.kept if a in box}
    covered = totals.where(_inside(kept)).where(_inside({f"tile_{a}": r for a, r in full.items()}))
    rim = cells.where(_inside(box)).where(~_inside(core))
    sums = covered.select(*plan.kept, "sx", "n").unionByName(rim.select(*plan.kept, "sx", "n")).groupBy(*plan.kept).agg(F.sum("sx").alias("sx"), F.sum("n").alias("n"))
    return divided(sums, plan.kept, plan.extent)


class CachedAverager:
    """Keeps the results of boxes that were asked for, by their bounds; storage grows with the different requests."""

    def __init__(self, answer):
        self.answer, self.kept, self.hits = answer, {}, 0

    def __call__(self, box: Mapping[str, Range], average_over: Iterable[str]) -> DataFrame:
        key = (tuple(sorted((a, tuple(r)) for a, r in box.items())), tuple(sorted(average_over)))
        if key in self.kept:
            self.hits += 1
        else:
            self.kept[key] = self.answer(box, average_over).persist()
        return self.kept[key]

    def clear(self) -> None:
        for df in self.kept.values():
            df.unpersist()
        self.kept.clear()


def range_average(cells: DataFrame, axis: str, lo: int, hi: int, value: str = "sx") -> DataFrame:
    """(s, avg) of one range of a line, as the difference of two cumulative sums: the last ones below its ends."""
    sums = running(cells.select(F.col(axis).alias("__m"), F.col(value).alias("sx")), [], {"sx": "sum"}, hi)
    below = lambda end: F.coalesce(F.max_by("sx", F.when(F.col("__m") < end, F.col("__m"))), F.lit(0))
    s = below(hi) - below(lo)
    return sums.where(F.col("__m") < hi).agg(s.alias("s"), (s.cast("double") / (hi - lo)).alias("avg"))
