"""Sums and averages of boxes from anchors and a few cells."""

from __future__ import annotations

import math
from collections.abc import Iterable, Mapping
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from boxsum.operators.build import AnchorStore, accumulate
from boxsum.plans.box import BoxPlan, Range, ScanTerm, plan_box
from boxsum.plans.spec import GridSpec, SpecError, common_step, usable


def _sign(column: str, values: list[tuple[Column, int]]) -> Column:
    """The sign of the first condition that holds; one that holds for all is a literal."""
    if len(values) == 1:
        return F.lit(values[0][1])
    out = F.when(values[0][0], values[0][1])
    for condition, sign in values[1:]:
        out = out.when(condition, sign)
    return out


def scan_rows(store: AnchorStore, term: ScanTerm) -> DataFrame:
    """The stored rows that one scan reads, with all their columns; one in several pieces once. Filters are on stored columns, so they reach the files."""
    rows = store.tables[term.subset] if term.subset else store.cells
    for a, qs in term.anchors.items():
        rows = rows.where(F.col(f"q_{a}").isin([x for x, _ in qs]))
    for a, gaps in term.gaps.items():
        rows = rows.where(reduce(lambda x, y: x | y, ((F.col(a) >= lo) & (F.col(a) < hi) for lo, hi, _ in gaps)))
    for a, (lo, hi) in term.kept.items():
        if (lo, hi) != (0, store.grid[a].n):
            rows = rows.where((F.col(a) >= lo) & (F.col(a) < hi))
    return rows


def scan_term(store: AnchorStore, term: ScanTerm, measures: Iterable[str]) -> DataFrame:
    """The rows of one scan with signed measures."""
    signs: list[Column] = []
    for a, qs in term.anchors.items():
        signs.append(_sign(a, [(F.col(f"q_{a}") == x, s) for x, s in qs]))
    for a, gaps in term.gaps.items():
        inside = [((F.col(a) >= lo) & (F.col(a) < hi), s) for lo, hi, s in gaps]
        # gaps of both ends may overlap where one anchor is above its end: then both signs count
        signs.append(inside[0][1] * F.lit(1) if len(inside) == 1 else sum((F.when(c, s).otherwise(0) for c, s in inside[1:]), F.when(inside[0][0], inside[0][1]).otherwise(0)))
    sign = reduce(lambda x, y: x * y, (s if isinstance(s, Column) else F.lit(s) for s in signs), F.lit(1))
    return scan_rows(store, term).select(*term.kept, *((F.col(m) * sign).alias(m) for m in measures))


def signed_rows(store: AnchorStore, plan: BoxPlan, measures: Iterable[str]) -> DataFrame:
    return reduce(DataFrame.unionByName, (scan_term(store, t, measures) for t in plan.scans))


def plan_of(store: AnchorStore, box: Mapping[str, Range], average_over: Iterable[str], mode: str = "floor") -> BoxPlan:
    return plan_box(store.grid, store.specs, box, average_over, mode, store.scan_cost)


def box_sum(store: AnchorStore, box: Mapping[str, Range], average_over: Iterable[str], mode: str = "floor", measures: Iterable[str] | None = None) -> DataFrame:
    """(kept axes, measures): sums over the box for each point of the kept axes that has a cell in the box."""
    measures = list(measures or store.grid.measures)
    plan = plan_of(store, box, average_over, mode)
    if not store.in_parts and len(plan.scans) == 1 and plan.scans[0].subset == plan.averaged and all(len(q) == 1 for q in plan.scans[0].anchors.values()):
        return scan_term(store, plan.scans[0], measures).where("n > 0")  # one anchor row a point: nothing to add up, no shuffle
    return signed_rows(store, plan, measures).groupBy(*plan.kept).agg(*(F.sum(m).alias(m) for m in measures)).where("n > 0")


def divided(rows: DataFrame, keys: Iterable[str], extent: int | Column, divisor: str = "cells") -> DataFrame:
    """(keys, s, n, avg) from summed measures: per cell of the box, per weight, or per cell that is there."""
    top, bottom = {"cells": ("sx", F.lit(extent)), "weight": ("swx", F.col("sw")), "present": ("sx", F.col("p"))}[divisor]
    return rows.select(*keys, F.col(top).alias("s"), "n", F.try_divide(F.col(top).cast("double"), bottom.cast("double")).alias("avg"))


def box_average(store: AnchorStore, box: Mapping[str, Range], average_over: Iterable[str], mode: str = "floor", divisor: str = "cells", complete: bool = False) -> DataFrame:
    """(kept axes, s, n, avg). n counts source rows in the box; `complete` adds the points of one kept axis without any."""
    measures = {"cells": ["sx", "n"], "weight": ["swx", "sw", "n"], "present": ["sx", "p", "n"]}[divisor]
    plan = plan_of(store, box, average_over, mode)
    out = divided(box_sum(store, box, average_over, mode, measures), plan.kept, plan.extent, divisor)
    if complete:
        if len(plan.kept) != 1:
            raise SpecError("only a single kept axis can be completed")
        (axis,) = plan.kept
        lo, hi = box.get(axis, (0, store.grid[axis].n))
        line = store.cells.sparkSession.range(lo, hi).select(F.col("id").cast("int").alias(axis))
        out = line.join(out, axis, "left").select(axis, F.coalesce("s", F.lit(0)).alias("s"), F.coalesce("n", F.lit(0)).alias("n"), "avg")
    return out


def area_series(store: AnchorStore, box: Mapping[str, Range], time: str = "t", **options) -> DataFrame:
    """Averages over all axes but time, for each time."""
    return box_average(store, box, [a for a in store.grid.names if a != time], **options)


def time_map(store: AnchorStore, box: Mapping[str, Range], time: str = "t", **options) -> DataFrame:
    """Averages over a time range, for each point of the other axes."""
    return box_average(store, box, [time], **options)


def box_moments(store: AnchorStore, box: Mapping[str, Range], average_over: Iterable[str], mode: str = "floor") -> DataFrame:
    """(kept axes, p, mean, variance): of the values of cells in the box.

    The variance is taken in exact decimals before dividing; where n * sum(x^2) has more than 38 digits, in doubles.
    """
    plan = plan_of(store, box, average_over, mode)
    sums = box_sum(store, box, average_over, mode, ["sx", "sxx", "p", "n"])
    sx, p, sxx = F.col("sx").cast("decimal(19,0)"), F.col("p").cast("decimal(19,0)"), F.col("sxx").cast("decimal(38,0)")
    exact = F.try_subtract(F.try_multiply(sxx, p), F.try_multiply(sx, sx))
    count = F.col("p").cast("double")
    mean = F.col("sx").cast("double") / count
    variance = F.coalesce(exact.cast("double") / (count * count), F.col("sxx").cast("double") / count - mean * mean)
    return sums.select(*plan.kept, "p", mean.alias("mean"), F.greatest(F.lit(0.0), variance).alias("variance"))


def box_average_many(store: AnchorStore, boxes: DataFrame, average_over: Iterable[str], measures: Iterable[str] = ("sx", "n"), mode: str = "floor") -> DataFrame:
    """(box_id, kept axes, s, n, avg) of a table of boxes: box_id and <axis>_lo, <axis>_hi for each axis, half-open.

    Each averaged axis that anchors are used for gives the signed anchors and gap cells of a box as arrays; each
    subset's scan is a plain equi-join on anchor numbers and gap indices, a range condition only on the other axes.
    Anchors are used for the most averaged axes all of whose subsets are there, at least one.
    """
    grid, over, measures = store.grid, store.grid.order(average_over), list(measures)
    kept = [a for a in grid.names if a not in over]
    used = usable(over, store.specs)
    if not used:
        raise SpecError("many boxes need a table of an averaged axis")
    plain = [a for a in grid.names if a not in used]
    subsets = [s for s in store.specs if set(s) <= set(used)]
    empty = F.array().cast("array<struct<i: int, sign: int>>")
    rows = boxes
    for a in used:
        step, n = common_step(grid, [store.specs[s] for s in subsets], a), grid[a].n
        piece = lambda i, s: F.struct(i.cast("int").alias("i"), F.lit(s).alias("sign"))
        span = lambda x, y, s: F.when(x < y, F.transform(F.sequence(x, y - 1), lambda i: piece(i, s))).otherwise(empty)  # noqa: E731, B023
        ends = {}
        for end in ("lo", "hi"):
            e = F.col(f"{a}_{end}")
            below = F.floor(e / step).cast("int")
            above = (below + 1) * step
            up = (above <= n) & (above - e < e - below * step) if mode == "nearest" else F.lit(False)
            ends[end] = e, F.when(up, below + 1).otherwise(below)
        (lo, q_lo), (hi, q_hi) = ends["lo"], ends["hi"]
        gap = lambda e, q, s: F.when(q * step > e, span(e, q * step, -s)).otherwise(span(q * step, e, s))  # noqa: E731, B023
        anchors = F.filter(F.array(piece(q_hi, 1), piece(q_lo, -1)), lambda p: p["i"] > 0)
        rows = rows.withColumn(f"anchors_{a}", F.when(q_lo == q_hi, empty).otherwise(anchors))
        rows = rows.withColumn(f"gaps_{a}", F.when(q_lo == q_hi, span(lo, hi, 1)).otherwise(F.concat(gap(hi, q_hi, 1), gap(lo, q_lo, -1))))
    terms = []
    for s in [(), *subsets]:
        wanted = rows.withColumn("sign", F.lit(1))
        for a in used:
            wanted = wanted.withColumn("piece", F.explode(f"{'anchors' if a in s else 'gaps'}_{a}")).withColumn(f"at_{a}", F.col("piece.i")).withColumn("sign", F.col("sign") * F.col("piece.sign")).drop("piece")
        wanted = wanted.select("box_id", "sign", *(f"at_{a}" for a in used), *(f"{a}_{end}" for a in plain for end in ("lo", "hi")))
        table = store.tables[s] if s else store.cells
        conditions = []
        for a in used:
            scale = common_step(grid, [store.specs[x] for x in subsets], a) // (grid[a].tile * store.specs[s].of(a)) if a in s else 1
            conditions.append(table[f"q_{a}" if a in s else a] == wanted[f"at_{a}"] * scale)
        conditions += [(table[a] >= wanted[f"{a}_lo"]) & (table[a] < wanted[f"{a}_hi"]) for a in plain]
        joined = table.join(wanted, reduce(lambda x, y: x & y, conditions))
        terms.append(joined.select("box_id", *(table[a] for a in kept), *((table[m] * wanted["sign"]).alias(m) for m in measures)))
    sums = reduce(DataFrame.unionByName, terms).groupBy("box_id", *kept).agg(*(F.sum(m).alias(m) for m in measures)).where("n > 0")
    extent = reduce(lambda x, y: x * y, (F.col(f"{a}_hi").cast("long") - F.col(f"{a}_lo") for a in over))
    return sums.join(boxes.select("box_id", extent.alias("extent")), "box_id").select("box_id", *kept, F.col("sx").alias("s"), "n", (F.col("sx").cast("double") / F.col("extent")).alias("avg"))


def patched_tile(store: AnchorStore, tile: Mapping[str, int], average_over: Iterable[str]) -> DataFrame:
    """(axes, value, role): a step-sized tile whose leading faces hold sums from the origin instead of their cells.

    A step is the least common multiple of the strides of an axis' tables, in tiles. Faces are replaced along the
    axes that anchors can be used for: the most of the averaged ones all of whose subsets are there (none, if there
    is no table). A cell at the tile's first index of the axes S of these (`role`, empty for none) holds the sum of
    all cells up to its own index along S; the rest is raw, and cells that are missing are 0. Summing from the
    tile's first cell to an end then gives the sum, along those axes, from the origin to that end, the end's cell
    included.
    """
    grid = store.grid
    over = usable(grid.order(average_over), store.specs)
    spark = store.cells.sparkSession
    subsets = [s for s in store.specs if s and set(s) <= set(over)]
    step = {a.name: a.tile * math.lcm(*(store.specs[s].of(a.name) for s in subsets if a.name in s)) for a in grid.axes}
    first = {a: tile[a] * step[a] for a in grid.names}
    for a in grid.names:
        if not 0 <= first[a] < grid[a].n:
            raise SpecError(f"{a} has no tile {tile[a]}")
    out = spark.range(1).select()
    for a in grid.names:
        out = out.withColumn(a, F.explode(F.sequence(F.lit(first[a]), F.lit(min(first[a] + step[a], grid[a].n) - 1))))
    roles = F.filter(F.array(*(F.when(F.col(a) == first[a], F.lit(a)) for a in over)), lambda x: x.isNotNull()) if over else F.array().cast("array<string>")
    out = out.select(*grid.names, roles.alias("role"))
    inside = reduce(lambda x, y: x & y, ((F.col(a) >= first[a]) & (F.col(a) < first[a] + step[a]) for a in grid.names))
    raw = store.cells.where(inside).groupBy(*grid.names).agg(F.sum("sx").alias("value"))
    out = out.join(raw, list(grid.names), "left").withColumn("value", F.coalesce("value", F.lit(0)))
    for s in subsets:
        if not all(tile[a] for a in s):
            continue  # nothing lies below the origin
        rest = [a for a in grid.names if a not in s]
        table = store.tables[s]
        for a in s:
            table = table.where(F.col(f"q_{a}") == first[a] // (grid[a].tile * store.specs[s].of(a)))
        below = table.groupBy(*rest).agg(F.sum("sx").alias("below"))  # without other axes, one row in any case
        out = out.join(below, rest, "left") if rest else out.crossJoin(below)
        holds = reduce(lambda x, y: x & y, (F.array_contains("role", a) for a in s))
        out = out.withColumn("value", F.col("value") + F.when(holds, F.coalesce("below", F.lit(0))).otherwise(0)).drop("below")
    return out


def tile_extrema(cells: DataFrame, grid: GridSpec, over: Iterable[str]) -> DataFrame:
    """(tile_<averaged axes>, kept axes, mn, mx) of each tile."""
    over = grid.order(over)
    kept = [a for a in grid.names if a not in over]
    return cells.groupBy(*(F.floor(F.col(a) / grid[a].tile).cast("int").alias(f"tile_{a}") for a in over), *kept).agg(F.min("sx").alias("mn"), F.max("sx").alias("mx"))


def running_extrema(cells: DataFrame, grid: GridSpec, axis: str) -> DataFrame:
    """(other axes, q_<axis>, mn, mx) of all cells below each tile boundary of an axis."""
    raw = cells.select(*grid.names, F.col("sx").alias("mn"), F.col("sx").alias("mx"))
    return accumulate(raw, [a for a in grid.names if a != axis], axis, grid[axis].tile, grid[axis].n, {"mn": "min", "mx": "max"})


def block_extrema(cells: DataFrame, grid: GridSpec, axis: str) -> DataFrame:
    """(other axes, level, tile_<axis>, mn, mx): of the 2^level tiles from each one on.

    Two blocks of a level cover any run of tiles. Each level is the one before with itself moved, on the tiles'
    extrema; a block without a cell has no row. Log2 of the tiles as many rows as there are tiles, at most.
    """
    others, at = [a for a in grid.names if a != axis], f"tile_{axis}"
    level = tile_extrema(cells, grid, (axis,))
    levels, size, k = [level.withColumn("level", F.lit(0))], 1, 0
    while 2 * size <= -(-grid[axis].n // grid[axis].tile):
        moved = level.withColumn(at, F.col(at) - size).where(F.col(at) >= 0)
        level = level.unionByName(moved).groupBy(*others, at).agg(F.min("mn").alias("mn"), F.max("mx").alias("mx"))
        size, k = 2 * size, k + 1
        levels.append(level.withColumn("level", F.lit(k)))
    return reduce(DataFrame.unionByName, levels).select(*others, "level", at, "mn", "mx")


def build_extrema(cells: DataFrame, grid: GridSpec, over: Iterable[str], method: str) -> DataFrame:
    """The table that `box_extrema` reads by a method: "tiles" for any axes, "prefix" and "blocks" for one."""
    over = grid.order(over)
    if method == "tiles":
        return tile_extrema(cells, grid, over)
    if method not in ("prefix", "blocks"):
        raise SpecError(f"unknown method {method}")
    if len(over) != 1:
        raise SpecError(f"{method} works along one axis")
    return (running_extrema if method == "prefix" else block_extrema)(cells, grid, over[0])


def box_extrema(cells: DataFrame, grid: GridSpec, box: Mapping[str, Range], average_over: Iterable[str], method: str = "tiles", table: DataFrame | None = None) -> DataFrame:
    """(kept axes, mn, mx) over the cells in a box, from a stored table (`build_extrema`) and the cells that it leaves.

    "tiles" reads the extrema of all covered tiles, "prefix" one row a kept point (boxes from the origin only),
    "blocks" two overlapping blocks of covered tiles; all of them the cells around.
    """
    over = grid.order(average_over)
    kept = [a for a in grid.names if a not in over]
    bounds = {a: box.get(a, (0, grid[a].n)) for a in grid.names}
    within = lambda names: reduce(lambda x, y: x & y, ((F.col(a) >= bounds[a][0]) & (F.col(a) < bounds[a][1]) for a in names), F.lit(True))
    table = build_extrema(cells, grid, over, method) if table is None else table
    full = {a: (-(-bounds[a][0] // grid[a].tile), bounds[a][1] // grid[a].tile) for a in over}
    if method == "tiles":
        covered = table.where(reduce(lambda x, y: x & y, ((F.col(f"tile_{a}") >= lo) & (F.col(f"tile_{a}") < hi) for a, (lo, hi) in full.items())))
    else:
        (a,) = over
        if method == "prefix" and bounds[a][0]:
            raise SpecError("running extrema answer boxes from the origin only")
        lo, hi = full[a]
        level = max(0, hi - lo).bit_length() - 1
        if method == "prefix":
            covered = table.where(F.col(f"q_{a}") == hi)
        else:
            covered = table.where(F.col("level") == level).where(F.col(f"tile_{a}").isin([lo, hi - (1 << max(level, 0))]))
    core = reduce(lambda x, y: x & y, ((F.col(a) >= lo * grid[a].tile) & (F.col(a) < hi * grid[a].tile) for a, (lo, hi) in full.items()))
    rim = cells.where(within(grid.names)).where(~core).select(*kept, F.col("sx").alias("mn"), F.col("sx").alias("mx"))
    return covered.where(within(kept)).select(*kept, "mn", "mx").unionByName(rim).groupBy(*kept).agg(F.min("mn").alias("mn"), F.max("mx").alias("mx"))
