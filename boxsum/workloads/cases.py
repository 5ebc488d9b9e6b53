"""What the registered queries are made of: stores over grids, and brute-force SQL for anchors and boxes."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from itertools import chain, combinations

from pyspark.sql import DataFrame, SparkSession

from boxsum.operators.build import AnchorStore
from boxsum.operators.query import box_average
from boxsum.plans.box import Range
from boxsum.sources import io
from boxsum.sources.grids import Grid

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def add(name: str, query, sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is there already")
    QUERIES[name] = query
    if sql:
        ORACLE_SQL[name] = sql


def all_subsets(axes: Iterable[str]) -> list[tuple[str, ...]]:
    axes = tuple(axes)
    return list(chain.from_iterable(combinations(axes, k) for k in range(1, len(axes) + 1)))


def store_of(spark: SparkSession, sf_dir: str, grid: Grid, subsets, stride=1, reuse: bool = True) -> AnchorStore:
    """A store whose tables are computed from the cells wherever they are read."""
    spec = grid.sized(spark, sf_dir)
    return AnchorStore.build(grid.cells(spark, sf_dir, spec), spec, subsets, stride, reuse)


_STORED: dict[tuple, str] = {}


def stored(spark: SparkSession, sf_dir: str, grid: Grid, subsets, stride=1) -> AnchorStore:
    """A store whose tables were written, once in a session, and are read from there; cells are read from the raw tables."""
    store = store_of(spark, sf_dir, grid, subsets, stride)
    key = (spark.sparkContext.applicationId, sf_dir, store.grid, tuple(sorted(store.specs.items())))
    if key not in _STORED:
        root = io.scratch(spark, store.grid.name)
        io.write_store(store, root, ("plain", "weighted", "weight") if "sw" in store.grid.measures else ("plain",), with_cells=False)
        _STORED[key] = root
    return io.read_store(spark, _STORED[key], store.cells)


def where(box: Mapping[str, Range]) -> str:
    return " AND ".join(f"{a} >= {lo} AND {a} < {hi}" for a, (lo, hi) in box.items()) or "TRUE"


def extent(grid: Grid, box: Mapping[str, Range], over: Iterable[str]) -> str:
    return " * ".join(str(box[a][1] - box[a][0]) if a in box else grid.length_sql(a) for a in over) or "1"


def box_sql(grid: Grid, box: Mapping[str, Range], over: Iterable[str], divisor: str = "cells") -> str:
    """(kept axes, s, n, avg) by reading all cells that have a place."""
    over = grid.spec.order(over)
    kept = [a for a in grid.spec.names if a not in over]
    top, bottom = {"cells": ("sum(sx)", extent(grid, box, over)), "weight": ("sum(swx)", "nullif(sum(sw), 0)"), "present": ("sum(sx)", "sum(p)")}[divisor]
    keys = "".join(f"{a}, " for a in kept)
    tail = f"GROUP BY {', '.join(kept)}" if kept else "HAVING count(*) > 0"
    placed = " AND ".join(f"{a} IS NOT NULL" for a in grid.spec.names)
    return f"WITH cells AS ({grid.sql}) SELECT {keys}CAST({top} AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n, CAST({top} AS DOUBLE) / CAST({bottom} AS DOUBLE) AS avg FROM cells WHERE {placed} AND {where(box)} {tail}"


def anchor_sql(grid: Grid, subset: Iterable[str], stride=1) -> str:
    """The rows of an anchor table with something below: tile sums joined with all anchors beyond them."""
    subset = grid.spec.order(subset)
    each = stride if isinstance(stride, Mapping) else dict.fromkeys(subset, stride)
    step = {a: grid.spec[a].tile * each.get(a, 1) for a in subset}
    columns = [f"q_{a}" if a in subset else a for a in grid.spec.names]
    tiles = ", ".join(f"{a} // {step[a]} AS m_{a}" if a in subset else a for a in grid.spec.names)
    joins = " ".join(f"JOIN (SELECT CAST(unnest(range(1, CAST({grid.length_sql(a)} AS BIGINT) // {step[a]} + 1)) AS INT) AS q_{a}) g_{a} ON m_{a} < q_{a}" for a in subset)
    placed = " AND ".join(f"{a} IS NOT NULL" for a in grid.spec.names)
    return f"WITH cells AS ({grid.sql}), tiles AS (SELECT {tiles}, sum(sx) AS sx, sum(n) AS n FROM cells WHERE {placed} GROUP BY ALL) SELECT {', '.join(columns)}, CAST(sum(sx) AS BIGINT) AS sx, CAST(sum(n) AS BIGINT) AS n FROM tiles {joins} GROUP BY {', '.join(columns)}"


def add_box(name: str, grid: Grid, box: Mapping[str, Range], over: Iterable[str], subsets=None, stride=1, mode: str = "floor", divisor: str = "cells", keep: bool | None = None) -> None:
    """A box average through anchors of all subsets of its averaged axes (or those given), against a full read.

    Experiments (and what says `keep`) answer from tables on storage, other queries compute theirs on the way.
    """
    keep = name.startswith("w") if keep is None else keep
    subsets = all_subsets(grid.spec.order(over)) if subsets is None else subsets

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return box_average((stored if keep else store_of)(spark, sf_dir, grid, subsets, stride), box, over, mode, divisor)

    add(name, query, box_sql(grid, box, over, divisor))


def add_anchor(name: str, grid: Grid, subset: Iterable[str], stride=1) -> None:
    subset = grid.spec.order(subset)
    add(name, lambda spark, sf_dir: store_of(spark, sf_dir, grid, [subset], stride).tables[subset], anchor_sql(grid, subset, stride))
