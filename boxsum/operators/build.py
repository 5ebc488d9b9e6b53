"""Anchor tables from cells: tile sums, running sums over tiles, and anchors carried over empty tiles."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxsum.plans.spec import AnchorCatalog, AnchorSpec, GridSpec, SpecError, Subset

#: Tiles of a one-dimensional running sum that one task adds up.
BLOCK = 1 << 16
SUM = {"sum": (F.sum, lambda a, b: a + b), "min": (F.min, F.least), "max": (F.max, F.greatest)}


def tile_sums(rows: DataFrame, keys: list[str], axis: str, step: int, measures: Mapping[str, str]) -> DataFrame:
    """(keys, m, measures): aggregates of each tile of `step` cells; partial aggregation comes before the exchange."""
    return rows.groupBy(*keys, F.floor(F.col(axis) / step).cast("int").alias("__m")).agg(*(SUM[how][0](c).alias(c) for c, how in measures.items()))


def running(sums: DataFrame, keys: list[str], measures: Mapping[str, str], tiles: int) -> DataFrame:
    """The measures accumulated over m within the keys, and the next m that has a row (`next`).

    A line of up to BLOCK tiles is one window. Longer lines are cut into blocks that add up on their own; the totals
    of the blocks before, one row a block, are put on top.
    """
    if tiles <= BLOCK and keys:
        by = Window.partitionBy(*keys).orderBy("__m")
        here = [SUM[how][0](c).over(by.rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias(c) for c, how in measures.items()]
        return sums.select(*keys, "__m", *here, F.lead("__m").over(by).alias("__next"))
    line = [F.col(k) for k in keys] or [F.lit(0)]  # without keys there is one line, of few blocks
    blocked = sums.withColumn("__block", F.floor(F.col("__m") / BLOCK).cast("int"))
    by = Window.partitionBy(*keys, "__block").orderBy("__m")
    here = [SUM[how][0](c).over(by.rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias(c) for c, how in measures.items()]
    before = Window.partitionBy(*line).orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    after = Window.partitionBy(*line).orderBy(F.desc("__block")).rowsBetween(Window.unboundedPreceding, -1)
    totals = blocked.groupBy(*keys, "__block").agg(F.min("__m").alias("__first"), *(SUM[how][0](c).alias(c) for c, how in measures.items()))
    offsets = totals.select(*keys, "__block", F.min("__first").over(after).alias("__next_block"), *(SUM[how][0](c).over(before).alias(f"{c}_before") for c, how in measures.items()))
    inside = blocked.select(*keys, "__block", "__m", *here, F.lead("__m").over(by).alias("__next"))
    on_top = [F.when(F.col(f"{c}_before").isNull(), F.col(c)).otherwise(SUM[how][1](F.col(c), F.col(f"{c}_before"))).alias(c) for c, how in measures.items()]
    return inside.join(offsets, [*keys, "__block"]).select(*keys, "__m", *on_top, F.coalesce("__next", "__next_block").alias("__next"))


def accumulate(rows: DataFrame, keys: list[str], axis: str, step: int, n: int, measures: Mapping[str, str], layout: str = "carried") -> DataFrame:
    """rows with `axis` replaced by q_<axis>: aggregates of all cells below each anchor.

    "carried" has a row for every anchor from a line's first tile on (a row that is missing means nothing below),
    "sparse" only those where something was added, to be looked up by the greatest anchor at or below, and "dense" a
    row for every anchor of each line that has a cell, 0 (or null for extrema) where nothing is below. A line
    without a cell has no rows in any.
    """
    last = n // step
    sums = tile_sums(rows, keys, axis, step, measures)
    if layout == "dense":
        nothing = [F.lit(0 if how == "sum" else None).cast(sums.schema[c].dataType).alias(c) for c, how in measures.items()]
        starts = sums.groupBy(*(keys or [F.lit("line")])).agg(F.lit(-1).alias("__m"), *nothing)
        sums = sums.unionByName(starts.select(sums.columns))
    run = running(sums, keys, measures, last)
    if layout == "sparse":
        return run.where(F.col("__m") < last).select(*keys, (F.col("__m") + 1).alias(f"q_{axis}"), *measures)
    if layout not in ("carried", "dense"):
        raise SpecError(f"unknown layout {layout}")
    begin, end = F.greatest(F.col("__m") + 1, F.lit(1)), F.least(F.coalesce("__next", F.lit(last)), F.lit(last))
    return run.where(begin <= end).select(*keys, F.explode(F.sequence(begin, end)).alias(f"q_{axis}"), *measures)


def columns_of(grid: GridSpec, subset: Subset) -> list[str]:
    return [f"q_{a}" if a in subset else a for a in grid.names]


def build_anchor(cells: DataFrame, grid: GridSpec, spec: AnchorSpec, parent: tuple[Subset, DataFrame] | None = None, layout: str = "carried", measures: Mapping[str, str] | None = None) -> DataFrame:
    """The anchor table of a specification, from cells or from a table of fewer axes with the same strides."""
    have, rows = parent or ((), cells)
    measures = measures or dict.fromkeys(grid.measures, "sum")
    todo = [a for a in spec.subset if a not in have]
    for k, a in enumerate(todo):
        keys = [c for c in columns_of(grid, have) if c != a]
        # sparse tables can't be parents, so only the last step may be sparse
        rows = accumulate(rows, keys, a, grid[a].tile * spec.of(a), grid[a].n, measures, layout if k == len(todo) - 1 else "carried")
        have = grid.order((*have, a))
    return rows.select(*columns_of(grid, have), *measures)


@dataclass
class AnchorStore:
    """Cells with their anchor tables."""

    grid: GridSpec
    cells: DataFrame
    specs: dict[Subset, AnchorSpec]
    tables: dict[Subset, DataFrame]
    parents: dict[Subset, Subset | None] = field(default_factory=dict)  # what build() made each table from
    in_parts: bool = False  # a key's measures may lie in several rows, which add up
    scan_cost: int = 0  # rows that a scan counts for when plans are compared

    @classmethod
    def build(cls, cells: DataFrame, grid: GridSpec, subsets: Iterable[Iterable[str]], stride: int | Mapping[str, int] | Mapping[Subset, Mapping[str, int]] = 1, reuse: bool = True) -> AnchorStore:
        """Tables of all subsets; with `reuse` each comes from the fewest-rowed table of one axis less and the same strides.

        Nothing is computed here. Reuse is of what is computed: `io.write_store` makes each table from the parent
        that it has written; tables that are not stored are computed from the cells wherever they are read.
        """
        per_table = isinstance(stride, Mapping) and any(isinstance(k, tuple) for k in stride)
        specs = {grid.order(s): AnchorSpec.uniform(grid, s, stride.get(grid.order(s), 1) if per_table else stride) for s in subsets}
        store = cls(grid, cells, specs, {})
        for s in sorted(specs, key=len):
            parents = [p for p in store.tables if len(p) == len(s) - 1 and set(p) < set(s) and all(specs[p].of(a) == specs[s].of(a) for a in p)] if reuse else []
            best = min(parents, key=lambda p: points(grid, specs[p]), default=None)
            store.parents[s] = best
            store.tables[s] = build_anchor(cells, grid, specs[s], (best, store.tables[best]) if best else None)
        return store

    def without(self, *subsets: Iterable[str]) -> AnchorStore:
        gone = {self.grid.order(s) for s in subsets}
        return replace(self, specs={s: v for s, v in self.specs.items() if s not in gone}, tables={s: v for s, v in self.tables.items() if s not in gone}, parents={})

    def catalog(self, kinds: Iterable[str] = ("plain",)) -> AnchorCatalog:
        out = AnchorCatalog(self.grid)
        for spec in self.specs.values():
            out.add(spec, kinds)
        return out


def points(grid: GridSpec, spec: AnchorSpec) -> int:
    """Rows of an anchor table over a grid without empty cells."""
    out = 1
    for a in grid.axes:
        out *= a.n // (a.tile * spec.of(a.name)) if spec.of(a.name) else a.n
    return out


def to_packed(table: DataFrame, axis: str, measures: Iterable[str] = ("sx",)) -> DataFrame:
    """One row a line of an axis: its indices, and an array of each measure's values in the same order.

    One measure's array is called `values`, of several each is called as the measure. Lines are bounded by the axis.
    """
    measures = list(measures)
    keys = [c for c in table.columns if c != axis and c not in (*measures, "sx", "n", "sw", "swx", "sxx", "p")]
    entry = F.struct(F.col(axis).alias("i"), *(F.col(m).alias(f"v{k}") for k, m in enumerate(measures)))
    packed = table.groupBy(*keys).agg(F.array_sort(F.collect_list(entry)).alias("line"))
    names = ["values"] if len(measures) == 1 else measures
    return packed.select(*keys, F.col("line")["i"].alias("index"), *(F.col("line")[f"v{k}"].alias(name) for k, name in enumerate(names)))


def lookup_sparse(table: DataFrame, axis: str, q: int, measures: Iterable[str]) -> DataFrame:
    """The row at anchor q of a sparse table with one accumulated axis: the greatest anchor at or below, by line."""
    keys = [c for c in table.columns if c != f"q_{axis}" and c not in set(measures)]
    below = table.where(F.col(f"q_{axis}") <= q)
    return below.groupBy(*keys).agg(*(F.max_by(m, f"q_{axis}").alias(m) for m in measures))
