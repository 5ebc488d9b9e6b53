"""Cells and anchor tables on storage, as a group of arrays with their attributes beside the raw data.

Under a root lie `cells` (the raw data, if it is written at all), `dimensions` (the axes, as JSON) and the group
`cells_accumulation_group`: its `attributes` (the tree of arrays by axis names, as JSON) and a folder for each array,
with its own `attributes` (axes and strides) and its rows in `data`. Plain sums, weighted sums and weights are arrays
of their own; the count of source rows is in the first kind that a store has. Reading goes by the attributes alone.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StringType, StructField, StructType
from pyspark.storagelevel import StorageLevel

from boxsum.operators.build import AnchorStore, build_anchor, columns_of
from boxsum.operators.query import build_extrema
from boxsum.plans.spec import AnchorCatalog, AxisSpec, GridSpec, SpecError, Subset, validate

GROUP_FOLDER = "cells_accumulation_group"
WEIGHTS_OF = {"weighted": ("swx",), "weight": ("sw",)}


def shared_folder(spark: SparkSession) -> str:
    """The folder from spark.checkpoint.dir, or that set in the session; a temporary one in local mode alone."""
    if root := spark.conf.get("spark.checkpoint.dir", None):
        return root
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not held.isEmpty():
        return held.get()
    master = spark.sparkContext.master
    if master != "local" and not master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    import tempfile

    return tempfile.gettempdir()


def scratch(spark: SparkSession, what: str) -> str:
    """A new path that driver and executors share."""
    return f"{shared_folder(spark).rstrip('/')}/boxsum-{what}-{uuid.uuid4().hex}"


def _file(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def write_json(spark: SparkSession, path: str, value: object) -> None:
    """A small file of metadata, written by the driver where Spark's other files are."""
    at, files = _file(spark, path)
    out = files.create(at, True)
    try:
        out.write(bytearray(json.dumps(value, indent=1).encode()))
    finally:
        out.close()


def read_json(spark: SparkSession, path: str):
    at, files = _file(spark, path)
    source = files.open(at)
    try:
        return json.loads(bytes(source.readAllBytes()))
    finally:
        source.close()


def write_cells(cells: DataFrame, grid: GridSpec, path: str, files: int | None = None) -> None:
    """Cells clustered by tile: files are ranges of tiles, sorted inside, so pushed filters skip row groups."""
    tiles = [F.floor(F.col(a.name) / a.tile) for a in grid.axes]
    files = files or max(1, int(cells.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    cells.repartitionByRange(files, *tiles).sortWithinPartitions(*tiles, *grid.names).write.mode("overwrite").parquet(path)


def measures_of(grid: GridSpec, kinds: Iterable[str]) -> dict[str, list[str]]:
    """The measures that each kind's arrays hold."""
    kinds = list(kinds)
    out = {k: [m for m in grid.measures if m not in ("n", "sw", "swx")] if k == "plain" else list(WEIGHTS_OF[k]) for k in kinds}
    if missing := {m for ms in out.values() for m in ms} - set(grid.measures):
        raise SpecError(f"the grid has no measures {sorted(missing)}")
    if "n" in grid.measures:
        out[kinds[0]].append("n")
    return out


def write_axes(spark: SparkSession, grid: GridSpec, root: str) -> None:
    write_json(spark, f"{root}/dimensions", {"grid": grid.name, "axes": [{"name": a.name, "n": a.n, "tile": a.tile, "origin": a.origin, "width": a.width, "wraps": a.wraps} for a in grid.axes]})


def read_axes(spark: SparkSession, root: str) -> tuple[str, tuple[AxisSpec, ...]]:
    raw = read_json(spark, f"{root}/dimensions")
    return raw["grid"], tuple(AxisSpec(**a) for a in raw["axes"])


def write_store(store: AnchorStore, root: str, kinds: Iterable[str] = ("plain",), with_cells: bool = True) -> AnchorCatalog:
    """The store under the root, the tables of fewer axes first.

    A table that `AnchorStore.build` derived from another is made from what was written of that, and those of one
    axis from the written cells, so the raw source is read once. Rows are counted while they are written.
    """
    spark, grid, kinds = store.cells.sparkSession, store.grid, tuple(kinds)
    parts = measures_of(grid, kinds)
    held = [m for ms in parts.values() for m in ms]
    cells = store.cells
    if with_cells:
        write_cells(cells, grid, f"{root}/cells")
        cells = spark.read.parquet(f"{root}/cells")
    catalog, written = AnchorCatalog(grid), {}
    for s in sorted(store.specs, key=len):
        catalog.add(store.specs[s], kinds)
        if s in store.parents:
            parent = store.parents[s]
            rows = build_anchor(cells, grid, store.specs[s], (parent, written[parent]) if parent else None, measures=dict.fromkeys(held, "sum"))
        else:
            rows = store.tables[s]
        qs, rest = [f"q_{a}" for a in s], [a for a in grid.names if a not in s]
        rows = rows.select(*columns_of(grid, s), *held)
        if len(kinds) > 1:
            rows = rows.persist(StorageLevel.DISK_ONLY)
        for k, measures in parts.items():
            seen, folder = Observation(), f"{root}/{GROUP_FOLDER}/{catalog.find(s, k)}"
            some = rows.select(*columns_of(grid, s), *measures).repartitionByRange(*qs, *rest).sortWithinPartitions(*qs, *rest)
            some.observe(seen, F.count(F.lit(1)).alias("rows")).write.mode("overwrite").parquet(f"{folder}/data")
            catalog.entries[s]["rows"] = seen.get["rows"]
            write_json(spark, f"{folder}/attributes", catalog.array_attributes(s))
        if len(kinds) > 1:
            rows.unpersist()
        written[s] = read_arrays(spark, f"{root}/{GROUP_FOLDER}", [catalog.find(s, k) for k in kinds])
    write_axes(spark, grid, root)
    write_json(spark, f"{root}/{GROUP_FOLDER}/attributes", catalog.export_attributes())
    return catalog


def read_arrays(spark: SparkSession, group: str, names: list[str]) -> DataFrame:
    """The rows of a subset's arrays together; what another array holds is 0, so that they add up."""
    frames = [spark.read.parquet(f"{group}/{name}/data") for name in names]
    if len(frames) == 1:
        return frames[0]
    every = list(dict.fromkeys(c for f in frames for c in f.columns))
    types = {c: f.schema[c].dataType for f in frames for c in f.columns}
    return reduce(DataFrame.unionByName, (f.select(*(F.col(c) if c in f.columns else F.lit(0).cast(types[c]).alias(c) for c in every)) for f in frames))


def read_store(spark: SparkSession, root: str, cells: DataFrame | None = None) -> AnchorStore:
    """The store as its attributes tell it: arrays by the group's tree, strides by each array's own file."""
    name, axes = read_axes(spark, root)
    group = f"{root}/{GROUP_FOLDER}"
    arrays: dict[Subset, list[str]] = {}
    for (subset, _), array in AnchorCatalog.import_attributes(read_json(spark, f"{group}/attributes")).items():
        arrays.setdefault(subset, []).append(array)
    grid, specs, tables = GridSpec(name, axes), {}, {}
    for subset, names in arrays.items():
        found = {validate(read_json(spark, f"{group}/{array}/attributes"), grid) for array in names}
        if len(found) != 1 or next(iter(found)).subset != subset:
            raise SpecError(f"the attributes of {names} don't fit {subset}")
        specs[subset], tables[subset] = found.pop(), read_arrays(spark, group, names)
    keys = {c for a in grid.names for c in (a, f"q_{a}")}
    measures = tuple(c for c in (next(iter(tables.values())).columns if tables else ()) if c not in keys)
    cells = spark.read.parquet(f"{root}/cells") if cells is None else cells
    return AnchorStore(replace(grid, measures=measures or grid.measures), cells, specs, tables, in_parts=any(len(n) > 1 for n in arrays.values()))


def write_extrema(cells: DataFrame, grid: GridSpec, root: str, over: Iterable[str], method: str) -> None:
    """The table of a method for extrema along some axes, under root/extrema."""
    over = grid.order(over)
    path = f"{root}/extrema/{method}_{'_'.join(over)}"
    table = build_extrema(cells, grid, over, method)
    order = [c for c in table.columns if c in ("level", *(f"tile_{a}" for a in over), *(f"q_{a}" for a in over))]
    table.repartitionByRange(*order).sortWithinPartitions(*order).write.mode("overwrite").parquet(f"{path}/data")
    write_json(cells.sparkSession, f"{path}/attributes", {"method": method, "over": list(over), "tiles": [a.tile for a in grid.axes]})


def read_extrema(spark: SparkSession, grid: GridSpec, root: str, over: Iterable[str], method: str) -> DataFrame:
    over = grid.order(over)
    path = f"{root}/extrema/{method}_{'_'.join(over)}"
    if read_json(spark, f"{path}/attributes") != {"method": method, "over": list(over), "tiles": [a.tile for a in grid.axes]}:
        raise SpecError("these extrema are of other tiles")
    return spark.read.parquet(f"{path}/data")


def only(store: AnchorStore, *subsets: Subset) -> AnchorStore:
    """The store with just these tables."""
    keep = {store.grid.order(s) for s in subsets}
    return replace(store, specs={s: v for s, v in store.specs.items() if s in keep}, tables={s: v for s, v in store.tables.items() if s in keep}, parents={})


def box_schema(grid: GridSpec) -> StructType:
    """box_id and, for each axis, its half-open bounds."""
    out = StructType([StructField("box_id", LongType())])
    for a in grid.names:
        out = out.add(f"{a}_lo", IntegerType()).add(f"{a}_hi", IntegerType())
    return out


def read_boxes(spark: SparkSession, path: str, grid: GridSpec, kind: str = "csv") -> tuple[DataFrame, DataFrame]:
    """(boxes, refused) from CSV with a header, JSON lines or Parquet, by a declared schema; refused ones are outside the grid or empty."""
    reader = spark.read.schema(box_schema(grid))
    rows = (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)
    good = F.col("box_id").isNotNull()
    for a in grid.axes:
        good = good & F.coalesce((F.col(f"{a.name}_lo") >= 0) & (F.col(f"{a.name}_lo") < F.col(f"{a.name}_hi")) & (F.col(f"{a.name}_hi") <= a.n), F.lit(False))
    return rows.where(good), rows.where(~good)


def read_dictionary(spark: SparkSession, path: str, axis: str, kind: str = "csv") -> DataFrame:
    """(<axis>, label) of an axis whose coordinates are names; small, as the axis is."""
    reader = spark.read.schema(StructType([StructField(axis, IntegerType()), StructField("label", StringType())]))
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)
