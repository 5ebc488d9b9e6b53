"""Keeping anchor tables up to date: appended slices, late cells, and a stream of events."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import replace
from functools import reduce

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boxsum.operators.build import AnchorStore, accumulate, build_anchor, columns_of
from boxsum.plans.spec import AnchorSpec, GridSpec, Subset, array_name
from boxsum.sources.grids import cents, hours
from boxsum.sources.io import scratch


def appended_rows(store: AnchorStore, new: DataFrame, n: int, time: str = "t") -> tuple[GridSpec, dict[Subset, DataFrame]]:
    """The grid with a time axis of n slices, and the rows that cells of later times add to each table.

    Tables without time only gain the new cells' rows. A table with time goes on from its last anchors: those, put
    where they stand, the older rows after them, and the new rows are accumulated together, and give the new anchors
    only. So what is read is the new cells, one step of the old ones, and an anchor a line.
    """
    grid = replace(store.grid, axes=tuple(replace(a, n=n) if a.name == time else a for a in store.grid.axes))
    measures = dict.fromkeys(grid.measures, "sum")
    added: dict[Subset, DataFrame] = {(): new.select(*grid.names, *grid.measures)}
    for s, spec in sorted(store.specs.items(), key=lambda x: len(x[0])):
        old = store.tables[s]
        if time not in s:
            added[s] = build_anchor(new, grid, spec).select(old.columns)
            continue
        parent = tuple(a for a in s if a != time)
        step = grid[time].tile * spec.of(time)
        last = store.grid[time].n // step
        same = parent in store.specs and all(store.specs[parent].of(a) == spec.of(a) for a in parent)
        before = store.cells if not parent else store.tables[parent] if same else None
        after = added[()] if not parent else added[parent] if same else None
        if before is None:
            own = replace(spec, stride=tuple(0 if a == time else k for a, k in zip(spec.axes, spec.stride, strict=True)))
            before, after = build_anchor(store.cells.where(F.col(time) >= last * step), store.grid, own), build_anchor(new, grid, own)
        columns = [*columns_of(grid, parent), *grid.measures]
        carried = old.where(F.col(f"q_{time}") == last).withColumn(time, F.lit(last * step))
        rows = [carried.select(columns), before.where(F.col(time) >= last * step).select(columns), after.select(columns)]
        keys = [c for c in columns_of(grid, parent) if c != time]
        added[s] = accumulate(reduce(DataFrame.unionByName, rows), keys, time, step, n, measures).select(old.columns)
    return grid, added


def append_slices(store: AnchorStore, new: DataFrame, n: int, time: str = "t") -> AnchorStore:
    """The store with cells of later times added, its time axis now of n slices."""
    grid, added = appended_rows(store, new, n, time)
    cells = store.cells.select(*grid.names, *grid.measures).unionByName(added.pop(()))
    return AnchorStore(grid, cells, dict(store.specs), {s: store.tables[s].unionByName(rows) for s, rows in added.items()})


def repair_late(store: AnchorStore, late: DataFrame) -> AnchorStore:
    """The store with late cells added: each one's values go into every anchor beyond it, in every table."""
    grid = store.grid
    totals = [F.sum(m).alias(m) for m in grid.measures]
    late = late.select(*grid.names, *grid.measures)
    tables = {}
    for s, spec in store.specs.items():
        delta = build_anchor(late, grid, spec)  # the late cells' own anchors reach every later one
        columns = columns_of(grid, s)
        tables[s] = store.tables[s].select(*columns, *grid.measures).unionByName(delta.select(*columns, *grid.measures)).groupBy(*columns).agg(*totals)
    cells = store.cells.select(*grid.names, *grid.measures).unionByName(late).groupBy(*grid.names).agg(*totals)
    return AnchorStore(grid, cells, dict(store.specs), tables)


# -- stores that grow by batches ----------------------------------------------------------------------------


class GrowingStore:
    """A store under a root to which batches add rows, never rewriting what is there.

    Cells, and each table's rows, lie in a folder a batch, and so does the length of the time axis after it. A batch
    reads the last anchors and the cells after them and writes its own cells and anchors; cells of times that
    anchors have passed already give rows for all anchors beyond them, to be added to those. Rows of one key add up. A
    batch that is tried again replaces its own folders and reads only earlier ones, so it counts once.
    """

    def __init__(self, spark: SparkSession, root: str, grid: GridSpec, subsets: Iterable[Iterable[str]], stride=1, time: str = "t"):
        self.spark, self.root, self.time = spark, root, time
        self.grid = replace(grid, axes=tuple(replace(a, n=0) if a.name == time else a for a in grid.axes))
        self.specs = {grid.order(s): AnchorSpec.uniform(grid, s, stride) for s in subsets}

    def _folder(self, subset: Subset) -> str:
        return f"{self.root}/{array_name(subset) if subset else 'cells'}"

    def _columns(self, subset: Subset) -> str:
        whole = [f"`{c}` int" for c in columns_of(self.grid, subset)]
        return ", ".join([*whole, *(f"`{m}` long" for m in self.grid.measures)])

    def _rows(self, subset: Subset, batches: list[int]) -> DataFrame:
        if not batches:
            return self.spark.createDataFrame([], self._columns(subset))
        return self.spark.read.schema(self._columns(subset)).parquet(*(f"{self._folder(subset)}/batch={k}" for k in batches))

    def _batches(self, before: int | None) -> list[tuple[int, int]]:
        """(batch, slices after it) of the batches that were finished."""
        try:
            done = self.spark.read.schema("batch long, n int").parquet(f"{self.root}/done").collect()  # a row a batch
        except AnalysisException:
            return []
        return sorted((r["batch"], r["n"]) for r in done if before is None or r["batch"] < before)

    def read(self, before: int | None = None) -> AnchorStore:
        done = self._batches(before)
        n = max(1, done[-1][1]) if done else 1  # an axis has a slice, if only an empty one
        grid = replace(self.grid, axes=tuple(replace(a, n=n) if a.name == self.time else a for a in self.grid.axes))
        numbers = [k for k, _ in done]
        return AnchorStore(grid, self._rows((), numbers), dict(self.specs), {s: self._rows(s, numbers) for s in self.specs}, in_parts=True)

    def add(self, cells: DataFrame, number: int) -> None:
        """A batch of cells of any times."""
        time, store = self.time, self.read(number)
        measures = [F.sum(m).alias(m) for m in self.grid.measures]
        path = f"{self._folder(())}/batch={number}"
        cells.groupBy(*self.grid.names).agg(*measures).write.mode("overwrite").parquet(path)
        cells = self.spark.read.schema(self._columns(())).parquet(path)
        top = cells.agg(F.max(time)).first()[0]
        n = max(store.grid[time].n, 0 if top is None else top + 1)
        for s, spec in self.specs.items():
            rows = []
            passed = store.grid[time].n // (self.grid[time].tile * spec.of(time)) * self.grid[time].tile * spec.of(time) if time in s else 0
            alone = AnchorStore(store.grid, store.cells, {s: spec}, {s: store.tables[s]}, in_parts=True)
            rows.append(appended_rows(alone, cells.where(F.col(time) >= passed), n, time)[1][s])
            if passed:  # to be added to the anchors there are, and to those that this batch makes
                longer = replace(store.grid, axes=tuple(replace(a, n=n) if a.name == time else a for a in store.grid.axes))
                rows.append(build_anchor(cells.where(F.col(time) < passed), longer, spec).select(rows[0].columns))
            reduce(DataFrame.unionByName, rows).write.mode("overwrite").parquet(f"{self._folder(s)}/batch={number}")
        self.spark.createDataFrame([(number, n)], "batch long, n int").coalesce(1).write.mode("overwrite").parquet(f"{self.root}/done/number={number}")

    def table(self, subset: Iterable[str]) -> DataFrame:
        """A table with one row a key."""
        subset = self.grid.order(subset)
        return self.read().tables[subset].groupBy(*columns_of(self.grid, subset)).agg(*(F.sum(m).alias(m) for m in self.grid.measures))


# -- streams ------------------------------------------------------------------------------------------------


def event_stream(spark: SparkSession, sf_dir: str, files_a_batch: int = 1, closing: str | None = None) -> DataFrame:
    """The events as a file stream, from one file or a folder of them, ts as a timestamp so that it can have a watermark.

    `closing` is a folder of the same columns that is read as well, for rows that come when all others have.
    """
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema

    def read(at: str) -> DataFrame:
        source, name = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch), at.rsplit("/", 1)
        # a table of one file is read as the folder around it, of which nothing else matches
        return source.parquet(at) if is_folder(spark, at) else source.option("pathGlobFilter", name[1]).parquet(name[0])

    rows = read(path)
    if closing is not None:
        rows = rows.unionByName(read(closing))
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def is_folder(spark: SparkSession, path: str) -> bool:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()


def gathered(stream: DataFrame, mode: str = "append", close: Callable[[], None] | None = None) -> DataFrame:
    """What a stream has emitted when its input is read, on storage under a new path; each batch replaces its own try.

    Appended rows are those of all batches, in "update" too; a complete result is the last batch's. With `close` the
    stream is run to the end of its input, then `close` adds to that, and it goes on from where it was.
    """
    spark = stream.sparkSession
    root, schema = scratch(spark, "stream"), stream.schema

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/rows/{'batch=last' if mode == 'complete' else f'batch={number}'}")

    for again in (False, True):
        if again and close is None:
            break
        if again:
            close()
        query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
        query.awaitTermination()
    try:
        return spark.read.schema(schema).parquet(f"{root}/rows").drop("batch")
    except AnalysisException:  # no input, no batch
        return spark.createDataFrame([], schema)


def closed(spark: SparkSession, sf_dir: str, make: Callable[[DataFrame], DataFrame], far: str = "2200-01-01") -> DataFrame:
    """What `make` (a stream with a watermark) appends for all events; a last row, far ahead, closes what is open then."""
    folder = scratch(spark, "closing")
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    nothing = spark.createDataFrame([], schema)
    nothing.write.parquet(folder)

    def close() -> None:
        columns = [F.lit(far).cast(f.dataType).alias(f.name) if f.name == "ts" else F.lit(None).cast(f.dataType).alias(f.name) for f in schema.fields]
        spark.range(1).select(*columns).write.mode("append").parquet(folder)

    return gathered(make(event_stream(spark, sf_dir, closing=folder)), close=close)


def stream_cells(stream: DataFrame, user: str = "user_id") -> DataFrame:
    """(u, t, sx, n): the cells that each micro-batch adds to, to be summed over batches."""
    return stream.select(F.col(user).cast("int").alias("u"), hours("ts").alias("t"), cents("value").alias("sx"), F.lit(1).cast("long").alias("n"))


def stream_store(stream: DataFrame, grid: GridSpec, subsets, stride=1, time: str = "t") -> GrowingStore:
    """The store that a stream's cells grow, batch by batch."""
    spark = stream.sparkSession
    root = scratch(spark, "growing")
    store = GrowingStore(spark, f"{root}/store", grid, subsets, stride, time)
    query = stream.writeStream.foreachBatch(store.add).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return store
