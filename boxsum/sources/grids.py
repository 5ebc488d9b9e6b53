"""The grids over the given tables: each with its axes, a builder of its cells, and the same cells in DuckDB's SQL.

Cells have an int column for each axis, `sx` (a bigint: exact cents or scaled integers) and `n` (source rows);
some grids add `p` (1 for a cell), `sxx` (the square, a decimal), `sw` and `swx` (weight, weight times value).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from boxsum.plans.spec import AxisSpec, GridSpec


@dataclass(frozen=True)
class Grid:
    """A grid over given tables. Axes of ids have as many cells as the ids need, `spec` says how many at least.

    `ids` has the table and column of such axes. A cell beyond an axis is an error; rows without a place are none.
    """

    spec: GridSpec
    build: Callable[[SparkSession, str], DataFrame]
    sql: str
    ids: dict[str, tuple[str, str]] = field(default_factory=dict, hash=False)

    def sized(self, spark: SparkSession, sf_dir: str) -> GridSpec:
        """The grid's axes as long as the tables have them: one number an axis, from the files' statistics or one column."""
        n = {}
        for axis, (name, column) in self.ids.items():
            top = table(spark, sf_dir, name).agg(F.max(column)).first()[0]
            n[axis] = max(self.spec[axis].n, 0 if top is None else int(top) + 1)
        return replace(self.spec, axes=tuple(replace(a, n=n.get(a.name, a.n)) for a in self.spec.axes))

    def cells(self, spark: SparkSession, sf_dir: str, spec: GridSpec | None = None) -> DataFrame:
        return on_grid(self.build(spark, sf_dir), spec or self.sized(spark, sf_dir))

    def length_sql(self, axis: str) -> str:
        """The length of an axis in DuckDB's SQL."""
        if axis not in self.ids:
            return str(self.spec[axis].n)
        name, column = self.ids[axis]
        return f"greatest({self.spec[axis].n}, (SELECT coalesce(max({column}), -1) + 1 FROM {name}))"

    def with_axes(self, **n: int) -> Grid:
        """The same grid with other lengths of axes, which are then given."""
        return replace(self, spec=replace(self.spec, axes=tuple(replace(a, n=n.get(a.name, a.n)) for a in self.spec.axes)), ids={a: x for a, x in self.ids.items() if a not in n})

    def with_tiles(self, **tile: int) -> Grid:
        return replace(self, spec=replace(self.spec, axes=tuple(replace(a, tile=tile.get(a.name, a.tile)) for a in self.spec.axes)))


def on_grid(cells: DataFrame, spec: GridSpec) -> DataFrame:
    """The cells that have a place; one beyond its axis is an error, as full ranges would leave it out."""
    nowhere = reduce(lambda x, y: x | y, (F.col(a.name).isNull() for a in spec.axes))
    within = reduce(lambda x, y: x & y, (F.col(a.name).between(0, a.n - 1) for a in spec.axes))
    said = F.concat(F.lit(f"a cell is outside its axis on {spec.name}: "), F.concat_ws(", ", *(F.concat(F.lit(f"{a.name} of {a.n}: "), F.col(a.name).cast("string")) for a in spec.axes)))
    return cells.where(F.when(nowhere, False).when(within, True).otherwise(F.raise_error(said).cast("boolean")))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(c: str | Column) -> Column:
    return F.round(F.col(c) * 100 if isinstance(c, str) else c * 100).cast("long")


def days(c: str, origin: str) -> Column:
    return F.datediff(F.col(c), F.lit(origin).cast("date")).cast("int")


def hours(c: str, origin: str = "2024-01-01") -> Column:
    """Whole hours since the origin; the column has no time zone."""
    return F.floor((F.unix_micros(F.col(c).cast("timestamp")) - F.unix_micros(F.lit(origin).cast("timestamp"))) / 3_600_000_000).cast("int")


def place(c: str) -> Column:
    """An id as a place on an axis; one that is no int is told as outside of it by -1."""
    return F.when(F.col(c).between(0, (1 << 31) - 2), F.col(c)).when(F.col(c).isNotNull(), F.lit(-1)).cast("int")


def cells_from_table(rows: DataFrame, axes: dict[str, Column], value: Column) -> DataFrame:
    """Rows to cells: one row for each point that occurs, its values summed and its rows counted."""
    return rows.groupBy(*(c.cast("int").alias(a) for a, c in axes.items())).agg(F.sum(value).alias("sx"), F.count("*").alias("n"))


_SHIP_SQL = """SELECT CAST(l_quantity AS INT) - 1 AS y, CAST(round(l_discount * 100) AS INT) AS x, CAST(date_diff('day', DATE '1995-01-02', l_shipdate) AS INT) AS t{more},
  CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS sx, count(*) AS n FROM lineitem GROUP BY ALL"""


def _ship(spark: SparkSession, sf_dir: str) -> DataFrame:
    axes = {"y": F.col("l_quantity").cast("int") - 1, "x": F.round(F.col("l_discount") * 100), "t": days("l_shipdate", "1995-01-02")}
    return cells_from_table(table(spark, sf_dir, "lineitem"), axes, cents("l_extendedprice"))


def _ship_more(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = F.col("sx").cast("decimal(19,0)")
    return _ship(spark, sf_dir).select("*", F.lit(1).cast("long").alias("p"), (wide * wide).cast("decimal(38,0)").alias("sxx"), F.col("n").alias("sw"), (F.col("n") * F.col("sx")).alias("swx"))


G1 = Grid(GridSpec("ship", (AxisSpec("y", 50, 10), AxisSpec("x", 11, 4), AxisSpec("t", 2499, 50))), _ship, _SHIP_SQL.format(more=""))
G1_MORE = Grid(replace(G1.spec, measures=("sx", "n", "p", "sxx", "sw", "swx")), _ship_more, f"SELECT *, 1 AS p, CAST(sx AS HUGEINT) * sx AS sxx, n AS sw, n * sx AS swx FROM ({_SHIP_SQL.format(more='')})")


#: Least lengths of the axes that are ids.
USERS, VECTORS, DOCUMENTS, CONVERSATIONS = 150, 500, 1000, 100
#: Most values of an axis whose places are the values' order.
NAMES = 1 << 16


def _activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cells_from_table(table(spark, sf_dir, "events"), {"u": place("user_id"), "t": hours("ts")}, cents("value"))


_HOUR = "CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) / 3600000000) AS INT) AS t"
G2 = Grid(GridSpec("activity", (AxisSpec("u", USERS, 25), AxisSpec("t", 720, 24))), _activity, f"SELECT CAST(user_id AS INT) AS u, {_HOUR}, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS sx, count(*) AS n FROM events GROUP BY ALL", {"u": ("events", "user_id")})


def dictionary(rows: DataFrame, column: str, to: str) -> DataFrame:
    """(column, to): the distinct values numbered in their order. More than `NAMES` are an error, so it can be broadcast."""
    values = rows.select(column).where(F.col(column).isNotNull()).distinct()
    checked = values.limit(NAMES + 1).agg(F.array_sort(F.collect_set(column)).alias("v"))
    few = F.when(F.size("v") <= NAMES, F.col("v")).otherwise(F.raise_error(F.lit(f"{column} has too many values for an axis")).cast(checked.schema["v"].dataType))
    return checked.select(F.posexplode(few).alias(to, column))


def _kind(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    return cells_from_table(events.join(F.broadcast(dictionary(events, "event_type", "e")), "event_type"), {"e": F.col("e"), "t": hours("ts")}, cents("value"))


G2B = Grid(GridSpec("kind", (AxisSpec("e", 5, 5), AxisSpec("t", 720, 24))), _kind, f"SELECT CAST(e AS INT) AS e, {_HOUR}, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS sx, count(*) AS n FROM events JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS e FROM (SELECT DISTINCT event_type FROM events)) USING (event_type) GROUP BY ALL")


def _plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = table(spark, sf_dir, "embeddings").select(place("vec_id").alias("r"), F.posexplode("embedding").alias("c", "v"))
    return points.select("r", "c", F.floor(F.col("v").cast("double") * 4096).cast("long").alias("sx"), F.lit(1).cast("long").alias("n"))


_PLANE_SQL = "SELECT CAST(vec_id AS INT) AS r, CAST(c - 1 AS INT) AS c, CAST(floor(CAST(embedding[c] AS DOUBLE) * 4096) AS BIGINT) AS sx, CAST(1 AS BIGINT) AS n FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS c FROM embeddings)"
G3 = Grid(GridSpec("plane", (AxisSpec("r", VECTORS, 50), AxisSpec("c", 64, 16))), _plane, _PLANE_SQL, {"r": ("embeddings", "vec_id")})


def hourly_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(t, k): events in each of 720 hours."""
    found = table(spark, sf_dir, "events").groupBy(hours("ts").alias("t")).agg(F.count("*").alias("k"))
    return spark.range(720).select(F.col("id").cast("int").alias("t")).join(F.broadcast(found), "t", "left").select("t", F.coalesce("k", F.lit(0)).alias("k"))


def spread(points: DataFrame) -> DataFrame:
    """The points of a plane by ranges of rows over all tasks: a small table is a single task, which would make all cells of a product with it.

    Neighbouring rows share a task, so tiles are mostly summed before an exchange.
    """
    spark = points.sparkSession
    return points.repartitionByRange(max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism), "r")


def dense_field(max_r: int | None = None) -> Grid:
    """The dense field: plane times hours; of the plane only the rows below max_r, if that is given (for timings)."""

    def cells(spark: SparkSession, sf_dir: str) -> DataFrame:
        plane = _plane(spark, sf_dir) if max_r is None else _plane(spark, sf_dir).where(F.col("r") < max_r)
        # 720 hours by design: the field is the product of the two
        return spread(plane).crossJoin(F.broadcast(hourly_counts(spark, sf_dir))).select("r", "c", "t", (F.col("sx") * F.col("k")).alias("sx"), F.lit(1).cast("long").alias("n"))

    # hours beyond the 720 are no cells of the field, in either engine
    where = "" if max_r is None else f" WHERE r < {max_r}"
    sql = f"SELECT r, c, t, sx * k AS sx, CAST(1 AS BIGINT) AS n FROM ({_PLANE_SQL}) CROSS JOIN (SELECT CAST(h AS INT) AS t, coalesce(k, 0) AS k FROM range(720) x(h) LEFT JOIN (SELECT {_HOUR}, count(*) AS k FROM events GROUP BY ALL) e ON e.t = h){where}"
    return Grid(GridSpec("field", (AxisSpec("r", max_r or VECTORS, 50), AxisSpec("c", 64, 16), AxisSpec("t", 720, 40))), cells, sql, {} if max_r else {"r": ("embeddings", "vec_id")})


def _floats(spark: SparkSession, sf_dir: str) -> DataFrame:
    plane = table(spark, sf_dir, "embeddings").select(place("vec_id").alias("r"), F.posexplode("embedding").alias("c", "v"))
    line = spark.range(720).select(F.col("id").cast("int").alias("t")).select("t", (1 + F.sin(F.col("t") / 7.0)).alias("wave"))
    value = (F.col("v").cast("double") + 0.5) * F.col("wave")
    # 720 hours by design, as of the dense field
    return spread(plane).crossJoin(F.broadcast(line)).select("r", "c", "t", value.alias("double"), value.cast("float").cast("double").alias("float"), F.lit(1).cast("long").alias("n"))


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    nations = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    ranked = nations.agg(F.array_sort(F.collect_list(F.struct("n_regionkey", "n_nationkey"))).alias("v")).select(F.posexplode("v").alias("place", "k")).select("place", F.col("k.n_nationkey").alias("c_nationkey"))
    rows = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(ranked), "c_nationkey")
    return cells_from_table(rows, {"nation": F.col("place"), "t": days("o_orderdate", "1995-01-01")}, cents("o_totalprice"))


G5 = Grid(GridSpec("orders", (AxisSpec("nation", 25, 5), AxisSpec("t", 2405, 50))), _orders, "SELECT CAST(place AS INT) AS nation, CAST(date_diff('day', DATE '1995-01-01', o_orderdate) AS INT) AS t, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS sx, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN (SELECT n_nationkey, row_number() OVER (ORDER BY n_regionkey, n_nationkey) - 1 AS place FROM nation) ON n_nationkey = c_nationkey GROUP BY ALL")


def _line(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(place("doc_id").alias("d"), F.col("n_chars").cast("long").alias("sx"), F.lit(1).cast("long").alias("n"))
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").cast("int").alias("d"), F.col("quality").cast("long").alias("w"))
    return docs.join(labels, "d", "left").select("d", "sx", "n", F.coalesce("w", F.lit(0)).alias("sw"), (F.coalesce("w", F.lit(0)) * F.col("sx")).alias("swx"))


G6 = Grid(GridSpec("line", (AxisSpec("d", DOCUMENTS, 50),), ("sx", "n", "sw", "swx")), _line, "SELECT CAST(d.doc_id AS INT) AS d, n_chars AS sx, CAST(1 AS BIGINT) AS n, CAST(coalesce(quality, 0) AS BIGINT) AS sw, CAST(coalesce(quality, 0) * n_chars AS BIGINT) AS swx FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id", {"d": ("documents", "doc_id")})


def _four(spark: SparkSession, sf_dir: str) -> DataFrame:
    axes = {"y": F.col("l_quantity").cast("int") - 1, "x": F.round(F.col("l_discount") * 100), "z": F.round(F.col("l_tax") * 100), "t": days("l_shipdate", "1995-01-02")}
    return cells_from_table(table(spark, sf_dir, "lineitem"), axes, cents("l_extendedprice"))


G7 = Grid(GridSpec("four", (AxisSpec("y", 50, 10), AxisSpec("x", 11, 4), AxisSpec("z", 9, 3), AxisSpec("t", 2499, 50))), _four, _SHIP_SQL.format(more=", CAST(round(l_tax * 100) AS INT) AS z"))


def _part(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part")
    return cells_from_table(part.join(F.broadcast(dictionary(part, "p_brand", "b")), "p_brand"), {"z": F.col("p_size") - 1, "b": F.col("b")}, cents("p_retailprice"))


G8 = Grid(GridSpec("part", (AxisSpec("z", 50, 10), AxisSpec("b", 25, 5))), _part, "SELECT p_size - 1 AS z, CAST(b AS INT) AS b, CAST(sum(CAST(round(p_retailprice * 100) AS BIGINT)) AS BIGINT) AS sx, count(*) AS n FROM part JOIN (SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS b FROM (SELECT DISTINCT p_brand FROM part)) USING (p_brand) GROUP BY ALL")


def _talk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cells_from_table(table(spark, sf_dir, "conversations"), {"k": place("conv_id"), "turn": F.col("turn")}, F.length("text").cast("long"))


G9 = Grid(GridSpec("talk", (AxisSpec("k", CONVERSATIONS, 20), AxisSpec("turn", 8, 4))), _talk, "SELECT CAST(conv_id AS INT) AS k, CAST(turn AS INT) AS turn, CAST(sum(length(text)) AS BIGINT) AS sx, count(*) AS n FROM conversations GROUP BY ALL", {"k": ("conversations", "conv_id")})


def _balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    customer = table(spark, sf_dir, "customer")
    return cells_from_table(customer.join(F.broadcast(dictionary(customer, "c_mktsegment", "m")), "c_mktsegment"), {"nation": F.col("c_nationkey"), "m": F.col("m")}, cents("c_acctbal"))


G10 = Grid(GridSpec("balance", (AxisSpec("nation", 25, 5), AxisSpec("m", 5, 5))), _balance, "SELECT c_nationkey AS nation, CAST(m AS INT) AS m, CAST(sum(CAST(round(c_acctbal * 100) AS BIGINT)) AS BIGINT) AS sx, count(*) AS n FROM customer JOIN (SELECT c_mktsegment, row_number() OVER (ORDER BY c_mktsegment) - 1 AS m FROM (SELECT DISTINCT c_mktsegment FROM customer)) USING (c_mktsegment) GROUP BY ALL")

G4 = dense_field()
#: The dense field in doubles, and in values that were single precision; no SQL, as sums of doubles depend on their order.
G4_FLOATS = Grid(replace(G4.spec, name="floats", measures=("double", "float", "n")), _floats, "", G4.ids)
GRIDS = {g.spec.name: g for g in (G1, G2, G2B, G3, G4, G5, G6, G7, G8, G9, G10)}
