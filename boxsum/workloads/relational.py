"""Operators around the methods: scans, joins, aggregates, windows, sets and functions over grids and anchors."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxsum.functions import udf
from boxsum.operators.baseline import densify
from boxsum.operators.build import build_anchor, to_packed
from boxsum.plans.spec import AnchorSpec
from boxsum.sources.grids import G1, G2, G2B, G3, G5, G6, G10, _orders, cents, days, hours, table
from boxsum.workloads.cases import add, anchor_sql, store_of
from boxsum.workloads.methods import boxes, boxes_sql

_SHIP = f"WITH cells AS ({G1.sql}) "
_ACT = f"WITH cells AS ({G2.sql}) "
_HOURLY = f"WITH hourly AS (SELECT t, CAST(sum(sx) AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n FROM ({G2.sql}) GROUP BY t) "


def hourly(s, d) -> DataFrame:
    return G2.cells(s, d).groupBy("t").agg(F.sum("sx").alias("s"), F.sum("n").alias("n"))


# -- scans, projections, predicates -------------------------------------------------------------------------
add("o01_scan_filter", lambda s, d: table(s, d, "lineitem").where("l_quantity between 8 and 33 and l_returnflag in ('A', 'N')").select("l_orderkey", "l_quantity", "l_returnflag"), "SELECT l_orderkey, l_quantity, l_returnflag FROM lineitem WHERE l_quantity BETWEEN 8 AND 33 AND l_returnflag IN ('A', 'N')")


def range_axis(s, d) -> DataFrame:
    """Every index of an axis with its tile and the source rows there, 0 where there are none."""
    line = s.range(0, 50).select(F.col("id").cast("int").alias("i"), F.floor(F.col("id") / 10).cast("int").alias("tile"))
    rows = G1.cells(s, d).groupBy(F.col("y").alias("i")).agg(F.sum("n").alias("n"))
    return line.join(rows, "i", "left").select("i", "tile", F.coalesce("n", F.lit(0)).alias("n"))


add("o02_range_axis", range_axis, _SHIP + "SELECT CAST(i AS INT) AS i, CAST(i // 10 AS INT) AS tile, CAST(coalesce(sum(n), 0) AS BIGINT) AS n FROM range(50) r(i) LEFT JOIN cells ON y = i GROUP BY i")
add("o03_posexplode_plane", lambda s, d: G3.cells(s, d), G3.sql)
add("o04_box_filter", lambda s, d: G1.cells(s, d).where("y >= 7 and y < 33 and x in (2, 4) and not (t <=> 100)").select("y", "x", "t", "sx"), _SHIP + "SELECT y, x, t, sx FROM cells WHERE y >= 7 AND y < 33 AND x IN (2, 4) AND t IS DISTINCT FROM 100")

# -- joins --------------------------------------------------------------------------------------------------
add("o05_dim_join", lambda s, d: G2B.cells(s, d), G2B.sql)
add("o06_sortmerge", lambda s, d: table(s, d, "orders").hint("merge").join(table(s, d, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(F.count("*").alias("n"), F.sum(cents("o_totalprice")).alias("s")), "SELECT c_nationkey, count(*) AS n, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS s FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_nationkey")
add("o06_grid_join", _orders, G5.sql)


def range_join(s, d) -> DataFrame:
    """Boxes against cells on one axis: the box's tiles are spelt out for an equi-join, then the bounds are tested."""
    tile = 50
    spelt = boxes(s, 40).select("box_id", "t_lo", "t_hi", F.explode(F.sequence(F.floor(F.col("t_lo") / tile), F.floor((F.col("t_hi") - 1) / tile))).alias("tile"))
    cells = G1.cells(s, d).withColumn("tile", F.floor(F.col("t") / tile))
    return cells.join(spelt, "tile").where("t >= t_lo and t < t_hi").groupBy("box_id").agg(F.sum("sx").alias("s"), F.sum("n").alias("n"))


add("o07_range_join", range_join, f"WITH cells AS ({G1.sql}), boxes AS ({boxes_sql(40)}) SELECT box_id, CAST(sum(sx) AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n FROM boxes JOIN cells ON t >= t_lo AND t < t_hi GROUP BY box_id")


def asof(s, d) -> DataFrame:
    """For wanted anchors of each line the latest one stored in the sparse layout, in one window over both."""
    sparse = build_anchor(G2.cells(s, d), G2.sized(s, d), AnchorSpec.uniform(G2.spec, ("t",)), layout="sparse")
    lines = sparse.select("u").distinct().crossJoin(s.createDataFrame([(5,), (17,), (29,)], "q_t int"))
    both = sparse.select("u", "q_t", "sx", F.lit(0).alias("asked")).unionByName(lines.select("u", "q_t", F.lit(None).cast("long").alias("sx"), F.lit(1).alias("asked")))
    w = Window.partitionBy("u").orderBy("q_t", "asked").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.select("u", "q_t", "asked", F.last("sx", ignorenulls=True).over(w).alias("sx")).where("asked = 1").select("u", "q_t", F.coalesce("sx", F.lit(0)).alias("sx"))


add("o08_asof_anchor", asof, _ACT + "SELECT l.u, q_t, CAST(coalesce(sum(sx), 0) AS BIGINT) AS sx FROM (SELECT DISTINCT u FROM cells WHERE t < 720) l CROSS JOIN (VALUES (5), (17), (29)) q(q_t) LEFT JOIN cells c ON c.u = l.u AND c.t < q_t * 24 GROUP BY l.u, q_t")
_TILES = "SELECT DISTINCT CAST(y // 10 AS INT) AS ty, CAST(x // 4 AS INT) AS tx, CAST(t // 50 AS INT) AS tt"


def tiles(cells: DataFrame) -> DataFrame:
    return cells.select(*(F.floor(F.col(a) / k).cast("int").alias(f"t{a}") for a, k in (("y", 10), ("x", 4), ("t", 50)))).distinct()


def semi(s, d) -> DataFrame:
    """Cells in any of some boxes: an equi-join on the tiles along t that a box touches, then its bounds."""
    tile = 50
    spelt = boxes(s, 30).select("y_lo", "y_hi", "x_lo", "x_hi", "t_lo", "t_hi", F.explode(F.sequence(F.floor(F.col("t_lo") / tile), F.floor((F.col("t_hi") - 1) / tile))).alias("at"))
    cells = G1.cells(s, d).withColumn("tile", F.floor(F.col("t") / tile))
    held = F.expr("tile = at and y >= y_lo and y < y_hi and x >= x_lo and x < x_hi and t >= t_lo and t < t_hi")
    return cells.join(spelt, held, "left_semi").agg(F.count("*").alias("n"), F.sum("sx").alias("s"))


add("o09_semi_tiles", semi, f"WITH cells AS ({G1.sql}), boxes AS ({boxes_sql(30)}) SELECT count(*) AS n, CAST(sum(sx) AS BIGINT) AS s FROM cells WHERE EXISTS (SELECT 1 FROM boxes WHERE y >= y_lo AND y < y_hi AND x >= x_lo AND x < x_hi AND t >= t_lo AND t < t_hi)")


def all_tiles(s) -> DataFrame:
    line = lambda n, c: s.range(n).select(F.col("id").cast("int").alias(c))
    return line(5, "ty").crossJoin(line(3, "tx")).crossJoin(line(50, "tt"))


_ALL_TILES = "SELECT CAST(a AS INT) AS ty, CAST(b AS INT) AS tx, CAST(c AS INT) AS tt FROM range(5) r(a), range(3) q(b), range(50) p(c)"
add("o10_anti_tiles", lambda s, d: all_tiles(s).join(tiles(G1.cells(s, d).where("sx > 20000000")), ["ty", "tx", "tt"], "left_anti"), _SHIP + f", seen AS ({_TILES} FROM cells WHERE sx > 20000000) SELECT * FROM ({_ALL_TILES}) x WHERE NOT EXISTS (SELECT 1 FROM seen s WHERE s.ty = x.ty AND s.tx = x.tx AND s.tt = x.tt)")
add("o11_densify", lambda s, d: densify(G10.cells(s, d), G10.spec), f"SELECT CAST(i AS INT) AS nation, CAST(j AS INT) AS m, coalesce(sx, 0) AS sx, coalesce(n, 0) AS n FROM range(25) a(i) CROSS JOIN range(5) b(j) LEFT JOIN ({G10.sql}) g ON g.nation = i AND g.m = j")


def anchor_difference(s, d) -> DataFrame:
    """Neighbouring anchors differ by their tile's sum."""
    acc = store_of(s, d, G1, [("t",)]).tables["t",]
    w = Window.partitionBy("y", "x").orderBy("q_t")
    return acc.select("y", "x", (F.col("q_t") - 1).alias("tile"), (F.col("sx") - F.coalesce(F.lag("sx").over(w), F.lit(0))).alias("sx")).where("sx <> 0")


add("o12_anchor_diff", anchor_difference, _SHIP + "SELECT y, x, CAST(t // 50 AS INT) AS tile, CAST(sum(sx) AS BIGINT) AS sx FROM cells WHERE t < 2450 GROUP BY ALL HAVING sum(sx) <> 0")

# -- aggregation --------------------------------------------------------------------------------------------
add("o13_distinct_tiles", lambda s, d: tiles(G1.cells(s, d)).groupBy("ty").agg(F.count_distinct("tx", "tt").alias("n")), _SHIP + f"SELECT ty, count(*) AS n FROM ({_TILES} FROM cells) GROUP BY ty")
add("o13_approx_distinct", lambda s, d: G1.cells(s, d).groupBy("y").agg(F.count_distinct("t").alias("n"), F.approx_count_distinct("t", 0.02).alias("about")).select("y", "n", (F.abs(F.col("about") - F.col("n")) <= 0.1 * F.col("n") + 1).alias("close")), _SHIP + "SELECT y, count(DISTINCT t) AS n, TRUE AS close FROM cells GROUP BY y")
_SETS = "SELECT ty, tx, CAST(sum(sx) AS BIGINT) AS s, CAST(grouping(ty) * 2 + grouping(tx) AS BIGINT) AS g FROM (SELECT CAST(y // 10 AS INT) AS ty, CAST(x // 4 AS INT) AS tx, sx FROM cells) GROUP BY "


def tiled(s, d) -> DataFrame:
    return G1.cells(s, d).select(F.floor(F.col("y") / 10).cast("int").alias("ty"), F.floor(F.col("x") / 4).cast("int").alias("tx"), "sx")


add("o14_cube_tiles", lambda s, d: tiled(s, d).cube("ty", "tx").agg(*grouped()), _SHIP + _SETS + "CUBE (ty, tx)")
add("o15_rollup_tiles", lambda s, d: tiled(s, d).rollup("ty", "tx").agg(*grouped()), _SHIP + _SETS + "ROLLUP (ty, tx)")


def grouped():
    return F.sum("sx").alias("s"), F.grouping_id().alias("g")


def grouping_sets(s, d) -> DataFrame:
    return s.sql("SELECT ty, tx, sum(sx) AS s, grouping_id() AS g FROM {rows} GROUP BY GROUPING SETS ((ty), (tx))", rows=tiled(s, d))


add("o16_grouping_sets", grouping_sets, _SHIP + _SETS + "GROUPING SETS ((ty), (tx))")
add("o17_stats", lambda s, d: G1.cells(s, d).groupBy("x").agg(F.count("*").alias("n"), F.min("sx").alias("mn"), F.max("sx").alias("mx"), F.round(F.stddev_pop("sx"), 2).alias("sd"), F.round(F.corr("y", "sx"), 6).alias("r"), F.round(F.regr_slope("sx", "y"), 3).alias("slope")), _SHIP + "SELECT x, count(*) AS n, min(sx) AS mn, max(sx) AS mx, round(stddev_pop(sx), 2) AS sd, round(corr(y, sx), 6) AS r, round(regr_slope(sx, y), 3) AS slope FROM cells GROUP BY x")
add("o18_pivot_kind", lambda s, d: G2B.cells(s, d).groupBy("t").pivot("e", [0, 1, 2, 3, 4]).agg(F.sum("sx")).select("t", *(F.col(str(k)).alias(f"e{k}") for k in range(5))), f"SELECT t, {', '.join(f'CAST(sum(CASE WHEN e = {k} THEN sx END) AS BIGINT) AS e{k}' for k in range(5))} FROM ({G2B.sql}) GROUP BY t")

# -- windows, order, sets -----------------------------------------------------------------------------------
# one series: its length is the axis, so a window without partitions is bounded
add("o19_running_sum", lambda s, d: hourly(s, d).select("t", F.sum("s").over(by_t().rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("s")), _HOURLY + "SELECT t, CAST(sum(s) OVER (ORDER BY t) AS BIGINT) AS s FROM hourly")


def by_t():
    return Window.orderBy("t")


add("o20_moving_avg", lambda s, d: hourly(s, d).select("t", F.sum("s").over(by_t().rangeBetween(-5, 0)).alias("s"), F.count("*").over(by_t().rangeBetween(-5, 0)).alias("k")), _HOURLY + "SELECT t, CAST(sum(s) OVER w AS BIGINT) AS s, count(*) OVER w AS k FROM hourly WINDOW w AS (ORDER BY t RANGE BETWEEN 5 PRECEDING AND CURRENT ROW)")


def ranks(s, d) -> DataFrame:
    w = Window.partitionBy(F.floor(F.col("t") / 24)).orderBy(F.desc("n"), "t")
    v = Window.partitionBy(F.floor(F.col("t") / 24)).orderBy(F.desc("n"))
    return hourly(s, d).select("t", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"))


add("o21_rank_hours", ranks, _HOURLY + "SELECT t, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER v AS INT) AS rk, CAST(dense_rank() OVER v AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS quarter FROM hourly WINDOW w AS (PARTITION BY t // 24 ORDER BY n DESC, t), v AS (PARTITION BY t // 24 ORDER BY n DESC)")
add("o22_lag_series", lambda s, d: hourly(s, d).select("t", (F.col("s") - F.lag("s").over(by_t())).alias("change"), F.lead("s").over(by_t()).alias("coming"), F.first("s").over(by_t()).alias("opening")), _HOURLY + "SELECT t, s - lag(s) OVER w AS change, lead(s) OVER w AS coming, first_value(s) OVER w AS opening FROM hourly WINDOW w AS (ORDER BY t)")
add("o23_topk_cells", lambda s, d: G1.cells(s, d).orderBy(F.desc("sx"), "y", "x", "t").limit(25), _SHIP + "SELECT * FROM cells ORDER BY sx DESC, y, x, t LIMIT 25")
add("o24_intersect_tiles", lambda s, d: tiles(G1.cells(s, d).where("sx > 15000000")).intersect(tiles(G1.cells(s, d).where("n > 1"))), _SHIP + f"{_TILES} FROM cells WHERE sx > 15000000 INTERSECT {_TILES} FROM cells WHERE n > 1")
add("o25_except_tiles", lambda s, d: tiles(G1.cells(s, d)).exceptAll(tiles(G1.cells(s, d).where("n > 2"))), _SHIP + f"{_TILES} FROM cells EXCEPT {_TILES} FROM cells WHERE n > 2")

# -- functions ----------------------------------------------------------------------------------------------
add("o26_math", lambda s, d: G10.cells(s, d).select("nation", "m", F.abs("sx").alias("a"), F.signum(F.col("sx").cast("double")).alias("sg"), F.pmod("sx", F.lit(7)).cast("long").alias("pm"), F.round(F.sqrt(F.abs("sx")), 6).alias("root"), F.greatest("nation", "m").alias("g"), F.least("nation", "m").alias("l"), F.try_divide(F.col("sx").cast("double"), F.col("m").cast("double")).alias("q")), f"SELECT nation, m, abs(sx) AS a, CAST(sign(sx) AS DOUBLE) AS sg, CAST(((sx % 7) + 7) % 7 AS BIGINT) AS pm, round(sqrt(abs(sx)), 6) AS root, greatest(nation, m) AS g, least(nation, m) AS l, CASE WHEN m <> 0 THEN CAST(sx AS DOUBLE) / CAST(m AS DOUBLE) END AS q FROM ({G10.sql})")
add("o27_hour_index", lambda s, d: table(s, d, "events").select("event_id", hours("ts").alias("t"), F.hour("ts").alias("h"), F.dayofmonth("ts").alias("dom"), days("ts", "2024-01-01").alias("day")), "SELECT event_id, CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) / 3600000000) AS INT) AS t, CAST(hour(ts) AS INT) AS h, CAST(day(ts) AS INT) AS dom, CAST(date_diff('day', DATE '2024-01-01', ts) AS INT) AS day FROM events")
add("o28_text_length", lambda s, d: table(s, d, "conversations").select(F.concat_ws("/", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("key"), F.lower("role").alias("role"), F.length("text").alias("size")), "SELECT CAST(conv_id AS VARCHAR) || '/' || CAST(turn AS VARCHAR) AS key, lower(role) AS role, CAST(length(text) AS INT) AS size FROM conversations")


def packed_slices(s, d) -> DataFrame:
    packed = to_packed(G2B.cells(s, d).select("e", "t", "sx"), "t")
    return packed.select("e", F.aggregate(F.slice("values", 11, 100), F.lit(0).cast("long"), lambda a, v: a + v).alias("s"), F.size("values").alias("k"), F.element_at("index", 1).alias("first"))


add("o29_packed_slice_sum", packed_slices, f"SELECT e, CAST(sum(CASE WHEN rn BETWEEN 11 AND 110 THEN sx ELSE 0 END) AS BIGINT) AS s, CAST(count(*) AS INT) AS k, min(t) AS first FROM (SELECT *, row_number() OVER (PARTITION BY e ORDER BY t) AS rn FROM ({G2B.sql})) GROUP BY e")
add("o30_json_k", lambda s, d: table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n"), F.sum(F.from_json("props", "k int")["k"]).alias("total")), "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n, CAST(sum(CAST(json_extract_string(props, '$.k') AS INT)) AS BIGINT) AS total FROM events GROUP BY 1")
add("o31_decimal_sum", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg((F.sum(F.col("l_extendedprice").cast("decimal(18,2)")) * 100).cast("long").alias("s")), "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) * 100 AS BIGINT) AS s FROM lineitem GROUP BY 1")


def sql_box(s, d) -> DataFrame:
    """The weak point of a session's views is their names, so the cells come as a parameter."""
    return s.sql("SELECT t, sum(sx) AS s, sum(n) AS n FROM {cells} WHERE y >= {lo} AND y < {hi} GROUP BY t", cells=G1.cells(s, d), lo=7, hi=33)


add("o32_sql_box", sql_box, _SHIP + "SELECT t, CAST(sum(sx) AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n FROM cells WHERE y >= 7 AND y < 33 GROUP BY t")


# -- user-defined functions ---------------------------------------------------------------------------------
def packed_running(s, d) -> DataFrame:
    packed = to_packed(G2B.cells(s, d).select("e", "t", "sx"), "t")
    summed = packed.select("e", F.arrays_zip("index", udf.packed_cumsum("values").alias("sums")).alias("z"))
    return summed.select("e", F.explode("z").alias("z")).select("e", F.col("z.index").alias("t"), F.col("z.sums").alias("s"))


add("u01_packed_cumsum", packed_running, f"SELECT e, t, CAST(sum(sx) OVER (PARTITION BY e ORDER BY t) AS BIGINT) AS s FROM ({G2B.sql})")
add("u02_comp_sum", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(udf.compensated_sum("l_extendedprice"), 2).alias("s")), "SELECT l_returnflag, round(CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE), 2) AS s FROM lineitem GROUP BY 1")


def pieces_by_table_function(s, d) -> DataFrame:
    """The pieces of each customer's days from the first order to the last."""
    udf.register(s)
    day = days("o_orderdate", "1995-01-01")
    spans = table(s, d, "orders").groupBy(F.col("o_custkey").alias("box_id")).agg(F.min(day).alias("t_lo"), (F.max(day) + 1).alias("t_hi")).where("t_lo is not null")
    return s.sql(f"SELECT box_id, p.* FROM {{spans}}, LATERAL box_pieces(t_lo, t_hi, 50, {G5.spec['t'].n}) p", spans=spans)


_SPANS = "SELECT o_custkey AS box_id, min(date_diff('day', DATE '1995-01-01', o_orderdate)) AS t_lo, max(date_diff('day', DATE '1995-01-01', o_orderdate)) + 1 AS t_hi FROM orders WHERE o_orderdate IS NOT NULL GROUP BY 1"
_ENDS = f"WITH e AS (SELECT box_id, t_lo, t_hi, CAST(t_lo // 50 AS INT) AS a, CAST(t_hi // 50 AS INT) AS b FROM ({_SPANS})) "
add("u03_pieces_udtf", pieces_by_table_function, _ENDS + " UNION ALL ".join(f"SELECT box_id, '{kind}' AS kind, CAST({lo} AS INT) AS lo, CAST({hi} AS INT) AS hi, {sign} AS sign FROM e WHERE {when}" for kind, lo, hi, sign, when in (
    ("gap", "t_lo", "t_hi", 1, "a = b"), ("anchor", "b", "b", 1, "a <> b AND b > 0"), ("anchor", "a", "a", -1, "a <> b AND a > 0"), ("gap", "b * 50", "t_hi", 1, "a <> b AND b * 50 < t_hi"), ("gap", "a * 50", "t_lo", -1, "a <> b AND a * 50 < t_lo"),
)))
add("o33_fact_of_axes", lambda s, d: G6.cells(s, d).agg(F.min("d").alias("lo"), F.max("d").alias("hi"), F.count("*").alias("n")), "SELECT CAST(min(doc_id) AS INT) AS lo, CAST(max(doc_id) AS INT) AS hi, count(*) AS n FROM documents")
add("o34_anchor_max_by", lambda s, d: store_of(s, d, G1, [("t",)]).tables["t",].groupBy("y", "x").agg(F.max_by("sx", "q_t").alias("sx")), f"SELECT y, x, sx FROM ({anchor_sql(G1, 't')}) QUALIFY row_number() OVER (PARTITION BY y, x ORDER BY q_t DESC) = 1")
