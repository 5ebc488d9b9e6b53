"""Methods, baselines and measures as queries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.functions import measure
from boxsum.operators import baseline, query
from boxsum.operators.build import AnchorStore, accumulate, build_anchor, lookup_sparse, points, to_packed
from boxsum.plans.box import plan_box
from boxsum.plans.spec import AnchorCatalog, AnchorSpec, subsets_for
from boxsum.sources import io
from boxsum.sources.grids import G1, G1_MORE, G4, G6, G7
from boxsum.streaming.upkeep import append_slices, repair_late
from boxsum.workloads.cases import add, add_anchor, add_box, all_subsets, anchor_sql, box_sql, store_of

REGION = {"y": (7, 33), "x": (2, 9)}
PERIOD = {"t": (123, 2001)}
BOX = REGION | PERIOD
LINE = {"d": (37, 861)}
FINE = G1.with_tiles(x=1)  # eleven tiles along x, so that a stride of three has anchors

# -- building -----------------------------------------------------------------------------------------------

add("m01_prefix_1d", lambda s, d: baseline.range_average(G6.cells(s, d), "d", *LINE["d"]), "SELECT CAST(sum(n_chars) AS BIGINT) AS s, CAST(sum(n_chars) AS DOUBLE) / 824 AS avg FROM documents WHERE doc_id >= 37 AND doc_id < 861")
for _s in all_subsets("yxt"):
    add_anchor(f"m0{min(len(_s), 3) + 2}_anchor_{''.join(_s)}", G1, _s)
add_anchor("m05_anchor_4d", G7, "yxzt")


def sparse_lookup(s, d) -> DataFrame:
    spec = AnchorSpec.uniform(G1.spec, ("y",))
    sparse = build_anchor(G1.cells(s, d), G1.spec, spec, layout="sparse")
    return lookup_sparse(sparse, "y", 3, ("sx", "n"))


add("m06_sparse_anchor_lookup", sparse_lookup, f"SELECT x, t, sx, n FROM ({anchor_sql(G1, 'y')}) WHERE q_y = 3")


def packed_lookup(s, d) -> DataFrame:
    store = store_of(s, d, G1, [("t",)])
    packed = to_packed(store.tables["t",], "q_t", ("sx", "n"))
    at = F.array_position("index", 7).cast("int")
    return packed.where(at > 0).select("y", "x", F.element_at("sx", at).alias("sx"), F.element_at("n", at).alias("n"))


add("m06_packed_anchor", packed_lookup, f"SELECT y, x, sx, n FROM ({anchor_sql(G1, 't')}) WHERE q_t = 7")


def dense_anchor(s, d) -> DataFrame:
    return build_anchor(G1.cells(s, d), G1.spec, AnchorSpec.uniform(G1.spec, ("t",)), layout="dense")


add("m06_dense_anchor", dense_anchor, f"WITH cells AS ({G1.sql}) SELECT l.y, l.x, q_t, CAST(coalesce(sum(sx), 0) AS BIGINT) AS sx, CAST(coalesce(sum(n), 0) AS BIGINT) AS n FROM (SELECT DISTINCT y, x FROM cells) l CROSS JOIN (SELECT CAST(k AS INT) AS q_t FROM range(1, 50) r(k)) LEFT JOIN cells c ON c.y = l.y AND c.x = l.x AND c.t < q_t * 50 GROUP BY ALL")


def hierarchy_equals_direct(s, d) -> DataFrame:
    subsets = [("y",), ("x",), ("y", "x"), ("y", "x", "t")]
    cells = G1.cells(s, d)
    reused, direct = (AnchorStore.build(cells, G1.spec, subsets, 1, r).tables["y", "x", "t"] for r in (True, False))
    off = reused.exceptAll(direct).select(F.lit(1).alias("reused"), F.lit(0).alias("direct")).unionByName(direct.exceptAll(reused).select(F.lit(0).alias("reused"), F.lit(1).alias("direct")))
    marked = off.withColumn("sx", F.lit(0)).withColumn("k", F.lit(0)).unionByName(reused.select(F.lit(0).alias("reused"), F.lit(0).alias("direct"), "sx", F.lit(1).alias("k")))
    return marked.agg(F.sum("reused").alias("only_reused"), F.sum("direct").alias("only_direct"), F.sum("k").alias("n_rows"), F.sum("sx").alias("total"))


add("m07_hierarchy_equals_direct", hierarchy_equals_direct, f"SELECT CAST(0 AS BIGINT) AS only_reused, CAST(0 AS BIGINT) AS only_direct, count(*) AS n_rows, CAST(sum(sx) AS BIGINT) AS total FROM ({anchor_sql(G1, 'yxt')})")
for _k in (1, 2, 4):
    add_box(f"m08_stride_{_k}", G1, BOX, "yx", stride=_k)
add_box("m08_stride_1_3_0", FINE, REGION, "yx", stride={"y": 1, "x": 3})
add_box("m08_stride_0_0_2", G1, PERIOD, "t", stride={"t": 2})


def both_modes(s, d) -> DataFrame:
    store = store_of(s, d, G1, all_subsets("yx"))
    return measure.union(query.area_series(store, REGION, mode=m).withColumn("mode", F.lit(m)) for m in ("floor", "nearest"))


add("m09_floor_vs_nearest", both_modes, " UNION ALL ".join(f"SELECT *, '{m}' AS mode FROM ({box_sql(G1, REGION, 'yx')})" for m in ("floor", "nearest")))

# -- patched tiles ------------------------------------------------------------------------------------------

TILE = {"y": 1, "x": 1, "t": 3}


def patched(s, d) -> DataFrame:
    return query.patched_tile(store_of(s, d, G1, all_subsets("yx")), TILE, "yx")


_TILE_SQL = "(SELECT CAST(y AS INT) AS y FROM range(10, 20) a(y)), (SELECT CAST(x AS INT) AS x FROM range(4, 8) b(x)), (SELECT CAST(t AS INT) AS t FROM range(150, 200) c(t))"
_ROLE = "concat_ws('+', CASE WHEN y <= 10 THEN 'y' END, CASE WHEN x <= 4 THEN 'x' END) AS role"
add("m10_patched_tile_roles", lambda s, d: patched(s, d).groupBy(F.concat_ws("+", "role").alias("role")).agg(F.count("*").alias("n_cells"), F.sum("value").alias("s")), f"WITH cells AS ({G1.sql}) SELECT role, n_cells, CAST(coalesce(s, 0) AS BIGINT) AS s FROM (SELECT {_ROLE}, count(*) AS n_cells FROM {_TILE_SQL} GROUP BY ALL) LEFT JOIN (SELECT {_ROLE}, sum(sx) AS s FROM cells WHERE y < 20 AND x < 8 AND t >= 150 AND t < 200 GROUP BY ALL) USING (role)")
add("m10_patched_tile_sum", lambda s, d: patched(s, d).where("y <= 16 and x <= 6").groupBy("t").agg(F.sum("value").alias("s")), f"WITH cells AS ({G1.sql}) SELECT k.t, CAST(coalesce(sum(sx), 0) AS BIGINT) AS s FROM (SELECT CAST(t AS INT) AS t FROM range(150, 200) c(t)) k LEFT JOIN cells ON cells.t = k.t AND y <= 16 AND x <= 6 GROUP BY k.t")

# -- plans and boxes ----------------------------------------------------------------------------------------


def plan_rows(s, d) -> DataFrame:
    """Each scan's pieces as axis:anchor*sign and axis:low-high*sign, the rows that it reads where none is missing, and those that it finds."""
    store = store_of(s, d, G1, all_subsets("yx"))
    plan = plan_box(store.grid, store.specs, BOX, "yx")
    anchors = lambda t: " ".join(f"{a}:{q}*{sign}" for a, qs in t.anchors.items() for q, sign in qs)
    gaps = lambda t: " ".join(f"{a}:{lo}-{hi}*{sign}" for a, gs in t.gaps.items() for lo, hi, sign in gs)
    told = lambda t: [F.lit(v).alias(k) for k, v in (("scan", "+".join(t.subset) or "cells"), ("anchors", anchors(t)), ("gaps", gaps(t)))]
    return measure.union(query.scan_term(store, t, ["n"]).agg(*told(t), F.lit(t.reads).cast("long").alias("reads"), F.count("*").alias("found")) for t in plan.scans)


# by hand: y [7, 33) in steps of 10 is anchor 3, gaps [30, 33) and -[0, 7); x [2, 9) in steps of 4 anchor 2, [8, 9) and -[0, 2); 1,878 days
_READ = {"cells": (G1.sql, "(y < 7 OR y >= 30 AND y < 33) AND (x < 2 OR x = 8)"), "y": (anchor_sql(G1, "y"), "q_y = 3 AND (x < 2 OR x = 8)"), "x": (anchor_sql(G1, "x"), "(y < 7 OR y >= 30 AND y < 33) AND q_x = 2"), "y+x": (anchor_sql(G1, "yx"), "q_y = 3 AND q_x = 2")}
_FOUND = " UNION ALL ".join(f"SELECT '{k}' AS scan, count(*) AS found FROM ({sql}) WHERE t >= 123 AND t < 2001 AND {w}" for k, (sql, w) in _READ.items())
add("m11_plan", plan_rows, f"""SELECT scan, anchors, gaps, CAST(k * 1878 AS BIGINT) AS reads, found FROM (VALUES
  ('cells', '', 'y:30-33*1 y:0-7*-1 x:8-9*1 x:0-2*-1', 10 * 3), ('y', 'y:3*1', 'x:8-9*1 x:0-2*-1', 1 * 3), ('x', 'x:2*1', 'y:30-33*1 y:0-7*-1', 10 * 1), ('y+x', 'y:3*1 x:2*1', '', 1)) v(scan, anchors, gaps, k) JOIN ({_FOUND}) USING (scan)""")


def needed_subsets(s, d) -> DataFrame:
    """The subsets that two services need, and the lines of cells that each one's table sums along."""
    cells = G1.cells(s, d)
    return measure.union(cells.select(*(a for a in G1.spec.names if a not in x)).distinct().agg(F.lit("+".join(x)).alias("subset"), F.lit(len(x)).alias("axes"), F.count("*").alias("lines")) for x in subsets_for(["yx", "t"], G1.spec))


add("m02_subsets", needed_subsets, f"WITH cells AS ({G1.sql}) " + " UNION ALL ".join(f"SELECT '{x}' AS subset, {n} AS axes, count(DISTINCT ({rest})) AS lines FROM cells" for x, n, rest in (("y", 1, "x, t"), ("x", 1, "y, t"), ("t", 1, "y, x"), ("y+x", 2, "t"))))
add_box("m12_global_series", G1, {}, "yx")
add_box("m13_box_1corner", G1, {"y": (0, 33), "x": (0, 9)}, "yx")
add_box("m13_box_2corner", G1, {"y": (7, 33), "x": (0, 9)}, "yx")
add_box("m13_box_4corner", G1, REGION, "yx")
add_box("m14_area_series", G1, BOX, "yx", mode="nearest")
add_box("m15_time_map", G1, PERIOD, "t")
for _d in ("x", "yt", "xt", "yxt"):
    add_box(f"m16_avg_{_d}", G1, BOX, _d)
add_box("m16_avg_4d", G7, BOX | {"z": (1, 8)}, "yxzt")
add_box("m17_missing_combo", G1, BOX, "yt", subsets=[("y",), ("t",)])
add_box("m18_weighted_series", G1_MORE, REGION, "yx", divisor="weight")
add_box("m18_present_series", G1_MORE, REGION, "yx", divisor="present")
add_box("m18_weighted_labels", G6, LINE, "d", divisor="weight")
add("m19_box_variance", lambda s, d: query.box_moments(store_of(s, d, G1_MORE, all_subsets("yx")), REGION, "yx"), f"""WITH cells AS ({G1_MORE.sql}) SELECT t, CAST(sum(p) AS BIGINT) AS p, CAST(sum(sx) AS DOUBLE) / CAST(sum(p) AS DOUBLE) AS mean,
  greatest(0.0, CAST(sum(sxx) * sum(p) - CAST(sum(sx) AS HUGEINT) * CAST(sum(sx) AS HUGEINT) AS DOUBLE) / (CAST(sum(p) AS DOUBLE) * CAST(sum(p) AS DOUBLE))) AS variance FROM cells WHERE y >= 7 AND y < 33 AND x >= 2 AND x < 9 GROUP BY t""")
_EXTREMA = "WITH cells AS ({sql}) SELECT {keys}, min(sx) AS mn, max(sx) AS mx FROM cells WHERE {where} GROUP BY {keys}"
add("m20_minmax_tiles", lambda s, d: query.box_extrema(G1.cells(s, d), G1.spec, REGION, "yx"), _EXTREMA.format(sql=G1.sql, keys="t", where="y >= 7 AND y < 33 AND x >= 2 AND x < 9"))
add("m20_minmax_prefix", lambda s, d: query.box_extrema(G1.cells(s, d), G1.spec, {"t": (0, 2001)}, "t", "prefix"), _EXTREMA.format(sql=G1.sql, keys="y, x", where="t < 2001"))
add("m20_minmax_blocks", lambda s, d: query.box_extrema(G1.cells(s, d), G1.spec, {"y": (7, 33)}, "y", "blocks"), _EXTREMA.format(sql=G1.sql, keys="x, t", where="y >= 7 AND y < 33"))


def stored_extrema(s, d) -> DataFrame:
    """A long range through two stored blocks a line."""
    root, cells = io.scratch(s, "extrema"), G1.cells(s, d)
    io.write_extrema(cells, G1.spec, root, "t", "blocks")
    return query.box_extrema(cells, G1.spec, PERIOD, "t", "blocks", io.read_extrema(s, G1.spec, root, "t", "blocks"))


add("m20_minmax_stored", stored_extrema, _EXTREMA.format(sql=G1.sql, keys="y, x", where="t >= 123 AND t < 2001"))


# -- catalog ------------------------------------------------------------------------------------------------


def example_catalog() -> AnchorCatalog:
    """Weighted data and weights for {y}, {x}, {t} and {y, x}; the other combinations are absent."""
    out = AnchorCatalog(G1.spec)
    for x in ("y", "x", "t", "yx"):
        out.add(AnchorSpec.uniform(G1.spec, tuple(x), {"y": 1, "x": 3, "t": 2} if x == "yx" else 1), ("weighted", "weight"))
    return AnchorCatalog.from_json(out.to_json())


_STRIDES = {"y": 1, "x": 1, "t": 1, "y+x": {"y": 1, "x": 3}}


def named_rows(s, d, catalog: AnchorCatalog, subset) -> DataFrame:
    """(n_rows) of the table that the catalog has for a subset, by its strides."""
    return build_anchor(G1.cells(s, d), G1.spec, AnchorSpec.uniform(G1.spec, subset, catalog.stride(subset))).agg(F.count("*").alias("n_rows"))


def catalog_rows(s, d) -> DataFrame:
    c = example_catalog()
    return measure.union(named_rows(s, d, c, x).select(F.lit("+".join(x)).alias("subset"), F.lit(k).alias("kind"), F.lit(p).alias("path"), "n_rows") for x, k, p, _ in c.rows())


_NAMED = " UNION ALL ".join(f"SELECT '{x}' AS subset, count(*) AS n_rows FROM ({anchor_sql(G1, x.split('+'), k)})" for x, k in _STRIDES.items())
add("m21_catalog_rows", catalog_rows, f"SELECT subset, k AS kind, p || replace(subset, '+', '_') AS path, n_rows FROM ({_NAMED}), (VALUES ('weighted', 'acc_weighted_'), ('weight', 'acc_wt_')) w(k, p)")


def lookups(s, d) -> DataFrame:
    c = example_catalog()
    asked = [(("x", "y"), "weighted"), (("y", "x"), "weight"), (("t",), "weighted"), (("t", "y"), "weighted"), (("y",), "plain")]
    rows = lambda a, path: named_rows(s, d, c, a) if path else s.range(1).select(F.lit(None).cast("long").alias("n_rows"))
    return measure.union(rows(a, path).select(F.lit("+".join(a)).alias("asked"), F.lit(k).alias("kind"), F.lit(path).cast("string").alias("path"), "n_rows") for a, k in asked for path in [c.find(a, k)])


add("m22_lookup", lookups, f"SELECT asked, kind, path, n_rows FROM (VALUES ('x+y', 'weighted', 'acc_weighted_y_x', 'y+x'), ('y+x', 'weight', 'acc_wt_y_x', 'y+x'), ('t', 'weighted', 'acc_weighted_t', 't'), ('t+y', 'weighted', NULL, NULL), ('y', 'plain', NULL, NULL)) v(asked, kind, path, subset) LEFT JOIN ({_NAMED}) USING (subset)")


def tile_to_anchor(s, d) -> DataFrame:
    """The tiles along x that have cells, each with the anchor at or below it by the catalog's stride."""
    tile = F.floor(F.col("x") / FINE.spec["x"].tile).cast("int")
    tiles = FINE.cells(s, d).groupBy(tile.alias("tile")).agg(F.count("*").alias("n_cells"))
    return tiles.select("tile", F.floor(F.col("tile") / example_catalog().stride("yx")["x"]).cast("int").alias("anchor"), "n_cells")


add("m23_tile_to_anchor", tile_to_anchor, f"SELECT x AS tile, CAST(x // 3 AS INT) AS anchor, count(*) AS n_cells FROM ({FINE.sql}) GROUP BY x")
add_box("m25_mixed_strides", G1, BOX, "yx", stride={("y",): {"y": 2}, ("x",): {"x": 1}, ("y", "x"): {"y": 1, "x": 2}})
add_box("m26_small_box", G1, {"y": (11, 18), "x": (4, 8)}, "yx")

# -- many boxes ---------------------------------------------------------------------------------------------

_N = {"y": 50, "x": 11, "t": 2499}
_PRIME = {"y": (7919, 104729), "x": (7907, 104723), "t": (7901, 104717)}


def boxes(s, n: int = 1000) -> DataFrame:
    out = s.range(n).withColumnRenamed("id", "box_id")
    for a, size in _N.items():
        p, r = _PRIME[a]
        lo = F.pmod(F.col("box_id") * p, F.lit(size))
        out = out.withColumn(f"{a}_lo", lo.cast("int")).withColumn(f"{a}_hi", (F.col(f"{a}_lo") + 1 + F.pmod(F.col("box_id") * r, size - F.col(f"{a}_lo"))).cast("int"))
    return out


def boxes_sql(n: int = 1000) -> str:
    lows = ", ".join(f"CAST((id * {_PRIME[a][0]}) % {size} AS INT) AS {a}_lo" for a, size in _N.items())
    highs = ", ".join(f"{a}_lo, CAST({a}_lo + 1 + (id * {_PRIME[a][1]}) % ({size} - {a}_lo) AS INT) AS {a}_hi" for a, size in _N.items())
    return f"SELECT id AS box_id, {highs} FROM (SELECT id, {lows} FROM range({n}) r(id))"


def many_sql(over: str, n: int, some: str = "TRUE") -> str:
    kept = [a for a in "yxt" if a not in over]
    keys = "".join(f", {a}" for a in kept)
    size = " * ".join(f"({a}_hi - {a}_lo)" for a in over)
    inside = " AND ".join(f"c.{a} >= b.{a}_lo AND c.{a} < b.{a}_hi" for a in "yxt")
    return f"WITH cells AS ({G1.sql}), boxes AS ({boxes_sql(n)}) SELECT box_id{keys}, CAST(sum(sx) AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n, CAST(sum(sx) AS DOUBLE) / CAST(any_value({size}) AS DOUBLE) AS avg FROM boxes b JOIN cells c ON {inside} WHERE {some} GROUP BY box_id{keys}"


add("m27_many_boxes_nearest", lambda s, d: query.box_average_many(store_of(s, d, G1, [("y",), ("x",), ("y", "x"), ("t",)]), boxes(s, 1000), "yxt", mode="nearest"), many_sql("yxt", 1000))
add("m27_many_boxes", lambda s, d: query.box_average_many(store_of(s, d, G1, all_subsets("yxt")), boxes(s, 1000), "yxt"), many_sql("yxt", 1000))

# -- upkeep and storage -------------------------------------------------------------------------------------


def appended(s, d, subset) -> DataFrame:
    cells = G1.cells(s, d)
    first = G1.with_axes(t=1777)
    store = AnchorStore.build(cells.where("t < 1777"), first.spec, all_subsets("yt"))
    return append_slices(store, cells.where("t >= 1777"), 2499).tables[subset]


add("m28_append_equals_rebuild", lambda s, d: appended(s, d, ("t",)), anchor_sql(G1, "t"))
add("m28_append_2d", lambda s, d: appended(s, d, ("y", "t")), anchor_sql(G1, "yt"))


def repaired(s, d) -> DataFrame:
    cells = G1.cells(s, d)
    late = (F.col("t") % 97 == 5) & (F.col("y") < 20)
    return repair_late(AnchorStore.build(cells.where(~late), G1.spec, all_subsets("yt")), cells.where(late)).tables["y", "t"]


add("m28_late_repair", repaired, anchor_sql(G1, "yt"))


def by_coordinates(s, d) -> DataFrame:
    spec = G1.spec
    low, high = spec["y"].span(7.0, 33.0), spec["x"].span(2.0, 8.5)
    return query.area_series(store_of(s, d, G1, all_subsets("yx")), {"y": low[0], "x": high[0]})


add("m29_coordinate_box", by_coordinates, box_sql(G1, REGION, "yx"))


def stored(s, d) -> DataFrame:
    root = io.scratch(s, "store")
    io.write_store(store_of(s, d, G1, all_subsets("yx")), root)
    return query.area_series(io.read_store(s, root), REGION)


add("m30_stored_series", stored, box_sql(G1, REGION, "yx"))


def stored_weights(s, d) -> DataFrame:
    """Weighted data and weights as arrays of their own, found by the attributes."""
    root = io.scratch(s, "weights")
    io.write_store(store_of(s, d, G1_MORE, all_subsets("yx")), root, ("weighted", "weight"), with_cells=False)
    return query.area_series(io.read_store(s, root, G1_MORE.cells(s, d)), REGION, divisor="weight")


add("m30_stored_weights", stored_weights, box_sql(G1_MORE, REGION, "yx", "weight"))

# -- baselines ----------------------------------------------------------------------------------------------

add("b1_scan_series", lambda s, d: baseline.scan_average(G1.cells(s, d), G1.spec, REGION, "yx"), box_sql(G1, REGION, "yx"))
add("b1_scan_map", lambda s, d: baseline.scan_average(G1.cells(s, d), G1.spec, PERIOD, "t"), box_sql(G1, PERIOD, "t"))
add("b2_full_prefix_box", lambda s, d: baseline.full_prefix_average(baseline.build_full_prefix(G1.cells(s, d), G1.spec, "yx"), G1.spec, REGION, "yx"), box_sql(G1, REGION, "yx"))


def cached(s, d) -> DataFrame:
    store = store_of(s, d, G1, [("t",)])
    ask = baseline.CachedAverager(lambda box, over: query.box_average(store, box, over))
    first = ask(PERIOD, "t")
    return first.unionByName(ask(PERIOD, "t")).withColumn("hits", F.lit(ask.hits))


_MAP = box_sql(G1, PERIOD, "t")
add("b3_cache", cached, f"SELECT *, 1 AS hits FROM ({_MAP}) UNION ALL SELECT *, 1 AS hits FROM ({_MAP})")
add("b7_tile_totals", lambda s, d: baseline.tile_total_average(G1.cells(s, d), G1.spec, REGION, "yx"), box_sql(G1, REGION, "yx"))

# -- measures -----------------------------------------------------------------------------------------------


def accuracy(s, d, box, over) -> DataFrame:
    store = store_of(s, d, G1, all_subsets(over))
    plan = plan_box(G1.spec, store.specs, box, over)
    return measure.nrmsd(baseline.scan_average(store.cells, G1.spec, box, over), query.box_average(store, box, over), list(plan.kept))


_ACCURATE = "SELECT CAST(0 AS BIGINT) AS unmatched, count(*) AS n, CAST(0 AS DOUBLE) AS nrmsd, CAST(0 AS DOUBLE) AS max_abs, CAST(0 AS DOUBLE) AS max_rel FROM ({})"
add("c1_nrmsd_series", lambda s, d: accuracy(s, d, REGION, "yx"), _ACCURATE.format(box_sql(G1, REGION, "yx")))
add("c1_nrmsd_map", lambda s, d: accuracy(s, d, PERIOD, "t"), _ACCURATE.format(_MAP))
_SERVICES = [("r",), ("c",), ("t",), ("r", "c")]


def _points_sql(strides) -> str:
    """Points of the field's tables by arithmetic alone."""
    n, tile = {a: f"CAST({G4.length_sql(a)} AS BIGINT)" for a in "rct"}, {"r": 50, "c": 16, "t": 40}
    rows = []
    for k in strides:
        for s in _SERVICES:
            terms = " * ".join(f"({n[a]} // ({tile[a]} * {k}))" if a in s else n[a] for a in n)
            rows.append(f"SELECT '{'_'.join(s)}' AS subset, {k} AS stride, CAST({terms} AS BIGINT) AS points, CAST({terms} AS DOUBLE) / CAST({' * '.join(n.values())} AS DOUBLE) AS fraction")
    return " UNION ALL ".join(rows)


def sweep(s, d, strides) -> DataFrame:
    grid = G4.sized(s, d)
    rows = [("_".join(x), k, points(grid, spec), points(grid, spec) / grid.cells) for k in strides for x in _SERVICES for spec in [AnchorSpec.uniform(grid, x, k)]]
    return s.createDataFrame(rows, "subset string, stride int, points long, fraction double")


add("c5_overhead_points", lambda s, d: sweep(s, d, (2,)), _points_sql((2,)))
add("c10_stride_sweep", lambda s, d: sweep(s, d, (1, 2, 4, 8)), _points_sql((1, 2, 4, 8)))


def reads(s, d) -> DataFrame:
    """What the plan expects to read, and what its scans find, on the dense field."""
    store = store_of(s, d, G4, all_subsets("rc"))
    box = {"r": (3, 77), "c": (5, 59), "t": (100, 200)}
    plan = plan_box(store.grid, store.specs, box, "rc")
    found = measure.union(query.scan_term(store, t, ["n"]).agg(F.count("*").alias("found")).select(F.lit("+".join(t.subset) or "cells").alias("scan"), F.lit(t.reads).alias("planned"), "found") for t in plan.scans)
    return found.withColumn("planned", F.col("planned").cast("long"))


# r: anchor 1, gaps [50, 77) and [0, 3); c: anchor 3, gaps [48, 59) and [0, 5); 100 slices
add("c9_cells_read", reads, "SELECT scan, CAST(k AS BIGINT) AS planned, CAST(k AS BIGINT) AS found FROM (VALUES ('cells', (27 + 3) * (11 + 5) * 100), ('r', 1 * (11 + 5) * 100), ('c', (27 + 3) * 1 * 100), ('r+c', 1 * 1 * 100)) v(scan, k)")


def tiles_touched(s, d) -> DataFrame:
    """Tiles of cells and anchor rows that the plan's scans expect to touch, and those that they find, on the dense field."""
    store = store_of(s, d, G4, all_subsets("rc"))
    return measure.touched(store, plan_box(store.grid, store.specs, {"r": (3, 77), "c": (5, 59), "t": (100, 200)}, "rc"))


# the plan of c9: an anchor row is there where a cell lies below its anchors
_WANTED = "(r < 3 OR r >= 50 AND r < 77) AND (c < 5 OR c >= 48 AND c < 59)"
_TILES = f"SELECT (SELECT count(DISTINCT (r // 50, c // 16, t // 40)) FROM range(500) a(r), range(64) b(c), range(100, 200) k(t) WHERE {_WANTED}) AS tiles, count(DISTINCT (r // 50, c // 16, t // 40)) AS found FROM ({G4.sql}) WHERE t >= 100 AND t < 200 AND {_WANTED}"
_ROWS = f"""SELECT CAST(1 * (11 + 5) * 100 + (27 + 3) * 1 * 100 + 1 * 1 * 100 AS BIGINT) AS anchor_rows, count(DISTINCT (c, t)) FILTER (r < 50 AND (c < 5 OR c >= 48 AND c < 59))
  + count(DISTINCT (r, t)) FILTER (c < 48 AND (r < 3 OR r >= 50 AND r < 77)) + count(DISTINCT t) FILTER (r < 50 AND c < 48) AS anchor_rows_found FROM ({G4.sql}) WHERE t >= 100 AND t < 200"""
add("c8_tiles_touched", tiles_touched, f"SELECT *, tiles + anchor_rows AS touched, found + anchor_rows_found AS touched_found FROM ({_TILES}) CROSS JOIN ({_ROWS})")


def top(s, d) -> DataFrame:
    return measure.headroom(store_of(s, d, G1, [("y", "x", "t")]).tables["y", "x", "t"])


add("c11_headroom", top, f"SELECT max(abs(sx)) AS largest, CAST(max(abs(sx)) AS DOUBLE) / 9223372036854775807.0 AS share FROM ({anchor_sql(G1, 'yxt')})")


def running_extremum(s, d) -> DataFrame:
    return accumulate(G1.cells(s, d).select("y", "x", "t", F.col("sx").alias("mx")), ["y", "x"], "t", 50, 2499, {"mx": "max"})


add("m20_anchor_max", running_extremum, f"WITH cells AS ({G1.sql}) SELECT y, x, q_t, max(sx) AS mx FROM cells JOIN (SELECT CAST(k AS INT) AS q_t FROM range(1, 50) r(k)) ON t < q_t * 50 GROUP BY ALL")
