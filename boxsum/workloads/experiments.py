"""The experiment workloads over the given tables."""

from __future__ import annotations

from dataclasses import replace
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.functions import measure
from boxsum.operators import baseline, query
from boxsum.operators.build import columns_of
from boxsum.plans.box import plan_box
from boxsum.sources.grids import G1, G1_MORE, G2, G2B, G3, G4, G4_FLOATS, G5, G6, G7, G8, G9, G10
from boxsum.workloads.cases import add, add_box, all_subsets, anchor_sql, box_sql, store_of, stored
from boxsum.workloads.methods import _ACCURATE, BOX, FINE, LINE, PERIOD, REGION, _points_sql, boxes, example_catalog, many_sql, sweep

SIZES_FIELD = tuple(range(80, 721, 80))  # hours; each ends on an anchor of stride 2
SIZES_SHIP = tuple(range(400, 2401, 400))  # days


def sized(grid, over: str, sizes, stride: int):
    """One result of all sizes of the time range, through anchors; and its SQL."""

    def run(s, d) -> DataFrame:
        store = stored(s, d, grid, all_subsets(grid.spec.order(over)), stride)
        return measure.union(query.box_average(store, {"t": (0, k)}, over).withColumn("size", F.lit(k)) for k in sizes)

    return run, " UNION ALL ".join(f"SELECT *, {k} AS size FROM ({box_sql(grid, {'t': (0, k)}, over)})" for k in sizes)


add("w01_series_g4", *sized(G4, "rc", SIZES_FIELD, 2))
add("w01_series_g1", *sized(G1, "yx", SIZES_SHIP, 1))
add_box("w02_series_full", G1, {}, "yx", stride=2)
add_box("w02_series_full_g4", G4, {}, "rc", stride=2)
add("w03_map_g4", *sized(G4, "t", SIZES_FIELD, 2))
add("w03_map_g1", *sized(G1, "t", SIZES_SHIP, 1))
add_box("w04_map_full", G4, {}, "t", stride=2)
add_box("w04_map_full_g1", G1, {}, "t", stride=2)


def at_ranges(found: DataFrame, ranges, **keys) -> DataFrame:
    """The figures with their keys, in a row for each range; one without a point has n = 0."""
    rows = [(*k, *r) for *k, r in product(*keys.values(), ranges)]
    every = found.sparkSession.range(1).select(F.inline(F.array(*(F.struct(*(F.lit(v).alias(c) for c, v in zip((*keys, "lo", "hi"), x, strict=True))) for x in rows))))
    return every.join(found, [*keys, "lo", "hi"], "left").withColumn("n", F.coalesce("n", F.lit(0)))


def accuracy(grid, space: str, sizes, stride: int):
    """NRMSD of both services at all sizes, in whole numbers; and its SQL. A service's full scan is one reading of the cells for all sizes."""
    services = (("series", space, ["t"]), ("map", "t", list(space)))
    ranges = [(0, k) for k in sizes]

    def run(s, d) -> DataFrame:
        rows = []
        for service, over, keys in services:
            store = stored(s, d, grid, all_subsets(over), stride)
            brute = query.divided(baseline.scan_sums(store.cells, store.grid, "t", ranges, over), [*keys, "lo", "hi"], F.col("extent"))
            fast = measure.union(query.box_average(store, {"t": r}, over).select("*", F.lit(r[0]).alias("lo"), F.lit(r[1]).alias("hi")) for r in ranges)
            found = at_ranges(measure.nrmsd(brute, fast, [*keys, "lo", "hi"], by=["lo", "hi"]), ranges)
            rows.append(found.select(F.lit(service).alias("service"), F.col("hi").alias("size"), "unmatched", "n", "nrmsd", "max_abs", "max_rel"))
        return measure.union(rows)

    return run, " UNION ALL ".join(f"SELECT '{service}' AS service, {k} AS size, * FROM ({_ACCURATE.format(box_sql(grid, {'t': (0, k)}, over))})" for service, over, _ in services for k in sizes)


add("w05_accuracy_int", *accuracy(G1, "yx", SIZES_SHIP, 1))
add("w05_accuracy_int_g4", *accuracy(G4, "rc", SIZES_FIELD, 2))


#: What NRMSD stays within: doubles, single-precision values in double sums, and anchors kept in single precision.
WITHIN = {"double": 1e-12, "float": 1e-12, "float_anchors": 2e-7}


def float_figures(s, d) -> DataFrame:
    """NRMSD at all sizes, and of an unaligned map, on a dense field of doubles, of values kept in single precision, and with anchors kept in single precision."""
    store = stored(s, d, G4_FLOATS, [*all_subsets("rc"), ("t",)], 2)
    views = {}
    for kind in WITHIN:
        value = F.col("double" if kind == "double" else "float")
        tables = {x: t.select(*columns_of(store.grid, x), (value.cast("float") if kind == "float_anchors" else value).alias("sx"), "n") for x, t in store.tables.items()}
        views[kind] = replace(store, grid=replace(store.grid, measures=("sx", "n")), cells=store.cells.select(*store.grid.names, value.alias("sx"), "n"), tables=tables)
    rows = []
    for service, over, keys in (("series", "rc", ["t"]), ("map", "t", ["r", "c"])):
        ranges = [*((0, k) for k in SIZES_FIELD), *([(31, 700)] if service == "map" else [])]
        keys = [*keys, "lo", "hi", "kind"]
        sums = baseline.scan_sums(store.cells, store.grid, "t", ranges, over, store.grid.measures)
        of_kind = F.inline(F.array(*(F.struct(F.lit(kind).alias("kind"), F.col("double" if kind == "double" else "float").alias("sx")) for kind in WITHIN)))
        brute = query.divided(sums.select(*keys[:-1], "extent", "n", of_kind), keys, F.col("extent"))
        fast = measure.union(query.box_average(view, {"t": r}, over).select("*", F.lit(r[0]).alias("lo"), F.lit(r[1]).alias("hi"), F.lit(kind).alias("kind")) for kind, view in views.items() for r in ranges)
        found = at_ranges(measure.nrmsd(brute, fast, keys, by=["kind", "lo", "hi"]), ranges, kind=WITHIN)
        rows.append(found.select(F.lit(service).alias("service"), "kind", (F.col("hi") - F.col("lo")).alias("size"), "unmatched", "n", "nrmsd", "max_abs", "max_rel"))
    return measure.union(rows)


def accuracy_float(s, d) -> DataFrame:
    """Whether the figures are within their limits, at all sizes."""
    limit = F.create_map(*(F.lit(x) for kv in WITHIN.items() for x in kv))[F.col("kind")]
    return float_figures(s, d).select("service", "kind", "size", "unmatched", "n", (F.col("nrmsd") <= limit).alias("within"))


_FLOAT = " UNION ALL ".join(
    f"SELECT '{service}' AS service, '{kind}' AS kind, {size} AS size, CAST(0 AS BIGINT) AS unmatched, {k} AS n, TRUE AS within"
    for kind in WITHIN for service, n, sizes in (("series", "CAST({} AS BIGINT)", SIZES_FIELD), ("map", "(SELECT CAST(sum(len(embedding)) AS BIGINT) FROM embeddings WHERE vec_id IS NOT NULL)", (*SIZES_FIELD, 669))) for size in sizes for k in [n.format(size)]
)
add("w05_accuracy_float", accuracy_float, _FLOAT)
_SERVICES = [("r",), ("c",), ("t",), ("r", "c")]


def generation(s, d) -> DataFrame:
    store = store_of(s, d, G4, _SERVICES, 2)
    return measure.union(store.tables[x].agg(F.lit("_".join(x)).alias("subset"), F.count("*").alias("rows"), F.sum("sx").alias("total")) for x in _SERVICES)


add("w06_generation_counts", generation, " UNION ALL ".join(f"SELECT '{'_'.join(x)}' AS subset, count(*) AS rows, CAST(sum(sx) AS BIGINT) AS total FROM ({anchor_sql(G4, x, 2)})" for x in _SERVICES))
add("w07_overhead", lambda s, d: sweep(s, d, (2,)), _points_sql((2,)))
for _k, _box in ((1, {"y": (0, 33), "x": (0, 9)}), (2, {"y": (7, 33), "x": (0, 9)}), (4, REGION)):
    add_box(f"w08_region_{_k}", G1, _box, "yx", stride=2, mode="nearest")
add_box("w08_region_field", G4, {"r": (13, 487), "c": (5, 59)}, "rc", stride=1, mode="nearest")
add_box("w09_map_interval", G1, PERIOD, "t", mode="nearest")
add_box("w09_map_activity", G2, {"t": (31, 700)}, "t", mode="nearest")
PLANE4 = G3.with_tiles(r=10, c=4)
ENDS = ((105, 9), (155, 62))


def stride4(s, d) -> DataFrame:
    store = stored(s, d, PLANE4, all_subsets("rc"), 4)
    return measure.union(query.box_average(store, {"r": (0, r), "c": (0, c)}, "rc", m).select(F.lit(m).alias("mode"), F.lit(r).alias("r_end"), F.lit(c).alias("c_end"), "s", "n") for r, c in ENDS for m in ("floor", "nearest"))


add("w10_stride4_modes", stride4, " UNION ALL ".join(f"SELECT '{m}' AS mode, {r} AS r_end, {c} AS c_end, s, n FROM ({box_sql(PLANE4, {'r': (0, r), 'c': (0, c)}, 'rc')})" for r, c in ENDS for m in ("floor", "nearest")))


def stride4_reads(s, d) -> DataFrame:
    """What the plans expect to read, and the cells that they find in the gaps."""
    store, rows = store_of(s, d, PLANE4, all_subsets("rc"), 4), []
    for r, c in ENDS:
        for m in ("floor", "nearest"):
            plan = plan_box(store.grid, store.specs, {"r": (0, r), "c": (0, c)}, "rc", m)
            told = zip(("mode", "r_end", "c_end", "scans", "anchor_rows", "gap_cells", "reads"), (m, r, c, *measure.reads_row(plan)), strict=True)
            rows.append(measure.union(query.scan_term(store, t, ["n"]) for t in plan.scans if not t.subset).agg(*(F.lit(v).alias(k) for k, v in told), F.count("*").alias("gap_found")))
    return measure.union(rows)


# by hand: steps 40 and 16; from below 25 x 9 cells and 35 x 14, from above 15 x 7 and 5 x 2
add("w10_stride4_reads", stride4_reads, f"SELECT v.*, (SELECT count(*) FROM ({PLANE4.sql}) WHERE r >= r_lo AND r < r_hi AND c >= c_lo AND c < c_hi) AS gap_found FROM (VALUES ('floor', 105, 9, 2, 9, 225, 234), ('nearest', 105, 9, 4, 23, 105, 128), ('floor', 155, 62, 4, 50, 490, 540), ('nearest', 155, 62, 4, 8, 10, 18)) v(mode, r_end, c_end, scans, anchor_rows, gap_cells, reads) JOIN (VALUES ('floor', 105, 80, 105, 0, 9), ('nearest', 105, 105, 120, 9, 16), ('floor', 155, 120, 155, 48, 62), ('nearest', 155, 155, 160, 62, 64)) g(m, e, r_lo, r_hi, c_lo, c_hi) ON m = mode AND e = r_end")
add("w11_full_cumulation", lambda s, d: baseline.full_prefix_average(baseline.build_full_prefix(G1.cells(s, d), G1.spec, "yx"), G1.spec, {"y": (3, 41), "x": (1, 10)}, "yx"), box_sql(G1, {"y": (3, 41), "x": (1, 10)}, "yx"))
add("w12_line", lambda s, d: baseline.range_average(G6.cells(s, d), "d", 1, 4), "SELECT CAST(sum(n_chars) AS BIGINT) AS s, CAST(sum(n_chars) AS DOUBLE) / 3 AS avg FROM documents WHERE doc_id >= 1 AND doc_id < 4")
add_box("w12_line_anchors", G6, LINE, "d")
_WEIGHTED = [("y",), ("x",), ("t",), ("y", "x")]
_SHORT = BOX | {"t": (123, 301)}


def weighted_catalog(s, d) -> DataFrame:
    """Every service through a catalog that lacks {y, t}, {x, t} and {y, x, t}."""
    store = stored(s, d, G1_MORE, _WEIGHTED)
    total = lambda over: query.box_average(store, _SHORT, over, divisor="weight").agg(F.sum("s").alias("s"), F.sum("n").alias("n"), F.count("*").alias("points")).select(F.lit(over).alias("service"), "*")
    return measure.union(total(o) for o in ("y", "x", "t", "yx", "yt", "xt", "yxt"))


add("w13_weighted_catalog", weighted_catalog, " UNION ALL ".join(f"SELECT '{o}' AS service, CAST(sum(s) AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n, count(*) AS points FROM ({box_sql(G1_MORE, _SHORT, o, 'weight')})" for o in ("y", "x", "t", "yx", "yt", "xt", "yxt")))
add_box("w14_stride_002", G1, PERIOD, "t", stride={"t": 2}, mode="nearest")
add_box("w14_stride_130", FINE, REGION, "yx", stride={"y": 1, "x": 3}, mode="nearest")
add_box("w14_stride_130_field", G4, {"r": (13, 487), "c": (5, 59), "t": (31, 700)}, "rc", stride={"r": 1, "c": 3}, mode="best")


def stride_lookup(s, d) -> DataFrame:
    """The strides of a table, and how many steps of theirs have cells."""
    c = example_catalog()
    stride = c.stride(("x", "y"))
    step = lambda a, k: F.floor(F.col(a) / (G1.spec[a].tile * k))
    return measure.union(G1.cells(s, d).agg(F.lit(c.find(("x", "y"), "weighted")).alias("path"), F.lit(a).alias("axis"), F.lit(k).alias("stride"), F.countDistinct(step(a, k)).alias("steps")) for a, k in stride.items())


add("w15_lookup", stride_lookup, f"WITH cells AS ({G1.sql}) SELECT 'acc_weighted_y_x' AS path, a AS axis, k AS stride, CASE a WHEN 'y' THEN (SELECT count(DISTINCT y // 10) FROM cells) ELSE (SELECT count(DISTINCT x // 12) FROM cells) END AS steps FROM (VALUES ('y', 1), ('x', 3)) v(a, k)")


def all_seven(s, d) -> DataFrame:
    store = store_of(s, d, G1, all_subsets("yxt"))
    return measure.union(t.agg(F.lit("_".join(x)).alias("subset"), F.count("*").alias("rows"), F.sum("sx").alias("total")) for x, t in store.tables.items())


add("w16_all_subsets", all_seven, " UNION ALL ".join(f"SELECT '{'_'.join(x)}' AS subset, count(*) AS rows, CAST(sum(sx) AS BIGINT) AS total FROM ({anchor_sql(G1, x)})" for x in all_subsets("yxt")))


def mix(s, d) -> DataFrame:
    """Mostly series and maps: by the last digit of its id, each box asks for one service; totals of each box."""
    store = stored(s, d, G1, all_subsets("yx") + [("t",)])
    wanted = boxes(s, 1000)
    series = query.box_average_many(store, wanted.where("box_id % 10 < 4"), "yx").groupBy("box_id").agg(F.sum("s").alias("s"), F.sum("n").alias("n"), F.count("*").alias("points"))
    maps = query.box_average_many(store, wanted.where("box_id % 10 >= 4 and box_id % 10 < 8"), "t").groupBy("box_id").agg(F.sum("s").alias("s"), F.sum("n").alias("n"), F.count("*").alias("points"))
    zonal = query.box_average_many(store, wanted.where("box_id % 10 >= 8"), "x").groupBy("box_id").agg(F.sum("s").alias("s"), F.sum("n").alias("n"), F.count("*").alias("points"))
    return measure.union([series, maps, zonal])


add("w17_mix", mix, " UNION ALL ".join(f"SELECT box_id, CAST(sum(s) AS BIGINT) AS s, CAST(sum(n) AS BIGINT) AS n, count(*) AS points FROM ({many_sql(o, 1000, w)}) GROUP BY box_id" for o, w in (("yx", "box_id % 10 < 4"), ("t", "box_id % 10 >= 4 AND box_id % 10 < 8"), ("x", "box_id % 10 >= 8"))))
for _name, _grid, _box, _over in (
    ("activity", G2, {"u": (3, 101), "t": (31, 700)}, "ut"), ("kind", G2B, {"t": (5, 611)}, "t"), ("plane", G3, {"r": (13, 487), "c": (5, 59)}, "r"), ("orders", G5, {"nation": (3, 19), "t": (77, 2222)}, ("nation", "t")),
    ("line", G6, LINE, "d"), ("four", G7, BOX | {"z": (2, 7)}, "yxz"), ("part", G8, {"z": (4, 37), "b": (3, 22)}, "b"), ("talk", G9, {"k": (7, 91), "turn": (1, 7)}, ("k",)), ("balance", G10, {"nation": (2, 23), "m": (0, 4)}, ("nation", "m")),
):
    add_box(f"w18_{_name}", _grid, _box, _over)
add_box("w20_box3d", G1, BOX, "yxt", mode="nearest")
add("w20_filter_and_sum", lambda s, d: baseline.scan_average(G1.cells(s, d), G1.spec, BOX, "yxt"), box_sql(G1, BOX, "yxt"))
