import random

import pytest
from pyspark.sql import functions as F

from boxsum.functions import measure
from boxsum.operators import baseline, build, query
from boxsum.operators.build import AnchorStore, accumulate
from boxsum.plans.box import plan_box
from boxsum.plans.spec import AnchorSpec, AxisSpec, GridSpec, SpecError
from boxsum.sources import io
from boxsum.streaming.upkeep import append_slices, repair_late
from boxsum.workloads.cases import all_subsets

CUBE = GridSpec("cube", (AxisSpec("a", 7, 2), AxisSpec("b", 8, 3), AxisSpec("c", 11, 2)))


@pytest.fixture(scope="module")
def cube(spark):
    r = random.Random(5)
    rows = [(i, j, k, r.randint(-50, 99), 1) for i in range(7) for j in range(8) for k in range(11) if r.random() < 0.7]
    return spark.createDataFrame(rows, "a int, b int, c int, sx long, n long").repartition(3).cache(), rows


def brute(rows, box, over):
    out = {}
    bounds = {x.name: box.get(x.name, (0, x.n)) for x in CUBE.axes}
    for *at, v, n in rows:
        if all(lo <= i < hi for i, (lo, hi) in zip(at, bounds.values(), strict=True)):
            key = tuple(i for i, name in zip(at, CUBE.names, strict=True) if name not in over)
            s, k = out.get(key, (0, 0))
            out[key] = (s + v, k + n)
    return out


def got(df, over):
    keys = [x for x in CUBE.names if x not in over]
    return {tuple(r[k] for k in keys): (r["sx"], r["n"]) for r in df.collect()}


@pytest.mark.parametrize("stride", [1, 2, {"a": 1, "b": 2, "c": 3}, {("a",): {"a": 2}, ("b",): {"b": 1}, ("a", "b"): {"a": 1, "b": 2}}])
def test_random_boxes_in_both_modes(spark, cube, stride):
    cells, rows = cube
    store = AnchorStore.build(cells, CUBE, all_subsets("abc"), stride)
    store.tables = {s: t.cache() for s, t in store.tables.items()}
    r = random.Random(7)
    for k in range(10):
        over = r.choice(all_subsets("abc"))
        box = {}
        for x in CUBE.axes:
            lo = r.choice([0, r.randrange(x.n)])
            box[x.name] = (lo, r.choice([x.n, r.randint(lo + 1, x.n)]))
        assert got(query.box_sum(store, box, over, ("floor", "nearest")[k % 2]), over) == brute(rows, box, over), (box, over)


def test_worked_grid_of_six_by_six(spark):
    grid = GridSpec("six", (AxisSpec("i", 6, 2), AxisSpec("j", 6, 3)))
    cells = spark.range(36).select(F.expr("int(id div 6) as i"), F.expr("int(id % 6) as j"), F.col("id").alias("sx"), F.lit(1).cast("long").alias("n"))
    store = AnchorStore.build(cells, grid, all_subsets("ij"))
    box = {"i": (1, 5), "j": (2, 6)}
    plan = plan_box(grid, store.specs, box, "ij")
    terms = {t.subset: query.scan_term(store, t, ["sx"]).agg(F.sum("sx")).first()[0] for t in plan.scans}
    assert terms == {("i", "j"): 276, ("i",): -76, ("j",): 144, (): -48}
    row = query.box_average(store, box, "ij").first()
    assert (row.s, row.n, row.avg) == (296, 16, 18.5)


def test_four_values(spark):
    cells = spark.createDataFrame([(0, 4), (1, 7), (2, 1), (3, 10)], "d int, sx long")
    row = baseline.range_average(cells, "d", 1, 4).first()
    assert (row.s, row.avg) == (18, 6.0)
    assert baseline.range_average(cells, "d", 0, 2).first().s == 11


def test_carried_and_sparse_anchors_over_empty_tiles(spark, monkeypatch):
    cells = spark.createDataFrame([(i, v, 1) for i, v in enumerate([3, 1, 4, 1, None, None, 2, 6, 5, 3]) if v is not None], "d int, sx long, n long")
    monkeypatch.setattr(build, "BLOCK", 2)
    rows = {r.q_d: r.sx for r in accumulate(cells, [], "d", 2, 10, {"sx": "sum"}).collect()}
    assert rows == {1: 4, 2: 9, 3: 9, 4: 17, 5: 25}
    sparse = accumulate(cells, [], "d", 2, 10, {"sx": "sum"}, "sparse")
    assert {r.q_d for r in sparse.collect()} == {1, 2, 4, 5}
    assert build.lookup_sparse(sparse, "d", 3, ["sx"]).first().sx == 9
    assert {r.q_d: r.sx for r in accumulate(cells, [], "d", 4, 10, {"sx": "sum"}).collect()} == {1: 9, 2: 17}  # ragged end
    assert accumulate(cells, [], "d", 40, 10, {"sx": "sum"}).count() == 0
    assert accumulate(cells.limit(0), [], "d", 2, 10, {"sx": "sum"}).count() == 0


def test_reused_and_direct_tables_are_equal(cube):
    cells, _ = cube
    reused, direct = (AnchorStore.build(cells, CUBE, all_subsets("abc"), 1, r) for r in (True, False))
    for s in reused.tables:
        assert sorted(map(tuple, reused.tables[s].collect())) == sorted(map(tuple, direct.tables[s].collect()))


def test_dense_tables_have_as_many_rows_as_counted(spark):
    cells = spark.range(7 * 8 * 11).select(F.expr("int(id div 88) as a"), F.expr("int(id div 11 % 8) as b"), F.expr("int(id % 11) as c"), F.lit(1).cast("long").alias("sx"), F.lit(1).cast("long").alias("n"))
    for stride in (1, 2):
        store = AnchorStore.build(cells, CUBE, all_subsets("abc"), stride)
        want = {"_".join(s): t.count() for s, t in store.tables.items()}
        assert {r.subset: r.points for r in measure.overhead(store).collect()} == want


def test_patched_tile_sums_to_every_prefix(spark, cube):
    cells, rows = cube
    store = AnchorStore.build(cells, CUBE, all_subsets("ab"), 2)
    for tile in ({"a": 1, "b": 1, "c": 2}, {"a": 0, "b": 1, "c": 0}):
        patched = query.patched_tile(store, tile, "ab").collect()
        first = {"a": tile["a"] * 4, "b": tile["b"] * 6}
        for a in range(first["a"], min(first["a"] + 4, 7)):
            for b in range(first["b"], min(first["b"] + 6, 8)):
                for c in {x.c for x in patched}:
                    s = sum(x.value for x in patched if x.a <= a and x.b <= b and x.c == c)
                    assert s == sum(v for i, j, k, v, _ in rows if i <= a and j <= b and k == c)
        assert {tuple(x.role) for x in patched} == {(), ("a",), ("b",), ("a", "b")}


@pytest.mark.parametrize("stride", [1, {("a",): {"a": 2}, ("b",): {"b": 1}, ("a", "b"): {"a": 3, "b": 2}}, {("a",): {"a": 2}, ("c",): {"c": 3}}])
def test_patched_tiles_of_any_catalog(spark, stride):
    grid = GridSpec("p", (AxisSpec("a", 14, 1), AxisSpec("b", 8, 2), AxisSpec("c", 9, 1)))
    r = random.Random(9)
    rows = [(i, j, k, r.randint(-9, 9), 1) for i in range(14) for j in range(8) for k in range(9) if r.random() < 0.5 and i > 2]
    cells = spark.createDataFrame(rows, "a int, b int, c int, sx long, n long").cache()
    subsets = all_subsets("ab") if stride == 1 else list(stride)
    store = AnchorStore.build(cells, grid, subsets, stride)
    steps = {"a": 1, "b": 2, "c": 1} if stride == 1 else {"a": 6, "b": 4, "c": 1} if ("a", "b") in stride else {"a": 2, "b": 2, "c": 1}
    over = set("ab") if ("a", "b") in store.specs else {"a"}
    for tile in ({"a": 1, "b": 1, "c": 2}, {"a": 2, "b": 0, "c": 0}, {"a": 0, "b": 0, "c": 8}):
        if any(tile[x] * steps[x] >= grid[x].n for x in "abc"):
            with pytest.raises(SpecError):
                query.patched_tile(store, tile, "ab")
            continue
        got = query.patched_tile(store, tile, "ab").collect()
        first = {x: tile[x] * steps[x] for x in "abc"}
        for end in ({x: min(first[x] + steps[x], grid[x].n) - 1 for x in "abc"}, {"a": first["a"], "b": first["b"], "c": first["c"]}):
            s = sum(x.value for x in got if x.a <= end["a"] and x.b <= end["b"] and x.c <= end["c"])
            assert s == sum(v for i, j, k, v, _ in rows if all((x in over or first[x] <= at) and at <= end[x] for x, at in zip("abc", (i, j, k), strict=True))), (tile, end)


def test_patched_tiles_of_empty_tables(spark, cube):
    cells, rows = cube
    nothing = AnchorStore.build(cells, CUBE, [])
    assert sum(x.value for x in query.patched_tile(nothing, {"a": 0, "b": 0, "c": 0}, "abc").collect()) == sum(v for i, j, k, v, _ in rows if i < 2 and j < 3 and k < 2)
    late = cells.where("a >= 6 and b >= 6 and c >= 10")
    store = AnchorStore.build(late, CUBE, all_subsets("abc"))
    got = query.patched_tile(store, {"a": 1, "b": 1, "c": 1}, "abc")
    assert got.count() == 2 * 3 * 2 and {x.value for x in got.collect()} == {0}


def test_append_and_repair_equal_a_rebuild(cube):
    cells, _ = cube
    whole = AnchorStore.build(cells, CUBE, all_subsets("abc"))
    short = GridSpec("cube", (*CUBE.axes[:2], AxisSpec("c", 7, 2)))
    longer = append_slices(AnchorStore.build(cells.where("c < 7"), short, all_subsets("abc")), cells.where("c >= 7"), 11, "c")
    late = (F.col("a") + F.col("c")) % 4 == 1
    repaired = repair_late(AnchorStore.build(cells.where(~late), CUBE, all_subsets("abc")), cells.where(late))
    alone = append_slices(AnchorStore.build(cells.where("c < 7"), short, [("b", "c")]), cells.where("c >= 7"), 11, "c")
    rows = lambda t: sorted(map(tuple, t.select(sorted(t.columns)).collect()))
    for s, t in whole.tables.items():
        assert rows(longer.tables[s]) == rows(t) == rows(repaired.tables[s])
    assert rows(alone.tables["b", "c"]) == rows(whole.tables["b", "c"])


def test_weights_missing_cells_and_empty_lines(spark):
    grid = GridSpec("w", (AxisSpec("d", 10, 3), AxisSpec("t", 4, 2)), ("sx", "n", "sw", "swx", "p"))
    rows = [(0, 0, 5, 1, 2), (1, 0, 7, 1, 0), (4, 2, 9, 1, 3), (5, 3, 4, 1, 0)]
    cells = spark.createDataFrame([(d, t, x, n, w, w * x, 1) for d, t, x, n, w in rows], "d int, t int, sx long, n long, sw long, swx long, p long")
    store = AnchorStore.build(cells, grid, [("d",)])
    out = {r.t: (r.s, r.avg) for r in query.box_average(store, {"d": (0, 6)}, "d", divisor="weight").collect()}
    assert out == {0: (10, 5.0), 2: (27, 9.0), 3: (0, None)}
    present = {r.t: r.avg for r in query.box_average(store, {"d": (0, 6)}, "d", divisor="present").collect()}
    assert present == {0: 6.0, 2: 9.0, 3: 4.0}
    full = {r.t: (r.s, r.avg) for r in query.box_average(store, {"d": (0, 6)}, "d", complete=True).collect()}
    assert full == {0: (12, 2.0), 1: (0, None), 2: (9, 1.5), 3: (4, 4 / 6)}


def brute_ends(rows, axis, lo, hi):
    out = {}
    for *at, v, _ in rows:
        i = CUBE.names.index(axis)
        if lo <= at[i] < hi:
            key = tuple(x for k, x in enumerate(at) if k != i)
            mn, mx = out.get(key, (v, v))
            out[key] = (min(mn, v), max(mx, v))
    return out


def ends(df, axis):
    return {tuple(r[a] for a in CUBE.names if a != axis): (r.mn, r.mx) for r in df.collect()}


def test_stored_extrema(spark, cube, tmp_path):
    cells, rows = cube
    for method in ("tiles", "prefix", "blocks"):
        io.write_extrema(cells, CUBE, f"file://{tmp_path}", "c", method)
        table = io.read_extrema(spark, CUBE, f"file://{tmp_path}", "c", method)
        assert ends(query.box_extrema(cells, CUBE, {"c": (0, 9)}, "c", method, table), "c") == brute_ends(rows, "c", 0, 9)
    # a run of tiles is two rows a line, however long
    blocks = io.read_extrema(spark, CUBE, f"file://{tmp_path}", "c", "blocks")
    assert blocks.where("level = 2 and tile_c in (0, 1)").groupBy("a", "b").count().agg(F.max("count")).first()[0] == 2
    with pytest.raises(SpecError):
        io.read_extrema(spark, GridSpec("cube", (*CUBE.axes[:2], AxisSpec("c", 11, 3))), f"file://{tmp_path}", "c", "blocks")
    with pytest.raises(SpecError):
        query.build_extrema(cells, CUBE, "ab", "blocks")


def test_variance_of_very_many_cells(spark):
    grid = GridSpec("v", (AxisSpec("d", 4, 2),), ("sx", "n", "p", "sxx"))
    # 10^11 cells that are 3 and as many that are 5; then numbers beyond 38 digits
    for k, tell in ((10**11, 1.0), (10**17, 1.0)):
        cells = spark.createDataFrame([(0, 3 * k, k, k, str(9 * k)), (1, 5 * k, k, k, str(25 * k))], "d int, sx long, n long, p long, sxx string").withColumn("sxx", F.col("sxx").cast("decimal(38,0)"))
        row = query.box_moments(AnchorStore.build(cells, grid, [("d",)]), {"d": (0, 2)}, "d").first()
        assert (row.p, row.mean, row.variance) == (2 * k, 4.0, tell)
    big = spark.createDataFrame([(0, 10**9, 10**9, 10**9, str(10**36))], "d int, sx long, n long, p long, sxx string").withColumn("sxx", F.col("sxx").cast("decimal(38,0)"))
    row = query.box_moments(AnchorStore.build(big, grid, [("d",)]), {"d": (0, 1)}, "d").first()
    assert row.variance == pytest.approx(1e27)


def test_moments_and_extrema(spark, cube):
    cells, rows = cube
    wide = GridSpec("cube", CUBE.axes, ("sx", "n", "p", "sxx"))
    more = cells.withColumn("p", F.lit(1).cast("long")).withColumn("sxx", (F.col("sx") * F.col("sx")).cast("decimal(38,0)"))
    box, over = {"a": (1, 6), "b": (2, 7)}, "ab"
    values = {}
    for i, j, k, v, _ in rows:
        if 1 <= i < 6 and 2 <= j < 7:
            values.setdefault(k, []).append(v)
    store = AnchorStore.build(more, wide, all_subsets(over))
    for r in query.box_moments(store, box, over).collect():
        m = sum(values[r.c]) / len(values[r.c])
        assert r.mean == pytest.approx(m) and r.variance == pytest.approx(sum((v - m) ** 2 for v in values[r.c]) / len(values[r.c]))
    assert {r.c: (r.mn, r.mx) for r in query.box_extrema(cells, CUBE, box, over).collect()} == {k: (min(v), max(v)) for k, v in values.items()}
    blocks = {(r.b, r.c): (r.mn, r.mx) for r in query.box_extrema(cells, CUBE, {"a": (1, 6)}, "a", "blocks").collect()}
    tiles = {(r.b, r.c): (r.mn, r.mx) for r in query.box_extrema(cells, CUBE, {"a": (1, 6)}, "a").collect()}
    assert blocks == tiles
    for a, size in (("a", 7), ("b", 8), ("c", 11)):
        for lo, hi in ((0, size), (1, size), (0, size - 1), (2, 4), (3, 5), (1, 2), (0, 1)):
            want = brute_ends(rows, a, lo, hi)
            for method in ("tiles", "blocks", *(["prefix"] if lo == 0 else [])):
                assert ends(query.box_extrema(cells, CUBE, {a: (lo, hi)}, a, method), a) == want, (a, lo, hi, method)
    with pytest.raises(SpecError):
        query.box_extrema(cells, CUBE, {"a": (1, 6)}, "a", "prefix")
    with pytest.raises(SpecError):
        query.box_extrema(cells, CUBE, box, over, "blocks")


def test_stored_tables_answer_with_pushed_filters(spark, cube, tmp_path):
    cells, rows = cube
    root = f"file://{tmp_path}/store"
    store = AnchorStore.build(cells, CUBE, all_subsets("ab"))
    catalog = io.write_store(store, root)
    again = io.read_store(spark, root)
    assert catalog.rows() and again.specs == store.specs
    assert {s: e["rows"] for s, e in catalog.entries.items()} == {s: t.count() for s, t in store.tables.items()}
    assert all(sorted(map(tuple, again.tables[s].select(t.columns).collect())) == sorted(map(tuple, t.collect())) for s, t in store.tables.items())
    box = {"a": (1, 6), "b": (2, 7), "c": (3, 9)}
    out = query.box_sum(again, box, "ab")
    assert got(out, "ab") == brute(rows, box, "ab")
    plan = out._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert "q_a" in plan and "PushedFilters: [In" in plan or "EqualTo(q_a" in plan
    assert "ReadSchema" in plan and "CartesianProduct" not in plan


def test_groups_of_weighted_arrays_and_weights(spark, tmp_path):
    grid = GridSpec("w", (AxisSpec("latitude", 10, 3), AxisSpec("longitude", 6, 2), AxisSpec("time", 4, 2)), ("sx", "n", "sw", "swx"))
    r = random.Random(3)
    rows = [(i, j, k, r.randint(-9, 9), 1, r.randint(0, 3)) for i in range(10) for j in range(6) for k in range(4) if r.random() < 0.8]
    cells = spark.createDataFrame([(i, j, k, v, n, w, w * v) for i, j, k, v, n, w in rows], "latitude int, longitude int, time int, sx long, n long, sw long, swx long")
    root = f"file://{tmp_path}/w"
    services = [("latitude",), ("longitude",), ("time",), ("latitude", "longitude")]
    io.write_store(AnchorStore.build(cells, grid, services, {("latitude",): {"latitude": 1}, ("latitude", "longitude"): {"latitude": 1, "longitude": 3}}), root, ("weighted", "weight"))
    tree = io.read_json(spark, f"{root}/{io.GROUP_FOLDER}/attributes")["_ACCUMULATION_GROUP"]
    assert tree["latitude"]["longitude"] == {"_DATA_WEIGHTED": "acc_weighted_latitude_longitude", "_WEIGHTS": "acc_wt_latitude_longitude", "time": {}} and tree["longitude"]["time"] == {}
    both = io.read_json(spark, f"{root}/{io.GROUP_FOLDER}/acc_wt_latitude_longitude/attributes")
    assert both == {"_ARRAY_DIMENSIONS": ["latitude", "longitude", "time"], "_ACCUMULATION_STRIDE": [1, 3, 0]}
    assert set(spark.read.parquet(f"{root}/{io.GROUP_FOLDER}/acc_wt_time/data").columns) == {"q_time", "latitude", "longitude", "sw"}
    store = io.read_store(spark, root)
    assert set(store.specs) == set(services) and store.in_parts
    for over, box in ((("latitude", "longitude"), {"latitude": (1, 8), "longitude": (2, 6)}), (("time",), {"time": (0, 2)}), (("time",), {"time": (1, 4)})):
        got = {tuple(x[a] for a in grid.names if a not in over): (x.s, x.avg) for x in query.box_average(store, box, over, divisor="weight").collect()}
        want = {}
        for i, j, k, v, _, w in rows:
            at = dict(zip(grid.names, (i, j, k), strict=True))
            if all(lo <= at[a] < hi for a, (lo, hi) in box.items()):
                s, t = want.get(key := tuple(at[a] for a in grid.names if a not in over), (0, 0))
                want[key] = (s + w * v, t + w)
        assert got == {key: (s, s / t if t else None) for key, (s, t) in want.items()}
    with pytest.raises(SpecError):
        io.write_store(AnchorStore.build(cells.drop("sw", "swx"), GridSpec("w", grid.axes), services), root, ("weighted",))


def test_boxes_that_end_on_anchors_need_no_shuffle(spark, cube, tmp_path):
    cells, rows = cube
    io.write_store(AnchorStore.build(cells, CUBE, all_subsets("ab")), f"file://{tmp_path}/s")
    store = io.read_store(spark, f"file://{tmp_path}/s")
    box = {"a": (0, 6), "b": (0, 3)}
    out = query.box_sum(store, box, "ab")
    assert got(out, "ab") == brute(rows, box, "ab")
    assert "Exchange" not in out._jdf.queryExecution().executedPlan().toString()


def test_accuracy_measure(spark):
    a = spark.createDataFrame([(1, 1.0), (2, 3.0), (3, 5.0)], "k int, avg double")
    b = spark.createDataFrame([(1, 1.0), (2, 3.5), (4, 5.0)], "k int, avg double")
    row = measure.nrmsd(a, b, ["k"]).first()
    assert row.unmatched == 2 and row.max_abs == 0.5 and row.nrmsd == pytest.approx((0.25 / 2) ** 0.5 / 4)
    flat = spark.createDataFrame([(1, 2.0), (2, 2.0)], "k int, avg double")
    assert measure.nrmsd(flat, flat, ["k"]).first().nrmsd is None
    assert measure.speedup(100.0, 0.1) == pytest.approx((1000, 3)) and measure.price(3600, 4.032) == pytest.approx(4.032)


def test_touched_counts_tiles_and_anchor_rows(spark, cube):
    cells, rows = cube
    store = AnchorStore.build(cells, CUBE, all_subsets("ab"))
    found = lambda box: measure.touched(store, plan_box(CUBE, store.specs, box, "ab")).first().asDict()
    # a: anchor 2 (below 4), gaps [4, 5) and [0, 1); b: anchor 2 (below 6), gaps [6, 7) and [0, 2); 11 slices of 6 tiles
    in_a, in_b = (0, 4), (0, 1, 6)
    tiles = {(i // 2, j // 3, k // 2) for i, j, k, *_ in rows if i in in_a and j in in_b}
    anchors = len({(j, k) for i, j, k, *_ in rows if i < 4 and j in in_b}) + len({(i, k) for i, j, k, *_ in rows if i in in_a and j < 6}) + len({k for i, j, k, *_ in rows if i < 4 and j < 6})
    planned = (1 * 3 + 2 * 1 + 1) * 11
    assert found({"a": (1, 5), "b": (2, 7)}) == {"tiles": 24, "found": len(tiles), "anchor_rows": planned, "anchor_rows_found": anchors, "touched": 24 + planned, "touched_found": len(tiles) + anchors}
    # a box that ends on anchors touches no cells
    slices = len({k for i, j, k, *_ in rows if i < 4 and j < 6})
    assert found({"a": (0, 4), "b": (0, 6)}) == {"tiles": 0, "found": 0, "anchor_rows": 11, "anchor_rows_found": slices, "touched": 11, "touched_found": slices}


def test_overflow_is_told(spark):
    big = spark.createDataFrame([(0, 2**62, 1), (1, 2**62, 1)], "d int, sx long, n long")
    grid = GridSpec("o", (AxisSpec("d", 2, 2),))
    with pytest.raises(Exception, match="OVERFLOW"):  # several tasks failing at once come as another class
        AnchorStore.build(big, grid, [("d",)]).tables["d",].collect()
    wide = AnchorStore.build(big.withColumn("sx", F.col("sx").cast("decimal(38,0)")), grid, [("d",)]).tables["d",]
    assert wide.first().sx == 2**63
    assert big.agg(F.try_sum("sx")).first()[0] is None


def test_dense_and_long_lines(spark, monkeypatch):
    r = random.Random(2)
    rows = [(k, i, r.randint(-9, 9), 1) for k in range(3) for i in range(40) if r.random() < 0.3 and i > 6 * k]
    cells = spark.createDataFrame(rows, "k int, d int, sx long, n long")
    for block in (1 << 16, 4):
        monkeypatch.setattr(build, "BLOCK", block)
        dense = {(x.k, x.q_d): x.sx for x in accumulate(cells, ["k"], "d", 3, 40, {"sx": "sum"}, "dense").collect()}
        assert dense == {(k, q): sum(v for a, i, v, _ in rows if a == k and i < 3 * q) for k in {x[0] for x in rows} for q in range(1, 14)}
        carried = {(x.k, x.q_d): x.sx for x in accumulate(cells, ["k"], "d", 3, 40, {"sx": "sum"}).collect()}
        assert carried.items() <= dense.items() and all(v == 0 for k, v in dense.items() if k not in carried)
    alone = {x.q_d: x.sx for x in accumulate(cells.where("k = 1").drop("k"), [], "d", 3, 40, {"sx": "sum"}, "dense").collect()}
    assert alone == {q: v for (k, q), v in dense.items() if k == 1}
    assert accumulate(cells.limit(0), ["k"], "d", 3, 40, {"sx": "sum"}, "dense").count() == 0


def test_plans_by_cost_and_mode(spark, cube):
    cells, rows = cube
    store = AnchorStore.build(cells, CUBE, all_subsets("abc"))
    box = {"a": (1, 6), "b": (2, 7), "c": (3, 10)}
    best = plan_box(CUBE, store.specs, box, "abc", "best").reads()
    assert best == min(plan_box(CUBE, store.specs, box, "abc", m).reads() for m in ("floor", "nearest"))
    assert got(query.box_sum(store, box, "abc", "best"), "abc") == brute(rows, box, "abc")
    store.scan_cost = 10**6
    assert len(query.plan_of(store, box, "abc").scans) == 1 and got(query.box_sum(store, box, "abc"), "abc") == brute(rows, box, "abc")


def test_many_boxes_by_modes_and_partial_catalogs(spark, cube):
    cells, rows = cube
    r = random.Random(1)
    made = []
    for k in range(12):
        lows = {x.name: r.randrange(x.n) for x in CUBE.axes}
        made.append((k, *(v for x in CUBE.axes for v in (lows[x.name], r.randint(lows[x.name] + 1, x.n)))))
    boxes = spark.createDataFrame(made, "box_id long, a_lo int, a_hi int, b_lo int, b_hi int, c_lo int, c_hi int")
    full = AnchorStore.build(cells, CUBE, all_subsets("abc"), {"a": 1, "b": 2, "c": 2})
    for store, over, mode in ((full, "abc", "nearest"), (full.without("abc", "bc"), "abc", "floor"), (full.without("ab"), "ab", "nearest")):
        out = {}
        for x in query.box_average_many(store, boxes, over, mode=mode).collect():
            out.setdefault(x.box_id, {})[tuple(x[a] for a in CUBE.names if a not in over)] = (x.s, x.n)
        for k, *b in made:
            assert out.get(k, {}) == brute(rows, {x: (b[2 * i], b[2 * i + 1]) for i, x in enumerate("abc")}, over)


def test_many_boxes_need_a_table(spark, cube):
    cells, rows = cube
    store = AnchorStore.build(cells, CUBE, all_subsets("ab"))
    boxes = spark.createDataFrame([(1, 1, 6, 2, 7, 3, 9), (2, 0, 7, 0, 8, 0, 11), (3, 2, 3, 4, 5, 0, 2)], "box_id long, a_lo int, a_hi int, b_lo int, b_hi int, c_lo int, c_hi int")
    out = {}
    for r in query.box_average_many(store, boxes, "ab").collect():
        out.setdefault(r.box_id, {})[r.c,] = (r.s, r.n)
    for b in boxes.collect():
        assert out.get(b.box_id, {}) == brute(rows, {x: (b[f"{x}_lo"], b[f"{x}_hi"]) for x in "abc"}, "ab")
    with pytest.raises(SpecError):
        query.box_average_many(store.without("a", "b", "ab"), boxes, "ab")
    assert AnchorSpec.uniform(CUBE, "ab").subset == ("a", "b")
