import json

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from boxsum.plans.box import pieces, plan_box, split_endpoint
from boxsum.plans.spec import DIMENSIONS, STRIDE, AnchorCatalog, AnchorSpec, AxisSpec, GridSpec, SpecError, common_step, subsets_for, validate

GRID = GridSpec("g", (AxisSpec("latitude", 12, 2), AxisSpec("longitude", 18, 3), AxisSpec("time", 20, 5)))


@given(st.integers(1, 60), st.integers(1, 9), st.sampled_from(["floor", "nearest"]), st.data())
@settings(max_examples=300, deadline=None)
def test_pieces_add_up_to_the_range(n, step, mode, data):
    lo = data.draw(st.integers(0, n - 1))
    hi = data.draw(st.integers(lo + 1, n))
    found = pieces(lo, hi, step, n, mode)
    weight = [0] * n
    for q, sign in found.anchors:
        assert 1 <= q <= n // step
        for i in range(q * step):
            weight[i] += sign
    for a, b, sign in found.gaps:
        for i in range(a, b):
            weight[i] += sign
    assert weight == [int(lo <= i < hi) for i in range(n)]


def test_endpoint_cases():
    at = lambda e, mode="floor": (lambda x: (x.q, x.low, x.high, x.sign))(split_endpoint(e, 10, 37, mode))
    assert at(0) == (0, 0, 0, 1) and at(20) == (2, 20, 20, 1) and at(37) == (3, 30, 37, 1)
    assert at(18, "nearest") == (2, 18, 20, -1) and at(15, "nearest") == (1, 10, 15, 1)  # a tie stays below
    assert at(37, "nearest") == (3, 30, 37, 1)  # there is no anchor above
    with pytest.raises(SpecError):
        split_endpoint(38, 10, 37)
    for bad in ((3, 3), (5, 2), (-1, 2), (0, 38)):
        with pytest.raises(SpecError):
            pieces(*bad, 10, 37)


def test_nearest_reads_fewer_cells():
    specs = {x: AnchorSpec.uniform(GRID, x, 2) for x in subsets_for(["latitude longitude".split()], GRID)}
    total = lambda mode: sum(plan_box(GRID, specs, {"latitude": (a, b), "longitude": (1, 17)}, ["latitude", "longitude"], mode).reads() for a in range(12) for b in range(a + 1, 13))
    assert total("nearest") < total("floor")


def test_subsets_of_services():
    assert subsets_for([["longitude", "latitude"], ["time"]], GRID) == [("latitude",), ("longitude",), ("time",), ("latitude", "longitude")]


def test_planner_falls_back_where_tables_are_missing():
    specs = {x: AnchorSpec.uniform(GRID, x) for x in (("latitude",), ("time",))}
    plan = plan_box(GRID, specs, {"time": (0, 20)}, ["latitude", "time"])
    assert plan.used in (("latitude",), ("time",)) and plan.reads() < GRID.cells
    assert plan_box(GRID, {}, {}, ["time"]).used == ()
    with pytest.raises(SpecError):
        plan_box(GRID, specs, {"depth": (0, 1)}, ["time"])


def test_reads_do_not_grow_with_an_aligned_box():
    specs = {x: AnchorSpec.uniform(GRID, x) for x in subsets_for([["latitude", "longitude"]], GRID)}
    reads = {plan_box(GRID, specs, {"latitude": (2, k), "longitude": (3, 15)}, ["latitude", "longitude"]).reads() for k in (4, 6, 8, 10, 12)}
    assert len(reads) == 1


def test_common_step_of_different_strides():
    grid = GridSpec("l", (AxisSpec("a", 100, 4), AxisSpec("b", 10, 5)))
    specs = [AnchorSpec(("a", "b"), (2, 0)), AnchorSpec(("a", "b"), (3, 1)), AnchorSpec(("a", "b"), (0, 1))]
    assert common_step(grid, specs, "a") == 24 and common_step(grid, specs, "b") == 5
    with pytest.raises(SpecError):
        common_step(grid, specs[:1], "b")


@pytest.mark.parametrize("names, stride", [(["latitude", "longitude", "time"], [1, 3]), (["latitude", "longitude", "time"], [0, 0, -1]), (["longitude", "latitude", "time"], [1, 0, 0]), (["latitude", "longitude", "depth"], [1, 0, 0]), (["latitude", "longitude", "time"], [0, 0, 0]), (["latitude", "longitude", "time"], [0, 1.5, 0]), (["latitude", "latitude", "time"], [1, 0, 0])])
def test_bad_attributes(names, stride):
    with pytest.raises(SpecError):
        validate({DIMENSIONS: names, STRIDE: stride}, GRID)


def test_missing_attributes_and_good_ones():
    for key in (DIMENSIONS, STRIDE):
        with pytest.raises(SpecError):
            validate({key: ["time"]})
    names = list(GRID.names)
    assert validate({DIMENSIONS: names, STRIDE: [0, 0, 2]}, GRID).subset == ("time",)
    assert validate({DIMENSIONS: names, STRIDE: [1, 3, 0]}, GRID).subset == ("latitude", "longitude")


def test_catalog_round_trip_lookup_and_tree():
    c = AnchorCatalog(GRID)
    for s in (["latitude"], ["longitude"], ["time"], ["longitude", "latitude"]):
        c.add(AnchorSpec.uniform(GRID, s, 2), ("weighted", "weight"))
    again = AnchorCatalog.from_json(c.to_json())
    assert again.rows() == c.rows()
    assert again.find(["longitude", "latitude"], "weighted") == "acc_weighted_latitude_longitude" and again.find(["time"], "plain") is None and again.find(["time", "latitude"], "weight") is None
    assert again.anchor_of(["time"], "time", 5) == 2
    tree = again.export_attributes()["_ACCUMULATION_GROUP"]
    assert tree["latitude"]["longitude"]["time"] == {} and tree["latitude"]["longitude"]["_WEIGHTS"] and tree["longitude"]["time"] == {}
    names = AnchorCatalog.import_attributes(again.export_attributes())
    assert names[("latitude", "longitude"), "weighted"] == "acc_weighted_latitude_longitude" and len(names) == 8
    for bad in ({}, {"x": 1}, {"_ACCUMULATION_GROUP": {"_DATA_WEIGHTED": "a"}}, {"_ACCUMULATION_GROUP": {"a": {"_OTHER": "b"}}}):
        with pytest.raises(SpecError):
            AnchorCatalog.import_attributes(bad)
    broken = json.loads(c.to_json())
    broken["tables"][0]["subset"] = ["time"]
    with pytest.raises(SpecError):
        AnchorCatalog.from_json(json.dumps(broken))


def test_spans_by_coordinate():
    lon = AxisSpec("lon", 36, 6, origin=-180.0, width=10.0, wraps=True)
    assert lon.span(-180, 180) == [(0, 36)] and lon.span(-35, 25) == [(14, 21)]
    assert lon.span(170, -170) == [(35, 36), (0, 1)]
    assert AxisSpec("t", 10, 5, width=0.5).span(1.0, 2.5) == [(2, 5)] and AxisSpec("t", 10, 5).span(11, 12) == []
    with pytest.raises(SpecError):
        AxisSpec("lat", 18, 6, origin=-90.0, width=10.0).span(20, -20)
