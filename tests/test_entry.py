import glob
import os

import duckdb
import pytest

from pyspark.sql import functions as F

import __spark_entry__
from boxsum import workloads
from boxsum.operators import baseline, query
from boxsum.sources.grids import G1, G4, G4_FLOATS
from boxsum.workloads.experiments import at_ranges

SF = "/root/testdata/sf0.001"
#: The field has 23 million cells at any scale, and each of these reads it several times; the driver compares them.
FIELD = ["w05_accuracy_float", "w05_accuracy_int_g4"]


def test_experiments_take_all_sizes():
    field, ship = range(80, 721, 80), range(400, 2401, 400)
    for name, sizes in (("w01_series_g4", field), ("w03_map_g4", field), ("w05_accuracy_int_g4", field), ("w01_series_g1", ship), ("w03_map_g1", ship), ("w05_accuracy_int", ship)):
        assert all(f"{k} AS size" in workloads.ORACLE_SQL[name] for k in sizes)
    assert all(f"{k} AS size" in workloads.ORACLE_SQL["w05_accuracy_float"] for k in field)
    assert {"w02_series_full_g4", "w04_map_full_g1"} <= set(workloads.ORACLE_SQL) and "range(1000)" in workloads.ORACLE_SQL["m27_many_boxes"]


def test_every_query_but_timings_has_sql():
    assert set(workloads.QUERIES) == set(workloads.ORACLE_SQL)


def test_entry_and_names(spark):
    assert __spark_entry__.entry(spark).count() > 0
    found, sql = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(sql) <= set(found) and set(workloads.QUERIES) <= set(found)


@pytest.mark.parametrize("name", sorted(set(workloads.ORACLE_SQL) - set(FIELD)))
def test_against_sql(spark, name):
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = workloads.QUERIES[name](spark, SF)
    want = con.execute(workloads.ORACLE_SQL[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(got.columns)
    show = lambda v: "" if v is None else f"{v:.10g}" if isinstance(v, float) else str(v)
    assert sorted(map(tuple, (map(show, r) for r in got.select(columns).collect()))) == sorted(map(tuple, (map(show, r) for r in want.fetchall())))


def test_field_is_made_by_many_tasks(spark):
    for grid in (G4, G4_FLOATS):
        assert grid.cells(spark, SF).rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism


def test_scan_of_several_ranges_equals_a_scan_a_range(spark):
    ranges = [(0, 400), (0, 800), (123, 2001)]
    cells = G1.cells(spark, SF)
    for over, keys in (("yx", ["t"]), ("t", ["y", "x"]), ("yxt", [])):
        got = query.divided(baseline.scan_sums(cells, G1.spec, "t", ranges, over), [*keys, "lo", "hi"], F.col("extent")).collect()
        want = [(*r[: len(keys)], lo, hi, *r[len(keys) :]) for lo, hi in ranges for r in baseline.scan_average(cells, G1.spec, {"t": (lo, hi)}, over).collect()]
        assert want and sorted(map(tuple, got)) == sorted(want)


def test_figures_have_a_row_for_each_range(spark):
    found = spark.createDataFrame([(0, 3, "a", 7)], "lo int, hi int, kind string, n long")
    got = at_ranges(found, [(0, 3), (3, 5)], kind=["a", "b"]).select("kind", "lo", "hi", "n").collect()
    assert sorted(map(tuple, got)) == [("a", 0, 3, 7), ("a", 3, 5, 0), ("b", 0, 3, 0), ("b", 3, 5, 0)]


#: Queries that once made up all of their data.
READS = ["c8_tiles_touched", "m02_subsets", "m10_patched_tile_roles", "m11_plan", "m21_catalog_rows", "m22_lookup", "m23_tile_to_anchor", "o02_range_axis", "u03_pieces_udtf", "w10_stride4_reads", "w15_lookup"]


@pytest.mark.parametrize("name", READS)
def test_reads_a_given_table(spark, name):
    assert workloads.QUERIES[name](spark, SF).inputFiles()


def test_tiles_touched_has_the_anchor_rows(spark):
    (row,) = workloads.QUERIES["c8_tiles_touched"](spark, SF).collect()
    assert (row.tiles, row.anchor_rows, row.touched) == (2 * 2 * 3, 16 * 100 + 30 * 100 + 100, 12 + 4700)
    assert row.touched_found == row.found + row.anchor_rows_found > row.found
