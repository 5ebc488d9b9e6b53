import duckdb
import pytest
from pyspark.sql import functions as F

from boxsum.operators import query
from boxsum.operators.build import AnchorStore
from boxsum.plans.spec import AxisSpec, GridSpec
from boxsum.sources import grids, io
from boxsum.workloads.cases import all_subsets, box_sql, store_of

GRID = GridSpec("small", (AxisSpec("a", 6, 2), AxisSpec("t", 4, 2)))


def test_boxes_and_names_from_text_files(spark, tmp_path):
    (tmp_path / "boxes.csv").write_text("box_id,a_lo,a_hi,t_lo,t_hi\n1,1,5,0,4\n2,0,7,0,4\n3,3,3,0,1\n4,,2,0,1\n")
    (tmp_path / "names.json").write_text('{"a": 0, "label": "north"}\n{"a": 1, "label": "south"}\n')
    boxes, refused = io.read_boxes(spark, f"file://{tmp_path}/boxes.csv", GRID)
    assert [r.box_id for r in boxes.collect()] == [1] and sorted(r.box_id for r in refused.collect()) == [2, 3, 4]
    assert {r.a: r.label for r in io.read_dictionary(spark, f"file://{tmp_path}/names.json", "a", "json").collect()} == {0: "north", 1: "south"}
    cells = spark.createDataFrame([(i, j, 10 * i + j, 1) for i in range(6) for j in range(4)], "a int, t int, sx long, n long")
    store = AnchorStore.build(cells, GRID, all_subsets("at"))
    row = query.box_average_many(store, boxes, "at").first()
    assert (row.s, row.n, row.avg) == (sum(10 * i + j for i in range(1, 5) for j in range(4)), 16, 26.5)


@pytest.mark.parametrize(("name", "axis"), [("plane", "r"), ("field", "r"), ("activity", "u"), ("line", "d"), ("talk", "k")])
def test_axes_of_ids_are_as_long_as_the_tables_need(spark, tmp_path, name, axis):
    grid = grids.GRIDS[name]
    first, column = grid.ids[axis]
    least = grid.spec[axis].n
    for top in (3, least + 7, -1):
        for i, t in enumerate({"field": [first, "events"], "line": [first, "labels"]}.get(name, [first])):
            rows = spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet").limit(3)
            ids = F.when(F.monotonically_increasing_id() == 0, F.lit(top)).when(F.monotonically_increasing_id() == 1, F.lit(None)).otherwise(F.lit(1))
            (rows.coalesce(1).withColumn(column, ids.cast(rows.schema[column].dataType)) if i == 0 else rows).write.parquet(f"{tmp_path}/{top}/{t}.parquet")
        at = f"{tmp_path}/{top}"
        if top < 0:
            with pytest.raises(Exception, match="outside its axis"):
                grid.cells(spark, at).agg(F.max(axis)).first()
            continue
        assert grid.sized(spark, at)[axis].n == max(least, top + 1)
        found = {r[0] for r in grid.cells(spark, at).select(axis).distinct().collect()}
        assert found == {1, top}
        # maps, series and SQL over the whole axis see the same rows
        con = duckdb.connect()
        for t in {"field": [first, "events"], "line": [first, "labels"]}.get(name, [first]):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at}/{t}.parquet/*.parquet'")
        for over in ([axis], [a for a in grid.spec.names if a != axis] or [axis]):
            got = query.box_average(store_of(spark, at, grid, all_subsets(over)), {}, over)
            sql = con.execute(box_sql(grid, {}, over))
            columns = [c[0] for c in sql.description]
            assert sorted(map(tuple, got.select(columns).collect())) == sorted(sql.fetchall())


def test_cells_beyond_other_axes_are_an_error(spark):
    cells = spark.createDataFrame([(0, 23, 1, 1), (1, 24, 1, 1), (None, 2, 1, 1)], "a int, t int, sx long, n long")
    spec = GridSpec("g", (AxisSpec("a", 2, 2), AxisSpec("t", 24, 2)))
    with pytest.raises(Exception, match="t of 24: 24"):
        grids.on_grid(cells, spec).count()
    assert grids.on_grid(cells.where("t < 24"), spec).count() == 1


def test_dictionaries_are_bounded(spark, monkeypatch):
    names = spark.createDataFrame([("b",), ("a",), (None,), ("b",)], "name string")
    assert {r.name: r.at for r in grids.dictionary(names, "name", "at").collect()} == {"a": 0, "b": 1}
    monkeypatch.setattr(grids, "NAMES", 1)
    with pytest.raises(Exception, match="too many values"):
        grids.dictionary(names, "name", "at").collect()


def test_no_temporary_folder_on_a_cluster(spark, monkeypatch):
    assert io.scratch(spark, "x").rsplit("/", 1)[1].startswith("boxsum-x-")
    held = type("S", (), {"conf": type("C", (), {"get": staticmethod(lambda *_: None)}), "sparkContext": type("X", (), {"master": "spark://h:1", "_jsc": type("J", (), {"sc": staticmethod(lambda: type("D", (), {"getCheckpointDir": staticmethod(lambda: type("O", (), {"isEmpty": staticmethod(lambda: True)}))}))})})})
    with pytest.raises(ValueError, match="checkpoint"):
        io.scratch(held, "x")
