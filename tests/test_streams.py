import pytest
from pyspark.sql import functions as F

from boxsum.operators import query
from boxsum.operators.build import AnchorStore
from boxsum.plans.spec import AxisSpec, GridSpec
from boxsum.streaming.upkeep import GrowingStore, closed, event_stream, gathered, stream_cells, stream_store
from boxsum.workloads import QUERIES
from boxsum.workloads.cases import all_subsets

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The events in a folder of four files, in order of time."""
    root = tmp_path_factory.mktemp("events")
    events = spark.read.parquet(f"{SF}/events.parquet")
    for k in range(4):
        events.where(F.col("event_id").between(250 * k, 250 * k + 249)).coalesce(1).write.mode("append").parquet(f"{root}/events.parquet")
    assert spark.read.parquet(f"{root}/events.parquet").count() == events.count()
    return str(root)


@pytest.fixture(scope="module")
def nothing(spark, tmp_path_factory):
    root = tmp_path_factory.mktemp("none")
    spark.read.parquet(f"{SF}/events.parquet").limit(0).write.parquet(f"{root}/events.parquet")
    return str(root)


def shown(df):
    return sorted(tuple(map(str, r)) for r in df.select(sorted(df.columns)).collect())


@pytest.mark.parametrize("name", ["s01_hour_slices", "s02_sliding", "s03_session", "s04_carry", "s06_stream_static", "s07_dedup_within_watermark", "s08_stream_stream", "w21_stream_equals_batch", "w21_stream_series"])
def test_folders_of_files_and_several_batches(spark, folder, nothing, name):
    assert shown(QUERIES[name](spark, folder)) == shown(QUERIES[name](spark, SF))
    assert QUERIES[name](spark, nothing).count() == 0


def test_each_slice_is_appended_once(spark, folder):
    seen = []

    def slices(events):
        return events.withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n")).select(F.unix_micros("window.start").alias("start"), "n")

    rows = closed(spark, folder, slices).collect()
    assert len({r.start for r in rows}) == len(rows) and sum(r.n for r in rows) == 1000
    open_ones = gathered(slices(event_stream(spark, folder)))  # without a closing row the last slices stay open
    seen = [r.start for r in open_ones.collect()]
    assert 0 < len(seen) < len(rows) and set(seen) <= {r.start for r in rows}
    batches = gathered(event_stream(spark, folder).groupBy("event_type").agg(F.count("*").alias("n")), "complete")
    assert batches.count() == 5 and batches.agg(F.sum("n")).first()[0] == 1000


GRID = GridSpec("g", (AxisSpec("a", 6, 2), AxisSpec("t", 30, 3)))


@pytest.mark.parametrize("stride", [1, 2])
def test_a_growing_store_equals_a_rebuild(spark, tmp_path, stride):
    import random

    r = random.Random(4)
    rows = [(r.randrange(6), t, r.randint(-9, 9), 1) for t in range(30) for _ in range(3)]
    batches = [rows[:20], rows[20:24], [], [*rows[24:60], *[(1, 0, 5, 1), (2, 7, -3, 1)]], [(3, 2, 4, 1)], rows[60:]]  # with late cells
    store = GrowingStore(spark, f"{tmp_path}/s{stride}", GRID, all_subsets("at"), stride)
    frame = lambda x: spark.createDataFrame(x, "a int, t int, sx long, n long")
    so_far = []
    for k, batch in enumerate(batches):
        store.add(frame(batch), k)
        if k == 3:
            store.add(frame(batch), k)  # a batch that is tried again
        so_far += batch
        n = max(t for _, t, _, _ in so_far) + 1
        grid = GridSpec("g", (GRID["a"], AxisSpec("t", n, 3)))
        whole = AnchorStore.build(frame(so_far), grid, all_subsets("at"), stride)
        for s in whole.tables:
            got = {tuple(x[c] for c in whole.tables[s].columns) for x in store.table(s).where("n > 0").collect()}
            assert got == {tuple(x) for x in whole.tables[s].collect()}, (k, s)
        box = {"a": (1, 5), "t": (0, n)}
        row = query.box_average(store.read(), box, "at").first()
        assert (row.s, row.n) == (sum(v for a, t, v, _ in so_far if 1 <= a < 5), sum(1 <= a < 5 for a, *_ in so_far))


def test_a_batch_writes_what_it_brings(spark, folder):
    grid = GridSpec("g", (AxisSpec("u", 150, 25), AxisSpec("t", 720, 24)))
    store = stream_store(stream_cells(event_stream(spark, folder)), grid, all_subsets("ut"))
    done = store._batches(None)
    assert len(done) == 4 and [n for _, n in done] == sorted(n for _, n in done)
    rows = [spark.read.parquet(f"{store.root}/acc_u/batch={k}").count() for k, _ in done]
    assert max(rows) < 0.5 * sum(rows)  # none goes over what is there
