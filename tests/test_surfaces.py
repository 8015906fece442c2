"""Stored layouts, table functions, learners, late rows, warm starts."""

import io
import uuid
from contextlib import redirect_stdout

import numpy as np
import pytest

from hyperembed.functions import tables
from hyperembed.operators import hypergraph as hg, lowrank as lr, tasks as tk
from hyperembed.session import work_folder
from hyperembed.sources import graphs, layout
from hyperembed.streaming import events as ev

SF = "/root/testdata/sf0.001"


def plan(df):
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain()
    return out.getvalue()


def test_bucketed_copies_join_without_an_exchange(spark, monkeypatch):
    h = graphs.order_baskets(spark, SF).graph
    name = f"inc_{uuid.uuid4().hex}"
    by_eid, by_vid = layout.write_bucketed(h, name, f"{work_folder(spark)}/{name}", 4)
    assert by_eid.count() == by_vid.count() == h.inc.count()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        sizes = by_eid.groupBy("eid").count()
        assert "Exchange" not in plan(by_eid.join(sizes, "eid"))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    for part in ("eid", "vid"):
        spark.sql(f"DROP TABLE {name}_by_{part}")


def test_partitioned_blocks_are_whole_and_pruned(spark):
    inc = graphs.order_baskets(spark, SF).graph.inc
    path = f"{work_folder(spark)}/blocks-{uuid.uuid4().hex}"
    layout.write_partitioned(inc, path, 4)
    assert sum(layout.read_block(spark, path, b).count() for b in range(4)) == inc.count() == layout.read_block(spark, path).count()
    assert "PartitionFilters: [isnotnull(block" in plan(layout.read_block(spark, path, 2))


def test_table_functions(spark, monkeypatch):
    tables.register(spark)
    df = spark.createDataFrame([(1, [3, 1, 2, 1]), (2, [7]), (3, []), (4, None), (5, [9, None, 8])], "eid long, members array<long>")
    df.createOrReplaceTempView("member_lists")
    got = sorted(tuple(r) for r in spark.sql("SELECT * FROM hyperedge_pairs(TABLE(member_lists))").collect())
    assert got == [(1, 1, 2), (1, 1, 3), (1, 2, 3), (5, 8, 9)]
    df = spark.createDataFrame([(5, 10, 4, 1), (6, 3, 1000, 1), (7, None, 4, 1), (8, 0, 4, 1)], "eid long, size long, nodes long, seed long")
    df.createOrReplaceTempView("wanted")
    got, again = (sorted(tuple(r) for r in spark.sql("SELECT * FROM random_members(TABLE(wanted))").collect()) for _ in range(2))
    assert got == again and [p for e, p in got if e == 5] == [0, 1, 2, 3] and len({p for e, p in got if e == 6}) == 3 and len(got) == 7


def test_pairs_in_several_batches(spark, monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(tables, "BATCH", 20)
    found = [p for t in tables.HyperedgePairs.func().eval(pa.RecordBatch.from_pydict({"eid": [1], "members": [list(range(30))]})) for p in zip(t["a"].to_pylist(), t["b"].to_pylist())]
    assert found == [(i, j) for i in range(30) for j in range(i + 1, 30)]


@pytest.mark.parametrize("learner", ["ridge", "logistic", "svc"])
def test_learners(spark, learner):
    rng = np.random.default_rng(1)
    centre = {"a": [3, 0, 0], "b": [0, 3, 0], "c": [0, 0, 3]}
    rows = [(i, (rng.normal(size=3) * 0.3 + centre["abc"[i % 3]]).tolist(), "abc"[i % 3]) for i in range(90)]
    vectors = spark.createDataFrame([(i, v) for i, v, _ in rows] + [(90, [0.0, 0.0, 0.0]), (91, [1.0, 0.0, 0.0])], "id long, vec array<double>")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows] + [(90, "only in the test"), (91, None)], "id long, y string")
    parts = tk.split(labels.where("id < 90").select("id"), 50).select("id", "is_train").union(spark.createDataFrame([(90, False), (91, False)], "id long, is_train boolean"))
    got = tk.classify(vectors, labels, parts, 3, learner=learner).collect()
    assert {r["id"] for r in got} == {r["id"] for r in parts.where("not is_train").collect()} - {91}
    assert all(r["predicted"] == r["y"] for r in got if r["id"] < 90)
    one = tk.classify(vectors, labels.where("y = 'a'"), parts, 3, learner=learner).collect()
    assert {r["predicted"] for r in one} == {"a"}
    assert tk.classify(vectors, labels.where("false"), parts, 3, learner=learner).count() == 0


def test_unknown_learner(spark):
    with pytest.raises(ValueError):
        tk.classify(None, None, None, 3, learner="forest")


def test_late_rows_are_dropped_and_counted(spark):
    folder = f"{work_folder(spark)}/late-{uuid.uuid4().hex}"
    schema = "event_id long, ts timestamp, user_id long, event_type string"
    day = lambda d: f"2024-01-{d:02d} 12:00:00"
    batches = ([(1, day(1), 1), (2, day(1), 2)], [(3, day(5), 1)], [(8, day(5), 1)], [(4, day(1), 3), (5, day(5), 3)], [(6, day(9), 1)], [(7, day(9), 1)])
    for rows in batches:
        spark.createDataFrame([(i, t, u, "click") for i, t, u in rows], "event_id long, t string, user_id long, event_type string").selectExpr(
            "event_id", "CAST(t AS TIMESTAMP) AS ts", "user_id", "event_type").coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(folder)
    name = f"closed_{uuid.uuid4().hex}"
    q = ev.closed_windows(stream).writeStream.outputMode("append").format("memory").queryName(name).option("checkpointLocation", f"{folder}-c").trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted(tuple(r) for r in spark.table(name).collect()) == [("2024-01-01 00:00", "click", 2, 2), ("2024-01-05 00:00", "click", 2, 3)]
    assert ev.dropped_late(q) == 1


def test_volumes_over_batches_equal_one_batch(spark):
    folder = f"{work_folder(spark)}/grow-{uuid.uuid4().hex}"
    spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", ev.F.col("ts").cast("timestamp")).repartition(3).write.parquet(folder)
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got = {(r["side"], r["id"]): r["total"] for r in ev.running_volumes(stream, f"{folder}-sums").collect()}
    rows = spark.read.parquet(folder)
    assert got["all", ""] == rows.count()
    assert {int(k[1]): v for k, v in got.items() if k[0] == "node"} == {r["user_id"]: r["count"] for r in rows.groupBy("user_id").count().collect()}


def test_library_svd_refuses_large_inputs(spark):
    h = hg.hypergraph_from(spark.createDataFrame([(e, v) for e in range(4) for v in range(e, e + 3)], "e long, v long"), "e", "v")
    with pytest.raises(ValueError):
        lr.svd_mllib(h, 2, most=3)
    assert np.allclose(lr.svd_mllib(h, 2), lr.svd_full(h, 2).sigma)


def test_centres_of_few_rows(spark):
    f = spark.createDataFrame([(i, [float(i % 2), 0.0]) for i in range(6)], "id long, vec array<double>")
    assert sorted(lr.sample_centres(f, 5).tolist()) == [[0.0, 0.0], [1.0, 0.0]]
    assert len(lr.sample_centres(f.where("false"), 5)) == 0


def test_drained_rows_are_written_by_executors(spark):
    folder = f"{work_folder(spark)}/drain-{uuid.uuid4().hex}"
    for d in (1, 2, 3):
        spark.range(4).selectExpr("id AS event_id", f"CAST('2024-01-0{d} 12:00:00' AS TIMESTAMP) AS ts", "id % 2 AS user_id", "'a' AS event_type").coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").option("maxFilesPerTrigger", 1).parquet(folder)
    whole, first = ev.drain(ev.sessions(stream)), ev.drain(stream.select("event_id"), "append")
    assert whole.inputFiles() and first.inputFiles()
    assert whole.count() == 6 and first.count() == 12
    assert {r["events"] for r in whole.collect()} == {2}


def test_library_svd_takes_the_smaller_side(spark):
    h = hg.hypergraph_from(spark.createDataFrame([(e, v) for e in range(3) for v in range(e, 9 + e)], "e long, v long"), "e", "v")
    assert np.allclose(lr.svd_mllib(h, 2, most=3), lr.svd_full(h, 2).sigma)


def test_shared_members_of_any_number_of_pairs(spark, monkeypatch):
    rows = [(e, v) for e in range(6) for v in range(9) if (e * v) % 3 != 1] + [(9, 0)]
    h = hg.hypergraph_from(spark.createDataFrame(rows, "e long, v long"), "e", "v", min_size=1)
    held = {e: {v for f, v in rows if f == e} for e, _ in rows}
    want = sorted((e, f, len(held[e] & held[f])) for e in held for f in held if e < f and held[e] & held[f])
    for listed in (2000, 4):
        monkeypatch.setattr(hg, "LISTED", listed)
        assert sorted(tuple(r) for r in hg.shared_members(h).collect()) == want
