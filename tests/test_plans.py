import pytest
from pyspark.sql import functions as F

from semtrie.operators import prep, profiles, truth
from semtrie.operators.neighbors import ranked
from semtrie.plans.planner import executed_plan, plan_build, shuffled_bytes
from semtrie.sources import sinks
from semtrie.sources import tables as T
from semtrie.streaming import streams as S


def test_scans_are_pruned_and_filters_pushed(spark, sf):
    plan = executed_plan(T.events_table(spark, sf).filter("event_type = 'view'").select("user_id"))
    assert "ReadSchema: struct<user_id:bigint,event_type:string>" in plan
    assert "EqualTo(event_type,view)" in plan


def test_profile_mean_is_partial(spark, sf):
    w = T.interest(spark, sf)
    plan = executed_plan(profiles.user_profiles(w.holding, w.doc_vectors))
    assert "partial_" in plan and "collect_list" not in plan


def test_top_k_is_cut_before_the_shuffle(spark):
    known = spark.range(100).select((F.col("id") % 5).alias("user_id"), F.col("id").alias("peer_id"), F.rand(1).alias("sim"))
    assert "WindowGroupLimit" in executed_plan(ranked(known).filter("rank <= 3"))


def test_exact_neighbors_has_no_cartesian(spark, sf):
    plan = executed_plan(truth.exact_neighbors(T.plain_vectors(spark, sf), 5))
    assert "Cartesian" not in plan and "NestedLoop" not in plan


def test_first_access_needs_one_shuffle(spark, sf):
    plan = executed_plan(prep.first_access(T.interest(spark, sf).access))
    assert plan.count("Exchange hashpartitioning(user_id") <= 2


def test_build_plan_bounds_a_task():
    p = plan_build(10**9, 768)
    assert p.local_rows * 8 * 768 * 4 <= 256e6 and 10 <= p.outer_levels <= 20


def test_scratch_tables_need_a_shared_folder_on_a_cluster(spark):
    from types import SimpleNamespace as Of

    from semtrie.plans import store

    def session(master, conf=None, given=None):
        folder = Of(isDefined=lambda: given is not None, get=lambda: given)
        context = Of(master=master, applicationId="app", _jsc=Of(sc=lambda: Of(getCheckpointDir=lambda: folder)))
        return Of(conf=Of(get=lambda name, default: conf or default), sparkContext=context)

    assert store.is_local("local") and store.is_local("local[8]") and not any(map(store.is_local, ("yarn", "spark://h:7077", "local-cluster[2,1,1024]")))
    assert store.shared_dir(session("yarn", "hdfs:///a/", "hdfs:///b")) == "hdfs:///a" and store.shared_dir(session("yarn", None, "hdfs:///b")) == "hdfs:///b"
    assert store.shared_dir(session("local[2]")).startswith("file:///")
    with pytest.raises(ValueError):
        store.shared_dir(session("yarn"))
    table = store.materialize(spark.range(3), "gone")
    store.discard(table)
    with pytest.raises(Exception, match="PATH_NOT_FOUND|FILE_NOT_EXIST|does not exist"):
        spark.read.parquet(table._scratch_path).count()


def test_the_graph_stays_off_the_driver_when_walks_are_distributed(spark, sf01, monkeypatch):
    from semtrie import experiments as X
    from semtrie.operators import hop

    s = X.coded(spark, sf01)
    monkeypatch.setattr(hop, "_whole_graph", lambda *a: 1 / 0)
    assert not X.walk(s, 1, local=False).isEmpty()
    monkeypatch.setattr(hop, "LOCAL_PEERS", 10)  # counted: above the bound the graph is not sent
    assert not X.walk(s, 1).isEmpty()


def test_shuffled_bytes_are_counted(spark):
    before = shuffled_bytes(spark)
    spark.range(10_000).repartition(5).count()
    assert shuffled_bytes(spark) > before


def test_placements_by_prefix_and_by_bucket(spark, tmp_path):
    places = spark.createDataFrame([("", 1, "0101"), ("", 2, "1"), ("", 3, "")], "tree_id string, user_id long, path string")
    sinks.write_placements(places, str(tmp_path / "p"))
    back = spark.read.parquet(str(tmp_path / "p"))
    assert {(r.user_id, r.path) for r in back.collect()} == {(1, "0101"), (2, "1"), (3, "")}
    assert "PartitionFilters: [isnotnull(path_prefix" in executed_plan(back.filter("path_prefix = '0101'"))
    spark.sql("CREATE DATABASE IF NOT EXISTS buckets_test LOCATION '" + str(tmp_path / "db") + "'")
    for name in ("a", "b"):
        sinks.save_bucketed(places, f"buckets_test.{name}", buckets=4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = executed_plan(spark.table("buckets_test.a").join(spark.table("buckets_test.b"), "user_id"))
        assert "Exchange" not in plan
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP DATABASE buckets_test CASCADE")


def test_log_formats_round_trip(spark, tmp_path):
    rows = spark.createDataFrame([(1, "a", "q one"), (2, "b", None)], "user_id long, doc_id string, query string").withColumn("ts", F.lit("2024-01-01 00:00:00").cast("timestamp")).select("user_id", "doc_id", "ts", "query")
    for fmt in sinks.FORMATS:
        sinks.write_access(rows, str(tmp_path / fmt), fmt)
        back = sinks.read_access(spark, str(tmp_path / fmt), fmt)
        assert {(r.user_id, r.doc_id, r.ts) for r in back.collect()} == {(r.user_id, r.doc_id, r.ts) for r in rows.collect()}


def test_levels_are_replaced_not_repeated(spark, tmp_path):
    nodes = spark.createDataFrame([("", 0), ("0", 1), ("1", 1)], "path string, depth int")
    for _ in range(2):
        for level in (0, 1):
            sinks.append_level(nodes, str(tmp_path / "nodes"), level)
    assert spark.read.parquet(str(tmp_path / "nodes")).count() == 3


def test_late_rows_are_dropped_and_audited(spark, tmp_path):
    import time

    schema = "event_id long, ts timestamp, user_id long, k long"
    src = str(tmp_path / "in")
    day = lambda i, d: [(i, f"2024-01-{d:02d} 12:00:00", 1, i)]
    for i, d in enumerate((10, 20, 1, 21)):
        spark.createDataFrame(day(i, d), "event_id long, ts string, user_id long, k long").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(src)
        time.sleep(1.1)  # file order is by time
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(src).withWatermark("ts", "2 days")
    out = S.run_to_table(stream.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")), "append")
    days = {r.window.start.day for r in out.collect()}
    assert 1 not in days and 10 in days
    batch = spark.read.parquet(src)
    assert [r.event_id for r in S.late_rows(batch, "2024-01-05 00:00:00").collect()] == [2]


def test_replayed_halves_equal_the_batch(spark, tmp_path, sf):
    e = T.table(spark, sf, "events").orderBy("ts").coalesce(1)
    n = e.count()
    ordered = e.withColumn("rn", F.monotonically_increasing_id())
    for name, part in (("events_1", ordered.filter(F.col("rn") < n // 2)), ("events_2", ordered.filter(F.col("rn") >= n // 2))):
        part.drop("rn").coalesce(1).write.parquet(str(tmp_path / name))
        for f in (tmp_path / name).glob("part-*.parquet"):
            f.rename(tmp_path / f"{name}.parquet")
    stream = S.events_stream(spark, str(tmp_path)).withColumnRenamed("k", "doc_id")
    vectors = T.vectors_table(spark, sf)
    got = {r.user_id: (r.n_docs, round(r.emb[0], 9)) for r in S.run_to_table(S.streaming_profiles(stream, vectors), "update", ["user_id"]).collect()}
    batch = T.events_table(spark, sf).withColumnRenamed("k", "doc_id").join(vectors, "doc_id").groupBy("user_id").agg(F.count("*").alias("n"), F.avg(F.get("emb", F.lit(0))).alias("e")).collect()
    assert got == {r.user_id: (r.n, round(r.e, 9)) for r in batch}
