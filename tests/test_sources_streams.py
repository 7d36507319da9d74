import shutil

import numpy as np
import pytest
from compare import SF_SMOKE, duck, plain
from pyspark.sql import functions as F

from shardgraph.functions.vectors import validated
from shardgraph.operators.centroids import preferences
from shardgraph.operators.partition import PartitionConfig, ShardPlan, partition_vectors, sample_state
from shardgraph.registry import read
from shardgraph.sources import tables
from shardgraph.sources.vecfile import VecFile, write_vecfile
from shardgraph.streaming import blocks, events


@pytest.mark.parametrize("fmt,opts", [("csv", {"header": True}), ("json", {}), ("orc", {}), ("parquet", {})])
def test_formats_round_trip(spark, tmp_path, fmt, opts):
    df = read(spark, SF_SMOKE, "nation")
    df.write.format(fmt).options(**opts).save(str(tmp_path / "t"))
    back = spark.read.format(fmt).options(**opts).schema(df.schema).load(str(tmp_path / "t"))
    assert sorted(back.collect()) == sorted(df.collect())


def test_text_and_binary(spark, tmp_path):
    (tmp_path / "a.txt").write_text("x\ny\n")
    assert [r.value for r in spark.read.text(str(tmp_path / "a.txt")).collect()] == ["x", "y"]
    assert bytes(spark.read.format("binaryFile").load(str(tmp_path)).first().content) == b"x\ny\n"


@pytest.mark.parametrize("kind", ["float32", "uint8"])
def test_vecfile(spark, tmp_path, kind):
    x = np.random.default_rng(0).integers(0, 200, (250, 5))
    path = str(tmp_path / "v.bin")
    write_vecfile(path, x, kind)
    spark.dataSource.register(VecFile)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    df = spark.read.format("vecfile").option("kind", kind).option("rowsPerPartition", "100").load(path)
    assert df.count() == 250
    some = df.where("vec_id >= 120 and vec_id < 130").orderBy("vec_id").collect()
    assert [r.vec_id for r in some] == list(range(120, 130))
    assert np.array_equal(np.array([r.embedding for r in some]), x[120:130])
    q = spark.readStream.format("vecfile").option("kind", kind).load(path).writeStream.format("memory").queryName(f"vf_{kind}").trigger(once=True).option("checkpointLocation", str(tmp_path / "c")).start()
    q.awaitTermination()
    assert spark.table(f"vf_{kind}").count() == 250


def test_invalid_vectors_raise(spark):
    for bad in ([1.0, None], [1.0], [1.0, float("nan")], None):
        with pytest.raises(Exception, match="not a finite vector"):
            validated(spark.createDataFrame([(1, bad)], "vec_id bigint, embedding array<double>"), 2).collect()


def test_partitioned_sink_prunes(spark, tmp_path):
    a = spark.range(100).select(F.col("id").alias("vec_id"), (F.col("id") % 4).cast("int").alias("shard_id"))
    a.repartitionById(4, "shard_id").sortWithinPartitions("vec_id").write.partitionBy("shard_id").parquet(str(tmp_path / "s"))
    got = spark.read.parquet(str(tmp_path / "s")).where("shard_id = 2")
    assert got.count() == 25
    assert "PartitionFilters: [isnotnull(shard_id" in got._jdf.queryExecution().toString()


def test_bucketed_tables_join_without_shuffle(spark):
    for t in ("b1", "b2"):
        spark.range(200).withColumnRenamed("id", "k").write.mode("overwrite").bucketBy(4, "k").sortBy("k").saveAsTable(t)
    plan = spark.table("b1").join(spark.table("b2").hint("merge"), "k")._jdf.queryExecution().toString()
    assert "Exchange hashpartitioning" not in plan
    for t in ("b1", "b2"):
        spark.sql(f"drop table {t}")


@pytest.fixture(scope="module")
def event_files(spark, tmp_path_factory):
    p = str(tmp_path_factory.mktemp("ev") / "files")
    e = read(spark, SF_SMOKE, "events")
    e.repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(p)
    return p, e.schema


def stream(spark, event_files):
    return events.event_stream(spark, event_files[0], event_files[1], 3)


def twin(sql):
    return sorted(repr([plain(x) for x in r]) for r in duck(SF_SMOKE).execute(sql).fetchall())


def table_rows(spark, name, cols):
    ntz = [F.col(c).cast("timestamp_ntz").alias(c) if t == "timestamp" else F.col(c) for c, t in spark.table(name).dtypes if c in cols]
    return sorted(repr([plain(r[c]) for c in cols]) for r in spark.table(name).select(*ntz).collect())


def test_windows_equal_batch(spark, event_files, tmp_path):
    events.run_available(events.tumbling(stream(spark, event_files)), "tum", str(tmp_path / "a"), "complete")
    assert table_rows(spark, "tum", ["hour", "event_type", "n"]) == twin("select date_trunc('hour', ts) as hour, event_type, count(*)::bigint from events group by all")
    events.run_available(events.sliding(stream(spark, event_files)), "sli", str(tmp_path / "b"), "complete")
    from shardgraph.catalog import CORE

    assert table_rows(spark, "sli", ["start_ts", "n"]) == twin(CORE["ev_sliding"].sql)
    events.run_available(events.sessions(stream(spark, event_files), "30 minutes"), "ses", str(tmp_path / "c"), "complete")
    assert table_rows(spark, "ses", ["user_id", "start_ts", "n"]) == twin(CORE["win_session_gaps"].sql)


def test_dedup_static_join_and_state(spark, event_files, tmp_path):
    events.run_available(events.deduplicated(stream(spark, event_files), ["user_id", "event_type"], "40 days"), "ded", str(tmp_path / "a"))
    assert spark.table("ded").count() == read(spark, SF_SMOKE, "events").select("user_id", "event_type").distinct().count()
    z = events.with_zones(stream(spark, event_files), read(spark, SF_SMOKE, "nation")).select("n_name", "event_id")
    events.run_available(z, "zon", str(tmp_path / "b"))
    assert spark.table("zon").count() == read(spark, SF_SMOKE, "events").count()
    events.run_available(events.instance_state(stream(spark, event_files)), "ist", str(tmp_path / "c"), "update")
    last = {r.user_id: (r.n, r.state) for r in spark.table("ist").groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("state", "n").alias("state")).collect()}
    want = {r.user_id: (r.n, r.s) for r in read(spark, SF_SMOKE, "events").groupBy("user_id").agg(F.count("*").alias("n"), F.max_by("event_type", "event_id").alias("s")).collect()}
    assert {k: v[0] for k, v in last.items()} == {k: v[0] for k, v in want.items()}
    assert last == want


def test_a_silent_instance_is_reported(spark, event_files, tmp_path):
    events.run_available(events.instance_state(stream(spark, event_files), quiet_ms=3600_000), "quiet", str(tmp_path / "q"), "update")
    rows = spark.table("quiet").collect()
    silent = {r.user_id for r in rows if r.state == "silent"}
    assert silent and silent <= {r.user_id for r in rows if r.state != "silent"}


def test_stream_join(spark, event_files, tmp_path):
    events.run_available(events.notice_then_end(stream(spark, event_files)), "sj", str(tmp_path / "a"))
    from shardgraph.catalog import CORE

    assert table_rows(spark, "sj", ["notice", "gone"]) == twin(CORE["ev_interval_join"].sql)
    events.run_available(events.notice_then_end(stream(spark, event_files), "left"), "slj", str(tmp_path / "b"))
    assert spark.table("slj").where("gone is not null").count() == spark.table("sj").count()


def test_late_rows_are_dropped_and_counted(spark, event_files, tmp_path):
    p = tmp_path / "late"
    e = spark.read.parquet(event_files[0])
    first, last = e.agg(F.min("ts"), F.max("ts")).first()
    e.where(F.col("ts") > F.lit(first) + F.expr("interval 10 days")).coalesce(1).write.parquet(str(p))
    s = events.tumbling(events.event_stream(spark, str(p), event_files[1], 1))
    ck = str(tmp_path / "ck")
    q = s.writeStream.format("memory").queryName("late1").outputMode("append").option("checkpointLocation", ck).trigger(availableNow=True).start()
    q.awaitTermination()
    e.where(F.col("ts") <= F.lit(first) + F.expr("interval 5 days")).coalesce(1).write.mode("append").parquet(str(p))
    q = s.writeStream.format("noop").outputMode("append").option("checkpointLocation", ck).trigger(availableNow=True).start()
    q.awaitTermination()
    dropped = sum(o["numRowsDroppedByWatermark"] for pr in q.recentProgress for o in pr["stateOperators"])
    assert dropped > 0


def test_block_stream_equals_batch_and_survives_replay(spark, tmp_path):
    rng = np.random.default_rng(2)
    x = rng.integers(-50, 50, (90, 3))
    v = spark.createDataFrame([(i, [int(c) for c in r]) for i, r in enumerate(x)], "vec_id bigint, q array<int>")
    c, cfg, plan = x[:3].astype(float), PartitionConfig(eps=None, blocks=3, radius_test=False), ShardPlan(3, 60)
    src = str(tmp_path / "src")
    for b in range(3):
        v.where(F.col("vec_id").between(30 * b, 30 * b + 29)).coalesce(1).write.mode("append").parquet(src)
    start = sample_state(preferences(v, c), np.full(3, 60))
    out = str(tmp_path / "out")
    assigner = blocks.BlockAssigner(out, c, plan, cfg, 90, start)
    s = spark.readStream.schema(v.schema).option("maxFilesPerTrigger", 1).parquet(src)
    blocks.partition_stream(s, assigner, str(tmp_path / "ck"))
    got = sorted((r.vec_id, r.shard_id, r.is_home) for r in spark.read.parquet(f"{out}/assignment").collect())
    homes = [g for g in got if g[2]]
    assert [h[0] for h in homes] == list(range(90))
    batches = sorted(p.name for p in (tmp_path / "out" / "assignment").iterdir() if p.is_dir())
    assert len(batches) == 3
    # the last batch delivered again changes nothing
    again = spark.read.parquet(f"{out}/assignment/{batches[2]}").where("is_home").select("vec_id").join(v, "vec_id")
    assigner(again, 2)
    assert sorted((r.vec_id, r.shard_id, r.is_home) for r in spark.read.parquet(f"{out}/assignment").collect()) == got
    routed = blocks.route_inserts(s, c, str(tmp_path / "routed"), str(tmp_path / "ck2"))
    assert routed is not None and spark.read.parquet(str(tmp_path / "routed")).count() == 90


def test_plans(spark):
    """Pushdown, pruning, no cartesian product, window group limit."""
    from shardgraph.catalog import CORE

    text = CORE["scan_parquet"].run(spark, SF_SMOKE)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(o_orderkey), IsNotNull(o_orderstatus)" in text and "o_totalprice" not in text.split("ReadSchema")[-1]
    assert "WindowGroupLimit" in CORE["preference_columns"].run(spark, SF_SMOKE)._jdf.queryExecution().toString()
    for name in ("join_range", "join_asof", "join_star", "preference_list"):
        assert "CartesianProduct" not in CORE[name].run(spark, SF_SMOKE)._jdf.queryExecution().toString()


def test_text_vectors(spark):
    d = tables.documents_768(spark, SF_SMOKE)
    n2 = [sum(x * x for x in r.q) for r in d.limit(20).collect()]
    assert all(0.95e6 < n < 1.05e6 for n in n2)
    shutil.rmtree("/tmp/none", ignore_errors=True)


def test_restart_continues_where_it_stopped(spark, event_files, tmp_path):
    e = spark.read.parquet(event_files[0])
    src, out, ck = str(tmp_path / "src"), str(tmp_path / "out"), str(tmp_path / "ck")
    for half in (0, 1):
        e.where(F.col("event_id") % 2 == half).coalesce(1).write.mode("append").parquet(src)
        s = events.with_zones(events.event_stream(spark, src, event_files[1], 1), read(spark, SF_SMOKE, "nation")).select("event_id", "n_name")
        q = s.writeStream.format("parquet").option("path", out).option("checkpointLocation", ck).trigger(availableNow=True).start()
        q.awaitTermination()
    ids = [r.event_id for r in spark.read.parquet(out).collect()]
    assert len(ids) == len(set(ids)) == e.count()


def test_output_modes(spark, event_files, tmp_path):
    s = lambda: events.tumbling(stream(spark, event_files))
    for mode in ("update", "complete"):
        events.run_available(s(), f"mode_{mode}", str(tmp_path / mode), mode)
    last = spark.table("mode_update").groupBy("hour", "event_type").agg(F.max("n").alias("n"))
    assert sorted(last.collect()) == sorted(spark.table("mode_complete").select("hour", "event_type", "n").collect())


def test_vectors_are_read_once(spark):
    """The partitioner evaluates its input once for all blocks, besides the ids for the block cuts."""
    reads = spark.sparkContext.accumulator(0)

    def watch(batches):
        for b in batches:
            reads.add(b.num_rows)
            yield b

    v = spark.range(200).select(F.col("id").alias("vec_id"), F.array(*[(F.col("id") * k % 17).cast("int") for k in (1, 3, 7)]).alias("q"))
    watched = v.mapInArrow(watch, v.schema)
    n0 = watched.select("vec_id", "q")
    partition_vectors(n0, np.array([[0.0, 0, 0], [9, 9, 9]]), ShardPlan(2, 300), PartitionConfig(blocks=4)).assignment.count()
    # one pass each: the block cuts, the preference lists; none per block
    assert reads.value <= 2 * 200


def test_hashed_units_equal_the_plan_of_words(spark):
    rows = [(1, "The cat, the CAT 42"), (2, None), (3, "  .. "), (4, "na\u00efve \u212a \u0130x"), (5, "a" * 50 + " b"), (1, "cat again"), (6, ""), (7, "word " * 3000)]
    texts = spark.createDataFrame(rows, "vec_id bigint, text string").repartition(3)
    for dims in (16, 768):
        want = {r.vec_id: r.q for r in tables.densify(tables.hashed_words(texts, dims), dims).collect()}
        df = tables.hashed_units(texts, dims)
        assert {r.vec_id: r.q for r in df.collect()} == want and df.count() == len(want)
    assert "Generate" not in tables.documents_768(spark, SF_SMOKE)._jdf.queryExecution().toString()
