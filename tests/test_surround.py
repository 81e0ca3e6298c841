"""Sources, sinks, streams, and the SQL surface."""

import pytest
from pyspark.sql import functions as F

from nearfield import sql
from nearfield.sources import formats, tables
from nearfield.streaming import thermo

SMALL = "/root/testdata/sf0.001"


def test_matrix_market_is_read_in_parts(spark, tmp_path):
    formats.register(spark)
    entries = [(i, j, i + j / 10) for i in range(1, 60) for j in range(1, 4)]
    path = tmp_path / "m.mtx"
    path.write_text("%%MatrixMarket matrix coordinate real general\n% a remark\n59 3 177\n" + "".join(f"{i} {j} {v}\n" for i, j, v in entries))
    for split in (7, 64, 10_000):
        got = spark.read.format("matrix_market").option("split", split).load(str(path))
        assert sorted(map(tuple, got.collect())) == [(i - 1, j - 1, v) for i, j, v in entries]
    path.write_text("%%MatrixMarket matrix coordinate pattern symmetric\n2 2 2\n1 1\n2 1\n")
    assert sorted(map(tuple, spark.read.format("matrix_market").load(str(path)).collect())) == [(0, 0, 1.0), (0, 1, 1.0), (1, 0, 1.0)]
    out = str(tmp_path / "out")
    formats.write_matrix_market(spark.createDataFrame([(1, 0, 2.5), (0, 0, 1.0)], "row long, col long, val double"), out)
    assert [r.value for r in spark.read.text(out).collect()] == ["1 1 1.0", "2 1 2.5"]


def test_coordinate_files(spark, tmp_path):
    formats.register(spark)
    path = tmp_path / "a.xyz"
    path.write_text("2\nfirst\nO 0 0 0\nH 0.96 0 0\n1\nsecond\nX 1 2 3\n")
    assert [tuple(r) for r in spark.read.format("xyz").load(str(path)).collect()] == [(0, 0, "O", 0.0, 0.0, 0.0), (0, 1, "H", 0.96, 0.0, 0.0), (1, 0, "X", 1.0, 2.0, 3.0)]


@pytest.mark.parametrize("kind", ["parquet", "orc", "csv", "json"])
def test_readers(spark, tmp_path, kind):
    df = spark.createDataFrame([(1, "a", 0.5), (2, None, 1.5)], "id long, s string, v double")
    df.write.format(kind).save(f"{tmp_path}/{kind}")
    got = tables.read(spark, f"{tmp_path}/{kind}", kind, "id long, s string, v double")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, df.collect()))


def test_a_step_is_overwritten_alone(spark, tmp_path):
    m = spark.createDataFrame([(0, 0, 1.0), (1, 0, 2.0)], "row long, col long, val double")
    for step, factor in ((1, 1.0), (2, 2.0), (1, 5.0)):
        tables.write_matrix(m.withColumn("val", F.col("val") * factor), f"{tmp_path}/m", 4, step)
    got = spark.read.parquet(f"{tmp_path}/m")
    assert {r.step: r.s for r in got.groupBy("step").agg(F.sum("val").alias("s")).collect()} == {1: 15.0, 2: 6.0}
    plan = got.where("step = 2")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(step" in plan


def test_copies_and_checkpoints(spark):
    r = tables.repeated(spark.range(3), 4, "id", 3)
    assert sorted(x.id for x in r.collect()) == list(range(12))
    assert tables.cut(r).count() == 12
    tables.run(r)


@pytest.fixture
def events(spark, tmp_path):
    """The events table as one file of its own folder, which a stream can watch."""
    spark.read.parquet(f"{SMALL}/events.parquet").orderBy("ts").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    batch = spark.read.parquet(f"{tmp_path}/events.parquet")
    stream = spark.readStream.schema(batch.schema).parquet(f"{tmp_path}/events.parquet")
    cols = ["event_id", "user_id", tables.utc("ts").alias("ts"), "value"]
    return batch.select(*cols), stream.select(*cols)


@pytest.mark.parametrize(("name", "build"), [("tumbling", thermo.tumbling), ("sliding", thermo.sliding), ("sessions", thermo.sessions)])
def test_stream_is_the_batch(spark, events, name, build):
    batch, stream = events
    got = thermo.run_to_memory(build(stream), f"w_{name}", "append" if name == "sessions" else "complete")
    want = build(batch)
    r = lambda df: sorted(tuple(x if not isinstance(x, float) else round(x, 6) for x in row) for row in df.collect())
    got, want = r(got), r(want)
    if name == "sessions":  # the last windows are open at the watermark
        assert set(got) <= set(want) and len(got) > 0.8 * len(want)
    else:
        assert got == want


def test_readings_past_the_watermark_are_dropped(spark, tmp_path):
    rows = [(1, 1, "2024-01-01 00:00:00", 1.0), (2, 1, "2024-01-03 00:00:00", 2.0)]
    make = lambda r: spark.createDataFrame(r, "event_id long, user_id long, ts string, value double").withColumn("ts", F.to_timestamp("ts"))
    make(rows).coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(make(rows).schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = thermo.tumbling(stream).writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{tmp_path}/c").option("path", f"{tmp_path}/out")
    run = lambda: q.trigger(availableNow=True).start().awaitTermination()
    run()
    make([(3, 1, "2024-01-01 01:00:00", 9.0), (4, 1, "2024-01-05 00:00:00", 3.0)]).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    run()  # from the checkpoint: the late reading finds its window closed
    got = sorted((str(r.start), r.n) for r in spark.read.parquet(f"{tmp_path}/out").collect())
    assert got == [("2024-01-01 00:00:00", 1), ("2024-01-03 00:00:00", 1)]


def test_thermostat_keeps_state(spark, events):
    batch, stream = events
    got = {r.user_id: r for r in thermo.run_to_memory(thermo.thermostat(stream, 2000.0), "thermo", "update").collect()}
    want = batch.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("value") * F.col("value")).alias("t")).collect()
    assert {u: (r.n, round(r.temperature, 6)) for u, r in got.items()} == {r.user_id: (r.n, round(r.t, 6)) for r in want}
    assert all(r.gamma >= 0 for r in got.values())


def test_joins_of_streams(spark, events):
    batch, stream = events
    masses = spark.createDataFrame([(0, 2.0)], "user_id long, mass double")
    got = thermo.run_to_memory(thermo.with_masses(stream, masses), "masses")
    assert got.count() == batch.count() and got.where("user_id = 0").agg(F.min("mass")).first()[0] == 2.0
    pairs = thermo.run_to_memory(thermo.paired_readings(stream, stream, "2 hours"), "pairs")
    b = batch.alias("a").join(batch.alias("b"), F.expr("a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOURS AND a.event_id <> b.event_id"))
    assert pairs.count() == b.count()


def test_a_repeated_batch_replaces_itself(spark, tmp_path):
    write = thermo.upsert_by_step(str(tmp_path / "s"))
    for _ in range(2):
        write(spark.range(5), 3)
    assert spark.read.parquet(str(tmp_path / "s")).count() == 5


def test_sql_surface(spark):
    sql.register(spark)
    m = spark.createDataFrame([(0, 0, 4.0), (1, 1, 2.0), (0, 1, 1.0), (1, 0, 1.0)], "row long, col long, val double")
    m.createOrReplaceTempView("m")
    assert sorted(r.t for r in spark.sql("SELECT t FROM pattern_cells(0.0D, 0.0D, 0.0D, 10.0D, 10.0D, 10.0D, 3.0D) LIMIT 3", ).collect())[0] is not None
    n = spark.sql("SELECT count(*) AS n FROM pattern_cells(1.0D, 1.0D, 1.0D, 9.0D, 9.0D, 9.0D, 3.0D)").first().n
    assert n == 27
    got = spark.sql("SELECT round(overlap_of('O', 'H', r), 9) AS s FROM VALUES (1.0D), (9.0D) AS t(r)").collect()
    assert got[0].s > 0 and got[1].s == 0
    t = spark.sql("SELECT dense_trace(row, col, val) AS t FROM m").first().t
    assert t == 6.0
    assert sql.run(spark, "SELECT count(*) AS n FROM m WHERE val > {least}", least=1.5).first().n == 2
    best = sql.top_per_group(m, "col", "val", 1)
    assert sorted((r.col, r.val) for r in best.collect()) == [(0, 4.0), (1, 2.0)]
    assert sql.lateral_top(spark, "m", 1).count() == 2


def test_bucketed_tables_join_without_a_shuffle(spark):
    from nearfield.sources.tables import write_bucketed

    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for name in ("left_rows", "right_rows"):
            write_bucketed(spark.range(1000).selectExpr("id AS k", f"id * 2 AS {name}_v"), name, "k", 4)
        both = spark.table("left_rows").join(spark.table("right_rows"), "k")
        plan = both._jdf.queryExecution().executedPlan().toString()
        assert "Exchange hashpartitioning" not in plan and both.count() == 1000
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
        for name in ("left_rows", "right_rows"):
            spark.sql(f"DROP TABLE IF EXISTS {name}")


def test_a_loop_s_rows_lose_their_estimate(spark):
    from nearfield.sources.tables import passing_folder, remove_folder, settle

    df = spark.range(50).selectExpr("id AS a", "id % 3 AS b")
    for _ in range(12):  # a checkpoint's estimate would be squared each time
        df = settle(df.join(df.withColumnRenamed("b", "c"), "a").select("a", "b"))
    assert df.count() == 50 and df.schema.names == ["a", "b"]
    folder = passing_folder(spark, "t")
    df.write.parquet(folder)
    remove_folder(spark, folder)
    import os

    assert not os.path.exists(folder.removeprefix("file:").replace("///", "/"))
