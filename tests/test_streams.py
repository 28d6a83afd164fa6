from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ldpspark.erm.descent import Model, gradient_sums, prepared, update
from ldpspark.functions import constants as C
from ldpspark.functions.rng import uniform
from ldpspark.sources.tables import load, read_any, save_model, load_model, write_reports
from ldpspark.streaming import stream

SF = "/root/testdata/sf0.001"
SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def split_files(spark, path):
    e = load(spark, SF, "events").orderBy("ts")
    rows = e.collect()
    for i in range(4):
        spark.createDataFrame(rows[i::4], SCHEMA).coalesce(1).write.parquet(f"{path}/f{i}")
    return f"{path}/*"


def signs(df):
    keep = F.when(uniform(F.col("event_id").cast("string"), "toss") < C.keep_probability(1.0), 1).otherwise(-1)
    return df.select("user_id", "event_id", "ts", F.lit(0).alias("j"), keep.alias("sign"))


def test_streamed_windows_equal_their_batch_twin(spark, tmp_path):
    path = split_files(spark, str(tmp_path / "in"))
    reports = signs(stream.timed(stream.event_stream(spark, path, SCHEMA, 1), "60 days"))
    q = stream.tumbling(reports, "7 days").writeStream.outputMode("complete").format("memory").queryName("w").start()
    q.processAllAvailable()
    q.stop()
    twin = stream.tumbling(signs(stream.timed(load(spark, SF, "events"))), "7 days")
    assert sorted(map(tuple, spark.table("w").collect())) == sorted(map(tuple, twin.collect()))


def test_one_report_per_user_and_period_and_late_rows(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00", 1), (2, "2024-01-02 00:00:00", 1), (3, "2024-01-30 00:00:00", 2)]
    make = lambda r, d: spark.createDataFrame(r, "event_id int, ts string, user_id int").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(f"{tmp_path}/s/{d}")
    make(rows, "a")
    got = []
    events = stream.timed(spark.readStream.schema("event_id int, ts timestamp_ntz, user_id int").parquet(f"{tmp_path}/s/*"), "1 day")
    q = stream.one_per_period(events, "user_id", "7 days").writeStream.foreachBatch(lambda df, n: got.extend(r["event_id"] for r in df.collect())).start()
    q.processAllAvailable()
    make([(4, "2024-01-03 00:00:00", 9)], "b")  # behind the watermark
    q.processAllAvailable()
    q.stop()
    assert len(got) == 2 and 3 in got and 4 not in got


def test_budget_gate_refuses_what_passes_the_limit(spark, tmp_path):
    path = split_files(spark, str(tmp_path / "in"))
    reports = signs(stream.timed(stream.event_stream(spark, path, SCHEMA, 1)))
    q = stream.budget_gate(reports, 1.0, 0.25).writeStream.outputMode("update").format("memory").queryName("gate").start()
    q.processAllAvailable()
    q.stop()
    last = {r["user_id"]: r for r in spark.table("gate").groupBy("user_id").agg(F.max("reports").alias("reports"), F.max("refused").alias("refused")).collect()}
    for r in load(spark, SF, "events").groupBy("user_id").count().collect():
        assert last[r["user_id"]]["reports"] == min(4, r["count"]) and last[r["user_id"]]["refused"] == max(0, r["count"] - 4)


def test_budget_gate_forgets_who_is_silent_for_a_horizon(spark, tmp_path):
    make = lambda r, d: spark.createDataFrame(r, "event_id int, ts string, user_id long").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(f"{tmp_path}/g/{d}")
    make([(1, "2024-01-01 00:00:00", 1), (2, "2024-01-01 01:00:00", 1), (3, "2024-01-01 01:00:00", 2)], "a")
    events = stream.timed(spark.readStream.schema("event_id int, ts timestamp_ntz, user_id long").parquet(f"{tmp_path}/g/*"), "1 hour")
    q = stream.budget_gate(events, 0.25, 0.25, 86_400).writeStream.outputMode("update").format("memory").queryName("forgets").start()
    for day, part in (("10", "b"), ("12", "c")):
        q.processAllAvailable()
        make([(4, f"2024-01-{day} 00:00:00", 3 if part == "b" else 1)], part)
    q.processAllAvailable()
    q.stop()
    got = [(r["user_id"], r["reports"], r["refused"]) for r in spark.table("forgets").collect()]
    assert sorted(got) == [(1, 1, 0), (1, 1, 1), (2, 1, 0), (3, 1, 0)]


def test_stream_trainer_replays_to_the_same_weights(spark, tmp_path):
    rng = np.random.default_rng(1)
    rows = [(f"u{i}", i, [float(v) for v in rng.uniform(-1, 1, 3)], float(rng.choice([-1, 1]))) for i in range(250)]
    frames = [spark.createDataFrame([(k, n, x, y) for n, (k, _, x, y) in enumerate(part)], "ukey string, ts int, x array<double>, y double") for part in (rows[:130], rows[130:])]
    trainer = stream.StreamTrainer(spark, str(tmp_path / "model"), 3, 1.0, 100, "logistic")
    trainer(frames[0], 0)
    trainer(frames[1], 1)
    trainer(frames[1], 1)  # the batch comes again
    model = Model("m", 3, 1.0, 1)
    for step, part in enumerate((rows[:100], rows[100:200])):
        users = prepared(spark.createDataFrame([(k, x, y) for k, _, x, y in part], "ukey string, x array<double>, y double"), mode="xx").withColumn("ub", F.lit(0.0))
        sums = {r["j"]: (r["total"], r["reports"]) for r in gradient_sums(users, [model], 0, "logistic", 1e-4).collect()}
        update(model, sums, step, 1.0, 0.0)
    assert np.allclose(trainer.weights(1), model.weights)


def test_sources_and_sinks(spark, tmp_path):
    reports = spark.range(100).select(F.col("id").cast("string").alias("ukey"), (F.col("id") % 3).alias("j"), F.lit(1).alias("sign"))
    write_reports(reports, str(tmp_path / "r"), by="j")
    back = read_any(spark, str(tmp_path / "r"), "parquet")
    assert back.where("j = 1").count() == 33 and "PartitionFilters: [isnotnull(j" in back.where("j = 1")._jdf.queryExecution().executedPlan().toString()
    for kind in ("csv", "json", "orc"):
        w = reports.write
        {"csv": w.option("header", True).csv, "json": w.json, "orc": w.orc}[kind](str(tmp_path / kind))
        assert read_any(spark, str(tmp_path / kind), kind, "ukey string, j long, sign int").count() == 100
    save_model(spark, str(tmp_path / "m"), "a", 1, [0.1, 0.2])
    save_model(spark, str(tmp_path / "m"), "a", 2, [0.3, 0.4])
    assert load_model(spark, str(tmp_path / "m"), "a") == [0.3, 0.4]
