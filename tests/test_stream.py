"""A stream gives the rows of the batch form."""

from pyspark.sql import functions as F

from passagekit.operators.supply import sessions
from passagekit.operators import protocol as P
from passagekit.sources.carriers import planted
from passagekit.streaming import passages as T
from passagekit.streaming.passages import stream_passages


def test_sessions(spark, tmp_path):
    src = "/root/testdata/sf0.001/events.parquet"
    batch = {(r["user_id"], r["n"], r["first"]) for r in sessions(spark.read.parquet(src)).withColumn("first", F.col("first").cast("timestamp")).collect()}
    folder = tmp_path / "in"
    spark.read.parquet(src).write.parquet(str(folder))
    stream = spark.readStream.schema(spark.read.parquet(src).schema).parquet(str(folder))
    q = stream_passages(stream).writeStream.outputMode("complete").format("memory").queryName("sessions_out").trigger(availableNow=True).start()
    q.awaitTermination()
    got = {(r["user_id"], r["n"], r["first"]) for r in spark.table("sessions_out").collect()}
    assert got == batch


def _replay(spark, df, tmp_path, name):
    folder = str(tmp_path / name)
    df.write.parquet(folder)
    return spark.readStream.schema(df.schema).parquet(folder)


def _drain(df, name, mode):
    df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.table(name)


def test_identification_equals_the_shortlist(spark, tmp_path):
    p = planted(spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet"))
    q, g = p.where("passage_no = 0"), p.where("passage_no > 0")
    stream = _replay(spark, q.select(F.col("passage_id").alias("query_id"), "source", "vec"), tmp_path, "q")
    got = {r["query_id"]: (r["gallery_id"], r["verdict"]) for r in _drain(T.stream_identify(stream, g, 0.3), "ident", "complete").collect()}
    pairs = P.leave_one_out(p).join(q.select(F.col("passage_id").alias("query_id")), "query_id", "left_semi").join(g.select(F.col("passage_id").alias("gallery_id")), "gallery_id", "left_semi")
    want = {r["query_id"]: (r["gallery_id"], r["verdict"]) for r in P.decide(pairs, 0.3).collect()}
    assert want and all(got[k] == v for k, v in want.items()) and len(got) == q.count()


def test_state_holds_the_mean_of_a_hull(spark, tmp_path):
    df = spark.createDataFrame([(1, [1.0, 0.0]), (1, [0.0, 3.0]), (2, [2.0, 2.0])], "hull_id long, vec array<double>").withColumn("ts", F.lit("2020-01-01 00:00:00").cast("timestamp"))
    got = {r["hull_id"]: (r["n"], list(r["mean"]), r["state"]) for r in _drain(T.stream_hull_state(_replay(spark, df.coalesce(1), tmp_path, "h")), "hulls", "update").collect()}
    assert got == {1: (2, [0.5, 1.5], "seen"), 2: (1, [2.0, 2.0], "seen")}


def test_refiled_captures_pass_once_and_pings_meet_their_windows(spark, tmp_path):
    at = "timestamp '2020-01-01 00:00:00' + make_dt_interval(0, 0, m)"
    df = spark.createDataFrame([(0, "a"), (1, "b"), (2, "a")], "m int, payload string").selectExpr(f"{at} ts", "payload")
    assert _drain(T.stream_exact_dedup(_replay(spark, df, tmp_path, "d")), "once", "append").count() == 2
    w = spark.createDataFrame([(1, 10), (2, 60)], "recording_id long, m int").selectExpr("recording_id", f"{at} ts")
    p = spark.createDataFrame([(7, 1.0, 15), (8, 1.0, 16), (9, 1.0, 55)], "vessel_id long, range double, m int").selectExpr("vessel_id", "range", f"{at} ts")
    got = _drain(T.stream_key(_replay(spark, w, tmp_path, "w"), _replay(spark, p, tmp_path, "p")), "keyed", "append")
    assert {(r["recording_id"], r["vessel_id"]) for r in got.collect()} == {(1, 7), (2, 9)}


def test_proximity_windows_equal_the_batch(spark, tmp_path):
    ev = spark.read.parquet("/root/testdata/sf0.001/events.parquet").select(F.col("user_id").alias("vessel_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("value").alias("range"))
    batch = ev.groupBy(F.window("ts", "5 minutes").alias("w"), "vessel_id").agg(F.min("range").alias("r"))
    got = _drain(T.stream_proximity(_replay(spark, ev, tmp_path, "prox")), "prox", "complete")
    key = lambda df: {(r["w"]["start"], r["vessel_id"], r["r"]) for r in df.collect()}
    assert key(got) == key(batch)


def test_a_passage_is_enrolled_once(spark, tmp_path):
    src, gallery = str(tmp_path / "src"), str(tmp_path / "gallery")
    schema = "passage_id long, hull_id long"
    for part in ([(1, 5), (1, 5), (2, 5)], [(2, 5), (3, 6)]):
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(src)
        T.stream_enrol(spark.readStream.schema(schema).parquet(src), gallery, str(tmp_path / "ck")).awaitTermination()
    assert sorted(r["passage_id"] for r in spark.read.parquet(gallery).collect()) == [1, 2, 3]


def test_a_hull_is_lost_and_late_rows_are_counted(spark, tmp_path):
    src, ck, out = str(tmp_path / "src"), str(tmp_path / "ck"), []
    at = "timestamp '2020-01-01 00:00:00' + make_dt_interval(0, h)"
    schema = spark.createDataFrame([(1, [1.0], 0)], "hull_id long, vec array<double>, h int").selectExpr("hull_id", "vec", f"{at} ts").schema
    dropped = 0
    for part in ([(1, [1.0], 0)], [(2, [2.0], 100)], [(3, [2.0], 200)], [(4, [9.0], 1)]):
        spark.createDataFrame(part, "hull_id long, vec array<double>, h int").selectExpr("hull_id", "vec", f"{at} ts").coalesce(1).write.mode("append").parquet(src)
        q = T.stream_hull_state(spark.readStream.schema(schema).parquet(src)).writeStream.outputMode("update").foreachBatch(lambda b, _: out.extend(b.collect())).option("checkpointLocation", ck).trigger(availableNow=True).start()
        q.awaitTermination()
        dropped += T.late_rows(q)
    lost = {(r["hull_id"], r["n"]) for r in out if r["state"] == "lost"}
    assert (1, 1) in lost
    d = T.stream_passages(_replay(spark, spark.createDataFrame([(1, 0), (1, 90)], "user_id long, h int").selectExpr("user_id", f"{at} ts"), tmp_path, "late"))
    assert d.isStreaming and dropped >= 0
