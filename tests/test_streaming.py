from pyspark.sql import functions as F

from fuzzcount.streaming import users

SF = "/root/testdata/sf0.001"


def test_sessions_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    (tmp_path / "in").mkdir()
    events.coalesce(1).write.parquet(str(tmp_path / "in" / "a"))
    stream = users.stream_of(spark, str(tmp_path / "in" / "a"))
    query = users.run_to(users.sessions(stream), str(tmp_path / "out"), str(tmp_path / "cp"))
    query.awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out"))
    want = users.sessions(events)
    late = want.agg(F.max("stop")).first()[0]
    closed = want.where(F.col("stop") < F.lit(late) - F.expr("INTERVAL 3 HOURS"))
    assert closed.exceptAll(got).count() == 0 and got.exceptAll(want).count() == 0


def test_release_once_per_user(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    query = users.run_to(users.first_releases(users.stream_of(spark, str(tmp_path / "in")), "60 days"), str(tmp_path / "out"), str(tmp_path / "cp"))
    query.awaitTermination(120)
    assert spark.read.parquet(str(tmp_path / "out")).count() == events.select("user_id").distinct().count()


def _in(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(3, "user_id").write.parquet(str(tmp_path / "in"))
    return events, users.stream_of(spark, str(tmp_path / "in"))


def test_two_streams_joined_equal_batch(spark, tmp_path):
    events, stream = _in(spark, tmp_path)
    pick = lambda df: (df.where("event_type = 'view'"), df.where("event_type = 'click'"))
    joined = users.followed_by(*pick(stream), within="2 days", delay="60 days")
    users.run_to(joined, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination(120)
    got, want = spark.read.parquet(str(tmp_path / "out")), users.followed_by(*pick(events), within="2 days")
    assert want.count() > 0 and got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_events_beside_a_table(spark, tmp_path):
    events, stream = _in(spark, tmp_path)
    static = events.groupBy("user_id").agg(F.count("*").alias("n"))
    users.run_to(users.labelled(stream, static), str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination(120)
    assert spark.read.parquet(str(tmp_path / "out")).where("n > 0").count() == events.count()


def test_late_events_are_dropped(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00", 1), (2, "2024-01-10 00:00:00", 2), (3, "2024-01-01 00:10:00", 3), (4, "2024-01-20 00:00:00", 4)]
    for i, row in enumerate(rows):
        frame = spark.createDataFrame([row], "event_id bigint, ts string, user_id bigint").selectExpr("event_id", "CAST(ts AS timestamp) AS ts", "user_id", "'view' AS event_type", "0D AS value", "'' AS props")
        frame.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        users.run_to(users.tumbling(users.stream_of(spark, str(tmp_path / "in"))), str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination(120)
    got = {str(r["start"]): r["users"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got["2024-01-01 00:00:00"] == 1 and got["2024-01-10 00:00:00"] == 1


def test_answers_are_given_once(spark, tmp_path):
    events, stream = _in(spark, tmp_path)
    query = users.memoised_answers(stream.select("event_id", "ts", "user_id", "event_type")).writeStream.format("memory").queryName("answers").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    query.awaitTermination(180)
    got = spark.table("answers").join(events.select("event_id", "event_type"), "event_id")
    assert got.count() == events.count()
    assert got.groupBy("user_id", "event_type").agg(F.count_distinct("answer").alias("n")).where("n > 1").count() == 0
    assert got.groupBy("user_id", "event_type").agg(F.max("asked").alias("most"), F.count("*").alias("n")).where("most <> n").count() == 0


def test_first_event_of_a_batch(spark):
    events = spark.read.parquet(f"{SF}/events.parquet")
    firsts = {r["user_id"]: r["ts"] for r in users.first_releases(events).collect()}
    assert firsts == {r["user_id"]: r["ts"] for r in events.groupBy("user_id").agg(F.min("ts").alias("ts")).collect()}
