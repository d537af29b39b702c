import shutil

from pyspark.sql import functions as F

from ripplerank.operators import decompose
from ripplerank.sources import edges as E
from ripplerank.streaming import buffer
from tests.helpers import SMALL, named, scores


def write_parts(spark, tmp_path):
    """Events in time order, a file for each part of them, so that every trigger sees one."""
    events = spark.read.parquet(f"{SMALL}/events.parquet").orderBy("ts", "event_id").collect()
    schema = spark.read.parquet(f"{SMALL}/events.parquet").schema
    for i in range(4):
        spark.createDataFrame(events[i * 250 : (i + 1) * 250], schema).coalesce(1).write.parquet(str(tmp_path / f"part{i}"))
    (tmp_path / "events.parquet").mkdir()
    for i in range(4):
        part = next((tmp_path / f"part{i}").glob("*.parquet"))
        shutil.copy(part, tmp_path / "events.parquet" / f"{i}.parquet")
    return str(tmp_path)


def test_batches_answer_like_one_batch(spark, tmp_path):
    d = write_parts(spark, tmp_path)
    g = named(spark, "cust_part")
    answers, checkpoint = str(tmp_path / "answers"), str(tmp_path / "checkpoint")
    requests = buffer.query_events(spark, d).where("request_id < 60")
    buffer.answer_batches(g, None, requests, answers, laps=2, k=5, checkpoint=checkpoint).awaitTermination()
    got = spark.read.parquet(f"{answers}/batch=*")
    users = spark.read.parquet(f"{d}/events.parquet").where("event_id < 60").select((F.col("user_id") + E.KIND["customer"]).alias("query")).distinct()
    want = scores(decompose.batch_ppr(g, None, users, 2, k=5))
    assert scores(got) == want
    n = got.count()
    buffer.answer_batches(g, None, requests, answers, laps=2, k=5, checkpoint=checkpoint).awaitTermination()  # nothing new
    assert spark.read.parquet(f"{answers}/batch=*").count() == n


def test_late_requests_are_dropped_once_the_watermark_has_passed(spark, tmp_path):
    rows = [[(1, "2024-01-01 00:00:00", 1), (2, "2024-01-10 00:00:00", 1)], [(3, "2024-01-10 01:00:00", 2)], [(4, "2024-01-01 05:00:00", 3), (5, "2024-01-11 02:00:00", 3)], [(6, "2024-01-12 03:00:00", 4)]]
    source = tmp_path / "events.parquet"
    source.mkdir()
    for i, part in enumerate(rows):  # one trigger for each file, in order
        df = spark.createDataFrame(part, "event_id long, t string, user_id long").select("event_id", F.col("t").cast("timestamp").alias("ts"), "user_id", F.lit("q").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
        df.coalesce(1).write.parquet(str(tmp_path / f"p{i}"))
        shutil.copy(next((tmp_path / f"p{i}").glob("*.parquet")), source / f"{i}.parquet")
        stream = buffer.windowed(buffer.query_events(spark, str(tmp_path)))
        q = stream.writeStream.outputMode("append").format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        q.awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out"))
    assert {str(r.start)[:10]: r.requests for r in got.collect()} == {"2024-01-01": 1, "2024-01-10": 2, "2024-01-11": 1}


def test_repeats_state_and_joined_answers(spark, tmp_path):
    d = write_parts(spark, tmp_path)
    raw = spark.read.parquet(f"{d}/events.parquet")
    users = raw.select("user_id").distinct().count()
    once = buffer.drain(buffer.unrepeated(buffer.query_events(spark, d), "400 days"), "once")
    assert once.count() == once.select("query").distinct().count() == users
    state = buffer.drain(buffer.per_query_state(buffer.query_events(spark, d)), "state", "update").groupBy("query").agg(F.max("requests").alias("n"))
    assert {r.query: r.n for r in state.collect()} == {r[0] + E.KIND["customer"]: r[1] for r in raw.groupBy("user_id").count().collect()}
    cached = once.select("query").distinct().select("query", F.lit(1).cast("long").alias("vertex"), F.lit(0.5).alias("score"), F.lit(1).alias("rank"))
    cached = spark.createDataFrame(cached.collect(), cached.schema)
    assert buffer.drain(buffer.with_answers(buffer.query_events(spark, d), cached), "joined").count() == raw.count()


def test_running_degrees(spark, tmp_path):
    E.edges_from_pairs(spark, [(1, 2), (1, 3), (2, 1)]).write.parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema("src long, dst long").parquet(str(tmp_path / "e"))
    got = buffer.drain(buffer.running_degrees(stream), "degrees", "complete")
    assert {r.src: r.out_deg for r in got.collect()} == {1: 2, 2: 1}
