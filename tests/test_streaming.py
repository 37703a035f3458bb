import datetime as dt

from pyspark.sql import Window
from pyspark.sql import functions as F

from geoprobe.streaming import monitor


def test_stream_equals_batch(spark, sf_dir, tmp_path):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").orderBy("ts").coalesce(1)
    pieces = events.withColumn("part", F.ntile(4).over(Window.orderBy("ts")))
    for i in range(1, 5):
        pieces.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = monitor.daily_density(monitor.captures_stream(spark, str(tmp_path / "in"), 10), late="3650 days")
    monitor.write_batches(stream, str(tmp_path / "out"), str(tmp_path / "check")).awaitTermination(120)
    got = {(str(r["window"]["start"])[:10], r["region"]): r["n"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    day = F.date_format("ts", "yyyy-MM-dd")
    want = {(r["d"], r["region"]): r["n"] for r in events.groupBy(day.alias("d"), F.pmod("user_id", F.lit(8)).alias("region")).agg(F.count("*").alias("n")).collect()}
    assert sum(got.values()) == sum(want.values()) and got == want


def stream_of(spark, rows, folder, parts=4):
    """Rows as a stream of files in time order, with a time-zoned event time."""
    pieces = rows.withColumn("part", F.ntile(parts).over(Window.orderBy("ts")))
    for i in range(1, parts + 1):
        pieces.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(str(folder / "in"))
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 10).parquet(str(folder / "in")).withColumn("ts", F.col("ts").cast("timestamp"))


def finished(stream, folder, mode="append"):
    query = stream.writeStream.outputMode(mode).format("memory").queryName("got").option("checkpointLocation", str(folder / "check")).trigger(availableNow=True).start()
    query.awaitTermination(120)
    return stream.sparkSession.table("got").collect()


def test_sliding_rate_equals_batch(spark, tmp_path):
    rows = spark.range(400).select((F.lit("2024-01-01").cast("timestamp") + F.expr("make_interval(0, 0, 0, 0, 0, int(id) * 3)")).alias("ts"), F.lit("m").alias("model"), F.when(F.col("id") % 2 == 0, "a").otherwise("b").alias("transform"), (F.col("id") % 3).cast("int").alias("pred0"), (F.col("id") % 5 % 3).cast("int").alias("pred"))
    rows = spark.createDataFrame(rows.collect(), rows.schema)
    got = {(r["window"]["start"], r["transform"]): (r["n"], r["switched"]) for r in finished(monitor.sliding_rate(stream_of(spark, rows, tmp_path), "3650 days"), tmp_path, "complete")}
    want = {}
    for r in rows.collect():
        start = r["ts"].replace(minute=r["ts"].minute // 10 * 10, second=0)
        for k in range(6):
            key = start - dt.timedelta(minutes=10 * k), r["transform"]
            n, s = want.get(key, (0, 0))
            want[key] = n + 1, s + (r["pred"] != r["pred0"])
    assert got == want


def test_sessions_and_late_rows(spark, tmp_path):
    at = lambda m: dt.datetime(2024, 1, 1) + dt.timedelta(minutes=m)
    rows = spark.createDataFrame([(1, at(0)), (1, at(20)), (1, at(60)), (2, at(5)), (1, at(200)), (3, at(300))], "user_id long, ts timestamp")
    got = {(r["user_id"], r["session_window"]["start"]): r["n"] for r in finished(monitor.sessions(stream_of(spark, rows, tmp_path, 1), late="10 minutes"), tmp_path, "complete")}
    assert got == {(1, at(0)): 2, (1, at(60)): 1, (2, at(5)): 1, (1, at(200)): 1, (3, at(300)): 1}


def test_seen_in_training_equals_batch(spark, sf_dir, tmp_path):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", "ts")
    site = F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    sites = events.where("event_id % 7 = 0").select(site.alias("site")).distinct()
    got = sorted(r["event_id"] for r in finished(monitor.seen_in_training(stream_of(spark, events, tmp_path), sites), tmp_path))
    assert got == sorted(r["event_id"] for r in events.withColumn("site", site).join(sites, "site", "left_semi").collect()) and got
