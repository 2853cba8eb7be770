from pyspark.sql import functions as F

from textfactor.operators import factorize
from textfactor.streaming import streams

EVENTS = "event_id long, ts timestamp, user_id long, event_type string"


def rows(spark):
    data = [(i, f"2024-01-0{1 + i // 8} 0{i % 8}:10:00", i % 2, ["view", "click", "buy"][i % 3]) for i in range(24)]
    return spark.createDataFrame(data, "event_id long, ts string, user_id long, event_type string").withColumn("ts", F.col("ts").cast("timestamp"))


def run(query, name):
    q = query.writeStream.outputMode("append").format("memory").queryName(name).start()
    q.processAllAvailable()
    q.stop()


def test_encode_stream(spark, tmp_path):
    t = spark.createDataFrame([(1, "abcabcabc"), (2, "xyxyxy")], "text_id long, text string")
    t.write.parquet(str(tmp_path / "t"))
    run(streams.encode_stream(streams.read_stream(spark, str(tmp_path / "t"), t.schema)), "coded")
    assert sorted(map(tuple, spark.table("coded").collect())) == sorted(map(tuple, factorize.factorize(t).collect()))


def test_windows_equal_batch(spark, tmp_path):
    e = rows(spark)
    e.repartition(1).sortWithinPartitions("ts").write.parquet(str(tmp_path / "e"))
    batch = {r["start"]: r["text"] for r in streams.window_texts(e).collect()}
    run(streams.window_texts(streams.read_stream(spark, str(tmp_path / "e"), e.schema)), "windows")
    got = {r["start"]: r["text"] for r in spark.table("windows").collect()}
    assert got and all(batch[k] == v for k, v in got.items())


def test_late_rows_are_dropped(spark, tmp_path):
    e = rows(spark)
    e.where("event_id >= 8").repartition(1).write.parquet(str(tmp_path / "e"))
    e.where("event_id < 8").repartition(1).write.mode("append").parquet(str(tmp_path / "e"))
    run(streams.window_texts(streams.read_stream(spark, str(tmp_path / "e"), e.schema), late="1 hour"), "late")
    assert len(spark.table("late").collect()) <= 2


def test_incremental_parse():
    assert streams.incremental_parse("abcd", "abcdab") == [(5, 6, 1)]
    assert streams.incremental_parse("", "xyz") == []


def test_stateful_encode(spark, tmp_path):
    a = spark.createDataFrame([("u", 1, "hello world"), ("v", 1, "zz")], "k string, o long, x string")
    b = spark.createDataFrame([("u", 2, "hello again")], "k string, o long, x string")
    a.repartition(1).write.parquet(str(tmp_path / "s"))
    b.repartition(1).write.mode("append").parquet(str(tmp_path / "s"))
    run(streams.stateful_encode(streams.read_stream(spark, str(tmp_path / "s"), a.schema), "k", "o", "x"), "state")
    got = [tuple(r) for r in spark.table("state").collect()]
    assert any(k == "u" and n >= 5 for k, _, n, _ in got)
