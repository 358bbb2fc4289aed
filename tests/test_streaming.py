import numpy as np

from joinlearn.sources.tables import table
from joinlearn.streaming import moments as st
from pyspark.sql import functions as F


def _parts(spark, sf, tmp_path, n=4):
    events = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path = str(tmp_path / "in")
    for i in range(n):
        events.where(F.col("event_id") % n == i).coalesce(1).write.mode("append").parquet(path)
    return events, path


def test_deltas_add_up_to_the_batch(spark, sf, tmp_path):
    events, path = _parts(spark, sf, tmp_path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    q = st.maintain(stream, ["event_type"], "value", str(tmp_path / "out"), str(tmp_path / "cp"))
    q.awaitTermination(120)
    got = {r.event_type: r for r in st.current(spark, ["event_type"], str(tmp_path / "out")).collect()}
    for r in st.sums(events, ["event_type"], "value").collect():
        assert got[r.event_type].n == r.n and np.isclose(got[r.event_type].s1, r.s1) and np.isclose(got[r.event_type].s2, r.s2)


def test_retractions(spark):
    df = spark.createDataFrame([("a", 2.0, 1), ("a", 3.0, 1), ("a", 2.0, -1)], "k string, v double, sign int")
    r = st.sums(df, ["k"], "v", "sign").first()
    assert (r.n, r.s1, r.s2) == (1, 3.0, 9.0)


def test_running_state_and_windows(spark, sf, tmp_path):
    events, path = _parts(spark, sf, tmp_path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 2).parquet(path)
    q = st.running(stream, "user_id", "value").writeStream.outputMode("update").format("memory").queryName("running_users").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {r.user_id: r.n for r in spark.sql("select user_id, max(n) as n from running_users group by 1").collect()}
    assert got == {r.user_id: r["count"] for r in events.groupBy("user_id").count().collect()}
    w = st.windowed(spark.readStream.schema(events.schema).parquet(path), ["event_type"], "value", late="1 day")
    q = w.writeStream.outputMode("append").format("memory").queryName("windows_out").option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    closed = spark.table("windows_out").agg(F.sum("n")).first()[0]
    assert 0 < closed <= events.count()
    d = st.distinct_events(spark.readStream.schema(events.schema).parquet(path)).join(spark.createDataFrame([("click", 1)], "event_type string, w int"), "event_type")
    q = d.writeStream.outputMode("append").format("memory").queryName("clicks_out").option("checkpointLocation", str(tmp_path / "c3")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.table("clicks_out").count() == events.where("event_type = 'click'").count()
