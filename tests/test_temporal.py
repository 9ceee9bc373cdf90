"""As-of and range joins, and the stateful stream operator."""

from datetime import datetime, timedelta

from rulegraph.operators.temporal import as_of_join, range_join
from rulegraph.streaming.incremental import patient_updates


def test_as_of_join_equals_brute_force(spark):
    left = [(u, t) for u in (1, 2, 3) for t in (0, 5, 10)]
    right = [(1, 3, 30), (1, 5, 50), (1, 5, 51), (2, 11, 7)]
    got = as_of_join(spark.createDataFrame(left, "u int, t int"), spark.createDataFrame(right, "u int, t int, v int"), ["u"], "t", "v")
    want = {(u, t, max(((b, v) for a, b, v in right if a == u and b <= t), default=(None, None))[1]) for u, t in left}
    assert {tuple(r) for r in got.select("u", "t", "v").collect()} == want


def test_range_join_equals_brute_force(spark):
    points = [(k, t) for k in (1, 2) for t in range(0, 40, 3)]
    ranges = [(1, 2, 9), (1, 8, 30), (2, 12, 12), (2, 39, 50)]
    got = range_join(spark.createDataFrame(points, "k int, t int"), spark.createDataFrame(ranges, "k int, a int, b int"), ["k"], "t", "a", "b", 10)
    assert {(r["k"], r["t"], r["a"]) for r in got.collect()} == {(k, t, a) for k, t in points for q, a, b in ranges if k == q and a <= t <= b}


def test_patient_state_follows_a_stream(spark, tmp_path):
    day = lambda n: datetime(2024, 1, 1) + timedelta(days=n)
    batches = [[(1, "exposure", day(0)), (2, "symptom", day(3))], [(1, "symptom", day(5)), (2, "exposure", day(4))], [(1, "tested", day(6))]]
    folder = str(tmp_path / "in")
    for b in batches:
        spark.createDataFrame(b, "user_id bigint, kind string, ts timestamp").coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema("user_id bigint, kind string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(folder)
    seen = []
    query = patient_updates(stream).writeStream.outputMode("update").foreachBatch(lambda df, n: seen.extend((n, r["user_id"], r["positive"]) for r in df.collect())).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert [(u, p) for _, u, p in sorted(seen)] == [(1, True), (1, False)]
