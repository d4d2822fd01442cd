from datetime import datetime, timedelta

from pyspark.sql import functions as F

from orderstat.streaming import windows

START = datetime(2024, 1, 1)


def _events(spark, rows):
    return spark.createDataFrame([(k, START + timedelta(minutes=m), t, float(v)) for k, m, t, v in rows], "event_id long, ts timestamp, event_type string, value double")


def _run(spark, found, base):
    job = found.writeStream.format("parquet").option("checkpointLocation", f"{base}/state").option("path", f"{base}/out").outputMode("append").trigger(availableNow=True).start()
    job.awaitTermination()
    return job, spark.read.schema(found.schema).parquet(f"{base}/out")


def _stream(spark, base, batches):
    for k, rows in enumerate(batches):
        _events(spark, rows).coalesce(1).write.mode("append").parquet(f"{base}/in")
    return spark.readStream.schema(_events(spark, []).schema).option("maxFilesPerTrigger", 1).parquet(f"{base}/in")


def test_medians_of_closed_windows(spark, tmp_path):
    base = f"file://{tmp_path}"
    first = [(k, k, "a", k) for k in range(60)] + [(100 + k, k, "b", 7) for k in range(3)]
    stream = _stream(spark, base, [first, [(200, 200, "a", 1)], [(201, 5, "a", 10**6), (202, 400, "a", 1)]])
    _, out = _run(spark, windows.stateful_ranks(stream, "value", F.window("ts", "1 hour"), ["event_type"], ["0.5", "1"], "10 minutes"), base)
    got = {(r["start"], r["event_type"], r["fraction"]): r["value"] for r in out.collect() if r["start"] == START}
    assert got == {(START, "a", 0.5): 29.0, (START, "a", 1.0): 59.0, (START, "b", 0.5): 7.0, (START, "b", 1.0): 7.0}  # the late row is not in it


def test_histograms_without_repeated_events(spark, tmp_path):
    base = f"file://{tmp_path}"
    stream = _stream(spark, base, [[(1, 1, "a", 5), (1, 1, "a", 5), (2, 2, "a", 6)], [(3, 300, "a", 1)], [(4, 900, "a", 1)]])
    counts = windows.window_counts(stream, "value", F.session_window("ts", "30 minutes"), ["event_type"], unique="event_id")
    _, out = _run(spark, counts, base)
    first = out.filter(F.col("start") < START + timedelta(minutes=10))
    assert sorted((r["value"], r["n"]) for r in first.collect()) == [(5.0, 1), (6.0, 1)]
    medians = windows.ranks_of_counts(first, ["event_type"], ["0.5"]).collect()
    assert [(r["rank"], r["value"]) for r in medians] == [(1, 5.0)]


def test_each_batch(spark):
    seen = []
    windows.each_batch(lambda df: seen.append(df.collect()), "value", ["0.5"], ["event_type"])(_events(spark, [(k, k, "a", k) for k in range(9)]), 0)
    assert [r["value"] for r in seen[0]] == [4.0]
