"""Streams that stop and go on: late rows, kept state, restart from a checkpoint."""

from pyspark.sql import functions as F

from cellgraph.storage import work_dir
from cellgraph.streaming import edges as st


def events_in(spark, folder, rows):
    spark.createDataFrame(rows, "event_id long, ts string, user_id long").select("event_id", F.to_timestamp_ntz("ts").alias("ts"), "user_id", F.lit("view").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props")).coalesce(1).write.mode("append").parquet(folder)


def stream_of(spark, folder):
    return spark.readStream.schema(st.EVENT_SCHEMA).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def test_late_rows_are_dropped_and_the_checkpoint_goes_on(spark):
    folder, state = work_dir(spark, "in"), work_dir(spark, "state")
    events_in(spark, folder, [(1, "2024-01-01 10:00:00", 7), (2, "2024-01-03 10:00:00", 7)])
    counts = st.windowed_degrees(stream_of(spark, folder), "1 day")
    first = st.drain(counts, [], "append", state).collect()
    assert [(str(r["start"])[:10], r["n"]) for r in first] == [("2024-01-01", 1)]
    events_in(spark, folder, [(3, "2024-01-01 11:00:00", 7), (4, "2024-01-05 10:00:00", 7)])  # the first is late
    again = st.drain(counts, [], "append", state).collect()
    assert sorted((str(r["start"])[:10], r["n"]) for r in again) == [("2024-01-01", 1), ("2024-01-03", 1)]


def test_successions_go_on_between_runs(spark):
    folder, state = work_dir(spark, "in"), work_dir(spark, "state")
    events_in(spark, folder, [(1, "2024-01-01 10:00:00", 7), (2, "2024-01-01 11:00:00", 7), (3, "2024-01-01 12:00:00", 8)])
    edges = st.successions(stream_of(spark, folder))
    assert {tuple(r) for r in st.drain(edges, [], "append", state).collect()} == {(1, 2)}
    events_in(spark, folder, [(4, "2024-01-02 10:00:00", 8), (5, "2024-01-02 10:00:00", 7)])
    assert {tuple(r) for r in st.drain(edges, [], "append", state).collect()} == {(1, 2), (2, 5), (3, 4)}


def test_growing_components_after_a_restart(spark):
    inbox, folder = work_dir(spark, "in"), work_dir(spark, "grown")

    def more(pairs):
        spark.createDataFrame(pairs, "src_key long, dst_key long").coalesce(1).write.mode("append").parquet(inbox)

    more([(5, 6), (7, 8), (None, 9)])
    assert {tuple(r) for r in st.follow_edges(spark, inbox, folder).last().collect()} == {(5, 5), (6, 5), (7, 7), (8, 7)}
    more([(8, 6), (20, 21)])
    more([(3, 20)])
    grown = st.follow_edges(spark, inbox, folder)
    assert {tuple(r) for r in grown.last().collect()} == {(5, 5), (6, 5), (7, 5), (8, 5), (3, 3), (20, 3), (21, 3)}
    assert grown.edges(10).count() == 10 and grown.edges(0).count() == 4
