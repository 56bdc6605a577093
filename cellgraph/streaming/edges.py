"""Edges that arrive as a stream: windowed degrees, deduplication, joins, incremental labels.

Every function works on any streaming DataFrame of events; the queries run them over the
given table with the ``availableNow`` trigger and return what a sink has then.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..oracle import sqlgen
from ..registry import query
from ..storage import delete, work_dir, write_table

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 4) -> DataFrame:
    """The events table as a stream; event times are zoned, since watermarks want that."""
    found = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", "*.parquet")
    table = spark.read.parquet(f"{sf_dir}/events.parquet")
    folder = work_dir(spark, "events-in")
    table.select([c.split()[0] for c in EVENT_SCHEMA.split(", ")]).write.parquet(folder)
    return found.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_degrees(events: DataFrame, length: str, slide: str | None = None, watermark: str = "10 minutes") -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", watermark).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def session_degrees(events: DataFrame, gap: str, watermark: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def drain(stream: DataFrame, keys: list[str], mode: str = "update", folder: str | None = None) -> DataFrame:
    """Run to the end of what is there, from a Parquet sink: the last value of each key
    (update), all rows (append), or what the last batch wrote (complete).  With the
    ``folder`` of an earlier call it goes on from that one's checkpoint."""
    spark = stream.sparkSession
    folder = folder or work_dir(spark, "drain")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{folder}/out/b{number:09d}")

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.option("recursiveFileLookup", True).parquet(f"{folder}/out")
    if mode == "complete":
        rows = rows.filter(F.col("_batch") == rows.agg(F.max("_batch")).first()[0])
    if not keys:
        return rows.drop("_batch")
    rest = [c for c in rows.columns if c not in (*keys, "_batch")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "_batch").alias("v")).select(*keys, "v.*")


def _stamp(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf_dir):
    return _stamp(drain(windowed_degrees(event_stream(spark, sf_dir), "1 day"), ["start", "user_id"]))


@query("stream_sliding", "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts) - to_hours(CAST(k * 6 AS INTEGER)), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM events, range(0, 4) x(k) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return _stamp(drain(windowed_degrees(event_stream(spark, sf_dir), "1 day", "6 hours"), ["start", "user_id"]))


_SESSIONS = """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k"""


@query("stream_session", _SESSIONS)
def stream_session(spark, sf_dir):
    """All sessions, also those still open, in complete mode: what the last batch wrote."""
    return _stamp(drain(session_degrees(event_stream(spark, sf_dir), "30 minutes"), [], "complete"))


@query("stream_session_append", _SESSIONS + " HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) FROM events) - INTERVAL 10 MINUTE")
def stream_session_append(spark, sf_dir):
    """Sessions that the watermark, ten minutes behind the last event, has closed."""
    return _stamp(drain(session_degrees(event_stream(spark, sf_dir), "30 minutes"), [], "append"))


@query("stream_complete", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def stream_complete(spark, sf_dir):
    """Running counts in complete mode, over several batches."""
    return drain(event_stream(spark, sf_dir, 1).groupBy("user_id").agg(F.count("*").alias("n")), [], "complete")


@query("stream_late_rows", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM events GROUP BY ALL HAVING date_trunc('day', min(ts)) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 10 MINUTE")
def stream_late_rows(spark, sf_dir):
    """Every event once more, after the watermark has passed: late rows change no closed window."""
    folder = work_dir(spark, "late-in")
    table = spark.read.parquet(f"{sf_dir}/events.parquet").select([c.split()[0] for c in EVENT_SCHEMA.split(", ")])
    table.write.parquet(folder)
    stream = spark.readStream.schema(EVENT_SCHEMA).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))
    counts, state = windowed_degrees(stream, "1 day"), work_dir(spark, "late")
    drain(counts, [], "append", state)
    closed = table.filter(F.col("ts") < F.lit(table.agg(F.max("ts")).first()[0]) - F.expr("INTERVAL 2 DAYS"))
    closed.write.mode("append").parquet(folder)
    return _stamp(drain(counts, [], "append", state))


@query("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")
def stream_dedup(spark, sf_dir):
    events = event_stream(spark, sf_dir).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
    return drain(events.select("event_id", "user_id"), [], "append")


@query("stream_join", "SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 2 HOUR")
def stream_join(spark, sf_dir):
    """Views with purchases of the same user in the next two hours: a bounded-state join."""
    views = event_stream(spark, sf_dir).filter("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "40 days")
    buys = event_stream(spark, sf_dir).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "40 days")
    return drain(views.join(buys, F.expr("u1 = u2 AND t2 BETWEEN t1 AND t1 + INTERVAL 2 HOURS")).select("view_id", "purchase_id"), [], "append")


@query("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf_dir):
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_name")
    return drain(event_stream(spark, sf_dir).join(customers, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"), [], "append")


@query("stream_succession", "SELECT s AS src_key, t AS dst_key FROM (SELECT event_id AS s, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS t FROM events) WHERE t IS NOT NULL")
def stream_succession(spark, sf_dir):
    return drain(successions(event_stream(spark, sf_dir, 100_000)), [], "append")


def successions(events: DataFrame) -> DataFrame:
    """Edges from each user's event to the user's next one, with the last one of each user as
    kept state; batches are taken to come in the order of time."""
    import pandas as pd

    def follow(key, frames, state):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for e in rows["event_id"]:
            if last is not None:
                out.append((int(last), int(e)))
            last = int(e)
        state.update((last,))
        yield pd.DataFrame(out, columns=["src_key", "dst_key"])

    return events.select("event_id", "user_id", "ts").groupBy("user_id").applyInPandasWithState(follow, "src_key long, dst_key long", "last long", "append", "NoTimeout")


class GrowingComponents:
    """Components of edges that only ever come in: each micro-batch is appended to the edge
    store and the labels are refolded from where they were, starting with the vertices that
    the batch touched; the others take part only once a label of theirs changes.  Everything
    is written under the batch's number, so a batch that is run again overwrites itself."""

    def __init__(self, spark: SparkSession, folder: str, max_rounds: int = 10_000):
        self.spark, self.folder, self.max_rounds = spark, folder, max_rounds

    def _labels(self, number: int) -> DataFrame:
        path = f"{self.folder}/labels/b{number:09d}"
        return self.spark.read.parquet(path) if number >= 0 else self.spark.createDataFrame([], "key long, label long")

    def edges(self, number: int) -> DataFrame:
        """Both directions of all edges up to batch ``number``."""
        return self.spark.read.schema("src_key long, dst_key long, batch long").parquet(f"{self.folder}/edges").filter(F.col("batch") <= number).select("src_key", "dst_key")

    def fold(self, batch: DataFrame, number: int) -> None:
        new = batch.select("src_key", "dst_key").dropna().distinct()
        both = new.unionByName(new.select(F.col("dst_key").alias("src_key"), F.col("src_key").alias("dst_key")))
        write_table(both, f"{self.folder}/edges/batch={number}")
        edges, rounds = self.edges(number), f"{self.folder}/rounds/b{number:09d}"
        touched = both.select(F.col("src_key").alias("key")).distinct()
        old = self._labels(number - 1)
        start = old.join(touched.withColumn("changed", F.lit(True)), "key", "full").select("key", F.coalesce("label", "key").alias("label"), F.coalesce("changed", F.lit(False)).alias("changed"))
        state = write_table(start, f"{rounds}/r0")
        for k in range(1, self.max_rounds + 1):
            front = state.filter("changed").select(F.col("key").alias("src_key"), "label")
            got = edges.join(front, "src_key").groupBy(F.col("dst_key").alias("key")).agg(F.min("label").alias("inc"))
            nxt = state.join(got, "key", "left").select("key", F.least("label", "inc").alias("label"), F.coalesce(F.col("inc") < F.col("label"), F.lit(False)).alias("changed"))
            state = write_table(nxt, f"{rounds}/r{k}")
            if state.filter("changed").isEmpty():
                break
        else:
            raise RuntimeError(f"labels not settled after {self.max_rounds} rounds")
        write_table(state.select("key", "label"), f"{self.folder}/labels/b{number:09d}")
        delete(self.spark, rounds)

    def last(self) -> DataFrame:
        """(key, label) after the last batch."""
        rows = self.spark.read.option("recursiveFileLookup", True).parquet(f"{self.folder}/labels").withColumn("b", F.regexp_extract(F.input_file_name(), "/b([0-9]{9})/", 1))
        return rows.filter(F.col("b") == rows.agg(F.max("b")).first()[0]).select("key", "label")


def follow_edges(spark: SparkSession, inbox: str, folder: str) -> GrowingComponents:
    """Fold what is new in ``inbox`` (src_key, dst_key), a file a micro-batch, into the components
    kept in ``folder``; called again it goes on from its checkpoint."""
    grown = GrowingComponents(spark, folder)
    stream = spark.readStream.schema("src_key long, dst_key long").option("maxFilesPerTrigger", 1).parquet(inbox)
    append_to_grid(stream, grown.fold, f"{folder}/checkpoint").awaitTermination()
    return grown


@query("stream_wcc", sqlgen.wcc("custurg", "SELECT v.raw_key AS key, w.raw_key AS label FROM c JOIN v ON v.vid = c.vid JOIN v w ON w.vid = c.attr"))
def stream_wcc(spark, sf_dir):
    """Components of edges that arrive as a stream of three files."""
    from ..sources.builders import g_custurg

    inbox = work_dir(spark, "edges-in")
    edges = g_custurg(spark, sf_dir).withColumn("part", F.pmod(F.xxhash64("src_key", "dst_key"), F.lit(3)))
    edges.repartition(3, "part").select("src_key", "dst_key").write.option("maxRecordsPerFile", 100_000_000).parquet(inbox)
    return follow_edges(spark, inbox, work_dir(spark, "growing")).last()


def append_to_grid(stream: DataFrame, fold: Callable[[DataFrame, int], None], checkpoint: str):
    """Feed each micro-batch of edges to ``fold`` exactly once per batch number."""
    return stream.writeStream.foreachBatch(fold).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


__all__ = ["GrowingComponents", "append_to_grid", "drain", "event_stream", "follow_edges", "session_degrees", "successions", "windowed_degrees"]
