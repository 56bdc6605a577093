"""Exact deduplication with the state of a Structured Streaming query.

The stream's state is an index keyed by content digest, without watermark or timeout, in
the disk-backed RocksDB state store: for each digest the row that stays so far (length,
stable document id, row number, and locator: source file and row in it) and how many rows
have had it.  Partial aggregation in the map tasks folds the copies of a hot text before
the shuffle, so a group of any size costs one row a task.

A digest that was hit is only a candidate.  The locators of its rows lead back to the full
bytes, which are compared (smallest and largest as byte strings are equal exactly if all
are); rows of a digest that holds different texts are grouped anew by their bytes.
Locators also say which rows go.  Rows that don't come from files one to one (a join, say)
are written to the shared folder first, which gives them a place to point to.

Answers go back to the rows by a join on the digest; digests of more than ``HOT_SHARE`` of
all rows, fewer than its inverse at any size, are broadcast instead, so that no task gets
all rows of one.

Nulls count as empty texts, a null id sorts after all others, and of rows that agree in
length and id the last written stays.  An empty input gives an empty result.  A very long
text is one value, as in any column.  Only the id and text columns are read, and names used
inside are new ones, so other columns may have any name.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import fresh_names, materialise, shared_dir

HOT_SHARE = 0.001
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
#: Settings of the state store while the stream runs.  Without preallocation a partition of
#: the state takes the room of its keys, not 4 MB of manifest.
_STORE = {"spark.sql.streaming.stateStore.providerClass": ROCKSDB, "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false"}


def normalised(text):
    """The text without ASCII white space; null as empty."""
    out = F.coalesce(text, F.lit(""))
    for space in (" ", "\n", "\t", "\r", "\x0b", "\x0c"):
        out = F.replace(out, F.lit(space), F.lit(""))
    return out


def _is_scan(docs: DataFrame) -> bool:
    """Whether every row of ``docs`` is a row of a file, and no other row is the same one."""
    node = docs._jdf.queryExecution().analyzed()
    while node.children().size() == 1 and node.nodeName() in ("Project", "Filter", "SubqueryAlias"):
        node = node.children().head()
    if not node.children().isEmpty() or "_metadata" in (c.lower() for c in docs.columns):
        return False
    try:
        docs.select("_metadata.row_index")
    except AnalysisException:
        return False
    return True


def located(docs: DataFrame) -> tuple[DataFrame, str, str]:
    """``docs`` with a locator, as two more columns: (rows, name of the file's column, of the row's)."""
    file, row = fresh_names(docs, "file", "row")
    if not _is_scan(docs):
        names = [f"c{k}" for k in range(len(docs.columns))]  # any names may be written, but not any two
        held = materialise(docs.toDF(*names), shared_dir(docs.sparkSession, "located"))
        held = held.select(*names, F.col("_metadata.file_path").alias(file), F.col("_metadata.row_index").alias(row))
        return held.toDF(*docs.columns, file, row), file, row
    return docs.select("*", F.col("_metadata.file_path").alias(file), F.col("_metadata.row_index").alias(row)), file, row


def inbox_rows(rows: DataFrame, id_col: str, text_col: str, key_hex: int, file: str, row: str) -> DataFrame:
    """The narrow rows that enter the stream: digest, id, length and locator, no text."""
    text = F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))
    own = rows.select(
        F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.sha2(normalised(text).cast("binary"), 256).alias("sha"), F.char_length(text).cast("long").alias("n_points"),
        F.col(file).alias("file"), F.col(row).alias("row"),
    )
    return own.withColumns({"key": F.substring("sha", 1, key_hex), "rid": F.monotonically_increasing_id()})


def keep_state(stream: DataFrame) -> DataFrame:
    """The keyed state as a streaming aggregation: which row of each digest stays, and the count."""
    rank = F.struct("n_points", (-F.col("doc_id")).alias("neg_id"), "rid", "file", "row")
    return stream.groupBy("key").agg(F.max(rank).alias("keep"), F.count("*").alias("group_size"))


def drain(spark: SparkSession, inbox: str, schema, folder: str, files_per_batch: int = 4096) -> DataFrame:
    """Run the stream over what is in ``inbox`` and not yet seen; the current state of each key.

    Running it again with the same ``folder`` continues from the kept state, so later
    batches meet everything earlier ones left.  Each micro-batch writes the keys it changed
    under its own number, so a repeated batch overwrites itself.
    """
    before = {k: spark.conf.get(k, None) for k in _STORE}
    for k, v in _STORE.items():
        spark.conf.set(k, v)
    try:
        stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(inbox)

        def changed(batch: DataFrame, number: int) -> None:
            batch.withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{folder}/changes/part{number:09d}")

        query = keep_state(stream).writeStream.outputMode("update").option("checkpointLocation", f"{folder}/state").foreachBatch(changed).trigger(availableNow=True).start()
        query.awaitTermination()
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)
    kept = keep_state(spark.read.schema(schema).parquet(inbox)).schema
    changes = spark.read.schema(kept.add("batch", "long")).option("recursiveFileLookup", True).parquet(f"{folder}/changes")
    return changes.groupBy("key").agg(F.max(F.struct("batch", "keep", "group_size")).alias("last")).select("key", "last.keep", "last.group_size")


def _answers(inbox: DataFrame, groups: DataFrame, on: str, total: int) -> DataFrame:
    """``inbox`` left-joined with the groups of several rows, hot ones by broadcast."""
    hot = F.broadcast(groups.filter(F.col("group_size") > HOT_SHARE * total))
    seldom = inbox.join(hot.select(on), on, "left_anti").join(groups.hint("merge"), on, "left")
    return seldom.unionByName(inbox.join(hot, on)) if total else seldom


def _decide(rows: DataFrame, file: str, row: str, id_col: str, text_col: str, key_hex: int, folder: str) -> DataFrame:
    """The inbox rows with ``keep`` and ``group_size``, null where a row is alone."""
    spark = rows.sparkSession
    narrow = inbox_rows(rows, id_col, text_col, key_hex, file, row)
    inbox = materialise(narrow, f"{folder}/inbox")
    state = materialise(drain(spark, f"{folder}/inbox", narrow.schema, folder), f"{folder}/keys")
    total = inbox.count()
    marked = materialise(_answers(inbox, state.filter("group_size > 1"), "key", total), f"{folder}/marked")

    hits = marked.filter("group_size > 1").select("key", F.col("file").alias("at_file"), F.col("row").alias("at_row"))
    bodies = rows.select(normalised(F.col(f"`{text_col}`").cast("string")).alias("body"), F.col(file).alias("b_file"), F.col(row).alias("b_row"))
    met = bodies.join(hits.hint("merge"), (F.col("b_file") == F.col("at_file")) & (F.col("b_row") == F.col("at_row")))
    mixed = materialise(met.groupBy("key").agg((F.min("body") != F.max("body")).alias("differs")).filter("differs").select("key"), f"{folder}/mixed")
    if mixed.isEmpty():
        return marked
    if key_hex >= 64:
        raise RuntimeError("different texts share a whole SHA-256 digest")
    sure = marked.join(mixed, "key", "left_anti")
    doubt = inbox.join(mixed, "key", "left_semi")
    rank = F.struct("n_points", (-F.col("doc_id")).alias("neg_id"), "rid", "file", "row")
    anew = doubt.groupBy("sha").agg(F.max(rank).alias("keep"), F.count("*").alias("group_size")).filter("group_size > 1")
    return sure.unionByName(_answers(doubt, anew, "sha", total))


def dedup_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", key_hex: int = 64, folder: str | None = None) -> DataFrame:
    """One row for each input row: doc_id, keep_id, group_size, kept, text_sha256, and the
    locator (keep_file, keep_row) of the row that stays.

    ``key_hex``: hex digits of the digest that key the state; fewer make different texts
    collide, which the comparison of full bytes then takes apart.
    """
    rows, file, row = located(docs)
    found = _decide(rows, file, row, id_col, text_col, key_hex, folder or shared_dir(docs.sparkSession, "exact"))
    keep = F.col("keep")
    return found.select(
        "doc_id",
        F.when(keep.isNull(), F.col("doc_id")).otherwise(-keep["neg_id"]).alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        (keep.isNull() | (keep["rid"] == F.col("rid"))).alias("kept"),
        F.col("sha").alias("text_sha256"),
        F.coalesce(keep["file"], F.col("file")).alias("keep_file"),
        F.coalesce(keep["row"], F.col("row")).alias("keep_row"),
    )


def keep_firsts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", key_hex: int = 64) -> DataFrame:
    """The rows of ``docs`` that stay, one of each text, with all their columns."""
    rows, file, row = located(docs)
    found = _decide(rows, file, row, id_col, text_col, key_hex, shared_dir(docs.sparkSession, "exact"))
    gone_file, gone_row = fresh_names(rows, "gone_file", "gone_row")
    gone = found.filter(F.col("keep.rid") != F.col("rid")).select(F.col("file").alias(gone_file), F.col("row").alias(gone_row))
    return rows.join(gone.hint("merge"), (F.col(file) == F.col(gone_file)) & (F.col(row) == F.col(gone_row)), "left_anti").drop(file, row)


def op4_exact_stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_exact(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("keep_file", "keep_row")


ORACLE_SQL = r"""
WITH d AS (
  SELECT doc_id, length(coalesce(text, '')) AS n_points,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents
), g AS (
  SELECT doc_id, text_sha256,
         first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY n_points DESC, doc_id) AS keep_id,
         count(*) OVER (PARTITION BY text_sha256) AS group_size
  FROM d
)
SELECT doc_id, keep_id, group_size, keep_id = doc_id AS kept, text_sha256 FROM g
"""
