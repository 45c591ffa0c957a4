"""Exact deduplication as a stream with keyed state on disk.

The first pass writes (digest, doc_id) of every row: a narrow table. A streaming query reads it in bounded micro-batches; its
state, in RocksDB and never expired, holds for each digest the stable identifier (the largest doc_id, which is the
content locator as well) and the number of rows. Rows are summed up on the map side before they are dealt by digest, so a text
with a third of all rows is a few rows there. Every hit (a row that isn't the one its digest keeps) is then compared with
the kept row byte by byte; if a digest stands for several texts, its rows are grouped again by the text itself. Joins with the state
send the rows of a digest with many rows nowhere (common.looked_up), so no task gets all of them.

Texts are equal when identical after lower-casing A-Z; null counts as empty. Rows that share the doc_id of the kept row are kept as well.
Rows without a doc_id are counted; they are neither kept nor dropped (kept is null). An empty table gives no rows; columns other than doc_id and text
are ignored; texts of any length pass as digests, and whole only where they are hits.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
#: Settings of the stream: RocksDB, which reserves 4 MB of disk for each partition's log unless told not to, and buffers for each
#: partition in native memory; together they may take this much of an executor. Stores of a stream that has ended are closed by the next maintenance.
SETTINGS = {
    "spark.sql.streaming.stateStore.providerClass": ROCKS, "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true", "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "64",
    "spark.sql.streaming.stateStore.maintenanceInterval": "5s",
}
#: Files of the digest table that one micro-batch takes.
BATCH_FILES = 256
#: A table of this many (long, long, int) rows at most is broadcast: 24 MB.
BROADCAST_ROWS = 1_000_000
#: Rows that are compared with one copy of a kept text.
SALT_ROWS = 1000


def normalised(text: str = "text") -> Column:
    return F.translate(F.coalesce(F.col(text), F.lit("")), string.ascii_uppercase, string.ascii_lowercase)


def keep_state(digests: DataFrame, batch_files: int = BATCH_FILES) -> DataFrame:
    """digest, keep_id, group_size: the state after the whole stream. digests is a written table of digest, doc_id."""
    spark = digests.sparkSession
    folder = common.shared_folder(spark, "dedup-stream")
    own = spark.newSession()  # the stream's settings stay out of the caller's session
    for k, v in {**SETTINGS, **{k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.session.timeZone")}}.items():
        own.conf.set(k, v)
    stream = own.readStream.schema(digests.schema).option("maxFilesPerTrigger", batch_files).parquet(digests.shared_path)
    state = stream.groupBy("digest").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    # a batch that is run again after a failure overwrites its own rows
    sink = lambda df, k: df.write.mode("overwrite").parquet(f"{folder}/updates/batch={k}")
    query = state.writeStream.outputMode("update").foreachBatch(sink).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    schema = "digest binary, keep_id long, group_size long"
    if query.lastProgress is None:  # no file, no batch
        return spark.createDataFrame([], schema)
    updates = spark.read.schema(schema).parquet(f"{folder}/updates/*")
    # both only grow from batch to batch
    return updates.groupBy("digest").agg(F.max("keep_id").alias("keep_id"), F.max("group_size").alias("group_size"))


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def exact_dedup(docs: DataFrame, digest_bytes: int = 32, batch_files: int = BATCH_FILES) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every row. digest_bytes < 32 makes digests collide, for tests."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2(normalised(), 256)).alias("sha"))
    rows = common.written(rows.select(F.substring("sha", 1, digest_bytes).alias("digest"), "doc_id", "sha"), "dedup-digests")
    groups = common.written(keep_state(rows, batch_files), "dedup-groups")
    verdict = common.written(common.looked_up(rows, groups, "digest", "group_size"), "dedup-verdict")
    hits = verdict.where("group_size > 1 and doc_id <> keep_id").select("doc_id", "keep_id", F.pmod(F.xxhash64("doc_id"), F.ceil(F.col("group_size") / SALT_ROWS)).cast("int").alias("salt"))
    kept = verdict.where("group_size > 1 and doc_id = keep_id").select("doc_id", F.ceil(F.col("group_size") / SALT_ROWS).cast("int").alias("salts")).groupBy("doc_id").agg(F.max("salts").alias("salts"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), normalised().alias("bytes"))
    theirs = texts.join(_small(hits), "doc_id")
    # one row of the kept doc_id is enough; rows that repeat it are compared through the digest of the whole text below
    ours = texts.join(_small(kept), "doc_id").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).select(F.col("doc_id").alias("keep_id"), "salt", F.col("bytes").alias("kept_bytes"))
    wrong = theirs.join(ours, ["keep_id", "salt"]).where("bytes <> kept_bytes").select("keep_id").distinct()
    wrong_digests = common.written(verdict.join(wrong, "keep_id", "left_semi").select("digest").distinct(), "dedup-wrong")
    out = ["doc_id", "keep_id", "group_size", F.expr("doc_id = keep_id").alias("kept"), F.lower(F.hex("sha")).alias("text_sha256")]
    if wrong_digests.isEmpty():
        return verdict.select(*out)
    whole = texts.withColumn("sha", F.unhex(F.sha2("bytes", 256))).withColumn("digest", F.substring("sha", 1, digest_bytes)).join(wrong_digests, "digest", "left_semi")
    parts = whole.groupBy("bytes").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    return verdict.join(wrong_digests, "digest", "left_anti").select(*out).unionByName(whole.join(parts, "bytes").select(*out))


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(common.table(spark, sf_dir, "documents"))
