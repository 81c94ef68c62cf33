"""Exact deduplication by a stateful stream.

The stream keeps disk-backed keyed state (RocksDB) that never expires: for each
digest the stable identifier of the row that stays, how many rows had it, and a
locator of that row's content. Digests only nominate: rows whose digest was hit
are read again by their locators and their full bytes compared, and a digest that stands for
different bytes is taken apart. Only DataFrame and SQL functions are used.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from .common import join_per_key, partitions_for, scratch, stored, texts_of

ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def folded(text: Column) -> Column:
    """Lower-case A-Z and nothing else. Where all bytes are ASCII, lower() does the same and is faster."""
    return F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))


def sha256(text: Column) -> Column:
    return F.unhex(F.sha2(text.cast("binary"), 256))


def digest_log(docs: DataFrame, digest=sha256) -> DataFrame:
    """One slim row per document: what the stream reads."""
    return texts_of(docs).select("doc_id", digest(folded(F.col("text"))).alias("digest"), F.octet_length("text").cast("long").alias("n_bytes"), locator().alias("locator"))


def locator() -> Column:
    """Where a row's content lies: its file, its doc_id, and a checksum that tells rows of one doc_id, or of none, apart."""
    return F.concat(F.input_file_name(), F.lit("#"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit("#"), F.hex(F.xxhash64("text")))


def keyed_state(log: DataFrame) -> DataFrame:
    """The state of a (streaming) digest log: per digest the largest doc_id, its locator and the count. Nothing expires."""
    return log.groupBy("digest").agg(F.max(F.struct("doc_id", "locator")).alias("keeper"), F.count(F.lit(1)).alias("group_size"))


def run_stream(spark: SparkSession, log_path: str, schema, state_path: str, files_per_batch: int = 256) -> DataFrame:
    """Feed a written digest log through the stateful stream until it is used up; return the last state of each digest.

    Restartable: the offsets, the state and the rows that each micro-batch
    changed all live in ``state_path``, and a repeated micro-batch overwrites
    its own folder.
    """
    session = spark.newSession()
    session.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKSDB)
    # Each state partition's store would set aside megabytes of disk for logs that stay small.
    session.conf.set("spark.sql.streaming.stateStore.rocksdb.allowFAllocate", "false")
    # An executor's stores share one bounded cache, and finished ones are unloaded soon.
    session.conf.set("spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage", "true")
    session.conf.set("spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB", "128")
    session.conf.set("spark.sql.streaming.stateStore.maintenanceInterval", "10s")
    session.conf.set("spark.sql.shuffle.partitions", partitions_for(spark))
    session.conf.set("spark.sql.session.timeZone", "UTC")

    def put(changed: DataFrame, batch: int) -> None:
        changed.write.mode("overwrite").parquet(f"{state_path}/changed/batch={batch}")

    stream = session.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(log_path)
    query = keyed_state(stream).writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", f"{state_path}/offsets").trigger(availableNow=True).start()
    query.awaitTermination()
    changed = spark.read.schema("digest binary, keeper struct<doc_id: bigint, locator: string>, group_size bigint, batch int").parquet(f"{state_path}/changed")
    return changed.groupBy("digest").agg(F.max(F.struct("batch", "keeper", "group_size")).alias("s")).select("digest", F.col("s.keeper.doc_id").alias("keep_id"), F.col("s.keeper.locator").alias("locator"), F.col("s.group_size").alias("group_size"))


def exact_dedup(docs: DataFrame, digest=sha256) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, locator.

    Texts are equal when identical after lower-casing A-Z only; of equal texts
    the row with the largest doc_id stays. Null text counts as empty. A null
    doc_id loses against any other; repeated rows (same doc_id, equal text) all
    carry the same answer, so a caller who wants one of them drops duplicates
    by doc_id. An empty table gives an empty result. Other columns are ignored.
    """
    spark = docs.sparkSession
    log_path, state_path = scratch(spark, "digests"), scratch(spark, "dedup-state")
    log = digest_log(docs, digest)
    seen = Observation()
    log.observe(seen, F.count(F.lit(1)).alias("n")).write.parquet(log_path)
    log = spark.read.schema(log.schema).parquet(log_path)
    if log.isEmpty():
        state = log.select("digest", F.col("doc_id").alias("keep_id"), "locator", F.col("n_bytes").alias("group_size"))
    else:
        state = stored(run_stream(spark, log_path, log.schema, state_path), "dedup-digests")
    total = seen.get["n"]
    named = join_per_key(log.select("doc_id", "digest", F.xxhash64("locator").alias("place")), state, ["digest"], "group_size", total)

    # Full bytes of every row whose digest was hit, by its locator: copies spread over all tasks, and each task sends at most one
    # pair of texts for a digest. Two locators with one checksum only put more texts side by side.
    hits = named.where("group_size > 1").select("place", "digest").distinct()
    texts = texts_of(docs).select("text", F.xxhash64(locator()).alias("place")).join(hits, "place").select("digest", folded(F.col("text")).alias("text"))
    clash = stored(texts.groupBy("digest").agg(F.min("text").alias("a"), F.max("text").alias("b")).where("a <> b").select("digest"), "clash")
    if clash.isEmpty():
        return named.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), "locator")

    # Some digests stand for different bytes: group those rows by the bytes themselves.
    own = texts_of(docs).select("doc_id", folded(F.col("text")).alias("text")).withColumn("digest", digest(F.col("text"))).join(clash, "digest", "left_semi")
    groups = own.groupBy("digest", "text").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    apart = own.join(groups, ["digest", "text"]).select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), F.lit("").alias("locator"))
    rest = named.join(clash, "digest", "left_anti")
    return rest.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), "locator").unionByName(apart)




def keep_last_copies(docs: DataFrame) -> DataFrame:
    """The rows of ``docs``, all columns as they are, without exact copies: of equal texts the row with the largest doc_id stays.

    Of repeated rows, and of equal texts of which none has a doc_id, one stays.
    """
    result = stored(exact_dedup(docs), "exact")
    kept = result.where("kept").select("doc_id", F.col("text_sha256").alias("exact_digest"))
    marked = docs.withColumn("exact_digest", F.lower(F.hex(sha256(folded(F.coalesce("text", F.lit("")))))))
    # doc_id is in the join's key, so that copies spread over all tasks.
    out = marked.where("doc_id IS NOT NULL").join(kept.where("doc_id IS NOT NULL").distinct(), ["doc_id", "exact_digest"], "left_semi").select(*marked.columns)
    if not kept.where("doc_id IS NOT NULL").groupBy("doc_id", "exact_digest").count().where("count > 1").isEmpty():
        out = out.dropDuplicates(["doc_id", "exact_digest"])
    if not kept.where("doc_id IS NULL").isEmpty():
        no_id = marked.where("doc_id IS NULL").join(kept.where("doc_id IS NULL").select("exact_digest").distinct(), "exact_digest", "left_semi")
        out = out.unionByName(no_id.select(*marked.columns).dropDuplicates(["exact_digest"]))
    return out.drop("exact_digest")
