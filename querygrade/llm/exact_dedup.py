"""Exact deduplication as a stateful stream.

Every document gets a signature: SHA-256 of its normalised bytes (ASCII white space deleted), its
length in code points, its stable identifier and a content locator (file and row).  Signatures are
streamed through an aggregation keyed by digest whose state lives on disk (RocksDB) and never expires:
for each digest it retains the best identifier with its locator and the number of rows.  Spark's partial aggregation
combines a batch before the shuffle, so a digest held by a third of all rows brings at most one row per task.
Each trigger appends the digests it changed; the newest line of a digest is its state.

A hit (a row whose digest belongs to another row) is only a duplicate when its full bytes equal those of
the row that stays: the texts of hits and of kept rows are joined and compared.  Rows that
differ (digest collisions) leave their group and are grouped among themselves by their bytes.

Defined cases: null text counts as empty; empty texts equal each other; repeated rows with one id are
rows of their own in ``group_size`` and share ``keep_id``, and only the first of the kept id's rows is ``kept``;
of rows without id one may stay only where no row with an id has as many code points, with a null ``keep_id``; other columns, whatever their names, are ignored; an empty
table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ASCII_SPACE, fresh_path, stored, table, texts_as_bytes, unused_names

#: Session settings of the stream: state on local disk, small files where many state partitions hold little.
STATE_SETTINGS = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
}
SIGNATURE = "doc_id long, digest binary, n_points long, at string, row long"


def signatures(docs: DataFrame, digest_bytes: int = 32) -> DataFrame:
    """doc_id, digest, n_points (code points of the original), at and row (content locator: file and row in it)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t or b"" for t in texts_as_bytes(batch.column(1))]
            digests = [hashlib.sha256(t.translate(None, ASCII_SPACE)).digest()[:digest_bytes] for t in texts]
            points = [len(t) if t.isascii() else len(t.decode("utf-8", "replace")) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.binary()), pa.array(points, pa.int64()), batch.column(2), batch.column(3)], names=["doc_id", "digest", "n_points", "at", "row"])

    return located(docs).mapInArrow(run, SIGNATURE)


def places(docs: DataFrame) -> list[Column]:
    """File and row in it, whatever columns the rows have themselves."""
    hidden = docs.metadataColumn("_metadata")
    return [hidden.getField("file_path"), hidden.getField("row_index")]


def located(docs: DataFrame) -> DataFrame:
    """doc_id, text and the content locator of rows that are read straight from files."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *(c.alias(n) for c, n in zip(places(docs), ("at", "row"), strict=True)))


def on_files(docs: DataFrame) -> DataFrame:
    """``docs`` itself where its rows have a place in files, else a stored copy."""
    try:
        located(docs)
        return docs
    except AnalysisException:
        return stored(docs, "documents")


def _best():
    """Order of the row that stays: most code points, then smallest id; rows without id last."""
    return F.max(F.struct("n_points", F.col("doc_id").isNotNull().alias("named"), (-F.col("doc_id")).alias("minus_id"), (-F.col("row")).alias("minus_row"), "at"))


def dedup_stream(spark: SparkSession, signature_path: str, files_per_trigger: int = 10_000) -> DataFrame:
    """State of every digest after all signature files under a path have streamed through.

    digest, group_size, best (n_points, minus_id, locator).  The checkpoint keeps the state, so a later
    call with the same ``state_dir`` would go on from it; queries use a fresh one.
    """
    sink, state = fresh_path(spark, "dedup-changes"), fresh_path(spark, "dedup-state")
    before = {key: spark.conf.get(key, None) for key in STATE_SETTINGS}
    for key, value in STATE_SETTINGS.items():
        spark.conf.set(key, value)
    try:
        stream = spark.readStream.schema(SIGNATURE).option("maxFilesPerTrigger", files_per_trigger).parquet(signature_path)
        held = stream.groupBy("digest").agg(F.count(F.lit(1)).alias("group_size"), _best().alias("best"))

        def write(changed: DataFrame, batch: int) -> None:
            changed.withColumn("batch", F.lit(batch).cast("long")).write.mode("overwrite").parquet(f"{sink}/part={batch}")

        query = held.writeStream.outputMode("update").option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(write).start()
        query.awaitTermination()
        n_batches = len(query.recentProgress)
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)
    shape = "digest binary, group_size long, best struct<n_points:long,named:boolean,minus_id:long,minus_row:long,at:string>, batch long"
    fs = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(sink)
    if not fs.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(fs):
        return spark.createDataFrame([], shape).drop("batch")
    lines = spark.read.schema(shape).parquet(f"{sink}/*")
    if n_batches <= 1:
        return lines.drop("batch")
    newest = lines.groupBy("digest").agg(F.max_by(F.struct("group_size", "best"), "batch").alias("x"))
    return stored(newest.select("digest", "x.group_size", "x.best"), "dedup-newest")


def _bare(col: str) -> Column:
    return F.translate(F.coalesce(F.col(col), F.lit("")), " \t\n\x0b\f\r", "")


def exact_dedup(docs: DataFrame, digest_bytes: int = 32, files_per_trigger: int = 10_000) -> DataFrame:
    """doc_id, at, row, keep_id, group_size, kept, digest: one row for each row of ``docs``."""
    docs = on_files(docs)
    spark = docs.sparkSession
    path = fresh_path(spark, "signatures")
    signatures(docs, digest_bytes).write.parquet(path)
    signed = spark.read.schema(SIGNATURE).parquet(path)
    state = dedup_stream(spark, path, files_per_trigger)
    keep = [(-F.col("best.minus_id")).alias("keep_id"), F.col("best.at").alias("keep_at"), (-F.col("best.minus_row")).alias("keep_row")]
    placed = stored(signed.join(state, "digest").select("doc_id", "at", "row", "digest", "group_size", "n_points", *keep), "dedup-placed")
    stays = (F.col("at") == F.col("keep_at")) & (F.col("row") == F.col("keep_row"))
    several = placed.where("group_size > 1").select("at", "row", "digest", "keep_at", "keep_row")
    members = stored(several.join(located(docs).select("at", "row", "text"), ["at", "row"]), "dedup-members")
    keepers = members.where(stays).select("keep_at", "keep_row", F.col("text").alias("keep_text"))
    other = members.where(~stays).join(keepers, ["keep_at", "keep_row"]).where(_bare("text") != _bare("keep_text")).select("at", "row", "digest", F.sha2(_bare("text").cast("binary"), 512).alias("bytes_key"))
    other = stored(other, "dedup-collisions")
    whole = placed.withColumn("kept", stays).select("doc_id", "at", "row", "keep_id", "group_size", "kept", "digest")
    if other.isEmpty():
        return whole
    # digest collisions: rows that differ form groups by their bytes, and their first groups shrink
    rows = other.join(placed.select("at", "row", "doc_id", "n_points"), ["at", "row"])
    best = rows.groupBy("digest", "bytes_key").agg(F.count(F.lit(1)).alias("size2"), _best().alias("best2"))
    moved = rows.join(best, ["digest", "bytes_key"]).select("at", "row", "size2", "best2")
    left = rows.groupBy("digest").agg(F.count(F.lit(1)).alias("gone"))
    fixed = whole.join(moved, ["at", "row"], "left").join(left, "digest", "left")
    out = F.col("size2").isNotNull()
    return fixed.select(
        "doc_id", "at", "row", "digest",
        F.when(out, -F.col("best2.minus_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.when(out, F.col("size2")).otherwise(F.col("group_size") - F.coalesce("gone", F.lit(0))).alias("group_size"),
        F.when(out, (F.col("at") == F.col("best2.at")) & (F.col("row") == -F.col("best2.minus_row"))).otherwise(F.col("kept")).alias("kept"),
    )


def without_copies(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, all columns as they are."""
    docs = on_files(docs)
    at, row = unused_names(docs.columns, "at", "row")
    kept = exact_dedup(docs).where("kept").select(F.col("at").alias(at), F.col("row").alias(row))
    placed = docs.withColumns(dict(zip((at, row), places(docs), strict=True)))
    return placed.join(kept, [at, row], "left_semi").select(*[F.col(f"`{c}`") for c in docs.columns])


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = exact_dedup(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


SQL = r"""
WITH t AS (
  SELECT doc_id, coalesce(text, '') AS body, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm FROM documents
), w AS (
  SELECT doc_id, sha256(norm) AS text_sha256,
         first_value(doc_id) OVER (PARTITION BY norm ORDER BY length(body) DESC, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS keep_id,
         count(*) OVER (PARTITION BY norm) AS group_size
  FROM t
)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM w
"""
