"""Helpers shared by the training-data operators: tables, shared storage, hashing, components.

Everything that must outlive an executor is written under the folder that the session names in
``spark.checkpoint.dir``.  Only where a session on ``local[n]`` names none (unit tests) a temporary
folder of this process is used; elsewhere a session without one is an error.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from querygrade.sources.tables import importable

#: ASCII white space of the word pattern ``[^\x20\x09-\x0D]+``; ``bytes.split()`` splits on exactly these.
ASCII_SPACE = b"\x09\x0a\x0b\x0c\x0d\x20"
#: The same class for JVM regular expressions.
SPACE_CLASS = r"[\x20\x09-\x0D]"

_local_scratch: str | None = None


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    importable(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A folder that driver and executors share; never a machine-local one on a cluster."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not (spark.conf.get("spark.master", "local") or "").startswith("local[") and spark.conf.get("spark.master", "local") != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    global _local_scratch
    if _local_scratch is None:
        _local_scratch = tempfile.mkdtemp(prefix="shared_scratch_")
        atexit.register(shutil.rmtree, _local_scratch, True)
    return f"file://{_local_scratch}"


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage with a Parquet table in the shared folder and read it back."""
    spark = df.sparkSession
    path = fresh_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, path: str) -> None:
    """Delete a table that no later plan reads."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


class StoredChain:
    """Rounds of an iteration: each round's table replaces the one before the last."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.label, self.paths = spark, label, []

    def put(self, df: DataFrame) -> DataFrame:
        path = fresh_path(self.spark, self.label)
        df.write.parquet(path)
        self.paths.append(path)
        while len(self.paths) > 2:
            discard(self.spark, self.paths.pop(0))
        return self.spark.read.schema(df.schema).parquet(path)


def unused_names(columns: list[str], *names: str) -> list[str]:
    """Each name, or with underscores before it where ``columns`` (in any case) hold it."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def crc32_of_id(col: str = "doc_id") -> Column:
    """crc32 of the id written as decimal text: the split key of the held-out folds."""
    return F.crc32(F.col(col).cast("string").cast("binary"))


def texts_as_bytes(column) -> list:
    """An Arrow string column as a list of ``bytes`` (None for null)."""
    import pyarrow as pa

    return column.cast(pa.binary() if pa.types.is_string(column.type) else pa.large_binary()).to_pylist()


class BoundedCache(dict):
    """A dict that computes missing values and starts anew when ``limit`` entries are held."""

    def __init__(self, make, limit: int = 1 << 19):
        super().__init__()
        self.make, self.limit = make, limit

    def __missing__(self, key):
        if len(self) >= self.limit:
            self.clear()
        value = self[key] = self.make(key)
        return value


_ODD = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F))


def fold_pair(left: np.ndarray, right: np.ndarray, lane: int = 0) -> np.ndarray:
    """Order-dependent 64-bit mix of two equally long arrays; two lanes give 128 bits."""
    out = left * _ODD[lane] + (right ^ (right >> np.uint64(31))) * _ODD[lane + 1]
    out ^= out >> np.uint64(29)
    out *= _ODD[lane + 2]
    return out ^ (out >> np.uint64(32))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(a long, b long)``; returns (node, root), root the least node.

    Alternates two star contractions.  In each, a node's neighbours are re-attached to its least
    neighbour, so that every component ends as one star around its least node.  Every step is an
    aggregation with map-side combine and a join back, on rows of two longs; nothing is collected but
    two numbers for each round.  Isolated nodes do not appear; no edges give an empty table.
    """
    spark = edges.sparkSession
    chain = StoredChain(spark, "star")
    now = chain.put(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u is not null and v is not null and u <> v").distinct())
    seen = None
    for _ in range(max_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        wide = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = wide.groupBy("u").agg(F.min("v").alias("m"))
        joined = wide.join(low, "u")
        flat = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = chain.put(flat.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
