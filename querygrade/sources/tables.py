"""Sources and sinks: Parquet tables, JSON-lines answers, CSV."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ANSWER_SCHEMA = "model_id long, qid long, variant int, run int, answer string, _corrupt_record string"


def importable(spark: SparkSession) -> None:
    """Let Python workers of this session import the package from where the driver has it."""
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", os.environ.get("PYTHONPATH", "")).split(os.pathsep) if p]
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *paths])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_local: str | None = None


def shared_folder(spark: SparkSession) -> str:
    """The session's shared folder; a temporary one of this process only on ``local[n]`` without one (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not (spark.conf.get("spark.master", None) or "local").startswith("local") or "cluster" in (spark.conf.get("spark.master", None) or ""):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    global _local
    if _local is None:
        _local = tempfile.mkdtemp(prefix="shared_")
        atexit.register(shutil.rmtree, _local, True)
    return f"file://{_local}"


def spread(df: DataFrame) -> DataFrame:
    """Narrow rows that much work follows for, dealt over as many tasks as the session's shuffles have, however few files hold them."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def written(df: DataFrame, label: str) -> DataFrame:
    """A table of the shared folder in place of a plan that is read more than once."""
    path = f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def csv_round_trip(df: DataFrame, label: str) -> DataFrame:
    """``df`` written as CSV and read again with its schema; empty strings and nulls stay apart."""
    path = f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    options = {"header": "true", "escape": '"', "nullValue": "\\N", "emptyValue": "", "multiLine": "true"}
    df.write.options(**options).csv(path)
    return df.sparkSession.read.options(**options).schema(df.schema).csv(path)


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Temporary views of tables for SQL text."""
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def write_answers(answers: DataFrame, path: str) -> None:
    """One JSON line for each answer, in question order inside each file."""
    answers.sortWithinPartitions("model_id", "qid", "variant", "run").write.mode("overwrite").option("ignoreNullFields", "false").json(path)


def read_answers(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(answers, lines that are not answers)."""
    lines = spark.read.schema(ANSWER_SCHEMA).option("columnNameOfCorruptRecord", "_corrupt_record").json(path)
    bad = F.col("_corrupt_record").isNotNull() | F.col("model_id").isNull() | F.col("qid").isNull()
    return lines.where(~bad).drop("_corrupt_record"), lines.where(bad).select("_corrupt_record")
