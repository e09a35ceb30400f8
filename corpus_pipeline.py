"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again by the next.

1. ``toxicity``: documents that the learned lexicon model scores at 0.3 or more go.
2. ``exact_dedup``: of texts that are equal but for ASCII white space, the longest stays (then the smallest id).
3. ``simhash_near_dedup``: of near duplicates (five-word shingles, similarity 0.8 or more), the smallest id stays.
4. ``pii``: detected personal data get keyed surrogates; ``n_chars`` follows the new text.
5. ``packing``: the texts' tokens are packed into sequences of 2048; this stage returns the pieces.

Rows keep all their columns through stages 1 to 4; rows with null ids or texts are treated as the operators say.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from querygrade.llm import exact_dedup as _exact
from querygrade.llm import near_documents as _near
from querygrade.llm import packing as _packing
from querygrade.llm import pii as _pii
from querygrade.llm import toxicity as _toxicity
from querygrade.llm.common import fresh_path, table


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _toxicity.learn(docs, table(spark, sf_dir, "labels")).keep_clean(docs)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _exact.without_copies(docs)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _near.without_near_copies(docs)


def pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = _pii.pseudonymize(docs).select(*docs.columns)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _packing.pack_documents(docs, _packing.default_tokenizer(), added_tokens=True)


STAGES = [("toxicity", toxicity), ("exact_dedup", exact_dedup), ("simhash_near_dedup", simhash_near_dedup), ("pii", pii), ("packing", packing)]

#: No SQL twin: learned scores and packing are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = fresh_path(spark, f"stage-{name}")
        out = stage(spark, docs, sf_dir)
        out.write.parquet(path)
        docs = spark.read.schema(out.schema).parquet(path)
    return docs
