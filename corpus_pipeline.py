"""The corpus pipeline: five stages over documents, each written as Parquet and read again for the next.

Good documents pass the quality classifier; one document of each group of near copies stays; documents with benchmark windows go; personal data
is masked; the rest is mixed to the target weights. The last stage returns the mix itself: a row for each draw.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from diversify.llm import fingerprints, leaks, mixing, pii, quality

STAGES = [
    ("quality classifier", quality.keep_good),
    ("SimHash near-dedup", fingerprints.keep_one),
    ("benchmark decontamination", leaks.drop_leaks),
    ("PII", pii.mask_stage),
    ("mixing sources", mixing.mix_stage),
]
#: Trained models and fingerprints are beyond SQL; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages on ``documents``; what they return is kept in the folder that spark.checkpoint.dir names."""
    folder = f"{spark.conf.get('spark.checkpoint.dir', None) or tempfile.mkdtemp('-pipeline')}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
