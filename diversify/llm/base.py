"""What the corpus operators share: reading, checkpoints, label folds and bounded training samples."""

from __future__ import annotations

import json
import tempfile
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the word contracts: space and \x09-\x0D. ``bytes.split()`` splits on the same six bytes.
SPACE = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """Some rows of the driver as a frame, through a literal; ``createDataFrame`` would start Python workers on the executors for them."""
    names = [part.split()[0] for part in schema.split(", ")]
    text = json.dumps([dict(zip(names, r, strict=True)) for r in rows])
    return spark.range(0, 1, 1, 1).select(F.inline_outer(F.from_json(F.lit(text), f"array<struct<{schema}>>"))).where(F.lit(bool(rows)))


def checkpoint(df: DataFrame) -> DataFrame:
    """``df`` computed once and written to the shared checkpoint folder, so a lost executor costs a read, not the lineage.

    The folder is the session's (spark.checkpoint.dir); only where none is set, as in tests, a temporary one is taken.
    """
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp("-checkpoint"))
    return df.checkpoint()


def renamed(docs: DataFrame, stage: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """A stage that keeps columns, run on ``docs`` with all but doc_id and text under names that clash with none of its own."""
    names = {c: c if c in ("doc_id", "text") else f"own{k}" for k, c in enumerate(docs.columns)}
    kept = stage(docs.select(*(F.col(f"`{c}`").alias(n) for c, n in names.items())))
    return kept.select(*(F.col(n).alias(c) for c, n in names.items()))


def lowered(text: Column) -> Column:
    """A-Z to a-z and nothing else; ``lower`` would change other letters too."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.translate(text, upper, upper.lower())


def between(text: Column, separators: str) -> Column:
    """The non-empty pieces of a text between separators; none for null.

    A split takes linear time, while Spark's functions that extract all matches copy the text for each match.
    """
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), separators, -1), "")


def word_count(text: Column) -> Column:
    """Number of words of the contracts as a long; 0 for null."""
    return F.size(between(text, SPACE)).cast("long")


def held_out(doc_id: Column) -> Column:
    """The held-out third: crc32 of the id as text, modulo 3, is 1. A null id is not held out (and has no label either)."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, most: int) -> DataFrame:
    """(doc_id, y, text) of at most ``most`` labelled documents outside the held-out third, a row each.

    The sample is drawn from the labels alone, by the order of a hash of the id, so it is the same in every run; being of bounded size it is
    broadcast and only its own texts are shuffled. Null labels are no labels; of repeated ones the largest counts, of rows with one id the text with the least hash.
    """
    picked = (
        labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
        .orderBy(F.xxhash64(F.lit("sample"), "doc_id"), "doc_id").limit(most)
    )
    found = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")
    return found.groupBy("doc_id").agg(F.first("y").alias("y"), F.min(F.struct(F.xxhash64("text").alias("h"), "text"))["text"].alias("text"))
