"""Near copies by SimHash: 64-bit fingerprints of word shingles, linked where two or fewer bits differ, found with vantage points.

Only distinct fingerprints are compared. A vantage point and a radius split them into those inside and those outside; by the triangle
inequality a fingerprint outside can only be near one that is inside by less than two bits of distance, and just those visit
the outer side too. Several such splits, one vantage point for each level, deal the fingerprints to shards; within a shard the tree is
carried on with vantage points of its own. Every pair within two bits meets in some shard, so the links are exact. A shard with too many
fingerprints (one huge cluster) is dealt differently: two fingerprints differ in at most two bits if and only if some value is within one bit of both, so the
64 + 1 values around each are its keys and each key links what shares it.

Defined cases: a null or empty text has fingerprint zero; fewer than three words make one shingle; a row with a null id gets the
component of its fingerprint (null if no id shares it); repeated rows get a row each. Other columns are ignored.
"""

from __future__ import annotations

from itertools import pairwise

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.llm.base import checkpoint, renamed, table
from diversify.llm.links import components, local_components
from diversify.llm.textblocks import U, Words, slices

SHINGLE, SEED, NEAR = 3, 42, 2
#: Fingerprints that a shard should hold, and the number from which it is dealt by neighbouring values.
SHARD, CROWD = 4000, 40_000
#: Most levels of vantage points: a level has about a fifth of the fingerprints visit both sides, so more would copy each over the 65 times of its neighbouring values.
LEVELS = 19
_BALL = np.concatenate((np.zeros(1, U), U(1) << np.arange(64, dtype=U)))


def fingerprints(texts: list[bytes]) -> np.ndarray:
    """A fingerprint for each text, as uint64."""
    words = Words(texts, lower=True)
    out = np.zeros(len(texts), U)
    n = words.counts
    last = np.repeat(words.first[1:], n)  # first word of the next text
    at = np.arange(words.n)
    whole = np.minimum(at + SHINGLE, last)
    used = (at + SHINGLE <= last) | ((np.repeat(n, n) < SHINGLE) & (at == np.repeat(words.first[:-1], n)))
    begins, stops = words.starts[used].tolist(), words.ends[whole[used] - 1].tolist()
    if not begins:
        return out
    raw, digest = words.raw, xxhash.xxh64_intdigest
    h = np.fromiter((digest(raw[a:b], SEED) for a, b in zip(begins, stops, strict=True)), U, len(begins))
    doc = words.doc[used]
    edges = np.concatenate(([0], np.flatnonzero(doc[1:] != doc[:-1]) + 1, [len(doc)]))
    set_bits = np.empty((len(edges) - 1, 64), np.int64)
    for k, (a, b) in enumerate(pairwise(edges)):
        set_bits[k] = np.unpackbits(h[a:b].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    over = set_bits * 2 > np.diff(edges)[:, None]
    out[doc[edges[:-1]]] = np.packbits(over, axis=1, bitorder="little").view(U).ravel()
    return out


def with_fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, th, fp as a signed long) of every row; th is the hash of the text."""

    def made(batches):
        for batch in batches:
            for first, texts in slices(batch.column("text")):
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, len(texts)), batch.column("th").slice(first, len(texts)), pa.array(fingerprints(texts).view(np.int64))], ["doc_id", "th", "fp"])

    return docs.select("doc_id", F.xxhash64("text").alias("th"), "text").mapInArrow(made, f"doc_id {dict(docs.dtypes)['doc_id']}, th long, fp long")


def _around(f: np.ndarray, root: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Joins what shares a value within one bit."""
    keys = (f[at][:, None] ^ _BALL).ravel()
    who = np.repeat(at, len(_BALL))
    order = np.argsort(keys, kind="stable")
    keys, who = keys[order], who[order]
    same = keys[1:] == keys[:-1]
    return _join(root, who[1:][same], who[:-1][same])


def _join(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    differ = root[a] != root[b]
    return local_components(len(root), root[a[differ]], root[b[differ]])[root] if differ.any() else root


def near_roots(f: np.ndarray) -> np.ndarray:
    """For each of some distinct fingerprints the index of the first in its component; a vantage-point tree over them."""
    root, todo = np.arange(len(f)), [np.arange(len(f))]
    while todo:
        at = todo.pop()
        if len(at) <= 384:
            a, b = np.nonzero(np.triu(np.bitwise_count(f[at][:, None] ^ f[at][None, :]) <= NEAR, 1))
            root = _join(root, at[a], at[b])
            continue
        away = np.bitwise_count(f[at] ^ f[at[len(at) // 2]])
        radius = int(np.median(away))
        inner, outer = at[away <= radius], at[away > radius - NEAR]
        if max(len(inner), len(outer)) > 0.9 * len(at):
            root = _around(f, root, at)
        else:
            todo += [inner, outer]
    return root


def _sides(distance: Column, radius: int) -> Column:
    """0: inside, 1: outside; both for those inside that can be near one outside."""
    return F.when(distance <= radius - NEAR, F.array(F.lit(0))).when(distance <= radius, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(1)))


def _dealt(prints: DataFrame, rows: int) -> DataFrame:
    """(shard, fp): each fingerprint in its own shard and in those that it visits. Vantage points and radii come from the data."""
    levels = 0
    while rows * 0.6**levels > SHARD and levels < LEVELS:
        levels += 1
    if not levels:
        return prints.select(F.lit(0).cast("long").alias("shard"), "fp")
    points = [r.fp for r in prints.orderBy(F.xxhash64("fp"), "fp").limit(levels).collect()]
    away = [F.bit_count(F.col("fp").bitwiseXOR(F.lit(p))) for p in points]
    radii = prints.agg(*(F.percentile_approx(d, 0.5).alias(f"r{k}") for k, d in enumerate(away))).first()
    shards = F.array(F.lit(0).cast("long"))
    for d, r in zip(away, radii, strict=True):
        shards = F.flatten(F.transform(shards, _numbers(_sides(d, r))))
    return prints.select(F.explode(shards).alias("shard"), "fp")


def _numbers(sides: Column):
    return lambda shard: F.transform(sides, lambda side: shard * 2 + side)


def near_links(prints: DataFrame) -> DataFrame:
    """(a, b): links whose components are those of all pairs of distinct fingerprints within two bits."""
    dealt = _dealt(prints, prints.count())
    crowds = dealt.groupBy("shard").count().where(F.col("count") > CROWD).select("shard")  # at most one for every CROWD rows; broadcast only if small

    def linked(t: pa.Table) -> pa.Table:
        fp = np.unique(t.column("fp").to_numpy())
        root = near_roots(fp.view(U))
        moved = root != np.arange(len(fp))
        return pa.table({"a": fp[moved], "b": fp[root[moved]]})

    shards = dealt.join(crowds, "shard", "left_anti").groupBy("shard").applyInArrow(linked, "a long, b long")
    ball = F.explode(F.array(*(F.col("fp").bitwiseXOR(F.lit(int(v))) for v in _BALL.view(np.int64))))
    keys = dealt.join(crowds, "shard", "left_semi").select("fp").distinct().select("fp", ball.alias("key"))
    least = keys.groupBy("key").agg(F.min("fp").alias("b"))
    crowd_links = keys.join(least, "key").where("fp <> b").select(F.col("fp").alias("a"), "b")
    return shards.unionByName(crowd_links)


def _in_components(docs: DataFrame) -> DataFrame:
    """(doc_id, th, fp, root, component_id) of every row of ``docs``: th is the hash of its text, root the fingerprint that names its component."""
    rows = checkpoint(with_fingerprints(docs))
    classes = checkpoint(rows.groupBy("fp").agg(F.min("doc_id").alias("least")))
    found = components(near_links(classes.select("fp")), "a", "b")
    of = classes.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("root"))
    ids = of.join(of.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("fp", "root", "component_id")
    return rows.join(ids, "fp").select("doc_id", "th", "fp", "root", "component_id")


def near_copies(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, component_id) of every row of ``docs``."""
    return _in_components(docs).select("doc_id", "fp", "component_id")


def simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_copies(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of each group of near copies the document with the smallest id stays, once; rows without an id stay. Rows that repeat an id are judged by their own text."""
    first = _in_components(docs).where("doc_id = component_id").groupBy("root").agg(F.min("doc_id").alias("doc_id"), F.min("th").alias("th"))

    def kept(d: DataFrame) -> DataFrame:
        own = d.withColumn("th", F.xxhash64("text")).join(first, ["doc_id", "th"], "left_semi").dropDuplicates(["doc_id", "th"])
        return own.drop("th").unionByName(d.where("doc_id IS NULL"))

    return renamed(docs, kept)


QUERIES = {"op8_vantage_simhash": simhash}
SQL: dict[str, str] = {}
