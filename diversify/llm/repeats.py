"""Removal of passages that stand earlier in the corpus too, by seed and extend.

Every window of 20 words contains a winnowed anchor: the smallest hash among its runs of 6 words. Consecutive windows with the same
anchor form a seed together with the words around the anchor that they cover. Seeds with equal anchors and equal words are copies, all
but the first of them repeated; this settles the inside of long copies with one row for each anchor. Where the words around equal
anchors differ, a copy begins or ends: only there the seeds are extended window by window, to the left and to the right of the anchor,
and windows with equal words are compared. The windows found are exactly those whose words also start earlier; adjacent ones cover maximal repeats.

A batch of documents settles its own copies before anything is shuffled, so a passage that very many documents share is one row a batch,
however many copies there are: of the tens of thousands of rows that a batch shuffles, at most one has the same anchor and words.

A frequent phrase with other words around it each time would still gather at its anchor. Anchors that a sample shows to be frequent are
therefore dealt by anchor and words, and all their first seeds extended, without asking whether the words around differ: extending a seed
that needs it not is more work, never another result. So the sample decides only where rows go, as that of a range partitioning does.

Defined cases: null and empty texts have no words; documents of fewer than 20 words lose none; a row with a null id is left whole and
is nobody's earlier copy; rows that repeat id and text are the same document and lose the same words. Other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from diversify.llm.base import checkpoint, table
from diversify.llm.textblocks import U, WORD_BASE, Prefixes, Words, leftmost_minima, mixed, slices

WINDOW, ANCHOR = 20, 6
_RUNS = WINDOW - ANCHOR + 1
#: A place in a document: first window (30 bits), number of windows (up to 15), and 29 bits of the text's hash to tell rows with one id apart.
_START, _COUNT = 33, 29
_TAG = (1 << _COUNT) - 1
SECOND_BASE = 0xA24BAED4963EE407
#: One document in SAMPLED is asked for frequent anchors: those of at least OFTEN sampled seeds, of these the MOST_OFTEN most frequent.
SAMPLED, OFTEN, MOST_OFTEN = 32, 1000, 100_000
#: States of a row: plain, known to have an earlier copy, of a frequent anchor.
PLAIN, DONE, FREQUENT = 0, 1, 2
_NONE = np.zeros(0, np.int64)


def _tags(texts: list[bytes]) -> np.ndarray:
    return np.fromiter((xxhash.xxh64_intdigest(t) & _TAG for t in texts), np.int64, len(texts))


def _long(x: np.ndarray) -> np.ndarray:
    return x.astype(U).view(np.int64)


def _seeds(texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """(text, anchor hash, hash of the seed's words, place) of the seeds of some texts."""
    words = Words(texts)
    ends = words.first[words.doc + 1] if words.n else words.doc
    n = words.n - WINDOW + 1
    if n <= 0:
        return (np.zeros(0, np.int64),) * 4
    hashes = words.hashes()
    runs = Prefixes(hashes, WORD_BASE)
    at = np.arange(words.n - ANCHOR + 1)
    gram = runs.of(at, at + ANCHOR)
    anchor = leftmost_minima(gram, _RUNS)
    valid = np.flatnonzero(np.arange(n) + WINDOW <= ends[:n])
    if not len(valid):
        return (np.zeros(0, np.int64),) * 4
    new = np.concatenate(([True], (anchor[valid[1:]] != anchor[valid[:-1]]) | (valid[1:] != valid[:-1] + 1)))
    begin = valid[new]
    count = np.diff(np.append(np.flatnonzero(new), len(valid)))
    seed = anchor[begin]
    around = Prefixes(mixed(hashes ^ U(SECOND_BASE)), SECOND_BASE).of(begin, begin + count + WINDOW - 1)
    around = mixed(around ^ (seed - begin).astype(U))
    doc = words.doc[begin]
    place = ((begin - words.first[doc]) << _START) | (count << _COUNT) | _tags(texts)[doc]
    return doc, _long(gram[seed]), _long(around), place


def _settled(key: np.ndarray, other: np.ndarray, ids: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, done): rows in the order of key, other, id and place; done: an equal key and other stands earlier in these rows."""
    order = np.lexsort((place, ids, other, key))
    k, o, d, p = key[order], other[order], ids[order], place[order] >> _START
    same = np.concatenate(([False], (k[1:] == k[:-1]) & (o[1:] == o[:-1])))
    head = np.maximum.accumulate(np.where(same, 0, np.arange(len(k))))
    done = same & ((d > d[head]) | (p > p[head]))
    return order, done


def _rows(ids: np.ndarray, key: np.ndarray, other: np.ndarray, place: np.ndarray, frequent: np.ndarray) -> pa.RecordBatch:
    order, done = _settled(key, other, ids, place)
    key, other, ids, place = key[order], other[order], ids[order], place[order]
    state = np.where(done, DONE, PLAIN).astype(np.int8)
    if len(frequent):
        often = np.isin(key, frequent) & ~done
        state[often] = FREQUENT
        key = np.where(often, _long(mixed(key.astype(U) ^ mixed(other.astype(U)))), key)
    key = np.where(done, _long(mixed(ids.astype(U) ^ mixed(place.astype(U)))), key)  # what is done is dealt evenly
    return pa.RecordBatch.from_arrays([pa.array(x) for x in (key, other, ids, place, state)], ["a", "b", "doc_id", "place", "state"])


_ROWS = "a long, b long, doc_id long, place long, state byte"


def _gathered(parts: list[tuple[np.ndarray, ...]], frequent: np.ndarray = _NONE) -> pa.RecordBatch | None:
    return _rows(*(np.concatenate(x) for x in zip(*parts, strict=True)), frequent) if parts else None


def _earlier(rows: DataFrame) -> DataFrame:
    """``rows`` with later: an equal (a, b) stands earlier. Runs over sorted rows with what came first of their group."""
    w = Window.partitionBy("a", "b").orderBy("doc_id", "place").rowsBetween(Window.unboundedPreceding, 0)
    # Plain columns only: an expression here would be computed before the shuffle and be shuffled too.
    of = rows.withColumn("first_id", F.first("doc_id").over(w)).withColumn("first_place", F.first("place").over(w))
    above = F.shiftright("first_place", _START) < F.shiftright("place", _START)
    later = (F.col("state") == DONE) | (F.col("first_id") < F.col("doc_id")) | ((F.col("first_id") == F.col("doc_id")) & above)
    return of.withColumn("later", later).drop("first_id", "first_place")


def _named(docs: DataFrame) -> DataFrame:
    """The rows with an id. Every join by id starts from this same plan, so that the texts are shuffled once and read twice."""
    own = "doc_id" if dict(docs.dtypes)["doc_id"] == "bigint" else F.col("doc_id").cast("long")  # even a cast that does nothing would make two plans of it
    return docs.select(own, "text").where("doc_id IS NOT NULL")


def _seed_rows(docs: DataFrame, frequent: np.ndarray = _NONE) -> DataFrame:
    def made(batches):
        for batch in batches:
            ids, parts = batch.column("doc_id").to_numpy(), []
            for first, texts in slices(batch.column("text")):
                doc, *found = _seeds(texts)
                parts.append((ids[first + doc], *found))
            if (out := _gathered(parts, frequent)) is not None:
                yield out

    return docs.mapInArrow(made, _ROWS)


def frequent_anchors(docs: DataFrame) -> np.ndarray:
    """Anchors that are frequent in a sample of documents even after copies are settled: MOST_OFTEN at most."""
    counts = _seed_rows(docs.where(F.pmod(F.xxhash64(F.lit("sample"), "doc_id"), F.lit(SAMPLED)) == 0)).where(F.col("state") == PLAIN).groupBy("a").agg(F.count("*").alias("n"))
    most = counts.where(F.col("n") >= OFTEN).orderBy(F.desc("n"), "a").limit(MOST_OFTEN)
    return np.array([r.a for r in most.collect()], np.int64)


def seeds(docs: DataFrame) -> DataFrame:
    """(doc_id, repeated, open): places of the seeds that are copies, and of those to be extended window by window."""
    named = _named(docs)
    rows = _seed_rows(named, frequent_anchors(named))
    anchor = Window.partitionBy("a")
    mixed_group = (F.col("state") == FREQUENT) | (F.min("b").over(anchor) < F.max("b").over(anchor))
    told = _earlier(rows.withColumn("mixed", mixed_group)).where("later OR mixed")
    return told.groupBy("doc_id").agg(F.collect_list(F.when(F.col("later"), F.col("place"))).alias("repeated"), F.collect_list(F.when(~F.col("later"), F.col("place"))).alias("open"))


def _places(column: pa.ListArray, row: int) -> np.ndarray:
    return np.asarray(column[row].values) if column[row].is_valid else np.zeros(0, np.int64)


def windows(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """(doc_id, windows): places of single windows, from the open seeds of ``marks``, whose words start earlier too."""

    def made(batches):
        for batch in batches:
            ids, open_, parts = batch.column("doc_id").to_numpy(), batch.column("open"), []
            for first, texts in slices(batch.column("text")):
                words, tags = Words(texts), _tags(texts)
                hashes = words.hashes()
                one, two = Prefixes(hashes, WORD_BASE), Prefixes(mixed(hashes ^ U(SECOND_BASE)), SECOND_BASE)
                for k in range(len(texts)):
                    place = _places(open_, first + k)
                    place = np.unique(place[(place & _TAG) == tags[k]])
                    count = (place >> _COUNT) & 15
                    begin = np.repeat(place >> _START, count) + (np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count))
                    at = begin + words.first[k]
                    parts.append((np.full(len(at), ids[first + k]), _long(one.of(at, at + WINDOW)), _long(two.of(at, at + WINDOW)), (begin << _START) | (1 << _COUNT) | tags[k]))
            if (out := _gathered(parts)) is not None:
                yield out

    some = marks.where(F.size("open") > 0).select("doc_id", "open")
    rows = _named(docs).join(some, "doc_id").select("doc_id", "text", "open").mapInArrow(made, _ROWS)
    return _earlier(rows).where("later").groupBy("doc_id").agg(F.collect_list("place").alias("windows"))


def without_repeats(docs: DataFrame) -> DataFrame:
    """(doc_id, n_words, n_removed, kept, kept_sha256) of every row of ``docs``; kept: the kept words joined by one space."""
    marks = checkpoint(seeds(docs))
    single = windows(docs, marks)

    def made(batches):
        for batch in batches:
            repeated, single = batch.column("repeated"), batch.column("windows")
            for first, texts in slices(batch.column("text")):
                tags, out = _tags(texts), []
                for k, text in enumerate(texts):
                    words = text.split()
                    place = np.concatenate((_places(repeated, first + k), _places(single, first + k)))
                    place = place[(place & _TAG) == tags[k]]
                    removed = 0
                    if len(place):
                        edge = np.zeros(len(words) + 1, np.int64)
                        np.add.at(edge, place >> _START, 1)
                        np.add.at(edge, (place >> _START) + ((place >> _COUNT) & 15) + WINDOW - 1, -1)
                        gone = np.cumsum(edge[:-1]) > 0
                        removed = int(gone.sum())
                        words = [w for w, g in zip(words, gone.tolist(), strict=True) if not g]
                    kept = b" ".join(words)
                    out.append((len(words) + removed, removed, kept, hashlib.sha256(kept).hexdigest()))
                n, gone, kept, digest = zip(*out, strict=True)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, len(texts)), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string()), pa.array(digest)], ["doc_id", "n_words", "n_removed", "kept", "kept_sha256"])

    nobody = F.lit(None).cast("array<long>")
    joined = _named(docs).join(marks.select("doc_id", "repeated"), "doc_id", "left").join(single, "doc_id", "left").select("doc_id", "text", "repeated", "windows")
    unnamed = docs.where("doc_id IS NULL").select(F.col("doc_id").cast("long"), "text", nobody.alias("repeated"), nobody.alias("windows"))
    return joined.unionByName(unnamed).mapInArrow(made, "doc_id long, n_words long, n_removed long, kept string, kept_sha256 string")


def repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return without_repeats(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


QUERIES = {"op3_seed_extend_repeats": repeats}
SQL: dict[str, str] = {}
