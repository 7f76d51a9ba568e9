"""Benchmark decontamination by winnowing, with DataFrame functions only.

Both sides hash every run of 5 words and keep, for each window of 10 words, the smallest of its 6 hashes; equal windows keep equal hashes, so
joining documents and items on the kept hashes loses no shared window. Neighbouring windows mostly keep the same hash, and a document has
one row for such a run of windows. A match is a candidate only: it is extended to the whole windows of the run, and their words are compared
with those of the items' windows. Items of fewer than 10 words are one window that is hashed whole.

The words of a text are split once for all sizes of windows. The fingerprints are slim rows that meet those of the benchmark, which are
broadcast while their number is under BROADCAST. Only documents with a candidate have their texts read again: while the candidates are fewer
than CANDIDATES they are broadcast, and no text is shuffled; beyond, both are shuffled by the hash of the text.

Defined cases: null and empty texts have no words and no hits; items without words never occur; items with a null id can be hit but
are not listed; rows that repeat an id are separate rows, each judged by its own text; items that repeat an id are one item. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from diversify.llm.base import between, checkpoint, lowered, table

WINDOW, RUN = 10, 5
#: Most windows of the benchmark that are broadcast; each takes some 100 bytes.
BROADCAST = 1_000_000
#: Most runs of windows that are broadcast as candidates; each takes some 50 bytes.
CANDIDATES = 500_000
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
GAP_ANY_CASE = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def words(text: Column) -> Column:
    return between(lowered(text), GAP)


def _hashes(w: Column, run: int) -> Column:
    """Hash of the run of words at each position that has one."""
    return F.transform(F.slice(w, F.lit(1), F.greatest(F.size(w) - (run - 1), F.lit(0))), lambda x, i: F.xxhash64(x, *(F.get(w, i + k) for k in range(1, run))))


def _kept(h: Column) -> Column:
    """Winnowing: the smallest hash of each window, by the window's first word."""
    span = WINDOW - RUN + 1
    return F.transform(F.slice(h, F.lit(1), F.greatest(F.size(h) - (span - 1), F.lit(0))), lambda x, i: F.least(x, *(F.get(h, i + k) for k in range(1, span))))


def _with_prints(rows: DataFrame, sizes: list[int], *keep: str) -> DataFrame:
    """``keep`` of ``rows`` (with w, their words) and p<size>: the print of each window of so many words.

    Every step reads plain columns: within a function over an array an expression would be computed anew for each element.
    """
    runs = rows.select(*keep, *(_hashes(F.col("w"), RUN if size == WINDOW else size).alias(f"h{size}") for size in sizes))
    return runs.select(*keep, *((_kept(F.col(f"h{WINDOW}")) if size == WINDOW else F.col(f"h{size}")).alias(f"p{size}") for size in sizes))


def _starts(prints: Column) -> Column:
    """Where a print differs from the one before."""
    return F.array_compact(F.transform(prints, lambda x, i: F.when((i == 0) | (x != F.get(prints, i - 1)), i)))


def _runs(prints: Column, starts: Column, size: int) -> Column:
    """(size, at, n, print) of each run of n neighbouring windows with one print, the first of them at ``at``."""
    end = lambda i: F.coalesce(F.get(starts, i + 1), F.size(prints))
    return F.transform(starts, lambda x, i: F.struct(F.lit(size).alias("size"), x.alias("at"), (end(i) - x).alias("n"), F.get(prints, x).alias("print")))


def benchmark_windows(items: DataFrame) -> DataFrame:
    """(item_id, size, gram, print): every window of every item."""
    w = items.select("item_id", words(F.col("text")).alias("w")).where(F.size("w") > 0).withColumn("size", F.least(F.size("w"), F.lit(WINDOW)))
    parts = []
    for size in [r[0] for r in w.select("size").distinct().orderBy("size").collect()]:  # at most ten
        own = _with_prints(w.where(F.col("size") == size), [size], "item_id", "size", "w").select("item_id", "size", "w", F.posexplode_outer(f"p{size}").alias("at", "print"))
        parts.append(own.select("item_id", "size", F.array_join(F.slice("w", F.col("at") + 1, F.lit(size)), " ").alias("gram"), "print"))
    out = parts[0] if parts else items.sparkSession.createDataFrame([], f"item_id {dict(items.dtypes)['item_id']}, size int, gram string, print long")
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.distinct()


def hits(docs: DataFrame, items: DataFrame) -> DataFrame:
    """(doc_id, th, n_hit, items): documents with a window of an item; th: a hash of the text that tells rows with one id apart."""
    bench = checkpoint(benchmark_windows(items))
    small = F.broadcast if bench.count() <= BROADCAST else (lambda df: df)
    named = docs.select("doc_id", F.xxhash64("text").alias("th"), "text")
    sizes = [r[0] for r in bench.select("size").distinct().orderBy("size").collect()]
    if not sizes:
        return named.select("doc_id", "th", F.lit(0).cast("long").alias("n_hit"), F.array().cast("array<string>").alias("items")).limit(0)
    # One split and one pass for all sizes. An outer explode: for an inner one the optimizer filters on the array's size beforehand, which would
    # compute the words anew for each element.
    own = _with_prints(named.select("doc_id", "th", words(F.col("text")).alias("w")), sizes, "doc_id", "th")
    own = own.select("*", *(_starts(F.col(f"p{size}")).alias(f"s{size}") for size in sizes))
    runs = own.select("doc_id", "th", F.inline_outer(F.concat(*(_runs(F.col(f"p{size}"), F.col(f"s{size}"), size) for size in sizes))))
    found = runs.join(small(bench.select("size", "print").distinct()), ["size", "print"]).select("doc_id", "th", "at", "n", "size")
    candidates = checkpoint(found.groupBy("doc_id", "th").agg(F.collect_list(F.struct("at", "n", "size")).alias("runs")))
    some = F.broadcast if (candidates.agg(F.sum(F.size("runs"))).first()[0] or 0) <= CANDIDATES else (lambda df: df)
    same_row = (F.col("d.th") == F.col("c.th")) & F.col("d.doc_id").eqNullSafe(F.col("c.doc_id"))
    texts = named.alias("d").join(some(candidates).alias("c"), same_row).select("d.doc_id", "d.th", words(F.col("text")).alias("w"), "runs")
    starts = lambda r: F.transform(F.sequence(r["at"], r["at"] + r["n"] - 1), lambda k: F.struct(k.alias("at"), r["size"].alias("size")))
    texts = texts.withColumn("windows", F.array_distinct(F.flatten(F.transform("runs", starts))))
    gram = F.transform("windows", lambda x: F.struct(x["at"].alias("at"), x["size"].alias("size"), F.array_join(F.slice("w", x["at"] + 1, x["size"]), " ").alias("gram")))
    grams = texts.select("doc_id", "th", F.inline_outer(gram)).distinct()
    there = grams.join(small(bench.select("size", "gram").distinct()), ["size", "gram"])
    before = Window.partitionBy("doc_id", "th").orderBy("at", "size").rowsBetween(Window.unboundedPreceding, -1)
    end = F.col("at") + F.col("size")
    new = F.greatest(F.lit(0), end - F.greatest("at", F.coalesce(F.max(end).over(before), F.col("at"))))
    covered = there.select("doc_id", "th", new.alias("new")).groupBy("doc_id", "th").agg(F.sum("new").cast("long").alias("n_hit"))
    listed = there.select("doc_id", "th", "size", "gram").distinct().join(small(bench.select("size", "gram", F.col("item_id").cast("string").alias("item"))), ["size", "gram"])
    listed = listed.groupBy("doc_id", "th").agg(F.array_sort(F.collect_set("item")).alias("items"))
    c, i = covered.alias("c"), listed.alias("i")
    return c.join(i, (F.col("c.th") == F.col("i.th")) & F.col("c.doc_id").eqNullSafe(F.col("i.doc_id"))).select("c.doc_id", "c.th", "n_hit", "items")


def contamination(docs: DataFrame, items: DataFrame) -> DataFrame:
    """(doc_id, n_words, n_hit, items) of every row of ``docs``; items: ids as strings, sorted."""
    base = docs.select("doc_id", F.xxhash64("text").alias("th"), F.size(between(F.col("text"), GAP_ANY_CASE)).cast("long").alias("n_words"))
    h = hits(docs, items).alias("h")
    joined = base.alias("b").join(h, (F.col("b.th") == F.col("h.th")) & F.col("b.doc_id").eqNullSafe(F.col("h.doc_id")), "left")
    return joined.select("b.doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents without a window of the benchmark."""
    found = hits(docs, table(spark, sf_dir, "benchmark")).alias("h")
    same = (F.xxhash64("d.text") == F.col("h.th")) & F.col("d.doc_id").eqNullSafe(F.col("h.doc_id"))
    return docs.alias("d").join(found, same, "left_anti").select(*(f"d.{c}" for c in docs.columns))


QUERIES = {"op9_winnowed_leaks": leaks}
SQL = {
    "op9_winnowed_leaks": r"""
WITH d AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
    FROM documents
), i AS (
    SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
    FROM benchmark
), spans AS (SELECT item_id, w, least(len(w), 10) AS n FROM i WHERE len(w) > 0
), grams AS (
    SELECT DISTINCT item_id, n, array_to_string(list_slice(w, s + 1, s + n), ' ') AS g
    FROM (SELECT item_id, w, n, unnest(range(len(w) - n + 1)) AS s FROM spans)
), places AS (
    SELECT doc_id, n, s, array_to_string(list_slice(w, s + 1, s + n), ' ') AS g
    FROM (SELECT doc_id, w, n, unnest(range(len(w) - n + 1)) AS s FROM d, (SELECT DISTINCT n FROM spans) WHERE len(w) >= n)
), hit AS (SELECT doc_id, n, s, item_id FROM places JOIN grams USING (n, g)
), covered AS (
    SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM (SELECT DISTINCT doc_id, n, s FROM hit)) GROUP BY doc_id
), listed AS (
    SELECT doc_id, count(*) AS n_items, string_agg(id, ',' ORDER BY id) AS ids FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS id FROM hit) GROUP BY doc_id
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN listed USING (doc_id)
"""
}
