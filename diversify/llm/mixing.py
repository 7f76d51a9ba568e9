"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

A keyed hash deals the documents of each source to 1,024 blocks; the hash order is a random permutation of blocks and, within a block,
of documents. A source's target becomes a number of draws from its permuted blocks: whole passes, then the first blocks of another
pass, whose last block is taken up to the exact word (its last document is cut there, so a source misses its target by less than one word).

The draws of all sources are dealt to output shards by a tree: each node splits its shards in two and draws how many blocks of every
source go left from the multivariate hypergeometric distribution of its own counts, so each shard's mix is as random as a shuffle of
all draws would make it while source quotas stay exact. A shard's draws of a source are the next ones in permuted order: shards are
disjoint. Documents of a shard are then shuffled locally: a keyed hash gives each its turn.

Only block sums leave the rows: their number is bounded by sources times blocks, and no source is sorted or held by one task. The driver
plans with a row for each source, MOST_SOURCES at most; more raise an error. Where the last block of a source is cut, its documents are
ranked through 1,024 sub-blocks, again by sums.

Defined cases: a null text has size 0; a null source is a source (the last one); a null id is dealt by its text; empty tables give no
rows; a source without words has target 0; repeated rows get a row each and are drawn like any other document; columns of the result's
names are replaced, others kept, whatever they are called.
"""

from __future__ import annotations

import hashlib
from itertools import accumulate

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from diversify.llm.base import SPACE, between, checkpoint, small_frame, table, word_count

WEIGHTS, SHARE, REPEATS = (3, 1, 2), 1.5, 2
BLOCKS, MOST_SOURCES, SEED = 1024, 100_000, 20
#: Least shards, and words of a shard: their number grows with the mix.
SHARDS, SHARD_WORDS = 16, 50_000_000
#: Runs of turns that are written apart, and most bytes of the block table that are broadcast (ROW for each).
RUNS, BROADCAST, ROW = 16, 64_000_000, 64


def key(doc_id: Column, text: Column) -> Column:
    """60 bits of the MD5 of the id, or of the text where there is none, as a long."""
    named = F.coalesce(doc_id.cast("string"), F.concat(F.lit("text "), F.md5(F.coalesce(text, F.lit("")))))
    return F.conv(F.substring(F.md5(named), 1, 15), 16, 10).cast("long")


def targets(sizes: list[int], weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, repeats: int = REPEATS) -> list[float]:
    """Words for each source: ``share`` times all words by weight, at most ``repeats`` times the source, the excess reshared by weight.

    In the order of size over weight the sources reach their ceilings; the level is that of the first split into ceilings and rest that holds.
    """
    w = [weights[k % len(weights)] for k in range(len(sizes))]
    order = sorted(range(len(sizes)), key=lambda k: (sizes[k] / w[k], k))
    left, over = share * sum(sizes), sum(w)
    level = float("inf")
    for k in order:
        if left / over <= repeats * sizes[k] / w[k]:
            level = left / over
            break
        left -= repeats * sizes[k]
        over -= w[k]
    return [min(float(repeats * n), level * x) if n else 0.0 for n, x in zip(sizes, w, strict=True)]


def log_factorial(n: np.ndarray) -> np.ndarray:
    """Logarithms of factorials: sums of logarithms, Stirling's series from 32."""
    n = np.asarray(n, float)
    m = np.maximum(n, 32)
    series = (m + 0.5) * np.log(m) - m + 0.5 * np.log(2 * np.pi) + 1 / (12 * m) - 1 / (360 * m**3) + 1 / (1260 * m**5)
    return np.where(n < 32, np.cumsum(np.log(np.maximum(np.arange(32), 1)))[np.minimum(n, 31).astype(int)], series)


def hypergeometric(good: int, bad: int, n: int, u: float) -> int:
    """The number of good ones among n drawn of good + bad: the smallest whose cumulative probability reaches u."""
    low, high = max(0, n - bad), min(good, n)
    mean = n * good / max(good + bad, 1)
    wide = 12 * np.sqrt(mean * (1 + bad) / max(good + bad, 1) + 1) + 12  # what is farther away has no probability that a double could add
    x = np.arange(max(low, int(mean - wide)), min(high, int(mean + wide)) + 1)
    choose = lambda a, b: log_factorial(np.asarray(a)) - log_factorial(b) - log_factorial(a - b)
    p = np.exp(choose(good, x) + choose(bad, n - x) - choose(good + bad, np.asarray(n)))
    return int(min(x[0] + np.searchsorted(np.cumsum(p), u), high))


def uniform(*parts: int) -> float:
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:15], 16) / 2**60


def splitting_tree(draws: list[int], shards: int, seed: int = SEED) -> np.ndarray:
    """(shard, source) numbers of draws with the given column sums and rows that differ by one at most in theirs.

    A node's draw is multivariate: source after source, each hypergeometric among what is left of the later ones.
    """
    out = np.zeros((shards, len(draws)), np.int64)
    total = int(sum(draws))
    upto = [total * k // shards for k in range(shards + 1)]
    todo = [(0, shards, list(draws))]
    while todo:
        a, b, own = todo.pop()
        if b - a == 1:
            out[a] = own
            continue
        middle = (a + b) // 2
        left, need, others = [], upto[middle] - upto[a], sum(own)
        for k, n in enumerate(own):
            others -= n
            left.append(hypergeometric(n, others, need, uniform(seed, a, b, k)) if n and need else 0)
            need -= left[-1]
        todo += [(a, middle, left), (middle, b, [x - y for x, y in zip(own, left, strict=True)])]
    return out


def shards_for(words: int, least: int = SHARDS) -> int:
    """Shards of a mix of so many words."""
    return max(least, -(-words // SHARD_WORDS))


def draws(docs: DataFrame, shards: int | None = None, seed: int = SEED) -> DataFrame:
    """``docs`` (size, source, key and more) with source_size, target and draws: an array of (pass, shard, words), empty where the mix takes nothing.

    The document's own columns travel as one struct, so that none can clash with the plan's.
    """
    spark = docs.sparkSession
    kept = [c for c in docs.columns if c not in ("source_size", "target", "draws")]
    keyed = docs.select(F.struct(*kept).alias("row"), "source", "size", "key", F.shiftright("key", 50).cast("int").alias("block"))
    per_block = keyed.groupBy("source", "block").agg(F.sum("size").alias("words"))
    known = per_block.groupBy("source").agg(F.sum("words").alias("words"), F.count("*").alias("blocks")).orderBy(F.asc_nulls_last("source")).limit(MOST_SOURCES + 1).collect()
    if len(known) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    goal = targets([r.words for r in known])
    per_source = [(k, r.source, r.words, goal[k]) for k, r in enumerate(known)]
    sources = small_frame(spark, per_source, f"rank int, source {docs.schema['source'].dataType.simpleString()}, source_size long, target double")
    ranked = per_block.alias("p").join(F.broadcast(sources).alias("s"), F.expr("p.source <=> s.source")).select("rank", "block", "words")
    by_source = Window.partitionBy("rank").orderBy("block")
    before = F.sum("words").over(by_source) - F.col("words")
    placed = checkpoint(ranked.select("rank", "block", F.col("words").alias("block_words"), (F.row_number().over(by_source) - 1).alias("place"), before.alias("before")))
    passes = [divmod(int(g + 0.5), r.words) if r.words else (0, 0) for g, r in zip(goal, known, strict=True)]
    rest = small_frame(spark, [(k, e, x) for k, (e, x) in enumerate(passes)], "rank int, passes long, rest long")
    begun = {r.rank: r.n for r in placed.join(F.broadcast(rest), "rank").where("before < rest").groupBy("rank").agg(F.count("*").alias("n")).collect()}
    quota = [e * r.blocks + begun.get(k, 0) for (k, r), (e, _) in zip(enumerate(known), passes, strict=True)]
    tree = splitting_tree(quota, shards or shards_for(sum(int(g + 0.5) for g in goal)), seed)
    plan = [(k, *passes[k], r.blocks, list(accumulate(tree[:, k].tolist()))) for k, r in enumerate(known)]
    plans = small_frame(spark, plan, "rank int, passes long, rest long, blocks long, upto array<long>")
    table_ = F.broadcast(placed) if ROW * sum(r.blocks for r in known) <= BROADCAST else placed
    rows = keyed.alias("d").join(F.broadcast(sources).alias("s"), F.expr("d.source <=> s.source")).select("row", "key", "size", "block", "rank", "source_size", "target")
    rows = rows.join(table_, ["rank", "block"]).join(F.broadcast(plans), "rank")
    cut = (F.col("before") < F.col("rest")) & (F.col("rest") < F.col("before") + F.col("block_words"))
    inside, last = rows.where(~cut), rows.where(cut).withColumn("sub", F.shiftright("key", 40).cast("int"))
    sums = last.groupBy("rank", "sub").agg(F.sum("size").alias("w"))
    sums = sums.select("rank", "sub", (F.sum("w").over(Window.partitionBy("rank").orderBy("sub")) - F.col("w")).alias("sub_before"))
    in_order = Window.partitionBy("rank", "sub").orderBy("key", F.col("row.doc_id"), "size").rowsBetween(Window.unboundedPreceding, 0)
    at = F.col("before") + F.col("sub_before") + F.sum("size").over(in_order) - F.col("size")
    last = last.join(sums, ["rank", "sub"]).withColumn("extra", F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - at)))
    inside = inside.withColumn("extra", F.when(F.col("before") < F.col("rest"), F.col("size")).otherwise(0))
    both = inside.unionByName(last.select(*inside.columns))

    def draw(n: Column, words: Column) -> Column:
        """Pass n of the document's block: its position among the source's draws tells the shard."""
        position = n * F.col("blocks") + F.col("place")
        return F.struct(n.cast("int").alias("pass"), F.size(F.filter("upto", lambda u: u <= position)).alias("shard"), words.cast("long").alias("words"))

    every = F.when(F.col("passes") > 0, F.sequence(F.lit(0).cast("long"), F.col("passes") - 1)).otherwise(F.array().cast("array<long>"))
    whole = F.transform(every, lambda n: draw(n, F.col("size")))
    part = F.when(F.col("extra") > 0, F.array(draw(F.col("passes"), F.col("extra")))).otherwise(F.slice(whole, 1, 0))
    taken = F.when(F.col("size") > 0, F.concat(whole, part)).otherwise(F.slice(whole, 1, 0))
    return both.select("row.*", "source_size", "target", taken.alias("draws"))


def mix(docs: DataFrame, shards: int | None = None, seed: int = SEED) -> DataFrame:
    """The mix itself: rows of ``docs`` once for each draw, with pass, shard, words and turn (the order within the shard).

    A document that its source's target cuts has its first words, joined by single spaces.
    """
    names = [c for c in docs.columns if c not in ("pass", "shard", "words", "turn")]
    slim = docs.select(F.struct(*names).alias("doc"), "doc_id", "source", word_count(F.col("text")).alias("size"), key(F.col("doc_id"), F.col("text")).alias("key"))
    drawn = draws(slim, shards, seed).select("doc", "size", "key", F.explode("draws").alias("draw"))
    head = F.array_join(F.slice(between(F.col("doc.text"), SPACE), F.lit(1), F.col("draw.words").cast("int")), " ")
    text = F.when(F.col("draw.words") < F.col("size"), head).otherwise(F.col("doc.text")).alias("text")
    turn = F.xxhash64(F.lit(seed), "draw.shard", "draw.pass", "key").alias("turn")
    return drawn.select(*(text if c == "text" else F.col("doc")[c].alias(c) for c in names), "draw.*", turn)


def shuffled(mixed: DataFrame) -> DataFrame:
    """The mix in its shards, each in the order of its turns: RUNS runs of turns a shard, so that a shard need not be one task."""
    run = F.shiftrightunsigned("turn", 64 - RUNS.bit_length() + 1)
    return mixed.repartition("shard", run).sortWithinPartitions("shard", F.shiftrightunsigned("turn", 1), "turn", "doc_id", "pass")


def mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    slim = checkpoint(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), key(F.col("doc_id"), F.col("text")).alias("key")))
    taken = F.aggregate("draws", F.lit(0).cast("long"), lambda a, d: a + d["words"])
    written = F.array_join(F.transform("draws", lambda d: F.concat_ws(":", d["pass"].cast("string"), d["shard"].cast("string"), d["words"].cast("string"))), ",")
    return draws(slim).select("doc_id", "size", "source_size", "target", taken.alias("taken"), written.alias("draws"))


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: the mix of all documents, shard by shard in shuffled order."""
    return shuffled(mix(docs))


QUERIES = {"op5_hypergeometric_mix": mixing}
#: The same tree by recursion: a row for each node, source after source, then its two halves.
SQL = {
    "op5_hypergeometric_mix": r"""
WITH RECURSIVE sized AS (
    SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
           ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'text ' || md5(coalesce(text, '')))), 1, 15))::BIGINT AS k
    FROM documents
), sources AS (
    SELECT source, sum(size)::BIGINT AS s, [3, 1, 2][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS w, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS rank
    FROM sized GROUP BY source
), filled AS (
    SELECT *, (sum(s) OVER ())::DOUBLE * 1.5 - coalesce(sum(2 * s) OVER before, 0)::DOUBLE AS words_left,
           (sum(w) OVER ())::DOUBLE - coalesce(sum(w) OVER before, 0)::DOUBLE AS weight_left
    FROM sources WINDOW before AS (ORDER BY s::DOUBLE / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), level AS (
    SELECT min_by(words_left / weight_left, s::DOUBLE / w) AS l FROM filled WHERE words_left / weight_left <= 2 * s::DOUBLE / w
), goals AS (
    SELECT source, rank, s, CASE WHEN s = 0 THEN 0.0::DOUBLE ELSE least(2.0::DOUBLE * s, coalesce(l, 'inf'::DOUBLE) * w) END AS target FROM sources, level
), planned AS (
    SELECT *, floor(target + 0.5)::BIGINT AS words, CASE WHEN s = 0 THEN 0 ELSE floor(target + 0.5)::BIGINT // s END AS passes,
           CASE WHEN s = 0 THEN 0 ELSE floor(target + 0.5)::BIGINT % s END AS rest
    FROM goals
), walked AS (
    SELECT doc_id, size, s, target, p.rank, passes, rest, k >> 50 AS block,
           (sum(size) OVER (PARTITION BY p.rank ORDER BY k, doc_id, size ROWS UNBOUNDED PRECEDING))::BIGINT - size AS before
    FROM sized JOIN planned p ON sized.source IS NOT DISTINCT FROM p.source
), blocks AS (
    SELECT rank, block, row_number() OVER (PARTITION BY rank ORDER BY block) - 1 AS place, count(*) OVER (PARTITION BY rank) AS n, begins < rest AS begun, passes
    FROM (SELECT rank, block, min(before) AS begins, any_value(rest) AS rest, any_value(passes) AS passes FROM walked GROUP BY rank, block)
), quotas AS (
    SELECT list(q ORDER BY rank) AS own, sum(q)::BIGINT AS total FROM (SELECT rank, (any_value(passes) * any_value(n) + count(*) FILTER (begun))::BIGINT AS q FROM blocks GROUP BY rank)
), shards AS (SELECT greatest(16, ceil(sum(words) / 50000000.0))::BIGINT AS shards FROM planned
), lf AS (SELECT [lgamma((i + 1)::DOUBLE) FOR i IN range(total + 1)] AS f FROM quotas
), tree AS (
    SELECT 0::BIGINT AS a, shards AS b, own, []::BIGINT[] AS went, total * (shards // 2) // shards AS need, total, shards FROM quotas, shards
    UNION ALL (
    SELECT a, b, own, went, need, total, shards FROM (
        SELECT t.a, t.b, any_value(t.own) AS own, any_value(t.need) - x AS need, list_append(any_value(t.went), x) AS went, any_value(t.total) AS total, any_value(t.shards) AS shards
        FROM (
            SELECT *, least(any_value(low) OVER node + count(*) FILTER (c < u) OVER node, any_value(high) OVER node) AS x
            FROM (
                SELECT *, sum(exp(f[good + 1] - f[i + 1] - f[good - i + 1] + f[bad + 1] - f[need - i + 1] - f[bad - need + i + 1] - f[good + bad + 1] + f[need + 1] + f[good + bad - need + 1]))
                          OVER (PARTITION BY a, b ORDER BY i) AS c
                FROM (
                    SELECT *, unnest(range(low, high + 1)) AS i
                    FROM (
                        SELECT *, greatest(0, need - bad) AS low, least(good, need) AS high
                        FROM (
                            SELECT tree.*, f, own[len(went) + 1] AS good, coalesce(list_sum(own[len(went) + 2:]), 0)::BIGINT AS bad,
                                   ('0x' || substr(md5(concat_ws(':', 20, a, b, len(went))), 1, 15))::BIGINT / 1152921504606846976.0::DOUBLE AS u
                            FROM tree, lf WHERE b - a > 1 AND len(went) < len(own)
                        )
                    )
                )
            )
            WINDOW node AS (PARTITION BY a, b)
        ) t GROUP BY t.a, t.b, x
    )
    UNION ALL
    SELECT CASE side WHEN 0 THEN a ELSE (a + b) // 2 END AS a1, CASE side WHEN 0 THEN (a + b) // 2 ELSE b END AS b1,
           CASE side WHEN 0 THEN went ELSE [own[i] - went[i] FOR i IN range(1, len(own) + 1)] END, []::BIGINT[],
           total * ((a1 + b1) // 2) // shards - total * a1 // shards, total, shards
    FROM tree, (SELECT unnest([0, 1]) AS side) WHERE b - a > 1 AND len(went) = len(own)
    )
), upto AS (
    SELECT rank, list(u ORDER BY a) AS upto FROM (
        SELECT a, rank, sum(n) OVER (PARTITION BY rank ORDER BY a) AS u FROM (SELECT a, unnest(own) AS n, unnest(range(len(own))) AS rank FROM tree WHERE b - a = 1 AND len(went) = 0)
    ) GROUP BY rank
), taken AS (
    SELECT w.*, n, place, upto, CASE WHEN size = 0 THEN 0 ELSE greatest(0, least(size, rest - before)) END AS extra
    FROM walked w JOIN blocks b ON b.rank = w.rank AND b.block = w.block JOIN upto ON upto.rank = w.rank
)
SELECT doc_id, size, s AS source_size, target, (passes * size + extra)::BIGINT AS taken,
       CASE WHEN size = 0 THEN '' ELSE array_to_string([concat_ws(':', p, len([u FOR u IN upto IF u <= p * n + place]), CASE WHEN p < passes THEN size ELSE extra END)
           FOR p IN range(passes + (extra > 0)::BIGINT)], ',') END AS draws
FROM taken
"""
}
