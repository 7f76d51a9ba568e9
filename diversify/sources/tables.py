"""Point spaces of the given tables, and the generated cloud of the benchmarks."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.operators.space import PointSpace


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load(spark: SparkSession, fmt: str, path: str, schema: str | None = None) -> DataFrame:
    """csv, json, orc or parquet, with a given schema where the format has none."""
    reader = spark.read.format(fmt)
    if schema:
        reader = reader.schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def suppliers(spark: SparkSession, sf_dir: str) -> PointSpace:
    df = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("pid"), F.round("s_acctbal").cast("long").alias("x"), (F.col("s_nationkey").cast("long") * 400).alias("y"), F.col("s_nationkey").cast("long").alias("grp"))
    return PointSpace(df, ("x", "y"))


def lattice(spark: SparkSession, sf_dir: str) -> PointSpace:
    """Distinct positions of the lines; ids are packed positions, so neither a sort nor a rank is needed."""
    li = read(spark, sf_dir, "lineitem")
    q, d, t = F.round("l_quantity").cast("long"), F.round(F.col("l_discount") * 100).cast("long"), F.round(F.col("l_tax") * 100).cast("long")
    df = li.select((q * 10000 + d * 100 + t).alias("pid"), q.alias("x"), (5 * d).alias("y"), (6 * t).alias("z")).distinct()
    return PointSpace(df, ("x", "y", "z"))


def prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pid, x, y, z, w, mult): the lattice with a price axis and the number of lines at each position."""
    li = read(spark, sf_dir, "lineitem")
    q, d, t = F.round("l_quantity").cast("long"), F.round(F.col("l_discount") * 100).cast("long"), F.round(F.col("l_tax") * 100).cast("long")
    w = F.round(F.col("l_extendedprice") / 1000).cast("long")
    return li.select((w * 1000000 + q * 10000 + d * 100 + t).alias("pid"), q.alias("x"), (5 * d).alias("y"), (6 * t).alias("z"), w.alias("w")).groupBy("pid", "x", "y", "z", "w").agg(F.count("*").alias("mult"))


def parts(spark: SparkSession, sf_dir: str) -> PointSpace:
    df = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("pid"), F.col("p_size").cast("long").alias("x"), (F.round(F.col("p_retailprice") * 10) - 9000).cast("long").alias("y"), F.col("p_brand").alias("grp"))
    return PointSpace(df, ("x", "y"))


def customers(spark: SparkSession, sf_dir: str) -> PointSpace:
    df = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("pid"), F.round("c_acctbal").cast("long").alias("x"), F.col("c_nationkey").cast("long").alias("grp"))
    return PointSpace(df, ("x",))


def orders(spark: SparkSession, sf_dir: str) -> PointSpace:
    df = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("pid"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("long").alias("x"), F.round(F.col("o_totalprice") / 100).cast("long").alias("y"))
    return PointSpace(df, ("x", "y"))


def events(spark: SparkSession, sf_dir: str) -> PointSpace:
    x = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(1704067200000000)) / 60000000).cast("long")
    df = read(spark, sf_dir, "events").select(F.col("event_id").alias("pid"), "ts", x.alias("x"), F.round(F.col("value") * 10).cast("long").alias("y"), F.col("event_type").alias("grp"), "user_id")
    return PointSpace(df, ("x", "y"))


def embeddings(spark: SparkSession, sf_dir: str) -> PointSpace:
    df = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pid"), F.col("embedding").cast("array<double>").alias("v"), F.col("label").cast("long").alias("grp"))
    return PointSpace(df, ("v",), "angular")


def letter_runs(text: str):
    """Lower-case runs of letters; a split is linear, extracting all matches copies the text for each."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-z]+", -1), "")


def vocabulary(docs: DataFrame, size: int = 5000) -> DataFrame:
    """(word, n, term): the most frequent words of all texts, by number and then by word."""
    words = docs.select(F.explode_outer(letter_runs("text")).alias("word"))
    top = words.where("word IS NOT NULL").groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(size)
    return top.withColumn("term", F.expr("row_number() OVER (ORDER BY n DESC, word)") - 1)  # ``size`` rows


def word_counts(docs: DataFrame, size: int = 5000) -> DataFrame:
    """(pid, term, cnt) of the words of the vocabulary, which has ``size`` rows and is broadcast."""
    words = docs.select(F.col("doc_id").alias("pid"), F.explode_outer(letter_runs("text")).alias("word"))
    return words.join(F.broadcast(vocabulary(docs, size)), "word").groupBy("pid", "term").agg(F.count("*").alias("cnt"))


def word_vectors(docs: DataFrame, size: int = 5000, min_words: int = 10) -> PointSpace:
    """Sparse count vectors of the documents with at least ``min_words`` distinct words of the vocabulary."""
    v = word_counts(docs, size).groupBy("pid").agg(F.sort_array(F.collect_list(F.struct("term", "cnt"))).alias("v")).where(F.size("v") >= min_words)
    return PointSpace(v, ("v",), "sparse")


def token_sets(docs: DataFrame) -> PointSpace:
    """Distinct lower-case words of the whole texts."""
    toks = F.sort_array(F.array_distinct(letter_runs("text")))
    return PointSpace(docs.select(F.col("doc_id").alias("pid"), toks.alias("v")), ("v",), "jaccard")


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pid, v): orders as sets of parts."""
    return read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("pid")).agg(F.sort_array(F.collect_set("l_partkey")).alias("v"))


def page_text(pages: DataFrame) -> DataFrame:
    """(page_id, text): pages without scripts, styles, comments and tags."""
    t = F.coalesce("html", F.lit(""))
    for pattern in (r"(?s)<!--.*?-->", r"(?is)<script.*?</script>", r"(?is)<style.*?</style>", r"(?s)<[^>]*>"):
        t = F.regexp_replace(t, pattern, " ")
    return pages.select("page_id", F.trim(F.regexp_replace(t, r"[ \t\n\r]+", " ")).alias("text"))


def ball_sphere(spark: SparkSession, n: int, k: int, seed: int = 0, partitions: int | None = None) -> DataFrame:
    """(pid, x, y, z): k points on the unit sphere, the others uniform in the ball of radius 0.8. Values follow from the id, not from the partitioning."""

    def uniform(salt: int):
        return (F.pmod(F.xxhash64("pid", F.lit(seed), F.lit(salt)), F.lit(1 << 53)) + F.lit(0.5)) / F.lit(float(1 << 53))

    rows = spark.range(0, n, 1, partitions).withColumnRenamed("id", "pid")
    height, turn = 2 * uniform(1) - 1, 2 * math.pi * uniform(2)
    r = F.when(F.col("pid") < k, 1.0).otherwise(0.8 * F.pow(uniform(3), F.lit(1 / 3)))
    flat = F.sqrt(1 - height * height)
    return rows.select("pid", (r * flat * F.cos(turn)).alias("x"), (r * flat * F.sin(turn)).alias("y"), (r * height).alias("z"))


def customer_ball(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pid, x, y, z): customers in the unit ball. Nation, balance and key are scaled to a cube around zero, whose surface becomes the sphere."""
    o = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("pid"), F.col("c_nationkey").cast("double").alias("a"), F.col("c_acctbal").cast("double").alias("b"), F.col("c_custkey").cast("double").alias("c"))
    o = o.where("a IS NOT NULL AND b IS NOT NULL AND c IS NOT NULL")
    span = o.agg(*(f(n).alias(f"{n}_{w}") for n in "abc" for w, f in (("lo", F.min), ("hi", F.max))))
    side = lambda n: F.when(F.col(f"{n}_hi") > F.col(f"{n}_lo"), 2 * (F.col(n) - F.col(f"{n}_lo")) / (F.col(f"{n}_hi") - F.col(f"{n}_lo")) - 1).otherwise(0.0)
    cube = o.crossJoin(F.broadcast(span)).select("pid", *(side(n).alias(n) for n in "abc"))  # one row
    norm, far = F.sqrt(sum((F.col(n) * F.col(n) for n in "bc"), F.col("a") * F.col("a"))), F.greatest(*(F.abs(F.col(n)) for n in "abc"))
    pull = F.when(norm > 0, far / norm).otherwise(0.0)
    return cube.select("pid", *((F.col(n) * pull).alias(x) for n, x in zip("abc", "xyz", strict=True)))
