"""Licence notices in documents: a sparse word n-gram logistic regression over paragraphs, confirmed by templates. DataFrame functions only.

Paragraphs end at lines without a letter or digit and are judged sentence by sentence, as a notice often stands within other text. A
sentence over several lines is judged as a whole, as notices are wrapped, and line by line, as lists of notices have no full stops; the
whole counts only for families that none of its lines has. A sentence does not end at the point of an abbreviation.

Words are those of a normal form: small letters, one spelling of licence, versions as "version 2" however they are written, identifiers as
one word without "only" and "or later". The regression is multinomial over hashed 1- to 3-grams. Training examples are notices composed
of introductions and the names and texts of each family; for the unknown class, sentences with the same words that give no licence, and a
bounded sample of the documents' own sentences that hold a cue but no template. Its scale is calibrated on examples whose name the
regression has not seen (folds are drawn by name), so the unknown class competes with honest probabilities.

A sentence has a notice of a family if the family's probability among all classes, the unknown one included, is CERTAIN or more, and if a
template of that family stands in it: the template's word pairs in order, all of a short one, TEMPLATE of a long one. Every template holds
one of HINTS, so sentences without one cannot have a notice and are skipped unscored.

Defined cases: null and empty texts have no notices; repeated ids keep a row each, judged by their own text; a document
may carry several families; without documents the model still trains on the composed examples. Other columns are ignored.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.llm.base import between, checkpoint, small_frame, table

#: Hashed grams, most sentences of the documents that are examples of the unknown class, folds by name.
BUCKETS, SAMPLE, FOLDS = 1 << 14, 1000, 5
#: Least probability, least share of a long template's word pairs, and words from which a template is long.
CERTAIN, TEMPLATE, LONG = 0.6, 0.8, 8
UNKNOWN = "unknown"

# Names, identifiers and key sentences by family, in the normal form of ``tokens``.
FAMILIES = {
    "apache": (
        "apache license version 2", "apache 2 license", "apache version 2 license", "apache software license", "apache license", "apache-2",
        "spdx-license-identifier apache-2",
    ),
    "mit": (
        "mit license", "mit x11 license", "expat license", "spdx-license-identifier mit", "license mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files",
    ),
    "isc": (
        "isc license", "spdx-license-identifier isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted",
    ),
    "gpl": (
        "gnu general public license version 3", "gnu general public license version 2", "gnu general public license", "gnu gpl", "gpl version 3",
        "gpl version 2", "gpl license", "gpl 2", "gpl 3", "gpl-3", "gpl-2", "spdx-license-identifier gpl-2",
    ),
    "lgpl": (
        "gnu lesser general public license version 2.1", "gnu lesser general public license", "gnu library general public license", "gnu lgpl",
        "lgpl version 3", "lgpl version 2.1", "lgpl license", "lgpl 3", "lgpl 2.1", "lgpl-2.1", "lgpl-3", "lgpl-2",
    ),
    "agpl": (
        "gnu affero general public license version 3", "gnu affero general public license", "affero general public license", "gnu agpl", "agpl version 3",
        "agpl license", "agpl 3", "agpl-3",
    ),
    "bsd": (
        "bsd license", "bsd 3-clause license", "bsd 2-clause license", "3-clause bsd", "2-clause bsd", "bsd-3-clause", "bsd-2-clause", "bsd style license",
        "bsd-style license", "spdx-license-identifier 0bsd", "redistribution and use in source and binary forms with or without modification are permitted",
    ),
    "mpl": ("mozilla public license version 2", "mozilla public license", "mpl version 2", "mpl 2", "mozilla.org mpl 2", "mpl version 1.1", "mpl license", "mpl-2", "mpl-1.1"),
    "epl": ("eclipse public license version 2", "eclipse public license", "epl version 2", "epl version 1", "epl-2", "epl-1"),
    "cc-by-nc": (
        "cc by-nc 4", "cc by-nc", "cc by-nc-sa 4", "cc by-nc-sa", "cc by-nc-nd 4", "cc by-nc-nd", "cc-by-nc-4", "cc-by-nc-sa-4", "cc-by-nc-nd-4",
        "creative commons attribution-noncommercial license", "creative commons attribution-noncommercial", "creative commons attribution noncommercial",
        "creative commons attribution-noncommercial 4 international license",
        "creative commons attribution-noncommercial-sharealike 4 international license",
        "creative commons attribution-noncommercial-noderivatives 4 international license",
    ),
    "cc-by-sa": (
        "cc by-sa 4", "cc by-sa 3", "cc by-sa", "cc-by-sa-4", "cc-by-sa-3", "creative commons attribution-sharealike license",
        "creative commons attribution-sharealike", "creative commons attribution sharealike",
        "creative commons attribution-sharealike 4 international license",
    ),
    "cc-by": (
        "cc by 4", "cc by 3", "cc by license", "cc-by-4", "cc-by-3", "creative commons attribution 4 international license",
        "creative commons attribution 3 unported license", "creative commons attribution license", "creative commons by 4",
    ),
    "public-domain": (
        "cc0 1 universal", "cc0 license", "cc0-1", "cc0 dedication", "public domain dedication", "dedicated to the public domain",
        "released into the public domain", "placed in the public domain", "the unlicense", "unlicense license",
    ),
    "zlib": ("zlib license", "zlib libpng license", "spdx-license-identifier zlib"),
    "boost": ("boost software license version 1", "boost software license", "boost license", "bsl-1"),
    "artistic": ("artistic license version 2", "artistic license 2", "perl artistic license", "artistic-2"),
    "eupl": ("european union public license", "eupl version 1.2", "eupl license", "eupl-1.2"),
    "proprietary": (
        "all rights reserved", "may not be reproduced without permission", "may not be copied or distributed without written permission",
        "proprietary and confidential",
    ),
}
INTROS = (
    "", "licensed under the", "licensed under", "released under the", "this work is licensed under the", "this work is licensed under",
    "distributed under the terms of the", "available under", "code license",
    "this software is provided under the", "you may use this file under the", "it is free software under the", "published under",
    "copyright 2020 by the authors", "see the", "spdx-license-identifier",
)
#: Sentences with the templates' words that give no licence.
NO_FAMILY = (
    "licensed under a custom agreement", "see the license file for details", "the license of the driver was renewed",
    "a licensed professional must be present", "released under pressure",
    "distributed under the table", "this work is done", "the public license office is open", "version 2 of the report", "version 3 of the plan",
    "all rights and duties", "the general public was invited to the opening",
    "a creative work of the commons", "please read the license", "copyright questions are hard", "under the terms of the treaty",
    "this software is provided by the office", "you may use this file",
    "the apache helicopter version 2 software had a license", "an apache pilot lost his license", "the apache tribe and its land",
    "an apache web server ran version 2", "he studied at mit and has a driving license",
    "the mit campus and its library", "a gnu and a zebra", "the gnu grazed near the general store", "the public license plate of the general",
    "she held a general license for public works", "the bsd conference took place",
    "a bsd kernel was compiled", "redistribution of wealth and income", "redistribution in source countries", "the mozilla mascot and the public",
    "mozilla released a browser", "an eclipse of the sun was public",
    "the house of commons debated creative attribution", "the village commons and a license to graze", "a public domain name was sold",
    "the public hearing in the domain of the king", "the rights of guests were reserved",
    "seats reserved for members with all rights", "permission is granted to enter the building", "permission to use the road is required",
    "a boost for software sales", "an artistic license of the painter", "artistic license allows poets to bend rules",
    "zlib compresses the files", "the european union and the public", "attribution of the painting is unsure", "the noncommercial use of land",
    "cc the manager by noon", "proprietary methods of the firm", "written permission of the owner",
    "a license is required for fishing", "the license expired",
    "the license fee was paid", "licensed premises close at ten", "an unlicensed driver", "an apache license plate was stolen",
    "license plates are sold", "he drove mit license and insurance", "they want to boost license revenue", "boost license fees", "license und ausweis",
    "all rights reserved seats were sold", "reserved seats for the press", "the mit license plate collection",
    "the copyright office is closed", "copyright law is studied here",
)
HINTS = (
    "licen", "hereby granted", "gpl", "gnu", "bsd", "redistribution", "mpl", "epl", "eupl", "cc by", "cc-by", "cc0", "commons",
    "public domain", "rights reserved", "reproduced without", "apache", "bsl-", "artistic-", "confidential", "distributed without",
)

#: Between sentences: lines without a letter or digit, or white space after an end that is no abbreviation's.
BREAK = r"\r?\n(?:[^\p{L}\p{N}\r\n]*+\r?\n)+|(?<=[.!?])(?<!(?i:\b(?:v|ver|vers|rev|no|nr|cf|e\.g|i\.e|inc|ltd|corp)\.))\s+"


def hinted(text: Column) -> Column:
    low = F.lower(text)
    return reduce(lambda a, b: a | b, [low.contains(h) for h in HINTS])


def tokens(sentence: Column) -> Column:
    """Words of the normal form, with the points and dashes inside them: those at their ends belong to the gaps."""
    t = F.regexp_replace(F.lower(sentence), "licence", "license")
    t = F.regexp_replace(t, r"(?<![a-z0-9])([al]?gpl|mpl|epl|eupl)v(?=[0-9])", "$1 version ")
    t = F.regexp_replace(t, r"(?<![a-z0-9.-])v(?:er(?:s(?:ion)?)?)?(?:\.\s*+|\s++)?(?=[0-9])", "version ")
    t = F.regexp_replace(t, r"(?<=[a-z0-9])-(?:or-later|only)(?![a-z0-9-])", "")
    t = F.regexp_replace(t, r"(?<=[0-9])\.0(?!\.?[0-9a-z])", "")
    return between(t, r"(?:[^a-z0-9.-]|[.-](?=[^a-z0-9]|$)|(?<![a-z0-9])[.-])++")


def buckets(words: Column) -> Column:
    """The distinct hashed 1- to 3-grams of an array of words."""
    gram = lambda *x: F.pmod(F.xxhash64(*x), F.lit(BUCKETS)).cast("int")
    one = F.transform(words, lambda x: gram(x))
    two = F.transform(F.slice(words, F.lit(1), F.greatest(F.size(words) - 1, F.lit(0))), lambda x, i: gram(x, F.get(words, i + 1)))
    three = F.transform(F.slice(words, F.lit(1), F.greatest(F.size(words) - 2, F.lit(0))), lambda x, i: gram(x, F.get(words, i + 1), F.get(words, i + 2)))
    return F.array_distinct(F.concat(one, two, three))


def word_pairs(words: Column) -> Column:
    """The distinct pairs of neighbouring words."""
    firsts = F.slice(words, F.lit(1), F.greatest(F.size(words) - 1, F.lit(0)))
    return F.array_distinct(F.transform(firsts, lambda x, i: F.concat(x, F.lit(" "), F.get(words, i + 1))))


def examples() -> list[tuple[str, str, str]]:
    """(family, name, text) composed of introductions and names, and the unknown ones, each its own name."""
    named = [(family, name, intro) for family, names in FAMILIES.items() for name in names for intro in (INTROS if len(name.split()) < LONG else INTROS[:3])]
    known = [(family, name, f"{intro} {name}".strip()) for family, name, intro in named]
    return known + [(UNKNOWN, x, y) for x in NO_FAMILY for y in (x, f"he said that {x}", f"{x} in the end")]


def templates_in(words: Column) -> Column:
    """The families of which a template stands in an array of words, in order."""
    pairs, found = word_pairs(words), []
    for family, names in FAMILIES.items():
        short = [n.split() for n in names if 1 < len(n.split()) < LONG]
        long_ = [n.split() for n in names if len(n.split()) >= LONG]
        tests = [F.arrays_overlap("w", F.array(*(F.lit(n) for n in names if " " not in n)))] if any(" " not in n for n in names) else []
        several = [p for p in ([f"{a} {b}" for a, b in zip(n, n[1:], strict=False)] for n in short) if len(p) > 1]
        one = [" ".join(n) for n in short if len(n) == 2]
        tests += [F.arrays_overlap("p", F.array(*map(F.lit, one)))] if one else []
        tests += [F.size(F.array_except(F.array(*map(F.lit, p)), "p")) == 0 for p in several]
        for n in long_:
            p = sorted({f"{a} {b}" for a, b in zip(n, n[1:], strict=False)})
            tests.append(F.size(F.array_intersect(F.array(*map(F.lit, p)), "p")) >= TEMPLATE * len(p))
        found.append((family, reduce(lambda a, b: a | b, tests)))
    return pairs, F.filter(F.array(*(F.when(t, F.lit(f)) for f, t in found)), lambda x: x.isNotNull())


def with_templates(sentences: DataFrame) -> DataFrame:
    """``sentences`` (with w, their words) with families: those of the templates that stand in them."""
    pairs, found = templates_in(F.col("w"))
    return sentences.withColumn("p", pairs).withColumn("families", found).drop("p")


@dataclass
class Regression:
    """Classes, weights by bucket and class, biases and the calibrated scale."""

    classes: list[str]
    weights: np.ndarray
    bias: np.ndarray
    scale: float

    def frame(self, spark: SparkSession) -> DataFrame:
        """(bucket, c0, c1, ..): the scaled weights of the buckets that have any."""
        used = np.flatnonzero(np.abs(self.weights).sum(1) > 1e-6)
        names = ", ".join(f"c{k} double" for k in range(len(self.classes)))
        rows = [(int(k), *(round(float(x), 9) for x in self.weights[k] * self.scale)) for k in used]
        return checkpoint(small_frame(spark, rows, f"bucket int, {names}"))  # else every description of the plan would hold it


def scored(sentences: DataFrame, model: Regression) -> DataFrame:
    """The columns of ``sentences`` but w, their words, with family, the likeliest class, and its probability p.

    Grams meet the weights, which are bounded by BUCKETS and broadcast, and are summed where they are before the shuffle.
    """
    keys = [c for c in sentences.columns if c != "w"]
    grams = sentences.select(*keys, F.explode_outer(buckets(F.col("w"))).alias("bucket")).join(F.broadcast(model.frame(sentences.sparkSession)), "bucket", "left")
    n = range(len(model.classes))
    sums = grams.groupBy(*keys).agg(*(F.sum(F.coalesce(f"c{k}", F.lit(0.0))).alias(f"c{k}") for k in n))
    level = F.array(*(F.round(F.col(f"c{k}") + F.lit(float(model.bias[k] * model.scale)), 9) for k in n))
    top = F.array_max("z")
    total = F.aggregate("z", F.lit(0.0), lambda a, x: a + F.exp(x - top))
    family = F.element_at(F.array(*map(F.lit, model.classes)), F.array_position("z", top).cast("int"))
    return sums.select(*keys, level.alias("z")).select(*keys, family.alias("family"), F.round(1 / total, 6).alias("p"))


def fit(rows: list[tuple[str, str, list[int]]], vocabulary: set[int], rounds: int = 100) -> Regression:
    """rows: family, name, buckets. Adam with a quadratic penalty, from zero. The scale minimises the loss of each fold's names under a model without them.

    Only grams of the composed examples (``vocabulary``) have weights, so a notice is found among any other words of its sentence.
    """
    classes = [*FAMILIES, UNKNOWN]
    y = np.array([classes.index(f) for f, _, _ in rows])
    kept = [np.array([x for x in b if x in vocabulary], np.int64) for _, _, b in rows]
    row, col = np.repeat(np.arange(len(rows)), [len(b) for b in kept]), np.concatenate(kept)
    used, place = np.unique(col, return_inverse=True)
    names = sorted({(f, n) for f, n, _ in rows})
    fold_of = {x: k % FOLDS for k, x in enumerate(names)}
    fold = np.array([fold_of[f, n] for f, n, _ in rows])
    # Of the sparse matrix of examples and grams only distinct rows are trained on, with their numbers.
    x = np.zeros((len(rows), len(used)), np.float32)
    x[row, place] = 1
    hot = np.eye(len(classes), dtype=np.float32)[y]
    weight = 1 / np.bincount(y, minlength=len(classes))[y]  # classes count alike
    weight = (weight / weight.mean()).astype(np.float32)

    def train(keep: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        a, h, u = x[keep], hot[keep], weight[keep][:, None]
        w, b = np.zeros((len(used), len(classes)), np.float32), np.zeros(len(classes), np.float32)
        m = [np.zeros_like(w), np.zeros_like(b)]
        v = [np.zeros_like(w), np.zeros_like(b)]
        for step in range(1, rounds + 1):
            gap = (_softmax(a @ w + b) - h) * u / len(a)
            for k, slope in enumerate((a.T @ gap + 1e-4 * w, gap.sum(0))):
                m[k], v[k] = 0.9 * m[k] + 0.1 * slope, 0.99 * v[k] + 0.01 * slope**2
                move = 0.05 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-9)
                if k:
                    b = b - move
                else:
                    w = w - move
        return w, b

    z = np.zeros((len(rows), len(classes)))
    for k in range(FOLDS):
        if (fold != k).any() and (fold == k).any():
            w, b = train(fold != k)
            z[fold == k] = x[fold == k] @ w + b
    loss = lambda t: -(weight * np.log(_softmax(z * t)[np.arange(len(y)), y] + 1e-12)).mean()
    scale = float(min(np.geomspace(0.25, 4, 25), key=loss))
    w, b = train(np.ones(len(rows), bool))
    full = np.zeros((BUCKETS, len(classes)))
    full[used] = w
    return Regression(classes, full, b.astype(float), scale)


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def sentences(docs: DataFrame) -> DataFrame:
    """(doc_id, th, at, part, w): words of the sentences with a hint (part 0) and of the lines of such as have several (1, 2, ..)."""
    cut = F.filter(F.split("text", BREAK), hinted)
    rows = docs.where(hinted(F.col("text"))).select("doc_id", F.xxhash64("text").alias("th"), F.posexplode(cut).alias("at", "sentence"))
    lines = F.split("sentence", r"\r?\n")
    pieces = F.concat(F.array(F.array_join(lines, " ")), F.when(F.size(lines) > 1, lines).otherwise(F.array().cast("array<string>")))
    cued = rows.select("doc_id", "th", "at", F.posexplode(pieces).alias("part", "sentence")).where(hinted(F.col("sentence")))
    return cued.select("doc_id", "th", "at", "part", tokens(F.col("sentence")).alias("w")).distinct()


def train(spark: SparkSession, cued: DataFrame | None = None) -> Regression:
    """The regression from the composed examples and from whole sentences of ``cued`` (with part, w and families) that hold no template."""
    composed = small_frame(spark, examples(), "family string, name string, sentence string").withColumn("w", tokens(F.col("sentence")))
    got = [(r.family, r.name, r.b) for r in composed.select("family", "name", buckets(F.col("w")).alias("b")).collect()]
    vocabulary = sorted({x for *_, b in got for x in b})
    if cued is not None:
        # A row for each of SAMPLE buckets of a hash, the one with the smallest hash: minima are combined where the sentences are, nothing is sorted.
        known = F.from_json(F.lit(json.dumps(vocabulary)), "array<int>")
        others = cued.where((F.size("families") == 0) & (F.col("part") == 0)).select(F.xxhash64("w").alias("h"), F.array_sort(F.array_intersect(buckets(F.col("w")), known)).alias("b"))
        others = others.groupBy(F.pmod("h", F.lit(SAMPLE)).alias("k")).agg(F.min(F.struct("h", "b"))["b"].alias("b"))
        got += [(UNKNOWN, f"sentence {','.join(map(str, r.b))}", r.b) for r in others.collect()]
    return fit(sorted((f, n, sorted(b)) for f, n, b in got), set(vocabulary))


def notices(docs: DataFrame) -> DataFrame:
    """(doc_id, th, at, family, p, n): sentences with a notice of a family, and how many of their lines have one."""
    cued = checkpoint(with_templates(sentences(docs)))
    found = scored(cued.where(F.size("families") > 0), train(docs.sparkSession, cued))
    found = found.where((F.col("p") >= CERTAIN) & F.array_contains("families", F.col("family")))
    return found.groupBy("doc_id", "th", "at", "family").agg(F.max("p").alias("p"), F.greatest(F.count_if(F.col("part") > 0), F.lit(1)).alias("n"))


def licence_scan(docs: DataFrame) -> DataFrame:
    """(doc_id, family, families, n_notices, confidence) of every row: the surest family, all families, number of notices."""
    n = notices(docs).groupBy("doc_id", "th").agg(
        F.max_by("family", F.struct("p", "family")).alias("family"), F.array_join(F.array_sort(F.collect_set("family")), ",").alias("families"),
        F.sum("n").alias("n_notices"), F.max("p").alias("confidence"),
    )
    base = docs.select("doc_id", F.xxhash64("text").alias("th")).alias("d")
    joined = base.join(n.alias("n"), (F.col("d.th") == F.col("n.th")) & F.col("d.doc_id").eqNullSafe(F.col("n.doc_id")), "left")
    number = F.coalesce("n_notices", F.lit(0)).cast("long").alias("n_notices")
    families, confidence = F.coalesce("families", F.lit("")).alias("families"), F.coalesce("confidence", F.lit(0.0)).alias("confidence")
    return joined.select("d.doc_id", "family", families, number, confidence)


def licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licence_scan(table(spark, sf_dir, "documents").select("doc_id", "text"))


QUERIES = {"op4_licence_paragraphs": licences}
SQL: dict[str, str] = {}
