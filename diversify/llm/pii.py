"""Personal data by weak supervision, with DataFrame functions only.

Patterns propose spans with their exact places. Labelers vote on each span, for, against or not at all: the kind's own check, gazetteers
(top-level domains, country codes, card issuers, cue words), the words around it, what touches it, and how its characters
vary. Expectation-maximisation over the vote patterns estimates, for each kind, how common true spans are and, for each labeler, how it votes on true and on false ones. The
posteriors then train the span classifier, a logistic regression over votes, kind and length, which decides on the proposed spans beyond
the base ones. Base spans (pattern and check hold) always stay.

Votes are few values, so spans are summed to patterns where they are: at most one row for each combination of votes, kind and length
class reaches the driver, whatever the corpus's size; every span of every document is in those sums. Deciding is an expression.

Places: a text is cut into gaps and matches in turn, and a running sum of their lengths gives code points.

Defined cases: null and empty texts have no spans; a document is told from others with its id by a hash of its text, so repeated
ids keep a row each; texts without anything proposed still get a row. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from diversify.llm.base import checkpoint, table

KINDS = ("email", "ip", "card", "phone", "secret")
#: Proposing patterns by kind. Possessive parts and starts only where a run starts: the same leftmost matches as the plain patterns, in linear time.
#: A card's run has 14 digits at least, as shorter ones always fail. The last ones propose only, among them numbers that a base match swallows with their neighbours.
#: Each has a quick test that every text with a match passes.
PATTERNS = (
    ("email", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@"),
    ("ip", r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", r"[0-9]\.[0-9]"),
    ("card", r"[0-9](?:[ -]?[0-9]){13,}+", r"[0-9](?:[ -]?[0-9]){13}"),
    ("phone", r"\+[0-9][ ().0-9-]+[0-9]", r"\+[0-9]"),
    ("secret", r"(?i)\b(?:token|secret|password|passwd|api[_-]?key|access[_-]?key)\s{0,3}[=:]\s{0,3}[\"']?[A-Za-z0-9_./+-]{12,}+[\"']?", "[=:]"),
    ("email", r"(?i)\b[A-Za-z0-9._%+-]{1,64}+ ?[\[(](?:at|@)[\])] ?[A-Za-z0-9-]{1,63}+(?: ?[\[(]?(?:dot|\.)[\])]? ?[A-Za-z]{2,24}+){1,3}+", r"(?i)[\[(](?:at|@)[\])]"),
    ("phone", r"(?<![+0-9().-])(?:\+[0-9]{1,3} ?)?(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9])", r"[0-9]{3}[ .-][0-9]{4}"),
    ("card", r"(?<![0-9])[0-9]{4}(?:[ -]?[0-9]{4}){3}(?![0-9])", r"[0-9](?:[ -]?[0-9]){13}"),
)
BASE = 4  # the first four patterns are those of the base spans
ACCEPT = 0.9
AROUND = 24
PRIOR = (50, 2)
LABELERS = ("check", "gazetteer", "context", "border", "variety")

# Gazetteers.
DOMAINS = "com org net edu gov mil int info biz io co ai dev app me eu de fr es it nl be at ch uk us ca au jp cn in br mx ru pl se no dk fi pt ie example test"
COUNTRY = "1 7 20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 54 55 56 57 60 61 62 63 64 65 66 81 82 84 86 90 91 92 351 352 353 358 380 420"
ISSUERS = r"^(?:4|5[1-5]|2[2-7]|3[47]|35|36|38|6011|62|64|65)"
CUES = {
    "email": r"(?i)\b(?:e-?mail|mail|contact|write to|address|adresse|correo|courriel)\b",
    "ip": r"(?i)\b(?:ip|host|server|address|addr|client|from|login|adresse)\b",
    "card": r"(?i)\b(?:card|visa|mastercard|amex|credit|debit|payment|karte|carte|tarjeta)\b",
    "phone": r"(?i)\b(?:tel|phone|call|fax|mobile|cell|telefon|t[ée]l[ée]phone|tel[ée]fono|whatsapp)\b",
    "secret": r"(?i)\b(?:key|token|secret|bearer|authorization|credential|password|env|export)\b",
}
AGAINST = r"(?i)\b(?:version|isbn|issn|doi|order|invoice|page|figure|table|section|lot|sku|build|release)\b"


def _any(column: Column, values: str) -> Column:
    return column.isin(values.split())


def _vote(yes: Column, no: Column) -> Column:
    return F.when(yes, 1).when(no, -1).otherwise(0)


def luhn(digits: Column) -> Column:
    """Luhn's check of a string of digits."""
    each = F.transform(F.split(F.reverse(digits), ""), lambda c, i: F.when(i % 2 == 0, c.try_cast("int")).otherwise(F.when(c.try_cast("int") > 4, c.try_cast("int") * 2 - 9).otherwise(c.try_cast("int") * 2)))
    return F.aggregate(each, F.lit(0), lambda a, x: a + F.coalesce(x, F.lit(0))) % 10 == 0


def _numbered(rule: int):
    """A piece with its number; odd ones are matches, of gaps only the ends are kept."""
    return lambda x, i: F.struct(
        F.lit(rule).alias("rule"), i.alias("i"), F.length(x).alias("length"), F.when(i % 2 == 1, x).alias("value"), F.when(i % 2 == 0, F.left(x, F.lit(AROUND))).alias("head"), F.when(i % 2 == 0, F.right(x, F.lit(AROUND))).alias("tail")
    )


def proposals(docs: DataFrame) -> DataFrame:
    """(doc_id, th, rule, kind, start, end, value, before, after) of every match of every pattern; places in code points, end exclusive."""
    # Two marks around each match, then a split at the marks: gap, match, gap, match, .., gap. Both take linear time. Marks of the text's own become another control character.
    text = F.coalesce(F.col("text"), F.lit(""))
    clean = F.when(text.contains("\x01") | text.contains("\x02"), F.translate(text, "\x01\x02", "\x03\x03")).otherwise(text)
    named = docs.select("doc_id", F.xxhash64("text").alias("th"), clean.alias("t"))
    none, found = F.array().cast("array<struct<rule:int,i:int,length:int,value:string,head:string,tail:string>>"), []
    for rule, (_, pattern, test) in enumerate(PATTERNS):
        pieces = F.split(F.regexp_replace("t", pattern, "\x01$0\x02"), "[\x01\x02]", -1)
        found.append(F.coalesce(F.when(F.col("t").rlike(test), F.transform(pieces, _numbered(rule))), none))
    # An outer explode, as for an inner one the optimizer would filter on the lists' size and compute them twice.
    rows = named.select("doc_id", "th", F.inline_outer(F.concat(*found))).where("rule IS NOT NULL")
    order = Window.partitionBy("doc_id", "th", "rule").orderBy("i")
    rows = rows.withColumn("again", F.coalesce(F.lag("i").over(order) == F.col("i"), F.lit(False))).where("NOT again").drop("again")  # of a repeated row
    end = F.sum(F.col("length").cast("long")).over(order.rowsBetween(Window.unboundedPreceding, 0))
    kind = F.element_at(F.array(*(F.lit(k) for k, *_ in PATTERNS)), F.col("rule") + 1)
    placed = rows.withColumns({"end": end, "before": F.lag("tail").over(order), "after": F.lead("head").over(order)}).where("value IS NOT NULL")
    return placed.select("doc_id", "th", "rule", kind.alias("kind"), (F.col("end") - F.col("length")).alias("start"), "end", "value", "before", "after")


def labelled(spans: DataFrame) -> DataFrame:
    """``spans`` with base (its pattern and check hold) and the labelers' votes."""
    v, kind, rule = F.col("value"), F.col("kind"), F.col("rule")
    digits = F.regexp_replace(v, "[^0-9]", "")
    n = F.length(digits)
    parts = F.split(v, r"\.")
    octets = F.forall(parts, lambda x: (F.length(F.ltrim(x, F.lit("0"))) <= 3) & (F.coalesce(x.try_cast("decimal(38,0)"), F.when(F.ltrim(x, F.lit("0")) == "", 0)) <= 255))
    valid = F.when(kind == "email", F.lit(True)).when(kind == "ip", octets).when(kind == "card", n.between(14, 19) & luhn(digits)).when(kind == "phone", n.between(10, 15)).otherwise(True)
    spans = spans.withColumn("valid", F.coalesce(valid, F.lit(False))).withColumn("base", F.col("valid") & (rule < BASE))
    tld = F.lower(F.regexp_extract(v, r"([A-Za-z]+)$", 1))
    code = F.regexp_extract(v, r"^\+([0-9]+)", 1)
    known = F.exists(F.array(F.substring(code, 1, 1), F.substring(code, 1, 2), F.substring(code, 1, 3)), lambda c: _any(c, COUNTRY))
    gazetteer = (
        F.when(kind == "email", _vote(_any(tld, DOMAINS), F.length(tld) < 2)).when(kind == "phone", _vote(known, (rule < BASE) & ~known))
        .when(kind == "card", _vote(digits.rlike(ISSUERS), digits.rlike("^0"))).when(kind == "ip", _vote(F.lit(False), v.rlike(r"^0|^25[6-9]|^[3-9][0-9][0-9]")))
        .otherwise(_vote(v.rlike(r"(?i)^(?:token|secret|password|api)"), F.lit(False)))
    )
    around = F.concat_ws(" ", "before", "after")
    cue = F.lit(False)
    for k, pattern in CUES.items():
        cue = F.when(kind == k, around.rlike(pattern)).otherwise(cue)
    touches = F.col("before").rlike(r"[A-Za-z0-9_./@-]$") | F.col("after").rlike(r"^[A-Za-z0-9_/@-]|^\.[0-9]")
    kinds_of_chars = F.size(F.array_distinct(F.split(F.regexp_replace(F.lower(v), "[^a-z0-9]", ""), "")))
    votes = {
        "check": _vote(F.col("valid"), ~F.col("valid")), "gazetteer": gazetteer, "context": _vote(cue, F.col("before").rlike(AGAINST)),
        "border": _vote(~touches, touches), "variety": _vote(kinds_of_chars >= 5, kinds_of_chars <= 3),
    }
    size = F.least(F.floor(F.length(v) / 8), F.lit(5)).cast("int")
    return spans.select("*", *(c.cast("int").alias(k) for k, c in votes.items()), size.alias("size"))


def estimate(patterns: list[tuple[str, tuple[int, ...], int]], rounds: int = 50) -> dict[tuple[str, tuple[int, ...]], float]:
    """Posterior of true spans by kind and votes. A labeler's votes are independent given the truth; patterns: kind, votes, number of spans."""
    posterior: dict[tuple[str, tuple[int, ...]], float] = {}
    votes = np.array([p[1] for p in patterns]).reshape(len(patterns), -1)
    count, kind = np.array([p[2] for p in patterns], float), np.array([p[0] for p in patterns])
    truth = 1 / (1 + np.exp(-1.5 * votes.sum(1) - 3 * votes[:, 0]))
    for _ in range(rounds):
        log_odds = np.zeros(len(patterns))
        for k in np.unique(kind):
            here = kind == k
            share = np.clip((truth * count)[here].sum() / count[here].sum(), 0.02, 0.98)
            log_odds[here] += np.log(share / (1 - share))
        for j in range(votes.shape[1]):
            # Counts of a prior: a labeler is right in two of three of its votes, the kind's own check in nearly all.
            right = PRIOR[0] if j == 0 else PRIOR[1]
            yes = np.array([(truth * count)[votes[:, j] == v].sum() + p for v, p in ((-1, 1), (0, 1), (1, right))])
            no = np.array([((1 - truth) * count)[votes[:, j] == v].sum() + p for v, p in ((-1, right), (0, 1), (1, 1))])
            log_odds += np.log((yes / yes.sum()) / (no / no.sum()))[votes[:, j] + 1]
        truth = 1 / (1 + np.exp(-np.clip(log_odds, -30, 30)))
    for k, v, t in zip(kind, votes, truth, strict=True):
        posterior[str(k), tuple(int(x) for x in v)] = float(t)
    return posterior


def train(spans: DataFrame) -> Column:
    """P(true span) as an expression over the columns of ``labelled``."""
    groups = spans.groupBy("kind", *LABELERS, "size").count().orderBy("kind", *LABELERS, "size").collect()  # at most 5 x 3**5 x 6 rows
    if not groups:
        return F.lit(0.0)
    summed: dict[tuple[str, tuple[int, ...]], int] = {}
    for r in groups:
        at = r.kind, tuple(r[k] for k in LABELERS)
        summed[at] = summed.get(at, 0) + r["count"]
    truth = estimate([(k, v, n) for (k, v), n in summed.items()])
    x = np.array([[1.0, *(float(r["kind"] == k) for k in KINDS), *(float(r[k] == s) for k in LABELERS for s in (-1, 1)), *(float(r["size"] == s) for s in range(6))] for r in groups])
    y = np.array([truth[r["kind"], tuple(r[k] for k in LABELERS)] for r in groups])
    n = np.array([r["count"] for r in groups], float)
    n /= n.sum()
    w = np.zeros(x.shape[1])
    for _ in range(25):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        curve = (x * (n * (p * (1 - p) + 1e-6))[:, None]).T @ x + 1e-3 * np.eye(len(w))
        w -= np.linalg.solve(curve, x.T @ (n * (p - y)) + 1e-3 * w)
    names = [F.lit(1.0), *((F.col("kind") == k).cast("double") for k in KINDS), *((F.col(k) == s).cast("double") for k in LABELERS for s in (-1, 1)), *((F.col("size") == s).cast("double") for s in range(6))]
    level = F.lit(0.0)
    for value, c in zip(w.tolist(), names, strict=True):
        level = level + c * F.lit(value)
    return 1 / (1 + F.exp(-level))


def spans(docs: DataFrame) -> DataFrame:
    """(doc_id, th, kind, start, end, base, p): base spans and those that the classifier adds; an added one overlaps no base span."""
    voted = checkpoint(labelled(proposals(docs)).select("doc_id", "th", "kind", "start", "end", "base", *LABELERS, "size").distinct())
    judged = voted.withColumn("p", train(voted)).where(F.col("base") | (F.col("p") >= ACCEPT))
    order = Window.partitionBy("doc_id", "th").orderBy("start", F.col("base").desc(), "end", "kind")
    end_before = F.max(F.when(F.col("base"), F.col("end"))).over(order.rowsBetween(Window.unboundedPreceding, -1))
    start_after = F.min(F.when(F.col("base"), F.col("start"))).over(order.rowsBetween(1, Window.unboundedFollowing))
    clear = F.coalesce(end_before <= F.col("start"), F.lit(True)) & F.coalesce(start_after >= F.col("end"), F.lit(True))
    return judged.withColumn("clear", clear).where(F.col("base") | F.col("clear")).select("doc_id", "th", "kind", "start", "end", "base", "p").dropDuplicates(["doc_id", "th", "kind", "start", "end"])


def found(docs: DataFrame) -> DataFrame:
    """(doc_id, th, spans): per document with any, its spans as (start, rank of kind, kind, end, base) in order."""
    rank = F.array_position(F.array(*(F.lit(k) for k in KINDS)), F.col("kind")).cast("int")
    one = F.struct("start", rank.alias("rank"), "end", "kind", "base")
    return spans(docs).groupBy("doc_id", "th").agg(F.array_sort(F.collect_list(one)).alias("spans"))


def _with_spans(docs: DataFrame) -> DataFrame:
    """(doc, spans): each row as a struct, so that no column of its own can clash, and its spans in order."""
    f = found(docs).alias("f")
    d = docs.select(F.struct(*docs.columns).alias("doc"), "doc_id", F.xxhash64("text").alias("th")).alias("d")
    none = F.array().cast("array<struct<start:bigint,rank:int,end:bigint,kind:string,base:boolean>>")
    joined = d.join(f, (F.col("d.th") == F.col("f.th")) & F.col("d.doc_id").eqNullSafe(F.col("f.doc_id")), "left")
    return joined.select("doc", F.coalesce("f.spans", none).alias("spans"))


def _of(kind: str):
    return lambda x: x["kind"] == kind


def _written(column: Column) -> Column:
    return F.array_join(F.transform(column, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    f = found(docs).alias("f")
    rows = docs.select("doc_id", F.xxhash64("text").alias("th")).alias("d")
    joined = rows.join(f, (F.col("d.th") == F.col("f.th")) & F.col("d.doc_id").eqNullSafe(F.col("f.doc_id")), "left")
    none = F.array().cast("array<struct<start:bigint,rank:int,end:bigint,kind:string,base:boolean>>")
    named = joined.select("d.doc_id", F.coalesce("f.spans", none).alias("s")).withColumn("b", F.filter("s", lambda x: x["base"]))
    counts = (F.size(F.filter("b", _of(k))).cast("long").alias(f"n_{k}") for k in KINDS[:BASE])
    return named.select("doc_id", *counts, F.sha2(_written(F.col("b")), 256).alias("base_sha256"), _written(F.col("s")).alias("spans"))


def masked(docs: DataFrame) -> DataFrame:
    """``docs`` with each span, overlapping ones as one, replaced by its kind in brackets."""
    rows, text = _with_spans(docs), F.col("doc.text")
    # Spans in order; one that begins before the last one's end widens it.
    start = F.array().cast("array<struct<start:bigint,end:bigint,kind:string>>")
    last = lambda a: F.element_at(a, -1)
    wider = lambda a, s: F.struct(last(a)["start"].alias("start"), F.greatest(last(a)["end"], s["end"]).alias("end"), last(a)["kind"].alias("kind"))
    widen = lambda a, s: F.concat(F.slice(a, F.lit(1), F.size(a) - 1), F.array(wider(a, s)))
    append = lambda a, s: F.concat(a, F.array(F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    overlaps = lambda a, s: (F.size(a) > 0) & (F.try_element_at(a, F.lit(-1))["end"] > s["start"])
    rows = rows.select("doc", F.aggregate("spans", start, lambda a, s: F.when(overlaps(a, s), widen(a, s)).otherwise(append(a, s))).alias("merged"))
    before = lambda i: F.when(i > 0, F.get("merged", i - 1)["end"]).otherwise(0)
    gap = lambda s, i: F.substr(text, before(i).cast("int") + 1, (s["start"] - before(i)).cast("int"))
    piece = lambda s, i: F.concat(gap(s, i), F.lit("["), F.upper(s["kind"]), F.lit("]"))
    tail = F.substr(text, F.try_element_at("merged", F.lit(-1))["end"].cast("int") + 1)
    clean = F.when(F.size("merged") > 0, F.concat(F.array_join(F.transform("merged", piece), ""), tail)).otherwise(text).alias("text")
    return rows.select(*(clean if c == "text" else F.col("doc")[c].alias(c) for c in docs.columns))


def mask_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: every document stays, its personal data replaced."""
    return masked(docs)


QUERIES = {"op1_weak_supervision_pii": personal_data}
SQL: dict[str, str] = {}
