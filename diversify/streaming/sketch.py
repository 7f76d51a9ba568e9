"""Structured Streaming: the one-pass sketch as state, and the stream operators around it."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from diversify.functions.kernels import Sketch
from diversify.operators import solvers
from diversify.plans.params import strict

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
PROVIDER = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def event_stream(spark: SparkSession, path: str, schema: str = EVENTS, files: int = 1) -> DataFrame:
    """Parquet files of a folder as they come; timestamps without zone are read as such and cast."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def dump(s: Sketch) -> str:
    """A sketch as text, for state and for files."""
    rows = lambda some: [[int(i), [float(c) for c in p]] for i, p in some]
    return json.dumps({
        "k": s.k, "m": s.m, "kind": s.kind, "metric": s.metric, "square": s.square, "phase": s.phase, "seen": s.seen, "kept": rows(zip(s.ids, s.x, strict=True)),
        "held": [rows(h) for h in s.held], "count": [int(c) for c in s.count], "removed": rows(s.removed), "log": [[float(v) for v in r] for r in s.log],
    })


def restore(text: str) -> Sketch:
    d = json.loads(text)
    s = Sketch(d["k"], d["m"], d["kind"], d.get("metric", "euclid"))
    rows = lambda some: [(i, np.array(p)) for i, p in some]
    s.m, s.square, s.phase, s.seen, s.count = d["m"], d["square"], d["phase"], d["seen"], d["count"]
    s.ids, s.x = [i for i, _ in d["kept"]], [np.array(p) for _, p in d["kept"]]
    s.held, s.removed = [rows(h) for h in d["held"]], rows(d["removed"])
    s.log = [(int(a), b, int(c), int(e), int(f)) for a, b, c, e, f in d["log"]]
    return s


class SketchProcessor(StatefulProcessor):
    """One sketch a shard. Rows of a micro-batch are put in the order of time and id; the state is bounded by the sketch's size."""

    def __init__(self, k: int, m: int, kind: str, metric: str = "euclid"):
        self.k, self.m, self.kind, self.metric = k, m, kind, metric

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("sketch", "text string")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        s = restore(self.state.get()[0]) if self.state.exists() else Sketch(self.k, self.m, self.kind, self.metric)
        batch = pd.concat(list(rows)).sort_values(["at", "pid"])
        s.update(batch.pid.to_numpy(), np.stack(batch.v.to_numpy()))
        self.state.update((dump(s),))
        found = [(key[0], i, p.tolist(), False) for i, p, _ in s.result()] if s.kind == "points" else [(key[0], i, p.tolist(), False) for held in s.held for i, p in held]
        yield pd.DataFrame({"shard": [f[0] for f in found], "pid": [f[1] for f in found], "v": [f[2] for f in found], "seen": [s.seen] * len(found), "threshold": [s.threshold] * len(found)})

    def close(self) -> None:
        pass


def sketch(stream: DataFrame, k: int, k_prime: int, objective: str = "edge", shards: int = 1, metric: str = "euclid") -> DataFrame:
    """(shard, pid, v, seen, threshold) after each micro-batch of (pid, at, v). One shard is the stream of the theory; of several the union is a core-set too."""
    stream.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", PROVIDER)
    kind = "delegates" if strict(objective) else "points"
    keyed = stream.select(F.pmod("pid", F.lit(shards)).cast("long").alias("shard"), "pid", "at", "v")
    out = "shard long, pid long, v array<double>, seen long, threshold double"
    return keyed.groupBy("shard").transformWithStateInPandas(SketchProcessor(k, k_prime, kind, metric), out, "Update", "None")


def finalise(core: DataFrame, k: int, objective: str, metric: str = "euclid") -> DataFrame:
    """The solver on the latest core-sets of all shards (shard, pid, v, seen)."""
    last = F.max("seen").over(Window.partitionBy("shard"))
    return solvers.solve(core.withColumn("_last", last).where("seen = _last"), k, objective, metric)


def save_state(sketches: dict[int, Sketch], spark: SparkSession, path: str) -> None:
    spark.createDataFrame([(s, dump(x)) for s, x in sketches.items()], "shard long, text string").write.mode("overwrite").parquet(path)


def load_state(spark: SparkSession, path: str) -> dict[int, Sketch]:
    """One row a shard."""
    return {r.shard: restore(r.text) for r in spark.read.parquet(path).collect()}


def with_lateness(df: DataFrame, ts: str, delay: str) -> DataFrame:
    return df.withWatermark(ts, delay)


def dedupe_stream(df: DataFrame, ids: list[str], ts: str, delay: str) -> DataFrame:
    """Each id once within the watermark; state is dropped after it."""
    return df.withWatermark(ts, delay).dropDuplicatesWithinWatermark(ids)


def windowed(df: DataFrame, ts: str, width: str, slide: str | None = None) -> DataFrame:
    """``df`` with win, the start of its tumbling or each of its sliding windows."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    return df.withColumn("_w", w).withColumn("win", F.col("_w.start")).drop("_w")


def windowed_pick(df: DataFrame, ts: str, width: str, k: int, objective: str = "edge", slide: str | None = None) -> DataFrame:
    """(win, pid, pick_rank, v, value) of (pid, v, ts): a diverse choice of each window."""
    return solvers.solve(windowed(df, ts, width, slide), k, objective, by="win")


def sessions(df: DataFrame, ts: str, gap: str, by: str) -> DataFrame:
    """(by, session_start, rows, widest): sessions and the largest distance between their extremes along x."""
    return df.groupBy(by, F.session_window(ts, gap).alias("s")).agg(F.count("*").alias("rows"), (F.max("x") - F.min("x")).alias("widest")).select(by, F.col("s.start").alias("session_start"), "rows", "widest")


def stream_candidates(stream: DataFrame, anchors: DataFrame, reach: float) -> DataFrame:
    """The second pass on a live stream: points within reach of a frozen anchor (anchor_pid, a), of which there are at most k."""
    gap = F.aggregate(F.zip_with("v", "a", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    return stream.crossJoin(F.broadcast(anchors)).where(gap <= reach * reach)


def stream_pair(a: DataFrame, b: DataFrame, by: str, seconds: int, delay: str) -> DataFrame:
    """Pairs of rows of two streams with one ``by`` whose times (ta, tb) differ by at most ``seconds``; watermarks bound the state."""
    left, right = a.withWatermark("ta", delay), b.withWatermark("tb", delay).withColumnRenamed(by, "_by")
    near = F.expr(f"{by} = _by AND tb BETWEEN ta - INTERVAL {seconds} SECONDS AND ta + INTERVAL {seconds} SECONDS")
    return left.join(right, near).drop("_by")


def rate_probe(spark: SparkSession, rows_per_s: int) -> DataFrame:
    """(pid, at, v) from the rate source, to measure processedRowsPerSecond."""
    u = lambda n: F.pmod(F.xxhash64("value", F.lit(n)), F.lit(10**6)) / F.lit(1e6)
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_s).load().select(F.col("value").alias("pid"), F.col("timestamp").alias("at"), F.array(u(1), u(2), u(3)).alias("v"))


def two_pass_stream(spark: SparkSession, path: str, make, k: int, k_prime: int, objective: str) -> DataFrame:
    """Two replays of one source: ``make`` turns its rows into (pid, v, at). The first pass sketches with counts, the second finds members."""
    from diversify.operators.rounds import two_pass

    return two_pass(make(spark.read.parquet(path)), k, k_prime, objective, ("at", "pid"))
