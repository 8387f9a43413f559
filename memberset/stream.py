"""Filters over streams."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from . import kernels as K
from .build import LINE_SCHEMA, W, build, build_choice, candidate_rows, insert_more, keys_of, routed
from .geometry import WORDS, FilterSpec
from .keys import free_names, key64
from .probe import by_array

#: Every so many versions the whole filter is written; between them only the shards that changed.
COMPACT = 16


def maintain(stream: DataFrame, key: str, spec: FilterSpec, path: str, checkpoint: str):
    """Writer that folds every micro-batch into a versioned filter; replays repeat the same version.

    path/v=<batch> has the shards that the batch's keys touched, each in full, and every COMPACT-th version all shards;
    ``maintained`` puts the latest together.
    """

    def fold(batch: DataFrame, number: int) -> None:
        spark, keys = batch.sparkSession, keys_of(batch, key).persist()
        before = maintained(spark, path, number - 1)
        touched = F.broadcast(routed(keys, spec).select("shard").distinct())  # spec.shards rows at most
        old = before.join(touched, "shard", "left_semi")
        lines = insert_more(old, keys, spec) if number else build(keys, spec)
        if number % COMPACT == 0:
            lines = lines.unionByName(before.join(touched, "shard", "left_anti"))
        lines.write.mode("overwrite").parquet(f"{path}/v={number}")
        keys.unpersist()

    return stream.writeStream.foreachBatch(fold).option("checkpointLocation", checkpoint)


def maintained(spark, path: str, number: int) -> DataFrame:
    """The filter's lines after batch ``number``."""
    if number < 0:
        return spark.createDataFrame([], LINE_SCHEMA)
    paths = [f"{path}/v={v}" for v in range(number - number % COMPACT, number + 1)]
    parts = None
    for v, p in enumerate(paths):
        part = spark.read.schema(LINE_SCHEMA).parquet(p).withColumn("v", F.lit(v))
        parts = part if parts is None else parts.unionByName(part)
    latest = F.broadcast(parts.groupBy("shard").agg(F.max("v").alias("v")))
    return parts.join(latest, ["shard", "v"]).drop("v").select("shard", "line", *W, "ones")


def _fresh(lines: np.ndarray, keys: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """Which keys are new to the filter, in order, each inserted as it comes; a repeat finds its own bits."""
    x, held = K.prepared(np.ascontiguousarray(keys), spec), np.zeros(len(keys), bool)
    K.insert(lines, K.candidates(x, spec), K.footprints(x, spec), spec, held=held)
    return ~held


def first_seen_stream(stream: DataFrame, key: str, ts: str, spec: FilterSpec) -> DataFrame:
    """(key64, ts): keys not seen before, as far as a filter tells: repeats never pass, a new key is lost with the FPR.

    The state is one filter shard per group, of fixed size, whatever the number of keys.
    """
    rows = routed(keys_of(stream, key, F.unix_micros(F.col(ts))), spec)

    def run(shard: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        lines = np.frombuffer(state.get[0], np.uint64).reshape(-1, WORDS).copy() if state.exists else np.zeros((spec.lines, WORDS), np.uint64)
        rows_ = pd.concat(list(batches)).sort_values(["ord", "key64"])
        new = _fresh(lines, rows_["key64"].to_numpy(), spec)
        state.update((lines.tobytes(),))
        yield rows_.loc[new, ["key64", "ord"]]

    return rows.groupBy("shard").applyInPandasWithState(run, "key64 long, ord long", "lines binary", "append", GroupStateTimeout.NoTimeout)


def first_seen(df: DataFrame, key: str, order: str, spec: FilterSpec) -> DataFrame:
    """The same over a table: (key64, ord) of the first row of each key that the filter takes for new, streamed shard by shard."""
    return build_choice(keys_of(df, key, F.col(order)), spec, report="fresh")


def window_filters(df: DataFrame, key: str, ts: str, spec: FilterSpec, width: str = "1 day", late: str = "1 day", slide: str | None = None) -> DataFrame:
    """Line-local filter per time window (tumbling or sliding): a mergeable aggregate, for streams and tables alike."""
    events = df.select(F.col(ts).alias("ts"), key64(df, key).alias("key64")).where("key64 is not null")
    marked = _marked(events, spec)
    if df.isStreaming:
        marked = marked.withWatermark("ts", late)
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = marked.groupBy(window.alias("w"), "shard", "line").agg(*[F.bit_or(f"m{i}").alias(w) for i, w in enumerate(W)])
    return out.select(F.col("w.start").alias("window_start"), "shard", "line", *W)


def _marked(events: DataFrame, spec: FilterSpec) -> DataFrame:
    """(ts, key64) -> ts, shard, line and the masks of the key's footprint in a line-local filter."""
    one = FilterSpec("linelocal", spec.k, 1, spec.shards, spec.lines, spec.bits, spec.seed, spec.premix)
    names = [f"m{i}" for i in range(WORDS)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = K.prepared(batch.column(1).to_numpy(), one)
            mask = K.footprints(x, one)
            columns = [batch.column(0), pa.array(K.shard_of(x, one).astype(np.int32)), pa.array(K.candidates(x, one)[:, 0].astype(np.int32))]
            yield pa.RecordBatch.from_arrays([*columns, *(pa.array(np.ascontiguousarray(mask[:, i]).view(np.int64)) for i in range(WORDS))], ["ts", "shard", "line", *names])

    return events.select("ts", "key64").mapInArrow(run, "ts timestamp, shard int, line int, " + ", ".join(f"{m} long" for m in names))


def session_filters(df: DataFrame, per: str, key: str, ts: str, spec: FilterSpec, gap: str) -> DataFrame:
    """Line-local filter per session: the keys of a value of ``per`` between pauses of ``gap`` or more (tables only).

    Sessions are found first, as windows; their lines are then a mergeable aggregate. Rows without a time, a key or a
    ``per`` are in none.
    """
    events = df.select(F.col(per).alias("per"), F.col(ts).cast("timestamp").alias("ts"), key64(df, key).alias("key64")).where("per is not null and ts is not null and key64 is not null")
    spans = events.groupBy("per", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events"))
    spans = spans.select("per", F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"))
    inside = events.join(spans, "per").where("ts >= session_start and ts < session_end").select("per", "session_start", "session_end", "key64").distinct()
    one = FilterSpec("linelocal", spec.k, 1, spec.shards, spec.lines, spec.bits, spec.seed, spec.premix)
    marks = candidate_rows(inside.select("key64").distinct(), one).drop("choice")
    lines = inside.join(marks, "key64").groupBy("per", "session_start", "session_end", "shard", "line")
    return lines.agg(*[F.bit_or(f"m{i}").alias(w) for i, w in enumerate(W)])


class RotatingPair:
    """Two generations of a filter: probes ask both, inserts go to the younger, which becomes the older when full."""

    def __init__(self, spec: FilterSpec):
        self.spec, self.held, self.lap = spec, 0, 0
        self.young, self.old = (np.zeros((spec.lines, WORDS), np.uint64) for _ in range(2))

    def rotate(self) -> None:
        self.old, self.young, self.held = self.young, np.zeros_like(self.young), 0

    def offer(self, keys: np.ndarray) -> np.ndarray:
        """Which keys neither generation knew when they came; all are known afterwards."""
        x, held = K.prepared(np.ascontiguousarray(keys), self.spec), np.zeros(len(keys), bool)
        cand, mask = K.candidates(x, self.spec), K.footprints(x, self.spec)
        known = K.lookup(self.old, cand, mask)[0]
        K.insert(self.young, cand, mask, self.spec, held=held)
        self.held += int((~held).sum())
        if self.held >= self.spec.capacity:
            self.rotate()
        return ~(known | held)


def rotating_stream(stream: DataFrame, key: str, ts: str, spec: FilterSpec, period_seconds: int, idle: str | None = None) -> DataFrame:
    """(key64, ord): keys that neither the current nor the previous generation of the filter holds.

    The state of a shard is a pair of generations. The younger one becomes the older when its ``period_seconds`` of event
    time are over or it has the keys that the shard was sized for; so a key is forgotten after one to two periods, and
    the state is bounded whatever the stream. With ``idle`` (seconds of processing time without rows, as text) a timer drops the pair.
    """
    rows = routed(keys_of(stream, key, F.unix_micros(F.col(ts))), spec)
    period, room = period_seconds * 1_000_000, max(1, spec.capacity // spec.shards) if spec.capacity else None
    one = replace(spec, shards=1, capacity=room or 1 << 62)

    def run(shard: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        pair, began = RotatingPair(one), None
        if state.exists:
            young, old, pair.held, began = state.get
            pair.young, pair.old = (np.frombuffer(b, np.uint64).reshape(-1, WORDS).copy() for b in (young, old))
        rows_ = pd.concat(list(batches)).sort_values(["ord", "key64"])
        began = int(rows_["ord"].iloc[0]) if began is None else began
        for lap, some in rows_.groupby(((rows_["ord"] - began) // period).clip(lower=0), sort=True):
            for _ in range(min(2, int(lap) - pair.lap)):
                pair.rotate()
            pair.lap = max(pair.lap, int(lap))
            yield some.loc[pair.offer(some["key64"].to_numpy()), ["key64", "ord"]]
        state.update((pair.young.tobytes(), pair.old.tobytes(), pair.held, began + pair.lap * period))
        if idle:
            state.setTimeoutDuration(int(idle) * 1000)

    timer = GroupStateTimeout.ProcessingTimeTimeout if idle else GroupStateTimeout.NoTimeout
    return rows.groupBy("shard").applyInPandasWithState(run, "key64 long, ord long", "young binary, old binary, held long, began long", "append", timer)


def stream_prefilter(stream: DataFrame, key: str, lines: DataFrame, spec: FilterSpec, table: DataFrame, table_key: str) -> DataFrame:
    """Stream rows that a static filter lets pass, then the exact join with the static table."""
    (maybe,) = free_names(stream, "maybe")
    some = by_array(stream, key, lines, spec, maybe).where(F.col(maybe)).drop(maybe)
    return some.join(table, some[key] == table[table_key])
