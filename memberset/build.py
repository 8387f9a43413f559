"""Building filters as tables: one row per non-empty line (shard, line, w0..w7, ones).

Line-local and classic filters are unions, so lines are OR-ed in tasks and once more after the only shuffle.
Multi-choice insertion depends on order: repeats are dropped by a partial aggregate, keys go to their shard, are sorted by
(ord, key) there, and one task at a time owns a shard's lines. Results depend on the data and the spec only.
Null keys are not inserted; repeated keys change nothing; an empty input gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .geometry import LINE_BITS, WORDS, FilterSpec
from .hashing import constant, mul64, premix, reduce_to
from .keys import free_names, key64

W = [f"w{i}" for i in range(WORDS)]
DENSE_BYTES = 64 << 20
LINE_SCHEMA = "shard int, line int, " + ", ".join(f"{w} long" for w in W) + ", ones int"


def keys_of(df: DataFrame, key: str | Column, order: str | Column | None = None) -> DataFrame:
    """(key64, ord): keys of any type that a filter takes; null keys are dropped."""
    c = key64(df, key)
    o = c if order is None else F.col(order) if isinstance(order, str) else order
    return df.select(c.alias("key64"), o.cast("long").alias("ord")).where("key64 is not null")


def _line_batch(shard: np.ndarray, line: np.ndarray, words: np.ndarray) -> pa.RecordBatch:
    columns = [pa.array(shard.astype(np.int32)), pa.array(line.astype(np.int32)), *(pa.array(np.ascontiguousarray(words[:, i]).view(np.int64)) for i in range(WORDS)), pa.array(K.ones(words).astype(np.int32))]
    return pa.RecordBatch.from_arrays(columns, ["shard", "line", *W, "ones"])


def _merged(line: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """OR of the masks of equal lines."""
    order = np.argsort(line, kind="stable")
    line, mask = line[order], mask[order]
    cut = np.flatnonzero(np.concatenate(([True], line[1:] != line[:-1])))
    return line[cut], np.bitwise_or.reduceat(mask, cut, axis=0)


def line_masks(keys: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray]:
    """(global line number, words) to OR for keys of a union filter, equal lines merged."""
    x = K.prepared(keys, spec)
    at = K.shard_of(x, spec) * spec.lines
    if spec.kind == "classic":
        address = K.addresses(x, spec)
        line = (at[:, None] + address // LINE_BITS).reshape(-1)
        return _merged(line, K.masks((address % LINE_BITS).reshape(-1, 1)))
    return _merged(at + K.candidates(x, spec)[:, 0], K.footprints(x, spec))


def build_union(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """Classic and line-local filters: partial OR in the map tasks, one shuffle, final OR.

    A task ORs into an array of its own where the whole filter fits ``DENSE_BYTES``, else into sorted runs of lines.
    """

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = np.zeros((spec.shards * spec.lines, WORDS), np.uint64)
        flat = words.reshape(-1)
        for batch in batches:
            x = K.prepared(batch.column(0).to_numpy(), spec)
            at = K.shard_of(x, spec) * spec.lines
            if spec.kind == "classic":
                bit = (at[:, None] * LINE_BITS + K.addresses(x, spec)).reshape(-1)
                np.bitwise_or.at(flat, bit >> 6, np.uint64(1) << (bit & 63).astype(np.uint64))
            else:
                np.bitwise_or.at(words, at + K.candidates(x, spec)[:, 0], K.footprints(x, spec))
        used = np.flatnonzero(words.any(1))
        for lo in range(0, len(used), 1 << 16):
            part = used[lo : lo + (1 << 16)]
            yield _line_batch(part // spec.lines, part % spec.lines, words[part])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_line, held = np.empty(0, np.int64), np.empty((0, WORDS), np.uint64)
        for batch in batches:
            line, words = line_masks(batch.column(0).to_numpy(), spec)
            held_line, held = _merged(np.concatenate([held_line, line]), np.concatenate([held, words]))
            if len(held_line) > 1 << 19:
                yield _line_batch(held_line // spec.lines, held_line % spec.lines, held)
                held_line, held = held_line[:0], held[:0]
        if len(held_line):
            yield _line_batch(held_line // spec.lines, held_line % spec.lines, held)

    parts = keys.select("key64").mapInArrow(dense if spec.bytes <= DENSE_BYTES else run, LINE_SCHEMA)
    return _or_lines(parts)


def _or_lines(parts: DataFrame) -> DataFrame:
    out = parts.groupBy("shard", "line").agg(*[F.bit_or(w).alias(w) for w in W])
    return with_ones(out)


def with_ones(lines: DataFrame) -> DataFrame:
    total = F.bit_count(W[0])
    for w in W[1:]:
        total = total + F.bit_count(w)
    return lines.select("shard", "line", *W, total.cast("int").alias("ones"))


def shard_column(df: DataFrame, value: str, shard: str, spec: FilterSpec) -> DataFrame:
    """df with the shard (int) of the long column ``value``, hashed in the JVM."""
    (x,) = free_names(df, "x")
    rows = df.withColumn(x, premix(F.col(value)) if spec.premix else F.col(value))
    rows = rows.withColumn(x, mul64(F.col(x), constant(spec.seed, K.SHARD)))
    return rows.withColumn(shard, reduce_to(F.col(x), spec.shards, spec.u).cast("int")).drop(x)


def routed(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """(shard, ord, key64)"""
    return shard_column(keys.select("key64", "ord"), "key64", "shard", spec).select("shard", "ord", "key64")


def distinct_keys(keys: DataFrame) -> DataFrame:
    """Each key once, at its first place: a partial aggregate, so that a hot key sends one row per task."""
    return keys.groupBy("key64").agg(F.min("ord").alias("ord"))


def _partitions(df: DataFrame, spec: FilterSpec) -> int:
    return max(1, min(spec.shards, 2 * df.sparkSession.sparkContext.defaultParallelism if spec.shards < 1 << 14 else spec.shards))


def build_choice(keys: DataFrame, spec: FilterSpec, into: DataFrame | None = None, report: str = "", distinct: bool = False) -> DataFrame:
    """Multi-choice insertion in order of (ord, key64) within each shard, on top of the lines of ``into``.

    Repeats of a key change nothing, so they are dropped before the shuffle; ``distinct`` says that there are none.
    report: "" gives the lines; "shards" (shard, keys, skipped); "fresh" the (key64, ord) that the filter did not hold
    when they came.
    """
    n = _partitions(keys, spec)
    rows = routed(keys if distinct else distinct_keys(keys), spec).withColumn("old", F.lit(None).cast("binary"))
    if into is not None:  # a shard's old lines come first, one row each
        old = into.select("shard", F.lit(None).cast("long").alias("ord"), F.col("line").cast("long").alias("key64"), packed().alias("old"))
        rows = rows.unionByName(old)
    rows = rows.repartitionById(n, F.col("shard") % n).sortWithinPartitions("shard", F.col("old").isNull(), "ord", "key64")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, lines, n_keys, skipped = -1, None, 0, 0

        def finish() -> pa.RecordBatch:
            if report == "shards":
                return pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([n_keys], pa.int64()), pa.array([skipped], pa.int64())], ["shard", "keys", "skipped"])
            used = np.flatnonzero(lines.any(1))
            return _line_batch(np.full(len(used), shard), used, lines[used])

        for batch in batches:
            owner = batch.column(0).to_numpy()
            cut = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1], [True]))) if len(owner) else []
            for lo, hi in zip(cut[:-1], cut[1:]):
                if owner[lo] != shard:
                    if lines is not None and report != "fresh":
                        yield finish()
                    shard, lines, n_keys, skipped = int(owner[lo]), np.zeros((spec.lines, WORDS), np.uint64), 0, 0
                part = batch.slice(lo, hi - lo)
                keys_ = part.column(2).to_numpy()
                n_old = (hi - lo) - part.column(3).null_count
                if n_old:
                    lines[keys_[:n_old]] = np.frombuffer(b"".join(part.column(3).slice(0, n_old).to_pylist()), ">u8").reshape(-1, WORDS)
                x = K.prepared(np.ascontiguousarray(keys_[n_old:]), spec)
                n_keys += len(x)
                held = np.zeros(len(x), bool)
                skipped += K.insert(lines, K.candidates(x, spec), K.footprints(x, spec), spec, held=held)
                if report == "fresh":
                    new = part.slice(n_old).filter(pa.array(~held))
                    yield pa.RecordBatch.from_arrays([new.column(2), new.column(1)], ["key64", "ord"])
        if lines is not None and report != "fresh":
            yield finish()

    return rows.mapInArrow(run, {"": LINE_SCHEMA, "shards": "shard int, keys long, skipped long", "fresh": "key64 long, ord long"}[report])


def packed() -> Column:
    """The line's words as 64 bytes, most significant byte first."""
    return F.concat(*[F.unhex(F.lpad(F.hex(w), 16, "0")) for w in W])


def build(keys: DataFrame, spec: FilterSpec, distinct: bool = False) -> DataFrame:
    return build_choice(keys, spec, distinct=distinct) if spec.kind == "choice" else build_union(keys, spec)


def insert_more(lines: DataFrame, keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """The filter after further keys; equal to a build of all keys when these come later in order."""
    return build_choice(keys, spec, into=lines) if spec.kind == "choice" else merge_or(lines, build_union(keys, spec))


def merge_or(a: DataFrame, b: DataFrame) -> DataFrame:
    """OR of two filters of one spec: the filter of both key sets for union filters. For multi-choice filters it has
    no false negatives either, but is fuller than a joint build: prefer ``insert_more``."""
    return _or_lines(a.unionByName(b))


EPOCH = 99  # number of the hash function that deals keys to epochs


def epoch_of(spec: FilterSpec, epochs: int, value: str = "key64") -> Column:
    return reduce_to(mul64(F.col(value), constant(spec.seed, EPOCH)), epochs)


def build_epochs(keys: DataFrame, spec: FilterSpec, epochs: int) -> DataFrame:
    """Batch insertion: keys of an epoch are priced on the lines as they were when it began, then all are written."""
    state = build_choice(keys.where(F.lit(False)), spec)
    total, added = spec.cost.tables(spec.k)
    dealt = distinct_keys(keys).withColumn("epoch", epoch_of(spec, epochs))

    for epoch in range(epochs):
        now = candidate_rows(dealt.where(F.col("epoch") == epoch), spec)
        joined = now.join(state.withColumnRenamed("ones", "before"), ["shard", "line"], "left")
        after = F.lit(0)
        for i, w in enumerate(W):
            after = after + F.bit_count(F.coalesce(w, F.lit(0).cast("long")).bitwiseOR(F.col(f"m{i}")))
        joined = joined.withColumn("j", after).withColumn("a", F.col("j") - F.coalesce("before", F.lit(0)))
        price = F.when(F.col("a") == 0, F.lit(-1).cast("long")).otherwise(F.array(*map(F.lit, total.tolist()))[F.col("j")] + F.array(*map(F.lit, added.tolist()))[F.col("a")])
        best = joined.groupBy("key64").agg(F.min_by(F.struct("shard", "line", *[f"m{i}" for i in range(WORDS)]), F.struct(price.alias("p"), F.col("choice"))).alias("b"))
        rows = best.select("b.shard", "b.line", *[F.col(f"b.m{i}").alias(W[i]) for i in range(WORDS)])
        state = _or_lines(state.drop("ones").unionByName(rows))
    return state


def build_fold(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """Multi-choice insertion as an SQL fold: a shard's keys in an array, its lines as the state of an aggregate.

    Exactly the one-by-one loop. The state is copied for every key and a shard's keys meet in one row, so this is for
    shards of a few lines (checks, engines without Python); ``build_choice`` is the plan for size.
    """
    total, added = (F.array(*map(F.lit, t.tolist())) for t in spec.cost.tables(spec.k))
    tried = candidate_rows(distinct_keys(keys), spec).join(distinct_keys(keys), "key64")
    mask = F.array(*[F.col(f"m{i}") for i in range(WORDS)])
    each = tried.groupBy("shard", "ord", "key64").agg(F.sort_array(F.collect_list(F.struct("choice", "line"))).alias("lines"), F.any_value(mask).alias("mask"))
    zero = F.lit(0).cast("long")

    def insert(state: Column, key: Column) -> Column:
        def word(line: Column, i: int) -> Column:
            return F.get(state, line * WORDS + i)

        def price(at: Column) -> Column:
            before = sum((F.bit_count(word(at["line"], i)) for i in range(WORDS)), F.lit(0))
            after = sum((F.bit_count(word(at["line"], i).bitwiseOR(key["mask"][i])) for i in range(WORDS)), F.lit(0))
            cost = F.when(after == before, F.lit(-1).cast("long")).otherwise(F.get(total, after) + F.get(added, after - before))
            return F.struct(cost.alias("price"), at["choice"].alias("choice"), at["line"].alias("line"))

        best = F.array_min(F.transform(key["lines"], price))["line"]
        # The state is one array of words; those of the chosen line take the mask.
        return F.transform(state, lambda w, i: F.when(F.floor(i / WORDS) == best, w.bitwiseOR(F.get(key["mask"], i % WORDS))).otherwise(w))

    arrived = each.groupBy("shard").agg(F.sort_array(F.collect_list(F.struct("ord", "key64", "lines", "mask"))).alias("keys"))
    state = arrived.select("shard", F.aggregate("keys", F.array_repeat(zero, spec.lines * WORDS), insert).alias("state"))
    lines = state.select("shard", "state", F.explode(F.sequence(F.lit(0), F.lit(spec.lines - 1))).alias("line"))
    return with_ones(lines.select("shard", "line", *[F.get("state", F.col("line") * WORDS + i).alias(w) for i, w in enumerate(W)])).where("ones > 0")


def candidate_rows(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """A row per key and candidate: key64, choice, shard, line, m0..m7."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys_ = batch.column(0).to_numpy()
            x = K.prepared(keys_, spec)
            cand, mask, shard = K.candidates(x, spec), K.footprints(x, spec), K.shard_of(x, spec)
            c = spec.choices
            wide = np.repeat(mask, c, axis=0)
            columns = [pa.array(np.repeat(keys_, c)), pa.array(np.tile(np.arange(1, c + 1, dtype=np.int32), len(keys_))), pa.array(np.repeat(shard, c).astype(np.int32)), pa.array(cand.reshape(-1).astype(np.int32))]
            yield pa.RecordBatch.from_arrays([*columns, *(pa.array(np.ascontiguousarray(wide[:, i]).view(np.int64)) for i in range(WORDS))], ["key64", "choice", "shard", "line", *(f"m{i}" for i in range(WORDS))])

    return keys.select("key64").mapInArrow(run, "key64 long, choice int, shard int, line int, " + ", ".join(f"m{i} long" for i in range(WORDS)))
