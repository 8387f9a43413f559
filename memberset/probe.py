"""Membership lookup. Four plans with the same answers; ``auto`` picks by the filter's size.

array       the filter as one array per Python worker, broadcast after a check of its size; only the key column goes to Python
expression  JVM expressions only: the lines as a broadcast table, joined once per candidate; no Python, no shuffle
join        keys -> candidate rows -> equi-join with the line table -> any candidate that holds the footprint
shard       rows meet the lines of their shard, lines first, rows streamed past them: filters and probes of any size

Keys may be of any type that a filter takes (``keys.as_key``). A null key's answer is null. The answer for an
inserted key is always true. Input columns keep their names, whatever they are; the answer's name is a parameter.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StructField, StructType

from . import kernels as K
from .build import W, candidate_rows, packed, shard_column
from .geometry import LINE_BITS, WORDS, FilterSpec
from .hashing import constant, mul64, premix, reduce_to
from .keys import columns_of, free_names, key64, quoted

#: Sizes up to which a filter is sent to every task: as an array, as a joined table.
BROADCAST_BYTES, EXPRESSION_BYTES = 128 << 20, 64 << 20
#: Probe rows that one task of the shard plan is meant to have.
SHARD_ROWS = 1 << 22
#: Keys that one process asks at once.
ASKED = 1 << 15


def as_array(lines: DataFrame, spec: FilterSpec) -> np.ndarray:
    """(shards x lines, 8) on the driver; refused beyond BROADCAST_BYTES."""
    return as_arrays([(lines, spec)])[0]


def as_arrays(filters: list[tuple[DataFrame, FilterSpec]]) -> list[np.ndarray]:
    """The arrays of several filters, built in one job; refused where they are beyond BROADCAST_BYTES together."""
    if sum(spec.bytes for _, spec in filters) > BROADCAST_BYTES:
        raise ValueError("filter too large for one array: use the join or shard plan")
    tagged = [lines.select(F.lit(i).alias("filter"), "shard", "line", *W) for i, (lines, _) in enumerate(filters)]
    got = reduce(DataFrame.union, tagged).toArrow()
    owner, shard, line = (got[c].to_numpy() for c in ("filter", "shard", "line"))
    words, out = [got[w].to_numpy().view(np.uint64) for w in W], []
    for i, (_, spec) in enumerate(filters):
        mine = np.flatnonzero(owner == i)
        array = np.zeros((spec.shards * spec.lines, WORDS), np.uint64)
        at = shard[mine].astype(np.int64) * spec.lines + line[mine]
        for j, w in enumerate(words):
            array[at, j] = w[mine]
        out.append(array)
    return out


def answers(array: np.ndarray, keys: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(maybe, number of the hit candidate or 0, bits or lines touched)."""
    x = K.prepared(keys, spec)
    base = K.shard_of(x, spec) * spec.lines
    if spec.kind == "classic":
        found, touched = K.classic_lookup(array.reshape(-1), base[:, None] * LINE_BITS + K.addresses(x, spec))
        return found, found.astype(np.int8), touched
    if spec.bits == "distinct":
        found, hit = K.lookup(array, base[:, None] + K.candidates(x, spec), K.footprints(x, spec))
    else:
        found, hit = K.lazy_lookup(array, x, base, spec)
    return found, hit, np.where(found, hit, spec.choices)


def asked_all(array: np.ndarray, keys: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """Whether the filter may hold the keys, asked in pieces of ASKED."""
    said = [answers(array, keys[lo : lo + ASKED], spec)[0] for lo in range(0, len(keys), ASKED)]
    return np.concatenate(said) if said else np.empty(0, bool)


def by_array(df: DataFrame, key: str | Column, lines: DataFrame, spec: FilterSpec, out: str = "maybe", details: bool = False) -> DataFrame:
    shared = df.sparkSession.sparkContext.broadcast(as_array(lines, spec))

    def asked(keys: pa.Array) -> tuple:
        found, hit, touched = answers(shared.value, keys.fill_null(0).to_numpy(), spec)
        return pa.array(found, mask=keys.is_null().to_numpy(zero_copy_only=False)), hit, touched

    def told_only(keys: pa.Array) -> pa.Array:
        return asked(keys)[0]

    if not details:
        return df.withColumn(out, F.arrow_udf(told_only, "boolean")(key64(df, key)))

    def all_three(keys: pa.Array) -> pa.Array:
        found, hit, touched = asked(keys)
        return pa.StructArray.from_arrays([found, pa.array(hit.astype(np.int32)), pa.array(touched.astype(np.int32))], ["maybe", "hit_choice", "touched"])

    (both,) = free_names(df, "answer")
    told = df.withColumn(both, F.arrow_udf(all_three, "maybe boolean, hit_choice int, touched int")(key64(df, key)))
    return told.withColumns({out: F.col(f"{both}.maybe"), "hit_choice": F.col(f"{both}.hit_choice"), "touched": F.col(f"{both}.touched")}).drop(both)


def by_expression(df: DataFrame, key: str | Column, lines: DataFrame, spec: FilterSpec, out: str = "maybe") -> DataFrame:
    """A left join per candidate with the broadcast lines (EXPRESSION_BYTES at most), and k bit tests in generated code."""
    if spec.kind == "classic" or spec.bits == "distinct":
        raise ValueError("the expression plan is for lines with random or sliced footprints")
    if spec.bytes > EXPRESSION_BYTES:
        raise ValueError("filter too large for a broadcast join: use the join or shard plan")
    x, at, bits, words, *to = free_names(df, "x", "at", "bits", "words", *(f"to{i}" for i in range(spec.choices)))
    edge = [LINE_BITS * i // spec.k for i in range(spec.k + 1)] if spec.bits == "sliced" else [0] * (spec.k + 1)
    rows = df.withColumn(x, key64(df, key))
    if spec.premix:
        rows = rows.withColumn(x, premix(F.col(x)))

    def hashed(index: int, b: int) -> Column:
        return reduce_to(mul64(F.col(x), constant(spec.seed, index)), b, spec.u)

    base = hashed(K.SHARD, spec.shards) * spec.lines
    address = [F.lit(edge[i]) + hashed(K.BIT + i, edge[i + 1] - edge[i] if spec.bits == "sliced" else LINE_BITS) for i in range(spec.k)]
    rows = rows.withColumns({to[i]: base + hashed(K.LINE + i, spec.lines) for i in range(spec.choices)} | {bits: F.array(*[a.cast("int") for a in address])})
    table = lines.select((F.col("shard").cast("long") * spec.lines + F.col("line")).alias(at), F.array(*W).alias(words))
    found = F.lit(False)
    for i in range(spec.choices):
        names = [f"{n}{i}" for n in (at, words)]
        rows = rows.join(F.broadcast(table.toDF(*names)), F.col(to[i]) == F.col(names[0]), "left")
        holds = F.lit(True)
        for j in range(spec.k):
            b = F.get(F.col(bits), F.lit(j))
            word = F.get(F.col(names[1]), F.shiftright(b, 6))
            holds = holds & (F.call_function("shiftrightunsigned", word, b.bitwiseAND(F.lit(63))).bitwiseAND(F.lit(1).cast("long")) == 1)
        found = found | F.coalesce(holds, F.lit(False))
    return rows.select(*columns_of(df), F.when(F.col(x).isNotNull(), found).alias(out))


def by_join(df: DataFrame, key: str | Column, lines: DataFrame, spec: FilterSpec, out: str = "maybe") -> DataFrame:
    """For line filters; the answers of distinct keys are joined back."""
    asked, answer = free_names(df, "asked", "answer")
    rows = df.withColumn(asked, key64(df, key))
    distinct = rows.select(F.col(asked).alias("key64")).where("key64 is not null").distinct()
    tried = candidate_rows(distinct, spec).join(lines.drop("ones"), ["shard", "line"], "left")
    holds = F.lit(True)
    for i, w in enumerate(W):
        holds = holds & (F.coalesce(w, F.lit(0).cast("long")).bitwiseAND(F.col(f"m{i}")) == F.col(f"m{i}"))
    found = tried.groupBy(F.col("key64").alias(asked)).agg(F.bool_or(holds).alias(answer))
    return rows.join(found, asked, "left").select(*columns_of(df), F.col(answer).alias(out))


def by_shard(df: DataFrame, key: str | Column, lines: DataFrame, spec: FilterSpec, out: str = "maybe") -> DataFrame:
    """One shuffle of the rows to their shard. A task reads a shard's lines, then streams the rows past them.

    A shard with more than SHARD_ROWS rows (a hot key's, say) is served by several tasks, each with a copy of its lines.
    """
    value, shard, part, line, old = free_names(df, "key64", "shard", "part", "line", "old")
    rows = shard_column(df.withColumn(value, F.coalesce(key64(df, key), F.lit(0).cast("long"))), value, shard, spec)
    null = key64(df, key).isNull()
    rows = rows.withColumn(shard, F.when(null, F.pmod(F.monotonically_increasing_id(), F.lit(spec.shards)).cast("int")).otherwise(F.col(shard)))
    # How many tasks a shard takes: a row per shard.
    where = shard_column(df.select(F.coalesce(key64(df, key), F.lit(0).cast("long")).alias(value)), value, shard, spec)
    parts = where.groupBy(shard).agg(F.ceil(F.count("*") / SHARD_ROWS).cast("int").alias(part))
    served = rows.join(F.broadcast(parts), shard, "left").withColumn(part, F.pmod(F.monotonically_increasing_id(), F.coalesce(part, F.lit(1))).cast("int"))
    served = served.select(shard, part, F.lit(None).cast("int").alias(line), F.lit(None).cast("binary").alias(old), F.when(~null, F.col(value)).alias(value), *columns_of(df))
    copies = lines.join(F.broadcast(parts.withColumnRenamed(shard, "shard")), "shard", "left")
    copies = copies.withColumn("copy", F.explode(F.sequence(F.lit(0), F.coalesce(part, F.lit(1)) - 1)))
    blank = [F.lit(None).cast(f.dataType).alias(f.name) for f in df.schema.fields]
    copies = copies.select(F.col("shard").alias(shard), F.col("copy").cast("int").alias(part), F.col("line").alias(line), packed().alias(old), F.lit(None).cast("long").alias(value), *blank)
    met = copies.union(served).repartition(shard, part).sortWithinPartitions(shard, part, F.col(old).isNull())
    met = met.toDF(*(f"c{i}" for i in range(len(met.columns))))  # mapInArrow looks columns up by plain names
    n_columns, one = len(df.columns), replace(spec, shards=1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, array = None, np.zeros((spec.lines, WORDS), np.uint64)
        for batch in batches:
            owner = np.stack([batch.column(i).to_numpy().astype(np.int64) for i in (0, 1)], 1)
            cut = np.flatnonzero(np.concatenate(([True], (owner[1:] != owner[:-1]).any(1), [True]))) if len(owner) else []
            for lo, hi in zip(cut[:-1], cut[1:]):
                if here != tuple(owner[lo]):
                    here = tuple(owner[lo])
                    array[:] = 0
                some = batch.slice(lo, hi - lo)
                n_old = some.num_rows - some.column(3).null_count
                if n_old:
                    array[some.column(2).slice(0, n_old).to_numpy()] = np.frombuffer(b"".join(some.column(3).slice(0, n_old).to_pylist()), ">u8").reshape(-1, WORDS)
                if n_old == some.num_rows:
                    continue
                some = some.slice(n_old)
                found, _, _ = answers(array, some.column(4).fill_null(0).to_numpy(), one)
                told = pa.array(found, mask=some.column(4).is_null().to_numpy(zero_copy_only=False))
                yield pa.RecordBatch.from_arrays([*some.columns[5:], told], [str(i) for i in range(n_columns + 1)])

    names = [str(i) for i in range(n_columns + 1)]
    schema = StructType([StructField(n, f.dataType, True) for n, f in zip(names, [*df.schema.fields, StructField(out, BooleanType())])])
    return met.mapInArrow(run, schema).toDF(*df.columns, out)


PLANS = {"array": by_array, "expression": by_expression, "join": by_join, "shard": by_shard}


def probe(df: DataFrame, key: str | Column, lines: DataFrame, spec: FilterSpec, plan: str = "auto", out: str = "maybe") -> DataFrame:
    """``df`` with a boolean ``out``. A column that has this name already must be renamed, or another name asked for."""
    if out in df.columns:
        raise ValueError(f"there is a column {out} already: give another name as out")
    if plan == "auto":
        plan = "array" if spec.bytes <= BROADCAST_BYTES else "shard"
    if plan == "join" and spec.kind == "classic":
        plan = "shard"
    return PLANS[plan](df, key, lines, spec, out)


__all__ = ["PLANS", "answers", "as_array", "as_arrays", "asked_all", "by_array", "by_expression", "by_join", "by_shard", "probe", "quoted"]
