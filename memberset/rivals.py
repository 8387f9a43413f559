"""Other membership structures, for comparison."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .build import build, distinct_keys, keys_of, shard_column
from .geometry import FilterSpec, plan_spec
from .hashing import constant, np_hash, np_premix
from .keys import columns_of, free_names, key64
from .probe import probe


def exact(keys: DataFrame, probes: DataFrame, key: str, out: str = "maybe") -> DataFrame:
    """The hash set itself: a left join on the distinct keys."""
    (asked,) = free_names(probes, "asked")
    have = keys.select(F.col("key64").alias(asked)).distinct().withColumn(out, F.lit(True))
    return probes.join(have, key64(probes, key) == F.col(asked), "left").drop(asked).withColumn(out, F.coalesce(out, F.lit(False)))


def fingerprint_set(keys: DataFrame, probes: DataFrame, key: str, slots: int, r: int, out: str = "maybe") -> DataFrame:
    """A set of (slot, r-bit remainder): the answers of a quotient filter, or of any static fingerprint table."""
    slot, rest = free_names(probes, "slot", "rest")

    def parts(c):
        h = F.xxhash64(c)
        return F.pmod(h, F.lit(slots)).alias(slot), F.shiftrightunsigned(F.xxhash64(c, F.lit(7)), 64 - r).alias(rest)

    have = keys.select(*parts(F.col("key64"))).distinct().withColumn(out, F.lit(True))
    asked = probes.select("*", *parts(key64(probes, key)))
    return asked.join(have, [slot, rest], "left").drop(slot, rest).withColumn(out, F.coalesce(out, F.lit(False)))


class Cuckoo:
    """Buckets of four fingerprints, two buckets per key; the count of buckets is a power of two. Fails when full.

    Insertion goes in rounds over all keys that wait: what fits its bucket is placed; from the second bucket on, one key of
    each full bucket takes a random slot there and sends its former holder to its other bucket.
    """

    SLOTS = 4

    def __init__(self, n: int, fingerprint_bits: int, load: float = 0.95, walk: int = 500, seed: int = 1):
        self.buckets = 1 << max(0, (int(n / load / self.SLOTS)).bit_length())
        self.bits, self.walk, self.seed = fingerprint_bits, walk, seed
        self.slots = np.zeros((self.buckets, self.SLOTS), np.int64)

    def parts(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        x = np_premix(keys.view(np.uint64))
        return np_hash(x, constant(self.seed, 1), self.buckets), 1 + np_hash(x, constant(self.seed, 2), (1 << self.bits) - 1)

    def other(self, bucket: np.ndarray, mark: np.ndarray) -> np.ndarray:
        return bucket ^ np_hash(mark.astype(np.uint64), constant(self.seed, 3), self.buckets)

    def insert(self, keys: np.ndarray) -> int:
        """Keys that found no place."""
        rng = np.random.default_rng(self.seed)
        bucket, mark = self.parts(keys)
        for turn in range(self.walk):
            order = np.argsort(bucket, kind="stable")
            bucket, mark = bucket[order], mark[order]
            first = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1]))) if len(bucket) else np.zeros(0, np.int64)
            rank = np.arange(len(bucket)) - np.repeat(first, np.diff(np.append(first, len(bucket))))
            held = (self.slots[bucket] != 0).sum(1)
            fits = held + rank < self.SLOTS
            self.slots[bucket[fits], (held + rank)[fits]] = mark[fits]
            bucket, mark = bucket[~fits], mark[~fits]
            if not len(bucket):
                return 0
            if turn:  # both buckets tried: one key per full bucket pushes another out
                lead = np.concatenate(([True], bucket[1:] != bucket[:-1]))
                at, slot = bucket[lead], rng.integers(self.SLOTS, size=int(lead.sum()))
                self.slots[at, slot], mark[lead] = mark[lead], self.slots[at, slot]
            bucket = self.other(bucket, mark)
        return len(bucket)

    def lookup(self, keys: np.ndarray) -> np.ndarray:
        bucket, mark = self.parts(keys)
        return (self.slots[bucket] == mark[:, None]).any(1) | (self.slots[self.other(bucket, mark)] == mark[:, None]).any(1)


def cuckoo_build(keys: DataFrame, n: int, fingerprint_bits: int, shards: int = 1, room: float = 1.1) -> DataFrame:
    """(shard, bucket, slots array<long>, failed): a cuckoo table per shard, each built by one task; failed counts the
    shard's keys without a place. ``room`` covers shards that get more than their share of the n keys."""
    route = FilterSpec(shards=shards)
    rows = shard_column(distinct_keys(keys).select("key64"), "key64", "shard", route).select("shard", "key64")
    rows = rows.repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", "key64")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, shard = [], None
        for batch in batches:
            if batch.num_rows:
                shard = batch.column(0)[0].as_py()
                parts.append(batch.column(1).to_numpy())
        if shard is not None:
            table = Cuckoo(max(1, round(room * n / shards)), fingerprint_bits)
            failed = table.insert(np.concatenate(parts))
            for lo in range(0, table.buckets, 1 << 16):
                some = table.slots[lo : lo + (1 << 16)]
                slots = pa.ListArray.from_arrays(pa.array(np.arange(len(some) + 1, dtype=np.int32) * table.SLOTS), pa.array(some.reshape(-1)))
                yield pa.RecordBatch.from_arrays([pa.array([shard] * len(some), pa.int32()), pa.array(np.arange(lo, lo + len(some))), slots, pa.array([failed] * len(some), pa.int64())], ["shard", "bucket", "slots", "failed"])

    return rows.mapInArrow(run, "shard int, bucket long, slots array<long>, failed long")


def cuckoo_probe(df: DataFrame, key: str, table: DataFrame, n: int, fingerprint_bits: int, shards: int = 1, room: float = 1.1, out: str = "maybe") -> DataFrame:
    """Both buckets of every row's key are joined in; a null key's answer is null. (Keys without a place are missed.)"""
    like = Cuckoo(max(1, round(room * n / shards)), fingerprint_bits)
    like.slots = None

    def places(keys: pa.Array) -> pa.Array:
        one, mark = like.parts(np.ascontiguousarray(keys.fill_null(0).to_numpy()))
        return pa.StructArray.from_arrays([pa.array(x) for x in (one, like.other(one, mark), mark)], ["one", "two", "mark"])

    value, shard, at, slots1, slots2 = free_names(df, "value", "shard", "at", "slots1", "slots2")
    rows = shard_column(df.withColumn(value, key64(df, key)), value, shard, FilterSpec(shards=shards))
    rows = rows.withColumn(at, F.arrow_udf(places, "one long, two long, mark long")(F.col(value)))
    for slots, which in ((slots1, "one"), (slots2, "two")):
        side = table.select(F.col("shard").alias(f"{slots}s"), F.col("bucket").alias(f"{slots}b"), F.col("slots").alias(slots))
        rows = rows.join(side, (F.col(shard) == F.col(f"{slots}s")) & (F.col(f"{at}.{which}") == F.col(f"{slots}b")), "left").drop(f"{slots}s", f"{slots}b")
    found = F.coalesce(F.array_contains(slots1, F.col(f"{at}.mark")), F.lit(False)) | F.coalesce(F.array_contains(slots2, F.col(f"{at}.mark")), F.lit(False))
    return rows.withColumn(out, F.when(F.col(value).isNotNull(), found)).drop(value, shard, at, slots1, slots2)


# --- the platform's own filters -----------------------------------------------------------------


@contextmanager
def runtime_filters(spark: SparkSession, least_bytes: int = 0) -> Iterator[None]:
    """Inside, Spark puts its own classic filter under shuffle joins whose large side has ``least_bytes`` or more.

    Plans are made when an action runs, so run it inside; the session's settings come back afterwards.
    """
    prefix = "spark.sql.optimizer.runtime.bloomFilter"
    wanted = {f"{prefix}.enabled": "true", f"{prefix}.applicationSideScanSizeThreshold": str(least_bytes)}
    before = {name: spark.conf.get(name, None) for name in wanted}
    for name, value in wanted.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.unset(name) if value is None else spark.conf.set(name, value)


def save_with_column_filter(df: DataFrame, key: str, path: str, n: int) -> None:
    """Parquet whose row groups carry a classic filter of the key for about n values: point lookups skip those that refuse."""
    df.write.option(f"parquet.bloom.filter.enabled#{key}", "true").option(f"parquet.bloom.filter.expected.ndv#{key}", str(n)).parquet(path)


class Growing:
    """A list of filters of doubling capacity; a key is in one of them or in none."""

    def __init__(self, first: int, k: int, kind: str = "choice", choices: int = 2):
        self.next, self.k, self.kind, self.choices = first, k, kind, choices
        self.parts: list[tuple[DataFrame, FilterSpec]] = []

    def add(self, df: DataFrame, key: str) -> None:
        keys = keys_of(df, key)
        spec = plan_spec(max(self.next, keys.count()), self.k + 1 + len(self.parts), self.kind, self.choices)  # halving FPRs sum to the target
        self.parts.append((build(keys, spec), spec))
        self.next *= 2

    def probe(self, df: DataFrame, key: str, out: str = "maybe") -> DataFrame:
        told = df
        held = F.lit(False)
        for i, (lines, spec) in enumerate(self.parts):
            (name,) = free_names(told, f"in{i}")
            told = probe(told, key, lines, spec, out=name)
            held = held | F.col(name)
        return told.withColumn(out, held).select(*columns_of(df), out)
