"""SimHash near-duplicates by tiled exact comparison of fingerprints.

A fingerprint is 64 majority votes over the XXH64 hashes of a text's word shingles. All pairs of
fingerprints within a Hamming radius are found exactly:

* equal fingerprints are collapsed first (a partial aggregate), so copies cost nothing;
* if two of them differ in at most ``radius`` bits, then of ``radius + s`` bit blocks at least ``s``
  are equal, so every choice of ``s`` blocks is one table of candidates (``s`` follows from the
  number of fingerprints: each table stays finely cut at any size, nothing is missed at any ``s``);
* rows of equal blocks lie in one run, sorted by population count and compared tile by tile with
  numpy exclusive-or and bit counts; tile pairs whose counts differ beyond the radius are skipped;
* a run of more than ``RUN_ROWS`` fingerprints is dealt over pairs of sub-runs, in many tasks.

Links leave the tiles as spanning edges, never as all pairs.

Defined results: null text = empty text, no words = fingerprint zero, which links like any other;
repeated rows and ids are kept; a null id takes part but never names a component unless the whole
component has none; an empty table gives no rows; extra input columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import columns_of, doc_text, free_name, keyed, stage
from .components import connected_components
from .xxh64 import hash_ranges

SHINGLE_WORDS = 4
RADIUS = 4
SEED = 42
TILE = 1024
RUN_ROWS = 16384
_LOW_BITS = np.uint64(0x0101010101010101)


def _votes(hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Fingerprint of each text; its hashes are hashes[first[i]:first[i + 1]] (may be none)."""
    sizes = np.diff(first)
    out = np.zeros(len(sizes), np.uint64)
    some = np.flatnonzero(sizes)
    if not len(some):
        return out
    # Runs of 255 hashes at most: eight one-byte counters fit in each 64-bit word.
    per = -(-sizes[some] // 255)
    owner = np.repeat(np.arange(len(some)), per)
    piece = np.arange(len(owner)) - np.repeat(np.cumsum(per) - per, per)
    cuts = first[:-1][some][owner] + 255 * piece
    run_of = np.cumsum(per) - per
    for shift in range(8):
        packed = np.add.reduceat((hashes >> np.uint64(shift)) & _LOW_BITS, cuts)
        counts = np.add.reduceat(packed.view(np.uint8).reshape(-1, 8).astype(np.int64), run_of, axis=0)
        for byte in range(8):
            out[some] |= (counts[:, byte] * 2 > sizes[some]).astype(np.uint64) << np.uint64(8 * byte + shift)
    return out


def fingerprints_of(texts: list[bytes], words: int = SHINGLE_WORDS, seed: int = SEED) -> np.ndarray:
    """uint64 fingerprint of each text (UTF-8). bytes.lower and bytes.split are ASCII only, as wanted."""
    lists = [t.lower().split() for t in texts]
    joined = [b" ".join(x) for x in lists]
    data = b" ".join(joined) + b" "
    n_words = np.fromiter(map(len, lists), np.int64, len(lists))
    ends = np.flatnonzero(np.frombuffer(data, np.uint8) == 32).astype(np.int64)
    # Texts without words leave an empty word each between the joining spaces: drop those.
    starts = np.concatenate(([0], ends[:-1] + 1)) if len(ends) else ends
    real = ends > starts
    starts, ends = starts[real], ends[real]
    n_shingles = np.where(n_words == 0, 0, np.maximum(1, n_words - words + 1))
    first = np.concatenate(([0], np.cumsum(n_shingles)))
    word0 = np.cumsum(n_words) - n_words
    text = np.repeat(np.arange(len(lists)), n_shingles)
    head = word0[text] + np.arange(first[-1]) - first[:-1][text]
    tail = np.minimum(head + words - 1, word0[text] + n_words[text] - 1)
    return _votes(hash_ranges(data, starts[head], ends[tail], seed), first)


def fingerprint(docs: DataFrame, words: int = SHINGLE_WORDS, seed: int = SEED, chunk_bytes: int = 2 << 20) -> DataFrame:
    """(doc_id, fp long): the bit pattern of each document's fingerprint."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, size, out = [], 0, []
            for value in batch.column(1).cast(pa.large_binary()):
                texts.append(value.as_py() or b"")
                size += len(texts[-1])
                if size >= chunk_bytes:
                    out.append(fingerprints_of(texts, words, seed))
                    texts, size = [], 0
            out.append(fingerprints_of(texts, words, seed))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(out).view(np.int64))], ["doc_id", "fp"])

    source = doc_text(docs)
    return source.mapInArrow(run, f"doc_id {source.schema['doc_id'].dataType.simpleString()}, fp long")


def _span_rows(x: np.ndarray, radius: int, tile: int = TILE) -> tuple[np.ndarray, np.ndarray]:
    """Spanning edges (index pairs) of the graph of all pairs within the radius among x."""
    order = np.argsort(np.bitwise_count(x), kind="stable")
    y = x[order]
    ones = np.bitwise_count(y).astype(np.int64)
    label = np.arange(len(y))
    a, b = [], []

    def root(i: int) -> int:
        while label[i] != i:
            label[i] = label[label[i]]
            i = label[i]
        return i

    for lo in range(0, len(y), tile):
        left = y[lo : lo + tile]
        for at in range(lo, len(y), tile):
            if ones[at] - ones[min(lo + tile, len(y)) - 1] > radius:
                break
            right = y[at : at + tile]
            near = np.bitwise_count(left[:, None] ^ right[None, :]) <= radius
            if at == lo:
                near = np.triu(near, 1)
            # Only hits between trees that are still apart matter; each one joins two of them.
            while near.any():
                i, j = np.nonzero(near)
                first = np.concatenate(([True], i[1:] != i[:-1]))
                for p, q in zip((i[first] + lo).tolist(), (j[first] + at).tolist()):
                    r, s = root(p), root(q)
                    if r != s:
                        label[max(r, s)] = min(r, s)
                        a.append(order[p])
                        b.append(order[q])
                tops_l = np.array([root(p) for p in range(lo, lo + len(left))])
                tops_r = np.array([root(q) for q in range(at, at + len(right))])
                near &= tops_l[:, None] != tops_r[None, :]
    return np.array(a, np.int64), np.array(b, np.int64)


def _forest(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of the links (u, v), those of a spanning forest."""
    up: dict[int, int] = {}
    keep = []

    def root(i: int) -> int:
        while (j := up.get(i, i)) != i:
            up[i] = up.get(j, j)
            i = j
        return i

    for k, (a, b) in enumerate(zip(u.tolist(), v.tolist())):
        a, b = root(a), root(b)
        if a != b:
            up[max(a, b)] = min(a, b)
            keep.append(k)
    return u[keep], v[keep]


def _compare_sorted(key: np.ndarray, x: np.ndarray, radius: int) -> tuple[list, list]:
    """Edges within every run of equal keys (rows are sorted by key)."""
    u, v = [], []
    cut = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1], [True])))
    size = np.diff(cut)
    short = np.repeat(size <= 64, size)
    index = np.flatnonzero(short)
    k, s = key[index], x[index]
    for step in range(1, 64):  # short runs: all of them at once, by distance within the run
        if len(k) <= step:
            break
        same = k[step:] == k[:-step]
        if not same.any():
            break
        hit = np.flatnonzero(same & (np.bitwise_count(s[step:] ^ s[:-step]) <= radius))
        u.append(s[hit])
        v.append(s[hit + step])
    for r in np.flatnonzero(size > 64):
        run = np.unique(x[cut[r] : cut[r + 1]])
        i, j = _span_rows(run, radius)
        u.append(run[i])
        v.append(run[j])
    return u, v


def blocks_for(n: int, radius: int = RADIUS) -> list[tuple[int, ...]]:
    """Masks of the candidate tables: each is s of radius + s near-equal bit blocks.

    s is the least one whose tables hold about 4096 fingerprints per key or fewer, at most radius.
    """
    for s in range(1, radius + 1):
        n_blocks = radius + s
        edge = [64 * i // n_blocks for i in range(n_blocks + 1)]
        if n >> (64 * s // n_blocks) <= 4096 or s == radius:
            blocks = [((1 << (edge[i + 1] - edge[i])) - 1) << edge[i] for i in range(n_blocks)]
            return [tuple(c) for c in combinations(blocks, s)]
    return []


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def links(fps: DataFrame, radius: int = RADIUS, n: int | None = None) -> DataFrame:
    """Distinct fingerprints (fp long) -> spanning edges (u, v) of the graph of all pairs within radius."""
    spark = fps.sparkSession
    n = fps.count() if n is None else n
    masks = [_signed(sum(c)) for c in blocks_for(n, radius)]
    rows = fps.select("fp", F.posexplode(F.array(*[F.lit(m) for m in masks])).alias("t", "mask"))
    rows = rows.select("fp", F.xxhash64(F.col("t"), F.col("fp").bitwiseAND(F.col("mask"))).alias("run"))
    large = rows.groupBy("run").count().where(F.col("count") > RUN_ROWS)
    large = large.select("run", F.ceil(F.col("count") / (RUN_ROWS // 2)).cast("int").alias("parts"))
    rows = rows.join(large, "run", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    mine = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
    rows = rows.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    rows = rows.select("fp", F.xxhash64("run", F.least("mine", "other"), F.greatest("mine", "other")).alias("run"))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def emit(key: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
            u, v = _compare_sorted(key, x, radius)
            pair = _forest(np.concatenate(u), np.concatenate(v)) if u else (x[:0], x[:0])
            return pa.RecordBatch.from_arrays([pa.array(side.view(np.int64)) for side in pair], ["u", "v"])

        key, x = np.empty(0, np.int64), np.empty(0, np.uint64)
        for batch in batches:
            key = np.concatenate([key, batch.column(0).to_numpy(zero_copy_only=False)])
            x = np.concatenate([x, batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)])
            if len(key) and key[0] != key[-1]:  # the last run may go on in the next batch
                done = int(np.searchsorted(key, key[-1]))
                yield emit(key[:done], x[:done])
                key, x = key[done:], x[done:]
        if len(key):
            yield emit(key, x)

    rows = rows.repartition("run").sortWithinPartitions("run", "fp").select("run", "fp")
    return rows.mapInArrow(compare, "u long, v long")


def _linked(prints: DataFrame, radius: int) -> tuple[DataFrame, DataFrame]:
    """Distinct fingerprints (fp, doc: least id) and, for those with links, fp and root (the component's least fingerprint)."""
    reps = stage(prints.groupBy("fp").agg(F.min("doc_id").alias("doc")), "reps")
    comp = connected_components(links(reps.select("fp"), radius))
    return reps, stage(comp.select(F.col("node").alias("fp"), "root"), "component")


def near_duplicates(docs: DataFrame, radius: int = RADIUS, words: int = SHINGLE_WORDS, seed: int = SEED) -> DataFrame:
    """One row per document: doc_id, fp (long), component_id (smallest id reachable over links)."""
    prints = stage(fingerprint(docs, words, seed), "fingerprints")
    reps, comp = _linked(prints, radius)
    named = comp.join(reps, "fp")
    least = named.groupBy("root").agg(F.min("doc").alias("least"))
    label = reps.join(named.join(least, "root").select("fp", "least"), "fp", "left").select("fp", F.coalesce("least", "doc").alias("component_id"))
    return prints.join(label, "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The documents with one row left of each component: that of smallest id.

    Null ids come last; rows of one id in one component go by fingerprint, then by their place in the table. Rows that
    share an id but lie in different components are judged each in its own.
    """
    row = free_name(docs, "row")
    rows = keyed(docs, row)
    prints = stage(fingerprint(rows.select("text", F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col(row).alias("row")).alias("doc_id"))), "fingerprints")
    _, comp = _linked(prints.select("fp", F.col("doc_id.id").alias("doc_id")), radius)
    placed = prints.join(comp, "fp", "left").select(F.coalesce("root", "fp").alias("root"), F.struct("doc_id.none", "doc_id.id", "fp", "doc_id.row").alias("at"))
    placed = stage(placed, "placed")
    first = placed.groupBy("root").agg(F.min("at").alias("first"))
    # By row, not by component: a component of many copies would meet in one task.
    gone = placed.select(F.col("at.row").alias(row)).join(first.select(F.col("first.row").alias(row)), row, "left_anti")
    return rows.join(stage(gone, "copies"), row, "left_anti").select(columns_of(docs))
