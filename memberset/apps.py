"""Uses: pre-filtered joins, q-gram sets, reads of two origins, contamination scores."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from . import kernels as K
from .build import build, keys_of
from .geometry import FilterSpec, plan_spec
from .keys import columns_of, free_names, quoted
from .probe import BROADCAST_BYTES, answers, as_arrays, probe
from .runs import distinct_grams, origin_hits

# The projection of letters to the four-letter alphabet goes round and round.
LETTERS = "abcdefghijklmnopqrstuvwxyz"
FOUR = "".join(str(i % 4) for i in range(26))

_SLICE = 1 << 18


def _digits(alphabet: str) -> np.ndarray:
    """Digit of every byte, -1 for none."""
    out = np.full(256, -1, np.int64)
    for i, letter in enumerate(LETTERS if alphabet == "four" else "acgt"):
        out[[ord(letter), ord(letter.upper())]] = i % 4
    return out


def grams_of(texts: list[bytes], q: int, alphabet: str = "four", canonical: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(index of the text, pos from 1, gram) of every window of q letters.

    four: all 26 letters, dealt to four digits; other bytes are dropped first. acgt: A, C, G, T are the digits 0 to 3, and windows
    with any other code point are skipped. canonical: the lesser of a window and its reverse complement (digit d against 3 - d).
    """
    data = np.frombuffer(b"".join(texts), np.uint8)
    owner, digit = np.repeat(np.arange(len(texts)), [len(t) for t in texts]), _digits(alphabet)[data]
    sign = digit >= 0 if alphabet == "four" else (data & 0xC0) != 0x80  # a byte per code point
    owner, digit = owner[sign], digit[sign]
    n = len(digit) - q + 1
    if n < 1:
        none = np.empty(0, np.int64)
        return none, none, none

    def windows(d: np.ndarray, forward: bool) -> np.ndarray:
        powers, width = [(1, d)], 1  # windows of doubling width, then the rest of q
        while 2 * width <= q:
            g = powers[-1][1]
            one, two = (g[:-width], g[width:]) if forward else (g[width:], g[:-width])
            powers.append((2 * width, (one << (2 * width)) | two))
            width *= 2
        out, at = np.zeros(n, np.int64), 0
        for width, g in reversed(powers):
            if q - at >= width:
                part = g[at : at + n]
                out = (out << (2 * width)) | part if forward else out | (part << (2 * at))
                at += width
        return out

    gram = windows(np.maximum(digit, 0), True)
    if canonical:
        gram = np.minimum(gram, windows(3 - np.maximum(digit, 0), False))
    good = owner[:n] == owner[q - 1 :]
    if alphabet != "four":
        bad = np.concatenate(([0], np.cumsum(digit < 0)))
        good &= bad[q:] == bad[:n]
    whole = np.flatnonzero(good)
    first = np.searchsorted(owner, np.arange(len(texts)))
    return owner[whole], whole - first[owner[whole]] + 1, gram[whole]


def _slices(texts: pa.Array) -> Iterator[tuple[int, list[bytes]]]:
    """(first row, texts as bytes) in pieces of about ``_SLICE`` bytes; a longer text is one of its own."""
    lo, size, held = 0, 0, []
    for i, t in enumerate(texts.cast(pa.large_binary())):
        held.append(t.as_py() or b"")
        size += len(held[-1])
        if size >= _SLICE or i == len(texts) - 1:
            yield lo, held
            lo, size, held = i + 1, 0, []


def qgrams(df: DataFrame, text: str, q: int = 31, alphabet: str = "four", canonical: bool = False) -> DataFrame:
    """df's other columns, pos (from 1) and gram: each window of q letters (31 at most) as a base-4 number. Short or null texts have none."""
    rest = [c for c in df.columns if c != text]
    n_rest = len(rest)
    source = df.select(*[F.col(quoted(c)).alias(f"c{i}") for i, c in enumerate(rest)], F.col(quoted(text)).alias("text"))
    schema = StructType([*source.schema.fields[:n_rest], StructField("pos", IntegerType()), StructField("gram", LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, texts in _slices(batch.column(n_rest)):
                owner, pos, gram = grams_of(texts, q, alphabet, canonical)
                kept = [batch.column(c).slice(lo).take(pa.array(owner)) for c in range(n_rest)]
                yield pa.RecordBatch.from_arrays([*kept, pa.array(pos.astype(np.int32)), pa.array(gram)], schema.names)

    return source.mapInArrow(run, schema).toDF(*rest, "pos", "gram")


#: Grams that a task sorts at once to drop repeats before the shuffle.
HELD_GRAMS = 1 << 20


def gram_sets(df: DataFrame, text: str, group: str, q: int = 31, alphabet: str = "four", canonical: bool = False) -> DataFrame:
    """(group, key64, ord): the distinct grams of each value of ``group`` (few of them).

    Most repeats go in the tasks already, by sorting; what is left goes to its place once and is compared there, without an
    aggregate before the shuffle that would hold nearly every gram. Groups travel as numbers.
    """
    kind, spark = df.schema[group].dataType, df.sparkSession
    source = df.select(F.col(quoted(group)).alias("g"), F.col(quoted(text)).alias("t")).where("g is not null and t is not null")
    names = sorted(r["g"] for r in source.select("g").distinct().collect())
    if not names:
        return spark.createDataFrame([], StructType([StructField(group, kind), StructField("key64", LongType()), StructField("ord", LongType())]))
    table = F.array(*[F.lit(n).cast(kind) for n in names])
    source = source.select((F.array_position(table, F.col("g")) - 1).cast("int").alias("g"), "t")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}

        def emit(g, parts: list) -> pa.RecordBatch:
            grams = K.once(np.concatenate(parts))
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(grams), g, np.int32)), pa.array(grams)], ["g", "key64"])

        for batch in batches:
            groups = batch.column(0).to_numpy()
            for lo, texts in _slices(batch.column(1)):
                owner, _, gram = grams_of(texts, q, alphabet, canonical)
                some = groups[lo : lo + len(texts)]
                for g in K.once(some).tolist():
                    parts = held.setdefault(g, [])
                    parts.append(gram[(some == g)[owner]])
                    if sum(map(len, parts)) >= HELD_GRAMS:
                        yield emit(g, held.pop(g))
        for g, parts in held.items():
            yield emit(g, parts)

    sets = source.mapInArrow(run, "g int, key64 long").repartition("g", "key64").distinct()
    return sets.select(F.get(table, F.col("g")).alias(group), "key64", F.col("key64").alias("ord"))


Sides = dict[str, list[tuple[DataFrame, FilterSpec, int | None]]]


def count_hits(df: DataFrame, text: str, sides: Sides, q: int = 31, alphabet: str = "four", fold: str | None = None) -> DataFrame:
    """df with ``grams`` (windows of the text) and, per name in ``sides``, a count of those that any of its filters may hold.

    sides: name -> (lines, spec, fold). Where ``fold`` names a column, a row is not asked of the filters of its own fold.
    Filters that fit a broadcast together are asked inside one pass over the texts: grams never become rows. Larger
    ones are asked by the shard plan and the counts joined back. A null or short text has no grams.
    """
    every = [x for some in sides.values() for x in some]
    own = F.coalesce(F.col(quoted(fold)).cast("int"), F.lit(-1)) if fold else F.lit(-1)
    if sum(spec.bytes for _, spec, _ in every) > BROADCAST_BYTES:
        return _count_by_shard(df, text, sides, q, alphabet, own)
    arrays = iter(as_arrays([(lines, spec) for lines, spec, _ in every]))
    shared = df.sparkSession.sparkContext.broadcast({name: [(next(arrays), spec, f) for _, spec, f in some] for name, some in sides.items()})

    def count(texts: pa.Array, folds: pa.Array) -> pa.Array:
        asked, mine = shared.value, folds.to_numpy()
        sums = np.zeros((len(texts), 1 + len(asked)), np.int64)
        for lo, some in _slices(texts):
            owner, _, gram = grams_of(some, q, alphabet)
            sums[lo : lo + len(some), 0] = np.bincount(owner, minlength=len(some))
            of = mine[lo : lo + len(some)][owner]
            for i, filters in enumerate(asked.values(), 1):
                found = np.zeros(len(gram), bool)
                for array, spec, f in filters:
                    ask = np.flatnonzero(~found if f is None else ~found & (of != f))
                    if len(ask):
                        found[ask] = answers(array, gram[ask], spec)[0]
                sums[lo : lo + len(some), i] = np.bincount(owner[found], minlength=len(some))
        return pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32) * sums.shape[1]), pa.array(sums.reshape(-1)))

    (counts,) = free_names(df, "counts")
    told = df.withColumn(counts, F.arrow_udf(count, "array<long>")(F.coalesce(F.col(quoted(text)), F.lit("")), own))
    return told.select(*columns_of(df), *[F.get(F.col(counts), F.lit(i)).alias(name) for i, name in enumerate(["grams", *sides])])


def _count_by_shard(df: DataFrame, text: str, sides: Sides, q: int, alphabet: str, own) -> DataFrame:
    (row,) = free_names(df, "row")
    rows = df.withColumn(row, F.monotonically_increasing_id()).persist()
    asked = qgrams(rows.select(F.col(row).alias("row"), own.alias("own"), F.col(quoted(text)).alias("text")), "text", q, alphabet)
    hits, n = {}, 0
    for name, some in sides.items():
        hits[name] = F.lit(False)
        for lines, spec, f in some:
            asked = probe(asked, "gram", lines, spec, out=f"in{n}")
            hits[name] = hits[name] | (F.col(f"in{n}") & (F.col("own") != F.lit(-2 if f is None else f)))
            n += 1
    sums = asked.groupBy(F.col("row").alias(row)).agg(F.count("*").alias("grams"), *[F.count_if(c).alias(name) for name, c in hits.items()])
    zero = F.lit(0).cast("long")
    return rows.join(sums, row, "left").select(*columns_of(df), *[F.coalesce(F.col(name), zero).alias(name) for name in ("grams", *sides)])


def _asked(left: DataFrame, right: DataFrame, key_left: str, key_right: str, k: int, spec: FilterSpec | None) -> tuple[DataFrame, str]:
    keys = keys_of(right, key_right)
    if spec is None:
        n = keys.agg(F.approx_count_distinct("key64")).first()[0]
        spec = plan_spec(max(1, n), k)
    (maybe,) = free_names(left, "maybe")
    return probe(left, key_left, build(keys, spec), spec, out=maybe), maybe


def prefilter(left: DataFrame, right: DataFrame, key_left: str, key_right: str, how: str = "inner", k: int = 10, spec: FilterSpec | None = None) -> DataFrame:
    """left join right on the keys, with a filter of right's keys asked before the join. Both keys are of one type.

    Rows that the filter refuses are certainly without a partner: they never reach the shuffle of the join. The
    exact join follows, so the rows are those of the plain join.
    how: inner | semi | anti.
    """
    asked, maybe = _asked(left, right, key_left, key_right, k, spec)
    same = F.col(f"l.{quoted(key_left)}") == F.col(f"r.{quoted(key_right)}")
    some = asked.where(F.col(maybe)).drop(maybe).alias("l")
    if how == "inner":
        return some.join(right.alias("r"), same)
    if how == "semi":
        return some.join(right.alias("r"), same, "left_semi")
    surely = asked.where(F.col(maybe).isNull() | ~F.col(maybe)).drop(maybe)
    return surely.unionByName(some.join(right.alias("r"), same, "left_anti"))


def prefilter_report(left: DataFrame, right: DataFrame, key_left: str, key_right: str, k: int = 10, spec: FilterSpec | None = None) -> DataFrame:
    """rows of left, survivors of the filter, partners (rows with a match), and false_survivors, which only the join removes."""
    asked, maybe = _asked(left, right, key_left, key_right, k, spec)
    have = right.select(F.col(quoted(key_right)).alias("_have")).distinct().withColumn("_partner", F.lit(True))
    met = asked.join(have, asked[quoted(key_left)] == have["_have"], "left")
    out = met.agg(F.count("*").alias("rows"), F.count_if(maybe).alias("survivors"), F.count("_partner").alias("partners"))
    return out.withColumn("false_survivors", F.col("survivors") - F.col("partners"))


def fold_of(key: str, folds: int):
    """Fold of a row by the checksum of its key; rows without a key are in fold 0."""
    return F.coalesce(F.pmod(F.crc32(F.col(key).cast("string").cast("binary")), F.lit(folds)), F.lit(0)).cast("int")


def _class(share: float, grams: str, a: str, b: str):
    some = F.col(grams) > 0
    is_a, is_b = some & (F.col(a) >= share * F.col(grams)), some & (F.col(b) >= share * F.col(grams))
    return F.when(is_a & is_b, "both").when(is_a, "a").when(is_b, "b").otherwise("neither")


def _letters(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(digit, index of the text) of every letter."""
    data = np.frombuffer(b"".join(texts), np.uint8)
    digit = _DIGIT_OF[data]
    kept = digit >= 0
    return digit[kept], np.repeat(np.arange(len(texts), dtype=np.int32), [len(t) for t in texts])[kept]


_DIGIT_OF = _digits("four").astype(np.int8)
_OTHERS = bytes(np.flatnonzero(_DIGIT_OF < 0).astype(np.uint8))


def gram_set(df: DataFrame, text: str, q: int = 31) -> DataFrame:
    """(key64, ord): the distinct grams of all texts, compared in buckets of runs."""
    return distinct_grams(df, text, q, _letters, _slices)


def _gram_count(text: str, q: int):
    """Windows of q letters of the text."""

    def count(texts: pa.Array) -> pa.Array:
        return pa.array([max(0, len((t.as_py() or b"").translate(None, _OTHERS)) - q + 1) for t in texts.cast(pa.large_binary())], pa.int64())

    return F.arrow_udf(count, "long")(F.coalesce(F.col(text), F.lit("")))


def _origin_rows(reads: DataFrame, origin_a: DataFrame | None, origin_b: DataFrame | None, folds: int) -> DataFrame:
    """(read_id, fold, text, is_read, origin) of all texts; reads with a column ``origin`` are texts of that origin too."""

    def fold(alone: int | None):
        return (F.col("fold") if folds > 1 else F.lit(alone)).cast("int").alias("fold")

    own = F.col("origin") if "origin" in reads.columns else F.lit(None).cast("string")
    rows = reads.select("read_id", fold(None), "text", F.lit(True).alias("is_read"), own.alias("origin"))
    for name, o in (("a", origin_a), ("b", origin_b)):
        if o is not None:
            rows = rows.unionByName(o.select(F.lit(None).cast("long").alias("read_id"), fold(0), "text", F.lit(False).alias("is_read"), F.lit(name).alias("origin")))
    return rows


def _sorted_reads(reads: DataFrame, hits: DataFrame, q: int, share: float, kinds: dict[str, str]) -> DataFrame:
    """read_id, grams and, by prefix in ``kinds``, hits_a, hits_b and the class (with the suffix)."""
    names = [f"{kind}_{o}" for kind in kinds for o in "ab"]
    sums = hits.where("read_id is not null").groupBy("read_id").agg(*[F.sum(n).alias(n) for n in names])
    whole = reads.select("read_id", _gram_count("text", q).alias("grams"))
    whole = whole.join(sums, "read_id", "left").select("read_id", "grams", *[F.coalesce(n, F.lit(0).cast("long")).alias(n) for n in names])
    return whole.select("*", *[_class(share, "grams", f"{kind}_a", f"{kind}_b").alias(name) for kind, name in kinds.items()])


def two_origins(reads: DataFrame, origin_a: DataFrame | None = None, origin_b: DataFrame | None = None, q: int = 27, k: int = 16, share: float = 0.5, choices: int = 2, folds: int = 1) -> DataFrame:
    """reads (read_id, text) -> grams, hits_a, hits_b and the class a | b | both | neither by the share of grams found.

    Every read has a row; one without grams is neither. With ``folds``, reads and origins have a column fold: each fold of an
    origin has filters of its own, and a read is asked of all but those of its fold (of all, where its fold is null). So a read
    never meets its own text; k grows so that the filters asked have the FPR of one. Reads and origins meet in buckets of grams
    (``runs``), each with filters sized by its distinct grams: no filter is ever held whole. Reads that are an origin's
    texts too may name it in a column ``origin`` instead (a, b or null).
    """
    hits = origin_hits(_origin_rows(reads, origin_a, origin_b, folds), q, folds, _letters, _slices, k + (folds - 1).bit_length(), choices, exact=False)
    return _sorted_reads(reads, hits, q, share, {"hits": "class"})


def two_origins_exact(reads: DataFrame, origin_a: DataFrame | None = None, origin_b: DataFrame | None = None, q: int = 27, share: float = 0.5, folds: int = 1) -> DataFrame:
    """The same with the sets themselves, compared bucket by bucket."""
    hits = origin_hits(_origin_rows(reads, origin_a, origin_b, folds), q, folds, _letters, _slices)
    hits = hits.select("read_id", F.col("exact_a").alias("hits_a"), F.col("exact_b").alias("hits_b"))
    return _sorted_reads(reads, hits, q, share, {"hits": "class"})


def two_origins_confusion(reads: DataFrame, origin_a: DataFrame | None = None, origin_b: DataFrame | None = None, q: int = 27, k: int = 16, share: float = 0.5, choices: int = 2, folds: int = 1) -> DataFrame:
    """Reads by class with the sets (exact) and with the filters (by_filter), and the bytes of either: 8 a gram against the filters' lines."""
    found = origin_hits(_origin_rows(reads, origin_a, origin_b, folds), q, folds, _letters, _slices, k + (folds - 1).bit_length(), choices)
    # A row per read with hits; the row without a read has the space.
    hits = found.groupBy("read_id").agg(*[F.sum(c).alias(c) for c in found.columns[1:]]).persist()
    out = _sorted_reads(reads, hits, q, share, {"exact": "exact", "hits": "by_filter"}).groupBy("exact", "by_filter").agg(F.count("*").alias("reads"))
    space = hits.agg((8 * F.coalesce(F.sum("held"), F.lit(0).cast("long"))).alias("exact_bytes"), F.coalesce(F.sum("filter_bytes"), F.lit(0).cast("long")).alias("filter_bytes"))
    return out.join(F.broadcast(space), how="cross")


def contamination(docs: DataFrame, benchmark: DataFrame, q: int = 31, k: int = 40) -> DataFrame:
    """doc_id, grams, hits, share for every document: how much of its grams the benchmark's filter holds. A document without
    grams has share 0. At k = 40 a false hit is a matter of 10^12 grams."""
    sets = gram_sets(benchmark.select(F.lit(0).alias("g"), "text"), "text", "g", q).persist()
    spec = plan_spec(max(1, sets.count()), k)
    counted = count_hits(docs.select("doc_id", "text"), "text", {"hits": [(build(sets, spec, distinct=True), spec, None)]}, q)
    return counted.select("doc_id", "grams", "hits", F.round(F.coalesce(F.col("hits") / F.nullif("grams", F.lit(0)), F.lit(0.0)), 9).alias("share"))
