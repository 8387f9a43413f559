"""Mixing sources to target weights by pivotal dependent rounding.

A document of source s should be copied target(s) / size(s) times. The whole part is taken outright; the
fractional parts are rounded dependently: two documents at a time trade words until the copy count
of one of them is whole, the direction drawn so that every expectation stays as it is and the words
of the pair stay the same. Documents are dealt by a hash of their id into leaves of about
``LEAF_ROWS`` rows; a leaf that null or repeated ids make ``HOT`` times as large is dealt again by row. A leaf leaves
one residual document at most, the residuals of ``FAN_IN`` leaves
meet in the next level, and so on to one per source. No level gathers more than its fan-in. The
root's residual is rounded too (``root="round"``: whole documents, off the target by less than that
document), or it gives the words that are left to the source, a part of one copy
(``root="split"``: within a word of the target).

Draws come from a keyed hash of the two documents, so reruns agree, whatever the partitions (rows that share an id are
told apart by their place in the table).

Defined results: null text has size 0; a null source is a source of its own, last in order; empty
documents take nothing; repeated rows and ids, null ids too, are mixed each row on its own; an empty table gives no
rows; extra columns are ignored.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StructField, StructType

from .common import columns_of, free_name, keyed, stage

WEIGHTS = (5, 2, 1)
MAX_COPIES = 3
LEAF_ROWS = 1024
FAN_IN = 1024
HOT = 8
SOURCES_AT_ONCE = 100_000
WORD = r"[^\x20\x09-\x0D]+"


def water_fill(sizes: list[int], weights: list[int], cap: int = MAX_COPIES) -> list[Fraction]:
    """Targets by weight that share sum(sizes), none above cap x its size, the excess reshared by weight."""
    left, open_, out = Fraction(sum(sizes)), set(range(len(sizes))), [Fraction(0)] * len(sizes)
    order = sorted(range(len(sizes)), key=lambda i: Fraction(cap * sizes[i], weights[i]))
    weight = sum(weights)
    for i in order:  # the first to reach its bound as the level rises
        if Fraction(cap * sizes[i], weights[i]) * weight > left:
            break
        out[i] = Fraction(cap * sizes[i])
        left, weight = left - out[i], weight - weights[i]
        open_.discard(i)
    for i in open_:
        out[i] = left * weights[i] / weight
    return out


def source_targets(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: int = MAX_COPIES) -> DataFrame:
    """(source, source_size, target, place): one row per source, in order of code points, null last."""
    spark = sized.sparkSession
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("source_rows")).collect()
    if len(sums) > 10 * SOURCES_AT_ONCE:
        raise ValueError("more sources than the driver should hold: group rare ones first")
    sums.sort(key=lambda r: (r["source"] is None, r["source"] or ""))
    goal = water_fill([r["source_size"] for r in sums], [weights[i % len(weights)] for i in range(len(sums))], cap)
    rows = [(r["source"], r["source_size"], r["source_rows"], float(t), i) for i, (r, t) in enumerate(zip(sums, goal))]
    return spark.createDataFrame(rows, "source string, source_size long, source_rows long, target double, place int")


def _unit(a: int, b: int, salt: int) -> float:
    """A number in [0, 1) from two keys (the splitmix64 finaliser)."""
    x = (a * 0x9E3779B97F4A7C15 + b * 0xC2B2AE3D27D4EB4F + salt) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & 0xFFFFFFFFFFFFFFFF
    return ((x ^ (x >> 31)) >> 11) / (1 << 53)


def pivot(keys: list[int], sizes: list[int], shares: list[float], salt: int, eps: float = 1e-9) -> tuple[list[float], int]:
    """Trade words between pairs until one share at most is fractional; returns shares and its index (-1: none).

    sum(size x share) stays, and every share is a martingale.
    """
    out, carry = list(shares), -1
    for i, share in enumerate(out):
        if share <= eps or share >= 1 - eps or not sizes[i]:
            out[i] = float(round(share)) if sizes[i] else 0.0
            continue
        if carry < 0:
            carry = i
            continue
        up = min((1 - out[carry]) * sizes[carry], out[i] * sizes[i])  # words from i to carry
        down = min(out[carry] * sizes[carry], (1 - out[i]) * sizes[i])
        move = up if _unit(keys[carry], keys[i], salt) * (up + down) < down else -down
        for k, words in ((carry, move), (i, -move)):
            p = out[k] + words / sizes[k]
            out[k] = 0.0 if p <= eps else 1.0 if p >= 1 - eps else p
        open_ = [k for k in (carry, i) if 0 < out[k] < 1]
        carry = open_[0] if open_ else -1
    return out, carry


def _level(df: DataFrame, salt: int) -> DataFrame:
    """One level of the tree over (row, h, size, share, place, leaf, sub): the new shares, and what stays fractional."""

    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by([("h", "ascending"), ("size", "ascending"), ("row", "ascending")])
        shares, open_ = pivot(group["h"].to_pylist(), group["size"].to_pylist(), group["share"].to_pylist(), salt)
        still = np.zeros(group.num_rows, bool)
        if open_ >= 0:
            still[open_] = True
        return group.set_column(group.column_names.index("share"), "share", pa.array(shares, pa.float64())).append_column("fractional", pa.array(still))

    schema = StructType([*df.schema.fields, StructField("fractional", BooleanType())])
    return stage(df.groupBy("place", "leaf", "sub").applyInArrow(run, schema), "pivot")


def _drawn(sized: DataFrame, weights: tuple[int, ...], cap: int, seed: int, root: str) -> DataFrame:
    """(row, doc_id, source, size), staged -> the same with source_size, target, copies (whole ones) and taken (words)."""
    targets = source_targets(sized, weights, cap)
    n_sources = targets.count()
    side = F.broadcast(targets) if n_sources <= SOURCES_AT_ONCE else targets
    wanted = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rows = sized.join(side, sized["source"].eqNullSafe(targets["source"]), "inner").drop(targets["source"])
    rows = rows.withColumn("base", F.floor(wanted + 1e-12)).withColumn("share", F.greatest(F.lit(0.0), wanted - F.col("base")))
    leaves = F.greatest(F.lit(1), F.ceil(F.col("source_rows") / LEAF_ROWS))
    rows = rows.withColumn("h", F.xxhash64(F.col("doc_id"), F.lit(seed))).withColumn("leaf", F.pmod(F.xxhash64("h"), leaves))
    hot = rows.groupBy("place", "leaf").count().where(F.col("count") > HOT * LEAF_ROWS)
    hot = stage(hot.select("place", "leaf", F.ceil(F.col("count") / LEAF_ROWS).alias("parts")), "hot")
    rows = rows.join(hot, ["place", "leaf"], "left").withColumn("sub", F.coalesce(F.pmod(F.xxhash64("row"), F.col("parts")), F.lit(0).cast("long"))).drop("parts")
    deep = int(hot.agg(F.max("parts")).first()[0] or 1)
    top = -(-int(targets.agg(F.max("source_rows")).first()[0] or 0) // LEAF_ROWS)
    done, level = [], _level(rows, seed)
    while deep > 1 or top > 1:  # first the parts of hot leaves, then the leaves
        done.append(level.where("not fractional"))
        rest = level.where("fractional").drop("fractional")
        if deep > 1:
            deep, rest = -(-deep // FAN_IN), rest.withColumn("sub", F.floor(F.col("sub") / FAN_IN))
        else:
            top, rest = -(-top // FAN_IN), rest.withColumn("leaf", F.floor(F.col("leaf") / FAN_IN))
        level = _level(rest, seed + len(done))
    done.append(level)
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    if root == "split":
        part = F.round(F.col("share") * F.col("size")).cast("long")
    else:
        # The draw of a root residual: its own hash against its share.
        drawn = F.shiftrightunsigned(F.xxhash64("h", F.lit(seed)), 11) / F.lit(float(1 << 53)) < F.col("share")
        out = out.withColumn("share", F.when(F.col("fractional"), drawn.cast("double")).otherwise(F.col("share")))
        part = F.lit(0).cast("long")
    copies = (F.col("base") + F.floor("share")).cast("long")
    taken = copies * F.col("size") + F.when(F.col("fractional") & (F.col("share") < 1), part).otherwise(0)
    return out.select("row", "doc_id", "source", "size", "source_size", "target", copies.alias("copies"), taken.alias("taken"))


def _size():
    return F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: int = MAX_COPIES, seed: int = 17, root: str = "split") -> DataFrame:
    """doc_id, source, size, source_size, target, copies (whole ones), taken (words), one row per document row."""
    sized = stage(docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "source", _size().alias("size")), "sizes")
    return _drawn(sized, weights, cap, seed, root).drop("row")


def apply_mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: int = MAX_COPIES, seed: int = 17) -> DataFrame:
    """The mixed corpus itself: each row as often as it was drawn (whole documents only)."""
    row, copies = free_name(docs, "row"), free_name(docs, "copies")
    rows = keyed(docs, row)
    sized = stage(rows.select(F.col(row).alias("row"), "doc_id", "source", _size().alias("size")), "sizes")
    drawn = _drawn(sized, weights, cap, seed, "round").where("copies > 0").select(F.col("row").alias(row), F.col("copies").cast("int").alias(copies))
    out = rows.join(drawn.hint("merge"), row)  # both sides grow alike
    return out.withColumn(free_name(out, "copy"), F.explode(F.sequence(F.lit(1), F.col(copies)))).select(columns_of(docs))
