"""Accuracy and cost measures of filters, as DataFrames or numbers.

``grid`` builds and measures many filters over the keys of a table in one job: keys are shuffled to their shard once,
and the task that has a shard's keys builds that shard of one filter after the other.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .build import build, routed, shard_column
from .cost import Cost, ExpCost
from .geometry import LINE_BITS, WORDS, FilterSpec, lines_for, plan_spec
from .keys import key64
from .models import choice_fpr, distinct_candidates, line_fpr
from .probe import answers, as_array, asked_all, by_array, probe


def fpr(lines: DataFrame, spec: FilterSpec, absent: DataFrame, key: str, plan: str = "auto") -> DataFrame:
    """probes, false_pos, fpr, log2_fpr over keys that were not inserted."""
    out = probe(absent, key, lines, spec, plan).agg(F.count("maybe").alias("probes"), F.count_if("maybe").alias("false_pos"))
    rate = F.col("false_pos") / F.col("probes")
    return out.select("probes", "false_pos", rate.alias("fpr"), F.when(F.col("false_pos") > 0, F.log2(rate)).alias("log2_fpr"))


def false_negatives(lines: DataFrame, spec: FilterSpec, present: DataFrame, key: str, plan: str = "auto") -> int:
    return probe(present, key, lines, spec, plan).where("not maybe").count()


def histogram(lines: DataFrame, spec: FilterSpec) -> DataFrame:
    """(ones, lines), empty lines included."""
    counted = lines.groupBy("ones").agg(F.count("*").alias("lines"))
    empty = lines.agg((F.lit(spec.shards * spec.lines) - F.count("*")).alias("lines")).select(F.lit(0).alias("ones"), "lines")
    return counted.unionByName(empty).where("lines > 0")


def load_summary(lines: DataFrame, spec: FilterSpec) -> DataFrame:
    """mean_ones, sd_ones, max_ones, load over all lines of the filter."""
    h, n = F.col("ones").cast("double"), F.col("lines").cast("double")
    sums = histogram(lines, spec).agg(F.sum(n).alias("n"), F.sum(n * h).alias("s"), F.sum(n * h * h).alias("q"), F.max("ones").alias("max_ones"))
    mean = F.col("s") / F.col("n")
    return sums.select(F.round(mean, 9).alias("mean_ones"), F.round(F.sqrt(F.col("q") / F.col("n") - mean * mean), 6).alias("sd_ones"), "max_ones", F.round(mean / LINE_BITS, 9).alias("load"))


def fpr_from_loads(lines: DataFrame, spec: FilterSpec) -> DataFrame:
    """Expected FPR from the ones of the lines: per shard, the chance of a footprint to lie in a line; then of any candidate; then the mean over shards."""
    ones, k = F.col("ones"), F.lit(float(spec.k))
    if spec.kind == "classic":
        one = F.pow(F.sum(ones) / F.lit(spec.lines * LINE_BITS), k)
    elif spec.bits == "distinct":
        table = F.array(*[F.lit(float(x)) for x in line_fpr(np.arange(LINE_BITS + 1), spec.k, "distinct")])
        one = F.sum(F.get(table, ones)) / F.lit(spec.lines)
    else:
        one = F.sum(F.pow(ones / LINE_BITS, k)) / F.lit(spec.lines)  # lines that are not there have no ones
    shards = lines.groupBy("shard").agg(one.alias("p"))
    total = F.lit(0.0)
    for candidates, weight in enumerate(distinct_candidates(spec.choices, spec.lines), 1):
        total = total + F.lit(weight) * (1 - F.pow(1 - F.col("p"), F.lit(float(candidates))))
    mean = F.sum(total if spec.choices > 1 else F.col("p")) / F.lit(spec.shards)
    return shards.agg(mean.alias("f")).select(F.lit(spec.kind).alias("kind"), F.lit(spec.k).alias("k"), F.round(F.log2("f"), 9).alias("log2_fpr"))


def overload_report(keys: DataFrame, spec: FilterSpec, distinct: bool = False) -> DataFrame:
    """inserted, capacity, gamma, and the penalty that a classic filter of this load would pay (FPR over 2^-k).

    ``distinct`` says that no key repeats.
    """
    if not spec.capacity:
        raise ValueError("the filter was not sized for a number of keys")
    gamma = F.col("inserted") / F.lit(spec.capacity)
    penalty = F.pow(2 * (1 - F.pow(F.lit(2.0), -gamma)), F.lit(float(spec.k)))
    return keys.agg((F.count if distinct else F.count_distinct)("key64").alias("inserted")).select("inserted", F.lit(spec.capacity).alias("capacity"), gamma.alias("gamma"), penalty.alias("penalty"))


def shard_balance(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    return routed(keys, spec).groupBy("shard").agg(F.count("*").alias("keys"))


def touches(keys: DataFrame, key: str, lines: DataFrame, spec: FilterSpec) -> DataFrame:
    """Mean lines (classic: addresses) read per lookup until the answer is known, and with all candidates fetched beforehand, by outcome."""
    eager = spec.k if spec.kind == "classic" else spec.choices
    out = by_array(keys, key, lines, spec, details=True).groupBy("maybe")
    return out.agg(F.round(F.avg("touched"), 6).alias("mean_touched"), F.count("*").alias("probes")).withColumn("eager", F.lit(eager))


def bits_examined(keys: DataFrame, key: str, lines: DataFrame, spec: FilterSpec) -> DataFrame:
    """Mean bits read per lookup, each candidate up to its first zero, by outcome."""
    shared = keys.sparkSession.sparkContext.broadcast(as_array(lines, spec))

    def count(raw: pa.Array) -> pa.Array:
        x = K.prepared(raw.fill_null(0).to_numpy(), spec)
        base, address = K.shard_of(x, spec) * spec.lines, K.addresses(x, spec)
        if spec.kind == "classic":
            return pa.array(K.classic_lookup(shared.value.reshape(-1), base[:, None] * LINE_BITS + address)[1])
        return pa.array(K.bits_examined(shared.value, base[:, None] + K.candidates(x, spec), address))

    asked = by_array(keys, key, lines, spec).withColumn("read", F.arrow_udf(count, "long")(key64(keys, key)))
    return asked.groupBy("maybe").agg(F.round(F.avg("read"), 6).alias("mean_bits"), F.count("*").alias("probes"))


# --- one filter in one process ------------------------------------------------------------------


def simulate(spec: FilterSpec, n: int, probes: int = 0) -> dict:
    """Build on n scrambled consecutive keys, probe ``probes`` later ones; FPR from loads unless probed."""
    keys = np.arange(n, dtype=np.int64)
    x = K.prepared(keys, spec)
    if spec.kind == "classic":
        address = K.addresses(x, spec)
        words = np.zeros((spec.lines, 8), np.uint64)
        np.bitwise_or.at(words.reshape(-1), address.reshape(-1) >> 6, np.uint64(1) << (address.reshape(-1) & 63).astype(np.uint64))
    else:
        words = np.zeros((spec.lines, 8), np.uint64)
        mask, cand = K.footprints(x, spec), K.candidates(x, spec)
        if spec.kind == "linelocal":
            np.bitwise_or.at(words, cand[:, 0], mask)
        else:
            K.insert(words, cand, mask, spec)
    ones = K.ones(words)
    hits = 0
    if probes:
        found, _, _ = answers(words, np.arange(n, n + probes, dtype=np.int64), replace(spec, shards=1))
        hits = int(found.sum())
    one = (ones.mean() / LINE_BITS) ** spec.k if spec.kind == "classic" else float(line_fpr(ones, spec.k, spec.bits).mean())
    rate = hits / probes if probes else choice_fpr(one, spec.choices, spec.lines)
    return {"probes": probes, "false_pos": hits, "fpr": rate, "log2_fpr": math.log2(rate) if rate else None, "mean_ones": float(ones.mean()), "max_ones": int(ones.max())}


def cell(kind: str, choices: int, k: int, lines: int, rel_size: float = 1.0, gamma: float = 1.0, probes: int = 0, **rest) -> tuple:
    """One filter of ``lines`` lines filled with gamma times the keys that its relative size means."""
    n = round(gamma * lines * LINE_BITS * math.log(2) / (k * rel_size))
    return FilterSpec(kind=kind, choices=choices, k=k, lines=lines, **rest), n, probes, rel_size, gamma


def required_size(kind: str, choices: int, k: int, lines: int = 400, bits: str = "random", steps: int = 9) -> float:
    """Relative size at which the FPR is 2^-k, by bisection over builds."""
    low, high = 0.9, 1.6
    for _ in range(steps):
        middle = (low + high) / 2
        spec, n, *_ = cell(kind, choices, k, lines, middle, bits=bits)
        low, high = (middle, high) if simulate(spec, n)["fpr"] > 2.0**-k else (low, middle)
    return (low + high) / 2


# --- many filters over the keys of a table ------------------------------------------------------
#: Keys that a shard of a grid's filters is meant for.
SHARD_KEYS = 1 << 16
#: Shards that a task fills side by side (keys of different shards never meet, so more of them are written in one step),
#: in turns of so many keys each.
BUNDLE, TURN = 8, 1 << 9


@dataclass(frozen=True)
class Cell:
    """A filter to be measured: ``rel_size`` times the classic size for n / gamma keys, filled with n; epochs 0: key by key."""

    kind: str = "choice"
    choices: int = 2
    k: int = 10
    bits: str = "random"
    rel_size: float = 1.0
    gamma: float = 1.0
    cost: Cost = field(default_factory=ExpCost)
    epochs: int = 0
    label: str = ""

    def spec(self, n: int, shards: int) -> FilterSpec:
        total = lines_for(max(1, n), self.k, self.rel_size / self.gamma)
        return FilterSpec(self.kind, self.k, self.choices, shards, math.ceil(total / shards), self.bits, cost=self.cost, capacity=round(n / self.gamma))


GRID = (
    "kind string, choices int, k int, bits string, cost string, label string, epochs int, rel_size double, gamma double, n long, bytes long, "
    "probes long, false_pos long, fpr_probed double, fpr double, log2_fpr double, mean_ones double, max_ones long"
)


def _measured(spec: FilterSpec, epochs: int, x: np.ndarray, own: np.ndarray, shards: int, asked: list[np.ndarray], kept: dict) -> tuple[int, int, int, float, float]:
    """Some shards of a filter, ``own`` the shard of every key: (false answers, ones, most ones of a line, chances of a false
    answer by the loads, their squares), added up over the shards. ``asked``: absent keys by shard."""
    words = np.zeros((shards * spec.lines, WORDS), np.uint64)
    if spec.kind == "classic":
        flat = words.reshape(-1)
        for lo in range(0, len(x), K.PIECE):
            part = slice(lo, lo + K.PIECE)
            address = (own[part, None] * (spec.lines * LINE_BITS) + K.addresses(x[part], spec)).reshape(-1)
            np.bitwise_or.at(flat, address >> 6, np.uint64(1) << (address & 63).astype(np.uint64))
    else:
        shape = spec.k, spec.bits
        if shape not in kept:  # the footprints are those of all sizes
            kept.clear()
            kept[shape] = K.footprints(x, spec)
        cand, mask = K.candidates(x, spec) + (own * spec.lines)[:, None], kept[shape]
        if spec.choices == 1:
            np.bitwise_or.at(words, cand[:, 0], mask)
        elif epochs:
            for s in range(shards):
                mine = np.flatnonzero(own == s)
                K.insert_epoch(words, cand[mine], mask[mine], spec, epochs)
        else:
            K.insert(words, cand, mask, spec, window=shards * TURN if shards > 1 else None)
    ones, one = K.ones(words).reshape(shards, -1), replace(spec, shards=1, premix=False, width=64)
    lines = words.reshape(shards, spec.lines, WORDS)
    wrong = sum(int(answers(lines[s], some, one)[0].sum()) for s, some in enumerate(asked) if len(some))
    p = [choice_fpr((o.mean() / LINE_BITS) ** spec.k if spec.kind == "classic" else float(line_fpr(o, spec.k, spec.bits).mean()), spec.choices, spec.lines) for o in ones]
    return wrong, int(ones.sum()), int(ones.max()), sum(p), sum(v * v for v in p)


def _in_turns(own: np.ndarray) -> np.ndarray:
    """An order of the keys, sorted by shard, in which the shards take turns of TURN keys."""
    first = np.searchsorted(own, own)
    return np.argsort((np.arange(len(own)) - first) // TURN, kind="stable")


def grid(keys: DataFrame, cells: list[Cell], absent: DataFrame | None = None, group: str | None = None, distinct: bool = False, shard_keys: int | None = None) -> DataFrame:
    """A row of GRID per cell (and per value of the column ``group``, few of them) for the distinct key64 of ``keys``.

    fpr is expected from the loads; fpr_probed is the share of false answers among ``absent`` (key64, group). The keys
    are copied once per share of the cells, as many shares as it takes to busy the cluster. ``distinct`` says that no
    (group, key64) repeats. Multi-choice insertion is faster in shards of more keys (``shard_keys``), which meet less.
    """
    spark = keys.sparkSession
    name = F.col(group) if group else F.lit("")
    have = keys.select(name.alias("g"), "key64", F.lit(False).alias("asked")).where("key64 is not null")
    have = have if distinct else have.distinct()
    if absent is not None:
        have = have.unionByName(absent.select(F.col(group).alias("g") if group else F.lit("").alias("g"), "key64", F.lit(True).alias("asked")))
    have = have.persist()
    counts = {r["g"]: r["n"] for r in have.where("not asked").groupBy("g").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return spark.createDataFrame([], (f"{group} string, " if group else "") + GRID)
    shards = max(1, math.ceil(max(counts.values()) / (shard_keys or SHARD_KEYS)))
    out = _sums(have, cells, counts, shards)
    fpr_ = F.col("p") / shards
    return out.select(
        *([F.col("g").alias(group)] if group else []), "kind", "choices", "k", "bits", "cost", "label", "epochs", "rel_size", "gamma", "n", "bytes", "probes",
        F.col("wrong").alias("false_pos"), F.when(F.col("probes") > 0, F.col("wrong") / F.col("probes")).alias("fpr_probed"), fpr_.alias("fpr"),
        F.round(F.log2(fpr_), 9).alias("log2_fpr"), F.round(F.col("ones") / F.col("lines"), 9).alias("mean_ones"), F.col("most").alias("max_ones"),
    )


def _sums(have: DataFrame, cells: list[Cell], counts: dict, shards: int) -> DataFrame:
    """have (g, key64, asked), ``counts`` keys to insert by g -> a row per g and cell with what ``_measured`` adds up."""
    spark, names = have.sparkSession, sorted(counts, key=str)
    cores = spark.sparkContext.defaultParallelism
    side = max(1, min(BUNDLE, shards * len(names) // (4 * cores)))
    bundles = math.ceil(shards / side)
    shares = max(1, min(len(cells), math.ceil(4 * cores / (bundles * len(names)))))
    # Costly cells first, dealt round; cells of one footprint lie together in a share.
    order = sorted(range(len(cells)), key=lambda i: (cells[i].choices > 1, cells[i].k, cells[i].bits), reverse=True)
    dealt = [sorted(order[i::shares], key=lambda j: (cells[j].k, cells[j].bits, j)) for i in range(shares)]
    route = FilterSpec(shards=shards)
    place = F.coalesce(*[F.when(F.col("g").eqNullSafe(F.lit(g)), F.lit(i)) for i, g in enumerate(names)])
    rows = shard_column(have.withColumn("place", place).where("place is not null"), "key64", "shard", route)
    rows = rows.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))))
    task = (F.col("place") * bundles + F.floor(F.col("shard") / side)) * shares + F.col("share")
    rows = rows.select(task.cast("int").alias("task"), "asked", "key64", (F.col("shard") % side).cast("int").alias("own"))
    parts = min(len(names) * bundles * shares, 1 << 14)
    rows = rows.repartitionById(parts, F.col("task") % parts).sortWithinPartitions("task", "asked", "own", "key64")
    sizes = [counts[g] for g in names]
    told = ["place", "cell", "n", "probes", "wrong", "ones", "most", "p", "pp"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, held = -1, []

        def finish() -> pa.RecordBatch:
            asked, values, own = (np.concatenate([b.column(i).to_numpy(zero_copy_only=False) for b in held]) for i in (1, 2, 3))
            x, own, out, kept = K.prepared(np.ascontiguousarray(values), route), own.astype(np.int64), [], {}
            n_in = int((~asked.astype(bool)).sum())
            at, bundle = task // shares // bundles, task // shares % bundles
            mine = min(side, shards - bundle * side)
            absent = np.split(x[n_in:].view(np.int64), np.searchsorted(own[n_in:], np.arange(1, mine)))
            turns, n_absent = _in_turns(own[:n_in]), len(x) - n_in
            x, own = x[turns], own[turns]
            for i in dealt[task % shares]:
                spec = cells[i].spec(sizes[at], shards)
                out.append((at, i, n_in, n_absent, *_measured(spec, cells[i].epochs, x, own, mine, absent, kept)))
            kinds = [pa.int32(), pa.int32(), *[pa.int64()] * 5, pa.float64(), pa.float64()]
            return pa.RecordBatch.from_arrays([pa.array([r[j] for r in out], t) for j, t in enumerate(kinds)], told)

        for batch in batches:
            owner = batch.column(0).to_numpy()
            cut = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1], [True]))) if len(owner) else []
            for lo, hi in zip(cut[:-1], cut[1:]):
                if owner[lo] != task:
                    if held:
                        yield finish()
                    task, held = int(owner[lo]), []
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield finish()

    built = rows.mapInArrow(run, "place int, cell int, n long, probes long, wrong long, ones long, most long, p double, pp double")
    sums = built.groupBy("place", "cell").agg(*[F.sum(c).alias(c) for c in ("n", "probes", "wrong", "ones", "p", "pp")], F.max("most").alias("most"))
    about = []
    for at, g in enumerate(names):
        for i, c in enumerate(cells):
            spec = c.spec(sizes[at], shards)
            about.append((at, g, i, c.kind, spec.choices, c.k, c.bits, type(c.cost).__name__, c.label, c.epochs, c.rel_size, c.gamma, spec.bytes, spec.shards * spec.lines))
    schema = "place int, g string, cell int, kind string, choices int, k int, bits string, cost string, label string, epochs int, rel_size double, gamma double, bytes long, lines long"
    return sums.join(F.broadcast(spark.createDataFrame(about, schema)), ["place", "cell"])


#: Shards that the first guess of a required size is made from; half the distance over which its slope is taken.
PILOT, ASIDE = 4, 0.01


def _guesses(keys: DataFrame, cells: list[Cell], n: int, shards: int, low: float, high: float) -> dict[int, tuple[float, float]]:
    """Cell -> (size, growth of log2 fpr with the size) near an FPR of 2^-k, by a bisection over a few shards: where to start on all of them."""
    route = FilterSpec(shards=shards)

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = K.shard_of(K.prepared(batch.column(0).to_numpy(), route), route)
            some = np.flatnonzero(own < PILOT)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(some)), pa.array(own[some].astype(np.int32))], ["key64", "own"])

    rows = keys.select("key64").mapInArrow(near, "key64 long, own int")
    rows = rows.withColumn("cell", F.explode(F.sequence(F.lit(0), F.lit(len(cells) - 1))))
    rows = rows.repartitionById(len(cells), F.col("cell")).sortWithinPartitions("own", "key64").select("cell", "own", "key64")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not sum(map(len, held)):
            return
        at, own, values = (np.concatenate([b.column(i).to_numpy() for b in held]) for i in range(3))
        own, c, kept = own.astype(np.int64), cells[int(at[0])], {}
        turns = _in_turns(own)
        x, own = K.prepared(np.ascontiguousarray(values), route)[turns], own[turns]

        def tried(size: float) -> float:
            return math.log2(max(_measured(replace(c, rel_size=size).spec(n, shards), c.epochs, x, own, PILOT, [], kept)[3] / PILOT, 1e-300))

        a, b = low, high
        while b - a > 1.2 * ASIDE:
            a, b = ((a + b) / 2, b) if tried((a + b) / 2) > -c.k else (a, (a + b) / 2)
        a, b = (a + b) / 2 - ASIDE, (a + b) / 2 + ASIDE
        left, right = tried(a), tried(b)
        here, there = _real_size(c, a, b, n, shards)
        # Where a few lines make the rate, the slope of a few shards is noise: it is held within what filters have.
        slope = max(min((right - left) / max(there - here, 1e-9), -c.k / 3), -1.2 * c.k)
        yield pa.RecordBatch.from_arrays([pa.array([int(at[0])], pa.int32()), pa.array([(a + b) / 2 - ((left + right) / 2 + c.k) / slope]), pa.array([slope])], ["cell", "size", "slope"])

    return {r["cell"]: (r["size"], r["slope"]) for r in rows.mapInArrow(run, "cell int, size double, slope double").collect()}


def _real_size(c: Cell, *at) -> list[float]:
    """The relative sizes, with lines whole: (sizes ..., n, shards)."""
    *sizes, n, shards = at
    return [shards * replace(c, rel_size=s).spec(n, shards).lines * LINE_BITS * math.log(2) / (n * c.k) for s in sizes]


def required_sizes(keys: DataFrame, cells: list[Cell], steps: int = 9, low: float = 0.9, high: float = 1.6) -> DataFrame:
    """Relative size (and overhead factor) at which each cell's filter of all the keys has an FPR of 2^-k, by bisection.

    A step of the bisection is built, from all keys, unless a filter that was built tells its outcome: by the growth of log2 fpr with the
    size, six deviations (from shard to shard) beside a quarter of the distance away from 2^-k. The first size to be built lies where a few shards have it.
    """
    keys = keys.select("key64").where("key64 is not null").distinct().persist()
    n = keys.count()
    shards = max(1, math.ceil(n / SHARD_KEYS))
    guess = _guesses(keys, cells, n, shards, low, high) if shards > PILOT else {}
    have = keys.select(F.lit("").alias("g"), "key64", F.lit(False).alias("asked"))
    built: list[dict[float, tuple[float, float]]] = [{} for _ in cells]

    def over(i: int, size: float) -> bool | None:
        """Whether the FPR is above 2^-k at that size, where it has been built or follows from what has been."""
        if size in built[i]:
            return built[i][size][0] > 2.0 ** -cells[i].k
        for at, (p, sd) in built[i].items():
            if i in guess and p > 0:
                here, there = _real_size(cells[i], at, size, n, shards)
                way = guess[i][1] * (there - here)
                gap = math.log2(p) + way + cells[i].k
                if abs(gap) > 6 * sd / (p * math.log(2)) + abs(way) / 4:
                    return gap > 0
        return None

    def bisected(judge) -> tuple[float, float, float | None]:
        """(low, high, None), or the first size that cannot be judged as the third."""
        a, b = low, high
        for _ in range(steps):
            said = judge((a + b) / 2)
            if said is None:
                return a, b, (a + b) / 2
            a, b = ((a + b) / 2, b) if said else (a, (a + b) / 2)
        return a, b, None

    def start(i: int) -> float:
        if i not in guess:
            return (low + high) / 2
        a, b, _ = bisected(lambda size: size < guess[i][0])
        return min((e for e in (a, b) if e not in (low, high)), key=lambda e: abs(e - guess[i][0]))

    wanted = {i: start(i) for i in range(len(cells))} if n else {}
    while wanted:
        tried = [replace(cells[i], rel_size=size, label=str(i)) for i, size in wanted.items()]
        for r in _sums(have, tried, {"": n}, shards).select("label", "p", "pp").collect():
            i, mean = int(r["label"]), r["p"] / shards
            sd = math.sqrt(max(0.0, r["pp"] / shards - mean * mean) / max(1, shards - 1))
            built[i][wanted[i]] = mean, sd
        wanted = {i: at for i in range(len(cells)) if (at := bisected(lambda size, i=i: over(i, size))[2]) is not None}
    ends = [bisected((lambda size, i=i: over(i, size)) if n else lambda size: False)[:2] for i in range(len(cells))]
    keys.unpersist()
    rows = [(c.kind, c.choices if c.kind == "choice" else 1, c.k, c.bits, (a + b) / 2, (a + b) / 2 / math.log(2)) for c, (a, b) in zip(cells, ends)]
    return keys.sparkSession.createDataFrame(rows, "kind string, choices int, k int, bits string, rel_size double, overhead double")


def overload_rows(filled: DataFrame, ks: list[int]) -> DataFrame:
    """filled (with gamma) for every k, with the penalty by the model (``models.overload``)."""
    k = F.col("k").cast("double")
    penalty = F.pow(1 - F.pow(F.lit(2.0), -F.col("gamma")), k) * F.pow(F.lit(2.0), k)
    return filled.withColumn("k", F.explode(F.array(*map(F.lit, ks)))).withColumn("penalty", F.round(penalty, 6))


def collisions(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """(k, keys, collided) for k up to the spec's: how many of the distinct keys have first k addresses that are not all different."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, first = 0, np.zeros(spec.k + 1, np.int64)
        for batch in batches:
            address = K.addresses(K.prepared(batch.column(0).to_numpy(), spec), spec)
            n, met = n + len(address), np.zeros(len(address), bool)
            for i in range(1, spec.k):
                met |= (address[:, :i] == address[:, i : i + 1]).any(1)
                first[i + 1] += int(met.sum())
        if n:
            columns = [pa.array(np.arange(1, spec.k + 1, dtype=np.int32)), pa.array(np.full(spec.k, n)), pa.array(first[1:])]
            yield pa.RecordBatch.from_arrays(columns, ["k", "keys", "collided"])

    return keys.select("key64").mapInArrow(run, "k int, keys long, collided long").groupBy("k").agg(F.sum("keys").alias("keys"), F.sum("collided").alias("collided"))


def keys_per_line(keys: DataFrame, ks: tuple[int, ...]) -> dict[int, tuple[int, int, dict[int, int]]]:
    """k -> (keys, lines, {keys in a line: lines}) of line-local filters of the distinct keys at the classic size."""
    n = keys.count()
    lines = {k: lines_for(n, k) for k in ks}

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, most in lines.items():
                spec = FilterSpec("linelocal", k, lines=most)
                line = np.sort(K.candidates(K.prepared(batch.column(0).to_numpy(), spec), spec)[:, 0])
                cut = np.flatnonzero(np.concatenate(([True], line[1:] != line[:-1], [True]))) if len(line) else np.zeros(1, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cut) - 1, k, np.int32)), pa.array(line[cut[:-1]].astype(np.int64)), pa.array(np.diff(cut))], ["k", "line", "held"])

    placed = keys.select("key64").mapInArrow(place, "k int, line long, held long")
    counted = placed.groupBy("k", "line").agg(F.sum("held").alias("held")).groupBy("k", "held").agg(F.count("*").alias("lines")).collect()
    out = {k: (n, lines[k], {r["held"]: r["lines"] for r in counted if r["k"] == k}) for k in ks}
    for _, total, held in out.values():
        held[0] = total - sum(held.values())
    return out


Timed = tuple[str, FilterSpec, bool]


def timed(keys: DataFrame, filters: list[Timed], runs: int = 3) -> DataFrame:
    """(filter, operation, run, seconds, keys) of the filters (name, spec, whether to look up), numbered as they come, over distinct (key64, ord).

    Insertion and, where asked for, lookups of all keys (hit) and of the same ones shifted by 2^40 (miss). Every run has all keys. The keys are
    dealt to the shards once per count of shards, as in a build; the task that has a shard's keys then writes and asks that shard, run
    by run. Seconds are those of the slowest shard, or all shards' seconds dealt to the cores if that is more: shards side by side, each in
    a process of its own, without the way of the keys to them.
    """
    spark = keys.sparkSession
    cores = spark.sparkContext.defaultParallelism
    parts = [[i for i, (_, s, _) in enumerate(filters) if s.shards == shards] for shards in sorted({s.shards for _, s, _ in filters})]
    found = None
    for mine in parts:
        route = filters[mine[0]][1]
        if any((s.seed, s.premix, s.u) != (route.seed, route.premix, route.u) for _, s, _ in (filters[i] for i in mine)):
            raise ValueError("filters of one count of shards have one seed and key width")
        some = _timed_shards(keys, filters, mine, route, runs, min(len(mine), math.ceil(4 * cores / route.shards)))
        found = some if found is None else found.unionByName(some)
    wall = F.greatest(F.max("seconds"), F.sum("seconds") / F.lit(cores))
    return found.groupBy("filter", "operation", "run").agg(wall.alias("seconds"), F.sum("keys").alias("keys"))


def _timed_shards(keys: DataFrame, filters: list[Timed], mine: list[int], route: FilterSpec, runs: int, shares: int) -> DataFrame:
    """(filter, operation, run, shard, keys, seconds) of filters that deal keys alike; each task has a shard of one share of them."""
    asks = any(filters[i][2] for i in mine)
    rows = keys.select("key64", "ord", F.lit(False).alias("absent"))
    if asks:
        rows = rows.unionByName(keys.select((F.col("key64") + F.lit(1 << 40)).alias("key64"), "ord", F.lit(True).alias("absent")))
    rows = shard_column(rows, "key64", "shard", route).withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))))
    n = route.shards * shares
    rows = rows.select((F.col("shard") * shares + F.col("share")).cast("int").alias("task"), "absent", "ord", "key64")
    rows = rows.repartitionById(min(n, 1 << 14), F.col("task") % min(n, 1 << 14)).sortWithinPartitions("task", "absent", "ord", "key64").select("task", "absent", "key64")
    # Costly filters first, dealt round.
    order = sorted(mine, key=lambda i: (filters[i][1].choices, filters[i][1].bits != "random", filters[i][1].k), reverse=True)

    def measured(task: int, held: list[pa.RecordBatch]) -> pa.RecordBatch:
        absent, values = (np.concatenate([b.column(i).to_numpy(zero_copy_only=False) for b in held]) for i in (1, 2))
        present = int((~absent.astype(bool)).sum())
        out = []
        for i in order[task % shares :: shares]:
            spec = replace(filters[i][1], shards=1)
            for run in range(runs):
                began = time.perf_counter()
                lines = K.filled(K.prepared(values[:present], spec), spec)
                out.append((i, "insert", run, task // shares, present, time.perf_counter() - began))
            for what, asked in (("hit", values[:present]), ("miss", values[present:])) if filters[i][2] else ():
                for run in range(runs):
                    began = time.perf_counter()
                    asked_all(lines, asked, spec)
                    out.append((i, what, run, task // shares, len(asked), time.perf_counter() - began))
        kinds = [pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.float64()]
        return pa.RecordBatch.from_arrays([pa.array([r[j] for r in out], t) for j, t in enumerate(kinds)], ["filter", "operation", "run", "shard", "keys", "seconds"])

    def run_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, held = -1, []
        for batch in batches:
            owner = batch.column(0).to_numpy()
            cut = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1], [True]))) if len(owner) else []
            for lo, hi in zip(cut[:-1], cut[1:]):
                if owner[lo] != task:
                    if held:
                        yield measured(task, held)
                    task, held = int(owner[lo]), []
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield measured(task, held)

    return rows.mapInArrow(run_all, "filter int, operation string, run int, shard int, keys long, seconds double")


THROUGHPUT = "name string, kind string, choices int, k int, shards int, operation string, plan string, n long, mkeys_per_s double"


def throughput(keys: DataFrame, filters: list[Timed], runs: int = 3) -> DataFrame:
    """Million keys per second (mean of ``runs``, ``timed``) of insertion, hit and miss lookups (plan ``array``), per filter; null without keys."""
    facts = [
        (i, name, s.kind, s.choices, s.k, s.shards, what, "" if what == "insert" else "array")
        for i, (name, s, asked) in enumerate(filters) for what in ("insert", "hit", "miss") if asked or what == "insert"
    ]
    facts = keys.sparkSession.createDataFrame(facts, "filter int, name string, kind string, choices int, k int, shards int, operation string, plan string")
    mean = timed(keys, filters, runs).groupBy("filter", "operation").agg(F.avg("seconds").alias("seconds"), F.max("keys").alias("n"))
    rate = (F.col("n") / F.col("seconds") / 1e6).alias("mkeys_per_s")
    return facts.join(mean, ["filter", "operation"], "left").select("name", "kind", "choices", "k", "shards", "operation", "plan", F.coalesce("n", F.lit(0).cast("long")).alias("n"), rate)


def plan_throughput(keys: DataFrame, specs: dict[str, FilterSpec], plans: tuple[str, ...], runs: int = 3) -> DataFrame:
    """Million keys per second (mean of ``runs``) of hit and miss lookups by Spark jobs, whole: the filter is sent, the keys are asked, the answers counted.

    ``keys`` (distinct key64, held in memory by the caller); absent keys are the same ones shifted by 2^40.
    """
    spark, rows = keys.sparkSession, []
    n = max(1, keys.count())
    absent = keys.select((F.col("key64") + F.lit(1 << 40)).alias("key64"))
    for name, spec in specs.items():
        lines = build(keys, spec, distinct=True).coalesce(4 * spark.sparkContext.defaultParallelism).persist()
        lines.count()
        for plan in plans:
            if plan in ("join", "expression") and spec.kind == "classic":
                continue
            for what, probes in (("hit", keys), ("miss", absent)):
                began = time.perf_counter()
                for _ in range(runs):
                    probe(probes.select("key64"), "key64", lines, spec, plan).agg(F.count_if("maybe")).collect()
                rows.append((name, spec.kind, spec.choices, spec.k, spec.shards, what, plan, n, n * runs / (time.perf_counter() - began) / 1e6))
        lines.unpersist()
    return spark.createDataFrame(rows, THROUGHPUT)


def four_kinds(n: int, k: int, shards: int = 4, sized: bool = False, bits: str = "random") -> dict[str, FilterSpec]:
    """The four filters side by side; ``sized``: each with the size that gives 2^-k (line-local 1.17, two 1.01, three 0.99 at k = 14)."""
    size = {"classic": 1.0, "linelocal": 1.17, "choice2": 1.01, "choice3": 0.99} if sized else dict.fromkeys(("classic", "linelocal", "choice2", "choice3"), 1.0)
    return {name: plan_spec(n, k, name.rstrip("23"), int(name[-1]) if name[-1].isdigit() else 1, size[name], shards=shards, bits=bits) for name in size}
