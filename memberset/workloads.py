"""Registered queries of the filter engine, each with its SQL reference where SQL can express it.

The measurements (FPR against size, required size, overload, cost forms, choices, batches) build filters of all kinds over
the packed (part, supplier) keys of lineitem, sized by their count. Bit-exact checks of single builds and lookups use fixed
geometries, which their SQL text holds (fuller filters merely answer ``maybe`` more often).
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import apps, build, hashing, measure, models, probe, rivals, stream
from .measure import Cell
from . import kernels as K
from . import sqlref as R
from .advise import advise
from .cost import AddedCost, ExpCost, LinearCost, PowerCost, TotalCost
from .geometry import FilterSpec, plan_spec

QUERIES: dict = {}
ORACLES: dict = {}


def _load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def _texts(spark: SparkSession, df: DataFrame) -> DataFrame:
    """df, straight from a table, for a pass over its texts: dealt out where the scan has fewer tasks than there are cores."""
    cores = spark.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


# Fixed geometries.
UNION = {"classic": FilterSpec("classic", 10, 1, 4, 160), "linelocal": FilterSpec("linelocal", 10, 1, 4, 160)}
ORDERS = "orders"
SMALL = {c: FilterSpec("choice", 10, c, 6, 8) for c in (2, 3)} | {4: FilterSpec("choice", 14, 4, 8, 8)}
KS = (4, 7, 10, 14, 17, 20)
SIZES = tuple(round(0.8 + 0.05 * i, 2) for i in range(11))
GAMMAS = (0.5, 0.8, 0.9, 1.0, 1.05, 1.1, 1.2, 1.5)
KINDS = (("classic", 1), ("linelocal", 1), ("choice", 2), ("choice", 3))


_LN2 = repr(math.log(2))
_sets_sql = "(SELECT o_orderpriority, count(DISTINCT o_custkey) AS keys FROM orders WHERE o_custkey IS NOT NULL GROUP BY o_orderpriority)"


def _key_sets(spark, sf_dir):
    """(o_orderpriority, keys): the customers of the orders of each priority, as the key sets that the models are asked about."""
    orders = _load(spark, sf_dir, "orders").where("o_custkey is not null").select("o_orderpriority", "o_custkey").distinct()
    return orders.groupBy("o_orderpriority").agg(F.count("*").alias("keys"))


# --- hashing -----------------------------------------------------------------------------------
for _name, _b in (("hash_odd", 1001), ("hash_pow2", 512), ("hash_even", 500)):

    def _hash(spark, sf_dir, b=_b):
        y = hashing.mul64(F.col("o_orderkey"), hashing.constant(1, 0))
        return _load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key64"), y.alias("y")).select("key64", hashing.reduce_to(F.col("y"), b).alias("h"))

    query(_name, f"SELECT o_orderkey AS key64, {hashing.sql_hash('o_orderkey', hashing.constant(1, 0), _b)} AS h FROM orders")(_hash)


for _b, _u, _name in ((512, 62, "hash_pow2_width"), (500, 54, "hash_even_width")):

    def _hash_u(spark, sf_dir, b=_b, u=_u):
        y = hashing.mul64(F.col("o_orderkey"), hashing.constant(1, 0))
        return _load(spark, sf_dir, "orders").select("o_orderkey", y.alias("y")).select("o_orderkey", hashing.reduce_to(F.col("y"), b, u).alias("h"))

    query(_name, f"SELECT o_orderkey, {hashing.sql_hash('o_orderkey', hashing.constant(1, 0), _b, _u)} AS h FROM orders")(_hash_u)


@query(
    "qgram_keys",
    f"""WITH t AS (SELECT item_id, translate(lower(regexp_replace(text, '[^A-Za-z]', '', 'g')), '{apps.LETTERS}', '{apps.FOUR}') AS s FROM benchmark)
SELECT item_id, CAST(pos AS INTEGER) AS pos, list_reduce(list_transform(string_split(substr(s, pos, 31), ''), lambda c: CAST(c AS BIGINT)), lambda a, b: a * 4 + b) AS gram
FROM (SELECT item_id, s, unnest(range(1, length(s) - 29)) AS pos FROM t WHERE length(s) >= 31)""",
)
def qgram_keys(spark, sf_dir):
    return apps.qgrams(_load(spark, sf_dir, "benchmark").select("item_id", "text"), "text", 31)


@query(
    "qgram_keys_documents",
    f"""WITH t AS (SELECT doc_id, translate(lower(regexp_replace(text, '[^A-Za-z]', '', 'g')), '{apps.LETTERS}', '{apps.FOUR}') AS s FROM documents)
SELECT doc_id, CAST(pos AS INTEGER) AS pos, list_reduce(list_transform(string_split(substr(s, pos, 31), ''), lambda c: CAST(c AS BIGINT)), lambda a, b: a * 4 + b) AS gram
FROM (SELECT doc_id, s, unnest(range(1, length(s) - 29)) AS pos FROM t WHERE length(s) >= 31)""",
)
def qgram_keys_documents(spark, sf_dir):
    return apps.qgrams(_load(spark, sf_dir, "documents").select("doc_id", "text"), "text", 31)


_acgt = "list_reduce(list_transform(string_split({w}, ''), lambda c: CAST(strpos('ACGT', c) - 1 AS BIGINT)), lambda a, b: a * 4 + b)"


@query(
    "qgram_keys_acgt",
    f"""SELECT item_id, CAST(pos AS INTEGER) AS pos, least({_acgt.format(w='w')}, {_acgt.format(w="reverse(translate(w, 'ACGT', 'TGCA'))")}) AS gram
FROM (SELECT item_id, pos, upper(substr(text, pos, 3)) AS w FROM (SELECT item_id, text, unnest(range(1, length(text) - 1)) AS pos FROM benchmark)) WHERE regexp_full_match(w, '[ACGT][ACGT][ACGT]')""",
)
def qgram_keys_acgt(spark, sf_dir):
    """Canonical 3-grams of the letters A, C, G, T (the items are ASCII text); windows with any other sign are skipped."""
    return apps.qgrams(_load(spark, sf_dir, "benchmark").select("item_id", "text"), "text", 3, "acgt", canonical=True)


def _footprints(bits: str):
    def run(spark, sf_dir):
        keys = build.keys_of(_load(spark, sf_dir, "part"), "p_partkey")
        return build.candidate_rows(keys, FilterSpec("linelocal", 10, 1, 1, 1, bits)).drop("choice", "shard", "line")

    return run


_one = FilterSpec("linelocal", 10, 1, 1, 1)
_w = ", ".join(R.SIGNED.format(v=f"max(CASE WHEN w = {i} THEN v ELSE CAST(0 AS UBIGINT) END)") + f" AS m{i}" for i in range(8))
for _bits in ("random", "distinct", "sliced"):
    _h = R.hashed("part", "p_partkey", FilterSpec("linelocal", 10, 1, 1, 1, _bits))
    query(
        f"footprint_{_bits}",
        f"WITH {_h} SELECT key64, {_w} FROM (SELECT key64, a >> 6 AS w, bit_or(CAST(power(2, a & 63) AS UBIGINT)) AS v FROM (SELECT key64, unnest(addresses) AS a FROM h) GROUP BY ALL) GROUP BY key64",
    )(_footprints(_bits))


# --- builds and lookups ------------------------------------------------------------------------
def _order_lines(spark, sf_dir, spec):
    return build.build(build.keys_of(_load(spark, sf_dir, "orders"), "o_orderkey"), spec)


def _even_orders(spark, sf_dir):
    return build.keys_of(_load(spark, sf_dir, "orders").where("o_orderkey % 2 = 0"), "o_orderkey")


for _kind, _spec in UNION.items():
    query(f"{_kind}_build", R.union_lines(ORDERS, "o_orderkey", _spec))(lambda spark, sf_dir, spec=_spec: _order_lines(spark, sf_dir, spec))

    def _probe_union(spark, sf_dir, spec=_spec):
        lines = build.build(_even_orders(spark, sf_dir), spec)
        return probe.probe(_load(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", lines, spec)

    query(f"{_kind}_probe", R.union_probe("(SELECT o_orderkey FROM orders WHERE o_orderkey % 2 = 0)", "o_orderkey", "lineitem", "l_orderkey", _spec))(_probe_union)

_apart = FilterSpec("linelocal", 10, 1, 4, 160, "distinct")
query("linelocal_distinct_build", R.union_lines(ORDERS, "o_orderkey", _apart))(lambda spark, sf_dir: _order_lines(spark, sf_dir, _apart))


def _customers(spark, sf_dir):
    return build.keys_of(_load(spark, sf_dir, "customer"), "c_custkey")


for _c, _spec in SMALL.items():
    query(f"choice{_c}_build", R.choice_lines("customer", "c_custkey", _spec))(lambda spark, sf_dir, spec=_spec: build.build(_customers(spark, sf_dir), spec))
    if _c <= 4:

        def _probe_choice(spark, sf_dir, spec=_spec, plan="join"):
            return probe.probe(_load(spark, sf_dir, "orders").select("o_custkey"), "o_custkey", build.build(_customers(spark, sf_dir).where("key64 % 3 = 0"), spec), spec, plan)

        _third = "(SELECT c_custkey FROM customer WHERE c_custkey % 3 = 0)"
        query(f"choice{_c}_probe", R.choice_probe(_third, "c_custkey", "orders", "o_custkey", _spec))(_probe_choice)
        if _c == 2:
            query("probe_by_array", ORACLES["choice2_probe"])(lambda spark, sf_dir: _probe_choice(spark, sf_dir, SMALL[2], "array"))
            query("probe_by_shard", ORACLES["choice2_probe"])(lambda spark, sf_dir: _probe_choice(spark, sf_dir, SMALL[2], "shard"))
            query("probe_by_expression", ORACLES["choice2_probe"])(lambda spark, sf_dir: _probe_choice(spark, sf_dir, SMALL[2], "expression"))

_apart2 = FilterSpec("choice", 10, 2, 6, 8, "distinct")
query("choice2_distinct_build", R.choice_lines("customer", "c_custkey", _apart2))(lambda spark, sf_dir: build.build(_customers(spark, sf_dir), _apart2))
query("choice_skip_count", R.choice_skips("customer", "c_custkey", SMALL[2]))(lambda spark, sf_dir: build.build_choice(_customers(spark, sf_dir), SMALL[2], report="shards"))
query("choice_epochs", R.choice_epochs("customer", "c_custkey", SMALL[2], 4, build.EPOCH))(lambda spark, sf_dir: build.build_epochs(_customers(spark, sf_dir), SMALL[2], 4))


query("choice_fold", R.choice_lines("customer", "c_custkey", SMALL[2]))(lambda spark, sf_dir: build.build_fold(_customers(spark, sf_dir), SMALL[2]))
query("choice_touches", R.choice_touches(_third, "c_custkey", "orders", "o_custkey", SMALL[2]))(
    lambda spark, sf_dir: measure.touches(_load(spark, sf_dir, "orders").select("o_custkey"), "o_custkey", build.build(_customers(spark, sf_dir).where("key64 % 3 = 0"), SMALL[2]), SMALL[2])
)


# String keys: filters of urls, asked by every plan; k = 40, so that the answers are those of the exact set.
def _url_filter(spark, sf_dir):
    urls = build.keys_of(_load(spark, sf_dir, "pages").where("page_id % 2 = 0"), "url")
    spec = plan_spec(max(1, urls.agg(F.count_distinct("key64")).first()[0]), 40, shards=3)
    return build.build(urls, spec), spec


@query("string_build", "SELECT count(DISTINCT url) AS urls, CAST(0 AS BIGINT) AS missed FROM pages WHERE page_id % 2 = 0")
def string_build(spark, sf_dir):
    lines, spec = _url_filter(spark, sf_dir)
    asked = probe.probe(_load(spark, sf_dir, "pages").where("page_id % 2 = 0").select("url"), "url", lines, spec)
    return asked.agg(F.count_distinct("url").alias("urls"), F.count_if(~F.col("maybe")).alias("missed"))


for _plan in probe.PLANS:

    def _probe_urls(spark, sf_dir, plan=_plan):
        return probe.probe(_load(spark, sf_dir, "pages").select("page_id", "url"), "url", *_url_filter(spark, sf_dir), plan)

    query(f"string_probe_{_plan}", "SELECT page_id, url, CASE WHEN url IS NULL THEN NULL ELSE url IN (SELECT url FROM pages WHERE page_id % 2 = 0 AND url IS NOT NULL) END AS maybe FROM pages")(_probe_urls)


@query("string_prefilter", "SELECT page_id, url FROM pages WHERE url IN (SELECT url FROM pages WHERE page_id % 2 = 0)")
def string_prefilter(spark, sf_dir):
    pages = _load(spark, sf_dir, "pages").select("page_id", "url")
    return apps.prefilter(pages, pages.where("page_id % 2 = 0").select("url"), "url", "url", "semi")


@query("choice_incremental", R.choice_lines("customer", "c_custkey", SMALL[2]))
def choice_incremental(spark, sf_dir):
    keys = _customers(spark, sf_dir)
    cut = keys.agg(F.percentile_approx("key64", 0.5)).first()[0] or 0
    first = build.build(keys.where(F.col("key64") <= cut), SMALL[2])
    return build.insert_more(first, keys.where(F.col("key64") > cut), SMALL[2])


@query("merge_or", R.union_lines(ORDERS, "o_orderkey", UNION["linelocal"]))
def merge_or(spark, sf_dir):
    keys = build.keys_of(_load(spark, sf_dir, "orders"), "o_orderkey")
    halves = [build.build(keys.where(F.col("key64") % 2 == i), UNION["linelocal"]) for i in (0, 1)]
    return build.merge_or(*halves)


# --- costs -------------------------------------------------------------------------------------
_priced = "SELECT key64, shard, l1, unnest(addresses) AS a FROM"
_even, _odd = (R.hashed(f"(SELECT o_orderkey FROM orders WHERE o_orderkey % 2 = {i})", "o_orderkey", UNION["linelocal"]).removeprefix("h AS ") for i in (0, 1))


@query(
    "cost_table",
    f"""WITH seen AS (SELECT DISTINCT shard, l1, a FROM ({_priced} {_even})), load AS (SELECT shard, l1, count(*) AS ones FROM seen GROUP BY ALL),
own AS (SELECT DISTINCT key64, shard, l1, a FROM ({_priced} {_odd})),
added AS (SELECT key64, shard, l1, count(*) - count(s.a) AS more FROM own LEFT JOIN seen s USING (shard, l1, a) GROUP BY ALL)
SELECT CAST(j AS INTEGER) AS j, CAST(more AS INTEGER) AS a, CAST(round({1 << 32} * pow({ExpCost().beta!r}, j / 128.0::DOUBLE)) AS BIGINT) + CAST(round({1 << 32} * more / 10::DOUBLE) AS BIGINT) AS cost_q, keys
FROM (SELECT coalesce(ones, 0) + more AS j, more, count(*) AS keys FROM added LEFT JOIN load USING (shard, l1) GROUP BY ALL)""",
)
def cost_table(spark, sf_dir):
    """What the odd order keys would cost in their lines of the even keys' filter: ones then and ones added, their price, and how many keys have it."""
    spec = UNION["linelocal"]
    lines = build.build(_even_orders(spark, sf_dir), spec).withColumnRenamed("ones", "before")
    odd = build.keys_of(_load(spark, sf_dir, "orders").where("o_orderkey % 2 = 1"), "o_orderkey")
    tried = build.candidate_rows(build.distinct_keys(odd), spec).join(F.broadcast(lines), ["shard", "line"], "left")
    after = F.lit(0)
    for i, w in enumerate(build.W):
        after = after + F.bit_count(F.coalesce(w, F.lit(0).cast("long")).bitwiseOR(F.col(f"m{i}")))
    met = tried.select(after.cast("int").alias("j"), (after - F.coalesce("before", F.lit(0))).cast("int").alias("a")).groupBy("j", "a").agg(F.count("*").alias("keys"))
    total, added = (F.array(*map(F.lit, t.tolist())) for t in ExpCost().tables(spec.k))
    return met.select("j", "a", (F.get(total, F.col("j")) + F.get(added, F.col("a"))).alias("cost_q"), "keys")


FORMS = {
    "exponential": ExpCost(), "exponential, knee 96": ExpCost(knee=96.0), "exponential, knee 192": ExpCost(knee=192.0), "exponential, weight 0.5": ExpCost(weight=0.5), "exponential, weight 2": ExpCost(weight=2.0),
    "total": TotalCost(), "added": AddedCost(), "linear": LinearCost(), "linear, weight 0.2": LinearCost(weight=0.2), "power": PowerCost(), "power 4": PowerCost(power=4.0),
}
BETAS = (1.1, 1.25, 1.5, ExpCost().beta, 2.0, 2.5, 3.0, 4.0)


@query("cost_forms")
def cost_forms(spark, sf_dir):
    """Cost functions, with their free parameters, against each other: two and three choices, both footprints."""
    return measure.grid(packed_pairs(spark, sf_dir), [Cell("choice", c, k, b, cost=f, label=name) for name, f in FORMS.items() for c in (2, 3) for k in (10, 14) for b in ("random", "distinct")])


@query("cost_beta_sweep")
def cost_beta_sweep(spark, sf_dir):
    return measure.grid(packed_pairs(spark, sf_dir), [Cell("choice", c, k, cost=ExpCost(beta=beta), label=f"{beta:.4f}") for beta in BETAS for c in (2, 3) for k in (10, 14, 17)]).withColumn("beta", F.col("label").cast("double"))


# --- measures ----------------------------------------------------------------------------------
def _lines_sql(spec: FilterSpec) -> str:
    return f"t AS ({R.union_lines(ORDERS, 'o_orderkey', spec)}), e AS (SELECT ones FROM t UNION ALL SELECT 0 FROM range({spec.shards * spec.lines} - (SELECT count(*) FROM t)))"


_ll = UNION["linelocal"]
query("load_histogram", f"WITH {_lines_sql(_ll)} SELECT ones, count(*) AS lines FROM e GROUP BY ones")(lambda spark, sf_dir: measure.histogram(_order_lines(spark, sf_dir, _ll), _ll).groupBy("ones").agg(F.sum("lines").alias("lines")))
query("load_summary", f"WITH {_lines_sql(_ll)} SELECT round(avg(ones), 9) AS mean_ones, round(stddev_pop(ones), 6) AS sd_ones, max(ones) AS max_ones, round(avg(ones) / 512, 9) AS load FROM e")(
    lambda spark, sf_dir: measure.load_summary(_order_lines(spark, sf_dir, _ll), _ll)
)
query("fpr_from_loads", f"WITH {_lines_sql(_ll)} SELECT 'linelocal' AS kind, 10 AS k, round(log2(avg(pow(ones / 512.0::DOUBLE, 10))), 9) AS log2_fpr FROM e")(lambda spark, sf_dir: measure.fpr_from_loads(_order_lines(spark, sf_dir, _ll), _ll))
query(
    "shard_balance",
    f"SELECT CAST(shard AS INTEGER) AS shard, count(*) AS keys FROM (SELECT {hashing.sql_hash('x', hashing.constant(1, K.SHARD), 8)} AS shard FROM (SELECT {hashing.sql_premix('l_orderkey')} AS x FROM lineitem)) GROUP BY shard",
)(lambda spark, sf_dir: measure.shard_balance(build.keys_of(_load(spark, sf_dir, "lineitem"), "l_orderkey"), FilterSpec(shards=8)))


@query("false_negatives_zero", "SELECT kind, CAST(0 AS BIGINT) AS misses FROM (VALUES ('classic'), ('linelocal'), ('choice2'), ('choice3')) t(kind)")
def false_negatives_zero(spark, sf_dir):
    keys, out = build.keys_of(_load(spark, sf_dir, "orders"), "o_orderkey"), []
    for name, spec in measure.four_kinds(keys.count(), 10).items():
        out.append(probe.probe(keys, "key64", build.build(keys, spec), spec).agg(F.count_if(~F.col("maybe")).alias("misses")).select(F.lit(name).alias("kind"), "misses"))
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3])


@query("fpr_empirical")
def fpr_empirical(spark, sf_dir):
    """Measured on odd order keys after inserting the even ones, all kinds at equal size."""
    keys, out = _even_orders(spark, sf_dir), []
    absent = _load(spark, sf_dir, "orders").where("o_orderkey % 2 = 1").select("o_orderkey")
    for name, spec in measure.four_kinds(keys.count(), 7).items():
        out.append(measure.fpr(build.build(keys, spec), spec, absent, "o_orderkey").select(F.lit(name).alias("kind"), "probes", "false_pos", "fpr", "log2_fpr"))
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3])


def _absent_pairs(spark, sf_dir):
    """As many keys as there are, none of them among those inserted (the supplier lies beyond all)."""
    return packed_pairs(spark, sf_dir).select((F.col("key64") + F.lit(1 << 20)).alias("key64")).distinct()


@query("fpr_fixed_size")
def fpr_fixed_size(spark, sf_dir):
    """FPR against relative size: four filters, two footprints, from the loads and by asking as many absent keys."""
    cells = [Cell(kind, c, k, b, rel) for kind, c in KINDS for b in ("random", "distinct") for k in KS for rel in SIZES if not (kind == "classic" and b == "distinct")]
    return measure.grid(packed_pairs(spark, sf_dir), cells, _absent_pairs(spark, sf_dir))


_free = [(kind, k, rel) for kind in ("classic", "linelocal") for k in (4, 10, 17) for rel in (0.8, 0.9, 1.0, 1.1, 1.2, 1.3)]


@query("fpr_order_free", R.order_free_grid("SELECT (l_partkey << 32) + l_suppkey AS key64 FROM lineitem", _free, measure.SHARD_KEYS))
def fpr_order_free(spark, sf_dir):
    """The same for the filters whose lines do not depend on the order of insertion, which SQL can build too."""
    return measure.grid(packed_pairs(spark, sf_dir), [Cell(kind, 1, k, "random", rel) for kind, k, rel in _free]).select("kind", "k", "rel_size", "n", "log2_fpr", "mean_ones", "max_ones")


@query("overload_curve")
def overload_curve(spark, sf_dir):
    """FPR over 2^-k when gamma times the planned keys are inserted, and its growth per further percent (on the log2 scale)."""
    cells = [Cell(kind, c, k, b, gamma=g) for kind, c in KINDS for b in ("random", "distinct") for k in (10, 14) for g in GAMMAS if not (kind == "classic" and b == "distinct")]
    out = measure.grid(packed_pairs(spark, sf_dir), cells).withColumn("penalty", F.col("fpr") * F.pow(F.lit(2.0), F.col("k").cast("double")))
    along = Window.partitionBy("kind", "choices", "k", "bits").orderBy("gamma")
    slope = (F.col("log2_fpr") - F.lag("log2_fpr").over(along)) / (100 * (F.col("gamma") - F.lag("gamma").over(along)))
    return out.withColumn("log2_per_percent", slope)


@query(
    "overload_model",
    """WITH y AS (SELECT CAST(year(o_orderdate) AS INTEGER) AS year, count(*) AS n FROM orders WHERE o_orderdate IS NOT NULL GROUP BY 1),
g AS (SELECT year, CAST(sum(n) OVER (ORDER BY year) AS BIGINT) AS capacity, CAST(sum(n) OVER () AS DOUBLE) / CAST(sum(n) OVER (ORDER BY year) AS DOUBLE) AS gamma FROM y)
SELECT year, capacity, gamma, k, round(pow(1 - pow(2.0::DOUBLE, -gamma), k) * pow(2.0::DOUBLE, k), 6) AS penalty FROM g, (VALUES (4), (10), (14)) b(k)""",
)
def overload_model(spark, sf_dir):
    """A filter sized for the orders up to a year's end, filled with all there are: what its FPR is over 2^-k by the model."""
    years = _load(spark, sf_dir, "orders").where("o_orderdate is not null").groupBy(F.year("o_orderdate").alias("year")).agg(F.count("*").alias("n"))
    so_far = F.sum("n").over(Window.orderBy("year"))  # a row a year
    gamma = F.sum("n").over(Window.partitionBy()).cast("double") / so_far.cast("double")
    return measure.overload_rows(years.select("year", so_far.alias("capacity"), gamma.alias("gamma")), [4, 10, 14])


@query("required_size")
def required_size(spark, sf_dir):
    """Relative size and overhead factor for an FPR of 2^-k: all kinds and footprints."""
    cells = [Cell(kind, c, k, b) for kind, c in KINDS for b in ("random", "distinct") for k in (4, 10, 14, 17, 20) if not (kind == "classic" and b == "distinct")]
    return measure.required_sizes(packed_pairs(spark, sf_dir), cells)


@query("choices_ablation")
def choices_ablation(spark, sf_dir):
    return measure.grid(packed_pairs(spark, sf_dir), [Cell("choice", c, k) for c in (1, 2, 3, 4) for k in KS])


@query("batch_ablation")
def batch_ablation(spark, sf_dir):
    """Insertion in R batches that are priced at their start (0: key by key)."""
    return measure.grid(packed_pairs(spark, sf_dir), [Cell("choice", c, 14, epochs=r) for c in (2, 3) for r in (0, 1, 4, 8, 16, 32, 64, 256)])


@query(
    "max_line_load",
    f"""WITH {_lines_sql(_ll)}, m AS (SELECT k, c AS choices, CAST(floor(512 * pow(pow(2.0::DOUBLE, -k) / c, 1.0::DOUBLE / k) + 1e-9) AS INTEGER) AS max_ones FROM (SELECT CAST(range AS INTEGER) AS k FROM range(1, 31)), (SELECT CAST(range AS INTEGER) AS c FROM range(1, 5)))
SELECT k, choices, max_ones, count(*) AS lines, count(*) FILTER (WHERE ones > max_ones) AS lines_over FROM m, e GROUP BY ALL""",
)
def max_line_load(spark, sf_dir):
    """Most ones a line may have for k bits and c choices, and how many lines of the orders' filter have more."""
    limits = spark.createDataFrame([(k, c, models.max_line_load(k, c)) for k in range(1, 31) for c in range(1, 5)], "k int, choices int, max_ones int")
    loads = measure.histogram(_order_lines(spark, sf_dir, _ll), _ll)
    over = F.sum(F.when(F.col("ones") > F.col("max_ones"), F.col("lines")).otherwise(0))
    return loads.crossJoin(F.broadcast(limits)).groupBy("k", "choices", "max_ones").agg(F.sum("lines").alias("lines"), over.alias("lines_over"))


_deep = FilterSpec("linelocal", 30, 1, 1, 1)


@query(
    "collision_curve",
    f"""WITH {R.hashed('orders', 'o_orderkey', _deep)},
m AS (SELECT k, round(1 - exp(sum(ln(1 - i / 512.0::DOUBLE))), 9) AS share FROM (SELECT CAST(range AS INTEGER) AS k FROM range(1, 31)) a, (SELECT range AS i FROM range(0, 30)) b WHERE i < k GROUP BY k)
SELECT k, share, count(*) AS keys, count(*) FILTER (WHERE len(list_distinct(list_slice(addresses, 1, k))) < k) AS collided FROM m, h GROUP BY ALL""",
)
def collision_curve(spark, sf_dir):
    """Chance that k addresses of a line are not all different, and the order keys whose first k addresses are not."""
    model = spark.createDataFrame([(k, round(models.collision(k), 9)) for k in range(1, 31)], "k int, share double")
    keys = build.distinct_keys(build.keys_of(_load(spark, sf_dir, "orders"), "o_orderkey"))
    return measure.collisions(keys, _deep).join(F.broadcast(model), "k").select("k", "share", "keys", "collided")


@query(
    "collision_observed",
    f"WITH {R.hashed('part', 'p_partkey', _one)} SELECT 10 AS k, round(avg(CASE WHEN len(list_distinct(addresses)) < 10 THEN 1.0 ELSE 0.0 END), 9) AS share FROM h",
)
def collision_observed(spark, sf_dir):
    rows = _footprints("random")(spark, sf_dir)
    ones = F.bit_count("m0")
    for i in range(1, 8):
        ones = ones + F.bit_count(f"m{i}")
    return rows.agg(F.round(F.avg((ones < 10).cast("double")), 9).alias("share")).select(F.lit(10).alias("k"), "share")


@query(
    "filter_overview",
    """WITH k AS (SELECT CAST(range AS INTEGER) AS k FROM range(1, 31)),
t AS (SELECT * FROM (VALUES
  ('classic', 1 / ln(2.0::DOUBLE), 0.0::DOUBLE, 1, 1.443::DOUBLE, -1, -1, -1, -1, true), ('linelocal', NULL, NULL, NULL, 1.565, 1, 1, 1, 1, true), ('choice2', NULL, NULL, NULL, 1.456, 2, 2, 1, 2, true),
  ('cuckoo', 1.053, 3.0, 2, 2.73, 1, NULL, 2, 2, false), ('quotient', 1.053, 2.125, 2, 2.55, NULL, NULL, NULL, NULL, false), ('vector_quotient', 1.0753, 2.914, 2, 2.77, 2, 2, 2, 2, false)
) t(filter, f, s, times, c10, il, ih, ll, lh, smooth))
SELECT *, ceil(best * keys * k / 8) AS best_bytes, ceil(worst * keys * k / 8) AS worst_bytes FROM (SELECT filter, k, round(f * (1 + s / k), 11) AS best, round(times * (f * (1 + s / k)), 11) AS worst, CASE k WHEN 10 THEN c10 END AS published_c10,
  CAST(CASE il WHEN -1 THEN k ELSE il END AS DOUBLE) AS insert_low, CAST(CASE ih WHEN -1 THEN k ELSE ih END AS DOUBLE) AS insert_high,
  CAST(CASE ll WHEN -1 THEN k ELSE ll END AS DOUBLE) AS lookup_low, CAST(CASE lh WHEN -1 THEN k ELSE lh END AS DOUBLE) AS lookup_high, smooth FROM t, k), """
    + _sets_sql,
)
def filter_overview(spark, sf_dir):
    """The filters side by side, and their bytes for the customers of each order priority."""
    out = _key_sets(spark, sf_dir).crossJoin(F.broadcast(models.overview(spark)))
    return out.withColumns({f"{end}_bytes": F.ceil(F.col(end) * F.col("keys") * F.col("k") / 8).cast("double") for end in ("best", "worst")})


@query("overview_measured")
def overview_measured(spark, sf_dir):
    """Overhead factors at k = 10 beside the published ones: by building (classic, line-local, two choices) and by the model (line-local)."""
    built = measure.required_sizes(packed_pairs(spark, sf_dir), [Cell(kind, c, 10) for kind, c in KINDS[:3]], steps=11)
    name = F.when(F.col("kind") == "choice", F.lit("choice2")).otherwise(F.col("kind"))
    known = F.coalesce(*[F.when(name == k, F.lit(v)) for k, v in models.AT_TEN.items()])
    model = F.when(name == "linelocal", F.lit(models.required_linelocal(10) / math.log(2))).when(name == "classic", F.lit(1 / math.log(2)))
    return built.select(name.alias("filter"), "k", "overhead", model.alias("model"), known.alias("published"))


@query(
    "classic_model",
    f"""SELECT o_orderpriority, k, n, m, round(load, 9) AS load, round(log2(pow(load, k)), 9) AS log2_fpr FROM (
  SELECT o_orderpriority, k, n, m, 1 - pow(1 - 1.0::DOUBLE / m, n * k) AS load FROM (SELECT o_orderpriority, k, keys AS n, CAST(round(keys * k / {_LN2}::DOUBLE) AS BIGINT) AS m FROM {_sets_sql}, (VALUES (4), (7), (10), (14), (17), (20)) t(k)))""",
)
def classic_model(spark, sf_dir):
    """Load and FPR of a classic filter, by the model, for the customers of each order priority."""
    sets = _key_sets(spark, sf_dir).withColumn("k", F.explode(F.array(*map(F.lit, KS)))).withColumnRenamed("keys", "n")
    sized = sets.withColumn("m", F.round(F.col("n") * F.col("k") / F.lit(math.log(2))).cast("long"))
    load = 1 - F.pow(1 - F.lit(1.0) / F.col("m"), (F.col("n") * F.col("k")).cast("double"))
    told = sized.withColumn("load", load)
    return told.select("o_orderpriority", "k", "n", "m", F.round("load", 9).alias("load"), F.round(F.log2(F.pow("load", F.col("k").cast("double"))), 9).alias("log2_fpr"))


@query("linelocal_model")
def linelocal_model(spark, sf_dir):
    """FPR of a line-local filter of the order keys at the classic size: by the keys that fall to each line, and by their Poisson share;
    and the relative size for 2^-k."""
    keys = build.distinct_keys(build.keys_of(_load(spark, sf_dir, "orders"), "o_orderkey"))
    rows = []
    for k, (n, lines, held) in measure.keys_per_line(keys, KS).items():
        seen = round(math.log2(models.linelocal_fpr_of(k, held)), 6) if n else None
        rows.append((k, n, lines, seen, round(math.log2(models.linelocal_fpr(k, 1.0)), 6), round(models.required_linelocal(k), 3)))
    return spark.createDataFrame(rows, "k int, keys long, lines long, log2_fpr double, model_log2_fpr double, rel_size double")


def _touched(spark, sf_dir, name: str):
    keys = _even_orders(spark, sf_dir)
    spec = measure.four_kinds(keys.count(), 10)[name]
    return measure.touches(_load(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", build.build(keys, spec), spec)


def _read(spark, sf_dir, name: str):
    keys = _even_orders(spark, sf_dir)
    spec = measure.four_kinds(keys.count(), 10)[name]
    return measure.bits_examined(_load(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", build.build(keys, spec), spec)


@query("touches")
def touches(spark, sf_dir):
    parts = [_touched(spark, sf_dir, n).withColumn("kind", F.lit(n)) for n in ("linelocal", "choice2", "choice3")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


query("bits_examined", R.classic_bits_examined("(SELECT o_orderkey FROM orders WHERE o_orderkey % 2 = 0)", "o_orderkey", "lineitem", "l_orderkey", 10, 4))(
    lambda spark, sf_dir: _read(spark, sf_dir, "classic")
)


@query("bits_examined_lines")
def bits_examined_lines(spark, sf_dir):
    parts = [_read(spark, sf_dir, n).withColumn("kind", F.lit(n)) for n in ("linelocal", "choice2", "choice3")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


# --- applications ------------------------------------------------------------------------------
SPECIES = ("es", "de", "en")  # small, medium, large
SPACE = {"classic": 1.0, "linelocal": 1.17, "choice2": 1.01, "choice3": 0.99}  # sizes that give 2^-14


def _species_cells() -> list[Cell]:
    return [Cell(name.rstrip("23"), int(name[-1]) if name[-1].isdigit() else 1, 14, rel_size=size, label=name) for name, size in SPACE.items()]


def _species_grams(spark, sf_dir):
    docs = _load(spark, sf_dir, "documents").where(F.col("lang").isin(*SPECIES))
    return apps.gram_sets(_texts(spark, docs.select("lang", "text")), "text", "lang", 31)


@query("qgram_build_species")
def qgram_build_species(spark, sf_dir):
    """31-gram sets of the three "species" in four filters, each at its own size: space, its ratio to the classic filter's, FPR from the loads."""
    out = measure.grid(_species_grams(spark, sf_dir), _species_cells(), group="lang", distinct=True, shard_keys=1 << 18)
    whole = F.max(F.when(F.col("label") == "classic", F.col("bytes"))).over(Window.partitionBy("lang"))
    return out.select("lang", F.col("label").alias("kind"), F.col("n").alias("keys"), "bytes", F.round(F.col("bytes") / whole, 6).alias("space_ratio"), "log2_fpr", "mean_ones", "max_ones")


@query("qgram_sets", f"""WITH t AS (SELECT lang, translate(lower(regexp_replace(text, '[^A-Za-z]', '', 'g')), '{apps.LETTERS}', '{apps.FOUR}') AS s FROM documents WHERE lang IN ('es', 'de', 'en'))
SELECT lang, count(DISTINCT w) AS grams FROM (SELECT lang, substr(s, pos, 31) AS w FROM (SELECT lang, s, unnest(range(1, length(s) - 29)) AS pos FROM t WHERE length(s) >= 31)) GROUP BY lang""")
def qgram_sets(spark, sf_dir):
    return _species_grams(spark, sf_dir).groupBy("lang").agg(F.count("*").alias("grams"))


@query("qgram_build_times")
def qgram_build_times(spark, sf_dir):
    """Seconds of each build of each set (least of 3 runs, timed in the shards, ``measure.timed``), and the ratio to the line-local one."""
    grams = _species_grams(spark, sf_dir).persist()
    counts = {r["lang"]: r["n"] for r in grams.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    facts, parts = [], []
    for lang in SPECIES:
        n = max(1, counts.get(lang, 0))
        specs = [c.spec(n, max(8, -(-n // (1 << 20)))) for c in _species_cells()]
        runs = measure.timed(grams.where(F.col("lang") == lang).select("key64", "ord"), [(name, spec, False) for name, spec in zip(SPACE, specs)])
        parts.append(runs.groupBy("filter").agg(F.min("seconds").alias("seconds")).withColumn("lang", F.lit(lang)))
        facts += [(lang, i, name, n, spec.bytes) for i, (name, spec) in enumerate(zip(SPACE, specs))]
    facts = spark.createDataFrame(facts, "lang string, filter int, kind string, keys long, bytes long")
    out = facts.join(parts[0].unionByName(parts[1]).unionByName(parts[2]), ["lang", "filter"], "left")
    local = F.max(F.when(F.col("kind") == "linelocal", F.col("seconds"))).over(Window.partitionBy("lang"))
    return out.select("lang", "kind", "keys", "seconds", "bytes", (F.col("keys") / F.col("seconds") / 1e6).alias("mkeys_per_s"), (F.col("seconds") / local).alias("over_linelocal"))


ORIGIN_FOLDS = 2


def _origins(spark, sf_dir):
    """All documents and conversation turns as reads; en documents are origin a, de documents b."""
    docs = _load(spark, sf_dir, "documents").select("doc_id", "text", "lang").withColumn("fold", apps.fold_of("doc_id", ORIGIN_FOLDS))
    origin = F.when(F.col("lang") == "en", "a").when(F.col("lang") == "de", "b")
    docs = _texts(spark, docs.select((-F.col("doc_id") - 1).alias("read_id"), "fold", "text", origin.alias("origin")))
    reads = _load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("read_id"), F.lit(None).cast("int").alias("fold"), "text", F.lit(None).cast("string").alias("origin"))
    return reads.unionByName(docs)


@query("two_origin_sort")
def two_origin_sort(spark, sf_dir):
    """All documents and conversations as reads, en and de as origins: a document is asked of the origins' other fold, a conversation of both."""
    return apps.two_origins(_origins(spark, sf_dir), folds=ORIGIN_FOLDS)


@query("two_origin_exact")
def two_origin_exact(spark, sf_dir):
    """The same reads sorted by the sets themselves."""
    return apps.two_origins_exact(_origins(spark, sf_dir), folds=ORIGIN_FOLDS)


@query("two_origin_confusion")
def two_origin_confusion(spark, sf_dir):
    """Reads by class with the exact sets and with the filters, and the space of either: 8 bytes a gram against the filters' lines."""
    return apps.two_origins_confusion(_origins(spark, sf_dir), folds=ORIGIN_FOLDS)


_some = "o_orderpriority = (SELECT min(o_orderpriority) FROM orders)"


def _priority(spark, sf_dir):
    orders = _load(spark, sf_dir, "orders")
    low = orders.agg(F.min("o_orderpriority")).first()[0]
    return orders.where(F.col("o_orderpriority") == low).select("o_orderkey", "o_custkey")


@query("prefilter_join", f"SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE {_some}")
def prefilter_join(spark, sf_dir):
    items = _load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber")
    return apps.prefilter(items, _priority(spark, sf_dir), "l_orderkey", "o_orderkey").select("l_orderkey", "l_linenumber", "o_custkey")


@query("prefilter_semi", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE {_some})")
def prefilter_semi(spark, sf_dir):
    return apps.prefilter(_load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber"), _priority(spark, sf_dir), "l_orderkey", "o_orderkey", "semi")


@query("prefilter_anti", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders WHERE {_some})")
def prefilter_anti(spark, sf_dir):
    return apps.prefilter(_load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber"), _priority(spark, sf_dir), "l_orderkey", "o_orderkey", "anti")


@query("prefilter_report")
def prefilter_report(spark, sf_dir):
    """What the filter lets through, and how much of it the join then removes, at k from 2 to 14."""
    items, parts = _load(spark, sf_dir, "lineitem").select("l_orderkey"), None
    for k in (2, 6, 10, 14):
        part = apps.prefilter_report(items, _priority(spark, sf_dir), "l_orderkey", "o_orderkey", k).withColumn("k", F.lit(k))
        parts = part if parts is None else parts.unionByName(part)
    return parts


@query(
    "contamination_score",
    f"""WITH g AS (SELECT 'd' AS side, doc_id AS id, translate(lower(regexp_replace(coalesce(text, ''), '[^A-Za-z]', '', 'g')), '{apps.LETTERS}', '{apps.FOUR}') AS s FROM documents
UNION ALL SELECT 'b', item_id, translate(lower(regexp_replace(coalesce(text, ''), '[^A-Za-z]', '', 'g')), '{apps.LETTERS}', '{apps.FOUR}') FROM benchmark),
w AS (SELECT side, id, substr(s, pos, 31) AS w FROM (SELECT side, id, s, unnest(range(1, length(s) - 29)) AS pos FROM g WHERE length(s) >= 31)),
b AS (SELECT DISTINCT w FROM w WHERE side = 'b'),
c AS (SELECT id AS doc_id, count(*) AS grams, count(b.w) AS hits FROM w LEFT JOIN b USING (w) WHERE side = 'd' GROUP BY id)
SELECT d.doc_id, coalesce(c.grams, 0) AS grams, coalesce(c.hits, 0) AS hits, round(coalesce(c.hits / c.grams, 0), 9) AS share, CAST(quality AS DOUBLE) AS quality FROM documents d LEFT JOIN c USING (doc_id) LEFT JOIN labels USING (doc_id)""",
)
def contamination_score(spark, sf_dir):
    score = apps.contamination(_load(spark, sf_dir, "documents"), _load(spark, sf_dir, "benchmark"))
    return score.join(_load(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", "grams", "hits", "share", F.col("quality").cast("double").alias("quality"))


@query("unknown_count")
def unknown_count(spark, sf_dir):
    """Capacity estimated from a hundredth of the documents, all of them inserted: overload and its price."""
    docs = _load(spark, sf_dir, "documents").select("doc_id", "text")
    some = apps.qgrams(docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(100)) == 0), "text", 31)
    guess = 100 * (some.agg(F.approx_count_distinct("gram")).first()[0] or 1)
    keys = apps.gram_set(_texts(spark, docs.select("text")), "text", 31)
    spec = measure.four_kinds(guess, 10)["choice2"]
    fpr, report = measure.fpr_from_loads(build.build(keys, spec, distinct=True), spec), measure.overload_report(keys, spec, distinct=True)
    return report.join(fpr.select("log2_fpr"), how="cross").select("capacity", "inserted", "gamma", "log2_fpr", "penalty")  # a row each


SEEN_SHARD_LINES = 1 << 12


def seen_spec(users: int) -> FilterSpec:
    """Filter for so many users at k = 40: their loads, and with them the chance to lose a user (2^-40 each), do not grow with the table."""
    spec = plan_spec(users, 40, shard_lines=SEEN_SHARD_LINES)
    return spec if spec.shards >= 4 else plan_spec(users, 40, shards=4)


@query("events_first_seen", "SELECT user_id, min(ts) AS first_ts FROM events WHERE user_id IS NOT NULL GROUP BY user_id")
def events_first_seen(spark, sf_dir):
    users = _load(spark, sf_dir, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), "ts")
    kind = users.schema["ts"].dataType
    spec = seen_spec(users.select("user_id").distinct().count())
    return stream.first_seen(users, "user_id", "us", spec).select(F.col("key64").alias("user_id"), F.timestamp_micros("ord").cast(kind).alias("first_ts"))


_daily = FilterSpec("linelocal", 10, 1, 2, 16)


@query("events_window_filters", R.window_lines("events", "user_id", "ts", _daily))
def events_window_filters(spark, sf_dir):
    events = _load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream.window_filters(events, "user_id", "ts", _daily, "1 day")


@query("events_session_filters")
def events_session_filters(spark, sf_dir):
    """A filter of event types' ids per session of a user (pauses of 12 hours)."""
    events = _load(spark, sf_dir, "events")
    return stream.session_filters(events, "user_id", "event_id", "ts", _daily, "12 hours")


@query("rival_cuckoo")
def rival_cuckoo(spark, sf_dir):
    """A cuckoo table of the even order keys (12-bit marks), asked for all orders of lineitem."""
    keys = _even_orders(spark, sf_dir)
    n = keys.count()
    table = rivals.cuckoo_build(keys, n, 12, 4)
    return rivals.cuckoo_probe(_load(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", table, n, 12, 4)


@query("rival_platform_join", f"SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE {_some}")
def rival_platform_join(spark, sf_dir):
    """The plain join, for which Spark may plan its own runtime filter (``rivals.runtime_filters``)."""
    items = _load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber")
    orders = _priority(spark, sf_dir).hint("merge")
    return items.join(orders, items["l_orderkey"] == orders["o_orderkey"]).select("l_orderkey", "l_linenumber", "o_custkey")


@query("rival_exact", "SELECT l_orderkey, l_orderkey % 2 = 0 AS maybe FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders)")
def rival_exact(spark, sf_dir):
    return rivals.exact(_even_orders(spark, sf_dir), _load(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey")


@query("rival_fingerprints")
def rival_fingerprints(spark, sf_dir):
    return rivals.fingerprint_set(_even_orders(spark, sf_dir), _load(spark, sf_dir, "lineitem").select("l_orderkey"), "l_orderkey", 1 << 14, 10)


@query(
    "advise",
    f"""SELECT o_orderpriority, keys, k, memory_bound, smallest, kind, choices, CAST(ceil(keys * k / {_LN2}::DOUBLE / 8) AS BIGINT) AS bytes FROM {_sets_sql},
    (SELECT CAST(range AS INTEGER) AS k, memory_bound, smallest, CASE WHEN range <= 3 THEN 'classic' WHEN range <= 7 OR NOT memory_bound THEN 'linelocal' ELSE 'choice' END AS kind,
    CASE WHEN range <= 7 OR NOT memory_bound THEN 1 WHEN smallest THEN 3 ELSE 2 END AS choices FROM range(1, 21), (VALUES (true), (false)) m(memory_bound), (VALUES (true), (false)) s(smallest))""",
)
def advise_(spark, sf_dir):
    """The filter advised for the customers of each order priority, by target and by what counts, and its bytes at the classic size."""
    grid = [(k, m, s, *advise(k, m, s)) for k in range(1, 21) for m in (False, True) for s in (False, True)]
    advised = spark.createDataFrame(grid, "k int, memory_bound boolean, smallest boolean, kind string, choices int")
    return _key_sets(spark, sf_dir).crossJoin(F.broadcast(advised)).withColumn("bytes", F.ceil(F.col("keys") * F.col("k") / F.lit(math.log(2)) / 8))


def packed_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_partkey, l_suppkey) of lineitem as one key."""
    return build.keys_of(_load(spark, sf_dir, "lineitem"), F.shiftleft(F.col("l_partkey"), 32) + F.col("l_suppkey"))


def _kinds(n: int, k: int, shards: int, bits: str = "random") -> dict[str, FilterSpec]:
    return {f"{name} {bits}": spec for name, spec in measure.four_kinds(n, k, shards=shards, bits=bits).items() if not (bits == "distinct" and name == "classic")}


def _distinct_pairs(spark, sf_dir):
    # Few tasks: every timed job passes over them.
    keys = build.distinct_keys(packed_pairs(spark, sf_dir)).coalesce(4 * spark.sparkContext.defaultParallelism).persist()
    return keys, max(1, keys.count())


def _timed_kinds(n: int, k: int, shards: int, bits: str = "random", lookups: bool = True) -> list[measure.Timed]:
    return [(name, spec, lookups) for name, spec in _kinds(n, k, shards, bits).items()]


@query("throughput")
def throughput(spark, sf_dir):
    """Build, hit and miss lookups by all plans at k = 14 (mean of 3 runs): in the shards' processes (array), by whole jobs (the other plans)."""
    keys, n = _distinct_pairs(spark, sf_dir)
    jobs = measure.plan_throughput(keys, _kinds(n, 14, 8), tuple(p for p in probe.PLANS if p != "array"))
    return measure.throughput(keys, _timed_kinds(n, 14, 8)).unionByName(jobs)


@query("throughput_by_shards")
def throughput_by_shards(spark, sf_dir):
    """Insertion at k = 14 against the count of writers."""
    keys, n = _distinct_pairs(spark, sf_dir)
    return measure.throughput(keys, [f for shards in (1, 2, 4, 8) for f in _timed_kinds(n, 14, shards, lookups=False)])


@query("throughput_by_k")
def throughput_by_k(spark, sf_dir):
    """Insertion (both footprints) and lookups (random) against k."""
    keys, n = _distinct_pairs(spark, sf_dir)
    filters = [f for k in (2, 3, 6, 10, 14, 20) for bits in ("random", "distinct") for f in _timed_kinds(n, k, 8, bits, lookups=bits == "random")]
    return measure.throughput(keys, filters)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefilter_join(spark, sf_dir)
