"""The filter engine against its plain loop, its closed forms and DuckDB."""

import datetime
import decimal
import math
import random
import time
import tracemalloc
import zlib
from dataclasses import replace

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from memberset import apps, build, hashing, measure, models, probe, rivals, runs, sqlfuncs, store, stream
from memberset import kernels as K
from memberset.advise import advise
from memberset.cost import FORMS, AddedCost, ExpCost, TotalCost
from memberset.geometry import FilterSpec, plan_spec
from memberset.workloads import ORACLES, QUERIES, packed_pairs

KINDS = (("classic", 1), ("linelocal", 1), ("choice", 2), ("choice", 3))
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def keys(spark):
    return spark.range(3000).select(F.col("id").alias("key64"), F.col("id").alias("ord"))


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_multiplication_wraps(spark):
    values = [0, 1, -1, 2**63 - 1, -(2**63), 123456789012345678]
    df = spark.createDataFrame([(v,) for v in values], "x long")
    for a in (3, hashing.PREMIX, hashing.constant(5, 2)):
        got = [r[0] & hashing.MASK for r in df.select(hashing.mul64(F.col("x"), a)).collect()]
        assert got == [v * a & hashing.MASK for v in values]


@pytest.mark.parametrize("b", [1, 2, 512, 500, 1001])
def test_hash_twins_agree(spark, b):
    values = np.array([0, 1, -1, 2**63 - 1, -(2**63), 99999], np.int64)
    a = hashing.constant(1, 0)
    df = spark.createDataFrame([(int(v),) for v in values], "x long").select(hashing.mul64(F.col("x"), a).alias("y"))
    assert [r[0] for r in df.select(hashing.reduce_to(F.col("y"), b)).collect()] == hashing_np(values, a, b)


def hashing_np(values, a, b):
    return hashing.np_hash(values.view(np.uint64), a, b).tolist()


@pytest.mark.parametrize("choices", [1, 2, 3, 4])
@pytest.mark.parametrize("bits", ["random", "distinct", "sliced"])
def test_levels_equal_the_loop(choices, bits):
    spec = FilterSpec(k=9, choices=choices, lines=24, bits=bits)
    x = K.prepared(np.random.default_rng(choices).integers(-(2**62), 2**62, 900), spec)
    cand, mask = K.candidates(x, spec), K.masks(K.addresses(x, spec))
    one, two = np.zeros((24, 8), np.uint64), np.zeros((24, 8), np.uint64)
    assert K.insert_each(one, cand, mask, spec) == K.insert(two, cand, mask, spec, window=137)
    assert (one == two).all()


def test_distinct_footprints_have_k_bits():
    spec = FilterSpec("linelocal", 20, 1, 1, 1, "distinct")
    assert (K.ones(K.masks(K.addresses(K.prepared(np.arange(500), spec), spec))) == 20).all()


@pytest.mark.parametrize("kind,choices", KINDS)
def test_no_false_negatives_and_plans_agree(spark, keys, kind, choices):
    spec = plan_spec(3000, 8, kind, choices, shards=3)
    lines = build.build(keys, spec).cache()
    assert measure.false_negatives(lines, spec, keys, "key64") == 0
    asked = spark.range(2000, 6000).withColumnRenamed("id", "key64")
    want = rows(probe.probe(asked, "key64", lines, spec, "array"))
    for plan in ("join", "shard"):
        assert rows(probe.probe(asked, "key64", lines, spec, plan).select("key64", "maybe")) == want


def test_build_does_not_depend_on_partitions_and_duplicates(spark, keys):
    spec = plan_spec(3000, 8, shards=3)
    want = rows(build.build(keys, spec))
    assert rows(build.build(keys.repartition(7).union(keys), spec)) == want


def test_dense_and_sorted_partials_agree(spark, keys, monkeypatch):
    for kind in ("classic", "linelocal"):
        spec = plan_spec(3000, 8, kind, 1, shards=3)
        want = rows(build.build(keys, spec))
        monkeypatch.setattr(build, "DENSE_BYTES", 0)
        assert rows(build.build(keys, spec)) == want
        monkeypatch.undo()


def test_incremental_and_merge(spark, keys):
    for kind, choices in KINDS:
        spec = plan_spec(3000, 8, kind, choices, shards=2)
        early, late = keys.where("key64 < 1000"), keys.where("key64 >= 1000")
        both = build.insert_more(build.build(early, spec), late, spec)
        assert rows(both) == rows(build.build(keys, spec))


def test_nulls_and_empty(spark):
    spec = FilterSpec(lines=8)
    none = build.keys_of(spark.createDataFrame([(None,)], "x long"), "x")
    lines = build.build(none, spec)
    assert lines.count() == 0
    asked = spark.createDataFrame([(None,), (1,)], "x long")
    for plan in ("array", "join"):
        assert {(r.x, r.maybe) for r in probe.probe(asked, "x", lines, spec, plan).collect()} == {(None, None), (1, False)}
    text = build.keys_of(spark.createDataFrame([("a",), (None,), ("b",)], "s string"), "s")
    assert text.count() == 2


def test_models():
    assert round(models.overload(1.1, 10), 3) == 1.912
    assert [models.max_line_load(10, c) for c in (1, 2, 3, 4)] == [256, 238, 229, 222]
    assert abs(models.collision(10) - 0.0846) < 1e-4
    assert abs(math.log2(models.linelocal_fpr(10, 1.0)) + 9.29) < 0.01
    assert abs(models.required_linelocal(14) - 1.174) < 0.002


def _log2(kind, c, k, **rest):
    spec, n, *_ = measure.cell(kind, c, k, 1000, **rest)
    return math.log2(measure.simulate(spec, n)["fpr"])


def test_reported_order_of_the_filters():
    assert _log2("choice", 3, 4) > _log2("choice", 2, 4) > _log2("linelocal", 1, 4)
    for k in (10, 14, 17):
        assert _log2("choice", 2, k) < _log2("linelocal", 1, k)
    for k in (14, 17):
        assert _log2("choice", 3, k) < _log2("choice", 2, k) and _log2("choice", 3, k) < -k


@pytest.mark.parametrize("kind,choices,k,want", [("linelocal", 1, 14, -12.23), ("choice", 2, 14, -13.93), ("choice", 3, 14, -14.11), ("choice", 2, 10, -9.93), ("choice", 3, 4, -3.54)])
def test_fpr_at_equal_size(kind, choices, k, want):
    assert abs(_log2(kind, choices, k) - want) < 0.17


def test_exponential_cost_wins():
    assert _log2("choice", 2, 14) < _log2("choice", 2, 14, cost=TotalCost()) < _log2("choice", 2, 14, cost=AddedCost())


def test_required_sizes():
    assert measure.required_size("linelocal", 1, 14) > 1.15
    assert 1.0 < measure.required_size("choice", 2, 14, 800) < 1.03
    assert 0.96 < measure.required_size("choice", 3, 14, 800) < 1.0


def test_empirical_agrees_with_loads():
    spec, n, *_ = measure.cell("choice", 2, 7, 600)
    model, found = measure.simulate(spec, n)["fpr"], measure.simulate(spec, n, 1 << 17)
    assert abs(found["false_pos"] - found["probes"] * model) < 4 * math.sqrt(found["probes"] * model)


def test_spec_round_trip():
    for form in FORMS.values():
        spec = FilterSpec(cost=form())
        assert FilterSpec.from_json(spec.to_json()) == spec
    assert replace(FilterSpec(), kind="linelocal").choices == 1
    assert ExpCost().tables(10)[0][0] == 1 << 32


def test_store_and_sql_functions(spark, keys, tmp_path):
    spec = plan_spec(3000, 8, shards=2)
    lines = build.build(keys, spec)
    store.save(lines, spec, str(tmp_path / "f"))
    again, got = store.load(spark, str(tmp_path / "f"))
    assert got == spec and rows(again) == rows(lines)
    assert store.describe(again, got)["max_ones"] <= 512
    sqlfuncs.register_filter(spark, "might_hold", again, got)
    assert spark.sql("SELECT count_if(might_hold(id)) FROM range(3000)").first()[0] == 3000
    sqlfuncs.register_tables(spark, spec)
    assert [tuple(r) for r in spark.sql("SELECT * FROM qgram_table('0123', 3)").collect()] == [(1, 6), (2, 27)]
    assert spark.sql("SELECT * FROM footprint_table(5)").count() == 8


def test_prefilter_is_exact(spark):
    left = spark.range(1000).withColumn("k", F.when(F.col("id") % 7 == 0, None).otherwise(F.col("id")))
    right = spark.range(0, 2000, 3).withColumnRenamed("id", "r")
    for how, join in (("inner", "inner"), ("semi", "left_semi"), ("anti", "left_anti")):
        assert apps.prefilter(left, right, "k", "r", how).count() == left.join(right, F.col("k") == F.col("r"), join).count()


def test_qgrams(spark):
    df = spark.createDataFrame([(1, "Ab-c d!"), (2, "ab"), (3, None)], "i long, t string")
    assert rows(apps.qgrams(df, "t", 3)) == [(1, 1, 6), (1, 2, 27)]


def test_document_qgrams_against_brute_force(spark, tmp_path):
    texts = [None, "", "é日本 ſ\u212a", "Ab-c" * 7 + "de", "Ab-c" * 7 + "def", "x" * 31, "é".join("The quick brown fox jumps over it all"), "zyxw vu\n" * 60_000]
    spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(3, "y" * 32)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    want = []
    for i, text in [*enumerate(texts), (3, "y" * 32)]:
        s = "".join(str("abcdefghijklmnopqrstuvwxyz".index(c) % 4) for c in (text or "").replace("\u212a", "").lower() if "a" <= c <= "z")
        want += [(i, p + 1, int(s[p : p + 31], 4)) for p in range(len(s) - 30)]
    assert rows(QUERIES["qgram_keys_documents"](spark, str(tmp_path))) == sorted(want)


def test_two_origins_sort_every_read(spark, sf):
    docs, said = (spark.read.parquet(f"{sf}/{t}.parquet").toPandas() for t in ("documents", "conversations"))
    got = {r.read_id: r for r in QUERIES["two_origin_sort"](spark, sf).collect()}
    assert set(got) == {-i - 1 for i in docs.doc_id} | {c * 1000 + t for c, t in zip(said.conv_id, said.turn)}

    def grams(text):
        _, _, g = apps.grams_of([(text or "").encode()], 27)
        return g.tolist()

    sets: dict = {(lang, fold): set() for lang in ("en", "de") for fold in (0, 1)}
    fold = {i: zlib.crc32(str(i).encode()) % 2 for i in docs.doc_id}
    for i, lang, text in zip(docs.doc_id, docs.lang, docs.text):
        if (lang, 0) in sets:
            sets[lang, fold[i]].update(grams(text))
    for i, text in [*zip(docs.doc_id, docs.text)][::5]:
        own, r = grams(text), got[-i - 1]
        assert r.grams == len(own) and (own or r["class"] == "neither")
        for hits, lang in ((r.hits_a, "en"), (r.hits_b, "de")):
            assert 0 <= hits - sum(g in sets[lang, 1 - fold[i]] for g in own) <= 2  # false positives at 2^-16


def test_rivals(spark, keys):
    cuckoo = rivals.Cuckoo(2000, 12)
    assert cuckoo.insert(np.arange(2000)) == 0 and cuckoo.lookup(np.arange(2000)).all()
    assert cuckoo.lookup(np.arange(10**6, 10**6 + 4000)).mean() < 0.02
    growing = rivals.Growing(100, 8)
    growing.add(keys.where("key64 < 100"), "key64")
    growing.add(keys.where("key64 >= 100"), "key64")
    assert growing.probe(keys, "key64").where("not maybe").count() == 0
    asked = spark.range(10).withColumnRenamed("id", "p")
    assert rivals.fingerprint_set(keys, asked, "p", 1 << 12, 10).where("maybe").count() == 10
    assert advise(3) == ("classic", 1) and advise(14) == ("choice", 2) and advise(14, smallest=True) == ("choice", 3) and advise(14, False) == ("linelocal", 1)


def test_streams(spark, tmp_path):
    spec = FilterSpec("choice", 30, 2, 2, 64)
    events = spark.range(400).select((F.col("id") % 50).alias("u"), F.timestamp_seconds("id").alias("ts"))
    for i in range(2):
        events.where(F.col("ts") < F.timestamp_seconds(F.lit(200)) if i == 0 else F.col("ts") >= F.timestamp_seconds(F.lit(200))).coalesce(1).write.parquet(str(tmp_path / "in" / f"b{i}"))
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    query = stream.first_seen_stream(source, "u", "ts", spec).writeStream.format("memory").queryName("fresh").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    query.awaitTermination(90)
    assert spark.table("fresh").count() == 50
    writer = stream.maintain(source, "u", spec, str(tmp_path / "f"), str(tmp_path / "c2")).trigger(availableNow=True).start()
    writer.awaitTermination(90)
    assert measure.false_negatives(spark.read.parquet(str(tmp_path / "f" / "v=1")), spec, spark.range(50), "id") == 0
    pair = stream.RotatingPair(replace(spec, shards=1, capacity=20))
    assert pair.offer(np.arange(10)).all() and not pair.offer(np.arange(10)).any()


def test_first_events_of_many_users(spark, tmp_path):
    users = 30_000  # more than three times what the filter of fixed size held
    events = spark.range(users + 500).select((F.col("id") % users).alias("user_id"), F.timestamp_seconds(F.col("id")).alias("ts"))
    events.write.parquet(str(tmp_path / "events.parquet"))
    got = QUERIES["events_first_seen"](spark, str(tmp_path)).select("user_id", F.unix_seconds("first_ts")).collect()
    assert sorted(map(tuple, got)) == [(i, i) for i in range(users)]


# --- keys of all types, odd names, hot keys ------------------------------------------------------
EXTREMES = [0, 1, -1, 2**63 - 1, -(2**63), 7, 7, None]


@pytest.mark.parametrize("kind,choices,bits", [("classic", 1, "random"), ("linelocal", 1, "sliced"), ("choice", 2, "random"), ("choice", 3, "distinct")])
@pytest.mark.parametrize("plan", sorted(probe.PLANS))
def test_every_plan_takes_every_key(spark, kind, choices, bits, plan):
    if plan == "expression" and (kind == "classic" or bits == "distinct"):
        pytest.skip("not for these footprints")
    rows_ = [(i, k, None if k is None else f"k{k}", None if k is None else bytearray(f"b{k}".encode()), None if k is None else datetime.date(2000, 1, 1 + abs(k) % 28), None if k is None else decimal.Decimal(abs(k) % 1000), None if k is None else k % 2 == 0, "x") for i, k in enumerate(EXTREMES)]
    df = spark.createDataFrame(rows_, "maybe int, `my key` long, `a.b` string, bin binary, day date, dec decimal(12,0), flag boolean, key64 string")
    spec = plan_spec(20, 12, kind, choices, shards=3, bits=bits)
    for key in df.columns[1:]:
        inserted = df.where(F.col("maybe") < 4)
        lines = build.build(build.keys_of(inserted, key), spec)
        got = probe.probe(df, key, lines, spec, plan, out="held").collect()
        assert len(got) == len(EXTREMES)
        have = {r[key] if key != "bin" else bytes(r.bin) for r in inserted.collect()}
        for r in got:
            value = bytes(r.bin) if key == "bin" and r.bin is not None else r[key]
            assert r.held is None if value is None else r.held == (value in have)
        assert {(r.maybe, r["my key"], r["a.b"]) for r in got} == {x[:3] for x in rows_}


def test_keys_that_would_lose_digits_are_refused(spark):
    df = spark.createDataFrame([(1.5, 2.5, decimal.Decimal("1.5"))], "d double, f float, x decimal(10,2)")
    for key in df.columns:
        with pytest.raises(TypeError):
            build.keys_of(df, key)
    spec = FilterSpec(lines=8)
    lines = build.build(build.keys_of(spark.range(3), "id"), spec)
    with pytest.raises(TypeError):
        probe.probe(df, "d", lines, spec)
    with pytest.raises(ValueError):
        probe.probe(spark.range(3).withColumn("maybe", F.lit(1)), "id", lines, spec)


def test_a_hot_shard_is_served_by_several_tasks(spark, keys, monkeypatch):
    spec = plan_spec(3000, 8, shards=3)
    lines = build.build(keys, spec).cache()
    hot = spark.range(4000).select(F.when(F.col("id") % 3 > 0, 17).when(F.col("id") % 9 == 0, None).otherwise(F.col("id")).alias("k"), "id")
    want = rows(probe.probe(hot.where("k is not null"), "k", lines, spec, "array"))
    monkeypatch.setattr(probe, "SHARD_ROWS", 200)
    got = probe.probe(hot, "k", lines, spec, "shard")
    assert rows(got.where("k is not null")) == want and got.where("k is null and maybe is null").count() == hot.where("k is null").count()
    assert hot.select(F.spark_partition_id()).distinct().count() >= 1 and rows(probe.probe(hot.limit(0), "k", lines, spec, "shard")) == []


def test_small_and_overfull_filters(spark):
    one = spark.range(1)
    for spec in (plan_spec(1, 10), plan_spec(1, 10, shards=7), FilterSpec("choice", 10, 3, 50, 1), FilterSpec("classic", 10, 1, 9, 1)):
        many = build.keys_of(one.crossJoin(spark.range(10_000).select(F.lit(5).alias("k"))), "k")
        lines = build.build(many, spec)
        assert rows(lines) == rows(build.build(build.keys_of(one.select(F.lit(5).alias("k")), "k"), spec))
        assert probe.probe(one.select(F.lit(5).alias("k")), "k", lines, spec).where("maybe").count() == 1
    spec = plan_spec(500, 10)
    full = build.keys_of(spark.range(1500), "id")
    report = measure.overload_report(full, spec).first()
    assert report.inserted == 1500 and report.gamma == 3.0 and report.penalty > 100
    lines = build.build(full, spec)
    assert measure.false_negatives(lines, spec, spark.range(1500), "id") == 0
    assert measure.fpr(lines, spec, spark.range(2000, 6000), "id").first().fpr > 10 * 2**-10


# --- builds ------------------------------------------------------------------------------------
def test_bits_are_never_taken_back(spark, keys):
    spec = plan_spec(3000, 10, shards=2)
    early = build.build(keys.where("key64 < 1500"), spec)
    late = build.insert_more(early, keys.where("key64 >= 1500"), spec).select("shard", "line", *[F.col(w).alias(f"n{w}") for w in build.W])
    kept = early.join(late, ["shard", "line"], "left")
    assert all(r[f"n{w}"] is not None and r[w] & r[f"n{w}"] == r[w] for r in kept.collect() for w in build.W)


def test_fold_and_epochs(spark):
    keys = spark.range(200).select(F.col("id").alias("key64"), (-F.col("id")).alias("ord"))
    for choices, bits in ((2, "random"), (3, "distinct")):
        spec = FilterSpec("choice", 8, choices, 3, 5, bits)
        assert rows(build.build_fold(keys.union(keys), spec)) == rows(build.build(keys, spec))
        for epochs in (1, 4):
            lines = build.build_epochs(keys, spec, epochs)
            assert measure.false_negatives(lines, spec, keys, "key64") == 0
    assert rows(build.build_epochs(keys.limit(0), spec, 2)) == rows(build.build_fold(keys.limit(0), spec)) == []


def test_lazy_lookup_and_bits_read():
    rng = np.random.default_rng(5)
    for choices, bits, k in ((1, "random", 7), (2, "random", 14), (3, "sliced", 10), (2, "random", 1)):
        spec = FilterSpec("choice", k, choices, lines=30, bits=bits)
        x = K.prepared(rng.integers(-(2**62), 2**62, 3000), spec)
        lines, cand, address = np.zeros((30, 8), np.uint64), K.candidates(x, spec), K.addresses(x, spec)
        K.insert(lines, cand[:900], K.masks(address)[:900], spec)
        want = K.lookup(lines, cand, K.masks(address))
        got = K.lazy_lookup(lines, x, np.zeros(len(x), np.int64), spec)
        assert (want[0] == got[0]).all() and (want[1] == got[1]).all()
        read = K.bits_examined(lines, cand, address)
        for i in range(0, 3000, 97):
            n = 0
            for c in cand[i]:
                bits_ = [int(lines[c, a >> 6]) >> int(a & 63) & 1 for a in address[i]]
                n += bits_.index(0) + 1 if 0 in bits_ else k
                if 0 not in bits_:
                    break
            assert read[i] == n


def test_key_width_decides_the_hash_of_even_moduli():
    a = hashing.constant(3, 1)
    for x in (0, 5, 2**54 - 1, 123456789):
        y = x * a % 2**64
        one = np.array([x], np.uint64)
        assert hashing.np_hash(one, a, 512, 54)[0] == (y >> 45) % 512 and hashing.np_hash(one, a, 500, 54)[0] == (y ^ (y >> 27)) % 500 and hashing.np_hash(one, a, 501, 54)[0] == y % 501
    assert FilterSpec(width=54).u == 64 and FilterSpec(width=54, premix=False).u == 54
    spec = FilterSpec("choice", 9, 2, 4, 16, premix=False, width=54)
    x = K.prepared(np.random.default_rng(1).integers(0, 2**54, 4000), spec)
    assert np.bincount(K.candidates(x, spec)[:, 0], minlength=16).min() > 150


# --- measures ----------------------------------------------------------------------------------
def test_candidates_may_coincide():
    rng = np.random.default_rng(0)
    for choices, lines in ((2, 4), (3, 5), (4, 3)):
        chance = models.distinct_candidates(choices, lines)
        drawn = rng.integers(0, lines, (20_000, choices))
        seen = np.bincount([len(set(r)) for r in drawn.tolist()], minlength=choices + 1)[1:] / 20_000
        assert abs(sum(chance) - 1) < 1e-12 and np.abs(seen - chance).max() < 0.02
    assert abs(models.choice_fpr(0.01, 2, 8) - (0.01 / 8 + 7 / 8 * (1 - 0.99**2))) < 1e-12


def test_grid_equals_build_and_probe(spark, monkeypatch):
    keys = build.keys_of(spark.range(4000).selectExpr("id * 7919 + 11 AS k"), "k")
    absent = spark.range(6000).selectExpr("-id - 1 AS key64")
    monkeypatch.setattr(measure, "SHARD_KEYS", 1500)
    cells = [measure.Cell(kind, c, k, b, rel, gamma) for kind, c in KINDS for k, b, rel, gamma in ((6, "random", 1.0, 1.0), (9, "distinct", 0.9, 1.2)) if (kind, b) != ("classic", "distinct")]
    got = {(r.kind, r.choices, r.k): r for r in measure.grid(keys, cells, absent).collect()}
    assert len(got) == len(cells)
    for cell in cells:
        spec, r = cell.spec(4000, 3), got[cell.kind, cell.choices, cell.k]
        assert spec.shards == 3 and r.bytes == spec.bytes and r.n == 4000
        lines = build.build(keys, spec)
        assert measure.fpr(lines, spec, absent, "key64").first().false_pos == r.false_pos and r.probes == 6000
        assert abs(measure.load_summary(lines, spec).first().mean_ones - r.mean_ones) < 1e-6
        assert abs(measure.fpr_from_loads(lines, spec).first().log2_fpr - r.log2_fpr) < 1e-6
    two = measure.grid(keys.withColumn("g", F.when(F.col("key64") % 3 == 0, "a").otherwise("b")), cells[:2], group="g").collect()
    assert {r.g for r in two} == {"a", "b"} and sum(r.n for r in two) == 8000
    assert measure.grid(keys.limit(0), cells).count() == 0


@pytest.fixture(scope="module")
def curves(spark):
    """FPR (log2) of the four filters on the packed keys of lineitem."""
    pairs = packed_pairs(spark, "/root/testdata/sf0.01")
    cells = [measure.Cell(kind, c, k, b, rel) for kind, c in KINDS for b in ("random", "distinct") for k in (4, 10, 14, 17) for rel in (0.9, 1.0, 1.1) if (kind, b) != ("classic", "distinct")]
    return {(r.kind, r.choices, r.k, r.bits, r.rel_size): r.log2_fpr for r in measure.grid(pairs, cells).collect()}


def test_reported_behaviour_at_the_table(curves):
    def at(kind, c, k, bits="random", rel=1.0):
        return curves[kind, c, k, bits, rel]

    for k in (4, 10, 14, 17):
        assert abs(at("classic", 1, k) + k) < 0.1  # by construction
        assert at("linelocal", 1, k) > at("classic", 1, k)
        for kind, c in KINDS:
            assert at(kind, c, k, rel=0.9) > at(kind, c, k) > at(kind, c, k, rel=1.1)
    assert 2.7 < at("linelocal", 1, 17) + 17 < 3.3  # a factor of about eight
    assert abs(at("linelocal", 1, 10) - at("classic", 1, 10) - 0.8) < 0.15
    assert at("choice", 3, 4) > at("choice", 2, 4) > at("linelocal", 1, 4)
    assert abs(at("choice", 2, 10) + 10) < 0.2 and abs(at("choice", 3, 10) + 10) < 0.2
    for k in (14, 17):
        assert at("choice", 3, k) < at("choice", 2, k) < at("linelocal", 1, k) and at("choice", 3, k) < at("classic", 1, k)
        assert at("choice", 2, k, "distinct") < at("choice", 2, k) and at("choice", 3, k, "distinct") < at("choice", 3, k)
    assert abs(at("choice", 2, 4, "distinct") - at("choice", 2, 4)) < 0.1


def test_published_overheads(spark):
    assert abs(models.required_linelocal(10) / math.log(2) - 1.565) < 0.01
    keys = build.keys_of(spark.range(60_000), "id")
    found = {(r.kind, r.choices): r.overhead for r in measure.required_sizes(keys, [measure.Cell(kind, c, 10) for kind, c in KINDS]).collect()}
    assert abs(found["linelocal", 1] - 1.565) < 0.012 and abs(found["choice", 2] - 1.456) < 0.012 and abs(found["classic", 1] - 1.443) < 0.012 and found["choice", 3] < found["choice", 2]
    table = {r.filter: r for r in models.overview(spark).where("k = 10").collect()}
    assert (table["cuckoo"].insert_low, table["cuckoo"].insert_high, table["quotient"].lookup_low) == (1, None, None)
    assert {k: r.published_c10 for k, r in table.items()} == models.AT_TEN and (table["choice2"].lookup_low, table["choice2"].lookup_high) == (1, 2)
    assert all(abs(table[n].worst - table[n].published_c10) < 0.05 for n in models.RIVALS)


def test_required_sizes_build_few_filters_of_all_keys(spark, keys, monkeypatch):
    """required_size (F3): the sizes of a bisection that builds every step, from fewer builds, each of all keys."""
    some, made, low, high = build.keys_of(spark.range(50_000), "id").select("key64"), [], 0.9, 1.6
    cells = [measure.Cell("classic", 1, 4), measure.Cell("linelocal", 1, 10), measure.Cell("choice", 2, 10, "distinct"), measure.Cell("choice", 3, 4)]
    monkeypatch.setattr(measure, "SHARD_KEYS", 1 << 9)
    monkeypatch.setattr(measure, "_sums", lambda have, tried, *rest, f=measure._sums: made.extend(tried) or f(have, tried, *rest))
    got = {(r.kind, r.choices): r.rel_size for r in measure.required_sizes(some, cells, steps=7).collect()}
    assert 0 < len(made) < 7 * len(cells)
    bounds = [(low, high)] * len(cells)
    for _ in range(7):
        tried = [replace(c, rel_size=(a + b) / 2, label=str(i)) for i, (c, (a, b)) in enumerate(zip(cells, bounds))]
        found = {int(r.label): r.fpr for r in measure.grid(some, tried).collect()}
        bounds = [(t.rel_size, b) if found[i] > 2.0**-t.k else (a, t.rel_size) for i, (t, (a, b)) in enumerate(zip(tried, bounds))]
    assert got == {(c.kind, c.choices if c.kind == "choice" else 1): (a + b) / 2 for c, (a, b) in zip(cells, bounds)}


@pytest.mark.parametrize("kind,choices,epochs", [("classic", 1, 0), ("linelocal", 1, 0), ("choice", 2, 0), ("choice", 3, 0), ("choice", 2, 8)])
def test_shards_filled_side_by_side_are_those_filled_alone(kind, choices, epochs):
    """required_size, fpr_fixed_size (F3, F6): several shards of a filter in one go, bit for bit as each alone."""
    spec = FilterSpec(kind, 10, choices, 3, 40)
    x, own = K.prepared(np.arange(6_000, dtype=np.int64), spec), np.repeat([0, 1, 2], [1_500, 2_500, 2_000])
    absent = [np.arange(s * 10_000, s * 10_000 + 500).view(np.int64) for s in (7, 8, 9)]
    turns = measure._in_turns(own)
    got = measure._measured(spec, epochs, x[turns], own[turns], 3, absent, {})
    each = [measure._measured(spec, epochs, x[own == s], np.zeros((own == s).sum(), np.int64), 1, [absent[s]], {}) for s in range(3)]
    assert got[:3] == (sum(e[0] for e in each), sum(e[1] for e in each), max(e[2] for e in each))
    assert got[3] == pytest.approx(sum(e[3] for e in each)) and got[4] == pytest.approx(sum(e[4] for e in each))


def test_batches_come_near_key_by_key(spark):
    keys = build.keys_of(spark.range(20_000), "id")
    got = {r.epochs: r.log2_fpr for r in measure.grid(keys, [measure.Cell("choice", 2, 14, epochs=r) for r in (0, 1, 8, 64)]).collect()}
    assert got[1] > got[8] > got[64] > got[0] - 0.05


def test_cost_forms_at_the_table(spark, sf):
    got = {(r.label, r.choices, r.k, r.bits): r.log2_fpr for r in QUERIES["cost_forms"](spark, sf).collect()}
    for c in (2, 3):
        best = got["exponential", c, 14, "random"]
        assert best < got["total", c, 14, "random"] and best < got["added", c, 14, "random"] and best < got["linear", c, 14, "random"]


# --- applications ------------------------------------------------------------------------------
def test_acgt_windows(spark):
    texts = ["ACGTNacgtt", "", None, "GATTACA" * 9, "é ACG", "AC"]
    df = spark.createDataFrame(list(enumerate(texts)), "i long, t string")
    for q, canonical in ((3, False), (4, True), (7, True), (31, True)):
        want = []
        for i, t in enumerate(texts):
            raw = (t or "").upper()
            for p in range(len(raw) - q + 1):
                w = raw[p : p + q]
                if all(c in "ACGT" for c in w):
                    d = ["ACGT".index(c) for c in w]
                    value = lambda ds: int("".join(map(str, ds)), 4)
                    want.append((i, p + 1, min(value(d), value([3 - x for x in d[::-1]])) if canonical else value(d)))
        assert rows(apps.qgrams(df, "t", q, "acgt", canonical)) == sorted(want)


def test_hits_are_counted_alike_by_broadcast_and_by_shard(spark, monkeypatch):
    texts = [(0, "The quick brown fox", 0), (1, None, 1), (2, "zzz", None), (3, "a quick brown dog and a quick brown fox", 1), (4, "", 0), (5, "brown foxes", None)]
    df = spark.createDataFrame(texts, "row long, text string, fold int").withColumn("counts", F.lit("x"))
    spec = plan_spec(60, 40, shards=2)
    grams = {i: apps.grams_of([(t or "").encode()], 5)[2].tolist() for i, t, _ in texts}

    def filter_of(i):
        return build.build(build.keys_of(apps.qgrams(df.where(f"row = {i}").select("text"), "text", 5), "gram"), spec), spec

    asked = {"one": [(0, 0)], "two": [(0, None), (3, 1)]}
    sides = {name: [(*filter_of(i), f) for i, f in some] for name, some in asked.items()}
    got = rows(apps.count_hits(df.na.fill({"text": "?"}).na.fill({"fold": 9}), "text", sides, 5, fold="fold"))
    want = [len(grams[i]) for i, _, _ in texts], *([sum(any(g in grams[j] for j, f in some if f is None or f != fold) for g in grams[i]) for i, _, fold in texts] for some in asked.values())
    assert [tuple(r[4:]) for r in got] == list(zip(*want)) and any(want[1]) and apps.count_hits(df, "text", sides, 5, fold="fold").count() == 6
    df = df.na.fill({"text": "?"}).na.fill({"fold": 9})
    monkeypatch.setattr(apps, "BROADCAST_BYTES", 0)
    assert rows(apps.count_hits(df, "text", sides, 5, fold="fold")) == got


def test_gram_sets(spark):
    df = spark.createDataFrame([("a", "abcdefg"), ("a", "abcdefg"), ("b", "abcdefg"), ("b", None), (None, "abcdefg"), ("c", "ab")], "g string, t string")
    got = apps.gram_sets(df, "t", "g", 4)
    assert rows(got.groupBy("g").count()) == [("a", 4), ("b", 4)] and rows(got.where("g = 'a'").select("key64")) == rows(apps.qgrams(df.where("g = 'b'").select("t"), "t", 4).select("gram"))


def test_exact_origins(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").toPandas()
    got = {r.read_id: r for r in QUERIES["two_origin_exact"](spark, sf).collect()}
    by_filter = {r.read_id: r for r in QUERIES["two_origin_sort"](spark, sf).collect()}
    assert set(got) == set(by_filter)
    grams = lambda text: apps.grams_of([(text or "").encode()], 27)[2].tolist()
    sets: dict = {(lang, f): set() for lang in ("en", "de") for f in (0, 1)}
    fold = {i: zlib.crc32(str(i).encode()) % 2 for i in docs.doc_id}
    for i, lang, text in zip(docs.doc_id, docs.lang, docs.text):
        if (lang, 0) in sets:
            sets[lang, fold[i]].update(grams(text))
    for i, text in zip(docs.doc_id, docs.text):
        own, r = grams(text), got[-i - 1]
        assert (r.grams, r.hits_a, r.hits_b) == (len(own), *(sum(g in sets[lang, 1 - fold[i]] for g in own) for lang in ("en", "de")))
    assert sum(by_filter[i]["class"] == r["class"] for i, r in got.items()) > 0.99 * len(got)


@pytest.mark.parametrize("q", [1, 5, 27, 31])
def test_runs_hold_every_window_in_few_bytes(q):
    texts = [b"a" * 300, b"", b"zz", b"The quick brown fox, again and again and again. " * 40, *(bytes(np.random.default_rng(i).integers(97, 123, 3000).astype(np.uint8)) for i in range(20))]
    digits, owner = apps._letters(texts)
    own, count, one, two, least = runs.runs_of(digits, owner, q)
    want, _, grams = apps.grams_of(texts, q)
    assert (runs.windows_of(count, one, two, q) == grams).all() and (np.repeat(own, count) == want).all()
    by_gram: dict = {}
    assert all(by_gram.setdefault(g, p) == p for g, p in zip(grams.tolist(), np.repeat(least, count).tolist()))  # equal windows meet
    raw = runs._packed(own.astype(np.int64), own.astype(np.uint16), count, one, two)
    assert all((a == b).all() for a, b in zip(runs._unpacked(raw), (own, own, count, one, two)))
    assert q < 27 or len(raw) < 4 * len(grams)  # a row per window took over 16


def _some_origins(spark):
    """Reads with a repeated and a null text, an odd fold, and origins with texts in common; and their hits by brute force."""
    word = lambda i: "".join(chr(97 + int(x)) for x in np.random.default_rng(i).integers(0, 26, 60))
    a = [(0, word(1)), (1, word(2)), (1, None), (0, word(5) + word(1))]
    b = [(0, word(3)), (1, word(1)), (1, "short")]
    reads = [(7, 0, word(1)), (8, 1, word(1)), (9, None, word(1) + "-" + word(3)), (-2, 0, word(9)), (10, 1, None), (1 << 60, 1, word(5) * 3), (3, 0, "x")]
    grams = lambda t: apps.grams_of([(t or "").encode()], 27)[2].tolist()
    want = {}
    for i, f, t in reads:
        own = grams(t)
        sets = [{g for at, x in o if at != f for g in grams(x)} for o in (a, b)]
        want[i] = len(own), *(sum(g in s for g in own) for s in sets)
    frame = lambda rows: spark.createDataFrame(rows, "fold int, text string")
    return spark.createDataFrame(reads, "read_id long, fold int, text string"), frame(a), frame(b), want


def test_origins_meet_without_rows_of_grams(spark, monkeypatch):
    """two_origin_exact (F1): no gram is a row of a shuffle, and the counts are those of the sets."""
    reads, a, b, want = _some_origins(spark)
    monkeypatch.setattr(apps, "qgrams", None)
    monkeypatch.setattr(apps, "gram_sets", None)
    got = {r.read_id: (r.grams, r.hits_a, r.hits_b) for r in apps.two_origins_exact(reads, a, b, folds=2).collect()}
    assert got == want and want[9][1] and want[7][1:] == (0, 34)
    monkeypatch.setattr(runs, "HELD_LETTERS", 100)
    assert {r.read_id: (r.grams, r.hits_a, r.hits_b) for r in apps.two_origins_exact(reads, a, b, folds=2).collect()} == want
    both = apps.two_origins_exact(reads.withColumn("origin", F.when(F.col("fold") == 1, "a")), folds=2).where("read_id = 7").first()
    assert (both.hits_a, both.hits_b) == (34, 0)  # read 8 has its text, in the other fold


def test_filters_of_origins_never_reach_the_driver(spark, monkeypatch):
    """two_origin_sort (F2): no array of a filter is collected or broadcast; no hit is lost and hardly any added."""
    reads, a, b, want = _some_origins(spark)
    for name in ("as_arrays", "gram_sets"):
        monkeypatch.setattr(apps, name, None)
    for choices in (1, 2):
        got = {r.read_id: (r.grams, r.hits_a, r.hits_b) for r in apps.two_origins(reads, a, b, choices=choices, folds=2).collect()}
        assert set(got) == set(want) and all(g[0] == w[0] and 0 <= g[1] - w[1] <= 2 and 0 <= g[2] - w[2] <= 2 for g, w in ((got[i], want[i]) for i in want))


def test_bucket_of_origins_without_the_sets_in_little_memory(spark, monkeypatch):
    """two_origin_sort (F2): the counts by the sets are left out of its pass, whose arrays stay under 75 bytes a window; hits are the same."""
    reads, a, b, _ = _some_origins(spark)
    passes, by_bucket = [], runs._by_bucket
    monkeypatch.setattr(runs, "_by_bucket", lambda met: passes.append(met) or by_bucket(met))
    apps.two_origins(reads, a, b, folds=2)
    apps.two_origins_confusion(reads, a, b, folds=2)
    rng, q, n = np.random.default_rng(3), 27, 30_000
    own = rng.integers(0, 4, n)  # a text that some of the others hold
    digits = np.concatenate([own if i % 5 == 0 else rng.integers(0, 4, n) for i in range(24)])
    owner, count, one, two, _ = runs.runs_of(digits, np.repeat(np.arange(24), n), q)
    tags = 1 + 2 * (np.arange(24) % 3) + 6 * (np.arange(24) % 2 + 1)
    raw = runs._packed(owner.astype(np.int64), tags[owner].astype(np.uint16), count, one, two)
    tracemalloc.start()
    plain = passes[0]([raw]).to_pydict()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    both = passes[-1]([raw]).to_pydict()
    assert peak < 75 * count.sum()
    assert sum(both["exact_a"]) and not any(plain["exact_a"] + plain["exact_b"])
    of = lambda got: {r: h for r, *h in zip(*(got[c] for c in ("read_id", "hits_a", "hits_b", "held", "filter_bytes"))) if any(h)}
    assert of(plain) == of(both)


def test_confusion_needs_one_pass_of_the_runs(spark, monkeypatch):
    """two_origin_confusion (F4): classes and space from the same buckets, without sets or filters held whole."""
    reads, a, b, want = _some_origins(spark)
    for name in ("as_arrays", "gram_sets", "qgrams"):
        monkeypatch.setattr(apps, name, None)
    got = apps.two_origins_confusion(reads, a, b, folds=2).collect()
    sets = [{g for at, t in o.collect() if at == f for g in apps.grams_of([(t or "").encode()], 27)[2].tolist()} for o in (a, b) for f in (0, 1)]
    kind = lambda n, x, y: "both" if n and 2 * x >= n and 2 * y >= n else "a" if n and 2 * x >= n else "b" if n and 2 * y >= n else "neither"
    exact: dict = {}
    for w in want.values():
        exact[kind(*w)] = exact.get(kind(*w), 0) + 1
    assert {r.exact: r.reads for r in got if r.exact == r.by_filter} == exact
    assert {r.exact_bytes for r in got} == {8 * sum(map(len, sets))} and all(r.filter_bytes > 0 for r in got)


def test_distinct_grams_without_rows_of_repeats(spark, sf, monkeypatch):
    """unknown_count (F5): repeats go inside the buckets of runs, no aggregate over all grams shuffles them."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    want = {r[0] for r in apps.qgrams(docs, "text", 31).select("gram").distinct().collect()}
    got = [r.key64 for r in apps.gram_set(docs, "text", 31).collect()]
    assert len(got) == len(want) and set(got) == want
    monkeypatch.setattr(build, "distinct_keys", None)
    assert QUERIES["unknown_count"](spark, sf).first().inserted == len(want)


def test_contamination_keeps_every_document(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").union(spark.createDataFrame([(-1, None), (-2, "")], "doc_id long, text string"))
    got = {r.doc_id: r for r in apps.contamination(docs, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
    assert len(got) == docs.count() and got[-1].grams == got[-2].grams == 0 and got[-1].share == 0.0


def test_prefilter_report(spark):
    left, right = spark.range(5000), spark.range(0, 10_000, 5).withColumnRenamed("id", "r")
    r = apps.prefilter_report(left, right, "id", "r", 4).first()
    assert (r.rows, r.partners) == (5000, 1000) and r.false_survivors == r.survivors - 1000 and 100 < r.false_survivors < 600


# --- rivals ------------------------------------------------------------------------------------
def test_cuckoo_tables(spark):
    keys = build.keys_of(spark.range(20_000), "id")
    table = rivals.cuckoo_build(keys.union(keys), 20_000, 12, 4).cache()
    assert table.agg(F.max("failed")).first()[0] == 0
    asked = spark.range(40_000).select(F.when(F.col("id") == 39_999, None).otherwise(F.col("id")).alias("slot"))
    got = rivals.cuckoo_probe(asked, "slot", table, 20_000, 12, 4)
    assert got.where("slot < 20000 and not maybe").count() == 0 and got.where("slot is null and maybe is null").count() == 1
    assert got.where("slot >= 20000 and maybe").count() < 100
    full = rivals.Cuckoo(1000, 8, walk=60)
    assert full.insert(np.arange(4 * full.buckets + 50)) >= 50


def test_platform_filters(spark, tmp_path):
    big, small = spark.range(50_000).withColumnRenamed("id", "a"), spark.range(0, 50_000, 1000).withColumnRenamed("id", "b")
    before = spark.conf.get("spark.sql.optimizer.runtime.bloomFilter.enabled")
    with rivals.runtime_filters(spark):
        assert big.join(small.hint("merge"), F.col("a") == F.col("b")).count() == 50
    assert spark.conf.get("spark.sql.optimizer.runtime.bloomFilter.enabled") == before
    rivals.save_with_column_filter(big, "a", str(tmp_path / "b"), 50_000)
    assert spark.read.parquet(str(tmp_path / "b")).where("a = 77").count() == 1


# --- streams -----------------------------------------------------------------------------------
def _stream_of(spark, df, path, cuts):
    for i, (lo, hi) in enumerate(zip(cuts, cuts[1:])):
        df.where((F.col("n") >= lo) & (F.col("n") < hi)).coalesce(1).write.parquet(f"{path}/b{i:02d}")
        time.sleep(0.02)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*")


def _drained(writer, path):
    query = writer.option("checkpointLocation", path).trigger(availableNow=True).start()
    query.awaitTermination(180)
    assert query.exception() is None


def test_maintained_filter_writes_what_changed(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(stream, "COMPACT", 3)
    spec = FilterSpec("choice", 10, 2, 16, 4)
    df = spark.range(40).select(F.col("id").alias("n"), (F.col("id") * 31).alias("k"))
    source = _stream_of(spark, df, str(tmp_path / "in"), [0, 30, 32, 34, 37, 40])
    stream.maintain(source, "k", spec, str(tmp_path / "f"), str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination(180)
    lines = stream.maintained(spark, str(tmp_path / "f"), 4)
    keys = build.keys_of(df, "k", "n")
    state = build.build(keys.where("ord < 30"), spec)
    for lo, hi in ((30, 32), (32, 34), (34, 37), (37, 40)):
        state = build.insert_more(state, keys.where(f"ord >= {lo} and ord < {hi}").withColumn("ord", F.col("key64")), spec)
    assert rows(lines) == rows(state)
    assert spark.read.parquet(str(tmp_path / "f" / "v=1")).select("shard").distinct().count() <= 2
    assert spark.read.parquet(str(tmp_path / "f" / "v=3")).select("shard").distinct().count() == lines.select("shard").distinct().count()


def test_window_filters_on_a_stream_drop_late_rows(spark, tmp_path):
    spec = FilterSpec("linelocal", 6, 1, 1, 4)
    times = [0, 3600, 86400 * 2, 86400 * 5, 100, 86400 * 9]  # the fifth comes four days late
    df = spark.createDataFrame([(i, 10 + i, t) for i, t in enumerate(times)], "n long, k long, s long").select("n", "k", F.timestamp_seconds("s").alias("ts"))
    source = _stream_of(spark, df, str(tmp_path / "in"), [0, 2, 3, 4, 5, 6])
    _drained(stream.window_filters(source, "k", "ts", spec, "1 day", "1 day").writeStream.format("memory").queryName("days").outputMode("append"), str(tmp_path / "c"))
    got = rows(spark.table("days"))
    want = rows(stream.window_filters(df.where("n <> 4 and n < 4"), "k", "ts", spec, "1 day"))
    assert got == want and len({r[0] for r in got}) == 3


def test_sessions(spark):
    spec = FilterSpec("linelocal", 6, 1, 2, 4)
    events = [("u", 0, 1), ("u", 50, 2), ("u", 200, 3), ("v", 60, 1), (None, 5, 1), ("u", None, 9), ("v", 61, None)]
    df = spark.createDataFrame(events, "user string, s long, k long").select("user", "k", F.timestamp_seconds("s").alias("ts"))
    got = {}
    for r in stream.session_filters(df, "user", "k", "ts", spec, "100 seconds").collect():
        got.setdefault((r.per, r.session_start.timestamp()), set()).add(tuple(r)[3:])
    want = {key: {tuple(x)[:-1] for x in build.build(build.keys_of(spark.createDataFrame([(k,) for k in ks], "k long"), "k"), spec).collect()} for key, ks in {("u", 0.0): [1, 2], ("u", 200.0): [3], ("v", 60.0): [1]}.items()}
    assert got == want


def test_rotating_stream_forgets(spark, tmp_path):
    spec = FilterSpec("choice", 30, 2, 2, 32)
    rows_ = [(0, 1, 0), (1, 2, 10), (2, 1, 20), (3, 1, 110), (4, 2, 150), (5, 3, 190), (6, 1, 410), (7, 3, 420)]
    df = spark.createDataFrame(rows_, "n long, k long, s long").select("n", "k", F.timestamp_seconds("s").alias("ts"))
    source = _stream_of(spark, df, str(tmp_path / "in"), [0, 2, 4, 6, 8])
    _drained(stream.rotating_stream(source, "k", "ts", spec, 100).writeStream.format("memory").queryName("rotated").outputMode("append"), str(tmp_path / "c"))
    got = [(r.key64, r.ord // 1_000_000) for r in spark.table("rotated").collect()]
    assert {(1, 0), (2, 10), (3, 190), (1, 410)} <= set(got) and (1, 20) not in got and (1, 110) not in got


def test_an_idle_pair_is_dropped_by_its_timer(spark, tmp_path):
    spec = FilterSpec("choice", 30, 2, 1, 32)
    df = spark.createDataFrame([(0, 5, 10), (1, 5, 11)], "n long, k long, s long").select("n", "k", F.timestamp_seconds("s").alias("ts"))
    source = _stream_of(spark, df, str(tmp_path / "in"), [0, 1])
    rotated = stream.rotating_stream(source, "k", "ts", spec, 100, idle="1").writeStream.format("memory").queryName("idle").outputMode("append")
    query = rotated.option("checkpointLocation", str(tmp_path / "c")).trigger(processingTime="1 second").start()
    try:
        for count, file in ((1, (1, 2)), (2, None)):
            end = time.time() + 60
            while spark.table("idle").count() < count and time.time() < end:
                time.sleep(0.5)
            assert spark.table("idle").count() == count
            if file:
                time.sleep(8)  # the pair is gone by now, so the key is new again
                df.where(F.col("n") == 1).coalesce(1).write.parquet(str(tmp_path / "in" / "later"))
    finally:
        query.stop()


def test_stream_prefilter(spark, tmp_path):
    spec = plan_spec(100, 10)
    table = spark.range(0, 200, 2).withColumnRenamed("id", "t")
    lines = build.build(build.keys_of(table, "t"), spec)
    df = spark.range(300).select(F.col("id").alias("n"), F.col("id").alias("k"), F.lit(0).alias("maybe"))
    source = _stream_of(spark, df, str(tmp_path / "in"), [0, 150, 300])
    _drained(stream.stream_prefilter(source, "k", lines, spec, table, "t").writeStream.format("memory").queryName("passed").outputMode("append"), str(tmp_path / "c"))
    assert sorted(r.k for r in spark.table("passed").collect()) == list(range(0, 200, 2))


def test_filter_aggregate(spark, keys):
    spec = FilterSpec("choice", 8, 2, 1, 40)
    sqlfuncs.register_aggregate(spark, "filter_of", spec)
    keys.createOrReplaceTempView("numbers")
    for r in spark.sql("SELECT key64 % 2 AS half, filter_of(key64) AS f FROM numbers WHERE key64 < 600 GROUP BY 1").collect():
        lines = np.frombuffer(r.f, ">u8").astype(np.uint64).reshape(-1, 8)
        found, _, _ = probe.answers(lines, np.arange(r.half, 600, 2), spec)
        assert found.all() and not probe.answers(lines, np.arange(10**6, 10**6 + 100), spec)[0].all()


@pytest.mark.parametrize("name", ["fpr_empirical", "touches", "bits_examined_lines", "unknown_count", "two_origin_confusion", "prefilter_report", "events_session_filters", "rival_cuckoo", "rival_fingerprints", "qgram_build_species", "linelocal_model"])
def test_query_without_sql_runs(spark, sf, name):
    got = QUERIES[name](spark, sf).collect()
    assert got and all(len(r) for r in got)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_matches_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want, got = con.execute(ORACLES[name]).df(), QUERIES[name](spark, sf).toPandas()
    assert sorted(want.columns) == sorted(got.columns) and len(want) == len(got)

    def rounded(df):
        df = df[sorted(df.columns)]
        return sorted(map(repr, [tuple(round(v, 8) if isinstance(v, float) else str(v) for v in r) for r in df.itertuples(index=False, name=None)]))

    assert rounded(want) == rounded(got)


FROM_TABLES = ["advise", "classic_model", "collision_curve", "cost_table", "filter_overview", "linelocal_model", "max_line_load", "overload_model"]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_models_are_asked_about_a_table(spark, name, tmp_path):
    """The keys come from orders: without the table there is no result, and with other orders another one."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()
    for what, n in (("few", 300), ("more", 60_000)):
        day = F.date_add(F.lit("2020-01-01").cast("date"), F.pmod(F.col("id") * F.col("id"), F.lit(1000)).cast("int"))
        some = spark.range(n).select(F.col("id").alias("o_orderkey"), (F.col("id") % 77).alias("o_custkey"), day.alias("o_orderdate"), F.lit("1-URGENT").alias("o_orderpriority"))
        some = some.where("o_orderkey < 300 or o_orderkey % 2 = 1").withColumn("o_custkey", F.when(F.lit(n > 300), F.col("o_orderkey")).otherwise(F.col("o_custkey")))
        some.write.parquet(f"{tmp_path}/{what}/orders.parquet")
    assert rows(QUERIES[name](spark, f"{tmp_path}/few")) != rows(QUERIES[name](spark, f"{tmp_path}/more"))


def test_keys_per_line_give_the_model(spark):
    keys = build.distinct_keys(build.keys_of(spark.range(50_000), "id"))
    for k, (n, lines, held) in measure.keys_per_line(keys, (4, 10)).items():
        assert n == 50_000 == sum(a * b for a, b in held.items()) and sum(held.values()) == lines
        assert abs(math.log2(models.linelocal_fpr_of(k, held)) - math.log2(models.linelocal_fpr(k, 1.0))) < 0.05


def _jobs_of(spark, make):
    """(rows, jobs that it took)."""
    sc = spark.sparkContext
    group = f"jobs-{np.random.default_rng().integers(1 << 40)}"
    sc.setJobGroup(group, "")
    try:
        return make().collect(), len(sc.statusTracker().getJobIdsForGroup(group))
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)


def test_timed_has_every_run_of_all_keys_and_fills_the_built_lines(spark):
    keys = spark.range(1, 5001).select(F.col("id").alias("key64"), F.col("id").alias("ord"))
    specs = measure.four_kinds(5000, 7, shards=3) | {"two": plan_spec(5000, 7, shards=2)}
    got = measure.timed(keys, [(name, spec, name != "classic") for name, spec in specs.items()], runs=2).collect()
    want = {(i, what, run) for i, name in enumerate(specs) for what in ("insert", "hit", "miss") for run in (0, 1) if what == "insert" or name != "classic"}
    assert {(r.filter, r.operation, r.run) for r in got} == want
    assert all(r["keys"] == 5000 and r.seconds > 0 for r in got)
    values = np.arange(1, 5001)
    for spec in specs.values():
        x = K.prepared(values, spec)
        lines = np.concatenate([K.filled(x[K.shard_of(x, spec) == s], spec) for s in range(spec.shards)])
        assert (lines == probe.as_array(build.build(keys, spec), spec)).all()


def test_throughput_by_k_deals_the_keys_once(spark, sf):
    """throughput_by_k (F9): every filter and lookup is timed in one pass over the keys, not in some 270 jobs."""
    rows, jobs = _jobs_of(spark, lambda: QUERIES["throughput_by_k"](spark, sf))
    assert len(rows) == len({(r.name, r.k, r.operation) for r in rows}) == 6 * (4 * 3 + 3) and jobs < 20
    assert all(r.mkeys_per_s > 0 for r in rows) and len({r.n for r in rows}) == 1


def test_throughput_by_shards_deals_the_keys_once(spark, sf):
    """throughput_by_shards (F10): a pass over the keys for all counts of writers, not a job for each run."""
    rows, jobs = _jobs_of(spark, lambda: QUERIES["throughput_by_shards"](spark, sf))
    assert {(r.kind, r.choices, r.shards, r.operation) for r in rows} == {(k, c, s, "insert") for k, c in (("classic", 1), ("linelocal", 1), ("choice", 2), ("choice", 3)) for s in (1, 2, 4, 8)} and jobs < 20
    assert all(r.mkeys_per_s > 0 for r in rows) and len({r.n for r in rows}) == 1


def test_a_bucket_is_written_and_asked_in_pieces(spark, monkeypatch):
    """two_origin_confusion (F4): no footprints of a whole bucket at once; pieces of any size give the same answers."""
    texts = ["".join(random.Random(i).choices("abcdefghij", k=400)) for i in range(40)]
    spec = plan_spec(9000, 17, shards=1)
    keys = apps.grams_of([t.encode() for t in texts], 27)[2]
    x, most = K.prepared(keys, spec), []
    whole = np.zeros((spec.lines, 8), np.uint64)
    K.insert(whole, K.candidates(x, spec), K.footprints(x, spec), spec)
    footprints = K.footprints
    monkeypatch.setattr(K, "footprints", lambda some, spec: most.append(len(some)) or footprints(some, spec))
    monkeypatch.setattr(K, "WRITTEN", 1000)
    monkeypatch.setattr(probe, "ASKED", 700)
    assert (K.filled(x, spec) == whole).all() and max(most) == 1000
    asked = np.concatenate([keys, keys + (1 << 40)])
    assert (probe.asked_all(whole, asked, spec) == probe.answers(whole, asked, spec)[0]).all() and len(probe.asked_all(whole, asked[:0], spec)) == 0


def test_qgram_build_times_deals_the_grams_once(spark, sf):
    """qgram_build_times (F7): the builds of all sets are timed in one pass, not in 36 jobs, and of all grams."""
    got, jobs = _jobs_of(spark, lambda: QUERIES["qgram_build_times"](spark, sf))
    kinds = ("classic", "linelocal", "choice2", "choice3")
    assert {(r.lang, r.kind) for r in got} == {(lang, kind) for lang in ("es", "de", "en") for kind in kinds} and len(got) == 12 and jobs < 36
    sets = {r.lang: r.grams for r in QUERIES["qgram_sets"](spark, sf).collect()}
    local = {r.lang: r.seconds for r in got if r.kind == "linelocal"}
    assert all(r["keys"] == sets[r.lang] and r.over_linelocal == r.seconds / local[r.lang] and math.isclose(r.mkeys_per_s, r["keys"] / r.seconds / 1e6) for r in got)


def test_throughput_times_the_array_plan_in_the_shards(spark, sf):
    """throughput (F8): builds and array lookups take no job of their own; the other plans are timed as whole jobs."""
    got = QUERIES["throughput"](spark, sf).collect()
    plans = {"array", "expression", "join", "shard"}
    want = {(k, c, "insert", "") for k, c in KINDS} | {(k, c, what, p) for k, c in KINDS for what in ("hit", "miss") for p in plans if k != "classic" or p in ("array", "shard")}
    assert len(got) == len(want) and {(r.kind, r.choices, r.operation, r.plan) for r in got} == want
    assert all(r.mkeys_per_s > 0 for r in got) and len({r.n for r in got}) == 1


def test_timed_seconds_are_not_less_than_the_cores_allow(spark, keys, monkeypatch):
    """qgram_build_times (F7): with more shards than cores, seconds are not those of a single shard."""
    spec = plan_spec(3000, 4, "linelocal", 1, shards=40)
    each = []
    shards_of = measure._timed_shards

    def kept(*args):
        each.append(shards_of(*args).persist())
        return each[-1]

    monkeypatch.setattr(measure, "_timed_shards", kept)
    one = measure.timed(keys, [("many", spec, False)], runs=1).first()
    took = [r.seconds for r in each[0].collect()]
    assert len(took) == 40 and one["keys"] == 3000
    assert math.isclose(one.seconds, max(max(took), sum(took) / spark.sparkContext.defaultParallelism))


def test_timed_keys_lie_in_few_partitions(spark, sf):
    """throughput (F4): every timed job passes over the keys, so they are not held in as many pieces as a shuffle has."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "200")
    try:
        from memberset.workloads import _distinct_pairs

        keys, n = _distinct_pairs(spark, sf)
        assert keys.rdd.getNumPartitions() <= 4 * spark.sparkContext.defaultParallelism and keys.count() == n > 0
        keys.unpersist()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
