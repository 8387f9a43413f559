"""Operators against brute force, round trips and held-out accuracy; nulls, empties, ties, clashing names."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from memberset.llm import audio, chat, common, components, decontam, html, huffman, langid, mixing, secrets, sharding, simhash
from memberset.llm.queries import HOSTILE_ID, ORACLES, QUERIES
from memberset.llm.xxh64 import hash_ranges

BPE = public_tokenizers.path("byte_bpe_50k.json")
ODD = [None, "", " ", "a", "a b c", "Hello, World!  two\n\nlines ", "é日本   ſK", "x" * 3000, "same text here of five words", "same text here of five words"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, target double, fp long, component_id long, run long, place int"


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").cache()


@pytest.fixture(scope="module")
def odd(spark):
    """Awkward documents, with columns whose names the operators use themselves."""
    rows = [(i, t, "en", None if i % 3 else "s", 0, 1, 1.0, 1, 1, 1, 1) for i, t in enumerate(ODD)]
    rows += [(3, "a", None, "s", 0, 1, 1.0, 1, 1, 1, 1), (None, "a", "de", "t", 0, 1, 1.0, 1, 1, 1, 1)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_xxh64():
    data = random.Random(1).randbytes(3000)
    starts = np.array([i % 2500 for i in range(0, 5000, 7)])
    ends = starts + np.arange(len(starts)) % 110
    assert [int(h) for h in hash_ranges(data, starts, ends)] == [xxhash.xxh64_intdigest(data[a:b], 42) for a, b in zip(starts, ends)]


# --- 1 -----------------------------------------------------------------------------------------
def test_audio_round_trip(docs, odd, empty):
    for table in (docs, odd):
        got = audio.store_and_extract(table).collect()
        texts = Counter((r.doc_id, r.text or "") for r in table.collect())
        assert len(got) == sum(texts.values())
        want = set()
        for (i, t), _ in texts.items():
            raw = t.encode()
            raw += b" " * (-len(raw) % 192 if raw else 192)
            want.add((i, len(t.encode()), len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-16:])))
        assert {(r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in got} == want
        assert len({r.payload_sha256 for r in got}) == len({(r.payload_sha256, r.media_sha256, r.feature) for r in got})
    assert audio.store_and_extract(empty).count() == 0


def test_resampling_and_segments():
    t = np.arange(12000) / 12000
    out = audio.resample(np.sin(2 * np.pi * 440 * t).astype(np.float32))
    assert len(out) == 8000
    inner = slice(200, -200)  # a filter of linear phase delays all tones alike, by a fraction of a sample
    best = max(np.corrcoef(out[inner], np.sin(2 * np.pi * 440 * (np.arange(8000) + d) / 8000)[inner])[0, 1] for d in np.arange(-3, 3, 0.05))
    assert best > 0.9999
    energy = np.zeros(50)
    energy[10:20], energy[20:24], energy[30:32] = 10, 2, 2
    assert audio.segments(energy) == [(10, 24)]
    mel, _ = audio.features(bytes(range(256)) * 40)
    import pyarrow as pa

    table = pa.ipc.open_stream(audio.tensors(mel)).read_all()
    assert table.schema.field("tensor").type == audio.TENSOR and table["stop_ms"][-1].as_py() == len(mel) * 10
    back = np.concatenate([np.array(x.as_py()).reshape(audio.CLIP, -1) for x in table["tensor"].combine_chunks().storage])
    assert (back[: len(mel)] == mel).all()


def test_features_reach_both_ends_of_the_recording():
    import pyarrow as pa

    rng = np.random.default_rng(1)
    for units in range(1, 60):
        text = rng.integers(97, 123, units * 192).astype(np.uint8)
        mel, found = audio.features(text.tobytes())
        changed = [slice(0, 1), slice(-2, None)] + [slice(-1, None)] * (units % 5 > 0)  # where hops end with the samples, the last byte alone can fall below a step
        for at in changed:
            other = text.copy()
            other[at] = 255
            assert (audio.features(other.tobytes())[0] != mel).any(), (units, at)
        table = pa.ipc.open_stream(audio.tensors(mel, audio.length_ms(text.tobytes()))).read_all()
        assert table["stop_ms"][-1].as_py() == units * 16 and (len(mel) - 1) * 10 < units * 16 <= len(mel) * 10
    quiet, loud = np.full(192 * 50, 128, np.uint8), np.where(np.arange(192 * 20) % 6 < 3, 0, 255).astype(np.uint8)
    assert audio.features(np.concatenate([quiet, loud]).tobytes())[1][-1][1] == 70 * 16


def test_long_recordings_are_worked_through_in_stretches(monkeypatch):
    payload = np.random.default_rng(3).integers(32, 127, 192 * 700).astype(np.uint8)
    whole, energy = audio.log_mel(payload)
    rate, n = audio.RATE_OUT, -(-len(payload) * 2 // 3)
    x = np.pad(audio.resample((payload.astype(np.float32) - 128) / 128), ((audio.WINDOW - audio.HOP) // 2, audio.WINDOW))
    assert len(x) == n + (audio.WINDOW - audio.HOP) // 2 + audio.WINDOW
    top = 2595 * math.log10(1 + rate / 2 / 700)
    edge = [700 * (10 ** (top * i / (audio.MELS + 1) / 2595) - 1) for i in range(audio.MELS + 2)]
    for frame in (0, 7, 400, len(whole) - 1):  # a plain transform of one window
        part = x[frame * audio.HOP :][: audio.WINDOW] * (0.5 - 0.5 * np.cos(2 * np.pi * np.arange(audio.WINDOW) / (audio.WINDOW - 1)))
        power = [abs(sum(part * np.exp(-2j * np.pi * k * np.arange(audio.WINDOW) / audio.FFT))) ** 2 for k in range(audio.FFT // 2 + 1)]
        for m in range(audio.MELS):
            a, b, c = edge[m : m + 3]
            value = sum(p * max(0, min((k * rate / audio.FFT - a) / (b - a), (c - k * rate / audio.FFT) / (c - b))) for k, p in enumerate(power))
            assert abs(4 * math.log(value + 1e-4) - whole[frame, m]) < 0.52
        assert abs(10 * math.log10(sum(power) + 1e-9) - energy[frame]) < 1e-2
    monkeypatch.setattr(audio, "STRETCH", 37)
    again, loud = audio.log_mel(payload)
    assert np.abs(again.astype(int) - whole).max() <= 1 and (again != whole).mean() < 1e-3 and np.abs(loud - energy).max() < 1e-3


def test_stored_tensors_are_what_is_returned(docs):
    got = audio.store_and_extract(docs).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    for r in got[::20]:
        raw = text[r.doc_id].encode()
        mel, found = audio.features(raw + b" " * (-len(raw) % 192 if raw else 192))
        clips = audio.clips_of(r.tensors)
        back = np.concatenate([part.storage.flatten().to_numpy() for part in clips["tensor"].chunks]).reshape(-1, audio.MELS)
        assert (back[: len(mel)] == mel).all() and not back[len(mel) :].any() and r.feature.startswith(f"{len(mel)}x16:{len(found)}:")
        assert [(s.start_ms, s.stop_ms) for s in r.segments] == found
        assert r.feature != audio._feature(audio.tensors(mel + np.int8(1), clips["stop_ms"][-1].as_py()), [s.asDict() for s in r.segments])


# --- 2 -----------------------------------------------------------------------------------------
def test_one_id_is_dealt_over_many_parts(spark):
    rows = [(7, f"text {i % 5}") for i in range(900)] + [(None, f"none {i % 3}") for i in range(600)] + [(i, "x") for i in range(300)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    nulls, bounds = huffman._bounds(table, 9)
    placed = table.withColumn("row", F.monotonically_increasing_id()).select("doc_id", huffman._place(nulls, bounds).alias("p")).collect()
    low, high, most = {}, {}, Counter(r.p for r in placed)
    for r in placed:
        low[r.doc_id], high[r.doc_id] = min(low.get(r.doc_id, 99), r.p), max(high.get(r.doc_id, 0), r.p)
    order = sorted(low, key=lambda i: (i is not None, i or 0))
    assert all(high[a] <= low[b] for a, b in zip(order, order[1:])) and most.most_common(1)[0][1] <= 450 and len(most) == 9
    got = sorted(huffman.read_files(spark, huffman.write_files(table, BPE, 50257)).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in got] == sorted((i for i, _ in rows), key=lambda i: (i is not None, i or 0))
    assert [r.start for r in got] == [sum(x.n_tokens for x in got[:i]) for i in range(len(got))]


def test_code_lengths_are_optimal_and_limited():
    import heapq

    rng = np.random.default_rng(2)
    for _ in range(20):
        counts = rng.integers(1, 500, rng.integers(2, 70))
        heap = [(int(c), 0) for c in counts]
        heapq.heapify(heap)
        cost = 0
        while len(heap) > 1:
            a, b = heapq.heappop(heap), heapq.heappop(heap)
            cost += a[0] + b[0]
            heapq.heappush(heap, (a[0] + b[0], 0))
        assert int((counts * huffman.code_lengths(counts, 25)).sum()) == cost
        short = huffman.code_lengths(counts, 7).astype(float)
        assert short.max() <= 7 and (2.0**-short).sum() <= 1


def test_piece_encoder_equals_the_library():
    encoder, plain, rng = huffman.PieceEncoder(BPE, 4, keep=40), Tokenizer.from_file(BPE), random.Random(4)
    parts = ["a", "Foo", "bar,", "x.", "\n", " ", "  ", "\t", "é", "Ünd", "12", "\x1c", "\xa0", "don't", "'s", "!!", "$$$", "\r\n", "日本", "_", "ſ", "<|endoftext|>", " ", "a,b"]
    for _ in range(3000):
        text = "".join(rng.choice(parts) + (" " if rng.random() < 0.5 else "") for _ in range(rng.randrange(9)))
        assert np.frombuffer(encoder.batch([text])[0], "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids


def test_pieces_are_whole_pretokens():
    plain, rng = Tokenizer.from_file(BPE), random.Random(9)
    encoder = huffman.PieceEncoder(BPE, 2, keep=500)
    signs = [*"ab1.'s,\t\n \r\x0b\x1c\x1f\x7f\x00", *"\xe9\xd7\xf7\xdf\u024f\u0250\xbb\xa0\x85\u2003\u2019\u3000\u1680\u180e\u200b\u4f60\U0001f600\u0663\xaa", "'s", "n't", "  ", " \n", "<|endoftext|>"]
    for _ in range(60):
        texts = ["".join(rng.choices(signs, k=rng.randrange(25))) for _ in range(60)]
        got = [np.frombuffer(x, "<u2").tolist() for x in encoder.batch(texts)]
        assert got == [plain.encode(t, add_special_tokens=False).ids for t in texts]
    assert encoder.batch([]) == [] and encoder.batch(["", ""]) == [b"", b""]


def test_huffman_files(spark, docs, odd, empty):
    plain = Tokenizer.from_file(BPE)
    for table in (docs, odd):
        got = huffman.read_files(spark, huffman.write_files(table, BPE, 50257), with_ids=True).collect()
        texts = sorted(((-1 if r.doc_id is None else r.doc_id, r.text or "") for r in table.collect()))
        ids = [(i, [*plain.encode(t, add_special_tokens=False).ids, 0]) for i, t in texts]
        assert Counter((-1 if r.doc_id is None else r.doc_id, tuple(r.ids)) for r in got) == Counter((i, tuple(x)) for i, x in ids)
        at = 0
        for r in sorted(got, key=lambda r: r.start):
            assert r.start == at and r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes())
            at += r.n_tokens
        order = [-1 if r.doc_id is None else r.doc_id for r in sorted(got, key=lambda r: r.start)]
        assert order == sorted(order)
    assert huffman.read_files(spark, huffman.write_files(empty, BPE, 50257)).count() == 0


# --- 3 -----------------------------------------------------------------------------------------
def test_water_fill():
    assert [float(x) for x in mixing.water_fill([10, 10, 10], [5, 2, 1])] == [18.75, 7.5, 3.75]
    out = [float(x) for x in mixing.water_fill([1, 10, 10], [5, 2, 1])]
    assert out[0] == 3 and abs(sum(out) - 21) < 1e-9 and abs(out[1] - 2 * out[2]) < 1e-9


def test_pivot_keeps_mass_and_expectation():
    rng = random.Random(3)
    sizes, shares = [rng.randrange(1, 50) for _ in range(9)], [rng.random() for _ in range(9)]
    mass, mean = sum(s * p for s, p in zip(sizes, shares)), np.zeros(9)
    for salt in range(3000):
        out, open_ = mixing.pivot(list(range(9)), sizes, shares, salt)
        assert abs(sum(s * p for s, p in zip(sizes, out)) - mass) < 1e-6
        assert sum(0 < p < 1 for p in out) == (open_ >= 0)
        mean += out
    assert np.abs(mean / 3000 - shares).max() < 0.05


def test_mix(docs, odd, empty):
    got = mixing.mix(docs).collect()
    assert got and sorted(map(tuple, got)) == sorted(map(tuple, mixing.mix(docs.repartition(5)).collect()))
    by: dict = {}
    for r in got:
        assert 0 <= r.taken <= 3 * r.size
        s = by.setdefault(r.source, [0, 0, r.target, r.source_size])
        s[0] += r.taken
        s[1] += r.size
    assert all(abs(t - goal) <= 1 and size == said for t, size, goal, said in by.values())
    words = {r.doc_id: len(re.findall(r"[^\x20\x09-\x0D]+", r.text)) for r in docs.collect()}
    assert all(r.size == words[r.doc_id] for r in got)
    assert mixing.mix(odd).count() == odd.count() and mixing.mix(empty).count() == 0
    assert mixing.apply_mix(docs).count() == mixing.mix(docs, root="round").agg(F.sum("copies")).first()[0]
    assert mixing.apply_mix(odd).columns == odd.columns and mixing.apply_mix(empty).count() == 0


def test_hot_ids_are_mixed_row_by_row(spark, monkeypatch):
    """Null and repeated ids: leaves stay small, the corpus has the words that were drawn, every row is its own."""
    rows = [(None, " ".join("ab"[i % 2] * (1 + i % 7)), ("s", "t", None)[i % 3]) for i in range(700)] + [(5, f"w {i} " + "z " * (i % 11), "s") for i in range(300)] + [(100 + i, "q " * (i % 9), "t") for i in range(200)]
    table = spark.createDataFrame(rows, "doc_id long, text string, source string")
    monkeypatch.setattr(mixing, "LEAF_ROWS", 16)
    monkeypatch.setattr(mixing, "FAN_IN", 4)
    seen, level = [], mixing._level

    def watched(df, salt):
        seen.append(df.groupBy("place", "leaf", "sub").count().agg(F.max("count")).first()[0])
        return level(df, salt)

    monkeypatch.setattr(mixing, "_level", watched)
    drawn = mixing.mix(table, root="round").collect()
    assert max(seen) <= 16 * mixing.HOT and len(drawn) == len(rows)
    taken, sizes, targets = Counter(), Counter(), {}
    for r in drawn:
        taken[r.source] += r.taken
        sizes[r.source] += r.size
        targets[r.source] = r.target
        assert r.taken == r.copies * r.size
    assert all(abs(taken[s] - targets[s]) <= 22 for s in targets)
    mixed = mixing.apply_mix(table).collect()
    words = Counter()
    for r in mixed:
        words[r.source] += len(r.text.split())
    assert all(abs(words[s] - targets[s]) <= 22 for s in targets)
    have = Counter((r[0], r[1], r[2]) for r in rows)
    assert all(n <= 3 * have[k] for k, n in Counter((r.doc_id, r.text, r.source) for r in mixed).items())


# --- 4 -----------------------------------------------------------------------------------------
ASSIGN = re.compile(rb"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I)


def brute_secrets(data: bytes):
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(data) if len(m[2]) >= 12]
    out += [(m.start(), 1, m.end()) for m in re.finditer(rb"AKIA[A-Z0-9]+", data) if len(m[0]) >= 18]
    out += [(m.start(), 2, m.end()) for m in re.finditer(rb"[0-9a-f]+", data) if len(m[0]) >= 16]
    return [(("assign", "access", "hex")[k], a, b) for a, k, b in sorted(out)]


def test_scanner_equals_regexes():
    scanner, rng = secrets.Scanner(), random.Random(7)
    start = scanner.linked()
    parts = ["password", "passwd", "secret", "token", "api_key", "apikey", "ToKeN", '"', "'", " ", "  ", ":", "=", "AKIA", "0123456789abcdef", "deadbeef", "ABCDEFGHIJKLMNOP", "x", "\n", "é", "-", "_", "/", "9", "ghp_"]
    for _ in range(4000):
        data = "".join(rng.choice(parts) for _ in range(rng.randrange(14))).encode()
        assert [s for s in scanner.spans(data, start) if s[0] in ("assign", "access", "hex")] == brute_secrets(data)


def test_scan(docs, odd, empty):
    text = {r.doc_id: r.text for r in docs.collect()}
    for r in secrets.scan(docs).collect():
        data = text[r.doc_id].encode()
        points = [(k, len(data[:a].decode()), len(data[:b].decode())) for k, a, b in brute_secrets(data)]
        assert r.base == ",".join(f"{k}:{a}:{b}" for k, a, b in points)
    assert secrets.scan(odd).count() == odd.count() and secrets.scan(empty).count() == 0
    assert secrets.redact("key é token=abcdefghijkl!", [("assign", 6, 24)]) == "key é [assign]!"


# --- 5 -----------------------------------------------------------------------------------------
def brute_fingerprint(text: str) -> int:
    w = (text or "").encode().lower().split()
    hs = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 4]), 42) for i in range(max(1, len(w) - 3))] if w else []
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(fps: list[int], ids: list) -> list:
    label = list(ids)
    changed = True
    while changed:
        changed = False
        for i, a in enumerate(fps):
            low = min(label[j] for j, b in enumerate(fps) if (a ^ b).bit_count() <= 4)
            changed |= low != label[i]
            label[i] = low
    return label


def test_near_duplicates(spark, docs, odd, empty):
    rows = docs.collect()
    fps = [brute_fingerprint(r.text) for r in rows]
    want = dict(zip([r.doc_id for r in rows], zip(fps, brute_components(fps, [r.doc_id for r in rows]))))
    got = simhash.near_duplicates(docs).collect()
    assert {r.doc_id: (r.fp & (1 << 64) - 1, r.component_id) for r in got} == want
    keep = simhash.keep_one(docs)
    assert {r.doc_id for r in keep.collect()} == {c for _, c in want.values()} and keep.columns == docs.columns
    zero = {r.doc_id: r.component_id for r in simhash.near_duplicates(odd).collect() if r.fp == 0}
    assert {zero[0], zero[1], zero[2]} == {0}
    assert simhash.near_duplicates(empty).count() == 0 and simhash.keep_one(empty).count() == 0
    kept = [r.doc_id for r in simhash.keep_one(odd).collect()]
    assert kept.count(3) == 1 and 9 not in kept


def test_one_row_of_each_component_stays(spark):
    one, two = "the first text has nine words in it altogether", "quite another story about ships and seas and storms"
    rows = [(3, one), (7, one), (7, two), (None, one), (None, one), (None, None), (9, two), (None, "all alone here with no id of its own")]
    for table in (spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([(9, None)], "row long, _row string").crossJoin(spark.createDataFrame(rows, "doc_id long, text string"))):
        got = simhash.keep_one(table)
        assert got.columns == table.columns
        assert Counter((r.doc_id, r.text) for r in got.collect()) == Counter([(3, one), (7, two), (None, None), (None, "all alone here with no id of its own")])


def test_row_keys(spark, tmp_path):
    table = spark.range(1000).selectExpr("id % 3 AS doc_id", "'x' AS text")
    table.repartition(7).write.parquet(str(tmp_path / "t"))
    read = spark.read.parquet(str(tmp_path / "t"))
    for df in (read, read.select("text", "doc_id"), read.where("doc_id > 0"), read.unionByName(read)):
        rows = common.keyed(df, "row")
        first, again = ([(r.row, r.doc_id) for r in rows.select("row", "doc_id").collect()] for _ in range(2))
        assert len({k for k, _ in first}) == df.count() and sorted(first) == sorted(again)
        assert rows.select("row").join(rows.select("row", "text"), "row").count() == df.count()


@pytest.mark.parametrize("n", [10, 10**7, 10**9, 10**12])
def test_links_lose_none_at_any_cut(spark, n):
    rng = random.Random(n)
    base = [rng.getrandbits(64) for _ in range(30)]
    fps = {b ^ sum(1 << p for p in rng.sample(range(64), rng.randrange(6))) for b in base for _ in range(60)}
    frame = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for f in fps], "fp long")
    comp = {r.node: r.root for r in components.connected_components(simhash.links(frame, n=n)).collect()}
    signed = sorted(f - (1 << 64) if f >> 63 else f for f in fps)
    want = brute_components([f & (1 << 64) - 1 for f in signed], signed)
    assert [comp.get(f, f) for f in signed] == want


# --- 6 -----------------------------------------------------------------------------------------
def test_gradients():
    rng = np.random.default_rng(0)
    gru = langid.Gru(4, rng)
    x, goal = rng.integers(0, 256, (6, 5)).astype(np.uint8), rng.normal(size=(6, 5, 4)).astype(np.float32)
    _, trail = gru.run(x, keep=True)
    d_byte, d_loop = gru.back(x, trail, goal)
    seen = [(gru.loop, d_loop, i, j) for i, j in ((0, 0), (1, 5), (3, 11))] + [(gru.byte, d_byte, x[t, 2], j) for t, j in ((0, 0), (2, 5), (5, 11))]
    for weight, slope, i, j in seen:
        held, sides = weight[i, j], []
        for e in (0.01, -0.01):
            weight[i, j] = held + e
            sides.append(float((gru.run(x)[0] * goal).sum()))
        weight[i, j] = held
        assert abs((sides[0] - sides[1]) / 0.02 - slope[i, j]) < 0.01 + 0.02 * abs(slope[i, j])


def test_training_lowers_the_loss_of_the_output_layer():
    """One step from the start must follow the gradient of the mean cross-entropy, found by differences."""
    rng = np.random.default_rng(4)
    x, length, lang = rng.integers(97, 123, (40, langid.STRETCH)).astype(np.uint8), np.full(40, langid.STRETCH), np.arange(40) % 2
    x[lang == 0, ::2] = 32

    def loss(model):
        p, _ = model._labels(np.ascontiguousarray(x.T))
        return -np.log(p[:, np.arange(40), lang]).mean()

    model = langid.Model(["a", "b"], 4)
    before = loss(model)
    slopes = {}
    for name, weight in (("out", model.out), ("bias", model.bias), ("byte", model.ways[0].byte)):
        at = (0, 1) if weight.ndim == 2 else (1,)
        at = (32, 1) if name == "byte" else at
        held = weight[at]
        weight[at] = held + 0.01
        slopes[name] = loss(model) - before, weight, at, held
        weight[at] = held
    model.train(x, length, lang, steps=1, batch=400, rate=0.001)
    for up, weight, at, held in slopes.values():
        assert (weight[at] - held) * up <= 0
    model.train(x, length, lang, steps=60, batch=40)
    assert loss(model) < 0.5 * before


def test_only_letters_tell_a_language(spark):
    assert not any(map(langid.has_letter, ["", "\u00b2\u00b2\u00b2 123", "\u00bd \u2460 \u2163 _ 7", "!?"])) and all(map(langid.has_letter, ["a", "1\u65e5", "\u00b2\u00e9"]))
    rows = [(i, "the quick brown fox and the dog", "en", "the") for i in range(12)] + [(20 + i, "der schnelle braune fuchs und der hund", "de", "x") for i in range(12)]
    rows += [(0, "\u00b2\u00b2\u00b2 123", None, ""), (None, "123", None, ""), (None, "the lazy dog and the fox", None, ""), (20, "...", None, "")]
    table = spark.createDataFrame(rows, "doc_id long, text string, lang string, score string").withColumn("a.b", F.lit(1)).withColumn("c`d e", F.lit(2))
    said = [(r.doc_id, r.lang_pred, r.score) for r in langid.identify(table).collect()]
    assert said.count((0, "und", 0.0)) == said.count((None, "und", 0.0)) == said.count((20, "und", 0.0)) == 1
    kept = Counter((r.doc_id, r.text) for r in langid.accepted(table).collect())
    assert langid.accepted(table).columns == table.columns
    assert kept == Counter((i, t) for i, t, _, _ in rows if langid.has_letter(t))  # rows without letters go, their namesakes stay


def test_many_languages(spark, monkeypatch):
    rows = [(j, chr(0x4E00 + 40 * (j % 300)) * 30, f"l{j % 300}") for j in range(1500)]
    got = langid.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert len(got) == 1500 and all(0 <= r.score <= 1 and r.lang_pred.startswith("l") for r in got)
    monkeypatch.setattr(langid, "MAX_LANGS", 5)
    langs, sample = langid.training_sample(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert len(langs) == 5 and {k for _, k in sample} <= set(langs)


def test_language_id(docs, odd, empty):
    got = {r.doc_id: r for r in langid.identify(docs).collect()}
    lang = {r.doc_id: r.lang for r in docs.collect()}
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) and 0 <= r.score <= 1 for i, r in got.items())
    held = [i for i, r in got.items() if r.held_out]
    assert sum(got[i].lang_pred == lang[i] for i in held) / len(held) > 0.9
    said = {r.doc_id: r.lang_pred for r in langid.identify(odd).collect()}
    assert said[0] == said[1] == said[2] == "und" and said[4] != "und"
    assert langid.identify(empty).count() == 0 and langid.accepted(odd).columns == odd.columns


# --- 7 -----------------------------------------------------------------------------------------
def words(text):
    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def test_decontamination(spark, sf, docs, odd, empty):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    extra = spark.createDataFrame([(9001, "Five words"), (9002, None), (9003, ""), (9001, "Five words")], "item_id long, text string")
    bench = bench.unionByName(extra)
    more = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(7001, "x five WORDS, five words y"), (7002, None)], "doc_id long, text string"))
    windows: dict = {}
    for r in bench.collect():
        w = words(r.text)
        for i in range(max(1, len(w) - 9) if w else 0):
            windows.setdefault(tuple(w[i : i + 10]), set()).add(r.item_id)
    lengths = {len(w) for w in windows}
    want = {}
    for r in more.collect():
        w, hit, items = words(r.text), set(), set()
        for i in range(len(w)):
            for n in lengths:
                if i + n <= len(w) and tuple(w[i : i + n]) in windows:
                    hit.update(range(i, i + n))
                    items |= windows[tuple(w[i : i + n])]
        want[r.doc_id] = (len(w), len(hit), sorted(items, key=str))
    index = decontam.build_index(more)
    got = {r.doc_id: (r.n_words, r.n_hit, r["items"]) for r in decontam.search(index, bench).collect()}
    assert got == want and want[7001][1] == 4
    near = {r.doc_id: r.n_near for r in decontam.search(index, spark.createDataFrame([(1, "words five x")], "item_id long, text string"), slop=2).collect()}
    assert near[7001] > 0
    assert decontam.search(decontam.build_index(odd), bench).count() == odd.count()
    assert decontam.search(decontam.build_index(empty), bench).count() == 0
    assert decontam.search(index, bench.limit(0)).where("n_hit > 0").count() == 0
    assert decontam.clean(odd, bench).columns == odd.columns


def test_benchmark_in_blocks(spark, sf, docs, monkeypatch):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    items = bench.unionByName(bench.selectExpr("item_id + 500 AS item_id", "concat(substring(text, 20, 90), ' ', text) AS text"))
    index = decontam.build_index(docs)
    want = sorted((r.doc_id, r.n_words, r.n_hit, sorted(r["items"]), r.n_near) for r in decontam.search(index, items, slop=5).collect())
    monkeypatch.setattr(decontam, "PHRASE_BYTES", 3000)
    got = sorted((r.doc_id, r.n_words, r.n_hit, sorted(r["items"]), r.n_near) for r in decontam.search(index, items, slop=5).collect())
    assert [r[:4] for r in got] == [r[:4] for r in want] and any(r[2] for r in want)
    assert all(a[4] >= b[4] and (a[4] > 0) == (b[4] > 0) for a, b in zip(got, want))  # a phrase of two blocks counts in both


def test_many_empty_texts_and_common_terms(spark, monkeypatch):
    many = spark.range(120_000).selectExpr("id AS doc_id", "IF(id % 40000 = 7, 'a b c d', '') AS text").coalesce(1)
    bench = spark.createDataFrame([(1, "b c"), (2, "zz"), (3, "a a a a a a a a a a")], "item_id long, text string")
    index = decontam.build_index(many)
    assert index.count() >= 120_000 // decontam.SEGMENT_DOCS and index.agg(F.max(F.octet_length("doc_first"))).first()[0] <= 4 * decontam.SEGMENT_DOCS
    got = decontam.search(index, bench)
    assert got.count() == 120_000 and {(r.doc_id, r.n_hit) for r in got.where("n_hit > 0").collect()} == {(7, 2), (40007, 2), (80007, 2)}
    row = dict(zip(decontam._INDEX, decontam._segment([1, 2], [b"a " * 50, b"b c a " * 20])))
    phrases = decontam.Phrases([(1, b"b c"), (3, b"a a a a a a a a a a"), (4, b"c a b")])
    want = [sorted(zip(x.tolist(), y.tolist())) for x, y in zip(*[iter(decontam._search(row, phrases, 3))] * 2)]
    monkeypatch.setattr(decontam, "SEATS_AT_ONCE", 8)
    assert [sorted(zip(x.tolist(), y.tolist())) for x, y in zip(*[iter(decontam._search(row, phrases, 3))] * 2)] == want and all(want)


def test_clean_judges_every_row_by_its_own_text(spark):
    dirty, good = "one two three four five six seven eight nine ten", "a clean row of words that no item holds at all anywhere"
    rows = [(1, f"so {dirty} so"), (1, good), (None, dirty), (None, good), (2, None), (2, "")]
    bench = spark.createDataFrame([(5, dirty), (6, None), (6, "")], "item_id long, text string")
    for table in (spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(rows, "doc_id long, text string").selectExpr("1 AS row", "2 AS n_hit", "*", "3 AS items", "4 AS `a.b`")):
        got = decontam.clean(table, bench)
        assert got.columns == table.columns and Counter((r.doc_id, r.text) for r in got.collect()) == Counter([(1, good), (None, good), (2, None), (2, "")])
    assert decontam.clean(table, bench.limit(0)).count() == len(rows)


# --- 8 -----------------------------------------------------------------------------------------
def test_hot_ids_are_spread(spark):
    rows = [(None, "same text") for _ in range(2000)] + [(4, f"t{i}") for i in range(2000)] + [(100 + i, "y" * (i % 50)) for i in range(2000)]
    got = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    size, n = Counter(), Counter()
    for r in got:
        size[r.shard] += r.size
        n[r.vslot] += 1
    share = sum(size.values()) / 40
    assert len(got) == 6000 and max(size.values()) - min(size.values()) < 0.06 * share and max(n.values()) < 20
    assert sorted((r.shard, r.slot) for r in got) == [(s, i) for s, k in sorted(Counter(r.shard for r in got).items()) for i in range(k)]


def test_sharding(spark, docs, odd, empty):
    got = sharding.shard(docs).collect()
    text = {r.doc_id: r.text.encode() for r in docs.collect()}
    by: dict = {}
    for r in got:
        assert r.size == len(text[r.doc_id]) + 16 and r.text_crc32 == zlib.crc32(text[r.doc_id])
        assert r.vslot == int(hashlib.md5(str(r.doc_id).encode()).hexdigest()[:8], 16) % sharding.SLOTS
        by.setdefault(r.shard, []).append(r)
    assert all(sorted(x.slot for x in rows) == list(range(len(rows))) for rows in by.values())
    for table in (odd, empty):
        assert sharding.shard(table).count() == table.count()
    rng = random.Random(1)
    loads = {s: rng.randrange(1, 1000) for s in range(4096)}
    first = sharding.spread(loads, 40)
    size = Counter()
    for s, shard in first.items():
        size[shard] += loads[s]
    assert max(size.values()) - min(size.values()) <= 1000
    table = sharding.SlotMap(spark)
    table.save(1, first)
    assert table.edit(1, lambda placed: sharding.grow(placed, loads)) == 2
    second = table.as_dict(2)
    moved = {s for s in first if first[s] != second[s]}
    assert table.as_dict(1) == first and moved and {second[s] for s in moved} == {40}
    assert abs(sum(loads[s] for s in moved) - sum(loads.values()) / 41) < 1000


# --- 9 -----------------------------------------------------------------------------------------
PAGE = """<!DOCTYPE html><html><head><title>T &amp; t</title><style>p{}</style><script>var a="</p>";</script></head><body><nav><ul><li><a href="/a">A</a></li></ul></nav>
<div class="cookie-notice">We use cookies</div><article><h1>Head &lt;1&gt;</h1><p><b>One  two<br>three<p>Four &amp five</p><div class="share">Share!</div><!-- no --></article>
<aside><p>side</p></aside><section id="comments"><p>I like it</p></section><form><p>Mail</p></form><footer>&copy; x</footer></body></html>"""


def test_wrappers_and_text(spark, sf, empty):
    more = PAGE.replace("<p>Four", "<ul><li>a</li><li>b</li></ul><p>Four")
    bare = "<html><body><div class='top'>Menu words</div><div id='text'><p>{0} one long paragraph of words {0}.</p><p>{0} more</p></div><div>Same foot</div></body></html>"
    rows = [(1, "http://H.example/x", PAGE), (2, "https://h.example:80/y", more), (3, None, None), (4, "http://z", "")]
    rows += [(10 + i, "http://b.example/", bare.format(i)) for i in range(6)]
    got = {r.page_id: r.text for r in html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == "Head <1>\n\nOne two three\n\nFour & five"
    assert got[2] == "Head <1>\n\nOne two three\n\na\n\nb\n\nFour & five"
    assert got[3] == got[4] == "" and got[12] == "2 one long paragraph of words 2.\n\n2 more"
    a, b = html.blocks(PAGE), html.blocks(more)
    wrapper = html.align(html.shape(a), html.shape(b))
    assert html.matches(wrapper, a) and html.matches(wrapper, b) and not html.matches(html.shape(a), b)
    assert html.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def main_texts(spark, rows):
    return {r.page_id: r.text for r in html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}


def test_text_follows_the_wrappers_slots(spark):
    page = "<html><body><article><h1>T{0}</h1><div class='share'>{1}</div><p>Words {0}</p></article><div class='foot'>Same</div></body></html>"
    rows = [(i, "http://same.example/", page.format(i, "Share it")) for i in range(4)] + [(10 + i, "http://other.example/", page.format(i, f"We share {i}")) for i in range(4)]
    got = main_texts(spark, rows)
    assert got[1] == "T1\n\nWords 1" and got[11] == "T1\n\nWe share 1\n\nWords 1"
    found = html.linked_blocks(rows[0][2])
    machine, slots, matched = html.placed(found, html.json.dumps(html.shape(found)))
    assert matched and [machine.paths[s] for s in slots] == [path for path, *_ in found]
    sums = {s: [4, 40, 0, 1, 2] for s in slots}
    assert html.page_text(found, html.json.dumps(html.shape(found)), sums, {}) != html.page_text(found, html.json.dumps(html.shape(found)), sums | {slots[1]: [4, 40, 0, 1, 1]}, {})


def test_two_templates_and_no_hosts(spark):
    first = "<html><body><nav>Home</nav><article><h1>A{0}</h1><p>Text {0}</p></article></body></html>"
    second = "<html><body><nav>Home</nav><div class=content><p>Long words of page {0}</p><div class=more>Further {0}</div></div></body></html>"
    rows = [(i, url, page.format(i)) for i, (url, page) in enumerate((u, p) for u in ("http://mixed.example/", None, "no url") for p in (first, second) for _ in range(3))]
    got = main_texts(spark, rows)
    for i, (_, _, page) in enumerate(rows):
        assert got[i] == (f"A{i}\n\nText {i}" if "<article>" in page else f"Long words of page {i}\n\nFurther {i}")


def test_names_in_an_article_drop_nothing_alone(spark):
    page = """<html><body><article id="post-cookie-recipes" data-role="form"><header><h1>Head {0}</h1></header><h2 id="related-work">Related {0}</h2>
<section id="search-engines"><p>Engines {0}</p></section><p class="ad-free">Free {0}</p><div class="form-theory">Theory {0}</div><div class="related"><p><a href="/x">Link {0}</a></p></div></article></body></html>"""
    rows = [(i, "http://slug.example/", page.format(i)) for i in range(3)]
    assert main_texts(spark, rows) == {i: "\n\n".join(f"{w} {i}" for w in ("Head", "Related", "Engines", "Free", "Theory")) for i in range(3)}


def test_pages_that_leave_out_tags_or_have_odd_names(spark):
    """No end tag of head, noise words within names around and in the article, and an unclosed button: nothing is lost."""
    body = "<article><h1>H{0}</h1><p class='notice-period'>Words of {0}</p></article>"
    pages = {
        "head": "<html><head><title>t</title><meta charset=x><body><nav>Menu</nav>" + body,
        "bare": "<html><head><title>t</title><link rel=x><nav>Menu</nav>" + body,
        "side": "<html><body><nav>Menu</nav><div class='layout has-sidebar'>" + body + "</div></body></html>",
        "main": "<html><body><nav>Menu</nav><div class='no-header'><main><h1>H{0}</h1><p class='notice-period'>Words of {0}</p></main></div></body></html>",
        "button": "<html><body><nav>Menu</nav><button class=x>" + body + "</body></html>",
    }
    rows = [(10 * k + i, f"http://{name}.example/", page.format(i)) for k, (name, page) in enumerate(pages.items()) for i in range(4)]
    assert main_texts(spark, rows) == {10 * k + i: f"H{i}\n\nWords of {i}" for k in range(len(pages)) for i in range(4)}


def _host_texts(pages: list[str], align) -> list[str]:
    """The whole method for one host, in one process."""
    found = [html.linked_blocks(p) for p in pages]
    whole = None
    for text in sorted({html.json.dumps(html.shape(html.blocks(p))) for p in pages}):
        whole = html.json.loads(text) if whole is None else align(whole, html.json.loads(text))
    wrapper, sums = html.json.dumps(whole), {}
    for f in found:
        _, slots, matched = html.placed(f, wrapper)
        for s, (n, chars, linked, low, high) in html._sums(f, slots).items() if matched else ():
            old = sums.setdefault(s, [0, 0, 0, low, high])
            old[:] = old[0] + n, old[1] + chars, old[2] + linked, min(old[3], low), max(old[4], high)
    return [html.page_text(f, wrapper, sums, {}) for f in found]


def test_the_inferred_wrapper_decides_the_text(spark):
    page = "<html><body><article><h1>T{0}</h1>{1}<div class='share'>Share it</div><p>Words {0}</p></article></body></html>"
    pages = [page.format(i, "<h2>More</h2>" * (i % 2)) for i in range(6)]
    want = _host_texts(pages, html.align)
    assert want == [f"T{i}\n\n" + "More\n\n" * (i % 2) + f"Words {i}" for i in range(6)]
    assert main_texts(spark, [(i, "http://w.example/", p) for i, p in enumerate(pages)]) == dict(enumerate(want))
    assert _host_texts(pages, lambda a, b: []) != want and _host_texts(pages, lambda a, b: a) != want


def test_hosts_with_many_shapes_merge_in_a_tree(spark, monkeypatch):
    page = "<html><body><article><h1>T{0}</h1>{1}<div class='share'>Share it</div><p>Words {0}</p></article></body></html>"
    odd_parts = ["<h2>a</h2>", "<ul><li>b</li></ul>", "<section><p>c</p></section>", "<table><tr><td>d</td></tr></table>", "<h3>e</h3>"]
    pages = [page.format(i, "".join(x for k, x in enumerate(odd_parts) if i >> k & 1)) for i in range(32)]
    rows = [(i, "http://tree.example/", p) for i, p in enumerate(pages)]
    want = main_texts(spark, rows)
    monkeypatch.setattr(html, "SHAPES_AT_ONCE", 3)
    assert main_texts(spark, rows) == want
    letters = "abcde"
    assert all(want[i] == "\n\n".join([f"T{i}", *(letters[k] for k in range(5) if i >> k & 1), f"Words {i}"]) for i in range(32))


def test_pages_against_the_articles(spark, sf):
    """Brute force over the whole table: the blocks inside <article>, markup dropped."""
    pages = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    got = {r.page_id: r.text for r in html.extract(spark.read.parquet(f"{sf}/pages.parquet")).collect()}
    for i, page in pages.items():
        inner = re.search(r"<article[^>]*>(.*)</article>", page, re.S)[1]
        parts = re.split(r"</?(?:h1|h2|h3|p|li|ul|div|section)\b[^>]*>", re.sub(r"<!--.*?-->|<(script|style)\b.*?</\1>", "", inner, flags=re.S))
        texts = [re.sub(r"\s+", " ", html.html_lib.unescape(re.sub(r"<[^>]+>", lambda m: " " if m[0].startswith("<br") else "", p))).strip() for p in parts]
        assert got[i] == "\n\n".join(filter(None, texts)), i
    clash = spark.read.parquet(f"{sf}/pages.parquet").selectExpr("*", "1 AS host", "2 AS wrapper", "3 AS slots", "4 AS part", "5 AS shape")
    assert {r.page_id: r.text for r in html.extract(clash).collect()} == got


# --- 10 ----------------------------------------------------------------------------------------
def test_chat_events(spark):
    events = [
        (1, 0, 1, 0, "delta", "user", "Hi "), (1, 0, 1, 1, "delta", "user", "there"), (1, 1, 1, 2, "delta", "assistant", "No"), (1, 1, 1, 3, "regenerate", "assistant", None),
        (1, 1, 1, 4, "delta", "assistant", "Ye"), (1, 1, 1, 5, "delta", "assistant", "s[INST]"), (1, 0, 1, 6, "edit", "user", "Hello \\ </s>"), (2, 0, 1, 0, "delta", None, None), (2, 1, 1, 1, "delta", "tool<x", "42"),
    ]
    log = spark.createDataFrame(events, "conv_id long, turn long, row int, seq long, kind string, role string, text string")
    got = {r.conv_id: r for r in chat.read_back(chat.format_log(log)).collect()}
    assert [(t.role, t.text) for t in got[1].turns] == [("user", "Hello \\ </s>"), ("assistant", "Yes[INST]")] and got[1].learned == "Yes[INST]"
    assert [(t.role, t.text) for t in got[2].turns] == [("", ""), ("tool<x", "42")] and got[2].learned == ""
    assert got[1].formatted.count("</s>") == 2 and got[1].formatted.count("[INST]") == 1
    assert chat.format_log(log.limit(0)).count() == 0


def test_chat_query_matches_sql(spark, sf):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW conversations AS SELECT * FROM '{sf}/conversations.parquet'")
    want = con.execute(ORACLES["op10_chat_format"]).df()
    got = QUERIES["op10_chat_format"](spark, sf).toPandas()[list(want.columns)]
    assert sorted(map(tuple, want.to_numpy().tolist())) == sorted(map(tuple, got.to_numpy().tolist())) and HOSTILE_ID in set(got["conv_id"])


# --- pipeline ----------------------------------------------------------------------------------
def test_pipeline(spark, sf, docs, empty):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "near_dedup", "decontamination", "mixing", "sharding"]
    kept = docs
    for _, step in corpus_pipeline.STAGES[:-1]:
        kept = step(spark, kept, sf)
        assert kept.columns == docs.columns
    for _, step in corpus_pipeline.STAGES:
        assert step(spark, empty.select(docs.columns), sf).count() == 0
    out = corpus_pipeline.run(spark, sf).collect()
    assert Counter(r.doc_id for r in out) == Counter(r.doc_id for r in kept.collect())
    assert sorted((r.shard, r.slot) for r in out) == [(s, i) for s, n in sorted(Counter(r.shard for r in out).items()) for i in range(n)]


def test_stages_on_awkward_rows(spark, sf, odd, docs):
    """Null and repeated ids, clashing names: every stage against what it must do to each row, before the corpus goes on."""
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    passage = bench.orderBy("item_id").first().text
    more = [(None, passage), (4, passage), (None, None), (None, "a b c"), (4, "123 456"), (3, "three clean words and then some more of them")]
    rows = [(i, t, "en", "s", 0, 1, 1.0, 1, 1, 1, 1) for i, t in more]
    table = odd.unionByName(spark.createDataFrame(rows, SCHEMA)).unionByName(docs.select("doc_id", "text", "lang", "source", "n_chars"), allowMissingColumns=True)
    whole = Counter((r.doc_id, r.text) for r in table.collect())
    steps = dict(corpus_pipeline.STAGES)

    kept = common.stage(steps["language_id"](spark, table, sf), "test")
    model = langid.fit(table)
    said = {t: p for t in {t for _, t in whole} for p in [dict(zip(("lang", "score"), (x[0] for x in langid.judge(model, [pa_scalar(t)]))))]}
    assert Counter((r.doc_id, r.text) for r in kept.collect()) == Counter({k: n for k, n in whole.items() if said[k[1]]["lang"] != "und" and said[k[1]]["score"] >= 0.3})

    single = common.stage(steps["near_dedup"](spark, kept, sf), "test")
    before = [(r.doc_id, r.text) for r in kept.collect()]
    roots = brute_components([brute_fingerprint(t) for _, t in before], list(range(len(before))))
    groups: dict = {}
    for root, row in zip(roots, before):
        groups.setdefault(root, []).append(row)
    after = Counter((r.doc_id, r.text) for r in single.collect())
    least = [min(g, key=lambda x: (x[0] is None, x[0] or 0))[0] for g in groups.values()]
    assert Counter(i for i, _ in after.elements()) == Counter(least) and not after - Counter(before)

    clean = common.stage(steps["decontamination"](spark, single, sf), "test")
    windows = {tuple(w[i : i + 10]) for r in bench.collect() for w in [words(r.text)] for i in range(max(1, len(w) - 9) if w else 0)}
    hit = lambda t: any(tuple(w[i : i + n]) in windows for w in [words(t)] for n in {len(x) for x in windows} for i in range(len(w) - n + 1))
    assert Counter((r.doc_id, r.text) for r in clean.collect()) == Counter({k: n for k, n in after.items() if not hit(k[1])})

    mixed = common.stage(steps["mixing"](spark, clean, sf), "test")
    drawn, got = mixing.mix(clean, root="round").collect(), Counter((r.doc_id, r.text) for r in mixed.collect())
    goal = {r.source: r.target for r in drawn}
    longest = max(r.size for r in drawn)
    size: Counter = Counter()
    for r in mixed.collect():
        size[r.source] += len(re.findall(mixing.WORD, r.text or ""))
    assert all(abs(size[s] - goal[s]) < longest for s in goal) and all(n <= 3 * kept_n for k, n in got.items() for kept_n in [Counter((r.doc_id, r.text) for r in clean.collect())[k]])
    placed = steps["sharding"](spark, mixed, sf).collect()
    assert Counter(r.doc_id for r in placed) == Counter(i for i, _ in got.elements())


def pa_scalar(value):
    import pyarrow as pa

    return pa.scalar(value, pa.string())
