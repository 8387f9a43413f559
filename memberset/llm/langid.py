"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads UTF-8 bytes in stretches of ``STRETCH``, forwards and backwards, and gives every byte a
distribution over the languages; a document's probabilities are the mean over all its bytes. It is
trained in numpy by backpropagation through time, with the loss taken at every position, on a
bounded sample: about ``DOCS_PER_LANG`` documents per language and ``SAMPLE_DOCS`` in all (those whose hashed id lies below a
threshold taken from the language's row count), ``CUTS`` stretches of each at hashed places; the ``MAX_LANGS`` most
frequent languages are learnt. Only text and language of the
training fold (crc32 of the id modulo ``FOLDS`` is not ``HELD_OUT``) are learnt from; the id serves to choose and to split only.

Defined results: null text, or none with a letter: ``und``, score 0; a null or unlabelled language is predicted, not
learnt from; a null id counts as held out; with no training row at all everything is ``und``; repeated rows
are predicted each; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_bucket, doc_text

FOLDS, HELD_OUT = 4, 2
STRETCH = 64
HIDDEN = 8
DOCS_PER_LANG, CUTS = 400, 6
MAX_LANGS, SAMPLE_DOCS = 4096, 102_400
STEPS, BATCH, RATE, SEED = 300, 256, 0.02, 5
LANES = 2048
#: Numbers in a working array, whatever the count of languages.
CELLS = 1 << 23
_MAY_BE_LETTER = re.compile(r"[^\W\d_]")  # superscripts, fractions and letter-like numbers too


def has_letter(text: str) -> bool:
    return any(m[0].isalpha() for m in _MAY_BE_LETTER.finditer(text))


def _sigmoid(x: np.ndarray) -> np.ndarray:
    """In place: half of one plus the hyperbolic tangent of half."""
    x *= 0.5
    np.tanh(x, out=x)
    x += 1
    x *= 0.5
    return x


class Gru:
    """One direction. ``byte`` is the input weight per byte value (gates r, z, n side by side), ``loop`` the recurrent one."""

    def __init__(self, hidden: int, rng: np.random.Generator):
        self.hidden = hidden
        self.byte = rng.normal(0, 0.3, (256, 3 * hidden)).astype(np.float32)
        self.loop = rng.normal(0, hidden**-0.5, (hidden, 3 * hidden)).astype(np.float32)

    def run(self, x: np.ndarray, keep: bool = False):
        """x (steps, lanes) of bytes -> states (steps, lanes, hidden) and, if asked for, what the way back needs."""
        h, k, (steps, lanes) = np.zeros((x.shape[1], self.hidden), np.float32), self.hidden, x.shape
        states, trail = np.empty((steps, lanes, k), np.float32), []
        given, looped = np.empty((lanes, 3 * k), np.float32), np.empty((lanes, 3 * k), np.float32)
        for t in range(steps):
            np.take(self.byte, x[t], axis=0, out=given, mode="clip")
            np.matmul(h, self.loop, out=looped)
            gate = _sigmoid(given[:, : 2 * k] + looped[:, : 2 * k])
            r, z, inner = gate[:, :k], gate[:, k:], looped[:, 2 * k :]
            n = np.tanh(given[:, 2 * k :] + r * inner)
            if keep:
                trail.append((h, r, z, n, inner.copy()))
            h = n + z * (h - n)
            states[t] = h
        return states, trail

    def back(self, x: np.ndarray, trail: list, grad: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Gradients of ``byte`` and ``loop`` from those of the states, last step first."""
        d_byte, d_loop, k = np.zeros_like(self.byte), np.zeros_like(self.loop), self.hidden
        carry = np.zeros_like(grad[0])
        for t in range(len(trail) - 1, -1, -1):
            h, r, z, n, inner = trail[t]
            dh = grad[t] + carry
            dn = dh * (1 - z) * (1 - n * n)
            dz = dh * (h - n) * z * (1 - z)
            dr = dn * inner * r * (1 - r)
            into = np.concatenate([dr, dz, dn], 1)
            looped = np.concatenate([dr, dz, dn * r], 1)
            np.add.at(d_byte, x[t], into)
            d_loop += h.T @ looped
            carry = dh * z + looped @ self.loop.T
        return d_byte, d_loop


class Model:
    def __init__(self, langs: list[str], hidden: int = HIDDEN, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.langs, self.ways = langs, (Gru(hidden, rng), Gru(hidden, rng))
        self.out = rng.normal(0, 0.1, (2 * hidden, len(langs))).astype(np.float32)
        self.bias = np.zeros(len(langs), np.float32)

    def _labels(self, x: np.ndarray, keep: bool = False):
        """Distribution at every position, (steps, lanes, languages)."""
        ahead, trail_a = self.ways[0].run(x, keep)
        behind, trail_b = self.ways[1].run(x[::-1], keep)
        k = self.ways[0].hidden
        scores = ahead @ self.out[:k] + behind[::-1] @ self.out[k:] + self.bias
        scores -= scores.max(2, keepdims=True)
        np.exp(scores, out=scores)
        scores /= scores.sum(2, keepdims=True)
        return scores, (ahead, behind, trail_a, trail_b)

    def train(self, x: np.ndarray, length: np.ndarray, lang: np.ndarray, steps: int = STEPS, batch: int = BATCH, rate: float = RATE, seed: int = SEED) -> None:
        """x (stretches, STRETCH) of bytes, their true lengths and language numbers. Adam, loss at every position."""
        rng = np.random.default_rng(seed)
        weights = [self.ways[0].byte, self.ways[0].loop, self.ways[1].byte, self.ways[1].loop, self.out, self.bias]
        first, second = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights]
        share = 1 / np.bincount(lang, minlength=len(self.langs)).clip(1)[lang]
        share /= share.sum()
        k = self.ways[0].hidden
        for step in range(1, steps + 1):
            pick = rng.choice(len(x), batch, p=share)  # every language as often as any other
            rows, n, goal = x[pick].T, length[pick], lang[pick]
            p, (ahead, behind, trail_a, trail_b) = self._labels(rows, keep=True)
            p[:, np.arange(batch), goal] -= 1
            p *= (np.arange(len(rows))[:, None] < n)[:, :, None] / n.sum()
            d_ahead, d_behind = p @ self.out[:k].T, (p @ self.out[k:].T)[::-1]
            flat = p.reshape(-1, p.shape[2])
            d_out = np.concatenate([ahead.reshape(-1, k).T @ flat, behind[::-1].reshape(-1, k).T @ flat])
            grads = [*self.ways[0].back(rows, trail_a, d_ahead), *self.ways[1].back(rows[::-1], trail_b, d_behind), d_out, flat.sum(0)]
            norm = np.sqrt(sum(float((g * g).sum()) for g in grads))
            pace = rate * min(1.0, 2 * (1 - step / (steps + 1)))
            for w, g, a, b in zip(weights, grads, first, second):
                g = g / max(1.0, norm)
                a += 0.1 * (g - a)
                b += 0.01 * (g * g - b)
                w -= pace * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-8)

    def pool(self, texts: list[bytes]) -> np.ndarray:
        """Mean over all positions of each text (texts are not empty), (texts, languages)."""
        n = np.array([len(t) for t in texts])
        per = -(-n // STRETCH)
        owner = np.repeat(np.arange(len(texts)), per)
        piece = np.arange(len(owner)) - np.repeat(np.cumsum(per) - per, per)
        length = np.minimum(STRETCH, n[owner] - STRETCH * piece)
        padded = np.zeros((len(owner), STRETCH), np.uint8)
        padded[np.arange(STRETCH) < length[:, None]] = np.frombuffer(b"".join(texts), np.uint8)
        total = np.zeros((len(texts), len(self.langs)))
        lanes = max(16, min(LANES, CELLS // (STRETCH * len(self.langs))))
        for lo in range(0, len(owner), lanes):
            part = np.ascontiguousarray(padded[lo : lo + lanes].T)
            p, _ = self._labels(part)
            inside = (np.arange(STRETCH)[:, None] < length[lo : lo + lanes]).astype(np.float32)
            whose = owner[lo : lo + lanes]
            cut = np.flatnonzero(np.concatenate(([True], whose[1:] != whose[:-1])))
            total[whose[cut]] += np.add.reduceat(np.einsum("tbc,tb->bc", p, inside), cut, axis=0)
        return total / n[:, None]


def training_sample(docs: DataFrame, per_lang: int = DOCS_PER_LANG, cuts: int = CUTS) -> tuple[list[str], list[tuple[bytes, str]]]:
    """Languages of the training fold and stretches (bytes, language) of the sample."""
    fold = docs.where(F.col("lang").isNotNull() & (crc_bucket("doc_id", FOLDS) != HELD_OUT)).select("doc_id", "lang", "text")
    counts = {r["lang"]: r["count"] for r in fold.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(MAX_LANGS).collect()}
    if not counts:
        return [], []
    share = min(per_lang, max(1, SAMPLE_DOCS // len(counts)))
    chances = docs.sparkSession.createDataFrame([(k, min(1.0, share / n)) for k, n in counts.items()], "lang string, chance double")
    draw = F.shiftrightunsigned(F.xxhash64("doc_id", F.lit(SEED)), 11) / F.lit(float(1 << 53))
    span = F.greatest(F.lit(1), F.char_length("text") - STRETCH + 1)
    stretch = [F.substring("text", (F.pmod(F.xxhash64("doc_id", F.lit(100 + i)), span) + 1).cast("int"), F.lit(STRETCH)) for i in range(cuts)]
    fold = fold.join(F.broadcast(chances), "lang")  # MAX_LANGS rows at most
    rows = fold.where(draw < F.col("chance")).select("lang", F.array(*stretch).alias("cuts")).collect()
    return sorted(counts), [(c.encode()[:STRETCH], r["lang"]) for r in rows for c in r["cuts"] or [] if c and c.strip()]


def fit(docs: DataFrame, steps: int = STEPS) -> Model | None:
    langs, sample = training_sample(docs)
    if not sample:
        return None
    sample.sort()
    x = np.zeros((len(sample), STRETCH), np.uint8)
    for i, (cut, _) in enumerate(sample):
        x[i, : len(cut)] = np.frombuffer(cut, np.uint8)
    model = Model(langs)
    model.train(x, np.array([len(c) for c, _ in sample]), np.array([langs.index(k) for _, k in sample]), steps)
    return model


def judge(model: Model | None, texts: pa.Array, chunk_bytes: int = 1 << 20) -> tuple[list[str], list[float]]:
    """Language and score of every text. Long texts are read whole, stretch by stretch; a null counts as empty."""
    said, score = ["und"] * len(texts), [0.0] * len(texts)
    rows, held, size = [], [], 0

    def pooled() -> np.ndarray:
        if len(held) > 1:
            return model.pool(held)
        parts = [held[0][i : i + chunk_bytes] for i in range(0, len(held[0]), chunk_bytes)]
        return sum(model.pool([p]) * len(p) for p in parts) / len(held[0])

    def settle() -> None:
        if rows:
            p = pooled()
            for i, best, top in zip(rows, p.argmax(1).tolist(), p.max(1).tolist()):
                said[i], score[i] = model.langs[best], min(1.0, max(0.0, round(top, 6)))
            rows.clear()
            held.clear()

    for i, value in enumerate(texts):
        text = value.as_py()
        if model is None or not text or not has_letter(text):
            continue
        data = text.encode()
        if size + len(data) > chunk_bytes or len(held) * len(model.langs) >= CELLS:
            settle()
            size = 0
        rows.append(i)
        held.append(data)
        size += len(data)
    settle()
    return said, score


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score."""
    source = doc_text(docs)
    id_type = source.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            said, score = judge(model, batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(said, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

    out = source.mapInArrow(run, f"doc_id {id_type}, lang_pred string, score double")
    held = F.coalesce(crc_bucket("doc_id", FOLDS) == HELD_OUT, F.lit(True))
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score")


def identify(docs: DataFrame) -> DataFrame:
    return predict(docs, fit(docs))


def accepted(docs: DataFrame, least: float = 0.3) -> DataFrame:
    """The rows whose own text's language is told with a score of ``least`` or more, whole and in one pass.

    No id takes part: a row neither goes nor stays on account of another with its id, or for having none.
    """
    model, at = fit(docs), docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            said, score = judge(model, batch.column(at))
            yield batch.filter(pa.array([k != "und" and p >= least for k, p in zip(said, score)], pa.bool_()))

    plain = docs.toDF(*(f"c{i}" for i in range(len(docs.columns))))  # mapInArrow looks columns up by plain names
    return plain.mapInArrow(run, plain.schema).toDF(*docs.columns)
