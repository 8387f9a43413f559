"""Audio features: polyphase resampling, overlapped log-mel filterbanks, hysteresis energy segmentation.

A payload is stored as an 8-bit mono WAV file; all features come from the file's bytes as read back.
Samples are resampled from ``RATE_IN`` to ``RATE_OUT`` by a polyphase filter, cut into overlapping windows centred on hops that tile the recording,
and turned into log-mel values (8-bit steps). Segments are stretches of energy that begin above a high and end below a
low threshold, both relative to the document's median. A document's features are an Arrow stream
of clips: a fixed-shape tensor of ``CLIP`` frames x ``MELS`` (the last one padded) with its time span. The streams are
stored beside the segments as a Parquet table; what is returned is read back from there.
Recordings are worked through in stretches of ``STRETCH`` frames: beside the payload a task holds one stretch and a
fifth of the payload's bytes (16 steps and an energy per 120 samples).

Defined results: null text = empty text (a payload of padding only); equal payloads give equal
values; repeated rows are recordings of their own; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import doc_text, stage

UNIT = 192
RATE_IN, RATE_OUT = 12000, 8000
UP, DOWN, TAPS = 2, 3, 24
WINDOW, HOP, FFT, MELS = 200, 80, 256, 16
CLIP, STRETCH = 32, 4096
HIGH_DB, LOW_DB = 3.0, 1.0
HEADER = 44


def payloads(docs: DataFrame, unit: int = UNIT) -> DataFrame:
    """doc_id, n_bytes, media (a WAV file whose samples are the padded UTF-8 bytes); JVM expressions only."""
    raw = F.col("text").cast("binary")
    n = F.octet_length("text")
    full = F.greatest(F.lit(1), F.ceil(n / unit)).cast("int") * unit

    def little(c, size: int):
        hexed = F.lpad(F.hex(c.cast("long")), 2 * size, "0")
        return F.unhex(F.concat(*[F.substring(hexed, 2 * i + 1, 2) for i in reversed(range(size))]))

    fmt = F.lit(bytearray(b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, RATE_IN, RATE_IN, 1, 8) + b"data"))
    pad = F.expr(f"repeat(' ', int(greatest(1, ceil(octet_length(text) / {unit}))) * {unit} - octet_length(text))").cast("binary")
    media = F.concat(F.lit(bytearray(b"RIFF")), little(full + HEADER - 8, 4), fmt, little(full, 4), raw, pad)
    return doc_text(docs).select("doc_id", n.cast("long").alias("n_bytes"), media.alias("media"))


def samples_of(wav: bytes) -> tuple[int, bytes]:
    """(rate, samples) of an 8-bit mono WAV file."""
    if wav[:4] != b"RIFF" or wav[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, rate = 12, 0
    while at < len(wav):
        name, size = wav[at : at + 4], int.from_bytes(wav[at + 4 : at + 8], "little")
        if name == b"fmt ":
            rate = int.from_bytes(wav[at + 12 : at + 16], "little")
        if name == b"data":
            return rate, wav[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    raise ValueError("no samples")


@lru_cache
def _phases(up: int = UP, down: int = DOWN, taps: int = TAPS) -> np.ndarray:
    """Windowed-sinc low-pass in ``up`` phases of ``taps`` taps, each summing to one."""
    n = up * taps
    t = np.arange(n) - (n - 1) / 2
    h = np.sinc(t / max(up, down)) * np.hamming(n)
    bank = h.reshape(taps, up).T[:, ::-1]
    return (bank / bank.sum(1, keepdims=True)).astype(np.float32)


def _signal(x: np.ndarray, first: int, stop: int) -> np.ndarray:
    """Places first..stop of a recording as floats, its ends going on; 8-bit samples become -1..1."""
    part = x[np.clip(np.arange(first, stop), 0, len(x) - 1)].astype(np.float32)
    return (part - 128) / 128 if x.dtype == np.uint8 else part


def resample(x: np.ndarray, up: int = UP, down: int = DOWN, first: int = 0, stop: int | None = None) -> np.ndarray:
    """Samples first..stop of the recording at the other rate.

    Polyphase: every output sample is one phase of the filter at one place of the input; no zeros are stuffed.
    """
    bank = _phases(up, down)
    taps = bank.shape[1]
    stop = -(-len(x) * up // down) if stop is None else stop
    cycle0, cycles = first // up, -(-stop // up) - first // up
    near = _signal(x, cycle0 * down - taps // 2, (cycle0 + cycles) * down + taps - taps // 2)
    out = np.empty((cycles, up), np.float32)
    windows = np.lib.stride_tricks.sliding_window_view(near, taps)
    for phase in range(up):
        ahead, p = divmod(phase * down, up)
        out[:, phase] = windows[ahead : ahead + cycles * down : down][:cycles] @ bank[p]
    return out.reshape(-1)[first - cycle0 * up : stop - cycle0 * up]


@lru_cache
def _mel_bank(rate: int = RATE_OUT, fft: int = FFT, mels: int = MELS) -> np.ndarray:
    """Triangles, evenly spaced on the mel scale, over the bins of the spectrum."""
    top = 2595 * np.log10(1 + rate / 2 / 700)
    edge = 700 * (10 ** (np.linspace(0, top, mels + 2) / 2595) - 1) * fft / rate
    bins = np.arange(fft // 2 + 1)[:, None]
    rise, fall = (bins - edge[:-2]) / (edge[1:-1] - edge[:-2]), (edge[2:] - bins) / (edge[2:] - edge[1:-1])
    return np.maximum(0, np.minimum(rise, fall)).astype(np.float32)


def log_mel(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(frames x MELS in steps of a quarter, int8; energy of each frame in dB) of samples at ``RATE_IN``.

    There is a frame for every hop begun, its window centred on the hop; beyond the ends there is silence.
    """
    taper, bank, mel, energy = np.hanning(WINDOW).astype(np.float32), _mel_bank(), [], []
    n, lead = -(-len(x) * UP // DOWN), (WINDOW - HOP) // 2
    frames = max(1, -(-n // HOP))
    for lo in range(0, frames, STRETCH):
        hi = min(frames, lo + STRETCH)
        a, b = lo * HOP - lead, (hi - 1) * HOP + WINDOW - lead
        heard = np.zeros(b - a, np.float32)
        heard[max(a, 0) - a : min(b, n) - a] = resample(x, first=max(a, 0), stop=min(b, n))
        view = np.lib.stride_tricks.sliding_window_view(heard, WINDOW)[::HOP]
        spectrum = np.fft.rfft(view * taper, FFT)
        power = spectrum.real**2 + spectrum.imag**2
        mel.append(np.rint(4 * np.log(power @ bank + np.float32(1e-4))).astype(np.int8))
        energy.append((10 * np.log10(power.sum(1) + 1e-9)).astype(np.float32))
    return np.concatenate(mel), np.concatenate(energy)


def segments(energy: np.ndarray, high: float = HIGH_DB, low: float = LOW_DB) -> list[tuple[int, int]]:
    """(first frame, frame after the last): on from above median + high until below median + low."""
    middle = np.median(energy)
    said = np.where(energy > middle + high, 1, np.where(energy < middle + low, -1, 0))
    at = np.maximum.accumulate(np.where(said != 0, np.arange(len(said)), -1))
    on = np.where(at >= 0, said[at], -1) > 0
    edge = np.flatnonzero(np.diff(np.concatenate(([0], on.view(np.int8), [0]))))
    return [(int(a), int(b)) for a, b in zip(edge[::2], edge[1::2])]


def _ms(frame: int) -> int:
    return frame * HOP * 1000 // RATE_OUT


def length_ms(payload: bytes) -> int:
    return -(-len(payload) * 1000 // RATE_IN)


TENSOR = pa.fixed_shape_tensor(pa.int8(), [CLIP, MELS])


def tensors(mel: np.ndarray, end: int | None = None) -> bytes:
    """Arrow stream of the clips: start_ms, stop_ms (of the last one: end, if given), tensor."""
    clips = -(-len(mel) // CLIP)
    padded = np.zeros((clips * CLIP, MELS), np.int8)
    padded[: len(mel)] = mel
    values = pa.FixedSizeListArray.from_arrays(pa.array(padded.reshape(-1)), CLIP * MELS)
    start = [_ms(i * CLIP) for i in range(clips)]
    stop = [_ms((i + 1) * CLIP) for i in range(clips - 1)] + [_ms(len(mel)) if end is None else end]
    batch = pa.record_batch([pa.array(start, pa.int64()), pa.array(stop, pa.int64()), pa.ExtensionArray.from_storage(TENSOR, values)], ["start_ms", "stop_ms", "tensor"])
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema) as writer:
        writer.write_batch(batch)
    return sink.getvalue().to_pybytes()


def features(payload: bytes) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Log-mel frames and segments (in ms, to the recording's end at most) of 8-bit samples."""
    mel, energy = log_mel(np.frombuffer(payload, np.uint8))
    end = length_ms(payload)
    return mel, [(_ms(a), min(_ms(b), end)) for a, b in segments(energy)]


_SPANS = pa.list_(pa.struct([("start_ms", pa.int64()), ("stop_ms", pa.int64())]))
_STORED = {"payload_bytes": pa.int64(), "payload_sha256": pa.string(), "tail_crc32": pa.int64(), "media_bytes": pa.int64(), "media_sha256": pa.string(), "segments": _SPANS, "tensors": pa.binary()}
ROWS_BYTES = 32 << 20


def extract(media: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media -> digests of the samples read back, segments, and the clips as an Arrow stream."""
    id_type = media.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, lo, size = [], 0, 0
            for i, value in enumerate(batch.column(2)):
                wav = value.as_py()
                _, payload = samples_of(wav)
                mel, found = features(payload)
                blob = tensors(mel, length_ms(payload))
                spans = [{"start_ms": a, "stop_ms": b} for a, b in found]
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(wav), hashlib.sha256(wav).hexdigest(), spans, blob))
                size += len(blob)
                if size >= ROWS_BYTES or i == batch.num_rows - 1:
                    n = len(rows)
                    arrays = [pa.array([r[j] for r in rows], t) for j, t in enumerate(_STORED.values())]
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, n), batch.column(1).slice(lo, n), *arrays], ["doc_id", "n_bytes", *_STORED])
                    rows, lo, size = [], i + 1, 0

    return media.mapInArrow(run, f"doc_id {id_type}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, segments array<struct<start_ms:long,stop_ms:long>>, tensors binary")


def clips_of(stream: bytes) -> pa.Table:
    """start_ms, stop_ms, tensor of a stored stream."""
    table = pa.ipc.open_stream(stream).read_all()
    if table.schema.field("tensor").type != TENSOR:
        raise ValueError("not a stream of clips")
    return table


def _feature(stream: bytes, spans: list[dict]) -> str:
    """Frames (by the last clip's end), segments, and a digest of all values and times."""
    table, digest = clips_of(stream), hashlib.sha256()
    for name in ("start_ms", "stop_ms"):
        digest.update(table[name].combine_chunks().to_numpy().astype("<i8").tobytes())
    for part in table["tensor"].chunks:
        digest.update(part.storage.flatten().to_numpy().tobytes())
    digest.update(",".join(f"{s['start_ms']}-{s['stop_ms']}" for s in spans).encode())
    frames = -(-table["stop_ms"][-1].as_py() // _ms(1))
    return f"{frames}x{MELS}:{len(spans)}:{digest.hexdigest()[:32]}"


def read_features(stored: DataFrame) -> DataFrame:
    """The stored table with ``feature``, computed from its tensors and spans."""

    @F.arrow_udf("string")
    def feature(streams: pa.Array, spans: pa.Array) -> pa.Array:
        return pa.array([_feature(a.as_py(), b.as_py()) for a, b in zip(streams, spans)], pa.string())

    return stored.withColumn("feature", feature("tensors", "segments"))


def store_and_extract(docs: DataFrame) -> DataFrame:
    """Store every document as a WAV file (a Parquet table of them), read it back, store its features, read those back."""
    return read_features(stage(extract(stage(payloads(docs), "media")), "features"))
