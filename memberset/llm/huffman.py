"""Token ids as canonical, length-limited Huffman code.

Encoding: texts are cut, a block of bytes at a time, where white space begins and where letters, digits and
punctuation meet, places that no byte-level pre-token spans, so the ids of a text are those of its pieces in a
row. Arrow numbers the distinct pieces of a block; each worker keeps the ids of pieces it has met, and only new
ones go to the tokenizers library (whole texts with a special token go to it as they are).
Ids are counted over the whole corpus, the counts give code lengths by package-merge, the lengths
alone give the canonical code.

File format: a folder with ``codebook`` (Parquet: id, length) and ``blocks`` (Parquet, rows in
ascending (part, block)); a block holds whole documents: their ids and token counts, the byte
offsets where each begins (documents are byte-aligned), the payload, and the bit offset of every
``CHECKPOINT``-th token of each document, so that any stretch can be decoded on its own. The decoder reads
``max_len`` bits at every checkpoint of a batch at once and looks up token and length in one table.

Defined results: null text = empty text (only the end id); null doc_id sorts first; repeated rows
are kept, ties of doc_id go by token count and then code; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_text, fresh_path, stage

CHECKPOINT = 64
BLOCK_BYTES = 256 << 10
MAX_LEN = 16
# Byte classes; a piece ends between two different ones of LETTER, DIGIT and PUNCT, and where SPACE begins after any but HOLD.
_OTHER, _LETTER, _DIGIT, _PUNCT, _SPACE, _HOLD = range(6)
_CLASS = np.full(256, _OTHER, np.uint8)  # the apostrophe stays OTHER: it may open a contraction
for _b in range(128):
    _c = chr(_b)
    _CLASS[_b] = _LETTER if _c.isalpha() else _DIGIT if _c.isdigit() else _SPACE if _c in "\t\n\v\f\r " else _HOLD if not _c.isprintable() else _OTHER if _c == "'" else _PUNCT
_ENDS = np.zeros((8, 8), bool)
_ENDS[_OTHER : _PUNCT + 1, _SPACE] = True
_ENDS[_LETTER : _PUNCT + 1, _LETTER : _PUNCT + 1] = ~np.eye(3, dtype=bool)
_ENDS = _ENDS.ravel()
# UTF-8 of the white space beyond ASCII.
_WHITE = rb"\xc2[\x85\xa0]", rb"\xe1\x9a\x80", rb"\xe2\x80[\x80-\x8a\xa8\xa9\xaf]", rb"\xe2\x81\x9f", rb"\xe3\x80\x80", rb"\s"
_ALONE = re.compile(rb" ?(?!" + rb"|".join(_WHITE) + rb")[^\n]+" + b"".join(rb"(?<!%s)" % w for w in _WHITE)).fullmatch
_REMEMBERED = 256  # bytes of a piece; longer ones are encoded whenever they come
_encoders: dict[tuple, PieceEncoder] = {}  # of this worker process; tasks that follow find its pieces known


def classes(raw: np.ndarray) -> np.ndarray:
    """Class of every byte of valid UTF-8 text (a character of two or three bytes: of each that matters)."""
    kind = _CLASS[raw]
    if not (raw >= 0xC2).any():
        return kind
    # U+00C0 to U+024F are letters but for two signs.
    lead = np.flatnonzero((raw >= 0xC3) & (raw <= 0xC9))
    after = raw[lead + 1]
    sign = (raw[lead] == 0xC3) & ((after == 0x97) | (after == 0xB7)) | (raw[lead] == 0xC9) & (after > 0x8F)
    letter = lead[~sign]
    kind[letter] = kind[letter + 1] = _LETTER
    # Last byte of a white-space character beyond ASCII: no piece begins after it.
    two = np.flatnonzero(raw == 0xC2) + 1
    kind[two[(raw[two] == 0x85) | (raw[two] == 0xA0)]] = _HOLD
    three = np.flatnonzero((raw >= 0xE1) & (raw <= 0xE3))
    code = (raw[three].astype(np.int32) & 15) << 12 | (raw[three + 1].astype(np.int32) & 63) << 6 | raw[three + 2] & 63
    white = (code == 0x1680) | (code >= 0x2000) & (code <= 0x200A) | (code == 0x2028) | (code == 0x2029) | (code == 0x202F) | (code == 0x205F) | (code == 0x3000)
    kind[three[white] + 2] = _HOLD
    return kind


class PieceEncoder:
    """Texts -> little-endian ids (width 2 or 4), by remembered pieces (``keep`` twice at most)."""

    def __init__(self, path: str, width: int, keep: int = 600_000):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.special = [t.content for t in self.tok.get_added_tokens_decoder().values()]
        self.type, self.keep, self.known, self.older = f"<u{width}", keep, {}, {}
        line_end = self.tok.encode("\n", add_special_tokens=False).ids
        self.line_end = line_end[0] if len(line_end) == 1 else None

    def ids(self, text: str) -> bytes:
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, self.type).tobytes()

    def learn(self, pieces: list[bytes]) -> dict[bytes, bytes]:
        """The ids of new pieces. Those with no white space at either end, but for one space in front, go to the library many at
        a time, one a line: between them a line end is a token of its own. The others go one by one."""
        found, row, lined = {}, [], self.line_end is not None
        for p in pieces:
            if p in self.older:
                found[p] = self.older[p]
            elif lined and _ALONE(p):
                row.append(p)
            else:
                found[p] = self.ids(p.decode())
        for lo in range(0, len(row), 128):  # longer rows cost the library more a piece
            part = row[lo : lo + 128]
            ids = np.array(self.tok.encode_batch_fast([b"\n".join(part).decode()], add_special_tokens=False)[0].ids, self.type)
            cut, packed = np.flatnonzero(ids == self.line_end) * ids.itemsize, ids.tobytes()
            starts, ends = [0, *(cut + ids.itemsize).tolist()], [*cut.tolist(), len(packed)]
            if len(starts) == len(part):
                found.update(zip(part, map(packed.__getitem__, map(slice, starts, ends))))
            else:  # a line end merged with a neighbour
                found.update((p, self.ids(p.decode())) for p in part)
        if len(self.known) > self.keep:
            self.known, self.older = {}, self.known
        self.known |= found
        for p in pieces:
            if len(p) > _REMEMBERED:
                del self.known[p]
        return found

    def encode(self, texts: pa.Array, end: bytes = b"") -> tuple[np.ndarray, np.ndarray]:
        """A string column without nulls -> the ids of all its texts in a row, each followed by ``end``; bounds of each."""
        texts = texts.cast(pa.large_string())
        bound = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[bound[0] : bound[-1]]
        bound = bound - bound[0]
        kind = classes(raw)
        starts = np.zeros(len(raw), bool)
        starts[1:] = _ENDS[kind[:-1] << 3 | kind[1:]]
        for s in self.special:
            for i in np.flatnonzero(pc.match_substring(texts, s).to_numpy(zero_copy_only=False)):
                starts[bound[i] : bound[i + 1]] = False
        starts[bound[:-1][np.diff(bound) > 0]] = True
        first = np.flatnonzero(starts)
        pieces = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(first), [None, pa.py_buffer(np.append(first, len(raw))), pa.py_buffer(raw)])
        numbered = pieces.dictionary_encode()
        distinct = numbered.dictionary.to_numpy(zero_copy_only=False).tolist()
        codes = list(map(self.known.get, distinct))
        if None in codes:
            new = self.learn([p for p, c in zip(distinct, codes) if c is None])
            codes = [new[p] if c is None else c for p, c in zip(distinct, codes)]
        closes = np.searchsorted(first, bound[1:])  # pieces up to the end of each text
        order = np.insert(numbered.indices.to_numpy(), closes, len(codes))
        out = pa.array([*codes, end], pa.large_binary()).take(pa.array(order))
        at = np.frombuffer(out.buffers()[1], np.int64)[: len(out) + 1]
        ids = np.frombuffer(out.buffers()[2] or b"", self.type, at[-1] // np.dtype(self.type).itemsize)
        return ids, np.append(0, at[closes + np.arange(1, len(texts) + 1)]) // ids.itemsize

    def batch(self, texts: list[str]) -> list[bytes]:
        ids, bound = self.encode(pa.array(texts, pa.string()))
        return [ids[b:e].tobytes() for b, e in zip(bound, bound[1:])]


def encoder_of(path: str, width: int) -> PieceEncoder:
    if (path, width) not in _encoders:
        _encoders[path, width] = PieceEncoder(path, width)
    return _encoders[path, width]


def code_lengths(counts: np.ndarray, limit: int) -> np.ndarray:
    """Optimal code lengths of at most ``limit`` bits for positive counts (package-merge)."""
    n = len(counts)
    if n == 1:
        return np.ones(1, np.uint8)
    if n > 1 << limit:
        raise ValueError("more symbols than codes of that length")
    order = np.argsort(counts, kind="stable")
    leaf = counts[order].astype(np.int64)
    level, merged_from = leaf, []
    for _ in range(limit - 1):
        pairs = level[: len(level) // 2 * 2].reshape(-1, 2).sum(1)
        both = np.concatenate([leaf, pairs])
        rank = np.argsort(both, kind="stable")
        merged_from.append(rank < n)
        level = both[rank]
    # Walk back: of the first 2n-2 items of the last level, leaves count once, packages open in pairs.
    take, depth = 2 * n - 2, np.zeros(n, np.int64)
    for is_leaf in reversed(merged_from):
        leaves = int(is_leaf[:take].sum())
        depth[:leaves] += 1
        take = 2 * (take - leaves)
    depth[:take] += 1
    out = np.empty(n, np.uint8)
    out[order] = depth
    return out


def canonical(ids: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes in order of (length, id); returns (order, code of each in that order)."""
    if not len(ids):
        return ids, ids
    order = np.lexsort((ids, lengths))
    ranked = lengths[order].astype(np.int64)
    top = int(ranked[-1])
    step = np.left_shift(1, top - ranked)
    return order, (np.cumsum(step) - step) >> (top - ranked)


class Codec:
    def __init__(self, ids: np.ndarray, lengths: np.ndarray):
        order, codes = canonical(ids, lengths)
        self.top = int(lengths.max()) if len(lengths) else 1
        size = int(ids.max()) + 1 if len(ids) else 1
        # One look-up each way: the code, or the token, above five bits of length.
        self.entry = np.zeros(size, np.uint32)
        self.entry[ids[order]] = (codes.astype(np.int64) << 5) | lengths[order]
        spread = np.left_shift(1, self.top - lengths[order].astype(np.int64)) if len(ids) else np.zeros(0, np.int64)
        self.token_at = np.ones(1 << self.top, np.uint32)
        self.token_at[: spread.sum()] = np.repeat((ids[order].astype(np.int64) << 5) | lengths[order], spread)

    def encode(self, ids: np.ndarray, n: np.ndarray) -> tuple[bytes, np.ndarray, np.ndarray]:
        """ids of documents of n tokens each (one at least) -> payload, byte start of each document, bit offsets of checkpoints."""
        entry = self.entry[ids]
        bits = (entry & 31).astype(np.int64)
        end = np.cumsum(bits)
        last = np.cumsum(n) - 1
        used = np.diff(end[last], prepend=0)
        doc_bytes = -(-used // 8)
        byte0 = np.cumsum(doc_bytes) - doc_bytes
        shift = 8 * byte0 - (end[last] - used)
        at = end - bits + np.repeat(shift, n)
        # Each code falls into one or two 64-bit words (big-endian bit order).
        word, room = at >> 6, 64 - (at & 63) - bits
        code = (entry >> 5).astype(np.uint64)
        over = np.maximum(-room, 0).astype(np.uint64)
        head = (code >> over) << np.maximum(room, 0).astype(np.uint64)
        cut = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
        out = np.zeros(int(doc_bytes.sum()) // 8 + 2, np.uint64)
        out[word[cut]] = np.bitwise_or.reduceat(head, cut)
        spill = np.flatnonzero(room < 0)
        out[word[spill] + 1] |= code[spill] << (64 + room[spill]).astype(np.uint64)
        payload = out.byteswap().tobytes()[: int(doc_bytes.sum())]
        return payload, byte0, at[_checkpoints(n)]

    def decode(self, payload: bytes, starts: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Tokens from independent stretches: bit offset and token count of each (``CHECKPOINT`` at most)."""
        raw = np.frombuffer(payload + bytes(8), np.uint8)
        words = np.ndarray((len(payload) + 1,), ">u4", raw, strides=(1,))
        first = np.cumsum(n) - n
        out = np.empty(int(n.sum()), np.uint32)
        at, drop, mask = starts.astype(np.int64), 32 - self.top, (1 << self.top) - 1
        order = np.argsort(-n, kind="stable")
        at, first, alive = at[order], first[order], n[order]
        for step in range(int(n.max()) if len(n) else 0):
            k = int(np.searchsorted(-alive, -step, side="left"))  # stretches with more than `step` tokens
            at, first = at[:k], first[:k]
            look = (words[at >> 3].astype(np.int64) >> (drop - (at & 7))) & mask
            token = self.token_at[look]
            out[first + step] = token >> 5
            at = at + (token & 31)
        return out


def _checkpoints(n: np.ndarray) -> np.ndarray:
    """Positions, in the row of all tokens, of every CHECKPOINT-th token of each document."""
    per = -(-n // CHECKPOINT)
    doc = np.repeat(np.arange(len(n)), per)
    return (np.cumsum(n) - n)[doc] + CHECKPOINT * (np.arange(len(doc)) - np.repeat(np.cumsum(per) - per, per))


def tokenize(docs: DataFrame, path: str, width: int, end_id: int = 0, chunk_bytes: int = 8 << 20) -> DataFrame:
    """(doc_id, n, ids) and, once per task, a row of (id, count) pairs in ``counts``."""
    source = doc_text(docs)
    id_type = source.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = encoder_of(path, width), np.array([end_id], f"<u{width}").tobytes()
        total = np.zeros(1, np.int64)
        names, kind = ["doc_id", "n", "ids", "counts"], None
        for batch in batches:
            kind = batch.column(0).type
            ends = np.cumsum(pc.binary_length(batch.column(1)).to_numpy().astype(np.int64))
            lo = 0
            while lo < batch.num_rows:  # whole texts, of about chunk_bytes together
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + chunk_bytes, side="right")))
                ids, bound = encoder.encode(batch.column(1).slice(lo, hi - lo), end)
                part = np.bincount(ids)
                total = np.pad(total, (0, max(0, len(part) - len(total))))
                total[: len(part)] += part
                packed = pa.LargeBinaryArray.from_buffers(pa.large_binary(), hi - lo, [None, pa.py_buffer(bound * width), pa.py_buffer(ids)]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(np.diff(bound)), packed, pa.nulls(hi - lo, pa.binary())], names)
                lo = hi
        if kind is not None:
            seen = np.flatnonzero(total)
            blob = np.stack([seen, total[seen]]).astype("<i8").tobytes()
            yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.array([blob], pa.binary())], names)

    return source.mapInArrow(run, f"doc_id {id_type}, n long, ids binary, counts binary")


def count_ids(tokens: DataFrame) -> DataFrame:
    """(id, count) over the corpus from the per-task counts, summed per partition before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, int] = {}
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                for i, c in np.frombuffer(blob, "<i8").reshape(2, -1).T.tolist():
                    total[i] = total.get(i, 0) + c
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int64()), pa.array(list(total.values()), pa.int64())], ["id", "count"])

    parts = tokens.where("counts is not null").select("counts").mapInArrow(run, "id long, count long")
    return parts.groupBy("id").agg(F.sum("count").alias("count"))


_BLOCKS = "part int, block long, first long, doc_ids array<{id}>, doc_tokens binary, doc_starts binary, marks binary, payload binary"


def write_files(docs: DataFrame, path: str, vocab_size: int, end_id: int = 0, folder: str | None = None, max_len: int = MAX_LEN) -> str:
    """Tokenise, count, code and write the files; returns their folder."""
    spark = docs.sparkSession
    folder = folder or fresh_path(spark, "huffman")
    width = 2 if vocab_size <= 1 << 16 else 4
    tokens = stage(tokenize(docs, path, width, end_id), "tokens")
    counts = count_ids(tokens).orderBy("id").toPandas()  # one row per id of the vocabulary at most
    ids = counts["id"].to_numpy(np.int64)
    limit = max(max_len, int(np.ceil(np.log2(max(2, len(ids))))) + 1)
    if limit > 25:
        raise ValueError("the decoder reads 25 bits at a time at most")
    lengths = code_lengths(counts["count"].to_numpy(np.int64), limit) if len(ids) else np.zeros(0, np.uint8)
    book = pa.table({"id": ids, "length": lengths.astype(np.int32)})
    spark.createDataFrame(book.to_pandas(), "id long, length int").coalesce(1).write.parquet(f"{folder}/codebook")
    codec = spark.sparkContext.broadcast((ids, lengths))  # bounded by the vocabulary

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = Codec(*codec.value)
        for batch in batches:
            values = batch.column(2).to_pylist()
            n, out, marks = batch.column(1).to_numpy(), [], []
            cut, size = [0], 0
            for i, v in enumerate(values):
                size += len(v)
                if size >= BLOCK_BYTES or i == len(values) - 1:
                    cut.append(i + 1)
                    size = 0
            for lo, hi in zip(cut, cut[1:]):
                payload, byte0, at = code.encode(np.frombuffer(b"".join(values[lo:hi]), f"<u{width}"), n[lo:hi])
                ends = np.append(byte0[1:], len(payload))
                per = np.cumsum(-(-n[lo:hi] // CHECKPOINT))
                for b, e, m in zip(byte0.tolist(), ends.tolist(), np.split(at, per[:-1])):
                    out.append(payload[b:e])
                    marks.append((m - 8 * b).astype("<u4" if 8 * (e - b) < 1 << 32 else "<u8").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.binary()), pa.array(marks, pa.binary())], ["doc_id", "n", "code", "marks"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, block, first = TaskContext.get().partitionId(), 0, 0
        for batch in batches:
            codes, all_marks = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            n, lo, size = batch.column(1).to_numpy(), 0, 0
            for i, code in enumerate(codes):
                size += len(code)
                if size < BLOCK_BYTES and i < len(codes) - 1:
                    continue
                hi = i + 1
                starts = np.array([0, *accumulate(map(len, codes[lo:hi]))], "<u8")[:-1]
                row = [
                    pa.array([part], pa.int32()), pa.array([block], pa.int64()), pa.array([first], pa.int64()),
                    pa.array([batch.column(0).slice(lo, hi - lo).to_pylist()], pa.list_(batch.column(0).type)),
                    *(pa.array([x], pa.binary()) for x in (n[lo:hi].astype("<u8").tobytes(), starts.tobytes(), b"".join(all_marks[lo:hi]), b"".join(codes[lo:hi]))),
                ]
                yield pa.RecordBatch.from_arrays(row, ["part", "block", "first", "doc_ids", "doc_tokens", "doc_starts", "marks", "payload"])
                block, first, lo, size = block + 1, first + int(n[lo:hi].sum()), hi, 0

    id_type = tokens.schema["doc_id"].dataType.simpleString()
    coded = tokens.where("n is not null").select("doc_id", "n", "ids").mapInArrow(encode, f"doc_id {id_type}, n long, code binary, marks binary")
    coded = coded.withColumn("row", F.monotonically_increasing_id())
    nulls, bounds = _bounds(tokens.where("n is not null").select("doc_id"), int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = coded.repartitionById(nulls + len(bounds) + 1, _place(nulls, bounds))
    ranged.sortWithinPartitions("doc_id", "n", "row").drop("row").mapInArrow(pack, _BLOCKS.format(id=id_type)).write.option("compression", "none").parquet(f"{folder}/blocks")
    return folder


def _bounds(ids: DataFrame, parts: int) -> tuple[int, list]:
    """Of about ``parts`` equal shares: how many are for null ids, and upper bounds of the others (approximate
    quantiles, one small row). An id that fills several shares is a bound several times."""
    n, some = ids.agg(F.count("*"), F.count("doc_id")).first()
    nulls = -(-parts * (n - some) // n) if n else 0
    rest = parts - nulls
    if rest < 2 or not some:
        return nulls, []
    row = ids.agg(F.percentile_approx("doc_id", [i / rest for i in range(1, rest)], 50 * parts).alias("q")).first()
    return nulls, list(row["q"])


def _place(nulls: int, bounds: list):
    """Part of a row, rising with its id, null ids first. A row whose id is a bound goes to any part on either side of it, by its number."""
    salt = F.xxhash64("row")
    below, upto = F.lit(0), F.lit(0)
    for b in bounds:
        below = below + (F.col("doc_id") > F.lit(b)).cast("int")
        upto = upto + (F.col("doc_id") >= F.lit(b)).cast("int")
    return F.coalesce(F.lit(nulls) + below + F.pmod(salt, upto - below + 1), F.pmod(salt, F.lit(max(1, nulls)))).cast("int")


def read_files(spark: SparkSession, folder: str, with_ids: bool = False) -> DataFrame:
    """Decode the files: doc_id, start, n_tokens, ids_crc32 and, if asked for, the ids."""
    book = spark.read.parquet(f"{folder}/codebook").toPandas()
    blocks = spark.read.parquet(f"{folder}/blocks")
    sums = blocks.groupBy("part").agg(F.max(F.struct("first", "block", "doc_tokens")).alias("last")).select("part", "last.first", "last.doc_tokens")
    ends = {r["part"]: r["first"] + int(np.frombuffer(r["doc_tokens"], "<u8").sum()) for r in sums.collect()}  # a row per file
    parts = sorted(ends)
    offset = dict(zip(parts, [0, *accumulate(ends[p] for p in parts)]))
    shared = spark.sparkContext.broadcast((book["id"].to_numpy(np.int64), book["length"].to_numpy(np.uint8), offset))
    kind = blocks.schema["doc_ids"].dataType.elementType.simpleString()

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, lengths, base = shared.value
        codec = Codec(ids, lengths)
        for batch in batches:
            part, first, blobs = batch.column(0).to_pylist(), batch.column(1).to_pylist(), [batch.column(i) for i in range(3, 7)]
            for r in range(batch.num_rows):
                n, begin = (np.frombuffer(blobs[i][r].as_py(), "<u8").astype(np.int64) for i in (0, 1))
                payload = blobs[3][r].as_py()
                per = -(-n // CHECKPOINT)
                wide = len(blobs[2][r].as_py()) == 8 * int(per.sum())
                marks = np.frombuffer(blobs[2][r].as_py(), "<u8" if wide else "<u4").astype(np.int64) + np.repeat(8 * begin, per)
                index = np.arange(int(per.sum())) - np.repeat(np.cumsum(per) - per, per)
                tokens = codec.decode(payload, marks, np.minimum(CHECKPOINT, np.repeat(n, per) - CHECKPOINT * index)).astype("<u4")
                raw, end = memoryview(tokens.tobytes()), np.cumsum(n)
                crc = [zlib.crc32(raw[4 * (e - k) : 4 * e]) for e, k in zip(end.tolist(), n.tolist())]
                columns = [batch.column(2).slice(r, 1).flatten(), pa.array(base[part[r]] + first[r] + end - n), pa.array(n), pa.array(crc, pa.int64())]
                if with_ids:
                    columns.append(pa.ListArray.from_arrays(pa.array(np.append(0, end), pa.int32()), pa.array(tokens.astype(np.int64))))
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: len(columns)])

    columns = blocks.select("part", "first", "doc_ids", "doc_tokens", "doc_starts", "marks", "payload")
    return columns.mapInArrow(decode, f"doc_id {kind}, start long, n_tokens long, ids_crc32 long" + (", ids array<long>" if with_ids else ""))
