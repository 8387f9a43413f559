"""Benchmark decontamination over a distributed positional inverted index.

The index is cut by documents into segments of ``SEGMENT_BYTES`` of text (a longer document is a segment of its
own) and ``SEGMENT_DOCS`` documents at most. A segment is one Parquet row: its documents with the position of their first word, its terms, and
per term the ascending list of positions; documents are ``GAP`` positions apart, so no match spans two.
Segments are independent, so building needs no shuffle and no word, however common, gathers anywhere.

A search takes phrases (the windows of the benchmark items) to every segment: a phrase with a term that the
segment lacks is out at once; else the postings of its rarest term, moved back by that term's offset,
are the candidates, and are intersected with the moved lists of the other terms from rare to common,
phrases of ``SEATS_AT_ONCE`` candidates at a time. What is left are exact phrase matches. With ``slop`` the same order of terms finds
proximity matches: places of the rarest term with every other term within the window length plus slop.
Phrases go out in blocks of about ``PHRASE_BYTES`` of benchmark text; what the blocks hit is united per document.

Defined results: null text = no words; an item without words has no window; an item shorter than a
window is one window; repeated rows are documents of their own; repeated items count once by id; empty tables give
no rows (documents) or no hits (benchmark); extra columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import columns_of, doc_text, free_name, keyed, stage

WINDOW = 10
SEGMENT_BYTES, SEGMENT_DOCS = 4 << 20, 1 << 14
GAP = 1 << 10
PHRASE_BYTES = 8 << 20
SEATS_AT_ONCE = 1 << 20
# Bytes outside words become spaces: all of ASCII but digits and letters.
_WORD_BYTES = bytes(b if b >= 0x80 or chr(b).isalnum() else 32 for b in range(256))


def words_of(text: bytes) -> list[bytes]:
    return text.lower().translate(_WORD_BYTES).split()


def _segment(ids: list, texts: list[bytes]) -> list:
    number: dict[bytes, int] = defaultdict()
    number.default_factory = number.__len__
    parts, first, n_words, at = [], [], [], 0
    for text in texts:
        words = words_of(text)
        parts.append(np.fromiter(map(number.__getitem__, words), np.int32, len(words)))
        first.append(at)
        n_words.append(len(words))
        at += len(words) + GAP
    terms = np.concatenate(parts)
    places = np.concatenate([np.arange(f, f + n, dtype=np.int64) for f, n in zip(first, n_words)])
    order = np.argsort(terms, kind="stable")
    counts = np.bincount(terms, minlength=len(number))
    return [ids, np.array(first, "<u4").tobytes(), np.array(n_words, "<u4").tobytes(), b" ".join(number), counts.astype("<u4").tobytes(), places[order].astype("<u4").tobytes()]


_INDEX = ["doc_ids", "doc_first", "doc_words", "terms", "counts", "places"]  # and segment, a name for it


def build_index(docs: DataFrame) -> DataFrame:
    """One row per segment, as Parquet in the shared folder."""
    source = doc_text(docs)
    id_type = source.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, texts, size, kind, made = [], [], 0, None, 0
        task = TaskContext.get().partitionId()

        def emit() -> pa.RecordBatch:
            nonlocal made
            row, made = _segment(ids, texts), made + 1
            columns = [pa.array([row[0]], pa.list_(kind)), *(pa.array([x], pa.binary()) for x in row[1:])]
            return pa.RecordBatch.from_arrays([*columns, pa.array([f"{task}-{made}"])], [*_INDEX, "segment"])

        for batch in batches:
            kind = batch.column(0).type
            for key, value in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.large_binary())):
                ids.append(key)
                texts.append(value.as_py())
                size += len(texts[-1])
                if size >= SEGMENT_BYTES or len(ids) == SEGMENT_DOCS:
                    yield emit()
                    ids, texts, size = [], [], 0
        if ids:
            yield emit()

    columns = ", ".join(f"{c} binary" for c in _INDEX[1:])
    return stage(source.mapInArrow(run, f"doc_ids array<{id_type}>, {columns}, segment string"), "postings")


class Phrases:
    """The search terms, the distinct phrases as rows of term numbers (-1 behind short ones), and the items that hold each."""

    def __init__(self, items: list[tuple[object, bytes]], window: int = WINDOW):
        number: dict[bytes, int] = defaultdict()
        number.default_factory = number.__len__
        parts, owner = [np.empty((0, window), np.int32)], [np.empty(0, np.int32)]
        for i, (_, text) in enumerate(items):
            words = words_of(text)
            held = np.fromiter(map(number.__getitem__, words), np.int32, len(words))
            if len(held) >= window:
                parts.append(np.lib.stride_tricks.sliding_window_view(held, window))
            elif len(held):
                parts.append(np.pad(held, (0, window - len(held)), constant_values=-1)[None])
            else:
                continue
            owner.append(np.full(len(parts[-1]), i, np.int32))
        self.terms, self.ids = list(number), [item for item, _ in items]
        self.rows, phrase = np.unique(np.concatenate(parts), axis=0, return_inverse=True)
        self.lengths = (self.rows >= 0).sum(1)
        pairs = np.unique(np.stack([phrase.reshape(-1), np.concatenate(owner)]), axis=1)
        self.first, self.owner = np.searchsorted(pairs[0], np.arange(len(self.rows) + 1)), pairs[1]

    def items(self, phrase: int) -> list:
        return [self.ids[i] for i in self.owner[self.first[phrase] : self.first[phrase + 1]].tolist()]


def _search(row: dict, phrases: Phrases, slop: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(phrase, start) of exact matches, (phrase, place) of proximity matches in one segment."""
    none = np.empty(0, np.int64)
    if not len(phrases.rows) or not row["terms"]:
        return none, none, none, none
    own = {t: i for i, t in enumerate(row["terms"].split(b" "))}
    here = np.array([own.get(t, -1) for t in phrases.terms] + [-1], np.int64)
    counts = np.frombuffer(row["counts"], "<u4").astype(np.int64)
    places = np.frombuffer(row["places"], "<u4").astype(np.int64)
    begin = np.cumsum(counts) - counts
    postings = (np.repeat(np.arange(len(counts)), counts) << 33) | places  # ascending: by term, then place
    blank = phrases.rows < 0
    local = here[phrases.rows]
    full = np.flatnonzero(~((local < 0) & ~blank).any(1))
    if not len(full):
        return none, none, none, none
    local, blank = local[full], blank[full]
    rank = np.argsort(np.where(blank, np.iinfo(np.int64).max, counts[local]), axis=1, kind="stable")
    rare = local[np.arange(len(full)), rank[:, 0]]
    reach = phrases.lengths[full] + (slop or 0)

    def narrowed(which, at, test):
        for k in range(1, rank.shape[1]):
            if not len(which):
                break
            column = rank[which, k]
            keep = blank[which, column] | test(local[which, column], at, column, which)
            which, at = which[keep], at[keep]
        return full[which], at

    def follows(term, start, column, which):
        key = (np.maximum(term, 0) << 33) | (start + column)
        found = np.minimum(np.searchsorted(postings, key), len(postings) - 1)
        return postings[found] == key

    def near(term, at, column, which):
        low = (np.maximum(term, 0) << 33) | np.maximum(at - reach[which], 0)
        found = np.minimum(np.searchsorted(postings, low), len(postings) - 1)
        return (postings[found] >= low) & (postings[found] <= ((term << 33) | (at + reach[which])))

    group = np.cumsum(counts[rare]) // SEATS_AT_ONCE
    parts = []
    for some in np.split(np.arange(len(full)), np.flatnonzero(np.diff(group)) + 1):
        n = counts[rare[some]]
        which = np.repeat(some, n)
        seat = places[np.repeat(begin[rare[some]], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
        start = seat - rank[which, 0]
        inside = start >= 0
        exact = narrowed(which[inside], start[inside], follows)
        parts.append((*exact, *((none, none) if slop is None else narrowed(which, seat, near))))
    return tuple(map(np.concatenate, zip(*parts)))


def _covered(doc: np.ndarray, start: np.ndarray, stop: np.ndarray, n: int) -> np.ndarray:
    """Words of each of n documents inside any of the spans (no span reaches into the next document)."""
    order = np.argsort(start, kind="stable")
    start, stop = start[order], stop[order]
    before = np.concatenate(([0], np.maximum.accumulate(stop)[:-1])) if len(stop) else stop
    return np.bincount(doc[order], np.maximum(0, stop - np.maximum(start, before)), n).astype(np.int64)


def search(index: DataFrame, benchmark: DataFrame, window: int = WINDOW, slop: int | None = None) -> DataFrame:
    """One row per indexed document: doc_id, n_words, n_hit, items (ids with an exact window), n_near (proximity matches).

    The benchmark's distinct rows go to the tasks block by block, dealt by hash; a block is ``PHRASE_BYTES`` of text on
    the average (an item that is longer is searched whole). The index is read once per block.
    """
    if window + (slop or 0) >= GAP:
        raise ValueError(f"window and slop must stay below the {GAP} positions between documents")
    asked = benchmark.select("item_id", F.coalesce("text", F.lit("")).alias("text")).distinct()
    size = asked.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = -(-size // PHRASE_BYTES) or 1
    if blocks == 1:
        return _search_block(index, asked, window, slop, False).drop("place", "spans")
    asked = stage(asked.withColumn("block", F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks))), "items")
    found = None
    for block in range(blocks):
        part = _search_block(index, asked.where(F.col("block") == block), window, slop, True)
        part = stage(part if block == 0 else part.where("n_hit > 0 or n_near > 0"), "hits")
        found = part if found is None else found.unionByName(part)
    same = found.groupBy("place").agg(
        F.any_value("doc_id").alias("doc_id"), F.max("n_words").alias("n_words"), F.sort_array(F.flatten(F.collect_list("spans"))).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.sum("n_near").alias("n_near"),
    )
    nothing = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("upto"))
    fresh = lambda at, s: F.greatest(F.lit(0).cast("long"), s["stop"] - F.greatest(s["start"], at["upto"]))
    union = F.aggregate("spans", nothing, lambda at, s: F.struct((at["n"] + fresh(at, s)).alias("n"), F.greatest(at["upto"], s["stop"]).alias("upto")))["n"]
    return same.select("doc_id", "n_words", union.alias("n_hit"), "items", "n_near")


def _search_block(index: DataFrame, asked: DataFrame, window: int, slop: int | None, with_spans: bool) -> DataFrame:
    spark = index.sparkSession
    items = [(r["item_id"], r["text"].encode()) for r in asked.select("item_id", "text").collect()]
    shared = spark.sparkContext.broadcast(Phrases(items, window))
    id_type = index.schema["doc_ids"].dataType.elementType.simpleString()
    kind = pa.int64() if asked.schema["item_id"].dataType.simpleString() in ("bigint", "int") else pa.string()
    span = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        phrases = shared.value
        for batch in batches:
            for r in range(batch.num_rows):
                row = {name: batch.column(i)[r].as_py() for i, name in enumerate(batch.schema.names) if name != "doc_ids"}
                first, n_words = (np.frombuffer(row[c], "<u4").astype(np.int64) for c in ("doc_first", "doc_words"))
                phrase, start, near, seat = _search(row, phrases, slop)
                doc, stop = np.searchsorted(first, start, side="right") - 1, start + phrases.lengths[phrase]
                items_of: dict[int, set] = defaultdict(set)
                for d, p in set(zip(doc.tolist(), phrase.tolist())):
                    items_of[d].update(phrases.items(p))
                n_near = np.bincount(np.searchsorted(first, seat, side="right") - 1, minlength=len(first))
                lists = [sorted(items_of[d], key=str) if d in items_of else [] for d in range(len(first))]
                spans_of: dict[int, list] = defaultdict(list)
                if with_spans:
                    for d, a, b in zip(doc.tolist(), (start - first[doc]).tolist(), (stop - first[doc]).tolist()):
                        spans_of[d].append({"start": a, "stop": b})
                places = [f"{row['segment']}-{d}" if with_spans else None for d in range(len(first))]
                columns = [batch.column(0).slice(r, 1).flatten(), pa.array(n_words), pa.array(_covered(doc, start, stop, len(first))), pa.array(lists, pa.list_(kind)), pa.array(n_near)]
                columns += [pa.array(places, pa.string()), pa.array([spans_of.get(d, []) for d in range(len(first))], span)]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_words", "n_hit", "items", "n_near", "place", "spans"])

    schema = f"doc_id {id_type}, n_words long, n_hit long, items array<{'bigint' if kind == pa.int64() else 'string'}>, n_near long, place string, spans array<struct<start:long,stop:long>>"
    return index.mapInArrow(run, schema)


def clean(docs: DataFrame, benchmark: DataFrame, least: int = 1) -> DataFrame:
    """The rows in whose own text fewer than ``least`` words lie in benchmark windows, whatever their ids."""
    row = free_name(docs, "row")
    rows = keyed(docs, row)
    index = build_index(rows.select(F.col(row).alias("doc_id"), "text"))
    hits = stage(search(index, benchmark).where(F.col("n_hit") >= least).select(F.col("doc_id").alias(row)), "hits")
    return rows.join(hits, row, "left_anti").select(columns_of(docs))
