"""numpy kernels of the filters: addresses, footprints, insertion by conflict levels, lookup."""

from __future__ import annotations

import numpy as np

from .geometry import LINE_BITS, WORDS, FilterSpec
from .hashing import constant, np_hash, np_premix

#: Numbers of the hash functions of a spec: shard, then candidate lines, then addresses.
SHARD, LINE, BIT = 0, 1, 100
#: Keys that are scheduled together: about a quarter of the lines, so that most of them do not meet.
LEAST_WINDOW, WINDOW = 1 << 9, 1 << 13
#: Keys whose footprints are made at once; keys that are written at once.
PIECE, WRITTEN = 1 << 13, 1 << 17


def once(values: np.ndarray) -> np.ndarray:
    """The distinct values, sorted (a sort and a comparison of neighbours: much faster than ``np.unique``, which hashes)."""
    s = np.sort(values)
    return s[np.concatenate(([True], s[1:] != s[:-1]))] if len(s) else s


def prepared(keys: np.ndarray, spec: FilterSpec) -> np.ndarray:
    x = keys.view(np.uint64)
    return np_premix(x) if spec.premix else x


def shard_of(x: np.ndarray, spec: FilterSpec) -> np.ndarray:
    return np_hash(x, constant(spec.seed, SHARD), spec.shards, spec.u)


def candidates(x: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """(keys, choices) line numbers within the shard."""
    return np.stack([np_hash(x, constant(spec.seed, LINE + i), spec.lines, spec.u) for i in range(spec.choices)], 1)


def addresses(x: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """(keys, k) bit numbers: within the line, or within the shard's bits for classic filters."""
    a = [constant(spec.seed, BIT + i) for i in range(spec.k)]
    if spec.kind == "classic":
        return np.stack([np_hash(x, c, spec.lines * LINE_BITS, spec.u) for c in a], 1)
    if spec.bits == "random":
        return np.stack([np_hash(x, c, LINE_BITS, spec.u) for c in a], 1)
    if spec.bits == "sliced":  # an address in each of k nearly equal slices
        edge = [LINE_BITS * i // spec.k for i in range(spec.k + 1)]
        return np.stack([edge[i] + np_hash(x, c, edge[i + 1] - edge[i], spec.u) for i, c in enumerate(a)], 1)
    # Distinct: a rank among the addresses still free, moved past those taken below it.
    taken, held = np.empty((len(x), spec.k), np.int64), np.empty((spec.k, len(x)), np.int16)
    for i, c in enumerate(a):
        r = np_hash(x, c, LINE_BITS - i, spec.u).astype(np.int16)
        for j in range(i):
            r += held[j] <= r
        taken[:, i] = r
        for j in range(i):  # held stays in order
            held[j], r = np.minimum(held[j], r), np.maximum(held[j], r)
        held[i] = r
    return taken


def masks(address: np.ndarray) -> np.ndarray:
    """(keys, 8) words of the footprints."""
    out = np.zeros((len(address), WORDS), np.uint64)
    flat, rows = out.reshape(-1), WORDS * np.arange(len(address))
    for i in range(address.shape[1]):
        b = address[:, i]
        flat[rows + (b >> 6)] |= np.uint64(1) << (b & 63).astype(np.uint64)
    return out


def footprints(x: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """``masks`` of the ``addresses``, piece by piece within the processor's caches."""
    out = np.zeros((len(x), WORDS), np.uint64)
    for lo in range(0, len(x), PIECE):
        part = x[lo : lo + PIECE]
        if spec.bits != "random" or spec.kind == "classic":
            out[lo : lo + PIECE] = masks(addresses(part, spec))
            continue
        flat, rows = out[lo : lo + PIECE].reshape(-1), WORDS * np.arange(len(part))
        for i in range(spec.k):
            b = np_hash(part, constant(spec.seed, BIT + i), LINE_BITS, spec.u)
            at = rows + (b >> 6)
            flat[at] = flat.take(at) | (np.uint64(1) << (b & 63).view(np.uint64))
    return out


_PAIRS, _FOURS = np.uint64(0x00FF00FF00FF00FF), np.uint64(0x0001000100010001)


def ones(words: np.ndarray) -> np.ndarray:
    """Bits set in the eight words of each line: byte counts side by side in one word, added up there."""
    v = np.bitwise_count(np.ascontiguousarray(words)).view(np.uint64)[..., 0]
    v = (v & _PAIRS) + ((v >> np.uint64(8)) & _PAIRS)
    return ((v * _FOURS) >> np.uint64(48)).view(np.int64)


#: A line as one value: rows are written several times faster than eight words each, and ``take`` reads them so.
_ROW = np.dtype(f"V{8 * WORDS}")


def insert_each(lines: np.ndarray, cand: np.ndarray, mask: np.ndarray, spec: FilterSpec) -> int:
    """The plain loop, a key at a time; returns how many found all their bits set."""
    total, added = spec.cost.tables(spec.k)
    skipped = 0
    for i in range(len(cand)):
        now = lines[cand[i]]
        new = now | mask[i]
        j, a = ones(new), ones(new) - ones(now)
        price = np.where(a == 0, -1, total[j] + added[a])
        best = int(np.argmin(price))
        skipped += int(a[best] == 0)
        lines[cand[i, best]] = new[best]
    return skipped


def insert(lines: np.ndarray, cand: np.ndarray, mask: np.ndarray, spec: FilterSpec, window: int | None = None, held: np.ndarray | None = None) -> int:
    """Same result as the loop: keys that are the earliest waiting for all their lines touch different lines
    (or wait for no one), so they are written in one step; then the next ones are.

    ``held`` (booleans), if given, becomes true for the keys that found all their bits set when they came.
    """
    total, added = spec.cost.tables(spec.k)
    first, load, rows, skipped = np.empty(len(lines), np.int64), ones(lines), lines.view(_ROW)[:, 0], 0
    window = window or min(max(len(lines) // 4, LEAST_WINDOW), WINDOW)
    for lo in range(0, len(cand), window):
        of, mine, waiting = cand[lo : lo + window], mask[lo : lo + window], np.arange(lo, min(lo + window, len(cand)))
        while len(waiting):
            # The last write of a repeated place stays, so go from the latest key to the earliest.
            first[of[::-1].reshape(-1)] = np.repeat(waiting[::-1], of.shape[1])
            ready = first.take(of[:, 0]) == waiting
            for i in range(1, of.shape[1]):
                ready &= first.take(of[:, i]) == waiting
            here, bits, low = of.compress(ready, 0), mine.compress(ready, 0), None
            for i in range(of.shape[1]):
                at = here[:, i]
                after = ones(lines.take(at, 0) | bits)
                a = after - load.take(at)
                price = total.take(after) + added.take(a)
                price[a == 0] = -1
                if low is None:
                    low, best, then = price, at, after
                else:
                    better = price < low
                    low, best, then = np.where(better, price, low), np.where(better, at, best), np.where(better, after, then)
            full = low < 0
            skipped += int(full.sum())
            if held is not None:
                held[waiting[ready]] = full
            bits |= lines.take(best, 0)
            rows[best] = bits.view(_ROW)[:, 0]
            load[best] = then
            late = ~ready
            of, mine, waiting = of.compress(late, 0), mine.compress(late, 0), waiting.compress(late)
    return skipped


def filled(x: np.ndarray, spec: FilterSpec) -> np.ndarray:
    """The lines of a shard with the prepared keys ``x``, piece by piece: footprints take eight times the space of the keys."""
    lines = np.zeros((spec.lines, WORDS), np.uint64)
    for lo in range(0, len(x), PIECE if spec.kind == "classic" else WRITTEN):
        if spec.kind == "classic":
            address = addresses(x[lo : lo + PIECE], spec).reshape(-1)
            np.bitwise_or.at(lines.reshape(-1), address >> 6, np.uint64(1) << (address & 63).astype(np.uint64))
            continue
        part = x[lo : lo + WRITTEN]
        cand, mask = candidates(part, spec), footprints(part, spec)
        if spec.choices == 1:
            np.bitwise_or.at(lines, cand[:, 0], mask)
        else:
            insert(lines, cand, mask, spec)
    return lines


def lookup(lines: np.ndarray, cand: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(found, first candidate that holds the footprint or 0, counted from 1)."""
    hit = np.zeros(len(cand), np.int8)
    for i in range(cand.shape[1] - 1, -1, -1):
        hit[((lines[cand[:, i]] & mask) == mask).all(1)] = i + 1
    return hit > 0, hit


#: Addresses after which a lazy lookup lets the refused keys go: most absent keys are out after the first few.
STEPS = (0, 1, 3, 7, 15, 31)


def lazy_lookup(lines: np.ndarray, x: np.ndarray, base: np.ndarray, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray]:
    """``lookup`` for random and sliced footprints; an address is only computed for keys that may still be held."""
    edge, words, hit = [LINE_BITS * i // spec.k for i in range(spec.k + 1)], lines.reshape(-1), np.zeros(len(x), np.int8)
    cand = candidates(x, spec)
    for choice in range(spec.choices - 1, -1, -1):
        row, y, at = np.arange(len(x)), x, WORDS * (base + cand[:, choice])
        for i in range(spec.k):
            a = constant(spec.seed, BIT + i)
            b = np_hash(y, a, LINE_BITS, spec.u) if spec.bits == "random" else edge[i] + np_hash(y, a, edge[i + 1] - edge[i], spec.u)
            bit = (words.take(at + (b >> 6)) >> (b & 63).view(np.uint64)) & np.uint64(1)
            if i in STEPS or i == spec.k - 1:
                keep = np.flatnonzero((bit if i == 0 else bit & so_far).astype(bool))  # much faster on booleans
                row, y, at = row.take(keep), y.take(keep), at.take(keep)
                so_far = np.ones(len(row), np.uint64)
            else:
                so_far = so_far & bit
        hit[row] = choice + 1
    return hit > 0, hit


def classic_lookup(words: np.ndarray, address: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(found, addresses read until the first zero, all of them on a hit)."""
    bit = (words[address >> 6] >> (address & 63).astype(np.uint64)) & np.uint64(1)
    miss = bit == 0
    return ~miss.any(1), np.where(miss.any(1), miss.argmax(1) + 1, address.shape[1])


def bits_examined(lines: np.ndarray, cand: np.ndarray, address: np.ndarray) -> np.ndarray:
    """Bits that a lookup reads, candidate after candidate, each up to its first zero; the first hit ends it."""
    read, open_ = np.zeros(len(cand), np.int64), np.ones(len(cand), bool)
    for i in range(cand.shape[1]):
        bit = (lines[cand[:, i, None], address >> 6] >> (address & 63).astype(np.uint64)) & np.uint64(1)
        miss = bit == 0
        whole = ~miss.any(1)
        read += np.where(open_, np.where(whole, address.shape[1], miss.argmax(1) + 1), 0)
        open_ &= ~whole
    return read


def insert_epoch(lines: np.ndarray, cand: np.ndarray, mask: np.ndarray, spec: FilterSpec, epochs: int) -> None:
    """Keys in ``epochs`` batches by arrival, each priced on the lines as they were at its start."""
    total, added = spec.cost.tables(spec.k)
    for part in np.array_split(np.arange(len(cand)), epochs):
        old = lines[cand[part]]
        j = ones(old | mask[part][:, None, :])
        a = j - ones(old)
        best = np.argmin(np.where(a == 0, -1, total[j] + added[a]), 1)
        np.bitwise_or.at(lines, cand[part, best], mask[part])
