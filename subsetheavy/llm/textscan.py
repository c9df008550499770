"""Vectorised reading of text columns: words, word hashes and shingle sets from Arrow buffers, without Python strings.

Everything here works on the UTF-8 bytes of a run of documents at once. Runs are cut at whole documents and hold about
a megabyte, so memory does not follow the batch; a longer document is a run of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_U = np.uint64
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
#: A random 64-bit value for each byte, upper case like lower case.
VALUE = np.random.default_rng(20240607).integers(0, 2**64, 256, dtype=_U)[FOLD]
BASE = _U(0x9E3779B97F4A7C15 | 1)
UNBASE = _U(pow(int(BASE), -1, 2**64))
LAGS = np.random.default_rng(11).integers(0, 2**63, 64, dtype=_U) * _U(2) + _U(1)
_powers: dict[str, np.ndarray] = {}


def mixed(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (shift, multiply) for each element."""
    h = h ^ (h >> _U(33))
    h *= _U(0xFF51AFD7ED558CCD)
    h ^= h >> _U(33)
    h *= _U(0xC4CEB9FE1A85EC53)
    h ^= h >> _U(33)
    return h


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers.get("up", ())) < n:
        size = max(n, 1 << 20)
        for name, base in (("up", BASE), ("down", UNBASE)):
            run = np.full(size, base, _U)
            run[0] = 1
            _powers[name] = np.multiply.accumulate(run)
    return _powers["up"], _powers["down"]


def raw(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = pc.fill_null(col, "")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    offs = np.frombuffer(col.buffers()[1], np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64) if len(col) else np.zeros(1, np.int64)
    data = np.frombuffer(col.buffers()[2], np.uint8) if col.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data, offs


def runs(col: pa.Array, size: int = 1 << 20) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, their bytes, offsets into these) for whole documents of about size bytes."""
    data, offs = raw(col)
    lo, n = 0, len(offs) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + size, "right")) - 1)
        yield lo, hi, data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
        lo = hi


def spans(keep: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of True in keep that lie in one document."""
    n = len(keep)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = keep.copy()
    first[1:] &= ~keep[:-1]
    inner = offs[1:-1][(offs[1:-1] > 0) & (offs[1:-1] < n)]
    first[inner] = keep[inner]
    last = keep.copy()
    last[:-1] &= ~keep[1:]
    last[inner - 1] = keep[inner - 1]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def owner(starts: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """The document of each start."""
    return np.searchsorted(offs, starts, "right") - 1


def span_hash(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, values: np.ndarray = VALUE) -> np.ndarray:
    """A 64-bit hash of each byte span, equal for equal bytes wherever they lie."""
    n = len(data)
    up, down = _power(n + 1)
    run = np.zeros(n + 1, _U)
    np.cumsum(values[data] * up[:n], out=run[1:])
    return mixed((run[ends] - run[starts]) * down[starts])


def word_hashes(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of the A-Z lower-cased words, for each document the index of its first word and after all the count)."""
    starts, ends = spans(~SPACE[data], offs)
    return span_hash(data, starts, ends), np.searchsorted(starts, offs)


def shingles(words: np.ndarray, at: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of k-word shingles, for each document its first). Fewer words than k make one shingle, none make none."""
    count = np.diff(at)
    n = len(words)
    if n == 0:
        return np.zeros(0, _U), np.zeros(len(at), np.int64)
    full = np.zeros(n, _U)
    part = np.zeros(n, _U)
    part += _U(k)
    for j in range(k):
        m = n - j
        full[:m] += words[j:] * LAGS[j]
    short = np.flatnonzero((count > 0) & (count < k))
    made = np.maximum(count - k + 1, np.minimum(count, 1))
    where = np.zeros(len(at), np.int64)
    np.cumsum(made, out=where[1:])
    take = np.repeat(at[:-1], made) + (np.arange(where[-1]) - np.repeat(where[:-1], made))
    out = full[take]
    for d in short:
        out[where[d]] = sum((int(words[at[d] + j]) * int(LAGS[j + 8]) for j in range(count[d])), 7 * int(count[d])) & (2**64 - 1)
    return mixed(out), where


def shingle_sets(data: np.ndarray, offs: np.ndarray, k: int = 5) -> Iterator[np.ndarray]:
    """For each document its distinct shingle hashes, ascending."""
    hashes, at = shingles(*word_hashes(data, offs), k)
    for lo, hi in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        if hi - lo < 2:
            yield hashes[lo:hi]
            continue
        own = np.sort(hashes[lo:hi])
        fresh = np.empty(hi - lo, bool)
        fresh[0] = True
        np.not_equal(own[1:], own[:-1], out=fresh[1:])
        yield own[fresh]


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


class Frequent:
    """Mergeable summary of frequent keys: at most size counters, each too low by no more than the keys seen over size."""

    def __init__(self, size: int = 1 << 16, hold: int = 1 << 20):
        self.size, self.hold, self.waiting, self.parts = size, hold, 0, []
        self.keys, self.counts = np.zeros(0, _U), np.zeros(0, np.int64)

    def add(self, keys: np.ndarray) -> None:
        self.parts.append(keys)
        self.waiting += len(keys)
        if self.waiting >= self.hold:
            self.settle()

    def settle(self) -> None:
        if not self.waiting:
            return
        keys, counts = np.unique(np.concatenate(self.parts), return_counts=True)
        self.parts, self.waiting = [], 0
        where = np.searchsorted(self.keys, keys)
        hit = np.zeros(len(keys), bool)
        if len(self.keys):
            inside = np.minimum(where, len(self.keys) - 1)
            hit = self.keys[inside] == keys
            self.counts[inside[hit]] += counts[hit]
        keys, counts = np.concatenate([self.keys, keys[~hit]]), np.concatenate([self.counts, counts[~hit]])
        if len(keys) > self.size:
            cut = np.partition(counts, len(counts) - self.size - 1)[len(counts) - self.size - 1]
            keep = counts > cut
            keys, counts = keys[keep], counts[keep] - cut
        order = np.argsort(keys)
        self.keys, self.counts = keys[order], counts[order]
