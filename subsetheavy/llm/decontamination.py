"""Benchmark decontamination: n-gram seeds find candidates, Smith-Waterman alignment scores them.

Words are runs of letters, digits and bytes over 127, letters A-Z and the accented capitals of Latin-1 lower-cased, so
case and punctuation don't hide a copy. Every n-gram of a test item is a seed, however many documents have it, as edits
may leave a much-copied item no rare one. Each document's stretch around an item's seeds is aligned with the item, local
alignment over words with +2 for a match and -1 for a change or a gap, unless the words that the two have in common
allow no leak in any order. The score is the alignment's part of a full match; a pair at LINE or over is a leak. Edits,
insertions and omissions cost what they change.

Test items are taken in blocks of bounded size, each against all documents, BLOCKS of them in one scan. Null and empty texts and items, and items
without words, leak nothing. Repeated rows give repeated results.
"""

from __future__ import annotations

from itertools import batched

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts

LINE, SEED = 0.5, 3
#: Words of test items in a block: what a task holds of the benchmark is bounded by it.
BLOCK = 1 << 20
#: Blocks that one scan of the documents meets; words and n-grams of a text are taken once for all of them.
BLOCKS = 8
#: Seed hits of a run of documents that are held at once, but for a document that has more.
HITS = 1 << 20
FOUND = "doc_id bigint, item_id bigint, score double, word_start bigint, word_end bigint"
_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


def words(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(word hashes, for each document the index of its first)."""
    if len(data) > 1:
        capital = np.flatnonzero((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97)) + 1
        if len(capital):
            data = data.copy()
            data[capital] |= 0x20
    starts, ends = ts.spans(_WORD[data], offs)
    return ts.span_hash(data, starts, ends), np.searchsorted(starts, offs)


class Items:
    """A block of test items with their n-grams: ascending codes with the item and place of each."""

    def __init__(self, ids: list[int], texts: list[str]):
        col = pa.array(texts, pa.large_string())
        data, offs = ts.raw(col)
        self.ids = np.array(ids, np.int64)
        self.words, self.at = words(data, offs)
        code, at = ts.shingles(self.words, self.at, SEED)
        item = np.repeat(np.arange(len(ids)), np.diff(at))
        place = np.arange(len(code)) - at[item]
        order = np.lexsort((place, item, code))
        self.code, self.item, self.place = code[order], item[order], place[order]
        self.known = np.zeros(1 << 16, bool)
        self.known[(self.code >> np.uint64(48)).astype(np.int64)] = True

    def hits(self, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index in code, first entry) of the n-grams that items have."""
        near = np.flatnonzero(self.known[(code >> np.uint64(48)).astype(np.int64)])
        where = np.searchsorted(self.code, code[near])
        ok = where < len(self.code)
        ok[ok] = self.code[where[ok]] == code[near[ok]]
        return near[ok], where[ok]


def align(item: np.ndarray, sizes: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(best local score, where it ends) for each row: item and text are padded arrays of word codes, 0 and 1."""
    n, m = item.shape
    w = text.shape[1]
    ramp = np.arange(w + 1)
    above = np.zeros((n, w + 1), np.int32)
    best, end = np.zeros(n, np.int32), np.zeros(n, np.int64)
    for i in range(m):
        here = np.zeros((n, w + 1), np.int32)
        here[:, 1:] = np.maximum(above[:, :-1] + np.where(text == item[:, i : i + 1], 2, -1), above[:, 1:] - 1)
        np.maximum(here, 0, out=here)
        here = np.maximum.accumulate(here + ramp, axis=1).astype(np.int32) - ramp.astype(np.int32)
        top = here.argmax(1)
        value = here[np.arange(n), top]
        better = (value > best) & (i < sizes)
        best[better], end[better] = value[better], top[better]
        above = here
    return best, end


def _padded(rows: list[np.ndarray], fill: int) -> np.ndarray:
    out = np.full((len(rows), max(map(len, rows))), fill, np.uint64)
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out


def _most(one: np.ndarray, other: np.ndarray) -> int:
    """The best score that any local alignment of one with other can have: its words in other match, others cost 1."""
    run = np.cumsum(np.where(np.isin(one, other), 2, -1))
    return int((run - np.minimum.accumulate(np.concatenate([[0], run[:-1]]))).max())


def leaks(items: Items, text_words: np.ndarray, at: np.ndarray, line: float, grams: tuple[np.ndarray, np.ndarray] | None = None) -> list[tuple[int, int, float, int, int]]:
    """(document, item, score, first word, word after the last) of each leak in a run of documents.
    grams: their n-grams, where they are known already."""
    code, where = grams if grams else ts.shingles(text_words, at, SEED)
    index, entry = items.hits(code)
    if not len(index):
        return []
    many = np.searchsorted(items.code, code[index], "right") - entry
    doc = np.searchsorted(where, index, "right") - 1
    total = np.cumsum(many)
    out, lo = [], 0
    while lo < len(index):
        # whole documents only, so that each pair is seen once
        last = max(lo, int(np.searchsorted(total, total[lo] - many[lo] + HITS, "right")) - 1)
        hi = int(np.searchsorted(doc, doc[last], "left"))
        hi = hi if hi > lo and last + 1 < len(index) else int(np.searchsorted(doc, doc[last], "right"))
        out += _aligned(items, text_words, at, where, line, doc[lo:hi], index[lo:hi], entry[lo:hi], many[lo:hi])
        lo = hi
    return out


def _aligned(items: Items, text_words, at, where, line: float, doc, index, entry, many) -> list[tuple[int, int, float, int, int]]:
    """leaks of the documents of these hits."""
    doc, index = np.repeat(doc, many), np.repeat(index, many)
    entry = np.repeat(entry, many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
    item, place = items.item[entry], index - where[doc]
    size = np.diff(items.at)
    order = np.lexsort((place, item, doc))
    doc, item, place = doc[order], item[order], place[order]
    fresh = np.ones(len(doc), bool)
    fresh[1:] = (doc[1:] != doc[:-1]) | (item[1:] != item[:-1]) | (place[1:] - place[:-1] > 2 * size[item[1:]])
    starts = np.flatnonzero(fresh)
    ends = np.concatenate([starts[1:], [len(doc)]]) - 1
    found: dict[tuple[int, int], tuple[float, int, int]] = {}
    jobs = []
    for s, e in zip(starts.tolist(), ends.tolist(), strict=True):
        d, i, m = int(doc[s]), int(item[s]), int(size[item[s]])
        lo, hi = max(0, int(place[s]) - m - m // 2), min(int(at[d + 1] - at[d]), int(place[e]) + SEED + m + m // 2)
        own, near = items.words[items.at[i] : items.at[i + 1]], text_words[at[d] + lo : at[d] + hi]
        if _most(own, near) >= line * 2 * m and _most(near, own) >= line * 2 * m:
            jobs.append((hi - lo, m, d, i, lo, hi))
    jobs.sort()
    get = lambda j: (items.words[items.at[j[3]] : items.at[j[3] + 1]], text_words[at[j[2]] + j[4] : at[j[2]] + j[5]])
    lo = 0
    while lo < len(jobs):
        hi = lo + 1
        while hi < len(jobs) and hi - lo < 256 and (hi - lo) * jobs[hi][0] < 1 << 17:
            hi += 1
        part, pairs = jobs[lo:hi], [get(j) for j in jobs[lo:hi]]
        lengths = np.array([j[1] for j in part])
        score, end = align(_padded([a for a, _ in pairs], 0), lengths, _padded([b for _, b in pairs], 1))
        good = np.flatnonzero(score >= line * 2 * lengths)
        if len(good):
            _, back = align(_padded([pairs[g][0][::-1] for g in good], 0), lengths[good], _padded([pairs[g][1][: end[g]][::-1] for g in good], 1))
            for g, b in zip(good.tolist(), back.tolist(), strict=True):
                j, value = part[g], float(score[g]) / (2 * part[g][1])
                if value > found.get((j[2], j[3]), (0.0,))[0]:
                    found[j[2], j[3]] = (value, j[4] + int(end[g]) - int(b), j[4] + int(end[g]))
        lo = hi
    return [(d, i, *v) for (d, i), v in sorted(found.items())]


def _found(held, line: float, texts):
    """(first document, block, its leaks) for each run of documents and each block."""
    for lo, _, data, offs in ts.runs(texts):
        text_words, at = words(data, offs)
        grams = ts.shingles(text_words, at, SEED)
        for block in held:
            yield lo, block.value, leaks(block.value, text_words, at, line, grams)


def _search(held, line: float):
    def go(batches):
        for batch in batches:
            ids = batch.column(0)
            for lo, items, got in _found(held, line, batch.column(1)):
                if got:
                    d, i, score, a, b = (np.array(x) for x in zip(*got, strict=True))
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(d + lo)), pa.array(items.ids[i]), pa.array(score), pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["doc_id", "item_id", "score", "word_start", "word_end"])

    return go


def _without(held, line: float, text_col: str):
    def go(batches):
        for batch in batches:
            keep = np.ones(len(batch), bool)
            for lo, _, got in _found(held, line, batch.column(batch.schema.get_field_index(text_col))):
                keep[[lo + d for d, *_ in got]] = False
            yield batch.filter(pa.array(keep))

    return go


def _blocks(benchmark: DataFrame):
    ids, texts, size = [], [], 0
    for row in benchmark.toLocalIterator():
        if row[0] is not None and row[1]:
            ids.append(row[0])
            texts.append(row[1])
            size += len(row[1]) // 4
        if size >= BLOCK:
            yield ids, texts
            ids, texts, size = [], [], 0
    if ids:
        yield ids, texts


def _held(docs: DataFrame, benchmark: DataFrame, item_col: str, item_text: str):
    """The benchmark's blocks as broadcasts, those of one scan together."""
    made = (Items(ids, texts) for ids, texts in _blocks(benchmark.select(F.col(item_col).cast("bigint"), F.col(item_text))))
    for some in batched((docs.sparkSession.sparkContext.broadcast(items) for items in made if len(items.code)), BLOCKS):
        yield list(some)


def benchmark_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", line: float = LINE) -> DataFrame:
    """(doc_id, item_id, score, word_start, word_end) for each document and test item that it leaks."""
    named = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    out = docs.sparkSession.createDataFrame([], FOUND)
    for held in _held(docs, benchmark, item_col, item_text):
        out = out.unionByName(named.mapInArrow(_search(held, line), FOUND))
    return out


def clean_docs(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", line: float = LINE) -> DataFrame:
    """The rows of docs, all columns, that leak no test item."""
    out = docs
    for held in _held(docs, benchmark, item_col, item_text):
        out = out.mapInArrow(_without(held, line, text_col), docs.schema)
    return out
