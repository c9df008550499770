"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics are counted on the bytes of whole texts with array operations. Trees are grown level by level on binned
statistics of a bounded labelled sample (SAMPLE rows) and kept as flat arrays (feature, threshold, leaf) with implicit
children, so that a block of documents goes down all trees at once. Null and empty texts have all-zero statistics and
get the score of such documents. With no labelled row every score is the line (all kept); with labels of one class
alone every score is that class.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import textscan as ts
from .learned import cut_at, kept_docs, sample_ids, sample_rows, scored_docs

SAMPLE = 20_000
_CLASS = np.zeros(256, np.int64)
for _i, _of in enumerate((range(97, 123), range(65, 91), range(48, 58), (32,), (10, 13), b".,;:?'\"-()", b"!", b"|", range(128, 256)), 1):
    _CLASS[list(_of)] = _i
NAMES = ["bytes", "words", "word_length", "lower", "upper", "digits", "blank", "breaks", "stops", "bangs", "bars", "wide", "symbols",
         "distinct_words", "top_word", "same_as_last", "distinct_triples", "line_length", "no_letter_words", "marked_ends", "short_words", "longest_word"]


def statistics(data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """One row of NAMES for each document."""
    n = len(offs) - 1
    size = np.diff(offs)
    doc = np.repeat(np.arange(n), size)
    kinds = np.bincount(doc * 10 + _CLASS[data], minlength=10 * n).reshape(n, 10)
    starts, ends = ts.spans(~ts.SPACE[data], offs)
    of = ts.owner(starts, offs)
    words = ts.span_hash(data, starts, ends)
    count = np.bincount(of, minlength=n)
    at = np.concatenate([[0], np.cumsum(count)])
    per = lambda x: np.bincount(of, weights=x, minlength=n) / np.maximum(count, 1)
    length = ends - starts
    letters = np.concatenate([[0], np.cumsum((_CLASS[data] == 1) | (_CLASS[data] == 2) | (_CLASS[data] == 9))])
    again = np.zeros(len(words))
    again[1:] = (words[1:] == words[:-1]) & (of[1:] == of[:-1])
    distinct, top = _distinct(words, of, n)
    tri, tri_at = ts.shingles(words, at, 3)
    tri_count = np.diff(tri_at)
    longest = np.zeros(n)
    if len(length):
        full = np.flatnonzero(count)
        longest[full] = np.maximum.reduceat(length, at[full])
    return np.column_stack([
        np.log1p(size), np.log1p(count), per(length), *(kinds[:, i] / np.maximum(size, 1) for i in (1, 2, 3, 4, 5, 6, 7, 8, 9, 0)),
        distinct / np.maximum(count, 1), top / np.maximum(count, 1), per(again),
        _distinct(tri, np.repeat(np.arange(n), tri_count), n)[0] / np.maximum(tri_count, 1), np.log1p(size / (kinds[:, 5] + 1)),
        per(letters[ends] == letters[starts]), per(~np.isin(_CLASS[data[ends - 1]], (1, 2, 3, 9))), per(length <= 3), np.log1p(longest),
    ]).astype(np.float32)


def _distinct(hashes: np.ndarray, of: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """For each document how many different hashes it has, and how often the most frequent comes."""
    if not len(hashes):
        return np.zeros(n), np.zeros(n)
    bits = max(1, int(n).bit_length())
    key = np.sort((of.astype(np.uint64) << np.uint64(64 - bits)) | (hashes >> np.uint64(bits)))
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    many = np.diff(np.concatenate([first, [len(key)]]))
    whose = (key[first] >> np.uint64(64 - bits)).astype(np.int64)
    distinct = np.bincount(whose, minlength=n)
    top = np.zeros(n)
    full = np.flatnonzero(distinct)
    top[full] = np.maximum.reduceat(many, np.concatenate([[0], np.cumsum(distinct)])[full])
    return distinct, top


@dataclass
class Trees:
    """Complete binary trees of one depth; the children of node i are 2i + 1 and 2i + 2."""

    feature: np.ndarray  # trees x inner nodes
    threshold: np.ndarray
    leaf: np.ndarray  # trees x leaves
    base: float

    def margins(self, x: np.ndarray) -> np.ndarray:
        count, inner = self.feature.shape
        tree, row = np.arange(count)[None, :], np.arange(len(x))[:, None]
        at = np.zeros((len(x), count), np.int64)
        for _ in range(inner.bit_length()):
            at = 2 * at + 1 + (x[row, self.feature[tree, at]] > self.threshold[tree, at])
        return self.base + self.leaf[tree, at - inner].sum(1)


def grow(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, bins: int = 64, rate: float = 0.15, l2: float = 2.0, least: int = 8) -> Trees:
    """Logistic boosting; each split is the best over the bin histograms of gradients and curvatures."""
    n, width = x.shape
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(width)]
    binned = np.column_stack([np.searchsorted(edges[f], x[:, f], "left") for f in range(width)])
    mean = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    base = float(np.log(mean / (1 - mean)))
    margin = np.full(n, base)
    inner = 2**depth - 1
    feature, threshold, leaf = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf, np.float32), np.zeros((trees, inner + 1))
    cell = np.arange(width) * bins + binned
    for t in range(trees):
        p = 1 / (1 + np.exp(-margin))
        grad, curve = y - p, p * (1 - p)
        at = np.zeros(n, np.int64)
        for d in range(depth):
            first, nodes = 2**d - 1, 2**d
            where = ((at - first)[:, None] * (width * bins) + cell).ravel()
            g, h, c = (np.bincount(where, weights=w, minlength=nodes * width * bins).reshape(nodes, width, bins).cumsum(2) for w in (np.repeat(grad, width), np.repeat(curve, width), None))
            gt, ht, ct = g[:, :, -1:], h[:, :, -1:], c[:, :, -1:]
            gain = g**2 / (h + l2) + (gt - g) ** 2 / (ht - h + l2) - gt**2 / (ht + l2)
            gain[(c < least) | (ct - c < least)] = 0
            best = gain.reshape(nodes, -1).argmax(1)
            for i in range(nodes):
                f, b = divmod(int(best[i]), bins)
                if gain[i, f, b] > 1e-6 and b < len(edges[f]):
                    feature[t, first + i], threshold[t, first + i] = f, edges[f][b]
            at = 2 * at + 1 + (x[np.arange(n), feature[t, at]] > threshold[t, at])
        slot = at - inner
        leaf[t] = rate * np.bincount(slot, weights=grad, minlength=inner + 1) / (np.bincount(slot, weights=curve, minlength=inner + 1) + l2)
        margin += leaf[t][slot]
    return Trees(feature, threshold, leaf, base)


def _sample_work(batches):
    for batch in batches:
        for lo, hi, data, offs in ts.runs(batch.column(2)):
            x = statistics(data, offs)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array(list(x), pa.list_(pa.float32()))], names=["id", "label", "x"])


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", id_col: str = "doc_id", text_col: str = "text", parts: int = 4, held: int = 2, sample: int = SAMPLE) -> tuple[Trees, float]:
    """(trees, cut), from at most `sample` labelled rows outside the held-out fold; a quarter of them sets the cut."""
    ids = sample_ids(labels, label, id_col, parts, held, sample)
    got = sample_rows(docs, ids, id_col, text_col, _sample_work, "id bigint, label int, x array<float>")
    y = got.column("label").to_numpy()
    if not len(y) or y.min() == y.max():
        return Trees(np.zeros((1, 1), np.int64), np.full((1, 1), np.inf, np.float32), np.zeros((1, 2)), 0.0), 0.0 if not len(y) else (40.0 if y[0] == 0 else -40.0)
    x = np.array(got.column("x").to_pylist(), np.float32)
    back = np.arange(len(y)) % 4 == 3
    if len(set(y[back])) < 2 or len(set(y[~back])) < 2:
        back[:] = True
        trees = grow(x, y)
    else:
        trees = grow(x[~back], y[~back])
    return trees, cut_at(trees.margins(x[back]), y[back], "recall")


def quality_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", parts: int = 4, held: int = 2, sample: int = SAMPLE) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs."""
    trees, cut = fit(docs, labels, "quality", id_col, text_col, parts, held, sample)
    return scored_docs(docs, lambda data, offs: trees.margins(statistics(data, offs)), cut, id_col, text_col, parts, held)


def good_docs(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", parts: int = 4, held: int = 2, sample: int = SAMPLE) -> DataFrame:
    """The rows of docs, all columns, that the classifier predicts 1."""
    trees, cut = fit(docs, labels, "quality", id_col, text_col, parts, held, sample)
    return kept_docs(docs, lambda data, offs: trees.margins(statistics(data, offs)), cut, text_col)
