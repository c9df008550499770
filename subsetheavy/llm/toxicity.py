"""Toxicity: a second-order factorization machine over hashed terms.

Terms are the distinct letter runs of the whole text, A-Z lower-cased, and their first HEADS bytes (an insult is also
known by its stem when compounds and endings differ), hashed to 2**BITS places. Places are chosen on
the bounded labelled sample by their chi-square with the label; the machine has a weight and RANK factors for each, and
its pair part sees combinations, such as an insult beside a group's name, that no sum of single weights can. Training is
mini-batch AdaGrad on the logistic loss. Null and empty texts have no term and get the base margin. With no labelled
row, or labels of class 0 alone, every score is 0; with class 1 alone, 1.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import textscan as ts
from .learned import cut_at, sample_ids, sample_rows, scored_docs

SAMPLE, BITS, RANK, CHOSEN = 8_000, 20, 8, 2048
HEADS = (3, 4, 5, 6, 8)
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True


def _place(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(64 - BITS)).astype(np.int64)


def terms(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places of each document's distinct terms, for each document the index of its first)."""
    starts, ends = ts.spans(_LETTER[data], offs)
    of = ts.owner(starts, offs) << BITS
    key = [of | _place(ts.span_hash(data, starts, ends))]
    for head in HEADS:
        longer = ends - starts > head
        key.append(of[longer] | _place(ts.span_hash(data, starts[longer], starts[longer] + head) ^ ts.LAGS[head]))
    key = np.sort(np.concatenate(key))
    key = key[np.concatenate([np.ones(min(1, len(key)), bool), key[1:] != key[:-1]])]
    return key & ((1 << BITS) - 1), np.searchsorted(key, np.arange(len(offs)) << BITS)


@dataclass
class Machine:
    slot: np.ndarray  # for each place its row, or -1
    base: float
    weight: np.ndarray
    factor: np.ndarray

    def margins(self, place: np.ndarray, at: np.ndarray) -> np.ndarray:
        row = self.slot[place]
        keep = row >= 0
        return self.of_rows(row[keep], np.concatenate([[0], np.cumsum(keep)])[at])

    def of_rows(self, row: np.ndarray, at: np.ndarray) -> np.ndarray:
        of = np.repeat(np.arange(len(at) - 1), np.diff(at))
        total = lambda x: np.bincount(of, weights=x, minlength=len(at) - 1)
        pair = sum(total(v) ** 2 - total(v * v) for v in self.factor[row].T)
        return self.base + total(self.weight[row]) + 0.5 * pair


def train(place: np.ndarray, at: np.ndarray, y: np.ndarray, epochs: int = 12, batch: int = 256, rate: float = 0.1, l2: float = 1e-4, seed: int = 5) -> Machine:
    of = np.repeat(np.arange(len(y), dtype=np.int32), np.diff(at))
    with1 = np.bincount(place, weights=y[of], minlength=1 << BITS)
    have = np.bincount(place, minlength=1 << BITS).astype(float)
    n, ones = len(y), float(y.sum())
    expect = have * ones / n
    chi = np.where(have >= 3, (with1 - expect) ** 2 / np.maximum(expect * (1 - have / n), 1e-9), 0)
    chosen = np.sort(np.argsort(-chi, kind="stable")[:CHOSEN])
    chosen = chosen[chi[chosen] > 0]
    slot = np.full(1 << BITS, -1, np.int32)
    slot[chosen] = np.arange(len(chosen))
    rng = np.random.default_rng(seed)
    m = Machine(slot, float(np.log((ones + 0.5) / (n - ones + 0.5))), np.zeros(len(chosen)), rng.normal(0, 0.02, (len(chosen), RANK)))
    keep = slot[place] >= 0
    row, at = slot[place[keep]], np.concatenate([[0], np.cumsum(keep)])[at]
    gw, gv, gb = np.full(len(chosen), 1e-3), np.full(m.factor.shape, 1e-3), 1e-3
    for _ in range(epochs):
        order = rng.permutation(n)
        for lo in range(0, n, batch):
            some = order[lo : lo + batch]
            size = at[some + 1] - at[some]
            mine = np.concatenate([[0], np.cumsum(size)])
            r = row[np.repeat(at[some], size) + np.arange(mine[-1]) - np.repeat(mine[:-1], size)]
            own = np.repeat(np.arange(len(some)), size)
            p = 1 / (1 + np.exp(-np.clip(m.of_rows(r, mine), -30, 30)))
            err = (p - y[some])[own] / 1.0
            v = m.factor[r]
            total = np.column_stack([np.bincount(own, weights=c, minlength=len(some)) for c in v.T])
            used, back = np.unique(r, return_inverse=True)
            dw = np.bincount(back, weights=err) / len(some) + l2 * m.weight[used]
            dv = np.column_stack([np.bincount(back, weights=c) for c in (err[:, None] * (total[own] - v)).T]) / len(some) + l2 * m.factor[used]
            db = float((p - y[some]).mean())
            gw[used] += dw**2
            gv[used] += dv**2
            gb += db**2
            m.weight[used] -= rate * dw / np.sqrt(gw[used])
            m.factor[used] -= 0.2 * rate * dv / np.sqrt(gv[used])
            m.base -= rate * db / gb**0.5
    return m


def _sample_work(batches):
    for batch in batches:
        for lo, hi, data, offs in ts.runs(batch.column(2)):
            place, at = terms(data, offs)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(place, pa.int32()))], names=["id", "label", "x"])


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", id_col: str = "doc_id", text_col: str = "text", parts: int = 3, held: int = 1, sample: int = SAMPLE) -> tuple[Machine, float]:
    """(machine, cut), from at most `sample` labelled rows outside the held-out fold; a quarter of them sets the cut."""
    ids = sample_ids(labels, label, id_col, parts, held, sample)
    got = sample_rows(docs, ids, id_col, text_col, _sample_work, "id bigint, label int, x array<int>").combine_chunks()
    y = got.column("label").to_numpy().astype(float)
    if not len(y) or y.min() == y.max():
        return Machine(np.full(1 << BITS, -1, np.int32), 0.0, np.zeros(0), np.zeros((0, RANK))), -40.0 if len(y) and y[0] == 1 else 40.0
    lists = got.column("x").combine_chunks()
    lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
    size = np.diff(lists.offsets.to_numpy())
    place, at = lists.flatten().to_numpy(), np.concatenate([[0], np.cumsum(size)])
    back = np.arange(len(y)) % 4 == 3
    if len(set(y[back])) < 2 or len(set(y[~back])) < 2:
        machine = train(place, at, y)
        return machine, cut_at(machine.margins(place, at), y, "f1")
    keep = np.repeat(~back, size)
    machine = train(place[keep], np.concatenate([[0], np.cumsum(size[~back])]), y[~back])
    return machine, cut_at(machine.margins(place[~keep], np.concatenate([[0], np.cumsum(size[back])])), y[back], "f1")


def toxicity_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", parts: int = 3, held: int = 1, sample: int = SAMPLE) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs."""
    machine, cut = fit(docs, labels, "toxic", id_col, text_col, parts, held, sample)
    return scored_docs(docs, lambda data, offs: machine.margins(*terms(data, offs)), cut, id_col, text_col, parts, held)
