"""Language ID by rank order: a document's most frequent n-grams against each language's, by out-of-place distance.

N-grams are runs of one to three letters within words, with word ends marked, A-Z and other letters lower-cased.
Profiles keep the TOP most frequent n-grams of a bounded sample of texts that carry a language (SAMPLE rows, spread by
hash). A document's distance to a language is the sum over its own TOP n-grams of how far each lies from its place in
the profile, TOP for one that the profile lacks. score is 1 less the distance over its largest value. Ties go to the
lesser name. Null texts and texts without a letter, and all texts where nothing could be learned, are `und` with 0.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold

SAMPLE, TOP = 8_000, 300
_EDGE = 1
_BLOCK = 1 << 19


@lru_cache(1)
def letters() -> np.ndarray:
    """For each code point itself if it is a letter, else 0."""
    every = np.arange(0x110000, dtype=np.uint32)
    keep = np.zeros(len(every), bool)
    for lo in range(0, 0x110000, 0x1000):
        if not 0xD000 <= lo < 0xE000:
            keep[lo : lo + 0x1000] = [chr(c).isalpha() for c in range(lo, lo + 0x1000)]
    keep[0xD000:0xD800] = [chr(c).isalpha() for c in range(0xD000, 0xD800)]
    return np.where(keep, every, 0).astype(np.uint32)


def grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(n-gram codes, the text of each). Three code points of 21 bits make a code."""
    lowered = [t.lower() for t in texts]
    code = letters()[np.frombuffer("\0".join(["", *lowered, ""]).encode("utf-32-le", "surrogatepass"), np.uint32)].astype(np.int64)
    of = np.repeat(np.arange(len(lowered)), [len(t) + 1 for t in lowered])
    of = np.concatenate([of, of[-1:]]) if len(of) else np.zeros(1, np.int64)
    is_letter = code > 0
    a = np.where(is_letter, code, _EDGE)
    pair = (a[:-1] << 21) | a[1:]
    keep2 = is_letter[:-1] | is_letter[1:]
    three = (a[:-2] << 42) | pair[1:]
    keep3 = is_letter[1:-1]
    return (np.concatenate([code[is_letter], pair[keep2], three[keep3]]), np.concatenate([of[is_letter], np.where(is_letter[1:], of[1:], of[:-1])[keep2], of[1:-1][keep3]]))


def ranked(codes: np.ndarray, top: int) -> np.ndarray:
    """The most frequent codes, first the most frequent, ties by code."""
    codes = np.sort(codes)
    first = np.flatnonzero(np.concatenate([np.ones(min(1, len(codes)), bool), codes[1:] != codes[:-1]]))
    many = np.diff(np.concatenate([first, [len(codes)]]))
    if len(first) > 4 * top:
        keep = many >= -np.partition(-many, top)[top]
        first, many = first[keep], many[keep]
    return codes[first[np.argsort(-many, kind="stable")[:top]]]


def _blocks(texts: list[str]):
    lo = size = 0
    for i, t in enumerate(texts):
        size += len(t)
        if size > _BLOCK or i + 1 == len(texts):
            yield lo, i + 1
            lo, size = i + 1, 0


def _count(batches):
    for batch in batches:
        texts, langs = batch.column(0).fill_null("").to_pylist(), np.array(batch.column(1).to_pylist(), object)
        for lo, hi in _blocks(texts):
            codes, of = grams(texts[lo:hi])
            for lang in sorted(set(langs[lo:hi])):
                own, many = np.unique(codes[np.isin(of, np.flatnonzero(langs[lo:hi] == lang))], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(own), pa.string()), pa.array(own), pa.array(many)], names=["lang", "gram", "n"])


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", parts: int = 4, held: int = 2, sample: int = SAMPLE, top: int = TOP) -> dict[str, np.ndarray]:
    """For each language its profile: n-gram codes in rank order. The sample is of `sample` rows as expected value."""
    from pyspark.sql import Window

    known = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where("lang is not null and id is not null").where(fold("id", parts) != held)
    # each language gives an even part of the sample, a rare one all it has
    langs = known.groupBy("lang").count().collect()
    if not langs:
        return {}
    each = max(50, sample // len(langs))
    share = F.create_map(*[x for r in langs for x in (F.lit(r["lang"]), F.lit(min(1.0, each / r["count"])))])
    chosen = known.where(F.pmod(F.xxhash64("id"), F.lit(1 << 30)) < share[F.col("lang")] * (1 << 30))
    counted = chosen.select("text", "lang").mapInArrow(_count, "lang string, gram bigint, n bigint").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    best = counted.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))).where(F.col("r") <= top).toArrow().sort_by([("lang", "ascending"), ("r", "ascending")])
    lang, gram = np.array(best.column("lang").to_pylist(), object), best.column("gram").to_numpy()
    return {name: gram[lang == name] for name in sorted(set(lang.tolist()))}


class Ranks:
    """All profiles in one sorted array of codes, with each language's rank of each code."""

    def __init__(self, profiles: dict[str, np.ndarray], top: int = TOP):
        self.names, self.top = sorted(profiles), top
        self.codes = np.unique(np.concatenate([np.zeros(0, np.int64), *profiles.values()]))
        self.rank = np.full((len(self.codes), len(self.names)), -1, np.int64)
        for i, name in enumerate(self.names):
            self.rank[np.searchsorted(self.codes, profiles[name]), i] = np.arange(len(profiles[name]))

    def judge(self, texts: list[str]) -> list[tuple[str, float]]:
        if not self.names:
            return [("und", 0.0)] * len(texts)
        out = []
        for lo, hi in _blocks(texts):
            codes, of = grams(texts[lo:hi])
            order = np.argsort(of, kind="stable")
            codes, cuts = codes[order], np.searchsorted(of[order], np.arange(hi - lo + 1))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                own = ranked(codes[a:b], self.top)
                if not len(own):
                    out.append(("und", 0.0))
                    continue
                where = np.minimum(np.searchsorted(self.codes, own), len(self.codes) - 1)
                rank = np.where((self.codes[where] == own)[:, None], self.rank[where], -1)
                far = np.where(rank < 0, self.top, np.abs(rank - np.arange(len(own))[:, None])).sum(0)
                i = int(far.argmin())
                out.append((self.names[i], float(1 - far[i] / (self.top * len(own)))))
        return out


def languages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", parts: int = 4, held: int = 2, sample: int = SAMPLE, top: int = TOP) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row of docs."""
    ranks = Ranks(fit(docs, id_col, text_col, lang_col, parts, held, sample, top), top)

    def work(batches):
        for batch in batches:
            got = ranks.judge(batch.column(1).fill_null("").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x for x, _ in got], pa.string()), pa.array([x for _, x in got], pa.float64())], names=["doc_id", "lang_pred", "score"])

    got = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(work, "doc_id bigint, lang_pred string, score double")
    return got.select("doc_id", (fold("doc_id", parts) == held).alias("held_out"), "lang_pred", "score")
