"""What the trained classifiers share: a bounded labelled sample, a calibrated cut and the scoring pass."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts
from .common import begins, fold, tidied

#: A score at which a row is predicted 1; the cut found on held-back sample rows is moved there.
LINE = 0.7
_LINE_AT = math.log(LINE / (1 - LINE))


def sample_ids(labels: DataFrame, label: str, id_col: str, parts: int, held: int, most: int) -> DataFrame:
    """At most `most` labelled ids outside the held-out fold, spread by hash; ids with differing labels take the lesser."""
    known = labels.where(F.col(label).isin(0, 1) & F.col(id_col).isNotNull()).where(fold(id_col, parts) != held)
    return known.groupBy(F.col(id_col).cast("bigint").alias("id")).agg(F.min(label).cast("int").alias("label")).orderBy(F.xxhash64("id"), "id").limit(most)


def sample_rows(docs: DataFrame, ids: DataFrame, id_col: str, text_col: str, work, schema: str) -> pa.Table:
    """What work makes of the sampled rows' (id, label, text); work gives one row for each. At most as many rows as ids."""
    got = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text")).join(F.broadcast(ids), "id").select("id", "label", "text")
    return got.mapInArrow(tidied(work), schema).dropDuplicates(["id"]).toArrow().sort_by("id")


def cut_at(margin: np.ndarray, y: np.ndarray, kind: str) -> float:
    """The margin that best divides the classes on rows not trained on: by F1 of class 1, or by mean recall."""
    order = np.argsort(-margin, kind="stable")
    m, hit = margin[order], y[order].astype(float)
    tp, fp = np.cumsum(hit), np.cumsum(1 - hit)
    value = 2 * tp / (tp + fp + hit.sum()) if kind == "f1" else tp / max(hit.sum(), 1) + 1 - fp / max((1 - hit).sum(), 1)
    value[:-1][m[:-1] == m[1:]] = -1
    i = int(np.argmax(value))
    return float((m[i] + m[i + 1]) / 2 if i + 1 < len(m) else m[i] - 1)


def scored(margin: np.ndarray, cut: float) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(margin - cut + _LINE_AT, -500, 500)))


def scored_docs(docs: DataFrame, margins, cut: float, id_col: str, text_col: str, parts: int, held: int) -> DataFrame:
    """(doc_id, held_out, score, predicted) for each row; margins(bytes, offsets) gives one margin a document."""

    def work(batches):
        begins("learned")
        for batch in batches:
            score = np.concatenate([np.zeros(0), *(scored(margins(data, offs), cut) for _, _, data, offs in ts.runs(batch.column(1)))])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score)], names=["doc_id", "score"])

    got = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidied(work), "doc_id bigint, score double")
    return got.select("doc_id", (fold("doc_id", parts) == held).alias("held_out"), "score", (F.col("score") >= LINE).cast("int").alias("predicted"))


def kept_docs(docs: DataFrame, margins, cut: float, text_col: str) -> DataFrame:
    """The rows of docs, all columns, whose score is at least the line."""

    def work(batches):
        begins("learned")
        for batch in batches:
            score = np.concatenate([np.zeros(0), *(scored(margins(data, offs), cut) for _, _, data, offs in ts.runs(batch.column(batch.schema.get_field_index(text_col))))])
            yield batch.filter(pa.array(score >= LINE))

    return docs.mapInArrow(tidied(work), docs.schema)
