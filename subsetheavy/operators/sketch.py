"""The one-pass heuristic: the product of sketched shares, with no guarantee."""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import StreamSpec, share_of
from .models import Model
from .summaries import count_min, count_min_estimate, misra_gries

#: Most candidates a listing goes through; more means the sketch is too narrow to tell heavy values from others.
MOST = 200_000


def fit_sketch(df: DataFrame, coords: Iterable[str], cut: float, width: int, depth: int = 5, seed: int | str = 0, hash: str = "xxhash64", candidates: DataFrame | None = None, cls: str | None = None) -> Model:
    """A product model whose shares are the sketch's estimates of each coordinate's candidates (its own heavy list from
    the same pass, if none are given). Estimates of a coordinate may sum to over 1, so lists have no 1 / cut bound."""
    if cls is not None:
        raise ValueError("the sketch can't give shares within a class")
    spec = StreamSpec.of(df, coords)
    share_of(cut, "cut")
    cells = count_min(df, spec.coords, width, depth, seed, hash).persist()
    # every row is in one cell of each row of the sketch
    m = cells.where((F.col("coord") == spec.coords[0]) & (F.col("depth_row") == 0)).agg(F.coalesce(F.sum("cnt"), F.lit(0))).first()[0]
    pool = misra_gries(df, spec.coords, min(math.ceil(2 / cut), max(width * depth, 1))) if candidates is None else candidates
    est = count_min_estimate(cells, pool, width, depth, seed, hash)
    return Model(est.select("coord", "value", F.col("estimate").alias("cnt"), (F.col("estimate") / float(max(m, 1))).alias("share")).persist(), m, cut, spec.coords, types=spec.types)


def sketch_all_heavy(model: Model, T: Iterable[str], cut: float) -> DataFrame:
    """The list by the sketch, refused where its candidates are too many to be heavy values."""
    from .expand import all_heavy

    many = model.table.where(F.col("share") >= cut).count()
    if many > MOST:
        raise ValueError(f"{many} candidates reach the cut: widen the sketch")
    return all_heavy(model, T, cut)
