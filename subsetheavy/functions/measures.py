"""Cost and accuracy measures of methods."""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Passes over the stream. The sketch and the counters that name its candidates fill in one pass; as two aggregates they
#: scan twice. Tests hold the models' figures against the scans that their jobs make.
PASSES = {"sample": 1, "sketch": 1, "product": 2, "mixture": 2, "exact": 1}


def estimate_errors(truth: DataFrame, estimates: DataFrame, on: Iterable[str], by: Iterable[str] = ()) -> DataFrame:
    """mse, mae and mape (percent) of `est` in estimates against `share` in truth; a missing estimate is 0."""
    on, by = list(on), list(by)
    est = estimates.select(*(F.col(c).alias(f"__{c}") for c in on), F.col("est"))
    got = truth.join(est, [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in on], "left").withColumn("__d", F.abs(F.coalesce("est", F.lit(0.0)) - F.col("share")))
    return got.groupBy(*by).agg(F.avg(F.col("__d") * F.col("__d")).alias("mse"), F.avg("__d").alias("mae"), (100 * F.avg(F.col("__d") / F.col("share"))).alias("mape"))


def confusion(reported: DataFrame, truth: DataFrame, on: Iterable[str], gamma: float, gap: float = 4.0) -> DataFrame:
    """reported: the joint values a method lists; truth: all observed ones with their share. tp, fp (share < gamma),
    fp_strict (share < gamma / gap, or never observed), fn, reported, negatives (observed under gamma, or reported only)."""
    on = list(on)
    rep = reported.select(*(F.col(c).alias(f"__{c}") for c in on), F.lit(True).alias("__yes"))
    both = truth.join(rep, [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in on], "full").select(F.coalesce("share", F.lit(0.0)).alias("s"), F.coalesce("__yes", F.lit(False)).alias("yes"))
    return both.agg(F.count_if(F.col("yes") & (F.col("s") >= gamma)).alias("tp"), F.count_if(F.col("yes") & (F.col("s") < gamma)).alias("fp"),
                    F.count_if(F.col("yes") & (F.col("s") < gamma / gap)).alias("fp_strict"), F.count_if(~F.col("yes") & (F.col("s") >= gamma)).alias("fn"),
                    F.count_if("yes").alias("reported"), F.count_if(F.col("s") < gamma).alias("negatives"))


def confusion_sweep(reported: DataFrame, score: str, truth: DataFrame, on: Iterable[str], gamma: float | Column, cuts: dict[float, float | Column], gap: float = 4.0, groups: DataFrame | None = None) -> DataFrame:
    """The rows of confusion for one list cut at several lines: (cut, tp, fp, fp_strict, fn, reported, negatives) for
    each name of cuts, whose list is the values with score >= its line. One join serves all of them. groups: the columns of
    on that tell lists apart, with a row for each list, whose columns come first in the result; gamma and lines may depend
    on them."""
    on, by = list(on), groups.columns if groups is not None else []
    rep = reported.select(*(F.col(c).alias(f"__{c}") for c in on), F.col(score).alias("__e"))
    met = truth.join(rep, [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in on], "full").select(*(F.coalesce(c, f"__{c}").alias(c) for c in by), F.col("share").isNotNull().alias("seen"), F.coalesce("share", F.lit(0.0)).alias("s"), "__e")
    # values differ in little that the cuts see, so they are counted by that first
    passed = {f"p{i}": F.coalesce(F.col("__e") >= line, F.lit(False)) for i, line in enumerate(cuts.values())}
    flags = {"heavy": F.col("s") >= gamma, "far": F.col("s") < gamma / gap} | passed
    kinds = met.groupBy(*by, "seen", *(f.alias(n) for n, f in flags.items())).agg(F.count("*").alias("n"))
    if groups is not None:
        # a list of nothing over nothing has its row of zeros too
        kinds = kinds.unionByName(groups.select(*by, *(F.lit(False).alias(n) for n in ("seen", *flags)), F.lit(0).cast("bigint").alias("n")))
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0))
    heavy, each = F.col("heavy"), []
    for i, name in enumerate(cuts):
        yes = F.col(f"p{i}")
        each.append(F.struct(F.lit(name).alias("cut"), total(yes & ~heavy).alias("fp"), total(yes & heavy).alias("tp"), total(yes & F.col("far")).alias("fp_strict"),
                             total(~yes & heavy).alias("fn"), total(yes).alias("reported"), total(~heavy & (yes | F.col("seen"))).alias("negatives")))
    return kinds.groupBy(*by).agg(F.array(*each).alias("all")).select(*by, F.explode("all").alias("e")).select(*by, *(f"e.{c}" for c in ("cut", "tp", "fp", "fp_strict", "fn", "reported", "negatives")))


def rates(points: DataFrame) -> DataFrame:
    """Adds tpr and fpr to rows of confusion."""
    return points.withColumn("tpr", F.when(F.col("tp") + F.col("fn") > 0, F.col("tp") / (F.col("tp") + F.col("fn"))).otherwise(0.0)).withColumn("fpr", F.when(F.col("negatives") > 0, F.col("fp") / F.col("negatives")).otherwise(0.0))


def auc(points: DataFrame, by: Iterable[str] = ()) -> DataFrame:
    """Area under (fpr, tpr) by trapezoids, from (0, 0) to (1, 1)."""
    by = list(by)
    ends = points.select(*by).distinct().select(*by, F.explode(F.array(F.struct(F.lit(0.0).alias("fpr"), F.lit(0.0).alias("tpr")), F.struct(F.lit(1.0).alias("fpr"), F.lit(1.0).alias("tpr")))).alias("e")).select(*by, "e.fpr", "e.tpr")
    w = Window.partitionBy(*by).orderBy("fpr", "tpr")
    steps = points.select(*by, "fpr", "tpr").unionByName(ends).select(*by, (F.col("fpr") - F.lag("fpr").over(w)).alias("dx"), (F.col("tpr") + F.lag("tpr").over(w)).alias("sy"))
    return steps.groupBy(*by).agg(F.coalesce(F.sum(F.col("dx") * F.col("sy") / 2), F.lit(0.0)).alias("auc"))


def memory_cells(method: str, d: int, size: int, classes: int = 1, survivors: int = 0) -> int:
    """Stored cells: sample d * rows; sketch d * cells; models d * counters, with the conditionals stored in the mixture."""
    return d * size + (classes * survivors if method == "mixture" else 0)


def budget_to_params(pct: float, d: int, m: int, classes: int = 1, depth: int = 5) -> dict[str, int]:
    """What pct percent of the stream's d * m cells buys of each method: sample rows, sketch width, counters."""
    size = max(1, math.floor(pct / 100 * m))
    return {"size": size, "cells": size, "width": max(1, size // depth), "depth": depth, "capacity": max(1, size)}


def success_rate(df: DataFrame, key: Iterable[str], T: Iterable[str], gamma: float, size: int, seeds: Iterable[int]) -> float:
    """Part of sampling runs in which every observed joint value is answered rightly (share >= gamma yes, < gamma/4 no)."""
    from ..operators.exact import exact_shares
    from ..operators.sampling import draw_sample, sample_all_heavy

    truth = exact_shares(df, T)
    runs = [confusion(sample_all_heavy(draw_sample(df, key, size, s), T, gamma / 2), truth, T, gamma).first() for s in seeds]
    return sum(r["fn"] == 0 and r["fp_strict"] == 0 for r in runs) / max(len(runs), 1)


def averaged(points: DataFrame, by: Iterable[str], values: Iterable[str] = ("tp", "fp", "fp_strict", "fn", "reported")) -> DataFrame:
    return points.groupBy(*by).agg(*(F.avg(v).alias(v) for v in values))
