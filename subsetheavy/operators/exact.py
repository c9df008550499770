"""True shares of joint values, and what is derived from them."""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..spec import long_form, share_of, subset, text, unclashed


def rows_of(df: DataFrame) -> int:
    return df.count()


def exact_shares(df: DataFrame, T: Iterable[str], m: int | None = None) -> DataFrame:
    """(T..., cnt, share) of every observed joint value."""
    T = subset(df.columns, T)
    unclashed(T, ("cnt", "share"))
    m = rows_of(df) if m is None else m
    return df.groupBy(*T).agg(F.count("*").alias("cnt")).withColumn("share", F.col("cnt") / F.lit(float(max(m, 1))))


def exact_all_heavy(df: DataFrame, T: Iterable[str], gamma: float, prune: bool = False) -> DataFrame:
    """Joint values of true share >= gamma. prune: first keep rows whose every coordinate is heavy alone, which a heavy
    joint value's rows are; almost no row then reaches the shuffle of joint values."""
    T, m = subset(df.columns, T), rows_of(df)
    share_of(gamma)
    if prune:
        # one scan counts all coordinates; each has at most 1/gamma heavy values
        heavy = long_form(df, T).groupBy("coord", "value").agg(F.count("*").alias("__n")).where(F.col("__n") >= gamma * m).persist()
        for c in T:
            own = heavy.where(F.col("coord") == c).select(F.col("value").alias("__v"))
            df = df.join(F.broadcast(own), text(c) == F.col("__v"), "left_semi")
    return exact_shares(df, T, m).where(F.col("share") >= gamma)


def matches(T: Iterable[str], v: Iterable[object]) -> Column:
    return reduce(lambda a, b: a & b, (F.col(c).eqNullSafe(F.lit(x)) for c, x in zip(T, v, strict=True)))


def exact_verdict(df: DataFrame, T: Iterable[str], v: Iterable[object], gamma: float) -> bool:
    hit, m = df.agg(F.count_if(matches(T, v)), F.count("*")).first()
    return m > 0 and hit >= gamma * m


def calibrate_gamma(df: DataFrame, Ts: Iterable[Iterable[str]], ratio: float = 0.01) -> DataFrame:
    """For each subset the share of its joint value at rank floor(ratio * distinct): the least threshold with at most
    that part of the joint values heavy, ties aside. (subcube, distinct_values, heavy, gamma)."""
    m, out = rows_of(df), []
    for T in map(tuple, Ts):
        # the number of joint values with each count is far smaller than the number of joint values
        by = exact_shares(df, T, m).groupBy("cnt").agg(F.count("*").alias("n"))
        w = Window.orderBy(F.desc("cnt")).rowsBetween(Window.unboundedPreceding, 0)
        ranked = by.select("cnt", F.sum("n").over(w).alias("upto"), F.sum("n").over(Window.partitionBy()).alias("total"))
        got = ranked.where(F.col("upto") >= F.greatest(F.floor(F.col("total") * ratio), F.lit(1))).agg(F.max("cnt").alias("cnt"), F.max("total").alias("distinct_values"), F.min(F.when(F.lit(True), F.col("upto"))).alias("heavy"))
        out.append(got.select(F.lit(",".join(T)).alias("subcube"), "distinct_values", "heavy", (F.col("cnt") / float(m)).alias("gamma")))
    return reduce(DataFrame.unionByName, out)


def fix_class(df: DataFrame, cls: str) -> DataFrame:
    """The rows of the most frequent class, ties to the lesser."""
    top = df.groupBy(F.col(cls).alias("__c")).count().orderBy(F.desc("count"), "__c").limit(1).select("__c")
    return df.join(F.broadcast(top), F.col(cls).eqNullSafe(F.col("__c")), "left_semi")


def cramers_v(df: DataFrame, a: str, b: str) -> DataFrame:
    """(a, b, v): association of two categorical columns, from counts alone."""
    joint = df.groupBy(F.col(a).alias("__x"), F.col(b).alias("__y")).agg(F.count("*").alias("n"))
    ca, cb = joint.groupBy(F.col("__x").alias("__a")).agg(F.sum("n").alias("na")), joint.groupBy(F.col("__y").alias("__b")).agg(F.sum("n").alias("nb"))
    m = joint.agg(F.sum("n").alias("m"))
    least = ca.agg(F.count("*").alias("ra")).crossJoin(cb.agg(F.count("*").alias("rb"))).crossJoin(m)
    term = joint.join(ca, F.col("__x").eqNullSafe(F.col("__a"))).join(cb, F.col("__y").eqNullSafe(F.col("__b"))).agg(F.sum(F.col("n").cast("double") * F.col("n") / (F.col("na").cast("double") * F.col("nb"))).alias("s"))
    # chi-square / m = sum n^2 / (na nb) - 1
    return term.crossJoin(least).select(F.lit(a).alias("a"), F.lit(b).alias("b"), F.when(F.least("ra", "rb") < 2, F.lit(0.0)).otherwise(F.sqrt(F.greatest(F.col("s") - 1, F.lit(0.0)) / (F.least("ra", "rb") - 1))).alias("v"))


def cramers_matrix(df: DataFrame, coords: Iterable[str]) -> DataFrame:
    return reduce(DataFrame.unionByName, (cramers_v(df, a, b) for a, b in combinations(coords, 2)))


def heavy_stats(df: DataFrame, Ts: dict[tuple[str, ...], float]) -> DataFrame:
    """(subcube, distinct_values, heavy, ratio) for each subset and its threshold."""
    m, out = rows_of(df), []
    for T, gamma in Ts.items():
        got = exact_shares(df, T, m).agg(F.count("*").alias("distinct_values"), F.count_if(F.col("share") >= gamma).alias("heavy"))
        out.append(got.select(F.lit(",".join(T)).alias("subcube"), "distinct_values", "heavy", (F.col("heavy") / F.col("distinct_values")).alias("ratio")))
    return reduce(DataFrame.unionByName, out)
