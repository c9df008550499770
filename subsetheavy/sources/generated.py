"""Rows drawn from a fitted model."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.models import Model
from ..spec import subset
from .tables import unit


def sample_from_mixture(model: Model, T: Iterable[str], rows: int, seed: int = 42) -> DataFrame:
    """(k, z, T...) for k under rows: a class by the prior, then each coordinate from its shares in the class, by the
    interval of cumulative shares that a number from the key's hash falls in. What survivors leave of 1 gives null."""
    if not model.mixture:
        raise ValueError("a class mixture is needed")
    T, spark = subset(model.coords, T), model.table.sparkSession
    k = F.col("k").cast("string")
    out = spark.range(rows).select(F.col("id").alias("k")).withColumn("u", unit(str(seed), k, "class"))
    at, steps = 0.0, []
    for z, share in model.prior:
        steps.append((z, at, at + share))
        at += share
    steps[-1] = (steps[-1][0], steps[-1][1], 1.0)
    prior = spark.createDataFrame(steps, "z string, lo double, hi double")
    out = out.join(F.broadcast(prior), (F.col("lo") <= F.col("u")) & (F.col("u") < F.col("hi"))).select("k", "z")
    names = F.array(*(F.lit(z) for z, _ in model.prior))
    each = model.table.where(F.col("coord").isin(*T)).select("coord", "value", F.explode(F.arrays_zip(names.alias("z"), F.col("cond").alias("f"))).alias("e")).select("coord", "value", F.col("e.z").alias("cz"), F.col("e.f").alias("f")).where("f > 0")
    w = Window.partitionBy("coord", "cz").orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
    steps = each.withColumn("hi", F.sum("f").over(w)).withColumn("lo", F.col("hi") - F.col("f"))
    for c in T:
        own = steps.where(F.col("coord") == c).select("cz", "lo", "hi", F.col("value").alias(c))
        drawn = out.withColumn("u", unit(str(seed), k, c))
        out = drawn.join(F.broadcast(own), (F.col("z") == F.col("cz")) & (F.col("lo") <= F.col("u")) & (F.col("u") < F.col("hi")), "left").drop("cz", "lo", "hi", "u")
    return out
