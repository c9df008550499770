"""How far a model's shares lie from the true ones, over every joint value, seen or not."""

from __future__ import annotations

from collections.abc import Iterable
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import decoded, long_form, subset, text
from .expand import all_heavy
from .models import Model, class_prior, mass_of


def exact_model(df: DataFrame, T: Iterable[str], cls: str | None = None, floor: float = 0.0) -> Model:
    """All values of T's coordinates of share >= floor, with exact shares."""
    T, m = subset(df.columns, T), df.count()
    types = dict(df.dtypes)
    if cls is None:
        table = long_form(df, T).groupBy("coord", "value").agg(F.count("*").alias("cnt")).withColumn("share", F.col("cnt") / float(max(m, 1)))
        return Model(table.where(F.col("share") >= floor), m, max(floor, 1e-300), T, types=types)
    prior = class_prior(df, cls)
    counted = long_form(df.withColumn("__z", text(cls)), T, ["__z"]).groupBy("coord", "value", "__z").agg(F.count("*").alias("cnt"))
    whole = counted.groupBy("coord", "value").agg(F.sum("cnt").alias("cnt"), F.map_from_entries(F.collect_list(F.struct("__z", "cnt"))).alias("by"))
    sizes = F.array(*(F.struct(F.lit(c).alias("z"), F.lit(float(round(s * m))).alias("n")) for c, s in prior))
    cond = F.transform(sizes, lambda p: F.coalesce(F.try_element_at(F.col("by"), p["z"]), F.lit(0)) / p["n"])
    table = whole.select("coord", "value", "cnt", (F.col("cnt") / float(m)).alias("share"), cond.alias("cond"))
    return Model(table.where(F.col("share") >= floor), m, max(floor, 1e-300), T, prior, cls, types=types)


def model_gap(df: DataFrame, T: Iterable[str], cls: str | None = None) -> DataFrame:
    """(subcube, observed_gap, unobserved_gap, gap). A joint value that never occurs has its mass as gap; only those of
    mass over the observed gap can matter, at most its inverse many, and prefix growth lists them."""
    T = subset(df.columns, T)
    m = df.count()
    model = exact_model(df, T, cls)
    counts = df.groupBy(*(text(c).alias(c) for c in T)).agg(F.count("*").alias("cnt"))
    joined = counts
    for c in T:
        own = model.of(c).select(F.col("value").alias("__v"), F.struct("share", *(["cond"] if cls else [])).alias(f"__p_{c}"))
        joined = joined.join(own, F.col(c) == F.col("__v")).drop("__v")
    masses = joined.select(*T, F.abs(F.col("cnt") / float(max(m, 1)) - mass_of(model, F.array(*(F.col(f"__p_{c}") for c in T)))).alias("gap"))
    seen = masses.agg(F.max("gap")).first()[0] or 0.0
    unseen = 0.0
    if 0 < seen < 1:
        # a value of less than that share is in no joint value of that mass, so at most 1 / seen a coordinate are left
        plain = Model(model.table.where(F.col("share") >= seen * (1 - 1e-12)).persist(), m, seen, T, model.prior, cls)  # values stay as text
        listed = all_heavy(plain, T, seen, reorder=False)
        missing = listed.join(counts.select(*(F.col(c).alias(f"__{c}") for c in T)), [F.col(c).eqNullSafe(decoded(F.col(f"__{c}"), "string")) for c in T], "left_anti")
        unseen = missing.agg(F.max("mass")).first()[0] or 0.0
    return df.sparkSession.createDataFrame([(",".join(T), float(seen), float(unseen), float(max(seen, unseen)))], "subcube string, observed_gap double, unobserved_gap double, gap double")


def model_gap_all(df: DataFrame, coords: Iterable[str], k: int, cls: str | None = None) -> DataFrame:
    """model_gap of every subset of at most k coordinates."""
    from functools import reduce

    coords = tuple(coords)
    return reduce(DataFrame.unionByName, (model_gap(df, T, cls) for n in range(1, k + 1) for T in combinations(coords, n)))


def total_variation(df: DataFrame, T: Iterable[str]) -> DataFrame:
    """(subcube, tv): half the sum of absolute differences from the product, unseen joint values by what is left of 1."""
    T, m = subset(df.columns, T), df.count()
    model = exact_model(df, T)
    joined = df.groupBy(*(text(c).alias(c) for c in T)).agg(F.count("*").alias("cnt"))
    for c in T:
        joined = joined.join(model.of(c).select(F.col("value").alias("__v"), F.struct("share").alias(f"__p_{c}")), F.col(c) == F.col("__v")).drop("__v")
    mass = mass_of(model, F.array(*(F.col(f"__p_{c}") for c in T)))
    got = joined.select((F.col("cnt") / float(max(m, 1))).alias("share"), mass.alias("mass"))
    return got.agg(F.sum(F.abs(F.col("share") - F.col("mass"))).alias("s"), F.sum("mass").alias("w")).select(F.lit(",".join(T)).alias("subcube"), ((F.col("s") + F.greatest(1 - F.col("w"), F.lit(0.0))) / 2).alias("tv"))


def gap_flags(gap: float, gamma: float) -> dict[str, bool]:
    """within_assumption: under gamma / 10, as assumed; enough: under gamma / 4, which right answers need."""
    return {"within_assumption": gap < gamma / 10, "enough": gap < gamma / 4}
