"""What the methods are compared with: one structure for each subset, the linearised tuple, itemsets, brute force."""

from __future__ import annotations

import math
from collections.abc import Iterable
from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as t

from ..spec import StreamSpec, subset, text
from .summaries import misra_gries


def linearised(df: DataFrame, T: Iterable[str], name: str) -> DataFrame:
    """The joint value of T as one column. Parts are escaped, so different joint values stay different."""
    esc = [F.replace(F.replace(text(c), F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|")) for c in T]
    return df.select("*", F.concat_ws("|", *esc).alias(name))


def per_subcube_summary(df: DataFrame, coords: Iterable[str], k: int, capacity: int) -> DataFrame:
    """(coord, value, counter): counters for each of the C(d, k) subsets, named by their coordinates. One scan."""
    coords = StreamSpec.of(df, coords).coords
    names = []
    for T in combinations(coords, k):
        name = "+".join(T)
        df = linearised(df, T, name)
        names.append(name)
    return misra_gries(df.select(*(f"`{n}`" for n in names)), names, capacity)


def per_subcube_cells(d: int, k: int, capacity: int) -> int:
    return math.comb(d, k) * capacity


def subcube_counts(df: DataFrame, Ts: Iterable[Iterable[str]]) -> DataFrame:
    """Exact joint counts of several subsets in one scan, by grouping sets: (subcube, vals array, cnt)."""
    Ts = [tuple(T) for T in Ts]
    every = list(dict.fromkeys(c for T in Ts for c in T))
    # long forms keep nulls of the data apart from nulls of the grouping
    base = df.select(*(text(c).alias(c) for c in every))
    got = base.groupingSets([[F.col(c) for c in T] for T in Ts], *every).agg(F.count("*").alias("cnt"), F.grouping_id().alias("gid"))
    pick = {sum(1 << (len(every) - 1 - i) for i, c in enumerate(every) if c not in T): T for T in Ts}
    named = [F.when(F.col("gid") == g, F.struct(F.lit(",".join(T)).alias("subcube"), F.array(*(F.col(c) for c in T)).alias("vals"))) for g, T in pick.items()]
    return got.select(F.coalesce(*named).alias("s"), "cnt").select("s.subcube", "s.vals", "cnt")


def unary_encode(df: DataFrame, key: Iterable[str], coords: Iterable[str]) -> DataFrame:
    """(row, item): each coordinate's value as an item of its own, so joint values are itemsets."""
    coords = tuple(coords)
    row = F.concat_ws("|", *(F.col(c).cast("string") for c in key)).alias("row")
    items = [F.concat_ws("=", F.lit(c), text(c)) for c in coords]
    return df.select(row, F.explode(F.array(*items)).alias("item"))


def itemset_heavy(df: DataFrame, T: Iterable[str], gamma: float) -> DataFrame:
    """Heavy joint values of T as frequent itemsets with one item of each coordinate: (items array, freq)."""
    from pyspark.ml.fpm import FPGrowth

    T = subset(df.columns, T)
    baskets = df.select(F.array(*(F.concat_ws("=", F.lit(c), text(c)) for c in T)).alias("items"))
    found = FPGrowth(itemsCol="items", minSupport=gamma, minConfidence=1.0).fit(baskets).freqItemsets
    return found.where(F.size("items") == len(T)).select(F.array_sort("items").alias("items"), "freq")


def frequent_flag_subcubes(df: DataFrame, flags: Iterable[str], gamma: float, k_max: int) -> DataFrame:
    """(flags array, share) of each set of at most k_max flags that are true together in a share >= gamma of rows, level
    by level: a set is counted only if every set of one flag fewer is frequent. Each level is one pass of counters."""
    flags = StreamSpec.of(df, flags).coords
    spark, m = df.sparkSession, df.count()
    level, found = [(f,) for f in sorted(flags)], []
    for _ in range(k_max):
        if not level:
            break
        got = df.agg(*(F.count_if(reduce(lambda a, b: a & b, (F.col(f) for f in s))).alias(str(i)) for i, s in enumerate(level))).first()
        now = [(s, got[i] / m) for i, s in enumerate(level) if m and got[i] >= gamma * m]
        found += now
        have = {s for s, _ in now}
        level = sorted({tuple(sorted({*a, *b})) for a in have for b in have if len({*a, *b}) == len(a) + 1})
        level = [s for s in level if all(tuple(x for x in s if x != f) in have for f in s)]
    kind = t.StructType([t.StructField("flags", t.ArrayType(t.StringType())), t.StructField("share", t.DoubleType())])
    return spark.createDataFrame([(list(s), v) for s, v in found], kind)


def maximal(found: DataFrame) -> DataFrame:
    """The sets that no other found set holds."""
    more = found.select(F.col("flags").alias("__f"))
    return found.join(more, (F.size("__f") > F.size("flags")) & (F.size(F.array_intersect("flags", "__f")) == F.size("flags")), "left_anti")


def lower_bound_bits(k: int, d: int, gamma: float) -> float:
    """Bits that any constant-pass method needs for itemsets, its constant taken as 1."""
    return k * d / gamma * math.log2(max(d / k, 1.0))
