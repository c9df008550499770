"""Uniform samples without replacement, as the rows of least priority.

A row's priority is a hash of the seed and its key. The sample of a union is the least rows of the parts' samples, so
samples merge, grow by increments, and come out the same under retries and any partitioning.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..spec import share_of, subset, unclashed
from .exact import matches

#: A sample up to this size is cut by a top-k; a larger one by a threshold first.
TOP = 200_000


def decision_line(gamma: float, gap: float = 4.0) -> float:
    """The share at which a sample's verdict is yes: between gamma, which must be reported, and gamma / gap, which must
    not, as far from one as from the other by ratio."""
    if gap <= 1:
        raise ValueError(f"gap must be over 1: {gap}")
    return share_of(gamma) / math.sqrt(gap)


def _tails(gap: float) -> float:
    """How many items a verdict needs, times gamma, for an error of 1/e by the two tail bounds at the decision line."""
    up = math.sqrt(gap) - 1
    return max(2 / (1 - 1 / math.sqrt(gap)) ** 2, gap * (2 + up) / up**2)


def sample_size_bound(gamma: float, k: int, d: int, n: int, delta: float = 0.1, gap: float = 4.0) -> int:
    """Items enough for every joint value of every k of d coordinates over n values to be judged right together."""
    return math.ceil(48 * (_tails(gap) / _tails(4.0)) / share_of(gamma) * (math.log(2 / delta) + k * math.log(d * n)))


def majority_repeats(delta: float, each: float = 0.25) -> int:
    """Independent samples, an odd number, whose majority errs with a chance of at most delta if each errs with `each`."""
    return 2 * math.ceil((math.log(1 / delta) / (2 * (0.5 - each) ** 2) - 1) / 2) + 1


def priority(key: Iterable[str], seed: int | str = 0, hash: str = "xxhash64") -> Column:
    """xxhash64: fast, in 64 bits. md5: the same number in any engine, in 32 bits."""
    key = list(key)
    if hash == "xxhash64":
        return F.xxhash64(F.lit(str(seed)), *key)
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.col(k).cast("string") for k in key])), 1, 8), 16, 10).cast("bigint")


def draw_sample(df: DataFrame, key: Iterable[str], size: int, seed: int | str = 0, hash: str = "xxhash64", by: Iterable[str] = ()) -> DataFrame:
    """size rows of df (of each group of by) with their priority. Ties go by the key, which must tell rows apart."""
    key, by = list(key), list(by)
    unclashed(df.columns, ("priority",))
    ranked = df.withColumn("priority", priority(key, seed, hash))
    if by:
        w = Window.partitionBy(*by).orderBy("priority", *key)
        return ranked.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= size).drop("__r")
    if size > TOP:
        # a map-side threshold with slack leaves little more than the sample to sort; too few rows fall back to all
        m = df.count()
        if m > 2 * size:
            low, span = (-(2**63), 2.0**64) if hash == "xxhash64" else (0, 2.0**32)
            part = size / m
            cut = low + (part + 6 * math.sqrt(part / m)) * span
            few = ranked.where(F.col("priority") <= F.lit(cut).cast("bigint"))
            return _least(few, ranked, key, size, low, (cut - low) / BUCKETS)
    return ranked.orderBy("priority", *key).limit(size)


#: Buckets of priorities by which a large sample is cut.
BUCKETS = 4096


def _least(few: DataFrame, ranked: DataFrame, key: list[str], size: int, low: float, step: float) -> DataFrame:
    """The size rows of least priority of few: whole buckets of priorities, and of the bucket in which the sample ends a
    sorted part, so that no task sorts or holds the sample. If few has fewer rows, of ranked."""
    bucket = F.least(F.floor((F.col("priority").cast("double") - low) / step), F.lit(BUCKETS - 1)).cast("int")
    counts = sorted((r["b"], r["n"]) for r in few.groupBy(bucket.alias("b")).agg(F.count("*").alias("n")).collect())
    before = 0
    for b, n in counts:
        if before + n >= size:
            last = few.where(bucket == b).orderBy("priority", *key).limit(size - before)
            return few.where(bucket < b).unionByName(last)
        before += n
    return ranked.orderBy("priority", *key).limit(size)


def draw_samples(ranked: DataFrame, key: Iterable[str], by: str, sizes: dict[str, dict[str, int]]) -> DataFrame:
    """draw_sample's rows for several sizes and for each group of by, from rows that have their md5 priority. sizes: those of
    each group, by a name. A row comes once for each sample that holds it, with the sample's name in the column sample."""
    key, spark = list(key), ranked.sparkSession
    unclashed(ranked.columns, ("sample", "lines"))
    bucket = F.floor(F.col("priority") / 2.0**32 * BUCKETS).cast("int")
    counts: dict[str, list[tuple[int, int]]] = {}
    for r in ranked.groupBy(by, bucket.alias("b")).agg(F.count("*").alias("n")).collect():
        counts.setdefault(r[by], []).append((r["b"], r["n"]))
    lines = []
    for group, each in sizes.items():
        ends = []
        for name, size in each.items():
            end, rest = BUCKETS, size
            for b, n in sorted(counts.get(group, [])):
                if rest < n:
                    end = b
                    break
                rest -= n
            # whole buckets under end, and the rest least rows of that one
            ends.append((name, end, rest))
        lines.append((group, ends))
    held = F.broadcast(spark.createDataFrame(lines, "__g string, lines array<struct<name string, end int, rest bigint>>"))
    met = ranked.join(held, F.col(by) == F.col("__g")).drop("__g").withColumn("__b", bucket)
    whole = met.withColumn("sample", F.explode(F.filter("lines", lambda x: x["end"] > F.col("__b"))["name"]))
    w = Window.partitionBy(by, "__b").orderBy("priority", *key)
    last = met.where(F.exists("lines", lambda x: (x["end"] == F.col("__b")) & (x["rest"] > 0))).withColumn("__r", F.row_number().over(w))
    last = last.withColumn("sample", F.explode(F.filter("lines", lambda x: (x["end"] == F.col("__b")) & (x["rest"] >= F.col("__r")))["name"])).drop("__r")
    return whole.unionByName(last).drop("lines", "__b")


def merge_samples(a: DataFrame, b: DataFrame, key: Iterable[str], size: int) -> DataFrame:
    """The sample of the union, from samples of its parts drawn with one seed; a row in both counts once."""
    key = list(key)
    both = a.unionByName(b).dropDuplicates(key)
    if size <= TOP:
        return both.orderBy("priority", *key).limit(size)
    low, high = both.agg(F.min("priority"), F.max("priority")).first()
    if low is None:
        return both
    return _least(both, both, key, size, float(low), max((float(high) - float(low)) / BUCKETS, 1.0))


def reservoir_sample(df: DataFrame, size: int, seed: int = 0) -> DataFrame:
    """The classic sequential reservoir in each partition; partitions then merge by drawing, for each kept place, from
    which of them it comes in proportion to their sizes. Kept as a variant: it depends on the partitioning."""
    kind = df.schema
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kind) + ", __seen bigint, __part string, __u double"

    def work(frames):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        rng, held, seen = random.Random(f"{seed}|{part}"), [], 0
        for frame in frames:
            for row in frame.itertuples(index=False, name=None):
                seen += 1
                if len(held) < size:
                    held.append(row)
                elif (j := rng.randrange(seen)) < size:
                    held[j] = row
        rng.shuffle(held)
        out = pd.DataFrame(held, columns=kind.names)
        out["__seen"], out["__part"] = seen, str(part)
        # exponential spacings: the order of the first places over all partitions is that of a uniform draw
        at, us = 0.0, []
        for i in range(len(held)):
            at += rng.expovariate(1.0) / max(seen - i, 1)
            us.append(at)
        out["__u"] = us
        yield out

    return df.mapInPandas(work, fields).orderBy("__u").limit(size).select(*kind.names)


def bernoulli_sample(df: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """Each row by itself with the same chance; the size is random."""
    return df.sample(fraction=fraction, seed=seed)


def sample_share(sample: DataFrame, T: Iterable[str], v: Iterable[object]) -> float:
    hit, m = sample.agg(F.count_if(matches(subset(sample.columns, T), v)), F.count("*")).first()
    return hit / m if m else 0.0


def sample_verdict(sample: DataFrame, T: Iterable[str], v: Iterable[object], cut: float) -> bool:
    """Whether v's share in the sample reaches the cut (gamma / 2 for the guarantee)."""
    return sample_share(sample, T, v) >= cut


def sample_all_heavy(sample: DataFrame, T: Iterable[str], cut: float) -> DataFrame:
    """(T..., cnt, share) of the sample's joint values with share >= cut."""
    T = subset(sample.columns, T)
    size = sample.count()
    return sample.groupBy(*T).agg(F.count("*").alias("cnt")).withColumn("share", F.col("cnt") / float(max(size, 1))).where(F.col("share") >= cut)


def sample_verdicts(sample: DataFrame, probes: DataFrame, T: Iterable[str], cut: float) -> DataFrame:
    """probes has T's columns; adds share and yes. Counts per joint value come first, so the join is of counts."""
    T = subset(sample.columns, T)
    size = sample.count()
    counts = sample.groupBy(*(F.col(c).alias(f"__{c}") for c in T)).agg(F.count("*").alias("__n"))
    on = [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in T]
    return probes.join(counts, on, "left").select(*probes.columns, (F.coalesce("__n", F.lit(0)) / float(max(size, 1))).alias("share")).withColumn("yes", F.col("share") >= cut)


def majority_verdict(df: DataFrame, key: Iterable[str], T: Iterable[str], v: Iterable[object], cut: float, size: int, seeds: Iterable[int | str] | None = None, hash: str = "xxhash64", delta: float = 0.1) -> bool:
    """The majority over independent samples: wrong with a chance that falls exponentially in their number. Without
    seeds, as many samples as delta needs."""
    votes = [sample_verdict(draw_sample(df, key, size, s, hash), T, v, cut) for s in (range(majority_repeats(delta)) if seeds is None else seeds)]
    return 2 * sum(votes) > len(votes)
