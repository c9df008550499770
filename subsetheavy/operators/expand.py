"""Lists all heavy joint values of a model by growing prefixes, one coordinate at a time."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import decoded, subset, unclashed
from .models import Model, prior_array

STRATEGIES = ("bucketed", "nested", "sorted", "cartesian")
#: Rows of a table of subsets that are broadcast; a longer table is joined by a shuffle.
MOST = 1_000_000


def _folded(a):
    return F.aggregate(a, F.lit(0.0), lambda acc, x: acc + x)


def _start(model: Model, coord: str) -> DataFrame:
    if not model.mixture:
        return model.of(coord).select(F.col("value").alias("__v1"), F.col("share").alias("__q"))
    return model.of(coord).select(F.col("value").alias("__v1"), F.zip_with(prior_array(model), F.col("cond"), lambda a, b: a * b).alias("__q"))


def _extended(model: Model):
    """The prefix's mass with the next value, by class in the mixture."""
    return F.zip_with(F.col("__q"), F.col("__s"), lambda a, b: a * b) if model.mixture else F.col("__q") * F.col("__s")


def _mass(model: Model, q):
    return _folded(q) if model.mixture else q


def _next(model: Model, coord: str, j: int) -> DataFrame:
    return model.of(coord).select(F.col("value").alias(f"__v{j}"), F.col("cond" if model.mixture else "share").alias("__s"))


def _grow(model: Model, have: DataFrame, coord: str, j: int, cut: float, strategy: str) -> DataFrame:
    names = [f"__v{i}" for i in range(1, j)]
    more = _next(model, coord, j)
    if strategy == "nested":
        got = have.join(F.broadcast(more), _mass(model, _extended(model)) >= cut)
        return got.select(*names, f"__v{j}", _extended(model).alias("__q"))
    top = F.array_max("__s") if model.mixture else F.col("__s")
    if strategy == "sorted":
        # the next survivors as one array by falling share, of which a prefix takes a leading part
        held = more.agg(F.reverse(F.array_sort(F.collect_list(F.struct(top.alias("t"), F.col("__s").alias("s"), F.col(f"__v{j}").alias("v"))))).alias("__all"))
        reach = F.filter(F.col("__all"), lambda e: e["t"] * _mass(model, F.col("__q")) >= cut)
        got = have.crossJoin(F.broadcast(held)).select(*names, "__q", F.explode(reach).alias("__e")).select(*names, F.col("__e.v").alias(f"__v{j}"), "__q", F.col("__e.s").alias("__s"))
        return got.where(_mass(model, _extended(model)) >= cut).select(*names, f"__v{j}", _extended(model).alias("__q"))
    # by powers of two: a prefix of mass q reaches shares >= cut / q, which lie in few buckets
    bucketed = more.where(top > 0).withColumn("__b", F.floor(-F.log2(top)).cast("int"))
    reach = F.floor(F.log2(_mass(model, F.col("__q")) / cut) + 1e-9).cast("int")
    spread = have.where(reach >= 0).withColumn("__b", F.explode(F.sequence(F.lit(0), reach)))
    got = spread.join(F.broadcast(bucketed), "__b")
    return got.where(_mass(model, _extended(model)) >= cut).select(*names, f"__v{j}", _extended(model).alias("__q"))


def all_heavy(model: Model, T: Iterable[str], cut: float | None = None, strategy: str = "bucketed", reorder: bool = True) -> DataFrame:
    """(T..., mass) of every joint value of survivors whose model share reaches the cut. Every step keeps at most 1 / cut
    prefixes, as the model's shares sum to one, so nothing here grows with the stream. Coordinates with few survivors
    go first; the result has T's order. cut below the model's own line finds no value that the line has dropped."""
    T = subset(model.coords, T)
    unclashed(T, ("mass",))
    cut = model.lam if cut is None else cut
    if strategy not in STRATEGIES:
        raise ValueError(f"no such strategy: {strategy}")
    if strategy == "cartesian":
        return _cartesian(model, T, cut)
    order = list(T)
    if reorder and len(T) > 2 and not model.mixture:
        sizes = {r["coord"]: r["n"] for r in model.table.where(F.col("coord").isin(*T)).groupBy("coord").agg(F.count("*").alias("n")).collect()}
        order = sorted(T, key=lambda c: (sizes.get(c, 0), T.index(c)))
    have = _start(model, order[0]).where(_mass(model, F.col("__q")) >= cut)
    for j, c in enumerate(order[1:], 2):
        have = _grow(model, have, c, j, cut, strategy)
    return _named(model, have, order, T)


def _named(model: Model, have: DataFrame, order: list[str], T: tuple[str, ...]) -> DataFrame:
    named = {c: decoded(F.col(f"__v{i}"), model.types.get(c, "string")).alias(c) for i, c in enumerate(order, 1)}
    return have.select(*(named[c] for c in T), _mass(model, F.col("__q")).alias("mass"))


def _cartesian(model: Model, T: tuple[str, ...], cut: float) -> DataFrame:
    """Every combination of survivors: the baseline, for checks on small models."""
    have = _start(model, T[0])
    for j, c in enumerate(T[1:], 2):
        names = [f"__v{i}" for i in range(1, j)]
        have = have.crossJoin(_next(model, c, j)).select(*names, f"__v{j}", _extended(model).alias("__q"))
    return _named(model, have, list(T), T).where(F.col("mass") >= cut)


def all_heavy_many(model: Model, subcubes: DataFrame, k_max: int, cut: float | None = None) -> DataFrame:
    """subcubes: (subcube_id, pos from 1, coord[, prior array, in place of the model's]). All subsets at once in k_max joins:
    (subcube_id, vals array, mass)."""
    cut = model.lam if cut is None else cut
    cols = F.col("cond") if model.mixture else F.col("share")
    few = F.broadcast if subcubes.count() <= MOST else lambda df: df
    ks = subcubes.groupBy(F.col("subcube_id").alias("s0")).agg(F.max("pos").alias("k"))
    size = subcubes.join(ks, F.col("subcube_id") == F.col("s0")).drop("s0")
    prior = F.col("prior") if "prior" in subcubes.columns else prior_array(model) if model.mixture else None
    start = F.zip_with(prior, F.col("cond"), lambda a, b: a * b) if model.mixture else F.col("share")
    have = size.where("pos = 1").withColumnRenamed("coord", "c0").join(F.broadcast(model.table), F.col("c0") == F.col("coord")).select("subcube_id", "k", F.array("value").alias("vals"), start.alias("__q")).where(_mass(model, F.col("__q")) >= cut)
    done = have.where("k = 1")
    for j in range(2, k_max + 1):
        at = size.where(F.col("pos") == j).select(F.col("subcube_id").alias("s1"), F.col("coord").alias("c1"))
        step = have.where(F.col("k") >= j).join(few(at), F.col("subcube_id") == F.col("s1"))
        more = model.table.select(F.col("coord").alias("c2"), F.col("value").alias("v2"), cols.alias("__s"))
        met = step.join(F.broadcast(more), (F.col("c1") == F.col("c2")) & (_mass(model, _extended(model)) >= cut))
        have = met.select("subcube_id", "k", F.concat("vals", F.array("v2")).alias("vals"), _extended(model).alias("__q"))
        done = done.unionByName(have.where(F.col("k") == j))
    return done.select("subcube_id", "vals", _mass(model, F.col("__q")).alias("mass"))


def pairs_examined(model: Model, T: Iterable[str], cut: float | None = None) -> dict[str, int]:
    """For each strategy, how many pairs of a prefix and a next value it looks at to list T in its order."""
    T, cut = subset(model.coords, T), model.lam if cut is None else cut
    sizes = {r["coord"]: r["n"] for r in model.table.where(F.col("coord").isin(*T)).groupBy("coord").agg(F.count("*").alias("n")).collect()}
    total = dict.fromkeys(STRATEGIES, 0)
    have, combined = _start(model, T[0]).where(_mass(model, F.col("__q")) >= cut), sizes.get(T[0], 0)
    for j, c in enumerate(T[1:], 2):
        more = _next(model, c, j)
        top = F.array_max("__s") if model.mixture else F.col("__s")
        met = have.select(_mass(model, F.col("__q")).alias("__m")).join(F.broadcast(more.select(top.alias("__t"))), F.lit(True))
        bucket = F.floor(-F.log2("__t"))
        reach = F.floor(F.log2(F.col("__m") / cut) + 1e-9)
        n, near, close = met.agg(F.count("*"), F.count_if((F.col("__t") > 0) & (bucket <= reach)), F.count_if(F.col("__t") * F.col("__m") >= cut)).first()
        combined *= sizes.get(c, 0)
        for s, more_pairs in (("nested", n), ("bucketed", near), ("sorted", close), ("cartesian", combined)):
            total[s] += more_pairs
        have = _grow(model, have, c, j, cut, "bucketed")
    return total


def check_downward(model: Model, T: Iterable[str], cut: float | None = None) -> DataFrame:
    """Heavy joint values of T whose part on one coordinate fewer is not heavy: always none. (dropped, misses)."""
    from functools import reduce

    T = subset(model.coords, T)
    whole, out = all_heavy(model, T, cut), []
    for c in T if len(T) > 1 else ():
        rest = [x for x in T if x != c]
        less = all_heavy(model, rest, (model.lam if cut is None else cut) * (1 - 1e-12)).select(*(F.col(x).alias(f"__{x}") for x in rest))
        missing = whole.join(less, [F.col(x).eqNullSafe(F.col(f"__{x}")) for x in rest], "left_anti")
        out.append(missing.agg(F.count("*").alias("misses")).select(F.lit(c).alias("dropped"), "misses"))
    return reduce(DataFrame.unionByName, out) if out else model.table.sparkSession.createDataFrame([], "dropped string, misses bigint")


def bounds_report(model: Model, T: Iterable[str], cut: float | None = None) -> DataFrame:
    """(step, prefixes, bound): how many prefixes each growth step keeps, and 1 / cut."""
    from functools import reduce

    T, line = subset(model.coords, T), model.lam if cut is None else cut
    steps = [all_heavy(model, T[:j], line, reorder=False).agg(F.count("*").alias("prefixes")).select(F.lit(j).alias("step"), "prefixes", F.lit(1 / line).alias("bound")) for j in range(1, len(T) + 1)]
    return reduce(DataFrame.unionByName, steps)
