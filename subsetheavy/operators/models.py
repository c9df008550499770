"""Two-pass models: the product of shares, and the class mixture with an observed class."""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as t

from ..sources.tables import settled
from ..spec import NULL_MARK, StreamSpec, encode, long_form, share_of, subset, text
from .summaries import candidates_of, counters_by, first_pass, first_scan

#: Candidates that a second pass broadcasts at most; beyond that the rows are joined by a shuffle.
FEW = 2_000_000
#: Classes that a mixture has at most: its prior is an array in each expression.
CLASSES = 10_000
#: Between a model's name and a coordinate, where one table holds several models.
OF = "\x1f"


@dataclass
class Model:
    """Exact shares of each coordinate's survivors; in the mixture also their shares within each class.

    table: (coord, value, cnt, share[, cond array by class]). Its size is bounded by coordinates / lam, not by rows,
    which is what makes it fit for broadcasts. complete_above: no value of a larger share is missing."""

    table: DataFrame
    m: int
    lam: float
    coords: tuple[str, ...]
    prior: list[tuple[str, float]] | None = None
    cls: str | None = None
    complete_above: float = 0.0
    types: dict[str, str] = field(default_factory=dict)

    @property
    def mixture(self) -> bool:
        return self.prior is not None

    @property
    def complete(self) -> bool:
        return self.complete_above <= self.lam

    def of(self, coord: str) -> DataFrame:
        return self.table.where(F.col("coord") == coord)


def second_pass(df: DataFrame, candidates: DataFrame, coords: Iterable[str], m: int, lam: float, keep: Iterable[str] = ()) -> DataFrame:
    """Exact counts of the candidates, those of share >= lam. keep: columns to count apart (the class). Candidates are at
    most coordinates * 4 / lam rows and are broadcast (given ones, if that few); rows meet them inside the scan's stage."""
    few = candidates.select(F.col("coord").alias("c0"), F.col("value").alias("v0")).distinct().persist()
    hits = long_form(df, coords, keep).join(F.broadcast(few) if few.count() <= FEW else few, (F.col("coord") == F.col("c0")) & (F.col("value") == F.col("v0"))).drop("c0", "v0")
    counted = hits.groupBy("coord", "value", *keep).agg(F.count("*").alias("cnt"))
    return counted if keep else counted.where(F.col("cnt") >= lam * m).withColumn("share", F.col("cnt") / float(max(m, 1)))


def fit_product(df: DataFrame, coords: Iterable[str], gamma: float, cut: float | None = None, summary: str = "counters", capacity: int | None = None, candidates: DataFrame | None = None) -> Model:
    """Coordinates taken as near independent. cut: the line the shares are kept to, gamma / 2 if not given."""
    spec = StreamSpec.of(df, coords)
    lam = share_of(gamma) / 2 if cut is None else cut
    above = lam / 2
    if candidates is None and summary == "counters":
        # rows are counted by the scan that feeds the counters
        c = math.ceil(4 / lam) if capacity is None else capacity
        counters, m, _ = first_scan(df, spec.coords, c)
        candidates, above = candidates_of(counters, lam, max(m, 1), c)
    else:
        m = df.count()
        if candidates is None:
            candidates, above = first_pass(df, spec.coords, lam, max(m, 1), summary, capacity)
    # small whatever the stream, and read by every step of a listing
    return Model(second_pass(df, candidates, spec.coords, m, lam).persist(), m, lam, spec.coords, complete_above=above, types=spec.types)


def class_prior(df: DataFrame, cls: str) -> list[tuple[str, float]]:
    """(class, share), by class. Classes are few by assumption: their number is bounded, not that of rows."""
    got = df.groupBy(text(cls).alias("z")).count().collect()
    m = sum(r["count"] for r in got)
    return sorted((r["z"], r["count"] / m) for r in got)


def fit_mixture(df: DataFrame, coords: Iterable[str], cls: str, gamma: float, cut: float | None = None, summary: str = "counters", capacity: int | None = None, candidates: DataFrame | None = None) -> Model:
    """Coordinates taken as near independent within each class. The share of a value is the sum over classes of the
    counts that give its conditional shares, so the second pass is one aggregate."""
    if not cls:
        raise ValueError("a class column must be named; it is not learned")
    spec = StreamSpec.of(df, coords, cls)
    lam = share_of(gamma) / 2 if cut is None else cut
    above = lam / 2
    if candidates is None and summary == "counters":
        # classes and rows are counted by the scan that feeds the counters
        c = math.ceil(4 / lam) if capacity is None else capacity
        counters, m, classes = first_scan(df, spec.coords, c, cls)
        prior = sorted((z, n / m) for z, n in classes.items())
        candidates, above = candidates_of(counters, lam, max(m, 1), c)
    else:
        prior = class_prior(df, cls)
        m = df.count()
        if candidates is None:
            candidates, above = first_pass(df, spec.coords, lam, max(m, 1), summary, capacity)
    if len(prior) > CLASSES:
        raise ValueError(f"{len(prior)} classes: a class column has few values")
    z = df.withColumn("__z", text(cls))
    counted = second_pass(z, candidates, spec.coords, m, lam, ["__z"])
    whole = counted.groupBy("coord", "value").agg(F.sum("cnt").alias("cnt"), F.map_from_entries(F.collect_list(F.struct("__z", "cnt"))).alias("by")).where(F.col("cnt") >= lam * m)
    sizes = F.array(*(F.struct(F.lit(c).alias("z"), F.lit(float(round(s * m))).alias("n")) for c, s in prior)) if prior else F.array()
    cond = F.transform(sizes, lambda p: F.coalesce(F.try_element_at(F.col("by"), p["z"]), F.lit(0)) / p["n"])
    table = whole.select("coord", "value", "cnt", (F.col("cnt") / float(max(m, 1))).alias("share"), cond.alias("cond"))
    return Model(table.persist(), m, lam, spec.coords, prior, cls, above, spec.types)


def fit_mixtures(df: DataFrame, coords: Iterable[str], cls: str, by: str, classes: dict[str, dict[str, int]], wanted: dict[str, tuple[str, float, int]]) -> tuple[Model, dict[str, list[float]]]:
    """fit_mixture for several groups of rows, lines and capacities, from the two scans that one takes. classes: each group's
    rows by class; wanted: by a model's name its group, line and counters. Gives one model whose coordinates are named
    name OF coord, and the groups' priors in the order of its cond."""
    spec, spark = StreamSpec.of(df, coords, cls), df.sparkSession
    if max(map(len, classes.values()), default=0) > CLASSES:
        raise ValueError("a class column has few values")
    m = {g: sum(of.values()) for g, of in classes.items()}
    capacities: dict[str, set[int]] = {}
    for g, _, n in wanted.values():
        capacities.setdefault(g, set()).add(n)
    # the least counter of a candidate, as in candidates_of
    lines = [(x, g, n, lam / 4 * m[g] if n >= 4 / lam else 0.0, lam * m[g]) for x, (g, lam, n) in wanted.items()]
    named = F.broadcast(spark.createDataFrame(lines, "model string, grp string, capacity bigint, least double, line double"))
    candidates = settled(counters_by(df, spec.coords, by, capacities).join(named, ["grp", "capacity"]).where(F.col("counter") >= F.col("least")).select("model", "grp", "coord", "value", "line"))
    few = candidates.select(F.col("grp").alias("g0"), F.col("coord").alias("c0"), F.col("value").alias("v0")).distinct().persist()
    rows = long_form(df.select(F.col(by).alias("__g"), text(cls).alias("__z"), *spec.coords), spec.coords, ["__g", "__z"])
    hits = rows.join(F.broadcast(few) if few.count() <= FEW else few, (F.col("__g") == F.col("g0")) & (F.col("coord") == F.col("c0")) & (F.col("value") == F.col("v0"))).drop("g0", "c0", "v0")
    counted = hits.groupBy("__g", "coord", "value", "__z").agg(F.count("*").alias("cnt"))
    whole = counted.groupBy("__g", "coord", "value").agg(F.sum("cnt").alias("cnt"), F.map_from_entries(F.collect_list(F.struct("__z", "cnt"))).alias("by"))
    sizes = F.broadcast(spark.createDataFrame([(g, float(m[g]), sorted((z, float(n)) for z, n in of.items())) for g, of in classes.items()], "__g string, m double, sizes array<struct<z string, n double>>"))
    cond = F.transform("sizes", lambda p: F.coalesce(F.try_element_at(F.col("by"), p["z"]), F.lit(0)) / p["n"])
    shares = whole.join(sizes, "__g").select(F.col("__g").alias("grp"), "coord", "value", "cnt", (F.col("cnt") / F.col("m")).alias("share"), cond.alias("cond"))
    table = candidates.join(shares, ["grp", "coord", "value"]).where(F.col("cnt") >= F.col("line")).select(F.concat("model", F.lit(OF), "coord").alias("coord"), "value", "cnt", "share", "cond")
    priors = {g: [n / m[g] for _, n in sorted(of.items())] for g, of in classes.items()}
    return Model(settled(table), sum(m.values()), min(lam for _, lam, _ in wanted.values()), tuple(f"{x}{OF}{c}" for x in wanted for c in spec.coords), [], cls, types={f"{x}{OF}{c}": t for x in wanted for c, t in spec.types.items()}), priors


def prior_array(model: Model):
    return F.array(*(F.lit(s) for _, s in model.prior))


def mass_of(model: Model, parts):
    """The model's share of a joint value from the array of its coordinates' (share[, cond]) in order."""
    if not model.mixture:
        return F.aggregate(parts, F.lit(1.0), lambda acc, p: acc * p["share"])
    by_class = F.aggregate(parts, prior_array(model), lambda acc, p: F.zip_with(acc, p["cond"], lambda a, b: a * b))
    return F.aggregate(by_class, F.lit(0.0), lambda acc, x: acc + x)


def verdicts(model: Model, probes: DataFrame, cut: float | None = None) -> DataFrame:
    """probes: (probe_id, coords array, vals array). Gives (probe_id, mass, yes); mass is null where a value is no
    survivor or the lengths differ."""
    cut = model.lam if cut is None else cut
    cols = ["share", "cond"] if model.mixture else ["share"]
    each = probes.where(F.size("coords") == F.size("vals")).select("probe_id", F.size("coords").alias("k"), F.posexplode(F.arrays_zip("coords", "vals")).alias("pos", "cv")).select("probe_id", "k", "pos", F.col("cv.coords").alias("c0"), F.coalesce("cv.vals", F.lit(NULL_MARK)).alias("v0"))
    met = each.join(F.broadcast(model.table), (F.col("c0") == F.col("coord")) & (F.col("v0") == F.col("value")))
    whole = met.groupBy("probe_id", "k").agg(F.array_sort(F.collect_list(F.struct("pos", *cols))).alias("parts")).where(F.size("parts") == F.col("k")).select(F.col("probe_id").alias("p0"), mass_of(model, F.col("parts")).alias("mass"))
    return probes.select("probe_id").join(whole, F.col("probe_id") == F.col("p0"), "left").select("probe_id", "mass", F.coalesce(F.col("mass") >= cut, F.lit(False)).alias("yes"))


def verdict(model: Model, T: Iterable[str], v: Iterable[object], cut: float | None = None) -> bool:
    """Whether every value survives and the model's share of v reaches the cut."""
    T, v = subset(model.coords, T), tuple(v)
    if len(T) != len(v):
        raise ValueError("as many values as coordinates")
    spark = model.table.sparkSession
    probe = spark.createDataFrame([(0, list(T), [encode(x) for x in v])], "probe_id int, coords array<string>, vals array<string>")
    return bool(verdicts(model, probe, cut).first()["yes"])


def pin_class(model: Model, z: object) -> Model:
    """The mixture where the class itself is asked for: only that class counts."""
    prior = [(c, s if c == encode(z) else 0.0) for c, s in model.prior]
    return Model(model.table, model.m, model.lam, model.coords, prior, model.cls, model.complete_above, model.types)


def save_model(model: Model, path: str) -> None:
    """Shares partitioned by coordinate, and beside them what else the model holds."""
    model.table.write.mode("overwrite").partitionBy("coord").parquet(f"{path}/shares")
    spark = model.table.sparkSession
    head = [(model.m, model.lam, list(model.coords), model.cls, model.complete_above, [f"{c}\x1f{s!r}" for c, s in model.prior] if model.mixture else None, dict(model.types))]
    spark.createDataFrame(head, "m bigint, lam double, coords array<string>, cls string, complete_above double, prior array<string>, types map<string,string>").coalesce(1).write.mode("overwrite").parquet(f"{path}/head")


def load_model(spark: SparkSession, path: str) -> Model:
    h = spark.read.parquet(f"{path}/head").first()
    prior = [(c, float(s)) for c, s in (x.split("\x1f") for x in h["prior"])] if h["prior"] is not None else None
    fields = [t.StructField("value", t.StringType()), t.StructField("cnt", t.LongType()), t.StructField("share", t.DoubleType())] + ([t.StructField("cond", t.ArrayType(t.DoubleType()))] if prior is not None else []) + [t.StructField("coord", t.StringType())]
    return Model(spark.read.schema(t.StructType(fields)).parquet(f"{path}/shares"), h["m"], h["lam"], tuple(h["coords"]), prior, h["cls"], h["complete_above"], h["types"])


def merge_counts(a: Model, b: Model) -> Model:
    """Models of two parts of a stream, counted for the same candidates, as one. In mixtures a class that only one part
    has counts as none in the other."""
    if a.mixture != b.mixture or a.coords != b.coords or a.cls != b.cls:
        raise ValueError("models of one kind, of the same coordinates and class")
    m = a.m + b.m
    if a.mixture:
        rows = {z: round(dict(a.prior).get(z, 0.0) * a.m) + round(dict(b.prior).get(z, 0.0) * b.m) for z in dict(a.prior) | dict(b.prior)}
        prior = sorted((z, n / max(m, 1)) for z, n in rows.items())

        def counts(part: Model) -> DataFrame:
            """(coord, value, cnt, by): the counts within the classes of the whole."""
            at = {z: (i, round(s * part.m)) for i, (z, s) in enumerate(part.prior)}
            by = [F.round(F.col("cond")[at[z][0]] * at[z][1]).cast("bigint") if z in at else F.lit(0).cast("bigint") for z, _ in prior]
            return part.table.select("coord", "value", "cnt", F.array(*by).alias("by"))

        add = [F.sum(F.col("by")[i]).alias(f"__{i}") for i in range(len(prior))]
        both = counts(a).unionByName(counts(b)).groupBy("coord", "value").agg(F.sum("cnt").alias("cnt"), *add)
        cond = F.array(*(F.col(f"__{i}") / float(max(rows[z], 1)) for i, (z, _) in enumerate(prior)))
        table = both.select("coord", "value", "cnt", (F.col("cnt") / float(max(m, 1))).alias("share"), cond.alias("cond"))
        return Model(table.where(F.col("share") >= a.lam), m, a.lam, a.coords, prior, a.cls, max(a.complete_above, b.complete_above), a.types)
    both = a.table.select("coord", "value", "cnt").unionByName(b.table.select("coord", "value", "cnt")).groupBy("coord", "value").agg(F.sum("cnt").alias("cnt"))
    return Model(both.withColumn("share", F.col("cnt") / float(max(m, 1))).where(F.col("share") >= a.lam), m, a.lam, a.coords, None, None, max(a.complete_above, b.complete_above), a.types)
