"""The experiments: memory budgets and cut sweeps over the derived streams, with the measures they report."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.measures import auc, averaged, budget_to_params, confusion_sweep, estimate_errors, rates
from ..operators.exact import exact_shares, fix_class, heavy_stats
from ..operators.expand import STRATEGIES, all_heavy, all_heavy_many, pairs_examined
from ..operators.models import OF, Model, fit_mixture, fit_mixtures, fit_product
from ..operators.sampling import draw_sample, draw_samples, priority
from ..operators.sketch import fit_sketch
from ..sources.tables import CLICK_SUBCUBES, ROW_KEY, SEARCH_COORDS, SIZES, SYNTH_SUBCUBES, clicks, settled, synth, websearch
from ..spec import text

GAMMA, SEED = 0.002, "s7"
BUDGETS = (0.1, 0.5, 1.0, 2.0, 5.0, 10.0)
CUTS = (0.25, 0.5, 0.75, 1.0, 1.25, 1.5, 2.0)


def kept(df: DataFrame) -> DataFrame:
    """A derived stream that several measures read is kept by the block store (memory, then disk)."""
    return df.persist()


def warm_up(spark: SparkSession, sf_dir: str, budgets: Iterable[float] = BUDGETS) -> DataFrame:
    """(pct, method, subcube, mse, mae, mape) of the ten largest joint values: sample against sketch at equal memory."""
    df = kept(fix_class(synth(spark, sf_dir), "z"))
    m, coords, out = df.count(), tuple(SIZES), []
    truths = {T: kept(exact_shares(df, T, m).orderBy(F.desc("cnt"), *T).limit(10)) for T in SYNTH_SUBCUBES}
    asked = [t.select(F.explode(F.array(*(F.struct(F.lit(c).alias("coord"), F.col(c).cast("string").alias("value")) for c in T))).alias("e")).select("e.coord", "e.value") for T, t in truths.items()]
    probe = kept(reduce(DataFrame.unionByName, asked).distinct())
    for pct in budgets:
        # one sample and one sketch at each budget serve all subsets
        b = budget_to_params(pct, len(coords), m)
        s = kept(draw_sample(df, ["k"], b["size"], SEED, "md5"))
        model = fit_sketch(df, coords, 1e-9 + 1 / m, b["width"], b["depth"], SEED, "md5", candidates=probe)
        for T, truth in truths.items():
            got = s.groupBy(*T).agg((F.count("*") / float(b["size"])).alias("est"))
            est = truth.select(*T)
            for c in T:
                own = model.of(c).select(F.col("value").cast("bigint").alias("__v"), F.col("share").alias(f"__s_{c}"))
                est = est.join(F.broadcast(own), F.col(c) == F.col("__v")).drop("__v")
            est = est.select(*T, reduce(lambda a, b: a * b, (F.col(f"__s_{c}") for c in T)).alias("est"))
            for method, e in (("sample", got), ("sketch", est)):
                out.append(estimate_errors(truth, e, T).select(F.lit(pct).alias("pct"), F.lit(method).alias("method"), F.lit(",".join(T)).alias("subcube"), "mse", "mae", "mape"))
    return reduce(DataFrame.unionByName, out)


def joint_values(df: DataFrame, Ts: Iterable[tuple[str, ...]], by: Iterable[str] = ()) -> DataFrame:
    """(by..., subcube, vals, cnt): how often each joint value of each subset comes, values as texts, from one scan."""
    each, by = {",".join(T): F.array(*(text(c) for c in T)) for T in Ts}, list(by)
    made = df.select(*by, *(v.alias(f"__{i}") for i, v in enumerate(each.values()))).unpivot(by, [f"__{i}" for i in range(len(each))], "__t", "vals")
    names = F.array(*(F.lit(n) for n in each))
    return made.groupBy(*by, "__t", "vals").agg(F.count("*").alias("cnt")).select(*by, names[F.substring("__t", 3, 9).cast("int")].alias("subcube"), "vals", "cnt")


#: The columns of a curve.
CURVE = "pct double, method string, cut double, subcube string, tp bigint, fp bigint, fp_strict bigint, fn bigint, reported bigint, negatives bigint"


class Swept(dict[str, list[tuple]]):
    """Rows of a curve by method, (cut, subcube, tp, ...), that one sweep of many curves has made."""


def curve(df: DataFrame, key: Iterable[str], coords: tuple[str, ...], Ts: dict[tuple[str, ...], float], methods: Iterable[str] | Swept, pct: float, cls: str | None = None, factors: Iterable[float] = CUTS) -> DataFrame:
    """(pct, method, cut, subcube, tp, fp, fp_strict, fn, reported, negatives): each method at one memory budget over a
    sweep of cuts, cut in units of each subset's gamma. The subsets share a method's scan, listing and join. methods: names,
    or the rows where a sweep of many curves has made them."""
    if isinstance(methods, Swept):
        return df.sparkSession.createDataFrame([(pct, method, *r) for method, rows in methods.items() for r in rows], CURVE)
    df = kept(df)
    m, spark = df.count(), df.sparkSession
    b = budget_to_params(pct, len(coords), m)
    factors = tuple(factors)
    low = min(Ts.values()) * min(factors)
    entry = F.explode(F.array(*(F.struct(F.lit(",".join(T)).alias("subcube_id"), F.lit(j).alias("pos"), F.lit(c).alias("coord")) for T in Ts for j, c in enumerate(T, 1))))
    asked = spark.range(1).select(entry.alias("e")).select("e.*")
    groups = spark.range(1).select(F.explode(F.array(*(F.lit(",".join(T)) for T in Ts))).alias("subcube"))
    gammas = {",".join(T): gamma for T, gamma in Ts.items()}
    gamma = reduce(lambda have, n: F.when(F.col("subcube") == n, gammas[n]).otherwise(have), gammas, F.lit(None).cast("double")) if len(set(gammas.values())) > 1 else F.lit(next(iter(gammas.values())))
    truth = kept(joint_values(df, Ts).withColumn("share", F.col("cnt") / float(max(m, 1))))
    out = []
    for method in methods:
        if method == "sample":
            drawn = kept(draw_sample(df, key, b["size"], SEED, "md5"))
            listed = joint_values(drawn, Ts).withColumn("score", F.col("cnt") / float(max(min(b["size"], m), 1)))
        else:
            if method == "sketch":
                model = fit_sketch(df, coords, low, b["width"], b["depth"], cls=None)
            else:
                fit: Callable[..., Model] = fit_product if method == "product" else lambda d, c, g, **k: fit_mixture(d, c, cls, g, **k)
                model = fit(df, coords, min(1.0, 2 * low), cut=low, capacity=b["capacity"])
            model.table = kept(model.table)
            listed = all_heavy_many(model, asked, max(map(len, Ts)), low).select(F.col("subcube_id").alias("subcube"), "vals", F.col("mass").alias("score"))
        # one list at the least cut holds those of all others
        got = confusion_sweep(listed.where(F.col("score") >= gamma * min(factors)), "score", truth, ("subcube", "vals"), gamma, {f: gamma * f for f in factors}, groups=groups)
        out.append(got.select(F.lit(pct).alias("pct"), F.lit(method).alias("method"), "cut", "subcube", *got.columns[2:]))
    return reduce(DataFrame.unionByName, out)


def independent_curve(spark: SparkSession, sf_dir: str, pct: float = 2.0, methods: Iterable[str] = ("sample", "product")) -> DataFrame:
    return curve(fix_class(synth(spark, sf_dir), "z"), ["k"], tuple(SIZES), {T: GAMMA for T in SYNTH_SUBCUBES}, methods, pct)


def mixture_curve(spark: SparkSession, sf_dir: str, pct: float = 2.0) -> DataFrame:
    return curve(synth(spark, sf_dir), ["k"], tuple(SIZES), {T: GAMMA for T in SYNTH_SUBCUBES}, ("sample", "mixture"), pct, "z")


CLICK_AXES = tuple(dict.fromkeys(c for T in CLICK_SUBCUBES for c in T))


def clicks_curve(spark: SparkSession, sf_dir: str, pct: float = 10.0, methods: Iterable[str] = ("sample", "product")) -> DataFrame:
    return curve(clicks(spark, sf_dir), ROW_KEY, CLICK_AXES, CLICK_SUBCUBES, methods, pct)


def over_budgets(made: Callable[..., DataFrame], spark: SparkSession, sf_dir: str, pcts: Iterable[float], **more) -> DataFrame:
    """(pct, method, cut, averages over the subsets) of a curve at several memory budgets, one budget at a time."""
    out = []
    for pct in pcts:
        got = made(spark, sf_dir, pct, **more)
        out.append(spark.createDataFrame(got.collect(), got.schema))
    return averaged(reduce(DataFrame.unionByName, out), ["pct", "method", "cut"], ("tp", "fp", "fp_strict", "fn", "reported", "negatives"))


def correlated_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The control whose coordinates hang together: the product must miss what the sample finds."""
    T = ("geo_region", "geo_nation", "lang")
    return curve(clicks(spark, sf_dir), ROW_KEY, T, {T: 0.01}, ("sample", "product"), 10.0, factors=(0.5, 1.0))


def search_sweep(df: DataFrame, classes: dict[str, dict[str, int]], runs: Iterable[tuple[str, ...]], gammas: Iterable[float], pcts: Iterable[float]) -> DataFrame:
    """(subset, gamma, pct, method, cut, subcube, tp, fp, fp_strict, fn, reported, negatives): the curves of all subsets of the
    stream, gammas and budgets together, so that the scans, lists and joins are the same however many they are. df has the
    rows' md5 priority; classes: each subset's rows by class."""
    runs, gammas, pcts, spark = tuple(runs), tuple(gammas), tuple(pcts), df.sparkSession
    sizes = {n: sum(of.values()) for n, of in classes.items()}
    buys = {(n, pct): budget_to_params(pct, len(SEARCH_COORDS), m) for n, m in sizes.items() for pct in pcts}
    few = lambda rows, kind: F.broadcast(spark.createDataFrame(rows, kind))
    every = few([(n, gamma, pct, float(sizes[n])) for n, gamma, pct in product(sizes, gammas, pcts)], "subset string, gamma double, pct double, m double")
    truth = settled(joint_values(df, runs, ["subset"])).join(every, "subset").select("subset", "gamma", "pct", F.explode(F.array(F.lit("sample"), F.lit("mixture"))).alias("method"), "subcube", "vals", (F.col("cnt") / F.col("m")).alias("share"))

    drawn = draw_samples(df, ROW_KEY, "subset", {n: {str(pct): buys[n, pct]["size"] for pct in pcts} for n in sizes})
    held = few([(n, str(pct), gamma, pct, float(min(buys[n, pct]["size"], sizes[n]))) for n, gamma, pct in product(sizes, gammas, pcts)], "subset string, sample string, gamma double, pct double, size double")
    sampled = settled(joint_values(drawn, runs, ["subset", "sample"])).join(held, ["subset", "sample"]).select("subset", "gamma", "pct", F.lit("sample").alias("method"), "subcube", "vals", (F.col("cnt") / F.col("size")).alias("score"))

    points = {str(i): a for i, a in enumerate(product(sizes, gammas, pcts))}
    low = {x: gamma * min(CUTS) for x, (_, gamma, _) in points.items()}
    model, priors = fit_mixtures(df, SEARCH_COORDS, "day", "subset", classes, {x: (n, low[x], buys[n, pct]["capacity"]) for x, (n, _, pct) in points.items()})
    asked = spark.createDataFrame([((x, ",".join(T)), j, f"{x}{OF}{c}", priors[n]) for x, (n, _, _) in points.items() for T in runs for j, c in enumerate(T, 1)], "subcube_id struct<model string, subcube string>, pos int, coord string, prior array<double>")
    names = few([(x, *a) for x, a in points.items()], "model string, subset string, gamma double, pct double")
    # grown to the least line of all models; each one's own follows
    listed = all_heavy_many(model, asked, max(map(len, runs)), min(low.values())).select("subcube_id.model", "subcube_id.subcube", "vals", F.col("mass").alias("score"))
    mixed = listed.join(names, "model").select("subset", "gamma", "pct", F.lit("mixture").alias("method"), "subcube", "vals", "score")

    gamma, by = F.col("gamma"), ("subset", "gamma", "pct", "method", "subcube")
    groups = spark.createDataFrame(list(product(sizes, gammas, pcts, ("sample", "mixture"), (",".join(T) for T in runs))), "subset string, gamma double, pct double, method string, subcube string")
    lists = sampled.unionByName(mixed).where(F.col("score") >= gamma * min(CUTS))
    return confusion_sweep(lists, "score", truth, (*by, "vals"), gamma, {f: gamma * f for f in CUTS}, groups=groups)


def search_curve(spark: SparkSession, sf_dir: str, gammas: Iterable[float] = (0.05, 0.1), pcts: Iterable[float] = (0.2, 2.0, 10.0), subsets: int = 10) -> DataFrame:
    """(gamma, pct, method, cut, ...): averages over the most frequent brands and the eight runs of three neighbouring
    slots, for each gamma and memory budget."""
    gammas, pcts, runs = tuple(gammas), tuple(pcts), [SEARCH_COORDS[i : i + 3] for i in range(8)]
    df = kept(websearch(spark, sf_dir).withColumn("priority", priority(ROW_KEY, SEED, "md5")))
    classes: dict[str, dict[str, int]] = {}
    for r in df.groupBy("subset", text("day").alias("z")).agg(F.count("*").alias("n")).collect():
        classes.setdefault(r["subset"], {})[r["z"]] = r["n"]
    names = sorted(classes, key=lambda n: (-sum(classes[n].values()), n))[:subsets]
    swept = {a: Swept(sample=[], mixture=[]) for a in product(names, gammas, pcts)}
    if names:
        # a row for each curve, method, cut and run of slots
        for r in search_sweep(df.where(F.col("subset").isin(names)), {n: classes[n] for n in names}, runs, gammas, pcts).collect():
            swept[r["subset"], r["gamma"], r["pct"]][r["method"]].append((r["cut"], r["subcube"], *r[6:]))
    rows: list[tuple] = []
    for (n, gamma, pct), made in swept.items():
        got = curve(df.where(F.col("subset") == n), ROW_KEY, SEARCH_COORDS, dict.fromkeys(runs, gamma), made, pct, "day")
        rows += [(gamma, *r) for r in got.collect()]
    df.unpersist()
    return averaged(spark.createDataFrame(rows, f"gamma double, {CURVE}"), ["gamma", "pct", "method", "cut"])


def roc(points: DataFrame) -> DataFrame:
    """(pct, method, auc) from a curve, subsets averaged."""
    # the area reads its points twice, and they are a row for each method and cut
    summed = kept(points.groupBy("pct", "method", "cut").agg(*(F.sum(c).alias(c) for c in ("tp", "fp", "fn", "negatives"))))
    return auc(rates(summed), ["pct", "method"])


def parameter_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(workload, subcubes, avg_heavy, avg_ratio)."""
    s = kept(synth(spark, sf_dir))
    parts = {"generated, fixed class": heavy_stats(fix_class(s, "z"), {T: GAMMA for T in SYNTH_SUBCUBES}), "generated, whole": heavy_stats(s, {T: GAMMA for T in SYNTH_SUBCUBES}), "clicks": heavy_stats(clicks(spark, sf_dir), CLICK_SUBCUBES)}
    w = kept(websearch(spark, sf_dir))
    Ts = [SEARCH_COORDS[i : i + 3] for i in range(8)]
    web = []
    sizes = w.groupBy("subset").agg(F.count("*").alias("m"))
    for T in Ts:
        n = w.groupBy("subset", *T).agg(F.count("*").alias("n")).join(F.broadcast(sizes), "subset")
        web.append(n.groupBy("subset").agg(F.count_if(F.col("n") >= 0.05 * F.col("m")).alias("heavy"), F.count("*").alias("distinct_values")).select(F.lit(",".join(T)).alias("subcube"), "distinct_values", "heavy", (F.col("heavy") / F.col("distinct_values")).alias("ratio")))
    parts["web search"] = reduce(DataFrame.unionByName, web)
    return reduce(DataFrame.unionByName, (p.agg(F.countDistinct("subcube").alias("subcubes"), F.avg("heavy").alias("avg_heavy"), F.avg("ratio").alias("avg_ratio")).select(F.lit(n).alias("workload"), "*") for n, p in parts.items()))


def strategy_scaling(spark: SparkSession, sf_dir: str, k_max: int = 8) -> DataFrame:
    """(k, strategy, heavy, pairs): every strategy lists the same number at each k, and looks at so many pairs of a
    prefix and a value for it."""
    model = fit_product(clicks(spark, sf_dir), SCALING, 0.002)
    model.table = kept(model.table)
    out = []
    for k in range(1, k_max + 1):
        pairs = pairs_examined(model, SCALING[:k], 0.001)
        out += [all_heavy(model, SCALING[:k], 0.001, s, reorder=False).agg(F.count("*").alias("heavy")).select(F.lit(k).alias("k"), F.lit(s).alias("strategy"), "heavy", F.lit(pairs[s]).alias("pairs")) for s in STRATEGIES if s != "cartesian" or k <= 4]
    return reduce(DataFrame.unionByName, out)


SCALING = ("os", "lang", "engine", "geo_region", "browser", "referrer", "plugins", "visit_no")


def top_of(df: DataFrame, by: str, n: int, order: str) -> DataFrame:
    w = Window.partitionBy(by).orderBy(F.desc(order))
    return df.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= n).drop("__r")
