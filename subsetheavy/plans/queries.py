"""Registered queries of the methods, variants, baselines, measures and workloads, with their SQL where it can say them."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures as ms
from ..operators import baselines as bl
from ..operators import exact as ex
from ..operators import gap as gp
from ..operators import models as md
from ..operators import sampling as sp
from ..operators import sketch as sk
from ..operators import summaries as sm
from ..operators.expand import all_heavy, all_heavy_many, bounds_report, check_downward
from ..sources import tables as tb
from ..spec import long_form
from . import questions as qu
from . import workloads as wl

GAMMA = 0.002
LAM = GAMMA / 2
X = tuple(tb.SIZES)
T3 = ("x1", "x2", "x3")
Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def go(f: Query) -> Query:
        _queries[name] = f
        if sql:
            _sql[name] = sql
        return f

    return go


def synth(spark, d):
    return tb.synth(spark, d)


W = tb.with_sql
ONE = f"{W('synth')}, one AS (SELECT * FROM synth WHERE z = (SELECT z FROM synth GROUP BY z ORDER BY count(*) DESC, z LIMIT 1))"


def one(spark, d):
    return ex.fix_class(tb.synth(spark, d), "z")


def long_sql(src: str, coords, keep: str = "") -> str:
    return " UNION ALL ".join(f"SELECT {keep}'{c}' AS coord, CAST({c} AS VARCHAR) AS value FROM {src}" for c in coords)


def marginals_sql(src: str, coords) -> str:
    """CTEs mg(coord, value, cnt, share)."""
    return f"lf AS ({long_sql(src, coords)}), mg AS (SELECT coord, value, count(*) AS cnt, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM {src}) AS share FROM lf GROUP BY coord, value)"


def product_sql(src: str, T, cut: float, keep: float) -> str:
    joins = " ".join(f"JOIN (SELECT * FROM mg WHERE coord = '{c}' AND share >= {keep!r}) m{i} ON {'TRUE' if i == 0 else ' * '.join(f'm{j}.share' for j in range(i + 1)) + f' >= {cut * (1 - 1e-9)!r}'}" for i, c in enumerate(T))
    mass = " * ".join(f"m{i}.share" for i in range(len(T)))
    return f"SELECT {', '.join(f'm{i}.value AS {c}' for i, c in enumerate(T))}, round({mass}, 9) AS mass FROM (SELECT 1) o {joins} WHERE {mass} >= {cut!r}"


def shown(df: DataFrame, T) -> DataFrame:
    return df.select(*(F.col(c).cast("string").alias(c) for c in T), F.round("mass", 9).alias("mass"))


# ---- sampling
_PRI = "CAST(('0x' || substr(md5('{seed}|' || {key}), 1, 8))::BIGINT AS BIGINT)"


@query("q_sample_draw", f"{W('synth')} SELECT k, z, x1, {_PRI.format(seed='7', key='k')} AS priority FROM synth ORDER BY priority, k LIMIT 3360")
def _(spark, d):
    return sp.draw_sample(synth(spark, d).select("k", "z", "x1"), ["k"], 3360, 7, "md5")


@query("q_sample_merge", f"{W('synth')} SELECT k, {_PRI.format(seed='7', key='k')} AS priority FROM synth ORDER BY priority, k LIMIT 1000")
def _(spark, d):
    s = synth(spark, d).select("k")
    a, b = (sp.draw_sample(s.where(F.col("k") % 2 == i), ["k"], 1000, 7, "md5") for i in (0, 1))
    return sp.merge_samples(a, b, ["k"], 1000)


@query("q_sample_stratified", f"{W('synth')} SELECT z, k, priority FROM (SELECT z, k, {_PRI.format(seed='7', key='k')} AS priority, row_number() OVER (PARTITION BY z ORDER BY {_PRI.format(seed='7', key='k')}, k) AS r FROM synth) WHERE r <= 100")
def _(spark, d):
    return sp.draw_sample(synth(spark, d).select("z", "k"), ["k"], 100, 7, "md5", by=["z"])


_SMP = f"smp AS (SELECT * FROM synth ORDER BY {_PRI.format(seed='7', key='k')}, k LIMIT 3360)"


@query("q_sample_all_heavy", f"{W('synth')}, {_SMP} SELECT x1, x2, x3, count(*) AS cnt, count(*) / 3360.0::DOUBLE AS share FROM smp GROUP BY x1, x2, x3 HAVING count(*) / 3360.0::DOUBLE >= 0.001")
def _(spark, d):
    return sp.sample_all_heavy(sp.draw_sample(synth(spark, d), ["k"], 3360, 7, "md5"), T3, LAM)


@query("q_sample_verdicts", f"""{W('synth')}, {_SMP}, pr AS (SELECT x1, x2, x3 FROM synth GROUP BY x1, x2, x3 ORDER BY count(*) DESC, x1, x2, x3 LIMIT 50)
SELECT x1, x2, x3, coalesce(n, 0) / 3360.0::DOUBLE AS share, coalesce(n, 0) / 3360.0::DOUBLE >= 0.001 AS yes FROM pr LEFT JOIN (SELECT x1, x2, x3, count(*) AS n FROM smp GROUP BY x1, x2, x3) USING (x1, x2, x3)""")
def _(spark, d):
    s = synth(spark, d)
    probes = s.groupBy(*T3).count().orderBy(F.desc("count"), *T3).limit(50).select(*T3)
    return sp.sample_verdicts(sp.draw_sample(s, ["k"], 3360, 7, "md5"), probes, T3, LAM)


@query("q_sample_reservoir")
def _(spark, d):
    return sp.reservoir_sample(synth(spark, d), 1000, 3)


@query("q_sample_bernoulli")
def _(spark, d):
    return sp.bernoulli_sample(synth(spark, d), 0.02, 3)


_BOUND = ("l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_discount")


@query("q_sample_size_bound", f"SELECT 0.002::DOUBLE AS gamma, 3 AS k, 5 AS d, n, CAST(ceil(48 / 0.002::DOUBLE * (ln(2 / 0.1::DOUBLE) + 3 * ln(5 * n))) AS BIGINT) AS items FROM (SELECT greatest({', '.join(f'count(DISTINCT {c})' for c in _BOUND)}) AS n FROM lineitem)")
def _(spark, d):
    """n is the number of values of the coordinate that has most."""
    n = max(tb.table(spark, d, "lineitem").agg(*(F.countDistinct(c) for c in _BOUND)).first())
    return spark.createDataFrame([(GAMMA, 3, len(_BOUND), n, sp.sample_size_bound(GAMMA, 3, len(_BOUND), n))], "gamma double, k int, d int, n bigint, items bigint")


def _majority_sql(seeds, size):
    votes = " UNION ALL ".join(f"SELECT count(*) FILTER (WHERE q.x1 = v.x1 AND q.x2 = v.x2 AND q.x3 = v.x3) / {size}.0::DOUBLE >= 0.001 AS vote FROM (SELECT x1, x2, x3 FROM one ORDER BY {_PRI.format(seed=s, key='k')}, k LIMIT {size}) q, v" for s in seeds)
    return f"{ONE}, v AS (SELECT x1, x2, x3 FROM one GROUP BY x1, x2, x3 ORDER BY count(*) DESC, x1, x2, x3 LIMIT 1), vt AS ({votes}) SELECT x1, x2, x3, (SELECT 2 * count(*) FILTER (WHERE vote) > count(*) FROM vt) AS yes FROM v"


@query("q_sample_majority", _majority_sql(range(3), 2686))
def _(spark, d):
    s = one(spark, d)
    v = s.groupBy(*T3).count().orderBy(F.desc("count"), *T3).first()[:3]
    return spark.createDataFrame([(*v, sp.majority_verdict(s, ["k"], T3, v, LAM, 2686, range(3), "md5"))], "x1 bigint, x2 bigint, x3 bigint, yes boolean")


# ---- first and second pass
_MUST = f"{W('synth')}, {marginals_sql('synth', X)} SELECT coord, value, cnt FROM mg WHERE cnt >= 0.005 * (SELECT count(*) FROM synth)"


def _candidates(spark, d, summary):
    """The candidates that must be there (share >= lam / 2) and are, and those that must not (share < lam / 4) and are: the
    true values of share >= lam / 2 if nothing is missing and nothing light came in."""
    s = synth(spark, d)
    m = s.count()
    got, _ = sm.first_pass(s, X, 0.01, m, summary)
    mg = long_form(s, X).groupBy("coord", "value").agg(F.count("*").alias("cnt"))
    found = mg.join(F.broadcast(got.select(F.col("coord").alias("c0"), F.col("value").alias("v0"))), (F.col("coord") == F.col("c0")) & (F.col("value") == F.col("v0")), "left_semi")
    return found.where((F.col("cnt") >= 0.005 * m) | (F.col("cnt") < 0.0025 * m))


for _n, _s in (("q_candidates_contain", "counters"), ("q_cm_superset", "count_min"), ("q_exact_superset", "exact")):
    query(_n, _MUST)(lambda spark, d, s=_s: _candidates(spark, d, s))


@query("q_mg_superset", f"{W('synth')}, {marginals_sql('synth', X)} SELECT coord, value FROM mg WHERE share > 1 / 501.0::DOUBLE")
def _(spark, d):
    """Values over the counters' bound, found among the counters."""
    s = synth(spark, d)
    held = sm.misra_gries(s, X, 500).select(F.col("coord").alias("c0"), F.col("value").alias("v0"))
    mg = long_form(s, X).groupBy("coord", "value").agg(F.count("*").alias("n")).where(F.col("n") > s.count() / 501.0)
    return mg.join(held, (F.col("coord") == F.col("c0")) & (F.col("value") == F.col("v0")), "left_semi").select("coord", "value")


@query("q_freqitems_superset", f"{W('synth')}, {marginals_sql('synth', X)} SELECT coord, value FROM mg WHERE share >= 0.005")
def _(spark, d):
    s = synth(spark, d)
    held = sm.frequent_items(s, X, 0.0025).select(F.col("coord").alias("c0"), F.col("value").alias("v0"))
    mg = long_form(s, X).groupBy("coord", "value").agg(F.count("*").alias("n")).where(F.col("n") >= 0.005 * s.count())
    return mg.join(held, (F.col("coord") == F.col("c0")) & (F.col("value") == F.col("v0")), "left_semi").select("coord", "value")


_CELL = "CAST((('0x' || substr(md5('9|' || r || '|' || coord || '|' || value), 1, 8))::BIGINT) % 200 AS INT)"
_CELLS = f"cells AS (SELECT coord, CAST(r AS INT) AS depth_row, {_CELL} AS bucket, count(*) AS cnt FROM lf, range(5) t(r) GROUP BY ALL)"


@query("q_cm_cells", f"{W('synth')}, lf AS ({long_sql('synth', ('x3', 'x5'))}), {_CELLS} SELECT coord, depth_row, bucket, cnt FROM cells")
def _(spark, d):
    return sm.count_min(synth(spark, d), ["x3", "x5"], 200, 5, 9, "md5")


@query("q_cm_estimate", f"{W('synth')}, lf AS ({long_sql('synth', ('x3', 'x5'))}), {_CELLS}, pr AS (SELECT coord, value FROM lf GROUP BY coord, value HAVING count(*) >= 500) SELECT coord, value, min(cnt) AS estimate FROM (SELECT coord, value, CAST(r AS INT) AS depth_row, {_CELL} AS bucket FROM pr, range(5) t(r)) JOIN cells USING (coord, depth_row, bucket) GROUP BY coord, value")
def _(spark, d):
    s = synth(spark, d)
    probes = long_form(s, ["x3", "x5"]).groupBy("coord", "value").count().where("count >= 500").select("coord", "value")
    return sm.count_min_estimate(sm.count_min(s, ["x3", "x5"], 200, 5, 9, "md5"), probes, 200, 5, 9, "md5")


@query("q_cm_built_in", f"{W('synth')} SELECT CAST(x1 AS VARCHAR) AS value, count(*) AS cnt FROM synth GROUP BY x1 HAVING count(*) >= 0.005 * (SELECT count(*) FROM synth)")
def _(spark, d):
    """Frequent values whose estimate by the engine's own sketch lies between the count and the count with its error."""
    s = synth(spark, d)
    m = s.count()
    true = s.groupBy(F.col("x1").cast("string").alias("value")).agg(F.count("*").alias("cnt")).where(F.col("cnt") >= 0.005 * m)
    est = sm.built_in_estimates(s, "x1", [r["value"] for r in true.collect()], 0.001, 0.99)
    return true.join(F.broadcast(est.withColumnRenamed("value", "v0")), F.col("value") == F.col("v0")).where((F.col("estimate") >= F.col("cnt")) & (F.col("estimate") <= F.col("cnt") + 0.001 * m)).select("value", "cnt")


@query("q_marginals_exact", f"{W('synth')}, {marginals_sql('synth', X)} SELECT coord, value, cnt, share FROM mg")
def _(spark, d):
    return gp.exact_model(synth(spark, d), X).table.select("coord", "value", "cnt", "share")


@query("q_survivors", f"{W('synth')}, {marginals_sql('synth', X)} SELECT coord, value, cnt, round(share, 9) AS share FROM mg WHERE share >= 0.001")
def _(spark, d):
    return md.fit_product(synth(spark, d), X, GAMMA).table.select("coord", "value", "cnt", F.round("share", 9).alias("share"))


@query("q_survivors_few_counters", f"{W('synth')}, {marginals_sql('synth', X)} SELECT coord, value, cnt, round(share, 9) AS share FROM mg WHERE share >= 0.001")
def _(spark, d):
    """Fewer counters than the gap needs: every stored value goes to the second pass, and none is lost."""
    return md.fit_product(synth(spark, d), X, GAMMA, capacity=1200).table.select("coord", "value", "cnt", F.round("share", 9).alias("share"))


# ---- product model
def product(spark, d):
    return md.fit_product(one(spark, d), X, GAMMA)


for _k, _T in ((1, X[:1]), (2, X[:2]), (3, X[:3]), (5, X)):
    query(f"q_product_all_heavy_k{_k}", f"{ONE}, {marginals_sql('one', _T)} {product_sql('one', _T, LAM, LAM)}")(lambda spark, d, T=_T: shown(all_heavy(product(spark, d), T), T))
for _s in ("nested", "sorted", "cartesian"):
    query(f"q_product_{_s}_equals", f"{ONE}, {marginals_sql('one', ('x4', 'x5'))} {product_sql('one', ('x4', 'x5'), LAM, LAM)}")(lambda spark, d, s=_s: shown(all_heavy(product(spark, d), ("x4", "x5"), strategy=s), ("x4", "x5")))

_PROBES = "pr AS (SELECT row_number() OVER (ORDER BY count(*) DESC, x1, x2, x3) AS probe_id, CAST(x1 AS VARCHAR) AS v1, CAST(x2 AS VARCHAR) AS v2, CAST(x3 AS VARCHAR) AS v3 FROM {src} GROUP BY x1, x2, x3 ORDER BY count(*) DESC, x1, x2, x3 LIMIT 170)"


def probes(df):
    from pyspark.sql import Window

    top = df.groupBy(*T3).count().orderBy(F.desc("count"), *T3).limit(170)
    return top.select(F.row_number().over(Window.orderBy(F.desc("count"), *T3)).cast("bigint").alias("probe_id"), F.array(*map(F.lit, T3)).alias("coords"), F.array(*(F.col(c).cast("string") for c in T3)).alias("vals"))


@query("q_product_verdicts", f"""{ONE}, {marginals_sql('one', T3)}, {_PROBES.format(src='one')}, s AS (SELECT * FROM mg WHERE share >= 0.001)
SELECT probe_id, round(a.share * b.share * c.share, 9) AS mass, coalesce(a.share * b.share * c.share >= 0.001, FALSE) AS yes FROM pr
LEFT JOIN s a ON a.coord = 'x1' AND a.value = v1 LEFT JOIN s b ON b.coord = 'x2' AND b.value = v2 LEFT JOIN s c ON c.coord = 'x3' AND c.value = v3""")
def _(spark, d):
    s = one(spark, d)
    return md.verdicts(md.fit_product(s, X, GAMMA), probes(s)).select("probe_id", F.round("mass", 9).alias("mass"), "yes")


def subcubes(spark, Ts):
    return spark.createDataFrame([(i, p, c) for i, T in enumerate(Ts) for p, c in enumerate(T, 1)], "subcube_id bigint, pos int, coord string")


_PAIRS = tuple(combinations(X, 2))


def many(model, spark):
    got = all_heavy_many(model, subcubes(spark, _PAIRS), 2)
    return got.select("subcube_id", F.col("vals")[0].alias("v1"), F.col("vals")[1].alias("v2"), F.round("mass", 9).alias("mass"))


_MANY = " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS subcube_id, a.value AS v1, b.value AS v2, round({{mass}}, 9) AS mass FROM s a JOIN s b ON a.coord = '{T[0]}' AND b.coord = '{T[1]}' WHERE {{mass}} >= 0.001" for i, T in enumerate(_PAIRS))


@query("q_product_many", f"{ONE}, {marginals_sql('one', X)}, s AS (SELECT * FROM mg WHERE share >= 0.001) " + _MANY.format(mass="a.share * b.share"))
def _(spark, d):
    return many(product(spark, d), spark)


@query("q_downward_product", "SELECT c AS dropped, CAST(0 AS BIGINT) AS misses FROM (VALUES ('x1'), ('x2'), ('x3'), ('x4')) v(c)")
def _(spark, d):
    return check_downward(product(spark, d), X[:4])


@query("q_bounds", f"{ONE}, {marginals_sql('one', X[:4])} " + " UNION ALL ".join(f"SELECT {j} AS step, count(*) AS prefixes, {1 / LAM!r}::DOUBLE AS bound FROM ({product_sql('one', X[:j], LAM, LAM)})" for j in (1, 2, 3, 4)))
def _(spark, d):
    return bounds_report(product(spark, d), X[:4])


@query("q_model_round_trip", f"{ONE}, {marginals_sql('one', T3)} {product_sql('one', T3, LAM, LAM)}")
def _(spark, d):
    path = f"{_scratch(spark)}/model-{uuid.uuid4().hex}"
    md.save_model(product(spark, d), path)
    return shown(all_heavy(md.load_model(spark, path), T3), T3)


def _scratch(spark) -> str:
    return tb.shared(spark, "models-")


@query("q_model_merge", f"{ONE}, {marginals_sql('one', X)} SELECT coord, value, cnt, round(share, 9) AS share FROM mg WHERE share >= 0.001")
def _(spark, d):
    s = one(spark, d)
    cand, _ = sm.first_pass(s, X, LAM, s.count())
    a, b = (md.fit_product(s.where(F.col("k") % 2 == i), X, GAMMA, cut=1e-12, candidates=cand) for i in (0, 1))
    a.lam = LAM
    return md.merge_counts(a, b).table.select("coord", "value", "cnt", F.round("share", 9).alias("share"))


# ---- class mixture
_PRIOR = "pz AS (SELECT CAST(z AS VARCHAR) AS z, count(*) AS n, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM synth) AS p FROM synth GROUP BY z)"
_LFZ = f"lfz AS ({long_sql('synth', X, 'CAST(z AS VARCHAR) AS z, ')}), cz AS (SELECT coord, value, z, count(*) AS n FROM lfz GROUP BY coord, value, z)"
_MIX = f"{W('synth')}, {_PRIOR}, {_LFZ}, {marginals_sql('synth', X)}, s AS (SELECT * FROM mg WHERE share >= 0.001), cd AS (SELECT coord, value, cz.z, cz.n / CAST(pz.n AS DOUBLE) AS f FROM cz JOIN pz USING (z) JOIN s USING (coord, value))"


def mixture_sql(T, where: str = "") -> str:
    joins = " ".join(f"JOIN cd c{i} ON c{i}.coord = '{c}' AND c{i}.z = pz.z" for i, c in enumerate(T))
    mass = "sum(p * " + " * ".join(f"c{i}.f" for i in range(len(T))) + ")"
    return f"SELECT {', '.join(f'c{i}.value AS {c}' for i, c in enumerate(T))}, round({mass}, 9) AS mass FROM pz {joins} {where} GROUP BY {', '.join(f'c{i}.value' for i in range(len(T)))} HAVING {mass} >= 0.001"


def mixture(spark, d):
    return md.fit_mixture(synth(spark, d), X, "z", GAMMA)


@query("q_prior", f"{W('synth')} SELECT CAST(z AS VARCHAR) AS z, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM synth) AS share FROM synth GROUP BY z")
def _(spark, d):
    return spark.createDataFrame(md.class_prior(synth(spark, d), "z"), "z string, share double")


@query("q_conditionals", f"{_MIX} SELECT coord, value, z, round(f, 9) AS f FROM cd")
def _(spark, d):
    m = mixture(spark, d)
    at = F.explode(F.arrays_zip(F.array(*(F.lit(z) for z, _ in m.prior)).alias("z"), F.col("cond").alias("f"))).alias("e")
    return m.table.select("coord", "value", at).select("coord", "value", "e.z", F.round("e.f", 9).alias("f")).where("f > 0")


@query("q_sufficient_statistic", f"{_MIX} SELECT coord, value, TRUE AS same FROM s")
def _(spark, d):
    """The prior-weighted conditionals of a value sum to its share."""
    m = mixture(spark, d)
    return m.table.select("coord", "value", (F.abs(md.mass_of(m, F.array(F.struct("share", "cond"))) - F.col("share")) < 1e-12).alias("same"))


for _k, _T in ((1, X[:1]), (2, X[:2]), (3, X[:3])):
    query(f"q_mixture_all_heavy_k{_k}", f"{_MIX} {mixture_sql(_T)}")(lambda spark, d, T=_T: shown(all_heavy(mixture(spark, d), T), T))
query("q_mixture_nested_equals", f"{_MIX} {mixture_sql(X[:2])}")(lambda spark, d: shown(all_heavy(mixture(spark, d), X[:2], strategy="nested"), X[:2]))


@query("q_mixture_verdicts", f"""{_MIX}, {_PROBES.format(src='synth')}, ms AS (SELECT probe_id, sum(p * a.f * b.f * c.f) AS mass FROM pr CROSS JOIN pz JOIN cd a ON a.coord = 'x1' AND a.value = v1 AND a.z = pz.z
JOIN cd b ON b.coord = 'x2' AND b.value = v2 AND b.z = pz.z JOIN cd c ON c.coord = 'x3' AND c.value = v3 AND c.z = pz.z GROUP BY probe_id),
al AS (SELECT probe_id FROM pr JOIN s a ON a.coord = 'x1' AND a.value = v1 JOIN s b ON b.coord = 'x2' AND b.value = v2 JOIN s c ON c.coord = 'x3' AND c.value = v3)
SELECT pr.probe_id, CASE WHEN al.probe_id IS NOT NULL THEN round(coalesce(mass, 0), 9) END AS mass, coalesce(mass >= 0.001, FALSE) AS yes FROM pr LEFT JOIN al ON al.probe_id = pr.probe_id LEFT JOIN ms ON ms.probe_id = pr.probe_id""")
def _(spark, d):
    s = synth(spark, d)
    return md.verdicts(mixture(spark, d), probes(s)).select("probe_id", F.round("mass", 9).alias("mass"), "yes")


@query("q_mixture_many", f"{_MIX}, ct AS (SELECT a.coord AS ca, b.coord AS cb, a.value AS v1, b.value AS v2, sum(p * a.f * b.f) AS mass FROM pz JOIN cd a ON a.z = pz.z JOIN cd b ON b.z = pz.z AND a.coord < b.coord GROUP BY ALL) SELECT CAST(CASE ca || cb {' '.join(f'''WHEN '{a}{b}' THEN {i}''' for i, (a, b) in enumerate(_PAIRS))} END AS BIGINT) AS subcube_id, v1, v2, round(mass, 9) AS mass FROM ct WHERE mass >= 0.001")
def _(spark, d):
    return many(mixture(spark, d), spark)


@query("q_mixture_class_in_T", f"{_MIX} {mixture_sql(X[:2], '''WHERE pz.z = '1' ''')}")
def _(spark, d):
    return shown(all_heavy(md.pin_class(mixture(spark, d), 1), X[:2]), X[:2])


@query("q_mixture_constant_class", f"{ONE}, {marginals_sql('one', T3)} {product_sql('one', T3, LAM, LAM)}")
def _(spark, d):
    """A class of one value gives the product model."""
    return shown(all_heavy(md.fit_mixture(one(spark, d), X, "z", GAMMA), T3), T3)


@query("q_downward_mixture", "SELECT c AS dropped, CAST(0 AS BIGINT) AS misses FROM (VALUES ('x1'), ('x2'), ('x3')) v(c)")
def _(spark, d):
    return check_downward(mixture(spark, d), T3)


# ---- sketch
_SK = f"""lf AS ({long_sql('one', ('x4', 'x5'))}), n AS (SELECT CAST(count(*) AS DOUBLE) AS m FROM one), pool AS (SELECT coord, value FROM lf GROUP BY coord, value HAVING count(*) >= 0.002 * (SELECT m FROM n)),
cells AS (SELECT coord, r, {_CELL.replace('200', '537')} AS bucket, count(*) AS cnt FROM lf, range(5) t(r) GROUP BY ALL),
mg AS (SELECT coord, value, min(cnt) / (SELECT m FROM n) AS share FROM (SELECT coord, value, r, {_CELL.replace('200', '537')} AS bucket FROM pool, range(5) t(r)) JOIN cells USING (coord, r, bucket) GROUP BY coord, value)"""


@query("q_sketch_all_heavy", f"{ONE}, {_SK} {product_sql('one', ('x4', 'x5'), GAMMA, 0.0)}")
def _(spark, d):
    s = one(spark, d)
    m = s.count()
    pool = long_form(s, ["x4", "x5"]).groupBy("coord", "value").count().where(F.col("count") >= GAMMA * m).select("coord", "value")
    return shown(sk.sketch_all_heavy(sk.fit_sketch(s, ["x4", "x5"], GAMMA, 537, 5, 9, "md5", candidates=pool), ("x4", "x5"), GAMMA), ("x4", "x5"))


@query("q_sketch_from_counters")
def _(spark, d):
    s = one(spark, d)
    return sk.sketch_all_heavy(sk.fit_sketch(s, X, GAMMA, 537, 5), T3, GAMMA)


# ---- exact, calibration, assumption
_T3S = "x1, x2, x3"


@query("q_exact_shares", f"{W('synth')} SELECT {_T3S}, count(*) AS cnt, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM synth) AS share FROM synth GROUP BY {_T3S}")
def _(spark, d):
    return ex.exact_shares(synth(spark, d), T3)


_EXACT = f"{W('synth')} SELECT {_T3S}, count(*) AS cnt, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM synth) AS share FROM synth GROUP BY {_T3S} HAVING count(*) >= 0.002 * (SELECT count(*) FROM synth)"
query("q_exact_all_heavy", _EXACT)(lambda spark, d: ex.exact_all_heavy(synth(spark, d), T3, GAMMA))
query("q_exact_all_heavy_pruned", _EXACT)(lambda spark, d: ex.exact_all_heavy(synth(spark, d), T3, GAMMA, prune=True))


@query("q_exact_verdict", f"{W('synth')} SELECT (SELECT max(n) FROM (SELECT count(*) AS n FROM synth GROUP BY {_T3S})) >= 0.002 * count(*) AS heavy, count(*) FILTER (WHERE x1 = -1 AND x2 = -1 AND x3 = -1) >= 0.002 * count(*) AS light FROM synth")
def _(spark, d):
    s = synth(spark, d)
    top = s.groupBy(*T3).count().orderBy(F.desc("count"), *T3).first()[:3]
    return spark.createDataFrame([(ex.exact_verdict(s, T3, top, GAMMA), ex.exact_verdict(s, T3, (-1, -1, -1), GAMMA))], "heavy boolean, light boolean")


def _calibrate_sql(T):
    c = ", ".join(T)
    return f"SELECT '{','.join(T)}' AS subcube, max(total) AS distinct_values, min(upto) FILTER (WHERE upto >= greatest(floor(total * 0.01), 1)) AS heavy, max(cnt) FILTER (WHERE upto >= greatest(floor(total * 0.01), 1)) / (SELECT CAST(count(*) AS DOUBLE) FROM synth) AS gamma FROM (SELECT cnt, CAST(sum(n) OVER (ORDER BY cnt DESC) AS BIGINT) AS upto, CAST(sum(n) OVER () AS BIGINT) AS total FROM (SELECT cnt, count(*) AS n FROM (SELECT count(*) AS cnt FROM synth GROUP BY {c}) GROUP BY cnt))"


@query("q_calibrate", f"{W('synth')} " + " UNION ALL ".join(map(_calibrate_sql, tb.SYNTH_SUBCUBES)))
def _(spark, d):
    return ex.calibrate_gamma(synth(spark, d), tb.SYNTH_SUBCUBES)


query("q_fix_class", f"{ONE} SELECT k, z, x1 FROM one")(lambda spark, d: one(spark, d).select("k", "z", "x1"))
query("q_synth_rows", f"{W('synth')} SELECT * FROM synth")(synth)


def _text(T):
    return ", ".join(f"CAST({x} AS VARCHAR) AS {x}" for x in T)


def _gap_sql(src, T, head):
    """Observed gap, and the largest mass over it among joint values that never occur, grown by prefixes."""
    n = f"(SELECT CAST(count(*) AS DOUBLE) FROM {src})"
    cols = ", ".join(T)
    seen = f"jc AS (SELECT {_text(T)}, count(*) AS cnt FROM {src} GROUP BY {cols}), og AS (SELECT max(abs(jc.cnt / {n} - {' * '.join(f'm{i}.share' for i in range(len(T)))})) AS g FROM jc {' '.join(f'''JOIN mg m{i} ON m{i}.coord = '{x}' AND m{i}.value = jc.{x}''' for i, x in enumerate(T))})"
    steps = [f"p0 AS MATERIALIZED (SELECT value AS {T[0]}, share AS q FROM mg, og WHERE coord = '{T[0]}' AND share >= g)"]
    for i, x in enumerate(T[1:], 1):
        steps.append(f"p{i} AS MATERIALIZED (SELECT p{i - 1}.* EXCLUDE (q), mg.value AS {x}, q * mg.share AS q FROM p{i - 1} JOIN (SELECT mg.* FROM mg, og WHERE coord = '{x}' AND share >= g) mg ON q * mg.share >= (SELECT g FROM og))")
    unseen = f"ug AS (SELECT coalesce(max(q), 0) AS u FROM p{len(T) - 1} ANTI JOIN jc USING ({cols}))"
    return f"{head}, {marginals_sql(src, T)}, {seen}, {', '.join(steps)}, {unseen} SELECT '{','.join(T)}' AS subcube, round(g, 9) AS observed_gap, round(u, 9) AS unobserved_gap, round(greatest(g, u), 9) AS gap FROM og, ug"


def _gap_mixture_sql(src, T, cls, head):
    n = f"(SELECT CAST(count(*) AS DOUBLE) FROM {src})"
    cols = ", ".join(T)
    base = f"pz AS (SELECT CAST({cls} AS VARCHAR) AS z, count(*) AS n, count(*) / {n} AS p FROM {src} GROUP BY {cls}), lfz AS ({long_sql(src, T, f'CAST({cls} AS VARCHAR) AS z, ')}), cz AS (SELECT coord, value, z, count(*) AS n FROM lfz GROUP BY ALL), cd AS (SELECT coord, value, cz.z, cz.n / CAST(pz.n AS DOUBLE) AS f FROM cz JOIN pz USING (z))"
    joins = " ".join(f"JOIN cd c{i} ON c{i}.coord = '{x}' AND c{i}.value = jc.{x} AND c{i}.z = pz.z" for i, x in enumerate(T))
    held = " * ".join(f"c{i}.f" for i in range(len(T)))
    js = ", ".join(f"jc.{x}" for x in T)
    seen = f"jc AS (SELECT {_text(T)}, count(*) AS cnt FROM {src} GROUP BY {cols}), mm AS (SELECT {js}, sum(p * {held}) AS mass FROM jc CROSS JOIN pz {joins} GROUP BY {js}), og AS (SELECT max(abs(cnt / {n} - coalesce(mass, 0))) AS g FROM jc LEFT JOIN mm USING ({cols}))"
    steps = [f"p0 AS MATERIALIZED (SELECT value AS {T[0]}, cd.z, p * f AS q FROM cd JOIN pz USING (z) WHERE coord = '{T[0]}' AND value IN (SELECT value FROM cd JOIN pz USING (z) WHERE coord = '{T[0]}' GROUP BY value HAVING sum(p * f) >= (SELECT g FROM og)))"]
    for i, x in enumerate(T[1:], 1):
        have = ", ".join(T[: i + 1])
        steps.append(f"r{i} AS MATERIALIZED (SELECT p{i - 1}.* EXCLUDE (q), cd.value AS {x}, q * f AS q FROM p{i - 1} JOIN cd ON cd.z = p{i - 1}.z AND cd.coord = '{x}')")
        steps.append(f"h{i} AS MATERIALIZED (SELECT {have} FROM r{i} GROUP BY {have} HAVING sum(q) >= (SELECT g FROM og)), p{i} AS MATERIALIZED (SELECT r{i}.* FROM r{i} SEMI JOIN h{i} USING ({have}))")
    last = len(T) - 1
    unseen = f"ug AS (SELECT coalesce(max(mass), 0) AS u FROM (SELECT {cols}, sum(q) AS mass FROM p{last} GROUP BY {cols}) ANTI JOIN jc USING ({cols}))"
    return f"{head}, {base}, {seen}, {', '.join(steps)}, {unseen} SELECT '{','.join(T)}' AS subcube, round(g, 9) AS observed_gap, round(u, 9) AS unobserved_gap, round(greatest(g, u), 9) AS gap FROM og, ug"


def gap_shown(df):
    return df.select("subcube", *(F.round(c, 9).alias(c) for c in ("observed_gap", "unobserved_gap", "gap")))


query("q_gap_product", _gap_sql("one", T3, ONE))(lambda spark, d: gap_shown(gp.model_gap(one(spark, d), T3)))
query("q_gap_product_whole", _gap_sql("synth", T3, W("synth")))(lambda spark, d: gap_shown(gp.model_gap(synth(spark, d), T3)))


@query("q_gap_mixture", _gap_mixture_sql("synth", T3, "z", W("synth")))
def _(spark, d):
    return gap_shown(gp.model_gap(synth(spark, d), T3, "z"))


_SMALL = ("os", "lang", "engine", "browser")


@query("q_gap_all_subsets", f"{W('clicks')} " + " UNION ALL ".join(f"SELECT * FROM ({_gap_sql('clicks', T, 'WITH o AS (SELECT 1)')})" for n in (1, 2) for T in combinations(_SMALL, n)))
def _(spark, d):
    return gap_shown(gp.model_gap_all(tb.clicks(spark, d), _SMALL, 2))


@query("q_total_variation", f"{W('clicks')}, {marginals_sql('clicks', _SMALL[:3])}, jc AS (SELECT {_text(_SMALL[:3])}, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM clicks) AS s FROM clicks GROUP BY os, lang, engine), b AS (SELECT s, a.share * b.share * c.share AS q FROM jc JOIN mg a ON a.coord = 'os' AND a.value = os JOIN mg b ON b.coord = 'lang' AND b.value = lang JOIN mg c ON c.coord = 'engine' AND c.value = engine) SELECT 'os,lang,engine' AS subcube, round((sum(abs(s - q)) + greatest(1 - sum(q), 0)) / 2, 9) AS tv FROM b")
def _(spark, d):
    return gp.total_variation(tb.clicks(spark, d), _SMALL[:3]).withColumn("tv", F.round("tv", 9))


@query("q_gap_flags", f"SELECT gap < 0.0002 AS within_assumption, gap < 0.0005 AS enough FROM ({_gap_sql('synth', T3, W('synth'))})")
def _(spark, d):
    """The whole generated stream is no product: the flags say so."""
    f = gp.gap_flags(gp.model_gap(synth(spark, d), T3).first()["gap"], GAMMA)
    return spark.createDataFrame([(f["within_assumption"], f["enough"])], "within_assumption boolean, enough boolean")


_CORR = (("geo_region", "geo_nation"), ("page_brand", "page"), ("lang", "os"), ("lang", "engine"))


def _cramers_sql(a, b):
    return f"SELECT '{a}' AS a, '{b}' AS b, round(CASE WHEN least(ra, rb) < 2 THEN 0 ELSE sqrt(greatest(s - 1, 0) / (least(ra, rb) - 1)) END, 9) AS v FROM (SELECT sum(n * n / (CAST(na AS DOUBLE) * nb)) AS s, count(DISTINCT {a}) AS ra, count(DISTINCT {b}) AS rb FROM (SELECT {a}, {b}, n, sum(n) OVER (PARTITION BY {a}) AS na, sum(n) OVER (PARTITION BY {b}) AS nb FROM (SELECT {a}, {b}, CAST(count(*) AS DOUBLE) AS n FROM clicks GROUP BY {a}, {b})))"


@query("q_cramers_v", f"{W('clicks')} " + " UNION ALL ".join(_cramers_sql(a, b) for a, b in _CORR))
def _(spark, d):
    from functools import reduce

    df = tb.clicks(spark, d)
    return reduce(DataFrame.unionByName, (ex.cramers_v(df, a, b) for a, b in _CORR)).withColumn("v", F.round("v", 9))


@query("q_sample_from_mixture", None)
def _(spark, d):
    """Rows drawn from a fitted mixture: a class, then each coordinate within it, by cumulative shares."""
    from ..sources.generated import sample_from_mixture

    return sample_from_mixture(mixture(spark, d), T3, 5000)


# ---- baselines
@query("q_per_subcube_summary")
def _(spark, d):
    return bl.per_subcube_summary(one(spark, d), X, 3, 500)


@query("q_grouping_sets_subcubes", f"{W('clicks')} SELECT CASE grouping(os, lang, engine) WHEN 1 THEN 'os,lang' WHEN 4 THEN 'lang,engine' WHEN 2 THEN 'os,engine' END AS subcube, coalesce(os, lang) AS v1, CASE WHEN grouping(engine) = 0 THEN engine ELSE lang END AS v2, count(*) AS cnt FROM clicks GROUP BY GROUPING SETS ((os, lang), (lang, engine), (os, engine))")
def _(spark, d):
    return bl.subcube_counts(tb.clicks(spark, d), (("os", "lang"), ("lang", "engine"), ("os", "engine"))).select("subcube", F.col("vals")[0].alias("v1"), F.col("vals")[1].alias("v2"), "cnt")


@query("q_cube_subcubes", f"{W('clicks')} SELECT os, lang, engine, grouping(os, lang, engine) AS g, count(*) AS cnt FROM clicks GROUP BY CUBE (os, lang, engine)")
def _(spark, d):
    return tb.clicks(spark, d).cube("os", "lang", "engine").agg(F.grouping_id().alias("g"), F.count("*").alias("cnt"))


@query("q_linearised_full", f"{W('clicks')} SELECT os || '|' || lang || '|' || engine || '|' || browser AS item, count(*) AS cnt FROM clicks GROUP BY item HAVING count(*) >= 0.01 * (SELECT count(*) FROM clicks)")
def _(spark, d):
    df = tb.clicks(spark, d)
    return bl.linearised(df, ("os", "lang", "engine", "browser"), "item").groupBy("item").agg(F.count("*").alias("cnt")).where(F.col("cnt") >= 0.01 * df.count())


@query("q_unary_itemset", f"{W('clicks')} SELECT 'engine=' || engine AS i1, 'lang=' || lang AS i2, 'os=' || os AS i3, count(*) AS freq FROM clicks GROUP BY ALL HAVING count(*) >= 0.05 * (SELECT count(*) FROM clicks)")
def _(spark, d):
    return bl.itemset_heavy(tb.clicks(spark, d), ("os", "lang", "engine"), 0.05).select(*(F.col("items")[i].alias(f"i{i + 1}") for i in range(3)), "freq")


@query("q_unary_encode", f"{W('clicks')} SELECT item, count(*) AS cnt FROM (SELECT 'os=' || os AS item FROM clicks UNION ALL SELECT 'lang=' || lang FROM clicks) GROUP BY item")
def _(spark, d):
    return bl.unary_encode(tb.clicks(spark, d), tb.ROW_KEY, ("os", "lang")).groupBy("item").agg(F.count("*").alias("cnt"))


_FS = " UNION ALL ".join(f"SELECT '{','.join(s)}' AS flags, count(*) FILTER (WHERE {' AND '.join(s)}) / CAST(count(*) AS DOUBLE) AS share FROM flags" for n in (1, 2, 3) for s in combinations(sorted(tb.FLAGS), n))


def flag_sets(spark, d):
    return bl.frequent_flag_subcubes(tb.flags(spark, d), tb.FLAGS, 0.2, 3)


@query("q_flag_subcubes", f"{W('flags')} SELECT * FROM ({_FS}) WHERE share >= 0.2")
def _(spark, d):
    return flag_sets(spark, d).select(F.array_join("flags", ",").alias("flags"), "share")


@query("q_maximal_subcubes", f"{W('flags')}, f AS (SELECT string_split(flags, ',') AS fs, share FROM ({_FS}) WHERE share >= 0.2) SELECT array_to_string(fs, ',') AS flags, share FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE len(g.fs) > len(f.fs) AND list_has_all(g.fs, f.fs))")
def _(spark, d):
    return bl.maximal(flag_sets(spark, d)).select(F.array_join("flags", ",").alias("flags"), "share")


@query("q_lower_bound", "SELECT 19 AS d, 3 AS k, gamma, round(3 * 19 / gamma * log2(19 / 3.0::DOUBLE), 6) AS bits FROM (SELECT max(n) / CAST(sum(n) AS DOUBLE) AS gamma FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_returnflag, l_linestatus, l_linenumber))")
def _(spark, d):
    """The bound for joint values as frequent as the most frequent one of three coordinates."""
    gamma = ex.exact_shares(tb.table(spark, d, "lineitem"), ("l_returnflag", "l_linestatus", "l_linenumber")).agg(F.max("share")).first()[0]
    return spark.createDataFrame([(19, 3, gamma, round(bl.lower_bound_bits(3, 19, gamma), 6))], "d int, k int, gamma double, bits double")


# ---- measures and workloads in SQL
_PCT = "greatest(1, floor({part!r}::DOUBLE * (SELECT count(*) FROM {src})))"


def _pri(key):
    joined = " || '|' || ".join(f"CAST({c} AS VARCHAR)" for c in key)
    return f"CAST(('0x' || substr(md5('{wl.SEED}|' || {joined}), 1, 8))::BIGINT AS BIGINT)"


def _drawn(name, src, key, pct) -> str:
    return f"{name} AS MATERIALIZED (SELECT * EXCLUDE (pri_at) FROM (SELECT *, row_number() OVER (ORDER BY {_pri(key)}, {', '.join(key)}) AS pri_at FROM {src}) WHERE pri_at <= {_PCT.format(part=pct / 100, src=src)})"


def _product_list(T, line, low) -> tuple[list[str], str]:
    """CTEs that grow prefixes over mg, and the name of the last, with T and e."""
    name = "l" + "_".join(T)
    out = [f"{name}0 AS MATERIALIZED (SELECT value AS {T[0]}, share AS e FROM mg WHERE coord = '{T[0]}' AND share >= {max(low, line * (1 - 1e-9))!r})"]
    for i, x in enumerate(T[1:], 1):
        near = line if i == len(T) - 1 else line * (1 - 1e-9)
        out.append(f"{name}{i} AS MATERIALIZED (SELECT p.* EXCLUDE (e), mg.value AS {x}, e * mg.share AS e FROM {name}{i - 1} p JOIN mg ON mg.coord = '{x}' AND mg.share >= {low!r} AND e * mg.share >= {near!r})")
    return out, f"{name}{len(T) - 1}"


def _mixture_list(T, line, low) -> tuple[list[str], str]:
    """The same over cd (coord, value, z, f) of the values of share >= low, and pz (z, p)."""
    name = "x" + "_".join(T)
    out = [f"{name}0 AS MATERIALIZED (SELECT value AS {T[0]}, cd.z, p * f AS q FROM cd JOIN pz USING (z) WHERE coord = '{T[0]}')"]
    for i, x in enumerate(T[1:], 1):
        have = ", ".join(T[: i + 1])
        out.append(f"{name}r{i} AS MATERIALIZED (SELECT p.* EXCLUDE (q), cd.value AS {x}, q * f AS q FROM {name}{i - 1} p JOIN cd ON cd.z = p.z AND cd.coord = '{x}')")
        out.append(f"{name}{i} AS MATERIALIZED (SELECT r.* FROM {name}r{i} r SEMI JOIN (SELECT {have} FROM {name}r{i} GROUP BY {have} HAVING sum(q) >= {line * (1 - 1e-9)!r}) h USING ({have}))")
    cols = ", ".join(T)
    out.append(f"{name} AS MATERIALIZED (SELECT {cols}, sum(q) AS e FROM {name}{len(T) - 1} GROUP BY {cols} HAVING sum(q) >= {line!r})")
    return out, name


def curve_sql(head, src, key, coords, Ts, methods, pct, cls=None, factors=wl.CUTS) -> str:
    """The rows of workloads.curve."""
    low = min(Ts.values()) * min(factors)
    ctes, parts = [marginals_sql(src, coords), _drawn("drawn", src, key, pct)], []
    if cls:
        ctes.append(f"pz AS (SELECT CAST({cls} AS VARCHAR) AS z, count(*) AS n, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM {src}) AS p FROM {src} GROUP BY {cls}), lfz AS ({long_sql(src, coords, f'CAST({cls} AS VARCHAR) AS z, ')}), cd AS MATERIALIZED (SELECT coord, value, c.z, c.n / CAST(pz.n AS DOUBLE) AS f FROM (SELECT coord, value, z, count(*) AS n FROM lfz GROUP BY ALL) c JOIN pz USING (z) SEMI JOIN (SELECT * FROM mg WHERE share >= {low!r}) USING (coord, value))")
    for T, gamma in Ts.items():
        name, cols, line = "_".join(T), ", ".join(T), gamma * min(factors)
        ctes.append(f"t{name} AS MATERIALIZED (SELECT {_text(T)}, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM {src}) AS s FROM {src} GROUP BY {cols})")
        for method in methods:
            if method == "sample":
                made, last = [f"s{name} AS MATERIALIZED (SELECT {_text(T)}, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM drawn) AS e FROM drawn GROUP BY {cols} HAVING e >= {line!r})"], f"s{name}"
            else:
                made, last = (_product_list if method == "product" else _mixture_list)(T, line, low)
            ctes += made
            on = " AND ".join(f"t.{c} IS NOT DISTINCT FROM r.{c}" for c in T)
            lines = ", ".join(f"({f!r}::DOUBLE, {gamma * f!r}::DOUBLE)" for f in factors)
            parts.append(f"SELECT {pct!r}::DOUBLE AS pct, '{method}' AS method, f AS cut, '{','.join(T)}' AS subcube, count(*) FILTER (WHERE yes AND s >= {gamma!r}) AS tp, count(*) FILTER (WHERE yes AND s < {gamma!r}) AS fp, count(*) FILTER (WHERE yes AND s < {gamma / 4!r}) AS fp_strict, count(*) FILTER (WHERE NOT yes AND s >= {gamma!r}) AS fn, count(*) FILTER (WHERE yes) AS reported, count(*) FILTER (WHERE s < {gamma!r} AND (yes OR seen)) AS negatives "
                         f"FROM (SELECT f, coalesce(s, 0) AS s, s IS NOT NULL AS seen, coalesce(e >= l, FALSE) AS yes FROM (SELECT t.s, r.e FROM t{name} t FULL JOIN {last} r ON {on}), (VALUES {lines}) c(f, l)) GROUP BY f")
    return f"{head}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


_SYN3 = {T: GAMMA for T in tb.SYNTH_SUBCUBES}
_W2 = lambda pct, methods=("sample", "product"): curve_sql(ONE, "one", ("k",), X, _SYN3, methods, pct)
_W3 = lambda pct: curve_sql(W("synth"), "synth", ("k",), X, _SYN3, ("sample", "mixture"), pct, "z")
_W4 = lambda pct, methods=("sample", "product"): curve_sql(W("clicks"), "clicks", tb.ROW_KEY, wl.CLICK_AXES, tb.CLICK_SUBCUBES, methods, pct)
_T4N = ("geo_region", "geo_nation", "lang")


def _averaged_sql(parts, values=("tp", "fp", "fp_strict", "fn", "reported", "negatives")) -> str:
    every = " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)
    return f"SELECT pct, method, cut, {', '.join(f'avg({v}) AS {v}' for v in values)} FROM ({every}) GROUP BY pct, method, cut"


def _roc_sql(points) -> str:
    return f"""WITH su AS (SELECT pct, method, cut, sum(tp) AS tp, sum(fp) AS fp, sum(fn) AS fn, sum(negatives) AS ng FROM ({points}) GROUP BY ALL),
ra AS (SELECT pct, method, CASE WHEN ng > 0 THEN fp / CAST(ng AS DOUBLE) ELSE 0 END AS fpr, CASE WHEN tp + fn > 0 THEN tp / CAST(tp + fn AS DOUBLE) ELSE 0 END AS tpr FROM su
  UNION ALL SELECT DISTINCT pct, method, e, e FROM su, (VALUES (0.0::DOUBLE), (1.0)) v(e)),
st AS (SELECT pct, method, fpr - lag(fpr) OVER w AS dx, tpr + lag(tpr) OVER w AS sy FROM ra WINDOW w AS (PARTITION BY pct, method ORDER BY fpr, tpr))
SELECT pct, method, round(coalesce(sum(dx * sy / 2), 0), 9) AS auc FROM st GROUP BY pct, method"""


def _warm_sql(budgets) -> str:
    ctes, parts = [marginals_sql("one", X)], []
    for T in tb.SYNTH_SUBCUBES:
        ctes.append(f"t{'_'.join(T)} AS MATERIALIZED (SELECT {', '.join(T)}, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM one) AS s FROM one GROUP BY {', '.join(T)} ORDER BY count(*) DESC, {', '.join(T)} LIMIT 10)")
    for i, pct in enumerate(budgets):
        ctes.append(_drawn(f"d{i}", "one", ("k",), pct))
        bucket = f"CAST((('0x' || substr(md5('{wl.SEED}|' || r || '|' || coord || '|' || value), 1, 8))::BIGINT) % (SELECT CAST(greatest(1, count(*) // 5) AS BIGINT) FROM d{i}) AS BIGINT)"
        ctes.append(f"v{i} AS MATERIALIZED (SELECT coord, value, cnt, r, {bucket} AS b FROM mg, range(5) t(r)), c{i} AS MATERIALIZED (SELECT coord, r, b, sum(cnt) AS n FROM v{i} GROUP BY ALL), e{i} AS MATERIALIZED (SELECT coord, value, min(n) / (SELECT CAST(count(*) AS DOUBLE) FROM one) AS share FROM v{i} JOIN c{i} USING (coord, r, b) GROUP BY coord, value)")
        for T in tb.SYNTH_SUBCUBES:
            name, cols = "_".join(T), ", ".join(T)
            sample = f"SELECT t.s, coalesce(e, 0) AS e FROM t{name} t LEFT JOIN (SELECT {cols}, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM d{i}) AS e FROM d{i} GROUP BY {cols}) USING ({cols})"
            joins = " ".join(f"JOIN e{i} m{j} ON m{j}.coord = '{c}' AND m{j}.value = CAST(t.{c} AS VARCHAR)" for j, c in enumerate(T))
            sketch = f"SELECT t.s, {' * '.join(f'm{j}.share' for j in range(len(T)))} AS e FROM t{name} t {joins}"
            for method, rows in (("sample", sample), ("sketch", sketch)):
                parts.append(f"SELECT {pct!r}::DOUBLE AS pct, '{method}' AS method, '{','.join(T)}' AS subcube, round(avg((e - s) * (e - s)), 12) AS mse, round(avg(abs(e - s)), 9) AS mae, round(100 * avg(abs(e - s) / s), 6) AS mape FROM ({rows})")
    return f"{ONE}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


def warm_shown(df):
    return df.select("pct", "method", "subcube", F.round("mse", 12).alias("mse"), F.round("mae", 9).alias("mae"), F.round("mape", 6).alias("mape"))


@query("q_errors_warmup", _warm_sql((0.5, 2.0)))
def _(spark, d):
    return warm_shown(wl.warm_up(spark, d, (0.5, 2.0)))


@query("q_heavy_stats", f"{ONE} " + " UNION ALL ".join(f"SELECT '{','.join(T)}' AS subcube, count(*) AS distinct_values, count(*) FILTER (WHERE n >= 0.002 * m) AS heavy, count(*) FILTER (WHERE n >= 0.002 * m) / CAST(count(*) AS DOUBLE) AS ratio FROM (SELECT count(*) AS n, (SELECT count(*) FROM one) AS m FROM one GROUP BY {', '.join(T)})" for T in tb.SYNTH_SUBCUBES))
def _(spark, d):
    return ex.heavy_stats(one(spark, d), {T: GAMMA for T in tb.SYNTH_SUBCUBES})


@query("q_tp_fp_curve", f"""{W('synth')}, {_SMP}, t AS (SELECT x1, x2, x3, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM synth) AS s FROM synth GROUP BY x1, x2, x3),
r AS (SELECT x1, x2, x3, count(*) / 3360.0::DOUBLE AS e FROM smp GROUP BY x1, x2, x3), b AS (SELECT s, coalesce(e, 0) AS e FROM t LEFT JOIN r USING (x1, x2, x3))
SELECT cut, count(*) FILTER (WHERE e >= 0.002 * cut AND s >= 0.002) AS tp, count(*) FILTER (WHERE e >= 0.002 * cut AND s < 0.002) AS fp, count(*) FILTER (WHERE e < 0.002 * cut AND s >= 0.002) AS fn FROM b, (VALUES (0.5::DOUBLE), (1.0), (2.0)) c(cut) GROUP BY cut""")
def _(spark, d):
    from functools import reduce

    s = synth(spark, d)
    truth, smp = ex.exact_shares(s, T3), sp.draw_sample(s, ["k"], 3360, 7, "md5")
    return reduce(DataFrame.unionByName, (ms.confusion(sp.sample_all_heavy(smp, T3, GAMMA * c), truth, T3, GAMMA).select(F.lit(c).alias("cut"), "tp", "fp", "fn") for c in (0.5, 1.0, 2.0)))


@query("q_roc_auc", _roc_sql(f"SELECT * FROM ({_W3(2.0)}) UNION ALL SELECT * FROM ({_W2(2.0)})".replace("'sample' AS method", "'sample' AS method")))
def _(spark, d):
    """Areas of the mixture against the sample on the whole stream, and of the product against the sample within a class,
    summed over both streams for the sample."""
    points = [wl.mixture_curve(spark, d), wl.independent_curve(spark, d)]
    held = [spark.createDataFrame(p.collect(), p.schema) for p in points]
    return wl.roc(held[0].unionByName(held[1])).withColumn("auc", F.round("auc", 9))


@query("q_memory", f"""{ONE}, {marginals_sql('synth', X)}, b AS (SELECT CAST(floor(0.02::DOUBLE * count(*)) AS BIGINT) AS n FROM synth), s AS (SELECT count(*) AS n FROM mg WHERE share >= 0.001), c AS (SELECT count(DISTINCT z) AS n FROM synth)
SELECT method, 5 * b.n + CASE WHEN method = 'mixture' THEN c.n * s.n ELSE 0 END AS cells FROM b, s, c, (VALUES ('sample'), ('sketch'), ('product'), ('mixture')) t(method)""")
def _(spark, d):
    """Cells that each method stores at 2 % of the stream, the mixture's conditionals counted on the fitted model."""
    s, m = synth(spark, d), mixture(spark, d)
    b, survivors = ms.budget_to_params(2.0, len(X), s.count()), m.table.count()
    return spark.createDataFrame([(n, ms.memory_cells(n, len(X), b["size"], len(m.prior), survivors)) for n in ("sample", "sketch", "product", "mixture")], "method string, cells bigint")


@query("q_success_rate")
def _(spark, d):
    c = tb.clicks(spark, d).select(*tb.ROW_KEY, "os", "lang").persist()
    size = min(c.count(), sp.sample_size_bound(0.2, 2, 2, 3))
    return spark.createDataFrame([(size, ms.success_rate(c, tb.ROW_KEY, ("os", "lang"), 0.2, size, range(5)))], "size bigint, rate double")


# ---- workloads
query("q_w1", _warm_sql(wl.BUDGETS))(lambda spark, d: warm_shown(wl.warm_up(spark, d)))
query("q_w2", _W2(2.0))(lambda spark, d: wl.independent_curve(spark, d))
query("q_w2_sketch")(lambda spark, d: wl.independent_curve(spark, d, methods=("sketch",)))
query("q_w3", _W3(2.0))(lambda spark, d: wl.mixture_curve(spark, d))
query("q_w4", _W4(10.0))(lambda spark, d: wl.clicks_curve(spark, d))
query("q_w4_sketch")(lambda spark, d: wl.clicks_curve(spark, d, methods=("sketch",)))
query("q_w4n", curve_sql(W("clicks"), "clicks", tb.ROW_KEY, _T4N, {_T4N: 0.01}, ("sample", "product"), 10.0, factors=(0.5, 1.0)))(lambda spark, d: wl.correlated_curve(spark, d))
query("q_w5")(lambda spark, d: wl.search_curve(spark, d))
#: Memory budgets at which every value over the least cut still has a counter, so that SQL can say the lists.
query("q_w2_budgets", _averaged_sql(_W2(p) for p in (2.0, 5.0, 10.0)))(lambda spark, d: wl.over_budgets(wl.independent_curve, spark, d, (2.0, 5.0, 10.0)))
query("q_w3_budgets", _averaged_sql(_W3(p) for p in (2.0, 5.0, 10.0)))(lambda spark, d: wl.over_budgets(wl.mixture_curve, spark, d, (2.0, 5.0, 10.0)))
query("q_w4_budgets", _averaged_sql(_W4(p) for p in (2.0, 5.0, 10.0)))(lambda spark, d: wl.over_budgets(wl.clicks_curve, spark, d, (2.0, 5.0, 10.0)))
query("q_w2_small")(lambda spark, d: wl.over_budgets(wl.independent_curve, spark, d, (0.1, 0.5, 1.0), methods=("sample", "product", "sketch")))


def _stats_sql(src, T, gamma):
    return f"SELECT '{','.join(T)}' AS subcube, count(*) FILTER (WHERE n / CAST(m AS DOUBLE) >= {gamma!r}) AS heavy, count(*) FILTER (WHERE n / CAST(m AS DOUBLE) >= {gamma!r}) / CAST(count(*) AS DOUBLE) AS ratio FROM (SELECT count(*) AS n, (SELECT count(*) FROM {src}) AS m FROM {src} GROUP BY {', '.join(T)})"


def _web_sql(T):
    return f"SELECT '{','.join(T)}' AS subcube, count(*) FILTER (WHERE n >= 0.05 * m) AS heavy, count(*) FILTER (WHERE n >= 0.05 * m) / CAST(count(*) AS DOUBLE) AS ratio FROM (SELECT w.subset, count(*) AS n, any_value(z.m) AS m FROM websearch w JOIN (SELECT subset, count(*) AS m FROM websearch GROUP BY subset) z ON z.subset = w.subset GROUP BY w.subset, {', '.join(f'w.{c}' for c in T)}) GROUP BY subset"


def _table_sql():
    parts = {"generated, fixed class": [ONE, [_stats_sql("one", T, GAMMA) for T in tb.SYNTH_SUBCUBES]], "generated, whole": [W("synth"), [_stats_sql("synth", T, GAMMA) for T in tb.SYNTH_SUBCUBES]],
             "clicks": [W("clicks"), [_stats_sql("clicks", T, g) for T, g in tb.CLICK_SUBCUBES.items()]], "web search": [W("websearch"), [_web_sql(tb.SEARCH_COORDS[i : i + 3]) for i in range(8)]]}
    return " UNION ALL ".join(f"SELECT '{name}' AS workload, count(DISTINCT subcube) AS subcubes, round(avg(heavy), 9) AS avg_heavy, round(avg(ratio), 9) AS avg_ratio FROM ({head} {' UNION ALL '.join(rows)})" for name, (head, rows) in parts.items())


query("q_parameter_table", _table_sql())(lambda spark, d: wl.parameter_table(spark, d).withColumns({c: F.round(c, 9) for c in ("avg_heavy", "avg_ratio")}))


@query("q_w6", f"{W('wide')} SELECT sr_name AS r, quarter(l_shipdate) AS q, p_type AS p, count(*) AS cnt FROM wide GROUP BY ALL HAVING count(*) >= 0.01 * (SELECT count(*) FROM wide)")
def _(spark, d):
    w = tb.wide(spark, d).select(F.col("sr_name").alias("r"), F.quarter("l_shipdate").cast("bigint").alias("q"), F.col("p_type").alias("p"))
    return ex.exact_all_heavy(w, ("r", "q", "p"), 0.01, prune=True).drop("share")


@query("q_w7", f"{W('ev')} SELECT user_id, event_type, hr, count(*) AS cnt FROM ev GROUP BY ALL HAVING count(*) >= 0.0004 * (SELECT count(*) FROM ev)")
def _(spark, d):
    return ex.exact_all_heavy(tb.ev(spark, d), ("user_id", "event_type", "hr"), 0.0004).drop("share")


@query("q_w8_bigrams", f"{W('grams')} SELECT lang, a, b, count(*) AS cnt FROM grams GROUP BY ALL HAVING count(*) >= 0.0005 * (SELECT count(*) FROM grams)")
def _(spark, d):
    return ex.exact_all_heavy(tb.grams(spark, d), ("lang", "a", "b"), 0.0005, prune=True).drop("share")


@query("q_w8_trigrams", f"{W('grams')} SELECT lang, a, b, c, count(*) AS cnt FROM grams GROUP BY ALL HAVING count(*) >= 0.0001 * (SELECT count(*) FROM grams)")
def _(spark, d):
    return ex.exact_all_heavy(tb.grams(spark, d), ("lang", "a", "b", "c"), 0.0001, prune=True).drop("share")


_GRAMS = f"{W('grams')}, pz AS (SELECT CAST(lang AS VARCHAR) AS z, count(*) AS n, count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM grams) AS p FROM grams GROUP BY lang), lfz AS ({long_sql('grams', ('a', 'b'), 'CAST(lang AS VARCHAR) AS z, ')}), {marginals_sql('grams', ('a', 'b'))}, cd AS MATERIALIZED (SELECT coord, value, c.z, c.n / CAST(pz.n AS DOUBLE) AS f FROM (SELECT coord, value, z, count(*) AS n FROM lfz GROUP BY ALL) c JOIN pz USING (z) SEMI JOIN (SELECT * FROM mg WHERE share >= 0.0001) USING (coord, value))"


@query("q_w8_mixture", (lambda made: f"{_GRAMS}, {', '.join(made[0])} SELECT a, b, round(e, 9) AS mass FROM {made[1]}")(_mixture_list(("a", "b"), 0.0002, 0.0001)))
def _(spark, d):
    g = tb.grams(spark, d).persist()
    return shown(all_heavy(md.fit_mixture(g, ("a", "b"), "lang", 0.0002), ("a", "b"), 0.0002), ("a", "b"))


query("q_w9", _gap_sql("first_words", T3, W("first_words")))(lambda spark, d: gap_shown(gp.model_gap(tb.first_words(spark, d), T3)))
query("q_w9_mixture", _gap_mixture_sql("first_words", T3, "lang", W("first_words")))(lambda spark, d: gap_shown(gp.model_gap(tb.first_words(spark, d), T3, "lang")))


def _w10_sql(n):
    T = _AXES[:n]
    one_each = " + ".join(f"(SELECT count(DISTINCT {c}) FROM clicks)" for c in T)
    pairs = " + ".join(f"(SELECT count(*) FROM (SELECT DISTINCT {a}, {b} FROM clicks))" for a, b in combinations(T, 2))
    return f"SELECT {n} AS d, {one_each} AS model_cells, {pairs} AS per_subcube_cells"


_AXES = ("os", "lang", "engine", "browser", "referrer", "plugins")


@query("q_w10", f"{W('clicks')} SELECT * FROM (" + " UNION ALL ".join(_w10_sql(n) for n in (3, 4, 5, 6)) + ")")
def _(spark, d):
    """Cells stored by one summary of each coordinate and by one of each pair of coordinates, built and counted."""
    c, out = tb.clicks(spark, d).persist(), []
    for n in (3, 4, 5, 6):
        T = _AXES[:n]
        out.append((n, sm.misra_gries(c, T, 100_000).count(), bl.per_subcube_summary(c, T, 2, 100_000).count()))
    return spark.createDataFrame(out, "d int, model_cells bigint, per_subcube_cells bigint")


def _w11_sql():
    parts, ctes = [], [marginals_sql("clicks", wl.SCALING)]
    for k in range(1, 9):
        made, last = _product_list(wl.SCALING[:k], 0.001, 0.001)
        ctes += [m.replace("los", f"k{k}los") for m in made]
        parts.append(f"SELECT {k} AS k, strategy, (SELECT count(*) FROM {last.replace('los', f'k{k}los')}) AS heavy FROM (VALUES ('bucketed'), ('nested'), ('sorted'){", ('cartesian')" if k <= 4 else ''}) t(strategy)")
    return f"{W('clicks')}, {', '.join(ctes)} {' UNION ALL '.join(parts)}"


query("q_w11", _w11_sql())(lambda spark, d: wl.strategy_scaling(spark, d).drop("pairs"))
query("q_w11_pairs")(lambda spark, d: wl.strategy_scaling(spark, d))


# ---- questions in SQL text, and functions of the user's own
def _asked(spark, d, model):
    qu.register(spark, model, "asked")
    return qu.heavy_sql(spark, T3, LAM, "asked").withColumn("mass", F.round("mass", 9))


query("q_sql_heavy_product", f"{ONE}, {marginals_sql('one', T3)} {product_sql('one', T3, LAM, LAM)}")(lambda spark, d: _asked(spark, d, product(spark, d)))
query("q_sql_heavy_mixture", f"{_MIX} {mixture_sql(T3)}")(lambda spark, d: _asked(spark, d, mixture(spark, d)))


@query("q_sql_verdicts", _sql["q_product_verdicts"])
def _(spark, d):
    """The verdicts of a table of questions, by SQL functions over a model that was saved and read again."""
    s, path = one(spark, d), f"{_scratch(spark)}/asked-{uuid.uuid4().hex}"
    md.save_model(md.fit_product(s, X, GAMMA), path)
    qu.register(spark, md.load_model(spark, path), "asked")
    probes(s).createOrReplaceTempView("questions")
    return spark.sql(f"SELECT probe_id, round(asked_share(coords, vals), 9) AS mass, asked_verdict(coords, vals, {LAM!r}D) AS yes FROM questions")


@query("q_sql_subcubes", "SELECT a.i AS a, b.i AS b FROM (VALUES ('x1', 1), ('x2', 2), ('x3', 3), ('x4', 4), ('x5', 5)) a(i, n) JOIN (VALUES ('x1', 1), ('x2', 2), ('x3', 3), ('x4', 4), ('x5', 5)) b(i, n) ON a.n < b.n")
def _(spark, d):
    qu.register(spark, product(spark, d), "asked")
    return spark.sql("SELECT a.coord AS a, b.coord AS b FROM subcubes('x1, x2, x3, x4, x5', 2) a JOIN subcubes('x1, x2, x3, x4, x5', 2) b ON a.subcube_id = b.subcube_id AND a.pos = 1 AND b.pos = 2")


@query("q_x1_scalar_function", f"{W('clicks')}, {marginals_sql('clicks', ('os', 'page'))} SELECT coord, value, CAST(floor(-log2(share)) AS BIGINT) AS band FROM mg")
def _(spark, d):
    """The bucket of a share by a vectorised function of the user's."""
    return gp.exact_model(tb.clicks(spark, d), ("os", "page")).table.select("coord", "value", qu.band("share").alias("band"))


@query("q_x2_group_function", f"{W('clicks')} SELECT lang, round(max(n) / CAST(sum(n) AS DOUBLE), 9) AS top FROM (SELECT lang, page, count(*) AS n FROM clicks GROUP BY lang, page) GROUP BY lang")
def _(spark, d):
    """The share of each group's most frequent value by a vectorised aggregate of the user's, over counts."""
    return tb.clicks(spark, d).groupBy("lang", "page").agg(F.count("*").alias("n")).groupBy("lang").agg(F.round(qu.top_share("n"), 9).alias("top"))


@query("q_u2", f"{W('clicks')} SELECT os, lang, NULL AS engine FROM clicks UNION ALL SELECT os, NULL, engine FROM clicks")
def _(spark, d):
    c = tb.clicks(spark, d)
    return c.select("os", "lang").unionByName(c.select("os", "engine"), allowMissingColumns=True)


@query("q_j10", f"{ONE}, {marginals_sql('one', ('x1', 'x4'))} {product_sql('one', ('x1', 'x4'), LAM, LAM)}")
def _(spark, d):
    """The range join behind a listing, mass * share >= line, as an equi-join on powers of two."""
    return shown(all_heavy(product(spark, d), ("x1", "x4"), strategy="bucketed"), ("x1", "x4"))


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)


