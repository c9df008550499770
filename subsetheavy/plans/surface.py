"""The relational surface around the methods: scans, predicates, joins, aggregates, windows, sets and functions.

Most entries are one SQL text for both engines over views of the tables and derived streams; hints are comments to the
other engine. Where spelling differs an entry has two texts."""

from __future__ import annotations

import re
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import tables as tb

#: name: SQL for both, or (this engine's SQL, the other's)
TEXTS: dict[str, str | tuple[str, str]] = {
    # scans and predicates
    "q_s1": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY l_returnflag, l_linestatus",
    "q_s2": "SELECT count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS s FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01 00:00:00'",
    "q_s5": ("SELECT k, explode(sequence(k, k + 2)) AS v FROM (SELECT DISTINCT l_suppkey AS k FROM lineitem)", "SELECT k, unnest(range(k, k + 3)) AS v FROM (SELECT DISTINCT l_suppkey AS k FROM lineitem)"),
    "q_p1": "SELECT length(bin(CAST(floor(l_extendedprice) AS BIGINT))) AS mag, CAST(round(l_discount * 100) AS INT) AS pct, count(*) AS n FROM lineitem GROUP BY 1, 2",
    "q_p2": "SELECT os, lang, engine FROM clicks",
    "q_p3": "SELECT count(*) AS n FROM clicks WHERE os IS NOT DISTINCT FROM 'F' AND lang IS NOT DISTINCT FROM 'R' AND plugins IS NOT DISTINCT FROM 5",
    "q_p4": "SELECT page, count(*) AS n FROM clicks WHERE page IN (SELECT page FROM clicks GROUP BY page HAVING count(*) >= 0.016 * (SELECT count(*) FROM clicks)) GROUP BY page",
    "q_p5": "SELECT CASE WHEN plugins < 3 THEN 'low' WHEN plugins < 7 THEN 'mid' ELSE 'high' END AS band, coalesce(nullif(lang, 'R'), '?') AS lang, count(*) AS n FROM clicks GROUP BY 1, 2",
    "q_p6": ("SELECT count(*) AS n FROM pages WHERE url LIKE 'https%' AND url RLIKE '/(en|fr)/' AND html IS NOT NULL AND page_id BETWEEN 10 AND 200", "SELECT count(*) AS n FROM pages WHERE url LIKE 'https%' AND regexp_matches(url, '/(en|fr)/') AND html IS NOT NULL AND page_id BETWEEN 10 AND 200"),
    "q_p7": "SELECT engine, lang, count(*) AS n FROM clicks GROUP BY engine, lang HAVING count(*) * 1.0 / (SELECT count(*) FROM clicks) >= 0.1",
    "q_p8": "SELECT count(*) AS n FROM (SELECT DISTINCT os, lang, page FROM clicks)",
    # joins
    "q_j1": "SELECT /*+ BROADCAST(h) */ l_returnflag, h.v, count(*) AS n FROM lineitem JOIN (SELECT p_partkey, p_brand AS v FROM part WHERE p_size <= 5) h ON l_partkey = p_partkey GROUP BY 1, 2",
    "q_j2": "SELECT /*+ MERGE(orders) */ o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    "q_j3": "SELECT /*+ SHUFFLE_HASH(customer) */ c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
    "q_j4": "SELECT t.page, t.n, coalesce(e.n, 0) AS est FROM (SELECT page, count(*) AS n FROM clicks GROUP BY page ORDER BY n DESC, page LIMIT 10) t LEFT JOIN (SELECT page, count(*) AS n FROM clicks WHERE os = 'F' GROUP BY page HAVING count(*) > 450) e ON t.page = e.page",
    "q_j5": "SELECT coalesce(a.page, b.page) AS page, a.n AS na, b.n AS nb FROM (SELECT page, count(*) AS n FROM clicks WHERE os = 'F' GROUP BY page HAVING count(*) > 470) a FULL OUTER JOIN (SELECT page, count(*) AS n FROM clicks WHERE os = 'O' GROUP BY page HAVING count(*) > 470) b ON a.page IS NOT DISTINCT FROM b.page",
    "q_j6": "SELECT lang, count(*) AS n FROM clicks LEFT SEMI JOIN (SELECT engine AS e FROM clicks GROUP BY engine ORDER BY count(*) DESC, engine LIMIT 1) t ON engine = t.e GROUP BY lang",
    "q_j7": "SELECT p_partkey FROM part LEFT ANTI JOIN (SELECT l_partkey FROM lineitem WHERE l_discount > 0.05) t ON p_partkey = t.l_partkey",
    "q_j8": "SELECT m, c, b FROM (SELECT DISTINCT l_returnflag AS m FROM lineitem) t CROSS JOIN (SELECT DISTINCT l_linenumber AS c FROM lineitem) u CROSS JOIN (SELECT DISTINCT c_mktsegment AS b FROM customer) w",
    "q_j9": "SELECT a.page AS p, b.page_brand AS q, round(a.s * b.s, 9) AS mass FROM (SELECT page, CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM clicks) AS s FROM clicks GROUP BY page) a JOIN (SELECT page_brand, CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM clicks) AS s FROM clicks GROUP BY page_brand) b ON a.s * b.s >= 0.0008",
    "q_j11": "SELECT b.name, count(*) AS n FROM (SELECT plugins FROM clicks) c JOIN (VALUES ('a', 0, 3), ('b', 3, 7), ('c', 7, 100)) b(name, lo, hi) ON b.lo <= c.plugins AND c.plugins < b.hi GROUP BY b.name",
    "q_j13": "SELECT a.item AS i1, b.item AS i2, count(*) AS n FROM items a JOIN items b ON a.row_id = b.row_id AND a.item < b.item GROUP BY 1, 2 HAVING count(*) >= 0.05 * (SELECT count(*) FROM clicks)",
    "q_j14": "SELECT a.v, count(*) AS n FROM (SELECT nullif(lang, 'R') AS v FROM clicks) a JOIN (VALUES ('A'), (NULL)) b(v) ON a.v IS NOT DISTINCT FROM b.v GROUP BY a.v",
    "q_j15": ("SELECT s, pos, c, n FROM (SELECT s, posexplode(cs) AS (pos, c) FROM (VALUES (1, array('os', 'lang')), (2, array('engine', 'os'))) t(s, cs)) JOIN (SELECT 'os' AS k, count(DISTINCT os) AS n FROM clicks UNION ALL SELECT 'lang', count(DISTINCT lang) FROM clicks UNION ALL SELECT 'engine', count(DISTINCT engine) FROM clicks) d ON c = d.k", "SELECT s, CAST(pos - 1 AS INT) AS pos, cs[pos] AS c, n FROM (SELECT s, cs, unnest(range(1, len(cs) + 1)) AS pos FROM (VALUES (1, ['os', 'lang']), (2, ['engine', 'os'])) t(s, cs)) JOIN (SELECT 'os' AS k, count(DISTINCT os) AS n FROM clicks UNION ALL SELECT 'lang', count(DISTINCT lang) FROM clicks UNION ALL SELECT 'engine', count(DISTINCT engine) FROM clicks) d ON cs[pos] = d.k"),
    "q_j16": "SELECT cr_name, sr_name, count(*) AS n FROM wide GROUP BY 1, 2",
    # aggregates
    "q_a1": "SELECT os, lang, plugins, count(*) AS n FROM clicks GROUP BY os, lang, plugins",
    "q_a2": ("SELECT coord, value, count(*) AS n FROM (SELECT os, lang, engine FROM clicks) UNPIVOT (value FOR coord IN (os, lang, engine)) GROUP BY coord, value", "SELECT coord, value, count(*) AS n FROM (UNPIVOT (SELECT os, lang, engine FROM clicks) ON os, lang, engine INTO NAME coord VALUE value) GROUP BY coord, value"),
    "q_a3": ("SELECT coord, value, browser, count(*) AS n FROM (SELECT browser, os, lang FROM clicks) UNPIVOT (value FOR coord IN (os, lang)) GROUP BY coord, value, browser", "SELECT coord, value, browser, count(*) AS n FROM (UNPIVOT (SELECT browser, os, lang FROM clicks) ON os, lang INTO NAME coord VALUE value) GROUP BY coord, value, browser"),
    "q_a4": "SELECT os, lang, engine, count(*) AS n FROM clicks GROUP BY GROUPING SETS ((os, lang), (lang, engine), (os))",
    "q_a5": "SELECT os, lang, engine, count(*) AS n FROM clicks GROUP BY CUBE (os, lang, engine)",
    "q_a6": "SELECT os, lang, engine, count(*) AS n FROM clicks GROUP BY ROLLUP (os, lang, engine)",
    "q_a7": "SELECT count(DISTINCT page) AS pages, count(DISTINCT browser) AS browsers, count(DISTINCT plugins) AS plugins FROM clicks",
    "q_a8": ("SELECT l_suppkey, max(round(aggregate(array(l_extendedprice, l_discount, l_tax), 1D, (a, x) -> a * x), 9)) AS product, max(round(aggregate(zip_with(array(0.5D, 0.5D), array(l_extendedprice, l_quantity), (a, b) -> a * b), 0D, (a, x) -> a + x), 9)) AS weighted FROM lineitem GROUP BY l_suppkey", "SELECT l_suppkey, max(round(l_extendedprice * l_discount * l_tax, 9)) AS product, max(round(0.5::DOUBLE * l_extendedprice + 0.5::DOUBLE * l_quantity, 9)) AS weighted FROM lineitem GROUP BY l_suppkey"),
    "q_a9": "SELECT lang, count(*) FILTER (WHERE plugins >= 5) AS hi, count(*) FILTER (WHERE plugins < 5) AS lo FROM clicks GROUP BY lang",
    "q_a10": ("SELECT * FROM (SELECT lang, os FROM clicks) PIVOT (count(1) FOR os IN ('F' AS f, 'O' AS o))", "SELECT lang, count(*) FILTER (WHERE os = 'F') AS f, count(*) FILTER (WHERE os = 'O') AS o FROM clicks GROUP BY lang"),
    "q_a11": ("SELECT max_by(page, struct(n, page)) AS top, max(n) AS n FROM (SELECT page, count(*) AS n FROM clicks GROUP BY page)", "SELECT arg_max(page, {'n': n, 'page': page}) AS top, max(n) AS n FROM (SELECT page, count(*) AS n FROM clicks GROUP BY page)"),
    "q_a12": ("SELECT round(percentile(n, 0.9), 6) AS p90, round(percentile(n, 0.5), 6) AS p50 FROM (SELECT CAST(count(*) AS DOUBLE) AS n FROM clicks GROUP BY page, browser)", "SELECT round(quantile_cont(n, 0.9), 6) AS p90, round(quantile_cont(n, 0.5), 6) AS p50 FROM (SELECT CAST(count(*) AS DOUBLE) AS n FROM clicks GROUP BY page, browser)"),
    "q_a13": "SELECT browser, round(avg(n), 6) AS mean, round(stddev_samp(n), 6) AS sd FROM (SELECT browser, page, CAST(count(*) AS DOUBLE) AS n FROM clicks GROUP BY browser, page) GROUP BY browser",
    "q_a15": ("SELECT lang, array_join(array_sort(collect_list(os)), ',') AS all_os FROM (SELECT DISTINCT lang, os FROM clicks) GROUP BY lang", "SELECT lang, array_to_string(list_sort(list(os)), ',') AS all_os FROM (SELECT DISTINCT lang, os FROM clicks) GROUP BY lang"),
    "q_a17": "SELECT os, count(DISTINCT page) AS pages, count(DISTINCT browser) AS browsers, CAST(sum(plugins) AS BIGINT) AS s FROM (SELECT nullif(os, 'F') AS os, page, browser, plugins FROM clicks) GROUP BY os",
    # windows, sorts, sets
    "q_n1": "SELECT lang, page, n, row_number() OVER (PARTITION BY lang ORDER BY n DESC, page) AS rn, rank() OVER (PARTITION BY lang ORDER BY n DESC) AS rk, dense_rank() OVER (PARTITION BY lang ORDER BY n DESC) AS dr FROM (SELECT lang, page, count(*) AS n FROM clicks GROUP BY lang, page)",
    "q_n2": "SELECT page, round(sum(s) OVER (ORDER BY page ROWS UNBOUNDED PRECEDING), 9) AS upto FROM (SELECT page, CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM clicks) AS s FROM clicks GROUP BY page)",
    "q_n3": "SELECT lang, os, round(CAST(n AS DOUBLE) / sum(n) OVER (PARTITION BY lang), 9) AS f FROM (SELECT lang, os, count(*) AS n FROM clicks GROUP BY lang, os)",
    "q_n4": "SELECT round(sum((x - px) * (y + py) / 2), 9) AS area FROM (SELECT x, y, coalesce(lag(x) OVER (ORDER BY q), 0) AS px, coalesce(lag(y) OVER (ORDER BY q), 0) AS py FROM (SELECT q, CAST(sum(neg) OVER (ORDER BY q) AS DOUBLE) / sum(neg) OVER () AS x, CAST(sum(pos) OVER (ORDER BY q) AS DOUBLE) / sum(pos) OVER () AS y FROM (SELECT l_quantity AS q, count(*) FILTER (WHERE l_returnflag = 'R') AS pos, count(*) FILTER (WHERE l_returnflag <> 'R') AS neg FROM lineitem GROUP BY l_quantity)))",
    "q_n5": "SELECT page, round(percent_rank() OVER (ORDER BY n), 9) AS pr, ntile(4) OVER (ORDER BY n, page) AS q, round(cume_dist() OVER (ORDER BY n), 9) AS cd FROM (SELECT page, count(*) AS n FROM clicks GROUP BY page)",
    "q_n6": ("SELECT CAST(d AS STRING) AS d, sum(n) OVER (ORDER BY datediff(d, DATE '2024-01-01') RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS week FROM (SELECT d, count(*) AS n FROM ev GROUP BY d)", "SELECT CAST(d AS VARCHAR) AS d, CAST(sum(n) OVER (ORDER BY d RANGE BETWEEN INTERVAL 6 DAYS PRECEDING AND CURRENT ROW) AS BIGINT) AS week FROM (SELECT d, count(*) AS n FROM ev GROUP BY d)"),
    "q_n7": "SELECT CAST(d AS VARCHAR(10)) AS d, lead(n) OVER (ORDER BY d) AS nx, first_value(n) OVER (ORDER BY d) AS fst, nth_value(n, 2) OVER (ORDER BY d ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS snd FROM (SELECT d, count(*) AS n FROM ev GROUP BY d)",
    "q_t1": "SELECT page, count(*) AS n FROM clicks GROUP BY page ORDER BY n DESC, page",
    "q_t2": "SELECT page, browser, count(*) AS n FROM clicks GROUP BY page, browser ORDER BY n DESC, page, browser LIMIT 10",
    "q_t3": "SELECT lang, page, n FROM (SELECT lang, page, n, row_number() OVER (PARTITION BY lang ORDER BY n DESC, page) AS r FROM (SELECT lang, page, count(*) AS n FROM clicks GROUP BY lang, page)) WHERE r <= 3",
    "q_t4": "SELECT page, count(*) AS n FROM clicks GROUP BY page ORDER BY n DESC, page LIMIT 5 OFFSET 5",
    "q_u1": "SELECT os AS v FROM clicks UNION ALL SELECT lang FROM clicks",
    "q_u3": "SELECT page FROM clicks WHERE os = 'F' AND plugins = 1 INTERSECT SELECT page FROM clicks WHERE os = 'O' AND plugins = 2",
    "q_u4": "SELECT page_brand, plugins FROM clicks WHERE os = 'F' AND visit_no < 3 EXCEPT SELECT page_brand, plugins FROM clicks WHERE os = 'O' AND visit_no < 2",
    "q_u5": "SELECT lang FROM clicks WHERE os = 'F' INTERSECT ALL SELECT lang FROM clicks WHERE os = 'O'",
    "q_u6": "SELECT lang FROM clicks WHERE os = 'F' EXCEPT ALL SELECT lang FROM clicks WHERE plugins > 5",
    "q_u7": "SELECT DISTINCT geo_region, dom_region FROM clicks",
    # functions
    "q_f1": ("SELECT p, count(*) AS n, sum(CAST(h AS BIGINT)) AS h FROM (SELECT conv(substr(md5(concat('42|', l_orderkey, '|', l_linenumber)), 1, 8), 16, 10) AS h, pmod(-l_orderkey, 5) AS p FROM lineitem) GROUP BY p", "SELECT p, count(*) AS n, CAST(sum(h) AS BIGINT) AS h FROM (SELECT ('0x' || substr(md5('42|' || l_orderkey || '|' || l_linenumber), 1, 8))::BIGINT AS h, ((-l_orderkey) % 5 + 5) % 5 AS p FROM lineitem) GROUP BY p"),
    "q_f2": ("SELECT page_id, lower(url) AS l, split(url, '/')[2] AS host, regexp_extract(url, '://([^./]+)', 1) AS h1, substring_index(url, '/', 3) AS base, length(url) AS n, translate(url, ':/', '..') AS t FROM pages", "SELECT page_id, lower(url) AS l, string_split(url, '/')[3] AS host, regexp_extract(url, '://([^./]+)', 1) AS h1, array_to_string(string_split(url, '/')[1:3], '/') AS base, length(url) AS n, translate(url, ':/', '..') AS t FROM pages"),
    "q_f3": ("SELECT sum(weekday(l_shipdate) + 1) AS w, sum(quarter(l_shipdate)) AS q, sum(year(l_shipdate)) AS y, sum(month(l_shipdate)) AS m, sum(datediff(l_shipdate, DATE '1992-01-01')) AS dd FROM lineitem", "SELECT CAST(sum(isodow(l_shipdate)) AS BIGINT) AS w, CAST(sum(quarter(l_shipdate)) AS BIGINT) AS q, CAST(sum(year(l_shipdate)) AS BIGINT) AS y, CAST(sum(month(l_shipdate)) AS BIGINT) AS m, CAST(sum(date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE))) AS BIGINT) AS dd FROM lineitem"),
    "q_f4": "SELECT plugins, round(ln(plugins + 1), 9) AS a, round(log2(plugins + 1), 9) AS b, round(exp(plugins / 10.0), 6) AS c, round(sqrt(plugins), 9) AS d, greatest(plugins, 3) AS e, least(plugins, 3) AS f, abs(-plugins) AS g, bin(plugins) AS h FROM (SELECT DISTINCT plugins FROM clicks)",
    "q_f5": ("SELECT k, size(v) AS n, array_join(transform(v, x -> x * 2), ',') AS t, array_join(filter(v, x -> x % 2 = 0), ',') AS f, aggregate(v, 0L, (a, x) -> a + x) AS s, exists(v, x -> x > 15) AS e, forall(v, x -> x >= k) AS a, array_position(v, k + 1) AS p, array_join(slice(v, 2, 2), ',') AS sl FROM (SELECT DISTINCT l_suppkey AS k, sequence(l_suppkey, l_suppkey + 4) AS v FROM lineitem)", "SELECT k, CAST(len(v) AS INT) AS n, array_to_string([x * 2 for x in v], ',') AS t, array_to_string([x for x in v if x % 2 = 0], ',') AS f, CAST(list_sum(v) AS BIGINT) AS s, list_aggregate([x > 15 for x in v], 'bool_or') AS e, list_aggregate([x >= k for x in v], 'bool_and') AS a, CAST(list_position(v, k + 1) AS BIGINT) AS p, array_to_string(v[2:3], ',') AS sl FROM (SELECT DISTINCT l_suppkey AS k, range(l_suppkey, l_suppkey + 5) AS v FROM lineitem)"),
    "q_f6": ("SELECT k, m['a'] AS a, array_join(map_keys(m), ',') AS ks, size(map_filter(m, (x, y) -> y > 2)) AS big FROM (SELECT l_suppkey AS k, map_from_entries(array(named_struct('k', 'a', 'v', count(*)), named_struct('k', 'b', 'v', count_if(l_linenumber = 1)))) AS m FROM lineitem GROUP BY l_suppkey)", "SELECT k, m['a'] AS a, array_to_string(map_keys(m), ',') AS ks, CAST(len([y for y in map_values(m) if y > 2]) AS INT) AS big FROM (SELECT l_suppkey AS k, MAP {'a': count(*), 'b': count(*) FILTER (WHERE l_linenumber = 1)} AS m FROM lineitem GROUP BY l_suppkey)"),
    "q_f7": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k, from_json(props, 'k INT').k AS k2, parse_url('http://a.b/c?x=1', 'QUERY', 'x') AS x FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, CAST(json_extract_string(props, '$.k') AS INT) AS k2, '1' AS x FROM events"),
    "q_f8": ("SELECT s.os AS os, s.lang AS lang, count(*) AS n FROM (SELECT named_struct('os', os, 'lang', lang) AS s FROM clicks) GROUP BY s.os, s.lang", "SELECT os, lang, count(*) AS n FROM clicks GROUP BY os, lang"),
    "q_f9": "SELECT a, b, count(*) AS n FROM grams GROUP BY a, b HAVING count(*) >= 40",
}
#: as-of by a running last value: one sort, no inequality join
TEXTS["q_j12"] = ("SELECT event_id, d, version FROM (SELECT event_id, CAST(d AS STRING) AS d, CAST(last(tag, true) OVER (ORDER BY d, o, event_id ROWS UNBOUNDED PRECEDING) AS STRING) AS version FROM (SELECT event_id, d, CAST(NULL AS DATE) AS tag, 1 AS o FROM ev UNION ALL SELECT -1, d, d, 0 FROM versions)) WHERE event_id >= 0", "SELECT event_id, CAST(e.d AS VARCHAR) AS d, CAST(v.d AS VARCHAR) AS version FROM ev e ASOF LEFT JOIN versions v ON e.d >= v.d")
_EXTRA = {
    "items": ("SELECT concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, price_cents) AS row_id, explode(array(concat('os=', os), concat('lang=', lang), concat('engine=', engine))) AS item FROM clicks",
              "SELECT l_orderkey || '|' || l_linenumber || '|' || l_partkey || '|' || l_suppkey || '|' || price_cents AS row_id, unnest(['os=' || os, 'lang=' || lang, 'engine=' || engine]) AS item FROM clicks"),
    "versions": ("SELECT DISTINCT d FROM ev WHERE day(d) % 7 = 1", "SELECT DISTINCT d FROM ev WHERE day(d) % 7 = 1"),
}
_NEEDS = {"items": ["clicks"], "versions": ["ev"]}


def _used(text: str) -> list[str]:
    words = set(re.findall(r"[a-z_0-9]+", text))
    found = [n for n in (*tb.STREAM_SQL, *_EXTRA) if n in words]
    for e in [n for n in found if n in _EXTRA]:
        found = [*(x for x in _NEEDS[e] if x not in found), *found]
    return sorted(found, key=lambda n: n in _EXTRA)


def _run(text: str):
    def go(spark: SparkSession, d: str) -> DataFrame:
        used = _used(text)
        tb.views(spark, d, *[t for t in tb.TABLES if re.search(rf"\b{t}\b", text)], *[n for n in used if n in tb.STREAM_SQL])
        for n in used:
            if n in _EXTRA:
                spark.sql(_EXTRA[n][0]).createOrReplaceTempView(n)
        return spark.sql(text)

    return go


def _other(text: str) -> str:
    text = text.replace("LEFT SEMI JOIN", "SEMI JOIN").replace("LEFT ANTI JOIN", "ANTI JOIN")
    used = _used(text)
    parts = [f"{n} AS ({_EXTRA[n][1] if n in _EXTRA else tb.STREAM_SQL[n]})" for n in used]
    return (f"WITH {', '.join(parts)} " if parts else "") + text


def round_trips(spark: SparkSession, d: str, kind: str) -> DataFrame:
    """A model-like table written in a format and read again with its schema."""
    from .queries import _scratch

    made = tb.clicks(spark, d).groupBy("os", "page").agg(F.count("*").alias("n"))
    path = f"{_scratch(spark)}/trip-{kind}-{uuid.uuid4().hex}"
    out = made.write.mode("overwrite")
    (out.partitionBy("os") if kind == "parquet" else out).format(kind).save(path)
    return spark.read.schema("os string, page string, n bigint").format(kind).load(path).select("os", "page", "n")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out = {n: _run(t if isinstance(t, str) else t[0]) for n, t in TEXTS.items()}
    for kind in ("parquet", "json", "csv", "orc"):
        out["q_s3" if kind == "parquet" else f"q_s4_{kind}"] = lambda spark, d, kind=kind: round_trips(spark, d, kind)
    out["q_a7_approx"] = lambda spark, d: tb.clicks(spark, d).agg(F.approx_count_distinct("page").alias("pages"))
    out["q_a12_approx"] = lambda spark, d: tb.clicks(spark, d).groupBy("page", "browser").count().agg(F.percentile_approx("count", 0.9).alias("p90"))
    return out


def oracle_sql() -> dict[str, str]:
    out = {n: _other(t if isinstance(t, str) else t[1]) for n, t in TEXTS.items()}
    trip = f"WITH clicks AS ({tb.STREAM_SQL['clicks']}) SELECT os, page, count(*) AS n FROM clicks GROUP BY os, page"
    return out | {n: trip for n in ("q_s3", "q_s4_json", "q_s4_csv", "q_s4_orc")}
