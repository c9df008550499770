"""Tables and the item streams derived from them, as DataFrames and as the same SQL for the checking engine."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: Fixed values of the generated stream: feature sizes, class cut points.
SIZES = {"x1": 10500, "x2": 8500, "x3": 6400, "x4": 3500, "x5": 300}
CUTS = (0.80, 0.88, 0.93, 0.96, 0.98, 0.99)
SYNTH_ROWS = 168_000
SYNTH_SUBCUBES = (("x1", "x2", "x3"), ("x2", "x3", "x4"), ("x3", "x4", "x5"))
CLICK_COORDS = ("geo_region", "geo_nation", "dom_region", "dom_nation", "cust_mag", "page", "page_brand", "page_mag", "visit_no", "referrer",
                "campaign_mag", "keywords", "engine", "browser", "width_mag", "height_mag", "plugins", "lang", "os")
CLICK_SUBCUBES = {("dom_nation", "page_mag", "campaign_mag"): 0.009, ("cust_mag", "page_mag", "plugins"): 0.016,
                  ("cust_mag", "campaign_mag", "height_mag"): 0.036, ("geo_region", "campaign_mag", "plugins"): 0.0095}
SEARCH_COORDS = tuple(f"x{i}" for i in range(1, 11))
ROW_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "price_cents")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared(spark: SparkSession, prefix: str = "scratch-") -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, a temporary one if driver and
    executors are one machine, else an error."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", "")
    if found:
        return found.rstrip("/")
    if spark.sparkContext.master != "local" and not spark.sparkContext.master.startswith(("local[", "local*")):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return "file://" + tempfile.mkdtemp(prefix=prefix)


def settled(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder: plans that read it often don't carry the plan that made it."""
    path = f"{shared(df.sparkSession, 'tables-')}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def unit(*parts: Column | str) -> Column:
    """A number in [0, 1) from the md5 of the parts joined by `|`, the same in any engine."""
    text = F.concat_ws("|", *[p if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint") / F.lit(4294967296.0)


def bits(x: Column) -> Column:
    """Number of binary digits of a whole number."""
    return F.length(F.bin(x.cast("bigint")))


def synth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class z and features x1..x5, independent given z by construction, from the order keys."""
    k = table(spark, sf_dir, "orders").select(F.explode(F.sequence(F.col("o_orderkey") * 12, F.col("o_orderkey") * 12 + 11)).alias("k")).where(F.col("k") < SYNTH_ROWS)
    text = F.col("k").cast("string")
    u = k.select("k", unit("42", text, "z").alias("uz"), *(unit("42", text, c).alias(f"u{c}") for c in SIZES))
    z = sum((F.when(F.col("uz") >= c, 1).otherwise(0) for c in CUTS), F.lit(0))
    u = u.withColumn("z", z.cast("int"))

    def feature(c: str, n: int) -> Column:
        v, low, high = F.col(f"u{c}"), F.col(f"u{c}") / 0.65, (F.col(f"u{c}") - 0.65) / 0.35
        a = F.when(v < 0.65, F.floor(6 * (low * low))).otherwise(6 + F.floor((n - 6) * (high * high)))
        return F.pmod(a + F.col("z") * (n // 9), F.lit(n)).cast("bigint").alias(c)

    return u.select("k", "z", *(feature(c, n) for c, n in SIZES.items()))


_UNIT = "('0x' || substr(md5('42|' || k || '|{c}'), 1, 8))::BIGINT / 4294967296.0"


def _synth_sql() -> str:
    us = ", ".join(f"{_UNIT.format(c=c)} AS u{c}" for c in ("z", *SIZES))
    z = " + ".join(f"(uz >= {c})::INT" for c in CUTS)
    xs = ", ".join(f"CAST((CASE WHEN u{c} < 0.65 THEN floor(6 * ((u{c} / 0.65) * (u{c} / 0.65))) ELSE 6 + floor({n - 6} * (((u{c} - 0.65) / 0.35) * ((u{c} - 0.65) / 0.35))) END + z * {n // 9}) % {n} AS BIGINT) AS {c}" for c, n in SIZES.items())
    return f"SELECT k, z, {xs} FROM (SELECT *, {z} AS z FROM (SELECT k, {us} FROM (SELECT o_orderkey * 12 + r AS k FROM orders, range(12) t(r)) WHERE k < {SYNTH_ROWS}))"


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its order, customer, part, supplier and both nations and regions. Dimensions are left to the
    optimizer, which broadcasts those under its threshold; lineitem and orders meet by key."""
    t = {n: table(spark, sf_dir, n) for n in ("lineitem", "orders", "customer", "part", "supplier", "nation", "region")}
    place = t["nation"].join(t["region"], F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    ours, theirs = (place.select(*(F.col(c).alias(p + c) for c in place.columns)) for p in ("c", "s"))
    return (t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
            .join(t["part"], F.col("l_partkey") == F.col("p_partkey")).join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
            .join(ours, F.col("c_nationkey") == F.col("cn_nationkey")).join(theirs, F.col("s_nationkey") == F.col("sn_nationkey")))


_WIDE_SQL = """SELECT l.*, o.*, c.*, p.*, s.*, cn.n_name AS cn_name, cr.r_name AS cr_name, sn.n_name AS sn_name, sr.r_name AS sr_name
FROM lineitem l JOIN orders o ON l_orderkey = o_orderkey JOIN customer c ON o_custkey = c_custkey JOIN part p ON l_partkey = p_partkey
JOIN supplier s ON l_suppkey = s_suppkey JOIN nation cn ON c_nationkey = cn.n_nationkey JOIN region cr ON cn.n_regionkey = cr.r_regionkey
JOIN nation sn ON s_nationkey = sn.n_nationkey JOIN region sr ON sn.n_regionkey = sr.r_regionkey"""


def cents() -> Column:
    return F.round(F.col("l_extendedprice") * 100).cast("bigint")


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nineteen coordinates of four groups (geography, page, search, external) over the star join, with its row key."""
    c = F.col
    made = {"geo_region": c("cr_name"), "geo_nation": c("cn_name"), "dom_region": c("sr_name"), "dom_nation": c("sn_name"), "cust_mag": bits(c("o_custkey")),
            "page": c("p_name"), "page_brand": c("p_brand"), "page_mag": bits(c("l_partkey")), "visit_no": c("l_linenumber"), "referrer": c("o_orderpriority"),
            "campaign_mag": bits(c("l_orderkey")), "keywords": c("p_type"), "engine": c("o_orderstatus"), "browser": c("c_mktsegment"),
            "width_mag": bits(F.floor("l_quantity")), "height_mag": bits(F.floor("l_extendedprice")), "plugins": F.round(c("l_discount") * 100).cast("int"),
            "lang": c("l_returnflag"), "os": c("l_linestatus")}
    return wide(spark, sf_dir).select(*(c(k) for k in ROW_KEY[:4]), cents().alias("price_cents"), *(v.alias(k) for k, v in made.items()))


_BIN = "length(bin(CAST({x} AS BIGINT)))"


def _clicks_sql() -> str:
    b = lambda x: _BIN.format(x=x)
    return f"""SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT) AS price_cents,
cr_name AS geo_region, cn_name AS geo_nation, sr_name AS dom_region, sn_name AS dom_nation, {b('o_custkey')} AS cust_mag, p_name AS page, p_brand AS page_brand,
{b('l_partkey')} AS page_mag, l_linenumber AS visit_no, o_orderpriority AS referrer, {b('l_orderkey')} AS campaign_mag, p_type AS keywords, o_orderstatus AS engine,
c_mktsegment AS browser, {b('floor(l_quantity)')} AS width_mag, {b('floor(l_extendedprice)')} AS height_mag, CAST(round(l_discount * 100) AS INT) AS plugins,
l_returnflag AS lang, l_linestatus AS os FROM ({_WIDE_SQL})"""


def websearch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten low-cardinality slots per row for the ten most frequent brands, class the ISO weekday of shipping."""
    t = {n: table(spark, sf_dir, n) for n in ("lineitem", "orders", "part")}
    rows = t["lineitem"].join(t["orders"].select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(t["part"].select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    top = rows.groupBy(F.col("p_brand").alias("top_brand")).count().orderBy(F.desc("count"), "top_brand").limit(10).select("top_brand")
    c = F.col
    slots = [bits(F.floor("l_extendedprice")), bits(F.floor("l_quantity")), bits(c("l_suppkey")), bits(c("o_custkey")), bits(c("l_orderkey")), bits(F.round(c("l_discount") * 100)),
             bits(F.round(c("l_tax") * 100)), bits(c("l_linenumber")), c("l_linestatus"), bits(c("l_partkey"))]
    return rows.join(F.broadcast(top), F.col("p_brand") == F.col("top_brand"), "left_semi").select(
        *(c(k) for k in ROW_KEY[:4]), cents().alias("price_cents"), c("p_brand").alias("subset"), (F.weekday("l_shipdate") + 1).alias("day"),
        *(s.cast("string").alias(n) for s, n in zip(slots, SEARCH_COORDS, strict=True)))


def _websearch_sql() -> str:
    b = lambda x: _BIN.format(x=x)
    slots = [b("floor(l_extendedprice)"), b("floor(l_quantity)"), b("l_suppkey"), b("o_custkey"), b("l_orderkey"), b("round(l_discount * 100)"), b("round(l_tax * 100)"), b("l_linenumber"), "l_linestatus", b("l_partkey")]
    rows = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey"
    return f"""SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT) AS price_cents, p_brand AS subset, isodow(l_shipdate) AS day,
{", ".join(f"CAST({s} AS VARCHAR) AS {n}" for s, n in zip(slots, SEARCH_COORDS, strict=True))} {rows}
WHERE p_brand IN (SELECT p_brand {rows} GROUP BY p_brand ORDER BY count(*) DESC, p_brand LIMIT 10)"""


def _words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", "lang", F.split(F.trim(F.lower("text")), r"\s+").alias("w"))


def grams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(lang, a, b, c): each run of three words; (a, b) are the bigrams."""
    at = F.explode(F.expr("sequence(0, size(w) - 3)"))
    got = _words(spark, sf_dir).where(F.size("w") >= 3).select("lang", "w", at.alias("i"))
    return got.select("lang", *(F.expr(f"w[i + {n}]").alias(c) for n, c in enumerate("abc")))


_WORDS_SQL = "SELECT doc_id, lang, regexp_split_to_array(trim(lower(text)), '\\s+') AS w FROM documents"
_GRAMS_SQL = f"SELECT lang, w[i] AS a, w[i + 1] AS b, w[i + 2] AS c FROM (SELECT lang, w, unnest(range(1, len(w) - 1)) AS i FROM ({_WORDS_SQL}) WHERE len(w) >= 3)"


def first_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _words(spark, sf_dir).where(F.size("w") >= 10).select("doc_id", "lang", *(F.expr(f"w[{i}]").alias(f"x{i + 1}") for i in range(10)))


_FIRST_SQL = f"SELECT doc_id, lang, {', '.join(f'w[{i}] AS x{i}' for i in range(1, 11))} FROM ({_WORDS_SQL}) WHERE len(w) >= 10"


def ev(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as coordinates: day, hour, type, user, the number in the properties, and the value's floor."""
    return table(spark, sf_dir, "events").select("event_id", F.to_date("ts").alias("d"), F.hour("ts").alias("hr"), "event_type", "user_id",
                                                  F.get_json_object("props", "$.k").cast("int").alias("k"), F.floor("value").alias("vb"))


_EV_SQL = "SELECT event_id, CAST(ts AS DATE) AS d, CAST(hour(ts) AS INT) AS hr, event_type, user_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, CAST(floor(value) AS BIGINT) AS vb FROM events"


def url_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = F.col("url")
    return table(spark, sf_dir, "pages").select(
        "page_id", F.regexp_extract(u, r"^([a-z]+)://", 1).alias("scheme"), F.regexp_extract(u, r"://([^./]+)\.", 1).alias("host1"), F.regexp_extract(u, r"\.([a-z]+)/", 1).alias("tld"),
        F.regexp_extract(u, r"://[^/]+/([a-z]+)/", 1).alias("lang"), F.regexp_extract(u, r"\?([a-z_]+)=", 1).alias("query_key"), F.regexp_extract(u, r"#(.*)$", 1).alias("anchor"))


_URL_SQL = r"""SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://([^./]+)\.', 1) AS host1, regexp_extract(url, '\.([a-z]+)/', 1) AS tld,
regexp_extract(url, '://[^/]+/([a-z]+)/', 1) AS lang, regexp_extract(url, '\?([a-z_]+)=', 1) AS query_key, regexp_extract(url, '#(.*)$', 1) AS anchor FROM pages"""
FLAGS = ("f_return", "f_final", "f_discount", "f_tax", "f_quantity", "f_early")


def flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six boolean coordinates of lineitem with the row key."""
    c = F.col
    made = (c("l_returnflag") == "R", c("l_linestatus") == "F", c("l_discount") >= 0.05, c("l_tax") >= 0.04, c("l_quantity") >= 25, c("l_linenumber") <= 3)
    return table(spark, sf_dir, "lineitem").select(*(c(k) for k in ROW_KEY[:4]), cents().alias("price_cents"), *(x.alias(n) for x, n in zip(made, FLAGS, strict=True)))


_FLAGS_SQL = """SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT) AS price_cents, l_returnflag = 'R' AS f_return, l_linestatus = 'F' AS f_final,
l_discount >= 0.05 AS f_discount, l_tax >= 0.04 AS f_tax, l_quantity >= 25 AS f_quantity, l_linenumber <= 3 AS f_early FROM lineitem"""

STREAMS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (synth, wide, clicks, websearch, grams, first_words, ev, url_parts, flags)}
STREAM_SQL = {"synth": _synth_sql(), "wide": _WIDE_SQL, "clicks": _clicks_sql(), "websearch": _websearch_sql(), "grams": _GRAMS_SQL, "first_words": _FIRST_SQL, "ev": _EV_SQL, "url_parts": _URL_SQL, "flags": _FLAGS_SQL}


def with_sql(*names: str) -> str:
    """The leading WITH of SQL that uses these streams."""
    return "WITH " + ", ".join(f"{n} AS ({STREAM_SQL[n]})" for n in names)


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Register tables and streams as temporary views for SQL text."""
    for n in names:
        (STREAMS[n](spark, sf_dir) if n in STREAMS else table(spark, sf_dir, n)).createOrReplaceTempView(n)
