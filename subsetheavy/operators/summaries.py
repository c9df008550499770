"""Small summaries of single coordinates: counters, sketches, and the first pass that finds candidate values."""

from __future__ import annotations

import math
import re
from collections.abc import Iterable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spec import long_form, text

COUNTERS = "coord string, value string, counter bigint"


def _lowered(counts: pd.Series, capacity: int) -> pd.Series:
    """At most capacity counters: the next largest count is taken off all, and what falls to zero goes."""
    if len(counts) <= capacity:
        return counts
    cut = np.partition(counts.to_numpy(), len(counts) - capacity - 1)[len(counts) - capacity - 1]
    return (counts - cut)[counts > cut]


def misra_gries(df: DataFrame, coords: Iterable[str], capacity: int, merged: bool = True, rows: bool = False) -> DataFrame:
    """(coord, value, counter), at most capacity counters for each coordinate; a counter is too low by at most
    rows / (capacity + 1), and a value with more rows than that has one. Each task keeps capacity counters a coordinate
    whatever it reads; tasks' counters merge in levels, so no task gets more than a fan of them. rows: also the number of
    rows, under the coordinate ROWS."""
    parts = _counted(df, list(coords), capacity, None, rows)
    return mg_merge(parts, capacity, exact=(ROWS,) if rows else ()) if merged else parts


#: In the place of a coordinate: the number of rows, and the rows of each class.
ROWS, CLASSES = "␀rows", "␀class"


def _counted(df: DataFrame, coords: list[str], capacity: int, cls: str | None, rows: bool = False) -> DataFrame:
    """Each task's counters; with rows also its number of rows, and with cls those of each class."""

    def work(frames):
        held, seen, classes = {c: pd.Series(dtype="int64") for c in coords}, 0, pd.Series(dtype="int64")
        for frame in frames:
            seen += len(frame)
            for c in coords:
                held[c] = _lowered(held[c].add(frame[c].value_counts(), fill_value=0).astype("int64"), capacity)
            if cls:
                classes = classes.add(frame["__z"].value_counts(), fill_value=0).astype("int64")
        for c, s in (held | ({CLASSES: classes} if cls else {})).items():
            yield pd.DataFrame({"coord": c, "value": s.index.astype(str), "counter": s.to_numpy()})
        if rows:
            yield pd.DataFrame({"coord": [ROWS], "value": [""], "counter": [seen]})

    return df.select(*(text(c).alias(c) for c in coords), *([text(cls).alias("__z")] if cls else [])).mapInPandas(work, COUNTERS)


def first_scan(df: DataFrame, coords: Iterable[str], capacity: int, cls: str | None = None) -> tuple[DataFrame, int, dict[str, int]]:
    """What a first pass needs, from one scan: counters of all coordinates, the number of rows, and the rows of each
    class. Classes are few by assumption."""
    got = mg_merge(_counted(df, list(coords), capacity, cls, rows=True), capacity, exact=(ROWS, CLASSES)).persist()
    exact = got.where(F.col("coord").isin(ROWS, CLASSES)).collect()
    counters = got.where(~F.col("coord").isin(ROWS, CLASSES))
    return counters, sum(r["counter"] for r in exact if r["coord"] == ROWS), {r["value"]: r["counter"] for r in exact if r["coord"] == CLASSES}


#: Rows that are counted between two lowerings where several counters fill from one scan.
CHUNK = 1 << 17


def counters_by(df: DataFrame, coords: Iterable[str], by: str, capacities: dict[str, set[int]]) -> DataFrame:
    """(grp, capacity, coord, value, counter): the counters of misra_gries for each group of by at each of its capacities,
    all from one scan. A task keeps the counters of all, and the values of CHUNK rows."""
    coords = list(coords)
    ids = [(g, n, c) for g, each in capacities.items() for n in sorted(each) for c in coords]
    room = {str(i): n for i, (_, n, _) in enumerate(ids)}
    at: dict[tuple[str, str], list[str]] = {}
    for i, (g, _, c) in enumerate(ids):
        at.setdefault((g, c), []).append(str(i))

    def work(batches):
        held = {i: pd.Series(dtype="int64") for i in room}

        def take(chunk):
            rows = pa.Table.from_batches(chunk)
            for c in coords:
                got = rows.select(["__g", c]).group_by(["__g", c]).aggregate([([], "count_all")]).to_pandas()
                for g, own in got.groupby("__g"):
                    counts = pd.Series(own["count_all"].to_numpy(), index=own[c].to_numpy())
                    for i in at.get((g, c), ()):
                        held[i] = _lowered(held[i].add(counts, fill_value=0).astype("int64"), room[i])

        chunk, n = [], 0
        for batch in batches:
            chunk.append(batch)
            n += batch.num_rows
            if n >= CHUNK:
                take(chunk)
                chunk, n = [], 0
        if chunk:
            take(chunk)
        for i, s in held.items():
            if len(s):
                yield pa.RecordBatch.from_pydict({"coord": [i] * len(s), "value": [str(v) for v in s.index], "counter": s.to_numpy()})

    parts = df.select(F.col(by).alias("__g"), *(text(c).alias(c) for c in coords)).mapInArrow(work, COUNTERS)
    names = df.sparkSession.createDataFrame([(str(i), *of) for i, of in enumerate(ids)], "i string, grp string, capacity bigint, c string")
    return mg_merge(parts, room).join(F.broadcast(names), F.col("coord") == F.col("i")).select("grp", "capacity", F.col("c").alias("coord"), "value", "counter")


def _levels(df: DataFrame, fan: int) -> int:
    """Levels in which so many tasks' counters merge by fans; the number of tasks is taken from the size of the scan."""
    spark = df.sparkSession
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    each = int(re.sub(r"\D", "", spark.conf.get("spark.sql.files.maxPartitionBytes", "134217728").split("b")[0]) or 1 << 27)
    tasks = max(size / max(each, 1 << 20), float(spark.sparkContext.defaultParallelism), 1.0)
    return max(2, min(4, math.ceil(math.log(tasks, fan))))


def mg_merge(parts: DataFrame, capacity: int | dict[str, int], fan: int = 64, exact: tuple[str, ...] = ()) -> DataFrame:
    """Merge counters of several parts of a stream, a fan of them in a group and level by level; any order and grouping
    keeps the bound. capacity: of all coordinates, or of each. exact: coordinates whose counters are not lowered."""

    def work(frame: pd.DataFrame) -> pd.DataFrame:
        coord = frame["coord"].iloc[0] if len(frame) else ""
        s = frame.groupby("value")["counter"].sum()
        s = s if coord in exact or not len(frame) else _lowered(s, capacity[coord] if isinstance(capacity, dict) else capacity)
        return pd.DataFrame({"coord": coord, "value": s.index.astype(str), "counter": s.to_numpy(), "part": int(frame["part"].iloc[0]) if len(frame) else 0})

    have = parts.withColumn("part", F.spark_partition_id().cast("bigint"))
    for _ in range(_levels(parts, fan) - 1):
        have = have.withColumn("part", F.floor(F.col("part") / fan)).groupBy("coord", "part").applyInPandas(work, COUNTERS + ", part bigint")
    return have.groupBy("coord").applyInPandas(work, COUNTERS + ", part bigint").drop("part")


def frequent_items(df: DataFrame, coords: Iterable[str], support: float) -> DataFrame:
    """(coord, value) by the engine's own frequent-item counters, all coordinates in one job."""
    coords = list(coords)
    if support < 1e-4:
        raise ValueError("the built-in needs a support of 1e-4 at least; use misra_gries")
    got = df.select(*(text(c).alias(c) for c in coords)).stat.freqItems(coords, support)
    return got.select(F.explode(F.array(*(F.struct(F.lit(c).alias("coord"), F.col(f"{c}_freqItems").alias("vs")) for c in coords))).alias("e")).select("e.coord", F.explode("e.vs").alias("value"))


def cell(coord: Column, value: Column, row: Column, width: int, seed: int | str = 0, hash: str = "xxhash64") -> Column:
    """The bucket of a value in a row of the sketch."""
    if hash == "md5":
        h = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), row.cast("string"), coord, value)), 1, 8), 16, 10).cast("bigint")
    else:
        h = F.xxhash64(F.lit(str(seed)), row, coord, value)
    return F.pmod(h, F.lit(width)).cast("int")


def count_min(df: DataFrame, coords: Iterable[str], width: int, depth: int = 5, seed: int | str = 0, hash: str = "xxhash64") -> DataFrame:
    """(coord, depth_row, bucket, cnt): one sketch for each coordinate; cells of parts add up. Rows are spread over the
    sketch before the one aggregate, whose state in a task is the cells, so values are never counted one by one."""
    spread = long_form(df, coords).select("coord", "value", F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("depth_row"))
    return spread.select("coord", "depth_row", cell(F.col("coord"), F.col("value"), F.col("depth_row"), width, seed, hash).alias("bucket")).groupBy("coord", "depth_row", "bucket").agg(F.count("*").alias("cnt"))


def count_min_estimate(cells: DataFrame, probes: DataFrame, width: int, depth: int = 5, seed: int | str = 0, hash: str = "xxhash64") -> DataFrame:
    """probes: (coord, value). Adds estimate, the least of its cells, never below the true count."""
    probes = probes.select("coord", "value").distinct()
    at = probes.select("coord", "value", F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("depth_row")).withColumn("bucket", cell(F.col("coord"), F.col("value"), F.col("depth_row"), width, seed, hash))
    return at.join(cells, ["coord", "depth_row", "bucket"], "left").groupBy("coord", "value").agg(F.min(F.coalesce("cnt", F.lit(0))).alias("estimate"))


def built_in_sketch(df: DataFrame, column: str, eps: float, confidence: float, seed: int = 7) -> DataFrame:
    """The engine's own sketch as one binary."""
    return df.agg(F.count_min_sketch(text(column), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))


def built_in_estimates(df: DataFrame, column: str, values: Iterable[str], eps: float, confidence: float, seed: int = 7) -> DataFrame:
    """(value, estimate) of a few asked values by the engine's own sketch, which the driver reads."""
    spark = df.sparkSession
    made = built_in_sketch(df, column, eps, confidence, seed).first()["sketch"]
    sketch = spark._jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(bytearray(made))
    return spark.createDataFrame([(v, sketch.estimateCount(v)) for v in values], "value string, estimate bigint")


def candidates_of(counters: DataFrame, lam: float, m: int, capacity: int) -> tuple[DataFrame, float]:
    """(candidates, the share above which none is missing) from merged counters of that capacity."""
    if capacity >= 4 / lam:
        return counters.where(F.col("counter") >= lam / 4 * m).select("coord", "value"), lam / 2
    return counters.select("coord", "value"), 1 / (capacity + 1)


def first_pass(df: DataFrame, coords: Iterable[str], lam: float, m: int, summary: str = "counters", capacity: int | None = None) -> tuple[DataFrame, float]:
    """(candidates (coord, value), the share above which none is missing). Values of share >= lam / 2 are candidates and
    those under lam / 4 are not; with a capacity too small for that gap every stored value is one."""
    coords = list(coords)
    if summary == "exact":
        counts = long_form(df, coords).groupBy("coord", "value").agg(F.count("*").alias("n"))
        return counts.where(F.col("n") >= lam / 2 * m).select("coord", "value"), 0.0
    if summary == "freq_items":
        return frequent_items(df, coords, lam / 4), lam / 4
    if summary == "count_min":
        width, depth = math.ceil(math.e / (lam / 4)), 5
        cells = count_min(df, coords, width, depth)
        pool = misra_gries(df, coords, math.ceil(4 / lam)).select("coord", "value")
        return count_min_estimate(cells, pool, width, depth).where(F.col("estimate") >= lam / 2 * m).select("coord", "value"), lam / 2
    if summary != "counters":
        raise ValueError(f"no such summary: {summary}")
    c = math.ceil(4 / lam) if capacity is None else capacity
    return candidates_of(misra_gries(df, coords, c), lam, m, c)
