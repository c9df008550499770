"""The one-pass structures over Structured Streaming, finished with what is available.

Events come from files with a fixed schema. Timestamps without a zone are cast before a watermark, which they can't
carry. State is bounded: windowed counts by the watermark, the sample and the counters by their size. Samples and counters are
kept as a table for each batch, under the batch's number: a batch that comes again finds its table and changes nothing,
and a run that starts again from its checkpoint goes on from the last table."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sampling import priority
from ..operators.summaries import COUNTERS, ROWS, cell, mg_merge, misra_gries
from ..sources.tables import shared, table
from ..spec import decoded, long_form

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def _folder(spark: SparkSession, name: str) -> str:
    return f"{shared(spark, 'streams-')}/{name}-{uuid.uuid4().hex}"


def event_files(spark: SparkSession, sf_dir: str, late: bool = False) -> str:
    """Events written as one folder of files a day. late: one early day comes last."""
    at = _folder(spark, "events")
    src = table(spark, sf_dir, "events")
    src = src.select(*(F.col(c.split()[0]).cast(c.split()[1]) for c in EVENTS.split(", "))).withColumn("day", F.dayofmonth("ts"))
    days = src.where("day <> 3") if late else src
    days.repartition("day").sortWithinPartitions("ts").drop("day").write.parquet(at)
    if late:
        src.where("day = 3").drop("day").coalesce(1).write.mode("append").parquet(at)
    return at


def events(spark: SparkSession, path: str, files: int = 10) -> DataFrame:
    got = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path)
    return got.withColumn("ts", F.col("ts").cast("timestamp"))


def finish(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None, mark: str | None = None) -> DataFrame | None:
    """Run over what is available. Without each, rows go to files (append) or to the last batch's table (complete).
    mark: the checkpoint, given to go on from it."""
    spark = stream.sparkSession
    out, mark = _folder(spark, "out"), mark or _folder(spark, "mark")
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", mark)
    if each is None and mode == "append":
        writer.format("parquet").option("path", out).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    if each is None:

        def each(batch: DataFrame, n: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/{n:06d}")
            last[0] = n

        last = [None]
        writer.foreachBatch(each).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{out}/{last[0]:06d}") if last[0] is not None else spark.createDataFrame([], stream.schema)
    writer.foreachBatch(each).start().awaitTermination()
    return None


def tumbling_counts(ev: DataFrame, delay: str = "1 day") -> DataFrame:
    w = F.window("ts", "1 day")
    return ev.withWatermark("ts", delay).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding_heavy(ev: DataFrame, part: float, delay: str = "1 day") -> DataFrame:
    """Joint values of (user, type) that come in at least so many of each two-day window's rows, by its class counts."""
    w = F.window("ts", "2 days", "1 day")
    return ev.withWatermark("ts", delay).groupBy(w, "event_type", F.pmod("user_id", F.lit(10)).alias("band")).agg(F.count("*").alias("n")).where(F.col("n") >= part).select(F.col("window.start").alias("start"), "event_type", "band", "n")


def sessions(ev: DataFrame, gap: str = "12 hours", delay: str = "1 day") -> DataFrame:
    return ev.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def deduplicated(ev: DataFrame, delay: str = "40 days") -> DataFrame:
    return ev.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def _whole(spark: SparkSession, root: str) -> dict[int, str]:
    """The batches whose tables are whole, by number."""
    at = spark._jvm.org.apache.hadoop.fs.Path(root)
    fs = at.getFileSystem(spark._jsc.hadoopConfiguration())
    found = fs.listStatus(at) if fs.exists(at) else []
    names = [s.getPath().getName() for s in found]
    return {int(n): f"{root}/{n}" for n in names if n.isdigit() and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{root}/{n}/_SUCCESS"))}


def kept_state(stream: DataFrame, root: str, kind: str, add: Callable[[DataFrame], DataFrame], merge: Callable[[DataFrame, DataFrame], DataFrame], mark: str | None = None) -> DataFrame:
    """The state after all batches: a table for each batch under root, made of the batch (add) and the table before
    (merge). Older tables than the last two go."""
    spark = stream.sparkSession
    mark = mark or f"{root}/mark"

    def each(batch: DataFrame, n: int) -> None:
        have = _whole(spark, root)
        if n in have:
            return
        before = max((k for k in have if k < n), default=None)
        own = add(batch)
        if before is not None:
            own = merge(own, spark.read.schema(kind).parquet(have[before]))
        own.write.mode("overwrite").parquet(f"{root}/{n:09d}")
        for k in sorted(have)[:-1]:
            old = spark._jvm.org.apache.hadoop.fs.Path(have[k])
            old.getFileSystem(spark._jsc.hadoopConfiguration()).delete(old, True)

    finish(stream, each=each, mark=mark)
    have = _whole(spark, root)
    return spark.read.schema(kind).parquet(have[max(have)]) if have else spark.createDataFrame([], kind)


def stream_sample(ev: DataFrame, size: int, seed: int = 7, root: str | None = None) -> DataFrame:
    """The uniform sample of all rows seen, the batches' least rows merged: exact, safe to replay and to start again."""
    least = lambda df: df.orderBy("priority", "event_id").limit(size)
    own = lambda batch: least(batch.select("event_id", priority(["event_id"], seed, "md5").alias("priority")))
    return kept_state(ev, root or _folder(ev.sparkSession, "sample"), "event_id bigint, priority bigint", own, lambda a, b: least(a.unionByName(b).dropDuplicates(["event_id"])))


def stream_counters(ev: DataFrame, coords: list[str], capacity: int, root: str | None = None, rows: bool = False) -> DataFrame:
    """Deterministic counters of each coordinate over all rows seen; a batch counts once, however often it comes. rows:
    also the number of rows, under the coordinate ROWS."""
    if not rows:
        return kept_state(ev, root or _folder(ev.sparkSession, "counters"), COUNTERS, lambda batch: misra_gries(batch, coords, capacity), lambda a, b: mg_merge(a.unionByName(b), capacity))
    merged = lambda parts: mg_merge(parts, capacity, exact=(ROWS,))
    return kept_state(ev, root or _folder(ev.sparkSession, "counters"), COUNTERS, lambda batch: merged(misra_gries(batch, coords, capacity, merged=False, rows=True)), lambda a, b: merged(a.unionByName(b)))


def updated_counts(ev: DataFrame) -> DataFrame:
    """Counts by type in update mode: each batch gives the rows that changed, of which the last stands."""
    spark, out = ev.sparkSession, _folder(ev.sparkSession, "updates")
    stream = ev.groupBy("event_type").agg(F.count("*").alias("n"))
    finish(stream, "update", lambda batch, n: batch.withColumn("at", F.lit(n).cast("bigint")).write.mode("overwrite").parquet(f"{out}/{n:09d}"))
    got = spark.read.schema("event_type string, n bigint, at bigint").option("recursiveFileLookup", "true").parquet(out)
    return got.groupBy("event_type").agg(F.max_by("n", "at").alias("n"))


def in_memory(ev: DataFrame) -> DataFrame:
    """Counts by type, complete mode, in the memory sink: for small results that the driver shows."""
    name = f"counts_{uuid.uuid4().hex}"
    stream = ev.groupBy("event_type").agg(F.count("*").alias("n"))
    stream.writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).option("checkpointLocation", _folder(ev.sparkSession, "mark")).start().awaitTermination()
    return ev.sparkSession.table(name)


def stream_cells(ev: DataFrame, coords: list[str], width: int, depth: int = 5, seed: int = 9) -> DataFrame:
    """A sketch that grows with the stream: its cells are plain additive state."""
    rows = long_form(ev, coords).select("coord", "value", F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("depth_row"))
    return rows.select("coord", "depth_row", cell(F.col("coord"), F.col("value"), F.col("depth_row"), width, seed, "md5").alias("bucket")).groupBy("coord", "depth_row", "bucket").agg(F.count("*").alias("cnt"))


def scored(ev: DataFrame, shares: DataFrame) -> DataFrame:
    """Each event with the model's share of its type: a stream joined with a small fitted table."""
    return ev.join(F.broadcast(shares.where("coord = 'event_type'").select(F.col("value").alias("__v"), "share")), F.col("event_type") == F.col("__v"), "left").select("event_id", "event_type", "share")


def followed(ev: DataFrame, first: str, then: str, within: str = "1 hour") -> DataFrame:
    """Pairs of events of one user where `then` comes within a time after `first`."""
    a = ev.where(F.col("event_type") == first).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta")).withWatermark("ta", "1 day")
    b = ev.where(F.col("event_type") == then).select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb")).withWatermark("tb", "1 day")
    return a.join(b, F.expr(f"u = v AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("a", "b")


#: Counters of a coordinate that a first run over a stream keeps at most.
MOST = 200_000


def _candidates(spark: SparkSession, path: str, coords: list[str], capacity: int, least: int) -> DataFrame | None:
    """(c0, v0): values among which is every one with so many rows. None if that takes more than MOST counters."""
    held = stream_counters(events(spark, path), coords, capacity, rows=True)
    sums = {r["coord"]: r["n"] for r in held.groupBy("coord").agg(F.sum("counter").alias("n")).collect()}
    rows = sums.pop(ROWS, 0)
    # each time one is lowered, at least capacity + 1 are, by as much
    if max((rows - sums.get(c, 0)) // (capacity + 1) for c in coords) < least:
        return held.where(F.col("coord") != ROWS).select(F.col("coord").alias("c0"), F.col("value").alias("v0"))
    need = rows // least
    return _candidates(spark, path, coords, need, least) if need <= MOST else None


def two_passes(spark: SparkSession, path: str, coords: list[str], capacity: int, least: int) -> DataFrame:
    """All values with at least so many rows, (coord, value, cnt): candidates from one run over the stream, exact counts
    of them from a bounded replay. Where the counters may have lost such a value, the first run is done again with as many
    as the rows ask for; where these are too many, the replay counts every value."""
    held = _candidates(spark, path, coords, capacity, least)
    again = long_form(events(spark, path), coords)
    if held is not None:
        again = again.join(F.broadcast(held), (F.col("coord") == F.col("c0")) & (F.col("value") == F.col("v0")))
    counted = finish(again.groupBy("coord", "value").agg(F.count("*").alias("cnt")), "complete")
    return counted.where(F.col("cnt") >= least).select("coord", decoded(F.col("value"), "string").alias("value"), "cnt")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    def run(f, mode="complete", late=False):
        return lambda spark, d: finish(f(events(spark, event_files(spark, d, late))), mode)

    shares = lambda spark, d: long_form(table(spark, d, "events"), ["event_type"]).groupBy("coord", "value").agg(F.count("*").alias("n")).withColumn("share", F.col("n") / float(table(spark, d, "events").count()))
    types = ("event_type", "user_id")
    return {
        "q_r1": lambda spark, d: run(tumbling_counts)(spark, d).select(F.date_format("start", "yyyy-MM-dd").alias("start"), "event_type", "n"),
        "q_r2": lambda spark, d: run(lambda e: sliding_heavy(e, 15))(spark, d).select(F.date_format("start", "yyyy-MM-dd").alias("start"), "event_type", "band", "n"),
        "q_r3": run(sessions, "append"),
        "q_r4": run(lambda e: tumbling_counts(e, "1 hour"), "append", late=True),
        "q_r5": lambda spark, d: run(deduplicated, "append")(spark, d).select("event_id"),
        "q_r6": lambda spark, d: stream_sample(events(spark, event_files(spark, d)), 500),
        "q_r7": lambda spark, d: stream_counters(events(spark, event_files(spark, d)), list(types), 50),
        "q_r8": run(lambda e: stream_cells(e, ["event_type"], 50)),
        "q_r9": lambda spark, d: finish(scored(events(spark, event_files(spark, d)), shares(spark, d))),
        "q_r10": run(lambda e: followed(e, "view", "purchase"), "append"),
        "q_s7": lambda spark, d: finish(events(spark, event_files(spark, d), 3)).select("event_id", "event_type"),
        "q_s8_memory": lambda spark, d: in_memory(events(spark, event_files(spark, d))),
        "q_r11_update": lambda spark, d: updated_counts(events(spark, event_files(spark, d), 3)),
        "q_r12": lambda spark, d: two_passes(spark, event_files(spark, d), list(types), 200, 100),
    }


def oracle_sql() -> dict[str, str]:
    u = "SELECT '{c}' AS coord, CAST({c} AS VARCHAR) AS value, count(*) AS cnt FROM events GROUP BY {c}"
    return {
        "q_r1": "SELECT strftime(ts, '%Y-%m-%d') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "q_r2": "SELECT strftime(s, '%Y-%m-%d') AS start, event_type, CAST(user_id % 10 AS BIGINT) AS band, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS s, event_type, user_id FROM events) GROUP BY 1, 2, 3 HAVING count(*) >= 15",
        "q_r5": "SELECT event_id FROM events",
        "q_s7": "SELECT event_id, event_type FROM events",
        "q_s8_memory": "SELECT event_type, count(*) AS n FROM events GROUP BY event_type",
        "q_r11_update": "SELECT event_type, count(*) AS n FROM events GROUP BY event_type",
        "q_r6": "SELECT event_id, ('0x' || substr(md5('7|' || event_id), 1, 8))::BIGINT AS priority FROM events ORDER BY priority, event_id LIMIT 500",
        "q_r8": "SELECT 'event_type' AS coord, CAST(r AS INT) AS depth_row, CAST((('0x' || substr(md5('9|' || r || '|event_type|' || event_type), 1, 8))::BIGINT) % 50 AS INT) AS bucket, count(*) AS cnt FROM events, range(5) t(r) GROUP BY ALL",
        "q_r9": "SELECT event_id, event_type, count(*) OVER (PARTITION BY event_type) / (SELECT CAST(count(*) AS DOUBLE) FROM events) AS share FROM events",
        "q_r10": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
        "q_r12": f"SELECT * FROM ({' UNION ALL '.join(u.format(c=c) for c in ('event_type', 'user_id'))}) WHERE cnt >= 100",
    }
