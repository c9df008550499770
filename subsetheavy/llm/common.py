"""What the text operators share: the shared scratch folder, written tables, fold arithmetic and components."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def scratch(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, a temporary one if driver and
    executors are one machine, else an error."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", "")
    if not found:
        if not spark.sparkContext.master.startswith(("local[", "local*")) and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="scratch-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found.rstrip("/")


def stored(df: DataFrame, name: str = "step") -> DataFrame:
    """df, written to the shared folder and read again: lineage ends, and a lost executor loses nothing."""
    return stored_at(df, name)[0]


def stored_at(df: DataFrame, name: str = "step") -> tuple[DataFrame, str]:
    spark = df.sparkSession
    path = f"{scratch(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def forget(spark: SparkSession, *paths: str) -> None:
    """Remove written tables that no later step reads."""
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def release(spark: SparkSession) -> None:
    """Let the engine remove the shuffle files of steps that are written and that nothing refers to any more; else they
    stay on the executors' disks until the driver happens to collect its garbage."""
    gc.collect()
    spark._jvm.System.gc()


def tidied(work: Callable) -> Callable:
    """work on batches; when it ends, freed memory goes back to the machine, as workers live on between tasks."""

    def go(batches):
        try:
            yield from work(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # other C libraries give memory back by themselves
                ctypes.CDLL(None).malloc_trim(0)

    return go


_kept: dict[str, Callable[[], object]] = {}


def begins(owner: str, clear: Callable[[], object] | None = None) -> None:
    """Called in a worker where an operator's work begins: what other operators keep there from task to task is let go.
    clear: how to let go of this one's."""
    for name in [n for n in _kept if n != owner]:
        _kept.pop(name)()
    if clear is not None:
        _kept[owner] = clear


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(key: str, parts: int) -> Column:
    """crc32 of the key as text, modulo parts; null keys fall in fold 0."""
    return F.coalesce(F.pmod(F.crc32(F.col(key).cast("string").cast("binary")), F.lit(parts)), F.lit(0))


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Connected components of undirected edges between long keys: (node, comp), comp the least key reachable.

    Least-neighbour hooking with pointer jumping. Each round is two equi-joins whose skewed side can be split and
    one partial aggregate, and ends in a written table, so the plan stays short however long a chain is; rounds grow
    with the logarithm of the diameter. Nothing is collected but a count of changed labels.
    """
    spark = edges.sparkSession
    both, at = stored_at(edges.where(F.col(a) != F.col(b)).select(F.struct(a, b).alias("p"), F.struct(b, a).alias("q"))
                         .select(F.explode(F.array(F.col("p").cast("struct<u:bigint,v:bigint>"), F.col("q").cast("struct<u:bigint,v:bigint>"))).alias("e"))
                         .select("e.u", "e.v"), "edges")
    labels, last = stored_at(both.groupBy(F.col("u").alias("node")).agg(F.least(F.min("v"), F.col("u")).alias("comp")), "labels")
    while True:
        seen = both.join(labels.hint("shuffle_hash"), both["u"] == labels["node"]).select(F.col("v").alias("node"), "comp")
        near, near_at = stored_at(seen.unionByName(labels).groupBy("node").agg(F.min("comp").alias("comp")), "near")
        up = near.select(F.col("node").alias("at"), F.col("comp").alias("over"))
        nxt, path = stored_at(near.join(up, near["comp"] == up["at"], "left").select("node", F.least("comp", F.coalesce("over", "comp")).alias("comp")), "labels")
        forget(spark, near_at)
        old = labels.select(F.col("node").alias("n0"), F.col("comp").alias("c0"))
        moved = nxt.agg(F.sum(F.col("comp").cast("decimal(38,0)"))).first()[0], old.agg(F.sum(F.col("c0").cast("decimal(38,0)"))).first()[0]
        forget(spark, last)
        labels, last = nxt, path
        if moved[0] == moved[1]:
            forget(spark, at)
            return labels
