"""Best-fit packing into bins of several permitted lengths.

Documents are cut into pieces of at most the largest length; a shard of documents (by hash, so that it fits
a task; rows that repeat are counted first and dealt by number, so that no id makes a shard) is packed by best fit, longest piece first: a piece goes to the open bin that it leaves the least room in, and
where none has room, to a new bin of the length with the least cost for each id that it can be expected to hold. When
all pieces are placed, each bin is downsized to the least permitted length that holds its contents. That is done for
each permitted length as the largest to open, so the lengths are chosen jointly, and the plan of least cost is kept.
The cost of a bin is its length, plus the square that attention takes, plus a fixed part.

Null and non-positive lengths take no room: such rows give one piece of length 0 in no bin. Order of rows and
partitions changes nothing; rows that repeat an id are packed each.
"""

from __future__ import annotations

from bisect import bisect_left, insort

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored

LENGTHS = (512, 1024, 2048, 4096, 8192)
SHARD_IDS, SHARD_ROWS = 1 << 24, 1 << 15
#: Equal rows that one shard takes together.
COPIES = 256
PACKED = "doc_id bigint, piece int, doc_start bigint, n_tokens bigint, bin_id bigint, bin_start bigint, bin_length bigint"


def bin_cost(length: int) -> float:
    return length + length * length / 65_536 + 64


def pack(sizes: np.ndarray, lengths: tuple[int, ...], cost=bin_cost) -> tuple[float, np.ndarray, np.ndarray, np.ndarray]:
    """(cost, bin of each piece, place in it, length of each bin) for pieces in descending order, none over the largest
    length: the best over all largest lengths to open."""
    best = None
    for most in range(len(lengths)):
        allowed = lengths[: most + 1]
        plan = _best_fit(sizes, allowed, lengths, cost)
        if best is None or plan[0] < best[0]:
            best = plan
    return best


def _best_fit(sizes, allowed, lengths, cost):
    left = int(sizes.sum())
    room: list[tuple[int, int]] = []  # (room, bin) ascending
    used: list[int] = []
    where, place = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
    for i, n in enumerate(sizes.tolist()):
        at = bisect_left(room, (n, -1))
        if at < len(room):
            free, b = room.pop(at)
        else:
            fits = [c for c in allowed if c >= n] or [next(c for c in lengths if c >= n)]
            free, b = min(fits, key=lambda c: (cost(c) / min(c, left), c)), len(used)
            used.append(0)
        where[i], place[i] = b, used[b]
        used[b] += n
        left -= n
        if free > n:
            insort(room, (free - n, b))
    final = np.array([lengths[bisect_left(lengths, u)] for u in used], np.int64)
    return sum(map(cost, final.tolist())), where, place, final


def _pack_shard(lengths: tuple[int, ...]):
    most = lengths[-1]

    def go(key, t):
        copies = np.repeat(np.arange(t.num_rows), t.column("copies").to_numpy())
        doc, n = t.column("doc_id").take(pa.array(copies)), t.column("n_tokens").fill_null(0).to_numpy()[copies]
        n = np.maximum(n, 0)
        pieces = np.maximum(-(-n // most), 1)
        row = np.repeat(np.arange(len(n)), pieces)
        piece = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        size = np.minimum(n[row] - piece * most, most)
        ids = doc.fill_null(0).to_numpy()
        order = np.lexsort((piece, n[row], ids[row], -size))
        row, piece, size = row[order], piece[order], size[order]
        full = size > 0
        where, place, length = np.full(len(row), -1, np.int64), np.zeros(len(row), np.int64), np.zeros(len(row), np.int64)
        if full.any():
            _, where[full], place[full], final = pack(size[full], lengths)
            length[full] = final[where[full]]
        name = np.where(where < 0, -1, (key[0].as_py() << 32) + where)
        return pa.table({"doc_id": doc.take(pa.array(row)), "piece": piece.astype(np.int32), "doc_start": piece * most, "n_tokens": size, "bin_id": pa.array(name, mask=where < 0), "bin_start": place, "bin_length": length})

    return go


def packed(sized: DataFrame, lengths: tuple[int, ...] = LENGTHS, id_col: str = "doc_id", size_col: str = "n_tokens") -> DataFrame:
    """(doc_id, piece, doc_start, n_tokens, bin_id, bin_start, bin_length) for every piece of every row."""
    lengths = tuple(sorted(set(lengths)))
    sized = stored(sized.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(size_col).cast("bigint").alias("n_tokens")), "sized")
    rows, ids = sized.agg(F.count("*"), F.sum("n_tokens")).first()
    shards = max(1, -(-rows // SHARD_ROWS), -(-(ids or 0) // SHARD_IDS))
    counted = sized.groupBy("doc_id", "n_tokens").agg(F.count("*").alias("n")).withColumn("part", F.explode(F.sequence(F.lit(0), F.ceil(F.col("n") / COPIES) - 1)))
    dealt = counted.withColumn("copies", F.least(F.lit(COPIES), F.col("n") - COPIES * F.col("part"))).withColumn("shard", F.pmod(F.xxhash64("doc_id", "n_tokens", "part"), F.lit(shards)))
    return dealt.select("shard", "doc_id", "n_tokens", "copies").groupBy("shard").applyInArrow(_pack_shard(lengths), PACKED)
