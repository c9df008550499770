"""N-gram Jaccard self-join by a size-aware heavy-light split.

A document is the set of its distinct 5-word shingles (64-bit hashes). Two sets link when 100 * |A n B| >= 80 * |A u B|.
Whatever the order of the tokens, two linked sets share at least l tokens among the first |X| - ceil(0.8 |X|) + l of
each. Small sets (size up to a boundary) are indexed by all fixed-size subsets, here pairs, of that prefix with l = 2,
so that one common passage alone makes no candidate; large sets are looked up in inverted lists of single prefix
tokens (l = 1), which the small sets that can reach over the boundary join too. The boundary is the one of least
estimated cost over the histogram of sizes. Tokens are ordered rare first: a mergeable frequent-key summary of all
shingles names at most 2**18 frequent ones; the order needs no more than that, and any order gives the same links.

Lists travel as blocks of packed arrays, dealt by key, and are read with vectorised code. A list of up to LIST sets
gives its pairs. A longer one under a shingle that the summary had missed teaches its length: the sets of such lists are
indexed anew in an order that has these shingles late, so that they meet under rarer ones; any two that link meet there
too, for any order does. Long lists that are left give star pairs to a pivot per size class. Those whose sets the links
found so far have not merged into one component are then compared in blocks: a pair meets at the least long key that
both sets have, goes no further if it is in one component or if counts of its tokens over cells (one or two tokens to a
cell, whatever the size) leave too small an overlap possible, and the rest are verified inside the task, which gives
the edges of a spanning forest and no pairs.
Pairs carry how many entries they share. Two sets can share no more tokens than those of the shorter-reaching prefix
that both hold and all that lie behind it, so a pair whose shared entries, with those that long lists may add, are too
few for a link goes without a look at its sets.
Every pair of a list thus is compared or already in one component: components are exact, with no caps, and what is
written for a group of copies follows its size and not its square. Every candidate is verified on whole sets. Ids and
cells move before any set does.

Nulls, empty texts and texts without words have no shingles and link with nothing. Rows with equal sets are one node,
whatever their number; rows that repeat a doc_id keep their rows. An empty table gives no rows.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as t

from . import textscan as ts
from .common import begins, components, forget, release, stored_at, tidied

#: Longest list whose pairs are all made at once.
LIST = 32
#: Sets and tokens that a block of a long list holds, about.
BLOCK, TOKENS = 1024, 1 << 22
#: Most often that lists which came out long are indexed anew.
ROUNDS = 2
HOT = 1 << 18
#: Nodes that a broadcast may name.
FEW = 1 << 20
#: Estimated comparisons that a single-token entry causes, against 1 for writing an entry.
SCAN = 4.0
#: Cost of a comparison of two sets of a long list, against 1 for reading a token.
PAIR = 8
SCAN_TABLE = "kind int, a bigint, b bigint, c bigint"
LISTED = "kind int, a bigint, b bigint, c bigint, d bigint, e bigint"


def _least(n: int, share: int) -> int:
    return -(-share * n // 100)


def _alone(n: int, share: int) -> bool:
    """Whether a set of n links with equal ones alone."""
    return 100 * n < share * (n + 1)


def _tiny(share: int) -> int:
    """The largest size at which one common token can be enough for a link, so that pairs of tokens would miss it."""
    return 100 // share


def _scan(k: int):
    """For each row (0, id, set size, fingerprint); for each task its frequent shingles (1, shingle, count, null)."""

    def go(batches):
        begins("jaccard")
        seen = ts.Frequent()
        for batch in batches:
            for lo, hi, data, offs in ts.runs(batch.column(1)):
                sets = list(ts.shingle_sets(data, offs, k))
                size = np.array([len(s) for s in sets], np.int64)
                every = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
                seen.add(every)
                at = np.concatenate([[0], np.cumsum(size)])
                yield _rows(0, batch.column(0).slice(lo, hi - lo), size, fingerprints(every, at))
        seen.settle()
        many = seen.counts > 1
        yield _rows(1, pa.array(ts.signed(seen.keys[many])), seen.counts[many], None)

    return go


def _rows(kind: int, a, b, c):
    n = len(a)
    return pa.RecordBatch.from_arrays([pa.array(np.full(n, kind, np.int32)), a.cast(pa.int64()), pa.array(b, pa.int64()), pa.nulls(n, pa.int64()) if c is None else pa.array(c)], names=["kind", "a", "b", "c"])


def fingerprints(every: np.ndarray, at: np.ndarray) -> np.ndarray:
    """One 64-bit value for each set, the same for the same elements."""
    total = np.zeros(len(every) + 1, np.uint64)
    np.cumsum(ts.mixed(every ^ np.uint64(0x5851F42D4C957F2D)), out=total[1:])
    return ts.signed(ts.mixed(total[at[1:]] - total[at[:-1]] + (at[1:] - at[:-1]).astype(np.uint64)))


def boundary(sizes: list[tuple[int, int]], share: int) -> int:
    """The largest size kept small, of least estimated cost over (size, number of sets)."""

    def cost(limit: int) -> float:
        total = 0.0
        for n, many in sizes:
            first = n - _least(n, share) + 1
            if n <= limit:
                total += many * (first + 1) * first / 2
            if 100 * n >= share * (limit + 1):
                total += many * first * (1 + SCAN)
        return total

    return min((0, *range(4, 12, 2), *range(12, 100, 4)), key=cost)


def _index(k: int, share: int, limit: int, hot, buckets: int, salted: int, only=None, bits: int = 0):
    """Blocks of (key, node, size, flags) by bucket; flags: 1 the key is dealt over several buckets, 2 it is a subset.
    hot: broadcast (shingles, counts). only: broadcast filter of the ids whose rows are read."""
    reach, near_tiny = -(-share * (limit + 1) // 100), 100 * _tiny(share) // share

    def go(batches):
        keys, counts = hot.value
        held: list[list[np.ndarray]] = []
        total = 0

        def flush():
            key, node, size, wide, sub = (np.concatenate(x) for x in zip(*held, strict=True))
            # a frequent key is dealt over buckets by node too
            spread = ts.mixed(key ^ np.uint64(77)) + np.where(wide > 0, ts.mixed(node) % np.maximum(wide, 1).astype(np.uint64), np.uint64(0))
            where = (spread % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(where, kind="stable")
            cuts = np.searchsorted(where[order], np.arange(buckets + 1))
            rows = [(b, order[cuts[b] : cuts[b + 1]]) for b in range(buckets) if cuts[b] < cuts[b + 1]]
            for part in range(0, len(rows), 64):
                some = rows[part : part + 64]
                pack = lambda x, kind: pa.array([x[o].astype(kind).tobytes() for _, o in some], pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array([b for b, _ in some], pa.int32()), pack(key, np.uint64), pack(node, np.uint64), pack(size, np.int32), pack((wide > 0) + 2 * sub, np.uint8)], names=["bucket", "keys", "nodes", "sizes", "flags"])

        for batch in batches:
            for _, _, data, offs in ts.runs(batch.column(1) if only is None else _picked(batch, only, bits)):
                sets = list(ts.shingle_sets(data, offs, k))
                size = np.array([len(s) for s in sets], np.int64)
                at = np.concatenate([[0], np.cumsum(size)])
                every = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
                nodes = fingerprints(every, at).view(np.uint64)
                often = np.zeros(len(every), np.int64)
                if len(keys) and len(every):
                    where = np.minimum(np.searchsorted(keys, every), len(keys) - 1)
                    hit = keys[where] == every
                    often[hit] = counts[where[hit]]
                out_k, out_n, out_s, out_w, out_f = [], [], [], [], []
                for d, n in enumerate(size.tolist()):
                    if _alone(n, share):
                        continue
                    own, rate = every[at[d] : at[d + 1]], often[at[d] : at[d + 1]]
                    first = n - _least(n, share) + 1
                    two = min(first + 1, n)
                    if rate.any():
                        order = np.argsort(rate, kind="stable")[:two]
                        own, rate = own[order], rate[order]
                    else:
                        own, rate = own[:two], rate[:two]
                    if n <= limit:
                        i, j = np.triu_indices(len(own), 1)
                        lo, hi = np.minimum(own[i], own[j]), np.maximum(own[i], own[j])
                        out_k.append(ts.mixed(lo * ts.LAGS[20] + hi * ts.LAGS[21]))
                        out_w.append(np.minimum(rate[i], rate[j]) // salted)
                        out_f.append(np.ones(len(i), np.uint8))
                    single = n >= reach or n <= near_tiny
                    if single:
                        out_k.append(own[:first])
                        out_w.append(rate[:first] // salted)
                        out_f.append(np.zeros(len(own[:first]), np.uint8))
                    made = (n <= limit) * (len(own) * (len(own) - 1) // 2) + single * min(first, len(own))
                    out_n.append(np.full(made, nodes[d]))
                    out_s.append(np.full(made, n))
                if out_k:
                    held.append([np.concatenate(out_k), np.concatenate(out_n), np.concatenate(out_s), np.concatenate(out_w), np.concatenate(out_f)])
                    total += len(held[-1][0])
                if total > 1 << 20:
                    yield from flush()
                    held, total = [], 0
        if held:
            yield from flush()

    return go


def _lists(share: int, limit: int, part: int):
    """From the blocks of one bucket, candidates (0, node, node, entries shared, size, size) and the entries of long or
    dealt lists (1, key, node, size, subset, null)."""

    def go(blocks):
        get = lambda name, kind: np.concatenate([np.frombuffer(x.as_buffer(), kind) for t in blocks for x in t.column(name)] or [np.zeros(0, kind)])
        key, node, size, flag = get("keys", np.uint64), get("nodes", np.uint64), get("sizes", np.int32), get("flags", np.uint8)
        if not len(key):
            return
        # single entries go first, as most keys have one
        order = np.argsort(key, kind="stable")
        key = key[order]
        same = np.zeros(len(key) + 1, bool)
        same[1:-1] = key[1:] == key[:-1]
        many = same[1:] | same[:-1] | (flag[order] & 1 > 0)
        order, key = order[many], key[many]
        node, size, flag = node[order], size[order], flag[order]
        order = np.lexsort((node, size, key))
        key, node, size, flag = key[order], node[order], size[order], flag[order]
        fresh = np.ones(len(key), bool)
        fresh[1:] = (key[1:] != key[:-1]) | (node[1:] != node[:-1])
        key, node, size, flag = key[fresh], node[fresh], size[fresh].astype(np.int64), flag[fresh]
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, int)
        length = np.diff(np.concatenate([starts, [len(key)]]))
        group = np.repeat(np.arange(len(starts)), length)
        big = (length > LIST)[group] | (flag & 1 > 0)
        first, second = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        index = np.flatnonzero(~big)
        for gap in range(1, LIST):
            index = index[index + gap < len(key)]
            index = index[group[index + gap] == group[index]]
            if not len(index):
                break
            # sets that are both small, but not tiny, meet by subsets alone
            near = index[(100 * size[index] >= share * size[index + gap]) & ((flag[index] > 1) | (size[index + gap] > limit) | (size[index] <= _tiny(share)))]
            first.append(near)
            second.append(near + gap)
        i, j = np.concatenate(first), np.concatenate(second)
        turned = node[i] > node[j]
        i, j = np.where(turned, j, i), np.where(turned, i, j)
        order = np.lexsort((node[j], node[i]))
        i, j = i[order], j[order]
        at = np.flatnonzero(np.concatenate([np.ones(min(1, len(i)), bool), (node[i][1:] != node[i][:-1]) | (node[j][1:] != node[j][:-1])]))
        shared = np.diff(np.concatenate([at, [len(i)]]))
        i, j = i[at], j[at]
        for o in range(0, len(i), part):
            x, y = i[o : o + part], j[o : o + part]
            yield _entries(0, node[x], node[y], shared[o : o + part], size[x], size[y])
        big = np.flatnonzero(big)
        for o in range(0, len(big), part):
            x = big[o : o + part]
            yield _entries(1, key[x], node[x], size[x], (flag[x] >> 1).astype(np.int64), np.zeros(len(x), np.int64))

    return go


def _entries(kind, a, b, *rest):
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, np.int32)), pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), *map(pa.array, rest)], names=["kind", "a", "b", "c", "d", "e"])


def _enough(share: int, limit: int, shared, sa, sb):
    """Whether sets of these sizes that share so many entries can link."""
    small, large = F.least(sa, sb), F.greatest(sa, sb)
    need = F.ceil((small + large) * share / F.lit(100.0 + share) - 1e-9) - F.ceil(large * share / F.lit(100.0) - 1e-9) + 1
    need = F.greatest(need, F.lit(1))
    return (100 * small >= share * large) & (shared >= F.when(_by_subsets(share, limit, sa, sb), need * (need + 1) / 2).otherwise(need))


def _by_subsets(share: int, limit: int, sa, sb):
    """Whether sets of these sizes meet by pairs of tokens and not by single ones."""
    return (F.greatest(sa, sb) <= limit) & (F.least(sa, sb) > _tiny(share))


def _filter_bits(bits: int):
    def go(batches):
        field = np.zeros(1 << bits, bool)
        for batch in batches:
            field[_slots(batch.column(0).fill_null(0).to_numpy(zero_copy_only=False), bits)] = True
        words = np.packbits(field).view(np.int64)
        some = np.flatnonzero(words)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(words[some])], names=["at", "bits"])

    return go


def _slots(ids: np.ndarray, bits: int) -> np.ndarray:
    return (ts.mixed(ids.view(np.uint64) ^ np.uint64(5)) >> np.uint64(64 - bits)).astype(np.int64)


def _picked(batch, field, bits: int) -> pa.Array:
    """The texts of the rows whose id may be asked for."""
    slot = _slots(batch.column(0).cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False), bits)
    return batch.column(1).filter(pa.array((field.value[slot >> 3] >> (7 - (slot & 7)).astype(np.uint8)) & 1 > 0))


def _cells(tokens: np.ndarray) -> bytes:
    """Counts of a set's tokens over as many cells as leave one or two to a cell: four bits each, 15 for 15 or more."""
    width = max(16, 1 << len(tokens).bit_length() - 1)
    count = np.minimum(np.bincount((tokens & np.uint64(width - 1)).astype(np.int64), minlength=width), 15).astype(np.uint8)
    return (count[::2] | count[1::2] << 4).tobytes()


def _counts(cells: list) -> np.ndarray:
    """A row of counts for each set of cells of one width."""
    packed = np.frombuffer(b"".join(cells), np.uint8).reshape(len(cells), -1)
    out = np.empty((len(cells), 2 * packed.shape[1]), np.uint8)
    out[:, ::2], out[:, 1::2] = packed & 15, packed >> 4
    return out


def _folded(count: np.ndarray, width: int) -> np.ndarray:
    """The counts over fewer cells. Sums stay in a byte, or are cut to a byte, which a full cell stands for."""
    while count.shape[-1] > width:
        half = count.shape[-1] // 2
        count = np.minimum(count[..., :half].astype(np.uint16) + count[..., half:], 255).astype(np.uint8)
    return count


def _full(count: np.ndarray) -> np.ndarray:
    """Which sets have a cell that does not tell its count."""
    return (count == 15).any(1)


def _sets(k: int, field, bits: int, cells: bool):
    """(node, set as packed hashes, or the counts of its tokens over cells) of the rows whose id may be asked for."""

    def go(batches):
        for batch in batches:
            for _, _, data, offs in ts.runs(_picked(batch, field, bits)):
                sets = list(ts.shingle_sets(data, offs, k))
                at = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int64)
                nodes = fingerprints(np.concatenate(sets), at)
                yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array([_cells(s) if cells else s.tobytes() for s in sets], pa.binary())], names=["node", "set"])

    return go


def _read(col):
    """col, whose sets must all have been read: a pair without its set would be lost without a word."""
    if col.null_count:
        raise ValueError(f"{col.null_count} candidates whose sets were not read")
    return col


def _links(x: np.ndarray, y: np.ndarray, share: int) -> bool:
    """Whether two ascending sets link."""
    small, large = (x, y) if len(x) <= len(y) else (y, x)
    if 100 * len(small) < share * len(large):
        return False
    where = np.minimum(np.searchsorted(large, small), len(large) - 1)
    both = int((large[where] == small).sum())
    return 100 * both >= share * (len(x) + len(y) - both)


def _may_link(share: int):
    """(a, b) of the pairs whose counts over cells leave an overlap possible that links them. The counts sum to the
    sets' sizes but where one is full."""

    def go(batches):
        for batch in batches:
            one, two = (_read(batch.column(i)).to_pylist() for i in (2, 3))
            widths: dict[tuple[int, int], list[int]] = {}
            for i, (x, y) in enumerate(zip(one, two, strict=True)):
                widths.setdefault((len(x), len(y)), []).append(i)
            keep = np.zeros(len(one), bool)
            for (wx, wy), rows in widths.items():
                some = max(1, (1 << 23) // max(wx, wy))
                for o in range(0, len(rows), some):
                    part = rows[o : o + some]
                    x, y = _counts([one[i] for i in part]), _counts([two[i] for i in part])
                    size, full = x.sum(1, dtype=np.int64) + y.sum(1, dtype=np.int64), _full(x) | _full(y)
                    most = np.minimum(_folded(x, 2 * min(wx, wy)), _folded(y, 2 * min(wx, wy))).sum(1, dtype=np.int64)
                    keep[part] = full | ((100 + share) * most >= share * size)
            keep = pa.array(keep)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], names=["a", "b"])

    return go


def _verify(share: int):
    def go(batches):
        for batch in batches:
            a, b = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            keep = np.zeros(len(a), bool)
            for i, (x, y) in enumerate(zip(_read(batch.column(2)), _read(batch.column(3)), strict=True)):
                keep[i] = _links(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), share)
            yield pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(b[keep])], names=["a", "b"])

    return go


class _Verifier:
    """Candidate pairs of nodes against whole sets, read again for the rows that candidates name."""

    def __init__(self, docs: DataFrame, nodes: DataFrame, k: int, share: int):
        self.docs, self.nodes, self.k, self.share = docs, nodes, k, share

    def rows_of(self, ends: DataFrame):
        """A broadcast filter of the ids of the nodes in column end, its bits, and how many nodes there are. Its size is
        bounded; where it fills up, more rows are read, and what follows still decides."""
        spark = ends.sparkSession
        asked, asked_at = stored_at(self.nodes.join(ends, self.nodes["node"] == ends["end"], "left_semi").select("doc_id"), "asked")
        many = asked.count()
        bits = min(27, max(16, math.ceil(math.log2(64 * many + 1))))
        field = np.zeros(1 << (bits - 6), np.int64)
        words = asked.coalesce(64).mapInArrow(_filter_bits(bits), "at bigint, bits bigint").groupBy("at").agg(F.bit_or("bits").alias("bits"))
        got = words.toArrow()
        field[got.column("at").to_numpy()] = got.column("bits").to_numpy()
        forget(spark, asked_at)
        return spark.sparkContext.broadcast(field.view(np.uint8)), bits, many

    def sets(self, ends: DataFrame, cells: bool = False) -> tuple[DataFrame, str]:
        """(node, set) of the nodes in column end, each once; cells: counts over cells in the place of sets."""
        ends, ends_at = stored_at(ends, "ends")
        field, bits, many = self.rows_of(ends)
        read = self.docs.mapInArrow(tidied(_sets(self.k, field, bits, cells)), "node bigint, set binary")
        made = stored_at(read.join(F.broadcast(ends) if many <= FEW else ends, F.col("node") == F.col("end"), "left_semi").dropDuplicates(["node"]), "sets")
        field.destroy()
        forget(ends.sparkSession, ends_at)
        return made

    @staticmethod
    def _beside(pairs: DataFrame, sets: DataFrame) -> DataFrame:
        one, two = sets.select(F.col("node").alias("na"), F.col("set").alias("sa")), sets.select(F.col("node").alias("nb"), F.col("set").alias("sb"))
        return pairs.join(one, F.col("a") == F.col("na"), "left").select("a", "b", "sa").join(two, F.col("b") == F.col("nb"), "left").select("a", "b", "sa", "sb")

    def links(self, pairs: DataFrame) -> tuple[DataFrame, list[str]]:
        spark = pairs.sparkSession
        every, every_at = stored_at(pairs.where("a <> b"), "pairs")
        ends = lambda p: p.select(F.explode(F.array("a", "b")).alias("end")).distinct()
        cells, cells_at = self.sets(ends(every), cells=True)
        near = self._beside(every, cells).mapInArrow(tidied(_may_link(self.share)), "a bigint, b bigint")
        pairs, pairs_at = stored_at(near, "near")
        forget(spark, every_at, cells_at)
        sets, sets_at = self.sets(ends(pairs))
        found, at = stored_at(self._beside(pairs, sets).mapInArrow(tidied(_verify(self.share)), "a bigint, b bigint"), "links")
        forget(spark, pairs_at, sets_at)
        return found, [at]


def _stars(lists: DataFrame, share: int) -> DataFrame:
    """(a, b): pairs of each long list's members with the largest member of their size class and of the class below."""
    step = math.log(100 / share)
    classed = lists.withColumn("class", F.floor(F.log(F.col("size").cast("double")) / step).cast("int"))
    pivots = classed.groupBy("key", "class").agg(F.max(F.struct("size", "node")).alias("top"))
    up = pivots.select(F.col("key").alias("pkey"), F.explode(F.array(F.col("class"), F.col("class") + 1)).alias("pclass"), F.col("top").alias("p"))
    up = stored_at(up, "pivots")[0]
    near = (100 * F.least("size", "p.size") >= share * F.greatest("size", "p.size")) & (F.col("node") != F.col("p.node"))
    return classed.join(up, (F.col("key") == F.col("pkey")) & (F.col("class") == F.col("pclass"))).where(near).select(F.least("node", "p.node").alias("a"), F.greatest("node", "p.node").alias("b"))


def _meetings(rows: DataFrame) -> DataFrame:
    """rows with key, node and size, dealt so that every two blocks of a key meet in one group (key, p, q): side 2 for a
    block with itself, else 0 and 1."""
    counted = rows.groupBy("key").agg(F.count("*").alias("n"), F.sum("size").alias("tokens")).where("n > 1")
    blocks = F.greatest(F.ceil(F.col("n") / BLOCK), F.least(F.ceil(F.col("tokens") / TOKENS), F.col("n"))).cast("int")
    full, _ = stored_at(counted.select(F.col("key").alias("k0"), blocks.alias("blocks")), "blocks")
    placed = rows.join(full, F.col("key") == F.col("k0")).drop("k0").withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    return placed.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")).select(
        "*", F.least("mine", "other").alias("p"), F.greatest("mine", "other").alias("q"),
        F.when(F.col("mine") == F.col("other"), 2).when(F.col("mine") < F.col("other"), 0).otherwise(1).alias("side")).drop("mine", "other", "blocks")


class _Grid:
    """Counts over cells of many sets, by width, and the most tokens that sets can share by them."""

    def __init__(self, cells: list):
        bytes_each = np.array([len(x) for x in cells])
        self.width = 2 * bytes_each
        self.row, self.full, self.made = np.zeros(len(cells), np.int64), np.zeros(len(cells), bool), {}
        for w in np.unique(bytes_each).tolist():
            own = np.flatnonzero(bytes_each == w)
            self.row[own] = np.arange(len(own))
            count = self.made[2 * w, 2 * w] = _counts([cells[i] for i in own.tolist()])
            self.full[own] = _full(count)

    def _at(self, width: int, to: int) -> np.ndarray:
        if (width, to) not in self.made:
            self.made[width, to] = _folded(self.made[width, width], to)
        return self.made[width, to]

    def most(self, i: int, others: np.ndarray) -> np.ndarray:
        out, mine = np.zeros(len(others), np.int64), int(self.width[i])
        for w in np.unique(self.width[others]).tolist():
            here, to = np.flatnonzero(self.width[others] == w), min(w, mine)
            rows = self.row[others[here]]
            for o in range(0, len(here), max(1, (1 << 23) // to)):
                some = slice(o, o + max(1, (1 << 23) // to))
                out[here[some]] = np.minimum(self._at(w, to)[rows[some]], self._at(mine, to)[self.row[i]]).sum(1, dtype=np.int64)
        return out


def _possible(t, share: int, here: int):
    """Index pairs of a group that may link: other components, sizes and cells that allow it, met at their least key."""
    side, size, comp = (t.column(c).to_numpy() for c in ("side", "size", "comp"))
    grid = _Grid(_read(t.column("cells")).to_pylist())
    lists = t.column("keys").to_pylist()
    table = np.full((len(lists), max(map(len, lists))), np.iinfo(np.int64).max)
    for i, x in enumerate(lists):
        table[i, : len(x)] = x
    same = (side == 2).all()
    one, two = (np.arange(len(side)),) * 2 if same else (np.flatnonzero(side == 0), np.flatnonzero(side == 1))
    for i in one.tolist():
        near = two[two > i] if same else two
        need = -(-share * (size[i] + size[near]) // (100 + share))
        keep = (comp[near] != comp[i]) & (need <= np.minimum(size[i], size[near]))
        near, need = near[keep], need[keep]
        if len(near):
            some = near[(grid.most(i, near) >= need) | grid.full[near] | grid.full[i]]
            if len(some):
                shared = np.isin(table[some], table[i][: len(lists[i])])
                first = table[some, shared.argmax(1)]
                yield i, some[shared.any(1) & (first == here)]


def _open_nodes(share: int):
    """(key, node) of the nodes that a key's group can't settle without their sets."""

    def go(key, t):
        hit = np.zeros(t.num_rows, bool)
        for i, some in _possible(t, share, key[0].as_py()):
            hit[some] = True
            hit[i] |= len(some) > 0
        node = t.column("node").to_numpy()[hit]
        return pa.table({"key": pa.array([key[0].as_py()] * len(node), pa.int64()), "node": node})

    return go


def _forest_of(share: int):
    """(a, b): links of a key's group, as many as merge its components."""

    def go(key, t):
        node, comp = t.column("node").to_numpy(), t.column("comp").to_numpy()
        sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in _read(t.column("set"))]
        _, root = np.unique(comp, return_inverse=True)
        up = list(range(len(root)))

        def top(x):
            while up[x] != x:
                up[x] = up[up[x]]
                x = up[x]
            return x

        out = []
        for i, some in _possible(t, share, key[0].as_py()):
            for j in some.tolist():
                a, b = top(int(root[i])), top(int(root[j]))
                if a != b and _links(sets[i], sets[j], share):
                    up[a] = b
                    out.append((min(node[i], node[j]), max(node[i], node[j])))
        return pa.table({"a": pa.array([a for a, _ in out], pa.int64()), "b": pa.array([b for _, b in out], pa.int64())})

    return go


def _settled(lists: DataFrame, comp: DataFrame, verifier: _Verifier, share: int) -> DataFrame:
    """The links that long lists still lack between components, as forests."""
    named, named_at = stored_at(lists.join(comp.select(F.col("node").alias("n0"), "comp"), F.col("node") == F.col("n0"), "left")
                                .select("key", "node", "size", F.coalesce("comp", "node").alias("comp")), "named")
    mixed, mixed_at = stored_at(named.groupBy("key").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1")).where("c0 <> c1").select(F.col("key").alias("mkey")), "mixed")
    inside, inside_at = stored_at(named.join(mixed, F.col("key") == F.col("mkey")).drop("mkey"), "inside")
    nodes = inside.groupBy("node").agg(F.sort_array(F.collect_list("key")).alias("keys"))
    cells, cells_at = verifier.sets(nodes.select(F.col("node").alias("end")), cells=True)
    known = nodes.select(F.col("node").alias("n2"), "keys").join(cells.select(F.col("node").alias("n1"), F.col("set").alias("cells")), F.col("n2") == F.col("n1"), "left").drop("n1")
    known, known_at = stored_at(known, "known")
    light = inside.join(known, F.col("node") == F.col("n2")).drop("n2")
    open_, open_at = stored_at(_meetings(light).groupBy("key", "p", "q").applyInArrow(_open_nodes(share), "key bigint, node bigint").distinct(), "open")
    # only sets that cells can't tell apart are read whole
    sets, sets_at = verifier.sets(open_.select(F.col("node").alias("end")).distinct())
    heavy = open_.join(inside.select(F.col("key").alias("k1"), F.col("node").alias("n3"), "size", "comp"), (F.col("key") == F.col("k1")) & (F.col("node") == F.col("n3"))).drop("k1", "n3")
    # sets come last, so that they move once
    met = _meetings(heavy.join(known, F.col("node") == F.col("n2")).drop("n2")).join(sets.withColumnRenamed("node", "n4"), F.col("node") == F.col("n4"), "left").drop("n4")
    found, _ = stored_at(met.groupBy("key", "p", "q").applyInArrow(_forest_of(share), "a bigint, b bigint"), "forest")
    forget(lists.sparkSession, named_at, mixed_at, inside_at, cells_at, known_at, open_at, sets_at)
    return found


def _listed(docs: DataFrame, k: int, share: int, limit: int, known: dict[int, int], entries: float, only, bits: int):
    """One round of the index: pairs (a, b) that may link, the entries of long lists (key, node, size, subset), and the
    paths of both."""
    spark = docs.sparkSession
    # at most HOT frequent shingles and those that long lists taught, of which the order alone depends
    order = np.array(sorted(known), np.int64).view(np.uint64)
    order.sort()
    hot = spark.sparkContext.broadcast((order, np.array([known[x] for x in order.view(np.int64).tolist()], np.int64)))
    buckets = int(max(12, min(8192, entries // 600_000)))
    listed, listed_at = stored_at(
        docs.mapInArrow(tidied(_index(k, share, limit, hot, buckets, 8192, only, bits)), "bucket int, keys binary, nodes binary, sizes binary, flags binary")
        .groupBy("bucket").applyInArrow(_one(_lists(share, limit, 1 << 16)), LISTED), "lists")
    hot.destroy()
    release(spark)
    held = listed.where("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("node"), F.col("c").alias("size"), F.col("d").alias("subset"))
    # how many entries of each set the pairs' counts may lack
    hidden, hidden_at = stored_at(held.groupBy("node").agg(F.sum(1 - F.col("subset")).alias("tokens"), F.sum("subset").alias("subsets")), "hidden")
    pairs = (listed.where("kind = 0").select("a", "b", F.col("d").alias("sa"), F.col("e").alias("sb"), F.col("c").alias("shared"))
             .groupBy("a", "b").agg(F.first("sa").alias("sa"), F.first("sb").alias("sb"), F.sum("shared").alias("shared")))
    ha, hb = (hidden.select(F.col("node").alias(f"n{x}"), F.col("tokens").alias(f"t{x}"), F.col("subsets").alias(f"u{x}")) for x in "ab")
    beside = pairs.join(ha, F.col("a") == F.col("na"), "left").join(hb, F.col("b") == F.col("nb"), "left")
    lacks = lambda x: F.least(F.coalesce(f"{x}a", F.lit(0)), F.coalesce(f"{x}b", F.lit(0)))
    more = F.when(_by_subsets(share, limit, F.col("sa"), F.col("sb")), lacks("u")).otherwise(lacks("t"))
    near, near_at = stored_at(beside.where(_enough(share, limit, F.col("shared") + more, F.col("sa"), F.col("sb"))).select("a", "b"), "counted")
    forget(spark, hidden_at)
    return near, held, [listed_at, near_at]


def _all_of(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _classes(docs: DataFrame, id_col: str, text_col: str, k: int, share: int) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, n, node) of all documents, and (node, doc_id, comp) of all sets: its least id and its component."""
    spark = docs.sparkSession
    docs = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    scanned, scanned_at = stored_at(docs.mapInArrow(tidied(_scan(k)), SCAN_TABLE), "scan")
    rows = scanned.where("kind = 0").select(F.col("a").alias("doc_id"), F.col("b").alias("n"), F.col("c").alias("node"))
    # at most HOT frequent shingles, of which the order alone depends
    often = scanned.where("kind = 1").groupBy("a").agg(F.sum("b").alias("n")).where("n >= 32").orderBy(F.desc("n"), "a").limit(HOT).toArrow()
    known = dict(zip(often.column(0).to_pylist(), often.column(1).to_pylist(), strict=True))
    alone = next((n for n in range(1, 101) if not _alone(n, share)), 1 << 30)
    sizes = [(int(r[0]), int(r[1])) for r in rows.where(f"n between {alone} and 1000").groupBy("n").count().collect()]
    limit = boundary(sizes, share)
    nodes, nodes_at = stored_at(rows.where("n > 0").groupBy("node").agg(F.min("doc_id").alias("doc_id")), "nodes")
    verifier = _Verifier(docs, nodes, k, share)
    pairs, lists, used = [], [], [nodes_at]
    only, bits, tokens, many = None, 0, *rows.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    entries = tokens * (100 - share) / 100 + many
    for turn in range(ROUNDS + 1):
        near, long, made = _listed(docs, k, share, limit, known, entries, only, bits)
        pairs.append(near)
        used += made
        if only is not None:
            only.destroy()
        lengths = long.where("subset = 0").groupBy("key").agg(F.count("*").alias("n"))
        learnt = [] if turn == ROUNDS else [r for r in lengths.orderBy(F.desc("n"), "key").limit(HOT).collect() if r["key"] not in known]
        # comparing such lists in blocks must cost more than another scan does
        if not learnt or sum(r["n"] ** 2 for r in learnt) * PAIR < tokens:
            lists.append(long)
            break
        fresh = spark.createDataFrame(pa.table({"k0": pa.array([r["key"] for r in learnt], pa.int64())}))
        again, again_at = stored_at(long.join(F.broadcast(fresh), F.col("key") == F.col("k0"), "left_semi"), "again")
        lists.append(long.join(F.broadcast(fresh), F.col("key") == F.col("k0"), "left_anti"))
        known |= {r["key"]: r["n"] for r in learnt}
        entries = again.select("node", "size").distinct().agg(F.sum(F.col("size") * (100 - share) / 100 + 1)).first()[0] or 0
        only, bits, _ = verifier.rows_of(again.select(F.col("node").alias("end")).distinct())
        used.append(again_at)
        release(spark)
    lists, lists_at = stored_at(_all_of(lists).select("key", "node", "size").distinct(), "long")
    links, made = verifier.links(_all_of([*pairs, _stars(lists, share)]).distinct())
    used += [lists_at, *made]
    release(spark)
    comp = components(links)
    extra = _settled(lists, comp, verifier, share)
    release(spark)
    if not extra.isEmpty():
        comp = components(links.unionByName(extra))
    named = nodes.join(comp.select(F.col("node").alias("n0"), "comp"), F.col("node") == F.col("n0"), "left").select("node", "doc_id", F.coalesce("comp", "node").alias("comp"))
    named = stored_at(named, "named")[0]
    forget(spark, *used)
    return rows, named


def jaccard_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, share: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, representative) for every row of docs.

    component_id is the least id reachable by links; representative says whether the row's own id is the component's.
    """
    rows, named = _classes(docs, id_col, text_col, k, share)
    least = stored_at(named.groupBy("comp").agg(F.min("doc_id").alias("component_id")), "least")[0]
    classes = stored_at(named.join(least.withColumnRenamed("comp", "c0"), F.col("comp") == F.col("c0")).select(F.col("node").alias("n1"), "component_id"), "classes")[0]
    return (rows.join(classes, (F.col("node") == F.col("n1")) & (F.col("n") > 0), "left")
            .select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
            .withColumn("representative", F.col("doc_id") == F.col("component_id")))


#: Columns that distinct_docs adds for a while; a table must not have them.
_NODE, _SIZE = "__set", "__set_size"


def _nodes_of(k: int, at: int):
    """Each batch with its rows' set fingerprint and set size."""

    def go(batches):
        for batch in batches:
            found, sizes = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for _, _, data, offs in ts.runs(batch.column(at)):
                sets = list(ts.shingle_sets(data, offs, k))
                size = np.array([len(s) for s in sets], np.int64)
                found.append(fingerprints(np.concatenate(sets), np.concatenate([[0], np.cumsum(size)])))
                sizes.append(size)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(found)), pa.array(np.concatenate(sizes))], names=[*batch.schema.names, _NODE, _SIZE])

    return go


def distinct_docs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, share: int = 80) -> DataFrame:
    """The rows of docs, all columns, one of each component: that of the least id (no id counts as the greatest), ties by
    the set's fingerprint and then by a hash of the whole row. Rows are decided one by one, so ids may repeat or be null.
    Rows without words link with nothing and all stay."""
    if {_NODE, _SIZE} & set(docs.columns):
        raise ValueError(f"columns {_NODE} and {_SIZE} are needed here")
    rows, named = _classes(docs, id_col, text_col, k, share)
    least = named.groupBy("comp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "node")).alias("e"))
    kept = least.select(F.col("e.node").alias("k_node"), F.col("e.doc_id").alias("k_id"))
    same = rows.join(kept, (F.col("node") == F.col("k_node")) & F.col("doc_id").eqNullSafe(F.col("k_id")) & (F.col("n") > 0)).groupBy("k_node", "k_id").agg(F.count("*").alias("same"))
    kept = stored_at(same, "kept")[0]
    many = kept.count()
    made = docs.mapInArrow(tidied(_nodes_of(k, docs.columns.index(text_col))), t.StructType([*docs.schema.fields, t.StructField(_NODE, t.LongType()), t.StructField(_SIZE, t.LongType())]))

    def of(some: DataFrame) -> DataFrame:
        few = F.broadcast(some) if many <= FEW else some
        return made.where(F.col(_SIZE) > 0).join(few, (F.col(_NODE) == F.col("k_node")) & F.col(id_col).cast("bigint").eqNullSafe(F.col("k_id")), "left_semi")

    out = made.where(F.col(_SIZE) == 0).unionByName(of(kept.where("same = 1")))
    if not kept.where("same > 1").isEmpty():
        # maps have no order and no hash, so such columns don't count
        plain = [f.name for f in docs.schema.fields if "map<" not in f.dataType.simpleString()]
        again = of(kept.where("same > 1")).groupBy(_NODE, _SIZE).agg(F.min_by(F.struct(*docs.columns), F.struct(F.xxhash64(*plain), F.hash(*plain))).alias("__row"))
        out = out.unionByName(again.select("__row.*", _NODE, _SIZE))
    return out.select(*docs.columns)


def _one(f):
    def go(t):
        got = list(f(t.to_batches()))
        return pa.Table.from_batches(got) if got else pa.table({"kind": pa.array([], pa.int32()), **{c: pa.array([], pa.int64()) for c in "abcde"}})

    return go
