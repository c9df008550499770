"""Embedding near-duplicates by cross-polytope hashing.

Each vector is turned by pseudo-random rotations (three rounds of sign flips and a fast Hadamard transform) and hashed
to its nearest signed axis; WIDTH such hashes make a table's key. A vector is dealt under its own key and, for each
table, the PROBES - 1 keys next in the margin lost (multiprobe). Vectors that share a key first meet as ids, lists of
keys and sketches of BITS random hyperplanes; a link's sketches are further apart than the cut with a chance under 1e-9.
Where two sketches are near, the vectors follow and are compared by cosine in double precision inside a task, as matrix
products, and no pair leaves it: a task gives each vector's number of links and the edges of a spanning forest of the
links. A pair that shares several keys counts at the least of them alone, and a vector goes to no key where it has no
such pair. A key with over BLOCK vectors is cut into blocks, and each pair of blocks is a task of its own; vectors that
are equal are one vector with a multiplicity, so copies cost nothing.

Nulls, zero vectors, vectors with null or non-finite parts, and empty lists link with nothing and form their own
component. Vectors of different lengths never link.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import components, forget, stored_at, tidied
from .textscan import mixed

TABLES, PROBES, BLOCK = 12, 3, 1024
BITS, RUN = 128, 1 << 14


def width_for(vectors: int, axes: int) -> int:
    """Hashes in a key, so that most keys of unrelated vectors have one vector."""
    return int(np.clip(np.ceil(np.log(8 * max(vectors, 2)) / np.log(2 * axes)), 1, 6))


def hadamard(x: np.ndarray) -> np.ndarray:
    """The transform of each row; the length is a power of two."""
    n, d = x.shape
    step = 1
    while step < d:
        x = x.reshape(n, d // (2 * step), 2, step)
        x = np.stack([x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]], axis=2).reshape(n, d)
        step *= 2
    return x / np.sqrt(d)


def keys(unit: np.ndarray, width: int, tables: int = TABLES, probes: int = PROBES, seed: int = 3) -> np.ndarray:
    """rows x tables x probes keys, the table's number mixed in."""
    n, d = unit.shape
    full = 1 << max(1, int(np.ceil(np.log2(max(d, 2)))))
    padded = np.zeros((n, full))
    padded[:, :d] = unit
    rng = np.random.default_rng(seed)
    out = np.zeros((n, tables, probes), np.uint64)
    rows = np.arange(n)
    for t in range(tables):
        best, axis, lost, other = [], [], [], []
        for _ in range(width):
            y = padded
            for _ in range(3):
                y = hadamard(y * rng.choice([-1.0, 1.0], full))
            size = np.abs(y)
            order = np.argpartition(-size, min(2, full - 1), axis=1)[:, : min(3, full)]
            order = np.take_along_axis(order, np.argsort(-np.take_along_axis(size, order, 1), axis=1), 1)
            code = (2 * order + (np.take_along_axis(y, order, 1) < 0)).astype(np.uint64)
            top = np.take_along_axis(size, order, 1)
            best.append(code[:, 0])
            for c in range(1, order.shape[1]):
                axis.append(len(best) - 1)
                lost.append(top[:, 0] - top[:, c])
                other.append(code[:, c])
        best, lost, other = np.array(best), np.array(lost), np.array(other)
        near = np.argsort(lost, axis=0, kind="stable")[: probes - 1]
        for p in range(probes):
            own = best.copy()
            if p:
                pick = near[min(p - 1, len(near) - 1)]
                own[np.array(axis)[pick], rows] = other[pick, rows]
            h = np.full(n, 1469598103934665603 + 7919 * t, np.uint64)
            for part in own:
                h = mixed(h * np.uint64(31) + part + np.uint64(1))
            out[:, t, p] = h
    return out


def _units(col) -> tuple[np.ndarray, list[np.ndarray | None]]:
    """For each row its unit vector, or None where it can have no link."""
    out = []
    for v in col.to_pylist():
        if not v or any(x is None for x in v):
            out.append(None)
            continue
        x = np.array(v, float)
        with np.errstate(over="ignore", invalid="ignore"):
            top = np.abs(x).max()
            size = np.sqrt((x * x).sum())
        out.append(None if not np.isfinite(top) or top == 0 else x / size if np.isfinite(size) and size > 0 else (x / top) / np.sqrt(((x / top) ** 2).sum()))
    return out


def _shape(kind: str):
    """(id, the vector's bytes or null), in the precision that the column has."""

    def go(batches):
        for batch in batches:
            unit = _units(batch.column(1))
            raw = [None if u is None else np.array(v, kind).tobytes() for u, v in zip(unit, batch.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(raw, pa.binary())], names=["vec_id", "raw"])

    return go


def _deal(width: int, tables: int, probes: int, kind: str):
    """(key, node) for each different key of each vector."""

    def go(batches):
        for batch in batches:
            raws = batch.column(1)
            for lo in range(0, len(batch), 1024):
                some = [np.frombuffer(r.as_buffer(), kind).astype(float) for r in raws.slice(lo, 1024)]
                node = batch.column(0).slice(lo, 1024).to_numpy(zero_copy_only=False)
                for d in sorted({len(x) for x in some}):
                    at = [i for i, x in enumerate(some) if len(x) == d]
                    k = keys(unit_rows([some[i] for i in at]), width, tables, probes).reshape(len(at), -1) ^ np.uint64(d)
                    k.sort(axis=1)
                    fresh = np.ones(k.shape, bool)
                    fresh[:, 1:] = k[:, 1:] != k[:, :-1]
                    row, col = np.nonzero(fresh)
                    yield pa.RecordBatch.from_arrays([pa.array(k[row, col].view(np.int64)), pa.array(node[at][row])], names=["key", "node"])

    return go


def unit_rows(vectors: list[np.ndarray]) -> np.ndarray:
    x = np.array(vectors)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def sketches(unit: np.ndarray, seed: int = 7) -> np.ndarray:
    """rows x 2 words with the sides of BITS random hyperplanes that each vector lies on."""
    planes = np.random.default_rng([seed, unit.shape[1]]).standard_normal((unit.shape[1], BITS))
    return np.packbits(unit @ planes > 0, axis=1).view(np.uint64)


def sketch_cut(line: float, loss: float = 1e-9) -> int:
    """The most sketch bits in which two vectors at this cosine differ, but for a chance under loss."""
    p = float(np.arccos(np.clip(line, -1.0, 1.0)) / np.pi)
    beyond, cut = 0.0, BITS
    while cut > 4 and beyond + math.comb(BITS, cut) * p**cut * (1 - p) ** (BITS - cut) < loss:
        beyond += math.comb(BITS, cut) * p**cut * (1 - p) ** (BITS - cut)
        cut -= 1
    return cut


def _sketched(kind: str):
    """The rows of the nodes, with their sketches."""

    def go(batches):
        for batch in batches:
            some = [np.frombuffer(r.as_buffer(), kind).astype(float) for r in batch.column("raw")]
            words = np.zeros((len(some), 2), np.uint64)
            for d in sorted({len(x) for x in some}):
                at = [i for i, x in enumerate(some) if len(x) == d]
                words[at] = sketches(unit_rows([some[i] for i in at]))
            both = words.view(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(both[:, 0].copy()), pa.array(both[:, 1].copy())], names=[*batch.schema.names, "s0", "s1"])

    return go


def _lists(column) -> np.ndarray:
    """Sorted lists of keys as the rows of a table, filled up with the greatest number."""
    column = column.combine_chunks()
    size = pc.list_value_length(column).to_numpy(zero_copy_only=False)
    out = np.full((len(size), int(size.max())), np.iinfo(np.int64).max)
    out[np.arange(out.shape[1])[None, :] < size[:, None]] = column.flatten().to_numpy(zero_copy_only=False)
    return out


def _least_at(lists: np.ndarray, a: np.ndarray, b: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Whether each key is the least of those that both nodes of the pair have; it is one of them."""
    least = np.full(len(a), np.iinfo(np.int64).max)
    ta, tb = lists[a], lists[b]
    open_ = np.ones(len(a), bool)
    for c in range(lists.shape[1]):
        i = np.flatnonzero(open_ & (ta[:, c] <= key))
        if not len(i):
            break
        hit = i[(tb[i] == ta[i, c : c + 1]).any(1)]
        least[hit] = ta[hit, c]
        open_[hit] = False
    return least == key


def _meetings(key: np.ndarray, side: np.ndarray, grid):
    """Runs of (row, row): the pairs of a task's rows, sorted by key, that share a key; those of long keys only where
    grid(rows, rows) says so. Side 2 meets its own kind, side 0 meets side 1."""
    cuts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    length = np.diff(np.concatenate([cuts, [len(key)]]))
    group = np.repeat(np.arange(len(cuts)), length)
    index = np.flatnonzero((length <= 24)[group] & (side == 2))
    for gap in range(1, 24):
        index = index[index + gap < len(key)]
        index = index[group[index + gap] == group[index]]
        for o in range(0, len(index), RUN):
            yield index[o : o + RUN], index[o : o + RUN] + gap
    for c, n in zip(cuts.tolist(), length.tolist(), strict=True):
        s = side[c : c + n]
        same = bool((s == 2).all())
        if n <= 24 and same:
            continue
        rows = np.arange(c, c + n)
        one, two = (rows, rows) if same else (rows[s == 0], rows[s == 1])
        for lo in range(0, len(one), 256):
            i, j = np.nonzero(grid(one[lo : lo + 256], two))
            x, y = one[lo : lo + 256][i], two[j]
            if same:
                x, y = x[x < y], y[x < y]
            for o in range(0, len(x), RUN):
                yield x[o : o + RUN], y[o : o + RUN]


def _sift(cut: int):
    """Of the keys dealt to a task, or two blocks of one key, the rows whose vector may link with another's there: their
    sketches differ in cut bits at most, and they share no lesser key."""

    def go(t):
        t = t.sort_by("key")
        key, node, side = (t.column(c).to_numpy() for c in ("key", "node", "side"))
        s0, s1 = (t.column(c).to_numpy().view(np.uint64) for c in ("s0", "s1"))
        _, back, at = np.unique(node, return_index=True, return_inverse=True)
        lists = _lists(t.column("keys").take(pa.array(back)))
        keep = np.zeros(len(key), bool)
        grid = lambda x, y: np.bitwise_count(s0[x, None] ^ s0[y]).astype(np.int16) + np.bitwise_count(s1[x, None] ^ s1[y]) <= cut
        for x, y in _meetings(key, side, grid):
            new = ~(keep[x] & keep[y])
            x, y = x[new], y[new]
            near = np.bitwise_count(s0[x] ^ s0[y]).astype(np.int16) + np.bitwise_count(s1[x] ^ s1[y]) <= cut
            x, y = x[near], y[near]
            here = _least_at(lists, at[x], at[y], key[x])
            keep[x[here]] = keep[y[here]] = True
        return t.select(["p", "q", "key", "node", "side", "blocks"]).filter(pa.array(keep))

    return go


def _compare(line: float, kind: str):
    """For the keys dealt to a task, or two blocks of one key: (0, node, links found here), (1, least node, node)."""

    def go(t):
        t = t.sort_by("key")
        key, node, side, many = (t.column(c).to_numpy() for c in ("key", "node", "side", "many"))
        name, back, at = np.unique(node, return_index=True, return_inverse=True)
        raws, lists = t.column("raw").take(pa.array(back)), _lists(t.column("keys").take(pa.array(back)))
        some = [np.frombuffer(x.as_buffer(), kind).astype(float) for x in raws]
        vec = np.zeros((len(name), max(map(len, some))))
        for d in {len(x) for x in some}:
            rows = [i for i, x in enumerate(some) if len(x) == d]
            vec[rows, :d] = unit_rows([some[i] for i in rows])
        weight = np.zeros(len(name), np.int64)
        weight[at] = many
        count, edge_a, edge_b = np.zeros(len(name), np.int64), [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for x, y in _meetings(key, side, lambda x, y: vec[at[x]] @ vec[at[y]].T >= line - 1e-9):
            a, b, k = at[x], at[y], key[x]
            sure = np.einsum("ij,ij->i", vec[a], vec[b]) >= line
            a, b, k = a[sure], b[sure], k[sure]
            here = _least_at(lists, a, b, k)
            a, b = a[here], b[here]
            np.add.at(count, a, weight[b])
            np.add.at(count, b, weight[a])
            edge_a.append(np.minimum(a, b))
            edge_b.append(np.maximum(a, b))
            if sum(map(len, edge_a)) > 1 << 18:
                x2, y2 = _forest(np.concatenate(edge_a), np.concatenate(edge_b))
                edge_a[:], edge_b[:] = [x2], [y2]
        low, far = _forest(np.concatenate(edge_a), np.concatenate(edge_b))
        hit = np.flatnonzero(count)
        return pa.table({"kind": np.concatenate([np.zeros(len(hit), np.int32), np.ones(len(far), np.int32)]), "a": np.concatenate([name[hit], name[low]]), "b": np.concatenate([count[hit], name[far]])})

    return go


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges (least node, node) with the same components as the given ones."""
    nodes, flat = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = flat[: len(a)], flat[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, x, low)
        np.minimum.at(new, y, low)
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    far = np.flatnonzero(label != np.arange(len(nodes)))
    return nodes[label[far]], nodes[far]


def _slot(rows: int, each: int) -> Column:
    """The task of a key: its own where the key has several blocks, else one of enough that each has about so many rows."""
    return F.when(F.col("blocks") > 1, F.col("key")).otherwise(F.pmod(F.xxhash64("key"), F.lit(max(1, rows // each)))).alias("slot")


def near_vectors(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", line: float = 0.95, tables: int = TABLES, probes: int = PROBES) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row."""
    # vectors move in the precision that they have, and are compared in double
    kind = "<f4" if vectors.schema[vec_col].dataType.simpleString() == "array<float>" else "<f8"
    each = np.dtype(kind).itemsize
    rows, rows_at = stored_at(vectors.select(F.col(id_col).cast("bigint").alias("vec_id"), F.col(vec_col).alias("v")).mapInArrow(tidied(_shape(kind)), "vec_id bigint, raw binary"), "vectors")
    # equal vectors are one node, named by their least id
    groups = rows.where("raw is not null").groupBy("raw").agg(F.min("vec_id").alias("node"), F.count("*").alias("many"))
    nodes, nodes_at = stored_at(groups, "nodes")
    count, longest = nodes.agg(F.count("*"), F.max(F.length("raw"))).first()
    width = width_for(count, max(2, (longest or 16) // each))
    tables += 6 * max(0, width - 3)
    dealt, dealt_at = stored_at(nodes.select("node", "raw").mapInArrow(tidied(_deal(width, tables, probes, kind)), "key bigint, node bigint"), "dealt")
    # keys of one vector go; the others' vectors are cut into blocks, and every pair of blocks meets once
    full, full_at = stored_at(dealt.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select(F.col("key").alias("k0"), F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks")), "keys")
    alive, alive_at = stored_at(dealt.join(full, F.col("key") == F.col("k0")).select("key", "node", "blocks"), "alive")
    own = nodes.join(alive.groupBy(F.col("node").alias("n0")).agg(F.sort_array(F.collect_list("key")).alias("keys")), F.col("node") == F.col("n0")).select("n0", "raw", "many", "keys")
    own, own_at = stored_at(own.mapInArrow(tidied(_sketched(kind)), "n0 bigint, raw binary, many bigint, keys array<bigint>, s0 bigint, s1 bigint"), "own")
    # ids, keys and sketches meet first; vectors go only to the keys where a pair of sketches is near
    placed = alive.join(own.select("n0", "keys", "s0", "s1"), F.col("node") == F.col("n0")).withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    meets = placed.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")).select(
        _slot(alive.count(), 65_536), F.least("mine", "other").alias("p"), F.greatest("mine", "other").alias("q"), "key", "node", "blocks", "keys", "s0", "s1",
        F.when(F.col("mine") == F.col("other"), 2).when(F.col("mine") < F.col("other"), 0).otherwise(1).alias("side"))
    near, near_at = stored_at(meets.groupBy("slot", "p", "q").applyInArrow(_sift(sketch_cut(line)), "p int, q int, key bigint, node bigint, side int, blocks int"), "near")
    heavy = near.join(own.select("n0", "raw", "many", "keys"), F.col("node") == F.col("n0")).select(_slot(near.count(), 16_384), "p", "q", "key", "node", "side", "raw", "many", "keys")
    found, found_at = stored_at(heavy.groupBy("slot", "p", "q").applyInArrow(_compare(line, kind), "kind int, a bigint, b bigint"), "met")
    comp = components(found.where("kind = 1").select("a", "b").distinct())
    links = found.where("kind = 0").groupBy(F.col("a").alias("n1")).agg(F.sum("b").alias("links"))
    out = (nodes.join(links, F.col("node") == F.col("n1"), "left").join(comp.select(F.col("node").alias("n2"), "comp"), F.col("node") == F.col("n2"), "left")
           .select(F.col("raw").alias("r0"), F.col("many"), F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("comp", "node").alias("comp")))
    out, _ = stored_at(out, "named")
    forget(vectors.sparkSession, nodes_at, dealt_at, full_at, alive_at, own_at, near_at, found_at)
    return (rows.join(out, F.col("raw") == F.col("r0"), "left")
            .select("vec_id", F.coalesce(F.col("links") + F.col("many") - 1, F.lit(0)).cast("bigint").alias("n_links"), F.coalesce("comp", "vec_id").alias("component_id"))
            .withColumn("kept", F.col("vec_id") == F.col("component_id")))
