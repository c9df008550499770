"""Each method against a plain version of itself, on small inputs."""

import math
import random
from functools import lru_cache

import numpy as np
import pytest

from subsetheavy.llm import decontamination as dc
from subsetheavy.llm import embeddings as em
from subsetheavy.llm import packing as pk
from subsetheavy.llm import quality as qu
from subsetheavy.llm import secrets as sc
from subsetheavy.llm import urls as ur


def test_best_fit_equals_a_plain_one():
    rng = random.Random(1)
    for lengths in ((8, 16, 32), (4, 32), (16,)):
        for _ in range(30):
            sizes = sorted((rng.randrange(1, lengths[-1] + 1) for _ in range(rng.randrange(1, 40))), reverse=True)
            plans = []
            for most in lengths:
                left, bins = sum(sizes), []
                for n in sizes:
                    fits = [b for b in bins if b[0] - b[1] >= n]
                    if fits:
                        best = min(fits, key=lambda b: b[0] - b[1])
                    else:
                        may = [c for c in lengths if n <= c <= most] or [min(c for c in lengths if c >= n)]
                        best = [min(may, key=lambda c: (pk.bin_cost(c) / min(c, left), c)), 0]
                        bins.append(best)
                    best[1] += n
                    left -= n
                plans.append(sum(pk.bin_cost(min(c for c in lengths if c >= used)) for _, used in bins))
            got, where, _, final = pk.pack(np.array(sizes), lengths)
            assert math.isclose(got, min(plans)) and math.isclose(got, sum(map(pk.bin_cost, final.tolist())))
            assert all(sum(s for s, w in zip(sizes, where) if w == b) <= final[b] for b in range(len(final)))


def test_trees_equal_a_walk():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 6)).astype(np.float32)
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.3)).astype(float)
    trees = qu.grow(x, y, trees=20, depth=3)
    inner = trees.feature.shape[1]

    def walk(row):
        total = trees.base
        for t in range(len(trees.feature)):
            at = 0
            while at < inner:
                at = 2 * at + (2 if row[trees.feature[t, at]] > trees.threshold[t, at] else 1)
            total += trees.leaf[t, at - inner]
        return total

    margin = trees.margins(x)
    assert np.allclose(margin, [walk(r) for r in x]) and ((margin > 0) == (y > 0)).mean() > 0.95


def test_alignment_equals_a_plain_table():
    rng = random.Random(4)
    words = [f"w{i}" for i in range(12)]

    def plain(a, b):
        """The best local score cell by cell: 2 for a match, 1 off for a change or a gap."""
        best, table = 0, [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(1, len(a) + 1):
            for j in range(1, len(b) + 1):
                table[i][j] = max(0, table[i - 1][j - 1] + (2 if a[i - 1] == b[j - 1] else -1), table[i - 1][j] - 1, table[i][j - 1] - 1)
                best = max(best, table[i][j])
        return best / (2 * len(b))

    for _ in range(40):
        item = [rng.choice(words) for _ in range(rng.randrange(6, 14))]
        text = [rng.choice(words) for _ in range(8)] + [w for w in item if rng.random() > 0.15] + [rng.choice(words) for _ in range(8)]
        items = dc.Items([1], [" ".join(item)])
        _, _, data, offs = next(dc.ts.runs(dc.pa.array([" ".join(text)])))
        got = dc.leaks(items, *dc.words(data, offs), 0.05)
        seeds = {tuple(item[i : i + 3]) for i in range(len(item) - 2)} & {tuple(text[i : i + 3]) for i in range(len(text) - 2)}
        assert bool(got) == bool(seeds and plain(text, item) >= 0.05)
        if got:
            assert got[0][2] <= plain(text, item) + 1e-9


def test_guess_cost_equals_all_segmentations():
    rng = random.Random(6)
    words = sc._RANK

    def plain(value):
        spans = list(sc._spans(value, words))
        each = math.log10(max(sc._alphabet(value), 10))

        @lru_cache(None)
        def best(at, count, brute):
            """Least cost of the rest; brute: whether the span before is brute force and may go on."""
            if at == len(value):
                return sc._ORDERS[count] if count < 13 else math.inf
            if count > 12:
                return math.inf
            ways = [best(at + 1, count + (not brute), True) + each]
            ways += [cost + best(end, count + 1, False) for end, cost in spans[at]]
            return min(ways)

        return best(0, 0, False)

    for _ in range(150):
        value = "".join(rng.choice(["password", "2019", "aaa", "qwe", "abc", "x", "7", "$", "Love"]) for _ in range(rng.randrange(1, 5)))
        assert math.isclose(sc.guess_cost(value), plain(value), abs_tol=1e-9)


def test_base_spans_equal_the_patterns():
    import re

    rng = random.Random(7)
    parts = ["password", "Secret", "api_key", "apikey", "token", " = ", ":", "=", '"', "abc123", "AKIA", "ABCDEFGH12345678", "0123456789abcdef", "deadbeefdeadbeef", " ", "\n", "é", "x"]
    for _ in range(500):
        t = "".join(rng.choice(parts) for _ in range(rng.randrange(14)))
        want = [("assign", m.start(), m.end()) for m in re.finditer(r"""(?i:(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?)([A-Za-z0-9+/_.=-]+)""", t) if len(m.group(2)) >= 6]
        want += [("access", m.start(), m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m.group()) >= 20]
        want += [("hex", m.start(), m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m.group()) >= 24]
        assert sorted(x for x in sc.find(t) if x[0] != "guess") == sorted(want)


def test_pair_term_finds_what_no_additive_weight_can(spark):
    """Insult words and group words are each as frequent among clean texts as among toxic ones; only together they tell."""
    import zlib

    from subsetheavy.llm.toxicity import toxicity_scores

    rng = random.Random(8)
    fill = [f"word{i}" for i in range(60)]
    rows, want = [], {}
    for i in range(900):
        kind = i % 4
        words = [rng.choice(fill) for _ in range(12)]
        if kind & 1:
            words.insert(rng.randrange(12), "vermin")
        if kind & 2:
            words.insert(rng.randrange(12), "outlanders")
        rows.append((i, " ".join(words)))
        want[i] = int(kind in (0, 3))  # both or none: the two words' own weights can't tell
    labels = spark.createDataFrame([(i, None, y) for i, y in want.items()], "doc_id bigint, quality int, toxic int")
    got = {r["doc_id"]: r["predicted"] for r in toxicity_scores(spark.createDataFrame(rows, "doc_id bigint, text string"), labels).collect()}
    held = [i for i in want if zlib.crc32(str(i).encode()) % 3 == 1]
    right = sum(got[i] == want[i] for i in held) / len(held)
    assert right > 0.75, right


@pytest.mark.parametrize("vectors,parts", [(50_000, 32), (1_000_000, 64), (1_000_000_000, 128)])
def test_recall_of_keys(vectors, parts):
    """Vectors at the line share a key at the widths that tables of any size get."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(1500, parts))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    side = rng.normal(size=x.shape)
    side -= (side * x).sum(1, keepdims=True) * x
    side /= np.linalg.norm(side, axis=1, keepdims=True)
    y = 0.951 * x + math.sqrt(1 - 0.951**2) * side
    width = em.width_for(vectors, parts)
    tables = em.TABLES + 6 * max(0, width - 3)
    a, b = (em.keys(v, width, tables).reshape(len(x), -1) for v in (x, y))
    met = np.array([len(np.intersect1d(p, q)) > 0 for p, q in zip(a, b)])
    assert met.mean() >= 0.98


def test_vectors_equal_brute_force(spark):
    rng = np.random.default_rng(5)
    base = rng.normal(size=(60, 24))
    rows = np.concatenate([base + s * rng.normal(size=base.shape) for s in (0, 0.05, 0.1, 0.2, 0.25)]).astype(np.float32)
    got = {r["vec_id"]: r for r in em.near_vectors(spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(rows)], "vec_id bigint, embedding array<float>")).collect()}
    x = rows.astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    hit = (x @ x.T >= 0.95) & ~np.eye(len(x), dtype=bool)
    found = np.array([got[i]["n_links"] for i in range(len(x))])
    assert (found <= hit.sum(1)).all() and found.sum() >= 0.95 * hit.sum() > 0


def test_many_entries_and_equal_digests(monkeypatch):
    hosts = [f"h{i}.example{i % 7}.net" for i in range(1_000_000)]
    held = ur.Filter(ur.pack((), hosts))
    assert len(held.digests) == 1_000_000 and (np.diff(held.digests.astype(object)) >= 0).all()
    asked = [("a.h77.example0.net", "/x"), ("h999999.example0.net", ""), ("nothing.example", "/"), ("h5.example5.net", "/")]
    assert [ok for _, ok in held.judge(asked)] == [h not in ("h77.example0.net",) and not any(("." + h).endswith("." + e) for e in (hosts[77], hosts[999_999], hosts[5])) for h, _ in asked]
    # every digest the same: the stored strings decide alone
    monkeypatch.setattr(ur.xxhash, "xxh64_intdigest", lambda b: 7)
    few = ur.Filter(ur.pack((("org", "/", True), ("x.org", "/b", False)), hosts[:50]))
    assert few.judge([("q.x.org", "/b"), ("y.org", "/b"), ("h3.example3.net", "/"), ("h3.example4.net", "/")]) == [("x.org/b", False), ("org/", True), (None, False), (None, True)]


def test_rank_order_distance_equals_a_plain_one():
    from collections import Counter

    from subsetheavy.llm import language as la

    rng = random.Random(11)
    words = {"aa": ["bala", "mata", "kaba", "tala"], "ii": ["miri", "tiki", "siri", "nini"], "ou": ["boulo", "mouto", "kala", "toro"]}

    def order(text, top):
        return [g for g, _ in sorted(Counter(la.grams([text])[0].tolist()).items(), key=lambda x: (-x[1], x[0]))][:top]

    profiles = {k: order(" ".join(rng.choice(w) for _ in range(200)), 60) for k, w in words.items()}
    judge = la.Ranks({k: np.array(v, np.int64) for k, v in profiles.items()}, 60)
    texts = [" ".join(rng.choice(words[rng.choice(list(words))]) for _ in range(rng.randrange(1, 15))) for _ in range(80)] + ["", "12 !?"]
    for text, (name, score) in zip(texts, judge.judge(texts), strict=True):
        own = order(text, 60)
        if not own:
            assert (name, score) == ("und", 0.0)
            continue
        far = {k: sum(abs(v.index(g) - r) if g in v else 60 for r, g in enumerate(own)) for k, v in profiles.items()}
        assert far[name] == min(far.values()) and math.isclose(score, 1 - far[name] / (60 * len(own)))


def test_sketches_of_links_are_within_the_cut():
    rng, cut = np.random.default_rng(5), em.sketch_cut(0.95)
    for axes in (3, 64, 768):
        a = em.unit_rows(list(rng.standard_normal((4000, axes))))
        far = rng.standard_normal((4000, axes))
        far = em.unit_rows(list(far - (far * a).sum(1, keepdims=True) * a))
        b = 0.95 * a + np.sqrt(1 - 0.95**2) * far  # cosine 0.95 sharp
        apart = lambda x, y: np.bitwise_count(em.sketches(x) ^ em.sketches(y)).sum(1)
        assert apart(a, b).max() <= cut
        assert np.mean(apart(a, far) <= cut) < 0.01
    assert em.sketch_cut(1.0) >= 4 and em.sketch_cut(-1.0) == em.BITS


def test_vectors_in_blocks_and_chains_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(em, "BLOCK", 16)
    rng = np.random.default_rng(8)
    base = rng.standard_normal((6, 32))
    rows = np.concatenate([base[rng.integers(0, 6, 300)] + rng.standard_normal((300, 32)) * 0.16, rng.standard_normal((100, 32))]).astype(np.float32)
    unit = em.unit_rows(list(rows.astype(float)))
    want = (unit @ unit.T >= 0.95).sum(1) - 1
    got = {r["vec_id"]: r["n_links"] for r in em.near_vectors(spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(rows)], "vec_id bigint, embedding array<float>")).collect()}
    assert want.sum() > 2000
    assert all(got[i] <= want[i] for i in range(len(rows)))
    assert sum(got.values()) >= 0.98 * want.sum()


def test_benchmark_blocks_share_scans(spark, monkeypatch):
    rng = random.Random(21)
    vocabulary = [f"w{i}" for i in range(400)]
    items = [(i, " ".join(rng.choice(vocabulary) for _ in range(20))) for i in range(24)]
    texts = [" ".join(rng.choice(vocabulary) for _ in range(40)) for _ in range(40)]
    for i in range(0, 24, 2):
        own = items[i][1].split()
        own[7] = "changed"
        texts[i] += " " + " ".join(own) + " end"
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    bench = spark.createDataFrame(items, "item_id bigint, text string").coalesce(1)
    want = sorted(map(tuple, dc.benchmark_leaks(docs, bench).collect()))
    assert [(d, i) for d, i, *_ in want] == [(i, i) for i in range(0, 24, 2)]
    left = sorted(r["doc_id"] for r in dc.clean_docs(docs, bench).collect())
    assert left == [i for i in range(40) if i >= 24 or i % 2]
    monkeypatch.setattr(dc, "BLOCK", 40)
    monkeypatch.setattr(dc, "BLOCKS", 5)
    found = dc.benchmark_leaks(docs, bench)
    blocks = sum(1 for _ in dc._blocks(bench))
    assert blocks > 5
    assert found._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == -(-blocks // 5)
    assert sorted(map(tuple, found.collect())) == want
    assert sorted(r["doc_id"] for r in dc.clean_docs(docs, bench).collect()) == left
