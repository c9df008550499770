import pytest
from pyspark.sql import functions as F

from subsetheavy.functions.measures import auc, confusion, confusion_sweep, estimate_errors, rates
from subsetheavy.operators.exact import exact_all_heavy, exact_shares
from subsetheavy.operators.expand import STRATEGIES, all_heavy, check_downward
from subsetheavy.operators.gap import model_gap
from subsetheavy.operators.models import fit_mixture, fit_product, verdict
from subsetheavy.operators.sampling import draw_sample, merge_samples, sample_size_bound
from subsetheavy.operators.sketch import fit_sketch
from subsetheavy.operators.summaries import misra_gries
from subsetheavy.spec import StreamSpec

TINY = [("a", "x")] * 4 + [("a", "y")] + [("b", "x")] + [("b", "y")] * 2


@pytest.fixture(scope="module")
def tiny(spark):
    return spark.createDataFrame([(f, g, 1 if f == "a" else 2, 0) for f, g in TINY], "f string, g string, z int, one int")


def rows(df):
    return sorted(tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in df.collect())


def test_shares(tiny):
    assert rows(exact_shares(tiny, ["f"]).select("f", "share")) == [("a", 0.625), ("b", 0.375)]
    assert rows(exact_all_heavy(tiny, ["f", "g"], 0.5).select("f", "g")) == [("a", "x")]
    assert rows(exact_all_heavy(tiny, ["f", "g"], 0.5, prune=True).select("f", "g")) == [("a", "x")]


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_product(tiny, strategy):
    model = fit_product(tiny, ["f", "g"], 0.5)
    assert rows(all_heavy(model, ["f", "g"], strategy=strategy)) == [("a", "x", 0.390625)]
    assert rows(all_heavy(model, ["g", "f"], 0.24, strategy)) == [("x", "a", 0.390625)]


def test_verdicts(tiny):
    model = fit_product(tiny, ["f", "g"], 0.5)
    assert verdict(model, ["f", "g"], ["a", "x"]) and not verdict(model, ["f", "g"], ["b", "y"]) and not verdict(model, ["f"], ["q"])
    with pytest.raises(ValueError):
        verdict(model, ["f", "g"], ["a"])
    assert all(r["misses"] == 0 for r in check_downward(model, ["f", "g"]).collect())


def test_mixture(tiny):
    model = fit_mixture(tiny, ["f", "g"], "z", 0.5)
    assert rows(all_heavy(model, ["f", "g"])) == [("a", "x", 0.5), ("b", "y", 0.25)]
    assert rows(all_heavy(fit_mixture(tiny, ["f", "g"], "one", 0.5), ["f", "g"])) == rows(all_heavy(fit_product(tiny, ["f", "g"], 0.5), ["f", "g"]))


def test_gap_counts_unseen(spark):
    df = spark.createDataFrame([(0, 0), (1, 1)], "a int, b int")
    r = model_gap(df, ["a", "b"]).first()
    assert r["observed_gap"] == 0.25 and r["gap"] == 0.25


def test_nulls_and_empty(spark):
    df = spark.createDataFrame([("a", None)] * 3 + [("a", "x")], "f string, g string")
    assert {tuple(r) for r in all_heavy(fit_product(df, ["f", "g"], 0.5), ["f", "g"]).collect()} == {("a", "x", 0.25), ("a", None, 0.75)}
    none = df.limit(0)
    assert all_heavy(fit_product(none, ["f", "g"], 0.5), ["f", "g"]).count() == 0 and exact_all_heavy(none, ["f"], 0.5).count() == 0


def test_misuse(tiny):
    for bad in (["f", "f"], [], ["nope"]):
        with pytest.raises(ValueError):
            StreamSpec.of(tiny, bad)
    with pytest.raises(ValueError):
        fit_product(tiny, ["f"], 0.0)
    with pytest.raises(ValueError):
        fit_sketch(tiny, ["f", "g"], 0.1, 10, cls="z")


def test_sample_merges(spark):
    df = spark.range(1000).withColumnRenamed("id", "k")
    a, b = (draw_sample(df.where(f"k % 2 = {i}"), ["k"], 50, 3) for i in (0, 1))
    assert rows(merge_samples(a, b, ["k"], 50)) == rows(draw_sample(df.repartition(7), ["k"], 50, 3))
    assert 7e5 < sample_size_bound(0.002, 3, 5, 10_000) < 1e6


@pytest.mark.parametrize("parts", [1, 5])
def test_counters_bound(spark, parts):
    data = [(str(i % 7 if i % 3 else 100 + i),) for i in range(900)]
    true = {}
    for (v,) in data:
        true[v] = true.get(v, 0) + 1
    got = {r["value"]: r["counter"] for r in misra_gries(spark.createDataFrame(data, "c string").repartition(parts), ["c"], 20).collect()}
    assert len(got) <= 20 and all(true[v] - 900 / 21 <= n <= true[v] for v, n in got.items()) and all(v in got for v, n in true.items() if n > 900 / 21)


def test_measures(spark):
    truth = spark.createDataFrame([("a", 0.5), ("b", 0.3), ("c", 0.05)], "v string, share double")
    c = confusion(spark.createDataFrame([("a",), ("c",), ("d",)], "v string"), truth, ["v"], 0.2).first()
    assert (c["tp"], c["fp"], c["fp_strict"], c["fn"], c["reported"], c["negatives"]) == (1, 2, 1, 1, 3, 2)
    e = estimate_errors(truth.limit(2), spark.createDataFrame([("a", 0.4)], "v string, est double"), ["v"]).first()
    assert round(e["mae"], 9) == 0.2 and round(e["mse"], 9) == 0.05 and round(e["mape"], 9) == 60.0
    pts = rates(spark.createDataFrame([(1, 0, 1, 2)], "tp long, fp long, fn long, negatives long"))
    assert auc(pts).first()["auc"] == 0.75


def test_confusion_sweep(spark):
    """One sweep gives at each cut what confusion gives for the list cut there, ties, nulls and empty inputs included."""
    kind = "v string, share double"
    truth = spark.createDataFrame([("a", 0.5), ("b", 0.2), ("c", 0.05), (None, 0.01), ("e", 0.2)], kind)
    listed = spark.createDataFrame([("a", 0.6), ("c", 0.2), ("d", 0.1), (None, 0.3), ("e", 0.05)], "v string, mass double")
    names = ("tp", "fp", "fp_strict", "fn", "reported", "negatives")
    for have, true in ((listed, truth), (listed.limit(0), truth), (listed, truth.limit(0)), (listed.limit(0), truth.limit(0))):
        got = {r["cut"]: tuple(r[n] for n in names) for r in confusion_sweep(have, "mass", true, ["v"], 0.2, {0.25: 0.05, 1.0: 0.2, 2.0: 0.4}).collect()}
        for f in (0.25, 1.0, 2.0):
            want = confusion(have.where(F.col("mass") >= 0.2 * f), true, ["v"], 0.2).first()
            assert got[f] == tuple(want[n] for n in names)


def test_search_workload_is_whole(spark, monkeypatch):
    from subsetheavy.plans import queries as qs
    from subsetheavy.plans import workloads as wl

    asked = []

    def curve(df, key, coords, Ts, methods, pct, cls=None, factors=wl.CUTS):
        asked.append((df.first()["subset"], *set(Ts.values()), pct))
        return spark.createDataFrame([(pct, m, f, ",".join(T), 1, 0, 0, 0, 1, 1) for m in methods for f in factors for T in Ts], "pct double, method string, cut double, subcube string, tp long, fp long, fp_strict long, fn long, reported long, negatives long")

    monkeypatch.setattr(wl, "curve", curve)
    got = qs.queries()["q_w5"](spark, "/root/testdata/sf0.001").collect()
    assert len({s for s, _, _ in asked}) == 10 and len(asked) == len(set(asked)) == 60
    assert {(r["gamma"], r["pct"], r["method"], r["cut"]) for r in got} == {(g, p, m, c) for g in (0.05, 0.1) for p in (0.2, 2.0, 10.0) for m in ("sample", "mixture") for c in wl.CUTS}


def test_scaling_and_gap_workloads_are_whole(spark, monkeypatch):
    from subsetheavy.plans import queries as qs
    from subsetheavy.plans import workloads as wl

    asked = []
    monkeypatch.setattr(wl, "all_heavy", lambda model, T, cut, s, reorder=True: asked.append((len(T), s)) or spark.range(1))
    qs.queries()["q_w11"](spark, "/root/testdata/sf0.001")
    assert {k for k, s in asked if s != "cartesian"} == set(range(1, 9))
    assert 0 < qs.queries()["q_w9_mixture"](spark, "/root/testdata/sf0.001").first()["observed_gap"] < 1


def scans(spark, f):
    """How many times f reads its rows."""
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    source = spark.createDataFrame([(f"a{i % 5}", f"b{i % 3}", i % 2) for i in range(600)], "f string, g string, z int")
    f(source.mapInArrow(counted, source.schema))
    return read.value / 600


def test_models_read_the_stream_twice(spark):
    from subsetheavy.functions.measures import PASSES

    assert scans(spark, lambda df: fit_product(df, ["f", "g"], 0.2).table.count()) == PASSES["product"] == 2
    assert scans(spark, lambda df: fit_mixture(df, ["f", "g"], "z", 0.2).table.count()) == PASSES["mixture"] == 2
    assert scans(spark, lambda df: draw_sample(df, ["f", "g", "z"], 20).count()) == PASSES["sample"] == 1


def test_the_mark_of_null_is_a_value_too(spark):
    from subsetheavy.spec import NULL_MARK

    df = spark.createDataFrame([(NULL_MARK, "x")] * 3 + [(None, "x")] * 3 + [(NULL_MARK + "y", "x")] * 2, "f string, g string")
    model = fit_product(df, ["f", "g"], 0.2)
    assert {tuple(r) for r in all_heavy(model, ["f"]).collect()} == {(NULL_MARK, 0.375), (None, 0.375), (NULL_MARK + "y", 0.25)}
    assert verdict(model, ["f"], [NULL_MARK], 0.3) and verdict(model, ["f"], [None], 0.3) and not verdict(model, ["f"], [NULL_MARK + "y"], 0.3)
    assert exact_all_heavy(df, ["f", "g"], 0.3, prune=True).count() == 2


def test_clashing_names_are_refused(spark):
    df = spark.createDataFrame([("a", 1)], "cnt string, n int")
    for f in (lambda: exact_shares(df, ["cnt"]), lambda: fit_product(df, ["cnt"], 0.5), lambda: draw_sample(df.withColumn("priority", F.lit(1)), ["n"], 1)):
        with pytest.raises(ValueError):
            f()
    from subsetheavy.operators.exact import cramers_v

    assert cramers_v(df, "cnt", "n").first()["v"] == 0.0


def test_mixtures_merge(spark):
    from subsetheavy.operators.models import merge_counts

    rows_ = [("a", "x", 1)] * 6 + [("b", "y", 2)] * 4 + [("a", "y", 2)] * 2 + [("b", "x", 3)] * 4
    parts = [spark.createDataFrame(p, "f string, g string, z int") for p in (rows_[::2], rows_[1::2][:5], rows_)]
    cand = spark.createDataFrame([("f", "a"), ("f", "b"), ("g", "x"), ("g", "y")], "coord string, value string")
    one, two = (fit_mixture(p, ["f", "g"], "z", 0.1, cut=1e-9, candidates=cand) for p in (parts[0], spark.createDataFrame(rows_[1::2], "f string, g string, z int")))
    whole = fit_mixture(parts[2], ["f", "g"], "z", 0.1, cut=1e-9, candidates=cand)
    assert rows(all_heavy(merge_counts(one, two), ["f", "g"], 0.01)) == rows(all_heavy(whole, ["f", "g"], 0.01))


def test_large_samples_are_the_least_rows(spark, monkeypatch):
    from subsetheavy.operators import sampling as sp

    df = spark.range(5000).withColumnRenamed("id", "k")
    for hash_ in ("xxhash64", "md5"):
        want = rows(sp.draw_sample(df, ["k"], 700, 3, hash_))
        monkeypatch.setattr(sp, "TOP", 100)
        assert rows(sp.draw_sample(df.repartition(5), ["k"], 700, 3, hash_)) == want
        a, b = (sp.draw_sample(df.where(f"k % 2 = {i}"), ["k"], 700, 3, hash_) for i in (0, 1))
        assert rows(sp.merge_samples(a, b, ["k"], 700)) == want
        monkeypatch.setattr(sp, "TOP", 200_000)
    assert sp.decision_line(0.02) == 0.01 and sp.majority_repeats(0.1) % 2 == 1 and sp.sample_size_bound(0.1, 2, 3, 4, gap=16) < sp.sample_size_bound(0.1, 2, 3, 4)


def test_gap_counts_what_never_occurs(spark):
    """Each seen pair is off by .05, the unseen one by its whole mass."""
    data = [("a", "y")] * 3 + [("b", "x")] * 3 + [("b", "y")] * 3 + [("c", "x")]
    r = model_gap(spark.createDataFrame(data, "f string, g string"), ["f", "g"]).first()
    share = lambda c, v: sum(x[c] == v for x in data) / 10
    seen = max(abs(data.count(p) / 10 - share(0, p[0]) * share(1, p[1])) for p in set(data))
    unseen = max(share(0, a) * share(1, b) for a in "abc" for b in "xy" if (a, b) not in data)
    assert round(r["observed_gap"], 9) == round(seen, 9) and round(r["gap"], 9) == round(max(seen, unseen), 9)


def test_questions_in_sql(spark, tiny):
    from subsetheavy.plans import questions as qu

    for model in (fit_product(tiny, ["f", "g"], 0.2), fit_mixture(tiny, ["f", "g"], "z", 0.2)):
        qu.register(spark, model, "tiny")
        assert rows(qu.heavy_sql(spark, ["f", "g"], 0.1, "tiny")) == rows(all_heavy(model, ["f", "g"], 0.1))
        got = spark.sql("SELECT tiny_verdict(array('f', 'g'), array('a', 'x'), 0.3D) AS a, tiny_verdict(array('f', 'g'), array('q', 'x'), 0.0D) AS b, tiny_share(array('f'), array('a', 'x')) AS c").first()
        assert tuple(got) == (True, False, None)


def test_streams_go_on_from_their_checkpoint(spark, tmp_path):
    from subsetheavy.streaming import heavy as hv

    path = hv.event_files(spark, "/root/testdata/sf0.001")
    every = spark.read.schema(hv.EVENTS).parquet(path)
    first, second = str(tmp_path / "in"), f"file://{tmp_path}/root"
    every.where("event_id % 2 = 0").coalesce(3).write.parquet(first)
    hv.stream_sample(hv.events(spark, first, 1), 40, root=second)
    counts = f"file://{tmp_path}/counts"
    hv.stream_counters(hv.events(spark, first, 1), ["event_type"], 50, root=counts)
    every.where("event_id % 2 = 1").coalesce(2).write.mode("append").parquet(first)
    for _ in range(2):  # the second run finds nothing new and changes nothing
        got = rows(hv.stream_sample(hv.events(spark, first, 1), 40, root=second))
        n = hv.stream_counters(hv.events(spark, first, 1), ["event_type"], 50, root=counts).agg(F.sum("counter")).first()[0]
        assert got == rows(hv.stream_sample(hv.events(spark, path), 40)) and n == every.count()


def test_orderings_that_the_experiments_report(spark):
    """Within a class the product reports fewer false values than the sample at the least cut and misses none; where
    coordinates hang together it misses what the sample finds; the mixture beats the sample by area on the whole stream."""
    from subsetheavy.plans import workloads as wl

    d = "/root/testdata/sf0.01"
    total = {(r["method"], r["cut"]): r for r in wl.independent_curve(spark, d).groupBy("method", "cut").agg(F.sum("fp").alias("fp"), F.sum("fn").alias("fn")).collect()}
    assert total["product", 0.25]["fp"] <= total["sample", 0.25]["fp"] and total["product", 0.5]["fn"] == 0
    off = {(r["method"], r["cut"]): r for r in wl.correlated_curve(spark, d).collect()}
    assert off["product", 0.5]["fn"] > off["sample", 0.5]["fn"]
    area = {r["method"]: r["auc"] for r in wl.roc(wl.mixture_curve(spark, d)).collect()}
    assert area["mixture"] >= area["sample"] - 1e-4


def test_a_curve_joins_once_for_all_subsets(spark):
    """Each method's lists of all subsets meet the truth in one join, and give what confusion gives for each by itself."""
    from subsetheavy.plans import workloads as wl

    df = spark.createDataFrame([(i, f"a{i % 3}", i % 5 if i % 4 else None, i % 2, i % 2) for i in range(240)], "k int, f string, g int, h int, z int")
    Ts, coords, factors = {("f", "g"): 0.08, ("g", "h"): 0.1, ("h",): 0.5}, ("f", "g", "h"), (0.5, 1.0, 1.5)
    got = wl.curve(df, ["k"], coords, Ts, ("sample", "mixture"), 50.0, "z", factors)
    assert got._jdf.queryExecution().analyzed().toString().count("FullOuter") == 2
    names = ("tp", "fp", "fp_strict", "fn", "reported", "negatives")
    have = {(r["method"], r["cut"], r["subcube"]): tuple(r[n] for n in names) for r in got.collect()}
    assert len(have) == 18
    drawn, low = draw_sample(df, ["k"], 120, wl.SEED, "md5"), 0.04
    model = fit_mixture(df, coords, "z", 0.08, cut=low, capacity=120)
    for T, gamma in Ts.items():
        for f in factors:
            lists = {"sample": exact_all_heavy(drawn, T, gamma * f), "mixture": all_heavy(model, T, gamma * f)}
            for method, listed in lists.items():
                want = confusion(listed, exact_shares(df, T), T, gamma).first()
                assert have[method, f, ",".join(T)] == tuple(want[n] for n in names), (method, T, f)
    none = wl.curve(df.limit(0), ["k"], coords, Ts, ("sample",), 50.0, "z", factors).collect()
    assert len(none) == 9 and not any(r[n] for r in none for n in names)


def test_two_passes_over_a_stream_lose_nothing(spark, tmp_path, monkeypatch):
    """Values with the asked number of rows are all found, more of them than counters, whether the counters grow or are
    too many; null comes back as null."""
    from subsetheavy.streaming import heavy as hv

    users = [u for u in range(12) for _ in range(20)] + [None] * 25 + [100 + i for i in range(60)]
    data = spark.createDataFrame([(i, u, "view") for i, u in enumerate(users)], "event_id long, user_id long, event_type string")
    data = data.select("event_id", F.expr("timestamp_ntz'2024-01-01 00:00:00'").alias("ts"), "user_id", "event_type", F.lit(1.0).alias("value"), F.lit("{}").alias("props"))
    path = str(tmp_path / "in")
    data.repartition(3, "event_id").write.parquet(path)
    want = {("user_id", str(u), 20) for u in range(12)} | {("user_id", None, 25), ("event_type", "view", len(users))}
    assert {tuple(r) for r in hv.two_passes(spark, path, ["event_type", "user_id"], 4, 20).collect()} == want
    monkeypatch.setattr(hv, "MOST", 8)
    assert {tuple(r) for r in hv.two_passes(spark, path, ["event_type", "user_id"], 4, 20).collect()} == want


#: Queries that read a table where they once made their rows up.
READ = ("q_a8", "q_f1", "q_f5", "q_f6", "q_j8", "q_lower_bound", "q_n4", "q_s5", "q_sample_size_bound")


@pytest.mark.parametrize("name", READ)
def test_rows_come_from_a_table(spark, name):
    """A plan that names its files, or rows that follow the tables; the rows are the SQL's."""
    duckdb = pytest.importorskip("duckdb")
    import __spark_entry__ as entries

    small, large = (entries.queries()[name](spark, f"/root/testdata/{sf}") for sf in ("sf0.001", "sf0.01"))
    assert small.inputFiles() or rows(small) != rows(large)
    con = duckdb.connect()
    for t in ("lineitem", "customer"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '/root/testdata/sf0.001/{t}.parquet'")
    assert rows(small) == sorted(tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in con.sql(entries.oracle_sql()[name]).fetchall())


def test_search_workload_makes_no_curve_by_itself(spark, monkeypatch):
    """All curves of the search workload come from one sweep, and are those that each subset, gamma and budget has alone."""
    from subsetheavy.plans import workloads as wl

    def slot(i, j):
        return None if (i + j) % 11 == 0 else "␀x" if (i * j) % 13 == 1 else f"v{(i * i + 3 * j) % (2 + j % 4)}"

    rows = [(i, i % 3, i, i % 5, 100 * i, "abc"[min(i // 130, 2)] if i < 290 else "a", 1 + i * i % 7, *(slot(i, j) for j in range(10))) for i in range(300)]
    kind = ", ".join(f"{c} bigint" for c in wl.ROW_KEY) + ", subset string, day int, " + ", ".join(f"{c} string" for c in wl.SEARCH_COORDS)
    df = spark.createDataFrame(rows, kind).repartition(3)
    names, gammas, pcts = ("tp", "fp", "fp_strict", "fn", "reported"), (0.05, 0.3), (20.0,)
    want = {}
    for gamma in gammas:
        for pct in pcts:
            for n in "ab":
                Ts = {wl.SEARCH_COORDS[i : i + 3]: gamma for i in range(8)}
                for r in wl.curve(df.where(F.col("subset") == n), wl.ROW_KEY, wl.SEARCH_COORDS, Ts, ("sample", "mixture"), pct, "day").collect():
                    want.setdefault((gamma, pct, r["method"], r["cut"]), []).append([r[c] for c in names])

    def never(*a, **k):
        raise AssertionError("made for one curve")

    monkeypatch.setattr(wl, "websearch", lambda spark, d: df)
    monkeypatch.setattr(wl, "draw_sample", never)
    monkeypatch.setattr(wl, "fit_mixture", never)
    got = {(r["gamma"], r["pct"], r["method"], r["cut"]): [r[c] for c in names] for r in wl.search_curve(spark, "", gammas, pcts, 2).collect()}
    assert set(got) == set(want) and len(got) == 28
    for at, each in want.items():
        assert len(each) == 16
        assert got[at] == pytest.approx([sum(v) / 16 for v in zip(*each, strict=True)], abs=1e-9), at
    assert any(v[0] and v[3] for v in got.values())
    monkeypatch.setattr(wl, "websearch", lambda spark, d: df.limit(0))
    assert wl.search_curve(spark, "", gammas, pcts, 2).collect() == []


def test_samples_of_groups(spark):
    """draw_samples keeps what a sort of each group's rows by priority and key keeps, ties and sizes over the group included."""
    from subsetheavy.operators.sampling import draw_samples

    rows = [(i, "ab"[i % 3 == 0], (i * 37 % 50) * (1 << 20)) for i in range(400)] + [(400 + i, "a", (1 << 32) - 1 - i * (1 << 26)) for i in range(60)]
    df = spark.createDataFrame(rows, "k int, g string, priority bigint").repartition(3)
    sizes = {"a": {"one": 1, "some": 100, "most": 299, "all": 9999}, "b": {"one": 3, "some": 134}}
    got = draw_samples(df, ["k"], "g", sizes).collect()
    for g, each in sizes.items():
        own = sorted((p, k) for k, of, p in rows if of == g)
        for name, size in each.items():
            assert sorted((r["priority"], r["k"]) for r in got if r["g"] == g and r["sample"] == name) == own[:size], (g, name)


def test_counters_of_groups(spark):
    """Each group and capacity has its own counters, with the bound of misra_gries."""
    from subsetheavy.operators.summaries import counters_by

    rows = [("ab"[i % 4 == 0], f"v{int((i * 7919 % 1000) ** 2 / 40000)}", i % 3 if i % 5 else None) for i in range(3000)]
    got = counters_by(spark.createDataFrame(rows, "g string, f string, h int").repartition(3), ["f", "h"], "g", {"a": {2, 8, 100}, "b": {1, 5}}).collect()
    for g, each in {"a": (2, 8, 100), "b": (1, 5)}.items():
        own = [r for r in rows if r[0] == g]
        for c, at in (("f", 1), ("h", 2)):
            true = {v: sum(1 for r in own if ("␀" if r[at] is None else str(r[at])) == v) for v in {"␀" if r[at] is None else str(r[at]) for r in own}}
            for n in each:
                held = {r["value"]: r["counter"] for r in got if (r["grp"], r["capacity"], r["coord"]) == (g, n, c)}
                assert len(held) <= n and set(held) <= set(true)
                assert all(true[v] - len(own) / (n + 1) <= held.get(v, 0) <= true[v] for v in true), (g, c, n)
    assert {r["grp"] for r in got} == {"a", "b"}
