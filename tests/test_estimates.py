"""Collision sums, cardinality, Jaccard, formulas, baselines, experiments."""

from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from frsketch.functions import collisions as c
from frsketch.operators import advisor, baselines, boolean, build, exact, jaccard, measures, simulate
from frsketch.operators.cardinality import cardinality
from frsketch.operators.similar_pairs import classes, similar_pairs
from frsketch.params import FrsParams


def exact_sum(n, m, p, q, r):
    total = Fraction(0)
    for i in range(1, 2**q + 1):
        for j in range(2**r):
            if i < 2**q:
                b1, b2 = Fraction(2**r + j, 2 ** (p + r + i)), Fraction(2**r + j + 1, 2 ** (p + r + i))
            else:
                b1, b2 = Fraction(j, 2 ** (p + r + i - 1)), Fraction(j + 1, 2 ** (p + r + i - 1))
            total += ((1 - b1) ** n - (1 - b2) ** n) * ((1 - b1) ** m - (1 - b2) ** m)
    return float(total * 2**p)


@pytest.mark.parametrize("case", [(100, 50, 2, 3, 3), (10, 5, 0, 3, 3), (7, 7, 1, 2, 2)])
def test_expected_collisions_equal_rational_arithmetic(case):
    assert c.expected_collisions(*case) == pytest.approx(exact_sum(*case), rel=1e-12)


def test_expected_collision_values():
    assert c.expected_collisions(100, 50, 2, 3, 3) == pytest.approx(0.086241047787323, rel=1e-12)
    assert c.expected_collisions(1e15, 1e15, 15, 6, 10) == pytest.approx(5.77083564, rel=1e-8)
    assert c.expected_collisions(2**10, 2**10, 6, 4, 4, loop="as_printed") < 0.92 * c.expected_collisions(2**10, 2**10, 6, 4, 4)
    assert c.LIMIT == pytest.approx(0.180337, abs=1e-6)
    assert c.expected_matches(100, 50, 0, 2, 3, 3) == pytest.approx(0.086241047787323, rel=1e-9)
    assert c.expected_matches(0, 0, 500, 4, 5, 3) == pytest.approx(16, rel=1e-3)
    assert c.expected_collisions_unbounded(10, 5, 3) == pytest.approx(c.expected_collisions(10, 5, 0, 6, 3), rel=1e-9)


def test_bounds_and_approximation_over_the_grid():
    for a in range(4, 80, 4):
        for p, q, r in ((6, 4, 4), (8, 5, 8), (15, 6, 10)):
            n = 2.0**a
            ec = c.expected_collisions(n, n, p, q, r)
            assert ec <= c.collision_bound(n, p, q, r)
            assert c.expected_collisions(n, n, 0, q, r) <= c.collision_bound_single(n, q, r)
            if a <= 2**q + p - 7:
                got = c.approx_expected_collisions(n, n, p, q, r)
                assert ec * 0.94 <= got <= ec * 1.0001
    with pytest.raises(ValueError):
        c.approx_expected_collisions(2.0**30, 1.0, 6, 4, 4)
    assert c.approx_expected_collisions(5, 2000, 6, 4, 4) == c.approx_expected_collisions(2000, 5, 6, 4, 4)


@pytest.mark.parametrize("n,m,q,r", [(1000, 1000, 4, 4), (50_000, 300, 4, 4), (10, 4, 3, 3), (200, 200, 3, 5)])
def test_regions_cover_all_boxes_within_their_bounds(n, m, q, r):
    masses, bounds = c.region_masses(n, m, q, r), c.region_bounds(n, q, r)
    assert all(0 <= masses[k] <= bounds[k] for k in bounds)
    assert sum(masses.values()) >= c.expected_collisions(n, m, 0, q, r, tail="overflow") * (1 - 1e-6)
    assert c.expected_collisions(n, m, 0, q, r) <= c.collision_bound_single(n, q, r)


def test_the_strip_outgrows_its_bound_beyond_the_window():
    assert c.region_masses(2000, 2000, 3, 5)["strip"] > 2 * c.region_bounds(2000, 3, 5)["strip"]


def test_infinite_cardinality_and_missing_pairs(spark):
    x = FrsParams(6, 4, 4)
    top = (x.last << x.r) + x.scale - 1
    full = spark.range(x.k).select(F.col("id").cast("int").alias("bucket"), F.lit(top).alias("reg"))
    assert cardinality(full, [], x, "minvalue").first()["est"] == float("inf")
    one = spark.createDataFrame([("a", 0, 9), ("b", 1, 9), ("c", 0, 9), ("c", 63, 200)], "k string, bucket int, reg int")
    for params in (x, FrsParams(10, 4, 8)):  # two words and lists of words
        got = {(r["a"], r["b"]): (r["c"], r["n_filled"]) for r in jaccard.pairwise_jaccard(one, "k", params).collect()}
        assert got == {("a", "b"): (0, 2), ("a", "c"): (1, 2), ("b", "c"): (0, 3)}
        slow = {(r["a"], r["b"]): (r["c"], r["n_filled"]) for r in jaccard.by_buckets(one, "k", params, None, "none", "filled").collect()}
        assert slow == got
    mh = one.withColumnRenamed("reg", "val")
    assert {(r["a"], r["b"]): r["c"] for r in baselines.minhash_jaccard(mh, "k").collect()} == {k: v[0] for k, v in got.items()}


@pytest.mark.parametrize("t", [0.1, 0.5, 0.9])
def test_overlap_correction_beats_disjoint_sums_where_sets_overlap(spark, t):
    """At small t it keeps the few percent by which its approximate base is low, and the exact sum is better."""
    x, n = FrsParams(10, 5, 4), 2.0**14
    g = 2 * n * t / (1 + t)
    row = (c.expected_matches(n - g, n - g, g, x.p, x.q, x.r), float(x.k), n, n)
    df = spark.createDataFrame([row], "c double, n_filled double, n double, m double")
    bias = {k: abs(jaccard.finish(df, x, k).first()["t_raw"] - t) for k in ("none", "exact", "overlap")}
    assert bias["overlap"] < 0.3 * bias["none"]
    assert (bias["overlap"] < bias["exact"]) == (t >= 0.5)


def test_bits_needed_grow_faster_for_inclusion_exclusion(spark):
    grid = [{"method": f"{k}@{p}", "kind": k, "p": p, "q": 6, "r": 10, "t": t, "n": 2.0**20} for k in ("frs", "incl_excl", "mle") for t in (0.05, 0.4) for p in (10,)]
    err = {(r["method"][:-3], r["t"]): r["mre"] for r in measures.relative_error_summary(simulate.register_trials(spark, grid, 60)).collect()}
    assert err["incl_excl", 0.05] > 2 * err["frs", 0.05]
    assert 1 < err["incl_excl", 0.05] / err["mle", 0.05] < 4


def test_hash_sweep_cuts_sets_into_segments(spark):
    x = FrsParams(6, 4, 4, hash="xx")
    got = {(r["t"], r["n_set"], r["rep"]): r["t_hat"] for r in simulate.hash_sweep(spark, [64, 100, 1000], (0.1, 0.5), 2, x).where("method = 'frs_64x8'").collect()}
    assert len(got) == 12
    for (t, n, rep), value in got.items():
        a, b = (build.sketch(s.withColumn("key", F.concat(F.lit(f"{rep}|"), F.col("x").cast("string"))), "key", [], x) for s in ranged(spark, int(n), t))
        assert jaccard.jaccard(a, b, x).first()["t_raw"] == value


def test_columns_equal_scalars(spark):
    rows = [(100.0, 50.0), (1.0, 1.0), (3000.0, 2000.0), (2.0**21, 2.0**20), (2.0**25, 2.0**5)]
    df = spark.createDataFrame(rows, "n double, m double")
    x = FrsParams(6, 4, 4)
    got = c.expected_collisions_df(df, 6, 4, 4).select("n", "m", "ec", c.approx_collisions_col(F.col("n"), F.col("m"), x).alias("ap"), c.range_status(F.col("n"), F.col("m"), x).alias("s")).collect()
    for r in got:
        assert r["ec"] == pytest.approx(c.expected_collisions(r["n"], r["m"], 6, 4, 4), rel=1e-9)
        if r["n"] > 2**22:
            assert r["ap"] is None and r["s"] == "error"
        else:
            assert r["ap"] == pytest.approx(c.approx_expected_collisions(r["n"], r["m"], 6, 4, 4), rel=1e-9)
    one = c.expected_collisions_df(spark.createDataFrame([(5, 5)], "n int, m int"), 0, 3, 3).first()["ec"]
    assert one == pytest.approx(exact_sum(5, 5, 0, 3, 3), rel=1e-9)


def ranged(spark, n, t):
    df = simulate.overlapping_ranges(spark, n, t)
    return [df.where(f"side = '{s}'") for s in "ab"]


@pytest.mark.parametrize("t,want", [(0.1, 5), (1 / 3, 25), (0.5, 34), (0.9, 57)])
def test_golden_matches_of_ranges(spark, t, want):
    x = FrsParams(6, 4, 4)
    a, b = (build.sketch(s, "x", [], x) for s in ranged(spark, 1000, t))
    row = jaccard.jaccard(a, b, x).first()
    assert (row["c"], row["n_filled"]) == (want, 64)


def test_jaccard_edges(spark):
    x = FrsParams(8, 4, 6)
    a = build.sketch(spark.range(3000), "id", [], x)
    b = build.sketch(spark.range(3000, 6000), "id", [], x)
    none = a.where("false")
    assert jaccard.jaccard(a, a, x).first()["t"] == 1.0
    assert jaccard.jaccard(none, none, x).first()["t"] is None
    assert jaccard.jaccard(a, none, x).first()["t"] == 0.0
    got = {k: jaccard.jaccard(a, b, x, correction=k).first() for k in jaccard.CORRECTIONS}
    assert got["none"]["t"] < 0.05 and got["exact"]["t_raw"] < got["none"]["t_raw"] or got["none"]["c"] == 0
    assert got["exact"]["ec"] == pytest.approx(got["limit"]["ec"], rel=0.1)
    with pytest.raises(ValueError):
        jaccard.jaccard(a, b, x, correction="other")


def test_cardinality_and_intersection(spark):
    x = FrsParams(10, 5, 8)
    for n in (3, 200, 5000, 60_000):
        sk = build.sketch(spark.range(n), "id", [], x)
        assert cardinality(sk, [], x).first()["est"] == pytest.approx(n, rel=0.12)
    low = cardinality(build.sketch(spark.range(100), "id", [], x), [], x, "minvalue").first()["est"]
    assert low > 300  # empty buckets count 1: useless below k
    a, b = (build.sketch(s, "x", [], x) for s in ranged(spark, 20_000, 0.5))
    got = jaccard.intersection_cardinality(a, b, x).first()
    assert got["est"] == pytest.approx(13_333, rel=0.15)


def test_formulas(spark):
    assert boolean.to_cnf(("or", ("and", "a", "b"), "c")) == [["a", "c"], ["b", "c"]]
    assert boolean.to_cnf(("and", "a", ("or", "a", "b"))) == [["a"]]
    df = spark.range(30_000).select("id", F.explode(F.array(F.lit("all"), F.when(F.col("id") % 2 == 0, "even").otherwise("odd"), F.when(F.col("id") % 3 == 0, "three").otherwise("rest"))).alias("name"))
    x = FrsParams(12, 5, 8)
    sk = build.sketch(df, "id", ["name"], x)
    for clauses in ([["even"]], [["even"], ["three"]], [["even", "odd"], ["three"]], [["all"], ["even"], ["three", "rest"], ["all", "odd"]]):
        want = exact.exact_cnf(df, "name", "id", clauses).first()["exact"]
        assert boolean.cnf_count(sk, clauses, x, "name").first()["est"] == pytest.approx(want, rel=0.15)
    with pytest.raises(ValueError):
        boolean.cnf_count(sk, [[]], x, "name")


def test_baselines_agree_with_the_truth(spark):
    t = 0.5
    df = simulate.overlapping_ranges(spark, 8000, t).withColumnRenamed("side", "k")
    x = FrsParams(11, 5, 8)
    sk = build.sketch(df, "x", ["k"], x)
    pairs = spark.createDataFrame([("a", "b")], "a string, b string")
    sizes = spark.createDataFrame([("a", 8000), ("b", 8000)], "k string, n long")
    got = {
        "kpart": baselines.minhash_jaccard(baselines.minhash_kpart(df, "x", ["k"], 11, 32), "k"),
        "khash": baselines.khash_jaccard(baselines.minhash_khash(df, "x", ["k"], 96), "k", 96),
        "kmv": baselines.kmv_jaccard(baselines.kmv(df, "x", ["k"], 512), "k", 512),
        "float": baselines.bottomk_float_jaccard(baselines.bottomk_float(baselines.kmv(df, "x", ["k"], 512), ["k"], FrsParams(0, 6, 12)), "k", 512),
        "bbit": baselines.bbit_jaccard(baselines.bbit_fingerprint(baselines.minhash_kpart(df, "x", ["k"], 11, 32), 4), "k", 4),
        "f2": baselines.f2_jaccard(baselines.f2_fingerprint(df, "x", ["k"], 128), sizes, "k"),
        "ie": baselines.incl_excl_jaccard(sk, "k", x),
        "mle": baselines.mle_jaccard(sk, "k", x, pairs),
        "frs": jaccard.pairwise_jaccard(sk, "k", x),
        "exact": exact.exact_jaccard(df, "k", "x"),
    }
    slack = {"khash": 0.16, "f2": 0.12, "exact": 1e-4}
    for name, frame in got.items():
        assert frame.first()["t"] == pytest.approx(t, abs=slack.get(name, 0.07)), name
    assert baselines.kmv_cardinality(baselines.kmv(df, "x", ["k"], 512), ["k"], 512).first()["est"] == pytest.approx(8000, rel=0.15)

    assert baselines.bbit_space(0.1, 0.9) < baselines.bbit_space(0.1, 0.5)


def test_similar_pairs_and_classes(spark):
    x = FrsParams(6, 4, 8)
    sets = {0: range(0, 400), 1: range(0, 400), 2: range(10, 410), 3: range(5000, 5400)}
    df = spark.createDataFrame([(k, v) for k, s in sets.items() for v in s], "k int, v int")
    sk = build.sketch(df, "v", ["k"], x)
    assert {r["key"]: r["rep"] for r in classes(sk, "k").collect()} == {0: 0, 1: 0, 2: 2, 3: 3}
    assert {(r["a"], r["b"]) for r in similar_pairs(sk, "k", x, 0.5).collect()} == {(0, 2)}


def test_error_measures_and_failure_points(spark):
    methods = [{"method": "frs", "kind": "frs", "p": 6, "q": 4, "r": 4}, {"method": "mh8", "kind": "minhash", "p": 6, "bits": 8}, {"method": "mh16", "kind": "minhash", "p": 5, "bits": 16}]
    grid = [m | {"t": t, "n": 2.0**e} for m in methods for t in (0.1, 0.5) for e in (8, 10, 13, 16, 19, 22, 25)]
    summary = measures.relative_error_summary(simulate.register_trials(spark, grid, 400)).cache()
    err = {(r["method"], r["t"], r["n_set"]): r["mre"] for r in summary.collect()}
    # calibrated by 2,000 repetitions beforehand
    for key, want in {("frs", 0.1, 2.0**13): 0.326, ("mh8", 0.1, 2.0**13): 2.19, ("mh16", 0.1, 2.0**19): 1.11, ("frs", 0.5, 2.0**25): 0.43, ("frs", 0.5, 2.0**16): 0.1}.items():
        assert err[key] == pytest.approx(want, rel=0.15)
    bad = {(r["method"], r["t"]): r["first_bad"] or float("inf") for r in measures.usable_range(summary).collect()}
    assert bad["mh8", 0.1] < bad["mh16", 0.1] < bad["frs", 0.1]
    plateau = np.sqrt(2 * 0.5 / (np.pi * 0.5 * 64))
    assert err["frs", 0.5, 2.0**10] == pytest.approx(plateau, rel=0.2)


def test_headline(spark):
    grid = [{"method": "raw", "kind": "frs", "p": 15, "q": 6, "r": 10, "t": 0.01, "n": 1e19}]
    assert measures.relative_error_summary(simulate.register_trials(spark, grid, 60)).first()["mre"] < 0.08


def test_disjoint_collision_moments(spark):
    n = 2.0**12
    got = simulate.trial_estimates(n, 0.0, {"kind": "frs", "p": 6, "q": 4, "r": 4}, 4000, 9) * 64
    ec = c.expected_collisions(n, n, 6, 4, 4)
    assert got.mean() == pytest.approx(ec, rel=0.08) and got.var() <= c.collision_variance_bound(ec)
    assert ec <= c.collision_bound(n, 6, 4, 4)


def test_hash_trials_match_the_register_model(spark):
    got = measures.relative_error_summary(simulate.hash_trials(spark, 1024, 0.5, FrsParams(6, 4, 4), 24))
    err = {r["method"]: r["mre"] for r in got.collect()}
    assert err["frs"] == pytest.approx(0.097, abs=0.06) and set(err) == {"frs", "minhash_64x8", "minhash_32x16"}


def test_advice():
    got = advisor.choose_params(0.1, 0.01, 1e19)
    assert got["r"] > np.log2(6 / (0.1 * 0.01)) and got["p"] == 7 and got["p_refined"] > got["p"]
    assert advisor.sketch_bits(FrsParams(15, 6, 10)) / 8 == 64 * 1024 and advisor.sketch_bits(FrsParams(6, 4, 4)) / 8 == 64
    orders = advisor.space_orders(0.1, 0.01, 1e12)
    assert orders["float_register"] < orders["minhash"] < orders["hll_incl_excl"]
