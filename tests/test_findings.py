"""Cases of the review's findings."""

import duckdb
import pytest
from pyspark.sql import functions as F

from frsketch.plans import registry

SF = "/root/testdata/sf0.001"


def shown(rows):
    return sorted(tuple("" if v is None else f"{v:.9g}" if isinstance(v, float) else str(v) for v in r) for r in rows)


def beside_sql(spark, d, name, **tables):
    """Sorted rows of a query and of its SQL over the tables (name=DataFrame), written below d."""
    con = duckdb.connect()
    for t, df in tables.items():
        df.write.mode("overwrite").parquet(f"{d}/{t}.parquet")
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet/*.parquet'")
    df = registry.QUERIES[name](spark, str(d))
    want = con.execute(f"select {', '.join(df.columns)} from ({registry.ORACLE_SQL[name]})").fetchall()
    return shown(df.collect()), shown(want)


def test_status_of_large_sets_is_that_of_the_sql(spark, tmp_path):
    o = spark.range(300_000).select(F.col("id").alias("o_custkey"), F.when(F.col("id") % 2 == 0, "1-URGENT").otherwise("2-HIGH").alias("o_orderpriority"))
    got, want = beside_sql(spark, tmp_path, "jaccard_corrected_approx_priorities", orders=o)
    assert got == want and len(got) == 1


def test_supplier_searches_ask_for_every_twentieth_key(spark):
    d = "/root/testdata/sf0.01"
    keys = {r[0] for r in spark.read.parquet(f"{d}/lineitem.parquet").select("l_suppkey").distinct().collect()}
    asked = {k for k in keys if k % 20 == 0}
    for name in ("f2_jaccard", "jaccard_corrected_approx", "jaccard_overlap_aware"):
        assert {(r["a"], r["b"]) for r in registry.QUERIES[name](spark, d).collect()} == {(a, b) for a in asked for b in keys - {a}}
    top = registry.QUERIES["top_similar_suppliers"](spark, d).collect()
    assert {(r["supp"], r["rank"]) for r in top} == {(a, i) for a in asked for i in (1, 2, 3)}


MOVED = ["bits_for_error", "ablation_buckets_and_window", "ablation_mantissa_bits", "ablation_corrections", "ablation_printed_loop", "card_infinite", "choose_params_table", "collision_error_by_mantissa", "expected_collisions_unbounded", "expected_collisions_large", "expected_collisions_small", "expected_collisions_grid"]


@pytest.mark.parametrize("name", MOVED)
def test_queries_read_the_orders(spark, name):
    assert any("orders" in f for f in registry.QUERIES[name](spark, SF).inputFiles())


def test_sketches_meet_key_by_key(spark):
    """Neither MinHash nor inclusion-exclusion joins or counts a row for each pair and bucket; values as by hand."""
    from frsketch.operators import baselines, build
    from frsketch.operators.cardinality import hll_estimate
    from frsketch.params import FrsParams

    params = FrsParams(4, 4, 6)
    rows = spark.range(400).select((F.col("id") % 7).alias("k"), F.pmod(F.xxhash64("id"), F.lit(60)).alias("x")).unionByName(spark.createDataFrame([(90, 1), (91, 777)], "k long, x long"))
    mh, sk = baselines.minhash_kpart(rows, "x", ["k"], 4, 8), build.sketch(rows, "x", ["k"], params)
    got = {"mh": baselines.minhash_jaccard(mh, "k"), "ie": baselines.incl_excl_jaccard(sk, "k", params)}
    for df in got.values():
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert not [x for x in plan.splitlines() if "Aggregate [a" in x or "Join Inner" in x and "bucket" in x]
    by = {}
    for r in mh.collect():
        by.setdefault(r["k"], {})[r["bucket"]] = r["val"]
    want = {(a, b): (sum(by[a][i] == by[b][i] for i in by[a].keys() & by[b].keys()), len(by[a].keys() | by[b].keys())) for a in by for b in by if a < b}
    assert {(r["a"], r["b"]): (r["c"], r["n_filled"]) for r in got["mh"].collect()} == want
    by = {}
    for r in sk.collect():
        by.setdefault(r["k"], {})[r["bucket"]] = r["reg"] >> params.r
    flat = [(a, b, sum(2.0 ** -max(by[a].get(i, 0), by[b].get(i, 0)) for i in by[a].keys() | by[b].keys()), len(by[a].keys() | by[b].keys())) for a in by for b in by if a < b]
    u = spark.createDataFrame(flat, "a long, b long, p double, f int").select("a", "b", hll_estimate(F.col("p"), F.col("f"), params.k).alias("u"))
    assert {(r["a"], r["b"]): pytest.approx(r["u"]) for r in u.collect()} == {(r["a"], r["b"]): r["u"] for r in got["ie"].collect()}


def test_similar_pairs_shuffle_no_words(spark):
    """Shingles leave their document as 64-bit hashes, and nothing but the least keys is grouped by whole sets."""
    from frsketch.functions.text import word_shingles
    from frsketch.operators.similar_pairs import jaccard_pairs

    rows = [(0, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e g"), (3, "x y z"), (4, None), (5, "q")]
    df = jaccard_pairs(word_shingles(spark.createDataFrame(rows, "k int, text string"), "k", "text"), "k", "shingle")
    plan = df._jdf.queryExecution().sparkPlan().toString()
    assert not [x for x in plan.splitlines() if "Aggregate(keys=[cells" in x or "Aggregate(keys=[key" in x and "element" in x.split("functions")[0]]
    assert [(r["a"], r["b"], round(r["t"], 6)) for r in df.collect()] == [(0, 2, 0.6)]


def test_banded_pairs_shuffle_no_words(spark):
    rows = [(k, " ".join(f"w{j}" for j in range(40) if j != k)) for k in range(2)] + [(2, "x y z"), (3, None)]
    sh = registry.word_shingles(spark.createDataFrame(rows, "k int, text string"), "k", "text")
    df = registry.similar_texts(sh, "k")
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert not [x for x in plan.splitlines() if "Join Inner" in x and "element" in x]
    one, two = ({tuple(t.split()[i : i + 3]) for i in range(37)} for _, t in rows[:2])
    for r in df.collect():
        assert (r["doc_a"], r["doc_b"], r["t_exact"]) == (0, 1, round(len(one & two) / len(one | two), 6))
    from frsketch.operators.similar_pairs import register_rows

    sk = spark.createDataFrame([(1, 3, 70), (1, 0, 5), (2, 0, 5)], "k int, bucket int, reg int")
    assert {(r["key"], tuple(r["cells"])) for r in register_rows(sk, "k").collect()} == {(1, (5, (3 << 32) + 70)), (2, (5,))}


def test_low_t_estimates_only_pairs_with_a_truth(spark, tmp_path):
    """Pairs of suppliers without a common part never meet, and no row stands for a pair and a part or bucket; figures as
    those of all pairs."""
    from frsketch.operators import baselines, build, exact
    from frsketch.operators.jaccard import pairwise_jaccard
    from frsketch.params import FrsParams

    rows = [(s + 100 * c, p + 1000 * c) for c in range(3) for s in range(9) for p in range(60) if (s * 7 + p * 5) % 11 < 4]
    rows += [(500, 7), (501, 9999), (None, 7), (500, None), (502, None), (None, None)] + rows[:50]
    li = spark.createDataFrame(rows, "l_suppkey long, l_partkey long")
    li.write.parquet(str(tmp_path / "lineitem.parquet"))
    df = registry.QUERIES["low_t_equal_bytes"](spark, str(tmp_path))
    plan = df._jdf.queryExecution().optimizedPlan().toString().splitlines()
    assert sum("FlatMapCoGroupsInArrow" in x for x in plan) == 4
    assert not [x for x in plan if "Aggregate [a" in x or "Join Inner" in x and ("bucket" in x or "element" in x or "(x#" in x)]
    sets = {}
    for s, p in rows:
        if s is not None and p is not None:
            sets.setdefault(s, set()).add(p)
    truth = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a in sets for b in sets if a < b and sets[a] & sets[b]}
    assert {(r["a"], r["b"]): r["t"] for r in exact.exact_jaccard(li, "l_suppkey", "l_partkey").collect()} == truth
    params = FrsParams(8, 4, 6)
    sk, k = build.sketch(li, "l_partkey", ["l_suppkey"], params), "l_suppkey"
    sizes = exact.exact_count(li, [k], "l_partkey").withColumnRenamed("exact", "n")
    every = {
        "frs": pairwise_jaccard(sk, k, params),
        "minhash_8bit": baselines.minhash_jaccard(baselines.minhash_kpart(li, "l_partkey", [k], 8, 8), k),
        "incl_excl": baselines.incl_excl_jaccard(sk, k, params),
        "f2": baselines.f2_jaccard(baselines.f2_fingerprint(li, "l_partkey", [k], 64), sizes, k),
    }
    got = {r["method"]: r for r in df.collect()}
    assert got.keys() == every.keys()
    for name, x in every.items():
        errors = [abs(r["t"] - truth[r["a"], r["b"]]) / truth[r["a"], r["b"]] for r in x.collect() if (r["a"], r["b"]) in truth]
        assert got[name]["pairs"] == len(errors) == len(truth)
        assert got[name]["mre"] == pytest.approx(sum(errors) / len(errors)) and got[name]["mean_t"] == pytest.approx(sum(truth.values()) / len(truth))


def test_given_pairs_have_the_values_of_all_pairs(spark):
    """Every column of every method, string keys, further columns kept, unknown and null keys left out."""
    from frsketch.operators import baselines, build, exact
    from frsketch.operators.jaccard import pairwise_jaccard
    from frsketch.params import FrsParams

    params = FrsParams(4, 4, 6)
    rows = spark.range(400).select(F.concat(F.lit("é"), (F.col("id") % 7).cast("string")).alias("k"), F.pmod(F.xxhash64("id"), F.lit(60)).alias("x"))
    rows = rows.unionByName(spark.createDataFrame([("z", 1), ("Z", 777)], "k string, x long"))
    sk, sizes = build.sketch(rows, "x", ["k"], params), exact.exact_count(rows, ["k"], "x").withColumnRenamed("exact", "n")
    mh, fp = baselines.minhash_kpart(rows, "x", ["k"], 4, 40), baselines.f2_fingerprint(rows, "x", ["k"], 32)
    pairs = spark.createDataFrame([("é0", "é3", 1), ("é5", "é2", 2), ("Z", "z", 3), ("Z", "none", 4), (None, "z", 5)], "a string, b string, own int")
    for of in (
        lambda **p: pairwise_jaccard(sk, "k", params, "approx", **p, **({"blocks": True} if p else {})),
        lambda **p: baselines.minhash_jaccard(mh, "k", **p),
        lambda **p: baselines.incl_excl_jaccard(sk, "k", params, **p),
        lambda **p: baselines.f2_jaccard(fp, sizes, "k", 4, **p),
    ):
        some, one = of(pairs=pairs), of()
        want = {frozenset((r["a"], r["b"])): r for r in one.collect()}
        got = some.collect()
        assert sorted(r["own"] for r in got) == [1, 2, 3]
        for r in got:
            w = want[frozenset((r["a"], r["b"]))]
            for c in set(one.columns) - {"a", "b", "n", "m"}:
                assert r[c] == (pytest.approx(w[c]) if isinstance(w[c], float) else w[c])
            if "n" in one.columns:
                assert {r["n"], r["m"]} == {w["n"], w["m"]}
    sets = {}
    for r in rows.collect():
        sets.setdefault(r["k"], set()).add(r["x"])
    truth = {(a, b): len(sets[a] & sets[b]) for a in sets for b in sets if a.encode() < b.encode() and sets[a] & sets[b]}
    assert {(r["a"], r["b"]): r["both"] for r in exact.exact_jaccard(rows, "k", "x").collect()} == truth
