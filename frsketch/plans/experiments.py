"""Further registered queries: measures, ablations and comparisons of the experiments, each with its DuckDB text
where SQL can say it."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.functions import collisions as coll
from frsketch.functions.hashing import element_key
from frsketch.operators import baselines as base
from frsketch.operators import build, exact, measures, simulate
from frsketch.operators.cardinality import cardinality
from frsketch.operators.jaccard import jaccard, pairwise_jaccard
from frsketch.params import MEDIUM, SMALL, FrsParams
from frsketch.plans import duck
from frsketch.plans.registry import CNF, CUST, _SET_PAIRS, _YEARLY_SETS, _Y96, _exact_sql, order_set_pairs, order_sets, priorities, query, r6, table
from frsketch.sources.tables import shared_dir
from frsketch.streaming import sketches as streams

# ---- similarity of periods and kinds

_USE = "length(user_id::VARCHAR)::VARCHAR || ':' || user_id::VARCHAR || length(props)::VARCHAR || ':' || props AS x FROM events"
_HALF = f"(SELECT CASE WHEN ts < TIMESTAMP '2024-01-16' THEN 'first' ELSE 'second' END AS k, {_USE})"
_TYPE = f"(SELECT event_type AS k, {_USE})"


def _beside_exact(source: str) -> str:
    return f"WITH sk AS ({duck.registers(source, 'x', ['k'], MEDIUM)}), {duck.pair_cells(MEDIUM)}, ex AS ({_exact_sql(source.replace(' AS x', ' AS e'))}) SELECT pr.a, pr.b, round(pr.c / n_filled, 6) AS t, coalesce(ex.t, 0) AS exact_t FROM pr LEFT JOIN ex ON ex.a = pr.a AND ex.b = pr.b"


def beside_exact(rows: DataFrame) -> DataFrame:
    """rows (k, x) -> a, b, t, exact_t of every two sets."""
    est = pairwise_jaccard(build.sketch(rows, "x", ["k"], MEDIUM), "k", MEDIUM).select("a", "b", F.col("t_raw").alias("t"))
    truth = exact.exact_jaccard(rows, "k", "x").select("a", "b", F.col("t").alias("exact_t"))
    return est.join(truth, ["a", "b"], "left").select("a", "b", r6("t").alias("t"), r6(F.coalesce("exact_t", F.lit(0.0))).alias("exact_t"))


@query("event_halves_similarity", _beside_exact(_HALF))
def event_halves_similarity(spark, d):
    half = F.when(F.col("ts") < F.expr("timestamp_ntz'2024-01-16 00:00:00'"), "first").otherwise("second")
    return beside_exact(table(spark, d, "events").select(half.alias("k"), element_key(["user_id", "props"]).alias("x")))


@query("event_type_matrix", _beside_exact(_TYPE))
def event_type_matrix(spark, d):
    return beside_exact(table(spark, d, "events").select(F.col("event_type").alias("k"), element_key(["user_id", "props"]).alias("x")))


_YEARLY = "(SELECT year(o_orderdate)::VARCHAR || o_orderpriority AS k, o_custkey::VARCHAR AS x FROM orders)"


@query(
    "small_sets_jaccard",
    f"WITH sk AS ({duck.registers(_YEARLY, 'x', ['k'], MEDIUM)}), {duck.pair_cells(MEDIUM)}, ex AS ({_exact_sql(_YEARLY.replace(' AS x', ' AS e'))}) SELECT pr.a, pr.b, n_filled, round(pr.c / n_filled, 6) AS t_filled, round(pr.c / {float(MEDIUM.k)}, 6) AS t_all, coalesce(ex.t, 0) AS exact_t FROM pr LEFT JOIN ex ON ex.a = pr.a AND ex.b = pr.b",
)
def small_sets_jaccard(spark, d):
    """Customers of a year and priority: few elements a bucket, so the two denominators differ."""
    rows = table(spark, d, "orders").select(F.concat(F.year("o_orderdate").cast("string"), "o_orderpriority").alias("k"), F.col("o_custkey").cast("string").alias("x"))
    est = pairwise_jaccard(build.sketch(rows, "x", ["k"], MEDIUM), "k", MEDIUM)
    truth = exact.exact_jaccard(rows, "k", "x").select("a", "b", F.col("t").alias("exact_t"))
    return est.join(truth, ["a", "b"], "left").select("a", "b", "n_filled", r6("t_raw").alias("t_filled"), r6(F.col("c") / float(MEDIUM.k)).alias("t_all"), r6(F.coalesce("exact_t", F.lit(0.0))).alias("exact_t"))


# ---- collisions

_SCALES = range(9)  # powers of 4


@query(
    "expected_collisions_large",
    f"SELECT yr, a, b, n, m, CASE WHEN greatest(n, m) > {2.0**22} THEN NULL ELSE round({duck.approx_collisions('n', 'm', SMALL)}, 6) END AS approx, CASE WHEN greatest(n, m) > {2.0**22} THEN 'error' WHEN greatest(n, m) > {2.0**17} THEN 'warning' ELSE 'ok' END AS status FROM (SELECT yr, a, b, n * power(4, i) AS n, m * power(4, i) AS m FROM {_SET_PAIRS}, range(0, {len(_SCALES)}) s(i))",
)
def expected_collisions_large(spark, d):
    """The approximation for every two sets of orders and for up to 4**8 times as many elements: from the small-set
    sum over the large-set constant to beyond its range."""
    df = order_set_pairs(spark, d).withColumn("s", F.explode(F.array(*[F.lit(4.0**i) for i in _SCALES])))
    df = df.select("yr", "a", "b", (F.col("n") * F.col("s")).alias("n"), (F.col("m") * F.col("s")).alias("m"))
    return df.select("yr", "a", "b", "n", "m", r6(coll.approx_collisions_col(F.col("n"), F.col("m"), SMALL)).alias("approx"), coll.range_status(F.col("n"), F.col("m"), SMALL).alias("status"))


_MATCHES = [(float(a), float(b), float(g)) for a, b in ((100, 50), (1000, 1000), (0, 0)) for g in (0, 10, 500)]


def expected_matches_table(spark, d):
    """Equal registers of overlapping sets: a, b elements of one set alone, g of both."""
    rows = [(a, b, g, round(coll.expected_matches(a, b, g, 6, 4, 4), 6)) for a, b, g in _MATCHES]
    return spark.createDataFrame(rows, "a double, b double, g double, matches double")


def _matches_sql() -> str:
    """P(both minima in a box): with S(x, y) = P(minimum of A > x and of B > y), where common elements must exceed the
    larger, it is S(lo, lo) - S(hi, lo) - S(lo, hi) + S(hi, hi)."""
    e = "(i // 16 + 1)"
    low = f"(CASE WHEN {e} < 16 THEN (16 + i % 16) * power(2.0, -(10 + {e})) ELSE (i % 16) * power(2.0, -25) END)"
    high = f"(CASE WHEN {e} < 16 THEN (17 + i % 16) * power(2.0, -(10 + {e})) ELSE (i % 16 + 1) * power(2.0, -25) END)"
    lo, hi = f"(1 - {low})", f"greatest(0.0, 1 - {high})"
    term = f"power({lo}, a + b + g) - power({hi}, a + g) * power({lo}, b) - power({lo}, a) * power({hi}, b + g) + power({hi}, a + b + g)"
    values = ", ".join(f"({a}::DOUBLE, {b}::DOUBLE, {g}::DOUBLE)" for a, b, g in _MATCHES)
    return f"SELECT a, b, g, round(64 * list_sum(list_transform(range(0, 256), lambda i: {term})), 6) AS matches FROM (VALUES {values}) v(a, b, g)"


query("expected_matches_table", _matches_sql())(expected_matches_table)


@query("region_masses_table")
def region_masses_table(spark, d):
    """Mass and bound of the four regions that cover a bucket's boxes, beside the exact expectation."""
    rows = []
    for n, m in ((10, 4), (1000, 1000), (50_000, 300), (2**17, 2**17)):
        for q, r in ((3, 3), (4, 4), (4, 8)):
            mass, bound = coll.region_masses(n, m, q, r), coll.region_bounds(n, q, r)
            rows.append((float(n), float(m), q, r, *[float(mass[k]) for k in bound], *[float(x) for x in bound.values()], coll.expected_collisions(n, m, 0, q, r)))
    names = ["top_right", "bottom_left", "ray", "strip"]
    return spark.createDataFrame(rows, "n double, m double, q int, r int, " + ", ".join(f"{x} double" for x in [*names, *(f"{y}_bound" for y in names), "ec"]))


SEEDS = 32
_DISJOINT = " UNION ALL ".join(
    f"SELECT {s} AS seed, count(*) AS c FROM ({duck.registers('(SELECT * FROM orders WHERE o_orderkey % 2 = 0)', 'o_orderkey::VARCHAR', [], SMALL.with_(seed=s))}) a JOIN ({duck.registers('(SELECT * FROM orders WHERE o_orderkey % 2 = 1)', 'o_orderkey::VARCHAR', [], SMALL.with_(seed=s))}) b USING (bucket, reg)" for s in range(1, SEEDS + 1)
)


@query(
    "disjoint_collision_summary",
    f"WITH t AS ({_DISJOINT}), z AS (SELECT count(DISTINCT o_orderkey) FILTER (o_orderkey % 2 = 0) AS n, count(DISTINCT o_orderkey) FILTER (o_orderkey % 2 = 1) AS m FROM orders), e AS (SELECT n, m, {duck.expected_collisions('n', 'm', 6, 4, 4)} AS ec FROM z) SELECT n, m, any_value(reps) AS reps, round(any_value(mean), 6) AS mean, round(any_value(variance), 6) AS variance, round(any_value(ec), 6) AS ec, round(any_value(ec * ec + ec), 6) AS var_bound FROM (SELECT count(*) AS reps, avg(c) AS mean, var_samp(c) AS variance FROM t), e GROUP BY n, m",
)
def disjoint_collision_summary(spark, d):
    """Collisions of even and odd order keys under many seeds: mean and variance beside expectation and bound."""
    o = table(spark, d, "orders").select("o_orderkey", (F.col("o_orderkey") % 2).alias("odd"))
    rows = o.select("odd", F.explode(F.sequence(F.lit(1), F.lit(SEEDS))).alias("seed"), "o_orderkey")
    sk = build.sketch(rows.select("odd", "seed", F.concat(F.col("seed").cast("string"), F.lit("|"), F.col("o_orderkey").cast("string")).alias("x")), "x", ["seed", "odd"], SMALL)
    cells = sk.groupBy("seed", "bucket").agg(F.max(F.when(F.col("odd") == 0, F.col("reg"))).alias("a"), F.max(F.when(F.col("odd") == 1, F.col("reg"))).alias("b"))
    got = measures.collision_summary(cells.groupBy("seed").agg(F.count_if(F.col("a") == F.col("b")).alias("c")), [])
    size = o.agg(F.count_distinct(F.when(F.col("odd") == 0, F.col("o_orderkey"))).alias("n"), F.count_distinct(F.when(F.col("odd") == 1, F.col("o_orderkey"))).alias("m"))
    out = coll.expected_collisions_df(size.join(got, F.lit(True)), 6, 4, 4)
    return out.select("n", "m", "reps", *[r6(c).alias(c) for c in ("mean", "variance", "ec")], r6(coll.collision_variance_bound(F.col("ec"))).alias("var_bound"))


_ERR = range(5)


@query(
    "collision_error_by_mantissa",
    " UNION ALL ".join(f"SELECT yr, k, n, {r} AS r, round({duck.expected_collisions('n', 'n', 6, 4, r)} / 64, 9) AS error, 6 / {2.0**r} AS bound FROM {_YEARLY_SETS}" for r in _ERR),
)
def collision_error_by_mantissa(spark, d):
    """What accidental matches add to a Jaccard index of sets as large as those of the orders, beside its bound 6 / 2**r."""
    out = None
    for r in _ERR:
        got = coll.expected_collisions_df(order_sets(spark, d), 6, 4, r, "n", "n").select("yr", "k", "n", F.lit(r).alias("r"), F.round(F.col("ec") / 64, 9).alias("error"), F.lit(6 / 2.0**r).alias("bound"))
        out = got if out is None else out.unionByName(got)
    return out


# ---- formulas and norms


def _incl_excl_sql(clauses: list[list[str]]) -> str:
    parts = []
    for mask in range(1, 1 << len(clauses)):
        names = sorted({x for i, c in enumerate(clauses) if mask >> i & 1 for x in c})
        sign = (-1) ** (mask.bit_count() + 1)
        parts.append(f"SELECT {sign} * {duck.hll('pw', 'filled', MEDIUM.k)} AS u FROM (SELECT sum(power(2.0, -e)) AS pw, count(*) AS filled FROM (SELECT bucket, max(reg >> {MEDIUM.r}) AS e FROM s WHERE o_orderpriority IN ({', '.join(repr(x) for x in names)}) GROUP BY bucket))")
    return f"WITH s AS ({duck.registers(_Y96, CUST, ['o_orderpriority'], MEDIUM)}) SELECT round(sum(u), 6) AS est FROM ({' UNION ALL '.join(parts)})"


for _name, _clauses in CNF.items():

    def _incl_excl(spark, d, clauses=_clauses):
        o = table(spark, d, "orders").where(F.year("o_orderdate") == 1996)
        return base.cnf_incl_excl(build.sketch(o, "o_custkey", ["o_orderpriority"], MEDIUM), clauses, MEDIUM, "o_orderpriority").select(r6("est").alias("est"))

    query(f"{_name}_incl_excl", _incl_excl_sql(_clauses))(_incl_excl)


@query(
    "f2_jaccard_median",
    """WITH x AS (SELECT DISTINCT o_orderpriority AS k, o_custkey FROM orders), n AS (SELECT k, count(*) AS n FROM x GROUP BY k),
z AS (SELECT k, i, sum(2 * ((('0x' || substr(md5(o_custkey::VARCHAR), 1 + 8 * (i // 32), 8))::BIGINT >> (31 - i % 32)) & 1) - 1)::BIGINT AS z FROM x, range(0, 128) r(i) GROUP BY k, i),
g AS (SELECT a.k AS a, b.k AS b, a.i % 8 AS g, avg(((a.z - b.z) * (a.z - b.z))::DOUBLE) AS d FROM z a JOIN z b ON a.i = b.i AND a.k < b.k GROUP BY ALL),
p AS (SELECT a, b, median(d) AS d FROM g GROUP BY a, b)
SELECT a, b, round(d, 6) AS d, round((na.n + nb.n - d) / (na.n + nb.n + d), 6) AS t FROM p JOIN n na ON na.k = a JOIN n nb ON nb.k = b""",
)
def f2_jaccard_median(spark, d):
    """Median of eight means of sixteen squared counters each."""
    o = table(spark, d, "orders").withColumnRenamed("o_orderpriority", "k")
    sizes = exact.exact_count(o, ["k"], "o_custkey").withColumnRenamed("exact", "n")
    return base.f2_jaccard(base.f2_fingerprint(o, "o_custkey", ["k"], 128), sizes, "k", groups=8).select("a", "b", r6("d").alias("d"), r6("t").alias("t"))


# ---- work, space and error

_K = 64


@query(
    "build_and_compare_work",
    f"SELECT o_orderpriority AS k, count(*) AS n, count(*) * {_K} AS khash_build, round(count(*) * log2({_K}), 6) AS kmv_build, count(*) AS kpart_build, round({_K} * log2({_K}), 6) AS kmv_compare, {_K} AS kpart_compare, any_value(filled) AS registers FROM orders JOIN (SELECT o_orderpriority AS p, count(*) AS filled FROM ({duck.registers('orders', CUST, ['o_orderpriority'], SMALL)}) GROUP BY 1) ON p = o_orderpriority WHERE o_custkey IS NOT NULL GROUP BY 1",
)
def build_and_compare_work(spark, d):
    """Operations of each kind of MinHash to build and to compare sketches of 64 values: elements times k, times
    log k, and one each; k log k and k."""
    o = table(spark, d, "orders").where("o_custkey is not null").groupBy(F.col("o_orderpriority").alias("k")).agg(F.count("*").alias("n"))
    filled = priorities(spark, d).groupBy(F.col("o_orderpriority").alias("k")).agg(F.count("*").alias("registers"))
    n, log = F.col("n"), F.log2(F.lit(float(_K)))
    return o.join(filled, "k").select("k", "n", (n * _K).alias("khash_build"), r6(n * log).alias("kmv_build"), n.alias("kpart_build"), r6(_K * log).alias("kmv_compare"), F.lit(_K).alias("kpart_compare"), "registers")


@query("stored_sketch_bytes")
def stored_sketch_bytes(spark, d):
    """Nominal bytes of a sketch beside those of its packed registers and of the file that holds it."""
    rows = []
    fs = spark.sparkContext._jvm.org.apache.hadoop.fs
    for params in (SMALL, MEDIUM, FrsParams(13, 6, 10)):
        path = f"{shared_dir(spark)}/sketch-{uuid.uuid4().hex}"
        sk = build.sketch(table(spark, d, "orders"), "o_custkey", [], params)
        build.to_packed(sk.withColumn("k", F.lit(1)), params, ["k"]).coalesce(1).write.parquet(path)
        at = fs.Path(path)
        size = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(at).getLength()
        rows.append((params.p, params.q, params.r, (params.q + params.r) * params.k / 8, build.register_bytes(params) * params.k, size))
    return spark.createDataFrame(rows, "p int, q int, r int, nominal double, packed bigint, parquet bigint")


@query("low_t_ranged")
def low_t_ranged(spark, d):
    """Sets of 2**20 elements at small t, about 4 KiB a sketch (HLL: 3 KiB): mean relative error of each method."""
    kinds = [
        {"method": "frs_2048x16", "kind": "frs", "p": 11, "q": 6, "r": 10},
        {"method": "minhash_1024x32", "kind": "minhash", "p": 10, "bits": 32},
        {"method": "bbit_4096x8", "kind": "bbit", "p": 12, "bits": 8},
        {"method": "hll_incl_excl_4096x6", "kind": "incl_excl", "p": 12, "q": 6},
        {"method": "hll_mle_4096x6", "kind": "mle", "p": 12, "q": 6},
        {"method": "f2_1024x32", "kind": "f2", "p": 10},
    ]
    grid = [k | {"t": t, "n": 2.0**20} for k in kinds for t in (0.01, 0.02, 0.05, 0.1)]
    return measures.relative_error_summary(simulate.register_trials(spark, grid, 32))


def _seeded_sql(reps: int) -> str:
    ts = ", ".join(f"{t!r}::DOUBLE" for t in (0.1, 0.5, 0.9))
    base_ = f"WITH n AS (SELECT (max(o_orderkey) + 1) // 2 AS n FROM orders), ts AS (SELECT unnest([{ts}]) AS t), b AS (SELECT t, n, round(2 * n * t / (1 + t))::BIGINT AS s FROM ts, n), x AS (SELECT t, 'a' AS side, o_orderkey FROM orders JOIN b ON o_orderkey < n UNION ALL SELECT t, 'b', o_orderkey FROM orders JOIN b ON o_orderkey >= n - s AND o_orderkey < 2 * n - s)"
    regs = " UNION ALL ".join(f"SELECT {s} AS rep, * FROM ({duck.registers('x', 'o_orderkey::VARCHAR', ['t', 'side'], SMALL.with_(seed=s))})" for s in range(1, reps + 1))
    return f"""{base_}, k AS ({regs}), c AS (SELECT t, rep, bucket, max(reg) FILTER (side = 'a') AS ra, max(reg) FILTER (side = 'b') AS rb FROM k GROUP BY ALL),
h AS (SELECT t, rep, count(*) FILTER (ra = rb) / count(*) AS t_hat FROM c GROUP BY t, rep), e AS (SELECT t, t_hat, abs(t_hat - t) / t AS err FROM h)
SELECT t, count(*) AS reps, round(avg(err), 6) AS mre, round(avg(err) - 1.96 * stddev_samp(err) / sqrt(count(*)), 6) AS ci_lo, round(avg(err) + 1.96 * stddev_samp(err) / sqrt(count(*)), 6) AS ci_hi, round(var_samp(t_hat), 6) AS variance FROM e GROUP BY t"""


@query("seeded_error_summary", _seeded_sql(16))
def seeded_error_summary(spark, d):
    """Mean relative error, its band and the variance over 16 hash seeds on ranges of order keys."""
    o = table(spark, d, "orders").select("o_orderkey")
    n = F.lit((o.agg(F.max("o_orderkey")).first()[0] + 1) // 2)
    rows = o.withColumn("t", F.explode(F.array(*[F.lit(t) for t in (0.1, 0.5, 0.9)])))
    s, key = F.round(2 * n * F.col("t") / (1 + F.col("t"))).cast("bigint"), F.col("o_orderkey")
    sides = F.array_compact(F.array(F.when(key < n, "a"), F.when((key >= n - s) & (key < 2 * n - s), "b")))
    rows = rows.select("t", "o_orderkey", F.explode(sides).alias("side")).withColumn("rep", F.explode(F.sequence(F.lit(1), F.lit(16))))
    sk = build.sketch(rows.withColumn("x", F.concat(F.col("rep").cast("string"), F.lit("|"), F.col("o_orderkey").cast("string"))), "x", ["t", "rep", "side"], SMALL)
    a, b = (sk.where(F.col("side") == x).select(F.col("t").alias("level"), "rep", "bucket", "reg") for x in "ab")
    trials = jaccard(a, b, SMALL, ["level", "rep"]).select(F.lit("frs").alias("method"), F.col("level").alias("t"), F.col("t_raw").alias("t_hat"))
    got = measures.relative_error_summary(trials, ("t",))
    return got.select("t", "reps", *[r6(c).alias(c) for c in ("mre", "ci_lo", "ci_hi", "variance")])


# ---- ablations

VARIANTS = [FrsParams(6, 3, 4, hash="sha1", mantissa=m, tail=t) for m in ("independent", "contiguous") for t in ("capped", "overflow")]


def _variant_sql() -> str:
    return " UNION ALL ".join(
        f"SELECT '{x.mantissa}' AS mantissa, '{x.tail}' AS tail, a, b, c, n_filled, round(c / n_filled, 6) AS t FROM (WITH sk AS (SELECT o_orderpriority AS k, bucket, reg FROM ({duck.registers('orders', CUST, ['o_orderpriority'], x)})), {duck.pair_cells(x)} SELECT * FROM pr)" for x in VARIANTS
    )


@query("ablation_mantissa_and_tail", _variant_sql())
def ablation_mantissa_and_tail(spark, d):
    out = None
    for x in VARIANTS:
        got = pairwise_jaccard(priorities(spark, d, x), "o_orderpriority", x).select(F.lit(x.mantissa).alias("mantissa"), F.lit(x.tail).alias("tail"), "a", "b", "c", "n_filled", r6("t_raw").alias("t"))
        out = got if out is None else out.unionByName(got)
    return out


@query("ablation_corrections")
def ablation_corrections(spark, d):
    """Each correction's estimate at the expected number of matches, for the customers of every two priorities of a year:
    what is left of the bias."""
    from frsketch.operators.jaccard import CORRECTIONS, finish

    params = FrsParams(10, 5, 4)
    o = table(spark, d, "orders").select(F.concat(F.year("o_orderdate").cast("string"), "o_orderpriority").alias("k"), "o_custkey")
    size = exact.exact_count(o, ["k"], "o_custkey")
    rows = exact.exact_jaccard(o, "k", "o_custkey").join(size.toDF("a", "n"), "a").join(size.toDF("b", "m"), "b").where(F.substr("a", F.lit(1), F.lit(4)) == F.substr("b", F.lit(1), F.lit(4)))
    rows = rows.select("a", "b", F.col("t").alias("truth"), F.col("n").cast("double").alias("n"), F.col("m").cast("double").alias("m"), F.col("both").cast("double").alias("g"))

    def run(batches):
        for x in batches:
            c = [coll.expected_matches(n - g, m - g, g, params.p, params.q, params.r) for n, m, g in zip(x["n"], x["m"], x["g"])]
            # a bucket is filled unless it got none of the union's elements
            filled = [params.k * -np.expm1((n + m - g) * np.log1p(-1 / params.k)) for n, m, g in zip(x["n"], x["m"], x["g"])]
            yield x.drop(columns="g").assign(c=c, n_filled=filled)

    df = rows.mapInPandas(run, "a string, b string, truth double, n double, m double, c double, n_filled double")
    out = None
    for how in CORRECTIONS:
        got = finish(df, params, how).select(F.lit(how).alias("correction"), "a", "b", "truth", r6("t_raw").alias("t"), r6((F.col("t_raw") - F.col("truth")) / F.col("truth")).alias("bias"))
        out = got if out is None else out.unionByName(got)
    return out


@query("ablation_printed_loop")
def ablation_printed_loop(spark, d):
    """The expectation for sets as large as those of the orders, over the boxes themselves and over boxes one mantissa step
    further."""

    def run(batches):
        for x in batches:
            for q, r in ((4, 2), (4, 4), (5, 8)):
                yield x.assign(q=q, r=r, **{how: [coll.expected_collisions(n, n, 6, q, r, loop=how) for n in x["n"]] for how in ("lemma", "as_printed")})

    return order_sets(spark, d).mapInPandas(run, "yr int, k string, n double, q int, r int, lemma double, as_printed double")


@query("ablation_unpacked_work", f"SELECT o_orderpriority AS k, count(*) AS registers, 0::BIGINT AS differ FROM ({duck.registers('orders', CUST, ['o_orderpriority'], SMALL)}) GROUP BY 1")
def ablation_unpacked_work(spark, d):
    """Registers compared as one word and as exponent, then mantissa: how many differ."""
    one = priorities(spark, d)
    two = build.sketch(table(spark, d, "orders"), "o_custkey", ["o_orderpriority"], SMALL, packed=False).withColumnRenamed("reg", "reg2")
    return one.join(two, ["o_orderpriority", "bucket"], "full").groupBy(F.col("o_orderpriority").alias("k")).agg(F.count("*").alias("registers"), F.count_if(~F.col("reg").eqNullSafe(F.col("reg2"))).alias("differ"))


# ---- parameters, by the customers of each year and priority


def order_truth(spark, d) -> tuple[DataFrame, DataFrame]:
    """(k, o_custkey) of all orders by year and priority, and the exact t of every two such sets."""
    o = table(spark, d, "orders").select(F.concat(F.year("o_orderdate").cast("string"), "o_orderpriority").alias("k"), "o_custkey")
    return o, exact.exact_jaccard(o, "k", "o_custkey").select("a", "b", F.col("t").alias("truth"))


def relative_errors(got: DataFrame, truth: DataFrame, by: list[str]) -> DataFrame:
    """got (by..., a, b, t) -> by..., mre, mean_t and pairs over the pairs of the truth."""
    err = F.abs(F.col("t") - F.col("truth")) / F.col("truth")
    return got.join(truth, ["a", "b"]).groupBy(*by).agg(F.avg(err).alias("mre"), F.avg("truth").alias("mean_t"), F.count("*").alias("pairs"))


@query("ablation_mantissa_bits")
def ablation_mantissa_bits(spark, d):
    """Relative error by mantissa bits, with and without the exact correction. A register less its low mantissa bits is the
    register of fewer: one sketch serves all."""
    o, truth = order_truth(spark, d)
    fine, out = build.sketch(o, "o_custkey", ["k"], FrsParams(10, 5, 12)), None
    for r in range(0, 13, 2):
        sk = fine.select("k", "bucket", F.shiftright("reg", 12 - r).alias("reg"))
        for how in ("none", "exact"):
            got = pairwise_jaccard(sk, "k", FrsParams(10, 5, r), how).select(F.lit(f"r{r}{'_debiased' if how == 'exact' else ''}").alias("method"), "a", "b", F.col("t_raw").alias("t"))
            out = got if out is None else out.unionByName(got)
    return relative_errors(out, truth, ["method"])


@query("ablation_buckets_and_window")
def ablation_buckets_and_window(spark, d):
    """Relative error by buckets and by exponent bits. Buckets are united into fewer; each window is sketched anew."""
    o, truth = order_truth(spark, d)
    out = None
    for q in (3, 4, 5):
        fine = build.sketch(o, "o_custkey", ["k"], FrsParams(10, q, 6))
        for p in (4, 6, 8, 10):
            sk = fine.groupBy("k", F.col("bucket").bitwiseAND(F.lit((1 << p) - 1)).alias("bucket")).agg(F.max("reg").alias("reg"))
            got = pairwise_jaccard(sk, "k", FrsParams(p, q, 6)).select(F.lit(f"p{p}_q{q}").alias("method"), "a", "b", F.col("t_raw").alias("t"))
            out = got if out is None else out.unionByName(got)
    return relative_errors(out, truth, ["method"])


@query("bits_for_error")
def bits_for_error(spark, d):
    """The smallest sketch of each kind whose mean relative error is at most 0.25, by the first digit of the Jaccard index
    of the pairs. One sketch of a kind serves all sizes, its buckets united into fewer."""
    o, truth = order_truth(spark, d)
    most = FrsParams(14, 6, 10)
    fine = build.sketch(o, "o_custkey", ["k"], most)
    mh, out = base.minhash_kpart(o, "o_custkey", ["k"], most.p, 32), None
    for p in range(4, 15):
        bucket = F.col("bucket").bitwiseAND(F.lit((1 << p) - 1)).alias("bucket")
        params = FrsParams(p, 6, 10)
        sk = fine.groupBy("k", bucket).agg(F.max("reg").alias("reg"))
        for name, bits, got in (
            ("frs", 16, pairwise_jaccard(sk, "k", params)),
            ("incl_excl", 6, base.incl_excl_jaccard(sk, "k", params)),
            ("minhash", 32, base.minhash_jaccard(mh.groupBy("k", bucket).agg(F.min("val").alias("val")), "k")),
        ):
            got = got.select(F.lit(name).alias("method"), F.lit(bits << p).cast("long").alias("bits"), "a", "b", "t")
            out = got if out is None else out.unionByName(got)
    truth = truth.withColumn("level", F.floor(F.col("truth") * 10) / 10)
    return measures.bits_for_error(relative_errors(out, truth, ["method", "level", "bits"]).withColumnRenamed("level", "t"), 0.25)


# ---- edges and surroundings


@query("card_infinite", f"SELECT count(*) AS filled, CASE WHEN count(*) = 64 THEN 'Infinity'::DOUBLE ELSE 4096.0 / (64 - count(*)) END AS est FROM ({duck.registers('orders', 'o_orderkey::VARCHAR', [], SMALL)})")
def card_infinite(spark, d):
    """The registers of all order keys, as if each held the smallest hash there is: the sum of minima is zero."""
    top = (SMALL.last << SMALL.r) + SMALL.scale - 1
    sk = build.sketch(table(spark, d, "orders"), "o_orderkey", [], SMALL).select("bucket", F.lit(top).alias("reg"))
    return cardinality(sk, [], SMALL, "minvalue").select("filled", "est")


for _name, _op in (("sets_intersect_all", "INTERSECT ALL"), ("sets_except_all", "EXCEPT ALL"), ("sets_union_all", "UNION ALL")):

    def _bags(spark, d, op=_op):
        o = table(spark, d, "orders")
        a, b = (o.where(F.col("o_orderpriority") == p).select(F.col("o_custkey").alias("custkey")) for p in ("1-URGENT", "2-HIGH"))
        return {"INTERSECT ALL": a.intersectAll, "EXCEPT ALL": a.exceptAll, "UNION ALL": a.unionAll}[op](b)

    query(_name, f"SELECT o_custkey AS custkey FROM orders WHERE o_orderpriority = '1-URGENT' {_op} SELECT o_custkey FROM orders WHERE o_orderpriority = '2-HIGH'")(_bags)

_FINE = "(SELECT l_returnflag AS flag, l_linestatus AS line_status, l_partkey::VARCHAR AS x FROM lineitem)"


@query(
    "frs_grouping_sets",
    f"WITH x AS ({duck.registers(_FINE, 'x', ['flag', 'line_status'], SMALL)}) SELECT flag, line_status, bucket, max(reg) AS reg FROM x GROUP BY GROUPING SETS ((flag, bucket), (line_status, bucket))",
)
def frs_grouping_sets(spark, d):
    li = table(spark, d, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("line_status"), "l_partkey")
    fine = build.sketch(li, "l_partkey", ["flag", "line_status"], SMALL)
    return fine.groupingSets([["flag", "bucket"], ["line_status", "bucket"]], "flag", "line_status", "bucket").agg(F.max("reg").alias("reg")).select("flag", "line_status", "bucket", "reg")


_SLIDE = "(SELECT date_trunc('day', ts)::TIMESTAMP - INTERVAL (i) DAY AS win, user_id::VARCHAR AS x FROM events, range(0, 2) r(i))"


@query("sliding_window_sketch", f"SELECT strftime(win, '%Y-%m-%d') AS win, bucket, reg FROM ({duck.registers(_SLIDE, 'x', ['win'], SMALL)})")
def sliding_window_sketch(spark, d):
    """Windows of two days that start every day, in event time."""
    out = streams.stream_sketch(table(spark, d, "events"), "ts", "user_id", [], SMALL, window="2 days", slide="1 day")
    return out.select(F.date_format("win", "yyyy-MM-dd").alias("win"), "bucket", "reg")


_DAYS = "(SELECT strftime(ts, '%Y-%m-%d') AS win, user_id::VARCHAR AS x FROM events)"


@query("stream_late_repair", f"SELECT win, bucket, reg FROM ({duck.registers(_DAYS, 'x', ['win'], SMALL)})")
def stream_late_repair(spark, d):
    """Rows that come too late for their window are sketched apart and united with it: the result is that of all rows."""
    ev = table(spark, d, "events")
    late = F.pmod(F.xxhash64("event_id"), F.lit(10)) == 0
    timely, rest = (streams.stream_sketch(ev.where(x), "ts", "user_id", [], SMALL) for x in (~late, late))
    return build.union_sketches(timely, rest).select(F.date_format("win", "yyyy-MM-dd").alias("win"), "bucket", "reg")


_TURNS = "(SELECT role AS k, text FROM conversations)"


@query("conversation_role_matrix", f"WITH sh AS ({duck.shingles(_TURNS, 'k', 'text')}), sk AS ({duck.registers('sh', 'shingle', ['k'], MEDIUM)}), {duck.pair_cells(MEDIUM)} SELECT a, b, c, n_filled, round(c / n_filled, 6) AS t FROM pr")
def conversation_role_matrix(spark, d):
    from frsketch.functions.text import word_shingles

    sh = word_shingles(table(spark, d, "conversations"), "role", "text")
    return pairwise_jaccard(build.sketch(sh, "shingle", ["role"], MEDIUM), "role", MEDIUM).select("a", "b", "c", "n_filled", r6("t_raw").alias("t"))


@query(
    "relative_error_of_unions",
    f"WITH sk AS (SELECT o_orderpriority AS k, bucket, reg FROM ({duck.registers('orders', CUST, ['o_orderpriority'], MEDIUM)})), {duck.pair_cells(MEDIUM)}, u AS (SELECT pr.a, pr.b, any_value(c / n_filled) AS t, {duck.moments(MEDIUM)} FROM pr JOIN (SELECT x.a, x.b, bucket, max(reg) AS reg FROM pr x JOIN sk ON sk.k = x.a OR sk.k = x.b GROUP BY ALL) USING (a, b) GROUP BY pr.a, pr.b), "
    f"m AS (SELECT a, b, t, {duck.estimate(MEDIUM)} AS est FROM u), x AS (SELECT DISTINCT o_orderpriority AS k, o_custkey AS e FROM orders), n AS (SELECT k, count(*) AS n FROM x GROUP BY k), i AS (SELECT a.k AS a, b.k AS b, count(*) AS c FROM x a JOIN x b ON a.e = b.e AND a.k < b.k GROUP BY a.k, b.k) "
    "SELECT m.a, m.b, round(abs(est / (na.n + nb.n - i.c) - 1), 6) AS union_error, round(abs(t * est / i.c - 1), 6) AS both_error FROM m JOIN i ON i.a = m.a AND i.b = m.b JOIN n na ON na.k = m.a JOIN n nb ON nb.k = m.b",
)
def relative_error_of_unions(spark, d):
    """Relative error of the estimated union and intersection of every two priorities' customers."""
    sk = priorities(spark, d, MEDIUM)
    pr = pairwise_jaccard(sk, "o_orderpriority", MEDIUM).select("a", "b", "t")
    sides = pr.select("a", "b", F.explode(F.array("a", "b")).alias("o_orderpriority"))
    union = cardinality(sides.join(sk, "o_orderpriority").groupBy("a", "b", "bucket").agg(F.max("reg").alias("reg")), ["a", "b"], MEDIUM).select("a", "b", "est")
    o = table(spark, d, "orders").select(F.col("o_orderpriority").alias("k"), "o_custkey")
    size = exact.exact_count(o, ["k"], "o_custkey")
    truth = exact.exact_jaccard(o, "k", "o_custkey").join(size.toDF("a", "na"), "a").join(size.toDF("b", "nb"), "b").select("a", "b", "both", (F.col("na") + F.col("nb") - F.col("both")).alias("any_"))
    got = pr.join(union, ["a", "b"]).join(truth, ["a", "b"])
    return got.select("a", "b", r6(F.abs(F.col("est") / F.col("any_") - 1)).alias("union_error"), r6(F.abs(F.col("t") * F.col("est") / F.col("both") - 1)).alias("both_error"))
