"""Jaccard index and intersection size from sketches."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.functions.collisions import LIMIT, approx_collisions_col, box_mass_cols, expected_collisions_df, range_status
from frsketch.functions.hashing import decode, exponent_of
from frsketch.operators.build import check_same, register_bytes, union_sketches
from frsketch.operators.cardinality import from_moments, moments
from frsketch.operators.meeting import cell_rows, equal_cells
from frsketch.params import FrsParams

CORRECTIONS = ("none", "exact", "approx", "limit", "overlap")
MAX_WORDS = 1024  # of a packed sketch; larger sketches meet bucket by bucket
BLOCKS = 8


def finish(df: DataFrame, params: FrsParams, correction: str = "none", denominator: str = "filled", small: Column | None = None) -> DataFrame:
    """From c, n_filled, n, m to ec, t_raw, t (clamped to 0..1) and status. ``correction``: none; exact
    or approx expectation of accidental matches; two own extensions: limit (the large-r constant) and
    overlap (accidental matches of overlapping sets). Both sets empty: null. ``small``: the exponent-only
    expectation, where the caller has it."""
    if correction not in CORRECTIONS:
        raise ValueError(f"correction {correction!r} is none of {CORRECTIONS}")
    n, m = F.col("n"), F.col("m")
    if correction == "none":
        df = df.withColumn("ec", F.lit(0.0))
    elif correction == "exact":
        df = expected_collisions_df(df, params.p, params.q, params.r)
    elif correction == "limit":
        df = df.withColumn("ec", approx_collisions_col(n, m, params, LIMIT, small))
    else:
        df = df.withColumn("ec", approx_collisions_col(n, m, params, bare=small))
    base = F.lit(float(params.k)) if denominator == "all" else F.col("n_filled").cast("double")
    base = F.when(base > 0, base)
    if correction == "overlap":
        share = F.col("c") / base
        c0 = F.col("ec") / params.k
        big, small = F.greatest(n, m), F.least(n, m)
        # solve t + c0 (a m + b n)(n + m)^2 / (2 n m u^2) = c / N, with a, b, u functions of t
        t: Column = share
        for _ in range(6):
            u = (n + m) / (1 + t)
            both = t * u
            extra = c0 * ((n - both) * m + (m - both) * n) * (n + m) * (n + m) / (2 * big * small * u * u)
            t = share - F.when(small > 0, extra).otherwise(0.0)
            df = df.withColumn("_t", t)
            t = F.col("_t")
        df = df.withColumn("t_raw", F.col("_t")).drop("_t")
    else:
        df = df.withColumn("t_raw", (F.col("c") - F.col("ec")) / base)
    clamped = F.when(F.col("t_raw").isNotNull(), F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("t_raw"))))
    return df.withColumn("t", clamped).withColumn("status", range_status(n, m, params))


def side_moments(params: FrsParams, side: str, how: str = "lower") -> list[Column]:
    reg = F.col(side)
    return [F.count(reg).alias(f"{side}_filled"), F.coalesce(F.sum(F.pow(F.lit(2.0), -exponent_of(reg, params))), F.lit(0.0)).alias(f"{side}_pow"), F.coalesce(F.sum(decode(reg, params, how)), F.lit(0.0)).alias(f"{side}_val")]


def jaccard(a: DataFrame, b: DataFrame, params: FrsParams, by: list[str] | None = None, correction: str = "none", denominator: str = "filled") -> DataFrame:
    """(by..., c, n_filled, n, m, ec, t_raw, t, status) of two sketches, for each value of ``by``. No join:
    both sides are laid over each other and grouped by bucket; every moment comes from that one pass."""
    check_same(a, b)
    by = by or []
    if clash := {"c", "n_filled", "n", "m", "ec", "t_raw", "t", "status", "ra", "rb", "bucket"} & set(by):
        raise ValueError(f"key columns named like results: {sorted(clash)}")
    both = a.select(*by, "bucket", F.col("reg").alias("ra"), F.lit(None).cast("int").alias("rb")).unionByName(b.select(*by, "bucket", F.lit(None).cast("int").alias("ra"), F.col("reg").alias("rb")))
    cells = both.groupBy(*by, "bucket").agg(F.max("ra").alias("ra"), F.max("rb").alias("rb"))
    got = cells.groupBy(*by).agg(F.count_if(F.col("ra") == F.col("rb")).alias("c"), F.count("*").alias("n_filled"), *side_moments(params, "ra"), *side_moments(params, "rb"))
    n = [from_moments(params, "auto", F.col(f"{s}_pow"), F.col(f"{s}_val"), F.col(f"{s}_filled"))[0] for s in ("ra", "rb")]
    got = got.select(*by, "c", "n_filled", n[0].alias("n"), n[1].alias("m"))
    return finish(got, params, correction, denominator)


def pairwise_jaccard(sk: DataFrame, key: str, params: FrsParams, correction: str = "none", denominator: str = "filled", least: float = 0.0, pairs: DataFrame | None = None, queries: Callable[[Column], Column] | None = None, blocks: bool = False) -> DataFrame:
    """(a, b, c, n_filled, n, m, ec, t_raw, t, status) of every two keys, a < b, or of the given pairs (a, b), or of
    every key a that ``queries`` holds for and every other key b. Keys without a common filled bucket are a pair too.

    Every two keys are as many rows as there are pairs of keys, whatever the plan: for very many keys give
    pairs, as ``similar_pairs`` and ``jaccard_pairs`` do. With ``blocks``, for many pairs a key, given pairs meet their
    sketches block by block instead of in a row for each pair and bucket, and keep their further columns."""
    lanes = 8 // register_bytes(params)
    if pairs is not None and blocks:
        out = by_blocks(sk, key, params, pairs, correction, denominator)
    elif pairs is None and params.k <= MAX_WORDS * lanes:
        out = every_two(sk, key, params, lanes, correction, denominator, queries)
    else:
        if queries is not None:
            names = sk.select(F.col(key).alias("b")).where("b is not null").distinct()
            pairs = names.select(F.col("b").alias("a")).where(queries(F.col("a"))).join(names, F.col("a") != F.col("b"))
        out = by_buckets(sk, key, params, pairs, correction, denominator)
    return out.where(F.col("t") >= least) if least > 0 else out


def by_blocks(sk: DataFrame, key: str, params: FrsParams, pairs: DataFrame, correction: str, denominator: str) -> DataFrame:
    """The given pairs, whose sketches are compared as arrays."""
    est, _ = from_moments(params)
    rows = cell_rows(sk, key, "reg", *moments(params)).select("key", "buckets", "vals", est.alias("est"))
    got = finish(equal_cells(pairs, rows, {"est": ("n", "m")}), params, correction, denominator)
    own = ["a", "b", "c", "n_filled", "n", "m", "ec", "t_raw", "t", "status"]
    return got.select(*own, *[c for c in pairs.columns if c not in own])


def by_buckets(sk: DataFrame, key: str, params: FrsParams, pairs: DataFrame | None, correction: str, denominator: str) -> DataFrame:
    """Sketches meet by bucket; where no pairs are given, all keys also meet at one that holds nothing."""
    one = sk.select(F.col(key).alias("a"), "bucket", F.col("reg").alias("ra"))
    two = sk.select(F.col(key).alias("b"), "bucket", F.col("reg").alias("rb"))
    if pairs is None:
        none = sk.select(F.col(key).alias("a"), F.lit(-1).alias("bucket"), F.lit(None).cast("int").alias("ra")).distinct()
        cells = one.unionByName(none).join(two.unionByName(none.toDF("b", "bucket", "rb")), "bucket").where("a < b")
    else:
        cells = pairs.select("a", "b").join(one, "a").join(two, ["b", "bucket"])
    got = cells.groupBy("a", "b").agg(F.count_if(F.col("ra") == F.col("rb")).alias("c"), F.count("ra").alias("both"))
    if pairs is not None:
        got = pairs.select("a", "b").join(got, ["a", "b"], "left")
    est, _ = from_moments(params)
    size = sk.groupBy(F.col(key).alias("key")).agg(*moments(params)).select("key", "filled", est.alias("est"))
    got = got.join(size.select(F.col("key").alias("a"), F.col("filled").alias("fa"), F.col("est").alias("n")), "a")
    got = got.join(size.select(F.col("key").alias("b"), F.col("filled").alias("fb"), F.col("est").alias("m")), "b")
    got = got.select("a", "b", F.coalesce("c", F.lit(0)).alias("c"), (F.col("fa") + F.col("fb") - F.coalesce("both", F.lit(0))).alias("n_filled"), "n", "m")
    return finish(got, params, correction, denominator)


def nonempty_lanes(v: Column, lanes: int) -> Column:
    """How many of a 64-bit word's lanes are not zero: each lane's bits are folded onto its lowest."""
    width = 64 // lanes
    step = width // 2
    while step:
        v = v.bitwiseOR(F.shiftrightunsigned(v, step))
        step //= 2
    return F.bit_count(v.bitwiseAND(F.lit(sum(1 << width * i for i in range(lanes)))))


def every_two(sk: DataFrame, key: str, params: FrsParams, lanes: int, correction: str, denominator: str, queries: Callable[[Column], Column] | None = None) -> DataFrame:
    """A key is one row of registers packed into 64-bit words; rows meet block by block, an equality join whose
    inputs are ``BLOCKS`` copies of the keys and whose only large output are the pairs."""
    words = -(-params.k // lanes)
    bits = 64 // lanes
    word = F.call_function("shiftleft", F.col("reg").cast("bigint"), (F.col("bucket") % lanes * bits).cast("int"))
    one = sk.groupBy(F.col(key).alias("key"), F.floor(F.col("bucket") / lanes).alias("w")).agg(F.bit_or(word).alias("v"), *moments(params))
    flat = words <= 32
    if flat:
        cells = [F.coalesce(F.max(F.when(F.col("w") == i, F.col("v"))), F.lit(0).cast("bigint")).alias(f"w{i}") for i in range(words)]
    else:  # every word of every key is there, so that sorted lists are dense
        none = sk.select(F.col(key).alias("key")).distinct().select("key", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(words - 1).cast("bigint"))).alias("w"), F.lit(0).cast("bigint").alias("v"), F.lit(0).cast("bigint").alias("filled"), F.lit(0.0).alias("_pow"), F.lit(0.0).alias("_val"))
        one = one.unionByName(none).groupBy("key", "w").agg(F.bit_or("v").alias("v"), *[F.sum(c).alias(c) for c in ("filled", "_pow", "_val")])
        cells = [F.transform(F.array_sort(F.collect_list(F.struct("w", "v"))), lambda x: x["v"]).alias("w")]
    est, _ = from_moments(params)
    rows = one.groupBy("key").agg(*cells, *[F.sum(c).alias(c) for c in ("filled", "_pow", "_val")])
    names = [f"w{i}" for i in range(words)] if flat else ["w"]
    rows = rows.select("key", *names, est.alias("est"))
    approx = correction not in ("none", "exact")
    mass = box_mass_cols(F.col("est"), params) if approx else []
    rows = rows.select("*", *[x.alias(f"m{i}") for i, x in enumerate(mass)])
    all_blocks = F.explode(F.sequence(F.lit(0), F.lit(BLOCKS - 1)))
    own = F.pmod(F.xxhash64("key"), F.lit(BLOCKS)).cast("int")
    asked = rows if queries is None else rows.where(queries(F.col("key")))
    a = asked.select(own.alias("i"), all_blocks.alias("j"), *[F.col(c).alias(f"a_{c}") for c in rows.columns])
    b = rows.select(all_blocks.alias("i"), own.alias("j"), *[F.col(c).alias(f"b_{c}") for c in rows.columns])
    # a given count is kept: by their bytes these few rows would be put into a few tasks
    a, b = (x.repartition(BLOCKS * BLOCKS, "i", "j") for x in (a, b))
    both = a.join(b, ["i", "j"]).where("a_key < b_key" if queries is None else "a_key <> b_key")
    if flat:
        pairs = [(F.col(f"a_w{i}"), F.col(f"b_w{i}")) for i in range(words)]
        filled = sum((nonempty_lanes(x.bitwiseOR(y), lanes) for x, y in pairs[1:]), nonempty_lanes(pairs[0][0].bitwiseOR(pairs[0][1]), lanes))
        differ = sum((nonempty_lanes(x.bitwiseXOR(y), lanes) for x, y in pairs[1:]), nonempty_lanes(pairs[0][0].bitwiseXOR(pairs[0][1]), lanes))
    else:
        add = lambda s, x: s + x
        filled = F.aggregate(F.zip_with("a_w", "b_w", lambda x, y: nonempty_lanes(x.bitwiseOR(y), lanes)), F.lit(0), add)
        differ = F.aggregate(F.zip_with("a_w", "b_w", lambda x, y: nonempty_lanes(x.bitwiseXOR(y), lanes)), F.lit(0), add)
    small = None
    if approx:
        for i in range(len(mass)):
            term = F.col(f"a_m{i}") * F.col(f"b_m{i}")
            small = term if small is None else small + term
        small = small * float(params.k)
    got = both.select(F.col("a_key").alias("a"), F.col("b_key").alias("b"), filled.cast("bigint").alias("n_filled"), differ.cast("bigint").alias("_d"), F.col("a_est").alias("n"), F.col("b_est").alias("m"), *([small.alias("_small")] if approx else []))
    got = got.select("a", "b", (F.col("n_filled") - F.col("_d")).alias("c"), "n_filled", "n", "m", *(["_small"] if approx else []))
    out = finish(got, params, correction, denominator, F.col("_small") if approx else None)
    return out.select("a", "b", "c", "n_filled", "n", "m", "ec", "t_raw", "t", "status")


def intersection_cardinality(a: DataFrame, b: DataFrame, params: FrsParams, by: list[str] | None = None, correction: str = "none") -> DataFrame:
    """(by..., t, union_est, est): Jaccard times the cardinality of the union."""
    by = by or []
    t = jaccard(a, b, params, by, correction).select(*by, "t")
    est, _ = from_moments(params)
    u = union_sketches(a.select(*by, "bucket", "reg"), b.select(*by, "bucket", "reg")).groupBy(*by).agg(*moments(params)).select(*by, est.alias("union_est"))
    got = t.join(u, by) if by else t.join(u, F.lit(True))
    return got.select(*by, "t", "union_est", (F.col("t") * F.col("union_est")).alias("est"))
