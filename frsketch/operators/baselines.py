"""The sketches and estimators compared with: MinHash variants, KMV, b-bit, norm reduction, HLL unions."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from frsketch.functions.hashing import digest, element_key, exponent_of, word
from frsketch.operators.cardinality import hll_estimate
from frsketch.operators.meeting import at_pairs, cell_rows, equal_cells, matrix, ones
from frsketch.params import FrsParams


def _keys(df: DataFrame, elements, by: list[str]) -> DataFrame:
    return df.select(*by, element_key(elements).alias("_key")).where("_key is not null")


# ---- k-partition MinHash


def minhash_kpart(df: DataFrame, elements, by: list[str], p: int, bits: int, params: FrsParams | None = None, contiguous: bool = False) -> DataFrame:
    """(by..., bucket, val): the smallest hash of each bucket at ``bits`` fixed bits. ``contiguous``
    takes the bits right after the bucket's, as the contiguous registers do."""
    params = (params or FrsParams()).with_(p=p)
    d = F.col("_d")
    rows = _keys(df, elements, by).select(*by, digest(F.col("_key"), params).alias("_d"))
    if contiguous:
        n = -(-(p + bits) // 32)
        whole = F.concat(*[F.lpad(F.conv(F.substring(d, 8 * i + 1, 8), 16, 2), 32, "0") for i in range(n)])
        bucket = F.conv(F.substring(whole, 1, p), 2, 10).cast("int") if p else F.lit(0)
        val = F.conv(F.substring(whole, p + 1, bits), 2, 10).cast("bigint")
    else:
        bucket = word(d, 0).bitwiseAND(F.lit((1 << p) - 1)).cast("int")
        if bits <= 32:
            val = F.shiftright(word(d, 8), 32 - bits) if bits < 32 else word(d, 8)
        else:  # 63 bits keep the sign free
            val = F.shiftleft(word(d, 8), min(bits, 63) - 32) + F.shiftright(word(d, 16), 64 - min(bits, 63))
    return rows.select(*by, bucket.alias("bucket"), val.alias("val")).groupBy(*by, "bucket").agg(F.min("val").alias("val"))


def minhash_union(*sketches: DataFrame) -> DataFrame:
    out = sketches[0]
    for s in sketches[1:]:
        out = out.unionByName(s)
    return out.groupBy(*[c for c in out.columns if c != "val"]).agg(F.min("val").alias("val"))


def every_two_lists(df: DataFrame, key: str, value: str, empty=None) -> DataFrame:
    """(a, b, fa, fb, va, vb) of every two keys a < b: how many buckets each fills, and its values of all buckets that any
    key fills, in one order; ``empty`` where it has none. A key is one row, and rows meet block by block."""
    rows = df.where(F.col(key).isNotNull()).select(F.col(key).alias("key"), "bucket", F.col(value).alias("v"), F.lit(1).alias("own"))
    none = rows.select("key").distinct().crossJoin(F.broadcast(rows.select("bucket").distinct()))  # at most as many as a sketch has
    rows = rows.unionByName(none.select("key", "bucket", F.lit(empty).cast(rows.schema["v"].dataType).alias("v"), F.lit(0).alias("own")))
    cells = rows.groupBy("key", "bucket").agg(F.max_by("v", "own").alias("v"), F.max("own").alias("own"))
    lists = cells.groupBy("key").agg(F.transform(F.array_sort(F.collect_list(F.struct("bucket", "v"))), lambda x: x["v"]).alias("v"), F.sum("own").alias("f"))
    block, every = F.pmod(F.xxhash64("key"), F.lit(8)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(7)))
    one = lists.select(block.alias("x"), every.alias("y"), F.col("key").alias("a"), F.col("f").alias("fa"), F.col("v").alias("va"))
    two = lists.select(every.alias("x"), block.alias("y"), F.col("key").alias("b"), F.col("f").alias("fb"), F.col("v").alias("vb"))
    # a given count is kept: by their bytes these few rows would be put into a few tasks
    return one.repartition(64, "x", "y").join(two.repartition(64, "x", "y"), ["x", "y"]).where("a < b").select("a", "b", "fa", "fb", "va", "vb")


def minhash_jaccard(mh: DataFrame, key: str, pairs: DataFrame | None = None) -> DataFrame:
    """(a, b, c, n_filled, t) of every two keys, or of the given pairs (a, b, further columns, which are kept)."""
    if pairs is not None:
        return equal_cells(pairs, cell_rows(mh, key, "val")).withColumn("t", F.col("c") / F.col("n_filled"))
    same, both = F.lit((1 << 32) + 1), F.lit(1 << 32)
    each = F.zip_with("va", "vb", lambda x, y: F.when(x == y, same).when(x.isNotNull() & y.isNotNull(), both).otherwise(F.lit(0).cast("bigint")))
    got = every_two_lists(mh, key, "val").select("a", "b", "fa", "fb", F.aggregate(each, F.lit(0).cast("bigint"), lambda s, x: s + x).alias("s"))
    n = F.col("fa") + F.col("fb") - F.shiftright("s", 32)
    got = got.select("a", "b", F.col("s").bitwiseAND(both - 1).alias("c"), n.alias("n_filled"))
    return got.select("a", "b", "c", "n_filled", (F.col("c") / F.col("n_filled")).alias("t"))


def minhash_cardinality(mh: DataFrame, by: list[str], p: int, bits: int) -> DataFrame:
    """(by..., est): k**2 over the sum of minima, empty buckets counting 1."""
    k, top = 1 << p, 2.0 ** min(bits, 63)
    return mh.groupBy(*by).agg((float(k) * k / (F.sum(F.col("val") / top) + (k - F.count("*")))).alias("est"))


# ---- MinHash with k hash functions


def minhash_khash(df: DataFrame, elements, by: list[str], k: int) -> DataFrame:
    """(by..., i, val): the smallest of hash function i, 48 bits. k hashes an element."""
    rows = _keys(df, elements, by).select(*by, "_key", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("i"))
    val = word(F.md5(F.concat(F.col("i").cast("string"), F.lit(":"), F.col("_key"))), 0, 12)
    return rows.select(*by, "i", val.alias("val")).groupBy(*by, "i").agg(F.min("val").alias("val"))


def khash_jaccard(mh: DataFrame, key: str, k: int) -> DataFrame:
    """(a, b, c, t)."""
    one = mh.select(F.col(key).alias("a"), "i", F.col("val").alias("va"))
    two = mh.select(F.col(key).alias("b"), "i", F.col("val").alias("vb"))
    got = one.join(two, "i").where("a < b").groupBy("a", "b").agg(F.count_if(F.col("va") == F.col("vb")).alias("c"))
    return got.select("a", "b", "c", (F.col("c") / float(k)).alias("t"))


# ---- k minimum values


def kmv(df: DataFrame, elements, by: list[str], k: int, salts: int = 64) -> DataFrame:
    """(by..., vals): the k smallest distinct 48-bit hashes, ascending. Each key is first cut to k values
    a salt (the hash's last bits), so no key gathers more than k * salts rows."""
    rows = _keys(df, elements, by).select(*by, word(F.md5("_key"), 0, 12).alias("v"))
    rows = rows.select(*by, "v", (F.col("v") % salts).alias("salt")).distinct()
    first = Window.partitionBy(*by, "salt").orderBy("v")
    rows = rows.withColumn("i", F.row_number().over(first)).where(F.col("i") <= k)
    lists = rows.groupBy(*by).agg(F.sort_array(F.collect_list("v")).alias("vals"))  # at most k * salts
    return lists.select(*by, F.slice("vals", 1, k).alias("vals"))


def kmv_cardinality(sk: DataFrame, by: list[str], k: int) -> DataFrame:
    """(by..., est): (k - 1) / k-th value; exact below k values."""
    top = F.element_at("vals", -1) / 2.0**48
    return sk.select(*by, F.when(F.size("vals") < k, F.size("vals").cast("double")).otherwise((k - 1) / top).alias("est"))


def kmv_jaccard(sk: DataFrame, key: str, k: int) -> DataFrame:
    """(a, b, c, t): share of the union's k smallest that both have. Sketches meet pair by pair."""
    return kmv_pairs(sk.select(F.col(key).alias("a"), F.col("vals").alias("va")), sk.select(F.col(key).alias("b"), F.col("vals").alias("vb")), k, F.col("a") < F.col("b"))


def kmv_pairs(one: DataFrame, two: DataFrame, k: int, on: Column) -> DataFrame:
    got = one.join(two, on)
    union = F.slice(F.sort_array(F.array_distinct(F.concat("va", "vb"))), 1, k)
    got = got.withColumn("u", union)
    c = F.size(F.array_intersect(F.array_intersect("u", "va"), "vb"))
    return got.select("a", "b", c.alias("c"), (c / F.size("u")).alias("t"))


def bottomk_float(sk: DataFrame, by: list[str], params: FrsParams) -> DataFrame:
    """A KMV sketch whose values are stored as float codes: (by..., codes), descending codes."""
    zeros, r = params.zeros, params.r

    def code(v):
        lead = F.when(v == 0, 0).otherwise(F.length(F.bin(v)))
        e = F.when(lead <= 48 - zeros, params.last).otherwise(49 - lead)
        m = F.call_function("shiftright", v, (F.lit(48) - F.least(e, F.lit(zeros)) - r).cast("int")).bitwiseAND(F.lit(params.scale - 1))
        return (e * params.scale + (params.scale - 1 - m)).cast("int")

    return sk.select(*by, F.sort_array(F.transform("vals", code), asc=False).alias("codes"))


def bottomk_float_jaccard(sk: DataFrame, key: str, k: int) -> DataFrame:
    """(a, b, c, t) from float codes, the larger code being the smaller hash."""
    one = sk.select(F.col(key).alias("a"), F.col("codes").alias("va"))
    two = sk.select(F.col(key).alias("b"), F.col("codes").alias("vb"))
    got = one.join(two, F.col("a") < F.col("b"))
    got = got.withColumn("u", F.slice(F.sort_array(F.array_distinct(F.concat("va", "vb")), asc=False), 1, k))
    c = F.size(F.array_intersect(F.array_intersect("u", "va"), "vb"))
    return got.select("a", "b", c.alias("c"), (c / F.size("u")).alias("t"))


# ---- b-bit fingerprints


def bbit_fingerprint(mh: DataFrame, b: int) -> DataFrame:
    """The low b bits of finished minima."""
    return mh.select(*[c for c in mh.columns if c != "val"], F.col("val").bitwiseAND(F.lit((1 << b) - 1)).alias("val"))


def bbit_jaccard(fp: DataFrame, key: str, b: int) -> DataFrame:
    """(a, b, c, n_filled, t): the share of equal fingerprints less the accidental ones."""
    got = minhash_jaccard(fp, key)
    return got.withColumn("t", (F.col("t") - 2.0**-b) / (1 - 2.0**-b))


def bbit_space(eps: float, t: float) -> float:
    """Order of the bits needed at high similarity."""
    return (1 - t) ** 2 / eps**2 * math.log(1 / (1 - t))


# ---- norm reduction


def f2_fingerprint(df: DataFrame, elements, by: list[str], counters: int) -> DataFrame:
    """(by..., i, z): sums of random signs over distinct elements, at most 128 counters a digest."""
    if counters > 128:
        raise ValueError("at most 128 counters")
    rows = _keys(df, elements, by).distinct().select(*by, F.md5("_key").alias("d"))
    # counters i and i + 32 are added up in one number, 32 bits each: ones of fewer than 2**32 elements
    two = [word(F.col("d"), 16 * j).bitwiseOR(F.shiftleft(word(F.col("d"), 16 * j + 8), 32)) for j in range(-(-counters // 64))]
    rows = rows.select(*by, *[x.alias(f"_w{j}") for j, x in enumerate(two)])
    mask = F.lit((1 << 32) + 1)
    sums = {(j, i): F.sum(F.shiftrightunsigned(f"_w{j}", 31 - i).bitwiseAND(mask)) for j in range(len(two)) for i in range(min(32, counters - 64 * j))}
    ones = {(2 * j + high, i): F.shiftrightunsigned(s, 32) if high else s.bitwiseAND(F.lit((1 << 32) - 1)) for (j, i), s in sums.items() for high in (0, 1)}
    wide = rows.groupBy(*by).agg(F.array(*[ones[divmod(i, 32)] * 2 - F.count("*") for i in range(counters)]).alias("z"))
    return wide.select(*by, F.posexplode("z").alias("i", "z"))


def f2_jaccard(fp: DataFrame, sizes: DataFrame, key: str, groups: int = 1, queries: Callable[[Column], Column] | None = None, pairs: DataFrame | None = None) -> DataFrame:
    """(a, b, d, t) of every two keys, a < b, or of every key a that ``queries`` holds for and every other key b, or of the given
    pairs (a, b, further columns, which are kept). d: mean (of ``groups`` means, their median) squared difference of the counters,
    the size of the symmetric difference. sizes: (key, n) exact counts."""
    lists = fp.groupBy(F.col(key).alias("key")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "z"))), lambda x: x["z"]).alias("z"))  # the counters
    total = F.col("na") + F.col("nb")
    t = ((total - F.col("d")) / (total + F.col("d"))).alias("t")
    if pairs is not None:
        rows = lists.join(sizes.select(F.col(key).alias("key"), "n"), "key")
        got = at_pairs(pairs, rows, counters_of, squared_differences(groups), "d double", {"n": ("na", "nb")})
        return got.select("a", "b", "d", t, *[c for c in pairs.columns if c not in ("a", "b")])
    own, every = F.pmod(F.xxhash64("key"), F.lit(8)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(7)))
    asked = lists if queries is None else lists.where(queries(F.col("key")))
    one = asked.select(own.alias("x"), every.alias("y"), F.col("key").alias("a"), F.col("z").alias("za"))
    two = lists.select(every.alias("x"), own.alias("y"), F.col("key").alias("b"), F.col("z").alias("zb"))
    got = one.repartition(64, "x", "y").join(two.repartition(64, "x", "y"), ["x", "y"]).where("a < b" if queries is None else "a <> b").select("a", "b", F.zip_with("za", "zb", lambda u, v: (u - v) * (u - v)).alias("sq"))
    # the mean of every groups-th square, from each start on
    mean = lambda g: F.aggregate(F.filter("sq", lambda x, i: i % groups == g), F.struct(F.lit(0).cast("bigint").alias("s"), F.lit(0).alias("n")), lambda s, x: F.struct((s["s"] + x).alias("s"), (s["n"] + 1).alias("n")), lambda s: s["s"] / s["n"])
    means = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(groups - 1)), mean)) if groups > 1 else F.array(F.aggregate("sq", F.lit(0).cast("bigint"), lambda s, x: s + x) / F.size("sq"))
    got = got.withColumn("_g", means).select("a", "b", ((F.element_at("_g", (groups + 1) // 2) + F.element_at("_g", groups // 2 + 1)) / 2).alias("d"))
    got = got.join(sizes.select(F.col(key).alias("a"), F.col("n").alias("na")), "a").join(sizes.select(F.col(key).alias("b"), F.col("n").alias("nb")), "b")
    return got.select("a", "b", "d", t)


def counters_of(rows: pa.Table) -> np.ndarray:
    return rows["z"].combine_chunks().flatten().to_numpy().reshape(rows.num_rows, -1)


def squared_differences(groups: int) -> Callable:
    def find(z: np.ndarray, ia: np.ndarray, ib: np.ndarray) -> list[np.ndarray]:
        sq = (z.take(ia, 0) - z.take(ib, 0)) ** 2
        means = np.sort(np.stack([x.sum(axis=1) / x.shape[1] for x in (sq[:, g::groups] for g in range(groups))]), axis=0)
        return [(means[(groups + 1) // 2 - 1] + means[groups // 2]) / 2]

    return find


# ---- HLL registers: inclusion-exclusion and maximum likelihood


def incl_excl_jaccard(sk: DataFrame, key: str, params: FrsParams, pairs: DataFrame | None = None) -> DataFrame:
    """(a, b, n, m, u, t) of every two keys, or of the given pairs (a, b, further columns, which are kept): t from the counts of
    both sets and of their union, exponents only."""
    e = sk.select(F.col(key).alias("key"), "bucket", exponent_of(F.col("reg"), params).alias("e"))
    power = F.sum(F.pow(F.lit(2.0), -F.col("e")))
    t = ((F.col("n") + F.col("m") - F.col("u")) / F.col("u")).alias("t")
    if pairs is not None:
        rows = cell_rows(e, "key", "e", hll_estimate(power, F.count("*"), params.k).alias("n"))
        got = at_pairs(pairs, rows, powers, union_powers, "_p double, _f bigint", {"n": ("n", "m")})
        got = got.withColumn("u", hll_estimate(F.col("_p"), F.col("_f"), params.k))
        return got.select("a", "b", "n", "m", "u", t, *[c for c in pairs.columns if c not in ("a", "b")])
    size = e.groupBy("key").agg(hll_estimate(power, F.count("*"), params.k).alias("n"))
    # the union's power of a bucket is the smaller one; 1 stands for an empty bucket
    two = every_two_lists(e.select("key", "bucket", F.pow(F.lit(2.0), -F.col("e")).alias("w")), "key", "w", 1.0)
    least = F.zip_with("va", "vb", lambda x, y: F.least(x, y))
    two = two.select("a", "b", F.filter(least, lambda x: x < 1).alias("w"))
    u = two.select("a", "b", F.aggregate("w", F.lit(0.0), lambda s, x: s + x).alias("p"), F.size("w").alias("f")).select("a", "b", hll_estimate(F.col("p"), F.col("f"), params.k).alias("u"))
    got = u.join(size.withColumnsRenamed({"key": "a"}), "a").join(size.withColumnsRenamed({"key": "b", "n": "m"}), "b")
    return got.select("a", "b", "n", "m", "u", t)


def powers(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """2**-e of every bucket, 1 where it is empty, and which are filled."""
    e = matrix(rows)
    return np.where(e < 0, 1.0, 2.0 ** -e.astype(float)).astype(np.float32), np.packbits(e >= 0, axis=1)  # powers of two are exact


def union_powers(ready: tuple[np.ndarray, np.ndarray], ia: np.ndarray, ib: np.ndarray) -> list[np.ndarray]:
    """Of the unions: the sum of 2**-e over filled buckets, and how many are filled."""
    w, full = ready
    f = ones(full[ia] | full[ib])
    return [np.minimum(w.take(ia, 0), w.take(ib, 0)).sum(axis=1, dtype=float) - (w.shape[1] - f), f]


MAX_TERMS = 12


def cnf_incl_excl(sk: DataFrame, clauses: list[list[str]], params: FrsParams, key: str = "name") -> DataFrame:
    """(est): |C1 and ... and Cm| by inclusion-exclusion over the HLL counts of all unions of clauses. 2**m - 1
    unions: the error of each adds up, and so does the work."""
    if len(clauses) > MAX_TERMS:
        raise ValueError(f"{len(clauses)} clauses; at most {MAX_TERMS}")
    terms = [(mask, (-1.0) ** (mask.bit_count() + 1), name) for mask in range(1, 1 << len(clauses)) for name in sorted({x for i, c in enumerate(clauses) if mask >> i & 1 for x in c})]
    lists = F.broadcast(sk.sparkSession.createDataFrame(terms, "mask int, sign double, set_name string"))  # the formula's size
    hit = sk.where(F.col(key).isin(sorted({x for c in clauses for x in c}))).join(lists, F.col(key).cast("string") == F.col("set_name"))
    united = hit.groupBy("mask", "sign", "bucket").agg(F.max(exponent_of(F.col("reg"), params)).alias("e"))
    counts = united.groupBy("mask", "sign").agg(hll_estimate(F.sum(F.pow(F.lit(2.0), -F.col("e"))), F.count("*"), params.k).alias("u"))
    return counts.agg(F.sum(F.col("sign") * F.col("u")).alias("est"))


def mle_from_histogram(ea: np.ndarray, eb: np.ndarray, count: np.ndarray, n: float, m: float, k: int, last: int) -> float:
    """The most likely |A and B| given both cardinalities: a Poisson model of joint exponents
    (0: empty), searched by golden section."""

    def log_likelihood(g: float) -> float:
        a, b = max(n - g, 1e-9), max(m - g, 1e-9)

        def joint(x, y):  # P(exponent of A <= x, of B <= y)
            fx, fy = (np.where(v >= last, 0.0, np.where(v < 0, np.inf, 2.0 ** -v.astype(float))) for v in (x, y))
            return np.exp(-(np.where(fx > 0, a * fx, 0) + np.where(fy > 0, b * fy, 0) + np.where(np.maximum(fx, fy) > 0, g * np.maximum(fx, fy), 0)) / k)

        p = joint(ea, eb) - joint(ea - 1, eb) - joint(ea, eb - 1) + joint(ea - 1, eb - 1)
        return float((count * np.log(np.maximum(p, 1e-300))).sum())

    lo, hi, phi = 0.0, min(n, m), (math.sqrt(5) - 1) / 2
    x, y = hi - phi * (hi - lo), lo + phi * (hi - lo)
    fx, fy = log_likelihood(x), log_likelihood(y)
    for _ in range(60):
        if fx < fy:
            lo, x, fx = x, y, fy
            y = lo + phi * (hi - lo)
            fy = log_likelihood(y)
        else:
            hi, y, fy = y, x, fx
            x = hi - phi * (hi - lo)
            fx = log_likelihood(x)
    return (lo + hi) / 2


def mle_jaccard(sk: DataFrame, key: str, params: FrsParams, pairs: DataFrame) -> DataFrame:
    """(a, b, both, t) for the given pairs, from joint histograms of exponents (at most (2**q + 1)**2
    rows a pair, one task a pair)."""
    e = sk.select(F.col(key).alias("key"), "bucket", exponent_of(F.col("reg"), params).alias("e"))
    power = F.sum(F.pow(F.lit(2.0), -F.col("e")))
    size = e.groupBy("key").agg(hll_estimate(power, F.count("*"), params.k).alias("n"))
    one = pairs.select("a", "b").join(e.withColumnsRenamed({"key": "a"}), "a").select("a", "b", "bucket", F.col("e").alias("ea"), F.lit(None).cast("int").alias("eb"))
    two = pairs.select("a", "b").join(e.withColumnsRenamed({"key": "b"}), "b").select("a", "b", "bucket", F.lit(None).cast("int").alias("ea"), F.col("e").alias("eb"))
    cells = one.unionByName(two).groupBy("a", "b", "bucket").agg(F.coalesce(F.max("ea"), F.lit(0)).alias("ea"), F.coalesce(F.max("eb"), F.lit(0)).alias("eb"))
    hist = cells.groupBy("a", "b", "ea", "eb").agg(F.count("*").alias("c"))
    hist = hist.join(size.withColumnsRenamed({"key": "a"}), "a").join(size.withColumnsRenamed({"key": "b", "n": "m"}), "b")
    kind = sk.schema[key].dataType.simpleString()
    k, last = params.k, params.last

    def solve(df: pd.DataFrame) -> pd.DataFrame:
        ea, eb, c = (df[x].to_numpy() for x in ("ea", "eb", "c"))
        ea, eb, c = np.r_[ea, 0], np.r_[eb, 0], np.r_[c, k - c.sum()]  # buckets that both leave empty
        n, m = float(df["n"].iloc[0]), float(df["m"].iloc[0])
        g = mle_from_histogram(ea, eb, c, n, m, k, last)
        return pd.DataFrame({"a": [df["a"].iloc[0]], "b": [df["b"].iloc[0]], "both": [g], "t": [g / (n + m - g)]})

    return hist.groupBy("a", "b").applyInPandas(solve, f"a {kind}, b {kind}, both double, t double")


