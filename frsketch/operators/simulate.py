"""Sets of known overlap: real elements from ranges, or bucket minima drawn directly."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from frsketch.params import FrsParams


def overlap_of(n: int, t: float) -> int:
    """Common elements of two n-sets with Jaccard t."""
    return round(2 * n * t / (1 + t))


def overlapping_ranges(spark: SparkSession, n: int, t: float) -> DataFrame:
    """(side, x): side a is 0..n-1, side b starts ``overlap_of`` before n."""
    s = overlap_of(n, t)
    a = spark.range(n).select(F.lit("a").alias("side"), F.col("id").alias("x"))
    return a.unionByName(spark.range(n - s, 2 * n - s).select(F.lit("b").alias("side"), F.col("id").alias("x")))


def encode(h: np.ndarray, q: int, r: int) -> np.ndarray:
    """Registers of bucket minima on (0, 1); infinity: empty (0)."""
    last = 1 << q
    fill = np.isfinite(h)
    x = np.where(fill, h, 0.5)
    frac, exp = np.frexp(x)  # x = frac * 2**exp, frac in [1/2, 1)
    e = np.minimum(1 - exp, last)
    head = e < last
    m = np.where(head, np.floor((2 * frac - 1) * (1 << r)), np.floor(np.ldexp(x, r + last - 1))).astype(np.int64)
    return np.where(fill, (e.astype(np.int64) << r) + (1 << r) - 1 - np.minimum(m, (1 << r) - 1), 0)


def minima(rng: np.random.Generator, n: float, k: int, reps: int) -> np.ndarray:
    """Smallest hash in each of k buckets of a random n-set, for ``reps`` repetitions (infinity: empty)."""
    if n <= 0:
        return np.full((reps, k), np.inf)
    if n < 1e9:
        size = rng.multinomial(int(round(n)), np.full(k, 1 / k), size=reps).astype(float)
    else:
        size = np.full((reps, k), n / k)
    u = rng.random((reps, k))
    with np.errstate(divide="ignore"):
        return np.where(size > 0, -np.expm1(np.log(u) / np.maximum(size, 1)), np.inf)


def trial_estimates(n: float, t: float, method: dict, reps: int, seed: int) -> np.ndarray:
    """Jaccard estimates of ``reps`` pairs of random n-sets. method: kind frs (p, q, r, correct), minhash (p, bits), bbit
    (p, bits), incl_excl or mle (p, q; exponents alone) or f2 (p: log2 of the counters)."""
    rng = np.random.default_rng(seed)
    k = 1 << method["p"]
    both = 2 * n * t / (1 + t)
    if method["kind"] == "f2":  # many random signs sum up to a normal variable
        d = 2 * (n - both) * (rng.standard_normal((reps, k)) ** 2).mean(axis=1)
        return (2 * n - d) / (2 * n + d)
    if method["kind"] == "bbit":  # equal minima, and others that agree in their low bits by chance
        hit = rng.random((reps, k)) < t + (1 - t) * 2.0 ** -method["bits"]
        return (hit.mean(axis=1) - 2.0 ** -method["bits"]) / (1 - 2.0 ** -method["bits"])
    a, b, c = (minima(rng, x, k, reps) for x in (n - both, n - both, both))
    x, y = np.minimum(a, c), np.minimum(b, c)
    if method["kind"] in ("incl_excl", "mle"):
        u, v = (encode(z, method["q"], 0) for z in (x, y))
        return np.array([exponent_estimate(a, b, k, 1 << method["q"], method["kind"]) for a, b in zip(u, v)])
    if method["kind"] == "frs":
        u, v = encode(x, method["q"], method["r"]), encode(y, method["q"], method["r"])
        hit, used = (u == v) & (u > 0), (u > 0) | (v > 0)
    else:
        u, v = (np.floor(np.where(np.isfinite(z), z, 0) * 2.0 ** method["bits"]) for z in (x, y))
        fx, fy = np.isfinite(x), np.isfinite(y)
        hit, used = (u == v) & fx & fy, fx | fy
    got = hit.sum(axis=1).astype(float)
    if method.get("correct") and method["kind"] == "frs":
        from frsketch.functions.collisions import expected_collisions

        got -= expected_collisions(n, n, method["p"], method["q"], method["r"])
    return got / np.maximum(used.sum(axis=1), 1)


def harmonic_count(e: np.ndarray, k: int) -> float:
    """The HLL estimate of exponents (0: empty)."""
    from frsketch.operators.cardinality import alpha

    raw, empty = alpha(k) * k * k / float(np.exp2(-e.astype(float)).sum()), int((e == 0).sum())
    return k * math.log(k / empty) if raw <= 2.5 * k and empty else raw


def exponent_estimate(a: np.ndarray, b: np.ndarray, k: int, last: int, kind: str) -> float:
    """Jaccard from two rows of exponents, by inclusion-exclusion or by maximum likelihood."""
    n, m = harmonic_count(a, k), harmonic_count(b, k)
    if kind == "incl_excl":
        u = harmonic_count(np.maximum(a, b), k)
        return (n + m - u) / u
    from frsketch.operators.baselines import mle_from_histogram

    cells, count = np.unique(np.stack([a, b]), axis=1, return_counts=True)
    g = mle_from_histogram(cells[0], cells[1], count, n, m, k, last)
    return g / (n + m - g)


def register_trials(spark: SparkSession, grid: list[dict], reps: int, seed: int = 1) -> DataFrame:
    """(method, t, n_set, n_union, rep, t_hat) for every row of the grid: method (name), kind, p, q, r, bits,
    correct, t, n. One task takes many rows; nothing is enumerated, so n is unbounded."""
    rows = [{"i": i, "method": g["method"], "kind": g["kind"], "p": g["p"], "q": g.get("q", 0), "r": g.get("r", 0), "bits": g.get("bits", 0), "correct": bool(g.get("correct")), "t": float(g["t"]), "n": float(g["n"])} for i, g in enumerate(grid)]
    kind = "i int, method string, kind string, p int, q int, r int, bits int, correct boolean, t double, n double"
    df = spark.createDataFrame(pd.DataFrame(rows), kind).repartition(min(len(rows), 64))

    def run(batches):
        for b in batches:
            for g in b.to_dict("records"):
                t_hat = trial_estimates(g["n"], g["t"], g, reps, seed + 7919 * g["i"])
                yield pd.DataFrame({"method": g["method"], "t": g["t"], "n_set": g["n"], "n_union": 2 * g["n"] / (1 + g["t"]), "rep": np.arange(reps), "t_hat": t_hat})

    return df.mapInPandas(run, "method string, t double, n_set double, n_union double, rep int, t_hat double")


def hash_trials(spark: SparkSession, n: int, t: float, params: FrsParams, reps: int, bits: tuple[tuple[int, int], ...] = ((6, 8), (5, 16))) -> DataFrame:
    """(method, t, n_set, n_union, rep, t_hat) by hashing real elements: the float-register sketch and
    MinHash of (p, bits) at the same size. All repetitions come from one pass, a seed each."""
    from frsketch.functions.hashing import hash_parts, pack, word

    rows = overlapping_ranges(spark, n, t).select("side", F.explode(F.sequence(F.lit(1), F.lit(reps))).alias("rep"), F.concat(F.col("x").cast("string")).alias("x"))
    rows = rows.select("side", "rep", F.concat(F.col("rep").cast("string"), F.lit("|"), F.col("x")).alias("key"))
    h = hash_parts(F.col("key"), params)
    frs = rows.select("side", "rep", h.alias("h")).select(F.lit("frs").alias("method"), "side", "rep", F.col("h.bucket").alias("bucket"), pack(F.col("h.e"), F.col("h.m"), params).cast("bigint").alias("v"))
    parts = [frs]
    for p, b in bits:
        d = rows.select("side", "rep", F.md5("key").alias("d"))
        parts.append(d.select(F.lit(f"minhash_{1 << p}x{b}").alias("method"), "side", "rep", word(F.col("d"), 0).bitwiseAND(F.lit((1 << p) - 1)).cast("int").alias("bucket"), (-F.shiftright(word(F.col("d"), 8), 32 - b)).alias("v")))
    every = parts[0]
    for x in parts[1:]:
        every = every.unionByName(x)
    best = every.groupBy("method", "rep", "bucket").agg(F.max(F.when(F.col("side") == "a", F.col("v"))).alias("a"), F.max(F.when(F.col("side") == "b", F.col("v"))).alias("b"))
    s = overlap_of(n, t)
    out = best.groupBy("method", "rep").agg((F.count_if(F.col("a") == F.col("b")) / F.count("*")).alias("t_hat"))
    return out.select("method", F.lit(float(t)).alias("t"), F.lit(float(n)).alias("n_set"), F.lit(float(2 * n - s)).alias("n_union"), "rep", "t_hat")


def hash_sweep(spark: SparkSession, sizes: list[int], ts: tuple[float, ...], reps: int, params: FrsParams = FrsParams(6, 4, 4, hash="xx")) -> DataFrame:
    """(method, t, n_set, n_union, rep, t_hat) by hashing real elements, for every set size and Jaccard t: float registers
    (p, q, r), MinHash of 2**p values of 8 bits and of 2**(p - 1) of 16 bits.

    All sets are ranges of integers, so the integers are cut at all ranges' ends, each segment is hashed and
    sketched once a repetition, and the sketch of a set is the union of its segments' sketches. The largest range is
    read once, whatever the number of sizes and t."""
    from frsketch.functions.hashing import hash_parts, pack

    pairs = [(n, t, overlap_of(n, t)) for n in sizes for t in ts]
    cuts = sorted({0, *(x for n, _, s in pairs for x in (n, n - s, 2 * n - s))})
    octave = lambda x: max(x, 1).bit_length()
    marks = {}
    for i, c in enumerate(cuts):
        marks.setdefault(octave(c), []).append((c, i))
    top, first = octave(cuts[-1]), 0
    grid = []  # octave, number of the segment that it begins in, cuts within it: the grid's size
    for o in range(1, top + 1):
        grid.append((o, first, [c for c, _ in marks.get(o, [])]))
        first = max([first, *(i for _, i in marks.get(o, []))])
    places = F.broadcast(spark.createDataFrame(grid, "octave int, first int, cuts array<bigint>"))
    x = spark.range(cuts[-1]).select("id", F.length(F.bin(F.greatest("id", F.lit(1)))).cast("int").alias("octave")).join(places, "octave")
    at = F.size(F.filter("cuts", lambda c: c <= F.col("id")))
    start = F.when(F.col("octave") == 1, at - 1).otherwise(F.col("first") + at)
    rows = x.select(start.alias("seg"), "id", F.explode(F.sequence(F.lit(1), F.lit(reps))).alias("rep"))
    key = F.concat(F.col("rep").cast("string"), F.lit("|"), F.col("id").cast("string"))
    h = hash_parts(key, params)
    value = F.shiftrightunsigned(F.xxhash64(F.lit(5), key), 48).cast("int")
    rows = rows.select("seg", "rep", h.alias("h"), value.alias("v"))
    sk = rows.groupBy("seg", "rep", F.col("h.bucket").alias("bucket")).agg(F.max(pack(F.col("h.e"), F.col("h.m"), params)).alias("reg"), F.min("v").alias("v"))
    number = {c: i for i, c in enumerate(cuts)}
    sets = [(n, t, side, i) for n, t, s in pairs for side, lo, hi in (("a", 0, n), ("b", n - s, 2 * n - s)) for i in range(number[lo], number[hi])]
    of = F.broadcast(spark.createDataFrame(pd.DataFrame(sets, columns=["n", "t", "side", "seg"]), "n bigint, t double, side string, seg int"))
    sk = sk.join(of, "seg").groupBy("n", "t", "rep", "side", "bucket").agg(F.max("reg").alias("reg"), F.min("v").alias("v"))
    half = 1 << params.p - 1
    keys = ["n", "t", "rep", "side"]
    parts = [
        sk.select(F.lit(f"frs_{params.k}x{params.q + params.r}").alias("method"), *keys, "bucket", F.col("reg").alias("v")),
        sk.select(F.lit(f"minhash_{params.k}x8").alias("method"), *keys, "bucket", F.shiftright("v", 8).alias("v")),
        sk.groupBy(*keys, F.col("bucket").bitwiseAND(F.lit(half - 1)).alias("bucket")).agg(F.min("v").alias("v")).select(F.lit(f"minhash_{half}x16").alias("method"), *keys, "bucket", "v"),
    ]
    cells = parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("method", "n", "t", "rep", "bucket").agg(F.max(F.when(F.col("side") == "a", F.col("v"))).alias("a"), F.max(F.when(F.col("side") == "b", F.col("v"))).alias("b"))
    out = cells.groupBy("method", "n", "t", "rep").agg((F.count_if(F.col("a") == F.col("b")) / F.count("*")).alias("t_hat"))
    union = 2 * F.col("n") / (1 + F.col("t"))
    return out.select("method", "t", F.col("n").cast("double").alias("n_set"), union.alias("n_union"), "rep", "t_hat")


def superloglog_constant(k: int = 1024, reps: int = 400, share: float = 0.7) -> float:
    """The constant that makes the truncated geometric mean unbiased, by simulation."""
    rng, ratio, n = np.random.default_rng(3), [], 1e7
    for _ in range(reps):
        h = minima(rng, n, k, 1)[0]
        e = np.sort(1 - np.frexp(h)[1])[: int(share * k)]
        ratio.append(n / (len(e) * 2 ** e.mean()))
    return float(np.median(ratio) if math.isfinite(ratio[0]) else 0)
