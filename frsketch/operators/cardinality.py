"""Distinct counts from registers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.functions.hashing import decode, exponent_of
from frsketch.operators.build import rollup_sketch, union_sketches
from frsketch.params import FrsParams

SWITCH = 1024  # mean elements a bucket from which the minimum values are used
ALPHA = {16: 0.673, 32: 0.697, 64: 0.709}  # fixed values of the published harmonic-mean estimator
LOGLOG = 0.39701  # fixed value of the published geometric-mean estimator
SUPER_SHARE = 0.7
SUPER = 1.093  # fixed value for the smallest 70 % of registers


def alpha(k: int) -> float:
    return ALPHA.get(k, 0.7213 / (1 + 1.079 / k))


def hll_estimate(power_sum: Column, filled: Column, k: int) -> Column:
    """power_sum: the sum of 2**-e over filled buckets."""
    raw = alpha(k) * k * k / (power_sum + (k - filled))
    return F.when((raw <= 2.5 * k) & (filled < k), k * F.log(k / (k - filled))).otherwise(raw)


def min_estimate(value_sum: Column, filled: Column, k: int) -> Column:
    """k**2 over the sum of minimum values, an empty bucket counting 1."""
    total = value_sum + (k - filled)
    return F.when(total == 0, F.lit(float("inf"))).otherwise(float(k) * k / F.when(total == 0, 1.0).otherwise(total))


def moments(params: FrsParams, how: str = "lower") -> list[Column]:
    """Aggregates that every estimator starts from."""
    reg = F.col("reg")
    return [F.count("*").alias("filled"), F.sum(F.pow(F.lit(2.0), -exponent_of(reg, params))).alias("_pow"), F.sum(decode(reg, params, how)).alias("_val")]


def from_moments(params: FrsParams, method: str = "auto", pow_: Column | None = None, val: Column | None = None, filled: Column | None = None) -> tuple[Column, Column]:
    """(estimate, method used)."""
    pow_, val, filled = (F.col(n) if c is None else c for n, c in (("_pow", pow_), ("_val", val), ("filled", filled)))
    hll, low = hll_estimate(pow_, filled, params.k), min_estimate(val, filled, params.k)
    if method == "hll":
        return hll, F.lit("hll")
    if method == "minvalue":
        return low, F.lit("minvalue")
    small = hll < SWITCH * params.k
    return F.when(small, hll).otherwise(low), F.when(small, "hll").otherwise("minvalue")


def cardinality(sk: DataFrame, by: list[str], params: FrsParams, method: str = "auto", how: str = "lower") -> DataFrame:
    """(by..., filled, est, method_used); method: auto, hll or minvalue."""
    est, used = from_moments(params, method)
    return sk.groupBy(*by).agg(*moments(params, how)).select(*by, "filled", est.alias("est"), used.alias("method_used"))


def union_cardinality(params: FrsParams, *sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The distinct count of a union, from the sketches alone."""
    by = by or []
    return cardinality(union_sketches(*[rollup_sketch(s, by) for s in sketches]), by, params)


def loglog(sk: DataFrame, by: list[str], params: FrsParams) -> DataFrame:
    """(by..., est) by the geometric mean of exponents; empty buckets count exponent 0."""
    e = F.sum(exponent_of(F.col("reg"), params))
    return sk.groupBy(*by).agg((LOGLOG * params.k * F.pow(F.lit(2.0), e / params.k)).alias("est"))


def superloglog(sk: DataFrame, by: list[str], params: FrsParams) -> DataFrame:
    """As ``loglog``, over the smallest 70 % of exponents."""
    take = int(SUPER_SHARE * params.k)
    counts = sk.groupBy(*by, exponent_of(F.col("reg"), params).alias("e")).agg(F.count("*").alias("c"))
    # at most 2**q + 1 exponents a key
    lists = counts.groupBy(*by).agg(F.sort_array(F.collect_list(F.struct("e", "c"))).alias("h"), F.sum("c").alias("filled"))
    start = F.struct(F.greatest(F.lit(take) - (params.k - F.col("filled")), F.lit(0)).cast("bigint").alias("left"), F.lit(0).cast("bigint").alias("sum"))
    got = F.aggregate("h", start, lambda a, x: F.struct((a["left"] - F.least(a["left"], x["c"])).alias("left"), (a["sum"] + x["e"] * F.least(a["left"], x["c"])).alias("sum")))
    return lists.select(*by, (SUPER * take * F.pow(F.lit(2.0), got["sum"] / take)).alias("est"))
