"""Accidental equality of registers: exact sums, approximations and bounds.

Scalar forms run on the driver with numpy; ``*_col`` forms are Columns. All sums use log1p and expm1,
so they hold for cardinalities far beyond 2**63.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.params import FrsParams

PRINTED = 0.169919487159739093975315012348  # fixed value: the published constant for large sets
LIMIT = 1 / (8 * math.log(2))  # what the exact sum tends to for r >= 4 (own derivation)


def boxes(p: int, q: int, r: int, tail: str = "capped", loop: str = "lemma") -> tuple[np.ndarray, np.ndarray]:
    """(lower edges, widths) of the registers' boxes in the hash space of one bucket's share. ``loop``
    as_printed shifts the mantissas by one (an ablation)."""
    last = (1 << q) + (tail == "overflow")
    e = np.repeat(np.arange(1, last + 1), 1 << r)
    m = np.tile(np.arange(1 << r), last).astype(float) + (loop == "as_printed")
    head = e < last
    shift = np.where(head, r + e, r + last - 1)
    low = np.where(head, (1 << r) + m, m) * 2.0 ** -(shift + p)
    return low, 2.0 ** -(shift + p).astype(float)


def box_mass(low, width, n):
    """P(the minimum of n uniform values falls in [low, low + width))."""
    low, width = np.asarray(low, dtype=float), np.asarray(width, dtype=float)
    rest = 1 - low
    with np.errstate(divide="ignore", invalid="ignore"):
        inner = np.where(width >= rest, -np.inf, np.log1p(-np.minimum(width / np.where(rest > 0, rest, 1), 1)))
        out = np.exp(n * np.log1p(-np.minimum(low, 1))) * -np.expm1(n * inner)
    return np.where(rest <= 0, 0.0, out)


def expected_collisions(n: float, m: float, p: int, q: int, r: int, tail: str = "capped", loop: str = "lemma") -> float:
    """Expected number of equal registers of two disjoint sets of n and m elements."""
    low, width = boxes(p, q, r, tail, loop)
    return float((box_mass(low, width, n) * box_mass(low, width, m)).sum() * 2**p)


def expected_collisions_unbounded(n: float, m: float, r: int, eps: float = 1e-15, most: int = 2_000) -> float:
    """One bucket, exponents without a last: terms are added until they fall below ``eps``."""
    total, seen = 0.0, False
    for e in range(1, most):
        low = ((1 << r) + np.arange(1 << r)) * 2.0 ** -(r + e)
        term = float((box_mass(low, 2.0 ** -(r + e), n) * box_mass(low, 2.0 ** -(r + e), m)).sum())
        total += term
        seen |= term > eps
        if term <= eps and (seen or e > math.log2(max(n, m, 1)) + 10):
            break
    return total


def out_of_range(p: int, q: int, r: int, limit: str = "default") -> float:
    return {"default": 2.0 ** (2**q + p), "alg": 2.0 ** (2**q + r), "prose89": 2.0**89}[limit]


def approx_expected_collisions(n: float, m: float, p: int, q: int, r: int, limit: str = "default", constant: float = PRINTED) -> float:
    """Small sets: the exponent-only sum over 2**r. Large sets: a constant. Raises past the range."""
    n, m = max(n, m), min(n, m)
    if n > out_of_range(p, q, r, limit):
        raise ValueError(f"{n:g} elements are beyond the range of (p, q, r) = ({p}, {q}, {r})")
    if n > 2.0 ** (p + 5):
        return constant * 2.0 ** (p - r) * 4 * (n / m) / (1 + n / m) ** 2 if m > 0 else 0.0
    return expected_collisions(n, m, p, q, 0) / 2**r


def expected_matches(a: float, b: float, g: float, p: int, q: int, r: int) -> float:
    """Expected equal registers of sets with a = |A - B|, b = |B - A|, g = |A and B| (own extension).
    With g = 0 it is ``expected_collisions``."""
    low, width = boxes(p, q, r)
    u, n, m = a + b + g, a + g, b + g
    rest = 1 - low
    l = np.log1p(-np.minimum(low, 1 - 1e-300))
    d = np.where(width >= rest, -np.inf, np.log1p(-np.minimum(width / np.where(rest > 0, rest, 1), 1)))
    with np.errstate(invalid="ignore"):
        ex = lambda c: np.expm1(c * d) if c > 0 else np.zeros_like(d)
        term = np.exp(u * l) * (ex(u) - ex(n) - ex(m))
    return float(np.where(rest <= 0, 0.0, term).sum() * 2**p)


def collision_bound(n: float, p: int, q: int, r: int) -> float:
    """Upper bound of the expectation over all buckets."""
    return 2**p * (5 / 2**r + n / 2.0 ** (p + 2**q + r))


def collision_bound_single(n: float, q: int, r: int) -> float:
    """Upper bound for one bucket."""
    return 6 / 2**r + n / 2.0 ** (2**q + r)


def collision_variance_bound(ec):
    return ec * ec + ec


def region_masses(n: float, m: float, q: int, r: int, points: int = 40_001) -> dict[str, float]:
    """Mass of the minima of n and m uniform values in the four regions that together cover a bucket's collision
    boxes: the square next to 1, the square at the origin, the band between the lines of slope l / (l + 1) and
    (l + 1) / l, and the band of half width 1 / (l H) between 1 / (l H) and 1 / H, with l = 2**r, H = 2**2**q. The
    bands are integrated over ln x by the trapezoid rule."""
    l, big = 2.0**r, 2.0 ** (2**q)
    least = 1 / (l * big)

    def tail(x, c):  # P(minimum of c values > x)
        return np.exp(c * np.log1p(-np.clip(x, 0, 1 - 1e-16))) * (x < 1)

    def band(lo, hi, below, above):
        x = np.exp(np.linspace(math.log(lo), math.log(hi), points))
        density = n * np.exp((n - 1) * np.log1p(-x)) * (tail(below(x), m) - tail(above(x), m)) * x
        return float(np.trapezoid(density, np.log(x)))

    return {
        "top_right": (l + 1) ** -(n + m),
        "bottom_left": float(np.expm1(n * np.log1p(-least)) * np.expm1(m * np.log1p(-least))),
        "ray": band(1e-12 / max(n, m), l / (l + 1), lambda x: x * l / (l + 1), lambda x: x * (l + 1) / l),
        "strip": band(least, 1 / big, lambda x: x - least, lambda x: x + least),
    }


def region_bounds(n: float, q: int, r: int) -> dict[str, float]:
    """Upper bounds of ``region_masses``, for n >= m. That of the strip holds inside the window only: at n of
    several 2**2**q it is exceeded."""
    l, big = 2.0**r, 2.0 ** (2**q)
    return {"top_right": 1 / l, "bottom_left": n / (l * big), "ray": 3 / l, "strip": 2 / l}


# ---- Columns


def _mass_col(low: Column, width: Column, n: Column) -> Column:
    rest = F.lit(1.0) - low
    whole = F.exp(n * F.log1p(-low))
    return F.when(width >= rest, whole).otherwise(whole * -F.expm1(n * F.log1p(-width / rest)))


def _box_cols(i: Column, p: int, q: int, r: int) -> tuple[Column, Column]:
    """(lower edge, width) of box number i = (e - 1) * 2**r + m."""
    last = 1 << q
    e, m = F.floor(i / (1 << r)) + 1, i % (1 << r)
    head = e < last
    shift = F.when(head, e + (r + p)).otherwise(r + last - 1 + p)
    width = F.pow(F.lit(2.0), -shift)
    return F.when(head, m + (1 << r)).otherwise(m) * width, width


def expected_collisions_df(df: DataFrame, p: int, q: int, r: int, n: str = "n", m: str = "m", name: str = "ec") -> DataFrame:
    """df with the exact expectation for its columns n and m. Each distinct pair of counts is summed
    once, over 2**(q + r) boxes, in parallel."""
    pairs = df.select(F.col(n).cast("double").alias("_n"), F.col(m).cast("double").alias("_m")).distinct()
    terms = pairs.withColumn("_i", F.explode(F.sequence(F.lit(0), F.lit((1 << q + r) - 1))))
    low, width = _box_cols(F.col("_i"), p, q, r)
    terms = terms.select("_n", "_m", low.alias("_low"), width.alias("_w"))
    one = terms.groupBy("_n", "_m").agg((F.sum(_mass_col(F.col("_low"), F.col("_w"), F.col("_n")) * _mass_col(F.col("_low"), F.col("_w"), F.col("_m"))) * 2**p).alias(name))
    return df.join(one, (F.col(n).cast("double") == F.col("_n")) & (F.col(m).cast("double") == F.col("_m")), "left").drop("_n", "_m")


def exponent_collisions_col(n: Column, m: Column, p: int, q: int) -> Column:
    """The exact expectation at r = 0: 2**q terms inside the row."""
    n, m = n.cast("double"), m.cast("double")

    def term(i):
        low, width = _box_cols(i, p, q, 0)
        return _mass_col(low, width, n) * _mass_col(low, width, m)

    return F.aggregate(F.transform(F.sequence(F.lit(0), F.lit((1 << q) - 1)), term), F.lit(0.0), lambda a, x: a + x) * 2**p


def box_mass_cols(n: Column, params: FrsParams) -> list[Column]:
    """The mass of each exponent's box under n elements a sketch: the exact expectation at r = 0 of two sets is 2**p times
    the sum of their products."""
    low, width = boxes(params.p, params.q, 0)
    return [_mass_col(F.lit(float(x)), F.lit(float(y)), n.cast("double")) for x, y in zip(low, width)]


def approx_collisions_col(n: Column, m: Column, params: FrsParams, constant: float = PRINTED, bare: Column | None = None) -> Column:
    """The approximation as a Column; null past the range (see ``range_status``). ``bare``: the exact expectation at
    r = 0, where the caller has it."""
    p, q, r = params.p, params.q, params.r
    n, m = n.cast("double"), m.cast("double")
    big, small = F.greatest(n, m), F.least(n, m)
    phi = 4 * big * small / ((big + small) * (big + small))
    return (
        F.when(big > out_of_range(p, q, r), F.lit(None).cast("double"))
        .when(big > 2.0 ** (p + 5), constant * 2.0 ** (p - r) * phi)
        .otherwise((exponent_collisions_col(n, m, p, q) if bare is None else bare) / 2**r)
    )


def range_status(n: Column, m: Column, params: FrsParams) -> Column:
    """ok; warning within five octaves of the range's end; error past it."""
    big, end = F.greatest(n, m), 2.0 ** (params.window + params.p)
    return F.when(big > end, "error").when(big > end / 32, "warning").otherwise("ok")


def collision_bound_col(n: Column, p: int, q: int, r: int) -> Column:
    return (n / 2.0 ** (p + 2**q + r) + 5 / 2**r) * 2**p
