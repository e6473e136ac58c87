"""Choosing parameters and accounting for space."""

from __future__ import annotations

import math

from frsketch.params import FrsParams


def choose_params(eps: float, t: float, n: float) -> dict[str, float]:
    """Parameters for a relative error of ``eps`` at Jaccard ``t`` and sets of up to ``n``: mantissa bits above
    log2(6 / (eps t)), buckets of order 1 / eps**2, a window that covers log2 n; and the own refinement
    k >= (1 - t) / (t eps**2)."""
    r = math.floor(math.log2(6 / (eps * t))) + 1
    p = math.ceil(math.log2(1 / eps**2))
    refined = math.ceil(math.log2(max(1.0, (1 - t) / (t * eps**2))))
    q = max(2, math.ceil(math.log2(max(2.0, math.log2(max(2.0, n)) - p + 5))))
    return {"p": p, "q": q, "r": r, "p_refined": refined, "bytes": (q + r) * 2**p / 8, "bytes_refined": (q + r) * 2**refined / 8}


def sketch_bits(params: FrsParams) -> int:
    """Nominal size: q + r bits a bucket."""
    return (params.q + params.r) << params.p


def fitting(eps: float, t: float, n: float, **kw) -> FrsParams:
    c = choose_params(eps, t, n)
    return FrsParams(int(c["p"]), min(6, int(c["q"])), int(c["r"]), **kw)


def space_orders(eps: float, t: float, n: float) -> dict[str, float]:
    """Orders of the bits needed by each kind of sketch."""
    loglog = math.log2(max(2.0, math.log2(max(2.0, n))))
    return {
        "float_register": (loglog + math.log2(1 / (t * eps))) / eps**2,
        "minhash": math.log2(max(2.0, n)) / eps**2,
        "hll_incl_excl": loglog / (eps * t) ** 2,
        "b_bit": 1 / eps**2,
        "b_bit_similar": (1 - t) ** 2 / eps**2 * math.log(1 / (1 - t)) if t < 1 else 0.0,
    }
