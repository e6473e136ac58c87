"""Elements to registers, as Catalyst expressions (whole-stage code generation throughout)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from frsketch.params import FrsParams


def element_key(cols: list[str | Column] | str | Column) -> Column:
    """One string for a tuple of columns; null if any part is. A single column is its own text; parts
    of a tuple carry their length, so ('a', 'bc') and ('ab', 'c') differ."""
    if not isinstance(cols, list):
        cols = [cols]
    text = [(F.col(c) if isinstance(c, str) else c).cast("string") for c in cols]
    if len(text) == 1:
        return text[0]
    return F.concat(*[x for t in text for x in (F.length(t).cast("string"), F.lit(":"), t)])


def digest(key: Column, params: FrsParams) -> Column:
    if params.seed:
        key = F.concat(F.lit(f"{params.seed}|"), key)
    return {"md5": F.md5, "sha1": F.sha1, "sha256": lambda c: F.sha2(c, 256)}[params.hash](key)


def word(hexes: Column, at: int, size: int = 8) -> Column:
    """``size`` hexadecimal digits from 0-based position ``at`` as a number."""
    return F.conv(F.substring(hexes, at + 1, size), 16, 10).cast("bigint")


def _high(w: Column, width: int, zeros: int) -> Column:
    return w if width == zeros else F.shiftright(w, width - zeros)


def exponent(words: list[Column], params: FrsParams) -> Column:
    """1 + zeros before the first one among the window's bits; the last exponent if there is none.
    words: 32-bit words that hold the window from the top."""
    zeros, last = params.zeros, params.last
    if zeros == 0:
        return F.lit(last)
    if zeros <= 32:
        w = _high(words[0], 32, zeros)
        return F.when(w == 0, last).otherwise(zeros + 1 - F.length(F.bin(w)))
    w = _high(words[1], 32, zeros - 32)
    low = F.when(w == 0, last).otherwise(zeros + 1 - F.length(F.bin(w)))
    return F.when(words[0] != 0, 33 - F.length(F.bin(words[0]))).otherwise(low)


def hash_parts(key: Column, params: FrsParams) -> Column:
    """struct(bucket, e, m) of an element key."""
    k, scale = params.k, params.scale
    if params.hash == "xx":
        one, two = F.xxhash64(F.lit(2 * params.seed + 1), key), F.xxhash64(F.lit(2 * params.seed + 2), key)
        w = F.shiftrightunsigned(two, 64 - params.zeros) if params.zeros else F.lit(0)
        e = F.when(w == 0, params.last).otherwise(params.zeros + 1 - F.length(F.bin(w)))
        bucket, m = one.bitwiseAND(F.lit(k - 1)), F.shiftrightunsigned(one, 32).bitwiseAND(F.lit(scale - 1))
    elif params.mantissa == "independent":
        d = digest(key, params)
        bucket, m = word(d, 0).bitwiseAND(F.lit(k - 1)), word(d, 24).bitwiseAND(F.lit(scale - 1))
        e = exponent([word(d, 8), word(d, 16)], params)
    else:
        d = digest(key, params)
        need = params.p + params.zeros + params.r
        bits = F.concat(*[F.lpad(F.conv(F.substring(d, 8 * i + 1, 8), 16, 2), 32, "0") for i in range(-(-need // 32))])
        at = F.instr(F.substring(bits, params.p + 1, max(params.zeros, 1)), "1") if params.zeros else F.lit(0)
        e = F.when(at == 0, params.last).otherwise(at)
        begin = F.when(at == 0, params.p + params.zeros).otherwise(params.p + at) + 1
        m = F.conv(F.substr(bits, begin, F.lit(params.r)), 2, 10).cast("bigint") if params.r else F.lit(0)
        bucket = F.conv(F.substring(bits, 1, params.p), 2, 10).cast("bigint") if params.p else F.lit(0)
    return F.struct(bucket.cast("int").alias("bucket"), e.cast("int").alias("e"), m.cast("int").alias("m"))


def pack(e: Column, m: Column, params: FrsParams) -> Column:
    """One comparable word: larger is the smaller hash, empty is 0."""
    return (e * params.scale + (params.scale - 1 - m)).cast("int")


def exponent_of(reg: Column, params: FrsParams) -> Column:
    return F.shiftright(reg, params.r)


def mantissa_of(reg: Column, params: FrsParams) -> Column:
    return F.lit(params.scale - 1) - reg.bitwiseAND(F.lit(params.scale - 1))


def decode(reg: Column, params: FrsParams, how: str = "lower") -> Column:
    """The smallest hash of a bucket on (0, 1), at its box's lower edge or middle. In the last exponent the
    mantissa counts from zero."""
    half = 0.5 if how == "midpoint" else 0.0
    e, m = exponent_of(reg, params), mantissa_of(reg, params) + half
    head = F.pow(F.lit(2.0), -e) * (1 + m / params.scale)
    return F.when(e < params.last, head).otherwise(m * 2.0 ** -(params.r + params.zeros))
