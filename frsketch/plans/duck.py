"""DuckDB texts of the registers and estimators, built from parameters, for the side-by-side checks."""

from __future__ import annotations

from frsketch.functions.collisions import PRINTED
from frsketch.operators.cardinality import SWITCH, alpha
from frsketch.params import FrsParams


def num(d: str, at: int, size: int = 8) -> str:
    return f"('0x' || substr({d}, {at + 1}, {size}))::BIGINT"


def length_of(w: str) -> str:
    return f"length(bin({w}))"


def registers(source: str, key: str, by: list[str], x: FrsParams) -> str:
    """SELECT by..., bucket, reg of every bucket. ``key`` is a VARCHAR expression over ``source``."""
    fn = {"md5": "md5", "sha1": "sha1", "sha256": "sha256"}[x.hash]
    seed = f"'{x.seed}|' || " if x.seed else ""
    cols = "".join(f"{c}, " for c in by)
    base = f"SELECT {cols}{fn}({seed}{key}) AS d FROM {source} WHERE ({key}) IS NOT NULL"
    if x.mantissa == "independent":
        bucket = f"({num('d', 0)} & {x.k - 1})"
        m = f"({num('d', 24)} & {x.scale - 1})"
        if x.zeros <= 32:
            w = f"({num('d', 8)} >> {32 - x.zeros})"
            e = f"(CASE WHEN {w} = 0 THEN {x.last} ELSE {x.zeros + 1} - {length_of(w)} END)"
        else:
            one, w = num("d", 8), f"({num('d', 16)} >> {64 - x.zeros})"
            e = f"(CASE WHEN {one} <> 0 THEN 33 - {length_of(one)} WHEN {w} = 0 THEN {x.last} ELSE {x.zeros + 1} - {length_of(w)} END)"
        mid = f"SELECT {cols}{bucket} AS bucket, {e} AS e, {m} AS m FROM ({base})"
    else:
        need = x.p + x.zeros + x.r
        bits = " || ".join(f"lpad(bin({num('d', 8 * i)}), 32, '0')" for i in range(-(-need // 32)))
        with_bits = f"SELECT {cols}{bits} AS b FROM ({base})"
        at = f"SELECT {cols}b, position('1' IN substr(b, {x.p + 1}, {x.zeros})) AS pos FROM ({with_bits})"
        begin = f"(CASE WHEN pos = 0 THEN {x.p + x.zeros} ELSE {x.p} + pos END + 1)"
        mid = f"SELECT {cols}('0b' || substr(b, 1, {x.p}))::BIGINT AS bucket, CASE WHEN pos = 0 THEN {x.last} ELSE pos END AS e, ('0b' || substr(b, {begin}, {x.r}))::BIGINT AS m FROM ({at})"
    keys = "".join(f"{c}, " for c in by)
    return f"SELECT {keys}bucket::INTEGER AS bucket, max(e * {x.scale} + {x.scale - 1} - m)::INTEGER AS reg FROM ({mid}) GROUP BY {keys}bucket"


def exponent(reg: str, x: FrsParams) -> str:
    return f"({reg} >> {x.r})"


def decode(reg: str, x: FrsParams) -> str:
    e, m = exponent(reg, x), f"({x.scale - 1} - ({reg} & {x.scale - 1}))"
    return f"(CASE WHEN {e} < {x.last} THEN power(2.0, -{e}) * (1 + {m} / {float(x.scale)}) ELSE {m} * power(2.0, -{x.r + x.zeros}) END)"


def hll(power: str, filled: str, k: int) -> str:
    raw = f"({alpha(k) * k * k!r} / ({power} + ({k} - {filled})))"
    return f"(CASE WHEN {raw} <= {2.5 * k} AND {filled} < {k} THEN {k} * ln({k} / ({k} - {filled})::DOUBLE) ELSE {raw} END)"


def minvalue(value: str, filled: str, k: int) -> str:
    return f"({float(k) * k!r} / ({value} + ({k} - {filled})))"


def moments(x: FrsParams, reg: str = "reg") -> str:
    return f"count({reg}) AS filled, coalesce(sum(power(2.0, -{exponent(reg, x)})), 0) AS pw, coalesce(sum({decode(reg, x)}), 0) AS vl"


def estimate(x: FrsParams, method: str = "auto", power: str = "pw", value: str = "vl", filled: str = "filled") -> str:
    a, b = hll(power, filled, x.k), minvalue(value, filled, x.k)
    return {"hll": a, "minvalue": b, "auto": f"(CASE WHEN {a} < {SWITCH * x.k} THEN {a} ELSE {b} END)"}[method]


def expected_collisions(n: str, m: str, p: int, q: int, r: int) -> str:
    """Sum over boxes by powers, for modest n and m."""
    scale, last = 1 << r, 1 << q
    low = f"(CASE WHEN i // {scale} + 1 < {last} THEN ({scale} + i % {scale}) * power(2.0, -({r + p + 1} + i // {scale})) ELSE (i % {scale}) * power(2.0, -{r + last - 1 + p}) END)"
    width = f"(CASE WHEN i // {scale} + 1 < {last} THEN power(2.0, -({r + p + 1} + i // {scale})) ELSE power(2.0, -{r + last - 1 + p}) END)"
    mass = lambda c: f"(power(1 - {low}, {c}) - power(greatest(0.0, 1 - {low} - {width}), {c}))"
    return f"(list_sum(list_transform(range(0, {scale * last}), lambda i: {mass(n)} * {mass(m)})) * {1 << p})"


def approx_collisions(n: str, m: str, x: FrsParams, constant: float = PRINTED) -> str:
    big, small = f"greatest({n}, {m})", f"least({n}, {m})"
    flat = f"{constant * 2.0 ** (x.p - x.r)!r} * 4 * {big} * {small} / (({big} + {small}) * ({big} + {small}))"
    return f"(CASE WHEN {big} > {2.0 ** (x.p + 5)} THEN {flat} ELSE {expected_collisions(n, m, x.p, x.q, 0)} / {x.scale} END)"


def pair_cells(x: FrsParams, pairs: str = "s.a < s.b") -> str:
    """From a CTE ``sk`` (k, bucket, reg): CTEs ``sz`` (k, filled, est) and ``pr`` (a, b, c, n_filled, n, m)."""
    return f"""sz AS (SELECT k, filled, {estimate(x)} AS est FROM (SELECT k, {moments(x)} FROM sk GROUP BY k)),
mt AS (SELECT a.k AS a, b.k AS b, count(*) FILTER (a.reg = b.reg) AS c, count(*) AS both_ FROM sk a JOIN sk b ON a.bucket = b.bucket AND {pairs.replace('s.a', 'a.k').replace('s.b', 'b.k')} GROUP BY a.k, b.k),
pr AS (SELECT sa.k AS a, sb.k AS b, coalesce(c, 0) AS c, sa.filled + sb.filled - coalesce(both_, 0) AS n_filled, sa.est AS n, sb.est AS m
  FROM sz sa JOIN sz sb ON {pairs.replace('s.a', 'sa.k').replace('s.b', 'sb.k')} LEFT JOIN mt ON mt.a = sa.k AND mt.b = sb.k)"""


def shingles(source: str, key: str, text: str, size: int = 3) -> str:
    words = f"SELECT {key} AS k, regexp_split_to_array(trim(lower({text})), '\\s+') AS w FROM {source}"
    one = " || ' ' || ".join(f"w[i + {j}]" for j in range(size))
    return f"SELECT k, unnest(list_transform(range(1, len(w) - {size - 2}), lambda i: {one})) AS shingle FROM ({words}) WHERE len(w) >= {size}"
