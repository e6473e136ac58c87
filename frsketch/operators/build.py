"""Sketches as tables (keys..., bucket, reg), and what keeps them closed: union, roll-up, cube, codec."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.functions.hashing import element_key, hash_parts, pack
from frsketch.params import FrsParams


def _tagged(df: DataFrame, params: FrsParams) -> DataFrame:
    return df.withMetadata("reg", {"frs": params.tag()})


def check_same(*sketches: DataFrame) -> None:
    """Sketches that carry their parameters must agree on them."""
    tags = [s.schema["reg"].metadata.get("frs") for s in sketches]
    seen = {tuple(sorted(t.items())) for t in tags if t}
    if len(seen) > 1:
        raise ValueError(f"sketches of different parameters: {sorted(seen)}")


def registers(df: DataFrame, elements: list[str] | str | Column, by: list[str], params: FrsParams) -> DataFrame:
    """(by..., bucket, reg) of every element: no shuffle."""
    parts = df.select(*by, element_key(elements).alias("_key")).where("_key is not null").select(*by, hash_parts(F.col("_key"), params).alias("_h"))
    return parts.select(*by, F.col("_h.bucket").alias("bucket"), pack(F.col("_h.e"), F.col("_h.m"), params).alias("reg"))


def sketch(df: DataFrame, elements: list[str] | str | Column, by: list[str] | None = None, params: FrsParams = FrsParams(), packed: bool = True) -> DataFrame:
    """One sketch for each value of ``by``. Partial maxima per task, then one shuffle of at most
    2**p rows for each key and task. ``packed=False`` compares exponent and mantissa apart."""
    by = by or []
    if packed:
        return _tagged(registers(df, elements, by, params).groupBy(*by, "bucket").agg(F.max("reg").alias("reg")), params)
    parts = df.select(*by, element_key(elements).alias("_key")).where("_key is not null").select(*by, hash_parts(F.col("_key"), params).alias("_h"))
    two = parts.groupBy(*by, F.col("_h.bucket").alias("bucket")).agg(F.max(F.struct(F.col("_h.e").alias("e"), (-F.col("_h.m")).alias("m"))).alias("x"))
    return _tagged(two.select(*by, "bucket", pack(F.col("x.e"), -F.col("x.m"), params).alias("reg")), params)


def union_sketches(*sketches: DataFrame) -> DataFrame:
    """The sketch of the union: the larger register of every bucket."""
    check_same(*sketches)
    out = sketches[0]
    for s in sketches[1:]:
        out = out.unionByName(s)
    return _keep_tag(sketches[0], out.groupBy(*[c for c in out.columns if c != "reg"]).agg(F.max("reg").alias("reg")))


def _keep_tag(source: DataFrame, df: DataFrame) -> DataFrame:
    meta = source.schema["reg"].metadata
    return df.withMetadata("reg", meta) if meta else df


def rollup_sketch(sk: DataFrame, by: list[str]) -> DataFrame:
    """Sketches of coarser keys from finer ones."""
    return _keep_tag(sk, sk.groupBy(*by, "bucket").agg(F.max("reg").alias("reg")))


def cube_sketch(sk: DataFrame, by: list[str]) -> DataFrame:
    """Sketches of all cells of the cube over ``by`` (null: all), with the grouping id ``g``. Base data
    are not read again."""
    sets = [[c for i, c in enumerate(by) if not g >> (len(by) - 1 - i) & 1] for g in range(1 << len(by))]
    cells = F.array(*[F.struct(F.lit(g).alias("g"), *[(F.col(c) if c in keep else F.lit(None).cast(sk.schema[c].dataType)).alias(c) for c in by]) for g, keep in enumerate(sets)])
    out = sk.select(F.explode(cells).alias("c"), "bucket", "reg").select("c.*", "bucket", "reg")
    return _keep_tag(sk, out.groupBy("g", *by, "bucket").agg(F.max("reg").alias("reg")))


def to_hll(sk: DataFrame, params: FrsParams) -> DataFrame:
    """The registers of an exponent-only sketch: (keys..., bucket, e)."""
    return sk.select(*[c for c in sk.columns if c != "reg"], F.shiftright("reg", params.r).alias("e"))


def register_bytes(params: FrsParams) -> int:
    most = (params.last << params.r) + params.scale - 1
    return 1 if most < 256 else 2 if most < 65_536 else 4


def to_packed(sk: DataFrame, params: FrsParams, by: list[str]) -> DataFrame:
    """(by..., p, q, r, regs): one binary of fixed-width registers a key."""
    kinds = ", ".join(f"`{c}` {sk.schema[c].dataType.simpleString()}" for c in by)
    width, k = register_bytes(params), params.k
    lists = sk.groupBy(*by).agg(F.collect_list(F.struct("bucket", "reg")).alias("cells"))  # at most 2**p

    def run(batches):
        for b in batches:
            cells = b.column(b.num_columns - 1)
            flat, ends = cells.flatten(), np.asarray(cells.offsets)
            bucket, reg = (np.asarray(flat.field(i)) for i in (0, 1))
            regs = []
            for lo, hi in zip(ends, ends[1:]):
                x = np.zeros(k, dtype=f"<u{width}")
                x[bucket[lo - ends[0] : hi - ends[0]]] = reg[lo - ends[0] : hi - ends[0]]
                regs.append(x.tobytes())
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(regs, pa.binary())], [*by, "regs"])

    out = lists.mapInArrow(run, (kinds + ", " if by else "") + "regs binary")
    return out.select(*by, *[F.lit(getattr(params, c)).alias(c) for c in ("p", "q", "r")], "regs")


def from_packed(df: DataFrame, params: FrsParams, by: list[str]) -> DataFrame:
    """Back to (by..., bucket, reg), without empty buckets; no Python."""
    width = register_bytes(params)
    parts = [F.conv(F.hex(F.expr(f"substring(regs, i * {width} + {j + 1}, 1)")), 16, 10).cast("int") * 256**j for j in range(width)]
    reg = parts[0]
    for x in parts[1:]:
        reg = reg + x
    out = df.select(*by, "regs", F.explode(F.sequence(F.lit(0), F.lit(params.k - 1))).alias("i"))
    return _tagged(out.select(*by, F.col("i").alias("bucket"), reg.cast("int").alias("reg")).where("reg > 0"), params)


def packed_union(a: Column, b: Column, params: FrsParams) -> Column:
    """Union of two packed registers: a vectorised maximum."""
    width = register_bytes(params)

    @F.pandas_udf("binary")
    def larger(x, y):
        kind = f"<u{width}"
        return x.combine(y, lambda u, v: np.maximum(np.frombuffer(u, kind), np.frombuffer(v, kind)).tobytes())

    return larger(a, b)


def compress_minhash(mh: DataFrame, params: FrsParams, bits: int) -> DataFrame:
    """The float-register sketch of a finished k-partition MinHash (keys..., bucket, val of ``bits``
    bits). On the bits of ``contiguous`` registers it equals the sketch built directly."""
    need = params.zeros + params.r
    if bits < need:
        raise ValueError(f"{bits} bits a value; {need} are needed")
    v = F.shiftright("val", bits - need) if bits > need else F.col("val")
    lead = F.when(v == 0, 0).otherwise(F.length(F.bin(v)))
    e = F.when(F.shiftright(v, params.r) == 0, params.last).otherwise(need + 1 - lead)
    # r bits after the leading one (or after the window)
    m = F.call_function("shiftright", v, (F.lit(need) - F.least(e, F.lit(params.zeros)) - params.r).cast("int")).bitwiseAND(F.lit(params.scale - 1))
    return _tagged(mh.select(*[c for c in mh.columns if c != "val"], pack(e, m, params).alias("reg")), params)
