"""Sketches along time: as-of look-ups, interval joins, day-over-day similarity."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from frsketch.operators.jaccard import finish, side_moments
from frsketch.operators.cardinality import from_moments
from frsketch.params import FrsParams


def as_of(left: DataFrame, at: str, right: DataFrame, ts: str, by: list[str], value: list[str]) -> DataFrame:
    """left with the values of the latest right row at or before ``at``, for equal ``by``. No join: both sides
    run through one window, so each row is read once however many rows stand before it."""
    slot = [c for c in left.columns if c not in by and c != at]
    kinds = {f.name: f.dataType for f in right.schema}
    rows = left.select(*by, F.col(at).alias("_t"), F.lit(1).alias("_side"), *slot, *[F.lit(None).cast(kinds[v]).alias(f"_{v}") for v in value])
    ref = right.select(*by, F.col(ts).alias("_t"), F.lit(0).alias("_side"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in slot], *[F.col(v).alias(f"_{v}") for v in value])
    w = Window.partitionBy(*by).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    out = rows.unionByName(ref)
    for v in value:
        out = out.withColumn(v, F.last(f"_{v}", ignorenulls=True).over(w))
    return out.where("_side = 1").select(*by, F.col("_t").alias(at), *slot, *value)


def interval_join(points: DataFrame, ts: str, spans: DataFrame, start: str, end: str, step: int = 86_400) -> DataFrame:
    """Points inside [start, end) of spans. Both sides are cut at multiples of ``step`` seconds and meet by
    equality, so no side is compared with all of the other."""

    def cell(c: Column) -> Column:
        return F.floor(F.unix_micros(c.cast("timestamp")) / (step * 1_000_000))

    cells = F.sequence(cell(F.col(start)), cell(F.col(end)))
    one = points.withColumn("_cell", cell(F.col(ts)))
    two = spans.withColumn("_cell", F.explode(cells))
    return one.join(two, "_cell").where((F.col(ts) >= F.col(start)) & (F.col(ts) < F.col(end))).drop("_cell")


def running_union(sk: DataFrame, day: str, params: FrsParams, span: int | None = None) -> DataFrame:
    """(day, bucket, reg): for each day of the sketches the union of all up to it or, with ``span``, of those of the
    last ``span`` days and itself. One window a bucket over days x buckets rows; no day is joined with the others."""
    days = sk.select(day).distinct()
    grid = days.select(day, F.explode(F.sequence(F.lit(0), F.lit(params.k - 1))).alias("bucket"), F.lit(None).cast("int").alias("reg"))
    cells = grid.unionByName(sk.select(day, "bucket", "reg")).groupBy("bucket", day).agg(F.max("reg").alias("reg"))
    w = Window.partitionBy("bucket").orderBy(F.datediff(day, F.lit("1970-01-01")))
    w = w.rowsBetween(Window.unboundedPreceding, 0) if span is None else w.rangeBetween(-span, 0)
    return cells.select(day, "bucket", F.max("reg").over(w).alias("reg")).where("reg is not null")


def consecutive_jaccard(sk: DataFrame, order: str, params: FrsParams, by: list[str] | None = None, correction: str = "none") -> DataFrame:
    """(by..., a, b, c, n_filled, n, m, ec, t_raw, t, status) of every sketch and the one before it. Steps
    are numbered once (without ``by``, all steps stand in one window: they are points in time, not rows); each register
    row then serves two pairs, and no sketch is joined with itself."""
    by = by or []
    steps = sk.select(*by, order).distinct()
    w = Window.partitionBy(*by).orderBy(order) if by else Window.orderBy(order)
    steps = steps.select(*by, F.lag(order).over(w).alias("a"), F.col(order), F.lead(order).over(w).alias("z"))
    rows = sk.join(steps, [*by, order])  # one row a step
    later = rows.where("a is not null").select(*by, "a", F.col(order).alias("b"), "bucket", F.lit(None).cast("int").alias("ra"), F.col("reg").alias("rb"))
    before = rows.where("z is not null").select(*by, F.col(order).alias("a"), F.col("z").alias("b"), "bucket", F.col("reg").alias("ra"), F.lit(None).cast("int").alias("rb"))
    cells = later.unionByName(before).groupBy(*by, "a", "b", "bucket").agg(F.max("ra").alias("ra"), F.max("rb").alias("rb"))
    got = cells.groupBy(*by, "a", "b").agg(F.count_if(F.col("ra") == F.col("rb")).alias("c"), F.count("*").alias("n_filled"), *side_moments(params, "ra"), *side_moments(params, "rb"))
    n = [from_moments(params, "auto", F.col(f"{s}_pow"), F.col(f"{s}_val"), F.col(f"{s}_filled"))[0].alias(m) for s, m in (("ra", "n"), ("rb", "m"))]
    return finish(got.select(*by, "a", "b", "c", "n_filled", *n), params, correction)
