"""Counting Boolean formulas of sets in conjunctive normal form.

A clause is a union, hence a maximum; the conjunction is an m-way match of the clauses' registers times
the cardinality of the union of all.
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.functions.collisions import approx_collisions_col
from frsketch.operators.cardinality import from_moments, moments
from frsketch.params import FrsParams

MAX_CLAUSES = 256


def to_cnf(expr) -> list[list[str]]:
    """Clauses of a formula: a name, ('and', x, ...) or ('or', x, ...). Without negation."""
    if isinstance(expr, str):
        return [[expr]]
    op, *args = expr
    parts = [to_cnf(a) for a in args]
    if op == "and":
        out = [c for p in parts for c in p]
    elif op == "or":
        size = 1
        for p in parts:
            size *= len(p)
        if size > MAX_CLAUSES:
            raise ValueError(f"{size} clauses; at most {MAX_CLAUSES}")
        out = [sorted({x for c in combo for x in c}) for combo in product(*parts)]
    else:
        raise ValueError(f"operator {op!r}")
    kept: list[list[str]] = []
    for c in sorted({tuple(sorted(set(c))) for c in out}, key=lambda c: (len(c), c)):
        if not any(set(k) <= set(c) for k in kept):  # a wider clause adds nothing
            kept.append(list(c))
    if len(kept) > MAX_CLAUSES:
        raise ValueError(f"{len(kept)} clauses; at most {MAX_CLAUSES}")
    return kept


def cnf_count(sk: DataFrame, clauses: list[list[str]], params: FrsParams, key: str = "name", correction: str = "none") -> DataFrame:
    """(c, n_filled, j, ec_bound, union_est, est) of the sketches (key, bucket, reg). ec_bound: the
    expected accidental matches of the first clause with each other one, summed (own extension), which
    ``correction='bound'`` subtracts for two clauses."""
    if not clauses or not all(clauses):
        raise ValueError("a formula needs clauses, and a clause needs sets")
    spark = sk.sparkSession
    rows = [(i, name) for i, c in enumerate(clauses) for name in sorted(set(c))]
    lists = F.broadcast(spark.createDataFrame(rows, "clause_id int, set_name string"))  # the formula's size
    hit = sk.where(F.col(key).isin(sorted({x for c in clauses for x in c}))).join(lists, F.col(key).cast("string") == F.col("set_name"))
    united = hit.groupBy("clause_id", "bucket").agg(F.max("reg").alias("reg"))
    cells = united.groupBy("bucket").agg(F.count("*").alias("k"), F.min("reg").alias("low"), F.max("reg").alias("reg"))
    est, _ = from_moments(params)
    whole = cells.agg(F.count_if((F.col("k") == len(clauses)) & (F.col("low") == F.col("reg"))).alias("c"), *moments(params))
    whole = whole.select("c", F.col("filled").alias("n_filled"), est.alias("union_est"))
    size = united.groupBy("clause_id").agg(*moments(params)).select("clause_id", est.alias("est"))
    first = size.where("clause_id = 0").select(F.col("est").alias("n"))
    rest = size.where("clause_id > 0").join(F.broadcast(first), F.lit(True))  # a row a clause
    ec = rest.agg(F.coalesce(F.sum(approx_collisions_col(F.col("n"), F.col("est"), params)), F.lit(0.0)).alias("ec_bound"))
    got = whole.join(F.broadcast(ec), F.lit(True))
    matches = F.col("c") - (F.col("ec_bound") if correction == "bound" else 0)
    j = F.when(F.col("n_filled") > 0, F.greatest(F.lit(0.0), matches / F.greatest(F.col("n_filled"), F.lit(1))))
    return got.select("c", "n_filled", j.alias("j"), "ec_bound", "union_est", (j * F.col("union_est")).alias("est"))
