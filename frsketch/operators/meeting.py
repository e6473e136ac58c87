"""Given pairs of keys meet the rows of their keys block by block, and are compared by arrays."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

BLOCKS = 12  # of keys; every two of them, and each with itself, are a group
TASKS = 96  # kept, for by their bytes few rows would be put into few tasks
CHUNK = 1 << 11  # pairs compared at once, few enough for a core's cache


def block(key: Column) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(BLOCKS)).cast("int")


def group(x: Column, y: Column) -> Column:
    return F.least(x, y) * BLOCKS + F.greatest(x, y)


def at_pairs(pairs: DataFrame, rows: DataFrame, prepare: Callable, find: Callable, found: str, ends: dict[str, tuple[str, str]] | None = None) -> DataFrame:
    """The given pairs (a, b, further columns) and the columns ``found`` of each. rows: one a key, (key, ...). A group's rows go
    through ``prepare`` as one Arrow table; ``find`` gets what it gave and the places of some pairs' keys in the table, and gives
    an array for each column. ends: columns of the rows that a pair takes over, with their names for a and for b. A row goes to
    ``BLOCKS`` groups, a pair to one. Pairs of a key without a row are left out."""
    ends = ends or {}
    kind = rows.schema["key"].dataType
    more = [c for c in pairs.columns if c not in ("a", "b")]
    left = pairs.select(F.col("a").cast(kind).alias("a"), F.col("b").cast(kind).alias("b"), *more).where("a is not null and b is not null")
    left = left.select(group(block(F.col("a")), block(F.col("b"))).alias("g"), "*").repartition(TASKS, "g")
    every = F.transform(F.sequence(F.lit(0), F.lit(BLOCKS - 1)), lambda y: group(block(F.col("key")), y))
    right = rows.where("key is not null").select(F.explode(every).alias("g"), "*").repartition(TASKS, "g")
    taken = [T.StructField(name, rows.schema[c].dataType) for c, names in ends.items() for name in names]
    schema = T.StructType(left.drop("g").schema.fields + T.StructType.fromDDL(found).fields + taken)

    def solve(mine: pa.Table, theirs: pa.Table) -> pa.Table:
        to = to_arrow_schema(schema)
        if not mine.num_rows or not theirs.num_rows:
            return to.empty_table()
        mine, names = mine.drop_columns(["g"]), theirs["key"].combine_chunks()
        at = [pc.index_in(mine[c], value_set=names) for c in "ab"]
        have = pc.and_(*[pc.is_valid(x) for x in at])
        mine, at = mine.filter(have), [x.filter(have).to_numpy() for x in at]
        if not mine.num_rows:
            return to.empty_table()
        ready = prepare(theirs)
        parts = [find(ready, at[0][i : i + CHUNK], at[1][i : i + CHUNK]) for i in range(0, mine.num_rows, CHUNK)]
        own = [pa.array(np.concatenate([p[i] for p in parts])) for i in range(len(parts[0]))]
        over = [theirs[c].take(pa.array(x)) for c in ends for x in at]
        return pa.table([*mine.columns, *own, *over], names=to.names).cast(to)

    return left.groupBy("g").cogroup(right.groupBy("g")).applyInArrow(solve, schema)


def cell_rows(sk: DataFrame, key: str, value: str, *more: Column) -> DataFrame:
    """(key, buckets, vals, and the aggregates ``more``): a sketch as one row a key."""
    one = sk.groupBy(F.col(key).alias("key")).agg(F.collect_list(F.struct("bucket", F.col(value).alias("v"))).alias("_l"), *more)  # at most a sketch's buckets
    return one.select("*", F.col("_l")["bucket"].alias("buckets"), F.col("_l")["v"].alias("vals")).drop("_l")


def matrix(rows: pa.Table) -> np.ndarray:
    """A row a key, a column a bucket; -1 where it is empty. Values are not negative."""
    buckets, vals = (rows[c].combine_chunks() for c in ("buckets", "vals"))
    size, flat = pc.list_value_length(buckets).to_numpy(), vals.flatten().to_numpy()
    column = buckets.flatten().to_numpy()
    narrow = np.int16 if flat.size and flat.max() < 1 << 15 else np.int64
    out = np.full((len(size), int(column.max(initial=0)) + 1), -1, narrow)
    out[np.repeat(np.arange(len(size)), size), column] = flat
    return out


def ones(bits: np.ndarray) -> np.ndarray:
    """How many of each row of packed bits are set."""
    return np.bitwise_count(bits).sum(axis=1, dtype=np.int64)


def equal_cells(pairs: DataFrame, rows: DataFrame, ends: dict[str, tuple[str, str]] | None = None) -> DataFrame:
    """The given pairs with c, the buckets in which both hold the same, and n_filled, those that either fills."""

    def prepare(rows: pa.Table):
        m = matrix(rows)
        return m, np.packbits(m >= 0, axis=1)

    def find(ready, ia: np.ndarray, ib: np.ndarray):
        m, full = ready
        n = ones(full[ia] | full[ib])
        same = np.packbits(m.take(ia, 0) == m.take(ib, 0), axis=1)
        return ones(same) - (m.shape[1] - n), n  # buckets empty in both are equal

    return at_pairs(pairs, rows, prepare, find, "c bigint, n_filled bigint", ends)
