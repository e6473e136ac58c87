"""Exact counterparts of every estimate."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

PARTS = 4096  # of the keys, for counting
TASKS = 96  # kept, however few their bytes


def members(df: DataFrame, key: str, element: str) -> DataFrame:
    """Distinct (key, element) without nulls."""
    return df.select(F.col(key).alias("key"), F.col(element).alias("element")).where("key is not null and element is not null").distinct()


def exact_count(df: DataFrame, by: list[str], element: str) -> DataFrame:
    return df.groupBy(*by).agg(F.count_distinct(element).alias("exact"))


def exact_jaccard(df: DataFrame, key: str, element: str, pairs: DataFrame | None = None) -> DataFrame:
    """(a, b, both, t) of every two keys that share an element, or of the given pairs (a, b)."""
    m = members(df, key, element)
    size = m.groupBy("key").agg(F.count("*").alias("n"))
    one, two = m.withColumnRenamed("key", "a"), m.withColumnRenamed("key", "b")
    if pairs is None:
        # an element's list goes to each of its keys as the keys after it; pairs are counted where their first key is, by arrays
        lists = m.groupBy("element").agg(F.array_sort(F.collect_list("key")).alias("keys")).where(F.size("keys") > 1)
        after = lists.select("keys", F.posexplode("keys").alias("i", "a")).where(F.col("i") < F.size("keys") - 1)
        after = after.select(F.pmod(F.xxhash64("a"), F.lit(PARTS)).alias("g"), "a", F.slice("keys", F.col("i") + 2, F.size("keys")).alias("bs"))
        got = common_elements(after.repartition(TASKS, "g"))
    else:
        got = pairs.select("a", "b").join(one, "a").join(two, ["b", "element"]).groupBy("a", "b").agg(F.count("*").alias("both"))
        got = pairs.select("a", "b").join(got, ["a", "b"], "left").fillna(0, ["both"])
    got = got.join(size.withColumnsRenamed({"key": "a", "n": "na"}), "a").join(size.withColumnsRenamed({"key": "b", "n": "nb"}), "b")
    return got.select("a", "b", "both", (F.col("both") / (F.col("na") + F.col("nb") - F.col("both"))).alias("t"))


def common_elements(after: DataFrame) -> DataFrame:
    """(a, b, both): how often b is in the lists of a. after: (g, a, bs), the rows of a key under one g."""
    kind = after.schema["a"].dataType
    schema = T.StructType([T.StructField("a", kind), T.StructField("b", kind), T.StructField("both", T.LongType())])

    def count(rows: pa.Table) -> pa.Table:
        lists = rows["bs"].combine_chunks()
        a, b = rows["a"].combine_chunks().dictionary_encode(), lists.flatten().dictionary_encode()
        wide = len(b.dictionary)
        cell = np.repeat(a.indices.to_numpy().astype(np.int64) * wide, lists.value_lengths().to_numpy()) + b.indices.to_numpy()
        if len(a.dictionary) * wide <= 4 * len(cell):
            n = np.bincount(cell)
            cell = np.flatnonzero(n)
            n = n[cell]
        else:
            cell, n = np.unique(cell, return_counts=True)
        got = [a.dictionary.take(pa.array(cell // wide)), b.dictionary.take(pa.array(cell % wide)), pa.array(n)]
        return pa.table(got, names=["a", "b", "both"]).cast(to_arrow_schema(schema))

    return after.groupBy("g").applyInArrow(count, schema)


def exact_cnf(df: DataFrame, key: str, element: str, clauses: list[list[str]]) -> DataFrame:
    """(exact): elements that are in a set of every clause."""
    rows = [(i, n) for i, c in enumerate(clauses) for n in sorted(set(c))]
    lists = F.broadcast(df.sparkSession.createDataFrame(rows, "clause_id int, set_name string"))
    hit = df.join(lists, F.col(key).cast("string") == F.col("set_name")).groupBy(element).agg(F.count_distinct("clause_id").alias("k"))
    return hit.agg(F.count_if(F.col("k") == len(clauses)).alias("exact"))
