"""All similar pairs among very many sketches.

Sketches meet in bands of equal registers instead of bucket by bucket. Keys with the same register row
are one class first, so copies never meet each other; pairs are given between class representatives.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.operators.jaccard import pairwise_jaccard
from frsketch.params import FrsParams


def cells() -> Column:
    """Buckets and registers, each two in one number: as structs they take four times the bytes."""
    return F.sort_array(F.collect_list(F.call_function("shiftleft", F.col("bucket").cast("bigint"), F.lit(32)) + F.col("reg"))).alias("cells")


def register_rows(sk: DataFrame, key: str) -> DataFrame:
    """(key, cells): each sketch as one sorted array of at most 2**p cells."""
    return sk.groupBy(F.col(key).alias("key")).agg(cells())


def classes(sk: DataFrame, key: str) -> DataFrame:
    """(key, rep): the least key with the same registers. The array is compared, not a hash of it."""
    rows = register_rows(sk, key)
    rep = rows.groupBy("cells").agg(F.min("key").alias("rep"))
    return rows.join(rep, "cells").select("key", "rep")


def candidate_pairs(sk: DataFrame, key: str, params: FrsParams, width: int = 4, filled: int | None = None) -> DataFrame:
    """(a, b), a < b: keys with a band of ``width`` equal registers, all filled (or at least ``filled`` of
    them, default all)."""
    filled = width if filled is None else filled
    bands = sk.groupBy(F.col(key).alias("key"), F.floor(F.col("bucket") / width).alias("band")).agg(cells())
    bands = bands.where(F.size("cells") >= filled)
    one = bands.select(F.col("key").alias("a"), "band", "cells")
    two = bands.select(F.col("key").alias("b"), "band", "cells")
    return one.join(two, ["band", "cells"]).where("a < b").select("a", "b").distinct()


def similar_pairs(sk: DataFrame, key: str, params: FrsParams, least: float = 0.5, width: int = 4, correction: str = "none") -> DataFrame:
    """Pairs of class representatives with an estimate of ``least`` or more (see ``classes`` for the
    members)."""
    reps = classes(sk, key).select("rep").distinct()
    own = sk.join(reps, F.col(key) == F.col("rep"), "left_semi")
    return pairwise_jaccard(own, key, params, correction, least=least, pairs=candidate_pairs(own, key, params, width))


def top_similar(pairs: DataFrame, k: int, both: bool = True) -> DataFrame:
    """(key, rank, other, t): each key's k most similar others, ties by the smaller one; with ``both`` false, the
    others b of each a alone."""
    from pyspark.sql import Window

    rows = pairs.select(F.col("a").alias("key"), F.col("b").alias("other"), "t")
    if both:
        rows = rows.unionByName(pairs.select(F.col("b").alias("key"), F.col("a").alias("other"), "t"))
    w = Window.partitionBy("key").orderBy(F.desc("t"), "other")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("key", "rank", "other", "t")


def hashed_sets(df: DataFrame, key: str, element: str) -> DataFrame:
    """(key, cells): each set as the sorted XXH64 of its elements."""
    m = df.select(F.col(key).alias("key"), F.xxhash64(element).alias("x"), F.col(element).alias("e")).where("key is not null and e is not null")
    return m.groupBy("key").agg(F.sort_array(F.collect_set("x")).alias("cells"))


def overlap(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """(u, v, both, any) of the pairs (u, v, ...): the sizes of intersection and union."""
    got = pairs.join(sets.select(F.col("key").alias("u"), F.col("cells").alias("cu")), "u").join(sets.select(F.col("key").alias("v"), F.col("cells").alias("cv")), "v")
    return got.withColumn("both", F.size(F.array_intersect("cu", "cv"))).withColumn("any", F.size("cu") + F.size("cv") - F.col("both")).drop("cu", "cv")


def jaccard_pairs(df: DataFrame, key: str, element: str, num: int = 1, den: int = 2) -> DataFrame:
    """(a, b, t), a < b: every two distinct sets of exact Jaccard num / den or more, each by its least key.

    No pair is lost, however small its sets: of two sets ordered by falling rarity, the first n - ceil(J n) + 1
    elements of the larger and the first m - ceil(2 J / (1 + J) m) + 1 of the smaller share one where the Jaccard
    index is J or more. Candidates meet there and are verified on the whole sets.

    Elements are held as their XXH64: two different ones of a pair being taken for one has a chance of some 10**-13 a pair at
    1,000 elements. Equal sets are those of equal size and 128-bit hash. Elements of one set alone come first in that
    order and meet nobody, so only their number is kept."""
    sets = hashed_sets(df, key, element)
    name = [F.xxhash64("cells"), F.xxhash64(F.lit(1), "cells"), F.size("cells")]
    first = sets.select("key", *[c.alias(f"h{i}") for i, c in enumerate(name)]).groupBy("h0", "h1", "h2").agg(F.min("key").alias("key")).select("key")
    sets = sets.join(first, "key", "left_semi")
    # one shuffle serves the counts and the join with them, since both take the same columns
    dealt = sets.select("key", F.explode("cells").alias("element")).repartition("element")
    often = dealt.groupBy("element").agg(F.count("key").alias("often"), F.max("key").alias("last")).where("often > 1").drop("last")
    rows = dealt.join(often, "element").groupBy("key").agg(F.sort_array(F.collect_list(F.struct("often", "element"))).alias("cells")).join(sets.select("key", F.size("cells").alias("n")), "key")
    probing, indexed = F.col("n") - F.ceil(F.col("n") * num / den) + 1, F.col("n") - F.ceil(2 * F.col("n") * num / (num + den)) + 1
    single = F.col("n") - F.size("cells")  # these come first
    rows = rows.select("key", "n", probing.alias("pr"), indexed.alias("ix"), single.alias("single"), "cells").where("pr > single")
    rows = rows.select("key", "n", "ix", "single", F.posexplode(F.slice("cells", F.lit(1), (F.col("pr") - F.col("single")).cast("int"))).alias("pos", "x")).select("key", "n", "ix", (F.col("single") + F.col("pos")).alias("pos"), F.col("x.element").alias("x"))
    a, b = rows.where("pos < ix").alias("a"), rows.alias("b")
    left = F.least(F.col("a.n") - F.col("a.pos"), F.col("b.n") - F.col("b.pos"))
    fits = (F.col("a.n") * den >= F.col("b.n") * num) & (left * (num + den) >= (F.col("a.n") + F.col("b.n")) * num)
    on = (F.col("a.x") == F.col("b.x")) & (F.struct("a.n", "a.key") < F.struct("b.n", "b.key")) & fits
    pairs = a.join(b, on).select(F.col("a.key").alias("u"), F.col("b.key").alias("v")).distinct()
    both = overlap(pairs, sets)
    return both.where(F.col("both") * den >= F.col("any") * num).select(F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b"), (F.col("both") / F.col("any")).alias("t"))
