"""Near copies by SimHash links and, for what these miss, prefixes; every link is verified by exact Jaccard
similarity of word shingles.

A text's words (ASCII lower case, split at white space) give a set of shingles, kept as XXH64 hashes of
seed 42; a text of fewer than ``width`` words is one shingle. Texts of the same set are one node.

First the SimHash operator (``simhash.links``) pairs the sets' fingerprints at ``BITS`` bits or fewer; the pairs
that have the similarity are links. A similarity of 0.8 is beyond its reach, since fingerprints of such pairs
differ in up to 14 of 64 bits, so sets of different classes then meet on prefixes, without loss:

Two sets of n >= m elements have Jaccard J >= ``num / den`` only if m >= J n and they share
J / (1 + J) (n + m) elements. In any common order of all elements, the first n - ceil(J n) + 1 of the larger
set (it probes) and the first m - ceil(2 J / (1 + J) m) + 1 of the smaller (it is indexed) then share one, and
from there on enough elements are left. So candidates meet on such prefixes and no pair is lost. Where they meet,
parity maps of 256 bits rule out most of those that differ in too many elements, so the near copies of a cloud that are
too far from each other make no rows; the rest is verified, by longer maps and then on the whole sets. The order is by hash, elements that a bounded sample of texts shows to be
frequent last: the sample bears on the cost alone.

A prefix element held by over ``HOT`` nodes (a dense cloud of near copies) first has its holders compared with
``PIVOTS`` of them. Of the classes found so far the largest one at each such element is then not paired
with itself, for its members are linked already; all other pairs are. Classes are exact, and a cloud that its
pivots link costs as much as it has members. What remains quadratic are many texts of like length that share
a rare element and are no near copies. Elements of one set alone are dropped first by the filter of fixed size
that the repeated-string operator has (where more elements repeat than it can tell apart, more rows pass).

Null and empty texts have the empty set and are one class. An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm import simhash
from frsketch.llm.components import roots
from frsketch.llm.shared import drop_stored, give_back, release, stored, texts as bounded
from frsketch.llm.suffix_dedup import filter_cells, repeat_filter

SEED = 42
SAMPLE = 4_000
FREQUENT = 100_000  # frequent elements sent to the workers
PIECE = 50_000  # words hashed together
HOT = 8
BITS = 4  # at which fingerprints are paired
PIVOTS = 4
PARITY_WORDS = 32  # 64-bit words of a parity map at the least
SHORT = [f"q{i}" for i in range(4)]  # words of the folded map that goes with each prefix element
MAX_BROADCAST = 1_000_000  # candidates, or their ids


def shingle_set(text: str | None, width: int) -> np.ndarray:
    """Distinct hashes, ascending."""
    words = (text or "").encode().lower().split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    n = max(1, len(words) - width + 1)
    digest, parts = xxhash.xxh64_intdigest, []
    for at in range(0, n, PIECE):
        some = words[at : at + PIECE + width - 1]
        joined = b" ".join(some)
        ends = (np.cumsum(np.fromiter(map(len, some), np.int64, len(some)) + 1) - 1).tolist()
        starts = [0, *[e + 1 for e in ends[:-1]]]
        m = max(1, len(some) - width + 1)
        parts.append(np.array([digest(joined[a:b], SEED) for a, b in zip(starts[:m], ends[min(width, len(some)) - 1 :])], dtype=np.uint64))
    return np.unique(np.concatenate(parts))


def set_fingerprint(s: np.ndarray) -> int:
    """A bit is set where over half the hashes have it; signed."""
    count = np.zeros(64, dtype=np.int64)
    for a in range(0, len(s), simhash.PIECE):
        count += np.unpackbits(s[a : a + simhash.PIECE].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * count > len(s), bitorder="little").view(np.int64)[0])


def parity_map(s: np.ndarray) -> np.ndarray:
    """A bit for each residue of the hashes: is it held an odd number of times. Two maps differ in no more bits
    than their sets in elements. There are as many bits as elements or more, a power of two; the halves of a map
    make the map of half the length."""
    bits = 64 * PARITY_WORDS
    while bits < len(s):
        bits *= 2
    odd = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def set_frame(docs: DataFrame, key: str, text_col: str, width: int, frequent: np.ndarray, share: tuple[int, int] | None = None) -> DataFrame:
    """key, node (16 bytes that stand for the set), n (its size), cells (the set in the common
    order). With a ``share``, cells are as much of it as probes, and fp (its fingerprint) and odd (its parity map)
    come before them."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches):
        for b in batches:
            nodes, sets, sizes, fps, odd = [], [], [], [], []
            for t in b.column(1).to_pylist():
                s = shingle_set(t, width)
                nodes.append(xxhash.xxh3_128_digest(s.tobytes()))
                rank = np.searchsorted(frequent, s)
                late = (frequent[np.minimum(rank, len(frequent) - 1)] == s) if len(frequent) else np.zeros(len(s), dtype=bool)
                n = len(s)
                sizes.append(n)
                if share:
                    fps.append(set_fingerprint(s))
                    odd.append(parity_map(s))
                upto = n if share is None or not n else n + n * share[0] // -share[1] + 1
                sets.append(np.concatenate([s[~late], s[late]])[:upto].view(np.int64))
            at = np.r_[0, np.cumsum([len(s) for s in sets])].astype(np.int32)
            cells = pa.ListArray.from_arrays(pa.array(at), pa.array(np.concatenate(sets) if sets else np.zeros(0, np.int64)))
            also = []
            if share:
                flat = np.concatenate(odd) if odd else np.zeros(0, np.int64)
                also = [pa.array(fps, pa.int64()), pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum([len(o) for o in odd])].astype(np.int32)), pa.array(flat))]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(nodes, pa.binary()), pa.array(sizes, pa.int32()), *also, cells], [key, "node", "n", *(["fp", "odd"] if share else []), "cells"])
        give_back()

    more = "fp long, odd array<long>, " if share else ""
    return bounded(docs).select(key, text_col).mapInArrow(run, f"`{key}` {kind}, node binary, n int, {more}cells array<long>")


def frequent_elements(docs: DataFrame, key: str, text_col: str, width: int) -> np.ndarray:
    """Elements of three or more texts of a sample, at most ``FREQUENT`` of them; they are put last in the
    common order, which changes no result."""
    n = docs.count()
    some = docs.where(F.pmod(F.xxhash64(text_col), F.lit(max(1, n // SAMPLE))) == 0)
    sets = set_frame(some, key, text_col, width, np.zeros(0, np.uint64)).dropDuplicates(["node"])
    top = sets.select(F.explode("cells").alias("x")).groupBy("x").count().where("count >= 3").orderBy(F.desc("count"), "x").limit(FREQUENT)
    return np.sort(top.select("x").toArrow().column("x").to_numpy().view(np.uint64))


def halved(odd):
    half = (F.size(odd) / 2).cast("int")
    return F.zip_with(F.slice(odd, 1, half), F.slice(odd, half + 1, half), lambda a, b: a.bitwiseXOR(b))


def alike(pairs: DataFrame, light: DataFrame, whole, num: int, den: int, name: str) -> DataFrame:
    """The pairs (u, v) whose whole sets have Jaccard num / den or more, stored. ``light`` has node, n and odd of every set:
    pairs whose parity maps differ in more bits than such sets can in elements go first. ``whole`` gives the sets
    (node, cells) of the nodes asked for, so only candidates' sets are ever written, and they go again."""
    u, v = (light.select(F.col("node").alias(x), F.col("n").alias(f"n{x}"), F.col("odd").alias(f"o{x}")) for x in "uv")
    # sets that fit in size have maps of one length, or one of twice the other's
    half_u, half_v = (F.when(F.size(x) > F.size(y), halved(F.col(x))).otherwise(F.col(x)) for x, y in (("ou", "ov"), ("ov", "ou")))
    differ = F.aggregate(F.zip_with(half_u, half_v, lambda a, b: F.bit_count(a.bitwiseXOR(b))), F.lit(0), lambda a, x: a + x)
    near = pairs.join(u, "u").join(v, "v").where(F.least("nu", "nv") * den >= F.greatest("nu", "nv") * num)
    near = near.where(differ * (num + den) <= (F.col("nu") + F.col("nv")) * (den - num))
    pairs = stored(near.select("u", "v"), "candidates")
    release(pairs.sparkSession)
    sets = whole(pairs.select("u").union(pairs.select("v")).distinct().withColumnRenamed("u", "node"))
    few = pairs.count() <= MAX_BROADCAST  # else the sets are shuffled to both ends of the pairs
    both = (F.broadcast(pairs) if few else pairs).join(sets.select(F.col("node").alias("u"), F.col("cells").alias("cu")), "u").join(sets.select(F.col("node").alias("v"), F.col("cells").alias("cv")), "v")
    common = F.size(F.array_intersect("cu", "cv"))
    out = stored(both.where(common * den >= (F.size("cu") + F.size("cv") - common) * num).select("u", "v"), name)
    drop_stored(pairs)
    drop_stored(sets)
    release(out.sparkSession)
    return out


def simhash_links(sets: DataFrame, whole, num: int = 4, den: int = 5, bits: int = BITS) -> DataFrame:
    """Pairs (u, v) of Jaccard num / den or more among the distinct sets ``node``, ``n``, ``fp``: sets of one fingerprint with
    the least of them, and the least of any two fingerprints that the SimHash operator links."""
    some = sets.where("n > 0").select("node", "fp")
    lead = stored(some.groupBy("fp").agg(F.min("node").alias("lead")), "fingerprints")
    same = some.join(lead, "fp").where("node <> lead").select(F.col("node").alias("u"), F.col("lead").alias("v"))
    near = simhash.links(lead.select("fp"), bits)
    near = near.join(lead.select(F.col("fp").alias("u"), F.col("lead").alias("a")), "u").join(lead.select(F.col("fp").alias("v"), F.col("lead").alias("b")), "v")
    return alike(same.unionByName(near.select(F.col("a").alias("u"), F.col("b").alias("v"))).distinct(), sets, whole, num, den, "simhash-links")


def prefix_rows(sets: DataFrame, num: int, den: int, wanted=None) -> DataFrame:
    """x of every element that probes; with ``wanted``, a broadcast filter, of those that pass it: x, node, n, pos (in the
    common order), ix (is it indexed) and ``SHORT``, the set's parity map folded."""

    def run(batches):
        bits = None if wanted is None else np.frombuffer(wanted.value, dtype=np.uint8)
        for b in batches:
            cells = b.column(2)
            x = np.asarray(cells.flatten())
            if bits is None:
                yield pa.RecordBatch.from_arrays([pa.array(x)], ["k"])
                continue
            size = np.asarray(cells.value_lengths())
            first, second = filter_cells(x.view(np.uint64))
            at = np.flatnonzero(bits[first >> 3] >> (first & 7).astype(np.uint8) & bits[second >> 3] >> (second & 7).astype(np.uint8) & 1)
            row = np.repeat(np.arange(len(size)), size)[at]
            pos = at - (np.cumsum(size) - size)[row]
            n = np.asarray(b.column(1)).astype(np.int64)[row]
            indexed = n - -(-2 * n * num // (num + den)) + 1
            odd = b.column(3)
            long = np.asarray(odd.value_lengths()).astype(np.int64)
            begin = (np.cumsum(long) - long) // len(SHORT)
            short = np.bitwise_xor.reduceat(np.asarray(odd.flatten()).reshape(-1, len(SHORT)), begin, axis=0)[row]
            yield pa.RecordBatch.from_arrays([pa.array(x[at]), b.column(0).take(pa.array(row)), pa.array(n, pa.int32()), pa.array(pos, pa.int32()), pa.array(pos < indexed), *[pa.array(q.copy()) for q in short.T]], ["x", "node", "n", "pos", "ix", *SHORT])
        give_back()

    kind = sets.schema["node"].dataType.simpleString()
    return bounded(sets).where("n > 0").select("node", "n", "cells", *([] if wanted is None else ["odd"])).mapInArrow(run, "k long" if wanted is None else f"x long, node {kind}, n int, pos int, ix boolean, " + ", ".join(f"{q} long" for q in SHORT))


def links(sets: DataFrame, whole, num: int = 4, den: int = 5, hot: int = HOT, pivots: int = PIVOTS, known: DataFrame | None = None) -> DataFrame:
    """Edges (u, v) among the distinct sets ``node``, ``n``, ``odd``, ``cells`` (what probes) so that two are joined by a path of edges
    exactly if they are by a path of pairs of Jaccard num / den or more. ``known``: such pairs found before, which
    are among the edges; what they join is not paired again."""
    wanted = sets.sparkSession.sparkContext.broadcast(repeat_filter(prefix_rows(sets, num, den)))
    release(sets.sparkSession)
    prefixes = rows = stored(prefix_rows(sets, num, den, wanted), "prefixes")  # elements that occur once are left out, but for those that the filter lets by
    crowd = rows.groupBy("x").agg(F.count("*").alias("g"), F.count_if("ix").alias("k")).where("g > 1 and k > 0")
    crowd = stored(crowd, "crowds")
    rows = rows.join(crowd.select("x", "g"), "x")
    a, b = F.struct("a.n", "a.node"), F.struct("b.n", "b.node")
    fits = (F.col("a.n") * den >= F.col("b.n") * num) & (F.least(F.col("a.n") - F.col("a.pos"), F.col("b.n") - F.col("b.pos")) * (num + den) >= (F.col("a.n") + F.col("b.n")) * num)
    differ = sum((F.bit_count(F.col(f"a.{q}").bitwiseXOR(F.col(f"b.{q}"))) for q in SHORT), F.lit(0))
    fits = fits & (differ * (num + den) <= (F.col("a.n") + F.col("b.n")) * (den - num))

    def meet(small, large, on):
        return small.alias("a").join(large.alias("b"), (F.col("a.x") == F.col("b.x")) & (a < b) & fits & on).select(F.col("a.node").alias("u"), F.col("b.node").alias("v"))

    first = known
    if known is None:
        rows = rows.withColumn("root", F.col("node"))
    else:
        rows = rows.join(stored(roots(sets.select("node"), known), "known-classes"), "node")
    met = rows = stored(rows.withColumn("big", F.lit(False)), "met")  # what shares an element with another
    drop_stored(prefixes)
    release(sets.sparkSession)
    dealt = not crowd.where(F.col("g") > hot).isEmpty()
    if dealt:
        whole_dense = dense = stored(rows.where(F.col("g") > hot).drop("big", "root"), "dense")
        least = pivots_of(dense, pivots)
        near = [meet(dense, least, F.lit(True)), meet(least, dense, F.lit(True))]
        first = alike(near[0].unionByName(near[1]).distinct(), sets, whole, num, den, "pivot-pairs")
        first = stored(first if known is None else first.unionByName(known), "pivot-links")
        label = stored(roots(dense.select("node").distinct(), first), "labels")
        dense = dense.join(label, "node")
        most = dense.groupBy("x", "root").count().groupBy("x").agg(F.max_by("root", F.struct("count", "root")).alias("main"))
        dense = dense.join(most, "x").withColumn("big", F.col("root") == F.col("main")).drop("main")
        rows = stored(rows.where(F.col("g") <= hot).unionByName(dense.select(rows.columns)), "dealt")
        drop_stored(met)
        drop_stored(whole_dense)
        release(sets.sparkSession)
    ix = rows.where("ix")
    apart = F.col("a.root") != F.col("b.root")
    pairs = meet(ix.where("not big"), rows, apart)
    if dealt:
        pairs = pairs.unionByName(meet(ix.where("big"), rows.where("not big"), apart))
    out = alike(pairs.distinct(), sets, whole, num, den, "prefix-links")
    return out if first is None else out.unionByName(first)


def pivots_of(dense: DataFrame, pivots: int) -> DataFrame:
    """Of the rows of each element those of the smallest hashed nodes; partial lists stay that short."""
    row = F.struct(F.xxhash64("node").alias("h"), "node", "n", "pos", *SHORT)
    dealt = dense.withColumn("part", F.pmod(F.xxhash64("node", F.lit(1)), F.lit(64)))
    some = dealt.groupBy("x", "part").agg(F.slice(F.array_sort(F.collect_list(row)), 1, pivots).alias("p"))
    best = some.groupBy("x").agg(F.slice(F.array_sort(F.flatten(F.collect_list("p"))), 1, pivots).alias("p"))
    return best.select("x", F.explode("p").alias("p")).select("x", "p.node", "p.n", "p.pos", *[f"p.{q}" for q in SHORT])


def copy_classes(docs: DataFrame, key: str = "doc_id", text_col: str = "text", width: int = 5, num: int = 4, den: int = 5, hot: int = HOT, pivots: int = PIVOTS) -> DataFrame:
    """key, root (the same for all rows of a class): texts joined by a path of pairs of Jaccard num / den or
    more. A row for each row of ``docs``; keys are neither null nor repeated."""
    frequent = frequent_elements(docs, key, text_col, width)
    table = stored(set_frame(docs, key, text_col, width, frequent, (num, den)), "sets")
    release(docs.sparkSession)
    nodes = stored(table.groupBy("node").agg(F.min(key).alias("id")), "nodes")
    first = table.join(nodes.select(F.col("id").alias(key)), key, "left_semi").select(F.col(key).alias("node"), "n", "fp", "odd", "cells")

    def whole(asked):
        asked = stored(asked.select(F.col("node").alias(key)), "asked")
        small = asked.count() <= MAX_BROADCAST  # else both sides are shuffled
        rows = docs.join(F.broadcast(asked) if small else asked, key, "left_semi")
        return stored(set_frame(rows, key, text_col, width, frequent).select(F.col(key).alias("node"), "cells"), "whole-sets")

    known = simhash_links(first, whole, num, den)
    label = roots(nodes.select(F.col("id").alias("node")), links(first, whole, num, den, hot, pivots, known))
    return table.select(key, "node").join(nodes, "node").select(key, F.col("id").alias("node")).join(label, "node").select(key, "root")
