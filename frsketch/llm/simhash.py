"""SimHash near-duplicates by the generalised pigeonhole.

Fingerprints: a text's words (ASCII lower case, split at white space) give shingles, each hashed with
XXH64 of seed 42; a bit is set where over half the hashes have it.

Search among distinct fingerprints for pairs at ``most`` differing bits or fewer:

* a bounded sample of fingerprints gives bit correlations; bits are grouped greedily so that
  correlated ones share a partition, which leaves the partitions close to independent;
* a pair within ``most`` bits must, in some partition i, differ in at most t_i bits whenever the
  (t_i + 1) sum to ``most + 1`` (t_i = -1: the partition is not probed). A dynamic programme over the
  partitions picks the t_i, and the outer loop the number of partitions, that minimise probes plus
  estimated candidates;
* every fingerprint is indexed by its partition values and probes the values within t_i bits;
  candidates are verified inside the join, and each pair passes in its first fitting partition only.

Values shared by more than ``HOT`` distinct fingerprints (a dense cloud of near copies) are not paired
up: members of such clouds are linked through all words within ``most // 2`` bits of them, since two
fingerprints within an even ``most`` bits share such a word and any two that share one are within
``most``. That is exact and linear in the cloud's size. Equal fingerprints are one node throughout.

A null or empty text has fingerprint zero, linked like any other. Repeated rows share a class. An
empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm.components import roots
from frsketch.llm.shared import give_back, stored, texts as bounded

SEED = 42
SAMPLE = 20_000
HOT = 4_096
PIECE = 60_000  # shingles whose bits are counted together


def fingerprints_of(texts: list[str], width: int = 4, seed: int = SEED) -> np.ndarray:
    """Fingerprints as signed 64-bit integers."""
    out = np.zeros(len(texts), dtype=np.uint64)
    hashes: list[int] = []
    owners: list[tuple[int, int]] = []

    def flush():
        if not owners:
            return
        h = np.array(hashes, dtype=np.uint64)
        size = np.array([n for _, n in owners])
        count = np.zeros((len(owners), 64), dtype=np.int64)
        at = np.r_[0, np.cumsum(size)]
        for a in range(0, len(h), PIECE):
            bits = np.unpackbits(h[a : a + PIECE].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            lo = np.searchsorted(at, a, side="right") - 1
            hi = np.searchsorted(at, min(a + PIECE, len(h)), side="left")
            cut = np.maximum(at[lo:hi], a) - a
            count[lo:hi] += np.add.reduceat(bits, cut, axis=0, dtype=np.int32)
        fp = np.packbits(2 * count > size[:, None], axis=1, bitorder="little").view(np.uint64).reshape(-1)
        out[[k for k, _ in owners]] = fp
        hashes.clear()
        owners.clear()

    digest = xxhash.xxh64_intdigest
    for k, text in enumerate(texts):
        words = text.encode().lower().split()
        if not words:
            continue
        joined = b" ".join(words)
        ends = (np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1).tolist()
        starts = [0, *[e + 1 for e in ends[:-1]]]
        n = max(1, len(words) - width + 1)
        hashes += [digest(joined[a:b], seed) for a, b in zip(starts[:n], ends[min(width, len(words)) - 1 :])]
        owners.append((k, n))
        if len(hashes) >= 4 * PIECE:
            flush()
    flush()
    return out.view(np.int64)


def fingerprint_frame(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 4) -> DataFrame:
    """id, fp (signed 64-bit)."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fingerprints_of(texts, width))], [id_col, "fp"])
        give_back()

    return bounded(docs).select(id_col, text_col).mapInArrow(run, f"{id_col} {kind}, fp long")


# ---- plan: partitions and thresholds


def group_bits(sample: np.ndarray, parts: int) -> list[list[int]]:
    """64 bits in ``parts`` groups of near-equal size, correlated bits together."""
    size = [64 // parts + (i < 64 % parts) for i in range(parts)]
    bits = np.unpackbits(sample.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float64)
    bits -= bits.mean(axis=0) if len(bits) else 0.5
    spread = np.sqrt((bits**2).sum(axis=0)) + 1e-9
    corr = np.abs(bits.T @ bits) / np.outer(spread, spread)
    left, out = set(range(64)), []
    for n in size:
        pool = sorted(left)
        first = max(pool, key=lambda b: sum(corr[b, c] for c in pool if c != b))
        group = [first]
        left.discard(first)
        while len(group) < n:
            nxt = max(sorted(left), key=lambda b: sum(corr[b, c] for c in group))
            group.append(nxt)
            left.discard(nxt)
        out.append(sorted(group))
    return out


def mask_of(bits: list[int]) -> int:
    return sum(1 << b for b in bits)


def flips(bits: list[int], most: int) -> list[int]:
    """Masks of up to ``most`` of the bits."""
    return [mask_of(list(c)) for k in range(most + 1) for c in combinations(bits, k)]


def pair_share(sample: np.ndarray, bits: list[int], most: int) -> float:
    """Estimated share of pairs that differ in at most ``most`` of these bits."""
    n = len(sample)
    floor = sum(comb(len(bits), k) for k in range(most + 1)) / 2.0 ** len(bits)
    if n < 2:
        return floor
    v = np.sort(sample & np.uint64(mask_of(bits)))
    hits = 0
    for f in flips(bits, min(most, 1)):
        x = v ^ np.uint64(f)
        hits += int((np.searchsorted(v, x, "right") - np.searchsorted(v, x, "left")).sum()) - (n if f == 0 else 0)
    seen = hits / (n * (n - 1.0))
    return max(seen * (1 if most < 2 else comb(len(bits), most) / len(bits)), floor)


def allocate(n: int, sample: np.ndarray, most: int, probe_cost: float = 1.0, check_cost: float = 0.05) -> tuple[list[list[int]], list[int], float]:
    """(partitions, thresholds, estimated cost) for n distinct fingerprints. The costs are those of a
    shuffled and sorted probe row and of a check inside the join, which takes a twentieth of it."""
    best = None
    for parts in range(2, most + 2):
        groups = group_bits(sample, parts)
        # price[i][u]: partition i with threshold u - 1
        price = [[0.0] + [n * sum(comb(len(g), k) for k in range(u)) * probe_cost + n * float(n) / 2 * pair_share(sample, g, u - 1) * check_cost for u in range(1, most + 2)] for g in groups]
        table: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
        for i in range(parts):
            nxt: dict[int, tuple[float, list[int]]] = {}
            for used, (c, us) in table.items():
                for u in range(most + 2 - used):
                    x = (c + price[i][u], [*us, u])
                    if used + u not in nxt or x[0] < nxt[used + u][0]:
                        nxt[used + u] = x
            table = nxt
        cost, us = table[most + 1]
        if best is None or cost < best[2]:
            best = (groups, [u - 1 for u in us], cost)
    return best


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def links(fps: DataFrame, most: int = 4, hot: int = HOT) -> DataFrame:
    """Edges (u, v) among distinct fingerprints ``fp`` so that two are joined by a path of edges
    exactly if they are by a path of pairs within ``most`` bits."""
    n = fps.count()
    rows = fps.orderBy(F.xxhash64("fp")).limit(SAMPLE).collect()  # a bounded sample, for costs only
    sample = np.array([r["fp"] for r in rows], dtype=np.int64).view(np.uint64)
    groups, limits, _ = allocate(n, sample, most)
    used = [(i, g, t) for i, (g, t) in enumerate(zip(groups, limits)) if t >= 0]
    fp = F.col("fp")

    def keyed(masks):
        """fp with one row for each (partition, value within the given flips)."""

        def cell(i, g, ms):
            own = fp.bitwiseAND(F.lit(signed(mask_of(g))))
            return F.transform(F.array(*[F.lit(signed(m)) for m in ms]), lambda m: F.struct(F.lit(i).alias("part"), own.bitwiseXOR(m).alias("val")))

        cells = [cell(*x) for x in masks]
        return fps.select(F.explode(F.concat(*cells)).alias("k"), "fp").select("k.part", "k.val", "fp")

    index = keyed([(i, g, [0]) for i, g, _ in used]).withColumnRenamed("fp", "v")
    probe = keyed([(i, g, flips(g, t)) for i, g, t in used]).withColumnRenamed("fp", "u")
    dense = index.groupBy("part", "val").count().where(F.col("count") > hot).select("part", "val")
    dense = stored(dense, "dense")
    edges = []
    if not dense.isEmpty():
        cloud = stored(index.join(dense, ["part", "val"], "left_semi").select(F.col("v").alias("u")).distinct(), "cloud")
        near = flips(list(range(64)), most // 2)
        around = cloud.select("u", F.explode(F.transform(F.array(*[F.lit(signed(m)) for m in near]), lambda m: F.col("u").bitwiseXOR(m))).alias("hub"))
        least = around.groupBy("hub").agg(F.min("u").alias("v"), F.count("*").alias("c")).where("c > 1").select("hub", "v")
        edges.append(around.join(least, "hub").where("u <> v").select("u", "v").distinct())
        # members of the cloud do not meet each other again in its own buckets
        inner = probe.join(dense, ["part", "val"], "left_semi").join(cloud, "u", "left_anti")
        probe = probe.join(dense, ["part", "val"], "left_anti").unionByName(inner)
        in_cloud = True
    else:
        in_cloud = False
    a, b = F.col("u"), F.col("v")
    differ = a.bitwiseXOR(b)
    ok = F.bit_count(differ) <= most
    ok = ok & ((a != b) if in_cloud else (a < b))
    for i, _, _ in used:
        for j, g, t in used:
            if j < i:
                ok = ok & ((F.col("p.part") != i) | (F.bit_count(differ.bitwiseAND(F.lit(signed(mask_of(g))))) > t))
    p, x = probe.alias("p"), index.alias("x")
    pairs = p.join(x, (F.col("p.part") == F.col("x.part")) & (F.col("p.val") == F.col("x.val")) & ok).select("u", "v")
    edges.append(pairs)
    out = edges[0]
    for e in edges[1:]:
        out = out.unionByName(e)
    return out


def near_duplicates(docs: DataFrame, most: int = 4, width: int = 4, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """id, fp, component_id (the smallest id of the class), n_same (rows with this fingerprint)."""
    table = stored(fingerprint_frame(docs, id_col, text_col, width), "fingerprints")
    nodes = stored(table.groupBy("fp").agg(F.min(id_col).alias("first"), F.count("*").alias("n_same")), "nodes")
    label = roots(nodes.select(F.col("fp").alias("node")), links(nodes.select("fp"), most, hot))
    label = label.join(nodes.withColumnRenamed("fp", "node"), "node")
    least = label.groupBy("root").agg(F.min("first").alias("component_id"))
    label = stored(label.join(least, "root").select(F.col("node").alias("fp"), "component_id", "n_same"), "classes")
    return table.join(label, "fp").select(id_col, "fp", "component_id", "n_same")


def hex_digits(fp):
    """16 lower-case digits of a signed fingerprint."""
    return F.lpad(F.lower(F.hex(fp)), 16, "0")
