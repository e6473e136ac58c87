"""SimHash classes, repeated strings and the pipeline against brute force."""

import collections
import hashlib
import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from frsketch.llm import simhash, suffix_dedup
from frsketch.llm.components import roots
from frsketch.llm.lyndon import suffix_array

SF = "/root/testdata/sf0.001"


def test_suffix_array_equals_sorting():
    rng = random.Random(1)
    for _ in range(1500):
        t = [rng.randrange(1, rng.choice((2, 3, 5, 60))) for _ in range(rng.randrange(0, 50))] + [0]
        assert suffix_array(t) == sorted(range(len(t)), key=lambda i: t[i:])
    t = [1] * 300 + [0]
    assert suffix_array(t) == list(range(300, -1, -1))


def brute_fp(text, width=4):
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    sh = [b" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))]
    h = [xxhash.xxh64_intdigest(x, 42) for x in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_classes(fps, most=4):
    parent = list(range(len(fps)))

    def find(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= most:
                parent[find(i)] = find(j)
    return [find(i) for i in range(len(fps))]


def same_classes(got, ids, fps):
    root = brute_classes(fps)
    least = collections.defaultdict(lambda: 1 << 60)
    for i, r in zip(ids, root):
        least[r] = min(least[r], i)
    assert got == {i: least[r] for i, r in zip(ids, root)}


def test_fingerprints_and_classes(spark):
    rng = random.Random(2)
    words = [f"v{k}" for k in range(300)]
    texts = []
    for _ in range(60):
        w = [rng.choice(words) for _ in range(rng.randrange(1, 200))]
        for _ in range(rng.randrange(1, 5)):
            v = list(w)
            for _ in range(rng.randrange(3)):
                v[rng.randrange(len(v))] = rng.choice(words)
            texts.append(" ".join(v))
    texts += ["", None, " \t\n", "Uno", "one two three", "É ü", texts[0], "x " * 30_000]
    rows = [(100 + i, t, i) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp int")
    got = simhash.near_duplicates(docs).select("doc_id", simhash.hex_digits(F.col("fp")).alias("f"), "component_id").collect()
    fps = [brute_fp(t) for t in texts]
    assert {r["doc_id"]: r["f"] for r in got} == {100 + i: f"{f:016x}" for i, f in enumerate(fps)}
    same_classes({r["doc_id"]: r["component_id"] for r in got}, [r[0] for r in rows], fps)
    assert simhash.near_duplicates(docs.where("false")).count() == 0


@pytest.mark.parametrize("hot", [4096, 3])
def test_links_keep_every_class(spark, hot):
    rng = np.random.default_rng(3)
    seeds = rng.integers(0, 1 << 63, 150, dtype=np.uint64)
    fps = set(seeds.tolist())
    for s in seeds[:25].tolist():
        for _ in range(14):
            x = s
            for b in rng.integers(0, 64, rng.integers(1, 7)).tolist():
                x ^= 1 << b
            fps.add(x)
    fps = sorted(fps)
    df = spark.createDataFrame([(simhash.signed(x),) for x in fps], "fp long")
    got = roots(df.select(F.col("fp").alias("node")), simhash.links(df, 4, hot)).collect()
    mine = collections.defaultdict(set)
    for r in got:
        mine[r["root"]].add(r["node"] % (1 << 64))
    want = collections.defaultdict(set)
    for x, r in zip(fps, brute_classes(fps)):
        want[r].add(x)
    assert sorted(map(sorted, mine.values())) == sorted(map(sorted, want.values()))


def test_allocation_covers_every_pair():
    sample = np.random.default_rng(4).integers(0, 1 << 63, 500, dtype=np.uint64)
    for n in (100, 50_000, 10_000_000):
        groups, limits, _ = simhash.allocate(n, sample, 4)
        assert sorted(b for g in groups for b in g) == list(range(64)) and sum(t + 1 for t in limits) == 5


def test_components_of_long_chains(spark):
    edges = spark.range(400).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")).where("u % 100 <> 99")
    got = roots(spark.range(400).select(F.col("id").alias("node")), edges)
    assert got.select("root").distinct().count() == 4


def brute_removal(rows):
    seen, out = set(), []
    for i, t in sorted(rows):
        raw = (t or "").encode()
        cover = bytearray(len(raw))
        for s in range(len(raw) - 99):
            w = raw[s : s + 100]
            if w in seen:
                cover[s : s + 100] = b"\1" * 100
            seen.add(w)
        kept = bytes(x for x, c in zip(raw, cover) if not c)
        runs = sum(1 for k in range(len(cover)) if cover[k] and (k == 0 or not cover[k - 1]))
        out.append((i, len(raw), len(raw) - len(kept), runs, hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("hot", [256, 1])
def test_removal_equals_brute_force(spark, hot, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    rng = random.Random(6)

    def noise(n, letters="abcdefgh éñ"):
        return "".join(rng.choice(letters) for _ in range(n))

    passages = [noise(n) for n in (99, 100, 101, 160, 400)]
    texts = [noise(rng.randrange(40)) + rng.choice(passages) + noise(rng.randrange(3)) + rng.choice(passages) + noise(rng.randrange(60)) for _ in range(60)]
    base = noise(900)
    for _ in range(15):
        v = list(base)
        for _ in range(rng.randrange(4)):
            v[rng.randrange(len(v))] = rng.choice("xyz")
        texts.append("".join(v))
    texts += [None, "", "short", "a" * 99, "a" * 100, "a" * 101, "a" * 1000, "ab" * 400, base, base, "é" * 120, noise(700, "ab"), noise(700, "ab")]
    rows = list(enumerate(texts))
    docs = spark.createDataFrame([(i, t, "l") for i, t in rows], "doc_id long, text string, lo string").repartition(5)
    got = suffix_dedup.without_repeats(docs, carry=["lo"]).collect()
    cols = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    assert sorted(tuple(r[c] for c in cols) for r in got) == brute_removal(rows)
    assert all(hashlib.sha256(r["kept"]).hexdigest() == r["kept_sha256"] and len(r["spans"]) == r["n_spans"] and r["lo"] == "l" for r in got)


def test_removal_edges(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "PIECE", 256)  # long texts in overlapping pieces
    rng = random.Random(8)
    long = "".join(rng.choice("abcdef") for _ in range(3000))
    rows = [(1, long), (2, long[500:1500] + "zz" + long[200:450])]
    docs = spark.createDataFrame(rows, "doc_id int, text string")
    got = suffix_dedup.without_repeats(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()
    assert sorted(map(tuple, got)) == brute_removal(rows)
    assert suffix_dedup.without_repeats(docs.where("false")).count() == 0
    odd = spark.createDataFrame([(None, long), (7, long), (7, long)], "doc_id int, text string")
    assert {(r["doc_id"], r["n_removed"]) for r in suffix_dedup.without_repeats(odd).collect()} == {(None, 0), (7, 0)}


def test_pipeline_stages(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    from frsketch.llm.queries import table
    from frsketch.llm.shared import stored

    docs = table(spark, SF, "documents")
    bench = [r["text"] for r in table(spark, SF, "benchmark").collect()]
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    for k, (name, stage) in enumerate(pipeline.STAGES):
        out = stored(stage(spark, docs, SF), name)
        rows = out.collect()
        after = {r["doc_id"]: r for r in rows}
        assert len(after) == len(rows) and set(after) <= set(before)
        if k < 4:
            assert out.columns == docs.columns and all(r["n_chars"] == len(r["text"]) for r in rows)
        if name == "toxicity":
            assert len(after) > 0.75 * len(before)
        if name == "simhash":
            ids = sorted(before)
            root = jaccard_classes([before[i] for i in ids])
            least = {}
            for i, r in zip(ids, root):
                least.setdefault(r, i)
            assert set(after) == set(least.values())
        if name == "suffix_array":
            want = {i: (n, gone) for i, n, gone, _, _ in brute_removal(list(before.items()))}
            assert set(after) == set(before)
            for i, r in after.items():
                n, gone = want[i]
                assert n - gone - 6 * 3 <= len(r["text"].encode()) <= n - gone
        if name == "decontamination":
            assert not any(b in r["text"] for r in rows for b in bench) and len(after) > 0.8 * len(before)
        if name == "byte_bpe":
            assert set(after) == set(before)
            assert all(r["decoded_sha256"] == hashlib.sha256(before[i].encode()).hexdigest() and r["n_tokens"] == len(r["ids"]) for i, r in after.items())
        else:
            before = {i: r["text"] for i, r in after.items()}
        docs = out


def word_set(text, width=5):
    w = (text or "").encode().lower().split()
    return frozenset(b" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))) if w else frozenset()


def jaccard_classes(texts):
    sets = [word_set(t) for t in texts]
    root = list(range(len(sets)))
    for i, a in enumerate(sets):
        for j in range(i):
            c = len(a & sets[j])
            if a == sets[j] or 5 * c >= 4 * (len(a) + len(sets[j]) - c) > 0:
                old, new = root[i], root[j]
                root = [new if r == old else r for r in root]
    return root


@pytest.mark.parametrize("hot", [64, 3])
def test_near_copies_equal_brute_force(spark, hot):
    from frsketch.llm import near_copies

    rng = random.Random(11)
    words = [f"v{k}" for k in range(400)]
    texts = [None, "", " ", "a b", "A  B", "a b c d e", "a b c d e f"]
    for k in range(40):
        w = [rng.choice(words) for _ in range(rng.randrange(3, 160))]
        for _ in range(8 if k else 90):
            v = list(w)
            for _ in range(rng.randrange(5)):
                v[rng.randrange(len(v))] = rng.choice(words)
            texts.append(" ".join(["all texts start with these words"] * (k % 2) + v))
    for at in (2100, 4800):  # on either side of a step in the length of parity maps
        w = [f"z{rng.randrange(10**6)}" for _ in range(at)]
        texts += [" ".join(w), " ".join(w[at // 20 :]), " ".join(w[at // 3 :]), " ".join("y" if k % 61 == 0 else x for k, x in enumerate(w)), " ".join("y" if k % 36 == 0 else x for k, x in enumerate(w))]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    got = collections.defaultdict(set)
    for r in near_copies.copy_classes(docs, hot=hot, pivots=2).collect():
        got[r["root"]].add(r["doc_id"])
    want = collections.defaultdict(set)
    for i, r in enumerate(jaccard_classes(texts)):
        want[r].add(i)
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, want.values()))
    assert near_copies.copy_classes(docs.where("false")).count() == 0


def test_pipeline_drops_copies_of_similarity_080(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    rng = random.Random(12)
    rows = []
    for k in range(30):
        w = [f"w{rng.randrange(10_000)}" for _ in range(204)]
        rows += [(2 * k, " ".join(w)), (2 * k + 1, " ".join([*w[:60], "x", *w[61:120], "y", *w[121:170], "z", *w[171:]]))]
    a, b = word_set(rows[0][1]), word_set(rows[1][1])
    assert 0.8 <= len(a & b) / len(a | b) < 0.9
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(r["doc_id"] for r in pipeline.simhash(spark, docs, SF).collect()) == list(range(0, 60, 2))


def test_pipeline_copies_with_null_and_repeated_ids(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    a, b, c, d = (" ".join(f"{x}{k}" for k in range(30)) for x in "abcd")
    rows = [(None, a), (None, b), (None, b), (7, c), (7, c), (9, d), (None, d), (7, "another text of the same id")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r["doc_id"]), r["text"]) for r in pipeline.simhash(spark, docs, SF).collect())
    assert got == sorted([("None", a), ("None", b), ("7", c), ("9", d), ("7", "another text of the same id")])


def test_near_copies_too_far_apart_make_no_candidates(spark, monkeypatch):
    """A text of 60 words with one word changed at places far from each other: Jaccard 46 / 66 of every two."""
    from frsketch.llm import near_copies

    base = [f"w{i}" for i in range(60)]
    rows = [(k, " ".join(base[: 5 + 5 * (k % 11)] + [f"x{k}"] + base[6 + 5 * (k % 11) :])) for k in range(110)]
    seen, real = [], near_copies.alike
    monkeypatch.setattr(near_copies, "alike", lambda pairs, *more: (seen.append(pairs.count()), real(pairs, *more))[1])
    got = near_copies.copy_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    sets = {k: set(near_copies.shingle_set(t, 5).tolist()) for k, t in rows}
    classes = {}
    for r in got:
        classes.setdefault(r["root"], set()).add(r["doc_id"])
    for a in sets:
        for b in sets:
            if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                assert any({a, b} <= c for c in classes.values())
    assert sorted(map(len, classes.values())) == [10] * 11
    assert seen[-1] < 300  # of 4,950 pairs of different places
