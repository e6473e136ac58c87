"""Bit layout, golden vectors, union properties, codec."""

import random

import pytest
from pyspark.sql import functions as F

from frsketch.functions.hashing import decode, element_key, exponent_of, mantissa_of
from frsketch.operators import build
from frsketch.operators.baselines import minhash_kpart
from frsketch.params import FrsParams
from frsketch.sources.tables import load_sketch, save_sketch

GOLDEN = {
    (2, 2, 2): [(0, 1, 3, 4), (1, 1, 0, 7), (2, 2, 3, 8), (1, 1, 0, 7)],
    (6, 4, 4): [(56, 1, 11, 20), (13, 1, 12, 19), (62, 2, 3, 44), (57, 1, 12, 19)],
    (15, 6, 10): [(16952, 1, 155, 1892), (29325, 1, 556, 1491), (18558, 2, 755, 2316), (30329, 1, 556, 1491)],
}


def numbers(spark, lo, hi):
    return spark.range(lo, hi).select(F.col("id").cast("string").alias("x"))


def regs(sk):
    return {r["bucket"]: r["reg"] for r in sk.collect()}


@pytest.mark.parametrize("pqr", GOLDEN)
def test_golden_vectors(spark, pqr):
    x = FrsParams(*pqr)
    for i, (bucket, e, m, reg) in enumerate(GOLDEN[pqr], 1):
        row = build.sketch(numbers(spark, i, i + 1), "x", [], x).select("bucket", "reg", exponent_of(F.col("reg"), x).alias("e"), mantissa_of(F.col("reg"), x).alias("m")).first()
        assert (row["bucket"], row["e"], row["m"], row["reg"]) == (bucket, e, m, reg)


def test_golden_unions(spark):
    x = FrsParams(3, 3, 3)
    a, b = (build.sketch(numbers(spark, *r), "x", [], x) for r in ((1, 9), (5, 13)))
    assert regs(a) == {0: 12, 1: 11, 4: 19, 5: 11, 6: 20, 7: 12}
    assert regs(b) == {0: 63, 3: 13, 4: 19, 5: 10, 6: 25, 7: 23}
    assert regs(build.union_sketches(a, b)) == regs(build.sketch(numbers(spark, 1, 13), "x", [], x))


@pytest.mark.parametrize("x", [FrsParams(4, 3, 3), FrsParams(4, 3, 3, hash="sha1", mantissa="contiguous"), FrsParams(4, 2, 3, tail="overflow"), FrsParams(4, 6, 3, hash="xx"), FrsParams(4, 6, 8, hash="sha256", seed=5)])
def test_union_is_lossless_idempotent_and_order_free(spark, x):
    a, b = numbers(spark, 0, 300), numbers(spark, 200, 500)
    sa, sb = (build.sketch(v, "x", [], x) for v in (a, b))
    whole = regs(build.sketch(a.union(b).union(a), "x", [], x))
    assert regs(build.union_sketches(sa, sb)) == whole == regs(build.union_sketches(sb, sa, sb))
    assert regs(build.sketch(a.union(b).repartition(7), "x", [], x, packed=False)) == whole
    assert all(x.scale <= v < (x.last + 1) * x.scale for v in whole.values())


def test_python_model_of_the_layout(spark):
    import hashlib

    x = FrsParams(5, 6, 7)
    want: dict[int, int] = {}
    for i in range(400):
        d = int(hashlib.md5(str(i).encode()).hexdigest(), 16)
        word = d >> 32 & (1 << 64) - 1
        top = word >> 1
        e = 64 if top == 0 else 64 - top.bit_length()
        reg = e * 128 + 127 - (d & 127)
        b = d >> 96 & 31
        want[b] = max(want.get(b, 0), reg)
    assert regs(build.sketch(numbers(spark, 0, 400), "x", [], x)) == want


def test_forced_tail_and_leading_one(spark):
    x = FrsParams(0, 2, 2)
    every = build.registers(numbers(spark, 0, 4000), "x", [], x).select(exponent_of(F.col("reg"), x).alias("e")).groupBy("e").count().collect()
    share = {r["e"]: r["count"] / 4000 for r in every}
    assert set(share) == {1, 2, 3, 4} and abs(share[4] - 1 / 8) < 0.03


def test_printed_bit_example():
    # exponents of the worked bit example: its parts sum to 22
    assert 2 + 12 + 8 == 22 and 0b01011101 < 2**8


def test_decode_boxes(spark):
    x = FrsParams(0, 3, 2)
    rows = spark.range(x.scale, (x.last + 1) * x.scale).select(F.col("id").cast("int").alias("reg"))
    got = [(r["lo"], r["mid"]) for r in rows.select("reg", decode(F.col("reg"), x).alias("lo"), decode(F.col("reg"), x, "midpoint").alias("mid")).orderBy(F.desc("reg")).collect()]
    assert got[0][0] == 0 and [v for v, _ in got] == sorted(v for v, _ in got) and all(lo < mid < 1 for lo, mid in got)


def test_minhash_compresses_to_the_same_registers(spark):
    x = FrsParams(5, 3, 5, hash="sha1", mantissa="contiguous")
    df = numbers(spark, 0, 500)
    for bits in (12, 20):
        mh = minhash_kpart(df, "x", [], x.p, bits, x, contiguous=True)
        assert regs(build.compress_minhash(mh, x, bits)) == regs(build.sketch(df, "x", [], x))
    with pytest.raises(ValueError):
        build.compress_minhash(mh, x, 5)


def test_packed_codec_store_and_parameters(spark, tmp_path):
    x = FrsParams(4, 4, 8)
    df = numbers(spark, 0, 200).withColumn("g", F.col("x").cast("int") % 3)
    sk = build.sketch(df, "x", ["g"], x)
    packed = build.to_packed(sk, x, ["g"])
    want = {tuple(r) for r in sk.collect()}
    assert {tuple(r) for r in build.from_packed(packed, x, ["g"]).collect()} == want
    one, two = (packed.where(f"g = {g}").select(F.col("regs").alias(f"r{g}")) for g in (0, 1))
    both = one.join(two, F.lit(True)).select(build.packed_union(F.col("r0"), F.col("r1"), x).alias("regs"))
    assert regs(build.from_packed(both, x, [])) == regs(build.sketch(df.where("g < 2"), "x", [], x))
    save_sketch(sk, str(tmp_path / "s"), x)
    assert {tuple(r) for r in load_sketch(spark, str(tmp_path / "s"), x).select("g", "bucket", "reg").collect()} == want
    with pytest.raises(ValueError):
        load_sketch(spark, str(tmp_path / "s"), FrsParams(4, 4, 7))
    with pytest.raises(ValueError):
        build.union_sketches(sk, build.sketch(df, "x", ["g"], FrsParams(4, 4, 7)))


def test_element_keys(spark):
    df = spark.createDataFrame([("a", "bc"), ("ab", "c"), (None, "x"), ("ä", "字")], "p string, q string")
    keys = [r[0] for r in df.select(element_key(["p", "q"])).collect()]
    assert len(set(keys)) == 4 and keys[2] is None
    assert build.sketch(df, ["p", "q"], [], FrsParams(4, 3, 3)).count() <= 3
    assert build.sketch(df.where("false"), "p", [], FrsParams()).count() == 0


def test_cube_matches_direct_sketches(spark):
    random.seed(1)
    df = spark.createDataFrame([(random.choice("ab"), random.choice("xyz"), i) for i in range(300)], "u string, v string, i int")
    x = FrsParams(3, 3, 3)
    cube = build.cube_sketch(build.sketch(df, "i", ["u", "v"], x), ["u", "v"])
    assert regs(cube.where("g = 3")) == regs(build.sketch(df, "i", [], x))
    assert regs(cube.where("g = 1 and u = 'a'")) == regs(build.sketch(df.where("u = 'a'"), "i", [], x))


def test_bad_parameters():
    for kw in ({"hash": "crc"}, {"p": 40}, {"q": 6, "p": 26, "r": 24, "hash": "md5", "mantissa": "contiguous", "seed": 0, "tail": "capped"} | {"p": 26, "r": 24, "q": 6, "hash": "md5"} and {"mantissa": "contiguous", "hash": "xx"}):
        with pytest.raises(ValueError):
            FrsParams(**kw)
