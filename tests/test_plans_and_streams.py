"""Registry against DuckDB, plan shape, streams."""

import random

import duckdb
import pytest
from pyspark.sql import functions as F

from frsketch.operators import build
from frsketch.params import FrsParams
from frsketch.plans import registry
from frsketch.sources.tables import table
from frsketch.streaming import sketches as streams

SF = "/root/testdata/sf0.001"
FAST = [n for n in registry.ORACLE_SQL if n not in ("conversation_similarity",)]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def shown(rows):
    return sorted(tuple("" if v is None else f"{v:.9g}" if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", FAST)
def test_query_equals_sql(spark, duck, name):
    df = registry.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    rel = duck.sql(registry.ORACLE_SQL[name])
    assert sorted(rel.columns) == cols
    want = duck.execute(f"select {', '.join(chr(34) + c + chr(34) for c in cols)} from ({registry.ORACLE_SQL[name]})").fetchall()
    assert shown(df.select(*cols).collect()) == shown(want)


def test_build_plan_has_no_python_one_exchange_and_reads_two_columns(spark):
    sk = build.sketch(table(spark, SF, "orders"), "o_custkey", ["o_orderpriority"], FrsParams())
    plan = sk._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Python" not in plan and "partial_max" in plan
    assert "ReadSchema: struct<o_custkey:bigint,o_orderpriority:string>" in plan


def test_stream_equals_batch_with_replays(spark, tmp_path):
    ev = table(spark, SF, "events")
    parts = str(tmp_path / "in")
    ev.union(ev.limit(200)).repartition(5).write.parquet(parts)
    x = FrsParams(4, 4, 4)
    live = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 2).parquet(parts)
    out = streams.stream_sketch(live, "ts", "user_id", ["event_type"], x, watermark="40 days")
    streams.run_to_end(out, streams.merge_batch(str(tmp_path / "t"), []), str(tmp_path / "c"))
    keys = ["win", "event_type"]
    got = {tuple(r) for r in streams.read_merged(spark, str(tmp_path / "t"), keys).collect()}
    assert got == {tuple(r) for r in streams.stream_sketch(ev, "ts", "user_id", ["event_type"], x).collect()}
    streams.compact(spark, str(tmp_path / "t"), keys, str(tmp_path / "u"))
    assert spark.read.parquet(str(tmp_path / "u")).count() == len(got)


def test_packed_state(spark, tmp_path):
    ev = table(spark, SF, "events")
    ev.repartition(3).write.parquet(str(tmp_path / "in"))
    x = FrsParams(4, 4, 4)
    live = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = streams.packed_state_sketch(live, "event_type", "user_id", x)
    streams.run_to_end(out, streams.merge_batch(str(tmp_path / "t"), []), str(tmp_path / "c"))
    got = {tuple(r) for r in streams.read_merged(spark, str(tmp_path / "t"), ["event_type"]).collect()}
    assert got == {tuple(r) for r in build.sketch(ev, "user_id", ["event_type"], x).collect()}


def test_sessions_are_formed_before_buckets(spark):
    rows = [("u", f"2024-01-01 00:{m:02d}:00", i) for i, m in enumerate((0, 5, 10, 50, 55))]
    df = spark.createDataFrame(rows, "u string, ts string, x int").withColumn("ts", F.to_timestamp("ts"))
    got = streams.session_sketch(df, "ts", "u", "x", FrsParams(8, 3, 3), "10 minutes")
    assert got.select("start").distinct().count() == 2


def test_time_queries_cover_whole_tables(spark):
    got = registry.QUERIES["asof_last_event_all"](spark, SF).agg(F.sum("n")).first()[0]
    assert got == table(spark, SF, "orders").count()
    events = table(spark, SF, "events")
    types = {r[0] for r in events.select("event_type").distinct().collect()}
    assert types <= set(registry.TYPES)
    assert {f"{t}_" for t in types} <= set(registry.QUERIES["pivot_distinct_all_types"](spark, SF).columns)
    last = registry.QUERIES["interval_window_sketch_all"](spark, SF).agg(F.max("id")).first()[0]
    end = events.where(F.expr(f"ts >= timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(0, {last * 60 + 100})"))
    assert end.isEmpty()


def test_all_similar_pairs_equal_brute_force(spark):
    """Texts of 3 to 60 words: most fill no band of four registers."""
    rng = random.Random(5)
    rows = []
    for _ in range(40):
        w = [f"w{rng.randrange(400)}" for _ in range(rng.randrange(3, 60))]
        for _ in range(3):
            v = list(w)
            for _ in range(rng.randrange(4)):
                v[rng.randrange(len(v))] = f"w{rng.randrange(400)}"
            rows.append((len(rows), " ".join(v)))
    sets = {}
    for k, t in rows:
        w = t.split()
        sets.setdefault(frozenset(zip(w, w[1:], w[2:])), k)
    want = {(a, b): round(len(s & t) / len(s | t), 6) for s, a in sets.items() for t, b in sets.items() if a < b and 2 * len(s & t) >= len(s | t)}
    sh = registry.word_shingles(spark.createDataFrame(rows, "k int, text string"), "k", "text")
    got = {(r["doc_a"], r["doc_b"]): r["t_exact"] for r in registry.all_similar_texts(sh, "k").collect()}
    assert got == want
    found = {(r["doc_a"], r["doc_b"]) for r in registry.similar_texts(sh, "k").collect()}
    assert not set(want) <= found  # the bands lose pairs


def test_containment_sketch_keeps_passages_of_long_texts(spark, tmp_path):
    rng = random.Random(6)
    word = lambda: f"w{rng.randrange(50_000)}"
    items = [[word() for _ in range(42)] for _ in range(6)]
    docs = [[word() for _ in range(3000)] + w + [word() for _ in range(3000)] for w in items]
    for name, key, rows in (("benchmark", "item_id", items), ("documents", "doc_id", docs)):
        spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(rows)], f"{key} long, text string").write.parquet(f"{tmp_path}/{name}.parquet")
    got = {(r["item"], r["doc"], r["exact"]) for r in registry.QUERIES["benchmark_containment_sketch"](spark, str(tmp_path)).collect()}
    assert got == {(f"i{k}", f"d{k}", 1.0) for k in range(6)}
