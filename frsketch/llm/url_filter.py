"""URL rules behind a blocked Bloom filter.

A list holds canonical entries ``host + path`` (host lower-cased, path up to ``?`` or ``#``). An entry
fits a URL whose host is the entry's or a subdomain of it and whose path starts with the entry's path.
Each URL is cut into candidate entries: its host's last labels, as many as some entry has, joined with
its path's first characters, as many as some entry has. A blocked Bloom filter (one block of four
64-bit words a key, one bit in each word) passes possible hits; an exact hash join against the list
removes the false ones; the longest entry left decides.

The filter's size follows the list up to ``MAX_BLOCKS`` blocks (4 MiB), beyond which it only passes
more false hits. The list is broadcast while it has at most ``MAX_BROADCAST`` rows, else shuffled. Hosts and
paths are stored once with a number for each row, on which hits meet their rows again: no host is a hot key.

Nulls and URLs without ``://`` have an empty host and path, which no entry fits. Equal entries with
different actions: ``block`` wins. Repeated rows keep a row each; an empty table or list is no error;
further columns of the pages are not read, and names cannot clash with the internal ones.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from frsketch.llm.shared import stored

WORDS = 4
MAX_BLOCKS = 1 << 17
MAX_BROADCAST = 100_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.instr(url, "://") > 0, F.substr(url, F.instr(url, "://") + 3)).otherwise("")
    rest = F.coalesce(rest, F.lit(""))
    return F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), UPPER, LOWER), F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def url_list(spark: SparkSession, rows: list[tuple[str, str, str]]) -> DataFrame:
    """(host, path, action) tuples as a list."""
    return spark.createDataFrame(rows, "entry_host string, entry_path string, action string")


def _block(key: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int")


def _bit(key: Column, word: int) -> Column:
    at = F.pmod(F.xxhash64(key, F.lit(word)), F.lit(64)).cast("int")
    return F.call_function("shiftleft", F.lit(1).cast("long"), at)


def bloom_rows(keys: DataFrame, blocks: int) -> DataFrame:
    """The filter as a table, one row for each block in use; ``keys`` has one column ``entry``."""
    e = F.col("entry")
    return keys.groupBy(_block(e, blocks).alias("b")).agg(*[F.bit_or(_bit(e, w)).alias(f"w{w}") for w in range(WORDS)])


def judge_urls(pages: DataFrame, rules: DataFrame, listed: DataFrame | None = None, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """id, host, path, rule (the deciding rule, or null), verdict, listed_as (the deciding list entry
    where no rule fits). ``rules`` and ``listed`` come from ``url_list``."""
    spark = pages.sparkSession
    entries = rules.withColumn("kind", F.lit(1))
    if listed is not None:
        entries = entries.unionByName(listed.withColumn("kind", F.lit(0)))
    entries = (
        entries.withColumn("entry", F.concat(F.translate("entry_host", UPPER, LOWER), "entry_path"))
        .groupBy("entry", "kind")
        .agg(F.max("action").alias("action"), F.max(F.size(F.split("entry_host", "\\."))).alias("labels"), F.max(F.length("entry_path")).alias("path_len"))
    )
    # the list's shape: a few numbers, not its rows
    shape = entries.agg(F.count("*").alias("n"), F.collect_set(F.struct("labels", "path_len")).alias("cuts")).first()
    cuts = sorted((c["labels"], c["path_len"]) for c in shape["cuts"])
    page = pages.select(F.col(id_col).alias("_id"), F.col(url_col).alias("_url"))
    host, path = host_and_path(F.col("_url"))
    page = page.select("_id", host.alias("host"), path.alias("path"))
    if not cuts:
        return page.select(F.col("_id").alias(id_col), "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"), F.lit(None).cast("string").alias("listed_as"))
    blocks = 1
    while blocks < MAX_BLOCKS and blocks * 64 * WORDS < 16 * shape["n"]:
        blocks *= 2
    # numbered once: the numbers are a join key, and another evaluation of the input may give others
    page = stored(page.withColumn("row", F.monotonically_increasing_id()), "urls").withColumn("labels", F.size(F.split("host", "\\.")))
    cands = F.filter(
        F.array(*[F.when((F.col("labels") >= k) & (F.length("path") >= n), F.concat(F.substring_index("host", ".", -k), F.substring("path", 1, n))) for k, n in cuts]),
        lambda c: c.isNotNull(),
    )
    page = page.withColumn("cands", cands)
    # the filter has MAX_BLOCKS rows at most
    cell = F.broadcast(bloom_rows(entries.select("entry"), blocks))
    hits = page.select("row", F.explode("cands").alias("entry")).withColumn("b", _block(F.col("entry"), blocks)).join(cell, "b")
    for w in range(WORDS):
        hits = hits.where(F.col(f"w{w}").bitwiseAND(_bit(F.col("entry"), w)) != 0)
    hits = hits.select("row", "entry")
    exact = entries.select("entry", "kind", "action")
    hits = hits.join(F.broadcast(exact) if shape["n"] <= MAX_BROADCAST else exact, "entry")
    best = hits.groupBy("row").agg(F.max(F.struct("kind", F.length("entry").alias("len"), "entry", "action")).alias("hit"))
    out = page.select("row", "_id", "host", "path").join(best, "row", "left")
    by_rule = F.col("hit.kind") == 1
    return out.select(
        F.col("_id").alias(id_col),
        "host",
        "path",
        F.when(by_rule, F.col("hit.entry")).alias("rule"),
        F.coalesce("hit.action", F.lit(default)).alias("verdict"),
        F.when(~by_rule, F.col("hit.entry")).alias("listed_as"),
    )
