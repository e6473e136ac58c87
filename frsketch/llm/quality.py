"""Quality rules and a hashed n-gram likelihood ratio, in DataFrame functions only.

Base counts come from whole texts. The learned part compares two multinomials over ``BUCKETS`` hashed
word unigrams and bigrams: one of trusted documents (label 1), one of all documents. A text's score is
its mean log ratio per n-gram; the threshold is a fixed low percentile of the scores of the labelled
trusted rows, so every document is decided by the same number and none by chance.

Every trusted row counts, and so does every document. Labels meet the texts by a sorted
join; the percentile comes from the lowest scores alone. What the driver sees is two count vectors of
``BUCKETS`` entries and two scores.

A null or empty text has no words, fails the base rules and is not kept. Without labels the target is
the corpus itself, all scores are 0 and pass. Repeated rows keep a row each; an empty table gives an
empty one; other columns are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.llm.shared import stored

BUCKETS = 16_384
KEEP_SHARE = 0.005
BLANKS = " \t\n\x0b\x0c\r"
BLANK_CLASS = "[\\x20\\x09-\\x0D]+"
SYMBOLS = "#*$%&|<>"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, BLANK_CLASS), "")


def _at(a: Column, i: Column) -> Column:
    return F.get(a, i)


def with_counts(rows: DataFrame, window: int = 5) -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and ``wh`` (hashed words) to
    rows with a non-null ``text``."""
    size = F.size
    out = rows.withColumn("wh", F.transform(words_of(F.col("text")), lambda w: F.xxhash64(w)))
    out = out.withColumn("lines", F.filter(F.split("text", "\n"), lambda x: F.translate(x, BLANKS, "") != ""))
    n = size("wh")

    def shingle(i):
        return F.xxhash64(*[_at(F.col("wh"), i + k) for k in range(window)])

    none = F.array().cast("array<bigint>")
    out = out.withColumn("sh", F.when(n >= window, F.transform(F.sequence(F.lit(0), n - window), shingle)).otherwise(none))
    out = out.withColumn("again", size(F.array_distinct("sh")) < size("sh"))
    pairs = F.sort_array(F.transform("sh", lambda h, i: F.struct(h.alias("h"), i.alias("p"))))
    out = out.withColumn("pairs", F.when(F.col("again"), pairs).otherwise(F.array().cast("array<struct<h:bigint,p:int>>")))

    def repeated(s, i):
        before, after = _at(F.col("pairs"), i - 1), _at(F.col("pairs"), i + 1)
        return F.coalesce((i > 0) & (before["h"] == s["h"]), F.lit(False)) | F.coalesce(after["h"] == s["h"], F.lit(False))

    out = out.withColumn("at", F.sort_array(F.transform(F.filter("pairs", repeated), lambda s: s["p"])))
    gaps = F.transform("at", lambda p, i: F.least(F.lit(window), F.coalesce(_at(F.col("at"), i + 1) - p, F.lit(window))))
    out = out.withColumn("n_repeat_words", F.aggregate(gaps, F.lit(0).cast("bigint"), lambda a, x: a + x))
    return out.select(
        *rows.columns,
        "wh",
        n.cast("bigint").alias("n_words"),
        F.length(F.translate("text", BLANKS, "")).cast("bigint").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", SYMBOLS, ""))).cast("bigint").alias("n_symbols"),
        (size("lines") - size(F.array_distinct("lines"))).cast("bigint").alias("n_dup_lines"),
        "n_repeat_words",
    )


def gram_buckets(wh: Column, buckets: int) -> Column:
    """Buckets of a text's unigrams and bigrams."""
    one = F.transform(wh, lambda h: F.pmod(h, F.lit(buckets)).cast("int"))
    two = F.transform(F.slice(wh, 2, F.greatest(F.size(wh) - 1, F.lit(0))), lambda h, i: F.pmod(F.xxhash64(_at(wh, i), h), F.lit(buckets)).cast("int"))
    return F.concat(one, two)


def gram_counts(docs: DataFrame, id_col: str, text_col: str, buckets: int, trusted: DataFrame | None = None) -> list[float]:
    """How often each bucket occurs in the documents, or in the trusted ones, plus one; on the driver one number a bucket."""
    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(text_col, F.lit("")).alias("text"))
    if trusted is not None:
        rows = rows.join(trusted.withColumnRenamed(id_col, "_id").hint("merge"), "_id", "left_semi")  # at any size the texts are shuffled once
    grams = rows.select(F.transform(words_of(F.col("text")), lambda w: F.xxhash64(w)).alias("wh")).select(F.explode(gram_buckets(F.col("wh"), buckets)).alias("b"))
    out = [1.0] * buckets
    for r in grams.groupBy("b").count().collect():
        out[r["b"]] += r["count"]
    return out


def log_ratios(docs: DataFrame, trusted: DataFrame, id_col: str, text_col: str, buckets: int) -> list[float]:
    """log p(bucket | trusted) - log p(bucket | corpus); add-one smoothing."""
    good = gram_counts(docs, id_col, text_col, buckets, trusted)
    n_good = sum(good)
    if n_good == buckets:
        return [0.0] * buckets
    raw = gram_counts(docs, id_col, text_col, buckets)
    n_raw = sum(raw)
    return [math.log(g / n_good) - math.log(r / n_raw) for g, r in zip(good, raw)]


def low_percentile(rows: DataFrame, col: str, share: float) -> float | None:
    """The exact percentile, between its two neighbours as ``percentile`` has it: only the lowest ``share`` of the rows is
    ordered."""
    n = rows.count()
    if not n:
        return None
    at = share * (n - 1)
    low = rows.select(col).orderBy(col).limit(math.ceil(at) + 1)
    two = [r[0] for r in low.orderBy(F.desc(col)).limit(2 if at > math.floor(at) else 1).collect()]
    return two[-1] + (two[0] - two[-1]) * (at - math.floor(at))


def quality_frame(docs: DataFrame, labels: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", buckets: int = BUCKETS, keep_share: float = KEEP_SHARE) -> DataFrame:
    """id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, score, kept."""
    spark = docs.sparkSession
    if labels is None:
        labels = spark.createDataFrame([], f"{id_col} {docs.schema[id_col].dataType.simpleString()}, {label_col} int")
    good = labels.where(F.col(label_col) == 1).select(id_col).where(F.col(id_col).isNotNull())
    good = stored(good.distinct(), "trusted")
    ratio = log_ratios(docs, good, id_col, text_col, buckets)
    model = F.expr("cast(split('" + ",".join(f"{x:.6g}" for x in ratio) + "', ',') as array<double>)")
    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(text_col, F.lit("")).alias("text"))
    out = with_counts(rows).withColumn("gb", gram_buckets(F.col("wh"), buckets))
    total = F.aggregate("gb", F.lit(0.0), lambda a, b: a + F.get(model, b))
    out = out.withColumn("score", F.round(F.when(F.size("gb") > 0, total / F.size("gb")).otherwise(0.0), 9))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    out = stored(out.select("_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), "score"), "scored")
    known = out.where(~F.col("base_failed")).join(good.withColumnRenamed(id_col, "_id"), "_id", "left_semi")
    cut = low_percentile(known, "score", keep_share)
    low = -math.inf if cut is None else cut
    return out.select(F.col("_id").alias(id_col), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "score", (~F.col("base_failed") & (F.col("score") >= F.lit(float(low)))).alias("kept"))
