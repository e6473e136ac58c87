"""A corpus cleaned in five stages, each on all that the one before kept.

Every stage takes (spark, docs, sf_dir). The first four return the columns of ``documents``; the last
returns each document's token ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from frsketch.llm.bpe import encode_frame
from frsketch.llm.decontaminate import find_leaks
from frsketch.llm.near_copies import copy_classes
from frsketch.llm.queries import table, tokenizer_file
from frsketch.llm.shared import release, stored
from frsketch.llm.suffix_dedup import without_repeats
from frsketch.llm.toxicity import ordinary_only


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents predicted toxic go."""
    release(spark)
    return ordinary_only(docs, table(spark, sf_dir, "labels"))


def simhash(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays, the one of the smallest id; a row without an id
    stays only where its class has none with one, and of a class's rows that repeat an id one stays. Near copies
    have Jaccard 0.8 or more of their sets of five-word shingles and are found without loss: SimHash links
    verified by exact Jaccard first, then prefixes, since fingerprints of such pairs differ in up to 14 of 64
    bits at sf0.1."""
    release(spark)
    rows = stored(docs.withColumn("_row", F.monotonically_increasing_id()), "rows")
    label = copy_classes(rows, "_row").join(rows.select("_row", "doc_id"), "_row")
    keep = label.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "_row")).alias("least")).select("least._row")
    return rows.join(keep, "_row", "left_semi").select(*docs.columns)


def suffix_array(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated strings are cut from the texts; where a cut parts a character, its rest goes too."""
    release(spark)
    others = [c for c in docs.columns if c not in ("doc_id", "text", "n_chars")]
    out = without_repeats(docs, carry=others)

    def as_text(batches):
        import pyarrow as pa

        for b in batches:
            kept = [x.decode("utf-8", "ignore") for x in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(kept, pa.string()), *b.columns[1:]], ["text", *b.schema.names[1:]])

    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in ["doc_id", *others])
    out = out.select("kept", "doc_id", *others).mapInArrow(as_text, f"text string, {kinds}")
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    release(spark)
    leaks = find_leaks(docs, table(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.join(leaks, "doc_id", "left_anti").select(*docs.columns)


def byte_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of what is left, with the digest of what they decode to."""
    release(spark)
    out = encode_frame(docs, tokenizer_file("byte_bpe_50k.tiktoken"))
    return out.select("doc_id", "n_tokens", "ids", "ids_sha256", "decoded_sha256")


STAGES = [("toxicity", toxicity), ("simhash", simhash), ("suffix_array", suffix_array), ("decontamination", decontamination), ("byte_bpe", byte_bpe)]

#: SQL cannot express the stages; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        docs = out if k == len(STAGES) - 1 else stored(out, f"stage-{name}")
    return docs
