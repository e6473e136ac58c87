"""Token-id files: texts encoded by a library tokenizer, ids in context-mixed segments.

Rows are range-partitioned and sorted by id, so files and segments follow ascending ids. A stored row
is one segment of up to ``SEGMENT`` ids: the ids and lengths of its documents and the coded payload
(``mixing_coder``: independent, checksummed blocks). A lost task rewrites its own file only. Reading
decodes segments independently; a document's start is the sum of all partitions and segments before
it, of which the driver sees one number a partition.

Null texts are empty (the end id alone). Repeated ids stay apart and are ordered by their text; rows
without an id come first. An empty table gives empty files. No other columns are read.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from frsketch.llm.mixing_coder import decode_segment, encode_segment
from frsketch.llm.shared import give_back, texts as bounded
from frsketch.llm.slice_ids import SliceIds
from frsketch.llm.token_counts import library

SEGMENT = 4_000_000


def write_tokens(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", segment: int = SEGMENT) -> None:
    """Writes the ids of every text, each followed by ``end_id``, to a folder of segment files."""
    kind = docs.schema[id_col].dataType.simpleString()
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = bounded(docs).select(F.col(id_col).alias("id"), F.coalesce(text_col, F.lit("")).alias("text"))
    rows = rows.repartitionByRange(parts, "id").sortWithinPartitions("id", "text").withColumn("part", F.spark_partition_id())

    def run(batches):
        known = SliceIds(library(tokenizer))
        end = np.array([end_id], dtype=np.uint32)
        keys: list = []
        sizes: list[int] = []
        flat: list[np.ndarray] = []
        total, seg, part = 0, 0, None

        def row():
            arrays = [pa.array([part], pa.int32()), pa.array([seg], pa.int32()), pa.array([total], pa.int64())]
            arrays += [pa.array([keys], pa.list_(id_type)), pa.array([sizes], pa.list_(pa.int32()))]
            return pa.RecordBatch.from_arrays([*arrays, pa.array([encode_segment(np.concatenate(flat))], pa.binary())], ["part", "seg", "n_ids", "ids", "sizes", "payload"])

        try:
            for b in batches:
                id_type = b.column(0).type
                ids, places = b.column(0).to_pylist(), b.column(2).to_pylist()
                found, counts = known.of_texts(b.column(1))
                upto = np.cumsum(counts).tolist()
                for k, (n, to) in enumerate(zip(counts.tolist(), upto)):
                    if total and total + n + 1 > segment:
                        yield row()
                        keys, sizes, flat, total, seg = [], [], [], 0, seg + 1
                    part = places[k]
                    keys.append(ids[k])
                    sizes.append(n + 1)
                    flat += [found[to - n : to], end]
                    total += n + 1
            if keys:
                yield row()
        finally:
            known.clear()
            give_back()

    schema = f"part int, seg int, n_ids long, ids array<{kind}>, sizes array<int>, payload binary"
    rows.mapInArrow(run, schema).write.parquet(path)


def read_tokens(spark: SparkSession, path: str, id_col: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """id, start, n_tokens, ids_crc32 and, when asked for, the token ids."""
    stored = spark.read.parquet(path)
    kind = stored.schema["ids"].dataType.elementType.simpleString()
    totals = stored.groupBy("part").agg(F.sum("n_ids").alias("n")).orderBy("part").collect()  # one a partition
    before, at = [], 0
    for r in totals:
        before.append((r["part"], at))
        at += r["n"]
    base = F.broadcast(spark.createDataFrame(before, "part int, before long"))
    own = F.sum("n_ids").over(Window.partitionBy("part").orderBy("seg")) - F.col("n_ids")
    begin = stored.select("part", "seg", "n_ids").withColumn("own", own).join(base, "part").select("part", "seg", (F.col("before") + F.col("own")).alias("begin"))
    schema = f"part int, seg int, {id_col} {kind}, pos long, n_tokens long, ids_crc32 long" + (", token_ids array<int>" if with_ids else "")

    def run(batches):
        for b in batches:
            for part, seg, keys, sizes, payload in zip(*[c.to_pylist() for c in b.columns]):
                ids = decode_segment(payload).astype("<u4")
                ends = np.cumsum(sizes)
                starts = ends - sizes
                crc = [zlib.crc32(ids[x:y].tobytes()) for x, y in zip(starts.tolist(), ends.tolist())]
                n = len(keys)
                arrays = [pa.array([part] * n, pa.int32()), pa.array([seg] * n, pa.int32()), pa.array(keys, b.column(2).type.value_type), pa.array(starts), pa.array(sizes, pa.int64()), pa.array(crc, pa.int64())]
                if with_ids:
                    arrays.append(pa.ListArray.from_arrays(pa.array(np.r_[0, ends], pa.int32()), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(arrays, ["part", "seg", id_col, "pos", "n_tokens", "ids_crc32", "token_ids"][: len(arrays)])

    got = stored.select("part", "seg", "ids", "sizes", "payload").mapInArrow(run, schema)
    out = got.join(begin, ["part", "seg"]).withColumn("start", F.col("begin") + F.col("pos"))
    return out.select(id_col, "start", "n_tokens", "ids_crc32", *(["token_ids"] if with_ids else []))
