"""Removal of repeated strings of ``LENGTH`` bytes across all texts, by suffix arrays over shards.

A window is ``LENGTH`` consecutive bytes of one text. A window that also starts earlier (smaller id, or
earlier in the same text) is repeated, and every byte of a repeated window goes.

Sharding. Each window belongs to the leftmost minimum, under a fixed hash, of its ``GRAM``-byte strings
(its anchor). Equal windows have equal anchors, so windows are only ever compared with those of the
same anchor string, and consecutive windows with one anchor travel as one row (about 1 row for 35
bytes, four numbers each). Three reductions come before any text moves:

1. anchor strings that occur once are dropped in the map task, by a filter of fixed size
   (``FILTER_BITS``; where more strings repeat than it can tell apart, it only lets more rows pass);
2. rows whose whole context (anchor offset and all bytes of their windows) is equal are one class; all
   but its first are repeated as they stand;
3. the first rows of anchor strings with several classes are cut into runs of up to ``RUN`` windows,
   keyed by the bytes that all windows of the run share, its core. Equal runs are one class, as before.

What is left are runs that share their core and differ at an end. Each is spelt as the bytes before the
core, one symbol for the core, and the bytes after it, so a window is always ``RUN`` symbols. The runs of
a shard are laid end to end and sorted by the suffix array of ``lyndon``; neighbours of equal first
``RUN`` symbols form a group whose first window stays. Cores with more than ``HOT`` different runs (an
end of a passage that very many texts share) are cut into single windows and grouped as such, so no
shard grows with the data. All steps combine equal rows before their shuffle.

Null texts are empty. Ids should be unique: rows that share an id count as one text at the same place
and get the same spans. Rows without an id keep their text and remove nothing. An empty table gives an
empty result; no other columns are read; texts below ``LENGTH`` bytes keep everything.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm.lyndon import suffix_array
from frsketch.llm.shared import drop_stored, give_back, release, stored, texts as bounded

LENGTH = 100
GRAM = 24
RUN = 16
HOT = 256
FILTER_BITS = 27
PLACE_BITS = 28
PIECE = 1 << 18  # bytes searched together
SORTED = 50_000  # symbols a suffix array


def hashes(buf: np.ndarray, gram: int) -> np.ndarray:
    """A 64-bit hash of every ``gram``-byte string, by doubling."""
    base = np.uint64(0x9E3779B97F4A7C15)
    parts, powers, m = {1: buf.astype(np.uint64) + np.uint64(1)}, {1: base}, 1
    with np.errstate(over="ignore"):
        while 2 * m <= gram:
            x = parts[m]
            parts[2 * m], powers[2 * m] = x[:-m] * powers[m] + x[m:], powers[m] * powers[m]
            m *= 2
        out, size = parts[m], m
        while size < gram:
            m //= 2
            if gram - size >= m:
                tail = parts[m][size:]
                out = out[: len(tail)] * powers[m] + tail[: len(out)]
                size += m
        out = (out ^ (out >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        return out ^ (out >> np.uint64(29))


def anchor_runs(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, length: int = LENGTH, gram: int = GRAM):
    """(anchor, first window, windows, hash of the anchor string) of every run; texts are
    buf[starts[i]:ends[i]], in order and end to end."""
    none = np.zeros(0, dtype=np.int64)
    fits = ends - starts >= length
    if not fits.any():
        return none, none, none, none.astype(np.uint64)
    h = hashes(buf, gram)
    low = np.uint64((1 << PLACE_BITS) - 1)
    key = (h & ~low) | np.arange(len(h), dtype=np.uint64)
    width, m = length - gram + 1, 1
    while 2 * m <= width:
        key = np.minimum(key[:-m], key[m:])
        m *= 2
    if width > m:
        key = np.minimum(key[: len(key) - (width - m)], key[width - m :])
    anchor = (key & low).astype(np.int64)
    change = np.zeros(len(anchor) + 1, dtype=np.int32)
    np.add.at(change, starts[fits], 1)
    np.add.at(change, ends[fits] - length + 1, -1)
    at = np.flatnonzero(np.cumsum(change[:-1]) > 0)
    a = anchor[at]
    cut = np.flatnonzero(np.r_[True, (np.diff(a) != 0) | (np.diff(at) != 1)])
    # two texts that meet without a gap in window starts cannot: LENGTH - 1 starts lie between them
    return a[cut], at[cut], np.diff(np.r_[cut, len(at)]), h[a[cut]]


def pieces(texts: list[str | None], most: int = PIECE):
    """Groups of (row, offset in the text, bytes), long texts in overlapping pieces."""
    group: list[tuple[int, int, bytes]] = []
    size = 0
    for k, t in enumerate(texts):
        raw = (t or "").encode()
        for off in range(0, max(1, len(raw) - LENGTH + 1), most):
            part = raw if len(raw) <= most else raw[off : off + most + LENGTH - 1]
            if size and size + len(part) > most:
                yield group
                group, size = [], 0
            group.append((k, off, part))
            size += len(part)
    if group:
        yield group


def filter_cells(h: np.ndarray) -> list[np.ndarray]:
    """Two bit positions of every hash in the filter."""
    top = np.uint64(64 - FILTER_BITS)
    with np.errstate(over="ignore"):
        return [((h * np.uint64(c)) >> top).astype(np.int64) for c in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)]


def anchor_frame(docs: DataFrame, id_kind: str, wanted=None) -> DataFrame:
    """k (anchor hash) of every run of windows of docs (id, text). With ``wanted``, a broadcast filter, of
    the runs that pass it: k, c (hash of the context), id and at (first window, anchor offset and
    number of windows in one number, see ``unpacked``)."""

    def run(batches):
        bits = None if wanted is None else np.frombuffer(wanted.value, dtype=np.uint8)
        for b in batches:
            keys, texts = b.column(0), b.column(1).to_pylist()
            for group in pieces(texts):
                size = np.fromiter((len(p) for _, _, p in group), np.int64, len(group))
                ends = np.cumsum(size)
                buf = b"".join([p for _, _, p in group])
                a, lo, n, h = anchor_runs(np.frombuffer(buf, dtype=np.uint8), ends - size, ends)
                if bits is not None and len(a):
                    x, y = filter_cells(h)
                    keep = (bits[x >> 3] >> (x & 7).astype(np.uint8) & bits[y >> 3] >> (y & 7).astype(np.uint8) & 1) == 1
                    a, lo, n, h = a[keep], lo[keep], n[keep], h[keep]
                if not len(a):
                    continue
                k = pa.array(h.view(np.int64))
                if bits is None:
                    yield pa.RecordBatch.from_arrays([k], ["k"])
                    continue
                digest = xxhash.xxh64_intdigest
                c = np.array([digest(buf[x : x + y + LENGTH - 1], z) for x, y, z in zip(lo.tolist(), n.tolist(), (a - lo).tolist())], dtype=np.uint64)
                text = np.searchsorted(ends, lo, side="right")
                shift = np.fromiter((o for _, o, _ in group), np.int64, len(group))[text] - (ends - size)[text]
                row = np.fromiter((r for r, _, _ in group), np.int64, len(group))[text]
                at = (lo + shift) << 14 | (a - lo) << 7 | n
                yield pa.RecordBatch.from_arrays([k, pa.array(c.view(np.int64)), keys.take(pa.array(row)), pa.array(at)], ["k", "c", "id", "at"])
        give_back()

    return docs.select("id", "text").mapInArrow(run, f"k long, c long, id {id_kind}, at long" if wanted is not None else "k long")


def unpacked(df: DataFrame) -> DataFrame:
    """(id, a, lo, n) of ``at``: anchor, first window, windows."""
    lo = F.shiftright("at", 14)
    return df.select("id", (lo + F.shiftright("at", 7).bitwiseAND(F.lit(127))).alias("a"), lo.alias("lo"), F.col("at").bitwiseAND(F.lit(127)).cast("int").alias("n"))


def repeat_filter(ks: DataFrame) -> bytes:
    """The filter of the anchor hashes that occur more than once; 2**FILTER_BITS bits whatever the input."""
    def run(batches):
        for b in batches:
            h = np.asarray(b.column(0)).view(np.uint64)
            cells = np.concatenate(filter_cells(h))
            word, bit = cells >> 6, cells & 63
            kind, first = np.unique(word, return_inverse=True)
            got = np.zeros(len(kind), dtype=np.uint64)
            np.bitwise_or.at(got, first, np.uint64(1) << bit.astype(np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array(got.view(np.int64))], ["w", "bits"])

    twice = ks.groupBy("k").agg(F.count("*").alias("m")).where("m > 1").select("k")
    words = twice.mapInArrow(run, "w long, bits long").groupBy("w").agg(F.bit_or("bits").alias("bits")).toArrow()
    out = np.zeros(1 << (FILTER_BITS - 6), dtype=np.int64)
    if words.num_rows:
        out[words.column("w").to_numpy()] = words.column("bits").to_numpy()
    return out.tobytes()


def others(rows: DataFrame, keys: list[str], place: str, also: list[str]) -> DataFrame:
    """(id, *also) of the rows that are not the first, by id and place, of those with equal keys. The
    firsts are stored, so both sides of the join come from exchanges and a hot key can be split."""
    first = rows.groupBy(*keys).agg(F.min(F.struct("id", place)).alias("f"), F.count("*").alias("m")).where("m > 1").select(*keys, F.col("f.id").alias("id1"), F.col(f"f.{place}").alias("place1"))
    got = rows.join(stored(first, "least"), keys)
    return got.where((F.col("id") != F.col("id1")) | (F.col(place) != F.col("place1"))).select("id", *also)


def cut_frame(docs: DataFrame, wanted: DataFrame, id_kind: str) -> DataFrame:
    """The wanted runs (id, a, lo, n), cut at multiples of ``RUN`` from the anchor: k1, k2 (hash of the
    core), before, after (the bytes on both sides of it), id, lo, n."""
    lists = wanted.groupBy("id").agg(F.collect_list(F.struct("a", "lo", "n")).alias("runs"))  # bounded by the text

    def run(batches):
        digest = xxhash.xxh3_128_digest
        for b in batches:
            ids, out = b.column(0), []
            for r, (text, runs) in enumerate(zip(b.column(1).to_pylist(), b.column(2).to_pylist())):
                raw = (text or "").encode()
                for x in runs:
                    a, lo, n = x["a"], x["lo"], x["n"]
                    for g in range((a - lo - n + 1) // RUN, (a - lo) // RUN + 1):
                        last = a - g * RUN
                        end = last - RUN + 1 + LENGTH
                        s0, s1 = max(lo, last - RUN + 1), min(lo + n - 1, last)
                        out.append((digest(raw[last:end], g), raw[s0:last], raw[end : s1 + LENGTH], r, s0, s1 - s0 + 1))
                if len(out) > 50_000:
                    yield rows_of(ids, out)
                    out = []
            if out:
                yield rows_of(ids, out)
        give_back()

    def rows_of(ids, out):
        k, before, after, r, s, n = zip(*out)
        k = np.frombuffer(b"".join(k), dtype="<i8").reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(k[:, 0]), pa.array(k[:, 1]), pa.array(before, pa.binary()), pa.array(after, pa.binary()), ids.take(pa.array(r)), pa.array(s, pa.int64()), pa.array(n, pa.int32())], ["k1", "k2", "before", "after", "id", "lo", "n"])

    schema = f"k1 long, k2 long, before binary, after binary, id {id_kind}, lo long, n int"
    return docs.select("id", "text").join(lists, "id").select("id", "text", "runs").mapInArrow(run, schema)


def repeated_windows(runs: list[tuple[int, bytes, bytes, object, int, int]]) -> list[tuple[int, int]]:
    """(run, window in it) of every window of the runs (core's number, before, after, id, lo, n) that an
    earlier one equals, by the suffix array of all of them."""
    t: list[int] = []
    owner: list[int] = []
    for k, (core, before, after, _, _, n) in enumerate(runs):
        owner += [k] * n + [-1] * (len(before) + len(after) + 2 - n)
        t += [x + 2 for x in before]
        t.append(258 + core)
        t += [x + 2 for x in after]
        t.append(1)
    t.append(0)
    begin, at = [], 0
    for _, before, after, *_ in runs:
        begin.append(at)
        at += len(before) + len(after) + 2
    out: list[tuple[int, int]] = []
    group: list[int] = []
    head: list[int] = []

    def close():
        if len(group) > 1:
            found = [(runs[owner[s]][3], runs[owner[s]][4] + s - begin[owner[s]], s) for s in group]
            least = min(f[:2] for f in found)
            out.extend((owner[s], s - begin[owner[s]]) for i, p, s in found if (i, p) != least)

    for s in suffix_array(t)[1:]:
        if owner[s] < 0:
            continue
        w = t[s : s + RUN]
        if w != head:
            close()
            group, head = [], w
        group.append(s)
    close()
    return out


def sorted_frame(shards: DataFrame, id_kind: str) -> DataFrame:
    """(id, lo, n) of the repeated windows among runs of equal core."""

    def run(batches):
        held: list[tuple] = []
        size, last, core = 0, None, 0
        id_type = None

        def flush():
            got = repeated_windows(held)
            if got:
                yield pa.RecordBatch.from_arrays([pa.array([held[k][3] for k, _ in got], id_type), pa.array([held[k][4] + p for k, p in got], pa.int64()), pa.array([1] * len(got), pa.int32())], ["id", "lo", "n"])

        for b in batches:
            id_type = b.column(4).type
            for k1, k2, *row in zip(*[c.to_pylist() for c in b.columns]):
                if (k1, k2) != last:
                    if size > SORTED:
                        yield from flush()
                        held, size, core = [], 0, 0
                    last, core = (k1, k2), core + 1
                held.append((core, *row))
                size += len(row[0]) + len(row[1]) + 2
        if held:
            yield from flush()

    parts = shards.repartition("k1", "k2").sortWithinPartitions("k1", "k2")
    return parts.select("k1", "k2", "before", "after", "id", "lo", "n").mapInArrow(run, f"id {id_kind}, lo long, n int")


def single_windows(shards: DataFrame) -> DataFrame:
    """(id, lo, n) of the repeated windows of runs under crowded cores, one row a window."""
    each = shards.select("k1", "k2", "before", "after", "id", "lo", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("i"))
    left = F.expr("substring(before, i + 1, length(before))")
    each = each.select("k1", "k2", left.alias("x"), "after", "id", (F.col("lo") + F.col("i")).alias("lo"), F.lit(1).alias("n"))
    each = each.select("k1", "k2", "x", F.expr(f"substring(after, 1, {RUN - 1} - length(x))").alias("y"), "id", "lo", "n")
    return others(each, ["k1", "k2", "x", "y"], "lo", ["lo", "n"])


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lo, n): windows lo .. lo + n - 1 of the text are repeated. Rows may overlap."""
    spark = docs.sparkSession
    kind = docs.schema[id_col].dataType.simpleString()
    rows = bounded(docs).where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    wanted = spark.sparkContext.broadcast(repeat_filter(anchor_frame(rows, kind)))
    release(spark)
    runs = stored(anchor_frame(rows, kind, wanted), "runs")
    found = [unpacked(stored(others(runs, ["k", "c"], "at", ["at"]), "repeats")).select("id", "lo", "n")]
    release(spark)
    classes = stored(runs.groupBy("k", "c").agg(F.min(F.struct("id", "at")).alias("f")).select("k", "f.id", "f.at"), "classes")
    drop_stored(runs)
    release(spark)
    several = classes.groupBy("k").agg(F.count("*").alias("m")).where("m > 1").select("k")
    first = stored(unpacked(classes.join(several, "k", "left_semi")), "firsts")
    drop_stored(classes)
    release(spark)
    cuts = stored(cut_frame(rows, first, kind), "cuts")
    drop_stored(first)
    release(spark)
    spelt = ["k1", "k2", "before", "after"]
    found.append(stored(others(cuts, spelt, "lo", ["lo", "n"]), "repeats"))
    least = cuts.groupBy(*spelt).agg(F.min(F.struct("id", "lo", "n")).alias("f")).select(*spelt, "f.*")
    least = stored(least, "spelt")
    drop_stored(cuts)
    shared = least.groupBy("k1", "k2").agg(F.count("*").alias("different")).where("different > 1")
    shards = stored(least.join(shared, ["k1", "k2"]), "shards")
    drop_stored(least)
    release(spark)
    found.append(stored(sorted_frame(shards.where(F.col("different") <= HOT), kind), "repeats"))
    found.append(stored(single_windows(shards.where(F.col("different") > HOT)), "repeats"))
    drop_stored(shards)
    release(spark)
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out


def without_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep_bytes: bool = True, carry: list[str] | None = None) -> DataFrame:
    """id, n_bytes, n_removed, n_spans, kept_sha256 of every row and, with ``keep_bytes``, spans (begin,
    end) and kept (the bytes left); then the carried columns of docs."""
    carry = carry or []
    kind = docs.schema[id_col].dataType.simpleString()
    spans = repeated_spans(docs, id_col, text_col).groupBy("id").agg(F.collect_list(F.struct("lo", "n")).alias("runs"))  # bounded by the text
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), *[F.col(c).alias(f"_{c}") for c in carry]).join(spans, "id", "left").select("id", "text", "runs", *[f"_{c}" for c in carry])
    schema = f"{id_col} {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", spans array<struct<begin:bigint,end:bigint>>, kept binary" if keep_bytes else "")
    schema += "".join(f", `{c}` {docs.schema[c].dataType.simpleString()}" for c in carry)

    def run(batches):
        for b in batches:
            out = []
            for text, runs in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                raw = (text or "").encode()
                cover: list[list[int]] = []
                for lo, end in sorted((x["lo"], x["lo"] + x["n"] - 1 + LENGTH) for x in runs or []):
                    if cover and lo <= cover[-1][1]:
                        cover[-1][1] = max(cover[-1][1], end)
                    else:
                        cover.append([lo, end])
                gone, at, parts = 0, 0, []
                for lo, end in cover:
                    parts.append(raw[at:lo])
                    at = end
                    gone += end - lo
                kept = b"".join(parts) + raw[at:]
                out.append((len(raw), gone, len(cover), hashlib.sha256(kept).hexdigest(), [{"begin": x, "end": y} for x, y in cover], kept))
            size, gone, n, digest, where, kept = zip(*out) if out else ([],) * 6
            arrays = [b.column(0), pa.array(size, pa.int64()), pa.array(gone, pa.int64()), pa.array(n, pa.int64()), pa.array(digest, pa.string())]
            if keep_bytes:
                arrays += [pa.array(where, pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))), pa.array(kept, pa.binary())]
            names = [id_col, "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"][: len(arrays)]
            yield pa.RecordBatch.from_arrays([*arrays, *b.columns[3:]], [*names, *carry])
        give_back()

    return rows.mapInArrow(run, schema)
