"""Toxicity by two class-conditional Kneser-Ney models.

Words (lower case) are spelt out between marks; each letter is predicted from the ``ORDER - 1`` before
it. The highest order has counts of its own for the toxic and for the ordinary class, discounted
towards a model that both share: counts of the highest order over every document, and below these
Kneser-Ney continuation counts (how many different letters stand before a string). A spelling that a
class has seldom or never seen falls back to what the corpus knows, which is the same for both and
cancels out. A text's score compares the two
log-likelihoods per letter and is put on 0..1 by a logistic curve fitted to labelled rows.

Words are counted before they are spelt out, so letter windows are made once a distinct word, and a scoring
task rates each distinct word once.

Counts live in hashed tables of ``2**BITS`` cells, so the model has a fixed size. Class counts come
from at most ``TRAIN_ROWS`` labelled rows a class (smallest hashed ids; a documented bound), shared
counts from all documents. The fit uses at most ``FIT_ROWS`` labelled rows that neither the
class counts nor the held-out fifth contain.

A null or empty text scores as one of likelihood ratio one. Without labels, or with one class only,
every score is 0. Repeated rows keep a row each; an empty table gives an empty one; no other column
is read.
"""

from __future__ import annotations

import uuid
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.llm.shared import Cache, give_back, release, stored, texts as bounded, unused

ORDER = 5
BITS = 20
DISCOUNT = 0.75
TRAIN_ROWS = 20_000
FIT_ROWS = 20_000
FOLDS = 5
ENTRY = 160  # bytes of a cached word besides its letters
TALLY = 250_000  # distinct words that a counting task holds before it hands them on
START, STOP = 1, 2


def fold(key: Column) -> Column:
    """crc32 of the id as text, modulo the number of folds; 0 is held out."""
    return F.pmod(F.crc32(key.cast("string")), F.lit(FOLDS))


# ---- letter windows


def windows(words: list[str], order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """(code points of every letter's window, one row a letter or end mark; letters a word)."""
    pad, stop = chr(START) * (order - 1), chr(STOP)
    flat = np.frombuffer("".join([pad + w + stop for w in words]).encode("utf-32-le"), dtype=np.uint32)
    lens = np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1
    if not len(words):
        return np.zeros((0, order), dtype=np.uint32), lens
    view = np.lib.stride_tricks.sliding_window_view(flat, order)
    begin = np.cumsum(lens + order - 1) - (lens + order - 1)
    at = np.repeat(begin - (np.cumsum(lens) - lens), lens) + np.arange(lens.sum())
    return view[at], lens


def cells(codes: np.ndarray, salt: int, bits: int = BITS) -> np.ndarray:
    """Table cell of each row of code points; rows of other lengths or salts get other hashes."""
    h = np.full(len(codes), 0x9E3779B97F4A7C15 * (2 * salt + 1) & 0xFFFFFFFFFFFFFFFF, dtype=np.uint64)
    for k in range(codes.shape[1]):
        h = (h ^ codes[:, k].astype(np.uint64)) * np.uint64(0xD6E8FEB86659FD93)
        h ^= h >> np.uint64(32)
    return (h >> np.uint64(64 - bits)).astype(np.int64)


# tables: name -> number of columns. top: gram (toxic, ordinary, all); ctx: its context (sums, then
# different letters after it); low: continuation counts; lctx: contexts of these (sum, different)
TABLES = {"top": 3, "ctx": 6, "low": 1, "lctx": 2}
_MODELS: dict[str, "Model"] = {}


class Model:
    def __init__(self, tables: dict[str, np.ndarray], order: int, bits: int):
        self.t, self.order, self.bits = tables, order, bits
        self.cache = Cache(ENTRY)
        self.sent = None

    def share(self, spark) -> tuple[str, object]:
        """(name, broadcast): the tables go out once, compressed, whoever scores with the model."""
        if self.sent is None:
            packed = {t: zlib.compress(v.tobytes(), 1) for t, v in self.t.items()}
            self.sent = uuid.uuid4().hex, spark.sparkContext.broadcast((packed, self.order, self.bits))
        return self.sent

    @classmethod
    def received(cls, name: str, sent) -> "Model":
        """The worker's copy, with its cache of words; one model a worker."""
        if name not in _MODELS:
            packed, order, bits = sent.value
            _MODELS.clear()
            _MODELS[name] = cls({t: np.frombuffer(zlib.decompress(v), dtype=np.float32).reshape(-1, TABLES[t]) for t, v in packed.items()}, order, bits)
        return _MODELS[name]

    def ratios(self, words: list[str]) -> np.ndarray:
        """log P(word | toxic) - log P(word | ordinary)."""
        codes, lens = windows(words, self.order)
        if not len(words):
            return np.zeros(0)
        t, d, bits = self.t, DISCOUNT, self.bits
        p = np.full(len(codes), 1.0 / 0x110000)
        for n in range(1, self.order):
            own = t["low"][cells(codes[:, self.order - n :], n, bits), 0]
            ctx = t["lctx"][cells(codes[:, self.order - n : -1], n, bits)]
            total = np.maximum(ctx[:, 0], 1.0)
            p = np.where(ctx[:, 0] > 0, np.maximum(own - d, 0) / total + d * ctx[:, 1] / total * p, p)
        own = t["top"][cells(codes, 0, bits)]
        ctx = t["ctx"][cells(codes[:, :-1], 0, bits)]
        logs = []
        for c in (2, 0, 1):
            total = np.maximum(ctx[:, c], 1.0)
            q = np.where(ctx[:, c] > 0, np.maximum(own[:, c] - d, 0) / total + d * ctx[:, 3 + c] / total * p, p)
            if c == 2:
                p = q  # shared by both classes
            else:
                logs.append(np.log(q))
        return np.add.reduceat(logs[0] - logs[1], np.cumsum(lens) - lens)

    def look_up(self, words: set[str]) -> Cache:
        missing = self.cache.lacking(words)
        for at in range(0, len(missing), 20_000):
            some = missing[at : at + 20_000]
            self.cache.update(zip(some, self.ratios(some).tolist()))
        return self.cache


def groups(texts: list[str], most: int = 1_000_000):
    at, size = 0, 0
    for k, t in enumerate(texts):
        if size and size + len(t) > most:
            yield at, k
            at, size = k, 0
        size += len(t)
    if at < len(texts):
        yield at, len(texts)


def count_words(rows: DataFrame) -> DataFrame:
    """rows (text, cls: 1 toxic, 0 ordinary, null neither) -> word, tox, ord, every: counts by class and over all rows."""
    names = ["word", "tox", "ord", "every"]

    def run(batches):
        every, by_class = Counter(), (Counter(), Counter())

        def handed_on():
            cols = [pa.array([c[w] for w in every], pa.int64()) for c in (by_class[1], by_class[0])]
            return pa.RecordBatch.from_arrays([pa.array(list(every), pa.string()), *cols, pa.array(list(every.values()), pa.int64())], names)

        for b in batches:
            for t, c in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                if not t:
                    continue
                words = t.lower().split()
                every.update(words)
                if c is not None:
                    by_class[c].update(words)
                if len(every) > TALLY:
                    yield handed_on()
                    for x in (every, *by_class):
                        x.clear()
        if every:
            yield handed_on()
        every = by_class = None
        give_back()

    got = bounded(rows).select("text", "cls").mapInArrow(run, "word string, tox long, ord long, every long")
    return got.groupBy("word").agg(*[F.sum(c).alias(c) for c in names[1:]])


def distinct_rows(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the distinct rows of code points, which one each row is). Three code points fill a sortable word."""
    cols = codes.astype(np.uint64)
    packed = [np.zeros(len(codes), dtype=np.uint64) for _ in range(-(-codes.shape[1] // 3))]
    for k in range(codes.shape[1]):
        packed[k // 3] = packed[k // 3] << np.uint64(21) | cols[:, k]
    order = np.lexsort(packed)
    new = np.ones(len(order), dtype=bool)
    new[1:] = np.any([x[order[1:]] != x[order[:-1]] for x in packed], axis=0)
    which = np.empty(len(order), dtype=np.int64)
    which[order] = np.cumsum(new) - 1
    return codes[order[new]], which


def spelt_out(words: DataFrame, order: int = ORDER) -> DataFrame:
    """words (word, tox, ord, every) -> gram and its counts."""

    def run(batches):
        for b in batches:
            words, n = b.column(0).to_pylist(), np.stack([c.to_numpy() for c in b.columns[1:]], axis=1)
            for lo, hi in groups(words, 400_000):
                codes, lens = windows(words[lo:hi], order)
                kinds, which = distinct_rows(codes)
                weight = np.repeat(n[lo:hi], lens, axis=0)
                sums = [pa.array(np.bincount(which, weight[:, c], len(kinds)).astype(np.int64)) for c in range(3)]
                text = np.ascontiguousarray(kinds).tobytes().decode("utf-32-le")
                yield pa.RecordBatch.from_arrays([pa.array([text[i : i + order] for i in range(0, len(text), order)]), *sums], ["gram", "tox", "ord", "every"])
        give_back()

    got = words.mapInArrow(run, "gram string, tox long, ord long, every long")
    return got.groupBy("gram").agg(*[F.sum(c).alias(c) for c in ("tox", "ord", "every")])


def hashed(grams: DataFrame, values: list[str], n: int, salt: int, bits: int) -> DataFrame:
    """grams (gram, values) summed by table cell: at most 2**bits rows of cell and values."""

    def run(batches):
        for b in batches:
            text = b.column(0).to_pylist()
            if not text:
                continue
            codes = np.frombuffer("".join(text).encode("utf-32-le"), dtype=np.uint32).reshape(len(text), n)
            yield pa.RecordBatch.from_arrays([pa.array(cells(codes, salt, bits), pa.int32()), *b.columns[1:]], ["cell", *values])

    kind = ", ".join(f"{v} double" for v in values)
    rows = grams.select("gram", *[F.col(v).cast("double") for v in values]).mapInArrow(run, f"cell int, {kind}")
    return rows.groupBy("cell").agg(*[F.sum(v).cast("float").alias(v) for v in values])


def fit_counts(rows: DataFrame, order: int = ORDER, bits: int = BITS) -> Model:
    """The model of rows (text, cls)."""
    grams = stored(spelt_out(count_words(rows), order), "grams")
    release(rows.sparkSession)
    cols = ["tox", "ord", "every"]
    tables = {t: np.zeros((1 << bits, k), dtype=np.float32) for t, k in TABLES.items()}

    def add(table: str, cells_of: DataFrame) -> None:  # at most 2**bits rows, column by column
        got = cells_of.toArrow()
        at = got.column("cell").to_numpy()
        for k, c in enumerate(got.column_names[1:]):
            np.add.at(tables[table][:, k], at, got.column(c).to_numpy())

    add("top", hashed(grams, cols, order, 0, bits))
    ctx = grams.groupBy(F.expr(f"substring(gram, 1, {order - 1})").alias("gram"))
    ctx = ctx.agg(*[F.sum(c).alias(f"s_{c}") for c in cols], *[F.count_if(F.col(c) > 0).alias(f"u_{c}") for c in cols])
    add("ctx", hashed(ctx, [f"s_{c}" for c in cols] + [f"u_{c}" for c in cols], order - 1, 0, bits))
    wide = grams.select("gram")
    for n in range(order - 1, 0, -1):
        low = stored(wide.groupBy(F.expr("substring(gram, 2)").alias("gram")).agg(F.count("*").alias("n")), f"low{n}")
        add("low", hashed(low, ["n"], n, n, bits))
        lctx = low.groupBy(F.expr(f"substring(gram, 1, {n - 1})").alias("gram")).agg(F.sum("n").alias("s"), F.count("*").alias("u"))
        add("lctx", hashed(lctx, ["s", "u"], n - 1, n, bits))
        wide = low.select("gram")
    release(rows.sparkSession)
    return Model(tables, order, bits)


def log_ratio_frame(docs: DataFrame, model: Model, text_col: str = "text", keep: list[str] | None = None, out_col: str = "_ratio") -> DataFrame:
    """The kept columns (default: all) and ``out_col``, the log-likelihood ratio per letter."""
    keep = docs.columns if keep is None else keep
    place = keep.index(text_col) if text_col in keep else len(keep)  # the text travels once
    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)
    name, sent = model.share(docs.sparkSession)

    def run(batches):
        m = Model.received(name, sent)
        try:
            for b in batches:
                texts = [t or "" for t in b.column(place).to_pylist()]
                out = np.zeros(len(texts))
                for lo, hi in groups(texts):
                    split = [t.lower().split() for t in texts[lo:hi]]
                    kinds = set().union(*split)
                    rated = m.look_up(kinds)
                    look = {w: rated[w] for w in kinds}  # small, so that it stays close
                    for k, ws in enumerate(split, lo):
                        if ws:
                            out[k] = sum([look[w] for w in ws]) / (sum(map(len, ws)) + len(ws))
                yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(out)], [*keep, out_col])
        finally:
            m.cache.clear()
            m = None
            _MODELS.clear()
            give_back()

    sent_cols = [F.col(f"`{c}`") for c in keep] + ([F.col(text_col).alias(unused("_text", keep))] if place == len(keep) else [])
    return bounded(docs).select(*sent_cols).mapInArrow(run, f"{kinds}, {out_col} double")


def fit_scale(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """(slope, offset) of the score 1 / (1 + exp(-(slope x + offset))): it crosses one half where F1
    over the given rows is best, and its slope is two over the spread of class 0."""
    if not len(x) or y.min() == y.max():
        return 0.0, -40.0
    order = np.argsort(-x, kind="stable")
    v, hit = x[order], np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(x) + 1) + y.sum())
    f1[:-1][v[:-1] == v[1:]] = 0  # equal ratios stay together
    k = int(np.argmax(f1))
    cut = (v[k] + v[k + 1]) / 2 if k + 1 < len(v) else v[k]
    slope = 2.0 / (float(x[y == 0].std()) or 1.0)
    return slope, -slope * float(cut)


def scored(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train_rows: int = TRAIN_ROWS, fit_rows: int = FIT_ROWS, keep: list[str] | None = None) -> tuple[DataFrame, str, str]:
    """The kept columns of docs (default: all) with the ratio and the score, and the names of these two."""
    known = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("_cls")).distinct()
    by_hash = [F.xxhash64("_id"), F.col("_id")]
    train = [known.where((F.col("_cls") == c) & fold(F.col("_id")).between(1, FOLDS - 2)).orderBy(*by_hash).limit(train_rows) for c in (0, 1)]
    train = stored(train[0].unionByName(train[1]), "train")  # at most 2 * train_rows rows
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("text"))
    model = fit_counts(rows.join(F.broadcast(train), "_id", "left").select("text", F.col("_cls").alias("cls")))
    rest = stored(known.where(fold(F.col("_id")) == FOLDS - 1).orderBy(*by_hash).limit(fit_rows), "fit")
    fit = log_ratio_frame(rows.join(F.broadcast(rest), "_id"), model, "text", ["_cls"]).toArrow()  # bounded by fit_rows
    slope, offset = fit_scale(fit.column("_ratio").to_numpy(), fit.column("_cls").to_numpy().astype(float))
    ratio, score = (unused(c, docs.columns) for c in ("_ratio", "_score"))
    z = F.lit(slope) * F.col(ratio) + F.lit(offset)
    out = log_ratio_frame(docs, model, text_col, keep, ratio)
    return out.withColumn(score, F.lit(1.0) / (F.lit(1.0) + F.exp(-F.greatest(F.least(z, F.lit(40.0)), F.lit(-40.0))))), ratio, score


def toxicity_frame(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train_rows: int = TRAIN_ROWS, fit_rows: int = FIT_ROWS) -> DataFrame:
    """id, held_out, ratio, score, predicted."""
    out, ratio, score = scored(docs, labels, id_col, text_col, label_col, train_rows, fit_rows, [id_col])
    return out.select(id_col, (F.coalesce(fold(F.col(id_col)), F.lit(0)) == 0).alias("held_out"), F.col(ratio).alias("ratio"), F.col(score).alias("score"), (F.col(score) >= 0.5).cast("int").alias("predicted"))


def ordinary_only(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> DataFrame:
    """docs without the rows predicted toxic."""
    out, _, score = scored(docs, labels, id_col, text_col, label_col)
    return out.where(F.col(score) < 0.5).select(*docs.columns)
