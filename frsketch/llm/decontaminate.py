"""Benchmark decontamination: edit distance by random-walk embedding and bit-sampling LSH.

Texts become sequences of words (lower case, punctuation dropped). A document leaks an item of m words
if some stretch of it is within ``floor((1 - similarity) * m)`` word edits of the item.

1. Windows. An item within e edits of a stretch shares at least ``m - q + 1 - e * q`` word q-grams with
   it, on diagonals (position in the document minus position in the item) that differ by e at most;
   q is chosen so that this is 1 or more. Item-sized windows are taken at the diagonals where that many
   shared q-grams meet, so no leak is lost and other text costs one look-up a word.
2. Embedding. Each window and item is spelt out by a random walk: step j emits the word under the
   cursor and moves on or stays by a random bit of (j, word). Sequences at a small edit distance give
   strings at a small Hamming distance. ``walks`` independent walks are used.
3. LSH. Each table samples positions of one walk; windows that share a key with an item are candidates.
   The number of tables follows from the agreement of edited items with their originals (measured on
   the items by simulation with a fixed seed) and the target recall.
4. Verification. The exact edit distance of the item to the best stretch around the window decides.

Items are broadcast; their total size is checked (``MAX_ITEM_BYTES``). Documents are read once and
nothing is shuffled but the hits. A null or empty text leaks nothing; null or wordless items fit
nothing; repeated rows keep a row each; an empty table on either side gives an empty result; no other
columns are read.
"""

from __future__ import annotations

import math
import random
import unicodedata
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm.shared import give_back, texts as bounded

MAX_ITEM_CHARS = 8_000_000  # of the items searched at once; more are searched in several parts
SIMILARITY = 0.8
RECALL = 0.995
SAMPLED = 3  # positions a key
WALKS = 8
END = 0  # emitted past the end of a sequence


def _punctuation() -> dict[int, str]:
    return {c: " " for c in range(0x3000) if unicodedata.category(chr(c))[0] in "PSZC"}


PUNCTUATION = _punctuation()


def words_of(text: str | None) -> list[str]:
    return (text or "").lower().translate(PUNCTUATION).split()


def edits_of(m: int, similarity: float = SIMILARITY) -> int:
    return int((1 - similarity) * m + 1e-9)


def gram_size(m: int, e: int) -> int:
    """The largest q of 1..3 with m - q + 1 - e * q >= 1."""
    return max([q for q in (1, 2, 3) if m - q + 1 - e * q >= 1], default=1)


def mix(x: np.ndarray, seed: int) -> np.ndarray:
    x = (x.astype(np.uint64) + np.uint64(seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)) * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def embed(rows: np.ndarray, walk: int, steps: int) -> np.ndarray:
    """rows: word ids from 1, END after each sequence's end. Returns the emitted words, ``steps`` a row."""
    n, width = rows.shape
    padded = np.c_[rows, np.zeros((n, 1), dtype=rows.dtype)]
    at, out, every = np.zeros(n, dtype=np.int64), np.empty((n, steps), dtype=rows.dtype), np.arange(n)
    for j in range(steps):
        w = padded[every, np.minimum(at, width)]
        out[:, j] = w
        at += (mix(w, walk * 100_003 + j + 1) >> np.uint64(17) & np.uint64(1)).astype(np.int64)
    return out


def keys_of(emitted: np.ndarray, positions: np.ndarray, table: int) -> np.ndarray:
    h = np.full(len(emitted), table + 1, dtype=np.uint64)
    for p in positions:
        h = mix(h ^ emitted[:, p].astype(np.uint64), int(p) + 7)
    return h


def best_stretch(item: list[int], text: list[int]) -> tuple[int, int]:
    """(least edit distance of the item to any stretch of the text, end of the first such stretch), by
    bit-parallel approximate matching."""
    m = len(item)
    full, top = (1 << m) - 1, 1 << (m - 1)
    where: dict[int, int] = {}
    for k, w in enumerate(item):
        where[w] = where.get(w, 0) | 1 << k
    plus, minus, score = full, 0, m
    best, end = m, 0
    for k, w in enumerate(text, 1):
        eq = where.get(w, 0)
        xv = eq | minus
        xh = (((eq & plus) + plus) ^ plus) | eq
        up, down = minus | ~(xh | plus) & full, plus & xh
        if up & top:
            score += 1
        elif down & top:
            score -= 1
        up, down = up << 1 & full, down << 1 & full
        plus, minus = down | ~(xv | up) & full, up & xv
        if score < best:
            best, end = score, k
    return best, end


@dataclass
class Index:
    """Items, their q-grams and their LSH tables."""

    items: list[tuple[object, list[int]]] = field(default_factory=list)
    vocab: dict[str, int] = field(default_factory=dict)
    similarity: float = SIMILARITY

    def build(self, rows: list[tuple[object, str]], recall: float = RECALL) -> "Index":
        for key, text in rows:
            ids = [self.vocab.setdefault(w, len(self.vocab) + 1) for w in words_of(text)]
            if ids:
                self.items.append((key, ids))
        self.edits = [edits_of(len(x), self.similarity) for _, x in self.items]
        self.q = [gram_size(len(x), e) for (_, x), e in zip(self.items, self.edits)]
        self.need = [max(1, len(x) - q + 1 - e * q) for (_, x), e, q in zip(self.items, self.edits, self.q)]
        base = len(self.vocab) + 1
        self.base = base
        self.grams: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        for q in sorted(set(self.q)):
            got = []
            for k, (_, x) in enumerate(self.items):
                if self.q[k] == q:
                    got += [(sum(w * base**t for t, w in enumerate(x[p : p + q])), k, p) for p in range(len(x) - q + 1)]
            code, item, pos = (np.array(c, dtype=np.int64) for c in zip(*sorted(got)))
            kind, first, size = np.unique(code, return_index=True, return_counts=True)
            self.grams[q] = (kind, first, size, np.c_[item, pos])
        self.tables(recall)
        return self

    def tables(self, recall: float) -> None:
        rng = random.Random(5)
        share = self.agreement(rng)
        n = max(1, math.ceil(math.log(1 - recall) / math.log(1 - min(0.999, share**SAMPLED))))
        self.plan = []
        for t in range(-(-n // WALKS) * WALKS):
            self.plan.append((t % WALKS, sorted(rng.random() for _ in range(SAMPLED))))
        self.lookup: dict[int, list[int]] = {}
        for m in sorted({len(x) for _, x in self.items}):
            these = [k for k, (_, x) in enumerate(self.items) if len(x) == m]
            for k, keys in zip(these, self.keys(np.array([self.items[k][1] for k in these], dtype=np.int64)).T.tolist()):
                for h in keys:
                    self.lookup.setdefault(h, []).append(k)

    def agreement(self, rng: random.Random) -> float:
        """Mean share of equal emitted words between items and copies edited up to the limit."""
        shares = []
        for k in range(0, len(self.items), max(1, len(self.items) // 50)):
            x = self.items[k][1]
            y = list(x)
            for _ in range(self.edits[k]):
                p, kind = rng.randrange(len(y)), rng.randrange(3)
                new = rng.randrange(1, self.base + 50)
                y[p : p + (kind > 0)] = [new] if kind < 2 else []
            y = (y + [END] * len(x))[: len(x)]
            for walk in range(3):
                a, b = embed(np.array([x, y]), walk, self.steps(len(x)))
                shares.append(float((a == b).mean()))
        return max(0.15, float(np.percentile(shares, 20))) if shares else 1.0

    @staticmethod
    def steps(m: int) -> int:
        return 2 * m + 2

    def keys(self, rows: np.ndarray) -> np.ndarray:
        """LSH keys, one row a table."""
        steps = self.steps(rows.shape[1])
        emitted = [embed(rows, w, steps) for w in range(WALKS)]
        return np.array([keys_of(emitted[w], np.array([int(f * steps) for f in at]), t) for t, (w, at) in enumerate(self.plan)])

    def windows(self, ids: np.ndarray, bounds: np.ndarray) -> set[tuple[int, int, int]]:
        """(text, item size, start) of the windows worth embedding. ids: word ids (0: not in any item)
        of all texts end to end; bounds: where texts begin, and the end."""
        out: set[tuple[int, int, int]] = set()
        for q, (kind, first, size, where) in self.grams.items():
            if len(ids) < q:
                continue
            ok = np.ones(len(ids) - q + 1, dtype=bool)
            code = np.zeros(len(ids) - q + 1, dtype=np.int64)
            for t in range(q):
                part = ids[t : len(ids) - q + 1 + t]
                ok &= part > 0
                code += part * self.base**t
            at = np.flatnonzero(ok)
            slot = np.minimum(np.searchsorted(kind, code[at]), len(kind) - 1)
            hit = kind[slot] == code[at]
            at, slot = at[hit], slot[hit]
            text = np.searchsorted(bounds, at, side="right") - 1
            inside = at + q <= bounds[text + 1]
            at, slot, text = at[inside], slot[inside], text[inside]
            if not len(at):
                continue
            n = size[slot]
            rep = np.repeat(np.arange(len(at)), n)
            pick = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + first[slot][rep]
            item, diag = where[pick, 0], at[rep] - where[pick, 1]
            text = text[rep]
            order = np.lexsort((diag, item, text))
            text, item, diag = text[order], item[order], diag[order]
            need, e = np.array(self.need)[item], np.array(self.edits)[item]
            last = np.arange(len(item)) + need - 1
            fits = last < len(item)
            j = np.minimum(last, len(item) - 1)
            fits &= (text[j] == text) & (item[j] == item) & (diag[j] - diag <= e)
            for k in np.flatnonzero(fits).tolist():
                for d in {int(diag[k]), int(diag[k + int(need[k]) // 2]), int(diag[j[k]])}:
                    out.add((int(text[k]), len(self.items[item[k]][1]), d))
        return out

    def search(self, texts: list[str | None]) -> list[tuple[int, int, int, int]]:
        """(text, item, distance, first word of the stretch's reach) of every leak."""
        ids, bounds = [], [0]
        get = self.vocab.get
        for t in texts:
            ids += [get(w, 0) for w in words_of(t)]
            bounds.append(len(ids))
        flat, ends = np.array(ids, dtype=np.int64), np.array(bounds)
        found = self.windows(flat, ends) if self.items and len(flat) else set()
        by_size: dict[int, list[tuple[int, int]]] = {}
        for text, m, start in found:
            by_size.setdefault(m, []).append((text, start))
        best: dict[tuple[int, int], tuple[int, int]] = {}
        for m, spots in sorted(by_size.items()):
            spots.sort()
            for lo in range(0, len(spots), 20_000):
                some = np.array(spots[lo : lo + 20_000])
                pos = some[:, 1:2] + np.arange(m)
                inside = (pos >= bounds_of(ends, some[:, 0], 0)) & (pos < bounds_of(ends, some[:, 0], 1))
                rows = np.where(inside, flat[np.clip(pos, 0, len(flat) - 1)], END)
                # words in no item must differ from the end mark
                rows = np.where(inside & (rows == 0), self.base + 1, rows)
                cands: dict[int, set[int]] = {}
                for keys in self.keys(rows):
                    for k, h in enumerate(keys.tolist()):
                        if h in self.lookup:
                            cands.setdefault(k, set()).update(self.lookup[h])
                for k, items in sorted(cands.items()):
                    text, start = spots[lo + k]
                    for item in items:
                        x, e = self.items[item][1], self.edits[item]
                        a, b = max(bounds[text], start - e), min(bounds[text + 1], start + max(m, len(x)) + 2 * e)
                        dist, end = best_stretch(x, ids[a:b])
                        if dist <= e and (dist, a - bounds[text]) < best.get((text, item), (e + 1, 0)):
                            best[text, item] = (dist, a - bounds[text])
        return [(t, i, d, a) for (t, i), (d, a) in sorted(best.items())]


def bounds_of(ends: np.ndarray, text: np.ndarray, shift: int) -> np.ndarray:
    return ends[text + shift][:, None]


def find_leaks(docs: DataFrame, items: DataFrame, similarity: float = SIMILARITY, recall: float = RECALL, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", most: int = MAX_ITEM_CHARS) -> DataFrame:
    """id, item, distance (word edits), n_words (of the item), first_word: one row for each document
    and item that it leaks."""
    spark = docs.sparkSession
    items = items.where(F.col(item_col).isNotNull()).select(F.col(item_col).alias("item"), F.col(item_text).alias("text"))
    parts = -(-(items.agg(F.sum(F.length("text"))).first()[0] or 0) // most) or 1
    out = None
    for k in range(parts):  # a row's part is that of its text
        rows = items.where(F.pmod(F.xxhash64("text"), F.lit(parts)) == k).orderBy("item", "text").collect()  # about ``most`` characters
        index = Index(similarity=similarity).build([tuple(r) for r in rows], recall)
        got = _search(docs, spark.sparkContext.broadcast(index), items.schema["item"].dataType.simpleString(), id_col, text_col, item_col)
        out = got if out is None else out.unionByName(got)
    return out


def _search(docs: DataFrame, sent, item_kind: str, id_col: str, text_col: str, item_col: str) -> DataFrame:
    kinds = [docs.schema[id_col].dataType.simpleString(), item_kind]
    schema = f"{id_col} {kinds[0]}, {item_col} {kinds[1]}, distance int, n_words int, first_word long"

    def run(batches):
        index = sent.value
        for b in batches:
            keys, texts, at = b.column(0), b.column(1).to_pylist(), 0
            while at < len(texts):
                end, size = at, 0
                while end < len(texts) and (end == at or size + len(texts[end] or "") < 4_000_000):
                    size += len(texts[end] or "")
                    end += 1
                hits = index.search(texts[at:end])
                if hits:
                    t, i, d, a = zip(*hits)
                    ids = keys.take(pa.array([x + at for x in t]))
                    named = pa.array([index.items[x][0] for x in i])
                    yield pa.RecordBatch.from_arrays([ids, named, pa.array(d, pa.int32()), pa.array([len(index.items[x][1]) for x in i], pa.int32()), pa.array(a, pa.int64())], [id_col, item_col, "distance", "n_words", "first_word"])
                at = end
        give_back()

    return bounded(docs).select(id_col, text_col).mapInArrow(run, schema)
