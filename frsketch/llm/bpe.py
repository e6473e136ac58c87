"""Byte-level BPE encoding and decoding by a rank file.

Slices come from ``pretokens``; each distinct slice is merged once and kept in a cache bounded in bytes,
which a task leaves empty. Misses are merged together: all of them lie end to end in one id array, every round looks up
the rank of each adjacent pair in an open-addressing table and merges, in every slice, the leftmost
pair of that slice's lowest rank (all occurrences that do not overlap).

Null texts count as empty: no ids, and the SHA-256 of the empty string. Repeated rows each get their
row; an empty table gives an empty table; other columns of the input are not read.
"""

from __future__ import annotations

import base64
import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm.pretokens import Slices
from frsketch.llm.shared import Cache, give_back, texts as bounded

ENTRY = 300  # bytes of a cached slice besides its own
BATCH_CHARS = 1_000_000


def read_ranks(path: str) -> list[bytes]:
    """Token bytes by id."""
    with open(path, "rb") as f:
        pairs = [line.split() for line in f if line.strip()]
    out = [b""] * len(pairs)
    for tok, rank in pairs:
        out[int(rank)] = base64.b64decode(tok)
    return out


class PairTable:
    """(left id, right id) -> merged id, as an open-addressing table for array look-ups."""

    BITS = 19

    def __init__(self, vocab: list[bytes]):
        by_bytes = {b: i for i, b in enumerate(vocab)}
        self.bytes_id = np.array([by_bytes[bytes([b])] for b in range(256)], dtype=np.int64)
        rows = []
        for rank, tok in enumerate(vocab):
            for cut in range(1, len(tok)):
                a, b = by_bytes.get(tok[:cut]), by_bytes.get(tok[cut:])
                if a is not None and b is not None:
                    rows.append((a << 20 | b, rank))
        keys, ranks = np.array(rows, dtype=np.int64).T
        size = 1 << self.BITS
        self.keys = np.full(size, -1, dtype=np.int64)
        self.ranks = np.full(size, NONE, dtype=np.int64)
        slot, left = self._slot(keys), np.arange(len(keys))
        self.probes = 0
        while len(left):
            self.probes += 1
            free = self.keys[slot[left]] == -1
            self.keys[slot[left[free]]] = keys[left[free]]
            done = self.keys[slot[left]] == keys[left]
            self.ranks[slot[left[done]]] = ranks[left[done]]
            left = left[~done]
            slot[left] = (slot[left] + 1) & (size - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        x = keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return (x >> np.uint64(64 - self.BITS)).astype(np.int64)

    def look_up(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Merged ids, NONE where the pair has none."""
        key = a << 20 | b
        slot = self._slot(key)
        out = np.full(len(key), NONE, dtype=np.int64)
        todo = None
        for _ in range(self.probes):
            k = self.keys[slot]
            hit = k == key
            if todo is None:
                out[hit] = self.ranks[slot[hit]]
                todo = np.flatnonzero(~hit & (k != -1))
            else:
                out[todo[hit]] = self.ranks[slot[hit]]
                todo = todo[~hit & (k != -1)]
            if not len(todo):
                break
            key = (a[todo] << 20) | b[todo]
            slot = (self._slot(key) + _ + 1) & ((1 << self.BITS) - 1)
        return out


NONE = np.int64(1 << 40)


def merge_all(table: PairTable, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all words end to end, how many each word has)."""
    if not words:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    lens = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    ids = table.bytes_id[np.frombuffer(b"".join(words), dtype=np.uint8)]
    owner = np.repeat(np.arange(len(words)), lens)
    done_ids, done_owner = [], []
    rank = np.full(len(ids), NONE, dtype=np.int64)
    rank[:-1] = np.where(owner[:-1] == owner[1:], table.look_up(ids[:-1], ids[1:]), NONE)
    while len(ids):
        head = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
        best = np.minimum.reduceat(rank, head)
        size = np.diff(np.r_[head, len(ids)])
        over = np.repeat(best == NONE, size)
        if over.any():
            done_ids.append(ids[over])
            done_owner.append(owner[over])
            keep = ~over
            ids, owner, rank, best, size = ids[keep], owner[keep], rank[keep], best[best != NONE], size[best != NONE]
            if not len(ids):
                break
        hit = rank == np.repeat(best, size)
        at = np.flatnonzero(hit)
        if len(at) > 1 and (np.diff(at) == 1).any():  # a run of overlapping hits: take every second one
            run = np.cumsum(np.r_[True, np.diff(at) != 1])
            first = np.r_[0, np.flatnonzero(np.diff(run)) + 1]
            at = at[(np.arange(len(at)) - first[run - 1]) % 2 == 0]
        ids[at] = rank[at]
        keep = np.ones(len(ids), dtype=bool)
        keep[at + 1] = False
        new = (np.cumsum(keep) - 1)[at]
        ids, owner, rank = ids[keep], owner[keep], rank[keep]
        for i in (new, new[new > 0] - 1):
            j = np.minimum(i + 1, len(ids) - 1)
            same = (i + 1 < len(ids)) & (owner[i] == owner[j])
            rank[i] = np.where(same, table.look_up(ids[i], ids[j]), NONE)
    all_ids = np.concatenate(done_ids) if done_ids else ids
    all_owner = np.concatenate(done_owner) if done_owner else owner
    order = np.argsort(all_owner, kind="stable")
    return all_ids[order], np.bincount(all_owner, minlength=len(words))


class Codec:
    """Encoder and decoder of one rank file, with a cache of merged slices."""

    def __init__(self, path: str):
        self.vocab = read_ranks(path)
        self.table = PairTable(self.vocab)
        self.cache = Cache(ENTRY)  # slice -> (ids as 32-bit integers, as decimals, what they decode to)

    def look_up(self, words: list[bytes]) -> Cache:
        """The cache, with every one of the words."""
        missing = self.cache.lacking(set(words))
        ids, counts = merge_all(self.table, missing)
        raw, flat, at = ids.astype("<i4").tobytes(), ids.tolist(), 0
        for w, n in zip(missing, counts.tolist()):
            some = flat[at : at + n]
            back = self.decode(some)
            self.cache[w] = (raw[4 * at : 4 * (at + n)], " ".join(map(str, some)).encode(), w if back == w else back)
            at += n
        return self.cache

    def encode(self, texts: list[str]) -> list[list[int]]:
        s = Slices(texts)
        table = self.look_up(s.words)
        out, at = [], 0
        for n in s.per_text.tolist():
            out.append(np.frombuffer(b"".join([table[w][0] for w in s.words[at : at + n]]), dtype="<i4").tolist())
            at += n
        return out

    def encode_with_offsets(self, text: str) -> tuple[list[int], list[int]]:
        """(ids, byte offset of each)."""
        ids = self.encode([text])[0]
        lens = [len(self.vocab[i]) for i in ids]
        return ids, [0, *np.cumsum(lens).tolist()][: len(ids)]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join([self.vocab[i] for i in ids])


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    """One per worker process and file."""
    return Codec(path)


def text_batches(batch, text: str = "text", most: int = BATCH_CHARS):
    """(row offset, texts) of an Arrow batch, cut so that one group has about ``most`` characters."""
    texts = [t or "" for t in batch.column(text).to_pylist()]
    at, size = 0, 0
    for k, t in enumerate(texts):
        if size and size + len(t) > most:
            yield at, texts[at:k]
            at, size = k, 0
        size += len(t)
    if at < len(texts):
        yield at, texts[at:]


def encode_frame(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """One row per text: id, ids (when asked for), n_tokens, digest of the ids, digest and text of
    what the ids decode to."""
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"{id_col} {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded string" if with_ids else "")

    def run(batches):
        c = codec(path)
        try:
            for batch in batches:
                keys = batch.column(0)
                for at, texts in text_batches(batch.select([1]), text_col):
                    yield encoded(c, keys.slice(at, len(texts)), texts)
        finally:
            c.cache.clear()
            give_back()

    def encoded(c: Codec, keys, texts: list[str]):
        s = Slices(texts)
        table = c.look_up(s.words)
        counts, in_decimals, decoded, ids, k = [], [], [], [], 0
        for n in s.per_text.tolist():
            got = [table[w] for w in s.words[k : k + n]]
            k += n
            raw = b"".join([g[0] for g in got])
            back = b"".join([g[2] for g in got])
            counts.append(len(raw) // 4)
            in_decimals.append(hashlib.sha256(b" ".join([g[1] for g in got])).hexdigest())
            decoded.append(back if with_ids else None)
            ids.append((hashlib.sha256(back).hexdigest(), raw if with_ids else b""))
        arrays = [keys, pa.array(counts, pa.int64()), pa.array(in_decimals, pa.string()), pa.array([x[0] for x in ids], pa.string())]
        if with_ids:
            flat = np.frombuffer(b"".join([x[1] for x in ids]), dtype="<i4")
            arrays += [pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(counts)], pa.int32()), pa.array(flat, pa.int32())), pa.array([x.decode() for x in decoded], pa.string())]
        return pa.RecordBatch.from_arrays(arrays, [id_col, "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"][: len(arrays)])

    return bounded(docs).select(id_col, F.col(text_col)).mapInArrow(run, schema)
