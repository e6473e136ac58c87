"""Adaptive context-mixing range coder for token ids.

Ids are cut into blocks that start from nothing: own models, own coder, own CRC-32. A block lists its
ids in order, with their counts, and codes places in that list, one range-coder step an id. Three
predictions are mixed: the id that last followed the two before (order 2), the id that last followed the
one before (order 1), and the block's counts (order 0). Their weights learn, apart for each pair of
confidences (how often orders 2 and 1 have just been right); what they leave is order 0's, never less than
one part in 32, so every id of the list can be coded at every place.

All blocks of a segment run in step as the lanes of numpy arrays; everything is integer arithmetic, so
any machine decodes what another wrote.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

BLOCK = 2_048
PLACE = 11  # log2 of BLOCK
SPREAD = np.int64(0x2F)  # of the id before the last, among the BLOCK contexts of order 2
MAGIC = b"IDM2"
SURE, TOP = 2, 3  # bits of a confidence, its largest value
RATE = 5
WHOLE = 16  # log2 of the mixed total
MOST = (1 << WHOLE) - BLOCK - 2  # of orders 1 and 2 together
WORD = 24  # bits that leave the coder at once; low and range have twice as many
HEAD = "<IIIII"
NONE = -1 << SURE  # no guess
ZERO, ONE, GOAL, MASK, WHOLE_32 = map(np.int32, (0, 1, MOST, BLOCK - 1, 1 << WHOLE))
SHORT_ONE, SHORT_TOP, WIDE_MASK, FULL_WORD = np.int16(1), np.int16(TOP), np.int64(BLOCK - 1), np.int64(1 << WORD)
LAST = np.float64((1 << WHOLE) - 1)


def _first_weights() -> np.ndarray:
    """(order 2, order 1) by confidences, before a block has taught better."""
    k = np.arange(TOP + 1)
    right = k / (k + 1.5)
    two = np.repeat(right, TOP + 1)
    one = np.tile(right, TOP + 1) * (1 - two) * 0.7
    return np.stack([two * MOST, one * MOST], axis=1).astype(np.int32).view(np.int64).reshape(-1)


FIRST = _first_weights()


class Lanes:
    """The models and coders of all blocks of a segment, in step. A place is where an id's run begins in its
    block's sorted ids. Rows of arrays with two rows are orders 2 and 1."""

    def __init__(self, n: int):
        self.lane = np.arange(n, dtype=np.int64)
        self.at_weight = self.lane << 2 * SURE
        self.base = np.stack([self.lane << PLACE, n + self.lane << PLACE])
        self.after = np.full(2 * n << PLACE, NONE, dtype=np.int16)  # place and confidence by what stands before
        self.by = np.empty((2, n), dtype=np.int64)
        self.weight = np.tile(FIRST, n)  # two 32-bit weights in one place
        self.hits = np.empty((n, 2), dtype=np.int32)
        self.edges = np.zeros((3, n), dtype=np.int32)  # of the shares: 0, the end of order 2's, of order 1's
        self.low, self.range = np.zeros(n, dtype=np.int64), np.full(n, 1 << 2 * WORD, dtype=np.int64)
        self.one, self.two = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)

    def predict(self) -> None:
        """Both guesses (-1: none) and where their shares of the whole end."""
        mix = self.two * SPREAD
        mix += self.one
        mix &= WIDE_MASK
        np.add(self.base[0], mix, out=self.by[0])
        np.add(self.base[1], self.one, out=self.by[1])
        had = self.after.take(self.by)
        self.sure, self.guess = had & TOP, had >> SURE
        both = self.sure[0] << SURE
        both |= self.sure[1]
        self.by_weight = self.at_weight + both
        self.has = self.weight.take(self.by_weight).view(np.int32).reshape(-1, 2)
        np.add(self.has[:, 0], ONE, out=self.edges[1])
        np.add(self.has[:, 1], ONE, out=self.edges[2])
        self.edges[2] += self.edges[1]
        self.rest = WHOLE_32 - self.edges[2]

    def code(self, hit_two, hit_one, run) -> tuple[np.ndarray, np.ndarray]:
        """Narrows to a guess, or to the id whose run has these two ends; returns (what low moved by, the lanes whose
        upper word is settled now)."""
        ends = run * self.rest
        ends >>= PLACE
        ends += self.edges[2]
        np.copyto(ends, self.edges[1:], where=hit_one)
        np.copyto(ends, self.edges[:2], where=hit_two)
        moved, size = ends.astype(np.int64)
        size -= moved
        self.range >>= WHOLE
        moved *= self.range
        self.low += moved
        self.range *= size
        return moved, np.flatnonzero(self.range < FULL_WORD)

    def push(self, some: np.ndarray) -> np.ndarray:
        """The settled words. A range that lies across a word's border is cut there, so that nothing carries."""
        low, room = self.low[some], self.range[some]
        up, low = low >> WORD, low & (1 << WORD) - 1
        self.low[some], self.range[some] = low << WORD, np.minimum(room, (1 << WORD) - low) << WORD
        return up

    def learn(self, hit_two, hit_one, place) -> None:
        """place: 16-bit integers."""
        self.hits[:, 0], self.hits[:, 1] = hit_two, hit_one
        more = self.hits * GOAL
        more -= self.has
        more >>= RATE
        more += self.has
        self.weight[self.by_weight] = more.view(np.int64).reshape(-1)
        sure = self.sure
        sure += SHORT_ONE
        np.minimum(sure, SHORT_TOP, out=sure)
        np.copyto(sure, SHORT_ONE, where=self.guess != place)
        sure |= place << SURE
        self.after[self.by] = sure
        self.two, self.one = self.one, place.astype(np.int64)


def _varints(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes end to end, how many each number has)."""
    used = np.ones(len(v), dtype=np.int64)
    for j in range(1, 5):
        used += v >> 7 * j > 0
    out = np.zeros((len(v), int(used.max(initial=1))), dtype=np.uint8)
    for j in range(out.shape[1]):
        out[:, j] = (v >> 7 * j & 127) | (used > j + 1) << 7
    return out[np.arange(out.shape[1]) < used[:, None]], used


def _read_varints(b: np.ndarray) -> np.ndarray:
    b = b.astype(np.int64)
    end = np.flatnonzero(b < 128)
    start = np.r_[0, end[:-1] + 1]
    place = np.arange(len(b)) - np.repeat(start, end - start + 1)
    return np.add.reduceat((b & 127) << (7 * place), start)


def encode_segment(ids: np.ndarray) -> bytes:
    """All ids of a segment, in blocks; the last block is filled up with its last id."""
    ids = np.asarray(ids, dtype=np.uint32)
    n = -(-len(ids) // BLOCK)
    if not n:
        return MAGIC + struct.pack("<I", 0)
    filled = np.full((n, BLOCK), ids[-1])
    filled.reshape(-1)[: len(ids)] = ids
    ranked = np.sort(filled, axis=1)
    fresh = np.ones((n, BLOCK), dtype=bool)
    np.not_equal(ranked[:, 1:], ranked[:, :-1], out=fresh[:, 1:])
    edge = np.flatnonzero(fresh)
    n_kinds = np.count_nonzero(fresh, axis=1)
    until = np.cumsum(n_kinds)
    kinds = ranked.reshape(-1)[edge]
    gaps = np.diff(kinds.astype(np.int64), prepend=0)
    gaps[until - n_kinds] = kinds[until - n_kinds]
    raw, used = _varints(gaps)
    cut = np.r_[0, np.cumsum(used)[until - 1]].tolist()
    bits = np.packbits(fresh, axis=1)
    run = (edge & BLOCK - 1) | np.diff(edge, append=n * BLOCK) + (edge & BLOCK - 1) << PLACE  # begin and end
    runs = np.empty((n, BLOCK), dtype=np.int32)
    few = int(kinds.max()) < 1 << 22
    table = np.zeros(int(kinds.max()) + 1 if few else 0, dtype=np.int32)
    heads, lists = [], []
    for k, (a, b) in enumerate(zip((until - n_kinds).tolist(), until.tolist())):
        if few:
            table[kinds[a:b]] = run[a:b]
            np.take(table, filled[k], out=runs[k])
        else:
            runs[k] = run[a:b][np.searchsorted(kinds[a:b], filled[k])]
        lists.append(zlib.compress(raw[cut[k] : cut[k + 1]].tobytes() + bits[k].tobytes(), 1))
        real = ids[k * BLOCK : (k + 1) * BLOCK]
        heads.append((len(real), zlib.crc32(real.astype("<u4"))))
    runs = np.ascontiguousarray(runs.T)
    lanes = Lanes(n)
    out = np.zeros((n, BLOCK + 1), dtype="<u4")
    used = np.zeros(n, dtype=np.int64)
    run = np.empty((2, n), dtype=np.int32)
    for t in range(BLOCK):
        np.bitwise_and(runs[t], MASK, out=run[0])
        np.right_shift(runs[t], PLACE, out=run[1])
        place = run[0].astype(np.int16)
        lanes.predict()
        hit_two, hit_one = lanes.guess == place
        hit_one &= ~hit_two
        _, some = lanes.code(hit_two, hit_one, run)
        if len(some):
            at = used[some]
            out[some, at] = lanes.push(some)
            used[some] = at + 1
        lanes.learn(hit_two, hit_one, place)
    out[lanes.lane, used] = (lanes.low + (1 << WORD) - 1) >> WORD  # the rest may be zeros
    used += 1
    parts = [MAGIC, struct.pack("<I", n)]
    for k in range(n):
        parts.append(struct.pack(HEAD, *heads[k], cut[k + 1] - cut[k], len(lists[k]), int(used[k])))
    coded = np.ascontiguousarray(out[:, : used.max()]).view(np.uint8).reshape(n, -1, 4)[:, :, :3].reshape(n, -1)
    for k in range(n):
        parts += [lists[k], coded[k, : 3 * used[k]].tobytes()]
    return b"".join(parts)


def decode_segment(raw: bytes) -> np.ndarray:
    """The ids; raises ValueError where a block's checksum differs."""
    if raw[:4] != MAGIC:
        raise ValueError("not a segment of token ids")
    (n,) = struct.unpack_from("<I", raw, 4)
    if not n:
        return np.zeros(0, dtype=np.int64)
    size = struct.calcsize(HEAD)
    heads = [struct.unpack_from(HEAD, raw, 8 + size * k) for k in range(n)]
    at, lists = 8 + size * n, []
    data = np.zeros((n, max(h[4] for h in heads) + 2, 4), dtype=np.uint8)
    for k, (_, _, gaps, listed, words) in enumerate(heads):
        try:
            lists.append(zlib.decompress(raw[at : at + listed]))
        except zlib.error as e:
            raise ValueError(f"block {k} is damaged") from e
        if len(lists[k]) != gaps + BLOCK // 8:
            raise ValueError(f"block {k} is damaged")
        at += listed
        data[k, :words, :3] = np.frombuffer(raw, dtype=np.uint8, count=3 * words, offset=at).reshape(-1, 3)
        at += 3 * words
    data = data.view("<u4").reshape(n, -1)
    fresh = np.unpackbits(np.frombuffer(b"".join([x[-BLOCK // 8 :] for x in lists]), dtype=np.uint8)).reshape(n, BLOCK)
    gaps = _read_varints(np.frombuffer(b"".join([x[: -BLOCK // 8] for x in lists]), dtype=np.uint8))
    edge = np.flatnonzero(fresh)
    until = np.cumsum(np.count_nonzero(fresh, axis=1))
    if len(gaps) != len(edge) or not fresh[:, 0].all():
        raise ValueError("a block's list is damaged")
    kinds = np.cumsum(gaps)
    before = np.r_[0, kinds[until[:-1] - 1]]  # each block's list begins anew
    long = np.diff(edge, append=n * BLOCK)
    kinds -= np.repeat(before, np.diff(until, prepend=0))
    ranked = np.repeat(kinds.astype(np.uint32), long).reshape(n, BLOCK)
    runs = np.repeat(((edge & BLOCK - 1) | (edge & BLOCK - 1) + long << PLACE).astype(np.int32), long)
    lanes = Lanes(n)
    ahead = (data[:, 0].astype(np.int64) << WORD) | data[:, 1]  # the coded number less low
    used, last = np.full(n, 2, dtype=np.int64), data.shape[1] - 1
    places = np.empty((BLOCK, n), dtype=np.int16)
    run = np.empty((2, n), dtype=np.int32)
    for t in range(BLOCK):
        lanes.predict()
        v = np.minimum(ahead / (lanes.range >> WHOLE), LAST)
        v = np.maximum(v, 0.0, out=v).astype(np.int32)
        hit_two = v < lanes.edges[1]
        v -= lanes.edges[2]
        hit_one = v < ZERO
        hit_one ^= hit_two
        v += ONE
        v <<= PLACE
        v -= ONE
        slot = (v / lanes.rest).astype(np.int64)
        np.maximum(slot, 0, out=slot)
        slot += lanes.base[0]
        got = runs.take(slot)
        np.bitwise_and(got, MASK, out=run[0])
        np.right_shift(got, PLACE, out=run[1])
        moved, some = lanes.code(hit_two, hit_one, run)
        place = run[0].astype(np.int16)
        np.copyto(place, lanes.guess[1], where=hit_one)
        np.copyto(place, lanes.guess[0], where=hit_two)
        places[t] = place
        ahead -= moved
        if len(some):
            lanes.push(some)
            ahead[some] = ahead[some] << WORD | data[some, np.minimum(used[some], last)]
            used[some] += 1
        lanes.learn(hit_two, hit_one, place)
    places = np.ascontiguousarray(places.T)
    out = []
    for k, (count, crc, *_) in enumerate(heads):
        part = ranked[k].take(places[k, :count])
        if zlib.crc32(part.astype("<u4")) != crc:
            raise ValueError(f"block {k} is damaged")
        out.append(part)
    return np.concatenate(out)
