"""Token ids of whole columns of texts by a ``tokenizers`` file, each distinct slice encoded once.

The texts of an Arrow column lie end to end already, so slices are cut points in its bytes. Whether a slice
starts at a character follows from its class and its neighbours' (``pretokens`` scans the same pattern as an
automaton): classes that differ, a blank that joins what follows, white space that gives its last character
away, and contractions, which begin only where no run of others goes on. Special strings are slices of their
own. Arrow numbers the slices of a column by its distinct ones; those not yet known go through the library's
model, spelt in its byte alphabet, and ids come back by gathering.

Nulls are empty. A vocabulary file that does not split by this pattern is given whole texts.
"""

from __future__ import annotations

import codecs
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

from frsketch.llm.pretokens import CONTRACTIONS, codepoint_classes
from frsketch.llm.shared import CACHE_BYTES
from frsketch.llm.token_counts import Library

ENTRY = 150  # bytes of a known slice besides its own, Arrow's table of them included
AT_ONCE = 8_192  # slices whose tokens are held as objects
BLANK = 4  # class of U+0020


def _byte_alphabet() -> str:
    """The character that stands for each byte in a byte-level vocabulary: its own where that prints, else one from
    U+0100 on."""
    prints = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    others = [b for b in range(256) if b not in set(prints)]
    to = dict(zip(prints, prints)) | {b: 0x100 + k for k, b in enumerate(others)}
    return "".join(chr(to[b]) for b in range(256))


ALPHABET = _byte_alphabet()


@lru_cache(maxsize=1)
def _byte_classes() -> np.ndarray:
    """Classes of ASCII characters; a place for all others."""
    return np.append(codepoint_classes()[:128], np.full(128, 2, dtype=np.uint8))


def slice_starts_local(codes: np.ndarray, cls: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Start flags of the slices of texts that lie end to end, by neighbours alone. codes: code points,
    or leading bytes; cls: classes; first: flags of first characters."""
    n = len(codes)
    if not n:
        return np.zeros(0, dtype=bool)
    last = np.append(first[1:], True)
    space = cls >= 3
    solid = ~space
    goes_on = np.zeros(n, dtype=bool)  # something solid of the same text follows
    goes_on[:-1] = solid[1:]
    goes_on &= ~last
    starts = first.copy()
    same = np.zeros(n, dtype=bool)
    np.equal(cls[1:], cls[:-1], out=same[1:])
    joined = np.zeros(n, dtype=bool)  # after a blank that joins it
    joined[1:] = (cls[:-1] == BLANK) & goes_on[:-1]
    after_space = np.zeros(n, dtype=bool)
    after_space[1:] = space[:-1]
    starts |= solid & ~same & ~joined
    starts |= space & (goes_on | ~after_space)
    quote = np.flatnonzero(codes == 0x27)
    quote = quote[starts[quote] & ~last[quote]]
    if len(quote):
        a = codes[quote + 1]
        b = np.where(last[quote + 1], 0, codes[np.minimum(quote + 2, n - 1)])
        for c in CONTRACTIONS:
            hit = quote[a == ord(c)] if len(c) == 1 else quote[(a == ord(c[0])) & (b == ord(c[1]))]
            starts[hit + 1] = False
            after = hit + len(c) + 1
            starts[after[after < n]] = True
    return starts


def cut_points(raw: np.ndarray, ends: np.ndarray, special=()) -> np.ndarray:
    """Byte offsets where the slices of texts begin. raw: UTF-8 of all texts end to end; ends: of each, in bytes;
    special: (begin, end) of special strings."""
    first = np.zeros(len(raw) + 1, dtype=bool)
    first[0] = True
    first[ends] = True
    for a, b in special:
        first[a] = first[b] = True
    first = first[:-1]
    keep = (raw & 0xC0) != 0x80  # the first byte of each character
    wide = np.flatnonzero(raw >= 0xC0)
    head = raw[keep] if len(wide) else raw
    cls = _byte_classes().take(head)
    if len(wide):
        lead = raw[wide].astype(np.uint32)
        code = lead & np.where(lead < 0xE0, 0x1F, np.where(lead < 0xF0, 0x0F, 0x07)).astype(np.uint32)
        for j, least in ((1, 0xC0), (2, 0xE0), (3, 0xF0)):
            more = lead >= least
            code[more] = code[more] << 6 | raw[wide[more] + j] & 0x3F
        cls[head >= 0xC0] = codepoint_classes().take(code)
        starts = np.zeros(len(raw), dtype=bool)
        starts[keep] = slice_starts_local(head, cls, first[keep])
    else:
        starts = slice_starts_local(head, cls, first)
    cut = np.flatnonzero(starts)
    for a, b in special:
        cut = cut[(cut <= a) | (cut >= b)]
    return cut


def _size(words: pa.Array) -> int:
    return pc.sum(pc.binary_length(words)).as_py() or 0


class SliceIds:
    """The slices that a vocabulary file has encoded so far, bounded in bytes, and their ids as arrays."""

    def __init__(self, lib: Library, limit: int = CACHE_BYTES):
        self.lib, self.limit = lib, limit
        self.whole = {codecs.charmap_decode(s.encode(), "strict", ALPHABET)[0]: i for s, i in lib.added.items()}
        self.special = regex.compile(lib.special.pattern.encode()) if lib.special else None
        self.clear()

    def clear(self) -> None:
        self.known = pa.array([], pa.large_binary())
        self.used = 0
        self.ids = np.zeros(0, dtype=np.uint32)
        self.begin = np.zeros(1, dtype=np.int64)  # of each known slice's ids, and the end

    def numbers(self, words: pa.Array) -> np.ndarray:
        """The numbers of distinct slices, which are all known afterwards."""
        at = pc.index_in(words, self.known)
        missing = words.filter(at.is_null())
        need = _size(missing) + ENTRY * len(missing)
        if self.used + need > self.limit and len(self.known):
            self.clear()
            at, missing = pa.nulls(len(words), pa.int32()), words
            need = _size(missing) + ENTRY * len(missing)
        out = at.fill_null(-1).to_numpy().astype(np.int64)
        if len(missing):
            out[out < 0] = np.arange(len(self.known), len(self.known) + len(missing))
            ids, counts = self.encode(missing)
            self.used += need
            self.known = pa.concat_arrays([self.known, missing])
            self.ids = np.concatenate([self.ids, ids])
            self.begin = np.append(self.begin, self.begin[-1] + np.cumsum(counts))
        return out

    def encode(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of some slices end to end, how many each has)."""
        edges = np.frombuffer(words.buffers()[1], dtype=np.int64)[words.offset : words.offset + len(words) + 1]
        spelt = codecs.charmap_decode(memoryview(words.buffers()[2])[edges[0] : edges[-1]], "strict", ALPHABET)[0]
        edges = (edges - edges[0]).tolist()
        tokenize, whole = self.lib.tok.model.tokenize, self.whole
        ids: list[int] = []
        counts: list[int] = []
        for k in range(0, len(words), AT_ONCE):
            some = [spelt[a:b] for a, b in zip(edges[k : k + AT_ONCE], edges[k + 1 : k + AT_ONCE + 1])]
            got = [[whole[w]] if w in whole else [t.id for t in tokenize(w)] for w in some]
            counts += map(len, got)
            ids += chain.from_iterable(got)
        return np.array(ids, dtype=np.uint32), np.array(counts, dtype=np.int64)

    def of_texts(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts end to end, how many each text has)."""
        texts = texts.fill_null("")
        if not self.lib.by_slices:
            got = [self.lib.encode(t)[0] for t in texts.to_pylist()]
            return np.array([i for g in got for i in g], dtype=np.uint32), np.fromiter(map(len, got), dtype=np.int64, count=len(got))
        if texts.type != pa.large_string():
            texts = texts.cast(pa.large_string())
        edges = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
        n_bytes = int(edges[-1] - edges[0])
        if not n_bytes:
            return np.zeros(0, dtype=np.uint32), np.zeros(len(texts), dtype=np.int64)
        data = texts.buffers()[2].slice(int(edges[0]), n_bytes)
        edges = edges - edges[0]
        cut = cut_points(np.frombuffer(data, dtype=np.uint8), edges[1:], self.specials(data, edges))
        slices = pa.Array.from_buffers(pa.large_binary(), len(cut), [None, pa.py_buffer(np.append(cut, n_bytes)), data])
        coded = slices.dictionary_encode()
        number = self.numbers(coded.dictionary).take(coded.indices.to_numpy())
        begin = self.begin.take(number)
        size = self.begin.take(number + 1) - begin
        upto = np.append(0, np.cumsum(size))
        ids = self.ids.take(np.repeat(begin - upto[:-1], size) + np.arange(upto[-1]))
        return ids, np.diff(upto.take(np.searchsorted(cut, edges)))

    def specials(self, data: pa.Buffer, edges: np.ndarray) -> list[tuple[int, int]]:
        """Where special strings stand inside the texts, the longest first where several begin."""
        if self.special is None:
            return []
        whole = data.to_pybytes()
        if not any(s.encode() in whole for s in self.lib.added):
            return []
        return [m.span() for a, b in zip(edges.tolist(), edges[1:].tolist()) if b > a for m in self.special.finditer(whole, a, b)]
