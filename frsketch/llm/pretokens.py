"""Vectorised pre-tokenisation for byte-level BPE, without regex.

The split pattern (contractions, ``" ?"`` + letters / numbers / others, white-space runs that give
their last character to what follows) is a finite automaton of eight states over eight symbol
classes. Every symbol is a function on states and functions compose associatively, so the states of
all positions come from a prefix scan over function ids: blocks are scanned side by side as array
rows, then the block totals are folded and pushed down. Texts are laid end to end; the first
character of each text uses a constant function, so no text sees its neighbour.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import regex

# states: what stands before the next character
FRESH, LETTERS, NUMBERS, OTHERS, SPACES, JOIN, ONE_LEFT, TWO_LEFT = range(8)
# symbols
S_LETTER, S_NUMBER, S_OTHER, S_SHORT, S_LONG, S_SPACE, S_LAST_BLANK, S_LAST_WS = range(8)
# the contractions of the pattern, fixed values
CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")


def _step(state: int, sym: int) -> tuple[int, bool]:
    """(next state, does a slice start at this character)."""
    if sym == S_LETTER:
        if state in (LETTERS, JOIN):
            return LETTERS, False
        if state == TWO_LEFT:
            return ONE_LEFT, False
        if state == ONE_LEFT:
            return FRESH, False
        return LETTERS, True
    if sym == S_NUMBER:
        return NUMBERS, state not in (NUMBERS, JOIN)
    if sym in (S_OTHER, S_SHORT, S_LONG):
        if state in (OTHERS, JOIN):
            return OTHERS, False
        return {S_OTHER: OTHERS, S_SHORT: ONE_LEFT, S_LONG: TWO_LEFT}[sym], True
    if sym == S_SPACE:
        return SPACES, state != SPACES
    return (JOIN, True) if sym == S_LAST_BLANK else (FRESH, True)


@lru_cache(maxsize=1)
def automaton():
    """(function id of each symbol, of each symbol at a text's start, composition table,
    images of FRESH, start flags by state and symbol). Ids enumerate the closure under composition."""
    gens = [tuple(_step(s, y)[0] for s in range(8)) for y in range(8)]
    firsts = [(g[FRESH],) * 8 for g in gens]
    ids: dict[tuple[int, ...], int] = {tuple(range(8)): 0}
    todo = [*gens, *firsts]
    for f in todo:
        ids.setdefault(f, len(ids))
    grown = True
    while grown:
        grown = False
        for f in list(ids):
            for g in gens + firsts:
                h = tuple(g[x] for x in f)
                if h not in ids:
                    ids[h] = len(ids)
                    grown = True
    fs = list(ids)
    comp = np.zeros((len(fs), len(fs)), dtype=np.uint16)
    for i, f in enumerate(fs):
        for j, g in enumerate(fs):
            h = tuple(g[x] for x in f)
            comp[i, j] = ids[h]
    flags = np.array([[_step(s, y)[1] for y in range(8)] for s in range(8)])
    image = np.array([f[FRESH] for f in fs], dtype=np.uint8)
    return (
        np.array([ids[g] for g in gens], dtype=np.uint16),
        np.array([ids[g] for g in firsts], dtype=np.uint16),
        comp,
        image,
        flags,
    )


@lru_cache(maxsize=1)
def codepoint_classes() -> np.ndarray:
    """0 letter, 1 number, 2 other, 3 white space, 4 the blank U+0020, by code point."""
    out = np.full(0x110000, 2, dtype=np.uint8)
    text = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    for k, cls in ((0, r"\p{L}+"), (1, r"\p{N}+"), (3, r"\s+")):
        for m in regex.finditer(cls, text):
            a, b = ord(text[m.start()]), ord(text[m.end() - 1])
            out[a : b + 1] = k
    out[0xD800:0xE000] = 2
    out[0x20] = 4
    return out


def scan(ids: np.ndarray, comp: np.ndarray, block: int = 512) -> np.ndarray:
    """Exclusive prefix composition of function ids, in blocks."""
    n, m = len(ids), comp.shape[0]
    flat = comp.reshape(-1)
    rows = -(-n // block)
    grid = np.zeros(rows * block, dtype=np.uint16)
    grid[:n] = ids
    grid = np.ascontiguousarray(grid.reshape(rows, block).T)
    before = np.empty_like(grid)
    acc = np.zeros(rows, dtype=np.uint16)
    for k in range(block):
        before[k] = acc
        acc = flat[acc.astype(np.intp) * m + grid[k]]
    carry = np.zeros(rows, dtype=np.uint16)
    c = 0
    for k, a in enumerate(acc.tolist()):
        carry[k] = c
        c = int(comp[c, a])
    out = flat[carry.astype(np.intp)[None, :] * m + before]
    return out.T.reshape(-1)[:n]


def slice_starts(codes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Start flags of the slices. codes: code points of all texts end to end; first: flags of each
    text's first character."""
    n = len(codes)
    if not n:
        return np.zeros(0, dtype=bool)
    gens, firsts, comp, image, flags = automaton()
    cls = codepoint_classes()[codes]
    last = np.empty(n, dtype=bool)  # last character of its text
    last[:-1] = first[1:]
    last[-1] = True
    solid_next = np.zeros(n, dtype=bool)
    solid_next[:-1] = (cls[1:] < 3) & ~last[:-1]
    sym = cls.copy()
    ws = cls >= 3
    sym[ws] = S_SPACE
    sym[ws & solid_next] = S_LAST_WS
    sym[(cls == 4) & solid_next] = S_LAST_BLANK
    quote = np.flatnonzero((codes == 0x27) & ~last)
    if len(quote):
        a = codes[quote + 1]
        b = np.where(last[quote + 1], 0, codes[np.minimum(quote + 2, n - 1)])
        for c in CONTRACTIONS:
            if len(c) == 1:
                sym[quote[a == ord(c)]] = S_SHORT
            else:
                sym[quote[(a == ord(c[0])) & (b == ord(c[1]))]] = S_LONG
    ids = gens[sym]
    ids[first] = firsts[sym[first]]
    state = image[scan(ids, comp)]
    state[first] = FRESH
    return flags[state, sym]


class Slices:
    """Pre-tokens of a list of texts: ``words`` (bytes, in order), ``per_text`` (how many each)."""

    def __init__(self, texts: list[str]):
        raws = [t.encode() for t in texts]
        whole = "".join(texts)
        codes = np.frombuffer(whole.encode("utf-32-le"), dtype=np.uint32)
        lens = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        ends = np.cumsum(lens)
        begins = ends - lens
        first = np.zeros(len(codes), dtype=bool)
        first[begins[lens > 0]] = True
        flags = slice_starts(codes, first)
        starts = np.flatnonzero(flags)
        if len(whole) == sum(map(len, raws)):
            cut = starts
        else:
            width = 1 + (codes >= 0x80).astype(np.int64) + (codes >= 0x800) + (codes >= 0x10000)
            cut = (np.cumsum(width) - width)[starts]
        buf = b"".join(raws)
        at = cut.tolist()
        at.append(len(buf))
        self.n_bytes = np.fromiter(map(len, raws), dtype=np.int64, count=len(raws))
        self.words = [buf[a:b] for a, b in zip(at, at[1:])]
        self.per_text = np.searchsorted(starts, ends) - np.searchsorted(starts, begins)
        self.starts = starts
