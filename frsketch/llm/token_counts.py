"""Token counts with the vocabulary's own library, huge texts in overlapping chunks.

A text longer than ``chunk`` characters is encoded in pieces that overlap. Each piece comes with
character offsets. Two neighbours are spliced at a boundary that is proven stable: the start of a
white-space run after a character that is not white space. The split pattern starts a slice there
whatever stands before, and no merge crosses a slice, so the tokens on either side are those of the
whole text. The splice also checks that both pieces have a token edge there; if no such place exists
in the overlap, the overlap doubles until there is one or the pieces become one.

Texts within one chunk are cut into slices, each distinct slice goes through the library once (a cache
bounded in bytes, which a task leaves empty), and counts are added up. Special strings in a text are single tokens, as the
library's default has it; they are cut out first.

Nulls count as empty (0 bytes, 0 tokens). Repeated rows keep a row each, an empty table gives an
empty table, and other columns are not read.
"""

from __future__ import annotations

import json
import os
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm.bpe import text_batches
from frsketch.llm.pretokens import Slices
from frsketch.llm.shared import Cache, give_back, texts as bounded

CHUNK = 65_536
OVERLAP = 1_024
ENTRY = 220  # bytes of a cached slice besides its own
EDGE = regex.compile(r"(?<=\S)\s")


class Library:
    """A ``tokenizers`` file with a bounded cache of encoded slices."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_padding()
        self.tok.no_truncation()
        with open(path, encoding="utf-8") as f:
            kind = json.load(f)
        pre = kind.get("pre_tokenizer") or {}
        self.by_slices = kind.get("normalizer") is None and pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space")
        added = {t["content"]: t["id"] for t in kind.get("added_tokens", [])}
        self.added = added
        self.special = regex.compile("|".join(map(regex.escape, sorted(added, key=len, reverse=True)))) if added else None
        self.cache = Cache(ENTRY)

    def slice_ids(self, words: list[bytes]) -> dict[bytes, tuple[int, ...]]:
        missing = self.cache.lacking(set(words))
        for at in range(0, len(missing), 20_000):
            some = missing[at : at + 20_000]
            got = self.tok.encode_batch_fast([w.decode() for w in some], add_special_tokens=False)
            self.cache.update((w, tuple(e.ids)) for w, e in zip(some, got))
        return self.cache

    def encode(self, text: str) -> tuple[list[int], list[tuple[int, int]]]:
        e = self.tok.encode(text, add_special_tokens=False)
        return e.ids, e.offsets

    def pieces(self, text: str) -> list[str | int]:
        """The text between special strings, and the ids of these."""
        if self.special is None:
            return [text]
        out: list[str | int] = []
        at = 0
        for m in self.special.finditer(text):
            out += [text[at : m.start()], self.added[m.group()]]
            at = m.end()
        return [*out, text[at:]] if at else [text]


def chunked_ids(lib: Library, text: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[int]:
    """Ids of a text encoded in overlapping chunks."""
    out: list[int] = []
    begin = 0  # start of the present chunk
    while True:
        end = begin + chunk
        if end + overlap >= len(text):
            return out + lib.encode(text[begin:])[0]
        widen, cut = overlap, None
        while cut is None:
            stop = min(len(text), end + widen)
            if stop == len(text):
                return out + lib.encode(text[begin:])[0]
            ids, offsets = lib.encode(text[begin:stop])
            after_ids, after = lib.encode(text[end:stop])
            edges, after_edges = {a for a, _ in offsets}, {a for a, _ in after}
            for m in EDGE.finditer(text, end + 1, stop - 1):
                if m.start() - begin in edges and m.start() - end in after_edges:
                    cut = m.start()
                    break
            widen *= 2
        out += [i for i, (a, _) in zip(ids, offsets) if a < cut - begin]
        begin = cut


@lru_cache(maxsize=2)
def library(path: str) -> Library:
    return Library(path)


def ids_of_texts(lib: Library, texts: list[str], chunk: int = CHUNK, overlap: int = OVERLAP):
    """Per text, its pieces' ids as a list of tuples (nothing is flattened)."""
    plain: list[str] = []
    plan: list[list] = []
    for t in texts:
        parts = []
        for p in lib.pieces(t):
            if isinstance(p, int):
                parts.append((p,))
            elif len(p) > chunk or not lib.by_slices:
                parts.append(chunked_ids(lib, p, chunk, overlap) if lib.by_slices else lib.encode(p)[0])
            elif p:
                parts.append(len(plain))
                plain.append(p)
        plan.append(parts)
    s = Slices(plain)
    table = lib.slice_ids(s.words)
    ends = np.cumsum(s.per_text).tolist() if plain else []
    for parts in plan:
        got: list = []
        for p in parts:
            if isinstance(p, int):
                got += [table[w] for w in s.words[ends[p - 1] if p else 0 : ends[p]]]
            else:
                got.append(p)
        yield got


def count_tokens(docs: DataFrame, path: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text", chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """id, n_bytes, n_tokens, over_limit."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        lib = library(path)
        try:
            for batch in batches:
                keys = batch.column(0)
                for at, texts in text_batches(batch.select([1]), text_col):
                    n = [sum(map(len, parts)) for parts in ids_of_texts(lib, texts, chunk, overlap)]
                    size = [len(t.encode()) for t in texts]
                    yield pa.RecordBatch.from_arrays(
                        [keys.slice(at, len(texts)), pa.array(size, pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                        [id_col, "n_bytes", "n_tokens", "over_limit"],
                    )
        finally:
            lib.cache.clear()
            give_back()

    return bounded(docs).select(id_col, F.col(text_col)).mapInArrow(run, f"{id_col} {kind}, n_bytes long, n_tokens long, over_limit boolean")
