"""Token files: ids of columns of texts, and what the coder of segments costs and rejects."""

import random
import time

import numpy as np
import pyarrow as pa
import pytest

pytest.importorskip("public_tokenizers")

from frsketch.llm import mixing_coder, queries, slice_ids, token_counts  # noqa: E402

PIECES = ["'", "s", "t", "re", "ve", "m", "ll", "d", " ", "  ", "\n", "\t", " ", "　", "a", "Z", "é", "ß", "漢", "1", "²", "٣", ".", "!", "😀", "́", "​", "\r\n", "<|endoftext|>", "<|", "|>"]


@pytest.fixture(scope="module")
def lib():
    return token_counts.library(queries.tokenizer_file("byte_bpe_50k.json"))


def holds(known, texts):
    ids, counts = known.of_texts(pa.array(texts, pa.string()))
    want = [known.lib.tok.encode(t or "", add_special_tokens=False).ids for t in texts]
    assert counts.tolist() == list(map(len, want))
    assert ids.tolist() == [i for w in want for i in w]


def test_column_ids_equal_the_library_on_whole_texts(lib):
    rng = random.Random(5)
    odd = ["".join(rng.choice(PIECES) for _ in range(rng.randrange(0, 40))) for _ in range(1500)]
    known = slice_ids.SliceIds(lib)
    holds(known, odd)
    for some in ([], [None, "", None], ["", "end 'l", "l", " ", None, "x"], ["".join(odd), None, "x" * 3000, " " * 500], ["<|endoftext|>", "a <|endoftext|>", "<|endoftext|><|endoftext|> "]):
        holds(known, some)
    for k in range(0, 1500, 50):
        holds(known, odd[k : k + 50])
    tight = slice_ids.SliceIds(lib, limit=2_000)
    for k in range(0, 300, 20):
        holds(tight, odd[k : k + 20])
        assert len(tight.ids) == tight.begin[-1] and len(tight.begin) == len(tight.known) + 1
    sliced = pa.array(odd, pa.string()).slice(7, 30)
    assert known.of_texts(sliced)[0].tolist() == known.of_texts(pa.array(odd[7:37], pa.string()))[0].tolist()


def test_each_distinct_slice_goes_through_the_library_once(lib, monkeypatch):
    known, seen = slice_ids.SliceIds(lib), []
    own = known.encode
    monkeypatch.setattr(known, "encode", lambda words: (seen.extend(words.to_pylist()), own(words))[1])
    for _ in range(3):
        known.of_texts(pa.array(["one two one two", " two one", None]))
    assert sorted(seen) == [b" one", b" two", b"one"]


def test_coding_costs_a_few_microseconds_an_id():
    ids = np.minimum(np.random.default_rng(2).zipf(1.3, 400_000), 50_000)

    def loop():
        t = time.thread_time()
        sum(range(50_000))
        return (time.thread_time() - t) * 1000

    slow = sorted(loop() for _ in range(15))[7]
    t = time.process_time()
    assert (mixing_coder.decode_segment(mixing_coder.encode_segment(ids)) == ids).all()
    assert (time.process_time() - t) / slow / len(ids) < 3e-6


def test_blocks_of_any_ids_and_damage_anywhere():
    rng = np.random.default_rng(3)
    for ids in (np.array([2**32 - 1, 0, 5, 2**32 - 1]), np.arange(2048) * 2_000_003 % 2**31, np.repeat(7, 4096), np.tile(np.arange(2048), 2)):
        assert (mixing_coder.decode_segment(mixing_coder.encode_segment(ids)) == ids).all()
    ids = np.minimum(rng.zipf(1.3, 5000), 50_000)
    raw = mixing_coder.encode_segment(ids)
    for _ in range(40):
        bad = bytearray(raw)
        bad[int(rng.integers(80, len(raw) - 8))] ^= int(rng.integers(1, 256))
        with pytest.raises(ValueError):
            mixing_coder.decode_segment(bytes(bad))
