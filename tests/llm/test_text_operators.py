"""Tokens, BPE, segments, decontamination, toxicity, quality, licences, URLs on small inputs."""

import base64
import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

public_tokenizers = pytest.importorskip("public_tokenizers")

from frsketch.llm import bpe, decontaminate, mixing_coder, pretokens, queries, token_counts, token_store, toxicity  # noqa: E402
from frsketch.llm.license_scan import scan_licences  # noqa: E402
from frsketch.llm.quality import low_percentile, quality_frame  # noqa: E402
from frsketch.llm.url_filter import judge_urls, url_list  # noqa: E402

SF = "/root/testdata/sf0.001"
ALPHABET = "ab'srevtmlld 1２\n\t  é.,!’ñ٣ 　字<|"
random.seed(7)
ODD = ["".join(random.choice(ALPHABET) for _ in range(random.randrange(0, 60))) for _ in range(800)]
ODD += ["", " ", "\n\n", "x" * 3000, " " * 500, "a <|endoftext|> b<|endoftext|>", "<|endoftext|>", "it's we'll 'S !'s 's"]
DOCS = [(i, t) for i, t in enumerate(ODD)] + [(-1, None), (5, ODD[5]), (None, "no id")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "zz", t) for i, t in DOCS], "doc_id long, text string, lang string, ids string").repartition(3)


def empty(df):
    return df.where("false")


def test_slices_equal_the_pattern():
    pat = __import__("regex").compile(public_tokenizers.PATTERN)
    s, at = pretokens.Slices(ODD), 0
    for t, n in zip(ODD, s.per_text.tolist()):
        assert [w.decode() for w in s.words[at : at + n]] == pat.findall(t)
        at += n
    ids, comp = np.random.default_rng(0).integers(0, 15, 5000).astype(np.uint16), pretokens.automaton()[2]
    want, acc = [], 0
    for i in ids.tolist():
        want.append(acc)
        acc = int(comp[acc, i])
    assert pretokens.scan(ids, comp, 64).tolist() == want


@pytest.fixture(scope="module")
def reference():
    import tiktoken

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library_and_decodes(spark, docs, reference):
    got = bpe.encode_frame(docs, queries.tokenizer_file("byte_bpe_50k.tiktoken")).collect()
    want = collections.Counter()
    for i, t in DOCS:
        ids = reference.encode_ordinary(t or "")
        want[i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest(), tuple(ids), t or ""] += 1
    assert collections.Counter((r[0], r[1], r[2], r[3], tuple(r[4]), r[5]) for r in got) == want
    c = bpe.codec(queries.tokenizer_file("byte_bpe_50k.tiktoken"))
    ids, at = c.encode_with_offsets("it's 字 here")
    assert c.decode(ids) == "it's 字 here".encode() and at[0] == 0 and at == sorted(at)
    assert bpe.encode_frame(empty(docs), queries.tokenizer_file("byte_bpe_50k.tiktoken")).count() == 0


@pytest.mark.parametrize("chunk,overlap", [(65_536, 1024), (50, 4), (17, 2)])
def test_token_counts_equal_the_library(spark, docs, chunk, overlap):
    path = queries.tokenizer_file("byte_bpe_50k.json")
    tok = token_counts.library(path).tok
    got = {tuple(r) for r in token_counts.count_tokens(docs, path, 40, chunk=chunk, overlap=overlap).collect()}
    want = set()
    for i, t in DOCS:
        n = len(tok.encode(t or "", add_special_tokens=False).ids)
        want.add((i, len((t or "").encode()), n, n > 40))
    assert got == want


def test_segments_round_trip_and_detect_damage():
    rng = np.random.default_rng(1)
    for ids in (np.zeros(0, int), np.array([50256]), rng.integers(0, 50_257, 2500), np.zeros(2049, int), np.minimum(rng.zipf(1.4, 4500), 60_000)):
        raw = mixing_coder.encode_segment(ids)
        assert (mixing_coder.decode_segment(raw) == ids).all()
    bad = bytearray(raw)
    bad[-200] ^= 255
    with pytest.raises(ValueError):
        mixing_coder.decode_segment(bytes(bad))
    assert len(mixing_coder.encode_segment(np.tile([7, 300, 9], 1000))) < 700


def test_token_store(spark, docs, tmp_path):
    path, tok = str(tmp_path / "t"), queries.tokenizer_file("byte_bpe_50k.json")
    some = docs.where("doc_id is null or doc_id < 60 or doc_id > 795")
    token_store.write_tokens(some, path, tok, end_id=0, segment=300)
    got = sorted(token_store.read_tokens(spark, path, with_ids=True).collect(), key=lambda r: r["start"])
    lib, start = token_counts.library(tok).tok, 0
    want = sorted([(i, t or "") for i, t in DOCS if i is None or i < 60 or i > 795], key=lambda p: (p[0] is not None, p[0] or 0, p[1]))
    assert len(got) == len(want)
    for r, (i, t) in zip(got, want):
        ids = [*lib.encode(t, add_special_tokens=False).ids, 0]
        assert (r["doc_id"], r["start"], r["n_tokens"], r["token_ids"]) == (i, start, len(ids), ids)
        assert r["ids_crc32"] == zlib.crc32(np.array(ids, dtype="<u4").tobytes())
        start += len(ids)
    token_store.write_tokens(empty(docs), str(tmp_path / "e"), tok)
    assert token_store.read_tokens(spark, str(tmp_path / "e")).count() == 0


def slow_edit(item, text):
    row = [0] * (len(text) + 1)
    for i, x in enumerate(item, 1):
        new = [i]
        for j, y in enumerate(text, 1):
            new.append(min(row[j - 1] + (x != y), row[j] + 1, new[j - 1] + 1))
        row = new
    return min(row)


def test_best_stretch_is_the_edit_distance():
    rng = random.Random(2)
    for _ in range(300):
        item, text = ([rng.randrange(4) for _ in range(rng.randrange(1, n))] for n in (9, 30))
        assert decontaminate.best_stretch(item, text)[0] == slow_edit(item, text)


def test_leaks_equal_brute_force(spark):
    rng = random.Random(3)
    vocab = [f"w{k}" for k in range(60)]
    items = [(k, " ".join(rng.choice(vocab) for _ in range(n))) for k, n in enumerate((8, 14, 20, 37, 60))] + [(90, None), (91, "...")]
    texts = []
    for k, (_, x) in enumerate(items[:5] * 12):
        w = x.split()
        for _ in range(rng.randrange(len(w) // 3)):
            p, kind = rng.randrange(len(w)), rng.randrange(3)
            w[p : p + (kind > 0)] = [rng.choice(vocab)] if kind < 2 else []
        texts.append((k, " ".join([rng.choice(vocab) for _ in range(rng.randrange(20))] + [y.upper() + "," for y in w] + [rng.choice(vocab)])))
    texts += [(500, None), (501, ""), (502, " ".join(vocab)), (3, texts[3][1])]
    docs = spark.createDataFrame([(i, t, 1) for i, t in texts], "doc_id long, text string, distance int")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontaminate.find_leaks(docs, bench).collect()}
    want = {}
    for i, t in texts:
        for k, x in items[:5]:
            item = decontaminate.words_of(x)
            d = slow_edit(item, decontaminate.words_of(t))
            if d <= decontaminate.edits_of(len(item)):
                want[i, k] = d
    missed = set(want) - set(got)
    assert set(got) <= set(want) and len(missed) <= 0.02 * len(want) and all(got[p] == want[p] for p in got)
    in_parts = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontaminate.find_leaks(docs, bench, most=60).collect()}
    assert set(in_parts) <= set(want) and len(set(want) - set(in_parts)) <= 0.02 * len(want)
    assert decontaminate.find_leaks(docs, empty(bench)).count() == 0 and decontaminate.find_leaks(empty(docs), bench).count() == 0


def test_every_planted_passage_is_found(spark):
    got = {(r["doc_id"], r["item_id"]) for r in queries.op10_decontamination(spark, SF).select("doc_id", "item_id").collect()}
    bench = queries.table(spark, SF, "benchmark").collect()
    exact = {(r["doc_id"], b["item_id"]) for r in queries.table(spark, SF, "documents").collect() for b in bench if b["text"] in r["text"]}
    assert exact and exact <= got


def test_toxicity_learns_and_handles_edges(spark):
    rng = random.Random(4)
    plain = ["house", "river", "window", "garden", "paper", "silver", "morning", "station"]
    rows, labels = [], []
    for k in range(600):
        w = [rng.choice(plain) for _ in range(40)]
        toxic = k % 4 == 0
        if toxic:
            for _ in range(3):
                w[rng.randrange(40)] = rng.choice(["vilejerk", "vilejerks", "dumbvile"])
        rows.append((k, " ".join(w)))
        labels.append((k, int(toxic), 1))
    rows += [(9001, None), (9002, ""), (9002, "house")]
    docs, lab = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int, quality int")
    got = {r["doc_id"]: r for r in toxicity.toxicity_frame(docs, lab).collect()}
    held = [k for k in range(600) if zlib.crc32(str(k).encode()) % 5 == 0]
    assert all(got[k]["held_out"] for k in held) and not got[next(k for k in range(600) if k not in held)]["held_out"]
    assert np.mean([got[k]["predicted"] == (k % 4 == 0) for k in held]) > 0.97
    assert all(0 <= r["score"] <= 1 for r in got.values()) and len(toxicity.toxicity_frame(docs, lab).collect()) == len(rows)
    kept = toxicity.ordinary_only(docs.withColumn("source", F.lit("s")), lab)
    assert kept.columns == ["doc_id", "text", "source"] and 430 < kept.count() < 470
    assert {r["predicted"] for r in toxicity.toxicity_frame(docs, empty(lab)).collect()} == {0}
    assert toxicity.toxicity_frame(empty(docs), lab).count() == 0


def plain_kneser_ney(rows, order=5, d=0.75):
    """word -> log-likelihood ratio, by dictionaries."""
    grams = collections.defaultdict(lambda: [0, 0, 0])  # toxic, ordinary, all
    for t, c in rows:
        for w in (t or "").lower().split():
            z = "\1" * (order - 1) + w + "\2"
            for k in range(len(w) + 1):
                g = grams[z[k : k + order]]
                g[2] += 1
                if c is not None:
                    g[1 - c] += 1
    levels, above = {}, set(grams)
    for n in range(order - 1, 0, -1):
        levels[n] = collections.Counter(g[1:] for g in above)
        above = set(levels[n])

    def mixed(count, follow, below):
        total = sum(follow)
        return max(count - d, 0) / total + d * sum(x > 0 for x in follow) / total * below if total else below

    def ratio(w):
        z, out = "\1" * (order - 1) + w + "\2", 0.0
        for k in range(len(w) + 1):
            g, p = z[k : k + order], 1.0 / 0x110000
            for n in range(1, order):
                at = g[order - n :]
                p = mixed(levels[n].get(at, 0), [v for x, v in levels[n].items() if x[:-1] == at[:-1]], p)
            near = [v for x, v in grams.items() if x[:-1] == g[:-1]]
            own = grams.get(g, [0, 0, 0])
            p = mixed(own[2], [v[2] for v in near], p)
            out += np.log(mixed(own[0], [v[0] for v in near], p)) - np.log(mixed(own[1], [v[1] for v in near], p))
        return out

    return ratio


def test_toxicity_ratios_equal_plain_kneser_ney(spark, monkeypatch):
    rng = random.Random(9)
    vocab = ["rot", "rotten", "Rose", "été", "字字", "a", "zz" * 20]
    rows = [(" ".join(rng.choice(vocab) for _ in range(rng.randrange(8))), rng.choice([0, 1, None])) for _ in range(40)] + [(None, 1), ("", 0), (" \n", None)]
    monkeypatch.setattr(toxicity, "TALLY", 3)
    model = toxicity.fit_counts(spark.createDataFrame(rows, "text string, cls int").repartition(3))
    ratio = plain_kneser_ney(rows)
    words = [*map(str.lower, vocab), "new", "rotter"]
    assert np.allclose(model.ratios(words), [ratio(w) for w in words], rtol=1e-6, atol=1e-6)
    texts = [(i, " ".join(rng.choice(words) for _ in range(n)), "x") for i, n in enumerate((1, 7, 40_000))]
    docs = spark.createDataFrame(texts, "doc_id int, _text string, _ratio string")
    got = {r["doc_id"]: r["r"] for r in toxicity.log_ratio_frame(docs, model, "_text", None, "r").collect()}
    each = {w: ratio(w) for w in words}
    for i, t, _ in texts:
        assert np.isclose(got[i], sum(each[w] for w in t.split()) / (len(t.replace(" ", "")) + len(t.split())), rtol=1e-6, atol=1e-6)


def test_toxicity_with_clashing_columns(spark):
    rows = [(i, "vile words here" if i % 2 else "calm river stones", "a", 1.0, "t", "x") for i in range(60)] + [(None, None, "a", 1.0, "t", "x")]
    docs = spark.createDataFrame(rows, "doc_id int, text string, _ratio string, _score double, _text string, cls string")
    labels = spark.createDataFrame([(i, i % 2, "q") for i in range(60)], "doc_id int, toxic int, text string")
    kept = toxicity.ordinary_only(docs, labels)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect() if r["doc_id"] is not None) == list(range(0, 60, 2))


def brute_counts(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    sh = [tuple(w[k : k + 5]) for k in range(len(w) - 4)]
    c, cover = collections.Counter(sh), set()
    for k, s in enumerate(sh):
        if c[s] > 1:
            cover.update(range(k, k + 5))
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), len(lines) - len(set(lines)), len(cover)


def test_quality_counts_and_verdict(spark):
    rng = random.Random(5)
    texts = [" ".join(rng.choice("ab") for _ in range(rng.randrange(60))) for _ in range(150)] + ["a b c d e f g " * 30, "x\n\nx\n x\ny", "\x0b\x0c", "#*$ <>|&% ü字"]
    texts += [" ".join(rng.choice(["good", "clean", "prose", "words"]) + str(rng.randrange(9)) for _ in range(80)) for _ in range(150)]
    texts += [" ".join(rng.choice("#$%&") * 4 + str(rng.randrange(99)) for _ in range(80)) for _ in range(60)]
    rows = [(i, t, "q") for i, t in enumerate(texts)] + [(999, None, "q")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string")
    lab = spark.createDataFrame([(i, int(150 < i < 304)) for i in range(len(texts))], "doc_id long, quality int")
    got = {r["doc_id"]: r for r in quality_frame(docs, lab).collect()}
    for i, t, _ in rows:
        n, chars, sym, dup, rep = brute_counts(t or "")
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, sym, dup, rep), t
        assert r["base_failed"] == (n < 10 or 100 * rep > 20 * n) and not (r["base_failed"] and r["kept"])
    good, bad = [got[i]["kept"] for i in range(154, 304)], [got[i]["kept"] for i in range(304, 364)]
    assert np.mean(good) > 0.97 and not any(bad)
    assert quality_frame(empty(docs), lab).count() == 0 and quality_frame(docs, None).where("kept").count() > 0


def test_licences(spark):
    rows = [
        (1, "a/LICENSE", "Released under the MIT License."),
        (2, "a/b/x.py", "code here"),
        (3, "a/b/c/COPYING", "This work is licensed under the GNU General Public License, version 3.\nmore words"),
        (4, "a/b/c/d/y.py", "more"),
        (5, "z/w.py", "# Licensed under the Apache License, Version 2.0.\nimport x"),
        (6, "z/v.py", "the license of the river"),
        (7, None, None),
        (2, "a/b/x.py", "code here"),
        (8, "q.py", ""),
        (9, "a/n.py", "Licensed under CC BY-NC 4.0."),
    ]
    df = spark.createDataFrame([(i, p, t, "") for i, p, t in rows], "doc_id int, path string, text string, dir string")
    got = sorted([(r["doc_id"], r["own"], r["licence"], r["from_dir"]) for r in scan_licences(df, F.col("path")).collect()], key=str)
    want = [(1, "MIT", "MIT", None), (2, None, "MIT", "a"), (2, None, "MIT", "a"), (3, "GPL-3.0", "GPL-3.0", None), (4, None, "GPL-3.0", "a/b/c"), (5, "Apache-2.0", "Apache-2.0", None), (6, None, None, None), (7, None, None, None), (8, None, None, None), (9, "CC-BY-NC-4.0", "CC-BY-NC-4.0", None)]
    assert got == sorted(want, key=str)
    assert scan_licences(empty(df), F.col("path")).count() == 0


def test_licences_over_lines_and_in_full(spark):
    gpl = "# Copyright (C) 2020 A. Body\n#\n# This program is free software: you can redistribute it and/or modify\n# it under the terms of the GNU General Public License as published by\n# the Free Software Foundation, either version 3 of the License, or\n# (at your option) any later version.\n#\n# This program is distributed in the hope that it will be useful,\n# but WITHOUT ANY WARRANTY; without even the implied warranty of\n# MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the\n# GNU General Public License for more details.\nimport os\n"
    mit = "MIT License\n\nCopyright (c) 2019 A. Body\n\nPermission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files (the \"Software\"), to deal\nin the Software without restriction, including without limitation the rights\nto use, copy, modify, merge, publish, distribute, sublicense, and/or sell\ncopies of the Software, and to permit persons to whom the Software is\nfurnished to do so, subject to the following conditions:\n"
    rows = [
        (1, gpl, "GPL-3.0"),
        (2, mit, "MIT"),
        (3, "                    GNU GENERAL PUBLIC LICENSE\n                       Version 3, 29 June 2007\n\n Copyright (C) 2007", "GPL-3.0"),
        (4, "Copyright 2020 A. Body. All rights reserved. Released under the MIT License, see the file for all of it.", "MIT"),
        (5, "// SPDX-License-Identifier: GPL-3.0-or-later\nint x;", "GPL-3.0"),
        (6, "/* Licensed under the Apache\n * License, Version 2.0. */", "Apache-2.0"),
        (7, "// SPDX-License-Identifier: Zlib", None),
        (8, "the program is free and the people of the city use the library for any purpose of the day", None),
        (9, None, None),
    ]
    rows += [(k, "the river and the city of the north", None) for k in range(10, 60)]
    df = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id int, text string")
    got = {r["doc_id"]: r["own"] for r in scan_licences(df, F.lit("a/x"), F.lit(False)).collect()}
    assert got == {i: want for i, _, want in rows}


def brute_url(url, entries, default="allow"):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = re.match(r"[^/?#]*", rest).group()
    path = re.match(r"[^?#]*", rest[len(host) :]).group()
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(kind, len(h + p), h + p, a) for h, p, a, kind in entries if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=(0, 0, None, default))
    return host, path, best[2] if best[0] == 1 else None, best[3]


@pytest.mark.parametrize("many", [0, 5000])
def test_urls(spark, many):
    urls = ["http://WWW.Example.com/en/1?x#y", "https://example.com/en/", "https://a.example.com/e", "x.net/es/", "http://x.net/es", "ftp://x.net/es/q", "http://com", "http://com/", "http://", None, "", "http://notexample.com/en/", "http://b.net?u=http://c.com/", "http://x.org/a://b.com/", "http://spam.org/x", "http://a.b.c.d.e.spam.org/", "http://exämple.com/en/"]
    rules = queries.URL_RULES + [(f"h{k}.org", f"/p{k}/", "block") for k in range(many)]
    listed = [("spam.org", "/", "block")]
    urls += [f"http://s.h{k}.org/p{k}/z" for k in range(0, many, 97)]
    pages = spark.createDataFrame([(i, u, "r") for i, u in enumerate(urls)] + [(0, urls[0], "r")], "page_id long, url string, row string")
    got = sorted([(r["page_id"], r["host"], r["path"], r["rule"], r["verdict"]) for r in judge_urls(pages, url_list(spark, rules), url_list(spark, listed)).collect()], key=str)
    entries = [(*r, 1) for r in rules] + [(*r, 0) for r in listed]
    assert got == sorted([(i, *brute_url(u, entries)) for i, u in [*enumerate(urls), (0, urls[0])]], key=str)
    assert judge_urls(empty(pages), url_list(spark, rules)).count() == 0
    assert judge_urls(pages, url_list(spark, []), None).where("verdict = 'allow' and rule is null").count() == len(urls) + 1


def test_every_trusted_row_counts(spark):
    rng = random.Random(8)
    docs = spark.createDataFrame([(i, " ".join(rng.choice("abcdefgh") + str(rng.randrange(30)) for _ in range(40))) for i in range(300)], "doc_id long, text string")
    lab = spark.range(60_000).selectExpr("id as doc_id", "1 as quality")  # all texts are trusted: nothing tells the two models apart
    assert {r["score"] for r in quality_frame(docs, lab).collect()} == {0.0}
    x = docs.selectExpr("cast(doc_id * doc_id as double) as x")
    for share in (0.0, 0.005, 0.4, 1.0):
        assert low_percentile(x, "x", share) == pytest.approx(x.selectExpr(f"percentile(x, {share})").first()[0])
