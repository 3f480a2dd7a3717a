"""Text operators against brute force, the tokenizers' own libraries and SQL, on odd and given rows."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from conftest import SF
from repeatfold.llm import bpe, license_scan, mixing, ngram_join, packing, quality, queries, substring_dedup, token_count
from repeatfold.llm.words import hash_spans, text_slices, window_hashes, word_slices

SPACES = r"[^ \t-\r]+"
LONG = " ".join(f"w{i % 91}" for i in range(30_000))
PASSAGE = " ".join(f"p{i}" for i in range(60))


def odd_rows():
    rng = random.Random(3)
    base = [" ".join(rng.choice("abcdefgh") * rng.randint(1, 3) for _ in range(120)) for _ in range(3)]
    near = [base[0].replace("a", "A", 5), base[0] + " tail of it", base[1][:-10]]
    texts = [None, "", " \t\n", "one", "one two three four", *base, *near, base[0], PASSAGE, f"x {PASSAGE} y", f"{PASSAGE} {PASSAGE}", LONG, "é 日本 😀 '<|endoftext|>' don't", "same " * 100, "x" * 5000]
    rows = [(i, t, "en" if i % 2 else None, f"src{i % 3}", len(t or ""), "extra") for i, t in enumerate(texts)]
    return rows + [rows[6], (None, "null id " * 10, "de", "src1", 80, "extra")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(odd_rows(), "doc_id long, text string, lang string, source string, n_chars long, keep string").repartition(5).cache()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def pairs(df):
    return [tuple(r) for r in df.select("doc_id", "text").collect()]


def test_words_are_those_of_the_pattern():
    texts = [r[1] for r in odd_rows()]
    got = []
    for s in word_slices(pa.array(texts, pa.string())):
        got += [[s.word(i).decode() for i in range(s.at[d], s.at[d + 1])] for d in range(s.n)]
    assert got == [re.findall(SPACES, t or "") for t in texts]


def test_hashes_tell_words_and_windows_apart():
    words = [f"{a}{b}" for a in "abcdefghij" * 3 for b in range(300)] + ["x" * n for n in range(1, 1500)]
    data = np.frombuffer("".join(words).encode(), np.uint8)
    end = np.cumsum([len(w) for w in words])
    h = hash_spans(data, end - np.array([len(w) for w in words]), end)
    assert len({*h.tolist()}) == len(set(words)) and dict(zip(words, h.tolist(), strict=True)) == {w: x for w, x in zip(words, h.tolist(), strict=True)}
    w = window_hashes(np.array([1, 2, 3, 1, 2, 3, 4], np.uint64), 3)
    assert w[0] == w[3] and len(set(w.tolist())) == 4


def brute_components(rows, least=80):
    sets = []
    for _, t in rows:
        w = re.findall(SPACES, re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    label = list(range(len(rows)))

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    where = defaultdict(list)
    for i, s in enumerate(sets):
        seen = Counter(j for x in s for j in where[x])
        for j, o in seen.items():
            if 100 * o >= least * (len(s) + len(sets[j]) - o):
                label[find(i)] = find(j)
        for x in s:
            where[x].append(i)
    ids = defaultdict(list)
    for i, (d, _) in enumerate(rows):
        if d is not None:
            ids[find(i)].append(d)
    return sorted(((d, len(sets[i]), min(ids[find(i)], default=d)) for i, (d, _) in enumerate(rows)), key=str)


@pytest.mark.parametrize("which", ["odd", "docs"])
def test_ngram_join(which, request):
    df = request.getfixturevalue(which)
    got = sorted(map(tuple, ngram_join.similar_components(df).collect()), key=str)
    assert got == brute_components(pairs(df))


def without_ids(rows):
    """A third of the ids go, and with them those of whole groups and of bridges."""
    words = [f"b{i}" for i in range(104)]
    chain = [(900, " ".join(words[:100])), (None, " ".join(words[2:102])), (902, " ".join(words[4:104]))]
    alone = [(None, "no id at all " * 9), (None, "no id at all " * 9 + "x")]
    return [(None if i % 3 == 1 or t == "same " * 100 else d, t) for i, (d, t, *_) in enumerate(rows)] + chain + alone


@pytest.mark.parametrize(("split", "very"), [(4000, 13), (2, 1)])
def test_ngram_join_of_rows_without_ids(spark, split, very, monkeypatch):
    """Rows without an id bridge others; very frequent tokens are dealt over partitions."""
    monkeypatch.setattr(ngram_join, "SPLIT", split)
    monkeypatch.setattr(ngram_join, "VERY_HOT", very)
    rows = without_ids(odd_rows())
    words = "k1 long, k2 long, cls long, _id long, grp string"
    df = spark.createDataFrame([(d, t, 1, 2, 3, 4, "x") for d, t in rows], f"doc_id long, text string, {words}").repartition(5)
    got = sorted(map(tuple, ngram_join.similar_components(df).collect()), key=str)
    assert got == brute_components(rows)
    label = {(r[0], r[1]): r for r in got}
    assert {r[2] for r in got if r[0] in (900, 902)} == {900} and len(label) <= len(got)
    kept = ngram_join.representatives(df)
    assert kept.columns == df.columns
    texts = [(r["doc_id"], r["text"]) for r in kept.collect()]
    assert len(texts) == len(set(texts)) and sum((t or "").startswith("no id at all") for _, t in texts) == 1
    assert {t for d, t in texts if d == 900 or (t or "").startswith("b2 ")} == {chain for d, chain in rows if d == 900}
    groups = {(r[2], r[1]) for r in got if r[2] is not None and r[1]}
    assert {c for c, _ in groups} == {d for d, t in texts if d is not None and re.findall(SPACES, t or "")}


def test_ngram_join_in_blocks(docs, monkeypatch):
    monkeypatch.setattr(ngram_join, "SPLIT", 2)
    monkeypatch.setattr(ngram_join, "FIRST", 0)  # everything is left to the exact phase
    assert sorted(map(tuple, ngram_join.similar_components(docs).collect()), key=str) == brute_components(pairs(docs))


def test_signature_tree_loses_no_pair():
    rng = np.random.default_rng(1)
    sets = []
    for _ in range(60):
        base = rng.integers(0, 2**63, rng.integers(5, 400)).astype(np.uint64)
        for _ in range(5):
            keep = base[rng.random(len(base)) > rng.random() * 0.25]
            sets.append(np.unique(keep) if len(keep) else base[:1])
    n = len(sets)
    want = {(i, j) for i in range(n) for j in range(i) if 100 * (o := len(np.intersect1d(sets[i], sets[j]))) >= 80 * (len(sets[i]) + len(sets[j]) - o)}
    tree = ngram_join.SignatureTree(np.array([len(s) for s in sets]), [ngram_join.bitmap(s) for s in sets], np.arange(n), None, 80)
    got = {(max(a, b), min(a, b)) for i, j in tree.candidates() for a, b in zip(i.tolist(), j.tolist(), strict=True)}
    assert want <= got and len(got) < n * n / 8


def brute_dedup(rows, width=35):
    words = [re.findall(SPACES, t or "") for _, t in rows]
    count = Counter(tuple(w[k : k + width]) for w in words for k in range(len(w) - width + 1))
    out = []
    for (d, _), w in zip(rows, words, strict=True):
        gone = set()
        for k in range(len(w) - width + 1):
            if count[tuple(w[k : k + width])] > 1:
                gone.update(range(k, k + width))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((d, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize(("which", "shard"), [("odd", 2000), ("odd", 1), ("docs", 2000), ("docs", 2)])
def test_substring_dedup(which, shard, request, monkeypatch):
    """Small shards send nearly every anchor through longer ones, and cut periodic texts."""
    monkeypatch.setattr(substring_dedup, "SHARD", shard)
    monkeypatch.setattr(substring_dedup, "SHARD_WORDS", 50 * shard)
    monkeypatch.setattr(substring_dedup, "RUN", max(16, shard))
    df = request.getfixturevalue(which)
    out = substring_dedup.dedup(df.select("doc_id", "text"), with_text=False)
    assert sorted(map(tuple, out.collect()), key=str) == brute_dedup(pairs(df))


def test_substring_dedup_keeps_texts_and_columns(odd):
    out = substring_dedup.dedup(odd)
    assert set(out.columns) == {*odd.columns, "n_words", "n_removed", "kept_sha256"}
    for r in out.collect():
        assert hashlib.sha256(r["text"].encode()).hexdigest() == r["kept_sha256"] and r["keep"] == "extra"
        assert len(re.findall(SPACES, r["text"])) == r["n_words"] - r["n_removed"]


def test_substring_dedup_with_clashing_names_and_text_ids(odd):
    mine = odd.selectExpr("cast(doc_id as string) doc_id", "text", "1 spans", "2 _did", "3 _uid", "4 k1", "5 _k1", "6 _spans", "'x' n_words", "7 anchor")
    out = substring_dedup.dedup(mine)
    assert set(out.columns) == {*mine.columns, "n_removed", "kept_sha256"}
    rows = out.collect()
    assert all((r["spans"], r["_did"], r["_uid"], r["k1"], r["_k1"], r["_spans"], r["anchor"]) == (1, 2, 3, 4, 5, 6, 7) for r in rows)
    assert sorted([(r["doc_id"] and int(r["doc_id"]), r["n_words"], r["n_removed"], r["kept_sha256"]) for r in rows], key=str) == brute_dedup(pairs(odd))


def test_automaton_counts():
    rng = random.Random(5)
    texts = [[rng.randrange(3) for _ in range(rng.randint(4, 30))] for _ in range(12)]
    a = substring_dedup.SuffixAutomaton()
    for k, t in enumerate(texts):
        a.add(t, 1 + k % 3)
    count = Counter()
    for k, t in enumerate(texts):
        for i in range(len(t) - 3):
            count[tuple(t[i : i + 4])] += 1 + k % 3
    for t in [*texts, [rng.randrange(4) for _ in range(40)]]:
        assert a.window_counts(t, 4) == [count[tuple(t[i : i + 4])] for i in range(len(t) - 3)]


def test_strip_reference(spark, odd):
    reference = spark.createDataFrame([(PASSAGE,), (None,), ("short",)], "text string")
    got = {r["doc_id"]: (r["n_matched"], r["text"]) for r in substring_dedup.strip_reference(odd, reference).collect()}
    by = {d: t for d, t in pairs(odd)}
    for d, t in by.items():
        n = len(re.findall(r"\bp\d+\b", t or ""))
        assert got[d] == (n, " ".join(w for w in re.findall(SPACES, t or "") if not (n and re.fullmatch(r"p\d+", w))))


def test_token_counts_equal_the_library(odd, docs):
    path = queries.tokenizer_path("piece_bpe_32k.model")
    library = bpe.piece_counter(path).library
    for df in (odd, docs):
        got = sorted(map(tuple, token_count.count_tokens(df, path).collect()), key=str)
        want = sorted(((d, len((t or "").encode()), n := len(library.encode(t or "")), n > 4096) for d, t in pairs(df)), key=str)
        assert got == want


def test_merging_equals_the_libraries():
    rng = random.Random(1)
    bits = ["a", "b", " ", "▁", "\n", "é", "the ", "in", ".", "'", "<", "|", "1", "日", "  ", "Σ", "́", "<s>", "×"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 60))) for _ in range(1500)] + [" " * 900, "ab" * 900]
    pieces, words = bpe.piece_counter(queries.tokenizer_path("piece_bpe_32k.model")), bpe.word_encoder(queries.tokenizer_path("word_bpe_49k.json"))
    got = np.concatenate([pieces.count(*s) for s in text_slices(pa.array(texts))])
    assert got.tolist() == [len(x) for x in pieces.library.encode(texts)]
    ids = []
    for s in word_slices(pa.array(texts)):
        flat, size = words.encode(s.data, s.start, s.end)
        at = np.concatenate([[0], np.cumsum(size)])
        ids += [flat[at[s.at[d]] : at[s.at[d + 1]]].tolist() for d in range(s.n)]
    assert ids == [e.ids for e in words.library.encode_batch(texts, add_special_tokens=False)]


def test_long_sequences_merge_like_short_ones():
    rng = random.Random(2)
    letters = ["ab", "a", "abcdefghijklmnopqrstuvwxyz", "etaoin=-_", "0123456789abcdef", "日本語é", "ABCdef+/0"]
    word = lambda n: "".join(rng.choices(rng.choice(letters), k=n))
    pieces, words = bpe.piece_counter(queries.tokenizer_path("piece_bpe_32k.model")), bpe.word_encoder(queries.tokenizer_path("word_bpe_49k.json"))
    for _ in range(100):
        own = [word(rng.randint(1, 60)) for _ in range(5)]
        symbols, lengths = pieces.char[[ord(c) for w in own for c in w]], np.array([len(w) for w in own])
        for a, b in zip(bpe.merge_all(symbols, lengths, pieces.table), bpe.merge_linked(symbols, lengths, pieces.table), strict=True):
            assert np.array_equal(a, b)
    texts = [rng.choice([" ", "\n", ""]).join(rng.choice([word(n), (word(rng.randint(1, 9)) * n)[:n]]) for n in rng.choices([3, 399, 400, 401, 2500], k=3)) for _ in range(150)]
    got = np.concatenate([pieces.count(*s) for s in text_slices(pa.array(texts))])
    assert got.tolist() == [len(x) for x in pieces.library.encode(texts)]
    for s in word_slices(pa.array(texts)):
        flat, size = words.encode(s.data, s.start, s.end)
        at = np.concatenate([[0], np.cumsum(size)])
        assert [flat[at[s.at[d]] : at[s.at[d + 1]]].tolist() for d in range(s.n)] == [words.library.encode(t, add_special_tokens=False).ids for t in texts[s.first : s.first + s.n]]


def test_packing_is_an_exact_round_trip(odd, docs):
    path = queries.tokenizer_path("word_bpe_49k.json")
    library = bpe.word_encoder(path).library
    for df in (odd.where("doc_id is not null").dropDuplicates(["doc_id"]), docs):
        pieces = defaultdict(list)
        rows = packing.as_sequences(packing.pack(df, path)).collect()
        assert len({r["sequence_id"] for r in rows}) == len(rows)
        for r in rows:
            pieces[r["doc_id"]].append(r)
        for d, t in pairs(df):
            own = sorted(pieces[d], key=lambda r: r["start"])
            ids = [*library.encode(t or "", add_special_tokens=False).ids, 2]
            assert [x for r in own for x in r["ids"]] == ids
            assert [r["length"] for r in own] == packing.binary_lengths(len(ids), 4096)
            for r in own:
                assert r["length"] == len(r["ids"]) == 1 << r["bucket"] and r["doc_tokens"] == len(ids) and r["offset"] == 0
                assert r["ids_crc32"] == zlib.crc32(np.array(r["ids"], "<u4").tobytes())


def test_license_rules(spark):
    grant = next(k for k, v in license_scan.SENTENCES.items() if v == "mit_grant")
    notice = next(k for k, v in license_scan.SENTENCES.items() if v == "mit_notice")
    rows = [(1, f"Intro. {grant.upper()}.\n{notice}!\nThe software is provided as is, without warranty of any kind."), (2, f"{grant}. Some words. {notice}."), (3, None), (4, ""), (5, "All rights reserved. Released under the MIT License."), (5, "Nothing here")]
    got = sorted((r["doc_id"], r["n_sentences"], r["licenses"]) for r in license_scan.scan(spark.createDataFrame(rows, "doc_id int, text string")).collect())
    assert got == [(1, 3, "MIT"), (2, 2, ""), (3, 0, ""), (4, 0, ""), (5, 0, ""), (5, 2, "Proprietary,MIT")]


def test_wrapped_licences(spark):
    mit = """The MIT License

Copyright (c) 2020 A B

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS BE LIABLE."""
    apache = """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law, it is distributed as it is."""
    rows = [(1, mit), (2, apache), (3, "\n".join(f" * {x}" for x in mit.split("\n"))), (4, apache.replace("\n", "\r\n# ")), (5, "\n\n".join(" ".join(x.split()) for x in mit.split("\n\n"))), (6, "a line\nAll rights reserved\nReleased under the\nMIT License\nand more")]
    got = {r["doc_id"]: (r["n_sentences"], r["licenses"]) for r in license_scan.scan(spark.createDataFrame(rows, "doc_id int, text string")).collect()}
    assert got == {1: (3, "MIT"), 2: (3, "Apache-2.0"), 3: (3, "MIT"), 4: (3, "Apache-2.0"), 5: (3, "MIT"), 6: (2, "Proprietary,MIT")}


def test_more_licences_with_copyright_lines_and_lists(spark):
    bsd = """Copyright (c) 2019-2021, Some Holder and Others

Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.
{}
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED."""
    third = """
3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.
"""
    gnu = """This {0} is free software; you can redistribute it and/or modify it under
the terms of the GNU {1}General Public License as published by the Free Software
Foundation; either version {2} of the License, or (at your option) any later
version."""
    mpl = """This Source Code Form is subject to the terms of the Mozilla Public
License, v. 2.0. If a copy of the MPL was not distributed with this
file, You can obtain one at https://mozilla.org/MPL/2.0/."""
    isc = """Copyright 2001 X

Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH
REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY
AND FITNESS."""
    rows = [(1, bsd.format("")), (2, bsd.format(third)), (3, gnu.format("program", "", "2")), (4, gnu.format("program", "", "3")), (5, gnu.format("library", "Lesser ", "2.1")), (6, mpl), (7, isc), (8, "Copyright 1999 Y"), (9, "copyright law of 1999")]
    df = spark.createDataFrame(rows, "doc_id int, text string").withColumns({"_ids": F.lit(1), "_known": F.lit(2), "_hits": F.lit(3)})
    out = license_scan.scan(df)
    got = {r["doc_id"]: (r["sentence_ids"].split(",")[0], r["licenses"], r["_ids"], r["_known"], r["_hits"]) for r in out.collect()}
    names = {1: "BSD-2-Clause", 2: "BSD-3-Clause", 3: "GPL-2.0-or-later", 4: "GPL-3.0-or-later", 5: "LGPL-2.1-or-later", 6: "MPL-2.0", 7: "ISC", 8: "", 9: ""}
    assert {k: v[1] for k, v in got.items()} == names and all(v[2:] == (1, 2, 3) for v in got.values())
    assert [got[k][0] for k in (1, 2, 7, 8, 9)] == ["copyright"] * 4 + [""]


def test_raking_reaches_the_marginals():
    rng = random.Random(2)
    cells = [(s, lang, t, rng.randint(1, 1000)) for s in ("a", "b", "other") for lang in ("x", "y") for t in ("p", "q")]
    want = [{"a": 0.7, "b": 0.3}, {"x": 0.5, "y": 0.5}, {"p": 0.9, "q": 0.1, "unseen": 0.5}]
    factor = mixing.rake(cells, want, 200)
    total = sum(c[3] for c in cells)
    share = lambda d, k: sum(c[3] * factor[c[:3]] for c in cells if c[d] == k) / total
    other = sum(c[3] for c in cells if c[0] == "other") / total
    assert abs(share(0, "other") - other) < 1e-6 and abs(share(0, "a") - 0.7 * (1 - other)) < 1e-6
    assert abs(share(1, "x") - 0.5) < 1e-6 and abs(share(2, "p") - 0.9) < 1e-6
    assert mixing.rake([], want) == {}


def test_mixing_of_odd_rows(odd):
    out = mixing.calibrate(odd.withColumns({"copies": F.lit("clash"), "_s": F.lit(1), "_k": F.lit(2)}))
    rows = out.collect()
    assert len(rows) == len(odd_rows()) and all(r["rate"] >= 0 and int(r["rate"]) <= r["copies"] <= int(r["rate"]) + 1 and (r["_s"], r["_k"]) == (1, 2) for r in rows)
    assert mixing.sample(out).count() == sum(r["copies"] for r in rows)
    assert mixing.calibrate(odd.where("doc_id < 0")).count() == 0
    with pytest.raises(ValueError, match="does not occur"):
        mixing.calibrate(odd, strict=True)


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_mixing_meets_its_targets(spark, sf):
    mixed = mixing.calibrate(spark.read.parquet(f"/root/testdata/{sf}/documents.parquet"), strict=True)
    rows = mixing.marginals(mixed).collect()
    assert len(rows) >= 27 and all(abs(r["wanted"] - r["expected"]) < mixing.CLOSE for r in rows)


def test_mixing_refuses_contradicting_targets(spark):
    df = spark.createDataFrame([(i, "w", "en" if i % 2 else "de", "src0" if i % 2 else "src1") for i in range(40)], "doc_id long, text string, lang string, source string")
    with pytest.raises(ValueError, match="instead of"):
        mixing.calibrate(df, source={"src0": 0.5, "src1": 0.5}, lang={"en": 0.9, "de": 0.1}, topic={"prose": 1.0}, strict=True)


def test_mixing_repeats_scarce_cells(spark):
    rows = [(i, "w " * 10 + ("@" if i % 50 == 0 else "x"), "en", "src0") for i in range(20_000)]
    topic = {"prose": 0.7, "contact": 0.3}
    mixed = mixing.calibrate(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string"), topic=topic)
    out = mixed.collect()
    assert max(r["copies"] for r in out) > 1
    got = {(r["dimension"], r["category"]): r for r in mixing.marginals(mixed, topic=topic).collect()}
    for k, want in (("contact", 0.3), ("prose", 0.7)):
        assert abs(got["topic", k]["wanted"] - want) < 1e-9 and abs(got["topic", k]["expected"] - want) < 1e-6 and abs(got["topic", k]["reached"] - want) < 0.01
    assert got["lang", "de"]["reached"] is None
    assert abs(sum(r["n_tokens"] * r["copies"] for r in out) / sum(r["n_tokens"] for r in out) - 0.5) < 0.01
    assert mixing.sample(mixed).count() == sum(r["copies"] for r in out)


def test_quality_on_held_out_labels(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    seen = labels.where("doc_id % 3 <> 0")
    out = quality.score(docs, quality.train(docs, seen)).join(labels.where("doc_id % 3 = 0"), "doc_id")
    r = out.agg(F.avg(F.when((F.col("quality") == 1) & (F.col("toxic") == 0), F.col("keep").cast("int"))).alias("clean"), F.avg(F.when(F.col("toxic") == 1, F.col("keep").cast("int"))).alias("toxic")).first()
    assert r["clean"] > 0.95 and r["toxic"] < 0.3


def test_quality_of_odd_rows(spark, odd):
    labels = spark.createDataFrame([(0, 1, 0), (1, None, 1), (None, 1, 0)], "doc_id long, quality int, toxic int")
    for m in (quality.train(odd, labels), quality.train(odd, labels.where("false"))):
        out = quality.score_rows(odd, m)
        assert out.count() == len(odd_rows()) and out.where("keep").count() == len(odd_rows())
    model = quality.Ordinal(np.zeros(1 << quality.BITS), np.array([-1.0, 0.5]))
    assert model.tails(np.array([0.0]))[0, 0] > model.tails(np.array([0.0]))[0, 1]


def test_empty_tables(spark, odd):
    none = odd.where("doc_id < 0")
    assert ngram_join.similar_components(none).count() == 0
    assert substring_dedup.dedup(none).count() == 0
    assert packing.pack(none, queries.tokenizer_path("word_bpe_49k.json")).count() == 0
    assert token_count.count_tokens(none, queries.tokenizer_path("piece_bpe_32k.model")).count() == 0
    assert license_scan.scan(none).count() == 0
