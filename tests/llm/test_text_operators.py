"""Rules, classifier, licences, packing and byte-pair encoding on small fixtures."""

import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from veilgrid.llm import bpe, isolation, license_scan, packing, pu_classifier
from veilgrid.llm.common import words_of
from veilgrid.llm.queries import tokenizer_files
from veilgrid.llm.text_stats import rule_counts

ODD = [None, "", " ", "one", "Grüße aus 東京 !!  \n\n  two words", "a b c a b c a b c", "x\ny\nx\n \nx", "#" * 300, "word " * 4000, "\x0b\x0c\r\t", "emoji 👩‍👩‍👧 done", "it's we'll I'd 123 4567 $%^"]
FILES = tokenizer_files()


def plain_counts(text):
    text = text or ""
    words = re.findall("[^\x20\x09-\x0d]+", text)
    lines = [x for x in text.split("\n") if re.search("[^\x20\x09-\x0d]", x)]
    seen = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    covered = {i + k for i in range(len(words) - 2) if seen[tuple(words[i : i + 3])] > 1 for k in range(3)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered)


@pytest.mark.parametrize("text", ODD)
def test_rule_counts(text):
    assert rule_counts(text, words_of(text)) == plain_counts(text)


def corpus(n=600):
    rng = np.random.default_rng(4)
    rows = []
    for i in range(n):
        words = ["".join(rng.choice(list("abcdefghij"), 2 + k % 7)) for k in rng.permutation(118 + i % 3)]
        bad = i % 10 == 0
        rows.append((i, " ".join(w.upper() + "!!" for w in words) if i % 20 == 0 else " ".join(w + "***" for w in words) if bad else ". ".join(" ".join(words[k : k + 10]) for k in range(0, 120, 10)), int(not bad)))
    return rows


@pytest.fixture(scope="module")
def labelled(spark):
    rows = corpus()
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string").cache()
    return docs, spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id long, quality int").cache()


def test_rules_find_odd_documents(spark, labelled):
    docs, labels = labelled
    out = {r.doc_id: r for r in isolation.quality_rules(docs, labels).collect()}
    assert not any(out[i].kept for i, _, q in corpus() if not q)
    assert sum(not out[i].kept for i, _, q in corpus() if q) <= 1  # the share of good rows that a threshold may cost
    kept = isolation.keep_good_rows(docs.withColumn("n_words", F.lit("clash")), labels)
    assert kept.columns == ["doc_id", "text", "n_words"] and {r.doc_id for r in kept.collect()} == {i for i, r in out.items() if r.kept}


def test_forest_path_lengths():
    rng = np.random.default_rng(0)
    x = np.vstack([rng.normal(size=(400, 4)), [[9, 9, 9, 9]]])
    score = isolation.grow_forest(x).score(x)
    assert score.argmax() == 400 and 0 < score.min() < score.max() < 1
    assert isolation.grow_forest(np.empty((0, 4))).score(x).shape == (401,)
    same = isolation.grow_forest(np.ones((50, 4)))
    assert np.allclose(same.score(np.ones((3, 4))), same.score(np.ones((1, 4))))


def test_rules_and_classifier_on_odd_rows(spark, labelled):
    _, labels = labelled
    docs = spark.createDataFrame([(k if k % 4 else None, t) for k, t in enumerate(ODD)] * 2, "doc_id long, text string").withColumn("score", F.lit(7))
    rules = isolation.quality_rules(docs, labels).collect()
    assert len(rules) == 2 * len(ODD) and all(not r.kept for r in rules if r.n_words < 50)
    scores = pu_classifier.quality_scores(docs, labels).collect()
    assert len(scores) == 2 * len(ODD) and all(0 <= r.score <= 1 and r.held_out in (True, False) for r in scores)
    none, nothing = docs.limit(0), labels.limit(0)
    assert isolation.quality_rules(none, nothing).count() == 0 and pu_classifier.quality_scores(none, nothing).count() == 0
    assert isolation.quality_rules(docs, nothing).count() == len(rules)
    assert isolation.keep_good_rows(docs, nothing).columns == docs.columns and pu_classifier.keep_quality_rows(docs, nothing).columns == docs.columns


def test_classifier_on_held_out_rows(spark, labelled):
    docs, labels = labelled
    truth = {i: q for i, _, q in corpus()}
    rows = pu_classifier.quality_scores(docs, labels).collect()
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    assert np.mean([r.predicted == truth[r.doc_id] for r in held]) > 0.95


def test_non_negative_risk_ignores_labels_of_negatives():
    rng = np.random.default_rng(2)
    good, bad = rng.normal(1, 1, (800, 3)), rng.normal(-1, 1, (800, 3))
    model = pu_classifier.fit_pu(good[:400], np.vstack([good[400:], bad[:400]]), 0.5)
    assert (model.score(good[:400]) > 0.5).mean() > 0.85 and (model.score(bad[400:]) < 0.5).mean() > 0.85
    assert pu_classifier.fit_pu(good[:0], bad, 0.5).score(bad).shape == (800,)


@pytest.mark.parametrize("share", [0.3, 0.6, 0.9])
def test_prior_is_estimated_without_negatives(share):
    rng = np.random.default_rng(8)
    n = 4000
    kinds = rng.random(n) < share
    unlabelled = np.where(kinds[:, None], rng.normal(1.5, 1, (n, 4)), rng.normal(-1.5, 1, (n, 4)))
    assert abs(pu_classifier.estimate_prior(rng.normal(1.5, 1, (3000, 4)), unlabelled) - share) < 0.05
    assert pu_classifier.estimate_prior(unlabelled[:2], unlabelled) == 0.5


def plain_risk(w, p, u, prior):
    """The non-negative risk of a linear model with logistic loss, written out."""
    loss = lambda z: np.log1p(np.exp(-z))
    zp, zu = p @ w[:-1] + w[-1], u @ w[:-1] + w[-1]
    return prior * loss(zp).mean() + max(0.0, loss(-zu).mean() - prior * loss(-zp).mean())


def test_fit_minimises_the_risk():
    """No point near the fit, nor a plain descent on the risk's numeric gradient, does much better."""
    rng = np.random.default_rng(6)
    p = rng.normal(1, 1, (600, 2))
    u = np.vstack([rng.normal(1, 1, (300, 2)), rng.normal(-1, 1, (300, 2))])
    model = pu_classifier.fit_pu(p, u, 0.5, epochs=600, batch=600, decay=0.0, rate=0.02)
    scaled = [(x - model.mean) / model.scale for x in (p, u)]
    found = plain_risk(np.append(model.weights, model.bias), *scaled, 0.5)
    w = np.zeros(3)
    for _ in range(1500):
        gradient = [(plain_risk(w + e, *scaled, 0.5) - plain_risk(w - e, *scaled, 0.5)) / 2e-4 for e in 1e-4 * np.eye(3)]
        w -= 0.2 * np.array(gradient)
    assert found < plain_risk(w, *scaled, 0.5) + 0.01


def test_repeated_ids_in_samples(spark, labelled):
    """An id that a thousand rows share is one row of a sample."""
    docs, labels = labelled
    many = docs.unionByName(docs.where("doc_id = 2").crossJoin(spark.range(1000)).select("doc_id", "text"))
    ids = docs.where("doc_id < 50").select("doc_id")
    p, u = pu_classifier._sample_vectors(many, ids, ids.where("doc_id < 10"))
    assert (len(p), len(u)) == (50, 10)


def plain_path(row, sample, rng, depth, limit):
    """Path length of one row in a tree grown on the fly: only the branch that the row takes is built."""
    spread = np.flatnonzero(sample.max(axis=0) > sample.min(axis=0)) if len(sample) > 1 else []
    if depth >= limit or not len(spread):
        n = len(sample)
        return depth + (0 if n <= 1 else 1 if n == 2 else 2 * (np.log(n - 1) + np.euler_gamma) - 2 * (n - 1) / n)
    f = rng.choice(spread)
    cut = rng.uniform(sample[:, f].min(), sample[:, f].max())
    return plain_path(row, sample[(sample[:, f] >= cut) == (row[f] >= cut)], rng, depth + 1, limit)


def test_forest_scores_against_single_branches():
    """Mean scores of the flat trees agree with path lengths grown row by row."""
    rng = np.random.default_rng(9)
    x = np.vstack([rng.normal(size=(250, 2)), [[6, 6], [0, 8]]])
    rows = np.array([0, 100, 250, 251])
    want = [np.exp2(-np.mean([plain_path(x[r], x[rng.choice(len(x), 64, replace=False)], rng, 0, 6) for _ in range(600)]) / isolation._expected_path(64)) for r in rows]
    got = isolation.grow_forest(x, trees=600, subsample=64).score(x[rows])
    assert np.allclose(got, want, atol=0.02)


def test_threshold_is_the_best_allowed_cut(spark, labelled):
    docs, labels = labelled
    stats = isolation.materialise(isolation.rule_statistics(docs))
    model, scored = isolation.fit_rules(stats, labels, max_good_rejected=0.02)
    rows = [(r.anomaly, r.quality) for r in scored.where(~isolation.base_failed()).join(labels, "doc_id").collect()]
    good, bad = ([a for a, q in rows if q == k] for k in (1, 0))
    cuts = [k / isolation.BINS for k in range(isolation.BINS + 1) if sum(a >= k / isolation.BINS for a in good) <= 0.02 * len(good)]
    most = max(sum(a >= c for a in bad) for c in cuts)
    assert sum(a >= model.threshold for a in bad) == most and sum(a >= model.threshold for a in good) <= 0.02 * len(good)


def test_license_sequences():
    scan = license_scan.scanner()
    header = "Licensed under the Apache License, Version 2.0 (the \"License\"). You may not use this file except in compliance with the License. You may obtain a copy of the License at\nhttp"
    assert [(m.license, m.rule, m.first, m.last) for m in scan(header)] == [("Apache-2.0", "apache-header", 0, 2)]
    two = scan("Text. Released under the MIT License.\nmore\nLicensed under CC BY-NC 4.0.")
    assert [m.license for m in two] == ["MIT", "CC-BY-NC-4.0"] and [m.text for m in two] == ["Released under the MIT License", "Licensed under CC BY-NC 4.0"]
    assert scan(None) == scan("") == scan("licensed under nothing.") == []
    assert [m.license for m in scan("RELEASED UNDER THE MIT LICENSE! Released under the MIT License?")] == ["MIT", "MIT"]


MIT = """MIT License

Copyright (c) 2020 Jane Doe

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
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.
"""
GPL = """A tool
Copyright (C) 2020 Jane Doe

This program is free software: you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation, either version 3 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details.
"""
GPL2 = GPL.replace("software:", "software;").replace("Foundation, either version 3", "Foundation; either version 2")
APACHE = """Copyright 2020 Jane Doe

Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
"""


BSD3 = """Copyright (c) 2020, Jane Doe
All rights reserved.

Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE
FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL
DAMAGES.
"""
BSD2 = BSD3[: BSD3.index("3. Neither")] + BSD3[BSD3.index("THIS SOFTWARE") :]
ISC = """Copyright (c) 2020 Jane Doe

Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH
REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND
FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT,
INDIRECT, OR CONSEQUENTIAL DAMAGES.
"""
MPL = """This Source Code Form is subject to the terms of the Mozilla Public
License, v. 2.0. If a copy of the MPL was not distributed with this
file, You can obtain one at https://mozilla.org/MPL/2.0/.
"""
LGPL = """This library is free software; you can redistribute it and/or
modify it under the terms of the GNU Lesser General Public
License as published by the Free Software Foundation; either
version 2.1 of the License, or (at your option) any later version.

This library is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the GNU
Lesser General Public License for more details.
"""
AGPL = GPL.replace("GNU General", "GNU Affero General")


@pytest.mark.parametrize("layout", ["wrapped", "crlf", "comment", "paragraphs", "one line"])
@pytest.mark.parametrize("notice,rule", [(MIT, "mit-text"), (GPL, "gpl-text"), (GPL2, "gpl-text"), (APACHE, "apache-header"), (BSD3, "bsd3-text"), (BSD2, "bsd2-text"), (ISC, "isc-text"), (MPL, "mpl-header"), (LGPL, "lgpl21-text"), (AGPL, "agpl3-text")])
def test_license_notices_unaltered(notice, rule, layout):
    text = {"wrapped": notice, "crlf": notice.replace("\n", "\r\n"), "comment": "".join(f" * {x}".rstrip() + "\n" for x in notice.splitlines()), "paragraphs": "\n".join(" ".join(x.split()) for x in notice.split("\n\n")), "one line": " ".join(notice.split())}[layout]
    found = [m for m in license_scan.scanner()(text) if m.rule != "reserved-line"]
    assert [m.rule for m in found] == [rule]
    assert len(set(found[0].text.split())) > 20 and all(w in text for w in found[0].text.split())


def test_license_names_and_identifier_lines():
    scan = license_scan.scanner()
    for name in ("the University of California, Berkeley", "Jane Doe", "x " * 19 + "y"):
        assert [m.rule for m in scan(BSD3.replace("the copyright holder nor", f"{name} nor"))] == ["reserved-line", "bsd3-text"]
    assert [m.rule for m in scan(BSD3.replace("the copyright holder nor", "x " * 21 + "nor"))] == ["reserved-line", "bsd2-text"]  # too long a name: the sentence isn't known
    assert [m.rule for m in scan(BSD3.replace("THE COPYRIGHT HOLDERS AND CONTRIBUTORS", "THE REGENTS AND CONTRIBUTORS"))] == ["reserved-line", "bsd3-text"]
    assert [(m.license, m.rule) for m in scan("// SPDX-License-Identifier: Apache-2.0\n# SPDX-License-Identifier: GPL-2.0-or-later\n/* SPDX-License-Identifier: MIT */")] == [("Apache-2.0", "spdx-line"), ("GPL-2.0-or-later", "spdx-line"), ("MIT", "spdx-line")]
    assert scan("SPDX-License-Identifier: Nothing-1.0") == []


def test_license_sentences_are_whole():
    scan = license_scan.scanner()
    assert [m.rule for m in scan("Released under\nthe MIT License.")] == ["mit-line"]
    for other in ("It is not licensed under the MIT License.", "Released under\n\nthe MIT License.", "Released under the MIT License or not.", "Released under. The MIT License.", "All rights reserved by us: nobody"):
        assert scan(other) == []


def test_license_scan_rows(spark):
    docs = spark.createDataFrame([(1, "Released under the MIT License."), (None, "All rights reserved."), (2, None), (3, "x" * 100_000), (1, "Released under the MIT License.")], "doc_id long, text string").withColumn("license", F.lit(0))
    assert sorted((r.doc_id or 0, r.license) for r in license_scan.scan_licenses(docs).collect()) == [(0, "Proprietary"), (1, "MIT"), (1, "MIT")]


def test_slices_are_small_and_whole(monkeypatch):
    import pyarrow as pa
    from veilgrid.llm import common

    monkeypatch.setattr(common, "SLICE_ROWS", 4)
    monkeypatch.setattr(common, "SLICE_BYTES", 10)
    texts = ["a", None, "", "bcd", "x" * 50, "y" * 11, "é", "tail", "t", "u", "v", "w"]
    batch = pa.RecordBatch.from_arrays([pa.array(range(12)), pa.array(texts)], names=["doc_id", "text"]).slice(1)
    parts = list(common.text_slices([batch, batch.slice(0, 0)]))
    assert [t for _, part in parts for t in part] == texts[1:] and [i for b, _ in parts for i in b.column(0).to_pylist()] == list(range(1, 12))
    assert all(len(p) <= 4 and (len(p) == 1 or sum(len((t or "").encode()) for t in p) <= 10) for _, p in parts)


@pytest.mark.parametrize("histogram", [{}, {1024: 5}, {1: 3000}, {600: 7, 424: 3, 1: 10, 512: 5}, {k: k % 7 + 1 for k in range(1, 1025)}, {1023: 4, 2: 9}])
def test_plan_places_each_length_as_often_as_asked(histogram):
    plan = packing.plan_packs(histogram)
    placed = Counter()
    for count, lengths in plan:
        assert count > 0 and 0 < sum(lengths) <= 1024
        for x in lengths:
            placed[x] += count
    assert placed == Counter(histogram)


def test_packing_is_whole_and_gapless(spark):
    from tokenizers import Tokenizer

    texts = [*ODD, "the same words again and again " * 900, "tail " * 1023, "a <|endoftext|> b", "<|endoftext|><|endoftext|>  <|endoftext|", "\n\n <|endoftext|>\n x"]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts)] + [(None, "null id"), (0, None)], "doc_id long, text string").withColumn("start", F.lit("clash"))
    pieces = packing.pack_documents(docs, FILES["json"], FILES["pattern"], with_ids=True).collect()
    tokenizer = Tokenizer.from_file(FILES["json"])
    for k, text in enumerate(texts[1:], 1):
        own = sorted((p for p in pieces if p.doc_id == k), key=lambda p: p.start)
        ids = [i for p in own for i in p.ids]
        assert ids == tokenizer.encode(text or "", add_special_tokens=False).ids + [0]
        assert all(p.ids_crc32 == zlib.crc32(np.array(p.ids, dtype="<u4").tobytes()) and p.doc_tokens == len(ids) and p.length == len(p.ids) for p in own)
    sequences = {}
    for p in pieces:
        sequences.setdefault(p.sequence_id, []).append((p.offset, p.length))
    assert sorted(sequences) == list(range(len(sequences)))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 1024
    assert packing.pack_documents(docs.limit(0), FILES["json"], FILES["pattern"]).count() == 0


def test_rank_encoder_and_library_agree():
    encode, library = packing.piece_encoder(FILES["json"], FILES["pattern"]), packing.library_encoder(FILES["json"])
    other = FILES["json"].replace("byte_bpe_50k", "word_bpe_49k")
    assert packing.ranks_of(FILES["json"]) and packing.ranks_of(other) is None
    marks = ["a <|endoftext|> b", "<|endoftext|>", "<|endoftext|><|endoftext|>", "x  <|endoftext|>  y\n<|endoftext", "<|endoftext|><|", "it's<|endoftext|>'s"]
    for text in [*ODD, *marks, "\u00a0\u3000  x", "".join(chr(c) for c in range(1, 0x3000, 7) if not 0xD800 <= c <= 0xDFFF)]:
        assert encode(text) == library(text)
        assert packing.piece_encoder(other, FILES["pattern"])(text) == packing.library_encoder(other)(text)


def test_contract_ids_of_an_added_token(spark):
    docs = spark.createDataFrame([(1, "a <|endoftext|> b")], "doc_id long, text string")
    assert [p.ids for p in packing.pack_documents(docs, FILES["json"], FILES["pattern"], with_ids=True).collect()] == [[64, 220, 50256, 275, 0]]


@pytest.mark.parametrize("most", [packing.MAX_BROADCAST, 0])
def test_equal_rows_are_packed_one_by_one(spark, most):
    docs = spark.createDataFrame([(7, "the same few words")] * 3000 + [(k, "word " * (k % 90)) for k in range(500)], "doc_id long, text string").repartition(5)
    pieces = packing.materialise(packing.document_pieces(docs, FILES["json"], FILES["pattern"], 128, True))
    placed = packing.place_pieces(pieces, 128, "<u2", most)
    rows = placed.collect()
    assert len({(p.sequence_id, p.offset) for p in rows}) == len(rows) == 3500
    whole = {r.sequence_id: r for r in packing.assemble_sequences(placed, 128).collect()}
    assert all(len(r.ids) == 128 for r in whole.values()) and sum(r.used for r in whole.values()) == sum(p.length for p in rows)
    assert all(whole[p.sequence_id].ids[p.offset : p.offset + p.length] == p.ids for p in rows)
    assert 1 - sum(p.length for p in rows) / (128 * len(whole)) < 0.03


def test_padding_is_small():
    rng = np.random.default_rng(5)
    for lengths in (rng.integers(1, 1025, 20_000), np.minimum(1024, rng.lognormal(5, 1, 20_000).astype(int) + 1), rng.integers(300, 700, 5000)):
        histogram = {int(k): int(n) for k, n in zip(*np.unique(lengths, return_counts=True), strict=True)}
        packs = sum(count for count, _ in packing.plan_packs(histogram))
        assert packs <= 1.06 * np.ceil(lengths.sum() / 1024) + 1 or lengths.min() > 256  # pieces near a half can't fill a sequence


def test_piece_table_forgets_in_generations(monkeypatch):
    from veilgrid.llm import pieces

    monkeypatch.setattr(pieces, "GENERATION", 3)
    asked = []
    table = pieces.PieceTable(lambda p: asked.append(p) or p.encode())
    for piece in "abcabcdabcdefghabc":
        assert table[piece] == piece.encode()
    assert len(table) <= 3 and len(table.old) <= 3 and len(asked) < 18


def plain_merge(piece, ranks):
    parts = [bytes([b]) for b in piece]
    while True:
        best = min(((ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)) if a + b in ranks), default=None)
        if best is None:
            return [ranks[p] for p in parts]
        i = best[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]


def test_segment_tree_merges():
    ranks = bpe.load_ranks(FILES["ranks"])
    rng = np.random.default_rng(1)
    for n in (1, 2, 3, 4, 5, 7, 8, 9, 31, 64, 200):
        for _ in range(30):
            piece = bytes(rng.choice(list(b"aeinorst hT\xc3\xa9"), n).tolist())
            assert bpe.merge_bytes(piece, ranks) == plain_merge(piece, ranks)


def test_encoding_matches_tiktoken(spark):
    import hashlib

    import tiktoken

    ranks = bpe.load_ranks(FILES["ranks"])
    encoding = tiktoken.Encoding("own", pat_str=FILES["pattern"], mergeable_ranks=ranks, special_tokens={})
    texts = [*ODD, "a" * 3000, "<|endoftext|> as text", " 　  x"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = {k: encoding.encode_ordinary(t or "") for k, t in enumerate(texts)}
    encoded = bpe.encode_documents(docs, FILES["ranks"], FILES["pattern"])
    assert {r.doc_id: r.ids for r in encoded.collect()} == want
    assert {r.doc_id: bytes(r.data).decode() for r in bpe.decode_documents(encoded, FILES["ranks"]).collect()} == {k: t or "" for k, t in enumerate(texts)}
    for r in bpe.round_trip(docs, FILES["ranks"], FILES["pattern"]).collect():
        assert r.n_tokens == len(want[r.doc_id]) and r.decoded_sha256 == hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest()
        assert r.ids_sha256 == hashlib.sha256(np.array(want[r.doc_id], dtype="<u4").tobytes()).hexdigest()
