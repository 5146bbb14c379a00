"""Fingerprints, links and components against brute force."""

import random
import re

import numpy as np
import pytest
import xxhash
from veilgrid.llm import simhash as S
from veilgrid.llm.components import connected_components

WORD = re.compile("[^\x20\x09-\x0d]+")


def plain_fingerprint(text):
    words = WORD.findall((text or "").translate({k: k + 32 for k in range(65, 91)}))
    if not words:
        return 0
    shingles = [" ".join(words)] if len(words) < 3 else [" ".join(words[i : i + 3]) for i in range(len(words) - 2)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_roots(fps, radius, group=None):
    close = np.bitwise_count(fps[:, None] ^ fps[None]) <= radius
    if group is not None:
        close &= group[:, None] == group[None]
    labels = np.arange(len(fps))
    while True:
        nxt = np.where(close, labels[None], len(fps)).min(axis=1)
        if (nxt == labels).all():
            return labels
        labels = nxt


def clusters(seed, flips=6):
    rng = np.random.default_rng(seed)
    out = []
    for base in rng.integers(0, 1 << 63, 25, dtype=np.uint64):
        for _ in range(rng.integers(1, 30)):
            x = int(base)
            for _ in range(rng.integers(0, flips)):
                x ^= 1 << int(rng.integers(64))
            out.append(x)
    fps = np.unique(np.array(out, dtype=np.uint64))
    rng.shuffle(fps)
    return fps


@pytest.mark.parametrize("text", [None, "", " \t\n", "One", "One two", "a b c", "Ünï côdé WORDS Aa\x0bbb\x0ccc", "x " * 500, "a b c d e"])
def test_fingerprint_matches_definition(text):
    assert S.simhash(text) == plain_fingerprint(text)


def test_long_text_is_hashed_in_pieces(monkeypatch):
    text = " ".join(str(i % 977) for i in range(5000))
    whole = S.simhash(text)
    monkeypatch.setattr(S, "HASH_CHUNK", 97)
    assert S.simhash(text) == whole == plain_fingerprint(text)


@pytest.mark.parametrize("radius", [1, 2, 3, 4, 5])
def test_bucket_links(radius):
    fps = clusters(radius)
    group = np.sort(np.random.default_rng(1).integers(0, 3, len(fps)))
    assert (S.link_bucket_rows(group, fps, radius) == plain_roots(fps, radius, group)).all()


@pytest.mark.parametrize("size", [10, 1 << 30, 1 << 40])
def test_tables_cover_every_pair_within_radius(size):
    masks = S.key_tables(size)
    random.seed(size)
    for _ in range(300):
        flips = 0
        for bit in random.sample(range(64), 3):
            flips |= 1 << bit
        assert any(flips & m == 0 for m in masks)


@pytest.mark.parametrize("limit", [S.BUCKET_LIMIT, 16])
def test_components_with_and_without_tiles(spark, limit):
    fps = clusters(9)
    frame = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    roots = {r.node: r.root for r in connected_components(S.fingerprint_links(frame, bucket_limit=limit)).collect()}
    signed = fps.view(np.int64)
    want = plain_roots(fps, 3)
    least = {}
    for x, w in zip(signed, want, strict=True):
        least[w] = min(least.get(w, int(x)), int(x))
    assert all(roots.get(int(x), int(x)) == least[w] for x, w in zip(signed, want, strict=True))


def test_documents_with_odd_rows(spark):
    rows = [(5, "a b c d e f g"), (3, "A b c d e f g"), (9, None), (7, ""), (8, " \n"), (None, "a b c d e f g"), (5, "a b c d e f g"), (11, "quite other words here and there"), (None, "alone in the world as a text")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'x' AS fp", "1 AS component_id")
    out = S.near_duplicates(docs).collect()
    by = {}
    for r in out:
        by.setdefault(r.doc_id, set()).add((r.fingerprint, r.component_id))
    assert len(out) == len(rows)
    assert {c for i in (5, 3) for _, c in by[i]} == {3} and {c for i in (9, 7, 8) for _, c in by[i]} == {7}
    assert by[7] == {("0" * 16, 7)} and {c for _, c in by[None]} == {3, None} and {c for _, c in by[11]} == {11}


def test_empty_table(spark):
    assert S.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).collect() == []


def test_components_of_paths_and_hubs(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, 1000 + k) for k in range(1, 300)] + [(7, 7), (None, 3), (5000, 5001), (5000, 5001)]
    roots = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(roots[i] == 0 for i in range(61)) and all(roots[1000 + k] == 1000 for k in range(300)) and roots[5001] == 5000
    assert connected_components(spark.createDataFrame([], "a long, b long")).collect() == []
