"""Byte-level BPE encoding and decoding over a rank file.

A segment tree over byte positions holds the leftmost minimum rank of the live neighbouring pairs. Each merge
reads the root, joins two neighbours and updates the ranks of the two pairs beside them on their paths to the
root, so a pre-token of n bytes takes O(n log n) steps however long it is.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.llm.common import text_slices
from veilgrid.llm.pieces import encoder

#: A leaf holds rank << PLACE | position, so that the least leaf is the leftmost one of the least rank.
PLACE = 32
NONE = 1 << 62
MASK = (1 << PLACE) - 1


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def merge_bytes(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Token ids of one pre-token's bytes."""
    whole = ranks.get(piece)
    if whole is not None:
        return [whole]
    get, n = ranks.get, len(piece)
    size = 1 << (n - 1).bit_length()  # leaf k is the pair of the parts that start at k and next to it
    tree = [NONE] * (2 * size)
    for k in range(n - 1):
        rank = get(piece[k : k + 2])
        if rank is not None:
            tree[size + k] = rank << PLACE | k
    for k in range((size + n - 1) >> 1, 0, -1):
        a, b = tree[2 * k], tree[2 * k + 1]
        tree[k] = a if a < b else b
    end, before = list(range(1, n + 1)), list(range(-1, n))  # of the part that starts at a position
    while (least := tree[1]) != NONE:
        k = least & MASK
        gone = end[k]
        stop = end[k] = end[gone]
        before[stop] = k
        rank = get(piece[k : end[stop]]) if stop < n else None
        tree[size + k] = NONE if rank is None else rank << PLACE | k
        tree[size + gone] = NONE
        p = before[k]
        if p >= 0:
            rank = get(piece[p:stop])
            tree[size + p] = NONE if rank is None else rank << PLACE | p
        else:
            p = k
        p, k, gone = (size + p) >> 1, (size + k) >> 1, (size + gone) >> 1
        while p:  # the three leaves' paths to the root, each shared node once
            a, b = tree[2 * p], tree[2 * p + 1]
            tree[p] = a if a < b else b
            if k != p:
                a, b = tree[2 * k], tree[2 * k + 1]
                tree[k] = a if a < b else b
            if gone != k:
                a, b = tree[2 * gone], tree[2 * gone + 1]
                tree[gone] = a if a < b else b
            p, k, gone = p >> 1, k >> 1, gone >> 1
    out, k = [], 0
    while k < n:
        out.append(ranks[piece[k : end[k]]])
        k = end[k]
    return out


def text_encoder(ranks: dict[bytes, int], pattern: str, name: str = "ranks") -> Callable[[str | None], bytes]:
    """From a whole text to its ids as little-endian unsigned 32-bit integers. ``name`` tells vocabularies apart."""
    return encoder(f"{name} {len(ranks)}", pattern, lambda: lambda piece: array("I", merge_bytes(piece.encode("utf-8"), ranks)).tobytes())


def decoder(ranks: dict[bytes, int]) -> Callable[[bytes], bytes]:
    tokens = {rank: token for token, rank in ranks.items()}

    def run(ids: bytes) -> bytes:
        return b"".join(map(tokens.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))

    return run


def _encode_with(reduce: Callable, schema: str, names: list[str], rank_path: str, pattern: str, docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ranks = load_ranks(rank_path)
        encode, decode = text_encoder(ranks, pattern, rank_path), decoder(ranks)
        for part, texts in text_slices(batches):
            columns = reduce([encode(t) for t in texts], decode)
            yield pa.RecordBatch.from_arrays([part.column(0), *columns], names=["doc_id", *names])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, " + schema)


def encode_documents(docs: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids ARRAY<INT>), one row per input row; a null or empty text has no ids, other columns aren't read."""

    def ids(encoded, _):
        return [pa.array([np.frombuffer(x, dtype="<i4") for x in encoded], type=pa.list_(pa.int32()))]

    return _encode_with(ids, "ids array<int>", ["ids"], rank_path, pattern, docs, id_col, text_col)


def decode_documents(encoded: DataFrame, rank_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, data BINARY): the bytes that the ids stand for; null ids stay null, an unknown id is an error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decode = decoder(load_ranks(rank_path))
        for b in batches:
            data = [None if x is None else decode(np.array(x, dtype="<u4").tobytes()) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(data, type=pa.binary())], names=["doc_id", "data"])

    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(run, "doc_id long, data binary")


def round_trip(docs: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of encoding and then decoding every whole text.

    Null texts count as empty; repeated rows repeat; null ids stay null; an empty table gives no rows.
    """

    def digests(encoded, decode):
        n = pa.array([len(x) // 4 for x in encoded], type=pa.int64())
        ids = pa.array([hashlib.sha256(x).hexdigest() for x in encoded], type=pa.string())
        return [n, ids, pa.array([hashlib.sha256(decode(x)).hexdigest() for x in encoded], type=pa.string())]

    return _encode_with(digests, "n_tokens long, ids_sha256 string, decoded_sha256 string", ["n_tokens", "ids_sha256", "decoded_sha256"], rank_path, pattern, docs, id_col, text_col)
