"""Sequence packing by shortest-pack-first over the length histogram.

Documents are cut at the sequence length; pieces are then known by their lengths only. Lengths are placed longest first
into the patterns with the most free room, pattern counts are split as they are used, and the finished patterns are
joined back to the pieces by each piece's rank among those of its length. The plan's size depends on the histogram
(at most 1024 lengths), not on the number of documents.

A piece's rank is its number among those of its length in the task that cut it, plus those of the tasks before: the pieces
themselves stay where they are, equal rows are numbered like any others, and no length, however common, meets in one task.
"""

from __future__ import annotations

import json
import re
import zlib
from array import array
from bisect import insort
from collections.abc import Callable, Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilgrid.llm.common import arrow_long, materialise, row_slices, text_slices
from veilgrid.llm.pieces import worker_value

SEQUENCE = 1024
END_ID = 0
#: Columns of a piece as it is cut: ``task`` and ``nth`` give its number among those of its length.
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, task long, nth long"
#: Tasks whose first ranks (8 bytes for each length up to the capacity) are broadcast: 64 MB; those of more tasks are joined by a shuffle.
MAX_BROADCAST = 8_192
#: Ids beyond this need four bytes in a stored piece; below it they take two.
SHORT_IDS = 1 << 16


def plan_packs(histogram: dict[int, int], capacity: int = SEQUENCE) -> list[tuple[int, tuple[int, ...]]]:
    """(count, lengths) patterns that hold each length exactly as often as the histogram says.

    Open patterns are kept by free room; a length goes into the shortest packs (most room) first, and a pattern is
    split when there are fewer pieces than packs of it.
    """
    open_packs: list[tuple[int, int, tuple[int, ...]]] = []  # (room, count, lengths), by room
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        if length > capacity:
            raise ValueError("a piece is longer than a sequence")
        grown = []
        while left and open_packs and open_packs[-1][0] >= length:
            room, count, lengths = open_packs.pop()
            fill = room // length  # as many copies as fit, spread over the packs evenly
            whole, rest = divmod(left, count)
            if whole >= fill:
                grown.append((room - fill * length, count, lengths + (length,) * fill))
                left -= fill * count
            else:
                if rest:
                    grown.append((room - (whole + 1) * length, rest, lengths + (length,) * (whole + 1)))
                grown.append((room - whole * length, count - rest, lengths + (length,) * whole))
                left = 0
        if left:
            fill = capacity // length
            packs, rest = divmod(left, fill)
            if packs:
                grown.append((capacity - fill * length, packs, (length,) * fill))
            if rest:
                grown.append((capacity - rest * length, 1, (length,) * rest))
        for pack in grown:
            insort(open_packs, pack)
    return [(count, lengths) for _, count, lengths in open_packs]


def pack_slots(plan: list[tuple[int, tuple[int, ...]]]) -> dict[int, list[tuple[int, int, int, int]]]:
    """length -> ascending (first rank, copies per sequence, first sequence, offset of the first copy)."""
    slots: dict[int, list[tuple[int, int, int, int]]] = {}
    used: dict[int, int] = {}
    sequence = 0
    for count, lengths in plan:
        offset = 0
        for length, same in groupby(lengths):
            copies = len(list(same))
            slots.setdefault(length, []).append((used.get(length, 0), copies, sequence, offset))
            used[length] = used.get(length, 0) + copies * count
            offset += copies * length
        sequence += count
    return slots


def read_vocabulary(tokenizer_path: str) -> dict:
    with open(tokenizer_path, encoding="utf-8") as f:
        return json.load(f)


def id_type(tokenizer_path: str) -> str:
    """Little-endian unsigned type that holds every id of the file."""
    from tokenizers import Tokenizer

    return "<u2" if Tokenizer.from_file(tokenizer_path).get_vocab_size(with_added_tokens=True) < SHORT_IDS else "<u4"


def ranks_of(tokenizer_path: str) -> tuple[dict[bytes, int], dict[str, int]] | None:
    """(token bytes -> id, added token -> id) of a plain byte-level file whose merges make ids in rising order; None for any other file.

    For such a file "the earliest merge first" and "the lowest id first" are one rule, so a rank encoder gives the same ids.
    Added tokens that a text holds are cut out first, as the library does by default.
    """
    known = read_vocabulary(tokenizer_path)
    model, cutter, added = known["model"], known.get("pre_tokenizer") or {}, known.get("added_tokens") or []
    if model["type"] != "BPE" or model.get("unk_token") or model.get("byte_fallback") or model.get("end_of_word_suffix") or model.get("continuing_subword_prefix") or model.get("ignore_merges") or model.get("dropout"):
        return None
    if known.get("normalizer") or cutter.get("type") != "ByteLevel" or cutter.get("add_prefix_space") or not cutter.get("use_regex", True):
        return None
    if any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") for t in added):
        return None
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves; the others follow from 256
    others = [b for b in range(256) if b not in set(printable)]
    byte_of = {chr(b): b for b in printable} | {chr(256 + k): b for k, b in enumerate(others)}
    vocabulary = model["vocab"]
    made = [vocabulary["".join(m if isinstance(m, list) else m.split(" "))] for m in model["merges"]]
    if made != sorted(made) or not all(set(t) <= byte_of.keys() for t, i in vocabulary.items() if i <= made[-1]):
        return None
    return {bytes(byte_of[c] for c in t): i for t, i in vocabulary.items() if i <= made[-1]}, {t["content"]: t["id"] for t in added}


def piece_encoder(tokenizer_path: str, pattern: str) -> Callable[[str | None], bytes]:
    """From a whole text to the ids of a tokenizers file, as the library's encode(text, add_special_tokens=False) gives them.

    A rank-ordered byte-level file is run by tiktoken's encoder, four times as fast; any other one by the tokenizers library.
    """
    def make():
        plain = ranks_of(tokenizer_path)
        if not plain:
            return library_encoder(tokenizer_path)
        import tiktoken

        ranks, added = plain
        encoding = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        cut = re.compile("|".join(map(re.escape, sorted(added, key=len, reverse=True)))) if added else None

        def encode(text: str | None) -> bytes:
            if not text:
                return b""
            if cut is None or not (marks := list(cut.finditer(text))):
                return array("I", encoding.encode_ordinary(text)).tobytes()
            out, at = array("I"), 0
            for m in marks:
                out.extend(encoding.encode_ordinary(text[at : m.start()]))
                out.append(added[m[0]])
                at = m.end()
            out.extend(encoding.encode_ordinary(text[at:]))
            return out.tobytes()

        return encode

    return worker_value(f"encoder {tokenizer_path}", make)


def library_encoder(tokenizer_path: str) -> Callable[[str | None], bytes]:
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(tokenizer_path)
    return lambda text: array("I", tokenizer.encode(text, add_special_tokens=False).ids).tobytes() if text else b""


def document_pieces(docs: DataFrame, tokenizer_path: str, pattern: str, capacity: int = SEQUENCE, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of at most ``capacity`` ids of every document, its ids followed by the end id; if asked for with their ids, as bytes of ``id_type``."""
    names = [x.split()[0] for x in PIECES.split(", ")]
    stored = id_type(tokenizer_path) if with_ids else ""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, seen, task = piece_encoder(tokenizer_path, pattern), [0] * (capacity + 1), TaskContext.get().partitionId()
        end = np.array([END_ID], dtype="<u4").tobytes()
        for part, texts in text_slices(batches):
            rows, ids = [], []
            for i, text in zip(part.column(0).to_pylist(), texts, strict=True):
                data = encode(text) + end
                for at in range(0, len(data), 4 * capacity):
                    piece = data[at : at + 4 * capacity]
                    length = len(piece) // 4
                    rows.append((i, at // 4, length, zlib.crc32(piece), len(data) // 4, task, seen[length]))
                    seen[length] += 1
                    if with_ids:
                        ids.append(np.frombuffer(piece, dtype="<u4").astype(stored).tobytes())
                    if len(ids) >= 2048:
                        yield batch(rows, ids)
                        rows, ids = [], []
            yield batch(rows, ids)

    def batch(rows, ids):
        columns = [pa.array(c, type=pa.int64()) for c in zip(*rows, strict=True)] or [pa.array([], type=pa.int64())] * len(names)
        return pa.RecordBatch.from_arrays(columns + [pa.array(ids, type=pa.binary())] * with_ids, names=names + ["data"] * with_ids)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, PIECES + ", data binary" * with_ids)


def place_pieces(pieces: DataFrame, capacity: int = SEQUENCE, stored: str = "", max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and ids where their ``stored`` type is given).

    ``pieces`` must be stable (a checkpoint or table): it is read for the counts and again to be placed. A task's first ranks are one
    array by length; those of up to ``max_broadcast`` tasks are broadcast, more are joined by a shuffle.
    """
    counts = materialise(pieces.groupBy("task", "length").count())
    histogram = {int(r["length"]): int(r["n"]) for r in counts.groupBy("length").agg(F.sum("count").alias("n")).collect()}
    slots = pack_slots(plan_packs(histogram, capacity))
    tables = {k: tuple(np.array(x, dtype=np.int64) for x in zip(*v, strict=True)) for k, v in slots.items()}
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    first = F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first")
    by_length = F.map_from_entries(F.collect_list(F.struct("length", "first"))).alias("by_length")  # at most capacity entries
    sparse = counts.select("task", "length", first).groupBy("task").agg(by_length)
    firsts = materialise(sparse.select("task", F.transform(F.sequence(F.lit(0), F.lit(capacity)), lambda n: F.try_element_at("by_length", n.cast("long"))).alias("firsts")))
    ranked = pieces.join(F.broadcast(firsts) if firsts.count() <= max_broadcast else firsts, "task").withColumn("first", F.get("firsts", F.col("length").cast("int")))
    out = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in row_slices(batches):
            columns = [b.column(k) for k in range(5)]
            n, r = columns[2].to_numpy(), b.column(5).to_numpy()
            sequence, offset = np.zeros((2, len(n)), dtype=np.int64)
            for k in np.unique(n):
                at = n == k
                first, copies, start, base = tables[int(k)]
                slot = np.searchsorted(first, r[at], side="right") - 1
                inside = r[at] - first[slot]
                sequence[at] = start[slot] + inside // copies[slot]
                offset[at] = base[slot] + inside % copies[slot] * k
            ids = [pa.array([np.frombuffer(x, dtype=stored).astype(np.int32) for x in b.column(6).to_pylist()], type=pa.list_(pa.int32()))] if stored else []
            yield pa.RecordBatch.from_arrays([*columns, arrow_long(sequence), arrow_long(offset), *ids], names=[*out, "sequence_id", "offset", *["ids"] * bool(stored)])

    rows = ranked.select(*out, (F.col("nth") + F.col("first")).alias("rank"), *["data"] * bool(stored))
    return rows.mapInArrow(run, ", ".join(f"{c} long" for c in [*out, "sequence_id", "offset"]) + ", ids array<int>" * bool(stored))


def pack_documents(docs: DataFrame, tokenizer_path: str, pattern: str, capacity: int = SEQUENCE, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids if asked for).

    Every id of every document, and its end id, lies in exactly one piece; sequences are filled from offset 0 without gaps. Null
    and empty texts are one end id; repeated rows and null ids are packed like others; an empty table gives no rows;
    other columns aren't read.
    """
    pieces = materialise(document_pieces(docs, tokenizer_path, pattern, capacity, with_ids, id_col, text_col))
    return place_pieces(pieces, capacity, id_type(tokenizer_path) if with_ids else "")


def assemble_sequences(placed: DataFrame, capacity: int = SEQUENCE, pad_id: int = END_ID) -> DataFrame:
    """(sequence_id, ids ARRAY<INT>, used): whole sequences from placed pieces with their ids, padded to the capacity; one shuffle of the ids."""
    ordered = F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("offset", "ids"))), lambda p: p["ids"]))
    whole = placed.groupBy("sequence_id").agg(ordered.alias("ids"))
    return whole.select("sequence_id", F.concat("ids", F.array_repeat(F.lit(pad_id), F.lit(capacity) - F.size("ids"))).alias("ids"), F.size("ids").alias("used"))


def placed_checksums(placed: DataFrame) -> DataFrame:
    """``ids_crc32`` taken anew from the ids of placed pieces; the ids themselves are dropped."""
    kept = placed.select(*[c for c in placed.columns if c not in ("ids", "ids_crc32")], "ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in row_slices(batches):
            ids = batch.column(batch.num_columns - 1)
            values, ends = ids.values.to_numpy(zero_copy_only=False).astype("<i4", copy=False), ids.offsets.to_numpy()
            sums = arrow_long([zlib.crc32(values[a:b]) for a, b in zip(ends[:-1], ends[1:], strict=True)])
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], sums], names=[*batch.schema.names[:-1], "ids_crc32"])

    return kept.mapInArrow(run, ", ".join(f"{c} long" for c in kept.columns[:-1]) + ", ids_crc32 long").select(*[c for c in placed.columns if c != "ids"])
