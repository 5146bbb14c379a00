"""Pre-tokens of whole texts and tables from pre-token to token bytes, kept per worker process."""

from __future__ import annotations

import sys
import types
from collections.abc import Callable

import regex

#: Entries of one generation of a table; two generations bound its memory at about 120 MB.
GENERATION = 300_000
#: Pre-tokens longer than this are encoded each time.
LONGEST_KEPT = 64


class PieceTable(dict):
    """pre-token -> little-endian unsigned 32-bit ids, filled on demand.

    A full generation becomes the old one; what is asked for again moves back from there, the rest is forgotten.
    """

    def __init__(self, encode: Callable[[str], bytes]):
        super().__init__()
        self.encode = encode
        self.old: dict[str, bytes] = {}

    def __missing__(self, piece: str) -> bytes:
        ids = self.old.get(piece)
        if ids is None:
            ids = self.encode(piece)
        if len(piece) <= LONGEST_KEPT:
            if len(self) >= GENERATION:
                self.old = dict(self)
                self.clear()
            self[piece] = ids
        return ids


def worker_value(name: str, make: Callable):
    """The value of this name in this process; workers run many tasks, and later ones find what earlier ones made."""
    held = sys.modules.setdefault("_held_values", types.ModuleType("_held_values")).__dict__
    if name not in held:
        held[name] = make()
    return held[name]


def encoder(name: str, pattern: str, make: Callable[[], Callable[[str], bytes]]) -> Callable[[str | None], bytes]:
    """A function from a whole text to its ids, each match of the pattern encoded separately. ``name`` tells vocabularies apart."""
    find, at = regex.compile(pattern).findall, worker_value(name, lambda: PieceTable(make())).__getitem__

    def run(text: str | None) -> bytes:
        return b"".join(map(at, find(text))) if text else b""

    return run
