"""Rule statistics of whole texts."""

from __future__ import annotations

from collections import Counter

import numpy as np

#: The characters counted as symbols.
SYMBOLS = "#*$%&|<>"
#: The white space that separates words.
SPACES = " \t\n\x0b\x0c\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

#: Columns of rule_counts, in order.
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Columns of rule_features, in order; each is a number that doesn't depend on the text's length alone.
FEATURES = ("symbols_per_word", "mean_word_chars", "dup_line_share", "repeat_word_share", "distinct_word_share", "upper_share", "digit_share", "marks_per_word", "adjacent_repeats", "words_per_line_log")


def rule_counts(text: str | None, words: list[bytes]) -> tuple[int, int, int, int, int]:
    """The five base counts; null counts as a text without words."""
    if not text:
        return 0, 0, 0, 0, 0
    chars = len(text) - sum(map(text.count, SPACES))
    symbols = sum(map(text.count, SYMBOLS))
    return len(words), chars, symbols, duplicate_lines(text), repeated_words(words)


def duplicate_lines(text: str) -> int:
    lines = [x for x in text.split("\n") if x.strip(SPACES)]
    return len(lines) - len(set(lines))


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a 3-word window which occurs at least twice in the text, its first occurrence included."""
    windows = list(zip(words, words[1:], words[2:], strict=False))
    seen = Counter(windows)
    if len(seen) == len(windows):
        return 0
    again = np.fromiter((seen[x] > 1 for x in windows), dtype=bool, count=len(windows))
    covered = np.zeros(len(words), dtype=bool)
    for k in range(3):
        covered[k : k + len(again)] |= again
    return int(covered.sum())


def rule_features(text: str | None, words: list[bytes], counts: tuple[int, ...]) -> tuple[float, ...]:
    n, chars, symbols, dup_lines, repeats = counts
    if not n:
        return (0.0,) * len(FEATURES)
    lines = max(1, text.count("\n") + 1)
    upper = sum(map(text.count, UPPER))
    digits = sum(map(text.count, "0123456789"))
    marks = sum(map(text.count, "!?;:|"))
    adjacent = sum(map(bytes.__eq__, words, words[1:]))
    return (symbols / n, chars / n, dup_lines / lines, repeats / n, len(set(words)) / n ** 0.9, upper / chars, digits / chars, marks / n, adjacent / n, float(np.log1p(n / lines)))
