"""Counts of a whole text, shared by the quality rules and the quality classifier."""

from __future__ import annotations

from operator import eq

import numpy as np

SYMBOLS = b"#*$%&|<>"
_SPACE = [32, *range(9, 14)]
_LOWER, _UPPER, _DIGIT = list(range(97, 123)), list(range(65, 91)), list(range(48, 58))

#: Names of what :func:`shares` returns.
SHARES = ["letters", "upper", "digits", "symbols", "exclaim", "stops", "commas", "other_marks", "word_length", "long_words", "adjacent_repeats", "distinct", "top_word", "lines_per_word", "marked_ends", "log_words"]


def histogram(raw: bytes) -> np.ndarray:
    return np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256)


def rule_counts(raw: bytes) -> tuple[int, int, int, int, int, list[bytes], np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, and the words and byte histogram they came from."""
    words, count = raw.split(), histogram(raw)
    code_points = len(raw) - int(count[0x80:0xC0].sum())
    chars = code_points - int(count[_SPACE].sum())
    symbols = int(count[list(SYMBOLS)].sum())
    dup = 0
    if count[10]:
        lines = [x for x in raw.split(b"\n") if x and x.strip(b" \t\n\r\x0b\x0c")]
        dup = len(lines) - len(set(lines))
    return len(words), chars, symbols, dup, repeated_words(words), words, count


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a window of three which the text has at least twice; a word counts once."""
    if len(words) < 4:
        return 0
    windows = list(zip(words, words[1:], words[2:]))
    first: dict = {}
    setdefault = first.setdefault
    starts = [setdefault(w, i) for i, w in enumerate(windows)]
    if len(first) == len(windows):
        return 0
    at = np.asarray(starts)
    twice = np.bincount(at, minlength=len(at)) > 1
    hit = twice[at]
    covered = np.zeros(len(words), dtype=bool)
    for k in range(3):
        covered[k : len(hit) + k] |= hit
    return int(covered.sum())


def shares(raw: bytes, words: list[bytes], count: np.ndarray) -> list[float]:
    """Measures of a text that its length hardly moves; an empty text has zeros."""
    n = len(words)
    if not n:
        return [0.0] * len(SHARES)
    size = max(1, len(raw) - int(count[_SPACE].sum()))
    lower, upper, digits, high = int(count[_LOWER].sum()), int(count[_UPPER].sum()), int(count[_DIGIT].sum()), int(count[128:].sum())
    marks = size - lower - upper - digits - high
    # In upper case, two-byte letters of Latin scripts have a last byte of 0x80 to 0x9E; they stay with "letters".
    symbols, exclaim, stops, commas = int(count[list(SYMBOLS)].sum()), int(count[33]), int(count[46]), int(count[44])
    seen: dict[bytes, int] = {}
    get = seen.get
    for w in words:
        seen[w] = get(w, 0) + 1
    ends = sum(w[-1] in b"#*$%&|<>!" for w in seen)
    return [
        (lower + upper + high) / size,
        upper / max(1, lower + upper),
        digits / size,
        symbols / size,
        exclaim / size,
        stops / n,
        commas / n,
        max(0, marks - symbols - exclaim - stops - commas) / size,
        min(size / n, 40.0) / 10,
        sum(len(w) > 20 for w in seen) / len(seen),
        sum(map(eq, words, words[1:])) / n,
        len(seen) / n**0.8,
        max(seen.values()) / n,
        count[10] / n,
        ends / len(seen),
        float(np.log(n)) / 10,
    ]
