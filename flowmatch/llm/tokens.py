"""Hashes of the tokens of texts: words with A-Z lower-cased, then one end for each text."""

from __future__ import annotations

import numpy as np

_U = np.uint64
_STEP = 0x5851F42D4C957F2D | 1


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit mixing of 64-bit numbers, one to one."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


END = mix(np.array([0x5EED], dtype=np.uint64))[0]


class Tokens:
    """Hashes of tokens, made for a block of texts at a time by running sums over its bytes."""

    def __init__(self):
        self.byte = mix(np.arange(1, 257, dtype=np.uint64) * _U(0x9E3779B97F4A7C15))
        self.space = np.zeros(256, dtype=bool)
        self.space[[32, *range(9, 14)]] = True
        self.power = self.inverse = np.ones(1, dtype=np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.power) < n:
            n = 1 << n.bit_length()
            self.power = np.cumprod(np.r_[_U(1), np.full(n - 1, _STEP, dtype=np.uint64)], dtype=np.uint64)
            self.inverse = np.cumprod(np.r_[_U(1), np.full(n - 1, pow(_STEP, -1, 1 << 64), dtype=np.uint64)], dtype=np.uint64)

    def of(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The texts' token hashes in order, ends included, and each text's number of tokens."""
        raw = np.frombuffer(b"\n".join(texts).lower() + b"\n", dtype=np.uint8)
        self._powers(len(raw))
        blank = self.space[raw]
        edge = np.flatnonzero(np.diff(blank, prepend=True))
        starts, ends = edge[::2], edge[1::2]
        sums = np.zeros(len(raw) + 1, dtype=np.uint64)
        np.cumsum(self.byte[raw] * self.power[: len(raw)], out=sums[1:])
        h = mix((sums[ends] - sums[starts]) * self.inverse[starts] + (ends - starts).astype(np.uint64))
        upto = np.cumsum([len(t) + 1 for t in texts])
        words = np.diff(np.searchsorted(starts, upto), prepend=0)
        size = words + 1
        out = np.full(int(size.sum()), END, dtype=np.uint64)
        keep = np.ones(len(out), dtype=bool)
        keep[np.cumsum(size) - 1] = False
        out[keep] = h
        return out, size


def batched(texts: list[bytes], limit: int = 1 << 20):
    """Runs of texts of about ``limit`` bytes; a longer text is a run of its own."""
    run, size = [], 0
    for t in texts:
        if run and size + len(t) > limit:
            yield run
            run, size = [], 0
        run.append(t)
        size += len(t)
    if run:
        yield run
