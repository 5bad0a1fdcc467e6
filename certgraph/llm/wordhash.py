"""Words of UTF-8 texts as 64-bit hashes, computed for whole batches of texts with numpy.

A word is a run of bytes other than space and the control characters tab to carriage return. Lower-casing
touches A-Z only. The hash of a word is a polynomial over random 64-bit values of its bytes, taken from
prefix sums, so the cost is a few array passes per byte and no Python object per word.
"""

from __future__ import annotations

import numpy as np

#: Bytes of text handled in one set of arrays.
SLICE_BYTES = 1 << 18

_U = np.uint64
_rng = np.random.default_rng(20240517)
BYTE_VALUE = _rng.integers(0, 2**64, 256, dtype=np.uint64) | _U(1)
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_BASE = 0x9E3779B97F4A7C15 | 5
_BASE_INV = pow(_BASE, -1, 1 << 64)
_WINDOW_COEF = _rng.integers(0, 2**64, 64, dtype=np.uint64) | _U(1)
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Spread all bits of 64-bit values."""
    x = x ^ (x >> _U(33))
    x = x * _U(0xFF51AFD7ED558CCD)
    x = x ^ (x >> _U(33))
    x = x * _U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> _U(33))


def power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _powers.get("up")
    if have is None or len(have) < n:
        size = max(n, SLICE_BYTES + 4096)
        for name, base in (("up", _BASE), ("down", _BASE_INV)):
            t = np.full(size, base & (2**64 - 1), dtype=np.uint64)
            t[0] = 1
            _powers[name] = np.multiply.accumulate(t)
    return _powers["up"], _powers["down"]


def text_bytes(text: str | None, lower: bool) -> bytes:
    raw = b"" if text is None else text.encode("utf-8", "surrogatepass")
    return raw.lower() if lower else raw


def slices(sizes: list[int], limit: int = SLICE_BYTES):
    """Ranges [a, b) of neighbouring texts of about `limit` bytes together; a longer text stands alone."""
    a, held = 0, 0
    for i, n in enumerate(sizes):
        if i > a and held + n > limit:
            yield a, i
            a, held = i, 0
        held += n
    if a < len(sizes):
        yield a, len(sizes)


class Words:
    """Word hashes of several texts: `hashes`, byte `starts` and `ends` in `data`, and `bounds` by text."""

    __slots__ = ("bounds", "data", "ends", "hashes", "offsets", "starts")

    def __init__(self, raws: list[bytes]):
        self.data = np.frombuffer(b"\n".join(raws) + b"\n", dtype=np.uint8)
        d = self.data
        space = _IS_SPACE[d]
        before = np.empty_like(space)
        before[0] = True
        before[1:] = space[:-1]
        self.starts = np.flatnonzero(~space & before)
        self.ends = np.flatnonzero(space & ~before)
        up, down = power_table(len(d))
        sums = np.zeros(len(d) + 1, dtype=np.uint64)
        np.cumsum(BYTE_VALUE[d] * up[: len(d)], out=sums[1:])
        self.hashes = mix((sums[self.ends] - sums[self.starts]) * down[self.starts])
        lengths = np.fromiter((len(r) + 1 for r in raws), dtype=np.int64, count=len(raws))
        self.offsets = np.zeros(len(raws) + 1, dtype=np.int64)
        np.cumsum(lengths, out=self.offsets[1:])
        self.bounds = np.searchsorted(self.starts, self.offsets)


def window_hashes(hashes: np.ndarray, width: int) -> np.ndarray:
    """One hash for each window of `width` neighbouring words (none if there are fewer)."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    out = hashes[:n] * _WINDOW_COEF[0]
    for k in range(1, width):
        out = out + hashes[k : k + n] * _WINDOW_COEF[k]
    return mix(out + _U(width))


def shingle_set(hashes: np.ndarray, width: int) -> np.ndarray:
    """Sorted distinct shingles of one text; fewer words than `width` make one shingle, no words none."""
    if len(hashes) == 0:
        return hashes
    return np.unique(window_hashes(hashes, min(width, len(hashes))))
