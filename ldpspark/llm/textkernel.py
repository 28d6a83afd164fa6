"""Word and shingle hashes of whole Arrow batches of texts, by array operations on their UTF-8 bytes.

A batch is worked in runs of at most ``RUN_BYTES`` (or one text, if longer), which bounds memory
whatever the lengths of the texts. Hashes are 64-bit polynomials over a random byte table,
finished by a mixing step; they depend on the word alone, so all executors agree.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

RUN_BYTES = 1 << 18
U = np.uint64

_rng = np.random.Generator(np.random.PCG64(20240607))
_BYTE = _rng.integers(0, 1 << 64, 256, dtype=np.uint64) | U(1)
_BASE = int(_rng.integers(0, 1 << 62)) * 4 + 3
_BASE_INV = pow(_BASE, -1, 1 << 64)
_LANE = _rng.integers(0, 1 << 64, 64, dtype=np.uint64) | U(1)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: Bytes that separate words, 0x09-0x0D and 0x20.
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[9, 10, 11, 12, 13, 32]] = False

#: Letters, digits and every byte of a character beyond ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[97:123] = ALNUM[65:91] = True
ALNUM[128:] = True

_powers: dict[str, np.ndarray] = {}


def _power(name: str, base: int, n: int) -> np.ndarray:
    have = _powers.get(name)
    if have is None or len(have) < n:
        size = max(n, RUN_BYTES + 1)
        steps = np.full(size, U(base), dtype=np.uint64)
        steps[0] = U(1)
        have = _powers[name] = np.multiply.accumulate(steps)
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


def texts_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column; a null text is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    n = len(column)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def runs(offsets: np.ndarray, size: int = RUN_BYTES):
    """Ranges of texts of about ``size`` bytes together."""
    n, a = len(offsets) - 1, 0
    while a < n:
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + size, "right")) - 1)
        yield a, min(b, n)
        a = min(b, n)


def word_bounds(raw: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and text number of each word; a word never crosses two texts."""
    w = inside[raw]
    if not len(w):
        z = np.zeros(0, np.int64)
        return z, z, z
    cut = np.zeros(len(w) + 1, dtype=bool)
    cut[offsets] = True
    before = np.empty_like(w)
    before[0], before[1:] = False, w[:-1]
    after = np.empty_like(w)
    after[-1], after[:-1] = False, w[1:]
    starts = np.flatnonzero(w & (~before | cut[:-1]))
    ends = np.flatnonzero(w & (~after | cut[1:])) + 1
    return starts, ends, np.searchsorted(offsets, starts, "right") - 1


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of lower-cased words (A-Z only)."""
    n = len(raw)
    if not n:
        return np.zeros(0, np.uint64)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum(_BYTE[LOWER[raw]] * _power("up", _BASE, n), out=sums[1:])
    h = (sums[ends] - sums[starts]) * _power("down", _BASE_INV, n)[starts]
    return mix(h + (ends - starts).astype(np.uint64) * _LANE[63])


def shingle_hashes(words: np.ndarray, of: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of ``size`` words of a text, in order, and their text numbers.

    A text of fewer words, but not none, has its whole sequence as its one shingle.
    """
    n = len(words)
    total = np.zeros(n, np.uint64)
    full = np.zeros(n, dtype=bool)
    for j in range(size):
        total[: max(0, n - j)] += words[j:] * _LANE[j]
    if n >= size:
        full[: n - size + 1] = of[: n - size + 1] == of[size - 1 :]
    first = np.ones(n, dtype=bool)
    first[1:] = of[1:] != of[:-1]
    for i in np.flatnonzero(first & ~full):
        k = int(np.searchsorted(of, of[i], "right")) - i
        tag = np.full(1, k, np.uint64) * _LANE[62:63]
        total[i : i + 1] = (words[i : i + k] * _LANE[:k]).sum(dtype=np.uint64) + tag
        full[i] = True
    return mix(total[full]), of[full]


def shingle_sets(column: pa.Array, size: int = 5):
    """Yields the sorted distinct shingle hashes of each text, in the order of the column."""
    raw, offsets = texts_of(column)
    for a, b in runs(offsets):
        part, at = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, ends, of = word_bounds(part, at, NOT_SPACE)
        hashes, text = shingle_hashes(word_hashes(part, starts, ends), of, size)
        edges = np.searchsorted(text, np.arange(b - a + 1))
        for i in range(b - a):
            own = np.sort(hashes[edges[i] : edges[i + 1]])
            if len(own) > 1:
                own = own[np.concatenate(([True], own[1:] != own[:-1]))]
            yield own
