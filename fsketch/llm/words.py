"""Words of many texts at once: places and hashes, in numpy over the bytes of an Arrow column."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

#: ASCII white space separates words.
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True

_LIMIT = 1 << 20
_rng = np.random.Generator(np.random.PCG64(20240229))
#: Per hash family: values of the 256 bytes and odd multipliers for bytes and words.
_FAMILIES = [
    (_rng.integers(1, 1 << 63, size=256, dtype=np.uint64), int(_rng.integers(1 << 40, 1 << 62)) * 2 + 1, int(_rng.integers(1 << 40, 1 << 62)) * 2 + 1)
    for _ in range(2)
]
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**i modulo 2**64 for i below n; kept, as bases are few."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(n, _LIMIT + 1)
        run = np.full(size, base & (2**64 - 1), dtype=np.uint64)
        run[0] = 1
        have = np.cumprod(run)
        if size <= 4 * _LIMIT:
            _powers[base] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads all bits of 64-bit values over all others."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


def buffer_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a binary column and the n + 1 offsets into them; nulls are empty."""
    n = len(column)
    if column.null_count:
        column = column.fill_null(b"")
    kind = np.int64 if pa.types.is_large_binary(column.type) else np.int32
    offsets = np.frombuffer(column.buffers()[1], dtype=kind)[column.offset : column.offset + n + 1].astype(np.int64)
    data = column.buffers()[2]
    whole = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def word_places(buf: np.ndarray, offsets: np.ndarray, space: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and text number of each word; no word runs over the end of its text."""
    sp = space[buf]
    if not len(buf):
        none = np.zeros(0, np.int64)
        return none, none, none
    before = np.empty(len(buf), bool)
    before[0], before[1:] = True, sp[:-1]
    heads = offsets[:-1]
    before[heads[heads < len(buf)]] = True
    after = np.empty(len(buf), bool)
    after[-1], after[:-1] = True, sp[1:]
    tails = offsets[1:]
    after[tails[tails > 0] - 1] = True
    starts, ends = np.flatnonzero(~sp & before), np.flatnonzero(~sp & after) + 1
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, family: int = 0) -> np.ndarray:
    """A 64-bit hash of each word, from running sums over the bytes; worked on in parts of bounded size."""
    table, base, _ = _FAMILIES[family]
    back = pow(base, -1, 2**64)
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        k = max(i + 1, int(np.searchsorted(ends, starts[i] + _LIMIT, side="right")))
        at, n = int(starts[i]), int(ends[k - 1] - starts[i])
        run = np.zeros(n + 1, np.uint64)
        np.cumsum(table[buf[at : at + n]] * powers(base, n), out=run[1:])
        s, e = starts[i:k] - at, ends[i:k] - at
        out[i:k] = mix((run[e] - run[s]) * powers(back, n)[s] + (e - s).astype(np.uint64))
        i = k
    return out


def rolling(hashes: np.ndarray, width: int, family: int = 0) -> np.ndarray:
    """A 64-bit hash of each run of ``width`` words."""
    _, _, base = _FAMILIES[family]
    back = pow(base, -1, 2**64)
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.empty(n, np.uint64)
    for i in range(0, n, _LIMIT // 2):
        k = min(n, i + _LIMIT // 2)
        part = hashes[i : k + width - 1]
        run = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part * powers(base, len(part)), out=run[1:])
        out[i:k] = mix((run[width:] - run[:-width]) * powers(back, k - i))
    return out
