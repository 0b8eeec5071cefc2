"""Word segmentation and 64-bit hashing over whole Arrow string columns.

Everything here is vectorised over all texts of a batch: no Python loop over
words or documents.  Word hashes come from one running polynomial sum over the
bytes (the multiplier is odd, hence invertible modulo 2**64), so the cost is a
few nanoseconds a byte.  Blocks of at most ``BLOCK`` bytes, cut between words,
bound the memory whatever the length of a text; their arrays of eight bytes a
byte fit the processor's cache.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

BLOCK = 1 << 18


def _lean() -> None:
    """Give large buffers back to the system at once: workers live long, and
    several share an executor's memory."""
    pa.set_memory_pool(pa.system_memory_pool())
    libc = ctypes.CDLL(None)
    if hasattr(libc, "mallopt"):  # glibc
        libc.mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD


_lean()
U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_BASE_INV = pow(_BASE, -1, 1 << 64)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: blank and the five control characters from tab to carriage return
BLANKS = np.zeros(256, bool)
BLANKS[[32, *range(9, 14)]] = True
#: every ASCII byte that is not a letter or a digit
NON_ALNUM = np.zeros(256, bool)
NON_ALNUM[:128] = True
NON_ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123)]] = False

_pow = np.ones(1, U)
_inv = np.ones(1, U)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _pow, _inv
    if len(_pow) < n:
        size = max(n, BLOCK + 1)
        with np.errstate(over="ignore"):
            steps = np.full(size, _BASE, U)
            steps[0] = 1
            _pow = np.cumprod(steps, dtype=U)
            steps[1:] = _BASE_INV
            _inv = np.cumprod(steps, dtype=U)
    return _pow, _inv


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    with np.errstate(over="ignore"):
        x = x + U((salt * 0xD1B54A32D192ED03 + 0x632BE59BD9B4E019) % (1 << 64))
        x ^= x >> U(30)
        x *= U(0xBF58476D1CE4E5B9)
        x ^= x >> U(27)
        x *= U(0x94D049BB133111EB)
        x ^= x >> U(31)
        return x


def buffers(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    n, at = len(column), column.offset
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = column.buffers()
    off = np.frombuffer(off, np.int64)[at : at + n + 1]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


def chunks(column: pa.Array, limit: int = BLOCK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of rows whose texts hold about ``limit`` bytes (a longer text
    comes alone): first row, last row + 1, bytes, offsets."""
    data, off = buffers(column)
    row, n = 0, len(off) - 1
    while row < n:
        end = max(row + 1, int(np.searchsorted(off, off[row] + limit, "right")) - 1)
        yield row, end, data[off[row] : off[end]], off[row : end + 1] - off[row]
        row = end


@dataclass
class Words:
    """start, end: byte positions; text: row of each word; hash: of its bytes."""

    start: np.ndarray
    end: np.ndarray
    text: np.ndarray
    hash: np.ndarray

    def first(self, texts: int) -> np.ndarray:
        """Index of each text's first word, and of the end."""
        return np.searchsorted(self.text, np.arange(texts + 1))


def script_cuts(data: np.ndarray) -> np.ndarray | None:
    """Byte positions before and after every character of the scripts that are
    written without blanks (Han, kana, Thai, Lao, Khmer, Myanmar)."""
    lead = np.flatnonzero(data >= 0xE0)
    if not len(lead):
        return None
    one, two = data[lead], data[np.minimum(lead + 1, len(data) - 1)]
    thai = (one == 0xE0) & (two >= 0xB8) & (two <= 0xBB)
    khmer = (one == 0xE1) & ((two <= 0x82) | (two == 0x9E) | (two == 0x9F))
    rare = (one == 0xF0) & (two >= 0xA0) & (two <= 0xB3)
    at = lead[((one >= 0xE3) & (one <= 0xE9)) | thai | khmer | rare]
    return np.concatenate([at, at + 3 + (data[at] == 0xF0)])


def words(data: np.ndarray, off: np.ndarray, separators: np.ndarray, prefixes: tuple[int, ...] = (), cuts: np.ndarray | None = None, hashed: bool = True) -> Words | tuple:
    """Words of all texts, A-Z lower-cased; with ``prefixes`` also the hashes
    of the words' first so many bytes; ``cuts``: where words begin besides;
    not ``hashed``: places only, the hashes are zeros."""
    parts, at, n = [], 0, len(data)
    bounds = np.zeros(n + 1, bool)
    bounds[off] = True
    if cuts is not None:
        bounds[cuts] = True
    while at < n:
        end = min(n, at + BLOCK)
        if end < n:
            cut = np.flatnonzero(separators[data[max(at, end - 65536) : end]])
            if len(cut):
                end = max(at, end - 65536) + int(cut[-1]) + 1
            else:  # no blank near: go on to the next one
                cut = np.flatnonzero(separators[data[end:]])
                end = end + int(cut[0]) + 1 if len(cut) else n
        low = LOWER[data[at:end]] if hashed else data[at:end]
        inside = ~separators[low]
        edge = bounds[at:end]
        before = np.empty(len(low), bool)
        before[0] = False
        before[1:] = inside[:-1]
        start = np.flatnonzero(inside & (~before | edge))
        after = np.empty(len(low), bool)
        after[-1] = False
        after[:-1] = inside[1:] & ~edge[1:]
        stop = np.flatnonzero(inside & ~after) + 1
        if not hashed:
            parts.append((start + at, stop + at, np.zeros(len(start), U)))
            at = end
            continue
        power, inverse = _powers(len(low) + 1)
        with np.errstate(over="ignore"):
            total = np.empty(len(low) + 1, U)
            total[0] = 0
            value = low.astype(U)
            value += U(1)
            value *= power[: len(low)]
            np.cumsum(value, out=total[1:])
            back, base = inverse[start], total[start]
            hashes = [mix((total[stop] - base) * back)]
            for k in prefixes:
                hashes.append(mix((total[np.minimum(stop, start + k)] - base) * back, k))
        parts.append((start + at, stop + at, *hashes))
        at = end
    cols = [np.concatenate(c) for c in zip(*parts)] if parts else [np.zeros(0, np.int64)] * 2 + [np.zeros(0, U)] * (1 + len(prefixes))
    text = np.repeat(np.arange(len(off) - 1), np.diff(np.searchsorted(cols[0], off)))
    out = Words(cols[0], cols[1], text, cols[2])
    return (out, cols[3:]) if prefixes else out


_GRAM = [pow(0xC2B2AE3D27D4EB4F, i + 1, 1 << 64) for i in range(256)]


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of ``k`` values, in order; shorter than h by k - 1."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, U)
    with np.errstate(over="ignore"):
        out = np.zeros(n, U)
        for i in range(k):
            out += h[i : i + n] * U(_GRAM[i])
        return mix(out, k)


_ODD, _ODD_INV = 0xD6E8FEB86659FD93, pow(0xD6E8FEB86659FD93, -1, 1 << 64)


def _odd_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    power, back = np.full(n, _ODD, U), np.full(n + 1, _ODD_INV, U)
    return np.cumprod(power, dtype=U), np.cumprod(back, dtype=U)


_odd = _odd_powers(BLOCK)


def sums(values: np.ndarray, like: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Running polynomial sum, the inverse powers and the powers, for hashes of
    any span; ``like``: sums of as many values, whose powers are taken over."""
    m = len(values)
    with np.errstate(over="ignore"):
        power, back = (like[2], like[1]) if like is not None else _odd if m <= BLOCK else _odd_powers(m)
        power, back = power[:m], back[: m + 1]
        total = np.zeros(m + 1, U)
        np.cumsum(values * power, out=total[1:])
    return total, back, power


def span(of: tuple, first: np.ndarray, last: np.ndarray, salt: int) -> np.ndarray:
    """Hashes of the values first..last - 1, the same wherever they stand."""
    total, back, _ = of
    with np.errstate(over="ignore"):
        return mix((total[last] - total[first]) * back[first], salt)
