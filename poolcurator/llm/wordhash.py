"""Words, shingles and hashes of whole UTF-8 texts with numpy, on Arrow buffers.

A word is a maximal run of ASCII letters, ASCII digits and bytes of non-ASCII characters, with
A-Z lower-cased. Texts are worked through in segments cut between words, so memory follows
the segment and not the text.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
SEGMENT = 1 << 18
#: Bytes of texts that are worked on at once.
SLICE = 1 << 20
_BASE = 0x9E3779B97F4A7C15
_LOWER = np.zeros(256, dtype=U)
for _c in [*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]:
    _LOWER[_c] = _c + 1
for _c in range(0x41, 0x5B):
    _LOWER[_c] = _c + 33
_IS_WORD = _LOWER > 0


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(n: int, base: int = _BASE) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i up to n at least."""
    have = _powers.get(base)
    if have is None or len(have[0]) < n:
        size = max(n, SEGMENT * 2)
        both = []
        for b in (base, pow(base, -1, 1 << 64)):
            line = np.full(size, b, dtype=U)
            line[0] = 1
            both.append(np.multiply.accumulate(line))
        have = _powers[base] = (both[0], both[1])
    return have


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string column; null rows are empty."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def release() -> None:
    """Gives freed memory back to the system: workers live on after a task, and an executor's share is small."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows, 65,536 at most, whose texts have about `most` bytes together."""
    _, off = utf8(batch.column(batch.schema.get_field_index(column)))
    i = 0
    while i < batch.num_rows:
        j = int(np.searchsorted(off, off[i] + most, "right")) - 1
        j = min(max(j, i + 1), batch.num_rows, i + (1 << 16))
        yield batch.slice(i, j - i)
        i = j
    release()


def words(raw: np.ndarray, off: np.ndarray, prefixes: tuple[int, ...] = ()) -> tuple[np.ndarray, np.ndarray, dict[int, np.ndarray]]:
    """Hash and row of every word in order, and hashes of the words' first p bytes (0 for shorter words)."""
    hashes, begins, heads = [], [], {p: [] for p in prefixes}
    lo, n = 0, len(raw)
    while lo < n:
        hi = min(n, lo + SEGMENT)
        while hi < n:  # cut between words
            window = raw[hi : hi + 4096]
            gap = np.flatnonzero(~_IS_WORD[window])
            if len(gap):
                hi += int(gap[0])
                break
            hi = min(n, hi + len(window))
        part = raw[lo:hi]
        value = _LOWER[part]
        is_word = value > 0
        first = is_word.copy()
        first[1:] &= ~is_word[:-1]
        a, b = np.searchsorted(off, [lo, hi])
        cuts = off[a:b] - lo
        first[cuts] = is_word[cuts]
        begin = np.flatnonzero(first)
        if len(begin):
            up, down = powers(len(part) + 1)
            value *= up[: len(part)]
            hashes.append(mix(np.add.reduceat(value, begin) * down[begin]))
            begins.append(begin + lo)
            if prefixes:
                total = np.zeros(len(part) + 1, dtype=U)
                np.cumsum(value, out=total[1:])
                ends = np.flatnonzero(is_word & ~np.append(is_word[1:] & ~first[1:], False)) + 1
                length = ends - begin
                for p in prefixes:
                    upto = np.minimum(begin + p, len(part))
                    head = mix((total[upto] - total[begin]) * down[begin] + U(p))
                    head[length <= p] = 0
                    heads[p].append(head)
        lo = hi
    if not hashes:
        return np.zeros(0, U), np.zeros(0, np.int64), {p: np.zeros(0, U) for p in prefixes}
    begin = np.concatenate(begins)
    return np.concatenate(hashes), np.searchsorted(off, begin, "right") - 1, {p: np.concatenate(x) for p, x in heads.items()}


_STEP = tuple(U(x) for x in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3))


def shingles(word: np.ndarray, row: np.ndarray, rows: int, k: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, row and first word (within its row) of every k-word shingle; a text with 1 to k-1 words is one shingle."""
    count = np.bincount(row, minlength=rows)
    begin = np.cumsum(count) - count
    n = len(word)
    place = np.arange(n) - begin[row]
    if n >= k:
        whole = row[: n - k + 1] == row[k - 1 :]
        h = np.zeros(n - k + 1, dtype=U)
        for j in range(k):
            h += word[j : n - k + 1 + j] * _STEP[j % 5] + U(j // 5)
        h, r, p = mix(h[whole]), row[: n - k + 1][whole], place[: n - k + 1][whole]
    else:
        h, r, p = np.zeros(0, U), np.zeros(0, np.int64), np.zeros(0, np.int64)
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        part = np.flatnonzero(np.isin(row, short))
        steps = np.array(_STEP, dtype=U)[place[part] % 5]
        edges = np.flatnonzero(np.append(True, row[part][1:] != row[part][:-1]))
        sums = np.add.reduceat(word[part] * steps, edges)
        h = np.append(h, mix(sums + count[short].astype(U)))
        r = np.append(r, short)
        p = np.append(p, np.zeros(len(short), np.int64))
    return h, r, p


def row_keys(word: np.ndarray, row: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit keys of each row's word sequence; 0 for rows without words."""
    count = np.bincount(row, minlength=rows)
    keys = []
    used = np.flatnonzero(count)
    begin = (np.cumsum(count) - count)[used]
    place = np.arange(len(word)) - (np.cumsum(count) - count)[row]
    for base in (0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9):
        key = np.zeros(rows, dtype=U)
        if len(used):
            up, _ = powers(int(count.max()) + 1, base)
            key[used] = mix(np.add.reduceat(word * up[place], begin) + count[used].astype(U))
        keys.append(key)
    return keys[0], keys[1]
