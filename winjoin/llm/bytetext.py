"""Vectorised tokenising of Arrow string batches on their raw UTF-8 bytes.

Words never span rows. Bytes of 0x80 and above belong to non-ASCII characters,
so a byte class table cuts UTF-8 text exactly as a character class would as
long as the class treats all non-ASCII characters alike.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: A-Z to a-z, all else unchanged.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: Digits, lower-case ASCII letters and everything outside ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = True
ALNUM[97:123] = True
ALNUM[128:] = True

#: Everything but blank and the control characters 9 to 13.
NONSPACE = np.ones(256, dtype=bool)
NONSPACE[9:14] = False
NONSPACE[32] = False

_MUL = np.uint64(0x9E3779B97F4A7C15)
_POWERS = np.cumprod(np.full(4096, _MUL, dtype=np.uint64), dtype=np.uint64)


def trim() -> None:
    """Give freed memory back at the end of a task: workers live on and serve other operators."""
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser: every input bit reaches every output bit."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def flat(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and its row offsets; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[offs[0] : offs[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, offs - offs[0]


def pieces(batch: pa.RecordBatch, text: str | int, most: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Row slices of about ``most`` bytes of text (one row at least)."""
    at = text if isinstance(text, int) else batch.schema.get_field_index(text)
    _, offs = flat(batch.column(at))
    start = 0
    while start < batch.num_rows:
        stop = max(start + 1, int(np.searchsorted(offs, offs[start] + most, side="right")) - 1)
        yield batch.slice(start, stop - start)
        start = stop


def spans(raw: np.ndarray, offs: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of all maximal runs of ``inside`` bytes, and for each row the index of its first run."""
    n = len(raw)
    if n == 0:
        empty = np.zeros(0, np.int64)
        return empty, empty, np.zeros(len(offs), np.int64)
    mask = inside[raw]
    before = np.empty(n + 1, bool)
    before[0] = False
    before[1:] = mask
    after = np.empty(n + 1, bool)
    after[:-1] = mask
    after[-1] = False
    # a row boundary ends every run
    cut = np.zeros(n + 1, bool)
    cut[offs] = True
    starts = np.flatnonzero(after & (~before | cut))
    ends = np.flatnonzero(before & (~after | cut))
    return starts, ends, np.searchsorted(starts, offs)


def run_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, block: int = 150_000) -> np.ndarray:
    """A 64-bit hash of the bytes of each run; work space is bounded by ``block`` runs."""
    out = np.empty(len(starts), np.uint64)
    for a in range(0, len(starts), block):
        s, e = starts[a : a + block], ends[a : a + block]
        size = e - s
        first = np.concatenate([[0], np.cumsum(size)[:-1]])
        within = np.arange(int(size.sum()), dtype=np.int64) - np.repeat(first, size)
        at = within + np.repeat(s, size)
        # positions beyond the table reuse it, told apart by their lap
        lap, within = within >> 12, within & 4095
        value = (raw[at].astype(np.uint64) + np.uint64(1) + (lap.astype(np.uint64) << np.uint64(9))) * _POWERS[within]
        out[a : a + block] = mix(np.add.reduceat(value, first) + size.astype(np.uint64))
    return out


def rows_of(first: np.ndarray, total: int) -> np.ndarray:
    """For each run the row that holds it, from each row's first run."""
    return np.repeat(np.arange(len(first) - 1), np.diff(np.append(first[:-1], total)))


def windows(hashes: np.ndarray, rows: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k consecutive runs of a row, and the index of each window's first run."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    out = np.zeros(n, np.uint64)
    for j in range(k):
        out = out * _MUL + hashes[j : j + n]
    at = np.flatnonzero(rows[:n] == rows[k - 1 :])
    return mix(out[at] + np.uint64(k)), at
