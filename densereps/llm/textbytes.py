"""Arrow string columns as numpy bytes, and word tables over them without a Python loop per word."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Bytes of text handled at once, whole texts at least.
CHUNK = 1 << 20

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Word bytes after lower-casing: digits, a-z, everything beyond ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[97:123] = ALNUM[128:] = True

_MIX = np.uint64(0x9E3779B97F4A7C15)
_STEP = np.uint64(0xD6E8FEB86659FD93)


def give_back() -> None:
    """Return freed memory to the system; a worker that waits for its next task would keep it."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def powers(base: np.uint64, n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(max(n - 1, 0), base, np.uint64)]))


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string array; a null is an empty text."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    wide = pa.types.is_large_string(texts.type)
    if not wide and not pa.types.is_string(texts.type):
        texts = texts.cast(pa.string())
    _, at, data = texts.buffers()
    kind = np.int64 if wide else np.int32
    if at is None or len(texts) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(at, kind)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(texts: pa.Array, size: int = CHUNK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, last row + 1, bytes, offsets) of runs of whole texts of about size bytes."""
    data, at = buffers(texts)
    row = 0
    while row < len(at) - 1:
        end = max(row + 1, int(np.searchsorted(at, at[row] + size, "right")) - 1)
        yield row, end, data[at[row] : at[end]], at[row : end + 1] - at[row]
        row = end


@dataclass
class Words:
    """Words of a run of texts, in order: byte range, 64-bit hash, and the text they are in."""

    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    text: np.ndarray
    lowered: np.ndarray
    stems: dict[int, np.ndarray]


def words(data: np.ndarray, at: np.ndarray, size: int = CHUNK, stems: tuple[int, ...] = ()) -> Words:
    """Words of [0-9a-z and non-ASCII] in lower-cased bytes; none crosses a text's end.

    stems: lengths in bytes; for each, the hash of every word's first so many bytes (of all, if it has fewer).
    """
    lowered = LOWER[data]
    starts, ends, hashes = [], [], []
    stem_hashes: dict[int, list[np.ndarray]] = {k: [] for k in stems}
    begin = 0
    while begin < len(lowered):
        stop = min(len(lowered), begin + size)
        while stop < len(lowered) and ALNUM[lowered[stop - 1]] and ALNUM[lowered[stop]]:
            gap = np.flatnonzero(~ALNUM[lowered[stop : stop + size]])
            stop = stop + int(gap[0]) if len(gap) else min(len(lowered), stop + size)
        part = lowered[begin:stop]
        inside = ALNUM[part]
        edge = np.zeros(len(part) + 1, bool)
        edge[at[(at >= begin) & (at <= stop)] - begin] = True
        first = inside.copy()
        first[1:] &= ~inside[:-1] | edge[1:-1]
        last = inside.copy()
        last[:-1] &= ~inside[1:] | edge[1:-1]
        s = np.flatnonzero(first)
        e = np.flatnonzero(last) + 1
        if len(s):
            where = np.flatnonzero(inside)
            lengths = e - s
            place = np.arange(len(where)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
            table = powers(_MIX, int(lengths.max()))
            with np.errstate(over="ignore"):
                weighted = (part[where].astype(np.uint64) + np.uint64(1)) * table[place]
                h = np.add.reduceat(weighted, np.cumsum(lengths) - lengths)
                h = (h ^ (h >> np.uint64(29))) * _STEP
                for k in stems:
                    g = np.add.reduceat(np.where(place < k, weighted, 0), np.cumsum(lengths) - lengths)
                    stem_hashes[k].append((g ^ (g >> np.uint64(29))) * _STEP + np.uint64(k))
            starts.append(s + begin)
            ends.append(e + begin)
            hashes.append(h)
        begin = stop
    join = lambda parts, kind: np.concatenate(parts) if parts else np.zeros(0, kind)
    start = join(starts, np.int64)
    firsts = {k: join(v, np.uint64) for k, v in stem_hashes.items()}
    return Words(start, join(ends, np.int64), join(hashes, np.uint64), np.searchsorted(at, start, "right") - 1, lowered, firsts)


def per_text(values: np.ndarray, text: np.ndarray, n: int) -> np.ndarray:
    """Sum of values for each of n texts."""
    return np.bincount(text, weights=values, minlength=n) if len(text) else np.zeros(n)
