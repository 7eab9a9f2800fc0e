"""Open addressing over 64-bit keys on arrays; the key of all ones stands for none and is not for use."""

from __future__ import annotations

import numpy as np

FREE = np.uint64(0xFFFFFFFFFFFFFFFF)
_SPREAD = np.uint64(0x9E3779B97F4A7C15)


def _home(keys: np.ndarray, bits: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return ((keys * _SPREAD) >> np.uint64(64 - bits)).astype(np.int64)


def hash_table(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(keys by slot, their rows by slot, -1 where free), at most half full. Keys are distinct."""
    bits = max(4, int(2 * max(1, len(keys)) - 1).bit_length())
    slots, rows = np.full(1 << bits, FREE), np.full(1 << bits, -1, np.int32)
    left, slot = np.arange(len(keys)), _home(keys, bits)
    while len(left):
        free = np.flatnonzero(slots[slot] == FREE)
        _, one = np.unique(slot[free], return_index=True)
        put = free[one]
        slots[slot[put]], rows[slot[put]] = keys[left[put]], left[put]
        stay = np.ones(len(left), bool)
        stay[put] = False
        left, slot = left[stay], (slot[stay] + 1) & ((1 << bits) - 1)
    return slots, rows


def find_slot(slots: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Slot of each key, or -1."""
    slot = _home(keys, len(slots).bit_length() - 1)
    at = slots[slot]
    found = np.where(at == keys, slot, -1)
    left = np.flatnonzero((at != keys) & (at != FREE))
    while len(left):
        slot[left] = (slot[left] + 1) & (len(slots) - 1)
        at = slots[slot[left]]
        same = at == keys[left]
        found[left[same]] = slot[left[same]]
        left = left[~same & (at != FREE)]
    return found
