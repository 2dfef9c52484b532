"""An open-addressing table from non-negative 63-bit keys to 32-bit values, looked up in arrays."""

from __future__ import annotations

import numpy as np

_PROBE = np.uint64(0x9E3779B97F4A7C15)


class LongTable:
    def __init__(self, keys: np.ndarray, values: np.ndarray, default: int):
        self.default = np.int32(default)
        self.bits = max(10, int(np.ceil(np.log2(max(1, len(keys)) * 4))))
        self.mask = (1 << self.bits) - 1
        self.slots = np.full(1 << self.bits, -1, np.int64)
        self.values = np.full(1 << self.bits, default, np.int32)
        at = self._slot(keys)
        left = np.arange(len(keys))
        while len(left):
            free = self.slots[at[left]] == -1
            self.slots[at[left[free]]] = keys[left[free]]
            placed = self.slots[at[left]] == keys[left]
            self.values[at[left[placed]]] = values[left[placed]]
            left = left[~placed]
            at[left] = (at[left] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * _PROBE) >> np.uint64(64 - self.bits)).astype(np.int64)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        at = self._slot(keys)
        found = self.slots[at]
        out = np.where(found == keys, self.values[at], self.default)
        open_ = np.flatnonzero((found != keys) & (found != -1))
        while len(open_):
            at[open_] = (at[open_] + 1) & self.mask
            found = self.slots[at[open_]]
            hit = found == keys[open_]
            out[open_[hit]] = self.values[at[open_[hit]]]
            open_ = open_[~hit & (found != -1)]
        return out
