"""The small tables of the hybrid gain table, as tasks use them."""

from __future__ import annotations

import numpy as np


class ProbeTable:
    """A small table from blocks to affinities with linear probing; what falls to 0 leaves no gap behind, as later entries of
    the probe sequence move up. Entries have the narrowest type that holds the vertex's incident weight."""

    TYPES = {8: np.uint8, 16: np.uint16, 32: np.uint32, 64: np.uint64}

    def __init__(self, degree: int, incident: int):
        slots = 1
        while slots < -(-3 * degree // 2):
            slots *= 2
        self.keys = np.full(slots, -1, dtype=np.int32)
        self.values = np.zeros(slots, dtype=self.TYPES[next(w for w in (8, 16, 32, 64) if incident < 1 << w)])

    def _slot(self, key: int) -> int:
        mask = len(self.keys) - 1
        at = key * 0x9E3779B1 >> 7 & mask
        while self.keys[at] != key and self.keys[at] != -1:
            at = at + 1 & mask
        return at

    def get(self, key: int) -> int:
        at = self._slot(key)
        return int(self.values[at]) if self.keys[at] == key else 0

    def add(self, key: int, delta: int) -> None:
        at = self._slot(key)
        value = int(self.values[at]) + delta if self.keys[at] == key else delta
        if value:
            self.keys[at], self.values[at] = key, value
        elif self.keys[at] == key:
            self._remove(at)

    def _remove(self, hole: int) -> None:
        mask = len(self.keys) - 1
        at = hole
        while True:
            at = at + 1 & mask
            if self.keys[at] == -1 or at == hole:
                break
            home = int(self.keys[at]) * 0x9E3779B1 >> 7 & mask
            if (at - home & mask) >= (at - hole & mask):
                self.keys[hole], self.values[hole], hole = self.keys[at], self.values[at], at
        self.keys[hole], self.values[hole] = -1, 0

    def items(self) -> dict[int, int]:
        return {int(k): int(v) for k, v in zip(self.keys, self.values, strict=True) if k != -1}
