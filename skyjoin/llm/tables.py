"""Hash tables in numpy arrays, for look-ups of whole batches, and the merges of a vocabulary in them."""

from __future__ import annotations

import numpy as np

from .piece_model import PieceModel

EMPTY = np.uint64(2**64 - 1)
#: The rank of a pair that makes no piece.
NONE = np.int32(2**31 - 1)


class Table:
    """64-bit keys to 32-bit numbers by linear probing."""

    def __init__(self, entries: int):
        """Room for about this many entries at a load of a third."""
        self.bits = max(4, int(np.ceil(np.log2(max(1, 3 * entries)))))
        self.clear()

    def clear(self) -> None:
        self.keys, self.values, self.used = np.full(1 << self.bits, EMPTY, np.uint64), np.zeros(1 << self.bits, np.int32), 0

    def _slot(self, key: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((key * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, key: np.ndarray) -> np.ndarray:
        """The number of each key, -1 where there is none."""
        mask, at = (1 << self.bits) - 1, self._slot(key)
        there = self.keys[at]
        hit = there == key
        out = np.where(hit, self.values[at], np.int32(-1))
        todo = np.flatnonzero(~hit & (there != EMPTY))
        while len(todo):
            at[todo] = (at[todo] + 1) & mask
            there = self.keys[at[todo]]
            hit = there == key[todo]
            out[todo[hit]] = self.values[at[todo[hit]]]
            todo = todo[~hit & (there != EMPTY)]
        return out

    def put(self, key: np.ndarray, value: np.ndarray) -> None:
        """Adds distinct keys that aren't there yet."""
        self.used += len(key)
        mask, at = (1 << self.bits) - 1, self._slot(key)
        while len(key):
            _, first = np.unique(at, return_index=True)  # one key a slot, where the slot is free
            first = first[self.keys[at[first]] == EMPTY]
            self.keys[at[first]], self.values[at[first]] = key[first], value[first]
            rest = np.ones(len(key), bool)
            rest[first] = False
            key, value, at = key[rest], value[rest], (at[rest] + 1) & mask

    def full(self, more: int) -> bool:
        return 3 * (self.used + more) > 2 << self.bits


def pair_key(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return a.astype(np.uint64) << np.uint64(32) | b.astype(np.uint64)


class Merges:
    """All pairs of pieces whose joined text is a piece, by the model's numbers."""

    def __init__(self, model: PieceModel):
        ids = model.ids
        self.rank = np.full(model.size, NONE, np.int32)
        for p, i in ids.items():
            self.rank[i] = model.rank[p]
        rows = [(ids[p[:k]], ids[p[k:]], i) for p, i in ids.items() for k in range(1, len(p)) if p[:k] in ids and p[k:] in ids]
        a, b, made = np.array(rows, np.int64).reshape(-1, 3).T
        self.table = Table(len(rows))
        self.table.put(pair_key(a, b), made.astype(np.int32))
        #: Pieces that make another piece of no higher rank: their other occurrences must wait.
        self.hasty = np.zeros(model.size, bool)
        for part in (a, b):
            self.hasty[part[self.rank[made] <= self.rank[part]]] = True

    def look(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and number of the piece that each pair makes; rank NONE where it makes none or a part is negative."""
        rank, made = np.full(len(left), NONE, np.int32), np.full(len(left), -1, np.int32)
        both = np.flatnonzero((left >= 0) & (right >= 0))
        found = self.table.get(pair_key(left[both], right[both]))
        there = found >= 0
        made[both[there]] = found[there]
        rank[both[there]] = self.rank[found[there]]
        return rank, made
