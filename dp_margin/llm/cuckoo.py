"""Cuckoo filters over 128-bit keys: vectorised look-up, insertion with evictions, deletion."""

from __future__ import annotations

import numpy as np

from .common import mix64

SLOTS = 4
MAX_KICKS = 500


class CuckooFilter:
    """Buckets of four 32-bit fingerprints. A key (k1, k2) lives in one of two buckets.

    No false negatives; a false positive needs an equal fingerprint in one of two buckets (about 8 * 2^-32).
    Deleting is right only for keys that were inserted, which the reference-count table guarantees.
    """

    def __init__(self, buckets: int = 16, table: np.ndarray | None = None):
        self.table = np.zeros((buckets, SLOTS), np.uint32) if table is None else table
        self.mask = np.uint64(len(self.table) - 1)

    @classmethod
    def for_keys(cls, k1, k2) -> CuckooFilter:
        buckets = 16
        while buckets * SLOTS * 0.8 < len(k1):
            buckets *= 2
        while True:
            made = cls(buckets)
            if all(made._place(*x) for x in zip(*made._address(k1, k2), strict=True)):
                return made
            buckets *= 2

    @classmethod
    def from_bytes(cls, data: bytes) -> CuckooFilter:
        return cls(table=np.frombuffer(data, np.uint32).reshape(-1, SLOTS).copy())

    def to_bytes(self) -> bytes:
        return self.table.tobytes()

    def _address(self, k1, k2):
        fp = (np.asarray(k2).astype(np.uint64) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        fp[fp == 0] = 1
        first = (mix64(np.asarray(k1).astype(np.uint64)) & self.mask).astype(np.int64)
        return first, self._other(first, fp), fp

    def _other(self, at, fp):
        return np.bitwise_xor(at, (mix64(np.asarray(fp, np.uint64)) & self.mask).astype(np.int64))

    def _place(self, first: int, second: int, fp: int) -> bool:
        for at in (first, second):
            free = np.flatnonzero(self.table[at] == 0)
            if len(free):
                self.table[at, free[0]] = fp
                return True
        at, undo = int(second), []
        for kick in range(MAX_KICKS):
            slot = kick % SLOTS
            undo.append((at, slot))
            fp, self.table[at, slot] = self.table[at, slot], fp
            at = int(self._other(np.array([at]), np.array([fp]))[0])
            free = np.flatnonzero(self.table[at] == 0)
            if len(free):
                self.table[at, free[0]] = fp
                return True
        for at, slot in reversed(undo):  # full: leave the filter as it was
            fp, self.table[at, slot] = self.table[at, slot], fp
        return False

    def insert(self, k1, k2) -> bool:
        """False if the filter is full: then rebuild it from the reference counts."""
        return all(self._place(*x) for x in zip(*self._address(k1, k2), strict=True))

    def delete(self, k1, k2) -> None:
        for first, second, fp in zip(*self._address(k1, k2), strict=True):
            for at in (first, second):
                held = np.flatnonzero(self.table[at] == fp)
                if len(held):
                    self.table[at, held[0]] = 0
                    break

    def contains(self, k1, k2) -> np.ndarray:
        first, second, fp = self._address(k1, k2)
        fp = fp[:, None]
        return (self.table[first] == fp).any(1) | (self.table[second] == fp).any(1)
