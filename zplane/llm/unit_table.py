"""A table of strings with bounded memory, for operators that work out each distinct unit of text once."""

from __future__ import annotations

import numpy as np

from zplane.llm import shingles as sh


class UnitTable:
    """Slots of strings seen before. Hashes only find a slot; the bytes, which are kept, decide whether it is the same string."""

    def __init__(self):
        self.runs: list[tuple[np.ndarray, np.ndarray]] = []  # (hash, slot) sorted by hash
        self.begin, self.bytes = np.zeros(1, np.int64), np.zeros(1 << 16, np.uint8)
        self.n = 0

    def __len__(self) -> int:
        return self.n

    @staticmethod
    def _raw(units) -> tuple[np.ndarray, np.ndarray]:
        """(bytes, offsets) of an Arrow array of large strings."""
        _, offsets, data = units.buffers()
        at = np.frombuffer(offsets, np.int64)[units.offset : units.offset + len(units) + 1]
        raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
        return raw, at - at[0]

    def find(self, units) -> tuple[np.ndarray, np.ndarray]:
        """(slot of every unit, -1 where there is none; hashes for add)."""
        raw, at = self._raw(units)
        size = np.diff(at)
        h = sh.mix(sh.range_hash(sh.prefix_hash(raw), at[:-1], at[1:]) + size.astype(np.uint64))
        slot = np.full(len(h), -1, np.int64)
        for keys, slots in self.runs:
            i = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
            hit = np.flatnonzero(keys[i] == h)
            found = slots[i[hit]]
            same = self.begin[found + 1] - self.begin[found] == size[hit]
            hit, found = hit[same], found[same]
            n = size[hit]
            ends = np.cumsum(n)
            step = np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - n, n)
            differ = raw[np.repeat(at[hit], n) + step] != self.bytes[np.repeat(self.begin[found], n) + step]
            bad = np.zeros(len(hit), bool)
            bad[np.repeat(np.arange(len(hit)), n)[differ]] = True
            slot[hit[~bad]] = found[~bad]
        return slot, h

    def add(self, units, h: np.ndarray) -> np.ndarray:
        """New slots for units that find() did not know."""
        raw, at = self._raw(units)
        used = int(self.begin[self.n])
        while used + len(raw) > len(self.bytes):
            self.bytes = np.concatenate([self.bytes, np.zeros_like(self.bytes)])
        self.bytes[used : used + len(raw)] = raw
        while self.n + len(h) >= len(self.begin):
            self.begin = np.concatenate([self.begin, np.zeros_like(self.begin)])
        slots = np.arange(self.n, self.n + len(h))
        self.begin[self.n + 1 : self.n + len(h) + 1] = used + at[1:]
        self.n += len(h)
        order = np.argsort(h, kind="stable")
        run = h[order], slots[order].astype(np.int32)
        while self.runs and len(self.runs[-1][0]) <= 2 * len(run[0]):  # runs grow geometrically
            run = tuple(np.concatenate(c) for c in zip(self.runs.pop(), run))
            order = np.argsort(run[0], kind="stable")
            run = tuple(c[order] for c in run)
        self.runs.append(run)
        return slots
