"""Relative-error rank sketch: a ladder of compactors that spare the favoured (high) end.

A level holds items of weight 2^level. When it is over capacity its lowest part is sorted and every
other item moves up a level; the number of sections spared at the high end follows the binary
count of past compactions, so high ranks are seldom touched. The coin is a fixed-seed generator.
"""

from __future__ import annotations

import numpy as np


class Req:
    def __init__(self, k: int = 12, seed: int = 1):
        self.k, self.levels, self.done, self.sections, self.size = k, [np.zeros(0)], [0], [3], [float(k)]
        self.coin = np.random.default_rng(seed)

    def _capacity(self, h: int) -> int:
        return 2 * self.sections[h] * self._section(h)

    def _section(self, h: int) -> int:
        return max(4, 2 * round(self.size[h] / 2))

    def add(self, values: np.ndarray) -> None:
        for part in np.array_split(values, max(1, len(values) // 2048)):
            self.levels[0] = np.concatenate([self.levels[0], part])
            self._settle()

    def merge(self, other: Req) -> None:
        for h, items in enumerate(other.levels):
            self._level(h)
            self.levels[h] = np.concatenate([self.levels[h], items])
            self.done[h] |= other.done[h]
        self._settle()

    def _level(self, h: int) -> None:
        while len(self.levels) <= h:
            self.levels.append(np.zeros(0))
            self.done.append(0)
            self.sections.append(3)
            self.size.append(float(self.k))

    def _settle(self) -> None:
        h = 0
        while h < len(self.levels):
            while len(self.levels[h]) >= self._capacity(h):
                self._compact(h)
            h += 1

    def _compact(self, h: int) -> None:
        items, half = np.sort(self.levels[h]), self.sections[h] * self._section(h)
        ones = (~self.done[h] & (self.done[h] + 1)).bit_length() - 1  # trailing ones of the count
        spared = half + max(0, self.sections[h] - ones - 1) * self._section(h)
        n = max(2, len(items) - spared) & ~1
        self._level(h + 1)
        self.levels[h + 1] = np.concatenate([self.levels[h + 1], items[int(self.coin.integers(2)) : n : 2]])
        self.levels[h] = items[n:]
        self.done[h] += 1
        if self.done[h] >= 1 << (self.sections[h] - 1) and self._section(h) > 4:
            self.sections[h] *= 2
            self.size[h] /= 2**0.5

    def items(self) -> tuple[np.ndarray, np.ndarray]:
        v = np.concatenate(self.levels)
        w = np.repeat(2.0 ** np.arange(len(self.levels)), [len(x) for x in self.levels])
        order = np.argsort(v, kind="stable")
        return v[order], w[order]

    def quantiles(self, qs) -> list[float]:
        v, w = self.items()
        upto = np.cumsum(w)
        return [float(v[min(len(v) - 1, int(np.searchsorted(upto, q * (upto[-1] - 1), "right")))]) for q in qs]

    def dump(self) -> bytes:
        head = [self.k, len(self.levels)]
        for h in range(len(self.levels)):
            head += [len(self.levels[h]), self.done[h], self.sections[h], self.size[h]]
        return np.concatenate([np.array(head, float), *self.levels]).tobytes()

    @classmethod
    def load(cls, raw: bytes) -> Req:
        a = np.frombuffer(raw)
        r, n = cls(int(a[0])), int(a[1])
        r.levels, r.done, r.sections, r.size = [], [], [], []
        at = 2 + 4 * n
        for h in range(n):
            length, done, sections, size = a[2 + 4 * h : 6 + 4 * h]
            r.levels.append(a[at : at + int(length)].copy())
            r.done.append(int(done))
            r.sections.append(int(sections))
            r.size.append(float(size))
            at += int(length)
        return r
