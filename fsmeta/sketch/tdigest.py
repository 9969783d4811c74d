"""t-digest: centroids whose weight is bounded by an arcsine scale, finest at both tails.

Compression is by scale bins: sorted centroids whose middle ranks fall into the same unit of the
scale become one. The result depends on the multiset of inputs and the batches only.
"""

from __future__ import annotations

import numpy as np


class TDigest:
    buffer = 4096

    def __init__(self, compression: float = 100.0):
        self.compression = compression
        self.mean, self.weight = np.zeros(0), np.zeros(0)
        self.low, self.high = np.inf, -np.inf

    def add(self, values: np.ndarray) -> None:
        if not len(values):
            return
        self.low, self.high = min(self.low, float(values.min())), max(self.high, float(values.max()))
        self._squeeze(np.concatenate([self.mean, values]), np.concatenate([self.weight, np.ones(len(values))]))

    def merge(self, other: TDigest) -> None:
        self.low, self.high = min(self.low, other.low), max(self.high, other.high)
        self._squeeze(np.concatenate([self.mean, other.mean]), np.concatenate([self.weight, other.weight]))

    def _squeeze(self, mean: np.ndarray, weight: np.ndarray) -> None:
        if not len(mean):
            return
        order = np.lexsort((weight, mean))
        mean, weight = mean[order], weight[order]
        upto = np.cumsum(weight)
        middle = np.clip((upto - weight / 2) / upto[-1], 0, 1)
        unit = np.floor(self.compression / np.pi * (np.arcsin(2 * middle - 1) + np.pi / 2))
        start = np.flatnonzero(np.concatenate([[True], unit[1:] != unit[:-1]]))
        self.weight = np.add.reduceat(weight, start)
        self.mean = np.add.reduceat(mean * weight, start) / self.weight

    def quantiles(self, qs) -> list[float]:
        n = self.weight.sum()
        centre = np.cumsum(self.weight) - self.weight / 2
        x = np.concatenate([[0], centre, [n]])
        y = np.concatenate([[self.low], self.mean, [self.high]])
        return [float(v) for v in np.interp(np.asarray(qs) * n, x, y)]

    def dump(self) -> bytes:
        return np.concatenate([[self.compression, self.low, self.high], self.mean, self.weight]).tobytes()

    @classmethod
    def load(cls, raw: bytes) -> TDigest:
        a = np.frombuffer(raw)
        t = cls(a[0])
        t.low, t.high = a[1], a[2]
        t.mean, t.weight = (x.copy() for x in np.split(a[3:], 2))
        return t
