"""Longest common extensions of two suffixes of one text (0-based positions inside kernels)."""

from __future__ import annotations

import numpy as np

Text = str | bytes


def first_difference(text: Text, i: int, j: int, limit: int) -> int:
    """How many of at most `limit` symbols agree from i and from j on; slices are compared in growing steps, then halved."""
    got, step = 0, 16
    while got < limit:
        size = min(step, limit - got)
        if text[i + got : i + got + size] == text[j + got : j + got + size]:
            got += size
            step *= 2
            continue
        while size > 1:
            half = size >> 1
            if text[i + got : i + got + half] == text[j + got : j + got + half]:
                got += half
                size -= half
            else:
                size = half
        return got
    return got


def suffix_match(text: Text, i: int, j: int) -> int:
    """Length of the longest common prefix of the suffixes at 1-based positions i and j; 0 beyond the end."""
    n = len(text)
    if not 1 <= i <= n or not 1 <= j <= n:
        return 0
    return first_difference(text, i - 1, j - 1, n - max(i, j) + 1)


def bounded_match(text: Text, i: int, j: int, limit: int) -> int:
    """suffix_match cut at `limit`, in time proportional to it."""
    n = len(text)
    if not 1 <= i <= n or not 1 <= j <= n:
        return 0
    return first_difference(text, i - 1, j - 1, min(limit, n - max(i, j) + 1))


class Direct:
    """Compares symbols; no index."""

    def __init__(self, text: Text):
        self.text, self.n = text, len(text)

    def __call__(self, i: int, j: int) -> int:
        return first_difference(self.text, i, j, self.n - max(i, j)) if max(i, j) < self.n else 0


class RankIndex:
    """Constant-time queries from suffix ranks, adjacent common prefixes and their range minima (built in O(n log n))."""

    def __init__(self, text: Text):
        self.n = n = len(text)
        codes = np.frombuffer(text, np.uint8).astype(np.int64) if isinstance(text, bytes) else np.fromiter(map(ord, text), np.int64, n)
        rank = np.unique(codes, return_inverse=True)[1].astype(np.int64) if n else codes
        span = 1
        while span < n:
            ahead = np.zeros(n, np.int64)
            ahead[: n - span] = rank[span:] + 1
            rank = np.unique(rank * (n + 1) + ahead, return_inverse=True)[1].astype(np.int64)
            span *= 2
        order = np.empty(n, np.int64)
        order[rank] = np.arange(n)
        self.rank = rank.tolist()
        common, carried = np.zeros(max(n, 1), np.int64), 0
        order_ = order.tolist()
        for i, r in enumerate(self.rank):
            if r:
                j = order_[r - 1]
                while i + carried < n and j + carried < n and text[i + carried] == text[j + carried]:
                    carried += 1
                common[r] = carried
                carried = max(carried - 1, 0)
            else:
                carried = 0
        self.table = [common]
        while 2 << (len(self.table) - 1) <= n:
            last, half = self.table[-1], 1 << (len(self.table) - 1)
            self.table.append(np.minimum(last[:-half], last[half:]))

    def __call__(self, i: int, j: int) -> int:
        if max(i, j) >= self.n:
            return 0
        if i == j:
            return self.n - i
        a, b = sorted((self.rank[i], self.rank[j]))
        level = (b - a).bit_length() - 1
        row = self.table[level]
        return int(min(row[a + 1], row[b + 1 - (1 << level)]))


class RollingHash:
    """Fingerprints sampled every `stride` symbols: equal samples are skipped by binary search, the rest is compared."""

    _MOD, _BASE = (1 << 61) - 1, 911382323

    def __init__(self, text: Text, stride: int = 512):
        self.text, self.n, self.stride = text, len(text), stride
        h, self.sample, self.power = 0, [0], [1]
        for at in range(0, self.n, stride):
            for c in text[at : at + stride]:
                h = (h * self._BASE + (c if isinstance(c, int) else ord(c)) + 1) % self._MOD
            if at + stride <= self.n:
                self.sample.append(h)
        self.pace = pow(self._BASE, stride, self._MOD)

    def _prefix(self, k: int) -> int:
        block = min(k // self.stride, len(self.sample) - 1)
        h = self.sample[block]
        for c in self.text[block * self.stride : k]:
            h = (h * self._BASE + (c if isinstance(c, int) else ord(c)) + 1) % self._MOD
        return h

    def _hash(self, i: int, size: int) -> int:
        return (self._prefix(i + size) - self._prefix(i) * pow(self._BASE, size, self._MOD)) % self._MOD

    def __call__(self, i: int, j: int) -> int:
        limit = self.n - max(i, j)
        if limit <= 0:
            return 0
        near = first_difference(self.text, i, j, min(limit, self.stride))
        if near < min(limit, self.stride) or near == limit:
            return near
        lo, hi = 1, limit // self.stride
        while lo < hi:  # the longest run of whole strides whose fingerprints agree
            mid = (lo + hi + 1) >> 1
            if self._hash(i, mid * self.stride) == self._hash(j, mid * self.stride):
                lo = mid
            else:
                hi = mid - 1
        skipped = lo * self.stride
        if self.text[i : i + skipped] != self.text[j : j + skipped]:  # a false fingerprint
            return first_difference(self.text, i, j, limit)
        return skipped + first_difference(self.text, i + skipped, j + skipped, limit - skipped)


BACKENDS = {"direct": Direct, "rank": RankIndex, "rolling": RollingHash}


def make(text: Text, kind: str = "direct"):
    """The common-extension backend of a text: 'direct', 'rank' or 'rolling'."""
    return BACKENDS[kind](text)
