"""Piece lattices of many short strings at once.

Strings of one length are rows of a matrix of code points. A vocabulary finds its pieces in all of them by rolling
hashes, one vector operation per piece length; a table of hash prefixes sorts out most misses and names the only piece
with a prefix, a sorted array settles prefixes of several pieces, and hits are confirmed code point by code point.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np

_BASE = np.uint64(0x9E3779B97F4A7C15)
_BITS = 20


class Vocabulary:
    """``pieces``: distinct non-empty strings; a piece's number is its place."""

    def __init__(self, pieces: list[str], longest: int | None = None):
        self.pieces = pieces
        self.longest = min(longest or 10**9, max(map(len, pieces), default=1))
        codes = [np.array([ord(c) for c in p], dtype=np.uint64) for p in pieces if len(p) <= self.longest]
        self.number = np.array([i for i, p in enumerate(pieces) if len(p) <= self.longest], dtype=np.int64)
        hashes = np.zeros(len(codes), dtype=np.uint64)
        for k, c in enumerate(codes):
            h = np.zeros(1, dtype=np.uint64)
            for x in c:
                h = (h + x + np.uint64(1)) * _BASE
            hashes[k] = h[0]
        order = np.argsort(hashes, kind="stable")
        self.hashes, self.number = hashes[order], self.number[order]
        if len(np.unique(self.hashes)) != len(self.hashes):
            raise ValueError("pieces repeat or their hashes collide")
        own = self._slot(self.hashes)
        self.slots = np.full(1 << _BITS, -1, dtype=np.int32)  # place in ``hashes``; -1: none, -2: several
        self.slots[own] = np.arange(len(own))
        self.slots[own[1:][own[1:] == own[:-1]]] = -2
        self.chars = np.zeros((len(codes), self.longest), dtype=np.uint32)
        for k, o in enumerate(order):
            self.chars[k, :len(codes[o])] = codes[o]

    @staticmethod
    def _slot(h: np.ndarray) -> np.ndarray:
        return (h >> np.uint64(64 - _BITS)).astype(np.int64)

    def match(self, codes: np.ndarray) -> list[np.ndarray]:
        """For each piece length l = 1, 2, ...: (rows, starts) piece numbers, -1 where the vocabulary has none."""
        n, length = codes.shape
        out, h, wide = [], np.zeros((n, length), dtype=np.uint64), codes.astype(np.uint64)
        for size in range(1, min(self.longest, length) + 1):
            starts = length - size + 1
            h = (h[:, :starts] + wide[:, size - 1:] + np.uint64(1)) * _BASE
            found = np.full((n, starts), -1, dtype=np.int32)
            place = self.slots[self._slot(h)]
            r, c = np.nonzero(place != -1)
            if len(r):
                own, at = h[r, c], place[r, c]
                if (many := np.flatnonzero(at == -2)).size:
                    at[many] = np.minimum(np.searchsorted(self.hashes, own[many]), len(self.hashes) - 1)
                ok = self.hashes[at] == own
                r, c, at = r[ok], c[ok], at[ok]
                same = np.ones(len(r), dtype=bool)
                for k in range(size):
                    same &= self.chars[at, k] == codes[r, c + k]
                if size < self.longest:
                    same &= self.chars[at, size] == 0
                found[r[same], c[same]] = self.number[at[same]]
            out.append(found)
        return out


def by_length(strings: list[str], most: int = 1 << 18):
    """(indices, code point matrix) of strings of one length, at most ``most`` code points together."""
    groups: dict[int, list[int]] = defaultdict(list)
    for i, s in enumerate(strings):
        groups[len(s)].append(i)
    for length, ids in sorted(groups.items()):
        if length == 0:
            continue
        step = max(1, most // length)
        for lo in range(0, len(ids), step):
            part = ids[lo:lo + step]
            raw = "".join(strings[i] for i in part).encode("utf-32-le", "surrogatepass")
            yield np.array(part), np.frombuffer(raw, dtype="<u4").reshape(len(part), length)
