"""Bit tries: of one set, of a chain of versions, and the linear-space update matrix that stands for all versions."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


class BitTrie:
    """A set of whole numbers below 2**width as a binary trie, level by level; levels are sorted distinct prefixes."""

    def __init__(self, values, width: int) -> None:
        v = np.unique(np.asarray(list(values), np.int64))
        self.width, self.levels = width, [np.unique(v >> (width - d)) for d in range(width + 1)]

    def _has(self, depth: int, prefix: int) -> bool:
        level = self.levels[depth]
        i = int(np.searchsorted(level, prefix))
        return i < len(level) and int(level[i]) == prefix

    def seek(self, x: int) -> int | None:
        """Least member that is at least x: one walk down, one jump to the last right turn left open, then leftmost."""
        if not len(self.levels[-1]) or x >= 1 << self.width:
            return None
        node, spare = 0, None
        for d in range(self.width):
            bit = (x >> (self.width - 1 - d)) & 1
            if not bit and self._has(d + 1, 2 * node + 1):
                spare = (d + 1, 2 * node + 1)
            node = 2 * node + bit
            if not self._has(d + 1, node):
                break
        else:
            return node
        if spare is None:
            return None
        d, node = spare
        for e in range(d, self.width):
            node = 2 * node + (0 if self._has(e + 1, 2 * node) else 1)
        return node

    def members(self) -> list[int]:
        return self.levels[-1].tolist()


@dataclass(frozen=True)
class _Node:
    left: _Node | None
    right: _Node | None


_LEAF = _Node(None, None)


class VersionedBitTrie:
    """Versions of a set: each copies only the paths it changes and shares the rest with earlier versions."""

    def __init__(self, width: int) -> None:
        self.width, self.roots, self.made = width, [], 0

    def _set(self, node: _Node | None, key: int, depth: int, present: bool) -> _Node | None:
        if depth == self.width:
            return _LEAF if present else None
        bit = (key >> (self.width - 1 - depth)) & 1
        left, right = (node.left, node.right) if node else (None, None)
        if bit:
            right = self._set(right, key, depth + 1, present)
        else:
            left = self._set(left, key, depth + 1, present)
        if left is None and right is None:
            return None
        self.made += 1
        return _Node(left, right)

    def apply(self, inserts=(), deletes=()) -> int:
        """A new version after the latest; returns its number."""
        root = self.roots[-1] if self.roots else None
        for k in deletes:
            root = self._set(root, k, 0, False)
        for k in inserts:
            root = self._set(root, k, 0, True)
        self.roots.append(root)
        return len(self.roots) - 1

    def members(self, version: int) -> list[int]:
        out: list[int] = []

        def walk(node: _Node | None, depth: int, prefix: int) -> None:
            if node is None:
                return
            if depth == self.width:
                out.append(prefix)
                return
            walk(node.left, depth + 1, 2 * prefix)
            walk(node.right, depth + 1, 2 * prefix + 1)

        walk(self.roots[version], 0, 0)
        return out

    def seek(self, version: int, x: int) -> int | None:
        def least(node: _Node | None, depth: int, prefix: int, tight: bool) -> int | None:
            if node is None:
                return None
            if depth == self.width:
                return prefix
            bit = (x >> (self.width - 1 - depth)) & 1 if tight else 0
            if not bit:
                got = least(node.left, depth + 1, 2 * prefix, tight)
                if got is not None:
                    return got
            return least(node.right, depth + 1, 2 * prefix + 1, tight and bool(bit))

        return None if x >= 1 << self.width else least(self.roots[version], 0, 0, True)


class RankBits:
    """A bit vector with prefix counts a block of 512 bits."""

    def __init__(self, bits: np.ndarray) -> None:
        self.n = len(bits)
        self.packed = np.packbits(np.asarray(bits, np.uint8), bitorder="little")
        padded = np.zeros(-(-self.n // 512) * 512, np.uint8)
        padded[: self.n] = bits
        self.blocks = np.concatenate(([0], np.cumsum(padded.reshape(-1, 512).sum(1, dtype=np.int64)))) if self.n else np.zeros(1, np.int64)

    def get(self, i: int) -> int:
        return int(self.packed[i >> 3] >> (i & 7)) & 1

    def rank(self, i: int) -> int:
        """Ones before position i."""
        b = i >> 9
        lo, hi = b << 6, i >> 3
        n = int(self.blocks[b]) + int(np.bitwise_count(self.packed[lo:hi]).sum())
        return n + (int(self.packed[hi] & ((1 << (i & 7)) - 1)).bit_count() if i & 7 else 0)

    def count(self, a: int, b: int) -> int:
        return self.rank(b) - self.rank(a)

    def bits(self) -> np.ndarray:
        return np.unpackbits(self.packed, bitorder="little", count=self.n)


class UpdateMatrix:
    """All versions of a set in linear space.

    Updates are numbered in order. At depth d they are grouped by the first d key bits, in update order within a
    group; B_d holds each update's next bit, E_d whether anything below the group's node exists right after it.
    Areas are half-open; a node's offset at a version is the number of its updates so far, minus one.
    """

    def __init__(self, width: int, length: int, b: list[RankBits], e: list[RankBits]) -> None:
        self.width, self.length, self.B, self.E = width, length, b, e

    @classmethod
    def build(cls, keys, signs, width: int) -> UpdateMatrix:
        keys, signs = np.asarray(keys, np.int64), np.asarray(signs, np.int64)
        order, b, e = np.arange(len(keys)), [], []
        for d in range(width + 1):
            group = keys[order] >> (width - d)
            fresh = np.concatenate(([True], group[1:] != group[:-1])) if len(group) else np.zeros(0, bool)
            run = np.cumsum(signs[order])
            base = np.maximum.accumulate(np.where(fresh, np.arange(len(run)), 0)) if len(run) else run
            before = np.where(base > 0, run[np.maximum(base - 1, 0)], 0) if len(run) else run
            e.append(RankBits((run - before > 0).astype(np.uint8)))
            if d < width:
                bit = (keys[order] >> (width - 1 - d)) & 1
                b.append(RankBits(bit.astype(np.uint8)))
                order = order[np.lexsort((bit, np.cumsum(fresh)))]  # stable: left part, then right part of every node
        return cls(width, len(keys), b, e)

    @property
    def bits(self) -> int:
        """Bits stored: leaf E bits alternate and need not be."""
        return 2 * self.width * self.length

    def child(self, depth: int, area: tuple[int, int], bit: int, at: int) -> tuple[tuple[int, int], int]:
        """Area and offset of a child."""
        s, e = area
        ones = self.B[depth].count(s, e)
        so_far = self.B[depth].count(s, min(e, s + at + 1)) if at >= 0 else 0
        if bit:
            return (e - ones, e), so_far - 1
        return (s, e - ones), (at + 1 - so_far) - 1

    def alive(self, depth: int, area: tuple[int, int], at: int) -> bool:
        s, e = area
        return s < e and at >= 0 and bool(self.E[depth].get(s + min(at, e - s - 1)))

    def alive_any(self, depth: int, area: tuple[int, int], p1: int, p2: int) -> bool:
        """Exists at offset p1 or after one of the later updates up to offset p2."""
        s, e = area
        lo, hi = max(p1, 0), min(p2, e - s - 1)
        return s < e and hi >= lo and self.E[depth].count(s + lo, s + hi + 1) > 0

    def alive_all(self, depth: int, area: tuple[int, int], p1: int, p2: int) -> bool:
        """Exists at offset p1 and after all later updates up to offset p2."""
        s, e = area
        hi = min(p2, e - s - 1)
        return s < e and p1 >= 0 and self.E[depth].count(s + p1, s + hi + 1) == hi + 1 - p1

    def seek(self, x: int, version: int, start: tuple[int, tuple[int, int], int] | None = None, levels: int | None = None) -> int | None:
        """Least member >= x after ``version`` updates. ``start`` (depth, area, offset) and ``levels`` search one component of a joined key."""
        depth0, area, at = start or (0, (0, self.length), version - 1)
        levels = self.width - depth0 if levels is None else levels
        if not self.alive(depth0, area, at) or x >= 1 << levels:
            return None
        node, spare = 0, None
        for d in range(levels):
            bit = (x >> (levels - 1 - d)) & 1
            right, r_at = self.child(depth0 + d, area, 1, at)
            if not bit:
                if self.alive(depth0 + d + 1, right, r_at):
                    spare = (d + 1, 2 * node + 1, right, r_at)
                area, at = self.child(depth0 + d, area, 0, at)
            else:
                area, at = right, r_at
            node = 2 * node + bit
            if not self.alive(depth0 + d + 1, area, at):
                break
        else:
            return node
        if spare is None:
            return None
        d, node, area, at = spare
        for e in range(d, levels):
            left, l_at = self.child(depth0 + e, area, 0, at)
            if self.alive(depth0 + e + 1, left, l_at):
                node, area, at = 2 * node, left, l_at
            else:
                node, (area, at) = 2 * node + 1, self.child(depth0 + e, area, 1, at)
        return node

    def members(self, version: int) -> list[int]:
        out, x = [], 0
        while (got := self.seek(x, version)) is not None:
            out.append(got)
            x = got + 1
        return out

    def window(self, p1: int, p2: int, mode: str) -> list[int]:
        """Members at some ("any") or every ("all") version from p1 to p2 updates; inner nodes only prune."""
        test = self.alive_any if mode == "any" else self.alive_all
        out: list[int] = []

        def walk(d: int, area: tuple[int, int], a: int, b: int, prefix: int) -> None:
            if not test(d, area, a, b):
                return
            if d == self.width:
                out.append(prefix)
                return
            for bit in (0, 1):
                (s, x), (_, y) = self.child(d, area, bit, a), self.child(d, area, bit, b)
                walk(d + 1, s, x, y, 2 * prefix + bit)

        walk(0, (0, self.length), p1 - 1, p2 - 1, 0)
        return out
