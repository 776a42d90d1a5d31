"""Ordered items with positions: the state of a top-k with a large k, in memory.

Blocks of sorted items, and a binary indexed tree over their sizes: an insert, a removal, the item at a position and the
position of an item each take O(log n) steps and the shift inside one block.  ``replaced`` finds what a change
does to the first k without visiting them.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterable
from itertools import accumulate
from typing import Any

BLOCK = 512


class Ranked:
    def __init__(self, items: Iterable = ()):
        found = sorted(items)
        self.blocks = [found[i : i + BLOCK] for i in range(0, len(found), BLOCK)]
        self._index()

    def _index(self) -> None:
        """Sums of sizes by position, and the last item of each block; again whenever a block comes or goes."""
        self.last = [b[-1] for b in self.blocks]
        self.size = sum(map(len, self.blocks))
        upto = [0, *accumulate(map(len, self.blocks))]
        self.tree = [0, *(upto[i] - upto[i & (i - 1)] for i in range(1, len(upto)))]

    def __len__(self) -> int:
        return self.size

    def _add(self, block: int, n: int) -> None:
        self.size += n
        i = block + 1
        while i < len(self.tree):
            self.tree[i] += n
            i += i & -i

    def _before(self, block: int) -> int:
        n = 0
        while block:
            n += self.tree[block]
            block &= block - 1
        return n

    def __getitem__(self, position: int) -> Any:
        if not 0 <= position < self.size:
            raise IndexError(position)
        at, step = 0, 1 << (len(self.tree) - 1).bit_length()
        while step:
            if at + step < len(self.tree) and self.tree[at + step] <= position:
                at += step
                position -= self.tree[at]
            step >>= 1
        return self.blocks[at][position]

    def position(self, item: Any) -> int:
        """How many items come before it."""
        at = bisect.bisect_left(self.last, item)
        return self.size if at == len(self.blocks) else self._before(at) + bisect.bisect_left(self.blocks[at], item)

    def insert(self, item: Any) -> None:
        if not self.blocks:
            self.blocks = [[item]]
            return self._index()
        at = min(bisect.bisect_left(self.last, item), len(self.blocks) - 1)
        block = self.blocks[at]
        bisect.insort(block, item)
        if len(block) > 2 * BLOCK:
            self.blocks[at : at + 1] = [block[:BLOCK], block[BLOCK:]]
            return self._index()
        self.last[at] = block[-1]
        self._add(at, 1)

    def remove(self, item: Any) -> None:
        at = bisect.bisect_left(self.last, item)
        i = bisect.bisect_left(self.blocks[at], item) if at < len(self.blocks) else 0
        if at == len(self.blocks) or self.blocks[at][i] != item:
            raise ValueError("an item is removed that isn't there")
        block = self.blocks[at]
        del block[i]
        if not block:
            del self.blocks[at]
            return self._index()
        self.last[at] = block[-1]
        self._add(at, -1)

    def replaced(self, gone: Iterable, new: Iterable, k: int) -> tuple[list, list]:
        """Remove and insert distinct items; returns those that leave the first k and those that get into them.

        What is left of the old items keeps its order, so beside the changed ones only those next to the old bound move.
        """
        if k <= 0:
            raise ValueError("k must be positive")
        gone, new = set(gone), set(new)
        gone, new = gone - new, new - gone
        held = min(k, self.size)
        bound = self[k - 1] if self.size >= k else None
        leaving = [x for x in gone if bound is None or x <= bound]
        for x in gone:
            self.remove(x)
        for x in new:
            self.insert(x)
        now = self[k - 1] if self.size >= k else None
        entering = [x for x in new if now is None or x <= now]
        moves = min(k, self.size) - len(entering) - (held - len(leaving))
        if not moves:
            return leaving, entering
        # the first old item that wasn't among the first k, or the last one that was
        at = self.size if bound is None else self.position(bound)
        if bound is not None and at < self.size and self[at] == bound:
            at += 1
        step, out = (1, entering) if moves > 0 else (-1, leaving)
        at -= step < 0
        while moves:
            x = self[at]
            if x not in new:
                out.append(x)
                moves -= step
            at += step
        return leaving, entering
