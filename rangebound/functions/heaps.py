"""Heaps that hold the same records in several orders at once.

Connected: each record knows its place in every heap, so taking the root of one heap deletes the record
from the others in logarithmic time. Unconnected: the others are searched; kept for comparison.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator, Sequence
from typing import Any


class ConnectedHeap:
    """orders: functions from a record to its key; heap i has the smallest key of orders[i] on top.
    Keys tie by the time of insertion."""

    def __init__(self, orders: Sequence[Callable[[Any], Any]]) -> None:
        self.orders = list(orders)
        self.heaps: list[list[list]] = [[] for _ in self.orders]  # entries: [key, stamp, record, places]
        self._stamp = 0
        self._of: dict[int, list[list]] = {}
        self.ops = 0

    def __len__(self) -> int:
        return len(self.heaps[0])

    def insert(self, rec: Any) -> int:
        """Returns a handle of the record, for delete()."""
        stamp, self._stamp = self._stamp, self._stamp + 1
        places = [0] * len(self.orders)
        entries = []
        for h, order in enumerate(self.orders):
            e = [order(rec), stamp, rec, places]
            entries.append(e)
            heap = self.heaps[h]
            heap.append(e)
            places[h] = len(heap) - 1
            self._up(h, len(heap) - 1)
        self._of[stamp] = entries
        return stamp

    def peek(self, h: int) -> Any:
        return self.heaps[h][0][2]

    def pop(self, h: int) -> Any:
        top = self.heaps[h][0]
        self.delete(top[1])
        return top[2]

    def delete(self, handle: int) -> None:
        entries = self._of.pop(handle)
        places = list(entries[0][3])
        for h in range(len(self.orders)):
            self._remove(h, places[h] if h == 0 else entries[h][3][h])

    def ascending(self, h: int) -> Iterator[Any]:
        """Records by heap h's order, without taking them: best-first over the tree."""
        heap = self.heaps[h]
        front = [(heap[0][0], heap[0][1], 0)] if heap else []
        while front:
            self.ops += 1
            _, _, i = heapq.heappop(front)
            yield heap[i][2]
            for c in (2 * i + 1, 2 * i + 2):
                if c < len(heap):
                    heapq.heappush(front, (heap[c][0], heap[c][1], c))

    def _put(self, h: int, i: int, e: list) -> None:
        self.heaps[h][i] = e
        e[3][h] = i

    def _up(self, h: int, i: int) -> None:
        heap, e = self.heaps[h], self.heaps[h][i]
        while i:
            p = (i - 1) >> 1
            self.ops += 1
            if (heap[p][0], heap[p][1]) <= (e[0], e[1]):
                break
            self._put(h, i, heap[p])
            i = p
        self._put(h, i, e)

    def _down(self, h: int, i: int) -> None:
        heap, e = self.heaps[h], self.heaps[h][i]
        n = len(heap)
        while (c := 2 * i + 1) < n:
            if c + 1 < n and (heap[c + 1][0], heap[c + 1][1]) < (heap[c][0], heap[c][1]):
                c += 1
            self.ops += 1
            if (e[0], e[1]) <= (heap[c][0], heap[c][1]):
                break
            self._put(h, i, heap[c])
            i = c
        self._put(h, i, e)

    def _remove(self, h: int, i: int) -> None:
        """The last leaf takes the free place and sifts up or down, as its key asks."""
        heap = self.heaps[h]
        leaf = heap.pop()
        if i == len(heap):
            return
        self._put(h, i, leaf)
        p = (i - 1) >> 1
        if i and (leaf[0], leaf[1]) < (heap[p][0], heap[p][1]):
            self._up(h, i)
        else:
            self._down(h, i)


class UnconnectedHeaps:
    """The same, with a linear search for a record in the heaps it wasn't taken from."""

    def __init__(self, orders: Sequence[Callable[[Any], Any]]) -> None:
        self.orders = list(orders)
        self.heaps: list[list[tuple]] = [[] for _ in self.orders]
        self._stamp = 0
        self.ops = 0

    def __len__(self) -> int:
        return len(self.heaps[0])

    def insert(self, rec: Any) -> int:
        stamp, self._stamp = self._stamp, self._stamp + 1
        for heap, order in zip(self.heaps, self.orders, strict=True):
            heapq.heappush(heap, (order(rec), stamp, rec))
        return stamp

    def peek(self, h: int) -> Any:
        return self.heaps[h][0][2]

    def pop(self, h: int) -> Any:
        top = self.heaps[h][0]
        self.delete(top[1])
        return top[2]

    def delete(self, handle: int) -> None:
        for heap in self.heaps:
            for i, e in enumerate(heap):
                self.ops += 1
                if e[1] == handle:
                    heap[i] = heap[-1]
                    heap.pop()
                    heapq.heapify(heap)
                    break

    def ascending(self, h: int) -> Iterator[Any]:
        for e in sorted(self.heaps[h], key=lambda e: e[:2]):
            yield e[2]
