"""Minimum-cost flow by successive shortest paths, for small graphs on the driver."""

from __future__ import annotations

import heapq


class Flow:
    def __init__(self, nodes: int):
        self.out: list[list[int]] = [[] for _ in range(nodes)]
        self.head: list[int] = []
        self.left: list[int] = []
        self.cost: list[int] = []

    def arc(self, a: int, b: int, room: int, cost: int) -> int:
        """Adds an arc and its reverse; returns the arc's number."""
        k = len(self.head)
        self.head += [b, a]
        self.left += [room, 0]
        self.cost += [cost, -cost]
        self.out[a].append(k)
        self.out[b].append(k + 1)
        return k

    def used(self, k: int) -> int:
        return self.left[k ^ 1]

    def run(self, source: int, sink: int, amount: int) -> int:
        """Sends up to `amount` at least cost; returns what was sent. Costs may be negative if the
        graph has no circle of negative cost."""
        n, far = len(self.out), float("inf")
        height = [0] * n
        for _ in range(n):  # potentials that make all costs non-negative
            moved = False
            for a in range(n):
                for k in self.out[a]:
                    if self.left[k] and height[a] + self.cost[k] < height[self.head[k]]:
                        height[self.head[k]] = height[a] + self.cost[k]
                        moved = True
            if not moved:
                break
        sent = 0
        while sent < amount:
            near, by = [far] * n, [-1] * n
            near[source] = 0
            heap = [(0, source)]
            while heap:
                d, a = heapq.heappop(heap)
                if d > near[a]:
                    continue
                for k in self.out[a]:
                    if self.left[k]:
                        b = self.head[k]
                        to = d + self.cost[k] + height[a] - height[b]
                        if to < near[b]:
                            near[b], by[b] = to, k
                            heapq.heappush(heap, (to, b))
            if by[sink] < 0:
                break
            for a in range(n):
                if near[a] < far:
                    height[a] += near[a]
            room, b = amount - sent, sink
            while b != source:
                room = min(room, self.left[by[b]])
                b = self.head[by[b] ^ 1]
            b = sink
            while b != source:
                self.left[by[b]] -= room
                self.left[by[b] ^ 1] += room
                b = self.head[by[b] ^ 1]
            sent += room
        return sent
