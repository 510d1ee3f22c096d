"""A navigable small-world graph over the centroids: approximate cell assignment in few hops."""

from __future__ import annotations

import heapq

import numpy as np

from nearcopy.functions.blocks import fast_squared_distances


class SmallWorldCoarse:
    """links: neighbours a node keeps; ef: candidates that a search holds. Nodes are added in order; each is linked
    both ways with
    the nearest ones found so far, and a node with too many links keeps its nearest and the few first (long) ones."""

    def __init__(self, centroids: np.ndarray, links: int = 32, ef: int = 64):
        self.centroids, self.links, self.ef = centroids, links, max(ef, links)
        self.graph: list[list[int]] = []
        for i in range(len(centroids)):
            near = self._walk(centroids[i], self.ef)[: max(1, links // 2)] if i else []
            self.graph.append([j for _, j in near])
            for _, j in near:
                own = self.graph[j]
                own.append(i)
                if len(own) > links:
                    far = own[:2]
                    d = fast_squared_distances(centroids[j : j + 1], centroids[own[2:]])[0]
                    self.graph[j] = far + [own[2:][k] for k in np.argsort(d, kind="stable")[: links - 2]]

    def _walk(self, x: np.ndarray, ef: int) -> list[tuple[float, int]]:
        if not self.graph:
            return []
        d0 = float(((x - self.centroids[0]) ** 2).sum())
        seen, front, best = {0}, [(d0, 0)], [(-d0, 0)]
        while front:
            d, at = heapq.heappop(front)
            if len(best) >= ef and d > -best[0][0]:
                break
            new = [j for j in self.graph[at] if j not in seen and j < len(self.graph)]
            seen.update(new)
            if not new:
                continue
            for j, dj in zip(new, ((self.centroids[new] - x) ** 2).sum(axis=1).tolist(), strict=True):
                if len(best) < ef or dj < -best[0][0]:
                    heapq.heappush(front, (dj, j))
                    heapq.heappush(best, (-dj, j))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-d, j) for d, j in best)

    def search(self, z: np.ndarray, n: int = 1) -> np.ndarray:
        out = np.zeros((len(z), n), np.int64)
        for i, x in enumerate(z):
            found = [j for _, j in self._walk(x, max(self.ef, n))][:n]
            out[i] = found + found[-1:] * (n - len(found))
        return out
