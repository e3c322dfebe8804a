"""A graph in which near vectors are found by walking."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np


def ranges(count: np.ndarray) -> np.ndarray:
    """0 .. c-1 for each c of ``count``, one after the other."""
    return np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)


class ProximityGraph:
    """A search graph over vectors: near neighbours, thinned so that links point in different directions."""

    def __init__(self, x: np.ndarray, degree: int = 16, alpha: float = 1.2, near: list[list[int]] | None = None):
        """``near`` has the links of ``near_links`` where they are known."""
        self.x = x
        self.links: list[list[int]] = list(map(list, near_links(x, 0, len(x), degree, alpha) if near is None else near))
        for i, own in enumerate(list(map(list, self.links))):
            for j in own:
                if i not in self.links[j] and len(self.links[j]) < 2 * degree:
                    self.links[j].append(i)
        self.entry = int(np.argmin(((x - x.mean(axis=0)) ** 2).sum(axis=1))) if len(x) else 0

    def search(self, q: np.ndarray, k: int, beam: int) -> tuple[list[int], int]:
        """The k best found with a beam, and how many nodes were read."""
        dist = {self.entry: float(((self.x[self.entry] - q) ** 2).sum())}
        todo, best, read = [(dist[self.entry], self.entry)], [(-dist[self.entry], self.entry)], 0
        while todo:
            d, i = heapq.heappop(todo)
            if len(best) >= max(k, beam) and d > -best[0][0]:
                break
            read += 1
            fresh = [j for j in self.links[i] if j not in dist]
            for j, e in zip(fresh, ((self.x[fresh] - q) ** 2).sum(axis=1).tolist(), strict=True):
                if j not in dist:
                    dist[j] = e
                    if len(best) < max(k, beam) or e < -best[0][0]:
                        heapq.heappush(todo, (e, j))
                        heapq.heappush(best, (-e, j))
                        if len(best) > max(k, beam):
                            heapq.heappop(best)
        return [j for _, j in sorted((-d, j) for d, j in best)[:k]], read

    def search_many(self, q: np.ndarray, k: int, beam: int, at_once: int = 256, limit: float = np.inf) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """What ``search`` reads for each row of ``q``, many rows side by side: for some rows at a time the row, node and squared distance of
        the k best, nearest first. A walk ends where ``max(k, beam)`` nodes nearer than the nearest unread one have been read, which is
        where the beam ends it; of nodes at the very distance of the beam's last all are read. Nodes
        beyond the squared distance ``limit`` are read like all others and not told.
        """
        width = max(map(len, self.links), default=0)
        links = np.full((len(self.links), max(width, 1)), -1, np.int32)
        for i, own in enumerate(self.links):
            links[i, : len(own)] = own
        for a in range(0, len(q), at_once):
            yield self._walk(links, q[a : a + at_once], a, k, max(k, beam), limit)

    def _walk(self, links: np.ndarray, q: np.ndarray, base: int, k: int, most: int, limit: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n = len(q)
        room = 4 * links.shape[1]
        seen = np.zeros((n, len(self.x)), bool)
        seen[:, self.entry] = True
        # of each row the nodes seen, their distances, the same while they wait to be read, and how many they are
        node, dist, wait = np.zeros((n, room), np.int32), np.full((n, room), np.inf), np.full((n, room), np.inf)
        node[:, 0] = self.entry
        dist[:, 0] = wait[:, 0] = ((self.x[self.entry] - q) ** 2).sum(axis=1)
        size, live, open_, read = np.ones(n, np.int64), np.arange(n), np.ones(n, bool), 0
        got: list[tuple[np.ndarray, ...]] = []

        def end(rows: np.ndarray, where: np.ndarray) -> None:
            """The k best of walks that have ended."""
            i, j = np.nonzero((np.arange(node.shape[1]) < size[where, None]) & (dist[where] <= limit))
            d, m, r = dist[where[i], j], node[where[i], j], rows[i]
            order = np.lexsort((m, d, r))
            i = i[order]
            place = ranges(np.bincount(i, minlength=len(where)))
            order = order[place < k]
            got.append((r[order] + base, m[order], d[order]))

        while len(live):
            each = np.arange(len(live))
            here = int(size.max())
            at = wait[:, :here].argmin(axis=1)
            least = wait[each, at]
            stop = np.isinf(least)
            if read >= most:  # before that no walk has read enough to end
                stop |= ((dist[:, :here] < least[:, None]).sum(axis=1)) >= most
            stop &= open_
            if stop.any():
                out = np.flatnonzero(stop)
                end(live[out], out)
                open_[out] = False
                if np.count_nonzero(open_) < 0.85 * len(open_):  # until then what has ended goes on, and nothing is told of it
                    go = np.flatnonzero(open_)
                    live, size, at, each, open_ = live[go], size[go], at[go], np.arange(len(go)), open_[go]
                    node, dist, wait = node[go], dist[go], wait[go]
                    if not len(go):
                        break
            wait[each, at] = np.inf
            read += 1
            to = links[node[each, at]]
            fresh = (to >= 0) & ~seen[live[:, None], to]
            i, j = np.nonzero(fresh)
            to = to[i, j]
            seen[live[i], to] = True
            count = fresh.sum(axis=1)
            if size.max() + links.shape[1] > node.shape[1]:
                more = node.shape[1]
                node = np.pad(node, ((0, 0), (0, more)))
                dist, wait = (np.pad(c, ((0, 0), (0, more)), constant_values=np.inf) for c in (dist, wait))
            col = size[i] + ranges(count)
            d = ((self.x[to] - q[live[i]]) ** 2).sum(axis=1)
            node[i, col], dist[i, col], wait[i, col] = to, d, d
            size = size + count
        return tuple(np.concatenate(c) for c in zip(*got, strict=True))


def near_links(x: np.ndarray, since: int, until: int, degree: int = 16, alpha: float = 1.2, rows: int = 256) -> list[list[int]]:
    """Of the nodes since .. until - 1 up to ``degree`` near neighbours each, nearest first; one goes if a kept one is about as near to it as the node."""
    sq = (x * x).sum(axis=1)
    out: list[list[int]] = []
    for at in range(since, until, rows):
        n = min(rows, until - at)
        block = sq[None, :] + sq[at : at + n, None] - 2 * x[at : at + n] @ x.T
        each = np.arange(n)
        block[each, at + each] = np.inf
        few = min(3 * degree, len(x) - 1)
        if few <= 0:
            out += [[] for _ in range(n)]
            continue
        pool = np.argpartition(block, few - 1, axis=1)[:, :few]
        near = np.take_along_axis(block, pool, 1)
        order = np.argsort(near, axis=1, kind="stable")
        pool, near = np.take_along_axis(pool, order, 1), np.take_along_axis(near, order, 1)
        kept, count = np.zeros((n, few), bool), np.zeros(n, np.int64)
        for c in range(few):
            # from each candidate to those that are kept before it
            i, j = np.nonzero(kept[:, :c] & (count < degree)[:, None])
            least = np.full(n, np.inf)
            np.minimum.at(least, i, ((x[pool[i, j]] - x[pool[i, c]]) ** 2).sum(axis=1))
            kept[:, c] = (count < degree) & (alpha * alpha * least > near[:, c])
            count += kept[:, c]
        out += [p[k].tolist() for p, k in zip(pool, kept, strict=True)]
    return out
