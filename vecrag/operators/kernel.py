"""Proximity graph of one partition: search, insertion, deletion, repair. Pure NumPy, deterministic.

Levels depend on (seed, id) only, candidates are ordered by (distance, id), so a retried task builds the same graph.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from dataclasses import dataclass, field

import numpy as np

M, ALPHA, EF_BUILD, MAX_LEVEL = 16, 1.2, 64, 15
#: Bytes of the distances that are held at once when a list is linked.
BLOCK_BYTES = 16 << 20
#: Distances of which only the least is looked at for a bound on the nearest ones.
GROUP = 32
#: Members of a pool up to which their distances to each other are taken all at once.
WIDEST = 512


def draw_level(node_id: int, m: int = M, seed: int = 42) -> int:
    """floor(-ln u / ln m) with u in (0, 1] from a hash of (seed, id): a share of about 1/m rises a level."""
    if m < 2:
        return 0
    u = (int.from_bytes(hashlib.blake2b(f"{seed}:{node_id}".encode(), digest_size=8).digest(), "little") + 1) / 2.0**64
    return min(MAX_LEVEL, int(-math.log(u) / math.log(m)))


def packed(vecs: np.ndarray) -> bytes:
    """Vectors in 4 bytes a number where that loses nothing, else in 8."""
    short = vecs.astype("<f4")
    return (short if (short == vecs).all() else vecs.astype("<f8")).tobytes()


def unpacked(data: bytes, n: int, dim: int) -> np.ndarray:
    return np.frombuffer(data, "<f8" if n * dim and len(data) == 8 * n * dim else "<f4").reshape(n, dim).astype(float)


def _select_rows(pts: np.ndarray, sq: np.ndarray, pool: np.ndarray, far: np.ndarray, alive: np.ndarray, cap: int, alpha: float) -> np.ndarray:
    """Robust selection for many pools at once: which of their (alive) members are taken."""
    p, s, rows, taken = pts[pool], sq[pool], np.arange(len(pool)), np.zeros(pool.shape, bool)
    between = alpha * np.sqrt(np.maximum(0, s[:, :, None] + s[:, None, :] - 2 * (p @ p.transpose(0, 2, 1))))
    for _ in range(cap):
        first = alive.argmax(1)
        some = alive[rows, first]
        if not some.any():
            break
        taken[rows[some], first[some]] = True
        alive[rows, first] = False
        alive &= between[rows, first] > far
    return taken


def chosen_links(pts: np.ndarray, wanted: np.ndarray, cap: int, ef_build: int, alpha: float = ALPHA) -> list[np.ndarray]:
    """For each wanted place in `pts` the places that it links to: selected from its nearest ones among all."""
    n, sq = len(pts), (pts**2).sum(1)
    if n < 2:
        return [np.zeros(0, int) for _ in wanted]
    take = min(n - 1, max(ef_build, cap))
    chosen: list[np.ndarray] = []
    step, at_once = max(1, BLOCK_BYTES // (8 * n)), max(1, BLOCK_BYTES // (32 * take * take))
    for at in range(0, len(wanted), step):  # distances of a block of nodes to all: memory is bounded
        rows = wanted[at : at + step]
        d = 2 * pts[rows] @ pts.T
        np.subtract(sq[rows, None] + sq, d, out=d)
        d[np.arange(len(rows)), rows] = np.inf
        some = d
        if n >= GROUP * 4 * take:  # the least of `take` groups are as many numbers, so their limit takes in the nearest ones
            width = n // GROUP
            some = d[:, : width * GROUP].reshape(len(rows), GROUP, width).min(1)
        limit = np.maximum(0, np.partition(some, take - 1, axis=1)[:, take - 1])
        limit = np.maximum(limit, (np.sqrt(limit) + 1e-11) ** 2)
        pools, fars = np.empty((len(rows), take), int), np.empty((len(rows), take))
        for k, (near, most) in enumerate(zip(d, limit, strict=True)):
            pool = np.flatnonzero(near <= most)
            far = np.sqrt(np.maximum(0, near[pool]))
            order = np.argsort(np.round(far, 12), kind="stable")[:take]
            pools[k], fars[k] = pool[order], far[order]
        for k in range(0, len(rows), at_once):
            part = slice(k, k + at_once)
            taken = _select_rows(pts, sq, pools[part], fars[part], np.ones(pools[part].shape, bool), cap, alpha)
            chosen += [pool[t] for pool, t in zip(pools[part], taken, strict=True)]
    return chosen


@dataclass
class Graph:
    dim: int
    m: int = M
    alpha: float = ALPHA
    ef_build: int = EF_BUILD
    seed: int = 42
    m0_factor: int = 1
    carry_entry: bool = True
    vecs: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    ids: list[int] = field(default_factory=list)
    levels: list[int] = field(default_factory=list)
    links: list[list[list[int]]] = field(default_factory=list)  # [node][level] -> positions
    deleted: list[bool] = field(default_factory=list)
    entry: int = -1
    max_level: int = -1
    n_dist: int = 0
    overflow_count: int = 0
    at: dict[int, int] = field(default_factory=dict)
    room: np.ndarray | None = field(default=None, repr=False, compare=False)  # vecs with space for more

    def __post_init__(self) -> None:
        if not self.vecs.size:
            self.vecs = np.zeros((0, self.dim))

    def cap(self, level: int) -> int:
        return self.m * (self.m0_factor if level == 0 else 1)

    def live(self) -> list[int]:
        return [k for k, gone in enumerate(self.deleted) if not gone]

    def dists(self, q: np.ndarray, nodes: list[int]) -> np.ndarray:
        self.n_dist += len(nodes)
        return np.sqrt(((self.vecs[nodes] - q) ** 2).sum(1))

    # -- search ------------------------------------------------------------------------------------------------
    def descend(self, q: np.ndarray, start: int, high: int, low: int) -> int:
        """Greedy walk from `start` on the levels high..low: the nearest node found."""
        best, best_d = start, float(self.dists(q, [start])[0])
        for level in range(high, low - 1, -1):
            while True:
                near = [n for n in (self.links[best][level] if level < len(self.links[best]) else []) if not self.deleted[n]]
                if not near:
                    break
                d = self.dists(q, near)
                k = min(range(len(near)), key=lambda i: (d[i], self.ids[near[i]]))
                if d[k] >= best_d:
                    break
                best, best_d = near[k], float(d[k])
        return best

    def beam(self, q: np.ndarray, starts: list[int], level: int, ef: int) -> list[tuple[float, int]]:
        """Best-first search of width ef on one level: (distance, node), nearest first; flagged nodes are only crossed."""
        seen = set(starts)
        d0 = self.dists(q, list(starts))
        frontier = [(float(d), self.ids[n], n) for d, n in zip(d0, starts, strict=True)]
        heapq.heapify(frontier)
        found = [(-d, -i, n) for d, i, n in frontier if not self.deleted[n]]
        heapq.heapify(found)
        while frontier:
            d, _, node = heapq.heappop(frontier)
            if len(found) >= ef and d > -found[0][0]:
                break
            near = [n for n in (self.links[node][level] if level < len(self.links[node]) else []) if n not in seen]
            if not near:
                continue
            seen.update(near)
            for nd, n in zip(self.dists(q, near).tolist(), near, strict=True):
                if len(found) < ef or nd <= -found[0][0]:
                    heapq.heappush(frontier, (nd, self.ids[n], n))
                    if not self.deleted[n]:
                        heapq.heappush(found, (-nd, -self.ids[n], n))
                        if len(found) > ef:
                            heapq.heappop(found)
        return [(-d, n) for d, i, n in sorted(found, key=lambda x: (-x[0], -x[1]))]

    def search(self, q: np.ndarray, k: int, ef: int) -> tuple[list[tuple[float, int]], int]:
        """The k nearest (distance, id) and the number of distances counted."""
        before = self.n_dist
        if self.entry < 0 or k <= 0:
            return [], 0
        start = self.descend(q, self.entry, self.max_level, 1) if self.max_level > 0 else self.entry
        found = self.beam(q, [start], 0, max(ef, k))
        return [(d, self.ids[n]) for d, n in found[:k]], self.n_dist - before

    def candidates(self, q: np.ndarray, ef: int) -> tuple[np.ndarray, int]:
        """Nodes that a search of width ef < n ends with, and the number of distances counted."""
        before = self.n_dist
        if self.entry < 0:
            return np.zeros(0, int), 0
        start = self.descend(q, self.entry, self.max_level, 1) if self.max_level > 0 else self.entry
        return np.array([n for _, n in self.beam(q, [start], 0, ef)], int), self.n_dist - before

    def crossed(self) -> tuple[np.ndarray, int]:
        """What a beam as wide as the graph ends with for any query: all unflagged nodes that the entry reaches, and the
        number of nodes crossed.
        """
        seen = self.reachable() if self.entry >= 0 else set()
        return np.array(sorted(n for n in seen if not self.deleted[n]), int), len(seen)

    # -- building ----------------------------------------------------------------------------------------------
    def prune(self, point: int, candidates: list[int], cap: int) -> list[int]:
        """Robust selection: take the nearest, drop every candidate that a taken one is alpha times closer to."""
        pool = [n for n in dict.fromkeys(candidates) if n != point and not self.deleted[n]]
        if not pool:
            return []
        d = self.dists(self.vecs[point], pool)
        order = sorted(range(len(pool)), key=lambda i: (d[i], self.ids[pool[i]]))
        ranked, away = [pool[i] for i in order], d[order]
        alive, taken = np.arange(len(ranked)), []
        pts = self.vecs[ranked]
        table = np.sqrt(((pts[:, None] - pts[None]) ** 2).sum(2)) if len(ranked) <= 2 * self.m else None  # of few, all at once
        while len(alive) and len(taken) < cap:
            first, alive = int(alive[0]), alive[1:]
            taken.append(ranked[first])
            if not len(alive):
                break
            self.n_dist += len(alive)
            between = table[first, alive] if table is not None else np.sqrt(((pts[alive] - pts[first]) ** 2).sum(1))
            alive = alive[self.alpha * between > away[alive]]
        return taken

    def link_both(self, node: int, nbrs: list[int], level: int) -> None:
        """Set a node's links and add the reverse ones; a list over its cap is pruned again."""
        self.links[node][level] = list(nbrs)
        for n in nbrs:
            back = self.links[n][level]
            if node not in back:
                back.append(node)
                if len(back) > self.cap(level):
                    self.links[n][level] = self.prune(n, back, self.cap(level))

    def _append(self, node_id: int, vec: np.ndarray, level: int) -> int:
        at = len(self.ids)
        if self.room is None or self.vecs.base is not self.room or at == len(self.room):
            self.room = np.empty((max(16, 2 * at), self.dim))
            self.room[:at] = self.vecs
        self.room[at] = vec
        self.vecs = self.room[: at + 1]
        self.ids.append(node_id)
        self.levels.append(level)
        self.links.append([[] for _ in range(level + 1)])
        self.deleted.append(False)
        self.at[node_id] = at
        return at

    def insert(self, node_id: int, vec, level: int | None = None) -> None:
        """Add a node; a live id is deleted first; the level of an id never changes."""
        vec = np.asarray(vec, float)
        if vec.shape != (self.dim,) or not np.isfinite(vec).all():
            raise ValueError(f"vector of {node_id} must have {self.dim} finite numbers")
        if node_id in self.at:
            self.delete(node_id)
        level = draw_level(node_id, self.m, self.seed) if level is None else level
        at = self._append(node_id, vec, level)
        if self.entry < 0:
            self.entry, self.max_level = at, level
            return
        start = self.entry
        if self.max_level > level:
            start = self.descend(vec, start, self.max_level, level + 1)
        for lv in range(min(level, self.max_level), -1, -1):
            found = [(d, n) for d, n in self.beam(vec, [start], lv, self.ef_build) if n != at]
            self.link_both(at, self.prune(at, [n for _, n in found], self.cap(lv)), lv)
            if found and self.carry_entry:
                start = found[0][1]
        if level > self.max_level:
            self.entry, self.max_level = at, level

    @classmethod
    def build(cls, ids, vecs, mode: str = "batch", repair: bool = True, levels: list[int] | None = None, chosen: list[np.ndarray] | None = None, **options) -> Graph:
        """`incremental` inserts in order of id; `batch` prunes from all pair distances of the (small) list. chosen: the level 0
        links of `chosen_links` by places in order of id, where other tasks have made them.
        """
        vecs = np.asarray(vecs, float)
        graph = cls(dim=vecs.shape[1] if vecs.ndim == 2 else 0, **options)
        order = np.argsort(np.asarray(ids), kind="stable") if len(ids) else []
        if mode == "incremental":
            for k in order:
                graph.insert(int(ids[k]), vecs[k], None if levels is None else levels[k])
        elif mode == "batch":
            graph.vecs = vecs[order] if len(order) else graph.vecs
            graph.ids = [int(ids[k]) for k in order]
            graph.at = {i: k for k, i in enumerate(graph.ids)}
            graph.levels = [draw_level(i, graph.m, graph.seed) for i in graph.ids] if levels is None else [levels[k] for k in order]
            graph.deleted = [False] * len(graph.ids)
            graph.links = [[[] for _ in range(lv + 1)] for lv in graph.levels]
            if graph.ids:
                graph.max_level = max(graph.levels)
                graph.entry = graph.levels.index(graph.max_level)
            for level in range(graph.max_level + 1):
                graph._link_all([k for k, lv in enumerate(graph.levels) if lv >= level], level, None if level else chosen)
        else:
            raise ValueError(f"no such mode: {mode}")
        if repair:
            graph.repair()
        return graph

    def _link_all(self, members: list[int], level: int, chosen: list[np.ndarray] | None = None) -> None:
        """Link all nodes of a level. chosen: what `chosen_links` gives for each of them, if that is there already."""
        if len(members) < 2:
            return
        pts, n, cap = self.vecs[members], len(members), self.cap(level)
        sq = (pts**2).sum(1)
        self.n_dist += n * (n - 1) // 2

        def away(i: int, pool: np.ndarray) -> np.ndarray:
            return np.sqrt(np.maximum(0, sq[i] + sq[pool] - 2 * pts[pool] @ pts[i]))

        def select(pool: np.ndarray, far: np.ndarray) -> np.ndarray:
            taken = []
            while len(pool) and len(taken) < cap:
                first = pool[0]
                taken.append(first)
                pool, far = pool[1:], far[1:]
                keep = self.alpha * away(first, pool) > far
                pool, far = pool[keep], far[keep]
            return np.array(taken, int)

        at_once = lambda width: max(1, BLOCK_BYTES // (32 * width * width))
        if chosen is None:
            chosen = chosen_links(pts, np.arange(n), cap, self.ef_build, self.alpha)
        back: list[set[int]] = [set(c.tolist()) for c in chosen]
        for i, c in enumerate(chosen):
            for j in c.tolist():
                back[j].add(i)
        many = sorted((i for i, s in enumerate(back) if cap < len(s) <= WIDEST), key=lambda i: len(back[i]))
        while many:  # pools of about the same size together
            part = many[-at_once(len(back[many[-1]])) :]
            del many[-len(part) :]
            pool, far = np.zeros((len(part), len(back[part[-1]])), int), np.full((len(part), len(back[part[-1]])), np.inf)
            for k, i in enumerate(part):
                own = np.array(sorted(back[i]), int)
                away_own = away(i, own)
                order = np.argsort(away_own, kind="stable")
                pool[k, : len(own)], far[k, : len(own)] = own[order], away_own[order]
            taken = _select_rows(pts, sq, pool, far, np.arange(pool.shape[1]) < np.array([len(back[i]) for i in part])[:, None], cap, self.alpha)
            for k, i in enumerate(part):
                self.links[members[i]][level] = [members[j] for j in pool[k][taken[k]].tolist()]
        for i, s in enumerate(back):
            if cap < len(s) <= WIDEST:
                continue
            pool = np.array(sorted(s), int)
            far = away(i, pool) if len(pool) else np.zeros(0)
            order = np.argsort(far, kind="stable")
            kept = pool[order] if len(pool) <= cap else select(pool[order], far[order])
            self.links[members[i]][level] = [members[j] for j in kept.tolist()]

    # -- deletion ----------------------------------------------------------------------------------------------
    def delete(self, node_id: int, lazy: bool = False, k_extra: int | None = None) -> bool:
        """Remove an id (False if it isn't there). lazy only flags it, for purge() later."""
        at = self.at.get(node_id)
        if at is None or self.deleted[at]:
            return False
        if lazy:
            self.deleted[at] = True
            if self.entry == at:
                self._new_entry()
            return True
        self._unlink(at, self.m if k_extra is None else k_extra)
        self._compact({at})
        self.repair()
        return True

    def delete_many(self, node_ids, k_extra: int | None = None) -> int:
        """Delete in order of id: all links to the deleted go before their neighbours are linked anew."""
        gone = sorted({self.at[i] for i in node_ids if i in self.at}, key=lambda n: self.ids[n])
        if gone:
            for at in gone:
                self.deleted[at] = True
            for at in gone:
                self._unlink(at, self.m if k_extra is None else k_extra)
            self._compact(set(gone))
            self.repair()
        return len(gone)

    def _unlink(self, at: int, k_extra: int) -> None:
        self.deleted[at] = True
        if self.entry == at:
            self._new_entry()
        for level in range(self.levels[at] + 1):
            holders = [n for n in range(len(self.ids)) if level < len(self.links[n]) and at in self.links[n][level]]
            former = sorted({*holders, *self.links[at][level]} - {at}, key=lambda n: self.ids[n])
            for n in holders:
                self.links[n][level].remove(at)
            self.links[at][level] = []
            former = [n for n in former if not self.deleted[n]]
            for n in former:
                self.reconnect(n, former, level, k_extra)

    def reconnect(self, node: int, former: list[int], level: int, k_extra: int) -> None:
        """New links of a former neighbour: its other links, the other former neighbours and nearest nodes, pruned."""
        near: list[int] = []
        if k_extra and self.entry >= 0 and level <= self.max_level:
            near = [n for _, n in self.beam(self.vecs[node], [node], level, k_extra + 1)]
        pool = [*self.links[node][level], *former, *near]
        self.link_both(node, self.prune(node, pool, self.cap(level)), level)

    def _new_entry(self) -> None:
        alive = self.live()
        if not alive:
            self.entry = self.max_level = -1
            return
        self.entry = min(alive, key=lambda n: (-self.levels[n], self.ids[n]))
        self.max_level = self.levels[self.entry]

    def _compact(self, gone: set[int]) -> None:
        keep = [n for n in range(len(self.ids)) if n not in gone]
        new = {n: k for k, n in enumerate(keep)}
        self.vecs = self.vecs[keep]
        self.links = [[[new[x] for x in lv if x in new] for lv in self.links[n]] for n in keep]
        self.ids, self.levels, self.deleted = [self.ids[n] for n in keep], [self.levels[n] for n in keep], [self.deleted[n] for n in keep]
        self.at = {i: k for k, i in enumerate(self.ids)}
        self.entry = new.get(self.entry, -1)
        if self.entry < 0:
            self._new_entry()

    def purge(self) -> int:
        """Remove flagged nodes for good; the number removed."""
        flagged = [self.ids[n] for n, gone in enumerate(self.deleted) if gone]
        return self.delete_many(flagged)

    # -- repair ------------------------------------------------------------------------------------------------
    def reachable(self, start: int | None = None, level: int = 0) -> set[int]:
        start = self.entry if start is None else start
        seen, todo = {start}, [start]
        while todo:
            for n in self.links[todo.pop()][level]:
                if n not in seen:
                    seen.add(n)
                    todo.append(n)
        return seen

    def repair(self) -> int:
        """Link nodes that level 0 cannot reach from the entry to the nearest reachable node with room."""
        fixed = 0
        if self.entry < 0:
            return 0
        ids = np.array(self.ids)
        seen = np.zeros(len(ids), bool)
        seen[list(self.reachable())] = True
        used = np.array([len(node[0]) for node in self.links])
        for node in np.argsort(ids, kind="stable").tolist():
            if seen[node]:
                continue
            inside = np.flatnonzero(seen)
            free = inside[used[inside] < self.cap(0)]
            if not len(free):
                free = inside
                self.overflow_count += 1
            d = self.dists(self.vecs[node], free)
            ties = free[d == d.min()]
            host = int(ties[np.argmin(ids[ties])])
            self.links[host][0].append(node)
            if host not in self.links[node][0] and used[node] < self.cap(0):
                self.links[node][0].append(host)
                used[node] += 1
            used[host] += 1
            seen[list(self._new(node, seen))] = True
            fixed += 1
        return fixed

    def _new(self, start: int, seen: np.ndarray) -> set[int]:
        """Nodes that `start` reaches on level 0 over nodes not seen yet."""
        found, todo = {start}, [start]
        while todo:
            for n in self.links[todo.pop()][0]:
                if n not in found and not seen[n]:
                    found.add(n)
                    todo.append(n)
        return found

    # -- stored form -------------------------------------------------------------------------------------------
    def to_row(self) -> dict:
        """Compressed rows over (level, node): link_ptr has an entry for each level of each node, plus one."""
        ptr, to = [0], []
        for node in self.links:
            for level in node:
                to += level
                ptr.append(len(to))
        return {
            "n": len(self.ids), "dim": self.dim, "m": self.m, "ids": list(self.ids), "vecs": packed(self.vecs), "levels": list(self.levels),
            "link_ptr": ptr, "link_to": to, "entry": self.entry, "max_level": self.max_level, "deleted": list(self.deleted), "n_dist_build": self.n_dist,
        }

    @classmethod
    def from_row(cls, row: dict, **options) -> Graph:
        graph = cls(dim=row["dim"], m=row["m"], **options)
        graph.vecs = unpacked(row["vecs"], row["n"], row["dim"])
        graph.ids, graph.levels, graph.deleted = list(row["ids"]), list(row["levels"]), list(row["deleted"])
        ptr, to, k = row["link_ptr"], row["link_to"], 0
        for level in graph.levels:
            graph.links.append([list(to[ptr[k + j] : ptr[k + j + 1]]) for j in range(level + 1)])
            k += level + 1
        graph.entry, graph.max_level = row["entry"], row["max_level"]
        graph.at = {i: n for n, i in enumerate(graph.ids)}
        return graph
