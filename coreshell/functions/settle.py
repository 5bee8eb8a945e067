"""Local fixpoints in one task: vertices of a block are re-estimated until none of them changes, against a frozen rim."""

from __future__ import annotations

import heapq
import tempfile
from collections.abc import Callable, Iterable, Iterator

import numpy as np

from coreshell.functions.hindex import h_index_block


#: Vertices of a step that are worked on one by one: fewer than make numpy's calls worth while.
FEW = 8


class Buckets:
    """Positions by key, taken out by the lowest key, all of one key at a time."""

    def __init__(self):
        self.held: dict[int, tuple[list[int], list[np.ndarray]]] = {}
        self.keys: list[int] = []

    def __bool__(self) -> bool:
        return bool(self.keys)

    def _at(self, key: int) -> tuple[list[int], list[np.ndarray]]:
        if key not in self.held:
            self.held[key] = ([], [])
            heapq.heappush(self.keys, key)
        return self.held[key]

    def put_one(self, position: int, key: int) -> None:
        self._at(key)[0].append(position)

    def put(self, some: np.ndarray, keys: np.ndarray) -> None:
        if not len(some):
            return
        order = np.argsort(keys, kind="stable")
        some, keys = some[order], keys[order]
        cuts = np.flatnonzero(np.diff(keys)) + 1
        for key, part in zip(keys[np.r_[0, cuts]].tolist(), np.split(some, cuts), strict=True):
            self._at(key)[1].append(part)

    def pop(self) -> tuple[int, np.ndarray | list[int]]:
        key = heapq.heappop(self.keys)
        ones, parts = self.held.pop(key)
        return key, np.concatenate([np.array(ones, np.int64), *parts]) if parts else ones


class Heap:
    """Positions below ``n`` by key, one at a time: a key and a position are one number, which compares faster than a pair."""

    def __init__(self, n: int, positions: np.ndarray, keys: np.ndarray):
        self.n, self.held = n, (keys.astype(np.int64) * n + positions).tolist()
        heapq.heapify(self.held)

    def put_one(self, position: int, key: int) -> None:
        heapq.heappush(self.held, key * self.n + position)

    def pop(self) -> int:
        return heapq.heappop(self.held) % self.n


def _places(ids: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    """What finds the positions of some of the ascending ``ids``: in a table where they lie close together, by counting where none is left out."""
    if len(ids) and int(ids[-1]) - int(ids[0]) == len(ids) - 1:
        return lambda some: some - ids[0]
    if not len(ids) or int(ids[-1]) - int(ids[0]) > 8 * len(ids):
        return lambda some: np.searchsorted(ids, some)
    table = np.zeros(int(ids[-1] - ids[0]) + 1, np.int32)
    table[ids - ids[0]] = np.arange(len(ids))
    return lambda some: table[some - ids[0]]


def _distinct(some: np.ndarray) -> np.ndarray:
    """Ascending, by one sort, which takes less than numpy's table of distinct numbers."""
    some = np.sort(some)
    return some[np.r_[True, some[1:] != some[:-1]]] if len(some) else some


class Block:
    """Arcs of some vertices as sorted, contiguous neighbour lists; neighbours outside keep the estimates they came with."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, est_src: np.ndarray, est_dst: np.ndarray):
        ordered = np.sort(src)
        self.ids = ordered[np.r_[True, ordered[1:] != ordered[:-1]]] if len(src) else src
        self.n = len(self.ids)
        mine, other = np.searchsorted(self.ids, src), np.searchsorted(self.ids, dst)
        other[other == self.n] = 0
        outside = self.ids[other] != dst if self.n else np.zeros(0, bool)
        rim, place = np.unique(dst[outside], return_inverse=True)
        other[outside] = self.n + place
        wide = self.n + len(rim)
        self.est = np.full(wide, np.iinfo(np.int64).max)
        self.est[mine] = est_src
        np.minimum.at(self.est, other[outside], est_dst[outside])  # of several copies the lowest is the latest
        # sorted lists in one sort of (vertex, neighbour) as one number
        self.nbrs = np.sort(mine * wide + other) % max(1, wide)
        self.size = np.bincount(mine, minlength=self.n)
        self.first = np.cumsum(self.size) - self.size
        self.evals = np.zeros(self.n, np.int64)

    @classmethod
    def whole(cls, edges: list[tuple[np.ndarray, np.ndarray]], ids: np.ndarray, est: np.ndarray) -> Block:
        """A whole graph without a rim: ``edges`` in parts (emptied while they are read), every edge once, and all vertices by ascending id.

        Some 25 bytes an arc at work: parts are turned into numbers of (vertex, neighbour) one by one and sorted in place.
        """
        b = cls.__new__(cls)
        b.ids, b.n, b.est = ids, len(ids), est.astype(np.int64)
        m, at, place = sum(len(u) for u, _ in edges), 0, _places(ids)
        keys = np.empty(2 * m, np.int64)
        while edges:
            u, v = (place(x).astype(np.int64) for x in edges.pop())
            keys[at : at + len(u)], keys[m + at : m + at + len(u)] = u * b.n + v, v * b.n + u
            at += len(u)
        keys.sort()
        begins = np.searchsorted(keys, np.arange(b.n + 1) * b.n)
        b.first, b.size = begins[:-1], np.diff(begins)
        b.nbrs = np.remainder(keys, max(1, b.n), out=keys).astype(np.int32)
        b.evals = np.zeros(b.n, np.int64)
        return b

    @classmethod
    def listed(cls, arcs: Iterable[tuple[np.ndarray, np.ndarray]], ids: np.ndarray, est: np.ndarray) -> Block:
        """A whole graph whose neighbour lists lie on the task's disk: ``arcs`` in parts ascending by source, and all vertices by ascending id.

        Some 40 bytes a vertex at work; of the lists only what is looked at is read."""
        b = cls.__new__(cls)
        b.ids, b.n, b.est = ids, len(ids), est.astype(np.int64)
        b.size, b.evals, place = np.zeros(b.n, np.int64), np.zeros(b.n, np.int64), _places(ids)
        with tempfile.TemporaryFile() as file:
            for src, dst in arcs:
                at, count = np.unique(src, return_counts=True)
                b.size[place(at)] += count
                file.write(place(dst).astype(np.int32).tobytes())
            file.flush()
            b.nbrs = np.memmap(file, np.int32, "r") if file.tell() else np.zeros(0, np.int32)
        b.first = np.cumsum(b.size) - b.size
        return b

    @classmethod
    def placed(cls, lists: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]], n_arcs: int, est: np.ndarray) -> Block:
        """A whole graph from (positions, sizes, neighbours' positions) of whole lists in any order, which lie as they came; ids are the positions.

        Some 4 bytes an arc and 40 a vertex at work."""
        b = cls.__new__(cls)
        b.n, b.est = len(est), est.astype(np.int32)
        b.ids, b.nbrs = np.arange(b.n), np.empty(n_arcs, np.int32)
        b.first, b.size, b.evals, at = *(np.zeros(b.n, np.int64) for _ in range(3)), 0
        for nodes, size, nbrs in lists:
            b.size[nodes], b.first[nodes] = size, at + np.cumsum(size, dtype=np.int64) - size
            b.nbrs[at : at + len(nbrs)] = nbrs
            at += len(nbrs)
        return b

    @classmethod
    def rimmed(cls, size: np.ndarray, nbrs: np.ndarray, est: np.ndarray, rim: np.ndarray) -> Block:
        """Lists of vertices one after the other, neighbours as places among them and then the rim, whose estimates are ``rim``; ids are the positions."""
        b = cls.__new__(cls)
        b.n, b.est, b.nbrs = len(size), np.concatenate([est, rim]).astype(np.int64), nbrs
        b.ids, b.size, b.evals = np.arange(b.n), size.astype(np.int64), np.zeros(b.n, np.int64)
        b.first = np.cumsum(b.size) - b.size
        return b

    def lists(self, some: np.ndarray) -> np.ndarray:
        """Neighbours of the vertices at ``some``, in a row."""
        size = self.size[some]
        ends = np.cumsum(size)
        return self.nbrs[np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(self.first[some] - ends + size, size)]

    def evaluate(self, some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(vertices of ``some`` whose estimate drops, their new estimates)."""
        self.evals[some] += 1
        new = h_index_block(self.size[some], self.est[some], self.est[self.lists(some)])
        down = new < self.est[some]
        return some[down], new[down]

    def wakened(self, changed: np.ndarray, old: np.ndarray, new: np.ndarray) -> np.ndarray:
        """Vertices of the block that one of ``changed`` supported and no longer does; estimates are already the new ones."""
        to = self.lists(changed)
        was, now = np.repeat(old, self.size[changed]), np.repeat(new, self.size[changed])
        mine = self.est[to]
        return _distinct(to[(to < self.n) & (now < mine) & (was >= mine)])

    def settle(self, active: np.ndarray, order: str = "priority") -> np.ndarray:
        """Run to the fixpoint from the ``active`` positions; the estimates.

        priority: all waiting vertices of the lowest estimate at a time, so that high ones aren't evaluated again for every
        drop below them. fifo: all waiting vertices at a time. Waiting vertices lie in buckets by estimate, so a step
        touches its members and their neighbours only, however large the block is.
        """
        waiting = np.zeros(self.n, bool)
        buckets, lowest = Buckets(), order == "priority"

        def wait(some: np.ndarray) -> None:
            some = some[~waiting[some]]
            waiting[some] = True
            buckets.put(some, self.est[some] if lowest else np.zeros(len(some), np.int64))

        wait(np.unique(active))
        one = self._one(waiting, buckets, lowest)
        while buckets:
            _, some = buckets.pop()
            if len(some) <= FEW:
                for i in some:
                    waiting[i] = False
                    one(int(i))
                continue
            some = np.asarray(some)
            waiting[some] = False
            changed, new = self.evaluate(some)
            old = self.est[changed].copy()
            self.est[changed] = new
            wait(self.wakened(changed, old, new))
        return self.est[: self.n]

    def settle_in(self, active: np.ndarray, order: str) -> np.ndarray:
        """To the fixpoint in the ``order`` priority, fifo or heap."""
        return self.settle_by_heap(active) if order == "heap" else self.settle(active, order)

    def _one(self, waiting: np.ndarray, buckets: Buckets | Heap, lowest: bool) -> Callable[[int], None]:
        """What evaluates one vertex and puts those that it wakes into ``buckets``, without numpy's cost of a call."""
        est, nbrs, first, size, evals, waits, n = *(memoryview(np.ascontiguousarray(x)) for x in (self.est, self.nbrs, self.first, self.size, self.evals, waiting)), self.n
        put = buckets.put_one

        def evaluate(i: int) -> None:
            evals[i] += 1
            old = est[i]
            a = first[i]
            to = nbrs[a : a + size[i]].tolist()
            theirs = [est[j] for j in to]
            if len(theirs) > 64 and sum([x >= old for x in theirs]) >= old:  # counting a hub's is cheaper than sorting them
                return
            theirs.sort(reverse=True)
            if len(theirs) >= old and (not old or theirs[old - 1] >= old):
                return
            new = 0
            for x in theirs:
                if x <= new:
                    break
                new += 1
            est[i] = new
            for j in to:
                x = est[j]
                if new < x <= old and j < n and not waits[j]:
                    waits[j] = True
                    put(j, x if lowest else 0)

        return evaluate

    def settle_by_heap(self, active: np.ndarray) -> np.ndarray:
        """The same, one vertex at a time from a heap ordered by lowest estimate (an estimate never changes while its vertex waits)."""
        waiting = np.zeros(self.n, bool)
        waiting[active] = True
        heap = Heap(self.n, np.asarray(active), self.est[active])
        one, waits, pop, held = self._one(waiting, heap, True), memoryview(waiting), heap.pop, heap.held
        while held:
            i = pop()
            waits[i] = False
            one(i)
        return self.est[: self.n]

    def rounds(self, active: np.ndarray, gate: str = "support") -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, dict[str, int]]]:
        """Synchronous rounds from the ``active`` positions until none are left: (active vertices, those that dropped, their old and new estimates,
        messages that each gate lets through) of each, exactly as rounds of the shared frontier go."""
        while n_active := len(active):
            changed, old, new = self.one_round(active)
            active, sent = self.concerned(changed, old, new, gate)
            yield n_active, changed, old, new, sent

    def one_round(self, active: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(those that dropped, their old and new estimates), all judged by the estimates before."""
        changed, new = self.evaluate(active)
        old = self.est[changed].copy()
        self.est[changed] = new
        return changed, old, new

    def concerned(self, changed: np.ndarray, old: np.ndarray, new: np.ndarray, gate: str) -> tuple[np.ndarray, dict[str, int]]:
        """(vertices that a round's drops wake, messages that each gate lets through); estimates are already the new ones."""
        to, size = self.lists(changed), self.size[changed]
        was, now, mine = np.repeat(old, size), np.repeat(new, size), self.est[to]
        lower = now < mine
        through = {"all": np.ones(len(to), bool), "lower": lower, "support": lower & (was >= mine)}
        active = _distinct(to[through["support" if gate == "counter" else gate]])
        if gate == "counter":
            size = self.size[active]
            owner = np.repeat(np.arange(len(active)), size)
            active = active[np.bincount(owner, self.est[self.lists(active)] >= self.est[active][owner], len(active)) < self.est[active]]
        return active, {k: int(x.sum()) for k, x in through.items()}

    def sweep(self, active: np.ndarray, batch: int) -> np.ndarray:
        """One pass over the active vertices in batches: each batch sees what the batches before it have changed."""
        for a in range(0, len(active), batch):
            changed, new = self.evaluate(active[a : a + batch])
            self.est[changed] = new
        return self.est[: self.n]


def peel(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, coreness, layer) by removing, level by level, all vertices of degree at most k at a time.

    Vertices lie in buckets by degree; a vertex that loses neighbours is put into its new bucket and its old entry is
    skipped later. So the work is linear in vertices and arcs, whatever the levels.
    """
    if not len(src):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    ids, once = np.unique(src), src < dst
    b = Block.whole([(src[once], dst[once])], ids, np.zeros(len(ids), np.int64))
    return b.ids, *peeled(b)


def peeled(b: Block) -> tuple[np.ndarray, np.ndarray]:
    """(coreness, layer) of the vertices of a whole graph."""
    degree = b.size.astype(np.int32)
    core, layer, alive = np.zeros(b.n, np.int32), np.zeros(b.n, np.int32), np.ones(b.n, bool)
    buckets = Buckets()
    buckets.put(np.arange(b.n, dtype=np.int32), degree)
    nbrs, first, size, degrees, living = (memoryview(np.ascontiguousarray(x)) for x in (b.nbrs, b.first, b.size, degree, alive))
    k = step = 0
    gone: np.ndarray | list[int] = []
    while len(gone) or buckets:
        if not len(gone):
            key, gone = buckets.pop()
            gone = [i for i in gone if living[i] and degrees[i] == key] if len(gone) <= FEW else (x := np.asarray(gone))[alive[x] & (degree[x] == key)]
            if not len(gone):
                continue
            k = max(k, key)
        step += 1
        core[gone], layer[gone], alive[gone] = k, step, False
        if len(gone) <= FEW:
            low = []
            for i in gone:
                for j in nbrs[first[i] : first[i] + size[i]].tolist():
                    if living[j]:
                        degrees[j] -= 1
                        if degrees[j] == k:
                            low.append(j)
                        elif degrees[j] > k:
                            buckets.put_one(j, degrees[j])
            gone = low
            continue
        to = b.lists(np.asarray(gone))
        touched, count = np.unique(to[alive[to]], return_counts=True)
        degree[touched] -= count
        low = degree[touched] <= k
        gone = touched[low]
        buckets.put(touched[~low], degree[touched[~low]])
    return core, layer


def sequential_cores(neighbours: dict[int, list[int]]) -> dict[int, int]:
    """Coreness of every vertex of an adjacency dictionary, one vertex at a time, as sequential graph libraries compute it.

    Vertices stand in a list sorted by degree, with the place where each degree begins. The first of those left is
    removed; each neighbour of a higher degree trades places with the first of its degree, whose stretch then begins
    one later. Linear in vertices and edges.
    """
    core = {v: len(of) for v, of in neighbours.items()}
    queue = sorted(core, key=core.get)
    place = {v: i for i, v in enumerate(queue)}
    begins: dict[int, int] = {}
    top = -1
    for i, v in enumerate(queue):
        for d in range(top + 1, core[v] + 1):
            begins[d] = i
        top = max(top, core[v])
    for v in queue:
        for u in neighbours[v]:
            if core[u] > core[v]:
                d = core[u]
                first = begins[d]
                other, at = queue[first], place[u]
                queue[first], queue[at] = u, other
                place[u], place[other] = first, at
                begins[d] = first + 1
                core[u] = d - 1
    return core
