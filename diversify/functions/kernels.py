"""Numpy kernels that run inside one task: traversals, sketches, solvers and exact measures over a block of points.

Points of a block are in the order of their ids, so that the first of equal candidates is the one with the smallest id. Distances are
compared through keys that grow with them (squares for Euclid), which stay exact integers on integer coordinates.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np


#: Metrics over coordinates, whose distances boxes bound.
PLAIN = ("euclid", "manhattan", "chebyshev")


class Block:
    """Ids and coordinates of some points with a metric.

    Dense rows for euclid, manhattan, chebyshev and angular; sets for jaccard; (terms, counts) for sparse, the angle between word counts.
    """

    def __init__(self, ids, data, metric: str = "euclid"):
        self.ids = np.asarray(ids, np.int64)
        order = np.argsort(self.ids, kind="stable")
        self.ids, self.metric = self.ids[order], metric
        if metric == "jaccard":
            self.sets = [frozenset(data[i]) for i in order]
        elif metric == "sparse":
            self.words = [(np.asarray(data[i][0], np.int64), np.asarray(data[i][1], float)) for i in order]
            self._lay()
        else:
            self.x = np.asarray(data, float).reshape(len(order), -1)[order]
            if metric == "angular":
                self.unit = self.x / np.linalg.norm(self.x, axis=1, keepdims=True)

    def _lay(self) -> None:
        self.terms = np.concatenate([np.zeros(0, np.int64), *(t for t, _ in self.words)])
        self.counts = np.concatenate([np.zeros(0), *(c for _, c in self.words)])
        self.row = np.repeat(np.arange(len(self.words)), [len(t) for t, _ in self.words])
        self.norm = np.bincount(self.row, weights=self.counts**2, minlength=len(self.words))

    def __len__(self) -> int:
        return len(self.ids)

    def keys_to(self, i: int, others: np.ndarray) -> np.ndarray:
        """Keys of the distances from point i to some, for the metrics of ``PLAIN``."""
        return self._gap_keys(self.x[others] - self.x[i])

    def keys(self, i: int) -> np.ndarray:
        """Keys of the distances from point i to all."""
        if self.metric == "jaccard":
            a = self.sets[i]
            return np.array([1 - len(a & b) / len(a | b) if a or b else 0.0 for b in self.sets])
        if self.metric == "angular":
            out = -np.round(self.unit @ self.unit[i], 12)
            out[i] = -1.0
            return out + 1
        if self.metric == "sparse":
            of = np.zeros(int(self.terms.max(initial=0)) + 1)
            of[self.words[i][0]] = self.words[i][1]
            dot = np.bincount(self.row, weights=self.counts * of[self.terms], minlength=len(self))
            return 1 - np.round(dot / np.sqrt(self.norm * self.norm[i]), 12)
        return self._gap_keys(self.x - self.x[i])

    def _gap_keys(self, gap: np.ndarray) -> np.ndarray:
        if self.metric == "manhattan":
            return np.abs(gap).sum(1)
        if self.metric == "chebyshev":
            return np.abs(gap).max(1)
        return np.einsum("ij,ij->i", gap, gap)

    def distance(self, key):
        """Distances of keys."""
        if self.metric == "euclid":
            return np.sqrt(key)
        if self.metric in ("angular", "sparse"):
            return np.arccos(np.clip(1 - np.asarray(key, float), -1, 1))
        return np.asarray(key, float)

    def matrix(self) -> np.ndarray:
        return np.array([self.distance(self.keys(i)) for i in range(len(self))]).reshape(len(self), len(self))

    def take(self, at) -> Block:
        out = Block.__new__(Block)
        at = np.sort(np.asarray(at, np.int64))
        out.ids, out.metric = self.ids[at], self.metric
        if self.metric == "jaccard":
            out.sets = [self.sets[i] for i in at]
        elif self.metric == "sparse":
            out.words = [self.words[i] for i in at]
            out._lay()
        else:
            out.x = self.x[at]
            if self.metric == "angular":
                out.unit = self.unit[at]
        return out


def farthest_first(b: Block, m: int, start: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(picks, owner, radii): the first min(m, n) anchors, for each point the rank of its nearest (ties to the earlier), the covering radius after each.

    Rows left at distance zero are picked by id, so that as many are returned as asked.
    """
    n = len(b)
    m = min(m, n)
    picks, owner, near, radii = [], np.zeros(n, np.int64), np.full(n, np.inf), []
    chosen = np.zeros(n, bool)
    for rank in range(m):
        at = start if rank == 0 else int(np.argmax(np.where(chosen, -1.0, near)))
        key = b.keys(at)
        better = key < near
        owner[better], near[better] = rank, key[better]
        chosen[at] = True
        owner[at], near[at] = rank, 0.0
        picks.append(at)
        radii.append(float(b.distance(near.max())))
    return np.array(picks, np.int64), owner, np.array(radii)


def delegates(picks: np.ndarray, owner: np.ndarray, cap: int) -> list[tuple[int, int]]:
    """(anchor, member) of each cluster: the anchor and up to cap-1 of its others with the smallest ids."""
    out = []
    for rank, anchor in enumerate(picks):
        members = np.flatnonzero(owner == rank)
        out += [(int(anchor), int(anchor)), *((int(anchor), int(x)) for x in members[members != anchor][: cap - 1])]
    return out


def counts(picks: np.ndarray, owner: np.ndarray, cap: int) -> np.ndarray:
    """Size of each anchor's cluster, at most cap."""
    return np.minimum(np.bincount(owner, minlength=len(picks)), cap)


class Sketch:
    """One pass over a stream with at most m kept points: kind 'points', 'delegates' or 'counts', metric 'euclid' or 'angular'.

    A phase merges kept points that are within twice the threshold of a survivor, then keeps newcomers farther than four thresholds from all
    kept ones until m + 1 are kept; the threshold doubles. Exact copies of kept points are delegates at most, so the
    first threshold is positive; while a merge removes nothing, the threshold doubles again. Distances are compared through keys: squares
    for Euclid (``square`` is the threshold's), angles themselves for the angular metric.
    """

    def __init__(self, k: int, m: int, kind: str = "points", metric: str = "euclid"):
        self.k, self.m, self.kind, self.metric = k, max(m, k), kind, metric
        self.two = 4 if metric == "euclid" else 2  # the key of twice a distance over the key of the distance
        self.ids: list[int] = []
        self.x: list[np.ndarray] = []
        self.held: list[list[tuple[int, np.ndarray]]] = []
        self.count: list[int] = []
        self.removed: list[tuple[int, np.ndarray]] = []
        self.square: float | None = None
        self.phase, self.seen, self.log = 0, 0, []
        self._rows = np.zeros((0, 0))

    def _ready(self, points: np.ndarray) -> np.ndarray:
        """Rows as distances need them: of length one for angles."""
        return points if self.metric == "euclid" else points / np.linalg.norm(points, axis=-1, keepdims=True)

    def _kept(self) -> np.ndarray:
        """The kept points, ready, in a matrix that grows with them."""
        n = len(self.x)
        if not n or len(self._rows) < n or self._rows.shape[1] != len(self.x[0]):
            self._rows = np.zeros((max(n, min(self.m + 1, 2 * n + 16)), len(self.x[0]) if n else 0))
            self._rows[:n] = self._ready(np.asarray(self.x)) if n else 0
        return self._rows[:n]

    def _to(self, rows: np.ndarray, p: np.ndarray) -> np.ndarray:
        """Keys of the distances from ready rows to one."""
        if self.metric == "angular":
            return np.arccos(np.clip(np.round(rows @ p, 12), -1, 1))
        gap = rows - p
        return np.einsum("ij,ij->i", gap, gap)

    def _join(self, host: int, who: list[tuple[int, np.ndarray]], count: int) -> None:
        room = self.k - len(self.held[host])
        self.held[host] += who[: max(room, 0)]
        self.count[host] = min(self.k, self.count[host] + count)

    def _join_all(self, hosts: np.ndarray, ids, points: np.ndarray) -> None:
        """Joins points to their hosts in order. A host takes its first ones up to k; only those are looked at one by one."""
        if self.kind == "points" or not len(hosts):
            return
        joined = np.bincount(hosts, minlength=len(self.x))
        self.count = np.minimum(np.asarray(self.count) + joined, self.k).tolist()
        if self.kind == "delegates":
            room = self.k - np.array([len(h) for h in self.held])
            open_ = np.flatnonzero(room[hosts] > 0)
            order = open_[np.argsort(hosts[open_], kind="stable")]
            of = hosts[order]
            first = np.flatnonzero(np.diff(of, prepend=-1)) if len(of) else np.zeros(0, int)
            rank = np.arange(len(of)) - np.repeat(first, np.diff(np.append(first, len(of))))
            for i in order[rank < room[of]].tolist():
                self.held[hosts[i]].append((int(ids[i]), points[i]))

    def _keep(self, pid: int, p: np.ndarray) -> None:
        self.ids.append(pid)
        self.x.append(p)
        self.held.append([(pid, p)])
        self.count.append(1)
        n = len(self.x)
        if len(self._rows) >= n and self._rows.shape[1] == len(p):
            self._rows[n - 1] = self._ready(p)

    def _merge(self) -> None:
        points = self._kept().copy()
        while True:
            # Greedy independent set in arrival order: a survivor covers all later points within twice the threshold.
            near, kept = np.full(len(points), np.inf), []
            for i in range(len(points)):
                if near[i] > self.two * self.square:
                    kept.append(i)
                    near[i:] = np.minimum(near[i:], self._to(points[i:], points[i]))
            gone = np.setdiff1d(np.arange(len(points)), kept)
            if len(gone):
                break
            self.log.append((self.phase, self.square, len(self.x), 0, self.seen))
            self.phase, self.square = self.phase + 1, self.square * self.two
        old = self.ids, self.x, self.held, self.count
        self.removed = [(old[0][i], old[1][i]) for i in gone]
        self.ids, self.x, self.held, self.count = ([v[i] for i in kept] for v in old)
        self._rows[: len(kept)] = points[kept]
        if self.kind != "points":
            for i in gone:  # the host is the nearest of all survivors
                self._join(int(np.argmin(self._to(points[kept], points[i]))), old[2][i], old[3][i])
        self.log.append((self.phase, self.square, len(self.x), len(gone), self.seen))

    def _nearest(self, block: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(host, key) of the nearest kept point of each ready row."""
        kept = self._kept()
        if self.metric == "angular":
            keys = np.arccos(np.clip(np.round(block @ kept.T, 12), -1, 1))
        else:
            keys = (block[:, None, 0] - kept[None, :, 0]) ** 2
            for c in range(1, block.shape[1]):
                keys += (block[:, None, c] - kept[None, :, c]) ** 2
        host = keys.argmin(1)
        return host, keys[np.arange(len(block)), host]

    def _full(self) -> None:
        """m + 1 points are kept: the first time their least distance becomes the threshold, later it doubles; then they are merged."""
        if self.square is None:
            rows = self._kept()
            self.square = min(float(self._to(rows[i + 1 :], rows[i]).min()) for i in range(len(rows) - 1))
            self.phase = 1
        else:
            self.phase, self.square = self.phase + 1, self.square * self.two
        self._merge()

    def update(self, ids, points) -> Sketch:
        """Feeds points in their order. Distances to the kept points are computed for a block at once and brought up to date as points are kept.

        Before there is a threshold, all points that differ from the kept ones are kept until there are m + 1.
        """
        if not len(ids):
            return self
        points = np.asarray(points, float).reshape(len(ids), -1)
        at = 0
        if not self.x:
            self.seen += 1
            self._keep(int(ids[0]), points[0])
            at = 1
        while at < len(ids):
            # Nearly every point is kept before there is a threshold, so far ones are not looked at yet.
            size = max(64, self.m + 1 - len(self.x)) if self.square is None else max(64, 1_000_000 // max(len(self.x), points.shape[1] // 8))
            block = points[at : at + size]
            ready = self._ready(block)
            host, near = self._nearest(ready)
            done, phase = 0, self.phase
            while done < len(block) and phase == self.phase:
                far = near[done:] > self.two * self.two * (self.square or 0.0)
                stop = done + int(np.argmax(far)) if far.any() else len(block)
                self._join_all(host[done:stop], ids[at + done : at + stop], block[done:stop])
                self.seen += stop - done
                done = stop
                if stop == len(block):
                    break
                self.seen += 1
                self._keep(int(ids[at + stop]), block[stop])
                done += 1
                if len(self.x) == self.m + 1:
                    self._full()
                else:
                    new = self._to(ready[done:], ready[stop])
                    closer = new < near[done:]
                    host[done:][closer], near[done:][closer] = len(self.x) - 1, new[closer]
            at += done
        return self

    def merge(self, other: Sketch) -> Sketch:
        """The sketch of both streams: the larger threshold, the other's kept points (and removed ones) as newcomers; the covering bounds add."""
        if other.square is not None and (self.square is None or other.square > self.square):
            return other.merge(self)
        for pid, p, held, count in zip(other.ids, other.x, other.held, other.count, strict=True):
            before = len(self.x)
            self.update([pid], [p])
            if len(self.x) > before:
                self.held[-1], self.count[-1] = held[: self.k], count
            elif self.kind != "points" and self.x:
                self._join(int(np.argmin(self._to(self._kept(), self._ready(np.asarray(p, float))))), held[1:], count - 1)
        return self

    @property
    def threshold(self) -> float:
        if self.square is None:
            return 0.0
        return float(np.sqrt(self.square) if self.metric == "euclid" else self.square)

    def result(self) -> list[tuple[int, np.ndarray, bool]]:
        """(id, point, filler): the kept points, topped up to k from those removed by the last merge."""
        out = [(i, p, False) for i, p in zip(self.ids, self.x, strict=True)]
        if self.kind == "points" and len(out) < self.k:
            out += [(i, p, True) for i, p in self.removed[: self.k - len(out)]]
        return out


def heavy_matching(b: Block, k: int) -> list[int]:
    """floor(k/2) times the farthest pair of unused points (ties to smaller ids); for odd k the unused point with the smallest id. Memory follows the number of points."""
    n = len(b)
    k = min(k, n)
    if b.metric in PLAIN and b.x.shape[1] <= 4:
        return _matching_by_reach(b, k)
    free = np.ones(n, bool)
    best, partner = np.full(n, -1.0), np.full(n, -1)

    def renew(i: int) -> None:
        key = np.where(free, b.keys(i), -1.0)
        key[: i + 1] = -1.0
        partner[i] = int(np.argmax(key))
        best[i] = key[partner[i]]

    for i in range(n):
        renew(i)
    out: list[int] = []
    for _ in range(k // 2):
        i = int(np.argmax(best))
        j = int(partner[i])
        out += [i, j]
        free[[i, j]] = False
        best[[i, j]] = -1.0
        for x in np.flatnonzero(free & ((partner == i) | (partner == j))):
            renew(int(x))
    if len(out) < k:
        out.append(int(np.argmax(free)))
    return out


def _matching_by_reach(b: Block, k: int) -> list[int]:
    """As ``heavy_matching``, but looks only at points whose distances from the middle allow a pair as far as the best one found."""
    n = len(b)
    free = np.ones(n, bool)
    middle = Block.__new__(Block)
    middle.metric, middle.x = b.metric, np.vstack([b.x.mean(0, keepdims=True), b.x]) if n else b.x
    reach = np.asarray(b.distance(middle.keys(0)[1:])) * (1 + 1e-9) + 1e-9 if n else np.zeros(0)
    order = np.argsort(-reach, kind="stable")
    out: list[int] = []
    for _ in range(k // 2):
        left = order[free[order]]
        far, best, pair = reach[left], -1.0, (n, n)
        for at in range(len(left)):
            least = float(b.distance(best)) if best >= 0 else -1.0
            others = left[at + 1 : np.searchsorted(-far, far[at] - least, "right")]  # those that reach far enough with this one
            if not len(others):
                break
            i = int(left[at])
            key = b.keys_to(i, others)
            top = float(key.max())
            if top >= best:
                j = int(others[key == top].min())
                pair = min(pair if top == best else (n, n), (min(i, j), max(i, j)))
                best = top
        out += pair
        free[list(pair)] = False
    if len(out) < k:
        out.append(int(np.argmax(free)))
    return out


def traversal_with_counts(b: Block, mult, k: int) -> dict[int, int]:
    """Coherent choice of total k: distinct anchors by farthest-first, then replicas of the earliest ones."""
    picks, _, _ = farthest_first(b, k)
    chosen = {int(p): 1 for p in picks}
    left = k - len(chosen)
    for p in picks:
        more = min(left, int(mult[p]) - 1)
        chosen[int(p)] += more
        left -= more
    return chosen


def matching_with_counts(b: Block, mult, k: int) -> dict[int, int]:
    """Coherent choice of total k: the farthest pair of distinct points with copies left, again and again; the last point's copies pair at distance zero.

    A pair stays the farthest until one of its points has no copies left, so it is taken as often at once. Memory follows the number of points.
    """
    left = np.asarray(mult, np.int64).copy()
    chosen: dict[int, int] = {}
    need = min(k, int(left.sum()))
    best, partner = np.full(len(b), -1.0), np.full(len(b), -1)

    def use(i: int, n: int) -> None:
        chosen[i] = chosen.get(i, 0) + n
        left[i] -= n

    def renew(i: int) -> None:
        key = np.where(left > 0, b.keys(i), -1.0)
        key[: i + 1] = -1.0
        partner[i] = int(np.argmax(key))
        best[i] = key[partner[i]] if left[i] > 0 else -1.0

    for i in range(len(b)):
        renew(i)
    while need >= 2:
        i = int(np.argmax(best))
        j = int(partner[i])
        if best[i] < 0:  # one point has all the copies that are left
            use(int(np.flatnonzero(left > 0)[0]), need)
            need = 0
            break
        n = min(int(left[i]), int(left[j]), need // 2)
        use(i, n)
        use(j, n)
        need -= 2 * n
        for x in (i, j):
            if left[x] == 0:
                best[x] = -1.0
                for y in np.flatnonzero((left > 0) & (partner == x)):
                    renew(int(y))
    if need:
        use(int(np.flatnonzero(left > 0)[0]), 1)
    return chosen


# Measures of a set, from its matrix of distances.


def edge(d: np.ndarray) -> float:
    n = len(d)
    return float(d[np.triu_indices(n, 1)].min()) if n > 1 else 0.0


def clique(d: np.ndarray) -> float:
    return float(d[np.triu_indices(len(d), 1)].sum())


def star(d: np.ndarray) -> float:
    return float(d.sum(1).min()) if len(d) else 0.0


def tree(d: np.ndarray) -> float:
    """Prim's algorithm."""
    n = len(d)
    near, done, total = d[0].copy() if n else np.zeros(0), np.zeros(n, bool), 0.0
    if n:
        done[0] = True
    for _ in range(n - 1):
        at = int(np.argmin(np.where(done, np.inf, near)))
        total += float(near[at])
        done[at] = True
        near = np.minimum(near, d[at])
    return total


def bipartition(d: np.ndarray, exact_upto: int = 16) -> tuple[float, bool]:
    """(cheapest cut with floor(k/2) on one side, whether it is exact): all halves, or swaps from the identity order (an upper bound)."""
    n = len(d)
    half = n // 2
    if n <= exact_upto:
        best = np.inf
        for side in combinations(range(n), half):
            inside = np.zeros(n, bool)
            inside[list(side)] = True
            best = min(best, float(d[inside][:, ~inside].sum()))
        return (0.0 if n < 2 else best), True
    inside = np.arange(n) < half
    while True:
        cost = d[inside][:, ~inside].sum()
        a, z = np.flatnonzero(inside), np.flatnonzero(~inside)
        i, j = np.unravel_index(np.argmin([[_cut_after(d, inside, x, y) for y in z] for x in a]), (len(a), len(z)))
        after = _cut_after(d, inside, a[i], z[j])
        if after >= cost - 1e-12:
            return float(cost), False
        inside[a[i]], inside[z[j]] = False, True


def _cut_after(d: np.ndarray, inside: np.ndarray, x: int, y: int) -> float:
    s = inside.copy()
    s[x], s[y] = False, True
    return float(d[s][:, ~s].sum())


def cycle(d: np.ndarray, exact_upto: int = 13) -> tuple[float, bool]:
    """(shortest tour, whether it is exact): a table over subsets, or a tree tour improved by reversals (at most twice the shortest)."""
    n = len(d)
    if n < 2:
        return 0.0, True
    if n <= 3:
        return float(d[np.triu_indices(n, 1)].sum()) if n == 3 else 2 * float(d[0, 1]), True
    if n <= exact_upto:
        full = 1 << (n - 1)
        best = np.full((full, n - 1), np.inf)
        for j in range(n - 1):
            best[1 << j, j] = d[0, j + 1]
        for s in range(1, full):
            for j in range(n - 1):
                if s >> j & 1 and s != 1 << j:
                    best[s, j] = min(best[s ^ (1 << j), i] + d[i + 1, j + 1] for i in range(n - 1) if s >> i & 1 and i != j)
        return float(min(best[full - 1, j] + d[j + 1, 0] for j in range(n - 1))), True
    parent, near, done, children = np.zeros(n, int), d[0].copy(), np.zeros(n, bool), [[] for _ in range(n)]
    done[0] = True
    for _ in range(n - 1):
        at = int(np.argmin(np.where(done, np.inf, near)))
        children[parent[at]].append(at)
        done[at] = True
        closer = d[at] < near
        parent[closer & ~done], near = at, np.minimum(near, d[at])
    tour, todo = [], [0]
    while todo:
        x = todo.pop()
        tour.append(x)
        todo += reversed(children[x])
    improved = True
    while improved:
        improved = False
        for i in range(n - 1):
            for j in range(i + 2, n - (i == 0)):
                a, b, c, e = tour[i], tour[i + 1], tour[j], tour[(j + 1) % n]
                if d[a, c] + d[b, e] < d[a, b] + d[c, e] - 1e-12:
                    tour[i + 1 : j + 1] = reversed(tour[i + 1 : j + 1])
                    improved = True
    return float(sum(d[tour[i], tour[(i + 1) % n]] for i in range(n))), False


def value(d: np.ndarray, objective: str) -> float:
    found = {"edge": edge, "clique": clique, "star": star, "tree": tree, "bipartition": bipartition, "cycle": cycle}[objective](d)
    return found[0] if isinstance(found, tuple) else found


def brute_force(b: Block, k: int, objective: str) -> tuple[list[int], float]:
    """The best k-subset, the first in the order of ids among equal ones."""
    k = min(k, len(b))
    if k == 3 and b.metric in PLAIN and b.x.shape[1] <= 4:
        return _best_of_boxes(b, objective)
    d = b.matrix()
    if k == 3:
        return _best_of_three(d, objective)
    best, at = -1.0, ()
    for some in combinations(range(len(b)), k):
        v = round(value(d[np.ix_(some, some)], objective), 9)
        if v > best:
            best, at = v, some
    return list(at), best


def _best_of_three(d: np.ndarray, objective: str) -> tuple[list[int], float]:
    """All triples, a matrix of them for each first point."""
    best, at = -1.0, (0, 1, 2)
    for i in range(len(d) - 2):
        ab, ac, bc = d[i, i + 1 :, None], d[i, None, i + 1 :], d[i + 1 :, i + 1 :]
        v = of_three(ab, ac, bc, objective)
        v = np.round(np.where(np.triu(np.ones_like(bc), 1) > 0, v, -1.0), 9)
        j, c = np.unravel_index(np.argmax(v), v.shape)
        if v[j, c] > best:
            best, at = float(v[j, c]), (i, i + 1 + int(j), i + 1 + int(c))
    return list(at), best


def of_three(ab, ac, bc, objective: str):
    """An objective of three points, which grows with each of their distances."""
    if objective == "edge":
        return np.minimum(np.minimum(ab, ac), bc)
    if objective == "tree":
        return ab + ac + bc - np.maximum(np.maximum(ab, ac), bc)
    if objective in ("star", "bipartition"):
        return np.minimum(np.minimum(ab + ac, ab + bc), ac + bc)
    return ab + ac + bc


#: Triples of boxes that are looked at in one step.
TRIPLES = 1 << 18


def _best_of_boxes(b: Block, objective: str) -> tuple[list[int], float]:
    """As ``_best_of_three`` without a matrix: triples of boxes, halved again and again, as long as their largest distances allow the best value found.

    Three copies of a position are as good as all of them. Boxes are the nodes of a tree over the positions; each bound holds for all triples of
    their points, and what is left at the end are points, so the result is the optimum, the first one in the order of ids.
    """
    place = np.unique(b.x, axis=0, return_inverse=True)[1].ravel()
    order = np.lexsort((np.arange(len(b)), place))
    start = np.flatnonzero(np.diff(place[order], prepend=-1))
    turn = np.arange(len(b)) - np.repeat(start, np.diff(np.append(start, len(b))))
    used = np.sort(order[turn < 3])
    x = b.x[used]
    # The tree: each node is a run of ``row``, halved at the middle of its longest side. A leaf is one point.
    row, first, last, child, todo = np.arange(len(x)), [0], [len(x)], [-1], [0]
    while todo:
        node = todo.pop()
        lo, hi = first[node], last[node]
        if hi - lo < 2:
            continue
        own = row[lo:hi]
        side = int(np.argmax(np.ptp(x[own], axis=0)))
        half = (hi - lo) // 2
        row[lo:hi] = own[np.argpartition(x[own, side], half)]
        child[node] = len(first)
        first += [lo, lo + half]
        last += [lo + half, hi]
        child += [-1, -1]
        todo += [child[node], child[node] + 1]
    first, last, child = np.array(first), np.array(last), np.array(child)
    low, high = np.empty((len(first), x.shape[1])), np.empty((len(first), x.shape[1]))
    for node in range(len(first) - 1, -1, -1):  # children have higher numbers
        if child[node] < 0:
            low[node] = high[node] = x[row[first[node]]]
        else:
            c = child[node]
            low[node], high[node] = np.minimum(low[c], low[c + 1]), np.maximum(high[c], high[c + 1])
    some = row[first]

    def reach(p: np.ndarray, q: np.ndarray) -> np.ndarray:
        return np.asarray(b.distance(b._gap_keys(np.maximum(high[p] - low[q], high[q] - low[p]))))

    def distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
        return np.asarray(b.distance(b._gap_keys(x[p] - x[q])))

    best, at = -1.0, (0, 1, 2)
    seed = farthest_first(b, 16)[0]
    for three in combinations(np.sort(seed).tolist(), 3):
        best = max(best, round(value(b.take(three).matrix(), objective), 9))
    best = np.nextafter(best, -1.0)  # found again below, with its first triple
    slack = 1e-9 * (1 + abs(float(best)))
    stack = [np.zeros((1, 3), np.int64)]
    while stack:
        t = stack.pop()
        if len(t) > TRIPLES:
            stack.append(t[:-TRIPLES])
            t = t[-TRIPLES:]
        bound = of_three(reach(t[:, 0], t[:, 1]), reach(t[:, 0], t[:, 2]), reach(t[:, 1], t[:, 2]), objective)
        t, bound = t[bound >= best - slack], bound[bound >= best - slack]
        size = last[t] - first[t]
        whole = (size == 1).all(1)
        if whole.any():
            p = np.sort(some[t[whole]], axis=1)
            v = np.round(of_three(distance(p[:, 0], p[:, 1]), distance(p[:, 0], p[:, 2]), distance(p[:, 1], p[:, 2]), objective), 9)
            top = float(v.max())
            if top >= best:
                p = used[p[v == top]]
                found = tuple(p[np.lexsort((p[:, 2], p[:, 1], p[:, 0]))[0]].tolist())
                at, best = (min(at, found) if top == best else found), top
        t, bound, size = t[~whole], bound[~whole], size[~whole]
        if not len(t):
            continue
        # A point of each box: a value that the best one reaches at least.
        p = some[t[(t[:, 0] != t[:, 1]) & (t[:, 0] != t[:, 2]) & (t[:, 1] != t[:, 2])]]
        if len(p):
            top = float(np.round(of_three(distance(p[:, 0], p[:, 1]), distance(p[:, 0], p[:, 2]), distance(p[:, 1], p[:, 2]), objective), 9).max())
            if top > best:
                best = np.nextafter(top, -1.0)
        # The largest box is halved; equal boxes are halved together, as their points are in no order.
        order_ = np.argsort(bound, kind="stable")
        t, size = t[order_], size[order_]
        n = np.take_along_axis(t, np.argmax(size, axis=1)[:, None], 1)[:, 0]
        same = (t == n[:, None]).sum(1)
        rest = np.where(t == n[:, None], -1, t)
        a, z = child[n], child[n] + 1
        made = []
        one = same == 1
        others = np.sort(rest[one], axis=1)[:, 1:]
        made += [np.column_stack([others, c[one]]) for c in (a, z)]
        two = same == 2
        other = rest[two].max(1)
        made += [np.column_stack([other, p[two], q[two]]) for p, q in ((a, a), (a, z), (z, z))]
        three = same == 3
        made += [np.column_stack([p[three], q[three], r[three]]) for p, q, r in ((a, a, a), (a, a, z), (a, z, z), (z, z, z))]
        t = np.concatenate(made)
        # A box holds as many points as a triple takes from it.
        times = (t[:, :, None] == t[:, None, :]).sum(2)
        t = t[(last[t] - first[t] >= times).all(1)]
        if len(t):
            stack.append(t)
    return list(at), best


def local_search(b: Block, k: int) -> list[int]:
    """The best swap while it raises the sum of distances, from the heavy matching. The sum grows strictly, so it ends. Memory: k rows of distances."""
    inside = {i: np.asarray(b.distance(b.keys(i))) for i in heavy_matching(b, k)}
    while 0 < len(inside) < len(b):
        a = sorted(inside)
        rows = np.stack([inside[i] for i in a])
        to = rows.sum(0)
        gain = to[None, :] - to[a][:, None] - rows
        gain[:, a] = -np.inf
        i, z = np.unravel_index(np.argmax(gain), gain.shape)
        if gain[i, z] <= 1e-9:
            break
        del inside[a[i]]
        inside[int(z)] = np.asarray(b.distance(b.keys(int(z))))
    return sorted(inside)
