"""In-task search structures over one block of points: the batch-built cover tree and its rivals.

All have ``query(q, eps)`` -> (query position, point position, distance) of the pairs at most eps apart.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np

from .metrics import Metric, slack

STRICT, COMPACT = "strict", "compact"


#: Pairs that an answer is meant to hold at most.
MOST_PAIRS = 1 << 21
#: Hubs of more points than the first are looked at by a sample of the second before they are split.
LARGE_HUB, HUB_SAMPLE = 4096, 1024


class Pace:
    """How many queries to ask at a time, from how many pairs the last ones had: an answer holds few more than ``MOST_PAIRS``,
    however dense the points lie."""

    def __init__(self, most: int = 4096, first: int = 512):
        self.most, self.rows = most, min(first, most)

    def strips(self, n: int, ask) -> Iterator[tuple[int, tuple]]:
        """(first row, answer) of ``ask(lo, hi)`` over n rows."""
        at = 0
        while at < n:
            hi = min(n, at + self.rows)
            found = ask(at, hi)
            yield at, found
            self.rows = max(1, min(self.most, 4 * self.rows, (hi - at) * MOST_PAIRS // max(1, len(found[0]))))
            at = hi


def _ceil_log2(r: float) -> int:
    return int(np.ceil(np.log2(r))) if r > 0 else -1074


class CoverTree:
    """Built level by level: a hub is split by farthest-first centres until the farthest point left lies within the threshold.

    ``threshold``: "radius" splits to half the hub's radius, "level" to 2**(level - 1) with level = ceil(log2(radius)).
    ``levels``: "compact" derives a child's level from its radius, "strict" goes one level down a step, keeping self-children.
    ``leaf_size``: hubs of at most so many points become bucket leaves, as do hubs of equal points and hubs that
    ``bailout`` stops: those with more centres than that part of their points. A large hub is not split to find that out where a sample
    tells how many others lie within the threshold of a point in the mean, d, and log(1 + d) / d, the part that as many random links would
    leave as centres, is beyond ``bailout`` (this decides on costs only). ``node_bound``: by which bound queries enter a
    vertex if they name none.
    """

    def __init__(self, x: np.ndarray, metric: Metric, leaf_size: int = 32, threshold: str = "radius", levels: str = COMPACT, bailout: float = 0.25, triangle_skip: bool = True, node_bound: str = "radius"):
        if node_bound == "level" and levels == STRICT:
            raise ValueError("strict levels do not bound radii")
        self.x, self.metric, self.leaf_size, self.threshold, self.levels, self.bailout, self.skip, self.node_bound = x, metric, leaf_size, threshold, levels, bailout, triangle_skip, node_bound
        self.centre: list[int] = []
        self.radius: list[float] = []
        self.level: list[int] = []
        self.parent: list[int] = []
        self.children: list[list[int]] = []
        self.members: list[np.ndarray | None] = []
        self.bailed = 0
        if len(x):
            self._build()

    def _node(self, centre: int, radius: float, level: int, parent: int) -> int:
        self.centre.append(centre)
        self.radius.append(radius)
        self.level.append(level)
        self.parent.append(parent)
        self.children.append([])
        self.members.append(None)
        if parent >= 0:
            self.children[parent].append(len(self.centre) - 1)
        return len(self.centre) - 1

    def _build(self) -> None:
        everyone = np.arange(len(self.x))
        d = self.metric.row(self.x, self.x[0])
        r = float(d.max())
        frontier = [(self._node(0, r, _ceil_log2(r), -1), everyone, d)]
        while frontier:
            later = []
            for node, members, dist in frontier:
                r = self.radius[node]
                if r == 0 or len(members) <= self.leaf_size:
                    self.members[node] = members
                    continue
                parts = self._split(node, members, dist)
                if parts is None:
                    self.bailed += 1
                    self.members[node] = members
                    continue
                for centre, own, near in parts:
                    radius = float(near.max())
                    level = self.level[node] - 1 if self.levels == STRICT else _ceil_log2(radius)
                    later.append((self._node(centre, radius, level, node), own, near))
            frontier = later

    def _split(self, node: int, members: np.ndarray, dist: np.ndarray):
        limit = self.radius[node] / 2 if self.threshold == "radius" else 2.0 ** (self.level[node] - 1)
        if len(members) > max(LARGE_HUB, self.leaf_size) and self.bailout < 1:
            some = self.x[np.random.default_rng(0).choice(members, HUB_SAMPLE, replace=False)]
            close = len(self.metric.within(some, some, limit)[0]) - HUB_SAMPLE
            degree = max(1e-9, close / (HUB_SAMPLE * (HUB_SAMPLE - 1)) * (len(members) - 1))
            if np.log1p(degree) / degree > self.bailout:
                return None
        centres, near, owner = [self.centre[node]], dist.copy(), np.zeros(len(members), int)
        between = [0.0]  # of the newest centre to the earlier ones
        while True:
            far = int(near.argmax())
            if near[far] <= limit:
                break
            if len(centres) + 1 > max(2, self.bailout * len(members)) and len(members) > self.leaf_size and self.bailout < 1:
                return None
            new = members[far]
            if self.skip:
                between = self.metric.row(self.x[np.array(centres)], self.x[new])
                ask = np.flatnonzero(near > between[owner] / 2)  # nearer points cannot change their centre
            else:
                ask = np.arange(len(members))
            d = self.metric.row(self.x[members[ask]], self.x[new])
            moved = d < near[ask]
            near[ask[moved]] = d[moved]
            owner[ask[moved]] = len(centres)
            centres.append(int(new))
        order = np.argsort(owner, kind="stable")
        ends = np.cumsum(np.bincount(owner, minlength=len(centres)))
        return [(c, members[o], near[o]) for c, o in zip(centres, np.split(order, ends[:-1])) if len(o)]

    def bound(self, node: int, by: str) -> float:
        return self.radius[node] if by == "radius" else (2.0 ** self.level[node] if self.radius[node] > 0 else 0.0)

    def query(self, q: np.ndarray, eps: float, bound: str | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        bound = bound or self.node_bound
        found: list[tuple] = []
        work = [(0, np.arange(len(q)))] if len(self.centre) and len(q) else []
        while work:
            node, active = work.pop()
            d = self.metric.row(q[active], self.x[self.centre[node]])
            active = active[d <= slack(self.bound(node, bound) + eps)]
            if not len(active):
                continue
            if self.members[node] is not None:
                i, j, dist = self.metric.within(q[active], self.x[self.members[node]], eps)
                found.append((active[i], self.members[node][j], dist))
            else:
                work += [(c, active) for c in self.children[node]]
        return _joined(found)

    def numbered(self) -> tuple[np.ndarray, np.ndarray]:
        """The points through the leaves from left to right, and of each vertex the place of its last one."""
        leaves, last, held = [np.empty(0, int)], np.empty(len(self.centre), int), 0
        stack = [(0, False)] if len(self.centre) else []
        while stack:
            node, done = stack.pop()
            if self.members[node] is not None:
                leaves.append(self.members[node])
                held += len(leaves[-1])
                last[node] = held - 1
            elif done:
                last[node] = held - 1
            else:
                stack += [(node, True), *((c, False) for c in reversed(self.children[node]))]
        return np.concatenate(leaves), last

    def self_query(self, eps: float, rows: int = 4096) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Each pair of the tree's own points once, in blocks of at most ``rows`` queries. Points are numbered through the leaves from left to
        right, and a point enters only vertices with numbers beyond its own: about half of what ``query`` measures."""
        if not len(self.centre):
            return
        order, last = self.numbered()
        place = np.empty(len(order), int)
        place[order] = np.arange(len(order))

        def ask(at: int, end: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            found, work = [], [(0, order[at:end])]
            while work:
                node, active = work.pop()
                active = active[place[active] < last[node]]
                if not len(active):
                    continue
                d = self.metric.row(self.x[active], self.x[self.centre[node]])
                active = active[d <= slack(self.bound(node, self.node_bound) + eps)]
                if not len(active):
                    continue
                if self.members[node] is None:
                    work += [(c, active) for c in self.children[node]]
                    continue
                own, first = self.members[node], last[node] + 1 - len(self.members[node])
                guests = int(np.searchsorted(place[active], first))  # those of earlier leaves, then the leaf's own, each with what follows
                step = min(2048, max(256, len(own) // 16))
                for block, of in ((active[:guests], own), *((active[k : k + step], own[place[active[k]] - first :]) for k in range(guests, len(active), step))):
                    i, j, dist = self.metric.within(self.x[block], self.x[of], eps)
                    i, j = block[i], of[j]
                    keep = place[i] < place[j]
                    found.append((i[keep], j[keep], dist[keep]))
            return _joined(found)

        for _, found in Pace(rows).strips(len(order), ask):
            yield found

    def counts(self, q: np.ndarray, eps: float) -> np.ndarray:
        """How many points lie within eps of each query; whole vertices inside the ball are not opened."""
        out, size = np.zeros(len(q), np.int64), self.sizes()
        work = [(0, np.arange(len(q)))] if len(self.centre) and len(q) else []
        while work:
            node, active = work.pop()
            d = self.metric.row(q[active], self.x[self.centre[node]])
            inside = slack(d + self.radius[node]) <= eps
            out[active[inside]] += size[node]
            active = active[~inside & (d <= slack(self.radius[node] + eps))]
            if not len(active):
                continue
            if self.members[node] is not None:
                i, _, _ = self.metric.within(q[active], self.x[self.members[node]], eps)
                np.add.at(out, active[i], 1)
            else:
                work += [(c, active) for c in self.children[node]]
        return out

    def sizes(self) -> np.ndarray:
        out = np.array([len(m) if m is not None else 0 for m in self.members], np.int64)
        for node in range(len(out) - 1, 0, -1):  # children come after their parents
            out[self.parent[node]] += out[node]
        return out

    def under(self, node: int) -> np.ndarray:
        found, work = [], [node]
        while work:
            n = work.pop()
            if self.members[n] is not None:
                found.append(self.members[n])
            work += self.children[n]
        return np.concatenate(found)

    def rows(self, pids: np.ndarray) -> list[tuple]:
        """(node, parent, level, pid, radius, size, is_leaf, members), the members being the pids of a leaf."""
        size = self.sizes()
        return [
            (n, self.parent[n], self.level[n], int(pids[self.centre[n]]), self.radius[n], int(size[n]), m is not None, None if m is None else [int(v) for v in pids[m]])
            for n, m in enumerate(self.members)
        ]

    @classmethod
    def of_rows(cls, rows: Iterable[tuple], pids: np.ndarray, x: np.ndarray, metric: Metric, **options) -> CoverTree:
        """The tree that ``rows`` tell of, over the points it was built on, in any order; no distance is measured."""
        tree = cls(x[:0], metric, **options)
        tree.x = x
        order = np.argsort(pids, kind="stable")
        ranked = pids[order]

        def places(of) -> np.ndarray:
            at = np.minimum(np.searchsorted(ranked, of), max(len(ranked) - 1, 0))
            if not len(ranked) or (ranked[at] != of).any():
                raise ValueError("the tree has points that are not given")
            return order[at]

        held = 0
        for n, (node, parent, level, pid, radius, _, is_leaf, members) in enumerate(sorted(rows, key=lambda r: r[0])):
            if node != n:
                raise ValueError("the tree lacks vertices")
            tree._node(int(places(np.array([pid]))[0]), radius, level, parent)
            if is_leaf:
                tree.members[n] = places(np.array(members, np.int64))
                held += len(members)
        if held != len(x):
            raise ValueError("the tree lacks points")
        return tree

    def depth(self) -> int:
        deep = [0] * len(self.centre)
        for n in range(1, len(deep)):
            deep[n] = deep[self.parent[n]] + 1
        return max(deep, default=-1) + 1

    def violations(self, sibling_only: bool = True) -> dict[str, int]:
        """Breaches of the invariants, by checking all of them: partition, nesting, covering, sibling separation, halving. Otherwise
        also ``level_separating``: pairs of points of one level l at most 2**l apart, which this construction does not rule out."""
        bad = dict.fromkeys(("partition", "nesting", "covering", "separating", "shrinking"), 0)
        if not sibling_only:
            bad["level_separating"] = 0
        if not len(self.centre):
            return bad
        if not sibling_only:
            level, centre = np.array(self.level), np.array(self.centre)
            for at in np.unique(level[np.array(self.radius) > 0]):
                x = self.x[np.unique(centre[level == at])]
                for k in range(len(x) - 1):
                    bad["level_separating"] += int((self.metric.to(x[k + 1 :], x[k]) <= 2.0**at).sum())
        bad["nesting"] = sum(bool(kids) and self.centre[n] not in [self.centre[k] for k in kids] for n, kids in enumerate(self.children))
        leaves = np.concatenate([m for m in self.members if m is not None])
        bad["partition"] = int(len(leaves) != len(self.x)) + int(len(np.unique(leaves)) != len(leaves))
        for n in range(len(self.centre)):
            bad["covering"] += int((self.metric.to(self.x[self.under(n)], self.x[self.centre[n]]) > slack(self.radius[n])).sum())
            kids = self.children[n]
            limit = self.radius[n] / 2 if self.threshold == "radius" else 2.0 ** (self.level[n] - 1)
            for i, a in enumerate(kids):
                bad["shrinking"] += int(self.radius[a] > slack(limit))
                for b in kids[i + 1 :]:
                    bad["separating"] += int(self.metric.to(self.x[[self.centre[a]]], self.x[self.centre[b]])[0] <= limit)
        return bad


def _joined(found: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    if not found:
        return np.empty(0, int), np.empty(0, int), np.empty(0)
    return tuple(np.concatenate(c) for c in zip(*found))


class _Plain:
    """Self queries of structures that save nothing there."""

    def self_query(self, eps: float, rows: int = 4096) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for at, (i, j, d) in Pace(rows).strips(len(self.x), lambda lo, hi: self.query(self.x[lo:hi], eps)):
            keep = i + at < j
            yield i[keep] + at, j[keep], d[keep]


class Scan(_Plain):
    """No structure: every query meets every point."""

    def __init__(self, x: np.ndarray, metric: Metric, **_):
        self.x, self.metric = x, metric

    def self_query(self, eps: float, rows: int = 2048) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Each block of rows meets itself and what follows."""
        for at, (i, j, d) in Pace(rows).strips(len(self.x), lambda lo, hi: self.metric.within(self.x[lo:hi], self.x[lo:], eps)):
            keep = i < j
            yield i[keep] + at, j[keep] + at, d[keep]

    def query(self, q: np.ndarray, eps: float):
        return _joined([(i + k, j, d) for k in range(0, len(q), 2048) for i, j, d in [self.metric.within(q[k : k + 2048], self.x, eps)]])


class SortedScan(_Plain):
    """Points in order of their projection on ``axis``, of length 1 (their own first principal component by default): a query meets
    the window of those at most eps from its own. Euclidean only."""

    def __init__(self, x: np.ndarray, metric: Metric, axis: np.ndarray | None = None, mean: np.ndarray | float = 0.0, **_):
        if axis is None and len(x):
            mean = x.mean(0)
            axis = np.linalg.eigh((x - mean).T @ (x - mean))[1][:, -1]
        self.metric, self.axis, self.mean = metric, 1.0 if axis is None else axis, mean
        at = self.along(x)
        self.order = np.argsort(at, kind="stable")
        self.x, self.at = x[self.order], at[self.order]

    def along(self, x: np.ndarray) -> np.ndarray:
        return ((x - self.mean) * self.axis).sum(1)

    def _windows(self, x: np.ndarray, at: np.ndarray, eps: float, first: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pairs, by places, of points in order of projection with those in their windows; from place ``first`` on where they are own."""
        found = []
        for k in range(0, len(x), 256):
            part = at[k : k + 256]
            room = eps + 1e-9 * (np.abs(part).max() + eps) + 1e-12
            lo = np.searchsorted(self.at, part[0] - room) if first is None else first + k
            i, j, d = self.metric.within(x[k : k + 256], self.x[lo : np.searchsorted(self.at, part[-1] + room, "right")], eps)
            found.append((i + k, j + lo, d))
        return _joined(found)

    def self_query(self, eps: float, rows: int = 4096) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for at, (i, j, d) in Pace(rows).strips(len(self.x), lambda lo, hi: self._windows(self.x[lo:hi], self.at[lo:hi], eps, lo)):
            keep = i + at < j
            yield self.order[i[keep] + at], self.order[j[keep]], d[keep]

    def query(self, q: np.ndarray, eps: float):
        at = self.along(q) if len(q) and len(self.x) else np.empty(0)
        order = np.argsort(at, kind="stable")
        i, j, d = self._windows(q[order], at[order], eps)
        return order[i], self.order[j], d


class _Binary(_Plain):
    """A binary tree of index arrays; subclasses say how to split and which queries may enter a side."""

    def __init__(self, x: np.ndarray, metric: Metric, leaf_size: int = 32, **_):
        self.x, self.metric, self.leaf_size = x, metric, leaf_size
        self.nodes: list[tuple] = []
        work = [np.arange(len(x))] if len(x) else []
        # breadth first, so a node's sides lie at known places
        while work:
            own = work.pop(0)
            cut = self.cut(own) if len(own) > leaf_size else None
            if cut is None:
                self.nodes.append((own, None, 0))
            else:
                key, sides = cut
                self.nodes.append((None, key, len(self.nodes) + len(work) + 1))
                work += sides

    def query(self, q: np.ndarray, eps: float):
        found, work = [], [(0, np.arange(len(q)))] if self.nodes and len(q) else []
        while work:
            node, active = work.pop()
            own, key, at = self.nodes[node]
            if own is not None:
                i, j, d = self.metric.within(q[active], self.x[own], eps)
                found.append((active[i], own[j], d))
                continue
            for side, may in enumerate(self.enter(key, q[active], eps)):
                if may.any():
                    work.append((at + side, active[may]))
        return _joined(found)


class KdTree(_Binary):
    """Median splits of the widest dimension; Euclidean (or any larger) distances only."""

    def cut(self, own):
        x = self.x[own]
        dim = int(np.ptp(x, axis=0).argmax())
        at = float(np.median(x[:, dim]))
        low = x[:, dim] <= at
        return None if low.all() or not low.any() else ((dim, at), [own[low], own[~low]])

    def enter(self, key, q, eps):
        dim, at = key
        return q[:, dim] <= slack(at + eps), q[:, dim] >= at - eps - 1e-9 * (abs(at) + eps) - 1e-12


class BallTree(_Binary):
    """Two far apart members as poles; each side is kept with its covering ball."""

    def cut(self, own):
        a = own[self.metric.row(self.x[own], self.x[own[0]]).argmax()]
        da = self.metric.row(self.x[own], self.x[a])
        b = own[da.argmax()]
        db = self.metric.row(self.x[own], self.x[b])
        low = da <= db
        if low.all():
            return None
        return ((int(a), float(da[low].max()), int(b), float(db[~low].max())), [own[low], own[~low]])

    def enter(self, key, q, eps):
        a, ra, b, rb = key
        return self.metric.row(q, self.x[a]) <= slack(ra + eps), self.metric.row(q, self.x[b]) <= slack(rb + eps)


class VpTree(_Binary):
    """Inside and outside of the median ball around a vantage point."""

    def cut(self, own):
        p = int(own[0])
        d = self.metric.row(self.x[own], self.x[p])
        mu = float(np.median(d))
        low = d <= mu
        return None if low.all() else ((p, mu), [own[low], own[~low]])

    def enter(self, key, q, eps):
        p, mu = key
        d = self.metric.row(q, self.x[p])
        return d <= slack(mu + eps), slack(d + eps) >= mu


INDEXES = {"cover": CoverTree, "scan": Scan, "sorted": SortedScan, "kd": KdTree, "ball": BallTree, "vp": VpTree}
