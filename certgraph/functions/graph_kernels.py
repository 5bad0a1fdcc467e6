"""Graph routines that run inside one task, on graphs of certificate size. No Spark here.

Graphs are adjacency mappings from each vertex to the set of its neighbours: a dict, or a `PackedGraph`, which holds arrays and
makes the set of a vertex when a search first asks for it.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable, Container, Iterable, Iterator, Mapping
from itertools import combinations

import numpy as np

Graph = Mapping[int, set[int]]


class PackedGraph(Mapping):
    """An adjacency in three arrays (16 bytes for each edge end and vertex); only sets in use are kept as Python objects."""

    #: Vertices whose neighbour sets are held at a time.
    MOST_SETS = 200_000

    def __init__(self, u: np.ndarray, v: np.ndarray, vertices: np.ndarray):
        self.ids = np.unique(np.concatenate([u, v, vertices]).astype(np.int64))
        a, b = np.concatenate([u, v]), np.concatenate([v, u])
        order = np.argsort(a, kind="stable")
        self.ends = b[order].astype(np.int64)
        self.starts = np.searchsorted(a[order], np.append(self.ids, self.ids[-1] + 1) if len(self.ids) else np.zeros(1))
        self._sets: dict[int, set[int]] = {}

    @staticmethod
    def bytes_of(edges: int, vertices: int) -> int:
        return 16 * (edges + vertices)

    def __getitem__(self, x: int) -> set[int]:
        found = self._sets.get(x)
        if found is None:
            i = int(np.searchsorted(self.ids, x))
            if i == len(self.ids) or self.ids[i] != x:
                raise KeyError(x)
            if len(self._sets) >= self.MOST_SETS:
                self._sets.clear()
            found = self._sets[x] = set(self.ends[self.starts[i] : self.starts[i + 1]].tolist())
        return found

    def __iter__(self) -> Iterator[int]:
        return iter(self.ids.tolist())

    def __len__(self) -> int:
        return len(self.ids)

    def __getstate__(self):
        return {**self.__dict__, "_sets": {}}


def graph_of(edges: Iterable[tuple[int, int]], vertices: Iterable[int] = ()) -> dict[int, set[int]]:
    g: dict[int, set[int]] = {v: set() for v in vertices}
    for u, v in edges:
        if u != v:
            g.setdefault(u, set()).add(v)
            g.setdefault(v, set()).add(u)
    return g


class DisjointSets:
    """Disjoint sets with path compression and union by rank; `parity` tells on which side of its root an element is."""

    def __init__(self):
        self.parent: dict[int, int] = {}
        self.rank: dict[int, int] = {}
        self.parity: dict[int, int] = {}
        self.steps = 0

    def find(self, x: int) -> int:
        if x not in self.parent:
            self.parent[x], self.rank[x], self.parity[x] = x, 0, 0
            return x
        path = []
        while self.parent[x] != x:
            path.append(x)
            x = self.parent[x]
            self.steps += 1
        side = 0
        for y in reversed(path):
            side ^= self.parity[y]
            self.parity[y], self.parent[y] = side, x
        return x

    def join(self, a: int, b: int, across: int = 1) -> bool:
        """False if both were in one set; `across` tells whether the ends are on different sides."""
        x, y = self.find(a), self.find(b)
        if x == y:
            return False
        side = self.parity[a] ^ self.parity[b] ^ across
        if self.rank[x] < self.rank[y]:
            x, y = y, x
        self.parent[y], self.parity[y] = x, side
        self.rank[x] += self.rank[x] == self.rank[y]
        return True


def kept_edges(edges: Iterable[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Of (seq, u, v) in the given order those that join two components so far."""
    sets = DisjointSets()
    return [e for e in edges if sets.join(e[1], e[2])]


class ForestFold:
    """The kept edges of a stream that comes in chunks of arrays, in order of seq; holds a few words for each vertex.

    Ends that a chunk finds in one set already are dropped all at once; only the others are joined one by one. `parity` tells
    on which side of its root a vertex is, and `odd` holds the first edge that closed an odd cycle.
    """

    def __init__(self, dense: int | None = None):
        """`dense` says that vertices are 0 ... dense - 1, which need no dictionary."""
        self.dense = dense is not None
        self.ids, self.slots = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.up, self.side = np.arange(dense or 0), np.zeros(dense or 0, np.int8)
        self.odd: tuple[int, int, int] | None = None

    @property
    def words(self) -> int:
        """Words held for the vertices met so far."""
        return 2 * len(self.ids) + 2 * len(self.up)

    def _slots(self, x: np.ndarray) -> np.ndarray:
        if self.dense:
            return x
        new = np.setdiff1d(x, self.ids)
        if len(new):
            at = np.searchsorted(self.ids, new)
            n = len(self.up)
            self.ids = np.insert(self.ids, at, new)
            self.slots = np.insert(self.slots, at, np.arange(n, n + len(new)))
            self.up = np.append(self.up, np.arange(n, n + len(new)))
            self.side = np.append(self.side, np.zeros(len(new), np.int8))
        return self.slots[np.searchsorted(self.ids, x)]

    def _roots(self, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        r, side = self.up[s], self.side[s].copy()
        while True:
            up = self.up[r]
            going = up != r
            if not going.any():
                break
            side[going] ^= self.side[r[going]]
            r = up
        self.up[s], self.side[s] = r, side
        return r, side

    def offer(self, seq: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Which edges of the chunk are kept, as a mask."""
        su, sv = self._slots(u), self._slots(v)
        (ru, pu), (rv, pv) = self._roots(su), self._roots(sv)
        keep = np.zeros(len(u), dtype=bool)
        sets = DisjointSets()
        for i in np.flatnonzero((ru != rv) | (pu == pv)).tolist():
            a, b, across = int(ru[i]), int(rv[i]), 1 ^ int(pu[i]) ^ int(pv[i])
            if a != b and sets.join(a, b, across):
                keep[i] = True
            elif self.odd is None and (0 if a == b else sets.parity[a] ^ sets.parity[b]) != across:
                self.odd = (int(seq[i]), int(u[i]), int(v[i]))
        for x in list(sets.parent):
            self.up[x], self.side[x] = sets.find(x), sets.parity[x]
        return keep


def odd_cycle_edge(edges: Iterable[tuple[int, int, int]]) -> tuple[int, int, int] | None:
    """The first edge that closes a cycle of odd length; None if the graph is bipartite."""
    sets = DisjointSets()
    for e in edges:
        if not sets.join(e[1], e[2]) and sets.parity[e[1]] == sets.parity[e[2]]:
            return e
    return None


def preorder(forest: Graph) -> list[tuple[int, int]]:
    """(vertex, root) in depth-first preorder: roots and children by ascending id."""
    out, seen = [], set()
    for root in sorted(forest):
        if root in seen:
            continue
        stack = [root]
        seen.add(root)
        while stack:
            x = stack.pop()
            out.append((x, root))
            for y in sorted(forest[x], reverse=True):
                if y not in seen:
                    seen.add(y)
                    stack.append(y)
    return out


def scan_first_forest(g: Graph, pick: str | Callable[[list[int]], int] = "fifo", starts: Iterable[int] | None = None) -> tuple[list[tuple[int, int]], list[int]]:
    """Scan-first search in memory: tree edges (parent, child) and the vertices in scan order.

    `pick` chooses the next marked vertex: "fifo", "lifo", "smallest", or a function of the list of marked vertices. It
    is only the order of visits that "lifo" takes from depth-first search: a scan still marks all neighbours at once.
    """
    marked, tree, order = set(), [], []
    for root in starts if starts is not None else sorted(g):
        if root in marked:
            continue
        marked.add(root)
        open_ = [root]
        while open_:
            if pick == "fifo":
                x = open_.pop(0)
            elif pick == "lifo":
                x = open_.pop()
            elif pick == "smallest":
                x = open_.pop(open_.index(min(open_)))
            else:
                x = pick(open_)
                open_.remove(x)
            order.append(x)
            for y in sorted(g[x]):
                if y not in marked:
                    marked.add(y)
                    tree.append((x, y))
                    open_.append(y)
    return tree, order


def first_neighbours(edges: Iterable[tuple[int, int, int]], position: dict[int, int]) -> dict[int, tuple[int, int]]:
    """For each vertex that has a neighbour placed before it, the one placed first, with the edge's seq."""
    best: dict[int, tuple[int, int]] = {}
    for seq, u, v in edges:
        p, c = (u, v) if position[u] < position[v] else (v, u)
        if c not in best or position[p] < position[best[c][0]]:
            best[c] = (p, seq)
    return best


#: Forests of fewer vertices, and those of more levels than one for so many vertices, are numbered vertex by vertex.
FEW, FLAT = 2000, 64


def preorder_arrays(n: int, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Place in depth-first preorder, root and depth of each of the vertices 0 ... n - 1 of a forest with edges a[i] - b[i]."""
    heads, tails = np.concatenate([a, b]), np.concatenate([b, a])
    order = np.lexsort((tails, heads))
    starts, tails = np.searchsorted(heads[order], np.arange(n + 1)), tails[order]
    found = _preorder_by_levels(n, a, b, starts, tails) if n >= FEW else None
    return _preorder_by_vertices(n, starts.tolist(), tails.tolist()) if found is None else found


def _preorder_by_vertices(n: int, starts: list[int], tails: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    place, root, depth = [-1] * n, [0] * n, [0] * n
    at = 0
    for r in range(n):
        if place[r] >= 0:
            continue
        stack = [r]
        while stack:
            x = stack.pop()
            place[x], root[x] = at, r
            at += 1
            for y in reversed(tails[starts[x] : starts[x + 1]]):
                if place[y] < 0:
                    depth[y] = depth[x] + 1
                    stack.append(y)
    return np.array(place), np.array(root), np.array(depth)


def _preorder_by_levels(n: int, a: np.ndarray, b: np.ndarray, starts: np.ndarray, tails: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """The same, a level of all trees at a time: sizes of subtrees from below, then places from above. None if there are too many levels."""
    root = StreamForest(n)
    root.offer(a, b)
    root = root.label
    parent, depth, size = np.full(n, -1), np.zeros(n, np.int64), np.ones(n, np.int64)
    here = np.flatnonzero(root == np.arange(n))
    levels = [here]
    while len(here):
        if len(levels) > n // FLAT:
            return None
        count = starts[here + 1] - starts[here]
        own = np.repeat(here, count)
        y = tails[np.arange(len(own)) - np.repeat(np.cumsum(count) - count, count) + np.repeat(starts[here], count)]
        down = y != parent[own]
        here = y[down]  # children by parent, and by id for each
        parent[here], depth[here] = own[down], len(levels)
        levels.append(here)
    for here in levels[:0:-1]:
        np.add.at(size, parent[here], size[here])
    place = np.empty(n, np.int64)
    place[levels[0]] = np.cumsum(size[levels[0]]) - size[levels[0]]
    for here in levels[1:]:
        if len(here):
            before = np.cumsum(size[here]) - size[here]
            first = np.append(True, parent[here[1:]] != parent[here[:-1]])
            place[here] = place[parent[here]] + 1 + before - before[first][np.cumsum(first) - 1]
    return place, root, depth


class StreamForest:
    """The edges a[i] - b[i] between vertices 0 ... n - 1 that join two trees of what came before, many edges at a time.

    That is the minimum spanning forest by place in the stream, so each round takes the first edge out of every tree; `label` is the smallest
    vertex of each vertex's tree.
    """

    def __init__(self, n: int):
        self.label = np.arange(n)

    def offer(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Which of the next edges are kept, as a mask."""
        keep = np.zeros(len(a), dtype=bool)
        x, y = self.label[a], self.label[b]
        live = np.flatnonzero(x != y)
        x, y = x[live], y[live]
        while len(live):
            first = np.full(len(self.label), len(live))
            # of values put in one place the last one stays, here the smallest
            first[x[::-1]] = np.arange(len(live) - 1, -1, -1)
            other = np.full(len(self.label), len(live))
            other[y[::-1]] = np.arange(len(live) - 1, -1, -1)
            np.minimum(first, other, out=first)
            tree = np.flatnonzero(first < len(live))
            edge = first[tree]
            keep[live[edge]] = True
            to = np.arange(len(self.label))
            to[tree] = x[edge] + y[edge] - tree
            ends = tree[(to[to[tree]] == tree) & (tree < to[tree])]  # two trees that took the same edge
            to[ends] = ends
            while True:
                further = to[to]
                if np.array_equal(further, to):
                    break
                to = further
            least = np.arange(len(to))
            np.minimum.at(least, to[tree], tree)
            to = least[to]
            self.label = to[self.label]
            x, y = to[x], to[y]
            on = x != y
            live, x, y = live[on], x[on], y[on]
        return keep


#: Edges that folds handle in one set of arrays.
CHUNK = 1 << 16
#: Edges that a forest between numbered vertices takes at a time.
STEP = 1 << 20


def _handed(child: np.ndarray, parent: np.ndarray, seq: np.ndarray) -> np.ndarray:
    """For edges with the places of their ends: when each is handed on, -1 for the one that its child keeps.

    In order of arrival a child stores an edge from an earlier place than all before it, which displaces the one stored.
    """
    low, wide = int(seq.min()), int(seq.max()) - int(seq.min()) + 1
    one = (int(child.max()) + 1) * wide < 1 << 62  # both fit into one number, which is sorted faster
    order = np.argsort(child * wide + (seq - low)) if one else np.lexsort((seq, child))
    c, p, s = child[order], parent[order], seq[order]
    group = np.cumsum(np.append(0, c[1:] != c[:-1]))
    span = int(p.max()) + 2
    least = np.minimum.accumulate(p - group * span)  # later groups lie below earlier ones, so each begins anew
    stored = np.append(True, (group[1:] != group[:-1]) | (least[1:] < least[:-1]))
    when = s.copy()
    at = np.flatnonzero(stored)
    same = np.append(group[at[1:]] == group[at[:-1]], False)
    when[at] = np.where(same, s[np.append(at[1:], 0)], -1)
    out = np.empty_like(when)
    out[order] = when
    return out


def layered_mask(seq: np.ndarray, u: np.ndarray, v: np.ndarray, k: int, feed: str = "original", rule: str = "preorder") -> np.ndarray:
    """For each edge the scan-first forest that it is in, 1 ... k, or 0; each is built on what the earlier ones left.

    `feed` is the order in which the next layer's order sees an edge: as they came, or as they are handed on ("handover").
    """
    ids = np.unique(np.concatenate([u, v]))
    a, b = (np.searchsorted(ids, x).astype(np.int32) for x in (u, v))
    layer, left, when = np.zeros(len(u), dtype=np.int32), np.arange(len(u)), seq.copy()
    for i in range(1, k + 1):
        if not len(left):
            break
        left = left[np.argsort(when[left], kind="stable")]
        fold = StreamForest(len(ids))
        kept = np.concatenate([fold.offer(a[c], b[c]) for c in (left[j : j + STEP] for j in range(0, len(left), STEP))])
        place, root, depth = preorder_arrays(len(ids), a[left[kept]], b[left[kept]])
        if rule == "level":
            place = np.argsort(np.lexsort((np.arange(len(ids)), depth, root)))
        x, y = place[a[left]], place[b[left]]
        handed = _handed(np.maximum(x, y), np.minimum(x, y), seq[left])
        layer[left[handed < 0]] = i
        if feed == "handover":
            when[left] = handed
        left = left[handed >= 0]
    return layer


def layered_passes(n: int, a: np.ndarray, b: np.ndarray, k: int, feed: str = "handover", rule: str = "preorder", step: int = 1 << 20) -> np.ndarray:
    """`layered_mask` for edges a[i] - b[i] between vertices 0 ... n - 1 that lie in stream order, in k + 1 passes of a `step` at a time.

    Beside the edges it holds a byte for each, for the layer, and some words for each vertex. A child's stored edge is known by its
    parent's place; what is displaced or not stored goes on to the next layer's forest at once, in order of time.
    """
    layer = np.zeros(len(a), dtype=np.int8)

    def offer(fold: StreamForest, kept: list, x: np.ndarray, y: np.ndarray) -> None:
        keep = fold.offer(x, y)
        kept.append((x[keep], y[keep]))

    fold, kept = StreamForest(n), [(a[:0], b[:0])]
    for j in range(0, len(a), step):
        offer(fold, kept, a[j : j + step], b[j : j + step])
    for i in range(1, k + 1):
        place, root, depth = preorder_arrays(n, *(np.concatenate(x) for x in zip(*kept, strict=True)))
        if rule == "level":
            place = np.argsort(np.lexsort((np.arange(n), depth, root)))
        del root, depth
        vertex = np.argsort(place)
        least, held = np.full(n, n), np.full(n, -1)
        fold, kept = StreamForest(n), [(a[:0], b[:0])]
        for j in range(0, len(a), step):
            at = j + np.flatnonzero(layer[j : j + step] == 0)
            if not len(at):
                continue
            x, y = place[a[at]], place[b[at]]
            child, parent = np.maximum(x, y), np.minimum(x, y)
            order = np.argsort(child, kind="stable")
            c, p = child[order], parent[order]
            begins = np.append(True, c[1:] != c[:-1])
            group = np.cumsum(begins)
            run = np.minimum.accumulate(p - group * (n + 1)) + group * (n + 1)
            before = np.minimum(np.where(begins, n, np.append(n, run[:-1])), least[c])
            stored = p < before
            some = np.flatnonzero(stored)  # of a child's stored edges the last one is assigned last
            least[c[some]], held[c[some]] = p[some], at[order[some]]
            if i < k and feed == "handover":
                gone = np.empty_like(p)
                gone[order] = np.where(stored, before, p)
                on = gone < n
                offer(fold, kept, vertex[child[on]], vertex[gone[on]])
        layer[held[held >= 0]] = i
        if i < k and feed == "original":
            for j in range(0, len(a), step):
                on = layer[j : j + step] == 0
                offer(fold, kept, a[j : j + step][on], b[j : j + step][on])
    return layer


def layered_rows(edges: Iterable[tuple[int, int, int]], k: int) -> list[tuple[int, int, int, int]]:
    """Union of k scan-first forests of a list of edges, as (seq, u, v, layer)."""
    rows = np.array(sorted(edges), dtype=np.int64).reshape(-1, 3)
    layer = layered_mask(rows[:, 0], rows[:, 1], rows[:, 2], k)
    return [(*r, i) for r, i in zip(rows[layer > 0].tolist(), layer[layer > 0].tolist(), strict=True)]


class LayeredFold:
    """A layered certificate of a stream in chunks: what is held is certified together with a buffer twice as long, or of some chunks."""

    def __init__(self, k: int):
        self.k, self.peak = k, 0
        self.cert = tuple(np.zeros(0, np.int64) for _ in range(3))
        self.layer = np.zeros(0, np.int32)
        self.buffer: list[tuple[np.ndarray, ...]] = []
        self.waiting = 0

    def offer(self, seq: np.ndarray, u: np.ndarray, v: np.ndarray) -> None:
        self.buffer.append((seq, u, v))
        self.waiting += len(seq)
        if self.waiting >= max(8 * CHUNK, 2 * len(self.layer)):
            self.settle()

    def settle(self) -> tuple[tuple[np.ndarray, ...], np.ndarray]:
        """Edges held and their layers, after all that was offered."""
        if self.waiting:
            rows = tuple(np.concatenate(x) for x in zip(self.cert, *self.buffer, strict=True))
            self.peak = max(self.peak, 3 * len(rows[0]))
            layer = layered_mask(*rows, self.k)
            self.cert, self.layer = tuple(x[layer > 0] for x in rows), layer[layer > 0]
            self.buffer, self.waiting = [], 0
        return self.cert, self.layer


# ------------------------------------------------------------------------------------------------ disjoint paths


class PathFlow:
    """Flow of unit node capacities between two vertices, as node-disjoint paths that augmenting searches reroute.

    A vertex other than the ends carries at most one path. `nxt` and `prv` link the vertices along the paths. A search state
    is a vertex with the side on which it was reached: 0 free to leave by any edge, 1 reached along an edge into a vertex on
    a path, from where it can only go back along that path. Searches start from both ends and meet between. With `near` the sink is
    an extra vertex that `near` says who is joined to; a search then starts from the source and ends at the first state next to the sink.
    """

    def __init__(self, g: Graph, source: int, sink, cap: int, near: Container[int] | None = None):
        self.g, self.source, self.sink = g, source, sink
        self.near: Container[int] = g[sink] if near is None else near
        self._search = self._from_both if near is None else self._from_source
        self.nxt: dict[int, int] = {}
        self.prv: dict[int, int] = {}
        self.starts: list[int] = []
        self.value = self.searches = self.arcs = 0
        self.reached: Iterable[tuple] = ()
        if source in self.near:
            self.value = 1  # the edge itself is a path without inner vertices
        while self.value < cap and self._augment():
            self.value += 1

    def _augment(self) -> bool:
        self.searches += 1
        states = self._search()
        if states:
            self._reroute(states)
        return bool(states)

    def _onward(self, x: int, side: int) -> list[tuple]:
        """States after (x, side)."""
        prv, source, sink = self.prv, self.source, self.sink
        if x == source:
            return [(y, 1) if y in prv else (y, 0) for y in self.g[x] if y != sink and prv.get(y) != source]
        after = []
        if side == 0:
            ahead = self.nxt.get(x)
            after = [(y, 1) if y in prv else (y, 0) for y in self.g[x] if y != source and y != sink and y != ahead]
            if ahead != sink and x in self.near:
                after.append((sink, 0))
        back = prv.get(x)
        if back is not None and back != source:
            after.append((back, 0))
        return after

    def _before(self, y: int, side: int) -> list[tuple]:
        """States that (y, side) comes after."""
        nxt, prv, source, sink = self.nxt, self.prv, self.source, self.sink
        if y == sink:
            return [(x, 0) for x in self.g[sink] if x != source and nxt.get(x) != sink]
        if side == 0 and y in prv:
            z = nxt[y]
            return [] if z == sink else [(z, 0), (z, 1)]
        return [(x, 0) for x in self.g[y] if x != sink and (prv.get(y) if x == source else nxt.get(x)) != (source if x == source else y)]

    def _from_both(self) -> list[tuple] | None:
        ahead, behind = {(self.source, 0): None}, {(self.sink, 0): None}
        front, back = list(ahead), list(behind)
        while front and back:
            here, there, step = (ahead, behind, self._onward) if len(front) <= len(back) else (behind, ahead, self._before)
            found = []
            for state in front if here is ahead else back:
                near = step(*state)
                self.arcs += len(near)
                for other in near:
                    if other not in here:
                        here[other] = state
                        if other in there:
                            return self._way(other, ahead)[::-1] + self._way(behind[other], behind)
                        found.append(other)
            if here is ahead:
                front = found
            else:
                back = found
        return None

    @staticmethod
    def _way(state, came: dict) -> list[tuple]:
        out = []
        while state is not None:
            out.append(state)
            state = came[state]
        return out

    def _from_source(self) -> list[tuple] | None:
        start = (self.source, 0)
        came: dict[tuple, tuple | None] = {start: None}
        queue = deque([start])
        while queue:
            state = queue.popleft()
            near = self._onward(*state)
            self.arcs += len(near)
            for other in near:
                if other not in came:
                    came[other] = state
                    if other[1] == 0 and other[0] in self.near and self.nxt.get(other[0]) != self.sink:
                        return [*self._way(other, came)[::-1], (self.sink, 0)]
                    queue.append(other)
        self.reached = came
        return None

    def beyond(self) -> set[int]:
        """After a search from the source that found no further path: the vertices on its side of a smallest cut."""
        return {x for x, side in self.reached if side == 0}

    def _reroute(self, states: list[tuple]) -> None:
        gone, new = set(), []
        for (x, _), (y, _) in zip(states, states[1:], strict=False):
            if self.prv.get(x) == y and x != self.source and y != self.sink:
                gone.add((y, x))  # walked back along a path edge
            else:
                new.append((x, y))
        links = {(a, b) for a, b in self.nxt.items()} | {(self.source, s) for s in self.starts}
        links = (links - gone) | set(new)
        self.nxt = {a: b for a, b in links if a != self.source}
        self.prv = {b: a for a, b in links if b != self.sink}
        self.starts = [b for a, b in links if a == self.source]

    def paths(self) -> list[list[int]]:
        out = [[self.source, self.sink]] if self.source in self.near else []
        for x in sorted(self.starts):
            path = [self.source, x]
            while path[-1] != self.sink:
                path.append(self.nxt[path[-1]])
            out.append(path)
        return out

    def cut(self) -> list[int]:
        """Vertices of a smallest set that parts the ends; only if they are not adjacent and the flow was not capped."""
        reached, todo = {(self.source, 0)}, [(self.source, 0)]
        for state in todo:
            for other in self._onward(*state):
                if other not in reached:
                    reached.add(other)
                    todo.append(other)
        out = []
        for s in self.starts:
            # the last vertex of the path that a search can enter but not leave forward
            x, best = s, s
            while x != self.sink:
                if (x, 1) in reached or (x, 0) in reached:
                    best = x
                x = self.nxt[x]
            out.append(best)
        return sorted(out)


def local_connectivity(g: Graph, u: int, v: int, cap: int) -> int:
    return PathFlow(g, u, v, cap).value


# ------------------------------------------------------------------------------------------------ online certificate


class OnlineCertificate:
    """Keeps an edge if fewer than k node-disjoint paths join its ends in what was kept before.

    `core` files vertices by sets of which no two members are parted by fewer than k others; this stays true as edges are added, so an
    edge within a set is refused without a search. A vertex joins a set with k paths to it that share nothing but the vertex. Searches
    that no set spares are counted, and after some of them a set is begun around an end of the last one.
    """

    def __init__(self, k: int, edges: Iterable[tuple[int, int, int]] = ()):
        self.k, self.g, self.kept = k, {}, []
        self.sets = DisjointSets()  # one path is enough for k = 1
        self.flows = self.arcs = self.shortcuts = 0
        self.core: dict[int, int] = {}
        self.members: dict[int, set[int]] = {}
        self.beside: dict[int, dict[int, int]] = {}  # for vertices in no set, neighbours in each set
        self.shared: dict[tuple[int, int], set[int]] = {}  # of two sets, vertices of one that could be in the other
        self.unspared, self.patience = 0, 32 * k
        for e in edges:
            self._keep(e)

    @property
    def words(self) -> int:
        """Words held: each edge once as a row and at both ends, the vertices, the sets and what lies beside them."""
        return 5 * len(self.kept) + len(self.g) + 2 * len(self.core) + 3 * len(self.beside) + sum(map(len, self.shared.values()))

    def _keep(self, edge) -> None:
        self.kept.append(edge)
        u, v = edge[1], edge[2]
        if self.k == 1:
            self.sets.join(u, v)
        self.g.setdefault(u, set()).add(v)
        self.g.setdefault(v, set()).add(u)
        if self.core:
            for x, y in ((u, v), (v, u)):
                if x in self.core and y not in self.core and self._beside(y, self.core[x]):
                    self._join([y], self.core[x])

    def _beside(self, x: int, name: int) -> bool:
        """Counts one more neighbour in a set; whether they are k."""
        near = self.beside.setdefault(x, {})
        near[name] = near.get(name, 0) + 1
        return near[name] >= self.k

    def _join(self, todo: list[int], name: int) -> None:
        own = self.members.setdefault(name, set())
        for x in todo:
            if x in self.core:
                continue
            self.core[x] = name
            own.add(x)
            self.beside.pop(x, None)
            todo += [y for y in self.g[x] if y not in self.core and self._beside(y, name)]

    def _merge(self, a: int, b: int) -> None:
        """One set of two that k vertices belong to both of."""
        if len(self.members[a]) > len(self.members[b]):
            a, b = b, a
        self.shared = {pair: x for pair, x in self.shared.items() if a not in pair}
        gone, ready = self.members.pop(a), []
        for x in gone:
            self.core[x] = b
        self.members[b] |= gone
        for x in gone:
            for y in self.g[x]:
                if y not in self.core:
                    self.beside[y].pop(a, None)
                    if self._beside(y, b):
                        ready.append(y)
        self._join(ready, b)

    def _search(self, u: int, v, near: Container[int] | None = None) -> bool:
        flow = PathFlow(self.g, u, v, self.k, near)
        self.flows += 1
        self.arcs += flow.arcs
        return flow.value >= self.k

    def _belongs(self, x: int, name: int) -> bool:
        """Whether fewer than k vertices part x from no member of a set."""
        own = self.core.get(x)
        if own == name:
            return True
        pair = (min(own, name), max(own, name)) if own is not None else None
        if pair and x in self.shared.get(pair, ()):
            return True
        if not self._search(x, EXTRA, self.members[name]):
            return False
        if pair is None:
            self._join([x], name)
        else:
            both = self.shared.setdefault(pair, set())
            both.add(x)
            if len(both) >= self.k:
                self._merge(*pair)
        return True

    def _nearest(self, u: int, v: int) -> int | None:
        """The set of one of two vertices, or the one with most of their neighbours; None if there is none."""
        for x in (u, v):
            if x in self.core:
                return self.core[x]
        near = [(n, name) for x in (u, v) for name, n in self.beside.get(x, {}).items()]
        return max(near)[1] if near else None

    def _begin(self, x: int) -> None:
        """A new set from what lies around x, if k vertices for it are found there."""
        self.unspared = 0
        around, met = [x], {x}
        for y in around:
            if len(around) >= 32 * self.k:
                break
            new = [z for z in self.g[y] if z not in met and z not in self.core]
            met.update(new)
            around += new
        seed = inseparable_seed(self.g, self.k, sorted(around, key=lambda y: (-len(self.g[y]), y))[: 8 * self.k])
        self.patience = 32 * self.k if seed else 2 * self.patience
        if seed:
            self._join(seed, seed[0])

    def needs(self, u: int, v: int) -> bool:
        a, b = self.g.get(u), self.g.get(v)
        if a is None or b is None:
            self.shortcuts += 1
            return True
        if v in a:
            self.shortcuts += 1
            return False
        if len(a) < self.k or len(b) < self.k:
            self.shortcuts += 1
            return True
        own = self.core.get(u)
        if self.k == 1 or (own is not None and own == self.core.get(v)) or len(a & b) >= self.k:
            self.shortcuts += 1
            return self.k == 1 and self.sets.find(u) != self.sets.find(v)
        name = self._nearest(u, v)
        if name is not None:
            first, second = (u, v) if self.core.get(u) == name else (v, u)
            if self._belongs(first, name) and self._belongs(second, self.core[first]):
                return False
        if not self._search(u, v):
            return True
        self.unspared += 1
        if self.unspared >= self.patience:
            for x in (u, v):
                if x not in self.core:
                    self._begin(x)
                    break
        return False

    def offer(self, edge: tuple[int, int, int]) -> bool:
        if edge[1] == edge[2] or not self.needs(edge[1], edge[2]):
            return False
        self._keep(edge)
        return True


def folded_from_within(seq: np.ndarray, u: np.ndarray, v: np.ndarray, k: int, rounds: int = 64) -> np.ndarray:
    """Which edges the online method keeps if it meets them from the densest part outward, as a mask.

    Vertices with k edges at most, and then those that have no more left without them, come last, the first ones found at the very end: each
    edge of such a vertex arrives when the vertex has fewer than k others, so fewer than k paths join its ends and it is kept. Only edges between
    the remaining vertices are offered one by one, those of one vertex together and vertices with many edges first, so that sets
    whose members need no search form early. Stopping after some `rounds` leaves more edges to be offered.
    """
    keep, left = np.ones(len(u), dtype=bool), np.arange(len(u))
    ids, flat = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = flat[: len(u)], flat[len(u) :]
    for _ in range(rounds):
        many = np.bincount(np.concatenate([a[left], b[left]]), minlength=len(ids)) > k
        on = many[a[left]] & many[b[left]]
        if on.all():
            break
        left = left[on]
    size = np.bincount(np.concatenate([a[left], b[left]]), minlength=len(ids))
    x, y = a[left], b[left]
    of = np.where((size[x] < size[y]) | ((size[x] == size[y]) & (x < y)), x, y)
    c = OnlineCertificate(k)
    for i in left[np.lexsort((seq[left], of, -size[of]))].tolist():
        keep[i] = c.offer((int(seq[i]), int(u[i]), int(v[i])))
    return keep


# ------------------------------------------------------------------------------------------------ inseparable sets


def inseparable_seed(g: Graph, k: int, candidates: Iterable[int]) -> list[int]:
    """k of the candidates of which no set of fewer than k other vertices parts any two; none if they are not found."""
    found: list[int] = []
    for x in candidates:
        if all(y in g[x] or PathFlow(g, x, y, k).value >= k for y in found):
            found.append(x)
            if len(found) == k:
                return found
    return []


def component_of_each(g: PackedGraph) -> np.ndarray:
    """For each place in `g.ids` the smallest place of its component."""
    at = np.searchsorted(g.ids, g.ends)
    own = np.repeat(np.arange(len(g.ids)), np.diff(g.starts))
    label = np.arange(len(g.ids))
    while True:
        new = label.copy()
        np.minimum.at(new, own, label[at])
        new = np.minimum(new, new[new])
        new = new[new]
        if (new == label).all():
            return label
        label = new


def blocks(g: PackedGraph) -> list[list[int]]:
    """The largest parts of at least two vertices that stay connected without any one vertex, as places in `g.ids`; each begins with its top.

    A vertex in several parts is a cut vertex; every edge is in one part, a bridge in one of its own.
    """
    n, at, starts = len(g.ids), np.searchsorted(g.ids, g.ends).tolist(), g.starts.tolist()
    found, low, following, out, met = [-1] * n, [0] * n, starts[:n], [], 0
    for root in range(n):
        if found[root] >= 0:
            continue
        found[root] = low[root] = met
        met += 1
        way, held = [root], [root]
        while way:
            x = way[-1]
            i = following[x]
            if i < starts[x + 1]:
                following[x] = i + 1
                y = at[i]
                if found[y] < 0:
                    found[y] = low[y] = met
                    met += 1
                    way.append(y)
                    held.append(y)
                elif found[y] < low[x]:
                    low[x] = found[y]
            else:
                way.pop()
                if way:
                    up = way[-1]
                    if low[x] >= found[up]:
                        cut = len(held) - 1
                        while held[cut] != x:
                            cut -= 1
                        out.append([up, *held[cut:]])
                        del held[cut:]
                    elif low[x] < low[up]:
                        low[up] = low[x]
    return out


def block_graphs(g: PackedGraph, parts: list[list[int]], least: int = 3) -> Iterator[tuple[int, PackedGraph]]:
    """(place in `parts`, graph) of those of at least so many vertices, the largest first."""
    if len(parts) == 1 and len(parts[0]) == len(g.ids):
        if len(g.ids) >= least:
            yield 0, g
        return
    top, own = np.array([p[0] for p in parts], dtype=np.int64), np.full(len(g.ids), -1)
    for i, p in enumerate(parts):
        own[p[1:]] = i
    x, y = np.repeat(np.arange(len(g.ids)), np.diff(g.starts)), np.searchsorted(g.ids, g.ends)
    once = x < y
    x, y = x[once], y[once]
    # an edge lies where its lower end has its own part
    of = np.where(own[x] == own[y], own[x], np.where((own[y] >= 0) & (top[own[y]] == x), own[y], own[x]))
    order = np.argsort(of, kind="stable")
    cut = np.searchsorted(of[order], np.arange(len(parts) + 1))
    for i in sorted(range(len(parts)), key=lambda i: (-len(parts[i]), i)):
        if len(parts[i]) < least:
            break
        some = order[cut[i] : cut[i + 1]]
        yield i, PackedGraph(g.ids[x[some]], g.ids[y[some]], np.zeros(0, np.int64))


def inseparable_set(g: PackedGraph, k: int) -> set[int]:
    """One set of at least k vertices of which no two are parted by fewer than k others, and that no further vertex could join; empty if none is begun.

    It is grown from k vertices that are compared pairwise: a vertex joins with k neighbours there, or k paths into the set that share
    nothing but the vertex. One with fewer paths is parted from the set by fewer than k vertices, and so is all that lies on its
    side of them, however far the set grows.
    """
    degree = np.diff(g.starts)
    by_degree = np.lexsort((np.arange(len(g.ids)), -degree))
    by_degree = g.ids[by_degree[degree[by_degree] >= k - 1]].tolist()
    if len(by_degree) < k:
        return set()
    members: set[int] = set()
    beside: dict[int, int] = {}
    apart: set[int] = set()

    def join(todo: list[int]) -> None:
        for x in todo:
            if x in members:
                continue
            members.add(x)
            for y in g[x]:
                beside[y] = n = beside.get(y, 0) + 1
                if n == k and y not in members:
                    todo.append(y)

    join(inseparable_seed(g, k, by_degree[: 8 * k]))
    if members:
        for x in by_degree:
            if x not in members and x not in apart and len(g[x]) >= k:
                flow = PathFlow(g, x, EXTRA, k, members)
                if flow.value >= k:
                    join([x])
                else:
                    apart |= flow.beyond()
    return members


def inseparable_sets(g: PackedGraph, k: int, every: bool = False) -> np.ndarray:
    """For each place in `g.ids` the component whose inseparable set it is in, or -1; at most one set, of k vertices and more, for a component.

    Such a set lies within one block for k = 2 and more, so blocks are gone through by size until one has a set. A vertex left outside can be
    parted from it by fewer than k vertices. With `every` each block may have one, and sets have numbers of their own.
    """
    label = component_of_each(g)
    if k == 1:
        return label
    out = np.full(len(g.ids), -1)
    parts = blocks(g)
    done: set[int] = set()
    for i, own in block_graphs(g, parts, k):
        of = int(label[parts[i][0]])
        if of in done and not every:
            continue
        found = inseparable_set(own, k)
        if found:
            done.add(of)
            at = np.searchsorted(g.ids, np.fromiter(found, np.int64, len(found)))
            out[at[out[at] < 0]] = i if every else of
    return out


# ------------------------------------------------------------------------------------------------ separators


def component_count(g: Graph, removed: frozenset[int] | set[int] = frozenset()) -> int:
    seen, n = set(removed), 0
    for s in g:
        if s in seen:
            continue
        n += 1
        seen.add(s)
        todo = [s]
        while todo:
            for y in g[todo.pop()]:
                if y not in seen:
                    seen.add(y)
                    todo.append(y)
    return n


def distances_from(g: Graph, source: int) -> dict[int, int]:
    """Edges on a shortest path from the source to each vertex that it reaches."""
    found, todo = {source: 0}, [source]
    for x in todo:
        for y in g[x]:
            if y not in found:
                found[y] = found[x] + 1
                todo.append(y)
    return found


def within(g: Graph, u: int, v: int, t: int) -> bool:
    """Whether two different vertices are at most t edges apart, by steps from the end with the smaller front."""
    here, there = {u}, {v}
    front, back = here, there
    for _ in range(t):
        if len(front) > len(back):
            here, there, front, back = there, here, back, front
        front = set().union(*(g.get(x, ()) for x in front)) - here
        if not front:
            return False
        if not front.isdisjoint(there):
            return True
        here = here | front
    return False


def widest(g: PackedGraph, sources: list[int], words: int = 8) -> int:
    """The largest distance from any of the sources to a vertex that it reaches; a bit of 64 `words` for each source at a time."""
    degree = np.diff(g.starts)
    some = np.flatnonzero(degree)
    at, starts = np.searchsorted(g.ids, g.ends), g.starts[:-1][some]
    far = 0
    for begin in range(0, len(sources), 64 * words):
        own = np.searchsorted(g.ids, sources[begin : begin + 64 * words])
        bit = np.arange(len(own))
        reached = np.zeros((len(g.ids), words), dtype=np.uint64)
        np.bitwise_or.at(reached, (own, bit // 64), np.uint64(1) << (bit % 64).astype(np.uint64))
        steps = 0
        while len(some):
            more = reached[some] | np.bitwise_or.reduceat(reached[at], starts, axis=0)
            if (more == reached[some]).all():
                break
            reached[some] = more
            steps += 1
        far = max(far, steps)
    return far


def shortest_cycle(g: Graph, x: int, most: int | None = None) -> int | None:
    """Length of a cycle that a breadth-first search from x meets first, at least the girth and equal to it from some x; None if there is none up to `most`."""
    found, up = {x: 0}, {x: None}
    todo, shortest = [x], None if most is None else most + 1
    for y in todo:
        if shortest is not None and 2 * found[y] + 1 >= shortest:
            break
        for z in g[y]:
            if z not in found:
                found[z], up[z] = found[y] + 1, y
                todo.append(z)
            elif up[y] != z and (shortest is None or found[y] + found[z] + 1 < shortest):
                shortest = found[y] + found[z] + 1
    return None if most is not None and shortest > most else shortest


def pieces_without_each_vertex(g: Graph, removed: set[int]) -> tuple[int, dict[int, int]]:
    """Components of g without `removed`, and for each other vertex how many there are without it too."""
    found: dict[int, int] = {}
    low: dict[int, int] = {}
    extra: dict[int, int] = {}
    roots = 0
    for root in g:
        if root in removed or root in found:
            continue
        roots += 1
        found[root] = low[root] = len(found)
        extra[root] = 0
        stack = [(root, None, iter(g[root]))]
        while stack:
            x, up, rest = stack[-1]
            for y in rest:
                if y in removed or y == up:
                    continue
                if y in found:
                    low[x] = min(low[x], found[y])
                else:
                    found[y] = low[y] = len(found)
                    extra[y] = 1
                    stack.append((y, x, iter(g[y])))
                    break
            else:
                stack.pop()
                if up is not None:
                    low[up] = min(low[up], low[x])
                    extra[up] += low[x] >= found[up]
    # a root starts with no piece above it, any other vertex with one
    return roots, {x: roots - 1 + b for x, b in extra.items()}


class Pockets:
    """The vertices outside the inseparable sets of a graph, in connected pieces, and what their removal or that of their neighbours cuts off.

    An inseparable set for three vertices stays in one piece when two vertices go. All other pieces then lie within one pocket each, and
    the number of pieces is that of the sets and, added over the pockets, of those parts of a pocket that keep no neighbour in a set.
    """

    def __init__(self, core: np.ndarray, g: PackedGraph):
        self.sets = len(np.unique(core[core >= 0]))
        self.of: dict[int, int] = {}
        self.members: list[list[int]] = []
        out = set(g.ids[core < 0].tolist())
        for s in g.ids[core < 0].tolist():
            if s in self.of:
                continue
            todo = [s]
            self.of[s] = len(self.members)
            for x in todo:
                for y in g[x]:
                    if y in out and y not in self.of:
                        self.of[y] = len(self.members)
                        todo.append(y)
            self.members.append(todo)
        self._last: tuple | None = None

    def __getstate__(self):
        return {**self.__dict__, "_last": None}

    def outside(self, g: Graph, part: Iterable[int]) -> set[int]:
        """Neighbours of a part of a pocket in the sets."""
        return {y for x in part for y in g[x] if y not in self.of}

    def loose(self, g: Graph) -> list[tuple[set[int], int]]:
        """For each pocket its neighbours in the sets if there are two at most, and whether it is a whole component."""
        return [(near, int(not near)) for near in (self.outside(g, p) for p in self.members) if len(near) <= 2]

    def without(self, g: Graph, a: int) -> tuple[int, dict[int, int]]:
        """How many pieces more there are without a, a vertex in a pocket; and for other vertices how many more still without both than each alone adds."""
        at = self.of[a]
        if self._last is None or self._last[0] != at:
            inner = {x: {y for y in g[x] if y in self.of} for x in self.members[at]}
            near = self.outside(g, inner)
            inner[EXTRA] = set()
            for x in self.members[at]:
                if any(y not in self.of for y in g[x]):
                    inner[x].add(EXTRA)
                    inner[EXTRA].add(x)
            alone = pieces_without_each_vertex(inner, set())[1] if len(inner) > 2 else {}
            self._last = (at, inner, near, alone)
        _, inner, near, alone = self._last
        whole = int(not near)
        both: dict[int, int] = {}
        roots, left = pieces_without_each_vertex(inner, {a})
        mine = roots - 1 - whole
        for b in self.members[at]:
            if b > a:
                x = (left[b] - 1) - whole - mine - (alone[b] - 1 - whole)
                if x:
                    both[b] = x
        # parts that hang on a and one vertex of a set
        sole = next(iter(near)) if len(near) == 1 else None
        if sole is not None:
            both[sole] = -1
        seen = {a}
        for s in inner[a]:
            if s is EXTRA or s in seen:
                continue
            part = [s]
            seen.add(s)
            for x in part:
                for y in inner[x]:
                    if y is not EXTRA and y not in seen:
                        seen.add(y)
                        part.append(y)
            hold = self.outside(g, part)
            if len(hold) == 1:
                c = next(iter(hold))
                both[c] = both.get(c, 0) + 1
        return mine, {b: x for b, x in both.items() if x}


def nth_combination(n: int, r: int, index: int) -> tuple[int, ...]:
    """The combination of r out of range(n) at a place of their lexicographic order."""
    from math import comb

    out, x = [], 0
    while r:
        c = comb(n - x - 1, r - 1)
        if index < c:
            out.append(x)
            r -= 1
        else:
            index -= c
        x += 1
    return tuple(out)


def minimum_cuts(g: Graph, u: int, v: int, cap: int) -> list[tuple[int, ...]]:
    """All vertex sets of the smallest size below cap that part u from v; empty if adjacent or not below cap."""
    if v in g[u]:
        return []
    flow = PathFlow(g, u, v, cap)
    if flow.value >= cap:
        return []
    paths = [p[1:-1] for p in flow.paths()]

    def closure(seed: set[tuple[int, int]], begin: Iterable[tuple[int, int]]) -> set[tuple[int, int]] | None:
        """States that leave nothing to the residual graph beyond them; None if they reach v."""
        closed, todo = set(seed), list(begin)
        closed.update(todo)
        while todo:
            x, side = todo.pop()
            after: list[tuple[int, int]] = []
            if side == 0:
                if x in flow.near:
                    return None
                after = [(y, 1) if y in flow.prv else (y, 0) for y in g[x] if y != u]
            if x != u and flow.prv.get(x, u) != u:
                after.append((flow.prv[x], 0))
            for state in after:
                if state not in closed:
                    closed.add(state)
                    todo.append(state)
        return closed

    def cut_of(closed: set[tuple[int, int]]) -> tuple[int, ...]:
        # on each path the vertex that can be entered but not left
        return tuple(next(x for x in p if (x, 0) not in closed) for p in paths)

    # every closed set grows from the smallest by letting one of its cut's vertices through at a time
    first = closure(set(), [(u, 0)])
    found, todo = {cut_of(first)}, [first]
    while todo:
        closed = todo.pop()
        for x in cut_of(closed):
            more = closure(closed, [(x, 0), (x, 1)])
            if more is not None and (c := cut_of(more)) not in found:
                found.add(c)
                todo.append(more)
    return sorted(tuple(sorted(c)) for c in found)


# ------------------------------------------------------------------------------------------------ decisions and brute force


def check_flow(g: Graph, order, k: int, row: int) -> PathFlow:
    """The flow of one of the checks that together decide k-connectivity.

    `order` is ascending. Rows below k(k-1)/2 are pairs of the first k vertices; each further row takes one later vertex against
    all before it, joined to an extra vertex that is never built.
    """
    pairs = list(combinations(range(k), 2))
    if row < len(pairs):
        return PathFlow(g, order[pairs[row][0]], order[pairs[row][1]], k)
    at = k + row - len(pairs)
    return PathFlow(g, order[at], EXTRA, k, _Before(order, at))


def connectivity_check(g: Graph, order, k: int, row: int) -> tuple[int, int] | None:
    """The pair that fails one of these checks, or None."""
    flow = check_flow(g, order, k, row)
    return None if flow.value >= k else (flow.source, order[0] if flow.sink is EXTRA else flow.sink)


#: The extra vertex of a connectivity check.
EXTRA = object()


class _Before:
    """The first vertices of an ascending order, as what an extra vertex is joined to; nothing is copied."""

    def __init__(self, order, at: int):
        self.limit = order[at]

    def __contains__(self, x) -> bool:
        return x < self.limit


def is_k_connected(g: Graph, k: int) -> bool:
    if len(g) <= k or any(len(x) < k for x in g.values()):
        return False
    order = sorted(g)
    return all(connectivity_check(g, order, k, r) is None for r in range(k * (k - 1) // 2 + len(order) - k))


def brute_k_connected(g: Graph, k: int) -> bool:
    """By definition: more than k vertices, and connected after taking away any fewer than k."""
    return len(g) > k and all(component_count(g, set(s)) == 1 for r in range(k) for s in combinations(g, r))


def brute_separators(g: Graph, size: int) -> set[tuple[int, ...]]:
    whole = component_count(g)
    return {tuple(sorted(s)) for s in combinations(g, size) if component_count(g, set(s)) > whole}


def brute_minimum_certificate(g: Graph, k: int) -> int:
    """Fewest edges of a certificate, by trying all subgraphs; for a handful of vertices."""
    edges = sorted({(min(a, b), max(a, b)) for a in g for b in g[a]})
    if not brute_k_connected(g, k):
        return 0
    return next(r for r in range(len(edges) + 1) for s in combinations(edges, r) if brute_k_connected(graph_of(s, g), k))
