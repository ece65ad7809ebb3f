"""Per-request searches over a broadcast graph: depth-first, best-first and integer programming.

They serve graphs of a checked size (``plan.KERNEL_LINKS``) whose requests are many: requests are dealt out, the graph goes
to every executor once, and each request is searched on its own.  Larger graphs belong to the DataFrame loops.
"""

from __future__ import annotations

import heapq
from collections import deque
from functools import partial

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.baselines import flat
from boundpath.plans.plan import KERNEL_LINKS

#: Graphs of at least so many links are searched over arrays; below, plain loops are faster.
FLAT_LINKS = 1000

#: Arcs of one side that make a vertex a hub.
HUB = 256

ANSWER = "req_id bigint, status string, hops bigint, delay bigint, cost bigint, path array<bigint>, generated bigint"


class Graph:
    """Adjacency of arcs (src, dst, bw, delay, cost), both ways."""

    def __init__(self, rows):
        self.out, self.into = {}, {}
        for src, dst, bw, delay, cost in rows:
            self.out.setdefault(src, []).append((dst, bw, delay, cost))
            self.into.setdefault(dst, []).append((src, bw, delay, cost))
        self.vertices = set(self.out) | set(self.into)
        self._flat = None
        self._places = {}

    def flat(self):
        """The graph as arrays, which follow its changes; None for a small graph or one whose metrics aren't whole numbers."""
        if self._flat is None:
            arcs = [a for side in self.out.values() for a in side]
            whole = all(isinstance(x, int) for a in arcs for x in a[1:])
            self._flat = flat.Flat(self.out, self.into, self.vertices) if len(arcs) >= FLAT_LINKS and whole else False
        return self._flat or None

    def fill(self, src, dst, bw) -> None:
        """New bandwidth of the arcs from src to dst."""
        for side, a, b in ((self.out, src, dst), (self.into, dst, src)):
            arcs = side[a]
            for i in self._places_at(side, a).get(b, ()) if len(arcs) >= HUB else [i for i, x in enumerate(arcs) if x[0] == b]:
                arcs[i] = (b, bw, *arcs[i][2:])
        if self._flat:
            self._flat.put(src, dst, bw)

    def _places_at(self, side: dict, a) -> dict:
        """Where the arcs to each other end stand in the list of a hub, which is too long to go through for every one."""
        at = (side is self.out, a)
        if at not in self._places:
            places = self._places[at] = {}
            for i, x in enumerate(side[a]):
                places.setdefault(x[0], []).append(i)
        return self._places[at]

    def remove(self, src, dst, keep: int = 0, demand: int = 1) -> None:
        """Take the arcs from src to dst away, or (keep) leave them with that much bandwidth."""
        for side, a, b in ((self.out, src, dst), (self.into, dst, src)):
            side[a] = [x if x[0] != b else (b, keep, *x[2:]) for x in side[a] if x[0] != b or keep >= demand]
            self._places.pop((side is self.out, a), None)
        if self._flat:
            self._flat.put(src, dst, keep if keep >= demand else -1)

    def least(self, start: int, bw: int, metric: int, back: bool) -> dict:
        """Least total of a metric (2: delay, 3: cost) from start to every vertex; back: from every vertex to start."""
        sides = self.into if back else self.out
        best, heap = {start: 0}, [(0, start)]
        while heap:
            d, v = heapq.heappop(heap)
            if d > best[v]:
                continue
            for arc in sides.get(v, ()):
                if arc[1] >= bw and d + arc[metric] < best.get(arc[0], 1 << 62):
                    best[arc[0]] = d + arc[metric]
                    heapq.heappush(heap, (d + arc[metric], arc[0]))
        return best

    def fewest(self, end: int, bw: int) -> dict:
        """Fewest links from every vertex to end."""
        best, level = {end: 0}, [end]
        while level:
            after = []
            for v in level:
                for arc in self.into.get(v, ()):
                    if arc[1] >= bw and arc[0] not in best:
                        best[arc[0]] = best[v] + 1
                        after.append(arc[0])
            level = after
        return best


def _rank(objective: str, hops: int, delay: int, cost: int, path: tuple) -> tuple:
    return (cost, hops, delay, path) if objective == "cost" else (hops, delay, cost, path)


class _Front:
    """Vectors (hops, delay, cost) met at each vertex that no other of it dominates; equal ones all stay."""

    def __init__(self):
        self._at = {}

    def beats(self, v, vector: tuple) -> bool:
        """Whether a vector met before dominates this one; if not, it is remembered."""
        known = self._at.setdefault(v, [])
        h, d, c = vector
        for a, b, e in known:
            if a <= h and b <= d and e <= c and (a, b, e) != vector:
                return True
        known[:] = [x for x in known if not (h <= x[0] and d <= x[1] and c <= x[2])] + [vector]
        return False


def edfs(g: Graph, r, objective: str, max_hops: int, dominance: bool = True, suffix: bool = True):
    """Depth-first branch and bound: dominance of (hops, delay, cost) at vertices, rest bounds, and the best answer so far.

    suffix: the least hops, delay and cost that are left bound every path, and successors nearest to the destination go first."""
    rest_hops = g.fewest(r.dst, r.bw) if suffix else {}
    rest_delay = g.least(r.dst, r.bw, 2, True) if suffix else {}
    rest_cost = g.least(r.dst, r.bw, 3, True) if suffix else {}
    best, front, made = None, _Front(), 0
    work = [((r.src,), 0, 0)]
    while work:
        path, delay, cost = work.pop()
        if path[-1] == r.dst:
            key = _rank(objective, len(path) - 1, delay, cost, path)
            best = key if best is None or key < best else best
            continue
        if len(path) > max_hops:
            continue
        for to, bw, d, c in sorted(g.out.get(path[-1], ()), key=lambda x: (rest_hops.get(x[0], 0), x), reverse=True):
            if bw < r.bw or to in path:
                continue
            made += 1
            nd, nc = delay + d, cost + c
            if suffix and to not in rest_delay:
                continue
            if nd + rest_delay.get(to, 0) > r.delay or nc + rest_cost.get(to, 0) > r.cost:
                continue
            least_hops = len(path) + rest_hops.get(to, 0)
            if least_hops > max_hops or best is not None and (nc + rest_cost.get(to, 0) > best[0] if objective == "cost" else least_hops > best[0]):
                continue
            if dominance and front.beats(to, (len(path), nd, nc)):
                continue
            work.append(((*path, to), nd, nc))
    return best, made


def ebfs(g: Graph, r, objective: str, max_hops: int, suffix: bool = False):
    """Breadth first from the source with dominance, bounds and (for a cost) the best answer so far; suffix: rest bounds too."""
    f = g.flat() if objective == "hops" and r.src in g.vertices and r.dst in g.vertices and r.src != r.dst else None
    if f and flat.fits(f, r, max_hops):
        return flat.ebfs(f, r, max_hops, suffix)
    rest_delay = g.least(r.dst, r.bw, 2, True) if suffix else {}
    rest_cost = g.least(r.dst, r.bw, 3, True) if suffix else {}
    best, front, made, level, hops = None, _Front(), 0, [((r.src,), 0, 0)], 0
    while level and hops < max_hops:
        hops += 1
        after = []
        for path, delay, cost in level:
            for to, bw, d, c in g.out.get(path[-1], ()):
                if bw < r.bw or to in path:
                    continue
                made += 1
                nd, nc = delay + d, cost + c
                if suffix and to not in rest_delay or nd + rest_delay.get(to, 0) > r.delay or nc + rest_cost.get(to, 0) > r.cost:
                    continue
                if best is not None and objective == "cost" and nc + rest_cost.get(to, 0) > best[0]:
                    continue
                if front.beats(to, (hops, nd, nc)):
                    continue
                if to == r.dst:
                    key = _rank(objective, hops, nd, nc, (*path, to))
                    best = key if best is None or key < best else best
                else:
                    after.append(((*path, to), nd, nc))
        if best is not None and objective == "hops":
            break
        level = after
    return best, made


def loopless(g: Graph, r, objective: str):
    """Loop-free paths in canonical order, made lazily; the work between two paths is bounded by their length and the graph's size.

    What is left after a path falls into sets of paths: those that leave it at one of its vertices, over other arcs than paths before did.  Of every set the
    best is held.  It comes from a search directed by least rests; these go through the set's own beginning at times, so they are only estimates."""
    a, b, c = (3, None, 2) if objective == "cost" else (None, 2, 3)

    def weights(arc):
        return tuple(1 if m is None else arc[m] for m in (a, b, c))

    rest, labels = {}, [((0, 0, 0), r.dst)]
    while labels:
        left, v = heapq.heappop(labels)
        if v not in rest:
            rest[v] = left
            for arc in g.into.get(v, ()):
                if arc[1] >= r.bw and arc[0] not in rest:
                    heapq.heappush(labels, (tuple(map(sum, zip(left, weights(arc), strict=True))), arc[0]))
    made = 0

    def best(path: tuple, taken: tuple, total: tuple, without: frozenset):
        """(totals, path, places of its arcs) of the best path that begins with ``path`` and goes on by another arc than ``without``."""
        nonlocal made
        closed, heap = set(path[:-1]), [(total, path, taken, total)]
        while heap:
            _, way, arcs, sums = heapq.heappop(heap)
            v = way[-1]
            if v == r.dst:
                return sums, way, arcs
            if v in closed:
                continue
            closed.add(v)
            for i, arc in enumerate(g.out.get(v, ())):
                to = arc[0]
                if arc[1] < r.bw or to in closed or to not in rest or len(way) == len(path) and i in without:
                    continue
                made += 1
                after = tuple(map(sum, zip(sums, weights(arc), strict=True)))
                heapq.heappush(heap, (tuple(map(sum, zip(after, rest[to], strict=True))), (*way, to), (*arcs, i), after))
        return None

    sets = []

    def hold(path: tuple, taken: tuple, total: tuple, without: frozenset) -> None:
        got = best(path, taken, total, without)
        if got is not None:
            heapq.heappush(sets, (*got, len(path), without))

    if r.src in rest:
        hold((r.src,), (), (0, 0, 0), frozenset())
    while sets:
        total, path, arcs, begin, without = heapq.heappop(sets)
        yield (*total, path), made
        sums = (0, 0, 0)
        for n, (v, i) in enumerate(zip(path, arcs, strict=False), 1):
            if n >= begin:
                hold(path[:n], arcs[: n - 1], sums, (without if n == begin else frozenset()) | {i})
            sums = tuple(map(sum, zip(sums, weights(g.out[v][i]), strict=True)))


def next_shortest(g: Graph, r, objective: str, max_hops: int, bounds: bool, dominance: bool = False):
    """Loop-free paths in canonical order, best first with the exact least rest as estimate; made lazily.

    bounds: partial paths that can't keep the path bounds, with the least rest to the destination, are dropped.  Without bounds and dominance, and where
    any length is allowed, ``loopless`` does it."""
    if not bounds and not dominance and max_hops >= len(g.vertices) - 1:
        yield from loopless(g, r, objective)
        return
    rest = g.least(r.dst, r.bw, 3, True)
    rest_delay = g.least(r.dst, r.bw, 2, True) if bounds else {}
    heap, made, front = [], 0, _Front()

    def push(v, path, delay, cost):
        if v in rest:
            first = cost + rest[v] if objective == "cost" else len(path) - 1
            heapq.heappush(heap, (first, (len(path) - 1) if v == r.dst else -1, delay, cost, tuple(path), v))

    push(r.src, [r.src], 0, 0)
    ready, level = [], None
    while heap or ready:
        if ready and (not heap or heap[0][0] > level):
            yield heapq.heappop(ready), made
            continue
        first, _, delay, cost, path, v = heapq.heappop(heap)
        if v == r.dst:
            heapq.heappush(ready, _rank(objective, len(path) - 1, delay, cost, path))
            level = first
            continue
        if len(path) > max_hops:
            continue
        for to, bw, d, c in g.out.get(v, ()):
            if bw >= r.bw and to not in path and to in rest:
                made += 1
                if bounds and (delay + d + rest_delay[to] > r.delay or cost + c + rest[to] > r.cost):
                    continue
                if dominance and front.beats(to, (len(path), delay + d, cost + c)):
                    continue
                push(to, [*path, to], delay + d, cost + c)


def kshort_exact(g: Graph, r, objective: str, max_hops: int):
    """The next shortest path until one keeps the bounds, with dominance and rest bounds."""
    made = 0
    for key, made in next_shortest(g, r, objective, max_hops, True, True):
        return key, made
    return None, made


def layered(g: Graph, r, objective: str, max_hops: int, policy: str = "bfs", prefix: bool = True):
    """The layered double-pass search of one request; its backward pass goes breadth first, depth first or best first.

    Fewest hops: the layers up to the destination's first appearance, and a walk back through them.  Else, or if that walk finds nothing
    feasible, a walk back over all lengths against least labels, which dominance ends.  prefix: labels are used."""
    made = 0
    f = g.flat() if r.src in g.vertices and r.dst in g.vertices and r.src != r.dst else None
    if f:
        return _layered_flat(g, f, r, objective, max_hops, policy, prefix)
    if objective == "hops":
        layers, known, news = [{r.src: (0, 0)}], {r.src: (0, 0)}, True
        while r.dst not in layers[-1] and news and len(layers) <= max_hops:
            grown, news = {}, False
            for v, (bd, bc) in layers[-1].items():
                for to, bw, d, c in g.out.get(v, ()):
                    if bw >= r.bw and to != r.src:
                        old = grown.get(to)
                        grown[to] = (bd + d, bc + c) if old is None else (min(old[0], bd + d), min(old[1], bc + c))
            if prefix:
                grown = {v: b for v, b in grown.items() if b[0] <= r.delay and b[1] <= r.cost}
            for v, b in grown.items():  # layers without a new vertex or a lower label bring nothing that the second pass doesn't see
                old = known.get(v)
                if old is None or prefix and (b[0] < old[0] or b[1] < old[1]):
                    known[v], news = (b if old is None else (min(old[0], b[0]), min(old[1], b[1]))), True
            layers.append(grown)
        if r.dst in layers[-1]:
            best, made = _back(g, r, objective, policy, prefix, len(layers) - 1, lambda v, left: layers[left].get(v), False)
            if best is not None:
                return best, made
    if prefix:
        by_delay, by_cost = g.least(r.src, r.bw, 2, False), g.least(r.src, r.bw, 3, False)
        labels = {v: (x, by_cost[v]) for v, x in by_delay.items()}
    else:
        labels = dict.fromkeys(g.least(r.src, r.bw, 2, False), (0, 0))
    if r.dst not in labels or labels[r.dst][0] > r.delay or labels[r.dst][1] > r.cost:
        return None, made
    best, more = _back(g, r, objective, policy, prefix, min(max_hops, len(g.vertices) - 1), lambda v, left: labels.get(v), True)
    return best, made + more


def _layered_flat(g: Graph, f, r, objective: str, max_hops: int, policy: str, prefix: bool):
    """``layered`` with its forward passes over arrays."""
    src, dst, made = f.at[r.src], f.at[r.dst], 0
    met = f.meet(src, dst, r.bw)
    if met is None:
        return None, 0
    # with labels few paths are made, which plain loops do faster unless they go over all arcs of a hub
    levels = (not prefix or f.most >= HUB) and policy == "bfs" and objective == "hops" and flat.fits(f, r, max_hops)

    def walk_back(hops, label, any_length):
        if levels:
            return flat.back(f, r, prefix, hops, label, any_length)

        def one(v, left):
            low_d, low_c = label(left)
            d = low_d.item(f.at[v])
            return None if d == flat.FAR else (d, low_c.item(f.at[v]))

        return _back(g, r, objective, policy, prefix, hops, one, any_length)

    def beyond():
        """Whether no path keeps one of the bounds; only labels within them are made."""
        return f.least(src, r.bw, f.delay, False, r.delay)[dst] == flat.FAR or f.least(src, r.bw, f.cost, False, r.cost)[dst] == flat.FAR

    if objective == "hops":
        layers = flat.near(f, r, met, max_hops, prefix) or flat.layers(f, r, max_hops, prefix)
        if layers[-1][0][dst] < flat.FAR:
            best, made = walk_back(len(layers) - 1, lambda left: layers[left], False)
            if best is not None:
                return best, made
    if prefix and beyond():
        return None, made
    by_delay = f.least(src, r.bw, f.delay, False) if prefix else f.reached(src, r.bw)
    by_cost = f.least(src, r.bw, f.cost, False) if prefix else by_delay
    best, more = walk_back(min(max_hops, len(g.vertices) - 1), lambda left: (by_delay, by_cost), True)
    return best, made + more


def _back(g: Graph, r, objective: str, policy: str, prefix: bool, hops: int, label, any_length):
    """Suffixes from the destination: of exactly ``hops`` links, or (any_length) of at most so many."""
    best, front, made = None, _Front(), 0
    first = ((0, 0, 0), (r.dst,), 0, 0)
    work = [first] if policy == "kshort" else deque([first])
    while work:
        _, path, delay, cost = heapq.heappop(work) if policy == "kshort" else work.pop() if policy == "dfs" else work.popleft()
        used = len(path) - 1
        if path[0] == r.src and (any_length or used == hops):
            key = _rank(objective, used, delay, cost, path)
            best = key if best is None or key < best else best
            continue
        if used == hops or (best is not None and objective == "hops" and used + 1 > best[0]):
            continue
        for u, bw, d, c in g.into.get(path[0], ()):
            if bw < r.bw or u in path:
                continue
            known = label(u, hops - used - 1)
            if known is None:
                continue
            made += 1
            nd, nc = delay + d, cost + c
            low_d, low_c = (nd + known[0], nc + known[1]) if prefix else (nd, nc)
            if low_d > r.delay or low_c > r.cost:
                continue
            if best is not None and objective == "cost" and low_c > best[0]:
                continue
            # suffixes of one vertex compete; in the walk of one length those of its layer have equal hops
            if front.beats((u, used) if not any_length else u, (used + 1, nd, nc)):
                continue
            item = ((low_c, used, low_d) if objective == "cost" else (used, low_d, low_c), (u, *path), nd, nc)
            if policy == "kshort":
                heapq.heappush(work, item)
            else:
                work.append(item)
    return best, made


def arc_ip(g: Graph, r, objective: str, max_hops: int):
    """The arc-based 0/1 program: flow conservation, delay and cost rows, by simplex and branch and bound."""
    from boundpath.services.lp import solve_binary

    arcs = [(v, to, d, c) for v in sorted(g.out) for to, bw, d, c in sorted(g.out[v]) if bw >= r.bw and to != r.src and v != r.dst]
    vertices = sorted({a[0] for a in arcs} | {a[1] for a in arcs} | {r.src, r.dst})
    eq = [([1.0 * (a[0] == v) - 1.0 * (a[1] == v) for a in arcs], 1.0 if v == r.src else -1.0 if v == r.dst else 0.0) for v in vertices if v != r.dst]
    le = [([float(a[2]) for a in arcs], float(r.delay)), ([float(a[3]) for a in arcs], float(r.cost))]
    # a hair per arc keeps free cycles out of the relaxation; costs are whole numbers, so the optimum stays one
    x, nodes = solve_binary([a[3] + 1e-4 if objective == "cost" else 1.0 for a in arcs], eq, le)
    if x is None:
        return None, nodes
    step = {a[0]: a for a, used in zip(arcs, x, strict=True) if used}
    path, delay, cost = [r.src], 0, 0
    while path[-1] != r.dst:
        a = step[path[-1]]
        path.append(a[1])
        delay, cost = delay + a[2], cost + a[3]
    return _rank(objective, len(path) - 1, delay, cost, tuple(path)), nodes


def least_metric(g: Graph, r, objective: str, max_hops: int, metric: int = 2):
    """Dijkstra on links with enough bandwidth, least delay (2) or cost (3); the bounds are checked afterwards."""
    done, heap, made = set(), [(0, 0, 0, (r.src,))], 0
    while heap:
        total, hops, other, path = heapq.heappop(heap)
        v = path[-1]
        if v in done:
            continue
        done.add(v)
        if v == r.dst:
            delay, cost = (total, other) if metric == 2 else (other, total)
            return (_rank(objective, hops, delay, cost, path) if delay <= r.delay and cost <= r.cost else None), made
        for arc in g.out.get(v, ()):
            if arc[1] >= r.bw and arc[0] not in done:
                made += 1
                heapq.heappush(heap, (total + arc[metric], hops + 1, other + arc[5 - metric], (*path, arc[0])))
    return None, made


def relaxation(g: Graph, r, objective: str, max_hops: int, improve: bool = True):
    """One path bound (cost), fewest hops: layers of vertices whose least cost falls (the layered search), or, without improve, the least
    cost of every exact number of hops (iterative Bellman-Ford), until the destination is met.  Predecessors are kept per layer."""
    layer, best, steps, made = {r.src: 0}, {r.src: 0}, [], 0
    while layer and len(steps) < min(max_hops, len(g.vertices)):
        grown = {}
        for v, total in layer.items():
            for to, bw, _, c in g.out.get(v, ()):
                if bw < r.bw or to == r.src:
                    continue
                made += 1
                x = total + c
                if x <= r.cost and (not improve or x < best.get(to, 1 << 62)) and (x, v) < grown.get(to, (1 << 62, 0)):
                    grown[to] = (x, v)
        fell = [v for v, (x, _) in grown.items() if x < best.get(v, 1 << 62)]
        for v in fell:
            best[v] = grown[v][0]
        steps.append({v: p for v, (_, p) in grown.items()})
        if r.dst in grown:
            path = [r.dst]
            for step in reversed(steps):
                path.insert(0, step[path[0]])
            delay = sum(next(x[2] for x in g.out[a] if x[0] == b) for a, b in zip(path, path[1:], strict=False))
            return _rank(objective, len(path) - 1, delay, grown[r.dst][0], tuple(path)), made
        if not fell:  # longer walks can only come later and be no cheaper
            break
        layer = {v: x for v, (x, _) in grown.items()}
    return None, made


SEARCHES = {
    "least_delay": least_metric,
    "least_cost": partial(least_metric, metric=3),
    "edfs": edfs,
    "ebfs": ebfs,
    "ebfs_suffix": partial(ebfs, suffix=True),
    "kshort_exact": kshort_exact,
    "ldp": partial(layered, prefix=False),
    "ldp_prefix": layered,
    "dfs": partial(layered, policy="dfs"),
    "kshort": partial(layered, policy="kshort"),
    "single": relaxation,
    "ibf": partial(relaxation, improve=False),
    "arc_ip": arc_ip,
}


def _broadcast(links: DataFrame):
    rows = [tuple(r) for r in links.select("src", "dst", "bw", "delay", "cost").limit(KERNEL_LINKS + 1).collect()]
    if len(rows) > KERNEL_LINKS:
        raise ValueError(f"the graph has more than {KERNEL_LINKS} links: use the DataFrame search")
    return links.sparkSession.sparkContext.broadcast(rows)


def _as_row(req_id, key, made, objective):
    if key is None:
        return req_id, "NONE", None, None, None, None, made
    a, b, c, path = key
    hops, delay, cost = (b, c, a) if objective == "cost" else (a, b, c)
    return req_id, "FOUND", hops, delay, cost, list(path), made


def search(links: DataFrame, requests: DataFrame, method: str, objective: str = "hops", max_hops: int | None = None) -> DataFrame:
    """Answers of a kernel for every request, with the number of partial paths (or program nodes) it made.

    max_hops None: as many as a loop-free path can have."""
    sent = _broadcast(links)

    def run(frames):
        g = Graph(sent.value)
        for f in frames:
            rows = []
            for r in f.itertuples(index=False):
                if r.src == r.dst:
                    rows.append((r.req_id, "FOUND", 0, 0, 0, [r.src], 0))
                else:
                    rows.append(_as_row(r.req_id, *SEARCHES[method](g, r, objective, len(g.vertices) if max_hops is None else max_hops), objective))
            yield _frame(rows, ["req_id", "status", "hops", "delay", "cost", "path", "generated"])

    parts = max(1, min(64, requests.sparkSession.sparkContext.defaultParallelism))
    return requests.select("req_id", "src", "dst", "bw", "delay", "cost").repartition(parts, "req_id").mapInPandas(run, ANSWER)


def _frame(rows, names):
    out = pd.DataFrame(rows, columns=names)
    for c in ("hops", "delay", "cost"):
        if c in names:
            out[c] = out[c].astype("Int64")
    return out


def k_shortest(links: DataFrame, requests: DataFrame, k: int, objective: str = "cost", max_hops: int | None = None, bounded: bool = False) -> DataFrame:
    """The k best loop-free paths of each request; bounded: only those within the bounds."""
    sent = _broadcast(links)

    def run(frames):
        g = Graph(sent.value)
        for f in frames:
            rows = []
            for r in f.itertuples(index=False):
                for i, (key, _) in enumerate(next_shortest(g, r, objective, max_hops or len(g.vertices), bounded), 1):
                    rows.append((*_as_row(r.req_id, key, 0, objective)[:6], i))
                    if i == k:
                        break
            yield _frame(rows, ["req_id", "status", "hops", "delay", "cost", "path", "rank"])

    schema = ANSWER.replace("generated bigint", "rank int")
    parts = max(1, min(64, requests.sparkSession.sparkContext.defaultParallelism))
    return requests.select("req_id", "src", "dst", "bw", "delay", "cost").repartition(parts, "req_id").mapInPandas(run, schema)
