"""The kernels' searches over arrays, for graphs of many links: same answers and same counts of partial paths as ``kernels``.

Vertices are numbers in the order of their names, arcs lie by source in the order in which ``Graph`` lists them; a step of a search is
a few array operations over all partial paths of a length.
"""

from __future__ import annotations

import numpy as np

#: No label.
FAR = 1 << 62

#: Labels that ``Flat.ahead`` keeps.
AHEAD = 1 << 24


class Flat:
    """Arrays of a ``Graph``: arcs by source (and their order by destination), bandwidths that may change."""

    def __init__(self, out: dict, into: dict, vertices):
        self.names = sorted(vertices)
        self.at = {v: i for i, v in enumerate(self.names)}
        arcs = [(i, *a[:4]) for i, v in enumerate(self.names) for a in out.get(v, ())]
        ends = [(i, a[0]) for i, v in enumerate(self.names) for a in into.get(v, ())]
        n, names = len(self.names), np.array(self.names, np.int64)
        self.src, dst, self.bw, self.delay, self.cost = np.array(arcs, np.int64).T.copy()
        self.dst = np.searchsorted(names, dst)
        dst, src = np.array(ends, np.int64).T
        # both sides list the arcs of two vertices in one order, so the k-th of one is the k-th of the other
        key = self.src * n + self.dst
        self.by_ends = np.argsort(key, kind="stable")
        self.ends = key[self.by_ends]
        by_dst = np.empty(len(arcs), np.int64)
        by_dst[np.argsort(np.searchsorted(names, src) * n + dst, kind="stable")] = self.by_ends
        self.bit = np.left_shift(np.int64(1), (np.arange(n) * 40503 >> 4) % 63)
        self.sides = []
        for end, order in ((self.src, np.arange(len(arcs))), (self.dst, by_dst)):
            degree = np.bincount(end, minlength=n)
            self.sides.append((np.cumsum(degree) - degree, degree, order))
        #: arcs into one vertex, at most
        self.most = int(degree.max(initial=0))
        self._labels, self._ahead, self._along, self._lists = {}, {}, {}, None

    def put(self, src, dst, bw: int) -> None:
        """New bandwidth of the arcs between two vertices; below 0: none has it."""
        key = self.at[src] * len(self.names) + self.at[dst]
        first, last = np.searchsorted(self.ends, [key, key + 1])
        arcs = self.by_ends[first:last]
        for at, (_, lost) in list(self._labels.items()):
            if (self.bw[arcs] < at[1]).any() and bw >= at[1]:
                del self._labels[at]
            elif bw < at[1]:
                lost.extend(arcs[self.bw[arcs] >= at[1]].tolist())
        if (self.bw[arcs] < bw).any():
            self._ahead.clear()
        self.bw[arcs] = bw

    def around(self, v: np.ndarray, back: bool = False):
        """Arcs that leave (back: enter) each of the vertices, in order, and the places of their vertices in ``v``."""
        first, degree, order = self.sides[back]
        n = degree[v]
        owner = np.repeat(np.arange(len(v)), n)
        k = np.arange(len(owner)) + np.repeat(first[v] - (np.cumsum(n) - n), n)
        return order[k] if back else k, owner

    def usable(self, bw: int, back: bool = False):
        """What leads on over arcs of that bandwidth, as a function: vertices ->
        (other ends, delays and costs of all, places of the arcs in these, places of the vertices), in the order of ``around``."""
        _, _, order = self.sides[back]
        if back not in self._along:
            end, head = (self.dst, self.src) if back else (self.src, self.dst)
            self._along[back] = end[order], head[order], self.delay[order], self.cost[order]
        k = np.flatnonzero((self.bw[order] if back else self.bw) >= bw)
        end, head, delay, cost = (x[k] for x in self._along[back])
        degree = np.bincount(end, minlength=len(self.names))
        first = np.cumsum(degree) - degree

        def on(v):
            n = degree[v]
            owner = np.repeat(np.arange(len(v)), n)
            at = np.arange(len(owner)) + (first[v] - (np.cumsum(n) - n))[owner]
            return head[at], delay, cost, at, owner

        return on

    def meet(self, src: int, dst: int, bw: int):
        """(fewest links from src to dst, of which the last so many were seen from dst, links to dst where seen), or None if no links of that
        bandwidth lead there: both sides grow by turns until they meet or one ends."""
        seen, left = np.zeros(len(self.names), np.int8), np.full(len(self.names), -1, np.int32)
        seen[src], seen[dst], left[dst] = 1, 2, 0
        fronts, grown = [np.array([src]), np.array([dst])], [0, 0]
        while len(fronts[0]) and len(fronts[1]):
            back = len(fronts[1]) < len(fronts[0])
            k, _ = self.around(fronts[back], back)
            k = k[self.bw[k] >= bw]
            t = (self.src if back else self.dst)[k]
            mine, other = (2, 1) if back else (1, 2)
            if (seen[t] == other).any():
                return sum(grown) + 1, grown[1], left
            t = t[seen[t] == 0]
            seen[t] = mine
            grown[back] += 1
            fronts[back] = np.unique(t)
            if back:
                left[fronts[1]] = grown[1]
        return None

    def apart(self, src: int, dst: int, bw: int) -> bool:
        """Whether no links of that bandwidth lead from src to dst."""
        return self.meet(src, dst, bw) is None

    def reached(self, src: int, bw: int) -> np.ndarray:
        """0 for every vertex that links of that bandwidth lead to from src, FAR for others."""
        out = np.full(len(self.names), FAR)
        out[src], front = 0, np.array([src])
        while len(front):
            k, _ = self.around(front)
            t = self.dst[k[self.bw[k] >= bw]]
            t = t[out[t] == FAR]
            out[t] = 0
            front = np.unique(t)
        return out

    def least(self, start: int, bw: int, weight: np.ndarray, back: bool, most: int = FAR) -> np.ndarray:
        """Least totals from start to every vertex (back: from every vertex to start); those above ``most`` are left FAR.

        The last few results stay, to be mended where arcs have been lost since: they are not to be changed."""
        at = (start, bw, weight is self.cost, back, most)
        best, lost = self._labels.pop(at, (None, []))
        if best is None:
            best = np.full(len(self.names), FAR)
            best[start], front = 0, np.array([start])
        else:
            front = self._cut(best, lost, start, bw, weight, back, most) if lost else np.empty(0, np.int64)
        head, tail = (self.src, self.dst) if back else (self.dst, self.src)
        fell = np.zeros(len(self.names), bool)
        while len(front):
            k, _ = self.around(front, back)
            t, x = head[k], best[tail[k]] + weight[k]
            low = (x < best[t]) & (self.bw[k] >= bw) & (x <= most)
            t, x = t[low], x[low]
            np.minimum.at(best, t, x)
            fell[t] = True
            front = np.flatnonzero(fell)
            fell[front] = False
        self._labels[at] = best, []
        while len(self._labels) > 4:
            del self._labels[next(iter(self._labels))]
        return best

    def ahead(self, dst: int, bw: int, weight: np.ndarray) -> np.ndarray:
        """At most what is left from every vertex to dst: least totals of an earlier time, when the graph had as many arcs or more."""
        at = (dst, bw, weight is self.cost)
        if at not in self._ahead:
            best = self.least(dst, bw, weight, True)
            small = best[best < FAR].max() < 1 << 31
            self._ahead[at] = np.minimum(best, (1 << 31) - 1).astype(np.int32) if small else best.copy()
            while len(self._ahead) > max(1, AHEAD // len(self.names)):
                del self._ahead[next(iter(self._ahead))]
        return self._ahead[at]

    def lists(self):
        """Arcs that leave and that enter each vertex, as (arc, other end)."""
        if self._lists is None:
            out, into = ([[] for _ in self.names] for _ in range(2))
            for k, (s, t) in enumerate(zip(self.src.tolist(), self.dst.tolist(), strict=True)):
                out[s].append((k, t))
                into[t].append((k, s))
            self._lists = out, into, {False: self.delay.tolist(), True: self.cost.tolist()}
        return self._lists

    def _cut(self, best, lost: list, start: int, bw: int, weight, back: bool, most: int) -> np.ndarray:
        """Takes the labels that may have come over lost arcs back and gives those vertices what their other arcs bring; which ones have a label."""
        head, tail = (self.src, self.dst) if back else (self.dst, self.src)
        gone, k = np.zeros(len(best), bool), np.array(lost)
        while len(k):
            t = head[k]
            through = (best[t] < FAR) & (best[tail[k]] + weight[k] == best[t]) & ~gone[t] & (t != start)
            front = np.unique(t[through])
            gone[front] = True
            k, _ = self.around(front, back)
        cut = np.flatnonzero(gone)
        best[cut] = FAR
        k, _ = self.around(cut, not back)
        x = best[tail[k]] + weight[k]
        ok = (self.bw[k] >= bw) & (best[tail[k]] < FAR) & (x <= most)
        np.minimum.at(best, head[k[ok]], x[ok])
        return cut[best[cut] < FAR]


class _Front:
    """Undominated (delay, cost) of every vertex over the levels so far: delays rise and costs fall within a vertex.

    A vector is one number (vertex, delay, cost), so that plain sorting keeps them."""

    def __init__(self, n: int, span: int, rise: int):
        self.rise, self.low, self.high = rise, (rise - 1).bit_length(), (span - 1).bit_length()
        self.code, self.value = np.empty(0, np.int64), np.empty(0, np.int64)
        self.first_d, self.first_c, self.last_d, self.last_c = (np.full(n, FAR) for _ in range(4))

    def beaten(self, v, delay, cost):
        if not len(self.code):
            return np.zeros(len(v), bool)
        # the first vectors of a vertex beat most; the others are looked up
        out = (self.first_d[v] <= delay) & (self.first_c[v] <= cost)
        rest = np.flatnonzero(~out)
        v, delay, cost = v[rest], delay[rest], cost[rest]
        last = (self.last_d[v] <= delay) & (self.last_c[v] <= cost)
        out[rest] = last
        left = np.flatnonzero(~last & (self.first_d[v] <= delay))
        if len(left):
            v, delay, cost = v[left], delay[left], cost[left]
            k = np.searchsorted(self.code, ((v << self.high | delay) + 1) << self.low) - 1
            # of a smaller vertex the value is larger than any of this one, so no vertex has to be compared
            out[rest[left]] = (k >= 0) & (self.value[k] <= cost - v * self.rise)
        return out

    def add(self, v, delay, cost):
        code = np.concatenate([self.code, (v << self.high | delay) << self.low | cost])
        if not len(code):
            return
        code.sort()
        w, c = code >> self.low + self.high, code & (1 << self.low) - 1
        value = c - w * self.rise
        low = np.minimum.accumulate(value)
        falls = np.ones(len(code), bool)
        falls[1:] = low[1:] < low[:-1]
        k = np.flatnonzero(falls)
        self.code, self.value, w, c = code[k], value[k], w[k], c[k]
        d = self.code >> self.low & (1 << self.high) - 1
        ends = np.flatnonzero(w[1:] != w[:-1])
        first, last = np.concatenate([[0], ends + 1]), np.concatenate([ends, [len(w) - 1]])
        self.first_d[w[first]], self.first_c[w[first]] = d[first], c[first]
        self.last_d[w[last]], self.last_c[w[last]] = d[last], c[last]


def _beaten_before(v, delay, cost):
    """Which rows an earlier row of the same vertex dominates without being equal."""
    beaten = np.zeros(len(v), bool)
    # 16 bits are sorted by radix
    order = np.argsort(v.astype(np.uint16) if len(v) and v.max() < 1 << 16 else v, kind="stable")
    w = v[order]
    open_, step = np.flatnonzero(w[1:] == w[:-1]) + 1, 1
    d, c = (delay[order], cost[order]) if len(open_) else (delay, cost)
    while len(open_):
        before = open_ - step
        worse = (d[before] <= d[open_]) & (c[before] <= c[open_]) & ((d[before] < d[open_]) | (c[before] < c[open_]))
        beaten[order[open_[worse]]] = True
        step += 1
        open_ = open_[~worse & (open_ >= step)]
        open_ = open_[w[open_ - step] == w[open_]]
    return beaten


def fits(f: Flat, r, max_hops: int) -> bool:
    """Whether a level's vectors (vertex, delay and cost) are 64-bit numbers."""
    bits = [(_span(w, most, max_hops) - 1).bit_length() for w, most in ((f.delay, r.delay), (f.cost, r.cost))]
    return (len(f.names) + 1) << sum(bits) < FAR


def _span(weight: np.ndarray, bound: int, max_hops: int) -> int:
    return min(int(bound), int(weight.max(initial=0)) * max_hops) + 1


def ebfs(f: Flat, r, max_hops: int, suffix: bool):
    """``kernels.ebfs`` for fewest hops."""
    src, dst, made = f.at[r.src], f.at[r.dst], 0
    if suffix:
        if f.apart(src, dst, r.bw):  # every successor is counted and dropped
            k, _ = f.around(np.array([src]))
            return None, int(((f.bw[k] >= r.bw) & (f.dst[k] != src)).sum())
        rest_delay, rest_cost = f.least(dst, r.bw, f.delay, True, r.delay), f.least(dst, r.bw, f.cost, True, r.cost)
    front, on = _Front(len(f.names), _span(f.delay, r.delay, max_hops), _span(f.cost, r.cost, max_hops)), f.usable(r.bw)
    paths, delay, cost, hops = np.array([[src]], np.int32), np.zeros(1, np.int64), np.zeros(1, np.int64), 0
    marks = f.bit[paths[:, 0]]
    while len(paths) and hops < max_hops:
        hops += 1
        t, more_d, more_c, k, p = on(paths[:, -1])
        k, p, t = _outside(f, paths, marks, k, p, t)
        made += len(k)
        # nothing came to the destination before, so nothing beats what comes first: the other paths of this length are counted only
        there = np.flatnonzero(t == dst)
        if len(there):
            d, c = delay[p[there]] + more_d[k[there]], cost[p[there]] + more_c[k[there]]
            ok = (d <= r.delay) & (c <= r.cost)
            if ok.any():
                there, d, c = there[ok], d[ok], c[ok]
                first = np.lexsort((c, d))[0]
                ties = there[(d == d[first]) & (c == c[first])]
                path = min(tuple(x) for x in paths[p[ties]].tolist())
                return (hops, int(d[first]), int(c[first]), tuple(f.names[v] for v in path) + (r.dst,)), made
        d, c = delay[p] + more_d[k], cost[p] + more_c[k]
        ok = (d + rest_delay[t] <= r.delay) & (c + rest_cost[t] <= r.cost) if suffix else (d <= r.delay) & (c <= r.cost)
        paths, marks, delay, cost = _grown(f, front, paths, marks, ok, p, t, d, c)
    return None, made


def _grown(f: Flat, front, paths, marks, ok, p, t, d, c):
    """The next level: paths p on to vertices t where they are ``ok`` and nothing at their vertex beats them."""
    if not ok.all():
        k = np.flatnonzero(ok)
        p, t, d, c = p[k], t[k], d[k], c[k]
    if front is not None:
        k = np.flatnonzero(~front.beaten(t, d, c))
        p, t, d, c = p[k], t[k], d[k], c[k]
    k = np.flatnonzero(~_beaten_before(t, d, c))
    p, t, d, c = p[k], t[k], d[k], c[k]
    if front is not None:
        front.add(t, d, c)
    grown = np.empty((len(p), paths.shape[1] + 1), np.int32)
    grown[:, :-1], grown[:, -1] = paths[p], t
    return grown, marks[p] | f.bit[t], d, c


def _outside(f: Flat, paths, marks, k, p, t):
    """(k, p, t) of the vertices t that aren't on their path p: a mark of 63 bits a path rules most out, the rest is compared."""
    look = np.flatnonzero(marks[p] & f.bit[t])
    if not len(look):
        return k, p, t
    on = (paths[p[look]] == t[look, None]).any(axis=1)
    new = np.ones(len(t), bool)
    new[look[on]] = False
    new = np.flatnonzero(new)
    return k[new], p[new], t[new]


def back(f: Flat, r, prefix: bool, hops: int, label, any_length: bool):
    """``kernels._back`` breadth first, for fewest hops: suffixes from the destination, a level at a time.  label(left): least delay and cost of
    every vertex by that many links."""
    src, made, used = f.at[r.src], 0, 0
    front = _Front(len(f.names), _span(f.delay, r.delay, hops), _span(f.cost, r.cost, hops)) if any_length else None
    on = f.usable(r.bw, True)
    paths, delay, cost = np.array([[f.at[r.dst]]], np.int32), np.zeros(1, np.int64), np.zeros(1, np.int64)
    marks = f.bit[paths[:, 0]]
    while len(paths):
        there = np.flatnonzero(paths[:, -1] == src)
        best = None
        if len(there) and (any_length or used == hops):
            first = there[np.lexsort((cost[there], delay[there]))[0]]
            ties = there[(delay[there] == delay[first]) & (cost[there] == cost[first])]
            path = min(tuple(x[::-1]) for x in paths[ties].tolist())
            best = (used, int(delay[first]), int(cost[first]), tuple(f.names[v] for v in path))
            # in the queue, what stands before the first complete path is still extended and counted
            paths, delay, cost, marks = paths[: there[0]], delay[: there[0]], cost[: there[0]], marks[: there[0]]
        if used == hops:
            return best, made
        low_d, low_c = label(hops - used - 1)
        t, more_d, more_c, k, p = on(paths[:, -1])
        known = low_d[t] < FAR
        if not known.all():
            known = np.flatnonzero(known)
            k, p, t = k[known], p[known], t[known]
        k, p, t = _outside(f, paths, marks, k, p, t)
        made += len(k)
        if best is not None:
            return best, made
        d, c = delay[p] + more_d[k], cost[p] + more_c[k]
        ok = (d + low_d[t] <= r.delay) & (c + low_c[t] <= r.cost) if prefix else (d <= r.delay) & (c <= r.cost)
        paths, marks, delay, cost = _grown(f, front, paths, marks, ok, p, t, d, c)
        used += 1
    return None, made


def layers(f: Flat, r, max_hops: int, prefix: bool) -> list:
    """Least delay and cost of every vertex by exact length, up to the destination's first appearance (kernels.layered)."""
    src, dst = f.at[r.src], f.at[r.dst]
    n = len(f.names)
    usable = (f.bw >= r.bw) & (f.dst != src)
    low_d, low_c = np.full(n, FAR), np.full(n, FAR)
    low_d[src] = low_c[src] = 0
    out, here, news = [(low_d.copy(), low_c.copy())], np.array([src]), True
    while out[-1][0][dst] == FAR and news and len(out) <= max_hops:
        bd, bc = out[-1]
        k, _ = f.around(here)
        k = k[usable[k]]
        s, t = f.src[k], f.dst[k]
        d, c = np.full(n, FAR), np.full(n, FAR)
        np.minimum.at(d, t, bd[s] + f.delay[k])
        np.minimum.at(c, t, bc[s] + f.cost[k])
        if prefix:
            gone = (d > r.delay) | (c > r.cost)
            d[gone] = c[gone] = FAR
        here = np.flatnonzero(d < FAR)
        lower = (d[here] < low_d[here]) | (c[here] < low_c[here]) if prefix else low_d[here] == FAR
        news = bool(lower.any())
        low_d, low_c = np.minimum(low_d, d), np.minimum(low_c, c)
        out.append((d, c))
    return out


def near(f: Flat, r, met, max_hops: int, prefix: bool):
    """``layers`` for the fewest links that lead to the destination at all (met: ``Flat.meet``), right at the vertices of such paths, which are all
    that the walk back asks for; None if the destination isn't labelled at that length."""
    hops, seen, left = met
    if hops > max_hops:
        return None
    n, dst = len(f.names), f.at[r.dst]
    here = np.array([f.at[r.src]])
    d, c = np.full(n, FAR), np.full(n, FAR)
    d[here] = c[here] = 0
    out = [(d, c)]
    for used in range(1, hops + 1):
        bd, bc = out[-1]
        k, _ = f.around(here)
        k = k[(f.bw[k] >= r.bw) & (f.dst[k] != f.at[r.src])]
        if hops - used <= seen:
            k = k[left[f.dst[k]] == hops - used]
        s, t = f.src[k], f.dst[k]
        d, c = np.full(n, FAR), np.full(n, FAR)
        np.minimum.at(d, t, bd[s] + f.delay[k])
        np.minimum.at(c, t, bc[s] + f.cost[k])
        here = np.unique(t)
        if prefix:
            gone = here[(d[here] > r.delay) | (c[here] > r.cost)]
            d[gone] = c[gone] = FAR
            here = here[d[here] < FAR]
        out.append((d, c))
    return out if d[dst] < FAR else None


def shortest(f: Flat, r, metric: int):
    """(total, hops, other metric, path) of the least such path, or None if none keeps the bound on the metric (kernels.least_metric).

    Vertices are taken by their total and what is at least left from them (``Flat.ahead``), so few are seen."""
    import heapq

    src, dst = f.at[r.src], f.at[r.dst]
    weight, most = (f.delay, r.delay) if metric == 2 else (f.cost, r.cost)
    rest = f.ahead(dst, r.bw, weight)
    far = FAR if rest.dtype == np.int64 else (1 << 31) - 1
    rest, bw = memoryview(rest), memoryview(f.bw)
    out, into, weights = f.lists()
    mine, other = weights[metric == 3], weights[metric == 2]
    if rest[src] == far:
        return None
    best, settled, heap = {src: 0}, set(), [(rest[src], src)]
    while heap:
        key, v = heapq.heappop(heap)
        if key > most:
            break
        if v in settled:
            continue
        settled.add(v)
        if v == dst:  # all vertices of equally short paths come before anything longer
            most = key
            continue
        if len(settled) == 500 and dst not in settled and f.apart(src, dst, r.bw):
            return None
        x = best[v]
        for k, t in out[v]:
            y = x + mine[k]
            if bw[k] >= r.bw and rest[t] < far and y + rest[t] <= most and y < best.get(t, FAR):
                best[t] = y
                heapq.heappush(heap, (y + rest[t], t))
    if dst not in settled:
        return None
    # only arcs of least paths to the destination are left: few vertices
    arcs, seen, work = {}, {dst}, [dst]
    while work:
        v = work.pop()
        for k, u in into[v]:
            if u in settled and bw[k] >= r.bw and best[u] + mine[k] == best[v]:
                arcs.setdefault(u, []).append((v, mine[k], other[k]))
                if u not in seen:
                    seen.add(u)
                    work.append(u)
    done, heap = set(), [(0, 0, 0, (src,))]
    while heap:
        total, hops, extra, path = heapq.heappop(heap)
        v = path[-1]
        if v == dst:
            return total, hops, extra, tuple(f.names[x] for x in path)
        if v not in done:
            done.add(v)
            for to, w, o in arcs.get(v, ()):
                heapq.heappush(heap, (total + w, hops + 1, extra + o, (*path, to)))
    return None
