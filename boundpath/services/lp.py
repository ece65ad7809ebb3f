"""A small dense simplex and branch and bound, for programs of at most a few hundred columns on the driver or in a task."""

from __future__ import annotations

from itertools import count

import numpy as np

EPS = 1e-9


def simplex(c, eq, le, prices: bool = False):
    """Minimise c x with eq rows (a, b): a x = b, le rows: a x <= b, x >= 0.  (x, value), or None if infeasible; prices: also
    how much the value falls per unit of each le row's right side.

    Two phases; after many steps the entering column is chosen by number, so it always ends; unbounded programs raise."""
    n, rows = len(c), [*eq, *le]
    m, slack = len(rows), len(le)
    a = np.zeros((m, n + slack + m))
    b = np.array([r[1] for r in rows], float)
    for i, (row, _) in enumerate(rows):
        a[i, :n] = row
        if i >= len(eq):
            a[i, n + i - len(eq)] = 1.0
    flipped = b < 0
    a[flipped] *= -1
    b = np.abs(b)
    basis = list(range(n + slack, n + slack + m))
    for i in range(m):
        a[i, n + slack + i] = 1.0
    tab = np.hstack([a, b[:, None]])

    def pivot(i, enter):
        tab[i] /= tab[i, enter]
        column = tab[:, enter].copy()
        column[i] = 0.0
        rows = np.flatnonzero(np.abs(column) > EPS)
        tab[rows] -= column[rows, None] * tab[i]
        basis[i] = enter

    def run(cost, allowed):
        # steepest first; by lowest number (which can't cycle) once the steps get many
        for step in count():
            reduced = (cost - cost[basis] @ tab[:, :-1])[:allowed]
            enter = int(np.argmin(reduced)) if step < 20 * (m + n) else int(np.argmax(reduced < -EPS))
            if reduced[enter] >= -EPS:
                return
            up = np.flatnonzero(tab[:, enter] > EPS)
            if not len(up):
                raise ValueError("unbounded")
            ratio = tab[up, -1] / tab[up, enter]
            tied = up[ratio <= ratio.min() + 1e-12]
            pivot(int(min(tied, key=lambda i: basis[i])), enter)

    total = n + slack + m
    phase = np.zeros(total)
    phase[n + slack :] = 1
    run(phase, total)
    if sum(tab[i, -1] for i in range(m) if basis[i] >= n + slack) > 1e-7:
        return None
    for i in range(m):  # artificial columns at zero leave the basis where they can
        if basis[i] >= n + slack:
            j = next((j for j in range(n + slack) if abs(tab[i, j]) > EPS), None)
            if j is not None:
                pivot(i, j)
    cost = np.zeros(total)
    cost[:n] = c
    run(cost, n + slack)
    x = np.zeros(total)
    x[basis] = tab[:, -1]
    if prices:
        sign = np.where(flipped[len(eq):], -1.0, 1.0)
        return x[:n], float(np.dot(c, x[:n])), (cost - cost[basis] @ tab[:, :-1])[n : n + slack] * sign
    return x[:n], float(np.dot(c, x[:n]))


def solve_binary(c, eq, le):
    """Minimise c x over x in {0, 1}: (x or None, relaxations solved)."""
    n, best, value, nodes = len(c), None, float("inf"), 0
    stack: list[dict[int, int]] = [{}]
    while stack:
        fixed = stack.pop()
        nodes += 1
        fix = [([1.0 if j == i else 0.0 for j in range(n)], float(v)) for i, v in fixed.items()]
        got = simplex(c, [*eq, *fix], le) if n else None
        if got is None or got[1] > value - 1e-6:
            continue
        x = got[0]
        part = [i for i in range(n) if min(abs(x[i]), abs(x[i] - 1)) > 1e-6]
        if not part:
            if got[1] < value - 1e-9:
                best, value = [int(round(v)) for v in x], got[1]
            continue
        i = max(part, key=lambda i: (min(x[i] % 1, 1 - x[i] % 1), -i))
        stack += [{**fixed, i: 0}, {**fixed, i: 1}]
    return best, nodes


def max_min(flows: list[list[list]], capacity: dict, demand: list[float] | None = None) -> list[list[float]]:
    """Max-min fair rates, level by level.  flows[i]: its paths, each a list of links; result: a rate for each path.

    Every level raises the common rate of unfrozen flows as far as the links allow (one program), then freezes those whose
    own row has a price: they have just that rate in every solution of the level."""
    columns = [(i, p) for i, paths in enumerate(flows) for p in range(len(paths))]
    at = {c: j for j, c in enumerate(columns)}
    n, frozen, uses = len(columns), {}, {}
    for (i, p), j in at.items():
        for e in flows[i][p]:
            uses.setdefault(e, []).append(j)
    caps = []
    for e, js in uses.items():
        row = np.zeros(n + 1)
        np.add.at(row, js, 1.0)
        caps.append((row, float(capacity[e])))
    own = np.zeros((len(flows), n + 1))
    for (i, _), j in at.items():
        own[i, j] = 1.0
    limits = [(own[i], float(demand[i])) for i in range(len(flows)) if demand and flows[i]]
    goal = np.zeros(n + 1)
    goal[n] = -1.0
    x = np.zeros(n)
    while open_ := [i for i in range(len(flows)) if i not in frozen and flows[i]]:
        # a hair of slack for frozen rates keeps the program feasible under rounding
        fixed = [(-own[i], -rate * (1 - 1e-9)) for i, rate in frozen.items()]
        rise = [(-own[i] - goal, 0.0) for i in open_]
        full = [(own[i], rate) for i, rate in frozen.items()]
        got = simplex(goal, [], [*rise, *caps, *limits, *fixed, *full], True)
        level, x = float(got[0][n]), got[0][:n]
        stuck = [i for i, price in zip(open_, got[2], strict=False) if price > 1e-7]
        if demand:
            stuck += [i for i in open_ if i not in stuck and level >= demand[i] - 1e-9]
        for i in stuck or open_:
            frozen[i] = level
    return [[float(x[at[i, p]]) for p in range(len(paths))] for i, paths in enumerate(flows)]
