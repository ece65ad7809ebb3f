"""The path engine: worked examples, invariants, and every oracle at the smallest scale."""

import itertools
import random
from types import SimpleNamespace

import pytest
from pyspark.sql import functions as F

from boundpath import catalog
from boundpath.baselines import exact, flat, kernels
from boundpath.plans.plan import choose_method, explain_path, solve
from boundpath.search import ldp, single
from boundpath.services import allocate, embed, lp, pools, te
from boundpath.measures import measures
from boundpath.topology import networks

from .conftest import SF

REQ = "req_id bigint, src bigint, dst bigint, bw bigint, delay bigint, cost bigint"
LINK = "link_id bigint, src bigint, dst bigint, bw bigint, delay bigint, cost bigint"


def links_of(spark, arcs):
    return spark.createDataFrame([(i, *a) for i, a in enumerate(arcs)], LINK)


def random_graph(seed, n=9, m=26):
    rng = random.Random(seed)
    pairs = rng.sample([(a, b) for a in range(n) for b in range(n) if a != b], m)
    return [(a, b, rng.randint(1, 9), rng.randint(1, 20), rng.randint(1, 9)) for a, b in pairs]


def brute(arcs, r, objective="hops", most=8):
    """All feasible simple paths in canonical order."""
    out = {}
    for a, b, bw, d, c in arcs:
        if bw >= r[3]:
            out.setdefault(a, []).append((b, d, c))
    found = []

    def go(path, delay, cost):
        if path[-1] == r[2]:
            found.append((len(path) - 1, delay, cost, tuple(path)))
            return
        if len(path) <= most:
            for b, d, c in out.get(path[-1], ()):
                if b not in path and delay + d <= r[4] and cost + c <= r[5]:
                    go([*path, b], delay + d, cost + c)

    go([r[1]], 0, 0)
    return sorted(found, key=lambda p: p if objective == "hops" else (p[2], p[0], p[1], p[3]))


POOL = [(i, i % 9, (i * 4 + 3) % 9 if (i * 4 + 3) % 9 != i % 9 else (i + 1) % 9, 1 + i % 4, 25 + 5 * i, 10 + 3 * i) for i in range(9)]


def as_path(rows):
    return {r.req_id: tuple(r.path) if r.path else None for r in rows}


@pytest.mark.parametrize("objective", ["hops", "cost"])
@pytest.mark.parametrize("prune", [(), ("dom",), ("prefix",), ("dom", "prefix"), ("incumbents",), ("prefix", "incumbents")])
def test_answers_do_not_depend_on_pruning(spark, objective, prune):
    arcs = random_graph(3)
    want = {r[0]: (p[0][3] if (p := brute(arcs, r, objective, 5)) else None) for r in POOL}
    q = ldp.PathQuery(objective=objective, prune=frozenset(prune), max_hops=5)
    got = ldp.ldp_general(links_of(spark, arcs), spark.createDataFrame(POOL, REQ), q).answers.collect()
    assert as_path(got) == want


@pytest.mark.parametrize("seed", range(4))
@pytest.mark.parametrize("objective", ["hops", "cost"])
def test_kernels_are_exact(seed, objective):
    arcs = random_graph(seed)
    g = kernels.Graph(arcs)
    for r in POOL:
        ask = SimpleNamespace(req_id=r[0], src=r[1], dst=r[2], bw=r[3], delay=r[4], cost=r[5])
        best = brute(arcs, r, objective, 8)
        want = best[0][3] if best else None
        for method in ("edfs", "ebfs", "ebfs_suffix", "ldp", "ldp_prefix", "dfs", "kshort", "kshort_exact"):
            key, _ = kernels.SEARCHES[method](g, ask, objective, 8)
            assert (key[3] if key else None) == want, method
        key, _ = kernels.arc_ip(g, ask, objective, 8)
        place = 0
        assert (key[place] if key else None) == ((best[0][2] if objective == "cost" else best[0][0]) if best else None)


def test_example(spark):
    links = networks.example_links(spark)
    one = lambda bw, d, c: spark.createDataFrame([(0, 0, 3, bw, d, c)], REQ)
    general = lambda r: ldp.ldp_general(links, r, ldp.PathQuery(max_hops=3)).answers.first()
    r = general(one(5, 5, 5))
    assert (r.path, r.delay, r.cost) == ([0, 2, 1, 3], 3, 3)
    assert general(one(0, 5, 5)).path == [0, 2, 3]
    assert single.ldp_single(links, one(5, 5, 5)).first().path == [0, 2, 1, 3]
    layers = {(r.k, r.v): r.best_delay for r in ldp.forward_layers(links, one(5, 9, 9), 3).collect()}
    assert layers[1, 1] == 5 and layers[2, 1] == 2  # labels are per layer


def test_predecessors_do_not_drift(spark):
    """In-place relaxation would take the three-hop path of distance 4."""
    links = links_of(spark, [(0, 1, 9, 1, 1), (1, 2, 9, 1, 1), (0, 2, 9, 3, 1), (2, 3, 9, 2, 1)])
    r = single.ldp_single(links, spark.createDataFrame([(0, 0, 3, 1, 5, 99)], REQ)).first()
    assert (r.path, r.hops, r.delay) == ([0, 2, 3], 2, 5)


def test_verdicts(spark):
    arcs = [(0, 1, 9, 5, 1), (1, 2, 9, 5, 1), (3, 4, 9, 1, 1), (5, 6, 9, 1, 1), (6, 7, 9, -3, 1), (7, 6, 9, 1, 1)]
    asks = [(0, 0, 2, 1, 10, 9), (1, 0, 2, 1, 9, 9), (2, 0, 4, 1, 99, 9), (3, 2, 2, 1, 0, 9), (4, 5, 4, 1, 99, 9)]
    got = {r.req_id: r.status for r in single.ldp_single_status(links_of(spark, arcs), spark.createDataFrame(asks, REQ), 8).collect()}
    assert got == {0: "FOUND", 1: "INFEASIBLE", 2: "UNREACHABLE", 3: "FOUND", 4: "NEGATIVE_CYCLE"}
    capped = ldp.ldp_general(networks.example_links(spark), spark.createDataFrame([(0, 0, 3, 5, 5, 5)], REQ), ldp.PathQuery(max_hops=1)).answers.first()
    assert capped.status == "CAPPED"
    same = ldp.ldp_general(networks.example_links(spark), spark.createDataFrame([(0, 2, 2, 5, 5, 5)], REQ), ldp.PathQuery(max_hops=2)).answers.first()
    assert (same.status, same.hops, same.path) == ("FOUND", 0, [2])


def test_special_cases_agree(spark):
    arcs = random_graph(8)
    links = links_of(spark, arcs)
    reqs = spark.createDataFrame([(*r[:4], r[4], 1 << 40) for r in POOL], REQ)
    general = {r.req_id: r.hops for r in ldp.ldp_general(links, reqs, ldp.PathQuery(max_hops=8)).answers.collect()}
    assert {r.req_id: r.hops for r in single.ldp_single(links, reqs).collect()} == general
    assert {r.req_id: r.hops for r in exact.iter_bellman_ford(links, reqs).collect()} == general
    free = reqs.withColumn("delay", F.lit(1 << 40))
    assert {r.req_id: r.hops for r in single.ldp_links(links, free).collect()} == {r.req_id: r.hops for r in single.ldp_single(links, free).collect()}
    assert {r.req_id: r.cost for r in single.ldp_links_cost(links, free).collect()} == {r.req_id: r.cost for r in ldp.ldp_general(links, free, ldp.PathQuery(objective="cost", max_hops=8)).answers.collect()}


def test_k_best_all_and_pareto(spark):
    arcs = random_graph(5)
    links, reqs = links_of(spark, arcs), spark.createDataFrame(POOL, REQ)
    want = {r[0]: [p[3] for p in brute(arcs, r, "cost", 5)] for r in POOL}
    for k in (1, 3):
        got: dict = {}
        for r in ldp.ldp_k(links, reqs, k, max_hops=5).orderBy("req_id", "rank").collect():
            if r.path:
                got.setdefault(r.req_id, []).append(tuple(r.path))
        assert got == {i: p[:k] for i, p in want.items() if p}
    every = {(r.req_id, tuple(r.path)) for r in ldp.ldp_all(links, reqs, 5).collect() if r.path}
    assert every == {(i, p) for i, ps in want.items() for p in ps}
    front = {(r.req_id, r.delay, r.cost) for r in ldp.ldp_pareto(links, reqs, 5).collect() if r.path}
    for r in POOL:
        v = {(p[1], p[2]) for p in brute(arcs, r, "hops", 5)}
        assert {x[1:] for x in front if x[0] == r[0]} == {x for x in v if not any(y != x and y[0] <= x[0] and y[1] <= x[1] for y in v)}
    front2 = ldp.ldp_general(links, reqs, ldp.PathQuery(prune=frozenset({"prefix", "incumbents"}), pareto=True, max_hops=5)).answers
    assert {(r.req_id, r.delay, r.cost) for r in front2.collect() if r.path} == front
    for pruning in ("dom", "incumbents"):
        with pytest.raises(ValueError):
            ldp.PathQuery(k=2, prune=frozenset({pruning}))


def test_complete_paths_cut_suffixes(spark):
    arcs = random_graph(3)
    made = {}
    for prune in ((), ("incumbents",)):
        q = ldp.PathQuery(objective="cost", prune=frozenset(prune), max_hops=5)
        made[prune] = sum(s[3] for s in ldp.ldp_general(links_of(spark, arcs), spark.createDataFrame(POOL, REQ), q, stats=True).stats if s[1])
    assert made["incumbents",] < made[()]


def line(n, back=True):
    """A line of n links, with ways back that make circles."""
    return [(i, i + 1, 9, 1, 1) for i in range(n)] + [(i + 1, i, 9, 1, 1) for i in range(n) if back]


def test_no_length_is_too_long(spark):
    """A path of 10 links, more than the first pass looks at, is found by every method that is not told to stop before; stopping is reported."""
    links = links_of(spark, line(10))
    reqs = spark.createDataFrame([(0, 0, 10, 1, 20, 20), (1, 0, 10, 1, 9, 99), (2, 3, 20, 1, 99, 99), (3, 2, 5, 1, 99, 99)], REQ)
    want = {0: "FOUND", 1: "NONE", 2: "NONE", 3: "FOUND"}
    for objective in ("hops", "cost"):
        assert {r.req_id: r.status for r in solve(links, reqs, objective=objective).collect()} == want
        assert {r.req_id: r.status for r in exact.ebfs(links, reqs, objective, dominance=True).collect()} == want
        capped = {r.req_id: r.status for r in solve(links, reqs, objective=objective, max_hops=5).collect()}
        assert capped == {0: "CAPPED", 1: "NONE", 2: "NONE", 3: "FOUND"}
    for method in ("ldp", "ldp_prefix", "dfs", "kshort", "edfs", "ebfs_suffix", "kshort_exact"):
        assert {r.req_id: r.status for r in kernels.search(links, reqs, method).collect()} == want
    for run in (single.ldp_single, exact.iter_bellman_ford):
        assert {r.req_id: r.status for r in run(links, reqs).collect()} == want
    assert {r.req_id: r.hops for r in single.ldp_links(links, reqs).collect()} == {0: 10, 1: 10, 2: None, 3: 3}


def test_parallel_links_stay_apart(spark):
    """A fast and a cheap link between the same ends are two links: no path has the best of both."""
    links = links_of(spark, [(0, 1, 9, 1, 9), (0, 1, 9, 9, 1), (0, 1, 2, 1, 1), (1, 2, 9, 1, 1)])
    asks = [(0, 0, 2, 5, 5, 5), (1, 0, 2, 5, 99, 5), (2, 0, 2, 5, 5, 99), (3, 0, 2, 1, 5, 5)]
    got = {r.req_id: (r.status, r.delay, r.cost) for r in solve(links, spark.createDataFrame(asks, REQ)).collect()}
    assert got == {0: ("NONE", None, None), 1: ("FOUND", 10, 2), 2: ("FOUND", 2, 10), 3: ("FOUND", 2, 2)}


def test_whole_searches_by_enumeration(spark):
    """No cap, both objectives, on a graph full of circles."""
    arcs = random_graph(21, 7, 24)
    pool = [(r[0], r[1] % 7, r[2] % 7 if r[2] % 7 != r[1] % 7 else (r[1] + 1) % 7, *r[3:]) for r in POOL]
    links, reqs = links_of(spark, arcs), spark.createDataFrame(pool, REQ)
    for objective in ("hops", "cost"):
        want = {r[0]: (p[0][3] if (p := brute(arcs, r, objective, 99)) else None) for r in pool}
        for prune in (("dom", "prefix"), ("dom",)):
            q = ldp.PathQuery(objective=objective, prune=frozenset(prune))
            assert as_path(ldp.ldp_general(links, reqs, q).answers.collect()) == want
        assert as_path(exact.ebfs(links, reqs, objective, dominance=True, suffix=True).collect()) == want


def test_linear_program_equals_dijkstra(spark):
    """Without bounds the relaxed arc program is whole by itself and costs what the shortest path costs."""
    for seed in range(5):
        arcs = random_graph(40 + seed)
        for src, dst in ((0, 5), (3, 8)):
            eq = [([1.0 * (a[0] == v) - 1.0 * (a[1] == v) for a in arcs], 1.0 if v == src else 0.0) for v in range(9) if v != dst]
            got = lp.simplex([float(a[4]) for a in arcs], eq, [])
            best = kernels.Graph(arcs).least(src, 0, 3, False).get(dst)
            assert (got is None) == (best is None)
            if got:
                assert abs(got[1] - best) < 1e-9 and all(min(abs(x), abs(x - 1)) < 1e-9 for x in got[0])


def test_answers_without_broadcast(spark, monkeypatch):
    """Above the size limit the joins are Spark's choice; answers stay."""
    from boundpath import loop

    arcs, reqs = random_graph(4), spark.createDataFrame(POOL, REQ)
    links = links_of(spark, arcs)
    run = lambda: (as_path(ldp.ldp_general(links, reqs, ldp.PathQuery(max_hops=4)).answers.collect()), as_path(single.ldp_single(links, reqs).collect()))
    want = run()
    monkeypatch.setattr(loop, "SMALL_ROWS", 0)
    assert run() == want and "ResolvedHint" not in loop.small(reqs)._jdf.queryExecution().analyzed().toString()


def test_arc_program_equals_all_paths(spark):
    """The common rate over arcs is the least max-min rate over all loop-free paths."""
    arcs = random_graph(6, 5, 10)
    asks = [(0, 0, 3), (1, 1, 4), (2, 2, 0)]
    rows = te.te_arc_lp(links_of(spark, arcs), spark.createDataFrame(asks, "flow_id bigint, src bigint, dst bigint")).collect()
    every = [[list(zip(p[3], p[3][1:])) for p in brute(arcs, (0, s, t, 0, 10**6, 10**6))] for _, s, t in asks]
    got = lp.max_min(every, {(a, b): bw for a, b, bw, _, _ in arcs})
    assert all(every) and {round(r.rate, 6) for r in rows} == {round(min(sum(x) for x in got), 6)}


def test_skyline(spark):
    rows = spark.createDataFrame([(0, 2, 5, 1), (0, 6, 5, 1), (0, 3, 3, 1), (0, 3, 3, 1), (0, 1, 9, 1)], "g int, a int, b int, c int")
    for dims in (["a", "b"], ["a", "b", "c"]):
        assert sorted((r.a, r.b) for r in ldp.skyline(rows, ["g"], dims).collect()) == [(1, 9), (2, 5), (3, 3), (3, 3)]
    assert ldp.skyline(rows, ["g"], ["a", "b"], 4).count() == 5


def test_method_choice(spark):
    assert [choose_method(1, p, o) for p, o in ((0, "hops"), (0, "cost"), (1, "hops"), (1, "cost"), (2, "hops"))] == ["links", "links_cost", "single", "general", "general"]
    links, reqs = networks.example_links(spark), spark.createDataFrame([(0, 0, 3, 5, 5, 5)], REQ)
    assert solve(links, reqs, max_hops=3).first().path == [0, 2, 1, 3]
    assert solve(links, reqs, ("delay",)).first().path == [0, 2, 1, 3]
    assert solve(links, reqs, policy="ebfs", max_hops=3).first().path == [0, 2, 1, 3]
    assert solve(links, reqs, max_hops=3, strategy="auto").first().path == [0, 2, 1, 3]
    assert "method general" in explain_path(links, reqs)


def test_links_are_never_shared_beyond_capacity(spark):
    links = networks.n1_links(spark, SF)
    reqs = spark.range(30).select(F.col("id").alias("req_id"), (F.col("id") % 3).alias("src"), (5 + F.col("id") % 2).alias("dst"), F.lit(2).cast("bigint").alias("bw"), F.lit(9999).cast("bigint").alias("delay"), F.lit(99).cast("bigint").alias("cost"))
    decisions, loads = allocate.allocate(links, reqs)
    over = loads.join(links, "link_id").filter("load > bw or load < 0")
    assert over.count() == 0
    # one by one
    left = {(r.src, r.dst): [r.bw, r.delay, r.cost] for r in links.collect()}
    want = {}
    for r in reqs.orderBy("req_id").collect():
        g = kernels.Graph((s, t, b, x, c) for (s, t), (b, x, c) in left.items())
        key, _ = kernels.layered(g, r, "hops", 99)
        want[r.req_id] = key[3] if key else None
        for e in zip(key[3], key[3][1:]) if key else ():
            left[e][0] -= r.bw
    assert as_path(decisions.collect()) == want
    assert None in want.values() and any(want.values())


def test_two_flows_share_or_block(spark):
    """Least delay sends flow 1 over C and blocks flow 2; fewest hops under the bound leaves room."""
    links = links_of(spark, [(0, 1, 10, 15, 1), (0, 2, 10, 4, 1), (2, 1, 10, 4, 1)])
    flows = spark.createDataFrame([(1, 0, 1, 20), (2, 0, 2, 20)], "flow_id bigint, src bigint, dst bigint, delay bigint")
    for finder in ("ldp", "ldp_loop"):
        rates, loads = te.te_greedy(links, flows.filter("flow_id = 2").union(flows.filter("flow_id = 1")), finder, 8)
        got = {r.flow_id: r.rate for r in rates.collect()}
        assert got[1] + got[2] == 20000
    first = exact.ext_dijkstra_bounded(links, te.flow_requests(flows)).collect()
    assert as_path(first)[1] == (0, 2, 1)
    tight = te.flow_requests(flows.withColumn("delay", F.lit(10).cast("bigint")))
    assert as_path(single.ldp_single(links, tight).collect())[1] == (0, 2, 1)


def test_filling_ends_with_the_paths(spark):
    """A path of 18 links is used, and rounds that run out while flows have paths are an error."""
    links = links_of(spark, [(i, i + 1, 10, 1, 1) for i in range(18)])
    flows = spark.createDataFrame([(1, 0, 18, 99)], "flow_id bigint, src bigint, dst bigint, delay bigint")
    for finder in ("ldp", "ldp_loop"):
        assert te.te_greedy(links, flows, finder)[0].first().rate == 10000
    twice = links_of(spark, [(0, 1, 1, 1, 1), (0, 2, 1, 1, 1), (2, 1, 1, 1, 1)])
    one = spark.createDataFrame([(1, 0, 1, 99)], "flow_id bigint, src bigint, dst bigint, delay bigint")
    assert te.te_greedy(twice, one)[0].first().rate == 2000
    with pytest.raises(RuntimeError):
        te.te_greedy(twice, one, max_rounds=1)


@pytest.mark.parametrize("n", (3, 8))
def test_allocation_decides_every_request(spark, n):
    """All requests want the same best path in every round, so each round decides one."""
    links = links_of(spark, [a for k in range(2, n + 2) for a in ((0, k, 1, k, 1), (k, 1, 1, 1, 1))])
    reqs = spark.createDataFrame([(i, 0, 1, 1, 999, 99) for i in range(n)], REQ)
    got = {r.req_id: r.path for r in allocate.allocate(links, reqs)[0].collect()}
    assert got == {i: [0, i + 2, 1] for i in range(n)}


def test_simplex_and_fairness():
    x, value = lp.simplex([-3, -5], [], [([1, 0], 4), ([0, 2], 12), ([3, 2], 18)])
    assert abs(value + 36) < 1e-9 and abs(x[0] - 2) < 1e-9
    assert lp.simplex([1], [([1], 5)], [([1], 4)]) is None
    got = lp.max_min([[["a"]], [["a", "b"]], [["b"]], []], {"a": 2, "b": 10})
    assert [round(sum(r), 6) for r in got] == [1, 1, 9, 0]
    best, _ = lp.solve_binary([5, 4, 3], [([1, 1, 1], 2)], [([2, 3, 1], 4)])
    assert best == [0, 1, 1]


def test_fair_rates_are_max_min():
    """No flow can rise unless one that is no faster falls (a program for each flow)."""
    rng = random.Random(1)
    for _ in range(12):
        cap = {e: rng.randint(1, 9) for e in "abcdefg"}
        held = [[rng.sample("abcdefg", rng.randint(1, 3)) for _ in range(rng.randint(1, 3))] for _ in range(5)]
        got = lp.max_min(held, cap)
        rates, columns = [sum(x) for x in got], [(k, p) for k in range(5) for p in range(len(held[k]))]
        assert all(sum(x for f, ps in zip(held, got) for p, x in zip(f, ps) if e in p) <= cap[e] + 1e-6 for e in cap)
        for i in range(5):
            rows = [([1.0 * (e in held[k][p]) for k, p in columns], cap[e]) for e in cap]
            rows += [([-1.0 * (k == j) for k, p in columns], -rates[j] + 1e-7) for j in range(5) if j != i and rates[j] <= rates[i] + 1e-7]
            assert -lp.simplex([-1.0 * (k == i) for k, p in columns], [], rows)[1] <= rates[i] + 1e-4


def test_embedding_is_valid():
    cpu = {0: 10, 1: 10, 2: 10, 3: 10}
    arcs = [(a, b, 10, 1 + abs(a - b), abs(a - b)) for a, b in itertools.permutations(range(4), 2)]
    wires, nodes = [(0, 1, 4, 9), (1, 2, 4, 9), (0, 2, 4, 9)], {0: 3, 1: 4, 2: 5}
    demands = {(a, b): d for a, b, d, _ in wires}
    cost = {}
    for method in ("opt", "joint", "colgen", "auction"):
        sub = embed.Substrate(cpu, arcs)
        placed, routes = embed.embed_one(sub, nodes, wires, method, "ldp")
        assert len(set(placed.values())) == 3 and sub.fits(routes, demands)
        assert all(routes[a, b][0] == placed[a] and routes[a, b][-1] == placed[b] for a, b in routes)
        assert all(sum(sub.delay[e] for e in zip(p, p[1:])) <= 9 for p in routes.values())
        cost[method] = embed.embedding_cost(sub, placed, nodes, routes, demands, True)
    assert all(cost["opt"] <= c + 1e-9 for c in cost.values()) and cost["colgen"] <= cost["joint"] + 1e-9
    assert embed.place_auction(embed.Substrate(cpu, arcs), {0: 11})[0] is None


def simple_paths(arcs, s, t):
    out = {}
    for a, b, *_ in arcs:
        out.setdefault(a, []).append(b)

    def go(path):
        if path[-1] == t:
            yield tuple(path)
            return
        for x in out.get(path[-1], ()):
            if x not in path:
                yield from go([*path, x])

    return list(go([s]))


def test_embedding_optimum_by_enumeration():
    """Branch and bound against all placements with all combinations of paths; other algorithms are valid and no better."""
    rng = random.Random(4)
    for _ in range(6):
        cpu = {v: rng.randint(4, 20) for v in range(5)}
        arcs = [(a, b, rng.randint(2, 9), rng.randint(1, 9), rng.randint(1, 9)) for a, b in rng.sample(list(itertools.permutations(range(5), 2)), 14)]
        nodes = {i: rng.randint(1, 6) for i in range(3)}
        wires = [(a, b, rng.randint(1, 4), rng.randint(6, 20)) for a, b in ((0, 1), (1, 2), (0, 2))]
        sub, demands, best = embed.Substrate(cpu, arcs), {w[:2]: w[2] for w in wires}, None
        for choice in itertools.permutations(range(5), 3):
            placed = dict(enumerate(choice))
            if all(cpu[v] >= nodes[i] for i, v in placed.items()):
                every = [[p for p in simple_paths(arcs, placed[a], placed[b]) if sum(sub.delay[e] for e in zip(p, p[1:])) <= bound] for a, b, _, bound in wires]
                for combo in itertools.product(*every):
                    routes = {w[:2]: p for w, p in zip(wires, combo)}
                    if sub.fits(routes, demands):
                        cost = embed.embedding_cost(sub, placed, nodes, routes, demands, True)
                        best = cost if best is None else min(best, cost)
        got = embed.embed_one(sub, nodes, wires, "opt", "ldp")
        assert (got is None) == (best is None)
        if got:
            assert abs(embed.embedding_cost(sub, got[0], nodes, got[1], demands, True) - best) < 1e-6
        for method, finder in itertools.product(("joint", "colgen", "auction"), ("ldp", "dijkstra", "kpaths")):
            other = embed.embed_one(embed.Substrate(cpu, arcs), nodes, wires, method, finder)
            if other:
                assert sub.fits(other[1], demands) and all(sum(sub.delay[e] for e in zip(other[1][w[:2]], other[1][w[:2]][1:])) <= w[3] for w in wires)
                assert embed.embedding_cost(sub, other[0], nodes, other[1], demands, True) >= best - 1e-6
        split = embed.embed_one(embed.Substrate(cpu, arcs), nodes, wires, "colgen_split", "ldp")
        if split:
            load = {}
            for link, path, share in embed.flat(split[1]):
                for e in zip(path, path[1:]):
                    load[e] = load.get(e, 0) + share * demands[link]
            assert all(x <= sub.bw[e] + 1e-6 for e, x in load.items())
            assert all(abs(sum(share for _, share in found) - 1) < 1e-6 for found in split[1].values())


def test_pools_fill_whole_networks():
    """Copies until no more fit, the same by every exact finder; greedy filling leaves no flow a path with room."""
    arcs = random_graph(1, 30, 140)
    asks = [SimpleNamespace(req_id=i, flow_id=i, src=i, dst=(7 * i + 3) % 30, bw=1, delay=60, cost=40) for i in range(10)]
    asks = [a for a in asks if a.src != a.dst]
    rows = {m: [(x["copies"], x["hops"]) for x in pools.fill_pool(arcs, asks, m)] for m in ("ldp", "ldp_prefix", "ebfs", "ebfs_suffix", "edfs", "kshort_exact")}
    assert all(r == rows["ldp"] for r in rows.values()) and sum(c for c, _ in rows["ldp"]) > 20
    one = pools.Residual(arcs)
    for a, (copies, hops) in zip(asks, rows["ldp"]):  # one by one
        n = h = 0
        while (key := kernels.layered(one.graph, a, "hops", 99)[0]) is not None:
            one.take(key[3], 1)
            n, h = n + 1, h + len(key[3]) - 1
        assert (n, h) == (copies, hops)
    for a in asks:
        a.cost = 1 << 40
    got, load = pools.greedy_pool(arcs, asks, "ldp_prefix")
    cap = {(s, t): 1000 * b for s, t, b, _, _ in arcs}
    assert all(0 <= load[e] <= cap[e] for e in cap)
    rest = kernels.Graph((s, t, (cap[s, t] - load[s, t]) // len(asks), d, c) for s, t, _, d, c in arcs)
    assert all(kernels.layered(rest, a, "hops", 99)[0] is None for a in asks) and all(r > 0 for r, _, _ in got.values())


def test_depth_first_goes_straight_to_the_destination():
    """Without path bounds the least hops that are left steer the search: a few partial paths, where all loop-free ones up to the incumbent's length were made."""
    arcs = [(v, (v * k + k) % 300, 1, 1 + (7 * v + k) % 50, 1 + (3 * v + k) % 10) for v in range(300) for k in (1, 3, 5, 7) if v != (v * k + k) % 300]
    g, rng = kernels.Graph(arcs), random.Random(1)
    for _ in range(5):
        src, dst = rng.sample(range(300), 2)
        ask = SimpleNamespace(req_id=0, src=src, dst=dst, bw=1, delay=1 << 40, cost=1 << 40)
        key, made = kernels.edfs(g, ask, "hops", 300)
        assert key == kernels.ebfs(g, ask, "hops", 300)[0] and key is not None and made < 200


@pytest.mark.parametrize("objective", ["cost", "hops"])
def test_next_paths_beyond_the_last(objective):
    """All paths in order and none twice; where the destination is entered from the source only, the mesh behind the source isn't walked through."""
    for seed in range(20):
        arcs = random_graph(seed, 6, 16) + [(0, 1, 5, 3, 0)]
        r = SimpleNamespace(req_id=0, src=seed % 6, dst=(seed + 2) % 6, bw=seed % 4, delay=1 << 40, cost=1 << 40)
        want = brute(arcs, (0, r.src, r.dst, r.bw, r.delay, r.cost), objective)
        got = [k for k, _ in kernels.next_shortest(kernels.Graph(arcs), r, objective, 6, False)]
        assert [(k[1], k[2], k[0], k[3]) if objective == "cost" else k for k in got] == want

    class Asked(dict):
        times = 0

        def get(self, *a):
            self.times += 1
            return super().get(*a)

    mesh = [(a, b, 5, 1, 1) for a in range(8) for b in range(8) if a != b] + [(0, 9, 5, 1, 1)]
    g = kernels.Graph(mesh)
    g.out = Asked(g.out)
    r = SimpleNamespace(req_id=0, src=0, dst=9, bw=1, delay=1 << 40, cost=1 << 40)
    assert len([*kernels.next_shortest(g, r, objective, 9, False)]) == 1
    assert g.out.times < 100


@pytest.mark.parametrize("bounded", [True, False])
def test_program_of_a_network_beyond_its_limit(spark, monkeypatch, bounded):
    """Only links of the given paths are rows of the program, so the network may have more."""
    arcs = random_graph(1, 30, 140)
    flows = spark.createDataFrame([(i, i, (7 * i + 3) % 30, 60) for i in range(4)], "flow_id bigint, src bigint, dst bigint, delay bigint")
    rates = lambda: sorted(te.te_lp(links_of(spark, arcs), flows, 2, bounded).collect())
    want = rates()
    assert sum(r.rate for r in want) > 0
    monkeypatch.setattr(te, "LP_LINKS", 60)
    assert rates() == want


def test_hard_timeout_orders_a_link_over_its_frames(spark, tmp_path):
    """A link with more events of one trigger than an Arrow frame takes, the latest first: an allocation every hour of 20-minute steps."""
    rows = spark.range(60).select(F.col("id").alias("event_id"), F.expr("timestamp_ntz'2024-01-02 00:00:00' - make_interval(0, 0, 0, 0, 0, 20 * id)").alias("ts"), F.lit(5).cast("bigint").alias("user_id"), F.lit("view").alias("event_type"), F.lit(1.5).alias("value"), F.lit("{}").alias("props"))
    rows.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = sorted(catalog.queries()["timeout_hard"](spark, str(tmp_path)).collect(), key=lambda r: r.opened)
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    # 20 hours of three events; the last allocation's hour ends after the watermark
    assert [(r.link_id, r.load, r.n) for r in got] == [(5, 6, 3)] * 19 and {b.opened - a.opened for a, b in zip(got, got[1:])} == {3_600_000_000}


@pytest.mark.parametrize("name", ["bounds_map", "bounds_table"])
def test_bounds_come_from_a_table(spark, name):
    assert any("lineitem.parquet" in f for f in catalog.queries()[name](spark, SF).inputFiles())


def test_searches_over_arrays_count_like_the_plain_ones(monkeypatch):
    """Pools of a larger graph: the same copies, hops, searches and partial paths by arrays as by loops, which take too long on it."""
    arcs = random_graph(5, 60, 400)
    asks = [SimpleNamespace(req_id=i, src=i, dst=(7 * i + 3) % 60, bw=1 + i % 2, delay=20 + 3 * i, cost=10 + i) for i in range(20) if i != (7 * i + 3) % 60]
    got = {}
    for least in (10**9, 1):
        monkeypatch.setattr(kernels, "FLAT_LINKS", least)
        assert (kernels.Graph(arcs).flat() is None) == (least > 1)
        got[least] = {m: [{k: x for k, x in row.items() if not k.endswith("_ms")} for row in pools.fill_pool(arcs, asks, m)] for m in ("ldp", "ldp_prefix", "ebfs", "ebfs_suffix")}
        flows = [SimpleNamespace(flow_id=i, src=i, dst=(7 * i + 3) % 60, bw=1, delay=60, cost=1 << 40) for i in range(20) if i != (7 * i + 3) % 60]
        got[least].update({("greedy", m): pools.greedy_pool(arcs, flows, m) for m in ("ldp_prefix", "least_delay")})
    assert got[1] == got[10**9] and sum(r["copies"] for r in got[1]["ldp"]) > 20


def test_pools_in_parts_give_what_pools_in_order_give(spark, monkeypatch):
    monkeypatch.setattr(pools, "PART", 3)
    arcs = links_of(spark, random_graph(11, 12, 60))
    ask = "id AS req_id, id % 12 AS src, (id * 5 + 1 + int(id % 12 = (id * 5 + 1) % 12)) % 12 AS dst, 1L AS bw, 12L AS delay, 14L AS cost"
    kinds = {"layered_prefix": "ldp_prefix", "exhaustive": "ebfs", "cheapest": "least_cost"}
    asks = pools.as_pools([({"network": "n", "severity": v, "solver": s}, spark.range(n).selectExpr(*ask.split(", "))) for v, n in (("low", 20), ("few", 2)) for s in kinds])
    got = [sorted(pools.fill_pools({"n": arcs}, asks, kinds, scout=s).drop("map_ms", "allocate_ms").collect()) for s in (None, "layered_prefix")]
    assert got[0] == got[1] and len(got[0]) == 66
    took = {s: [r[4:7] for r in got[0] if r.severity == "low" and r.solver == s] for s in kinds}
    assert took["exhaustive"] == took["layered_prefix"] != took["cheapest"]  # the last one is run again, in order


def test_other_solvers_start_while_the_scout_goes_on(spark, monkeypatch):
    """Scouts tell the state after some requests; the rows are those of pools in order, whatever requests the others have."""
    monkeypatch.setattr(pools, "PART", 2)
    monkeypatch.setattr(pools, "STRETCH", 4)
    monkeypatch.setattr(pools, "BEHIND_S", 0)
    made, keep = [], pools.keep
    monkeypatch.setattr(pools, "keep", lambda df, tag: made.append(tag) or keep(df, tag))
    arcs = links_of(spark, random_graph(11, 12, 60))
    ask = "id AS req_id, id % 12 AS src, (id * 5 + 1 + int(id % 12 = (id * 5 + 1) % 12)) % 12 AS dst, 1L AS bw, 12L AS delay, 14L AS cost"
    kinds = {"layered_prefix": "ldp_prefix", "exhaustive": "ebfs", "more": "ebfs"}
    asks = pools.as_pools([({"network": "n", "severity": "low", "solver": s}, spark.range(9 if s != "more" else 11).selectExpr(*ask.split(", "))) for s in kinds])
    got = [sorted(pools.fill_pools({"n": arcs}, asks, kinds, scout=s).drop("map_ms", "allocate_ms").collect()) for s in (None, "layered_prefix")]
    assert got[0] == got[1] and len(got[0]) == 29
    assert sorted(made) == ["parts"] * 4 + ["scout"] * 3


def test_a_part_starts_from_what_was_taken(monkeypatch):
    """The state before a request is made at once, not arc by arc, and is that of the pool in order."""
    arcs = random_graph(5, 30, 200)
    asks = [SimpleNamespace(req_id=i, src=i, dst=(7 * i + 3) % 30, bw=1, delay=60, cost=40) for i in range(12) if i != (7 * i + 3) % 30]
    rows = pools.fill_pool(arcs, asks, "ldp_prefix")
    log = [x for row in rows[:6] for x in row["log"]]
    net = pools.Residual(arcs)
    for amount, *path in log:
        net.take(path, amount)
    monkeypatch.setattr(kernels.Graph, "fill", None)
    told = pools.Residual(arcs, taken=log)
    assert len(log) > 6 and (told.left, told.graph.out, told.graph.into) == (net.left, net.graph.out, net.graph.into)


def test_undominated_vectors_as_numbers():
    """Vectors of many vertices, up to the bounds, against every pair compared."""
    rng = random.Random(2)
    n, span, rise = 7, 9, 6
    front, known = flat._Front(n, span, rise), []
    for _ in range(12):
        rows = [(rng.randrange(n), rng.randrange(span), rng.randrange(rise)) for _ in range(8)]
        v, d, c = (kernels.flat.np.array(x, "int64") for x in zip(*rows, strict=True))
        assert front.beaten(v, d, c).tolist() == [any(k[0] == v and k[1] <= d and k[2] <= c for k in known) for v, d, c in rows]
        before = [any(k[0] == x[0] and k[1] <= x[1] and k[2] <= x[2] and k != x for k in rows[:i]) for i, x in enumerate(rows)]
        assert flat._beaten_before(v, d, c).tolist() == before
        front.add(v, d, c)
        known += rows


@pytest.mark.parametrize("back", [False, True])
def test_labels_are_mended_where_arcs_are_lost(back):
    rng, arcs = random.Random(5), random_graph(3, 40, 200)
    graphs = [kernels.Graph(arcs) for _ in range(2)]
    a, b = (flat.Flat(g.out, g.into, g.vertices) for g in graphs)
    for s, t, *_ in rng.sample(arcs, 120):
        now = rng.choice([-1, 0, 9])
        a.put(s, t, now), b.put(s, t, now)
        b._labels.clear()
        for weight in ("delay", "cost"):
            for most in (flat.FAR, 9):
                labels = [f.least(0, 1, getattr(f, weight), back, most).tolist() for f in (a, b)]
                assert labels[0] == labels[1]


def test_searches_to_one_destination_share_its_labels(monkeypatch):
    made = []
    monkeypatch.setattr(flat.Flat, "least", lambda *a, least=flat.Flat.least: made.append(a[1]) or least(*a))
    g = kernels.Graph(random_graph(8, 40, 300))
    f = flat.Flat(g.out, g.into, g.vertices)
    for src in f.names[1:9]:
        r = SimpleNamespace(src=src, dst=f.names[0], bw=1, delay=60, cost=60)
        key = kernels.least_metric(g, r, "hops", 40)[0]
        got = flat.shortest(f, r, 2)
        assert key[:3] == (got[1], got[0], got[2]) and key[3] == got[3]
        g.remove(*got[3][:2])
        f.put(*got[3][:2], -1)
    assert made == [f.at[f.names[0]]]


def test_layers_at_the_fewest_links_are_the_whole_ones():
    arcs = random_graph(8, 40, 120)
    g = kernels.Graph(arcs)
    f, seen = flat.Flat(g.out, g.into, g.vertices), 0
    for src, dst in itertools.permutations(f.names[:12], 2):
        r = SimpleNamespace(src=src, dst=dst, bw=1, delay=15, cost=15)
        met = f.meet(f.at[src], f.at[dst], 1)
        for prefix in (False, True):
            got, whole = met and flat.near(f, r, met, 40, prefix), flat.layers(f, r, 40, prefix)
            assert met or whole[-1][0][f.at[dst]] == flat.FAR
            if got:
                seen += 1
                assert len(got) == len(whole) and [x[f.at[dst]] for x in got[-1]] == [x[f.at[dst]] for x in whole[-1]]
                assert all((x == y)[y < flat.FAR].all() for have, want in zip(got, whole, strict=True) for y, x in zip(have, want, strict=True))
    assert seen > 50


def test_pools_run_in_tasks_of_their_own(spark):
    """Small tables of long pools: adaptive execution must not put all pools into one task."""
    names = [("customers", s, x) for s in ("low", "med", "tight") for x in ("layered", "layered_prefix", "exhaustive", "exhaustive_suffix")]
    asks = spark.createDataFrame([(*n, i, 0, 1, 1, 9, 9) for n in names for i in range(3)], "network string, severity string, solver string, " + REQ)
    arcs = links_of(spark, [(0, 1, 5, 1, 1)])
    done = pools.fill_pools({"customers": arcs}, asks, dict.fromkeys((n[2] for n in names), "ldp"))
    assert done.select(F.spark_partition_id().alias("p")).distinct().count() > len(names) // 2


def test_networks_are_sent_as_columns(spark):
    """Tasks of many networks get arrays, and make tuples of the arcs of their own."""
    arcs = {n: sorted(random_graph(n, 9, 20)) for n in (1, 2)}
    sent = pools.broadcast_networks({str(n): links_of(spark, a) for n, a in arcs.items()})
    assert not any(isinstance(x, list) for x in sent.value.values())
    assert {n: sorted(pools.arcs_of(sent, str(n))) for n in arcs} == arcs
    assert all(type(x) is int for x in pools.arcs_of(sent, "1")[0])


def test_networks_of_all_degrees_are_ranked_once(spark):
    from boundpath import loop

    two, four = (set(map(tuple, networks.n1_links(spark, SF, g).collect())) for g in (2, 4))
    assert two < four
    assert [k for k in loop._tables if k[1:3] == ("n1-arcs", SF)] == [(spark.sparkContext.applicationId, "n1-arcs", SF, 8)]


def test_the_scaling_comparison_has_all_customers(spark, tmp_path, monkeypatch):
    """Customers beyond key 10,000 are in its network and among its requests; the ``n2_links`` query keeps the network its SQL defines."""
    from boundpath.workloads import experiments

    n = 10030
    spark.range(n).selectExpr("id AS c_custkey", "int(id % 25) AS c_nationkey", "double(id % 97) AS c_acctbal").coalesce(1).write.parquet(f"{tmp_path}/customer.parquet")
    spark.range(2).selectExpr("id AS s_suppkey", "0 AS s_nationkey", "1.5D AS s_acctbal").coalesce(1).write.parquet(f"{tmp_path}/supplier.parquet")
    # one order and one line a customer, all at one supplier: every customer is followed by the next
    spark.range(n).selectExpr("id AS o_orderkey", "id AS o_custkey").coalesce(1).write.parquet(f"{tmp_path}/orders.parquet")
    lines = ("id AS l_orderkey", "1 AS l_linenumber", "id AS l_partkey", "0L AS l_suppkey", "2.0D AS l_quantity", "1.0D AS l_extendedprice", "timestamp_seconds(id) AS l_shipdate")
    spark.range(n).selectExpr(*lines).coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    monkeypatch.setattr(pools, "fill_pools", lambda nets, asks, *_, **__: (nets["customers"].collect(), asks.filter("network = 'customers' AND solver = 'layered' AND severity = 'low'").collect()))
    arcs, asks = experiments._scale(spark, str(tmp_path))
    assert {(r.src, r.dst) for r in arcs} == {(i, i + 1) for i in range(n - 1)}
    assert sorted((r.req_id, r.src, r.dst) for r in asks) == [(i, 37 * i % n, (53 * i + 11) % n) for i in range(n // 10)]
    assert max(r.dst for r in asks) >= 10000
    assert networks.n2_links(spark, str(tmp_path)).count() == 9999


def test_likely_pairs_are_all_pairs_of_a_small_hash(spark):
    """Many vertices: pairs are found by rests, not by asking all of them; few, or negative numbers: all are asked."""
    nodes = spark.range(40000, 42500).selectExpr("id * 7 AS v", "id % 10 AS x", "id % 11 AS y")
    u = (F.col("a.v") * 7919 + F.col("b.v") * 104729 + 31 * ((F.col("a.v") * F.col("b.v")) % 1009)) % 10007
    for below in (1, 3):
        likely, every = (networks._likely_pairs(nodes, n, below) for n in (10**6, 0))
        got = [sorted(q.filter(u < below).select("a.v", "b.v").collect()) for q in (likely, every)]
        assert got[0] == got[1] and len(got[0]) > 200
        assert likely.count() < every.count() / 500
        assert "NestedLoop" not in likely._jdf.queryExecution().toString()
    few = networks._likely_pairs(nodes.filter("x = 1").selectExpr("v - 300000 AS v", "x", "y"), 10**6, 1)
    assert few.count() == 250 * 249 // 2


def test_hubs_are_searched_over_arrays(spark, monkeypatch):
    """All arcs of a hub are looked at together, and filling one doesn't go over them; rows are those of the plain loops."""
    hub = [(0, i, 2, 1, 1) for i in range(1, 300)] + [(i, 0, 3, 1, 1) for i in range(1, 300)] + [(i, i + 1, 1 + i % 3, 2, 1) for i in range(1, 299)]
    arcs = hub + [a for a in random_graph(7, 300, 900) if 0 not in a[:2]]
    asks = [SimpleNamespace(req_id=i, src=1 + 7 * i, dst=280 - 5 * i, bw=1 + i % 2, delay=20, cost=20) for i in range(20)]
    monkeypatch.setattr(kernels, "FLAT_LINKS", 1)
    got, plain = {}, kernels._back
    for hub_from in (10**9, 256):
        monkeypatch.setattr(kernels, "HUB", hub_from)
        if hub_from == 256:
            monkeypatch.setattr(kernels, "_back", None)
        got[hub_from] = [{k: x for k, x in row.items() if not k.endswith("_ms")} for row in pools.fill_pool(arcs, asks, "ldp_prefix")]
    assert plain and got[256] == got[10**9] and sum(r["paths"] for r in got[256]) > 40


def test_energy(spark):
    util = spark.createDataFrame([(0, 1.0), (1, 0.5), (2, 0.0)], "link_id int, u double")
    r = measures.energy(util).first()
    assert (r.watts, r.idle, r.increase) == (5.55, 5.1, round(100 * (5.55 / 5.1 - 1), 6))


def test_reported_behaviour(spark):
    """What the sweeps are reported to show, on the tables of the middle size."""
    sf = "/root/testdata/sf0.01"
    q = catalog.queries()
    rows = lambda name: q[name](spark, sf).collect()
    w1 = {(r.network, r.severity, r.solver): r for r in rows("w1_scale")}
    for net in ("suppliers", "customers"):
        for sev in ("low", "med", "tight"):
            four = [w1[net, sev, s] for s in ("layered", "layered_prefix", "exhaustive", "exhaustive_suffix")]
            assert len({(r.served, r.copies, r.mean_hops) for r in four}) == 1  # all are exact
            assert four[1].generated <= four[0].generated <= four[2].generated and four[3].generated <= four[2].generated
    assert w1["customers", "low", "layered_prefix"].generated * 100 < w1["customers", "low", "exhaustive"].generated
    assert w1["customers", "low", "layered_prefix"].per_search < 3 * w1["suppliers", "low", "layered_prefix"].per_search  # fifteen times the vertices
    bed = {r.method: r for r in rows("w9_testbed")}
    assert all(bed[m].throughput >= bed["ext_dijkstra"].throughput and bed[m].mean_hops <= bed["ext_dijkstra"].mean_hops for m in bed)
    w5 = {(r.degree, r.stretch, r.finder): r for r in rows("w5_degree")}
    assert all(w5[8, s, "layered"].throughput >= w5[4, s, "layered"].throughput >= w5[1, s, "layered"].throughput for s in (4.0, 1.5, 1.0))
    assert sum(w5[g, 4.0, "layered"].throughput for g in (8, 6, 4)) >= sum(w5[g, 4.0, "least_delay"].throughput for g in (8, 6, 4))
    assert all(w5[g, 4.0, "layered"].mean_hops <= w5[g, 4.0, "least_delay"].mean_hops for g in (8, 6, 4, 2))


#: Queries without SQL: columns that say who a row is about, and what must hold for all rows.
INVARIANTS = {
    "alloc_strict": lambda r: (r.accepted == 1) == (r.path is not None and len(r.path) > 0),
    "alloc_first_commit": lambda r: (r.accepted == 1) == (r.path is not None and len(r.path) > 0),
    "c12_mapping_allocation": lambda r: r.map_ms > 0 and r.allocate_ms >= 0,
    "c2_path_times": lambda r: r.ms_per_search >= 0 and r.searches > 0,
    "embed_gap": lambda r: r.gap >= -1e-6,
    "lagrangian": lambda r: r.status == "NONE" or (r.delay <= 3535 and r.cost <= 50),
    "mixed_checked": lambda r: r.status == "NONE" or (r.delay <= 3535 and r.cost <= 50 and r.hops == r.path.count(">")),
    "reach_approx": lambda r: True,
    "te_arc_lp": lambda r: r.rate >= 0,
    "te_customers": lambda r: r.throughput > 0 and r.mean_hops >= 1,
    "te_fairness": lambda r: r.rate >= 0 and 0 < r.share <= 1,
    "te_greedy": lambda r: r.rate >= 0 and (r.rate == 0) == (r.paths == 0 or r.hops == 0),
    "te_greedy_dijkstra": lambda r: r.rate >= 0,
    "te_greedy_tables": lambda r: r.rate > 0,
    "te_lp_kshort": lambda r: r.rate >= 0,
    "te_lp_small": lambda r: r.rate >= 0,
    "te_scale": lambda r: r.rate > 0,
    "w10_robust": lambda r: r.copies >= r.served and r.requests >= r.served and r.searches >= r.requests,
    "w13_affected": lambda r: 0 <= r.req_id < 10,
    "w1_scale": lambda r: r.copies >= r.served and r.requests >= r.served and r.searches >= r.requests,
    "w3_program": lambda r: r.copies > 0,
    "w4_te_sweep": lambda r: 0 <= r.least <= r.median <= r.throughput,
    "w5_degree": lambda r: 0 <= r.least <= r.throughput and 0 <= r.energy_increase <= 17.65,
    "w6_embedding": lambda r: 0 <= r.ratio <= 1 and 0 <= r.energy_increase <= 17.65,
    "w7_chaining": lambda r: 0 <= r.ratio <= 1 and 0 <= r.energy_increase <= 17.65,
    "w8_optimum": lambda r: 0 <= r.ratio <= 1 and 0 <= r.energy_increase <= 17.65,
    "w9_testbed": lambda r: r.throughput > 0 and r.mean_hops >= 2,
}
EMBED = {n: (lambda r: (r.accepted == 1) == (r.cost is not None) and (not r.accepted or r.load > 0)) for n in catalog.queries() if n.startswith(("embed_", "chain_")) and n not in catalog.oracle_sql() and n != "embed_gap"}


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_oracle(spark, name):
    import glob
    import os
    import re

    import duckdb
    import pandas as pd

    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    a = catalog.queries()[name](spark, SF).toPandas()
    b = con.sql(catalog.oracle_sql()[name]).df()
    assert sorted(a.columns) == sorted(b.columns)

    def cell(v):
        if v is None or v is pd.NA or v is pd.NaT or v != v:
            return "null"
        return re.sub(r"\.0$", "", str(v))

    def rows(df):
        return sorted("|".join(cell(v) for v in r) for r in df[sorted(df.columns)].astype(object).itertuples(index=False, name=None))

    assert rows(a) == rows(b)


@pytest.mark.parametrize("name", sorted(set(catalog.queries()) - set(catalog.oracle_sql())))
def test_invariants(spark, name):
    rows, holds = catalog.queries()[name](spark, SF).collect(), (INVARIANTS | EMBED)[name]
    assert rows and all(holds(r) for r in rows)


@pytest.mark.parametrize("gone", [("boundpath/llm", "tests/llm"), ("boundpath/llm", "tests/llm", "corpus_pipeline.py")])
def test_entry_without_the_training_data_operators(tmp_path, gone):
    """The path queries stay when the folders of the training-data operators are deleted."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    top, copy = Path(__file__).resolve().parent.parent, tmp_path / "repo"
    shutil.copytree(top, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "*.json", "*.md"))
    for name in gone:
        shutil.rmtree(copy / name) if (copy / name).is_dir() else (copy / name).unlink(missing_ok=True)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); print(len(q), set(o) <= set(q), any(n.startswith('op') or n == 'pipeline' for n in q))"
    done = subprocess.run([sys.executable, "-B", "-c", code], cwd=copy, capture_output=True, text=True, check=True, timeout=120)
    assert done.stdout.split() == [str(len(catalog.queries())), "True", "False"]


def test_entry(spark):
    assert catalog.entry(spark, SF).count() == 10
