"""Choice of method, strategy and their explanation."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from boundpath.search import ldp, single

#: Above this many links a graph is not broadcast to kernels: the DataFrame loops take over.
KERNEL_LINKS = 2_000_000


@dataclass(frozen=True)
class PathPlan:
    method: str
    strategy: str
    why: str


def choose_method(n_link_bounds: int, n_path_bounds: int, objective: str = "hops") -> str:
    """The cheapest exact method: breadth first, least cost, layered relaxation, or the general search."""
    if n_path_bounds == 0:
        return "links" if objective == "hops" else "links_cost"
    if n_path_bounds == 1 and objective == "hops":
        return "single"
    return "general"


def choose_strategy(links: DataFrame, limit: int = KERNEL_LINKS) -> str:
    """``kernel`` where the graph has a checked size and may be broadcast, else ``loop``."""
    return "kernel" if links.limit(limit + 1).count() <= limit else "loop"


def plan(n_link_bounds: int, path_bounds: tuple[str, ...], objective: str) -> PathPlan:
    method = choose_method(n_link_bounds, len(path_bounds), objective)
    why = {"links": "no path bound, hops", "links_cost": "no path bound, a cost", "single": "one path bound, hops", "general": "several path bounds, or a bound with a cost"}[method]
    return PathPlan(method, "loop", why)


def solve(links: DataFrame, requests: DataFrame, path_bounds: tuple[str, ...] = ("delay", "cost"), objective: str = "hops", policy: str | None = None, max_hops: int | None = None, strategy: str = "loop", **options) -> DataFrame:
    """Answers by the method that the bounds allow, or by the named policy.

    max_hops None: any loop-free path; with a number, requests undecided there come back as CAPPED.  strategy ``auto``: with delay and cost bounds, a graph of checked size is searched by kernels."""
    from boundpath.baselines import exact, kernels

    name = policy or plan(1, path_bounds, objective).method
    if name == "links":
        return single.ldp_links(links, requests, max_hops)
    if name == "links_cost":
        return single.ldp_links_cost(links, requests, objective)
    if name == "single":
        return single.ldp_single(links, requests, path_bounds[0], max_hops)
    if name == "general" and strategy == "auto" and set(path_bounds) == {"delay", "cost"} and not options and choose_strategy(links) == "kernel":
        return kernels.search(links, requests, "ldp_prefix", objective, max_hops)
    if name == "general":
        return ldp.ldp_general(links, requests, ldp.PathQuery(metrics=path_bounds, objective=objective, max_hops=max_hops, **options)).answers
    if name == "ext_dijkstra":
        return exact.ext_dijkstra(links, requests, options.get("metric", "cost"))
    if name == "iter_bellman_ford":
        return exact.iter_bellman_ford(links, requests, path_bounds[0], max_hops)
    if name == "ebfs":
        return exact.ebfs(links, requests, objective, max_hops, **options)
    raise ValueError(f"unknown policy {name!r}")


def explain_path(links: DataFrame, requests: DataFrame, path_bounds=("delay", "cost"), objective: str = "hops") -> str:
    """The plan of the method and Spark's physical plan of one forward step."""
    p = plan(1, tuple(path_bounds), objective)
    reqs = ldp.with_classes(requests, path_bounds)
    step = ldp.grow_one(ldp.first_layer(reqs, path_bounds), links, ldp.class_table(reqs, path_bounds), path_bounds, True)
    return f"method {p.method} ({p.why}), strategy {choose_strategy(links)}\n" + step._jdf.queryExecution().toString()
