"""Layered double-pass search as a loop of DataFrame joins.

Requests with one source and equal bounds form a class and share the forward pass.  A layer k holds the vertices a walk
of exactly k links can reach, with the least value of each metric (the prefix labels), kept in the same aggregate.  A suffix grows
backwards from the destination; it survives if its vertex is in the layer, is not on the suffix, and can still meet the
bounds with the label of that vertex.

Two backward passes share these steps:

* *first arrivals* (fewest hops): every request whose destination appears within a few layers is walked back from the length at which it first does,
  through the layers of just that length.  All requests go together: those of a shorter length join the walk when it
  has come down to their layer.  Most requests are answered here.
* *all lengths* (a cost objective, several answers, or what the first pass left open): suffixes of 1, 2, 3, ... links of every total
  length at once, against the least label of a vertex over all layers.  A suffix is also dropped if one of fewer links at its vertex is no worse
  in any metric, so the walk ends by itself, at the latest after V - 1 links: nothing has to be capped.

``by_length`` walks every length on its own and counts what it makes.  Answers follow one canonical order (objective,
hops, metrics, vertices), so every pruning set and pass gives the same path.  With ``max_hops``, requests that are undecided there get the status CAPPED.

Metrics are columns ``delay`` and ``cost``; more can be declared.  Weights are non-negative integers.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.loop import SMALL_ROWS, empty, keep, keep_counted, small
from boundpath.operators.skyline import beaten_by_older, skyline

PRUNINGS = frozenset({"dom", "prefix", "bound", "incumbents"})
#: Steps that one job takes before its result is stored.
STRIDE = 3
#: Layers of the first pass, in two jobs; destinations that are farther are left to the second pass.
NEAR = 8
#: Steps of the label search that one job takes.
RELAX = 6


@dataclass(frozen=True)
class PathQuery:
    """What is asked of the links: metrics bounded end to end (columns of links and requests alike), the objective
    (``hops`` or a metric), pruning, and the longest path considered (None: any loop-free path)."""

    metrics: tuple[str, ...] = ("delay", "cost")
    objective: str = "hops"
    prune: frozenset[str] = field(default_factory=lambda: frozenset({"dom", "prefix"}))
    max_hops: int | None = None
    k: int = 1
    keep_all: bool = False
    pareto: bool = False

    def __post_init__(self):
        if unknown := set(self.prune) - PRUNINGS:
            raise ValueError(f"unknown pruning {sorted(unknown)}")
        if (self.k > 1 or self.keep_all) and self.prune & {"dom", "incumbents"}:
            raise ValueError("dominance keeps one path per vector: it can't be used when several paths are asked for")
        if self.objective != "hops" and self.objective not in self.metrics:
            raise ValueError(f"objective {self.objective!r} is not a metric")

    @property
    def order(self) -> list[str]:
        first = [self.objective] if self.objective != "hops" else []
        return first + ["hops", *[m for m in self.metrics if m != self.objective], "path"]

    @property
    def single(self) -> bool:
        """One answer of fewest hops."""
        return self.objective == "hops" and self.k == 1 and not self.keep_all and not self.pareto

    def within(self, extra: str = "") -> str:
        """SQL: totals (plus labels, if their prefix is given) keep all bounds."""
        return " and ".join(f"(max_{x} is null or {x}{f' + {extra}{x}' if extra else ''} <= max_{x})" for x in self.metrics)


def prune_links(links: DataFrame, requests: DataFrame) -> DataFrame:
    """Links that some class of requests may use: its bandwidth bound is met.  Adds class_id and the classes' bounds."""
    classes = requests.select("class_id", "bw").distinct().withColumnRenamed("bw", "bw_min")
    return links.join(small(classes), F.col("bw") >= F.col("bw_min")).drop("bw_min")


def with_classes(requests: DataFrame, metrics) -> DataFrame:
    """Adds class_id: the least req_id among requests of one source and equal bounds."""
    bounds = ["src", "bw", *metrics]
    ids = requests.groupBy(*bounds).agg(F.min("req_id").alias("class_id"))
    same = None
    for c in bounds:
        test = requests[c].eqNullSafe(ids[c])
        same = test if same is None else same & test
    return requests.join(ids, same).select(requests["*"], "class_id")


def first_layer(requests: DataFrame, metrics) -> DataFrame:
    one = requests.select("class_id", F.col("src").alias("v"), *[F.lit(0).cast("bigint").alias(f"best_{m}") for m in metrics]).distinct()
    return one.select("class_id", F.lit(0).alias("k"), "v", *[f"best_{m}" for m in metrics])


def grow_one(layer: DataFrame, links: DataFrame, classes: DataFrame, metrics, exclude: bool) -> DataFrame:
    """The next layer: one row per (class, vertex) with the least value of every metric.

    exclude: vertices whose least value already breaks a bound leave the layer.  The source never comes back."""
    f = layer.select("class_id", "k", F.col("v").alias("u"), *[f"best_{m}" for m in metrics])
    step = f.join(links, F.col("u") == links["src"]).join(classes, "class_id").filter((F.col("bw") >= F.col("bw_min")) & (F.col("dst") != F.col("c_src")))
    ends = ["class_id", (F.col("k") + 1).alias("k"), F.col("dst").alias("v")]
    if not metrics:
        return step.select(*ends).distinct()
    grown = step.groupBy(*ends).agg(*[F.min(F.col(f"best_{m}") + F.col(m)).alias(f"best_{m}") for m in metrics])
    if exclude:
        limit = classes.select("class_id", *[f"max_{m}" for m in metrics])
        grown = grown.join(limit, "class_id").filter(" and ".join(f"(max_{m} is null or best_{m} <= max_{m})" for m in metrics)).drop(*[f"max_{m}" for m in metrics])
    return grown


def class_table(requests: DataFrame, metrics) -> DataFrame:
    return requests.select("class_id", F.col("src").alias("c_src"), F.col("bw").alias("bw_min"), *[F.col(m).alias(f"max_{m}") for m in metrics]).distinct()


def forward_layers(links: DataFrame, requests: DataFrame, max_hops: int, metrics=("delay", "cost"), labels: bool = True) -> DataFrame:
    """All layers 0 to max_hops of every class: class_id, k, v, best_*."""
    reqs = with_classes(requests, metrics)
    classes = small(keep(class_table(reqs, metrics)))
    layer = keep(first_layer(reqs, metrics))
    layers = layer
    for _ in range(max_hops):
        layer, seen = keep_counted(grow_one(layer, links, classes, metrics, labels))
        if not seen["rows"]:
            break
        layers = layers.unionByName(layer)
    return layers


@dataclass
class Result:
    """answers: req_id, status, hops, metrics, path (array), rank; stats: length n, step, generated, kept, completed."""

    answers: DataFrame
    stats: list[tuple]


def _arcs(links: DataFrame, metrics) -> DataFrame:
    return links.select(F.col("src").alias("u"), F.col("dst").alias("to"), "bw", *[F.col(x).alias(f"w_{x}") for x in metrics])


def _starts(reqs: DataFrame, metrics) -> DataFrame:
    """Requests as suffixes without links, at their destinations."""
    zero = [F.lit(0).cast("bigint").alias(x) for x in metrics]
    return reqs.select("req_id", "class_id", "src", F.col("bw").alias("bw_min"), *[F.col(x).alias(f"max_{x}") for x in metrics], F.col("dst").alias("head"), F.array("dst").alias("path"), *zero)


def _extend(head: DataFrame, arcs: DataFrame, gate: DataFrame, metrics) -> DataFrame:
    """Suffixes one link longer: their new vertex is in the gate (class_id, v, best_*) and not yet on them."""
    g = gate.select(F.col("class_id").alias("g_class"), F.col("v").alias("g_v"), *[f"best_{x}" for x in metrics])
    rows = head.join(arcs, F.col("head") == F.col("to")).filter("bw >= bw_min")
    rows = rows.join(g, (F.col("class_id") == F.col("g_class")) & (F.col("u") == F.col("g_v")))
    return rows.filter(~F.array_contains("path", F.col("u"))).withColumns({x: F.col(x) + F.col(f"w_{x}") for x in metrics})


def _shape(rows: DataFrame, metrics, *more: str) -> DataFrame:
    columns = ["req_id", "class_id", "src", "bw_min", *[f"max_{x}" for x in metrics]]
    return rows.select(*columns, F.col("u").alias("head"), F.concat(F.array("u"), "path").alias("path"), *metrics, *more)


def _complete_beat(rows: DataFrame, complete: DataFrame, q: PathQuery) -> DataFrame:
    """Rows that no complete path beats in every metric, whatever their rest (with labels, the least rest)."""
    least = {x: F.col(x) + F.col(f"best_{x}") if "prefix" in q.prune else F.col(x) for x in q.metrics}
    known = complete.select(F.col("req_id").alias("c_req"), *[F.col(x).alias(f"c_{x}") for x in q.metrics])
    beaten, less = F.col("req_id") == F.col("c_req"), F.lit(False)
    for x in q.metrics:
        beaten = beaten & (F.col(f"c_{x}") <= least[x])
        less = less | (F.col(f"c_{x}") < least[x])
    return rows.join(known, beaten & less, "left_anti")


def walk_back(arcs: DataFrame, layers: dict[int, DataFrame], start: DataFrame, longest: int, q: PathQuery) -> DataFrame:
    """All surviving paths of the requests in ``start`` (suffixes without links, and ``n``, the number of links of their paths, at most ``longest``)."""
    m = q.metrics
    columns = [c for c in start.columns if c != "n"]
    head = None
    for k in range(longest, 0, -1):
        mine = start.filter(F.col("n") == k).select(*columns)
        head = mine if head is None else head.unionByName(mine)
        rows = _extend(head, arcs, layers[k - 1], m)
        if "prefix" in q.prune:
            rows = rows.filter(q.within("best_"))
        head = _shape(rows, m)
        if "dom" in q.prune:
            head = skyline(head, ["req_id", "head"], list(m))
        if (longest - k) % STRIDE == STRIDE - 1 and k > 1:
            head = keep(head, "suffixes")
    return head


def first_arrivals(links: DataFrame, reqs: DataFrame, q: PathQuery) -> DataFrame | None:
    """The best path of each request among those of the length at which its destination first appears, if that is within
    NEAR layers and one of them keeps the bounds."""
    m, exclude = q.metrics, "prefix" in q.prune
    classes = small(keep(class_table(reqs, m)))
    ends = reqs.select("req_id", "class_id", F.col("dst").alias("v"))
    horizon = NEAR if q.max_hops is None else min(NEAR, q.max_hops)
    layers, arrived, top = {0: keep(first_layer(reqs, m))}, None, 0
    while top < horizon:
        grown, both = layers[top], None
        for _ in range(min(NEAR // 2, horizon - top)):
            grown = grow_one(grown, links, classes, m, exclude)
            both = grown if both is None else both.unionByName(grown)
        table, seen = keep_counted(both, "layers", deepest=F.max("k"))
        if not seen["rows"]:
            break
        for k in range(top + 1, seen["deepest"] + 1):
            layers[k] = table.filter(F.col("k") == k)
        near = ends.join(table, ["class_id", "v"]).groupBy("req_id").agg(F.min("k").alias("n"))
        arrived = near if arrived is None else arrived.unionByName(near).groupBy("req_id").agg(F.min("n").alias("n"))
        arrived, met = keep_counted(arrived, "arrived", longest=F.max("n"))
        top = seen["deepest"]
        if met["rows"] == ends.count() or top % (NEAR // 2):
            break
    if arrived is None or not met["rows"]:
        return None
    start = _starts(reqs, m).join(F.broadcast(arrived) if met["rows"] <= SMALL_ROWS else arrived, "req_id")
    paths = walk_back(_arcs(links, m), layers, start, met["longest"], q).filter(q.within())
    return keep(best_of(paths.select("req_id", (F.size("path") - 1).alias("hops"), *m, "path"), q), "found")


def least_labels(links: DataFrame, reqs: DataFrame, metrics, bounded: bool = True) -> DataFrame:
    """(class_id, v, best_*): the least value of each metric over all walks from the class's source, of any number of links.

    bounded: vertices beyond a bound leave.  metrics may be empty: all vertices that can be reached.  A job takes RELAX steps in one plan without
    branches, since a vertex counts as its own neighbour at no cost; when a job changes neither the number of labels nor their sums, none
    can fall any more."""
    names = [f"best_{x}" for x in metrics]
    classes = small(keep(class_table(reqs, metrics)))
    stay = links.select("dst").union(links.select("src")).distinct()
    every = links.select("src", "dst", "bw", *metrics).unionByName(stay.select(F.col("dst").alias("src"), "dst", F.lit(1 << 62).alias("bw"), *[F.lit(0).cast("bigint").alias(x) for x in metrics]))
    every = keep(every, "arcs")
    limits = [f"(max_{x} is null or best_{x} <= max_{x})" for x in metrics] if bounded else []
    known, before = first_layer(reqs, metrics).select("class_id", "v", *names), None
    while True:
        for _ in range(RELAX):
            step = known.join(every, F.col("v") == F.col("src")).join(classes, "class_id").filter("bw >= bw_min")
            ends = ["class_id", F.col("dst").alias("v")]
            if metrics:
                step = step.withColumns({f"best_{x}": F.col(f"best_{x}") + F.col(x) for x in metrics})
                step = step.filter(" and ".join(limits)) if limits else step
                known = step.groupBy(*ends).agg(*[F.min(n).alias(n) for n in names])
            else:
                known = step.select(*ends).distinct()
        known, seen = keep_counted(known, "labels", **{n: F.sum(n) for n in names})
        if seen == before:
            return known
        before = seen


def all_lengths(links: DataFrame, reqs: DataFrame, q: PathQuery) -> tuple[DataFrame | None, DataFrame | None]:
    """(found, undecided): the answers over paths of every length at once, and the requests (req_id) that max_hops leaves undecided."""
    m, labels = q.metrics, "prefix" in q.prune
    gate = least_labels(links, reqs, m if labels else (), labels)
    if not labels:
        gate = gate.select("class_id", "v", *[F.lit(0).cast("bigint").alias(f"best_{x}") for x in m])
    gate, arcs = small(gate), _arcs(links, m)
    hopeful = gate.select("class_id", F.col("v").alias("head"))
    head, found, best, front = _starts(reqs, m).join(hopeful, ["class_id", "head"], "left_semi"), None, None, None
    for n in count(1):
        if q.max_hops is not None and n > q.max_hops:
            return found, keep(head.select("req_id").distinct())
        rows = _extend(head, arcs, gate, m).filter(q.within("best_"))
        if best is not None and q.prune:
            # what is still made has more links than the paths found, so it loses every tie
            rows = rows.join(best, "req_id", "left").filter(f"__inc is null or {q.objective} + best_{q.objective} < __inc").drop("__inc")
        if found is not None and "incumbents" in q.prune and (q.pareto or q.objective != "hops"):
            rows = _complete_beat(rows, found, q)
        new = _shape(rows, m)
        if "dom" in q.prune:
            new = beaten_by_older(new, front, ["req_id", "head"], list(m), strict=q.pareto)
        new, seen = keep_counted(new, "suffixes", complete=F.sum(F.when(F.col("head") == F.col("src"), 1).otherwise(0)))
        if not seen["rows"]:
            return found, None
        if seen["complete"]:
            whole = new.filter("head = src").select("req_id", F.lit(n).alias("hops"), *m, "path")
            found = whole if found is None else found.unionByName(whole)
            if not q.keep_all:
                found = keep(best_of(found, q), "found")
            best = _incumbent(found, q)
        head = new.filter("head != src")
        if q.single and found is not None:
            head = head.join(small(found.select("req_id")), "req_id", "left_anti")
        if "dom" in q.prune:
            vectors = new.select("req_id", "head", *m)
            front = vectors if front is None else front.unionByName(vectors)
            if n % 6 == 0:
                front = keep(front, "front")


def _incumbent(found: DataFrame, q: PathQuery) -> DataFrame | None:
    """(req_id, __inc): the cost that a new path has to beat, that of the k-th best so far (none before there are k)."""
    if q.objective == "hops" or q.keep_all or q.pareto:
        return None
    ranked = found.groupBy("req_id").agg(F.sort_array(F.collect_list(q.objective)).alias("all"))
    return F.broadcast(ranked.filter(F.size("all") >= q.k).select("req_id", F.get("all", F.lit(q.k - 1)).alias("__inc"))) if q.k <= 64 else None


def ldp_general(links: DataFrame, requests: DataFrame, q: PathQuery = PathQuery(), stats: bool = False) -> Result:
    """The layered double-pass search for all requests at once; stats: each length on its own, counted."""
    if stats:
        return by_length(links, requests, q)
    m = q.metrics
    reqs = keep(with_classes(requests, m))
    found = reqs.filter("src = dst").select("req_id", F.lit(0).alias("hops"), *[F.lit(0).cast("bigint").alias(x) for x in m], F.array("src").alias("path"))
    away, undecided = reqs.filter("src != dst"), None
    if q.single:
        near = first_arrivals(links, away, q)
        if near is not None:
            found = found.unionByName(near)
            away = keep(away.join(near.select("req_id"), "req_id", "left_anti"))
    if not empty(away):
        more, undecided = all_lengths(links, away, q)
        found = found if more is None else found.unionByName(more)
    return Result(_answers(requests, found, q, undecided), [])


def by_length(links: DataFrame, requests: DataFrame, q: PathQuery) -> Result:
    """Every length 1, 2, ... on its own through its own layers, one stored step after the other, with counts: (length, step, made, kept, complete)."""
    m = q.metrics
    reqs = keep(with_classes(requests, m))
    classes, arcs, start = small(keep(class_table(reqs, m))), _arcs(links, m), _starts(reqs, m)
    found = keep(reqs.filter("src = dst").select("req_id", F.lit(0).alias("hops"), *[F.lit(0).cast("bigint").alias(x) for x in m], F.array("src").alias("path")))
    log, layers = [], {0: keep(first_layer(reqs, m))}
    for n in count(1) if q.max_hops is None else range(1, q.max_hops + 1):
        layers[n], seen = keep_counted(grow_one(layers[n - 1], links, classes, m, "prefix" in q.prune))
        if not seen["rows"]:
            break
        head = start.filter("src != head")
        if q.single:
            head = head.join(found.select("req_id"), "req_id", "left_anti")
        head = head.join(layers[n].select("class_id", F.col("v").alias("head")), ["class_id", "head"], "left_semi")
        for k in range(n, 0, -1):
            made = _extend(head, arcs, layers[k - 1], m)
            kept = made.filter(q.within("best_")) if "prefix" in q.prune else made
            if q.objective != "hops" and q.prune and not q.keep_all and not q.pareto and q.k == 1:
                inc = found.select("req_id", F.col(q.objective).alias("__inc"))
                rest = f" + best_{q.objective}" if "prefix" in q.prune else ""
                kept = kept.join(inc, "req_id", "left").filter(f"__inc is null or {q.objective}{rest} <= __inc").drop("__inc")
            if "incumbents" in q.prune and (q.pareto or q.objective != "hops"):
                kept = _complete_beat(kept, found, q)
            kept = _shape(kept, m)
            if "dom" in q.prune:
                kept = skyline(kept, ["req_id", "head"], list(m))
            head, some = keep_counted(kept, "suffixes")
            log.append((n, k, made.count(), some["rows"], 0))
            if not some["rows"]:
                break
        else:
            new = keep(head.filter(q.within()).select("req_id", F.lit(n).alias("hops"), *m, "path"))
            log.append((n, 0, 0, 0, new.count()))
            found = found.unionByName(new)
            found = found if q.keep_all else keep(best_of(found, q))
    return Result(_answers(requests, found, q, None), log)


def best_of(found: DataFrame, q: PathQuery) -> DataFrame:
    if q.pareto:
        return skyline(found, ["req_id"], list(q.metrics))
    if q.k == 1:
        top = F.min(F.struct(*q.order)).alias("t")
        return found.groupBy("req_id").agg(top).select("req_id", *[F.col(f"t.{c}").alias(c) for c in ("hops", *q.metrics, "path")])
    rank = F.row_number().over(Window.partitionBy("req_id").orderBy(*q.order))
    return found.withColumn("r", rank).filter(F.col("r") <= q.k).drop("r")


def _answers(requests: DataFrame, found: DataFrame | None, q: PathQuery, undecided: DataFrame | None = None) -> DataFrame:
    m = q.metrics
    if found is None:
        found = requests.select("req_id", *[F.lit(None).cast("bigint").alias(x) for x in ("hops", *m)], F.lit(None).cast("array<bigint>").alias("path")).limit(0)
    if q.keep_all or q.pareto or q.k > 1:
        rank = F.row_number().over(Window.partitionBy("req_id").orderBy(*q.order))
        return found.select("req_id", F.lit("FOUND").alias("status"), F.col("hops").cast("bigint").alias("hops"), *m, "path", rank.alias("rank"))
    out = requests.select("req_id").join(found, "req_id", "left")
    status = F.when(F.col("hops").isNull(), "NONE").otherwise("FOUND")
    if undecided is not None:
        out = out.join(undecided.select("req_id", F.lit(True).alias("__open")), "req_id", "left")
        status = F.when(F.col("__open"), "CAPPED").otherwise(status)
    return out.select("req_id", status.alias("status"), F.col("hops").cast("bigint").alias("hops"), *m, "path", F.lit(1).alias("rank"))


def ldp_k(links, requests, k: int, objective: str = "cost", max_hops: int | None = None) -> DataFrame:
    """The k best paths of each request."""
    return ldp_general(links, requests, PathQuery(objective=objective, prune=frozenset({"prefix"}), k=k, max_hops=max_hops)).answers


def ldp_all(links, requests, max_hops: int | None = None) -> DataFrame:
    """All feasible loop-free paths (of at most ``max_hops`` links, if given)."""
    return ldp_general(links, requests, PathQuery(prune=frozenset({"prefix"}), keep_all=True, max_hops=max_hops)).answers


def ldp_pareto(links, requests, max_hops: int | None = None) -> DataFrame:
    """The feasible paths that no other dominates over the metrics."""
    return ldp_general(links, requests, PathQuery(pareto=True, max_hops=max_hops)).answers
