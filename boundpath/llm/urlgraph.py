"""URL filtering by rules and by trust spread over the host link graph.

Rules name a host (with its subdomains) and a path prefix; the longest rule that fits decides.  For pages without a rule
the host's standing decides: personalised PageRank spreads trust along links from hosts with allowed pages, and distrust
against the links from hosts with blocked pages (who links to blocked hosts is suspect).  A host is blocked where its
distrust is at least ``floor`` of an average seed and exceeds its trust by ``ratio``.

Ranks are per host and stay in DataFrames: one join and one partial aggregate per step, each step stored.  Steps go on until
what later ones could still move is a tenth of the floor, so no host's verdict hangs on when they stop.  Dangling mass goes back to the
seeds.  Defined cases: null url or no ``://`` has empty host and path, no rule, and is allowed; null html has no links;
hosts without links and without seeds are allowed; repeated rows count as further evidence of the same links.
"""

from __future__ import annotations

from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from boundpath.llm.shared import materialise, read_table
from boundpath.loop import keep_counted

#: (verdict, host, path prefix): fixed values of the contract.
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
DAMPING, RATIO, FLOOR = 0.85, 1.0, 0.01


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"^(?s).*?://([^/?#]*)", 1), F.lit("")), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    """What follows the host, its slash included, up to ``?``, ``#`` or the end."""
    return F.coalesce(F.regexp_extract(url, r"^(?s).*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, null where none does.  Length: host and path characters."""
    rule = verdict = None
    for kind, name, prefix in sorted(rules, key=lambda r: (-len(r[1]) - len(r[2]), r)):
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(prefix)
        text = name + prefix
        rule = F.when(fits, text) if rule is None else rule.when(fits, text)
        verdict = F.when(fits, kind) if verdict is None else verdict.when(fits, kind)
    return (rule, verdict) if rule is not None else (F.lit(None).cast("string"), F.lit(None).cast("string"))


def host_edges(pages: DataFrame) -> DataFrame:
    """(src, dst, n) of links between different hosts.  pages: (host, html)."""
    link = r"""(?i)(?:href|src)\s*=\s*["']?\s*(?:[a-z][a-z0-9+.-]*:)?//([^/?#"'\s<>]+)"""
    found = pages.filter("host != ''").select("host", F.explode(F.array_distinct(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit(link), 1))).alias("to"))
    found = found.select(F.col("host").alias("src"), F.translate("to", _UPPER, _LOWER).alias("dst"))
    return found.filter("src != dst and dst != ''").groupBy("src", "dst").agg(F.count("*").cast("double").alias("n"))


def personalised_rank(edges: DataFrame, seeds: DataFrame, damping: float = DAMPING, tolerance: float = 1e-6) -> DataFrame:
    """(host, rank) of PageRank with restart at the seeds, to within ``tolerance`` in the sum of all ranks' errors; edges: (src, dst, n), seeds: (host,
    weight).  Mass at hosts without out-links returns to the seeds, so ranks sum to 1.

    Ranks are proportional to the sum of what walks of 0, 1, 2, ... links bring from the seeds.  Each term has at most ``damping`` of
    the mass of the one before, which bounds what is left out."""
    total = seeds.agg(F.sum("weight")).first()[0]
    if not total:
        return seeds.select("host", F.lit(0.0).alias("rank")).limit(0)
    seeds = materialise(seeds.filter("weight > 0").select("host", (F.col("weight") / total).alias("x")), "seeds")
    out = edges.groupBy("src").agg(F.sum("n").alias("all"))
    share = materialise(edges.join(out, "src").select("src", "dst", (F.col("n") / F.col("all") * damping).alias("share")), "links")
    terms, mass = [seeds], 1.0
    for step in count(1):
        sent = terms[-1].join(share, F.col("host") == F.col("src")).groupBy(F.col("dst").alias("host")).agg(F.sum(F.col("x") * F.col("share")).alias("x"))
        sent, seen = keep_counted(sent, "rank", mass=F.sum("x"))
        terms.append(sent)
        mass += seen["mass"] or 0.0
        # what is left out changes the sum, and with it every rank: twice its share
        if 2 * (seen["mass"] or 0.0) * damping / (1 - damping) <= tolerance * mass:
            break
        if step % 8 == 0:
            before = _sum_terms(terms[:-1])
            terms = [materialise(before, "rank"), sent]
    return _sum_terms(terms).select("host", (F.col("x") / mass).alias("rank"))


def _sum_terms(terms: list[DataFrame]) -> DataFrame:
    out = terms[0]
    for term in terms[1:]:
        out = out.unionByName(term)
    return out.groupBy("host").agg(F.sum("x").alias("x"))


def host_standing(pages: DataFrame) -> DataFrame:
    """(host, trust, distrust, blocked) of all hosts with pages.  pages: (host, verdict of a rule or null, html)."""
    edges = materialise(host_edges(pages), "edges")
    votes = pages.filter("host != ''").groupBy("host").agg(
        F.count(F.when(F.col("verdict") == "allow", 1)).alias("good"), F.count(F.when(F.col("verdict") == "block", 1)).alias("bad"), F.count("*").alias("pages")
    )
    votes = materialise(votes, "hosts")
    # a seed weighs as the share of its pages that the rules judged so
    n_bad = votes.filter("bad > 0").count()
    enough = 0.1 * FLOOR / max(1, n_bad)
    trust = personalised_rank(edges, votes.select("host", (F.col("good") / F.col("pages")).alias("weight")).filter("weight > 0"), tolerance=enough)
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n")
    distrust = personalised_rank(back, votes.select("host", (F.col("bad") / F.col("pages")).alias("weight")).filter("weight > 0"), tolerance=enough)
    both = votes.select("host").join(trust.withColumnRenamed("rank", "trust"), "host", "left").join(distrust.withColumnRenamed("rank", "distrust"), "host", "left")
    both = both.na.fill(0.0, ["trust", "distrust"])
    return both.withColumn("blocked", (F.col("distrust") > F.col("trust") * RATIO) & (F.col("distrust") * max(1, n_bad) >= FLOOR))


def filter_urls(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of ``pages`` (page_id, url, html)."""
    url = F.col("url").cast("string")
    rows = pages.select("page_id", host_of(url).alias("host"), path_of(url).alias("path"), F.col("html").cast("string").alias("html"))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("rule", rule).withColumn("verdict", verdict)
    standing = host_standing(rows).filter("blocked").select(F.col("host").alias("b_host"))
    out = rows.drop("html").join(standing, F.col("host") == F.col("b_host"), "left")
    final = F.coalesce("verdict", F.when(F.col("b_host").isNotNull(), "block").otherwise("allow"))
    return out.select("page_id", "host", "path", "rule", final.alias("verdict"))


def op8_url_filter(spark, sf_dir: str) -> DataFrame:
    return filter_urls(read_table(spark, sf_dir, "pages"))


QUERIES = {"op8_url_filter": op8_url_filter}
#: The given pages link to no other host, so ranks are the seeds' shares; with links SQL would have to iterate (tests do).
ORACLES = {
    "op8_url_filter": r"""
WITH p AS (SELECT page_id, coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), '') AS raw, coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
 q AS (SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM p),
 rules AS (SELECT * FROM (VALUES {rules}) r(kind, name, prefix)),
 fit AS (SELECT page_id, kind, name || prefix AS rule, row_number() OVER (PARTITION BY page_id ORDER BY length(name) + length(prefix) DESC) AS n FROM q JOIN rules ON (host = name OR ends_with(host, '.' || name)) AND starts_with(path, prefix)),
 judged AS (SELECT q.*, rule, kind FROM q LEFT JOIN fit ON fit.page_id = q.page_id AND n = 1),
 votes AS (SELECT host, count(*) FILTER (kind = 'allow') / count(*) AS good, count(*) FILTER (kind = 'block') / count(*) AS bad FROM judged WHERE host <> '' GROUP BY host),
 total AS (SELECT sum(good) AS good, sum(bad) AS bad, count(*) FILTER (bad > 0) AS n FROM votes),
 blocked AS (SELECT host FROM votes v, total t WHERE v.bad > 0 AND v.bad / t.bad > coalesce(v.good / nullif(t.good, 0), 0) * {ratio} AND v.bad / t.bad * t.n >= {floor})
SELECT page_id, host, path, rule, coalesce(kind, CASE WHEN host IN (SELECT host FROM blocked) THEN 'block' ELSE 'allow' END) AS verdict FROM judged""".format(
        rules=", ".join(f"('{k}', '{n}', '{x}')" for k, n, x in RULES), ratio=RATIO, floor=FLOOR
    )
}
