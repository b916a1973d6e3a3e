"""URL filters: rules, and trust that flows along links between hosts.

Rules come first: a rule is a host and a path start, fits the host with all its subdomains, and the longest one that fits
decides. Every other url is judged by its host. Two personalised PageRanks run over the host graph: trust from the hosts
whose pages rules allow, along the links, and distrust from the hosts whose pages rules block, against the links: who
links to blocked hosts is distrusted. A host is blocked if its distrust is at least ``floor`` times the mean share of a
host and ``margin`` times its trust.

The graph. An edge is a link from a page's host to another host, weighted by the number of links; links inside a host
don't count. Relative links are such links. Ranks move by joins of edges and hosts; mass at hosts without outgoing
links returns to the seeds.

Everything is DataFrame functions.

Scale: links are counted per pair of hosts before they move, so the graph is far smaller than the pages and a host with a
third of all links is one row per partner. The rules are a list given by the caller (at most ``MAX_RULES``), written into
the plan as one table of suffixes. Each round of ranks ends in a shared table every ``SAVE_EVERY`` rounds.

Defined results: a null url or one without ``://`` has empty host and path, fits no rule and is allowed, as is a host the
graph and the seeds say nothing about; null html has no links; repeated rows each keep their row and count their links.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
MAX_RULES = 100_000
SAVE_EVERY = 5
#: A link's tag, and in it the reference, if that has a host of its own. Apart, both patterns read every character once.
TAG = r"(?i)<a\b[^>]*"
REFERENCE = r"""(?i)^<a\b.*?[\s"'/]href\s*=\s*["']?(?:https?:)?(//[^"'\s#?]+)"""
#: Fixed values: (rule, verdict) of the query.
RULES = (("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block"))


def _rest(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(_rest(url), F.lit("")), r"^([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(_rest(url), F.lit("")), r"^[^/?#]*([^?#]*)", 1)


def with_rule(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES) -> DataFrame:
    """Add rule and rule_verdict, null where none fits. ``pages`` has host and path.

    The rules of each host suffix stand in a literal map, longest rule first; a url looks its suffixes up and takes the
    longest of what fits, ties to the smaller string.
    """
    if len(rules) > MAX_RULES:
        raise ValueError(f"more than {MAX_RULES} rules")
    by_host: dict[str, list[tuple[str, str]]] = {}
    for rule, verdict in sorted(rules, key=lambda x: (-len(x[0]), x[0])):
        by_host.setdefault(rule.split("/", 1)[0], []).append((rule, verdict))
    if not by_host:
        return pages.withColumn("rule", F.lit(None).cast("string")).withColumn("rule_verdict", F.lit(None).cast("string"))
    table = F.create_map(*(x for host, own in by_host.items() for x in (F.lit(host), F.array(*(F.struct(F.lit(r).alias("rule"), F.lit(v).alias("verdict")) for r, v in own)))))
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    there = F.flatten(F.filter(F.transform(suffixes, lambda s: F.try_element_at(table, s)), lambda x: x.isNotNull()))
    fits = F.filter(there, lambda r: F.startswith(F.col("path"), F.substring(r["rule"], F.instr(r["rule"], "/"), F.length(r["rule"]))))
    best = F.element_at(F.array_sort(fits, lambda a, b: F.when(F.length(a["rule"]) != F.length(b["rule"]), F.length(b["rule"]) - F.length(a["rule"])).when(a["rule"] < b["rule"], -1).when(a["rule"] > b["rule"], 1).otherwise(0)), 1)
    found = pages.withColumn("__best", F.when(F.size(fits) > 0, best))
    return found.withColumn("rule", F.col("__best.rule")).withColumn("rule_verdict", F.col("__best.verdict")).drop("__best")


def host_edges(pages: DataFrame, html: str = "html") -> DataFrame:
    """src, dst, n: links between different hosts. ``pages`` has host and html."""
    tags = F.regexp_extract_all(F.coalesce(F.col(f"`{html}`"), F.lit("")), F.lit(TAG), 0)
    links = F.transform(tags, lambda x: F.regexp_extract(x, "(?s)" + REFERENCE, 1))
    hosts = F.transform(links, lambda x: host_of(F.concat(F.lit("x:"), x)))
    out = pages.where(F.col("host") != "").select(F.col("host").alias("src"), F.explode(hosts).alias("dst"))
    return out.where("dst <> '' and dst <> src").groupBy("src", "dst").agg(F.count("*").alias("n"))


def ranks(edges: DataFrame, seeds: DataFrame, out: str, damping: float = 0.85, rounds: int = 15) -> DataFrame:
    """Personalised PageRank (host, ``out``). ``edges``: src, dst, n; ``seeds``: host and weight, summing to 1 or empty."""
    degree = edges.groupBy("src").agg(F.sum("n").alias("total"))
    share = common.stored(edges.join(degree, "src").select("src", "dst", (F.col("n") / F.col("total")).alias("share")), "shares")
    sinks = share.select("src").distinct()
    rank = seeds.select("host", F.col("weight").alias("r"))
    if share.isEmpty():
        return rank.withColumnRenamed("r", out)
    for k in range(rounds):
        moved = share.join(rank, share["src"] == rank["host"]).groupBy("dst").agg(F.sum(F.col("r") * F.col("share")).alias("m")).select(F.col("dst").alias("host"), F.col("m"), F.lit(0.0).alias("weight"))
        stuck = rank.join(sinks, rank["host"] == sinks["src"], "left_anti").agg(F.coalesce(F.sum("r"), F.lit(0.0)).alias("stuck"))
        parts = moved.unionByName(seeds.select("host", F.lit(0.0).alias("m"), "weight")).groupBy("host").agg(F.sum("m").alias("m"), F.sum("weight").alias("weight"))
        rank = parts.join(F.broadcast(stuck)).select("host", (damping * F.col("m") + ((1 - damping) + damping * F.col("stuck")) * F.col("weight")).alias("r"))
        if k % SAVE_EVERY == SAVE_EVERY - 1 or k == rounds - 1:
            rank = common.stored(rank, f"rank-{out}")
    return rank.withColumnRenamed("r", out)


def seeds_of(hosts: DataFrame, count: str) -> DataFrame:
    """Each host's part of all pages that rules of one kind decide."""
    own = hosts.where(F.col(count) > 0)
    total = own.agg(F.sum(count).alias("total"))
    return own.join(F.broadcast(total)).select("host", (F.col(count) / F.col("total")).alias("weight"))


def judge(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, url: str = "url", html: str = "html", floor: float = 0.5, margin: float = 1.0) -> DataFrame:
    """``pages`` without its html, with host, path, rule, verdict and the host's trust and distrust."""
    kept = [c for c in pages.columns if c not in (html, "host", "path", "rule", "rule_verdict", "verdict", "trust", "distrust", "blocked")]
    base = pages.select(*(F.col(f"`{c}`") for c in kept), host_of(F.col(f"`{url}`")).alias("host"), path_of(F.col(f"`{url}`")).alias("path"), F.col(f"`{html}`").alias("__html"))
    edges = common.stored(host_edges(base, "__html"), "host-edges")
    ruled = with_rule(base.drop("__html"), rules)
    hosts = common.stored(ruled.groupBy("host").agg(F.count_if(F.col("rule_verdict") == "allow").alias("allowed"), F.count_if(F.col("rule_verdict") == "block").alias("denied")).where("host <> ''"), "hosts")
    trust = ranks(edges, seeds_of(hosts, "allowed"), "trust")
    distrust = ranks(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n"), seeds_of(hosts, "denied"), "distrust")
    both = trust.join(distrust, "host", "full_outer").select("host", F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"))
    n = both.select("host").unionAll(hosts.select("host")).distinct().agg(F.count("*").alias("n_hosts"))
    marked = both.join(F.broadcast(n)).select("host", "trust", "distrust", ((F.col("distrust") * F.col("n_hosts") >= floor) & (F.col("distrust") >= margin * F.col("trust"))).alias("blocked"))
    out = ruled.join(marked, "host", "left")
    verdict = F.coalesce("rule_verdict", F.when(F.col("blocked"), "block").otherwise("allow"))
    return out.select(*kept, "host", "path", "rule", verdict.alias("verdict"), F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"))


def op3_host_trust(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdict on every page's url."""
    pages = common.table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return judge(pages).select("page_id", "host", "path", "rule", "verdict", F.round("trust", 9).alias("trust"), F.round("distrust", 9).alias("distrust"))


def op3_sql(rounds: int = 15, damping: float = 0.85, floor: float = 0.5, margin: float = 1.0) -> str:
    """The query in DuckDB's SQL: rounds of ranks written out one after another."""
    rest = "CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END"
    rules = ", ".join(f"('{r}', '{v}', '{r.split('/', 1)[0]}', '/{r.split('/', 1)[1]}')" for r, v in RULES)
    low = lambda x: f"translate({x}, '{UPPER}', '{LOWER}')"
    reference = ("(?s)" + REFERENCE).replace("'", "''")
    parts = [
        f"rules(rule, verdict, rh, rp) AS (VALUES {rules})",
        f"p AS (SELECT page_id, html, {low("regexp_extract(rest, '^([^/?#]*)', 1)")} AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM (SELECT page_id, html, coalesce({rest}, '') AS rest FROM pages))",
        "fit AS (SELECT page_id, host, path, arg_max(struct_pack(rule := r.rule, verdict := r.verdict), length(r.rule)) AS best FROM (SELECT DISTINCT page_id, host, path FROM p) p JOIN rules r ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY ALL)",
        "ruled AS (SELECT p.page_id, p.host, p.path, f.best.rule AS rule, f.best.verdict AS rv FROM p LEFT JOIN fit f ON f.page_id = p.page_id AND f.host = p.host AND f.path = p.path)",
        f"l AS (SELECT host AS src, {low("regexp_extract(link, '^//([^/?#]*)', 1)")} AS dst FROM (SELECT host, regexp_extract(unnest(regexp_extract_all(coalesce(html, ''), '{TAG}', 0)), '{reference}', 1) AS link FROM p WHERE host <> ''))",
        "e AS (SELECT src, dst, count(*) AS n FROM l WHERE dst <> '' AND dst <> src GROUP BY ALL)",
        "h AS (SELECT host, count(*) FILTER (rv = 'allow') AS allow, count(*) FILTER (rv = 'block') AS block FROM ruled WHERE host <> '' GROUP BY ALL)",
    ]
    for kind, src, dst in (("allow", "src", "dst"), ("block", "dst", "src")):
        parts += [f"s_{kind} AS (SELECT host, {kind} / (SELECT sum({kind}) FROM h)::DOUBLE AS w FROM h WHERE {kind} > 0)", f"x_{kind} AS (SELECT {src} AS src, {dst} AS dst, n / sum(n) OVER (PARTITION BY {src})::DOUBLE AS share FROM e)", f"{kind}0 AS (SELECT host, w AS r FROM s_{kind})"]
        for k in range(rounds):
            parts.append(f"{kind}{k + 1} AS (SELECT host, {damping} * sum(m) + ({1 - damping!r}::DOUBLE + {damping} * (SELECT coalesce(sum(r), 0) FROM {kind}{k} WHERE host NOT IN (SELECT src FROM x_{kind}))) * sum(w) AS r FROM (SELECT dst AS host, r * share AS m, 0 AS w FROM x_{kind} JOIN {kind}{k} ON src = host UNION ALL SELECT host, 0, w FROM s_{kind}) GROUP BY host)")
    parts.append(f"t AS (SELECT coalesce(a.host, b.host) AS host, coalesce(a.r, 0) AS trust, coalesce(b.r, 0) AS distrust FROM allow{rounds} a FULL JOIN block{rounds} b ON a.host = b.host)")
    parts.append(f"m AS (SELECT *, distrust * (SELECT count(*) FROM (SELECT host FROM t UNION SELECT host FROM h)) >= {floor} AND distrust >= {margin} * trust AS blocked FROM t)")
    return "WITH " + ",\n".join(parts) + "\nSELECT page_id, r.host, path, rule, coalesce(rv, CASE WHEN blocked THEN 'block' ELSE 'allow' END) AS verdict, round(coalesce(trust, 0), 9) AS trust, round(coalesce(distrust, 0), 9) AS distrust FROM ruled r LEFT JOIN m ON r.host = m.host"
