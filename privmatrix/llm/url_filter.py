"""URL filter: rules first, then trust and distrust propagated over the hosts' link graph, with DataFrame functions only.

A rule is a host and the start of a path; it fits the host and all its subdomains. The longest fitting rule decides a URL.
For all others the host decides: trust starts at the hosts of allowed pages and follows the edges, distrust starts at the hosts of
blocked pages and follows them backwards (a page that leads to bad hosts is suspect), both as personalised PageRank. A host whose
distrust exceeds ``ratio`` times its trust is blocked. Edges are hyperlinks between hosts, and the ties between a host and its
parent domain, in both directions.

Both scores are shares of what all hosts hold, which sends the mass that ends at hosts without edges back to the seeds, and are
compared by their ratio, so a verdict does not depend on the size of the table. After a step a share ``damping`` of the mass that moved
before still moves; ``rounds_for`` takes as many steps as leave at most ``tolerance`` of it. Hosts farther than that from all seeds are allowed.

Null URLs and URLs without ``://`` have an empty host and path; no rule fits an empty host, it is no node of the graph and
is allowed. Ties of trust and distrust allow. Repeated pages count as often as they occur and get the same verdict.
``judge`` keeps extra columns; a column named like an output column is replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privmatrix.llm.store import dropped, written

#: The rules, as (verdict, host and start of the path).
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
DAMPING, TOLERANCE, RATIO = 0.85, 1e-3, 1.0
CUT_EVERY = 4
#: Scores whose ratio is this close to the limit are ties; sums in another order differ by far less.
TIE = 1e-9
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
_LINK = r"""(?i)href\s*=\s*["']?\s*[a-z][a-z0-9+.-]*://([^/?#"'\s>]+)"""


def host(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), _URL, 1), _UPPER, _LOWER)


def path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), _URL, 2)


def _longest_first(rules: tuple[tuple[str, str], ...]) -> list[tuple[str, str]]:
    return sorted(rules, key=lambda r: (-len(r[1]), r[1], r[0] != "block"))


def _matched(rules: tuple[tuple[str, str], ...], of: int) -> Column:
    """The longest fitting rule's verdict (0) or string (1). The rules are a short fixed list, so they are part of the plan."""
    out = F.lit(None).cast("string")
    for rule in reversed(_longest_first(rules)):
        name, slash, rest = rule[1].partition("/")
        fits = (F.col("host") == name) | F.endswith(F.col("host"), F.lit(f".{name}"))
        out = F.when(fits & F.startswith(F.col("path"), F.lit(slash + rest)), F.lit(rule[of])).otherwise(out)
    return out


def rounds_for(damping: float = DAMPING, tolerance: float = TOLERANCE) -> int:
    """Steps after which at most ``tolerance`` of the mass still moves."""
    return max(1, math.ceil(math.log(tolerance) / math.log(damping)))


def edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """source, target: distinct edges between different hosts."""
    own = pages.select(host(F.col(url_col)).alias("source"), F.transform(F.regexp_extract_all(F.coalesce(F.col(html_col), F.lit("")), F.lit(_LINK), 1), lambda x: F.translate(x, _UPPER, _LOWER)).alias("links"))
    links = own.select("source", F.explode(F.array_distinct("links")).alias("target"))
    hosts = pages.select(host(F.col(url_col)).alias("name")).unionByName(links.select(F.col("target").alias("name"))).distinct()
    labels = F.split("name", r"\.")
    chain = hosts.select(F.transform(F.sequence(F.lit(1), F.greatest(F.size(labels) - 1, F.lit(1))), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), ".")).alias("names"))
    ties = chain.select(F.explode(F.arrays_zip(F.col("names").alias("source"), F.slice("names", F.lit(2), F.size("names")).alias("target"))).alias("e")).select("e.source", "e.target").where("target IS NOT NULL").distinct()
    both = ties.unionByName(ties.select(F.col("target").alias("source"), F.col("source").alias("target")))
    return links.unionByName(both).where("source <> target AND source <> '' AND target <> ''").distinct()


def propagate(seeds: DataFrame, edge: DataFrame, damping: float = DAMPING, tolerance: float = TOLERANCE) -> DataFrame:
    """host, trust, distrust, each column summing to 1 (or 0 without seeds); seeds: host, trust0, distrust0, which do so too."""
    out = edge.groupBy("source").agg(F.count("*").alias("n_out"))
    into = edge.groupBy("target").agg(F.count("*").alias("n_in"))
    weighted = edge.join(out, "source").join(into, "target")
    zero, rounds = F.lit(0.0), rounds_for(damping, tolerance)
    messages = weighted.select(F.col("source").alias("from"), F.col("target").alias("to"), (1 / F.col("n_out")).alias("wt"), zero.alias("wd")).unionByName(
        weighted.select(F.col("target").alias("from"), F.col("source").alias("to"), zero.alias("wt"), (1 / F.col("n_in")).alias("wd"))
    )
    messages = written(messages.groupBy("from", "to").agg(F.sum("wt").alias("wt"), F.sum("wd").alias("wd")), "host-messages")
    state, before = seeds.select("host", F.col("trust0").alias("trust"), F.col("distrust0").alias("distrust")), None
    kept = state.select("host", ((1 - damping) * F.col("trust")).alias("trust"), ((1 - damping) * F.col("distrust")).alias("distrust"))
    for k in range(1, rounds + 1):
        sent = messages.join(state, messages["from"] == state["host"]).select(F.col("to").alias("host"), (damping * F.col("wt") * F.col("trust")).alias("trust"), (damping * F.col("wd") * F.col("distrust")).alias("distrust"))
        state = kept.unionByName(sent).groupBy("host").agg(F.sum("trust").alias("trust"), F.sum("distrust").alias("distrust"))
        if k % CUT_EVERY == 0 or k == rounds:
            state = written(state, "host-trust")
            if before is not None:
                dropped(before)
            before = state
    held = state.agg(F.sum("trust").alias("__t"), F.sum("distrust").alias("__d"))  # one row
    part = lambda c, total: F.coalesce(F.try_divide(F.col(c), F.col(total)), zero).alias(c)
    return state.join(F.broadcast(held)).select("host", part("trust", "__t"), part("distrust", "__d"))


def judge(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, url_col: str = "url", html_col: str = "html", damping: float = DAMPING, tolerance: float = TOLERANCE, ratio: float = RATIO) -> DataFrame:
    """``pages`` with host, path, rule, verdict and basis (rule or graph)."""
    names = ("host", "path", "rule", "verdict", "basis")
    ruled = pages.drop(*names).withColumns({"host": host(F.col(url_col)), "path": path(F.col(url_col))})
    ruled = ruled.withColumns({"rule": _matched(rules, 1), "__ruling": _matched(rules, 0)})
    counts = ruled.where("host <> ''").groupBy("host").agg(F.count_if(F.col("__ruling") == "allow").alias("a"), F.count_if(F.col("__ruling") == "block").alias("b"))
    totals = counts.agg(F.sum("a").alias("ta"), F.sum("b").alias("tb"))  # one row
    share = lambda n, total: F.coalesce(F.try_divide(F.col(n).cast("double"), F.col(total).cast("double")), F.lit(0.0))
    seeds = counts.join(F.broadcast(totals)).select("host", share("a", "ta").alias("trust0"), share("b", "tb").alias("distrust0"))
    seeds = written(seeds, "host-seeds")
    scores = propagate(seeds, written(edges(pages, url_col, html_col), "host-edges"), damping, tolerance)
    bad = scores.where(F.col("distrust") > ratio * F.col("trust") * (1 + TIE)).select(F.col("host").alias("__bad"))
    marked = ruled.join(bad, ruled["host"] == bad["__bad"], "left")
    return marked.withColumns({
        "verdict": F.coalesce("__ruling", F.when(F.col("__bad").isNotNull(), "block").otherwise("allow")),
        "basis": F.when(F.col("rule").isNotNull(), "rule").otherwise("graph"),
    }).drop("__bad", "__ruling")


def oracle(rules: tuple[tuple[str, str], ...] = RULES, damping: float = DAMPING, tolerance: float = TOLERANCE, ratio: float = RATIO) -> str:
    """DuckDB SQL for op4 over pages."""
    cases, rounds = {0: "CASE", 1: "CASE"}, rounds_for(damping, tolerance)
    for rule in _longest_first(rules):
        name, slash, rest = rule[1].partition("/")
        for of in cases:
            cases[of] += f" WHEN (host = '{name}' OR ends_with(host, '.{name}')) AND starts_with(path, '{slash}{rest}') THEN '{rule[of]}'"
    steps = []
    for k in range(1, rounds + 1):
        steps.append(f"""s{k} AS MATERIALIZED (SELECT coalesce(seeds.host, m.host) AS host, {1 - damping} * coalesce(t0, 0) + {damping} * coalesce(m.t, 0) AS t, {1 - damping} * coalesce(d0, 0) + {damping} * coalesce(m.d, 0) AS d
          FROM seeds FULL JOIN (SELECT host, sum(t) AS t, sum(d) AS d FROM (
            SELECT target AS host, s.t / n_out AS t, 0.0::DOUBLE AS d FROM w JOIN s{k - 1} s ON s.host = w.source UNION ALL
            SELECT source, 0.0::DOUBLE, s.d / n_in FROM w JOIN s{k - 1} s ON s.host = w.target) GROUP BY host) m ON m.host = seeds.host)""")
    lower = f"translate(%s, '{_UPPER}', '{_LOWER}')"
    return f"""WITH p AS (SELECT page_id, html, {lower % "regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1)"} AS host, regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path FROM pages),
      r AS (SELECT *, {cases[1]} END AS rule, {cases[0]} END AS ruling FROM p),
      links AS (SELECT DISTINCT host AS source, {lower % "unnest(regexp_extract_all(coalesce(html, ''), '(?i)href\\s*=\\s*[\"'']?\\s*[a-z][a-z0-9+.-]*://([^/?#\"''\\s>]+)', 1))"} AS target FROM p),
      hosts AS (SELECT host AS name FROM p UNION SELECT target FROM links),
      l AS (SELECT string_split(name, '.') AS l FROM hosts), c AS (SELECT l, unnest(range(1, len(l) - 1)) AS i FROM l),
      ties AS (SELECT DISTINCT array_to_string(l[i:], '.') AS a, array_to_string(l[i + 1:], '.') AS b FROM c),
      e AS (SELECT DISTINCT source, target FROM (SELECT source, target FROM links UNION ALL SELECT a, b FROM ties UNION ALL SELECT b, a FROM ties) WHERE source <> target AND source <> '' AND target <> ''),
      w AS MATERIALIZED (SELECT source, target, count(*) OVER (PARTITION BY source) AS n_out, count(*) OVER (PARTITION BY target) AS n_in FROM e),
      counts AS (SELECT host, count(*) FILTER (WHERE ruling = 'allow') AS a, count(*) FILTER (WHERE ruling = 'block') AS b FROM r WHERE host <> '' GROUP BY host),
      seeds AS MATERIALIZED (SELECT host, coalesce(a / nullif(sum(a) OVER (), 0), 0)::DOUBLE AS t0, coalesce(b / nullif(sum(b) OVER (), 0), 0)::DOUBLE AS d0 FROM counts),
      s0 AS (SELECT host, t0 AS t, d0 AS d FROM seeds), {", ".join(steps)}
      SELECT page_id, r.host, path, rule, coalesce(ruling, CASE WHEN d / nullif((SELECT sum(d) FROM s{rounds}), 0) > {ratio} * coalesce(t / nullif((SELECT sum(t) FROM s{rounds}), 0), 0) * {1 + TIE} THEN 'block' ELSE 'allow' END) AS verdict, CASE WHEN rule IS NULL THEN 'graph' ELSE 'rule' END AS basis
      FROM r LEFT JOIN s{rounds} ON r.host = s{rounds}.host"""
