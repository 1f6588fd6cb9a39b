"""URL filtering by rules and by propagation over the graph of hosts.

Rules judge a url by its host and path. They also make seeds: a host is
trusted as far as rules allow its pages, and distrusted as far as they block
them. Trust flows along host edges as personalised PageRank from the trusted
seeds; distrust flows against the edges, from the blocked seeds to those that
lead to them. Edges are links in pages, and steps between a host and the next
domain above it that has pages or subdomains. Both flows run until they have
converged. A url without a rule is blocked if its host has more distrust than
trust.

Defined cases: a url that is null or holds no ``://`` has empty host and path;
a host that neither flow reaches is allowed; null html has no links; repeated
rows are judged alike, and their links count again; without seeds everything
is allowed; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import forget, look_up, settle

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Share of mass that moves on at each step; both flows step until one step changes each by less than this in all (damping bounds it: 175 steps at most).
DAMPING, TOLERANCE = 0.85, 1e-12
#: Steps between two looks at the change; graphs of at most so many ways are stepped on the driver, by the same rule.
LOOK_EVERY, DRIVER_WAYS = 8, 500_000
LINK = r"""(?i)\b(?:href|src)\s*=\s*["']?(?:https?:)?//([^/?#"'\s>]+)"""


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path

    def fits(self, host: Column, path: Column) -> Column:
        return ((host == self.host) | host.endswith("." + self.host)) & path.startswith(self.path)


#: Fixed values.
RULES = (
    Rule("org", "/", "allow"),
    Rule("example.org", "/es/", "block"),
    Rule("example.org", "/en/1", "block"),
    Rule("com", "/fr/", "allow"),
    Rule("com", "/de/", "block"),
)


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_struct(host: Column, path: Column, rules: tuple[Rule, ...] = RULES) -> Column:
    """The longest rule that fits, as struct(rule, ruling), else null."""
    out = F.lit(None)
    for rule in sorted(rules, key=lambda r: len(r.name)):
        out = F.when(rule.fits(host, path), F.struct(F.lit(rule.name).alias("rule"), F.lit(rule.verdict).alias("ruling"))).otherwise(out)
    return out


def host_edges(pages: DataFrame, hosts: DataFrame) -> DataFrame:
    """(source, target, weight) without loops, combined before they are shuffled."""
    found = F.transform(F.regexp_extract_all("html", F.lit(LINK), 1), lambda h: F.translate(h, UPPER, LOWER))
    links = pages.select("host", F.explode(found).alias("target")).groupBy(F.col("host").alias("source"), "target").agg(F.count("*").cast("double").alias("weight"))
    above = hosts.select("host", F.regexp_extract("host", r"^[^.]+\.(.+\..+)$", 1).alias("parent")).where("parent != ''")
    steps = above.select(F.explode(F.array(F.struct(F.col("host").alias("source"), F.col("parent").alias("target")), F.struct(F.col("parent").alias("source"), F.col("host").alias("target")))).alias("e"))
    return links.unionByName(steps.select("e.source", "e.target", F.lit(1.0).alias("weight"))).where("source != target AND source != '' AND target != ''")


def _driver_flows(shares: DataFrame, start: DataFrame, limit: int, tolerance: float, damping: float) -> DataFrame:
    """``propagate``'s steps in memory: (host, trust, distrust)."""
    ways, seeds = shares.toArrow().to_pydict(), start.toArrow().to_pydict()
    hosts = sorted({*ways["host"], *ways["to"], *seeds["host"]})
    place = {h: i for i, h in enumerate(hosts)}
    columns = [pa.array(hosts, pa.string())]
    for flow in ("trust", "distrust"):
        own = [i for i, f in enumerate(ways["flow"]) if f == flow]
        source, to = (np.array([place[ways[c][i]] for i in own], dtype=np.int64) for c in ("host", "to"))
        share = np.array([ways["share"][i] for i in own], dtype=np.float64)
        seed = np.zeros(len(hosts))
        for f, h, m in zip(seeds["flow"], seeds["host"], seeds["mass"], strict=True):
            seed[place[h]] += m * (f == flow)
        mass = seed
        for _ in range(limit):
            moved = np.bincount(to, mass[source] * share * damping, len(hosts))
            last, mass = mass, moved + seed * (1 - moved.sum())
            if np.abs(mass - last).sum() < tolerance:
                break
        columns.append(pa.array(mass, pa.float64()))
    return shares.sparkSession.createDataFrame(pa.table(columns, names=["host", "trust", "distrust"]))


def propagate(edges: DataFrame, seeds: DataFrame, steps: int | None = None, damping: float = DAMPING) -> DataFrame:
    """(host, trust, distrust) from ``seeds`` (host, trust, distrust).

    Both flows step together: each edge carries trust forwards and distrust
    backwards. Mass at a host without a way on returns to the seeds. Without
    ``steps``, they go on until neither changes by ``TOLERANCE``.
    """
    limit = math.ceil(math.log(TOLERANCE / 2, damping)) if steps is None else steps
    ways = edges.select(
        F.explode(
            F.array(
                F.struct(F.lit("trust").alias("flow"), F.col("source").alias("host"), F.col("target").alias("to"), "weight"),
                F.struct(F.lit("distrust").alias("flow"), F.col("target").alias("host"), F.col("source").alias("to"), "weight"),
            )
        ).alias("w")
    ).select("w.*")
    ways = settle(ways.groupBy("flow", "host", "to").agg(F.sum("weight").alias("weight")), "url-ways")
    # A host with very many ways is looked up from a broadcast, here and in each step.
    degrees = settle(ways.groupBy("flow", "host").agg(F.sum("weight").alias("all_ways"), F.count("*").alias("n")), "url-degrees")
    total = ways.count()
    known = look_up(ways, degrees, ["flow", "host"], "n", "of", total)
    shares = settle(known.select("flow", "host", "to", (F.col("weight") / F.col("of.all_ways")).alias("share")), "url-shares")
    long = seeds.select(F.explode(F.array(*[F.struct(F.lit(f).alias("flow"), "host", F.col(f).cast("double").alias("mass")) for f in ("trust", "distrust")])).alias("s")).select("s.*").where("mass > 0")
    totals = long.groupBy("flow").agg(F.sum("mass").alias("total"))
    start = settle(long.join(F.broadcast(totals), "flow").select("flow", "host", (F.col("mass") / F.col("total")).alias("mass")), "url-seeds")
    if total + start.count() <= DRIVER_WAYS:
        return settle(_driver_flows(shares, start, limit, TOLERANCE if steps is None else 0.0, damping), "url-flows")
    mass, done = start, []
    for step in range(1, limit + 1):
        held = mass.join(degrees.select("flow", "host", "n"), ["flow", "host"])
        passed = look_up(shares, held, ["flow", "host"], "n", "held", total).where("held IS NOT NULL")
        moved = passed.select("flow", F.col("to").alias("host"), (F.col("held.mass") * F.col("share") * damping).alias("mass"))
        arrived = moved.groupBy("flow", "host").agg(F.sum("mass").alias("mass"))
        arrived = settle(arrived, "url-step")
        done.append(arrived)
        kept = arrived.groupBy("flow").agg(F.sum("mass").alias("moved"))
        back = start.join(F.broadcast(kept), "flow", "left").select("flow", "host", (F.col("mass") * (1 - F.coalesce("moved", F.lit(0.0)))).alias("mass"))
        last, mass = mass, arrived.unionByName(back).groupBy("flow", "host").agg(F.sum("mass").alias("mass"))
        if steps is None and step % LOOK_EVERY == 0:
            mass = settle(mass, "url-mass")
            change = mass.unionByName(last.withColumn("mass", -F.col("mass"))).groupBy("flow", "host").agg(F.abs(F.sum("mass")).alias("by"))
            if all(r["by"] < TOLERANCE for r in change.groupBy("flow").agg(F.sum("by").alias("by")).collect()):
                break
            forget(shares.sparkSession, *done)
            done = []
    wide = mass.groupBy("host").agg(*[F.sum(F.when(F.col("flow") == f, F.col("mass")).otherwise(0.0)).alias(f) for f in ("trust", "distrust")])
    return settle(wide, "url-flows")


def judge_urls(pages: DataFrame, rules: tuple[Rule, ...] = RULES, steps: int | None = None) -> DataFrame:
    """(page_id, host, path, rule, verdict, trust, distrust) of every page."""
    url = F.col("url")
    located = pages.select(F.col("page_id").cast("long").alias("page_id"), host_of(url).alias("host"), path_of(url).alias("path"), "html")
    ruled = located.withColumn("ruled", rule_struct(F.col("host"), F.col("path"), rules))
    counted = ruled.groupBy("host").agg(F.count("*").alias("pages"), F.count_if(F.col("ruled.ruling") == "allow").alias("trust"), F.count_if(F.col("ruled.ruling") == "block").alias("distrust"))
    hosts = settle(counted, "url-hosts")
    flows = propagate(host_edges(located, hosts), hosts.select("host", "trust", "distrust"), steps)
    known = hosts.select("host", "pages").join(flows, "host", "left").select("host", "pages", F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"))
    found = look_up(ruled.drop("html"), known, ["host"], "pages", "flow")
    method = F.when(F.col("flow.distrust") > F.col("flow.trust"), "block").otherwise("allow")
    return found.select("page_id", "host", "path", F.col("ruled.rule").alias("rule"), F.coalesce("ruled.ruling", method).alias("verdict"), F.col("flow.trust").alias("trust"), F.col("flow.distrust").alias("distrust"))


def sql(rules: tuple[Rule, ...] = RULES, digits: int = 9) -> str:
    """The rows of ``judge_urls`` with flows rounded; as many steps as damping can need."""
    fits = {r: f"((host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}'))" for r in sorted(rules, key=lambda r: -len(r.name))}
    pick = lambda of: "CASE " + " ".join(f"WHEN {fit} THEN '{of(r)}'" for r, fit in fits.items()) + " END"
    steps = math.ceil(math.log(TOLERANCE / 2, DAMPING))
    link = LINK.replace("'", "''")
    return f"""
WITH RECURSIVE located AS (SELECT page_id, html, translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), ''), '{UPPER}', '{LOWER}') AS host, coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
ruled AS (SELECT page_id, html, host, path, {pick(lambda r: r.name)} AS rule, {pick(lambda r: r.verdict)} AS ruling FROM located),
hosts AS (SELECT host, count(*) FILTER (ruling = 'allow') AS trust, count(*) FILTER (ruling = 'block') AS distrust FROM ruled GROUP BY host),
above AS (SELECT host, regexp_extract(host, '^[^.]+\\.(.+\\..+)$', 1) AS parent FROM hosts),
found AS (SELECT host AS source, translate(unnest(regexp_extract_all(html, '{link}', 1)), '{UPPER}', '{LOWER}') AS target FROM located),
edges AS (SELECT * FROM (SELECT source, target, 1.0::DOUBLE AS weight FROM found UNION ALL SELECT host, parent, 1.0 FROM above WHERE parent <> '' UNION ALL SELECT parent, host, 1.0 FROM above WHERE parent <> '') WHERE source <> target AND source <> '' AND target <> ''),
ways AS (SELECT flow, host, "to", sum(weight) AS weight FROM (SELECT 'trust' AS flow, source AS host, target AS "to", weight FROM edges UNION ALL SELECT 'distrust', target, source, weight FROM edges) GROUP BY flow, host, "to"),
shares AS (SELECT flow, host, "to", weight / sum(weight) OVER (PARTITION BY flow, host) AS share FROM ways),
long AS (SELECT 'trust' AS flow, host, trust AS n FROM hosts WHERE trust > 0 UNION ALL SELECT 'distrust', host, distrust FROM hosts WHERE distrust > 0),
seeds AS (SELECT flow, host, n / sum(n) OVER (PARTITION BY flow) AS mass FROM long),
mass AS (SELECT 0 AS step, flow, host, mass FROM seeds UNION ALL
  SELECT max(step) + 1, flow, host, sum(mass) FROM (
    SELECT m.step, m.flow, s."to" AS host, m.mass * s.share * {DAMPING} AS mass FROM mass m JOIN shares s ON m.flow = s.flow AND m.host = s.host WHERE m.step < {steps}
    UNION ALL
    SELECT k.step, d.flow, d.host, d.mass * (1 - k.moved) FROM seeds d JOIN (SELECT m.flow, max(m.step) AS step, coalesce(sum(m.mass * {DAMPING}) FILTER (EXISTS (SELECT 1 FROM shares s WHERE s.flow = m.flow AND s.host = m.host)), 0) AS moved FROM mass m WHERE m.step < {steps} GROUP BY m.flow) k ON d.flow = k.flow
  ) GROUP BY flow, host),
flows AS (SELECT host, coalesce(sum(mass) FILTER (flow = 'trust'), 0) AS trust, coalesce(sum(mass) FILTER (flow = 'distrust'), 0) AS distrust FROM mass WHERE step = {steps} GROUP BY host)
SELECT page_id, r.host, path, rule, coalesce(ruling, CASE WHEN coalesce(f.distrust, 0) > coalesce(f.trust, 0) THEN 'block' ELSE 'allow' END) AS verdict, round(coalesce(f.trust, 0), {digits}) AS trust, round(coalesce(f.distrust, 0), {digits}) AS distrust
FROM ruled r LEFT JOIN flows f ON r.host = f.host
"""
