"""URL filter: longest matching rule, else trust and distrust propagated over the host graph.

Pages link hosts by the absolute links in their HTML. Trust starts at hosts whose pages a rule
allows and follows links; distrust starts at hosts whose pages a rule blocks and follows links
backwards, to those who link there. Both are personalised PageRanks: a host's seed is the share of
its pages that the rules judge so; a score is restart * seed + (1 - restart) * what flows in. A url
without a rule is blocked if its host's distrust exceeds its trust and `doubt` of what a host with
all pages blocked starts with.

Edge cases: a null url, or one without "://", has an empty host and path and is judged as such;
null HTML has no links; links to the page's own host and repeated links of one page count as the
graph's weights say: own-host links not, repeated ones once; repeated rows each get their own result
row; empty tables give an empty result; extra columns are ignored.
"""

from __future__ import annotations

import json
from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import broadcast_if_small, materialize, table
from .spans import ascii_lower


@dataclass(frozen=True)
class UrlRule:
    host: str
    path: str
    verdict: str  # allow or block


# Fixed values of the contract.
RULES = (
    UrlRule("com", "/", "allow"),
    UrlRule("example.com", "/en/", "block"),
    UrlRule("www.example.com", "/en/", "allow"),
    UrlRule("net", "/es/", "block"),
    UrlRule("net", "/fr/", "block"),
)


@dataclass(frozen=True)
class RankConfig:
    """restart: share of a score that comes from the seed; rounds and settled: when to stop; doubt:
    share of a wholly blocked host's start from which distrust blocks."""

    restart: float = 0.15
    rounds: int = 30
    settled: float = 1e-4
    doubt: float = 0.5


def url_host(url: Column) -> Column:
    rest = _after_scheme(url)
    return ascii_lower(F.regexp_extract(rest, r"^[^/?#]*", 0))


def url_path(url: Column) -> Column:
    return F.regexp_extract(_after_scheme(url), r"^[^/?#]*([^?#]*)", 1)


def _after_scheme(url: Column) -> Column:
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def longest_rule(host: Column, path: Column, rules: Sequence[UrlRule]) -> Column:
    """struct(size, rule, verdict) of the longest rule that fits, or null. Looks up the host's
    suffixes, so the cost doesn't grow with the number of rules."""
    by_host: dict[str, list[dict]] = {}
    for r in rules:
        by_host.setdefault(r.host, []).append({"size": len(r.host) + len(r.path), "rule": r.host + r.path, "path": r.path, "verdict": r.verdict})
    known = F.from_json(F.lit(json.dumps(by_host)), "map<string,array<struct<size:int,rule:string,path:string,verdict:string>>>")
    labels = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    fits = F.filter(F.flatten(F.array_compact(F.transform(suffixes, lambda s: F.try_element_at(known, s)))), lambda r: F.startswith(path, r["path"]))
    return F.array_max(fits)


def host_edges(pages: DataFrame) -> DataFrame:
    """(src, dst, n): from how many pages of src a host dst is linked. pages: host, html."""
    links = F.regexp_extract_all("html", F.lit(r"(?i)href\s*=\s*[\x22\x27]?(?:[a-z][a-z0-9+.-]*:)?//([^/?#\x22\x27\s>]+)"), F.lit(1))
    each = pages.where(F.col("html").contains("//")).select(F.col("host").alias("src"), F.explode(F.array_distinct(F.transform(links, ascii_lower))).alias("dst"))
    return each.where("src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def propagate(seeds: DataFrame, edges: DataFrame, config: RankConfig = RankConfig()) -> DataFrame:
    """(host, score): seeds (host, seed) over edges (src, dst, n), weights n over a source's sum."""
    degree = edges.groupBy("src").agg(F.sum("n").alias("out"))
    steps = materialize(edges.join(degree, "src").select("src", "dst", (F.col("n") / F.col("out")).alias("share")), "host-steps")
    held = seeds.select("host", "seed", (config.restart * F.col("seed")).alias("score"))
    if steps.isEmpty():
        return held.select("host", "score")
    for _ in range(config.rounds):
        flow = held.where("score > 0").join(steps, F.col("host") == F.col("src")).groupBy("dst").agg(F.sum(F.col("score") * F.col("share")).alias("flow"))
        new = held.join(flow, F.col("host") == F.col("dst"), "full").select(
            F.coalesce("host", "dst").alias("host"), F.coalesce("seed", F.lit(0.0)).alias("seed"),
            (config.restart * F.coalesce("seed", F.lit(0.0)) + (1 - config.restart) * F.coalesce("flow", F.lit(0.0))).alias("score"),
            F.coalesce("score", F.lit(0.0)).alias("before"))
        new = materialize(new, "host-rank")
        moved = new.agg(F.max(F.abs(F.col("score") - F.col("before")))).first()[0] or 0.0
        held = new.select("host", "seed", "score")
        if moved < config.settled:
            break
    return held.select("host", "score")


def judged(pages: DataFrame, rules: Sequence[UrlRule] = RULES, config: RankConfig = RankConfig()) -> DataFrame:
    """One row per row of pages (page_id, url, html): page_id, host, path, rule, verdict, trust, distrust."""
    rows = pages.select("page_id", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"), "html")
    ruled = rows.select("page_id", "host", "path", longest_rule(F.col("host"), F.col("path"), rules).alias("best"))
    share = ruled.groupBy("host").agg(
        F.avg(F.when(F.col("best.verdict") == "allow", 1.0).otherwise(0.0)).alias("allowed"),
        F.avg(F.when(F.col("best.verdict") == "block", 1.0).otherwise(0.0)).alias("blocked"))
    share = materialize(share, "host-seeds")
    edges = materialize(host_edges(rows.select("host", "html")), "host-edges")
    trust = propagate(share.select("host", F.col("allowed").alias("seed")), edges, config)
    distrust = propagate(share.select("host", F.col("blocked").alias("seed")), edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n"), config)
    scores = materialize(share.select("host").join(trust.toDF("host", "trust"), "host").join(distrust.toDF("host", "distrust"), "host"), "host-scores")
    method = F.when((F.col("distrust") > F.col("trust")) & (F.col("distrust") >= config.doubt * config.restart), "block").otherwise("allow")
    return ruled.join(broadcast_if_small(scores, scores.count()), "host").select(
        "page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", method).alias("verdict"), "trust", "distrust")


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op2_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the rules alone say of op2_url_filter's rows; verdict is null where no rule fits."""
    return op2_url_filter(spark, sf_dir).select("page_id", "host", "path", "rule", F.when(F.col("rule").isNotNull(), F.col("verdict")).alias("verdict"))


def op2_rules_oracle() -> str:
    """DuckDB SQL of op2_rules."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    rows = ", ".join(f"('{r.host}', '{r.path}', '{r.verdict}')" for r in RULES)
    return f"""WITH rests AS (SELECT page_id, row_number() OVER () AS rid, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
        parts AS (SELECT page_id, rid, translate(regexp_extract(rest, '^[^/?#]*'), '{upper}', '{upper.lower()}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM rests),
        rules(rhost, rpath, verdict) AS (VALUES {rows}),
        fits AS (SELECT rid, rhost || rpath AS rule, verdict FROM parts JOIN rules ON ends_with('.' || host, '.' || rhost) AND starts_with(path, rpath)
                 QUALIFY row_number() OVER (PARTITION BY rid ORDER BY length(rhost) + length(rpath) DESC) = 1)
        SELECT page_id, host, path, rule, verdict FROM parts LEFT JOIN fits USING (rid)"""
