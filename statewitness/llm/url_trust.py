"""URL filters: rules on hosts and paths, and trust that spreads over the links between hosts.

1. Each URL is split into host and path and judged by the longest rule that fits (a rule fits its host
   and all subdomains, and the paths that start with its path). Rules are a configured list.
2. Links in the pages become host edges with their numbers of links; edges are summed before they move,
   so a page's or host's many links cost one row for each map task.
3. Personalised PageRank spreads trust from hosts with pages that a rule allows, along links, and distrust
   from hosts with pages that a rule blocks, against them (who links to a blocked host shares in its
   distrust). A seed weighs as much as the share of its host's pages that are judged so; a host without pages of
   its own, but covered by a rule for whole hosts, is a full seed. Both run in one loop; each round is a join and an
   aggregate, kept as a scratch table. It ends when ranks change by ``TOLERANCE`` in sum, or after ``ROUNDS``; what a
   later round could still change is then at most ``DAMPING`` to the power of ``ROUNDS`` of the seeds' sum.
4. A host whose distrust reaches ``FLOOR`` (a full seed has 1) and exceeds its trust is blocked; the
   page's verdict is the rule's, else its host's. A host without any rank is allowed.

Defined results: host and path of a null url, or one without ``://``, are empty; no rule fits an empty host;
pages without html have no links; a repeated row is judged each time; links within one host are no
edges; empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from statewitness.llm.scratch import Scratch

DAMPING, ROUNDS, TOLERANCE, FLOOR = 0.85, 25, 1e-6, 0.1
#: Ranks that differ by no more than this are equal.
TIE = 1e-9
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
HREF = r"(?i)\bhref\s*=\s*[\"']?(?:https?:)?//([^/?#\"'>\s]+)"


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def text(self) -> str:
        return self.host + self.path

    def fits(self, host: Column, path: Column) -> Column:
        return self.covers(host) & path.startswith(self.path)

    def covers(self, host: Column) -> Column:
        return (host == self.host) | host.endswith("." + self.host)

    @property
    def whole_host(self) -> bool:
        return self.path in ("", "/")


RULES = (
    Rule("org", "/", "allow"),
    Rule("example.org", "/es/", "block"),
    Rule("example.org", "/en/1", "block"),
    Rule("com", "/fr/", "allow"),
    Rule("com", "/de/", "block"),
)


def split_url(url: Column) -> tuple[Column, Column]:
    known = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(known, URL, 1), UPPER, LOWER), F.regexp_extract(known, URL, 2)


def by_longest(rules: tuple[Rule, ...], value, test) -> Column:
    """``value`` of the longest rule for which ``test`` holds, else null."""
    out = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(r.text), r.text)):
        out = F.when(test(rule), F.lit(value(rule))).otherwise(out)
    return out


def judged(pages: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """page_id, host, path, rule and the rule's verdict."""
    host, path = split_url(F.col("url"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"))
    fits = lambda r: r.fits(F.col("host"), F.col("path"))
    return rows.select("*", by_longest(rules, lambda r: r.text, fits).alias("rule"), by_longest(rules, lambda r: r.verdict, fits).alias("ruled"))


def host_edges(pages: DataFrame) -> DataFrame:
    """(src, dst, links) between different hosts."""
    src, _ = split_url(F.col("url"))
    dst = F.explode(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit(HREF), 1))
    rows = pages.select(src.alias("src"), dst.alias("dst")).withColumn("dst", F.translate("dst", UPPER, LOWER))
    return rows.filter("src <> '' AND dst <> '' AND src <> dst").groupBy("src", "dst").agg(F.count("*").alias("links"))


def seeds(pages: DataFrame, edges: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """(kind, host, seed): hosts by the share of their pages that rules allow or block."""
    own = judged(pages, rules).filter("host <> ''").groupBy("host").agg(F.avg((F.col("ruled") == "allow").cast("double")).alias("a"), F.avg((F.col("ruled") == "block").cast("double")).alias("b"), F.count("*").alias("n"), F.count("ruled").alias("m"))
    own = own.select("host", (F.coalesce("a", F.lit(0.0)) * F.col("m") / F.col("n")).alias("trust"), (F.coalesce("b", F.lit(0.0)) * F.col("m") / F.col("n")).alias("distrust"))
    verdict = by_longest(tuple(r for r in rules if r.whole_host), lambda r: r.verdict, lambda r: r.covers(F.col("host")))
    linked = edges.select(F.col("src").alias("host")).union(edges.select("dst")).distinct().join(own.select("host"), "host", "left_anti")
    linked = linked.select("host", (verdict == "allow").cast("double").alias("trust"), (verdict == "block").cast("double").alias("distrust")).fillna(0.0)
    both = own.unionByName(linked)
    rows = both.select("host", F.explode(F.create_map(F.lit("trust"), "trust", F.lit("distrust"), "distrust")).alias("kind", "share")).filter("share > 0")
    return rows.select("kind", "host", F.col("share").alias("seed"))


def spread(s: Scratch, edges: DataFrame, start: DataFrame, damping: float, rounds: int, tolerance: float) -> DataFrame:
    """(kind, host, rank): personalised PageRank of each kind; dangling weight returns to the seeds.

    Seeds are shares of pages, and a kind's ranks always add up to its seeds.
    """
    along = edges.select(F.lit("trust").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), "links")
    against = edges.select(F.lit("distrust").alias("kind"), F.col("dst").alias("a"), F.col("src").alias("b"), "links")
    both = along.union(against)
    out = both.groupBy("kind", "a").agg(F.sum("links").alias("all_links"))
    moves = s.save(both.join(out, ["kind", "a"]).select("kind", "a", "b", (F.col("links") / F.col("all_links")).alias("p")), "moves")
    seed = s.save(start, "seed")
    now = s.save(seed.withColumnRenamed("seed", "rank"), "rank-0", keep=True)
    if moves.isEmpty():
        return now
    totals = seed.groupBy("kind").agg(F.sum("seed").alias("n"))
    for turn in range(1, rounds + 1):
        given = now.join(moves, (now["kind"] == moves["kind"]) & (now["host"] == moves["a"])).select(moves["kind"], F.col("b").alias("host"), (F.col("rank") * F.col("p")).alias("got"))
        got = given.groupBy("kind", "host").agg(F.sum("got").alias("got"))
        passed = got.groupBy("kind").agg(F.sum("got").alias("passed"))
        lost = totals.join(passed, "kind", "left").select("kind", (1 - damping * F.coalesce("passed", F.lit(0.0)) / F.col("n")).alias("back"))
        moved = seed.join(F.broadcast(lost), "kind", "left")  # two rows, one for each kind
        new = got.join(moved, ["kind", "host"], "full_outer").select("kind", "host", (damping * F.coalesce("got", F.lit(0.0)) + F.coalesce(F.col("seed") * F.col("back"), F.lit(0.0))).alias("rank"))
        new = s.save(new, f"rank-{turn}", keep=True)
        change = new.alias("x").join(now.alias("y"), ["kind", "host"], "full_outer").agg(F.sum(F.abs(F.coalesce("x.rank", F.lit(0.0)) - F.coalesce("y.rank", F.lit(0.0))))).first()[0]
        s.drop(f"rank-{turn - 1}")
        now = new
        if (change or 0.0) <= tolerance:
            break
    return now


def blocked_hosts(s: Scratch, pages: DataFrame, rules: tuple[Rule, ...], damping: float = DAMPING, rounds: int = ROUNDS, floor: float = FLOOR) -> DataFrame:
    """(host, trust, distrust) of hosts whose distrust reaches the floor and exceeds their trust."""
    edges = s.save(host_edges(pages), "edges")
    rank = spread(s, edges, seeds(pages, edges, rules), damping, rounds, TOLERANCE)
    per = rank.groupBy("host").agg(F.sum(F.when(F.col("kind") == "trust", F.col("rank"))).alias("trust"), F.sum(F.when(F.col("kind") == "distrust", F.col("rank"))).alias("distrust"))
    per = per.select("host", F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"))
    return per.filter((F.col("distrust") >= floor) & (F.col("distrust") > F.col("trust") + TIE))


def filter_urls(pages: DataFrame, rules: tuple[Rule, ...] = RULES, damping: float = DAMPING, rounds: int = ROUNDS, floor: float = FLOOR) -> DataFrame:
    """One row per page: page_id, host, path, rule, verdict."""
    s = Scratch(pages.sparkSession)
    bad = s.save(blocked_hosts(s, pages.select("page_id", "url", "html"), rules, damping, rounds, floor).select("host"), "bad", keep=True)
    for name in list(s.paths):
        if name != "bad":
            s.drop(name)
    rows = judged(pages, rules).join(bad.withColumn("bad", F.lit(True)), "host", "left")
    verdict = F.coalesce("ruled", F.when(F.col("bad"), "block").otherwise("allow"))
    return rows.select("page_id", "host", "path", "rule", verdict.alias("verdict"))


def query(spark, sf_dir: str) -> DataFrame:
    return filter_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"))


#: The given pages have relative links only, so no rank moves between hosts and each host's ranks are its seeds'.
ORACLE = r"""
WITH p AS (
  SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path
  FROM pages),
r(rhost, rpath, action) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
m AS (
  SELECT page_id, host, path, rhost || rpath AS rule, action,
         row_number() OVER (PARTITION BY page_id, host, path ORDER BY length(rhost || rpath) DESC) AS k
  FROM p LEFT JOIN r ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath)),
j AS (SELECT page_id, host, path, rule, action FROM m WHERE k = 1),
h AS (SELECT host, count(*) FILTER (action = 'allow') / count(*) AS trust, count(*) FILTER (action = 'block') / count(*) AS distrust FROM j WHERE host <> '' GROUP BY host),
bad AS (SELECT host FROM h WHERE distrust >= 0.1 AND distrust > trust + 1e-9)
SELECT page_id, host, path, rule, coalesce(action, CASE WHEN host IN (SELECT host FROM bad) THEN 'block' ELSE 'allow' END) AS verdict FROM j
"""
