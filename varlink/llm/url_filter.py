"""Operator 4: URL filter by rules and empirical-Bayes host reputation. DataFrame functions only.

Explicit rules decide first. Pages that no rule fits are judged by the reputation of their host: labelled outcomes (bad
or good pages) are counted per host, and the host's bad rate is shrunk by a beta-binomial prior towards its registered
domain's, which is shrunk towards its suffix's, and that towards the rate of all labels. The strength of each prior is
estimated from the counts by moments. A host is blocked when it is surely worse than the whole: when the lower bound of
its posterior bad rate lies above ``block_over`` times the rate of all labels.

Outcomes come from labels and never from the rules; pages that a rule decides are left out of them, since the verdicts are
needed for the others. Counts are pre-aggregated per host, so a host with a third of all pages is one row of a small
table; the reputations are written once, and Spark knows their size when it joins them.

For reputations a host loses user, port and trailing dots; an address is its own domain below a common suffix; a registered
domain has one label more than its suffix, which is the last label or one of the two-label ``SUFFIXES``.

Edge cases: a null url, or one without ``://``, has empty host and path, and takes the verdict of the corpus-wide
posterior; hosts of one label are their own domain and suffix; without any labelled outcome everything that no rule
blocks is allowed; repeated rows each count; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, cut, fresh

# The rules (verdict, host, path) in their order.
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)


# Common public suffixes of two labels.
SUFFIXES = (
    "co.uk", "org.uk", "ac.uk", "gov.uk", "com.au", "net.au", "org.au", "edu.au", "co.nz", "co.jp", "ne.jp", "or.jp", "ac.jp", "co.kr", "com.br", "com.mx", "com.ar", "com.cn", "com.tw", "com.hk", "com.sg", "com.tr", "co.in", "co.il", "co.za",
)


@dataclass(frozen=True)
class Reputation:
    """``block_over``: how many times the rate of all labels a host's lower bound must exceed; ``z``: how many standard
    deviations below the posterior mean the bound lies; ``least`` and ``most``: limits of a prior's strength, in pages."""

    block_over: float = 1.0
    z: float = 1.645
    least: float = 2.0
    most: float = 1000.0


def host_of(url: Column) -> Column:
    return ascii_lower(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_columns(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest fitting rule as text, and its verdict; null where none fits."""
    text = verdict = F.lit(None).cast("string")
    for v, h, p in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        text, verdict = F.when(fits, h + p).otherwise(text), F.when(fits, v).otherwise(verdict)
    return text, verdict


#: What a host loses for its reputation, and what an address looks like (patterns that Java and RE2 read alike).
TRIMMED, ADDRESS = r"^[^@]*@|(:[0-9]*)?\.*$", r"^([0-9]+(\.[0-9]+){3}|\[.*\]|[0-9]+)$"


def bare_host(host: Column) -> Column:
    return F.regexp_replace(host, TRIMMED, "")


def suffix_of(bare: Column) -> Column:
    two = F.substring_index(bare, ".", -2)
    return F.when(bare.rlike(ADDRESS), F.lit("#address")).when(two.isin(*SUFFIXES), two).otherwise(F.substring_index(bare, ".", -1))


def domain_of(bare: Column) -> Column:
    two = F.substring_index(bare, ".", -2)
    return F.when(bare.rlike(ADDRESS), bare).when(two.isin(*SUFFIXES), F.substring_index(bare, ".", -3)).otherwise(two)


def _strength(counts: DataFrame, p: Reputation, parent: list[str]) -> DataFrame:
    """Prior strength of the groups below each ``parent``: moments of the beta-binomial, from ``bad`` and ``n``.

    With mean m and the groups' weighted variance v about it, the variance of a rate is m(1-m)/n plus the spread s of
    the true rates; m(1-m)/s - 1 is the strength.
    """
    n, bad = F.sum("n").cast("double"), F.sum("bad").cast("double")
    squares = F.sum(F.col("bad").cast("double") * F.col("bad") / F.col("n"))
    g = counts.groupBy(*parent).agg(n.alias("n"), bad.alias("bad"), squares.alias("squares"), F.count("*").alias("groups"))
    m = F.col("bad") / F.col("n")
    spread = (F.col("squares") - F.col("n") * m * m - (F.col("groups") - 1) * m * (1 - m)) / F.col("n")
    # one group says nothing of how groups differ: its prior stays weak
    kappa = F.when(F.col("groups") < 2, F.lit(p.least)).when(spread > 0, m * (1 - m) / spread - 1).otherwise(F.lit(p.most))
    return g.select(*parent, F.col("n").alias("n_up"), F.col("bad").alias("bad_up"), F.least(F.greatest(F.coalesce(kappa, F.lit(p.most)), F.lit(p.least)), F.lit(p.most)).alias("kappa"))


def reputations(outcomes: DataFrame, p: Reputation = Reputation()) -> DataFrame:
    """Posterior of every labelled host, domain and suffix and of the whole: ``level, name, rate, weight``.

    ``outcomes`` has bare hosts and counts: ``host``, ``n`` labelled pages, ``bad`` of them; levels are host, domain,
    suffix and all. ``rate`` is the posterior mean, ``weight`` the pages behind it (prior included).
    """
    hosts = outcomes.groupBy("host").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).withColumns({"domain": domain_of(F.col("host")), "suffix": suffix_of(F.col("host"))})
    hosts = cut(hosts, "url-hosts")  # small, and read at every level
    domains = hosts.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    suffixes = domains.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    rate = lambda bad, n, k, m: (bad + k * m) / (n + k)
    top = _strength(suffixes, p, []).select(((F.col("bad_up") + 1) / (F.col("n_up") + 2)).alias("top_rate"), F.col("kappa").alias("top_kappa"))
    s = suffixes.crossJoin(F.broadcast(top)).withColumns({"rate": rate(F.col("bad"), F.col("n"), F.col("top_kappa"), F.col("top_rate")), "weight": F.col("n") + F.col("top_kappa")})
    ks = _strength(domains, p, ["suffix"]).select("suffix", "kappa")
    d = domains.join(s.select("suffix", F.col("rate").alias("up")), "suffix").join(ks, "suffix").withColumns({"rate": rate(F.col("bad"), F.col("n"), F.col("kappa"), F.col("up")), "weight": F.col("n") + F.col("kappa")})
    kd = _strength(hosts, p, ["domain"]).select("domain", "kappa")
    h = hosts.join(d.select("domain", F.col("rate").alias("up")), "domain").join(kd, "domain").withColumns({"rate": rate(F.col("bad"), F.col("n"), F.col("kappa"), F.col("up")), "weight": F.col("n") + F.col("kappa")})
    part = lambda df, level, name: df.select(F.lit(level).alias("level"), name.alias("name"), "rate", "weight")
    whole = top.select(F.col("top_rate").alias("rate"), F.col("top_kappa").alias("weight"))
    return part(h, "host", F.col("host")).unionByName(part(d, "domain", F.col("domain"))).unionByName(part(s, "suffix", F.col("suffix"))).unionByName(part(whole, "all", F.lit("")))


def lower_bound(rate: Column, weight: Column, p: Reputation) -> Column:
    """Lower bound of a beta posterior with the given mean and pages, by its standard deviation."""
    return rate - F.lit(p.z) * F.sqrt(rate * (1 - rate) / (weight + 1))


def label_key(path: Column) -> Column:
    """The number that follows the first folder of a path: the given pages name the document that they show there."""
    return F.regexp_extract(path, "^/[^/]*/([0-9]+)", 1).try_cast("long")


def labelled_outcomes(ruled: DataFrame, host: str, key: Column, labels: DataFrame, among: Column) -> DataFrame:
    """``host, n, bad``: per bare host how many of its pages ``among`` have a label, and how many of these a bad one.

    ``labels`` has ``key`` and ``bad``; a key that is labelled more than once is bad if one of its labels is. Pages are
    counted per host and key before the join, so a key that many pages share is a few rows.
    """
    pages = ruled.filter(among).select(bare_host(F.col(host)).alias("host"), key.alias("key")).filter("key IS NOT NULL").groupBy("host", "key").agg(F.count("*").alias("n"))
    known = labels.filter("key IS NOT NULL AND bad IS NOT NULL").groupBy("key").agg(F.max("bad").alias("bad"))
    return pages.join(known, "key").groupBy("host").agg(F.sum("n").alias("n"), F.sum(F.when(F.col("bad"), F.col("n")).otherwise(F.lit(0))).alias("bad"))


def judge_urls(pages: DataFrame, outcomes: DataFrame | None = None, rules=RULES, p: Reputation = Reputation(), labels: DataFrame | None = None) -> tuple[DataFrame, list[str]]:
    """``pages`` with host, path, fitting rule and verdict under the returned names.

    Outcomes are labelled pages (``outcomes``: ``url, bad``), or labels of documents that the pages' paths name
    (``labels``: ``key, bad``; see :func:`label_key`), or both; without any, what no rule blocks is allowed.
    """
    host, path, rule, verdict, own, blocked = names = fresh(pages, "host", "path", "rule", "verdict", "own", "blocked")
    located = pages.withColumns({host: host_of(F.col("url")), path: path_of(F.col("url"))})
    text, said = rule_columns(F.col(host), F.col(path), rules)
    ruled = located.withColumns({rule: text, verdict: said})
    given = []
    if outcomes is not None:
        given.append(outcomes.filter("bad IS NOT NULL").groupBy(bare_host(host_of(F.col("url"))).alias("host")).agg(F.count("*").alias("n"), F.sum(F.col("bad").cast("long")).alias("bad")))
    if labels is not None:
        given.append(labelled_outcomes(ruled, host, label_key(F.col(path)), labels, F.col(verdict).isNull()))
    if not given:
        return ruled.withColumn(verdict, F.coalesce(F.col(verdict), F.lit("allow"))), names[:4]
    known = reputations(given[0] if len(given) == 1 else given[0].unionByName(given[1]), p)
    whole = known.filter("level = 'all'").select(F.col("rate").alias("whole"))
    said = lower_bound(F.col("rate"), F.col("weight"), p) > p.block_over * F.col("whole")
    known = cut(known.crossJoin(F.broadcast(whole)).select("level", "name", F.coalesce(said, F.lit(False)).alias("blocked")), "url-reputations")
    # The verdicts of all hosts that occur: a small table, made once from the distinct hosts.
    hosts = ruled.filter(F.col(verdict).isNull()).select(F.col(host).alias(own)).distinct().withColumn("own_host", bare_host(F.col(own)))
    hosts = hosts.withColumns({"own_domain": domain_of(F.col("own_host")), "own_suffix": suffix_of(F.col("own_host"))})
    for level in ("host", "domain", "suffix"):
        hosts = hosts.join(known.filter(F.col("level") == level).select(F.col("name").alias(f"own_{level}"), F.col("blocked").alias(f"by_{level}")), f"own_{level}", "left")
    top = known.filter("level = 'all'").select(F.col("blocked").alias("by_all"))
    hosts = hosts.join(F.broadcast(top), F.lit(True), "left").select(F.col(own), F.coalesce("by_host", "by_domain", "by_suffix", "by_all", F.lit(False)).alias(blocked))
    hosts = cut(hosts, "url-verdicts")
    out = ruled.join(hosts, F.col(host) == F.col(own), "left").withColumn(verdict, F.coalesce(F.col(verdict), F.when(F.col(blocked), "block").otherwise("allow")))
    return out.drop(own, blocked), names[:4]
