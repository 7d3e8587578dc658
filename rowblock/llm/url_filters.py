"""URL filters by empirical-Bayes host reputation (DataFrame functions only).

Given rules come first: the longest one that fits a url decides. Other pages follow their host's reputation:
labelled outcomes of its pages (bad: quality 0 or toxic 1) under a beta-binomial prior whose mean is
the estimate of the registered domain, which is shrunk to that of the suffix, which is shrunk
to the rate of all pages. The strength of each prior comes from the spread of the level's groups around
their parents (method of moments on the intra-class correlation). A host is blocked when
the lower bound of its posterior bad rate, mean - z sd, exceeds a limit.

A host is taken without user and port. Its suffix is its last label, or its last two where these are one of ``suffixes``; its
registered domain has one label more; an IP address or a host without dots is its own domain and suffix. Only page ids, urls and outcomes are
shuffled. Outcomes are summed by host map-side first, and the host table is written once; the rate of all pages and the three strengths
are single numbers that the next level's expressions hold. The join back is on the host, where a hot host is split by
the skew handling of the join.

Defined results: a url that is null or has no "://" has an empty host and path, and no rule fits it; pages without a host have no
reputation and are allowed; pages with the same id are judged one by one; labels of null are ignored; hosts without labels get their
domain's prior; without any labels every page without a rule is allowed; an empty table gives an empty result; other columns are not touched.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage

#: Fixed rules: (host, path, verdict).
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
#: Common suffixes of two labels under which names are registered.
SUFFIXES = ("ac.uk", "co.uk", "gov.uk", "org.uk", "com.au", "net.au", "org.au", "co.nz", "co.jp", "ne.jp", "or.jp", "co.in", "co.kr", "co.za", "com.ar", "com.br", "com.cn", "com.mx", "com.tr", "com.tw")
ADDRESS = r"^(\[.*\]|[0-9]+(\.[0-9]+){3})$"
URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Reputation:
    z: float = 1.645
    limit: float = 0.5
    least_rho: float = 0.0001
    most_rho: float = 0.5
    rate_without_labels: float = 0.1
    suffixes: tuple[str, ...] = SUFFIXES


def host_and_path(url: Column) -> tuple[Column, Column]:
    given = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(given, URL, 1), UPPER, LOWER), F.regexp_extract(given, URL, 2)


def rule_for(host: Column, path: Column, rules: tuple = RULES) -> tuple[Column, Column]:
    """The longest rule that fits, as text, and its verdict; null where none fits."""
    name = verdict = F.lit(None).cast("string")
    for own, start, says in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == own) | host.endswith(f".{own}")) & path.startswith(start)
        name, verdict = F.when(fits, F.lit(own + start)).otherwise(name), F.when(fits, F.lit(says)).otherwise(verdict)
    return name, verdict


def site(host: Column) -> Column:
    """A host without user and port."""
    return F.regexp_replace(host, r"^.*@|:[0-9]*$", "")


def domain_and_suffix(name: Column, suffixes: tuple[str, ...]) -> tuple[Column, Column]:
    address, two = name.rlike(ADDRESS), F.substring_index(name, ".", -2).isin(*suffixes)
    own = lambda labels: F.substring_index(name, ".", -labels)
    return F.when(address, name).when(two, own(3)).otherwise(own(2)), F.when(address, name).when(two, own(2)).otherwise(own(1))


def _strength(groups: DataFrame, control: Reputation) -> float:
    """The strength of the prior of a level, from groups with n, bad and their parents' mean: one number."""
    rate, mean = F.col("bad") / F.col("n"), F.col("prior")
    spread = F.sum(F.col("n") * F.pow(rate - mean, 2)) / F.sum(F.col("n") * mean * (1 - mean))
    size = F.sum("n") / F.count(F.lit(1))
    rho = F.when(size > 1, (spread - 1 / size) / (1 - 1 / size))
    held = F.greatest(F.lit(control.least_rho), F.least(F.lit(control.most_rho), F.coalesce(rho, F.lit(control.most_rho))))
    return groups.where("n > 0").agg((1 / held - 1).alias("strength")).first()["strength"]


def _shrunk(groups: DataFrame, control: Reputation) -> DataFrame:
    """groups with the strength of their level and their mean shrunk to the prior."""
    strength = F.lit(_strength(groups, control)).cast("double")
    return groups.withColumns({"strength": strength, "mean": (F.col("bad") + strength * F.col("prior")) / (F.col("n") + strength)})


def reputation(hosts: DataFrame, control: Reputation | None = None) -> DataFrame:
    """(host, by_host, rate, lower) from (host, n, bad); hosts without outcomes have n = 0."""
    control = control or Reputation()
    domain, suffix = domain_and_suffix(F.col("site"), control.suffixes)
    named = hosts.withColumn("site", site(F.col("host"))).select("host", "site", domain.alias("domain"), suffix.alias("suffix"), "n", "bad")
    hosts = cut_lineage(named)
    summed = lambda *by: hosts.groupBy(*by).agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    total = hosts.agg(F.sum("bad") / F.nullif(F.sum("n"), F.lit(0))).first()[0]
    rate = min(1 - 1e-6, max(1e-6, control.rate_without_labels if total is None else total))
    suffixes = _shrunk(summed("suffix").withColumn("prior", F.lit(rate)), control).select("suffix", F.col("mean").alias("prior"))
    domains = _shrunk(cut_lineage(summed("domain", "suffix").join(suffixes, "suffix")), control).select("domain", "suffix", F.col("mean").alias("prior"))
    judged = _shrunk(cut_lineage(summed("site", "domain", "suffix").join(domains, ["domain", "suffix"])), control)
    sd = F.sqrt(F.col("mean") * (1 - F.col("mean")) / (F.col("n") + F.col("strength") + 1))
    lower = F.col("mean") - control.z * sd
    verdicts = judged.select("site", F.when((lower > control.limit) & (F.col("site") != ""), "block").otherwise("allow").alias("by_host"), F.col("mean").alias("rate"), lower.alias("lower"))
    return hosts.select("host", "site").join(verdicts, "site").drop("site")


def host_outcomes(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """(host, n, bad) over all hosts of pages (page_id, host)."""
    bad = F.coalesce(F.col("quality") == 0, F.lit(False)) | F.coalesce(F.col("toxic") == 1, F.lit(False))
    outcomes = labels.where("doc_id IS NOT NULL AND (quality IS NOT NULL OR toxic IS NOT NULL)").select(F.col("doc_id").alias("page_id"), bad.cast("long").alias("bad"))
    known = pages.join(outcomes, "page_id").groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum("bad").alias("bad"))
    nothing = pages.select("host").distinct().select("host", F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("bad"))
    return known.union(nothing).groupBy("host").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))


def judge(pages: DataFrame, labels: DataFrame, rules: tuple = RULES, control: Reputation | None = None) -> DataFrame:
    """page_id, host, path, rule and verdict for every page."""
    host, path = host_and_path(F.col("url"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"))
    name, says = rule_for(F.col("host"), F.col("path"), rules)
    ruled = split.withColumns({"rule": name, "by_rule": says})
    verdicts = reputation(host_outcomes(split, labels), control).select("host", "by_host")
    return ruled.join(verdicts, "host", "left").select("page_id", "host", "path", "rule", F.coalesce("by_rule", "by_host", F.lit("allow")).alias("verdict"))
