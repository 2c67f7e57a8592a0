"""URL filter: block and allow rules, then empirical-Bayes host reputation (SQL functions only).

Labelled page outcomes (1 = bad) are counted by host, registered domain and suffix. A beta-binomial prior flows
down: the overall rate is the prior of a suffix, the suffix's posterior mean the prior of its domains, the
domain's that of its hosts. How much a level's prior weighs is estimated from the data: the moments of the groups' counts around
their parents' means give the correlation inside a group (see ``strength``). A url is blocked where the posterior
probability that its host's bad rate exceeds a limit is ``sure`` or more.

Defined results: a null url, or one without ``://``, has empty host and path; all such pages are one host with an empty
name. Hosts count with the pages at hand, so each has an outcome; repeated rows count with multiplicity as outcomes
and are judged one by one; null pages are not bad; texts and urls of any length are read whole; empty tables give an empty
result; clashing extra columns are not carried along.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stage

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: (host/path, verdict)
Rules = Sequence[tuple[str, str]]


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty for null or where ``://`` is missing."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), _UPPER, _LOWER)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def match_rules(host: Column, path: Column, rules: Rules) -> Column:
    """The longest rule that fits host (itself or a parent domain) and path prefix; else null.

    The rules are literals of the plan; at most 1,000 are accepted.
    """
    if len(rules) > 1000:
        raise ValueError("at most 1,000 rules")
    out = None
    for rule, _ in sorted(rules, key=lambda r: (-len(r[0]), r[0])):
        own, slash, rest = rule.partition("/")
        fits = ((host == own) | F.endswith(host, F.lit("." + own))) & F.startswith(path, F.lit(slash + rest))
        out = F.when(fits, F.lit(rule)) if out is None else out.when(fits, F.lit(rule))
    return F.lit(None).cast("string") if out is None else out


# Public suffixes of two labels; any other suffix is the last label.
SUFFIXES = ("ac.uk", "co.uk", "gov.uk", "org.uk", "com.au", "net.au", "org.au", "co.in", "co.jp", "co.kr", "co.nz", "co.za", "com.br", "com.cn", "com.mx", "com.tr")


def suffix_of(host: Column, suffixes: Sequence[str] = SUFFIXES) -> Column:
    two = F.substring_index(host, ".", -2)
    return F.when(two.isin(*suffixes), two).otherwise(F.substring_index(host, ".", -1))


def domain_of(host: Column, suffixes: Sequence[str] = SUFFIXES) -> Column:
    """The registered domain: the public suffix and one label more."""
    two = F.substring_index(host, ".", -2)
    return F.when(two.isin(*suffixes), F.substring_index(host, ".", -3)).otherwise(two)


def outcome_of(html: Column) -> Column:
    """A labelled outcome from a page's own content: 1 where symbols or exclamation marks stand in for text, else 0."""
    text = F.regexp_replace(F.coalesce(html, F.lit("")), r"<[^>]*>", " ")
    n = F.greatest(F.length(text), F.lit(1))
    symbols = F.length(text) - F.length(F.translate(text, "#*$%|", ""))
    shouts = F.length(text) - F.length(F.translate(text, "!", ""))
    return F.when((50 * symbols > n) | (50 * shouts > n), 1).otherwise(0)


#: Bounds of a prior's weight in pages, and the weight where no group has two pages.
LEAST, MOST, USUAL = 1.0, 1000.0, 20.0


def strength(groups: DataFrame, n: str, bad: str, mean: str, name: str) -> DataFrame:
    """One row, ``name``: the weight, in pages, of the prior of groups (n, bad) around their parents' means.

    With correlation r inside a group, (bad - n * mean)^2 exceeds n * mean * (1 - mean) by n * (n - 1) * mean * (1 - mean) * r
    on average; the weight is 1 / r - 1.
    """
    spread = F.col(mean) * (1 - F.col(mean))
    over = F.sum((F.col(bad) - F.col(n) * F.col(mean)) * (F.col(bad) - F.col(n) * F.col(mean)) - F.col(n) * spread)
    most = F.sum(F.col(n) * (F.col(n) - 1) * spread)
    r = F.least(F.greatest(over / most, F.lit(1 / (1 + MOST))), F.lit(1 / (1 + LEAST)))
    return groups.agg(F.when(most > 0, 1 / r - 1).otherwise(F.lit(USUAL)).alias(name))


def reputation(outcomes: DataFrame) -> DataFrame:
    """host, n, bad, and the posterior's alpha and beta.

    ``outcomes``: (host, bad) rows. The counts are pre-aggregated by host before any shuffle, so that a host with
    a third of all rows costs a row for each task; levels above are sums over hosts.
    """
    by_host = outcomes.groupBy("host").agg(F.count("*").alias("n"), F.sum("bad").alias("bad"))
    by_host = stage(by_host.select("*", domain_of(F.col("host")).alias("domain"), suffix_of(F.col("host")).alias("suffix")), "hosts")
    by_domain = by_host.groupBy("domain", "suffix").agg(F.sum("n").alias("dn"), F.sum("bad").alias("dbad"))
    by_suffix = by_domain.groupBy("suffix").agg(F.sum("dn").alias("sn"), F.sum("dbad").alias("sbad"))
    total = by_suffix.agg(((F.sum("sbad") + 1.0) / (F.sum("sn") + 2.0)).alias("t_mean"))

    def shrunk(groups: DataFrame, n: str, bad: str, mean: str) -> DataFrame:
        """The groups with their prior's weight ``k``."""
        return groups.join(F.broadcast(strength(groups, n, bad, mean, "k")))

    s = shrunk(by_suffix.join(F.broadcast(total)), "sn", "sbad", "t_mean")
    s = s.select("suffix", ((F.col("sbad") + F.col("k") * F.col("t_mean")) / (F.col("sn") + F.col("k"))).alias("s_mean"))
    d = shrunk(by_domain.join(s, "suffix"), "dn", "dbad", "s_mean")
    d = d.select("domain", ((F.col("dbad") + F.col("k") * F.col("s_mean")) / (F.col("dn") + F.col("k"))).alias("d_mean"))
    h = shrunk(by_host.join(d, "domain"), "n", "bad", "d_mean")
    return h.select("host", "n", "bad", (F.col("bad") + F.col("k") * F.col("d_mean")).alias("alpha"), (F.col("n") - F.col("bad") + F.col("k") * (1 - F.col("d_mean"))).alias("beta"))


#: Points of the density of a posterior.
POINTS = 512


def above(alpha: Column, beta: Column, limit: float) -> Column:
    """The probability that a beta(alpha, beta) rate exceeds ``limit``: its density summed at POINTS midpoints."""
    def log_density(j: Column) -> Column:
        x = (j + 0.5) / F.lit(float(POINTS))
        return (alpha - 1) * F.log(x) + (beta - 1) * F.log(1 - x)

    logs = F.transform(F.sequence(F.lit(0), F.lit(POINTS - 1)), log_density)
    weights = F.transform(logs, lambda v: F.exp(v - F.array_max(logs)))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda acc, v: acc + v)
    first = round(limit * POINTS)
    return total(F.slice(weights, first + 1, POINTS)) / total(weights)


def judge(pages: DataFrame, rules: Rules, limit: float = 0.5, sure: float = 0.95, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """id, host, path, rule, verdict, p_bad (that the host's bad rate exceeds ``limit``) for each row of ``pages``."""
    host, path = split_url(F.col(url_col))
    base = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path"))
    seen = pages.select(host.alias("host"), outcome_of(F.col(html_col)).alias("bad"))
    # A table, so that the join deals both sides itself and a host with very many pages can be split.
    rep = stage(reputation(seen).withColumn("p_bad", above(F.col("alpha"), F.col("beta"), limit)).select("host", "p_bad"), "reputation")
    x = base.join(rep, "host", "left")
    rule = match_rules(F.col("host"), F.col("path"), rules)
    verdicts = dict(rules)
    x = x.select("page_id", "host", "path", rule.alias("rule"), "p_bad")
    said = F.lit(None).cast("string")
    for r, v in verdicts.items():
        said = F.when(F.col("rule") == r, F.lit(v)).otherwise(said)
    own = F.when(F.col("p_bad") >= sure, F.lit("block")).otherwise(F.lit("allow"))
    return x.select("page_id", "host", "path", "rule", F.coalesce(said, own).alias("verdict"), "p_bad")
