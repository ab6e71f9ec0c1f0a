"""URL filters: rules, and host reputation by empirical Bayes.

Labelled outcomes of pages are shrunk from host to registered domain to suffix: a level's
prior is a beta distribution around the posterior mean of the level above, whose strength
is estimated from the spread of that level's rates (beta-binomial moments).  A host is
blocked when even the optimistic bound of its posterior share of good pages is too low.
Only counts per host cross the network; all is DataFrame functions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.store import Scratch

#: (host, path prefix, verdict): a rule fits its host and all subdomains.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LEVELS = ("suffix", "domain", "host")


def host_of(url: F.Column) -> F.Column:
    """After the first :// up to /, ?, # or the end, A-Z lower-cased; empty without ://."""
    rest = F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1))
    return F.translate(F.coalesce(rest, F.lit("")), _UPPER, _UPPER.lower())


def path_of(url: F.Column) -> F.Column:
    """After the host up to ?, # or the end; empty without ://."""
    return F.coalesce(F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)), F.lit(""))


def registered_domain(host: F.Column, suffix_labels: int = 1) -> F.Column:
    """The suffix and one label before it; a shorter host is its own domain."""
    return F.substring_index(host, ".", -(suffix_labels + 1))


def suffix_of(host: F.Column, suffix_labels: int = 1) -> F.Column:
    return F.substring_index(host, ".", -suffix_labels)


def rule_for(host: F.Column, path: F.Column, rules=RULES) -> tuple[F.Column, F.Column]:
    """(text, verdict) of the longest rule that fits; null without one.  Of equal lengths the first given wins."""
    text = verdict = F.lit(None).cast("string")
    for where, start, what in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == where) | host.endswith("." + where)) & path.startswith(start)
        text, verdict = F.when(fits, F.lit(where + start)).otherwise(text), F.when(fits, F.lit(what)).otherwise(verdict)
    return text, verdict


def _strength(counts: DataFrame, level: str, least: float, most: float) -> F.Column:
    """Beta-binomial prior strength a + b from the spread of rates around their parents' means, per level."""
    n, rate, mean = F.col("n"), F.col("good") / F.col("n"), F.col("mean")
    within = mean * (1 - mean)
    # E[n (rate - mean)^2] = within * (1 + (n - 1) rho); rho = 1 / (strength + 1)
    excess = F.sum(n * (rate - mean) * (rate - mean) - within)
    rho = excess / F.sum(within * (n - 1))
    return F.least(F.greatest(F.coalesce(F.when(rho > 0, 1 / rho - 1), F.lit(most)), F.lit(least)), F.lit(most)).alias(f"{level}_strength")


def reputation(outcomes: DataFrame, suffix_labels: int = 1, least: float = 1.0, most: float = 1000.0, z: float = 1.645) -> DataFrame:
    """outcomes(host string, good 0/1) -> one row per host with n, good, mean, lower, upper of its posterior share of good pages.

    Rows with a null host or outcome are not counted.  No outcomes: no rows.
    """
    seen = outcomes.where("host is not null and good is not null").groupBy("host").agg(
        F.count("*").alias("n"), F.sum(F.col("good").cast("long")).alias("good")
    )
    scratch = Scratch(outcomes.sparkSession, "reputation")
    hosts = seen.withColumns({"domain": registered_domain(F.col("host"), suffix_labels), "suffix": suffix_of(F.col("host"), suffix_labels)})
    # pages and labels are read once; all levels come from the counts of hosts
    hosts = scratch.save(hosts, "hosts")
    every = hosts.agg(F.sum("n").alias("n"), F.sum("good").alias("good")).first()
    start, above, of = F.lit((every.good + 1) / (every.n + 2) if every.n else 0.5), None, []
    for level in LEVELS:
        own = hosts.groupBy(*of, level).agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
        # a null join key never occurs: hosts are not null
        own = own.withColumn("mean", start) if above is None else own.join(above, of)
        own = scratch.save(own, f"{level}-counts")
        strength = F.lit(own.agg(_strength(own, level, least, most)).first()[0])  # one number
        a, b = F.col("mean") * strength + F.col("good"), (1 - F.col("mean")) * strength + F.col("n") - F.col("good")
        above = own.withColumns({"a": a, "b": b}).withColumn("mean", F.col("a") / (F.col("a") + F.col("b")))
        above, of = above.select(level, "n", "good", "mean", "a", "b") if level == "host" else above.select(level, "mean"), [level]
    total = F.col("a") + F.col("b")
    sd = F.sqrt(F.col("a") * F.col("b") / (total * total * (total + 1)))
    return above.select("host", "n", "good", "mean", (F.col("mean") - z * sd).alias("lower"), (F.col("mean") + z * sd).alias("upper"))


def judge(pages: DataFrame, outcomes: DataFrame, rules=RULES, least_good: float = 0.5, **options) -> DataFrame:
    """pages(page_id, url, ...) -> (page_id, host, path, rule, verdict, good_mean, good_upper), one row per page.

    A rule that fits decides; else a host whose upper posterior bound is below ``least_good``
    is blocked, and all others, unknown and empty hosts too, are allowed.
    """
    url = F.col("url")
    split = pages.select("page_id", host_of(url).alias("host"), path_of(url).alias("path"))
    text, verdict = rule_for(F.col("host"), F.col("path"), rules)
    known = reputation(outcomes, **options).select("host", F.col("mean").alias("good_mean"), F.col("upper").alias("good_upper"))
    method = F.when(F.col("good_upper") < least_good, F.lit("block")).otherwise(F.lit("allow"))
    out = split.join(known, "host", "left")
    return out.select("page_id", "host", "path", text.alias("rule"), F.coalesce(verdict, method).alias("verdict"), "good_mean", "good_upper")
