"""URL filters: curated rules, and empirical-Bayes reputation of hosts; DataFrame operations only.

*Rules* (action, host, path): a rule fits its host and all subdomains if the url's path starts with the rule's; the
longest fitting rule decides.

*Reputation* of the rest: outcomes of labelled pages (bad or not) are counted for suffix, registered domain and host. Each
level's bad share has a beta prior centred on the level above (host from domain, domain from suffix, suffix from all), whose strength is
fitted to the level by the method of moments, so hosts with few labels are shrunk and hosts with many speak for
themselves. A page is blocked if its host's lower posterior bound (mean less ``z`` deviations) exceeds ``most_bad``.

Counts are aggregated by host before any join and written; each level's posterior is written too, and its strength, one number, comes to the
driver. A host that holds a third of all pages is one row of the reputation table; verdicts are found for each distinct host, never for pages, and hosts
with more than an even share of the pages (fewer than partitions) are broadcast to them, so no task gets a hot host's pages. Posteriors are rounded to 9 digits.

Defined results. Null url or one without "://": host and path empty, no rule, and the reputation of the empty host. Unlabelled hosts get
their domain's, suffix's or the global posterior. No labels at all: allowed. Outcomes of pages that are not in the table, and null outcomes, do not count.
Repeated page rows are judged alike; each labelled row counts. Extra columns are ignored. The suffix is the last label of the host without user and port, or the
longest of ``suffixes`` (such as ``co.uk``) that it ends with; the registered domain has one label more. Urls of any length are read whole. Rules of equal length: the lesser text.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import slim, written

# The contract's rules (action, host, path).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
MOST_BAD, Z = 0.5, 1.645
LEAST_STRENGTH, MOST_STRENGTH = 1.0, 1000.0


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.instr(url, "://") > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise("")
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    return ascii_lower(host), F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)?", 1)


def located(pages: DataFrame) -> DataFrame:
    host, path = host_and_path(F.col("url"))
    return slim(pages, "page_id", "url").select("page_id", host.alias("host"), path.alias("path"))


def levels(host: Column, suffixes: Iterable[str] = ()) -> tuple[Column, Column]:
    """(registered domain, suffix). ``suffixes``: public suffixes of several labels, a driver-side list of some hundreds."""
    bare = F.regexp_replace(F.regexp_replace(host, r"^.*@", ""), r":[0-9]*$", "")
    labels = F.lit(1)
    for s in sorted(suffixes, key=lambda s: s.count(".")):
        labels = F.when((bare == s) | bare.endswith(f".{s}"), s.count(".") + 1).otherwise(labels)
    cut = lambda more: F.array_join(F.reverse(F.slice(F.reverse(F.split(bare, r"\.", -1)), F.lit(1), labels + more)), ".")
    return cut(1), cut(0)


def with_rule(pages: DataFrame, rules: Iterable[tuple[str, str, str]] = RULES) -> DataFrame:
    """Adds ``rule`` and ``action`` of the longest fitting rule (ties: the lesser text), else null.

    The rules are a driver-side list, compiled into one expression, longest first; hundreds are fine.
    """
    rule = action = F.lit(None).cast("string")
    for act, host, path in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), [-ord(c) for c in r[1] + r[2]])):
        fits = ((F.col("host") == host) | F.col("host").endswith(f".{host}")) & F.col("path").startswith(path)
        rule, action = F.when(fits, host + path).otherwise(rule), F.when(fits, act).otherwise(action)
    return pages.withColumns({"rule": rule, "action": action})


def _level(key: str, at: DataFrame) -> DataFrame:
    """``at`` (key, n, bad, and the prior's mean ``m``) to key, mean, variance: the beta-binomial posterior, written.

    Method of moments over the level's groups: the excess of the groups' variance around their priors over the binomial
    one gives the prior's strength.
    """
    off = F.col("bad") - F.col("n") * F.col("m")
    binomial = F.col("m") * (1 - F.col("m"))
    room = F.sum((F.col("n") - 1) * binomial)
    rho = F.when(room > 0, (F.sum(off * off / F.col("n")) - F.sum(binomial)) / room).otherwise(0.0)
    strength = F.when(rho > 0, F.least(F.greatest(1 / rho - 1, F.lit(LEAST_STRENGTH)), F.lit(MOST_STRENGTH))).otherwise(MOST_STRENGTH)
    k = F.lit(at.agg(F.round(strength, 6)).first()[0])
    a, b = k * F.col("m") + F.col("bad"), k * (1 - F.col("m")) + F.col("n") - F.col("bad")
    both = a + b
    return written(at.select(key, F.round(a / both, 9).alias("mean"), F.round(a * b / (both * both * (both + 1)), 12).alias("variance")), f"by_{key}")


def reputation(pages: DataFrame, outcomes: DataFrame, suffixes: Iterable[str] = ()) -> tuple[dict[str, DataFrame], tuple[float, float] | None]:
    """Posteriors of ``host``, ``domain`` and ``suffix``, and the mean and variance of all (None without labels); outcomes: page_id, bad (0 or 1)."""
    known = slim(outcomes, "page_id", "bad").where("page_id is not null and bad is not null")
    domain, suffix = levels(F.col("host"), suffixes)
    counted = located(pages).join(known, "page_id").groupBy("host").agg(F.count("*").alias("n"), F.sum(F.col("bad").cast("long")).alias("bad"))
    hosts = written(counted.withColumns({"domain": domain, "suffix": suffix}), "hosts")
    n, bad = F.sum("n"), F.sum("bad")
    a, b = bad + 0.5, n - bad + 0.5
    top = hosts.agg(F.round(a / (a + b), 9).alias("mean"), F.round(a * b / ((a + b) * (a + b) * (a + b + 1)), 12).alias("variance")).first()
    if top.mean is None:
        return {}, None
    found: dict[str, DataFrame] = {}
    for key, parent in (("suffix", None), ("domain", "suffix"), ("host", "domain")):
        counts = hosts.groupBy(key, *filter(None, [parent])).agg(n.alias("n"), bad.alias("bad"))
        prior = counts.join(found[parent].select(parent, F.col("mean").alias("m")), parent) if parent else counts.withColumn("m", F.lit(top.mean))
        found[key] = _level(key, written(prior, f"of_{key}"))
    return found, tuple(top)


def judge(pages: DataFrame, outcomes: DataFrame, rules: Iterable[tuple[str, str, str]] = RULES, most_bad: float = MOST_BAD, z: float = Z, suffixes: Iterable[str] = ()) -> DataFrame:
    """page_id, host, path, rule, verdict, posterior (mean), bound for every row of ``pages``; the last two are null without any labels."""
    known, top = reputation(pages, outcomes, suffixes)
    place = with_rule(located(pages), rules)
    domain, suffix = levels(F.col("host"), suffixes)
    hosts = place.groupBy("host").agg(F.count("*").alias("pages")).withColumns({"domain": domain, "suffix": suffix})
    for key, table in known.items():
        hosts = hosts.join(table.select(key, F.col("mean").alias(f"m_{key}"), F.col("variance").alias(f"v_{key}")), key, "left")
    mean, variance = (F.coalesce(*(F.col(f"{x}_{k}") for k in ("host", "domain", "suffix") if k in known), F.lit(top[i] if top else None).cast("double")) for i, x in enumerate("mv"))
    judged = written(hosts.select("host", "pages", mean.alias("mean"), F.round(mean - z * F.sqrt(variance), 6).alias("bound")), "judged")
    parts = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    share = max(1, (judged.agg(F.sum("pages")).first()[0] or 0) // parts)
    hot = F.broadcast(judged.where(F.col("pages") > share).drop("pages"))  # fewer than partitions
    named = place.join(hot, "host").unionByName(place.join(hot.select("host"), "host", "left_anti").join(judged.where(F.col("pages") <= share).drop("pages"), "host"))
    return named.select("page_id", "host", "path", "rule", F.coalesce("action", F.when(F.col("bound") > most_bad, "block").otherwise("allow")).alias("verdict"), F.round("mean", 6).alias("posterior"), "bound")


def outcomes_from_labels(labels: DataFrame) -> DataFrame:
    """Ratings of documents as outcomes of the pages of the same number: bad if toxic or of low quality."""
    return slim(labels, "doc_id", "quality", "toxic").select(F.col("doc_id").alias("page_id"), F.when((F.col("toxic") == 1) | (F.col("quality") == 0), 1).when(F.col("quality") == 1, 0).alias("bad"))
