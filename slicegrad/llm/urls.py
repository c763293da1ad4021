"""URL rules, and host reputation by empirical Bayes, in DataFrame and SQL functions only.

Labelled page outcomes (1 bad, 0 good) are counted by host, registered domain and suffix. Each level's rate is
shrunk to its parent's through a beta-binomial prior whose strength comes from how much the rates of that level
spread beyond chance. A page that no rule judges is blocked if its host's posterior says with ``SURE`` probability that
more than ``limit`` of the host's pages are bad (the lower bound of the beta posterior is above the limit).

``page_outcomes`` gives the labels where there is no table of them: a rule's verdict; else bad for a word of
``HOST_MARKS`` in the host, or for a page full of symbols; else good, if there is a page. Suffixes of several labels
(``SUFFIXES``) are one suffix.

Null urls, and urls without ``://``, have an empty host and path: no rule fits, and they share the empty host's
posterior. Null pages have no outcome of their own. Repeated rows are judged alike, and each counts; an empty table
gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicegrad.llm.common import cut, lower_ascii, text_or_empty

#: Fixed values of the contract: verdict, host and path of each rule.
RULES = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/")]
BROADCAST_HOSTS = 50_000
#: Parts of a host name that label its pages bad.
HOST_MARKS = ["casino", "free-bets", "spam", "ads-track", "adult", "cheap-pills"]
#: Suffixes of more than one label under which anyone may register.
SUFFIXES = ["co.uk", "org.uk", "ac.uk", "gov.uk", "com.au", "net.au", "org.au", "co.nz", "co.jp", "ne.jp", "com.br", "com.cn", "co.in", "co.kr", "co.za", "com.mx", "com.tr"]
JUNK = "|#*$%!"
JUNK_SHARE = 0.04
SURE = 0.95


def parted(url: Column) -> tuple[Column, Column]:
    """Host and path."""
    rest = F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)).otherwise("")
    rest = text_or_empty(rest)
    return lower_ascii(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)), F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)


def fitting(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits, as struct<rule, verdict>, or null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


_SUFFIX = "(?:" + "|".join(x.replace(".", r"\.") for x in SUFFIXES) + r"|[^.]*)$"


def domain_of(host: Column) -> Column:
    """The suffix and the label before it; the whole host, if it has no more."""
    return F.regexp_extract(host, r"(?:^|\.)((?:[^.]+\.)?" + _SUFFIX[:-1] + ")$", 1)


def suffix_of(host: Column) -> Column:
    return F.regexp_extract(host, r"(?:^|\.)(" + _SUFFIX[:-1] + ")$", 1)


def junk_share(html: Column) -> Column:
    return (F.length(html) - F.length(F.translate(html, JUNK, ""))) / F.greatest(F.length(html), F.lit(1))


def page_outcomes(host: Column, verdict: Column, html: Column | None) -> Column:
    """1 bad, 0 good, null unknown."""
    marked = host.rlike("|".join(HOST_MARKS))
    junk = F.lit(False) if html is None else F.coalesce(junk_share(html) > JUNK_SHARE, F.lit(False))
    known = marked if html is None else marked | (F.coalesce(F.length(html), F.lit(0)) > 0)
    return F.when(verdict.isNotNull(), (verdict == "block").cast("int")).when(known, (marked | junk).cast("int"))


GRID = 80


def tail(bad: Column, good: Column, limit: float) -> Column:
    """The probability of a rate above ``limit`` under the beta posterior with these pseudo-counts.

    Sums of its density over the logit, at steps of a tenth of its spread, eight spreads to either side of the middle.
    """
    middle, spread = F.log(bad / good), F.sqrt(1 / bad + 1 / good)
    edge = float(math.log(limit / (1 - limit)))

    def add(acc: Column, k: Column) -> Column:
        t = acc["m"] + acc["s"] * k / 10.0
        # bad * ln(x) + good * ln(1 - x) with x the logistic of t, less its value in the middle
        weight = F.exp(-bad * soft(-t) - good * soft(t) - acc["top"])
        return F.struct(acc["m"].alias("m"), acc["s"].alias("s"), acc["top"].alias("top"), (acc["all"] + weight).alias("all"), (acc["above"] + F.when(t > edge, weight).otherwise(0.0)).alias("above"))

    def soft(t: Column) -> Column:
        """ln(1 + exp(t)), without overflow."""
        return F.greatest(t, F.lit(0.0)) + F.log1p(F.exp(-F.abs(t)))

    start = F.struct(middle.alias("m"), spread.alias("s"), (-bad * soft(-middle) - good * soft(middle)).alias("top"), F.lit(0.0).alias("all"), F.lit(0.0).alias("above"))
    return F.aggregate(F.sequence(F.lit(-GRID), F.lit(GRID)), start, add, lambda acc: acc["above"] / acc["all"])


def shrunk(level: DataFrame, key: str, parent: str | None) -> DataFrame:
    """(key, parent's key, n, bad, prior) to the key's posterior mean ``rate`` and ``strength``.

    The prior's strength is p(1-p)/v - 1, v being the variance of rates beyond that of chance (moments).
    """
    rate = F.col("bad") / F.col("n")
    p = F.col("prior")
    over = level.agg(
        (F.sum(F.col("n") * (rate - p) * (rate - p)) - F.sum(p * (1 - p))).alias("excess"),
        F.sum("n").alias("total"), F.sum(p * (1 - p) * F.col("n")).alias("spread"),
    )
    v = F.greatest(F.col("excess") / F.col("total"), F.lit(1e-4))
    strength = over.select(F.least(F.greatest(F.col("spread") / F.col("total") / v - 1, F.lit(1.0)), F.lit(200.0)).alias("strength"))
    return level.crossJoin(F.broadcast(strength)).withColumn("rate", (F.col("bad") + F.col("strength") * p) / (F.col("n") + F.col("strength")))


def reputations(outcomes: DataFrame) -> DataFrame:
    """``outcomes``: (host, bad 0 or 1). Returns (host, rate, weight): posterior mean and pseudo-count."""
    hosts = cut(outcomes.groupBy("host").agg(F.count(F.lit(1)).cast("double").alias("n"), F.sum("bad").cast("double").alias("bad")).withColumn("domain", domain_of(F.col("host"))).withColumn("suffix", suffix_of(F.col("host"))))
    sums = [F.sum("n").alias("n"), F.sum("bad").alias("bad")]
    whole = hosts.agg(((F.coalesce(F.sum("bad"), F.lit(0.0)) + 1) / (F.coalesce(F.sum("n"), F.lit(0.0)) + 2)).alias("prior"))
    suffixes = shrunk(hosts.groupBy("suffix").agg(*sums).crossJoin(F.broadcast(whole)), "suffix", None).select("suffix", F.col("rate").alias("prior"))
    domains = shrunk(hosts.groupBy("domain", "suffix").agg(*sums).join(suffixes, "suffix"), "domain", "suffix").select("domain", F.col("rate").alias("prior"))
    return shrunk(hosts.join(domains, "domain"), "host", "domain").select("host", "rate", (F.col("n") + F.col("strength")).alias("weight"), "strength", "domain", "suffix")


def judge_urls(pages: DataFrame, url: str = "url", page_id: str = "page_id", rules=RULES, limit: float = 0.5, outcomes: DataFrame | None = None, html: str | None = None) -> DataFrame:
    """``page_id``, ``host``, ``path``, ``rule``, ``verdict``, ``risk`` (the probability that too many pages are bad) for every row.

    ``outcomes`` (host, bad) is a table of labels; without it ``page_outcomes`` are taken, with a look at the column
    ``html`` if it is named. A host without labelled pages has its domain's, then its suffix's, then the whole table's
    mean rate, at the strength of the prior among hosts.
    """
    host, path = parted(F.col(f"`{url}`"))
    split = pages.select(F.col(f"`{page_id}`").alias("page_id"), host.alias("host"), path.alias("path"), *([F.col(f"`{html}`").alias("_html")] if html else [])).withColumn("fit", fitting(F.col("host"), F.col("path"), rules))
    if outcomes is None:
        told = page_outcomes(F.col("host"), F.col("fit.verdict"), F.col("_html") if html else None)
        outcomes = split.select("host", told.alias("bad")).filter("bad is not null")
    known = cut(reputations(outcomes))
    mean = (F.sum(F.col("rate") * F.col("weight")) / F.sum("weight")).alias("rate")
    prior = F.max("strength").alias("weight")  # one number for all hosts

    def told_of(level: DataFrame, key: str) -> DataFrame:
        """(key, risk) of pseudo-counts ``rate`` and ``weight``."""
        rate = F.greatest(F.least(F.col("rate"), F.lit(1 - 1e-6)), F.lit(1e-6))
        return level.select(F.col(key).alias(f"_{key}"), tail(rate * F.col("weight"), (1 - rate) * F.col("weight"), limit).alias(f"risk_{key}"))

    by_host = cut(told_of(known, "host"))
    by_domain = told_of(known.groupBy("domain").agg(mean, prior), "domain")
    by_suffix = told_of(known.groupBy("suffix").agg(mean, prior), "suffix")
    whole = told_of(known.agg(mean, prior).withColumn("all", F.lit(0)), "all").select("risk_all")
    small = by_host.count() <= BROADCAST_HOSTS
    hint = F.broadcast if small else (lambda x: x)
    seen = split.drop("_html").withColumn("domain", domain_of(F.col("host"))).withColumn("suffix", suffix_of(F.col("host")))
    joined = seen
    for key, level in (("host", by_host), ("domain", by_domain), ("suffix", by_suffix)):
        joined = joined.join(hint(level), F.col(key) == F.col(f"_{key}"), "left")
    risk = F.coalesce("risk_host", "risk_domain", "risk_suffix", "risk_all", F.lit(0.0))
    verdict = F.coalesce(F.col("fit.verdict"), F.when(risk > SURE, "block").otherwise("allow"))
    out = joined.crossJoin(F.broadcast(whole))  # one row
    return out.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), verdict.alias("verdict"), risk.alias("risk"))
