"""URL filters: rules, then empirical-Bayes host reputation.

Labelled outcomes of pages (bad or not) are summed by host, registered domain and suffix. The overall rate is the prior
mean of a suffix, a suffix's posterior mean that of its domains, a domain's that of its hosts; how strongly each level
leans on the one above is a beta-binomial prior size fitted by moments over that level. A host is blocked if
the lower bound of its posterior bad rate (the 5 % quantile of the beta distribution) is above the limit; a host without labels has its domain's posterior, and so on up.

Only counts by host are shuffled; a hot host is one row after the map-side sum. Hosts meet pages in an adaptive join.

Defined cases: a null url or one without "://" has empty host and path, fits no rule and takes the overall prior; pages
without labels count nowhere; with no labels at all nothing is blocked by reputation; repeated rows stay rows; a
page with several labels is bad if one of them is; empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathweave.llm import common as C

#: The rules, as verdict and host with path.
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))
LIMIT, BOUND_SHARE, LEAST_SIZE, MOST_SIZE = 0.5, 0.05, 2.0, 200.0


def host_of(url: Column) -> Column:
    return C.ascii_lower(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits and its verdict (null if none)."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for says, r in sorted(rules, key=lambda x: len(x[1])):
        name, _, rest = r.partition("/")
        fits = ((host == name) | F.endswith(host, F.lit("." + name))) & F.startswith(path, F.lit("/" + rest))
        rule, verdict = F.when(fits, F.lit(r)).otherwise(rule), F.when(fits, F.lit(says)).otherwise(verdict)
    return rule, verdict


#: Labels that stand before a country's own label as part of the public suffix (as in co.uk).
SECOND_LEVEL = ("ac", "co", "com", "edu", "gob", "gov", "gouv", "mil", "ne", "net", "nom", "or", "org", "sch")


def name_of(host: Column) -> Column:
    """The host's name without user and port; addresses (only digits and dots, or in brackets) stay whole."""
    return F.regexp_replace(F.regexp_replace(host, r"^.*@", ""), r":[0-9]*$", "")


def suffix_of(host: Column) -> Column:
    """The public suffix: the last label, or the last two where a country's label follows one of SECOND_LEVEL. Addresses are
    their own suffix."""
    name = name_of(host)
    two = F.rlike(name, F.lit(r"(^|\.)(" + "|".join(SECOND_LEVEL) + r")\.[a-z]{2}$"))
    address = F.rlike(name, F.lit(r"^([0-9.]+|\[.*\])$"))
    return F.when(address, name).when(two, F.substring_index(name, ".", -2)).otherwise(F.substring_index(name, ".", -1))


def domain_of(host: Column) -> Column:
    """The registered domain: the suffix and the label before it (the whole of a shorter name)."""
    name, suffix = name_of(host), suffix_of(host)
    labels = F.size(F.split(suffix, r"\."))
    return F.when(name == suffix, name).when(labels == 2, F.substring_index(name, ".", -3)).otherwise(F.substring_index(name, ".", -2))


def _level(counts: DataFrame, key: str, up: DataFrame, up_key: str) -> DataFrame:
    """counts(key, up_key, n, bad), up(up_key, mean) -> with prior size, posterior a and b, and mean.

    Prior size by moments: the spread of rates around the parents' means beyond what chance makes gives how much
    children differ; the less they do, the larger the size."""
    own = counts.join(up.select(up_key, F.col("mean").alias("prior")), up_key)
    spread = F.pow(F.col("bad") - F.col("n") * F.col("prior"), 2)
    chance = F.col("n") * F.col("prior") * (1 - F.col("prior"))
    pairs = F.col("n") * (F.col("n") - 1) * F.col("prior") * (1 - F.col("prior"))
    fit = own.agg(F.sum(spread).alias("s"), F.sum(chance).alias("c"), F.sum(pairs).alias("p"))
    # Overdispersion: E[spread] = chance + pairs / (size + 1).
    rho = F.when((F.col("p") > 0) & (F.col("s") > F.col("c")), (F.col("s") - F.col("c")) / F.col("p")).otherwise(0.0)
    size = F.greatest(F.lit(LEAST_SIZE), F.least(F.lit(MOST_SIZE), F.when(rho > 0, 1 / rho - 1).otherwise(MOST_SIZE)))
    # One number for the level.
    found = fit.select(F.round(F.coalesce(size, F.lit(MOST_SIZE)), 6).alias("size")).first()["size"]
    own = own.withColumn("size", F.lit(found))
    a = F.col("prior") * F.col("size") + F.col("bad")
    b = (1 - F.col("prior")) * F.col("size") + F.col("n") - F.col("bad")
    return own.withColumn("a", a).withColumn("b", b).withColumn("mean", a / (a + b))


def incomplete_beta(x: np.ndarray, a: np.ndarray, b: np.ndarray, log_beta: np.ndarray) -> np.ndarray:
    """The beta distribution's share below x, by the continued fraction, from the side where it converges fast."""
    flip = x > (a + 1) / (a + b + 2)
    x, a, b = np.where(flip, 1 - x, x), np.where(flip, b, a), np.where(flip, a, b)
    with np.errstate(divide="ignore"):
        front = np.exp(a * np.log(x) + b * np.log1p(-x) - log_beta) / a
    tiny = 1e-300
    f, c, d = np.ones_like(x), np.ones_like(x), np.zeros_like(x)
    for i in range(200):
        m = i // 2
        if i == 0:
            term = np.ones_like(x)
        elif i % 2 == 0:
            term = m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m))
        else:
            term = -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))
        d = 1 / np.where(np.abs(1 + term * d) < tiny, tiny, 1 + term * d)
        c = 1 + term / np.where(np.abs(c) < tiny, tiny, c)
        f *= c * d
        if np.all(np.abs(1 - c * d) < 1e-12):
            break
    share = front * (f - 1)
    return np.where(flip, 1 - share, share)


def beta_quantile(a: np.ndarray, b: np.ndarray, share: float = BOUND_SHARE) -> np.ndarray:
    """x below which a share of the beta distribution lies, by bisection."""
    a, b = np.asarray(a, np.float64), np.asarray(b, np.float64)
    log_beta = np.array([math.lgamma(p) + math.lgamma(q) - math.lgamma(p + q) for p, q in zip(a, b)])
    low, high = np.zeros_like(a), np.ones_like(a)
    for _ in range(50):
        mid = (low + high) / 2
        below = incomplete_beta(mid, a, b, log_beta) < share
        low, high = np.where(below, mid, low), np.where(below, high, mid)
    return (low + high) / 2


def bounded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow function: kind, name, a, b, n -> with the lower bound of the posterior."""
    for batch in batches:
        bound = beta_quantile(batch.column(2).to_numpy(), batch.column(3).to_numpy()) if batch.num_rows else np.zeros(0)
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(bound)], [*batch.schema.names, "bound"])


def reputations(hosts: DataFrame, labels: DataFrame) -> DataFrame:
    """hosts(page_id, host), labels(page_id, bad) -> kind, name, a, b, n: posteriors of hosts, domains, suffixes and all."""
    judged = labels.filter("page_id is not null and bad is not null").groupBy("page_id").agg(F.max("bad").alias("bad"))
    seen = hosts.filter("host <> ''").join(judged, "page_id").groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum("bad").alias("bad"))
    seen = C.settle(seen.withColumn("domain", domain_of(F.col("host"))).withColumn("suffix", suffix_of(F.col("host"))), "hosts-counts")
    all_ = seen.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum("bad"), F.lit(0)).alias("bad")).select(F.lit("*").alias("all"), "n", ((F.col("bad") + 1) / (F.col("n") + 2)).alias("mean"), (F.col("bad") + 1.0).alias("a"), (F.col("n") - F.col("bad") + 1.0).alias("b"))
    suffix = _level(seen.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).withColumn("all", F.lit("*")), "suffix", all_, "all")
    domain = _level(seen.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")), "domain", suffix, "suffix")
    host = _level(seen, "host", domain, "domain")
    parts = [d.select(F.lit(k).alias("kind"), F.col(k).alias("name"), "a", "b", "n") for k, d in (("host", host), ("domain", domain), ("suffix", suffix), ("all", all_))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


def filtered(pages: DataFrame, labels: DataFrame, rules=RULES, limit: float = LIMIT) -> DataFrame:
    """pages(page_id, url), labels(page_id, bad) -> page_id, host, path, rule, verdict, bound."""
    read = pages.select("page_id", host_of(F.col("url").cast("string")).alias("host"), path_of(F.col("url").cast("string")).alias("path"))
    known = reputations(read, labels).select("kind", "name", F.col("a").cast("double").alias("a"), F.col("b").cast("double").alias("b"), F.col("n").cast("long").alias("n"))
    known = C.settle(known.mapInArrow(bounded, "kind string, name string, a double, b double, n long, bound double"), "hosts-known")
    of = lambda kind, name: known.filter(F.col("kind") == kind).select(F.col("name").alias(name), F.col("bound").alias(f"{kind}_bound"))
    # Bounds are found for the distinct hosts, then joined to pages once.
    hosts = read.select("host").distinct().withColumn("domain", domain_of(F.col("host"))).withColumn("suffix", suffix_of(F.col("host"))).withColumn("all", F.lit("*"))
    hosts = hosts.join(of("host", "host"), "host", "left").join(of("domain", "domain"), "domain", "left").join(of("suffix", "suffix"), "suffix", "left").join(of("all", "all"), "all", "left")
    hosts = hosts.select("host", F.coalesce("host_bound", "domain_bound", "suffix_bound", "all_bound", F.lit(0.0)).alias("bound"))
    # Written first: what is joined then is two plain tables, whose hot hosts the adaptive planner may split.
    hosts = C.settle(hosts, "hosts-bounds")
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    out = read.join(hosts, "host")
    return out.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("bound") > limit, F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"), F.round("bound", 9).alias("bound"))
