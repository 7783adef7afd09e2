"""URL filtering by empirical-Bayes host reputation, in DataFrame functions only.

Labelled page outcomes (bad or not) are counted per host, registered domain and suffix. Each level's
rate is shrunk to the level above: a Beta prior with the parent's posterior mean, whose strength is
fitted over all groups of the level by moments. A host without labels has its domain's posterior,
a domain without labels its suffix's, a suffix without labels the corpus's. A page is blocked where
the lower posterior bound of its host's bad rate, a quantile of its Beta posterior, is above the threshold; by default that is the
corpus's own rate, so a host is blocked once it is worse than the corpus with the stated probability.

Rules (host, path) come first: a rule fits its host and all subdomains if the URL's path starts with
the rule's, and the longest rule wins. In ``judge`` the pages that a rule decides are also the
labelled outcomes unless other labels are given.

The counts are aggregated with map-side combining, so a host with a third of all pages costs one row
a task, and written once; all levels are made from them. Of a level, one row of sums reaches the driver. Posteriors join pages on the host with a join that adaptive execution splits where a key is hot.

Defined results: a null URL, or one without ``://``, has an empty host and path, fits no rule and is
judged as the empty host; repeated rows are judged row by row; empty tables give empty results; with
no labels at all every rate is the neutral prior's and nothing is blocked; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import LOWER, UPPER, materialize

#: Second-level labels under which owners register third-level names.
SECOND_LEVEL = ("ac", "co", "com", "edu", "gov", "net", "org")
#: (host, path, verdict)
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))


def url_host(url: Column) -> Column:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), r"^(?s).*?://([^/?#]*)", 1)
    return F.translate(rest, UPPER, LOWER)


def url_path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"^(?s).*?://[^/?#]*([^?#]*)", 1)


def _bare(host: Column) -> Column:
    """Without user names and port."""
    return F.regexp_replace(F.regexp_replace(host, r"^.*@", ""), r":\d*$", "")


def suffix_of(host: Column) -> Column:
    parts = F.split(_bare(host), r"\.")
    n = F.size(parts)
    last, second = F.element_at(parts, -1), F.try_element_at(parts, F.lit(-2))
    return F.when((n >= 3) & (F.length(last) == 2) & second.isin(*SECOND_LEVEL), F.concat_ws(".", second, last)).otherwise(last)


def domain_of(host: Column) -> Column:
    bare, suffix = _bare(host), suffix_of(host)
    labels = F.size(F.split(suffix, r"\."))
    return F.call_function("substring_index", bare, F.lit("."), -(labels + 1))


def rule_verdict(host: Column, path: Column, rules) -> Column:
    """Struct (rule, verdict) of the longest rule that fits, else nulls."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for rule_host, rule_path, verdict in sorted(rules, key=lambda r: len(r[0]) + len(r[1])):
        fits = ((host == rule_host) | host.endswith(f".{rule_host}")) & path.startswith(rule_path)
        found = F.when(fits, F.struct(F.lit(rule_host + rule_path).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def _shrunk(level: DataFrame, key: str, up: str, parent: DataFrame, prior_strength: float, most: float = 1000.0) -> DataFrame:
    """Posterior (``_a``, ``_b``) of each group of a level, from its counts and its parent's posterior mean.

    The strength m solves, by moments over groups, Var(rate) = mu (1 - mu) / (m + 1) + sampling variance;
    it is one figure per level, from sums over all groups with labels.
    """
    joined = level.join(parent.select(F.col("_key").alias("_up_key"), (F.col("_a") / (F.col("_a") + F.col("_b"))).alias("_mean")), F.col(up) == F.col("_up_key"))
    rate, spread, seen = F.col("_bad") / F.col("_n"), F.col("_mean") * (1 - F.col("_mean")), F.col("_n") > 0
    # Sum over groups of n (rate - mean)^2 has expectation sum of spread * (1 + (n - 1) / (m + 1)).
    total = lambda x: F.coalesce(F.sum(F.when(seen, x)), F.lit(0.0))
    q, s0, s1 = joined.agg(total(F.col("_n") * (rate - F.col("_mean")) * (rate - F.col("_mean"))), total(spread), total(spread * (F.col("_n") - 1))).first()
    m = prior_strength if s1 <= 0 else most if q <= s0 else min(max(s1 / (q - s0) - 1, prior_strength), most)
    a, b = F.col("_mean") * m + F.col("_bad"), (1 - F.col("_mean")) * m + F.col("_n") - F.col("_bad")
    return materialize(joined.select(F.col(key).alias("_key"), a.alias("_a"), b.alias("_b")), "reputation-level")


def host_posteriors(outcomes: DataFrame, hosts: DataFrame, prior_strength: float = 8.0) -> tuple[DataFrame, float]:
    """Posterior (``_key``, ``_a``, ``_b``) of every host of ``hosts`` (column ``_host``), from ``outcomes`` (``_host``, ``_bad`` 0 or 1 or null where unlabelled), and the corpus's rate."""
    rows = outcomes.select("_host", "_bad").unionByName(hosts.select("_host", F.lit(None).cast("int").alias("_bad"))) if hosts is not outcomes else outcomes
    known = rows.groupBy("_host").agg(F.count("_bad").alias("_n"), F.coalesce(F.sum("_bad"), F.lit(0)).alias("_bad"))
    known = known.withColumn("_domain", domain_of(F.col("_host"))).withColumn("_suffix", suffix_of(F.col("_host")))
    known = materialize(known, "reputation-hosts")
    by_domain = materialize(known.groupBy("_domain", "_suffix").agg(F.sum("_n").alias("_n"), F.sum("_bad").alias("_bad")), "reputation-domains")
    by_suffix = materialize(by_domain.groupBy("_suffix").agg(F.sum("_n").alias("_n"), F.sum("_bad").alias("_bad")).withColumn("_all", F.lit(1)), "reputation-suffixes")
    n, bad = by_suffix.agg(F.coalesce(F.sum("_n"), F.lit(0)), F.coalesce(F.sum("_bad"), F.lit(0))).first()
    corpus = known.sparkSession.range(1).select(F.lit(1).alias("_key"), F.lit(bad + 1.0).alias("_a"), F.lit(n - bad + 1.0).alias("_b"))
    suffixes = _shrunk(by_suffix, "_suffix", "_all", corpus, prior_strength)
    domains = _shrunk(by_domain, "_domain", "_suffix", suffixes, prior_strength)
    return _shrunk(known, "_host", "_domain", domains, prior_strength), (bad + 1.0) / (n + 2.0)


def beta_quantile(a: str, b: str, q: float, steps: int = 240) -> Column:
    """The q-quantile of a Beta(a, b) rate, for columns ``a`` and ``b`` above 0.

    The density of the rate's logit is smooth with one peak, whatever a and b: it is summed over even steps from 14
    deviations below the logit's mean to 10 above, and the step where the sum passes q is cut in proportion.
    """
    # Digamma and trigamma, by one step of the recurrence and their asymptotic series.
    psi = lambda x: f"(ln({x} + 1) - 1 / (2 * ({x} + 1)) - 1 / (12 * ({x} + 1) * ({x} + 1)) - 1 / {x})"
    psi1 = lambda x: f"(1 / ({x} * {x}) + 1 / ({x} + 1) + 1 / (2 * ({x} + 1) * ({x} + 1)) + 1 / (6 * ({x} + 1) * ({x} + 1) * ({x} + 1)))"
    soft = lambda u: f"(greatest({u}, 0D) + log1p(exp(-abs({u}))))"
    at = f"named_struct('c', {psi(a)} - {psi(b)}, 's', sqrt({psi1(a)} + {psi1(b)}) * 24 / {steps}, 'top', {a} * {soft(f'-ln({a} / {b})')} + {b} * {soft(f'ln({a} / {b})')})"
    u = f"(g.c + g.s * (i - {steps} * 14 / 24D))"
    dense = f"transform(sequence(0, {steps}), i -> exp(g.top - {a} * {soft(f'(-{u})')} - {b} * {soft(u)}))"
    goal = f"{q} * aggregate(w, 0D, (x, y) -> x + y)"
    walk = f"aggregate(w, named_struct('sum', 0D, 'i', 0D, 'goal', {goal}), (x, y) -> named_struct('sum', x.sum + y, 'i', if(x.sum + y <= x.goal, x.i + 1, if(x.sum < x.goal, x.i + (x.goal - x.sum) / y, x.i)), 'goal', x.goal))"
    # Half a step back: a sum over whole steps stands for the integral up to their middle.
    found = f"transform(array({dense}), w -> {walk}.i - 0.5D)[0]"
    return F.expr(f"transform(array({at}), g -> 1 / (1 + exp(-(g.c + g.s * ({found} - {steps} * 14 / 24D)))))[0]")


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules=RULES, labels: DataFrame | None = None, threshold: float | None = None, level: float = 0.05, prior_strength: float = 8.0) -> DataFrame:
    """One row per page: id, ``host``, ``path``, ``rule``, ``verdict``, ``bad_low`` (the bound that unruled pages are judged by).

    ``labels``: optional (url, bad) outcomes; by default the rules' verdicts on these pages are the outcomes. ``bad_low`` is the
    ``level`` quantile of the host's posterior; ``threshold`` is the corpus's rate if not given.
    """
    read = pages.select(F.col(id_col).alias("_id"), url_host(F.col(url_col)).alias("_host"), url_path(F.col(url_col)).alias("_path"))
    read = read.withColumn("_rule", rule_verdict(F.col("_host"), F.col("_path"), rules))
    if labels is None:
        outcomes = hosts = read.select("_host", (F.col("_rule.verdict") == "block").cast("int").alias("_bad"))
    else:
        outcomes, hosts = labels.select(url_host(F.col("url")).alias("_host"), F.col("bad").cast("int").alias("_bad")), read
    posterior, rate = host_posteriors(outcomes, hosts, prior_strength)
    bounds = materialize(posterior.select("_key", beta_quantile("_a", "_b", level).alias("_low")), "reputation-bounds")
    judged = read.join(bounds, F.col("_host") == F.col("_key"), "left")
    own = F.when(F.col("_low") > (rate if threshold is None else threshold), F.lit("block")).otherwise(F.lit("allow"))
    return judged.select(F.col("_id").alias(id_col), F.col("_host").alias("host"), F.col("_path").alias("path"), F.col("_rule.rule").alias("rule"), F.coalesce(F.col("_rule.verdict"), own).alias("verdict"), F.col("_low").alias("bad_low"))
