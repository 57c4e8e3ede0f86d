"""URL filters: explicit rules first, then the reputation of hosts.

Labelled outcomes of pages (bad or not) are counted per host, registered domain and
suffix. Each level's expected share of bad pages is the prior of the level below: a
beta prior whose strength is estimated from how much the shares below differ. A
host is blocked when even a low quantile of its posterior share is above a limit.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_pass, materialize, rebatched
from .stats import beta_quantile

#: Default rules: (verdict, host, path); the longest that fits decides.
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: Second labels under which countries (suffixes of two letters) register names.
COUNTRY_SECONDS = ("ac", "co", "com", "edu", "go", "gob", "gouv", "gov", "id", "ltd", "me", "mil", "ne", "net", "nom", "or", "org", "plc", "sch")
#: A host is blocked when its bad share is above LIMIT with all but this probability.
LIMIT, DOUBT = 0.5, 0.05
#: Least and greatest strength of a prior, in pages.
STRENGTH = (1.0, 1000.0)
#: Rules beyond this number are joined as a table instead of being written into the plan.
INLINE_RULES = 500


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first :// up to / ? # or the end, A-Z lowered; path: then up to ? # or the end."""
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    host = F.coalesce(F.regexp_extract(url, pattern, 1), F.lit(""))
    path = F.coalesce(F.regexp_extract(url, pattern, 2), F.lit(""))
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def suffix_and_domain(host: Column, wide_suffixes: tuple[str, ...] | None = None) -> tuple[Column, Column]:
    """The suffix under which names are registered, and the registered domain.

    A suffix has two labels if it is among wide_suffixes (a public list may be given
    there), by default if a second label that countries use stands before a country's
    two letters; others have one.
    """
    labels = F.split(host, r"\.")
    last2 = F.substring_index(host, ".", -2)
    if wide_suffixes is None:
        wide = last2.rlike(rf"^(?:{'|'.join(COUNTRY_SECONDS)})\.[a-z]{{2}}$")
    else:
        wide = last2.isin(*wide_suffixes)
    suffix = F.when(wide, last2).otherwise(F.substring_index(host, ".", -1))
    domain = F.when(F.size(labels) <= F.when(wide, 2).otherwise(1), host).when(wide, F.substring_index(host, ".", -3)).otherwise(last2)
    return suffix, domain


def match_rules(pages: DataFrame, rules=RULES) -> DataFrame:
    """Add `rule` and `rule_verdict`: of the rules that fit host (or a parent of it) and path, the longest."""
    order = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[1], r[2], r[0]))
    host, path = F.col("host"), F.col("path")
    if len(order) <= INLINE_RULES:
        rule = verdict = F.lit(None).cast("string")
        for v, h, p in reversed(order):
            fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
            rule, verdict = F.when(fits, h + p).otherwise(rule), F.when(fits, v).otherwise(verdict)
        return pages.withColumns({"rule": rule, "rule_verdict": verdict})
    spark = pages.sparkSession
    table = spark.createDataFrame([(i, v, h, p) for i, (v, h, p) in enumerate(order)], "rank long, v string, rh string, rp string")
    # parents of a host: as many as it has labels; pages of one host and path share the work
    sites = pages.select("host", "path").distinct()
    parents = F.expr(r"transform(sequence(1, size(split(host, '\\.'))), k -> substring_index(host, '.', -k))")
    fits = sites.withColumn("rh", F.explode(parents)).join(table, "rh").where(F.col("path").startswith(F.col("rp")))
    first = fits.groupBy("host", "path").agg(F.min(F.struct("rank", F.concat("rh", "rp").alias("rule"), "v")).alias("m"))
    first = first.select("host", "path", F.col("m.rule").alias("rule"), F.col("m.v").alias("rule_verdict"))
    return pages.join(first, ["host", "path"], "left")


def _strength() -> Column:
    """Strength of the prior that a parent's keys share, by the method of moments over the keys' shares; rows: n, bad, p0."""
    share = F.col("bad") / F.col("n")
    spread = F.sum(F.col("n") * F.pow(share - F.col("p0"), 2))
    k = F.count("*")
    n = F.sum("n")
    p = F.first("p0")
    within = p * (1 - p)
    # spread among keys beyond what sampling alone gives, as a correlation of pages of a key
    extra = (spread - (k - 1) * within) / F.greatest((n - F.sum(F.col("n") * F.col("n")) / n) * within, F.lit(1e-9))
    rho = F.when((k < 2) | (within <= 0), F.lit(0.1)).otherwise(F.least(F.greatest(extra, F.lit(1e-4)), F.lit(0.5)))
    return F.least(F.greatest(1 / rho - 1, F.lit(STRENGTH[0])), F.lit(STRENGTH[1])).alias("m0")


def _bounds(doubt: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in rebatched(batches):
            low = beta_quantile(doubt, t.column("a").to_numpy(), t.column("b").to_numpy())
            yield from t.drop_columns(["a", "b"]).append_column("bad_bound", pa.array(low)).to_batches()

    return run


def reputations(outcomes: DataFrame, doubt: float = DOUBT, wide_suffixes: tuple[str, ...] | None = None) -> DataFrame:
    """host, n, bad, bad_share and bad_bound, from rows of (host, bad 0/1 or null).

    bad_share is the posterior mean, bad_bound the posterior's quantile at `doubt`.
    Hosts of domains and suffixes without any label take the level above's mean.
    """
    suffix, domain = suffix_and_domain(F.col("host"), wide_suffixes)
    by_host = outcomes.groupBy("host").agg(F.count("bad").alias("n"), F.coalesce(F.sum("bad"), F.lit(0)).cast("double").alias("bad"))
    by_host = materialize(by_host.withColumn("suffix", suffix).withColumn("domain", domain), "hosts")
    total = by_host.agg(F.sum("n"), F.sum("bad")).first()
    p_all = ((total[1] or 0.0) + 1.0) / ((total[0] or 0) + 2.0)
    above = None
    levels = ["host", "domain", "suffix"]
    for key, parent in (("suffix", None), ("domain", "suffix"), ("host", "domain")):
        counts = by_host.groupBy(*levels[levels.index(key) :]).agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
        if parent is None:
            counts = counts.withColumn("p0", F.lit(p_all))
            whole = counts.where("n > 0").agg(_strength()).first()[0]
            counts = counts.withColumn("m0", F.lit(whole).cast("double"))
        else:
            counts = counts.join(above.select(parent, F.col("mean").alias("p0")), parent)
            counts = counts.join(counts.where("n > 0").groupBy(parent).agg(_strength()), parent, "left")
        m0 = F.coalesce("m0", F.lit(10.0))
        a, b = F.col("p0") * m0 + F.col("bad"), (1 - F.col("p0")) * m0 + F.col("n") - F.col("bad")
        above = materialize(counts.withColumn("a", a).withColumn("b", b).withColumn("mean", F.col("a") / (F.col("a") + F.col("b"))), key)
    slim = above.select("host", "n", "bad", F.col("mean").alias("bad_share"), "a", "b")
    return arrow_pass(slim, _bounds(doubt), "host string, n long, bad double, bad_share double, bad_bound double")


def judge_pages(pages: DataFrame, labels: DataFrame, rules=RULES, limit: float = LIMIT) -> DataFrame:
    """page_id, host, path, rule, verdict, bad_share, bad_bound of every page.

    A page's outcome is the label of the same number: bad if of quality 0 or toxic;
    repeated labels count once, as bad if any of them is. A url without :// (or null)
    has empty host and path and is allowed, unless its host '' earns a block. Pages
    without page_id have no outcome; repeated rows each get a row and each count as a
    page of their host. Urls of any length are read whole; extra columns, whatever
    their names, are ignored; an empty table gives an empty result.
    """
    host, path = host_and_path(F.col("url").cast("string"))
    slim = materialize(pages.select(F.col("page_id").cast("long").alias("page_id"), host.alias("host"), path.alias("path")), "urls")
    bad = ((F.coalesce("quality", F.lit(1)) == 0) | (F.coalesce("toxic", F.lit(0)) == 1)).cast("int")
    marks = labels.where(F.col("quality").isNotNull() | F.col("toxic").isNotNull()).groupBy(F.col("doc_id").alias("page_id")).agg(F.max(bad).alias("bad"))
    known = reputations(slim.select("page_id", "host").join(marks, "page_id", "left"))
    judged = match_rules(slim, rules).join(known, "host", "left")
    by_host = F.when(F.col("bad_bound") > limit, "block").otherwise("allow")
    return judged.select("page_id", "host", "path", "rule", F.coalesce("rule_verdict", by_host).alias("verdict"), "bad_share", "bad_bound")
