"""URL rules, and host reputation by empirical-Bayes shrinkage.

Labelled page outcomes (bad or not) are counted per host. Counts per suffix, registered domain and host form a tree;
the mean of a level is the prior of the next: a beta prior with the parent's posterior mean and a strength fitted by the
method of moments over all nodes of that level. A host is blocked if the lower bound of its posterior is over a limit.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm.common import settle, table

#: fixed values: suffixes of several labels under which names are registered; any other suffix is the last label
SUFFIXES = ("co.uk", "org.uk", "ac.uk", "gov.uk", "com.au", "net.au", "org.au", "com.br", "co.jp", "co.in", "co.nz", "co.za", "com.cn", "com.mx", "com.tr", "github.io", "gitlab.io", "blogspot.com", "wordpress.com", "appspot.com")
#: (verdict, host, path)
RULES = (("allow", "com", "/"), ("block", "example.com", "/en/"), ("allow", "www.example.com", "/en/"), ("block", "net", "/es/"), ("block", "net", "/fr/"))
BLOCK_SHARE, SIGMAS = 0.5, 1.64
MADE = ("host", "path", "rule", "verdict", "mean", "bound", "_url")


def _rest(url: Column) -> Column:
    return F.substring(url, F.locate("://", url) + 3, F.greatest(F.length(url), F.lit(1)))


def host_of(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; empty for null or without ``://``."""
    host = F.regexp_extract(_rest(url), r"\A([^/?#]*)", 1)
    return F.when(F.locate("://", url) > 0, F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).otherwise("")


def path_of(url: Column) -> Column:
    return F.when(F.locate("://", url) > 0, F.regexp_extract(_rest(url), r"\A[^/?#]*([^?#]*)", 1)).otherwise("")


def with_parts(pages: DataFrame) -> DataFrame:
    rows = pages.withColumn("_url", F.coalesce(F.col("url"), F.lit("")))
    return rows.withColumns({"host": host_of(F.col("_url")), "path": path_of(F.col("_url"))}).drop("_url")


def rule_of(rules: Sequence[tuple[str, str, str]] = RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits host and path, or nulls."""
    rule = verdict = None
    for what, host, path in sorted(rules, key=lambda r: -len(r[1] + r[2])):
        fits = ((F.col("host") == host) | F.col("host").endswith(f".{host}")) & F.col("path").startswith(path)
        rule = F.when(fits, host + path) if rule is None else rule.when(fits, host + path)
        verdict = F.when(fits, what) if verdict is None else verdict.when(fits, what)
    return rule, verdict


def levels(host: Column, suffixes: Sequence[str] = SUFFIXES) -> dict[str, Column]:
    """Suffix (the longest listed one that the host ends with, else its last label) and registered domain (one label more).

    A host that is an address or a suffix by itself is its own domain.
    """
    labels = F.split(F.regexp_replace(host, r":[0-9]*\z", ""), r"\.")
    n = F.size(labels)

    def last(m: int) -> Column:
        return F.array_join(F.slice(labels, F.greatest(n - (m - 1), F.lit(1)), m), ".")

    address = host.rlike(r"\A[0-9.]+(:[0-9]*)?\z|\A\[")
    suffix, domain = last(1), last(2)
    for m in sorted({x.count(".") + 1 for x in suffixes}):
        listed = last(m).isin([x for x in suffixes if x.count(".") + 1 == m]) & (n >= m)
        suffix, domain = F.when(listed, last(m)).otherwise(suffix), F.when(listed, last(m + 1)).otherwise(domain)
    return {"suffix": F.when(address, "").otherwise(suffix), "domain": F.when(address, host).otherwise(domain)}


def reputations(hosts: DataFrame, suffixes: Sequence[str] = SUFFIXES) -> DataFrame:
    """Per host, from (host, bad, n): posterior ``mean`` and lower ``bound`` of the share of bad pages.

    Parents' strengths come from the spread of their children: one aggregate a level, one row per node.
    """
    rows = settle(hosts, "hosts").withColumns(levels(F.col("host"), suffixes))
    m0 = rows.agg(((F.coalesce(F.sum("bad"), F.lit(0)) + 0.5) / (F.coalesce(F.sum("n"), F.lit(0)) + 1)).alias("m0")).first()["m0"]

    def strength(nodes: DataFrame) -> float:
        """Method of moments: between-node variance over what sampling alone would give."""
        share = F.col("bad") / F.col("n")
        spread = nodes.where("n > 0").agg(F.sum("n").alias("N"), F.count(F.lit(1)).alias("k"), F.try_divide(F.sum("bad"), F.sum("n")).alias("p"), F.sum(F.col("n") * share * share).alias("q"), F.sum(F.col("n") * F.col("n")).alias("nn"))
        within = F.col("p") * (1 - F.col("p"))
        between = F.try_divide(F.col("q") - F.col("N") * F.col("p") * F.col("p") - (F.col("k") - 1) * within, F.col("N") - F.col("nn") / F.col("N"))
        good = (F.col("k") > 1) & (between > 0) & (within > 0)
        return spread.select(F.when(good, F.greatest(F.lit(0.5), F.least(F.lit(1000.0), within / between - 1))).otherwise(F.lit(10.0)).alias("s")).first()["s"]

    def shrunk(parent: Column, s: float) -> Column:
        return (F.col("bad") + parent * s) / (F.col("n") + s)

    sums = [F.sum("bad").alias("bad"), F.sum("n").alias("n")]
    suffixes, domains = rows.groupBy("suffix").agg(*sums), rows.groupBy("suffix", "domain").agg(*sums)
    s0, s1, s2 = (strength(x) for x in (suffixes, domains, rows))
    suffixes = suffixes.select("suffix", shrunk(F.lit(m0), s0).alias("m1"))
    domains = domains.join(suffixes, "suffix").select("suffix", "domain", shrunk(F.col("m1"), s1).alias("m2"))
    mean = shrunk(F.col("m2"), s2)
    weight = F.col("n") + s2
    out = rows.join(domains, ["suffix", "domain"]).withColumn("mean", mean)
    return out.select("host", "mean", (F.col("mean") - SIGMAS * F.sqrt(F.col("mean") * (1 - F.col("mean")) / (weight + 1))).alias("bound"))


def labelled_pages(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """(host, bad, n) over all pages: a page is bad if the labels of the document in its url say toxic or low quality."""
    known = labels.where(F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("_doc")).agg(F.max(((F.col("toxic") == 1) | (F.col("quality") == 0)).cast("long")).alias("_bad"))
    ids = pages.select("host", F.expr("try_cast(nullif(regexp_extract(path, '([0-9]{1,18})', 1), '') as bigint)").alias("_doc"))
    return ids.join(known, "_doc", "left").groupBy("host").agg(F.sum(F.coalesce("_bad", F.lit(0))).alias("bad"), F.count("_bad").alias("n"))


def judge(pages: DataFrame, labels: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES, share: float = BLOCK_SHARE, suffixes: Sequence[str] = SUFFIXES) -> DataFrame:
    """Add host, path, rule, verdict, and the host's posterior ``mean`` and ``bound`` (columns of these names are replaced).

    A rule's verdict stands; else a host is blocked if its bound is over ``share``, and allowed otherwise. Null urls
    have an empty host and path and are judged as that host. Repeated rows are judged alike and count as pages.
    ``suffixes``: where a registered domain begins, for suffixes of several labels.
    """
    rows = with_parts(pages.drop(*MADE))
    found = reputations(labelled_pages(rows, labels), suffixes)
    rule, verdict = rule_of(rules)
    joined = rows.join(found, "host")
    return joined.withColumns({"rule": rule, "verdict": F.coalesce(verdict, F.when(F.col("bound") > share, "block").otherwise("allow"))})


def op9_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return judge(pages, table(spark, sf_dir, "labels")).select("page_id", "host", "path", "rule", "verdict", "mean", "bound")
