"""Host reputation by empirical Bayes, with explicit rules before it.

Labelled page outcomes are counted by host, registered domain and suffix. Each level's rate is shrunk towards the level
above by a beta prior whose strength comes from the spread between siblings (moments of the beta-binomial): few labels
leave a host near its domain, many let it stand on its own. A host is blocked when even the upper posterior bound of
its rate of good pages is below the wanted rate.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from raydescent.llm.common import LOWER, UPPER, cut, skew_safe_lookup, spare

#: Suffixes of two labels under which names are registered.
TWO_LABEL_SUFFIXES = ("ac.uk", "co.in", "co.jp", "co.kr", "co.nz", "co.uk", "co.za", "com.au", "com.br", "com.cn", "com.mx", "com.tr", "gov.uk", "net.au", "org.au", "org.uk")


@dataclass(frozen=True)
class UrlRule:
    """Holds for a host and all its subdomains, on paths that start with path (at most some hundreds of rules)."""

    allow: bool
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path

    @classmethod
    def parse(cls, line: str) -> UrlRule:
        action, _, pattern = line.partition(" ")
        host, slash, path = pattern.partition("/")
        return cls(action == "allow", host, slash + path)


PRODUCTION_RULES = tuple(map(UrlRule.parse, ("allow org/", "block example.org/es/", "block example.org/en/1", "allow com/fr/", "block com/de/")))


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty for a null url or one without ://."""
    host = F.regexp_extract(url, "://([^/?#]*)", 1)
    path = F.regexp_extract(url, "://[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, UPPER, LOWER), F.lit("")), F.coalesce(path, F.lit(""))


def longest_rule(host: Column, path: Column, rules: tuple[UrlRule, ...]) -> tuple[Column, Column]:
    """The text and the verdict of the longest rule that fits, null if none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.text), len(r.host))):  # later conditions stand outside and win
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        name = F.when(fits, F.lit(r.text)).otherwise(name)
        verdict = F.when(fits, F.lit("allow" if r.allow else "block")).otherwise(verdict)
    return name, verdict


def domain_parts(host: Column, wide_suffixes: tuple[str, ...] = TWO_LABEL_SUFFIXES) -> tuple[Column, Column]:
    """Registered domain and suffix of a host, without user part, port and final dot. An IP address is its own domain.

    wide_suffixes: suffixes of two labels under which names are registered; all others have one label.
    """
    bare = F.regexp_replace(host, "^.*@", "")
    address = bare.rlike(r"^\[|^[0-9.]+(:[0-9]*)?$")
    name = F.when(bare.startswith("["), F.regexp_extract(bare, r"^(\[[^\]]*\]?)", 1)).otherwise(F.regexp_replace(bare, r"\.?(:[0-9]*)?$", ""))
    two, three = F.substring_index(name, ".", -2), F.substring_index(name, ".", -3)
    wide = two.isin(*wide_suffixes)
    suffix = F.when(address, F.lit("")).when(wide, two).otherwise(F.substring_index(name, ".", -1))
    return F.when(address, name).when(wide, three).otherwise(two), suffix


def _strength(level: DataFrame, mean: str, most: float = 10_000.0) -> float:
    """a+b of the beta prior from children with counts n, k under their parents' mean: moments of the beta-binomial."""
    m, n, k = F.col(mean), F.col("n"), F.col("k")
    over = F.sum((k - n * m) * (k - n * m) - n * m * (1 - m))
    room = F.sum(n * (n - 1) * m * (1 - m))
    got = level.where("n > 1").agg(over.alias("o"), room.alias("r")).first()
    if not got["r"]:
        return most
    rho = min(max(got["o"] / got["r"], 1 / (1 + most)), 0.5)
    return 1 / rho - 1


def host_reputation(pages: DataFrame, outcomes: DataFrame, z: float = 1.64, wide_suffixes: tuple[str, ...] = TWO_LABEL_SUFFIXES) -> DataFrame:
    """pages (page_id, host); outcomes (page_id, good 0/1; ids without a label are absent, null good is no label).

    Returns host, n_pages, n_labelled, good_mean, good_upper. Hosts without labels get their domain's rate, unknown
    domains their suffix's, and with no labels at all the mean is 1/2 with the widest bound. good_upper is the posterior
    mean and z posterior standard deviations, 1 at most: the normal stand-in for a beta quantile, which Spark lacks.
    """
    labelled = outcomes.where("good IS NOT NULL").groupBy("page_id").agg(F.max("good").alias("good"))
    domain, suffix = domain_parts(F.col("host"), wide_suffixes)
    hosts = pages.join(labelled, "page_id", "left").groupBy("host").agg(F.count("*").alias("n_pages"), F.count("good").alias("n"), F.coalesce(F.sum("good"), F.lit(0)).alias("k"))
    hosts = cut(hosts.select("host", domain.alias("domain"), suffix.alias("suffix"), "n_pages", F.col("n").cast("double"), F.col("k").cast("double")), "hosts")
    domains = hosts.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("k").alias("k"), F.count("*").alias("n_hosts"))
    suffixes = domains.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("k").alias("k"), F.count("*").alias("n_domains"))
    top = hosts.agg(F.sum("n").alias("n"), F.sum("k").alias("k"), F.count("*").alias("hosts")).first()
    mean = ((top["k"] or 0) + 1) / ((top["n"] or 0) + 2)

    def shrunk(level: DataFrame, parent: str, out: str) -> DataFrame:
        s = _strength(level, parent)
        return level.withColumn("_s", F.lit(s)).withColumn(out, (F.col("k") + s * F.col(parent)) / (F.col("n") + s))

    suffixes = shrunk(suffixes.withColumn("top_mean", F.lit(mean)), "top_mean", "suffix_mean").select("suffix", "suffix_mean", "n_domains")
    n_domains = domains.count()
    domains = skew_safe_lookup(domains, suffixes, "suffix", "n_domains", n_domains).drop("n_domains")
    domains = cut(shrunk(domains, "suffix_mean", "domain_mean").select("domain", "domain_mean", "n_hosts"), "domains")
    hosts = skew_safe_lookup(hosts, domains, "domain", "n_hosts", top["hosts"])
    hosts = shrunk(hosts, "domain_mean", "good_mean")
    weight = F.col("n") + F.col("_s")
    spread = F.sqrt(F.col("good_mean") * (1 - F.col("good_mean")) / (weight + 1))
    return hosts.select("host", "n_pages", F.col("n").cast("long").alias("n_labelled"), "good_mean", F.least(F.lit(1.0), F.col("good_mean") + z * spread).alias("good_upper"))


def judge_urls(pages: DataFrame, outcomes: DataFrame, rules: tuple[UrlRule, ...] = PRODUCTION_RULES, least_good: float = 0.5, z: float = 1.64) -> DataFrame:
    """page_id, host, path, rule, verdict, n_labelled, good_upper: one row per row of pages (page_id, url).

    A rule's verdict stands; else a host is blocked when good_upper < least_good. Null and odd urls have empty host and
    path and are judged as one host. Rows with one page_id are judged each by itself; their label counts for each.
    """
    host, path = url_parts(F.col("url"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"))
    facts = cut(host_reputation(split, outcomes, z), "reputation")
    total = facts.agg(F.sum("n_pages")).first()[0] or 0
    rows = skew_safe_lookup(split, facts, "host", "n_pages", total)
    rule, verdict = longest_rule(F.col("host"), F.col("path"), rules)
    own = F.when(F.col("good_upper") < least_good, "block").otherwise("allow")
    return rows.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, own).alias("verdict"), "n_labelled", "good_upper")


def filter_urls(pages: DataFrame, outcomes: DataFrame, rules: tuple[UrlRule, ...] = PRODUCTION_RULES, least_good: float = 0.5, z: float = 1.64) -> DataFrame:
    """The rows of pages whose host and path are allowed, columns as in pages; the judgement is made once per row."""
    host, path = url_parts(F.col("url"))
    h, p, n, up = spare(pages.columns, "_host", "_path", "_pages", "_upper")
    rows = pages.withColumns({h: host, p: path})
    split = rows.select("page_id", F.col(h).alias("host"))
    facts = cut(host_reputation(split, outcomes, z), "reputation").select(F.col("host").alias(h), F.col("n_pages").alias(n), F.col("good_upper").alias(up))
    total = facts.agg(F.sum(n)).first()[0] or 0
    _, verdict = longest_rule(F.col(h), F.col(p), rules)
    judged = skew_safe_lookup(rows, facts, h, n, total)
    own = F.when(F.col(up) < least_good, "block").otherwise("allow")
    return judged.where(F.coalesce(verdict, own) == "allow").select(*[F.col(f"`{c}`") for c in pages.columns])
