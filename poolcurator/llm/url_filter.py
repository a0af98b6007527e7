"""URL verdicts from rules and empirical-Bayes host reputations, with DataFrame functions only.

Rules give a verdict to the pages they fit. The others are judged by the reputation of their host, which comes
from labelled page outcomes: a label column of the caller's where there is one, else a word of the url that
names what is to be kept out (`BAD_WORDS`), else the verdict of a rule; a page that neither marks counts as
good. The bad share of a host has a beta prior whose mean is the posterior mean of its registered domain,
whose prior mean is that of its public suffix, whose prior mean is the share over all labelled pages; the
prior's strength at each level is fitted by moments from the spread of the shares one level below. A page is
blocked when the lower posterior bound of its host's share, mean minus `z` standard deviations of the beta
posterior, exceeds `block_above`: a host with little evidence of its own is not blocked for it, but may be for
its domain's.

Counts are added up per host in the tasks before any shuffle, so a hot host is one row per task. What the
levels need of each other as a whole, a mean and three strengths, are four numbers.

Defined cases: null urls and urls without :// have an empty host and path and belong to a host of that name;
null labels are no evidence; repeated rows count as often as they occur; hosts without labelled pages get
their domain's reputation; without labelled pages everything is allowed; an empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poolcurator.llm.store import attach_by_group, pick, write_table

# Host, path and verdict of the rules.
RULES = (
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
)
# Words of a url that label its page as one to keep out.
BAD_WORDS = ("adult", "ads", "bets", "casino", "pills", "poker", "porn", "track", "tracker", "viagra", "xxx")
# Public suffixes of two labels; any other last label is a suffix.
LONG_SUFFIXES = (
    "ac.jp", "ac.nz", "ac.uk", "ac.za", "co.id", "co.il", "co.in", "co.jp", "co.kr", "co.nz", "co.th", "co.uk", "co.za",
    "com.ar", "com.au", "com.br", "com.cn", "com.co", "com.hk", "com.mx", "com.my", "com.ph", "com.pl", "com.sg", "com.tr", "com.tw", "com.ua", "com.vn",
    "edu.au", "edu.cn", "gov.au", "gov.br", "gov.uk", "ne.jp", "net.au", "net.br", "net.cn", "or.jp", "or.kr", "org.au", "org.br", "org.cn", "org.nz", "org.uk", "org.za",
)
Z = 1.64
BLOCK_ABOVE = 0.5
#: Bounds of a prior's strength, in pages.
WEAKEST, STRONGEST = 1.0, 1000.0
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url) -> tuple[F.Column, F.Column]:
    """Host (A-Z lower-cased) and path of a url; both empty without ://."""
    url = F.coalesce(url, F.lit(""))
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.when(F.substring(rest, F.length(host) + 1, F.lit(1)) == "/", F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)).otherwise(F.lit(""))
    return F.translate(host, UPPER, LOWER), path


def match_rules(host, path, rules: Sequence[tuple[str, str, str]]) -> tuple[F.Column, F.Column]:
    """The longest rule that fits, and its verdict; null where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: (len(r[0]) + len(r[1]), r)):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(v)).otherwise(verdict)
    return rule, verdict


def registered_domain(host) -> tuple[F.Column, F.Column]:
    """The registered domain of a host, one label before its public suffix, and the suffix."""
    last = lambda n: F.substring_index(host, ".", -n)
    long = last(2).isin(*LONG_SUFFIXES)
    return F.when(long, last(3)).otherwise(last(2)), F.when(long, last(2)).otherwise(last(1))


def names_bad(url) -> F.Column:
    """Whether a word of the url is one of BAD_WORDS."""
    return F.translate(F.coalesce(url, F.lit("")), UPPER, LOWER).rlike(rf"(?:^|[^a-z0-9])(?:{'|'.join(BAD_WORDS)})(?:[^a-z0-9]|$)")


def strength(level: DataFrame, n: str, bad: str, m: str) -> float:
    """Strength of the priors with means m: s = b / v - 1 from the pages-weighted spread v of the shares around m and its binomial limit b, held within bounds."""
    share = F.col(bad) / F.nullif(F.col(n), F.lit(0))
    v, b = level.agg(F.sum(F.col(n) * (share - F.col(m)) * (share - F.col(m))), F.sum(F.col(n) * F.col(m) * (1 - F.col(m)))).first()
    return STRONGEST if not v else max(WEAKEST, min(STRONGEST, b / v - 1))


def posterior(bad, n, m, s: float) -> F.Column:
    return (bad + s * m) / (n + s)


def reputations(outcomes: DataFrame) -> DataFrame:
    """(host, n_pages, mean, sd) from (host, n_pages, n, bad): labelled and bad pages by host."""
    domain, suffix = registered_domain(F.col("host"))
    hosts, _ = write_table(outcomes.withColumns({"domain": domain, "suffix": suffix}), "host-outcomes")
    domains, _ = write_table(hosts.groupBy("suffix", "domain").agg(F.sum("n").alias("d_n"), F.sum("bad").alias("d_bad")), "domain-outcomes")
    suffixes = domains.groupBy("suffix").agg(F.sum("d_n").alias("s_n"), F.sum("d_bad").alias("s_bad"))
    n, bad = suffixes.agg(F.sum("s_n"), F.sum("s_bad")).first()
    whole = bad / n if n else 0.0
    s = suffixes.withColumn("m", F.lit(float(whole)))
    s = s.select("suffix", posterior(F.col("s_bad"), F.col("s_n"), F.col("m"), strength(s, "s_n", "s_bad", "m")).alias("s_mean"))
    d = domains.join(s, "suffix")
    d = d.select("suffix", "domain", posterior(F.col("d_bad"), F.col("d_n"), F.col("s_mean"), strength(d, "d_n", "d_bad", "s_mean")).alias("d_mean"))
    h = hosts.join(d, ["suffix", "domain"])
    own = strength(h, "n", "bad", "d_mean")
    mean = posterior(F.col("bad"), F.col("n"), F.col("d_mean"), own)
    return h.select("host", "n_pages", mean.alias("mean"), F.sqrt(mean * (1 - mean) / (F.col("n") + own + 1)).alias("sd"))


def filter_urls(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules: Sequence[tuple[str, str, str]] = RULES, z: float = Z, block_above: float = BLOCK_ABOVE, label_col: str | None = None) -> DataFrame:
    """One row per row of pages: id, host, path, rule, verdict, and the host's mean and lower bound. label_col: 1 for pages known to be bad, 0 for good ones."""
    host, path = host_and_path(F.col(url_col))
    rows = pick(pages, id_col, url_col, *([label_col] if label_col else []))
    label = F.col(label_col).cast("int") if label_col else F.when(names_bad(F.col(url_col)), 1)
    rows = rows.select(F.col(id_col).alias("id"), host.alias("host"), path.alias("path"), label.alias("label"))
    rule, verdict = match_rules(F.col("host"), F.col("path"), rules)
    rows = rows.withColumns({"rule": rule, "ruled": verdict})
    label = F.col("label") if label_col else F.coalesce("label", (F.col("ruled") == "block").cast("int"), F.lit(0))
    outcomes = rows.withColumn("label", label).groupBy("host").agg(F.count(F.lit(1)).alias("n_pages"), F.count("label").alias("n"), F.count_if(F.col("label") == 1).alias("bad"))
    known, _ = write_table(reputations(outcomes), "reputations")
    total = known.agg(F.coalesce(F.sum("n_pages"), F.lit(0))).first()[0]
    bound = F.greatest(F.lit(0.0), F.col("mean") - z * F.col("sd"))
    return attach_by_group(rows, known, ["host"], "n_pages", total).select(
        F.col("id").alias(id_col),
        "host",
        "path",
        "rule",
        F.coalesce("ruled", F.when(bound > block_above, F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"),
        F.round("mean", 6).alias("reputation"),
        F.round(bound, 6).alias("lower_bound"),
    )
