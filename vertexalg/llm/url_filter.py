"""Operator 8 [native]: URL filter by rules and by empirical-Bayes host reputation.

Labelled pages give good and bad outcomes per host. Hosts shrink to their registered domain, domains to
their suffix, suffixes to all pages: each level's posterior mean is the prior mean of the level below, and
the weight of a prior is estimated from how much the groups of that level differ (moments of the beta-binomial).
A page passes if the lower bound of its host's posterior reaches ``threshold``; rules come before that.

Scale: outcomes are summed per host before the shuffle; everything after works on hosts. Three single rows of moments
come to the driver. Pages without labels move once, to their host's row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C

THRESHOLD, Z = 0.5, 1.645
#: Second labels that registries of countries use, and forms of hosts. A suffix has two labels where
#: one of these stands before a country's two letters. Both Spark and the SQL read the patterns.
SECOND = ("ac", "asn", "co", "com", "edu", "gen", "go", "gob", "gouv", "gov", "govt", "gub", "id", "law", "ltd", "mil", "muni", "ne", "net", "nhs", "nic", "nom", "or", "org", "plc", "police", "sch")
PORT, ADDRESS = r":[0-9]*$", r"^[0-9]{1,3}(?:\.[0-9]{1,3}){3}$"
TWO_LABELS = rf"(?:^|\.)(?:{'|'.join(SECOND)})\.[a-z][a-z]$"


@dataclass(frozen=True)
class UrlRule:
    """verdict for host and its subdomains, where the path starts with path."""

    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: Fixed values.
RULES = (UrlRule("allow", "org", "/"), UrlRule("block", "example.org", "/es/"), UrlRule("block", "example.org", "/en/1"), UrlRule("allow", "com", "/fr/"), UrlRule("block", "com", "/de/"))


def _lower(x: Column) -> Column:
    return F.translate(x, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_of(url: Column) -> Column:
    """Between the first :// and the next / ? # or end, A-Z lowered; empty without one or for null."""
    return _lower(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    """From the end of the host to ? # or end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules: tuple[UrlRule, ...]) -> Column:
    """The longest rule that fits, as struct(rule, verdict); null if none does. Rules are a short fixed list."""
    out = None
    for r in sorted(rules, key=lambda r: (-len(r.name), r.name)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        value = F.struct(F.lit(r.name).alias("rule"), F.lit(r.verdict).alias("verdict"))
        out = F.when(fits, value) if out is None else out.when(fits, value)
    return out if out is not None else F.lit(None).cast("struct<rule: string, verdict: string>")


def with_levels(df: DataFrame) -> DataFrame:
    """Adds domain and suffix of host (port left out; a host of fewer labels, or an address, is its own domain)."""
    bare = F.regexp_replace("host", PORT, "")
    many, address = bare.rlike(TWO_LABELS), bare.rlike(ADDRESS)
    last = lambda n: F.substring_index(bare, ".", -n)
    domain = F.when(address, bare).when(many, last(3)).otherwise(last(2))
    suffix = F.when(address, "").when(many, last(2)).otherwise(last(1))
    return df.withColumn("domain", domain).withColumn("suffix", suffix)


def prior_weight(groups: DataFrame) -> tuple[float, float]:
    """(mean, weight) of the beta prior of groups (n, good): weight is 1/rho - 1 of the moment estimate of their likeness rho."""
    n, s = F.col("n").cast("double"), F.col("good").cast("double")
    row = groups.where("n > 0").agg(F.count("*").alias("k"), F.sum(n).alias("n"), F.sum(s).alias("s"), F.sum(n * n).alias("nn"), F.sum(s * s / n).alias("ss")).first()
    if not row["k"]:
        return 0.5, 2.0
    mean = (row["s"] + 1) / (row["n"] + 2)
    raw = row["s"] / row["n"]
    spread = row["ss"] - row["n"] * raw * raw
    free = row["n"] - row["nn"] / row["n"] - (row["k"] - 1)
    rho = (spread / (raw * (1 - raw)) - (row["k"] - 1)) / free if 0 < raw < 1 and free > 0 else 0.0
    return mean, 1 / min(max(rho, 0.01), 0.5) - 1


def reputation(outcomes: DataFrame, hosts: DataFrame, z: float = Z) -> DataFrame:
    """(host, mean, bound) for hosts (host): posterior mean and lower bound of the share of good pages.

    outcomes (host, good): null outcomes don't count. Hosts without outcomes have their domain's mean at the prior's weight."""
    counted = outcomes.where("good is not null").groupBy("host").agg(F.count("*").alias("n"), F.sum(F.col("good").cast("int")).cast("long").alias("good"))
    rows = with_levels(hosts.select("host").distinct().join(counted, "host", "left").na.fill(0, ["n", "good"]))
    rows = C.materialise(rows, "hosts")
    level = lambda key: rows.groupBy(*key).agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
    domains, suffixes = level(("suffix", "domain")), level(("suffix",))
    (mean, w_suffix), (_, w_domain), (_, w_host) = (prior_weight(x) for x in (suffixes, domains, rows))

    def post(prior: Column, weight: float) -> Column:
        return (prior * weight + F.col("good")) / (F.lit(weight) + F.col("n"))

    suffixes = suffixes.select("suffix", post(F.lit(mean), w_suffix).alias("prior"))
    domains = domains.join(suffixes, "suffix").select("suffix", "domain", post(F.col("prior"), w_domain).alias("prior"))
    found = rows.join(domains, ["suffix", "domain"]).withColumn("mean", post(F.col("prior"), w_host)).withColumn("weight", F.lit(w_host) + F.col("n"))
    return found.select("host", "mean", (F.col("mean") - z * F.sqrt(F.col("mean") * (1 - F.col("mean")) / (F.col("weight") + 1))).alias("bound"))


def judge(pages: DataFrame, outcomes: DataFrame, rules: tuple[UrlRule, ...] = RULES, threshold: float = THRESHOLD, z: float = Z) -> DataFrame:
    """(page_id, host, path, rule, verdict) per row of pages (page_id, url), from outcomes (url, good).

    A null url, or one without ://, has an empty host and path and is judged as the host ''. Pages that repeat an id or a url
    and null ids are judged each for itself; outcomes of no page count for their host's domain only if a page
    is of it; without outcomes the mean is 0.5; an empty table gives no row."""
    rows = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    ruled = rows.withColumn("by_rule", rule_of(F.col("host"), F.col("path"), rules))
    bounds = reputation(outcomes.select(host_of(F.col("url")).alias("host"), "good"), rows, z)
    judged = ruled.join(bounds, "host", "left")
    own = F.when(F.col("bound") >= threshold, "allow").otherwise("block")
    return judged.select("page_id", "host", "path", F.col("by_rule.rule").alias("rule"), F.coalesce("by_rule.verdict", own).alias("verdict"))


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages; a page's outcome is the quality label of the document whose number ends its path (each, if it has several).
    Nulls and empty tables: as in judge."""
    pages = C.table(spark, sf_dir, "pages").select("page_id", "url")
    labels = C.table(spark, sf_dir, "labels").where("quality is not null").select(F.col("doc_id").cast("string").alias("number"), F.col("quality").alias("good"))
    number = F.regexp_extract(path_of(F.col("url")), r"/0*([0-9]+)(?:\.html)?/?$", 1)
    outcomes = pages.select("url", number.alias("number")).where("number <> ''").join(labels, "number")
    return judge(pages, outcomes)


def _level_sql(level: str, prior: str, table: str, weight: str) -> str:
    return f"({prior} * {weight} + {table}.good) / ({weight} + {table}.n) as {level}"


def _weight_sql(table: str) -> str:
    return (
        f"(select 1 / least(greatest(coalesce(case when raw > 0 and raw < 1 and free > 0 then ((ss - n * raw * raw) / (raw * (1 - raw)) - (k - 1)) / free end, 0), 0.01), 0.5) - 1 as w, (s + 1) / (n + 2) as mean"
        f" from (select *, s / n as raw, n - nn / n - (k - 1) as free from (select count(*) as k, sum(n)::double as n, sum(good)::double as s, sum(n * n)::double as nn, sum(good::double * good / n) as ss from {table} where n > 0)))"
    )


OP8_SQL = f"""with p as (select page_id, url, translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host, coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') as path from pages),
o as (select host, quality as good from p join labels on regexp_extract(path, '/0*([0-9]+)(?:\\.html)?/?$', 1) = cast(doc_id as varchar) where quality is not null),
c as (select host, count(*) as n, cast(sum(good) as bigint) as good from o group by host),
b as (select host, bare, string_split(bare, '.') as parts, case when regexp_matches(bare, '{ADDRESS}') then 0 when regexp_matches(bare, '{TWO_LABELS}') then 2 else 1 end as level from (select distinct host, regexp_replace(host, '{PORT}', '') as bare from p)),
l as (select host, case when level = 0 then bare else array_to_string(parts[-level - 1:], '.') end as domain, case when level = 0 then '' else array_to_string(parts[-level:], '.') end as suffix from b),
h as (select l.*, coalesce(n, 0) as n, coalesce(good, 0) as good from l left join c using (host)),
d as (select suffix, domain, cast(sum(n) as bigint) as n, cast(sum(good) as bigint) as good from h group by all),
s as (select suffix, cast(sum(n) as bigint) as n, cast(sum(good) as bigint) as good from h group by all),
sp as (select suffix, {_level_sql("prior", "x.mean", "s", "x.w")} from s, {_weight_sql("s")} x),
dp as (select d.suffix, d.domain, {_level_sql("prior", "sp.prior", "d", "x.w")} from d join sp using (suffix), {_weight_sql("d")} x),
hp as (select h.host, {_level_sql("mean", "dp.prior", "h", "x.w")}, x.w + h.n as weight from h join dp using (suffix, domain), {_weight_sql("h")} x),
r as (select * from (values {", ".join(f"('{r.name}', '{r.verdict}', '{r.host}', '{r.path}')" for r in RULES)}) t(rule, verdict, rhost, rpath)),
f as (select page_id, max_by(rule, length(rule)) as rule, max_by(verdict, length(rule)) as verdict from p, r where (host = rhost or ends_with(host, '.' || rhost)) and starts_with(path, rpath) group by page_id)
select p.page_id, p.host, p.path, f.rule, coalesce(f.verdict, case when mean - {Z} * sqrt(mean * (1 - mean) / (weight + 1)) >= {THRESHOLD} then 'allow' else 'block' end) as verdict
from p left join f using (page_id) left join hp on p.host = hp.host"""
