"""URL filter: host and path rules first, then a logistic regression on hashed character n-grams, all as built-in functions.

A rule is (host, path, verdict): it fits its host and every subdomain when the url's path starts with the rule's
path; the longest rule string wins. Urls without a rule are judged by the model. The model is fitted from a small
labelled table (url, label: 1 block, 0 allow) of at most `max_labelled` rows; without one, the urls that the rules
decide serve as that table.

Defined cases: a null url or one without '://' has empty host and path and is judged by the model; with no labelled
row at all the model allows everything; repeated rows are judged alike; further columns of `pages` are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, read_table

# The rules of the contract.
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]

BITS = 12
GRAMS = (3, 4)


def url_parts(url):
    """(host, path) columns of a url."""
    u = F.coalesce(url, F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, F.expr("substring(coalesce(url, ''), instr(coalesce(url, ''), '://') + 3)")).otherwise(F.lit(""))
    host = ascii_lower(F.regexp_extract(rest, r"^([^/?#]*)", 1))
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return host, path


def rule_of(host, path, rules=RULES):
    """Struct (rule, verdict) of the longest rule that fits, else null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for h, p, verdict in sorted(rules, key=lambda r: (len(r[0] + r[1]), r)):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def features(host, path, bits: int = BITS, grams=GRAMS):
    """Hashed character n-grams of '^host|path$' as an array of slots; linear in the url's length."""
    chars = F.split(F.concat(F.lit("^"), host, F.lit("|"), path, F.lit("$")), "")
    slots = [F.transform(F.filter(F.transform(F.sequence(F.lit(1), F.size(chars)), lambda i: F.slice(chars, i, n)), lambda g: F.size(g) == n), lambda g: F.pmod(F.xxhash64(F.array_join(g, "")), F.lit(1 << bits)).cast("int")) for n in grams]
    return F.concat(*slots)


def fit(rows: list[tuple[list[int], int]], epochs: int = 30, rate: float = 0.5, l2: float = 1e-5, bits: int = BITS) -> list[float]:
    """Stochastic gradient on the bounded labelled rows; the last weight is the bias. Features count as 1/n each."""
    w = [0.0] * ((1 << bits) + 1)
    if not rows:
        w[-1] = -1.0
        return w
    for epoch in range(epochs):
        step = rate * 20 / (1 + 0.1 * epoch)
        for slots, label in rows:
            n = len(slots) or 1
            z = w[-1] + sum(w[s] for s in slots) / n
            g = 1 / (1 + math.exp(-max(-30.0, min(30.0, z)))) - label
            w[-1] -= 0.05 * step * g
            for s in slots:
                w[s] -= step * (g / n + l2 * w[s])
    return w


def judge(pages: DataFrame, labelled: DataFrame | None = None, rules=RULES, max_labelled: int = 2000, bits: int = BITS) -> DataFrame:
    """page_id, host, path, rule, verdict, score (the model's probability of block)."""
    host, path = url_parts(F.col("url"))
    base = pages.select("page_id", "url").select("page_id", host.alias("host"), path.alias("path")).withColumn("__rule", rule_of(F.col("host"), F.col("path"), rules))
    if labelled is None:
        table = base.where(F.col("__rule").isNotNull()).select("host", "path", (F.col("__rule.verdict") == "block").cast("int").alias("label"))
    else:
        table = labelled.select("url", "label").select(host.alias("host"), path.alias("path"), "label")
    table = table.where(F.col("label").isNotNull())
    # A share by hash that leaves about four times the bound, whatever the table's size; equal urls count once.
    share = min(1.0, 4 * max_labelled / max(1, table.agg(F.approx_count_distinct(F.xxhash64("host", "path"))).first()[0]))
    near = table.where(F.pmod(F.xxhash64("host", "path"), F.lit(1 << 20)) <= int(share * (1 << 20))).distinct()
    sample = near.orderBy(F.xxhash64("host", "path"), "host", "path", "label").limit(max_labelled)
    w = fit([(r[0], r[1]) for r in sample.select(features(F.col("host"), F.col("path"), bits), "label").collect()], bits=bits)
    # A constant of fixed size (2**bits weights), folded once by the optimizer.
    weights = F.from_json(F.lit("[" + ",".join(f"{x:.6g}" for x in w[:-1]) + "]"), "array<double>")
    slots = features(F.col("host"), F.col("path"), bits)
    total = F.aggregate(slots, F.lit(0.0), lambda acc, s: acc + F.get(weights, s))
    z = F.lit(w[-1]) + total / F.greatest(F.size(slots), F.lit(1))
    score = F.lit(1.0) / (F.lit(1.0) + F.exp(-z))
    return base.withColumn("score", score).select(
        "page_id", "host", "path", F.col("__rule.rule").alias("rule"),
        F.coalesce(F.col("__rule.verdict"), F.when(F.col("score") >= 0.5, F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"), "score",
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(read_table(spark, sf_dir, "pages"))


def rules_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Host, path and rule only: what SQL can state."""
    return judge(read_table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", F.when(F.col("rule").isNotNull(), F.col("verdict")).alias("rule_verdict"))


RULES_ORACLE = r"""
with p as (
  select page_id, case when strpos(coalesce(url, ''), '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages
), q as (
  select page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) as path from p
), r as (
  select *, case when (host = 'example.net' or host like '%.example.net') and path like '/en/%' then 'example.net/en/'
                 when (host = 'example.com' or host like '%.example.com') and path like '/de/%' then 'example.com/de/'
                 when (host = 'org' or host like '%.org') and path like '/fr/%' then 'org/fr/'
                 when (host = 'net' or host like '%.net') and path like '/%' then 'net/' end as rule from q
)
select page_id, host, path, rule,
       case when rule in ('net/', 'example.com/de/') then 'block' when rule is not null then 'allow' end as rule_verdict from r
"""
