"""URL filters: fixed host and path rules first, mined association rules for the rest.

A URL becomes a set of tokens: labels of its host and their words, its registrable part,
path segments (digits as ``#``) and query keys.  Spark's FP-growth mines token
combinations over labelled URLs, the label being one more item; combinations that imply
the bad label with enough support and confidence are rules, and a rule is dropped when a
rule with fewer of its tokens is at least as sure.  Tokens that stand in exactly the same
labelled URLs are mined as one (the first of them), and those in all of them not at all: a
rule that names more of them is never surer, and templates would make 2^k combinations.  Rules match through an inverted
index: each is filed under its rarest token, a URL meets only rules filed under its own
tokens, and the rest of the rule is then compared.

All of it is DataFrame functions and Spark's own miner.

Defined cases: a null URL, or one without ``://``, has empty host and path, no tokens and
the verdict allow; repeated URLs and rows keep their rows; null labels are not learned
from; without labels there are no rules; an empty table gives an empty table; extra
columns of the input pass through (an output whose name is taken is renamed).
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sitemine.llm.common import ascii_lower, fresh_name
from sitemine.session import broadcast_if_small, materialise

MIN_SUPPORT = 0.002
MIN_CONFIDENCE = 0.5
#: Labelled URLs that a rule must rest on, however few there are.
MIN_COUNT = 20
BAD = "label=bad"

#: (verdict, rule): the rule is a host, then the start of a path.
FIXED_RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))


def host_of(url: Column) -> Column:
    return ascii_lower(F.coalesce(F.regexp_extract(url, r"^[\s\S]*?://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"^[\s\S]*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def fixed_rule(host: Column, path: Column, rules: Sequence[tuple[str, str]] = FIXED_RULES) -> Column:
    """Struct(rule, verdict) of the longest fitting rule (the longer host among equals), or null."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rule in sorted(rules, key=lambda r: (len(r[1]), r[1].index("/"))):
        name, start = rule[: rule.index("/")], rule[rule.index("/") :]
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(start)
        found = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def url_tokens(url: Column) -> Column:
    """The sorted distinct tokens of a URL."""
    host, path = host_of(url), path_of(url)
    query = F.coalesce(F.regexp_extract(url, r"\?([^#]*)", 1), F.lit(""))
    labels = F.filter(F.split(host, r"\."), lambda x: x != "")
    words = F.filter(F.split(host, r"[.\-_]"), lambda x: x != "")
    segments = F.filter(F.split(F.regexp_replace(path, "[0-9]+", "#"), "/"), lambda x: x != "")
    keys = F.filter(F.transform(F.split(query, "&"), lambda x: F.substring_index(x, "=", 1)), lambda x: x != "")
    registered = F.when(F.size(labels) >= 2, F.array(F.concat(F.lit("site="), F.array_join(F.slice(labels, -2, 2), ".")))).otherwise(F.array().cast("array<string>"))
    named = [
        F.transform(labels, lambda x: F.concat(F.lit("host="), x)),
        F.transform(words, lambda x: F.concat(F.lit("word="), x)),
        registered,
        F.transform(segments, lambda x: F.concat(F.lit("path="), x)),
        F.transform(keys, lambda x: F.concat(F.lit("key="), x)),
    ]
    distinct = F.array_sort(F.array_distinct(F.concat(*named)))
    # a label that is one word says the same as the word
    return F.filter(distinct, lambda t: ~(t.startswith("word=") & F.array_contains(distinct, F.concat(F.lit("host="), F.substr(t, F.lit(6))))))


def mine_rules(labelled: DataFrame, *, url: str = "url", bad: str = "bad", min_support: float = MIN_SUPPORT, min_confidence: float = MIN_CONFIDENCE, min_count: int = MIN_COUNT) -> DataFrame:
    """(rule_id, tokens, rarest, confidence, support) from URLs with a boolean label."""
    own = labelled.where(F.col(bad).isNotNull()).select(F.monotonically_increasing_id().alias("row"), url_tokens(F.col(url)).alias("tokens"), F.col(bad).alias("bad"))
    own = materialise(own)
    empty = "rule_id bigint, tokens array<string>, rarest string, confidence double, support double"
    n = own.where((F.size("tokens") > 0) | F.col("bad")).count()
    if n < min_count or not n:
        return labelled.sparkSession.createDataFrame([], empty)
    each = own.select("row", F.explode("tokens").alias("token"))
    where = each.groupBy("token").agg(F.count("*").alias("n"), F.sum(F.xxhash64("row").cast("decimal(38,0)")).alias("rows"))
    first = materialise(where.where(F.col("n") < own.count()).groupBy("n", "rows").agg(F.min("token").alias("token")).select("token"))
    kept = each.join(broadcast_if_small(first), "token").groupBy("row").agg(F.collect_set("token").alias("kept"))
    label = F.when(F.col("bad"), F.array(F.lit(BAD))).otherwise(F.array().cast("array<string>"))
    items = own.join(kept, "row", "left").select(F.concat(F.coalesce("kept", F.array().cast("array<string>")), label).alias("items"))
    items = materialise(items.where(F.size("items") > 0))
    model = FPGrowth(itemsCol="items", minSupport=max(min_support * n, min_count) / max(1, items.count()), minConfidence=min_confidence).fit(items)
    sets = materialise(model.freqItemsets.select(F.array_sort("items").alias("items"), "freq"))
    with_bad = sets.where(F.array_contains("items", BAD) & (F.size("items") > 1)).select(F.array_remove("items", BAD).alias("tokens"), F.col("freq").alias("hits"))
    sure = with_bad.join(sets.withColumnRenamed("items", "tokens"), "tokens").withColumn("confidence", F.col("hits") / F.col("freq")).where(F.col("confidence") >= min_confidence)
    rules = materialise(sure.select(F.xxhash64("tokens").alias("rule_id"), "tokens", "confidence", (F.col("hits") / n).alias("support")))
    if rules.isEmpty():
        return labelled.sparkSession.createDataFrame([], empty)
    frequency = sets.where(F.size("items") == 1).select(F.col("items")[0].alias("token"), "freq")
    rarest = (
        rules.select("rule_id", F.explode("tokens").alias("token")).join(frequency, "token").groupBy("rule_id").agg(F.min_by("token", F.struct("freq", "token")).alias("rarest"))
    )
    filed = materialise(rules.join(rarest, "rule_id"))
    wider = filed.select(F.col("rule_id").alias("of"), F.col("confidence").alias("sure"), F.col("tokens").alias("all"), F.explode("tokens").alias("token"))
    beaten = (
        wider.join(filed, F.col("token") == F.col("rarest"))
        .where((F.size("tokens") < F.size("all")) & (F.size(F.array_except("tokens", "all")) == 0) & (F.col("confidence") >= F.col("sure")))
        .select(F.col("of").alias("rule_id"))
    )
    return materialise(filed.join(beaten, "rule_id", "left_anti").select("rule_id", "tokens", "rarest", "confidence", "support"))


def matches(urls: DataFrame, rules: DataFrame, *, url: str = "url") -> DataFrame:
    """(url, rule_id, confidence) of the surest rule for each distinct URL that one fits."""
    own = urls.where(F.col(url).isNotNull()).select(F.col(url).alias("url")).distinct().withColumn("own", url_tokens(F.col("url")))
    met = own.withColumn("token", F.explode("own")).join(broadcast_if_small(rules), F.col("token") == F.col("rarest"))
    fit = met.where(F.size(F.array_except("tokens", "own")) == 0)
    return fit.groupBy("url").agg(F.max_by(F.struct("rule_id", "confidence"), F.struct("confidence", "rule_id")).alias("best")).select("url", "best.*")


def judge(urls: DataFrame, rules: DataFrame, *, url: str = "url", fixed: Sequence[tuple[str, str]] = FIXED_RULES) -> DataFrame:
    """``urls`` plus host, path, rule, verdict, mined_rule (id of the association rule that fits, else null)."""
    hit_url, hit_rule, told = (fresh_name(urls, x) for x in ("hit_url", "hit_rule", "told"))
    host, path, rule, verdict, mined = (fresh_name(urls, x) for x in ("host", "path", "rule", "verdict", "mined_rule"))
    hits = matches(urls, rules, url=url).select(F.col("url").alias(hit_url), F.col("rule_id").alias(hit_rule))
    joined = urls.join(hits, F.col(url) == F.col(hit_url), "left").withColumns({host: host_of(F.col(url)), path: path_of(F.col(url))})
    block = F.when(F.col(hit_rule).isNotNull(), "block").otherwise("allow")
    return (
        joined.withColumn(told, fixed_rule(F.col(host), F.col(path), fixed))
        .withColumns({rule: F.col(told)["rule"], mined: F.col(hit_rule), verdict: F.coalesce(F.col(told)["verdict"], block)})
        .drop(hit_url, hit_rule, told)
    )


def labelled_pages(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """(url, bad): pages whose path names a labelled document; bad is low quality or toxic."""
    number = F.regexp_extract(path_of(F.col("url")), "^/[a-z]+/([0-9]+)", 1)
    seen = pages.select("url", number.try_cast("long").alias("doc_id"))  # no number, or none that an id can be, is null
    bad = (F.col("quality") == 0) | (F.coalesce("toxic", F.lit(0)) == 1)
    return seen.where(F.col("doc_id").isNotNull()).join(labels.select("doc_id", bad.alias("bad")), "doc_id").select("url", "bad")


def op3_url_rules(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality", "toxic")
    rules = mine_rules(labelled_pages(pages, labels))
    return judge(pages, rules).select("page_id", "host", "path", "rule", "verdict", "mined_rule")


def url_fixed_rules(spark, sf_dir: str) -> DataFrame:
    """What the fixed rules alone say of every page: the part of op3 that SQL can say."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    told = fixed_rule(host_of(F.col("url")), path_of(F.col("url")))
    return pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), told["rule"].alias("rule"), told["verdict"].alias("fixed_verdict"))


_FIXED_VALUES = ", ".join(f"('{verdict}', '{rule}')" for verdict, rule in FIXED_RULES)
FIXED_ORACLE = f"""
with p as (select page_id, url, case when instr(coalesce(url, ''), '://') > 0 then substr(url, instr(url, '://') + 3) end as rest from pages),
h as (select page_id, translate(coalesce(regexp_extract(rest, '^[^/?#]*'), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
  coalesce(regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*'), '') as path from p),
r as (select verdict, rule, substr(rule, 1, instr(rule, '/') - 1) as name, substr(rule, instr(rule, '/')) as start from (values {_FIXED_VALUES}) v(verdict, rule)),
fits as (select page_id, rule, verdict from h join r on (host = name or ends_with(host, '.' || name)) and starts_with(path, start)
  qualify row_number() over (partition by page_id order by length(rule) desc, instr(rule, '/') desc) = 1)
select page_id, host, path, rule, verdict as fixed_verdict from h left join fits using (page_id)
"""
