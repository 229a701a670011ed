"""URL filtering by hand-written rules and by association rules mined from labels.

Spark's FP-growth mines which combinations of URL tokens go with bad labels. Combinations with enough support and
confidence that are no larger than needed (no shorter one of at least the same confidence inside) become rules, and an inverted index
from token to rule finds the rules whose tokens all occur in a URL. Hand-written rules come first; the longest that fits wins.

Matching works on distinct URLs, so a URL that a third of the rows share is matched once. All of it is
DataFrame functions and joins that adaptive execution may broadcast (few rules) or split.

Defined results: a null URL, or one without `://`, has an empty host and path, no tokens and is allowed; with no labels, or no
combination that passes, nothing is blocked but by hand-written rules; every row gives one row; clashing columns are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import Scratch, ascii_lower, without

BAD = "label=bad"
#: A combination counts from this share of the labelled URLs on, and from this many; fewer prove nothing.
MIN_SUPPORT = 0.001
MIN_COUNT = 20
MIN_CONFIDENCE = 0.6
ADDRESS = r"(?s)^.*?://([^/?#]*)([^?#]*)"


@dataclass(frozen=True)
class Rule:
    """A verdict for a host with all its subdomains and a path prefix, written `host/path`."""

    text: str
    verdict: str

    @property
    def host(self) -> str:
        return self.text.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.text.partition("/")[2] if "/" in self.text else ""

    def fits(self, host: Column, path: Column) -> Column:
        return ((host == self.host) | host.endswith("." + self.host)) & path.startswith(self.path)


def host_of(url: Column) -> Column:
    return F.coalesce(ascii_lower(F.regexp_extract(url, ADDRESS, 1)), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, ADDRESS, 2), F.lit(""))


def tokens_of(url: Column) -> Column:
    """Distinct tokens: the host's labels, the words of the path (numbers as one) and the names of query parameters."""
    host, path = host_of(url), path_of(url)
    labels = F.transform(F.array_remove(F.split(host, r"\."), ""), lambda x: F.concat(F.lit("host="), x))
    words = F.transform(F.array_remove(F.split(F.regexp_replace(path, "[0-9]+", "0"), r"[/.\-_]"), ""), lambda x: F.concat(F.lit("path="), x))
    query = F.transform(F.regexp_extract_all(url, F.lit(r"[?&]([^=&#]+)="), F.lit(1)), lambda x: F.concat(F.lit("query="), x))
    return F.when(host != "", F.array_distinct(F.concat(labels, words, query))).otherwise(F.array().cast("array<string>"))


def mine(labelled: DataFrame, url: str, bad: str, min_support: float = MIN_SUPPORT, min_confidence: float = MIN_CONFIDENCE) -> DataFrame:
    """(tokens, confidence, support) of the rules that say `bad`; labelled: a row for each labelled URL, bad boolean."""
    spark = labelled.sparkSession
    scratch = Scratch(spark, "rules")
    baskets = labelled.where(F.col(url).isNotNull() & F.col(bad).isNotNull()).select(F.concat(tokens_of(F.col(url)), F.when(F.col(bad), F.array(F.lit(BAD))).otherwise(F.array().cast("array<string>"))).alias("items"))
    baskets = scratch.save(baskets.where(F.size("items") > 0), "baskets")
    n = baskets.count()
    if n < MIN_COUNT:
        return spark.createDataFrame([], "tokens array<string>, confidence double, support double")
    model = FPGrowth(itemsCol="items", minSupport=max(min_support, MIN_COUNT / n), minConfidence=min_confidence).fit(baskets)
    found = model.associationRules.where((F.size("consequent") == 1) & (F.col("consequent")[0] == BAD))
    found = scratch.save(found.select(F.array_sort("antecedent").alias("tokens"), "confidence", "support"), "found")
    # a rule goes if a shorter one inside it is as confident; what meets shares a token
    one = found.select(F.col("tokens").alias("t"), F.col("confidence").alias("c"), F.col("tokens")[0].alias("token"))
    many = found.select("tokens", "confidence", F.explode("tokens").alias("token"))
    covered = many.join(one, "token").where((F.size("t") < F.size("tokens")) & (F.col("c") >= F.col("confidence")) & (F.size(F.array_except("t", "tokens")) == 0))
    return scratch.save(found.join(covered.select("tokens").distinct(), "tokens", "left_anti"), "kept")


def matching(urls: DataFrame, url: str, rules: DataFrame) -> DataFrame:
    """(url, mined): distinct URLs that hold all tokens of a rule, with how many rules they fit.

    The index has each rule under the one of its tokens that the fewest URLs hold, so a common token (`host=com`) meets only rules that have no rarer one.
    """
    held = urls.select(F.col(url).alias("url")).where("url is not null").distinct().withColumn("held", tokens_of(F.col("url"))).select("url", "held", F.explode("held").alias("token"))
    each = rules.select("tokens", F.explode("tokens").alias("token"))
    often = held.join(each.select("token").distinct(), "token", "left_semi").groupBy("token").agg(F.count("*").alias("often"))
    index = each.join(often, "token", "left").groupBy("tokens").agg(F.min(F.struct(F.coalesce("often", F.lit(0)).alias("often"), "token"))["token"].alias("token"))
    hits = held.join(index, "token").where(F.size(F.array_except("tokens", "held")) == 0)
    return hits.groupBy("url").agg(F.count("*").alias("mined"))


def judge(pages: DataFrame, rules: list[Rule], mined: DataFrame, url: str = "url") -> DataFrame:
    """pages with host, path, rule (that decided, else null), mined (rules that fit) and verdict."""
    base = without(pages, "host", "path", "rule", "mined", "verdict")
    hits = matching(base, url, mined).withColumnRenamed("url", "__url")
    rows = base.join(hits, F.col(url) == F.col("__url"), "left").drop("__url")
    host, path = host_of(F.col(url)), path_of(F.col(url))
    rule = verdict = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.text), r.text)):  # the longest is looked at last, so outermost
        rule = F.when(r.fits(F.col("host"), F.col("path")), r.text).otherwise(rule)
        verdict = F.when(r.fits(F.col("host"), F.col("path")), r.verdict).otherwise(verdict)
    rows = rows.withColumns({"host": host, "path": path, "mined": F.coalesce("mined", F.lit(0))})
    return rows.withColumns({"rule": rule, "verdict": F.coalesce(verdict, F.when(F.col("mined") > 0, "block").otherwise("allow"))})
