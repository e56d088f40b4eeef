"""URL filter: host and path rules, and for the rest a ratio of two character language models.

The URLs that an allow rule or a block rule decides train one variable-order Markov model each. An
order's estimate is smoothed with that of the next shorter context (a Dirichlet prior), down to the
single character and to the uniform distribution. A URL's score is the difference of its log
likelihoods divided by its characters; the cut is calibrated on decided URLs that train nothing.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphwatch.functions.storage import table
from graphwatch.llm.text import ascii_lower

#: Context characters at most, prior strength, characters of the uniform base, one of so many decided URLs that calibrates.
ORDER, PRIOR, ALPHABET, FOLDS = 4, 2.0, 128, 5


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    rule: str  # host, then the path's beginning

    @property
    def host(self) -> str:
        return self.rule.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.rule.partition("/")[2] if "/" in self.rule else ""


RULES = (UrlRule("block", "net/"), UrlRule("allow", "example.net/en/"), UrlRule("block", "example.com/de/"), UrlRule("allow", "org/fr/"))


def host_of(url: Column) -> Column:
    return F.coalesce(ascii_lower(F.regexp_extract(url, r"^[\s\S]*?://([^/?#]*)", 1)), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"^[\s\S]*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules: tuple[UrlRule, ...] = RULES) -> Column:
    """The longest rule that fits, as struct(rule, verdict); null if none fits. The list is part of the plan."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for r in sorted(rules, key=lambda r: (len(r.rule), r.rule)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        found = F.when(fits, F.struct(F.lit(r.rule).alias("rule"), F.lit(r.verdict).alias("verdict"))).otherwise(found)
    return found


def _grams(urls: DataFrame, *keep: str) -> DataFrame:
    """All character sequences of 1 to ORDER + 1 characters that end at each place of ``s``; contexts before the start are padded."""
    padded = F.concat(F.lit("\x02" * ORDER), F.col("s"), F.lit("\x03"))
    ends = urls.select(*keep, padded.alias("_p")).select(*keep, "_p", F.explode(F.sequence(F.lit(ORDER + 1), F.char_length("_p"))).alias("_e"))
    last = F.substring("_p", F.col("_e") - ORDER, ORDER + 1)
    return ends.select(*keep, last.alias("gram"))


def gram_ratios(urls: DataFrame) -> DataFrame:
    """gram (ORDER + 1 characters) -> ``ratio``, the log likelihood ratio of its last character after the others.

    urls: s, accepted, rejected (0 or 1 each; both 0: counts for nothing, but its grams get ratios).
    """
    whole = _grams(urls, "accepted", "rejected").groupBy("gram").agg(F.sum("accepted").alias("a"), F.sum("rejected").alias("r"))
    # Shorter grams are the ends of the whole ones: their counts come from sums, not from the URLs again.
    levels = whole.select(F.explode(F.sequence(F.lit(1), F.lit(ORDER + 1))).alias("n"), "gram", "a", "r")
    levels = levels.groupBy("n", F.expr("right(gram, n)").alias("gram")).agg(F.sum("a").alias("a"), F.sum("r").alias("r"))
    # A context is followed by at most as many characters as there are, so these groups are small.
    after = Window.partitionBy("n", F.expr("left(gram, n - 1)"))
    levels = table(levels.withColumn("ta", F.sum("a").over(after)).withColumn("tr", F.sum("r").over(after)), "url-grams")
    smooth = lambda c, t, p: (F.col(c) + PRIOR * F.col(p)) / (F.col(t) + PRIOR)
    out = None
    for n in range(1, ORDER + 2):
        own = levels.filter(F.col("n") == n).select("gram", "a", "r", "ta", "tr")
        if out is None:
            own = own.withColumn("qa", F.lit(1 / ALPHABET)).withColumn("qr", F.lit(1 / ALPHABET))
        else:
            own = own.withColumn("_end", F.expr(f"right(gram, {n - 1})")).join(out, "_end")
        out = own.select(F.col("gram").alias("_end"), smooth("a", "ta", "qa").alias("qa"), smooth("r", "tr", "qr").alias("qr"))
    return out.select(F.col("_end").alias("gram"), (F.log("qa") - F.log("qr")).alias("ratio"))


def url_scores(urls: DataFrame) -> DataFrame:
    """s -> score for each distinct s of urls (s, accepted, rejected as long)."""
    # A fixed number of partitions: Spark would merge these few MB into one task, which would make all the grams.
    n = int(urls.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    once = urls.repartition(n, "s").groupBy("s").agg(F.sum("accepted").alias("accepted"), F.sum("rejected").alias("rejected"))
    ratios = table(gram_ratios(once), "url-ratios")
    each = _grams(once.select("s"), "s").groupBy("s", "gram").count()
    return each.join(ratios, "gram").groupBy("s").agg((F.sum(F.col("ratio") * F.col("count")) / F.sum("count")).alias("score"))


def calibrated_cut(scored: DataFrame) -> float:
    """The score that parts held-out decided URLs: half way between the 5th percentile of accepted and the 95th of rejected ones; 0 if a side is missing."""
    both = scored.filter("calibrates").agg(
        F.percentile_approx(F.when(F.col("label") == "allow", F.col("score")), 0.05, 1000).alias("a"),
        F.percentile_approx(F.when(F.col("label") == "block", F.col("score")), 0.95, 1000).alias("r"),
    ).first()
    return 0.0 if both is None or both.a is None or both.r is None else (both.a + both.r) / 2


def judge(pages: DataFrame, url: str = "url", rules: tuple[UrlRule, ...] = RULES) -> DataFrame:
    """``_page`` (all columns of pages), host, path, rule, verdict, score and cut.

    A null URL or one without ``://`` has an empty host and path; no rule with a host fits it, so
    its score decides like any other's. Without any decided URL all scores are 0 and all such
    URLs are allowed. Repeated URLs are scored once and get the same verdict. Ties go to allow.
    """
    rows = pages.select(F.struct("*").alias("_page"), host_of(pages[url]).alias("host"), path_of(pages[url]).alias("path"))
    rows = rows.withColumn("_rule", rule_of(F.col("host"), F.col("path"), rules)).withColumn("s", F.concat(F.col("host"), ascii_lower(F.col("path"))))
    held = F.pmod(F.xxhash64("s"), F.lit(FOLDS)) == 0
    known = rows.select("s", F.col("_rule.verdict").alias("label"), held.alias("calibrates")).groupBy("s", "label", "calibrates").count()
    train = lambda v: F.when((F.col("label") == v) & ~F.col("calibrates"), F.col("count")).otherwise(F.lit(0)).cast("long")
    scores = table(url_scores(known.select("s", train("allow").alias("accepted"), train("block").alias("rejected"))), "url-scores")
    cut = calibrated_cut(known.filter("label is not null").join(scores, "s").select("label", "calibrates", "score"))
    scored = rows.join(scores, "s", "left").withColumn("cut", F.lit(cut))
    model = F.when(F.col("score") >= F.col("cut"), "allow").otherwise("block")
    return scored.select("_page", "host", "path", F.col("_rule.rule").alias("rule"), F.coalesce("_rule.verdict", model).alias("verdict"), "score", "cut")


def op5_query(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge(pages).select("_page.page_id", "host", "path", "rule", "verdict", "score")
