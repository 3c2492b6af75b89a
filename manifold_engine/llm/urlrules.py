"""URL filtering with association rules, in DataFrame functions only.

Labelled urls become transactions of tokens (host labels, path segments, query
items, fragment) plus one item for a bad label.  Spark's FP-growth mines token
combinations on one half of the urls; rules that end in the bad item and pass
the limits of confidence, support, count and lift are kept, less those that
contain a shorter rule of no lower confidence.  The other half then judges each
rule: it must be as sure there, and surer than the share of bad urls by more
than chance, so that labels without a pattern give no rules.  Matching uses an
inverted index: each rule is filed under its rarest token, distinct urls look
up their tokens, and the rest of the rule must be contained.

Listed host-and-path rules come first: a rule fits its host and all subdomains
if the path starts with the rule's, the longest rule wins.  They are a short
parameter list, looked up inside the row by host suffix.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spool import spool

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BAD = "label:bad"


def host_of(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; else empty."""
    raw = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(raw, UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def tokens_of(url: Column) -> Column:
    """Distinct tokens of a url: ``h:`` host labels, ``p:`` path segments, ``q:`` query items, ``f:`` fragment."""
    query = F.regexp_extract(url, r"(?s)^.*?://[^?#]*\?([^#]*)", 1)
    frag = F.regexp_extract(url, r"(?s)^.*?://[^#]*#(.*)$", 1)

    def part(prefix, items):
        return F.transform(F.filter(items, lambda x: x != ""), lambda x: F.concat(F.lit(prefix), x))

    both = F.concat(part("h:", F.split(host_of(url), r"\.")), part("p:", F.split(path_of(url), "/")), part("q:", F.split(query, "&")), part("f:", F.array(frag)))
    return F.coalesce(F.array_distinct(both), F.array().cast("array<string>"))


RULES = "rule_id long, tokens array<string>, anchor string, confidence double, support double, lift double, held_count long, held_confidence double"


def mine_rules(labelled: DataFrame, url: str = "url", bad: str = "bad", min_support: float = 0.002, min_confidence: float = 0.6, min_count: int = 20, min_lift: float = 1.2, min_z: float = 3.0, held_out: bool = True) -> DataFrame:
    """``rule_id, tokens, anchor, confidence, support, lift, held_count, held_confidence`` mined from urls with a boolean label.

    A rule's combination must stand in ``min_count`` bad urls at least, however
    few are labelled.  With ``held_out`` half of the urls (by crc32) mine and the
    other half judges: there the rule needs ``min_count`` / 2 urls, the same
    confidence and ``min_z`` standard errors above the share of bad urls; without
    it these two columns are null.  Tokens rarer than the support limit cannot
    stand in a frequent set and are dropped before mining.  Null urls and null
    labels are left out; without labelled rows there are no rules.
    """
    spark = labelled.sparkSession
    half = (F.crc32(url) % 2 == 0) if held_out else F.lit(True)
    rows = labelled.where(F.col(url).isNotNull() & F.col(bad).isNotNull()).select(tokens_of(F.col(url)).alias("t"), F.col(bad).cast("boolean").alias("bad"), half.alias("fit"))
    rows = spool(rows, "transactions")
    every, judge_ = rows.where("fit"), rows.where("not fit")
    n, n_bad = every.agg(F.count("*"), F.sum(F.col("bad").cast("long"))).first()
    if not n or not n_bad:
        return spark.createDataFrame([], RULES)
    support = max(min_support, min_count / n)
    if support > 1:
        return spark.createDataFrame([], RULES)
    counts = every.select(F.explode("t").alias("token")).groupBy("token").count().where(F.col("count") >= support * n)
    frequent = spool(counts, "tokens")
    # rare tokens leave the transactions: by a join, as their number grows with the data
    rows_of = every.withColumn("r", F.monotonically_increasing_id())
    rows_of = spool(rows_of, "numbered")
    slim = rows_of.select("r", F.explode("t").alias("token")).join(frequent.select("token"), "token", "left_semi").groupBy("r").agg(F.collect_list("token").alias("t"))
    slim = rows_of.select("r", "bad").join(slim, "r", "left").select("bad", F.coalesce("t", F.array().cast("array<string>")).alias("t"))
    items = F.when(F.col("bad"), F.array_append("t", F.lit(BAD))).otherwise(F.col("t"))
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=min_confidence).fit(slim.select(items.alias("items")))
    found = model.associationRules.where(F.array_contains("consequent", BAD) & (F.col("lift") >= min_lift)).select(F.array_sort("antecedent").alias("tokens"), "confidence", "support", "lift")
    found = spool(found, "rules")
    # a rule says nothing new if a part of it is at least as sure
    part = found.select(F.col("tokens").alias("part"), F.col("confidence").alias("sure"), F.col("tokens")[0].alias("head"))
    wide = found.select("tokens", "confidence", F.explode("tokens").alias("head")).join(part, "head")
    idle = wide.where((F.size("part") < F.size("tokens")) & (F.size(F.array_except("part", "tokens")) == 0) & (F.col("sure") >= F.col("confidence"))).select("tokens").distinct()
    kept = found.join(idle, "tokens", "left_anti")
    rare = kept.select("tokens", F.explode("tokens").alias("token")).join(frequent, "token").groupBy("tokens").agg(F.min_by("token", F.struct("count", "token")).alias("anchor"))
    rules = spool(kept.join(rare, "tokens").select(F.xxhash64("tokens").alias("rule_id"), "tokens", "anchor", "confidence", "support", "lift"), "rules")
    if not held_out:
        return rules.select("*", F.lit(None).cast("long").alias("held_count"), F.lit(None).cast("double").alias("held_confidence"))
    share = judge_.agg(F.avg(F.col("bad").cast("double"))).first()[0]
    share = min(max(share or 0.0, 1e-6), 1 - 1e-6)
    hits = judge_.select("t", "bad", F.explode("t").alias("anchor")).join(rules.select("rule_id", "anchor", "tokens"), "anchor").where(F.size(F.array_except("tokens", "t")) == 0)
    seen = hits.groupBy("rule_id").agg(F.count("*").alias("held_count"), F.avg(F.col("bad").cast("double")).alias("held_confidence"))
    z = (F.col("held_confidence") - share) * F.sqrt(F.col("held_count") / (share * (1 - share)))
    sure = seen.where((F.col("held_count") * 2 >= min_count) & (F.col("held_confidence") >= min_confidence) & (z >= min_z))
    return spool(rules.join(sure, "rule_id").select(*[f.split()[0] for f in RULES.split(", ")]), "rules")


def match_rules(urls: DataFrame, rules: DataFrame, url: str = "url") -> DataFrame:
    """``url, learnt_rule, learnt_confidence`` of the distinct urls that some rule fits (the surest, then the least tokens)."""
    once = urls.select(F.col(url).alias("url")).where("url is not null").distinct().select("url", tokens_of(F.col("url")).alias("t"))
    hit = once.select("url", "t", F.explode("t").alias("anchor")).join(rules.select("anchor", "tokens", "confidence"), "anchor")
    hit = hit.where(F.size(F.array_except("tokens", "t")) == 0)
    best = hit.groupBy("url").agg(F.max(F.struct("confidence", F.array_join("tokens", " ").alias("rule"))).alias("m"))
    return best.select("url", F.col("m.rule").alias("learnt_rule"), F.col("m.confidence").alias("learnt_confidence"))


def listed_verdict(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> Column:
    """``struct<rule, verdict>`` of the longest listed rule ``(verdict, host, path)`` that fits, else null."""
    by_host: dict[str, list] = {}
    for verdict, h, p in rules:
        by_host.setdefault(h, []).append((p, verdict))
    if not by_host:
        return F.lit(None).cast("struct<rule:string,verdict:string>")
    known = []
    for h, own in sorted(by_host.items()):
        known += [F.lit(h), F.array(*[F.struct(F.lit(p).alias("path"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict")) for p, v in sorted(own)])]
    index = F.create_map(*known)
    labels = F.split(host, r"\.")
    n = F.size(labels)
    suffixes = F.transform(F.sequence(F.lit(1), n), lambda i: F.array_join(F.slice(labels, i, n), "."))
    listed = F.flatten(F.filter(F.transform(suffixes, lambda s: F.try_element_at(index, s)), lambda x: x.isNotNull()))
    fit = F.filter(listed, lambda r: F.startswith(path, r["path"]))
    best = F.array_max(F.transform(fit, lambda r: F.struct(F.length(r["rule"]).alias("l"), r["rule"].alias("rule"), r["verdict"].alias("verdict"))))
    return F.when(best.isNotNull(), F.struct(best["rule"].alias("rule"), best["verdict"].alias("verdict")))


def judge(pages: DataFrame, listed: list[tuple[str, str, str]], rules: DataFrame, url: str = "url") -> DataFrame:
    """``pages`` with ``host, path, rule, verdict, learnt_rule, learnt_confidence``.

    The verdict is the listed rule's, else ``block`` where a learnt rule fits,
    else ``allow``.  A null url, or one without ``://``, has empty host and path
    and only tokens it really has.  Columns with these names are replaced.
    """
    new = ("host", "path", "rule", "verdict", "learnt_rule", "learnt_confidence")
    learnt = match_rules(pages, rules, url).withColumnRenamed("url", "u__")
    kept = [F.col(c) for c in pages.columns if c not in new]
    out = pages.select(*kept).join(learnt, F.col(url) == F.col("u__"), "left").drop("u__")
    out = out.withColumn("host", host_of(F.col(url))).withColumn("path", path_of(F.col(url)))
    out = out.withColumn("l__", listed_verdict(F.col("host"), F.col("path"), listed))
    out = out.withColumn("rule", F.col("l__.rule")).withColumn("verdict", F.coalesce(F.col("l__.verdict"), F.when(F.col("learnt_rule").isNotNull(), F.lit("block")).otherwise(F.lit("allow"))))
    return out.drop("l__")
