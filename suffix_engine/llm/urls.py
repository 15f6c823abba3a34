"""URL filters: rules, and a tree of path templates for what no rule covers. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from suffix_engine.session import cut

#: (host, path prefix, verdict)
RULES = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))

#: Defaults: a node with more different next segments than this is a variable; depth of the tree (what lies deeper is one
#: wildcard); weight of the prior in a template's purity; from which blocked share a template is rejected; the test value
#: from which a branch counts as different from its siblings; labelled branches that must be alike for unlabelled siblings to go with them.
BRANCHES, DEPTH, WEIGHT, REJECT, DIFFERENT, SUPPORT = 16, 4, 4.0, 0.8, 2.0, 4
#: Parts that the rows of each node are dealt out by when they are joined with what was decided about it.
SALTS = 64


def parse(url: str) -> tuple[Column, Column]:
    """Host and path of a column of urls. Null, or no ://: both empty."""
    rest = F.when(F.locate("://", F.col(url)) > 0, F.expr(f"substring({url}, locate('://', {url}) + 3)")).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def apply_rules(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule and its verdict (null if none fits); the longest rule that fits decides, of equally long ones the first in order."""
    host, path = parse("url_text")
    out = pages.select(F.col("page_id"), F.col("url").cast("string").alias("url_text")).select("page_id", host.alias("host"), path.alias("path"))
    ordered = sorted(rules, key=lambda r: -len(r[0] + r[1]))
    fits = [((F.col("host") == h) | F.col("host").endswith("." + h)) & F.col("path").startswith(p) for h, p, _ in ordered]
    pick = lambda values: F.coalesce(*[F.when(f, F.lit(v)) for f, v in zip(fits, values, strict=True)], F.lit(None).cast("string"))
    return out.withColumn("rule", pick([h + p for h, p, _ in ordered])).withColumn("rule_verdict", pick([v for _, _, v in ordered]))


def templates(pages: DataFrame, branches: int = BRANCHES, depth: int = DEPTH, different: float = DIFFERENT, support: int = SUPPORT) -> DataFrame:
    """Adds template to rows with host, path and blocked (0, 1 or null), level by level.

    A segment below a node with many different ones becomes *. Below other nodes, the labelled branches whose blocked share does
    not differ from that of all of them merge into *, if there are two or more; with support or more, the
    unlabelled branches, of which nothing speaks against it, go with them. What is below the merged branches is one tree from there on.
    Segments are counted over all rows, with partial sums before each shuffle. A node's decision is one row, with at most as many segments
    as branches. In the joins back, rows are dealt out by node and a salt of their path, and a decision is sent to each salt, so a host with
    a large share of the rows is no task's alone.
    """
    segments = F.filter(F.split("path", "/"), lambda x: x != "")
    out = pages.withColumn("_s", segments).withColumn("template", F.lit("")).withColumn("_salt", F.pmod(F.xxhash64("path"), F.lit(SALTS)).cast("int"))
    for level in range(depth):
        out = out.withColumn("_x", F.get("_s", F.lit(level)))
        seen = out.where(F.col("_x").isNotNull()).groupBy("host", "template", "_x").agg(F.coalesce(F.sum("blocked"), F.lit(0)).cast("double").alias("b"), F.count("blocked").cast("double").alias("l"))
        node = seen.groupBy("host", "template").agg(F.count(F.lit(1)).alias("_n"), F.sum("b").alias("pb"), F.sum("l").alias("pl")).where((F.col("_n") > branches) | (F.col("pl") > 0))
        few = node.where(F.col("_n") <= branches).select(F.col("host").alias("_h"), F.col("template").alias("_t"), (F.col("pb") / F.col("pl")).alias("share"))
        # a variable node's many segments must not meet in one task for a join that keeps none of them
        dealt = few.withColumn("_few_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        child = seen.withColumn("_part", F.pmod(F.xxhash64("_x"), F.lit(SALTS)).cast("int")).join(dealt, (F.col("host") == F.col("_h")) & (F.col("template") == F.col("_t")) & (F.col("_part") == F.col("_few_salt")))
        alike = (F.col("l") > 0) & (F.abs(F.col("b") / F.col("l") - F.col("share")) <= different * F.sqrt(F.col("share") * (1 - F.col("share")) / F.col("l")))
        pooled = child.withColumn("alike", alike).groupBy("_h", "_t").agg(F.collect_list(F.when(F.col("alike"), F.col("_x"))).alias("same"), F.collect_list(F.when(F.col("l") == 0, F.col("_x"))).alias("rest"))
        merge = F.when(F.size("same") >= support, F.concat("same", "rest")).otherwise(F.col("same"))
        merged = pooled.where(F.size("same") > 1).select("_h", "_t", merge.alias("_merge"))
        many = node.where(F.col("_n") > branches).select(F.col("host").alias("_h"), F.col("template").alias("_t"), F.lit(None).cast("array<string>").alias("_merge"))
        decided = cut(many.unionByName(merged))  # nodes only; without it the plan would double at each level
        salted = decided.withColumn("_x_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        out = out.join(salted, (F.col("host") == F.col("_h")) & (F.col("template") == F.col("_t")) & (F.col("_salt") == F.col("_x_salt")), "left")
        wild = F.col("_h").isNotNull() & (F.col("_merge").isNull() | F.coalesce(F.array_contains("_merge", F.col("_x")), F.lit(False)))
        step = F.when(F.col("_x").isNull(), F.lit("")).when(wild, F.lit("/*")).otherwise(F.concat(F.lit("/"), F.col("_x")))
        out = out.withColumn("template", F.concat("template", step)).drop("_h", "_t", "_merge", "_x_salt")
    return out.withColumn("template", F.when(F.size("_s") > depth, F.concat("template", F.lit("/**"))).otherwise(F.col("template"))).drop("_s", "_x", "_salt")


def rejected_templates(labelled: DataFrame, weight: float = WEIGHT, reject: float = REJECT) -> DataFrame:
    """Host and template of what is rejected, from rows (host, template, blocked: 0 or 1 or null): where the blocked share, smoothed
    towards that of all labelled rows, is high enough. A template without a labelled row is not."""
    leaf = labelled.where(F.col("blocked").isNotNull()).groupBy("host", "template").agg(F.sum("blocked").cast("double").alias("b"), F.count(F.lit(1)).cast("double").alias("n"))
    prior = leaf.agg(F.coalesce(F.try_divide(F.sum("b"), F.sum("n")), F.lit(0.0)).alias("prior"))
    return leaf.crossJoin(F.broadcast(prior)).where((F.col("b") + weight * F.col("prior")) / (F.col("n") + weight) >= reject).select("host", "template")


def judge(pages: DataFrame, rules=RULES, labels: DataFrame | None = None, branches: int = BRANCHES, depth: int = DEPTH, weight: float = WEIGHT, reject: float = REJECT, support: int = SUPPORT) -> DataFrame:
    """page_id, host, path, rule, verdict: the rule's, else block if the page's template is rejected.

    The tree learns from the rules' verdicts and, where given, from labels (page_id, blocked: 0 or 1) of single pages; a label of its own
    outweighs the rule there, but never in the verdict. Of several labels of a page the highest counts, a null one for nothing.
    A null url, or one without ://, has an empty host and path and is allowed unless its (empty) template is rejected. All rows stay,
    repeated ones too. The prior is one row, so it can be broadcast. Other columns aren't read.
    """
    ruled = apply_rules(pages, rules)
    blocked = F.when(F.col("rule_verdict") == "block", 1).when(F.col("rule_verdict") == "allow", 0)
    if labels is not None:
        own = labels.where("page_id is not null").groupBy(F.col("page_id").alias("_page")).agg(F.max("blocked").cast("int").alias("_own"))
        ruled = ruled.join(own, F.col("page_id") == F.col("_page"), "left").withColumn("blocked", F.coalesce("_own", blocked)).drop("_page", "_own")
    else:
        ruled = ruled.withColumn("blocked", blocked)
    placed = templates(ruled, branches, depth, support=support)
    bad = cut(rejected_templates(placed, weight, reject).select(F.col("host").alias("_h"), F.col("template").alias("_t")))
    out = placed.join(bad, (F.col("host") == F.col("_h")) & (F.col("template") == F.col("_t")), "left")
    verdict = F.coalesce("rule_verdict", F.when(F.col("_h").isNotNull(), F.lit("block")).otherwise(F.lit("allow")))
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "template")
