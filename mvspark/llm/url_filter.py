"""URL filters: explicit rules first, then a path-template tree for each host.

Segments that look like numbers, dates or hashes become classes; what is left is aggregated to
distinct (host, path of classes) with its pages and labels, far fewer rows than pages. A page that a rule fits is
labelled by it: blocked or allowed; others have no label. Level by level, segments with little
support become wildcards, and siblings whose pages below look alike (same shapes of next segment) merge into one
branch: labelled ones where their share of blocked among labelled pages does not differ from that of all such
siblings by a test of proportions, those that differ by bins of the share, and unlabelled ones with each other. A
template's purity, the share of blocked among its labelled pages, is smoothed towards its host's, that towards all
labelled pages'; templates that have labelled pages of their own and whose purity reaches ``REJECT`` are blocked. A host's
purity alone blocks nothing, as rules that fit one branch say little about its siblings.

Defined results: null urls and urls without ``://`` have empty host and path, no rule, and the verdict
of that template; without any label nothing is blocked; segments beyond ``DEPTH`` count as one, which keeps their text; repeated
rows are judged one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import spread_join, written

#: (verdict, host, path) of the explicit rules
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
DEPTH, SUPPORT, SMOOTH, REJECT, BINS = 32, 8, 10.0, 0.8, 5
#: standard errors from the siblings' common share up to which a branch counts as like them
ALIKE = 1.96
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    u = F.coalesce(url, F.lit(""))
    host = F.translate(F.regexp_extract(u, "://([^/?#]*)", 1), _UPPER, _LOWER)
    return host, F.regexp_extract(u, "(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_for(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, else nulls."""
    name = verdict = F.lit(None).cast("string")
    for v, h, p in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        name, verdict = F.when(fits, h + p).otherwise(name), F.when(fits, v).otherwise(verdict)
    return name, verdict


def _class(s: Column) -> Column:
    return (
        F.when(s.rlike(r"^[0-9]{4}-[0-9]{2}(-[0-9]{2})?$"), "{date}")
        .when(s.rlike(r"^[0-9]+$"), "{n}")
        .when(s.rlike(r"^[0-9]+\.[A-Za-z]{1,5}$"), F.concat(F.lit("{n}."), F.element_at(F.split(s, r"\."), -1)))
        .when(s.rlike(r"^[0-9A-Fa-f-]{8,}$"), "{hex}")
        .otherwise(s)
    )


def templates(pages: DataFrame, label: Column, depth: int = DEPTH, support: int = SUPPORT) -> DataFrame:
    """(host, shape, template, pages, labelled, share): the template tree's leaf for each distinct path of classes.

    ``pages`` has host and path; ``label`` is 1 for blocked, 0 for allowed, null for pages without a label.
    """
    rows = written(
        pages.select("host", _shape(F.col("path"), depth).alias("shape"), label.cast("long").alias("bad"))
        .groupBy("host", "shape").agg(F.count("*").alias("n"), F.count("bad").alias("known"), F.coalesce(F.sum("bad"), F.lit(0)).alias("bad")), "paths"
    )
    deepest = min(depth + 1, rows.agg(F.max(F.size("shape"))).first()[0] or 0)
    sums = [F.sum(c).alias(c) for c in ("n", "known", "bad")]
    rows = rows.withColumn("template", F.lit(""))
    for level in range(deepest):
        seg, below = F.get(F.col("shape"), level), F.get(F.col("shape"), level + 1)
        shape_below = F.when(below.isNull(), "").when(below.startswith("{"), below).otherwise("w")
        kids = rows.where(seg.isNotNull()).groupBy("host", "template", seg.alias("seg")).agg(
            *sums, F.count("*").alias("paths"), F.array_join(F.array_sort(F.collect_set(shape_below)), "|").alias("below")
        )
        kids = kids.withColumn("name", F.when((F.col("n") < support) & ~F.col("seg").startswith("{"), "*").otherwise(F.col("seg")))
        kids = written(kids, "branches")
        named = kids.where("name <> '*'").groupBy("host", "template", "below")
        pool = named.agg(((F.sum("bad") + 0.5) / (F.sum("known") + 1)).alias("common"), F.count("*").alias("siblings"))
        kids = spread_join(kids, pool, ["host", "template", "below"], "siblings", "left")
        off = F.abs(F.col("bad") - F.col("known") * F.col("common")) / F.sqrt(F.col("known") * F.col("common") * (1 - F.col("common")))
        rate = F.when(F.col("known") == 0, F.lit(-2)).when(off <= ALIKE, F.lit(-1)).otherwise(F.floor((F.col("bad") + 0.5) / (F.col("known") + 1) * BINS))
        kids = written(kids.withColumn("rate", rate), "rates")
        alike = kids.where("name <> '*'").groupBy("host", "template", "below", "rate").agg(F.min("name").alias("first"), F.count("*").alias("k"))
        kids = spread_join(kids, alike, ["host", "template", "below", "rate"], "k", "left")
        name = F.when((F.col("name") != "*") & (F.col("k") > 1), F.concat(F.lit("~"), F.col("first"))).otherwise(F.col("name"))
        kids = kids.select("host", "template", "seg", name.alias("name"), "paths")
        rows = spread_join(rows.withColumn("seg", seg), kids, ["host", "template", "seg"], "paths", "left")
        rows = rows.withColumn("template", F.when(F.col("name").isNull(), F.col("template")).otherwise(F.concat("template", F.lit("/"), "name")))
        rows = written(rows.select("host", "shape", "n", "known", "bad", "template"), "tree")
    known, bad = rows.agg(F.sum("known"), F.sum("bad")).first()
    prior = (bad or 0) / known if known else 0.0
    hosts = rows.groupBy("host").agg(((F.sum("bad") + SMOOTH * prior) / (F.sum("known") + SMOOTH)).alias("host_share"), F.count("*").alias("paths"))
    leaf = written(rows.groupBy("host", "template").agg(F.sum("n").alias("pages"), F.sum("known").alias("known"), F.sum("bad").alias("bad"), F.count("*").alias("shapes")), "leaves")
    leaf = spread_join(leaf, hosts, ["host"], "paths")
    leaf = leaf.withColumn("share", (F.col("bad") + SMOOTH * F.col("host_share")) / (F.col("known") + SMOOTH))
    out = spread_join(rows.select("host", "shape", "template", "n"), leaf.select("host", "template", "pages", "share", F.col("known").alias("labelled"), "shapes"), ["host", "template"], "shapes")
    return out.select("host", "shape", "template", "pages", "labelled", "share", "n")


def _shape(path: Column, depth: int) -> Column:
    segs = F.transform(F.filter(F.split(path, "/"), lambda s: s != ""), _class)
    rest = F.concat(F.lit("{more}"), F.array_join(F.slice(segs, depth + 1, 1 << 20), "/"))
    return F.when(F.size(segs) > depth, F.concat(F.slice(segs, 1, depth), F.array(rest))).otherwise(segs)


def judge(pages: DataFrame, rules=RULES, depth: int = DEPTH) -> DataFrame:
    """One row per row of ``pages``: page_id, host, path, rule, verdict, template, share."""
    host, path = host_and_path(pages["url"].cast("string"))
    rows = pages.select(pages["page_id"].alias("page_id"), host.alias("host"), path.alias("path"))
    rule, verdict = rule_for(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("rule", rule).withColumn("known", verdict)
    tree = written(templates(rows, F.when(F.col("known") == "block", 1).when(F.col("known") == "allow", 0), depth), "templates")
    rows = rows.withColumn("shape", _shape(F.col("path"), depth))
    out = spread_join(rows, tree, ["host", "shape"], "n")
    learnt = F.when((F.col("share") >= REJECT) & (F.col("labelled") > 0), "block").otherwise("allow")
    return out.select("page_id", "host", "path", "rule", F.coalesce("known", learnt).alias("verdict"), "template", "share")
