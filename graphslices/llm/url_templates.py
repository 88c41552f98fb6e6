"""URL filter: rules by host and path, and else a tree of path templates with labelled purity.

Per host, the urls' paths form a tree of segments. Digits in a segment are generalised at once; then, level by level from the
root, the children of a node are looked at together: if they are many, the rare ones become the wildcard `*`; and of the rest
those whose share of bad labels does not differ from the node's (a z test) are merged into `*` as well, so that only branches that
the labels set apart keep their names. A template is rejected when its purity, the share of good labels smoothed towards its
host's, which is smoothed towards the whole table's, is below a threshold.

Pages are first counted by (host, shape of path): all later steps work on these counts, and pages are only joined with
the finished templates, where adaptive execution splits a host's rows over tasks. Nothing is collected or capped: the first `max_depth` levels are taken one at a time, and
from there on a stretch of segments that all of a node's shapes share, whose names stay, is passed in one step, so the steps are as many as the branchings of a path and not its segments.

Edge cases: a null url or one without `://` has an empty host and path, and takes part as the host ''; null labels count as unlabelled;
a page labelled several times counts each label; repeated rows are judged alike; an empty table gives an empty one; other columns of the pages are carried through by `judge`.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphslices.llm.common import ascii_lower, cut


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def text(self) -> str:
        return self.host + self.path


@dataclass(frozen=True)
class TreeLimits:
    """max_depth: so many levels are taken one at a time, all deeper ones by their branchings. max_children: above so many, children with less than rare_share of the node's pages become `*`. z: width of the test. prior: pseudo-labels. min_purity: threshold."""

    max_depth: int = 6
    max_children: int = 20
    rare_share: float = 0.05
    z: float = 1.96
    prior: float = 4.0
    min_purity: float = 0.5


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)
    return ascii_lower(host), path


def matching_rule(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """The longest rule that fits a url and its verdict; null where none does. rules is a hand-kept list, so it becomes one expression."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.text), r.text)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        name, verdict = F.when(fits, F.lit(r.text)).otherwise(name), F.when(fits, F.lit(r.verdict)).otherwise(verdict)
    return name, verdict


def shape(path: Column) -> Column:
    return F.regexp_replace(F.lower(path), "[0-9]+", "{n}")


def _shared_passed(tree: DataFrame) -> DataFrame:
    """tree with the segments that begin all of a node's open shapes moved to the template: an only child keeps its name."""
    ends = tree.where(F.size("seg") > 0).groupBy("host", "template").agg(F.min("seg").alias("a"), F.max("seg").alias("b"))
    # what the least and the greatest shape share, all share: the place of their first difference, or the length of the shorter
    differ = F.array_position(F.zip_with("a", "b", lambda x, y: F.equal_null(x, y)), False)
    shared = F.when(differ > 0, differ - 1).otherwise(F.least(F.size("a"), F.size("b"))).cast("int")
    ends = ends.select("host", "template", shared.alias("shared"))
    some = (F.col("shared") > 0) & (F.size("seg") > 0)
    return tree.join(ends, ["host", "template"], "left").withColumns({
        "template": F.when(some, F.concat("template", F.lit("/"), F.array_join(F.slice("seg", F.lit(1), F.col("shared")), "/"))).otherwise(F.col("template")),
        "seg": F.when(some, F.slice("seg", F.col("shared") + 1, F.size("seg"))).otherwise(F.col("seg")),
    }).drop("shared")


def templates(pages: DataFrame, limits: TreeLimits = TreeLimits()) -> DataFrame:
    """(host, shape, template, labelled, purity, rejected) from pages with host, path, labelled and bad (counts of labels)."""
    counts = {"n": F.count("*"), "labelled": F.sum("labelled"), "bad": F.sum("bad")}
    base = cut(pages.groupBy("host", shape(F.col("path")).alias("shape")).agg(*[c.alias(k) for k, c in counts.items()]))
    depth = base.agg(F.max(F.size(F.split("shape", "/")))).first()[0] or 1
    sums = lambda: [F.sum(c).alias(c) for c in counts]
    tree = base.withColumns({"seg": F.split("shape", "/"), "template": F.lit("")}).withColumn("seg", F.slice("seg", 2, F.size("seg")))
    level = 0
    while level < depth - 1:  # `seg` holds what is not yet in the template
        if level >= limits.max_depth:
            tree = cut(_shared_passed(tree))
            if tree.where(F.size("seg") > 0).isEmpty():
                break
        level += 1
        child = F.get("seg", F.lit(0))
        kids = tree.where(child.isNotNull()).groupBy("host", "template", child.alias("child")).agg(*sums())
        node = kids.groupBy("host", "template").agg(
            F.count("*").alias("fan"), F.sum("n").alias("all_n"), F.sum("labelled").alias("all_labelled"), F.sum("bad").alias("all_bad")
        )
        # try_divide: ANSI mode refuses a division by zero; a node without labels has no share, and then nothing stands apart
        share = F.try_divide("all_bad", "all_labelled")
        rare = (F.col("fan") > limits.max_children) & (F.col("n") < limits.rare_share * F.col("all_n"))
        off = F.abs(F.try_divide("bad", "labelled") - share)
        apart = off > limits.z * F.sqrt(F.try_divide(share * (1 - share), F.col("labelled")))
        name = F.when(F.col("child") == "", "").when(F.col("fan") == 1, F.col("child")).when(rare, "*").when(apart, F.col("child")).otherwise("*")
        kids = kids.join(node, ["host", "template"])
        kids = kids.withColumn("name", name).select("host", "template", "child", "name")
        tree = cut(
            tree.withColumn("child", child).join(kids, ["host", "template", "child"], "left")
            .withColumn("template", F.when(F.col("child").isNull(), F.col("template")).otherwise(F.concat("template", F.lit("/"), "name")))
            .select("host", "shape", "template", *counts, F.slice("seg", 2, F.size("seg")).alias("seg"))
        )
    smooth = lambda good, n, towards: (good + limits.prior * towards) / (n + limits.prior)
    hosts = tree.groupBy("host").agg(F.sum("labelled").alias("hl"), F.sum("bad").alias("hb"))
    total = hosts.agg(((F.sum(F.col("hl") - F.col("hb")) + 1) / (F.sum("hl") + 2)).alias("g"))  # one row
    hosts = hosts.crossJoin(F.broadcast(total)).select("host", smooth(F.col("hl") - F.col("hb"), F.col("hl"), F.col("g")).alias("towards"))
    leaves = tree.groupBy("host", "template").agg(F.sum("labelled").alias("l"), F.sum("bad").alias("b")).join(hosts, "host")
    pure = smooth(F.col("l") - F.col("b"), F.col("l"), F.col("towards"))
    leaves = leaves.select("host", "template", F.col("l").alias("all_labels"), pure.alias("purity"))
    return tree.join(leaves, ["host", "template"]).select(
        "host", "shape", "template", F.col("all_labels").alias("labelled"), "purity", ((F.col("all_labels") > 0) & (F.col("purity") < limits.min_purity)).alias("rejected")
    )


def judge(pages: DataFrame, labels: DataFrame, rules: list[Rule], limits: TreeLimits = TreeLimits()) -> DataFrame:
    """pages with host, path, rule, verdict, template and purity. labels: (page_id, bad)."""
    host, path = host_and_path(F.col("url"))
    known = labels.where("bad is not null").groupBy("page_id").agg(F.count("bad").alias("__l"), F.sum("bad").cast("long").alias("__b"))
    urls = pages.select("page_id", host.alias("host"), path.alias("path"))
    none = F.lit(0).cast("long")
    marked = urls.join(known, "page_id", "left").select("host", "path", F.coalesce("__l", none).alias("labelled"), F.coalesce("__b", none).alias("bad"))
    found = templates(marked, limits)
    found = found.select([F.col(c).alias(f"__{c}") for c in found.columns])
    rule, verdict = matching_rule(F.col("host"), F.col("path"), rules)
    judged = pages.withColumns({"host": host, "path": path}).withColumns({"rule": rule, "__verdict": verdict})
    judged = judged.join(found, (F.col("host") == F.col("__host")) & (shape(F.col("path")) == F.col("__shape")), "left")
    own = F.when(F.col("__rejected"), "block").otherwise("allow")
    out = judged.withColumns({"verdict": F.coalesce("__verdict", own), "template": F.col("__template"), "purity": F.col("__purity")})
    return out.drop("__verdict", *found.columns)
