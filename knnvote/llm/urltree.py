"""URL filtering by a path-template tree and labelled purity, with DataFrame operations only.

Per host, paths become templates: segments that vary (numbers, hex, many distinct values under one
parent) turn into wildcards, sibling branches that are statistically alike merge at every level, and a
template is rejected when the smoothed share of its labelled pages that are bad is high. Rules on hosts
and path prefixes come first, and serve as labels where no others are given.

Trees have any depth. Work goes level by level, over the levels alone at which paths of one host differ.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle

WILD = "*"
FAMILY = "~"  # begins the name of merged siblings; a digest of their most frequent subtree follows


@dataclass(frozen=True)
class Rule:
    action: str  # allow or block
    host: str
    path: str


#: The rules of the page filter.
RULES = (
    Rule("allow", "com", "/"),
    Rule("block", "example.com", "/en/"),
    Rule("allow", "www.example.com", "/en/"),
    Rule("block", "net", "/es/"),
    Rule("block", "net", "/fr/"),
)


def host_and_path(url: str) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL; both empty where it is null or has no `://`."""
    u = F.coalesce(F.col(url), F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, F.expr(f"substring(coalesce(`{url}`, ''), instr(coalesce(`{url}`, ''), '://') + 3)")).otherwise("")
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    host = F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    # the host may end at ? or #: the path is then empty
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return host, path


def ruled(host: Column, path: Column, rules: tuple[Rule, ...] = RULES) -> tuple[Column, Column]:
    """(rule as host + path, its action) of the longest rule that fits, or nulls; of equally long ones the first."""
    best = sorted(rules, key=lambda r: -len(r.host + r.path))
    rule, action = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in reversed(best):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        rule, action = F.when(fits, F.lit(r.host + r.path)).otherwise(rule), F.when(fits, F.lit(r.action)).otherwise(action)
    return rule, action


def segments(path: Column) -> Column:
    """All segments of a path, digits and hex generalised in each; a path that ends with `/` has an empty last one."""
    shape = lambda s: F.regexp_replace(F.regexp_replace(s, r"\b[0-9a-fA-F]{8,}\b", WILD), r"[0-9]+", WILD)
    return F.transform(F.split(F.regexp_replace(path, "^/", ""), "/"), shape)


def branching_levels(shapes: DataFrame) -> list[int]:
    """The levels, from 0, at which two paths of one host differ: nothing varies or merges at others."""
    held = shapes.select("host", F.posexplode("segs").alias("level", "seg"))
    kinds = held.groupBy("host", "level").agg(F.min("seg").alias("a"), F.max("seg").alias("b"))
    return sorted(r[0] for r in kinds.where("a <> b").select("level").distinct().collect())  # fewer numbers than a path has segments


def _upto(level: int) -> Column:
    """The path above a level, as text."""
    return F.array_join(F.slice("path", 1, F.lit(level)), "/")


def _below(level: int) -> Column:
    """A digest of the path below a level; paths that end there share one."""
    return F.md5(F.array_join(F.slice("path", F.lit(level + 2), F.size("path")), "/"))


def _renamed(level: int, name: Column) -> Column:
    return F.concat(F.slice("path", 1, F.lit(level)), F.array(name), F.slice("path", F.lit(level + 2), F.size("path")))


def generalised(shapes: DataFrame, levels: list[int], distinct: int = 8, share: float = 0.2) -> tuple[DataFrame, list[int]]:
    """shapes (host, segs, n, ...) with `path`, and the levels at which a parent has several paths: segments under one parent turn into a wildcard if they take at least
    `distinct` values, and those values are at least `share` of its pages.

    From the top down, a level at a time: counts by (host, parent, segment) are aggregated before they move, and the
    parents that vary are joined back. An empty segment, of a path that ends with `/`, stays as it is. Below a level
    at which every path is alone, none can vary or merge.
    """
    out = shapes.withColumn("path", F.col("segs"))
    for at, k in enumerate(levels):
        if not out.groupBy("host", _upto(k).alias("parent")).count().where("count > 1").limit(1).count():
            return out, levels[:at]
        here = out.withColumn("parent", _upto(k)).withColumn("seg", F.get("path", F.lit(k)))
        kinds = here.where("seg is not null").groupBy("host", "parent", "seg").agg(F.sum("n").alias("n"))
        varied = kinds.groupBy("host", "parent").agg(F.count("*").alias("values"), F.sum("n").alias("n"))
        varied = varied.where((F.col("values") >= distinct) & (F.col("values") >= share * F.col("n"))).select("host", "parent", F.lit(True).alias("varies"))
        here = here.join(varied, ["host", "parent"], "left")
        step = F.when(F.col("varies") & (F.col("seg") != ""), _renamed(k, F.lit(WILD))).otherwise(F.col("path"))
        out = settle(here.withColumn("path", step).drop("parent", "seg", "varies"), "generalised")
    return out, levels


def merged(tree: DataFrame, levels: list[int], overlap: float = 0.5, z: float = 1.96) -> DataFrame:
    """tree (host, path, n, labelled, bad, ...) with `path` renamed where siblings merge, from the lowest level up.

    Siblings of one parent whose most frequent subtree is the same are a family. A branch joins its family if the two
    distributions over subtrees overlap by at least `overlap`, and its bad share is within `z` standard errors of the
    family's; a branch without labels has no share that could differ. Branches are held against their family's pool, so the work
    is linear in the number of templates. A family's name depends on its subtree alone, so that equal subtrees of other
    branches are alike one level up.
    """
    for k in reversed(levels):
        here = tree.withColumn("parent", _upto(k)).withColumn("seg", F.get("path", F.lit(k))).withColumn("below", _below(k))
        parts = here.where("seg is not null").groupBy("host", "parent", "seg", "below").agg(*[F.sum(c).alias(c) for c in ("n", "labelled", "bad")])
        parts = settle(parts, "parts")
        branch = parts.groupBy("host", "parent", "seg").agg(F.max_by("below", F.struct("n", "below")).alias("mode"), *[F.sum(c).alias(c) for c in ("n", "labelled", "bad")])
        pool = branch.groupBy("host", "parent", "mode").agg(F.count("*").alias("members"), F.sum("n").alias("all_n"), F.sum("labelled").alias("all_labelled"), F.sum("bad").alias("all_bad")).where("members > 1")
        known = branch.join(pool, ["host", "parent", "mode"])
        both = parts.select("host", "parent", "seg", "below", F.col("n").alias("here_n")).join(known, ["host", "parent", "seg"])
        wide = both.groupBy("host", "parent", "mode", "below").agg(F.sum("here_n").alias("pool_n"))
        common = both.join(wide, ["host", "parent", "mode", "below"]).groupBy("host", "parent", "seg").agg(F.sum(F.least(F.col("here_n") / F.col("n"), F.col("pool_n") / F.col("all_n"))).alias("common"))
        p = F.try_divide("all_bad", "all_labelled")
        error = F.sqrt(F.try_divide(p * (1 - p), F.col("labelled")))
        alike = (F.col("labelled") == 0) | (F.abs(F.try_divide("bad", "labelled") - p) <= z * error + 1e-9)
        joins = known.join(common, ["host", "parent", "seg"]).where((F.col("common") >= overlap) & alike)
        named = joins.select("host", "parent", "seg", F.concat(F.lit(FAMILY), F.substring("mode", 1, 8)).alias("family"))
        step = F.when(F.col("family").isNotNull(), _renamed(k, F.col("family"))).otherwise(F.col("path"))
        tree = settle(here.join(named, ["host", "parent", "seg"], "left").withColumn("path", step).drop("parent", "seg", "below", "family"), "merged")
    return tree


def purity(tree: DataFrame, strength: float = 4.0) -> DataFrame:
    """tree with labelled_host and bad_share: the smoothed share of bad pages among the labelled ones of each (host, path).

    A template leans on its host's share with the weight of `strength` pages, and a host on the share of all labelled pages; a half
    stands for that where nothing is labelled.
    """
    whole = tree.agg(F.coalesce(F.try_divide(F.sum("bad"), F.sum("labelled")), F.lit(0.5)).alias("base"))  # one row
    smooth = lambda bad, n, prior: (F.col(bad) + strength * F.col(prior)) / (F.col(n) + strength)
    hosts = tree.groupBy("host").agg(F.sum("bad").alias("b"), F.sum("labelled").alias("labelled_host")).crossJoin(F.broadcast(whole))
    hosts = hosts.select("host", "labelled_host", smooth("b", "labelled_host", "base").alias("host_share"))
    groups = tree.groupBy("host", "path").agg(F.sum("bad").alias("group_bad"), F.sum("labelled").alias("group_labelled"))
    shares = groups.join(hosts, "host").select("host", "path", "labelled_host", smooth("group_bad", "group_labelled", "host_share").alias("bad_share"))
    return tree.join(shares, ["host", "path"])


def template_tree(pages: DataFrame, label: str = "bad", distinct: int = 8, share: float = 0.2, overlap: float = 0.5, z: float = 1.96, strength: float = 4.0) -> DataFrame:
    """(host, segs, template, labelled_host, bad_share): one row for every host and path shape among pages (host, segs, label)."""
    counts = [F.count("*").alias("n"), F.count(label).alias("labelled"), F.coalesce(F.sum(F.col(label).cast("long")), F.lit(0)).alias("bad")]
    shapes = settle(pages.groupBy("host", "segs").agg(*counts), "shapes")
    tree, levels = generalised(shapes, branching_levels(shapes), distinct, share)
    tree = merged(tree, levels, overlap, z)
    return purity(tree, strength).select("host", "segs", F.concat(F.lit("/"), F.array_join("path", "/")).alias("template"), "labelled_host", "bad_share")


def judge(pages: DataFrame, page_id: str = "page_id", url: str = "url", rules: tuple[Rule, ...] = RULES, labels: DataFrame | None = None, reject: float = 0.8) -> DataFrame:
    """(page_id, host, path, rule, verdict, template, bad_share) for every row of pages.

    labels: (page_id, bad boolean) of known pages; without it the pages that rules decide are the labelled
    ones. A page without a rule is blocked if its template's smoothed bad share is at least `reject` and its host has
    a labelled page; others are allowed. Null urls, and urls without `://`, have empty host and path, and count as a host
    of their own. Repeated rows each keep their row; an empty table gives an empty result. Further columns of pages
    are ignored.
    """
    host, path = host_and_path(url)
    seen = pages.select(F.col(page_id).cast("long").alias("page_id"), host.alias("host"), path.alias("path"))
    rule, action = ruled(F.col("host"), F.col("path"), rules)
    seen = seen.withColumn("rule", rule).withColumn("action", action).withColumn("segs", segments(F.col("path")))
    if labels is None:
        seen = seen.withColumn("bad", F.when(F.col("action").isNotNull(), F.col("action") == "block"))
    else:
        known = labels.groupBy(F.col("page_id").cast("long").alias("page_id")).agg(F.max("bad").alias("bad"))
        seen = seen.join(known, "page_id", "left")
    out = seen.join(settle(template_tree(seen), "templates"), ["host", "segs"], "left")
    method = F.when((F.col("bad_share") >= reject) & (F.col("labelled_host") > 0), F.lit("block")).otherwise(F.lit("allow"))
    return out.select("page_id", "host", "path", "rule", F.coalesce("action", method).alias("verdict"), "template", "bad_share")
