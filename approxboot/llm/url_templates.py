"""URL filtering by a tree of path templates.

Explicit rules come first: the longest rule whose host and path fit decides. Other urls are judged by their
template: per host, path segments that vary become wildcards, by counts alone; sibling templates whose labels are
statistically alike are merged, and a template is rejected when the smoothed share of bad labels under it
lies clearly above that of all labelled urls.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from approxboot.llm.common import table, written

# Rules as (verdict, host, path).
RULES = [
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
]


def host_of(url: Column) -> Column:
    """What stands after the first :// up to /, ?, # or the end, A-Z lower-cased; empty without ://."""
    host = F.regexp_extract(url, r"^(?s).*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    """What follows the host up to ?, # or the end; empty without ://."""
    return F.coalesce(F.regexp_extract(url, r"^(?s).*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_for(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> tuple[Column, Column]:
    """The longest fitting rule's text and verdict; null where none fits. A host's rule holds for its subdomains."""
    text = verdict = None
    for v, h, p in sorted(rules, key=lambda r: -len(r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        text = F.when(fits, F.lit(h + p)) if text is None else text.when(fits, F.lit(h + p))
        verdict = F.when(fits, F.lit(v)) if verdict is None else verdict.when(fits, F.lit(v))
    none = F.lit(None).cast("string")
    return (none, none) if text is None else (text, verdict)


@dataclass(frozen=True)
class TemplateParams:
    """distinct_share: segments with at least this share of distinct values among their rows vary; min_distinct values at least.
    likeness: siblings whose smoothed bad shares differ by at most this many standard errors merge.
    prior_weight: rows that the overall bad share counts as. lift, errors: a template is rejected whose smoothed bad
    share is at least lift times the overall one, and more than errors standard errors above it."""

    depth: int = 6
    distinct_share: float = 0.2
    min_distinct: int = 8
    likeness: float = 1.0
    prior_weight: float = 10.0
    lift: float = 1.25
    errors: float = 1.0


def segments(path: Column, depth: int) -> Column:
    """Segments of a path, empty ones left out; what lies beyond depth is one last segment."""
    parts = F.filter(F.split(path, "/"), lambda s: s != "")
    rest = F.array_join(F.slice(parts, depth, 1_000_000), "/")
    return F.when(F.size(parts) > depth, F.concat(F.slice(parts, 1, depth - 1), F.array(rest))).otherwise(parts)


def shapes(urls: DataFrame, params: TemplateParams) -> DataFrame:
    """(host, shape, rows, n, k) for urls (host, path, bad): rows by host and segments, with labelled and bad ones.

    Partial counts are made before anything is shuffled, so a hot host costs as much as its distinct shapes.
    """
    shaped = urls.select("host", segments(F.col("path"), params.depth).alias("shape"), "bad")
    return shaped.groupBy("host", "shape").agg(F.count(F.lit(1)).alias("rows"), F.count("bad").alias("n"), F.coalesce(F.sum("bad"), F.lit(0)).alias("k"))


def templates(shaped: DataFrame, params: TemplateParams = TemplateParams()) -> DataFrame:
    """shaped with template: the shape with wildcards for segments that vary.

    Level by level from the host down. A node whose children are many and mostly distinct, by rows, gets
    one wildcard child. A literal segment is written with its * doubled, so that it is never a wildcard.
    """
    out = written(shaped.withColumn("template", F.lit("")), "templates")
    for level in range(params.depth):
        here = out.withColumn("_v", F.get("shape", F.lit(level)))
        if here.where("_v is not null").isEmpty():
            break
        by_value = here.where("_v is not null").groupBy("host", "template", "_v").agg(F.sum("rows").alias("_n"))
        nodes = by_value.groupBy("host", "template").agg(F.count(F.lit(1)).alias("_distinct"), F.sum("_n").alias("_rows"))
        wild = nodes.where((F.col("_distinct") >= params.min_distinct) & (F.col("_distinct") >= params.distinct_share * F.col("_rows")))
        wild = wild.select("host", "template", F.lit(True).alias("_wild"))
        joined = here.join(wild, ["host", "template"], "left")
        step = F.when(F.col("_v").isNull(), F.lit("")).otherwise(F.concat(F.lit("/"), F.when(F.col("_wild"), F.lit("*")).otherwise(F.regexp_replace("_v", "[*]", "**"))))
        out = written(joined.withColumn("template", F.concat("template", step)).select(*out.columns), "templates")
    return out


def judged_templates(tree: DataFrame, params: TemplateParams = TemplateParams()) -> DataFrame:
    """(host, template, group, bad_share, verdict) from rows (host, template, n, k).

    Siblings (same host and parent) are ordered by their smoothed bad share, ties by template; a neighbour within
    likeness standard errors joins the group before it. The group's share, smoothed toward that of all labelled
    rows, decides. Templates without labels get the overall share and are allowed; so are all where no row is
    labelled. An empty tree gives no rows.
    """
    stats = tree.groupBy("host", "template").agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
    total = stats.agg(F.sum("k").alias("_k"), F.sum("n").alias("_n")).select((F.coalesce("_k", F.lit(0)) + 1).alias("_a"), (F.coalesce("_n", F.lit(0)) + 2).alias("_b"))
    w = params.prior_weight
    # total is one row
    s = stats.join(F.broadcast(total)).withColumn("_prior", F.col("_a") / F.col("_b"))
    s = s.withColumn("_share", (F.col("k") + w * F.col("_prior")) / (F.col("n") + w)).withColumn("_parent", F.regexp_replace("template", "/[^/]*$", ""))
    order = Window.partitionBy("host", "_parent").orderBy("_share", "template")
    error = lambda share, n: F.sqrt(share * (1 - share) / (n + w))
    s = s.withColumn("_se", error(F.col("_share"), F.col("n")))
    apart = F.col("_share") - F.lag("_share").over(order) > params.likeness * F.sqrt(F.col("_se") ** 2 + F.lag("_se").over(order) ** 2)
    s = s.withColumn("_cut", F.when(apart, 1).otherwise(0))
    s = s.withColumn("group", F.sum("_cut").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    groups = Window.partitionBy("host", "_parent", "group")
    s = s.withColumn("_gk", F.sum("k").over(groups)).withColumn("_gn", F.sum("n").over(groups))
    s = s.withColumn("bad_share", (F.col("_gk") + w * F.col("_prior")) / (F.col("_gn") + w))
    clear = (F.col("bad_share") >= params.lift * F.col("_prior")) & (F.col("bad_share") - params.errors * error(F.col("bad_share"), F.col("_gn")) > F.col("_prior"))
    return s.select("host", "template", "group", "bad_share", F.when(clear, "block").otherwise("allow").alias("verdict"))


def judge(urls: DataFrame, labels: DataFrame, rules: list[tuple[str, str, str]] | None = None, params: TemplateParams = TemplateParams()) -> DataFrame:
    """urls (id, url) with host, path, rule, template, bad_share and verdict; labels: (id, bad 0/1).

    labels.id is matched with the column label_id of urls, or id where there is none. Every row keeps its place:
    repeated ids and urls too. A null url, or one without ://, has an empty host and path and the empty template;
    a null id has no label. Repeated labels of an id count as their largest, null ones as none. Urls of any length
    are judged whole. Other columns are not looked at; an empty table gives an empty one.
    """
    rules = RULES if rules is None else rules
    named = F.col("label_id" if "label_id" in urls.columns else "id")
    parsed = urls.select("id", named.alias("_label"), host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    one = labels.where("id is not null").groupBy(F.col("id").alias("_label")).agg(F.max("bad").alias("bad"))
    tree = templates(shapes(parsed.join(one, "_label", "left"), params), params)
    verdicts = judged_templates(tree, params)
    own = tree.join(verdicts, ["host", "template"]).select("host", "shape", "template", "bad_share", F.col("verdict").alias("_own"))
    text, verdict = rule_for(F.col("host"), F.col("path"), rules)
    out = parsed.withColumn("shape", segments(F.col("path"), params.depth)).join(written(own, "templates"), ["host", "shape"], "left")
    return out.select("id", "host", "path", text.alias("rule"), "template", "bad_share", F.coalesce(verdict, F.col("_own")).alias("verdict"))


def document_number(url: Column) -> Column:
    """The number that a url's path ends with, with or without an ending: that of the document which its page shows."""
    return F.regexp_extract(path_of(url), "/([0-9]{1,18})([.][A-Za-z]+)?/?$", 1).try_cast("long")


def op5_path_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts on all pages. A page shows the document that its url numbers, so that document's label is the page's: bad is low quality or toxic."""
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), "url", document_number(F.col("url")).alias("label_id"))
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("id"), F.greatest(1 - F.col("quality"), F.col("toxic")).alias("bad"))
    out = judge(pages, labels)
    return out.select(F.col("id").alias("page_id"), "host", "path", "rule", "verdict", "template", F.round("bad_share", 6).alias("bad_share"))


QUERIES = {"op5_path_templates": op5_path_templates}
ORACLES: dict[str, str] = {}
