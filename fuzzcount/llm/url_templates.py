"""URL filtering by rules and by a tree of path templates per host.

Rules name a host (which covers its subdomains) and a path prefix; the longest rule that fits decides.
Where none fits, templates do.  Paths are cut into segments and numbers in them become `#`.  Level by level, down to the deepest path,
a node of a host's tree turns its rare children (by pages or by their share) into the wildcard `*` when it has many, and folds children
whose share of blocked pages cannot be told from their siblings' into `~`.  Each template is then judged by
its purity: the blocked share of its labelled pages, smoothed towards a low base, so that a template of which
nothing is known passes.  Labels are the rules' own verdicts, or a column of the caller's.

Only DataFrame operations are used; pages are counted per host and path first, so a host with a third of
all pages sends a few rows on, and the joins back to pages can be split.

Edge cases: a null url, or one without `://`, has an empty host and path and is judged like any other; repeated urls share a template and keep a row each; without any labelled
page every verdict is allow; an empty table gives no rows.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzcount.llm.text import LOWER, UPPER
from fuzzcount.sources.tables import cut

MANY_CHILDREN, FEW_PAGES, RARE_SHARE = 8, 2, 0.02
Z = 1.96
PRIOR, BASE = 4.0, 0.1
REJECT = 0.5

Rule = tuple[str, str]
#: The rules of the contract, as (verdict, host and path).
RULES: list[Rule] = [("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/")]


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(_after_scheme(url), r"^[^/?#]*", 0), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(_after_scheme(url), r"^[^/?#]*([^?#]*)", 1)


def _after_scheme(url: Column) -> Column:
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def rule_for(host: Column, path: Column, rules: list[Rule]) -> Column:
    """The longest fitting rule as struct(rule, verdict), or null."""
    found = []
    for verdict, rule in sorted(rules, key=lambda r: (-len(r[1]), r[1])):
        name, _, rest = rule.partition("/")
        found.append(F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"), F.lit(name).alias("host"), F.lit("/" + rest).alias("path")))
    if not found:
        return F.lit(None).cast("struct<rule:string,verdict:string,host:string,path:string>")
    fits = F.filter(F.array(*found), lambda r: ((host == r["host"]) | F.endswith(host, F.concat(F.lit("."), r["host"]))) & F.startswith(path, r["path"]))
    return F.get(fits, 0)


def segments_of(path: Column) -> Column:
    """The generalised segments of a path; an array of one empty string for an empty path."""
    return F.transform(F.split(F.regexp_replace(path, r"^/|/$", ""), "/"), lambda s: F.regexp_replace(s, "[0-9]+", "#"))


def _sums() -> list[Column]:
    return [F.sum(c).alias(c) for c in ("pages", "labelled", "blocked")]


def templates(paths: DataFrame) -> DataFrame:
    """`paths` (host, segments, pages, labelled, blocked; one row each) with the `template` of each."""
    rows = cut(paths.withColumn("template", F.lit("")))
    done, level = [], 0
    while rows.head(1):
        # Paths that end above this level have their template; the others go on.
        ended = F.size("segments") <= level
        done.append(rows.where(ended))
        rows = cut(rows.where(~ended).withColumn("segment", F.get("segments", level)))
        children = cut(rows.groupBy("host", "template", "segment").agg(*_sums()))
        nodes = cut(
            children.groupBy("host", "template").agg(
                F.count("*").alias("children"), F.sum("pages").alias("all_pages"), F.sum("labelled").alias("all_labelled"), F.sum("blocked").alias("all_blocked")
            )
        )
        seen = children.join(nodes, ["host", "template"])
        rare = (F.col("children") >= MANY_CHILDREN) & (F.col("pages") <= F.greatest(F.lit(FEW_PAGES), RARE_SHARE * F.col("all_pages")))
        pooled = F.col("all_blocked") / F.col("all_labelled")
        error = F.sqrt(pooled * (1 - pooled) * (1 / F.col("labelled")))
        alike = (F.col("children") > 1) & (F.col("labelled") > 0) & (F.abs(F.col("blocked") / F.col("labelled") - pooled) <= Z * error)
        name = F.when(rare, "*").when(alike, "~").otherwise(F.col("segment"))
        named = cut(seen.select("host", "template", "segment", F.concat("template", F.lit("/"), name).alias("next")))
        rows = cut(rows.join(named, ["host", "template", "segment"]).withColumn("template", F.col("next")).drop("next", "segment"))
        level += 1
    return reduce(DataFrame.unionByName, done, rows)


def purity(rows: DataFrame) -> DataFrame:
    """(host, template, purity) of each template of `rows`: its blocked share, smoothed towards `BASE`."""
    own = rows.groupBy("host", "template").agg(*_sums())
    return own.select("host", "template", ((F.col("blocked") + PRIOR * BASE) / (F.col("labelled") + PRIOR)).alias("purity"))


def judge(pages: DataFrame, rules: list[Rule] = RULES, label_col: str | None = None) -> DataFrame:
    """One row per row of `pages` (page_id, url): host, path, rule, verdict, template, purity.

    `label_col` names a column that is true for pages to block, false for good ones and null elsewhere;
    without it the rules' verdicts are the labels.
    """
    label = [F.col(label_col).alias("label")] if label_col else []
    read = pages.select(F.col("page_id"), host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), *label)
    read = read.withColumn("found", rule_for(F.col("host"), F.col("path"), rules))
    read = read.withColumn("segments", segments_of(F.col("path"))).withColumn("label", F.col("label") if label_col else F.col("found.verdict") == "block")
    paths = read.groupBy("host", "segments").agg(F.count("*").alias("pages"), F.count("label").alias("labelled"), F.count_if("label").alias("blocked"))
    named = templates(paths)
    named = cut(named)
    judged = cut(named.join(cut(purity(named)), ["host", "template"]).select("host", "segments", "template", "purity"))
    return read.join(judged, ["host", "segments"]).select(
        "page_id", "host", "path", F.col("found.rule").alias("rule"),
        F.coalesce("found.verdict", F.when(F.col("purity") >= REJECT, "block").otherwise("allow")).alias("verdict"), "template", F.round("purity", 6).alias("purity"),
    )
