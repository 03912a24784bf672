"""URL filter by a path-template tree, in DataFrame functions only.

A url's path segments are first generalised by form (numbers, dates, hex runs, long mixed words stand as wildcards of
their kind). Equal paths of a host are counted together, and on these counted templates the tree is built level by
level: a level where a node has very many rare children turns into one wildcard, and sibling branches of enough urls that
lead on to the same forms in like shares (chi-square against their pooled shares) merge into one; small branches, of which
a test can tell nothing, stay apart. Urls that a fixed rule decides are the labelled ones; a template is rejected when
enough of it is labelled and its share of blocked labels, smoothed towards its host's share, is high. So a verdict reaches
the unlabelled urls of a template, and of branches merged with labelled ones.

Nulls and edges: a null url, or one without ``://``, has an empty host and path, matches no rule and is allowed;
repeated rows are judged each, alike; an empty table gives an empty result. The tree has ``depth`` levels; all segments
below them, generalised each, are the form of the last one, so paths that differ there are different templates.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from derivatrace.llm.common import ascii_lower, column, cut


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


#: The rules of the query.
RULES = (
    Rule("allow", "com", "/"),
    Rule("block", "example.com", "/en/"),
    Rule("allow", "www.example.com", "/en/"),
    Rule("block", "net", "/es/"),
    Rule("block", "net", "/fr/"),
)


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty for null or without ``://``."""
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    body = F.coalesce(url, F.lit(""))
    return ascii_lower(F.regexp_extract(body, pattern, 1)), F.regexp_extract(body, pattern, 2)


def rule_column(rules: tuple[Rule, ...], host: Column, path: Column, value) -> Column:
    """value(rule) of the longest rule that fits, else null."""
    out = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.text), len(r.host), r.verdict == "block")):  # the last one wrapped is tried first
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        out = F.when(fits, F.lit(value(r))).otherwise(out)
    return out


def generalised(segment: Column) -> Column:
    """A segment's form: variable parts as wildcards, a file ending kept."""
    ending = F.regexp_extract(segment, r"(\.[A-Za-z][A-Za-z0-9]{0,4})$", 1)
    stem = F.regexp_replace(segment, r"\.[A-Za-z][A-Za-z0-9]{0,4}$", "")
    kind = (
        F.when(stem.rlike(r"^\d+$"), F.lit("{n}"))
        .when(stem.rlike(r"^\d{4}-\d{2}(-\d{2})?$"), F.lit("{date}"))
        .when(stem.rlike(r"^(?=.*\d)[0-9A-Fa-f-]{8,}$"), F.lit("{hex}"))
        .when(stem.rlike(r"\d") & (F.length(stem) >= 12), F.lit("{mixed}"))
        .otherwise(stem)
    )
    return F.concat(kind, ending)


def templates(pages: DataFrame, url: str, rules: tuple[Rule, ...], depth: int) -> DataFrame:
    """Each row's host, path, rule, label and template levels t1..t<depth> and the rest (form of each segment)."""
    host, path = url_parts(column(pages, url))
    out = pages.withColumns({"_host": host, "_path": path})
    out = out.withColumns({"_rule": rule_column(rules, F.col("_host"), F.col("_path"), lambda r: r.text), "_label": rule_column(rules, F.col("_host"), F.col("_path"), lambda r: r.verdict)})
    out = out.withColumn("_segments", F.split(F.regexp_replace("_path", "^/", ""), "/", -1))
    below = F.slice("_segments", depth + 1, F.greatest(F.size("_segments") - depth, F.lit(0)))
    rest = F.when(F.size("_segments") > depth, F.concat(F.lit("/"), F.array_join(F.transform(below, generalised), "/"))).otherwise(F.lit(""))
    return out.withColumns({**{f"_t{i + 1}": F.when(F.size("_segments") > i, generalised(F.get("_segments", F.lit(i)))).otherwise(F.lit("")) for i in range(depth)}, f"_t{depth + 1}": rest})


def critical_value(free: Column, z: float) -> Column:
    """The chi-square value that z's upper tail leaves, by the cube approximation; 0 without a degree of freedom."""
    part = F.lit(2.0) / (9.0 * free)
    return F.when(free > 0, free * F.pow(1.0 - part + z * F.sqrt(part), F.lit(3.0))).otherwise(F.lit(0.0))


def tree(counted: DataFrame, depth: int, *, most_children: int, rare: float, z: float, least_branch: int) -> DataFrame:
    """Add node columns n1..n<depth>: the segment's form, ``*`` for a wildcard, ``~`` for a merged branch.

    counted has a row for each host and lexical template, with its rows n, so every step works on pre-aggregated rows.
    """
    out, parents = counted, ["_host"]
    for i in range(1, depth + 1):
        seg, after = f"_t{i}", f"_t{i + 1}"
        kids = out.groupBy(*parents, seg).agg(F.sum("n").alias("_kn"))
        wide = kids.groupBy(*parents).agg(F.count(F.lit(1)).alias("_kids"), F.sum("_kn").alias("_all"), F.max("_kn").alias("_top"))
        variable = wide.where((F.col("_kids") > most_children) & (F.col("_top") <= rare * F.col("_all"))).select(*parents, F.lit(True).alias("_variable"))
        out = out.join(variable, parents, "left").withColumn(f"_n{i}", F.when(F.col("_variable") & (F.col(seg) != ""), F.lit("*")).otherwise(F.col(seg))).drop("_variable")
        # Branches against the pooled shares of the forms that follow, by chi-square.
        cells = out.groupBy(*parents, f"_n{i}", after).agg(F.sum("n").alias("_c"))
        pooled = cells.groupBy(*parents, after).agg(F.sum("_c").alias("_pc"))
        totals = pooled.groupBy(*parents).agg(F.sum("_pc").alias("_pn"), F.sum(F.col("_pc") * F.col("_pc")).alias("_psq"), F.count(F.lit(1)).alias("_forms"))
        branch = cells.groupBy(*parents, f"_n{i}").agg(F.sum("_c").alias("_bn"))
        # sum over all forms of (c - n q)^2 / (n q) = sum over the branch's forms of c^2 / (n q) - n
        parts = cells.join(pooled, [*parents, after]).groupBy(*parents, f"_n{i}").agg(F.sum(F.col("_c") * F.col("_c") / F.col("_pc")).alias("_x"))
        tested = parts.join(branch, [*parents, f"_n{i}"]).join(totals, parents)
        statistic = F.col("_x") * F.col("_pn") / F.col("_bn") - F.col("_bn")
        free = F.col("_forms") - 1
        alike = tested.where((statistic <= critical_value(free, z) + F.lit(1e-6)) & (F.col("_bn") >= least_branch)).where(F.col(f"_n{i}") != "").select(*parents, f"_n{i}", F.lit(True).alias("_alike"))
        several = alike.groupBy(*parents).agg(F.count(F.lit(1)).alias("_like")).where("_like > 1").drop("_like")  # one alone keeps its name
        alike = alike.join(several, parents)
        out = cut(out.join(alike, [*parents, f"_n{i}"], "left").withColumn(f"_n{i}", F.when(F.col("_alike"), F.lit("~")).otherwise(F.col(f"_n{i}"))).drop("_alike"), f"url-level{i}")
        parents = [*parents, f"_n{i}"]
    return out


def url_filter(pages: DataFrame, *, id_col: str = "page_id", url: str = "url", rules: tuple[Rule, ...] = RULES, depth: int = 3, most_children: int = 50, rare: float = 0.2, z: float = 2.326, least_branch: int = 10, weight: float = 10.0, least_labels: int = 10, least_coverage: float = 0.25, reject_at: float = 0.9) -> DataFrame:
    """page_id, host, path, rule (null: none), verdict (allow or block), template and its smoothed purity.

    most_children, rare: a node with more children, none of a larger share, has a wildcard for them. z: the test merges
    what isn't unlike at that normal quantile (1%); least_branch: urls that a branch needs to be merged. weight: labels
    that the host's share counts for; a template is rejected from ``reject_at`` on, if at least least_labels of its urls
    and least_coverage of them are labelled.
    """
    lean = pages.select(column(pages, id_col).alias("page_id"), column(pages, url).alias("url"))
    rows = templates(lean, "url", rules, depth)
    levels = [f"_t{i}" for i in range(1, depth + 2)]
    counted = cut(rows.groupBy("_host", *levels).agg(F.count(F.lit(1)).alias("n"), F.count("_label").alias("labelled"), F.count_if(F.col("_label") == "block").alias("blocked")), "url-templates")
    nodes = tree(counted, depth, most_children=most_children, rare=rare, z=z, least_branch=least_branch)
    path = [*[f"_n{i}" for i in range(1, depth + 1)], f"_t{depth + 1}"]
    merged = nodes.groupBy("_host", *path).agg(F.sum("n").alias("_n"), F.sum("labelled").alias("_l"), F.sum("blocked").alias("_b"))
    hosts = counted.groupBy("_host").agg(F.sum("labelled").alias("_hl"), F.sum("blocked").alias("_hb"))
    prior = (F.col("_hb") + 0.5 * weight) / (F.col("_hl") + weight)
    purity = (F.col("_b") + weight * prior) / (F.col("_l") + weight)
    judged = merged.join(hosts, "_host").withColumn("purity", purity)
    reject = (F.col("purity") >= reject_at) & (F.col("_l") >= least_labels) & (F.col("_l") >= least_coverage * F.col("_n"))
    judged = judged.select("_host", *path, "purity", reject.alias("_reject"))
    found = nodes.join(judged, ["_host", *path]).select("_host", *levels, "_reject", "purity", F.concat_ws("/", "_host", *[F.when(F.col(c) != "", F.col(c)) for c in path]).alias("template"))
    out = rows.join(found, ["_host", *levels], "left")
    verdict = F.coalesce("_label", F.when(F.col("_reject"), F.lit("block")).otherwise(F.lit("allow")))
    return out.select("page_id", F.col("_host").alias("host"), F.col("_path").alias("path"), F.col("_rule").alias("rule"), verdict.alias("verdict"), "template", "purity")
