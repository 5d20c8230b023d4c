"""URL filter by rules and by a tree of path templates for each host.

Rules name a host, with its subdomains, and a path prefix; the longest that fits decides. They also label URLs for the tree:
level by level, a path segment that few URLs of its place share becomes a wildcard, and sibling branches whose labelled shares
of blocked URLs do not differ by chance merge, as do those without labels. The purity of a node is its labelled share of
blocked URLs, drawn towards the purity of the node above it, and that of a host towards the share of all labelled URLs. So a
template without labels has the evidence of the branch that it stands in. A template is rejected when its purity is high
enough; URLs that no rule fits get the verdict of their template.
"""

from __future__ import annotations

import string
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxpress.llm.common import cut_lineage

#: (verdict, host and path prefix)
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))


def host_of(url: Column) -> Column:
    rest = F.substring_index(F.concat(F.lit("x"), url), "://", 1)
    after = F.substring(url, F.length(rest) + F.lit(3), F.length(url))
    host = F.regexp_extract(after, r"^[^/?#]*", 0)
    return F.when(F.instr(url, "://") > 0, F.translate(host, string.ascii_uppercase, string.ascii_lowercase)).otherwise(F.lit(""))


def path_of(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"^(?s:.*?)://[^/?#]*([^?#]*)", 1)).otherwise(F.lit(""))


def rule_for(host: Column, path: Column, rules: Sequence[tuple[str, str]]) -> Column:
    """The longest rule that fits, or null; a few hundred rules at most, as one expression."""
    out = F.lit(None).cast("string")
    for _, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        name, slash, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def path_templates(urls: DataFrame, depth: int, common: int, z: float) -> DataFrame:
    """Adds template, and levels of it from the host down, to rows (host, path, n, blocked, labelled): one per distinct host and path."""
    segments = F.slice(F.split(F.regexp_replace("path", r"^/", ""), "/", -1), 1, depth)
    t = urls.withColumn("segs", segments).withColumn("template", F.lit("")).withColumn("levels", F.array(F.lit("")))
    for d in range(1, depth + 1):
        t = t.withColumn("seg", F.try_element_at("segs", F.lit(d)))
        kids = t.where("seg is not null").groupBy("host", "template", "seg").agg(*[F.sum(c).alias(f"{c}_k") for c in ("n", "labelled", "blocked")])
        kids = kids.where((F.col("n_k") >= common) & (F.col("seg") != ""))
        rate = F.try_divide(F.col("blocked_k"), F.col("labelled_k"))
        place = Window.partitionBy("host", "template").orderBy(rate.asc_nulls_first(), "seg")
        # siblings in order of their share, those without one first; a new branch where the step to the next is more than chance
        pooled = (F.col("blocked_k") + F.lag("blocked_k").over(place) + 1) / (F.col("labelled_k") + F.lag("labelled_k").over(place) + 2)
        noise = F.sqrt(pooled * (1 - pooled) * (F.try_divide(F.lit(1.0), F.col("labelled_k")) + F.try_divide(F.lit(1.0), F.lag("labelled_k").over(place))))
        apart = (F.col("labelled_k") > 0) & F.coalesce(rate - F.lag(rate).over(place) > F.lit(z) * noise, F.lit(True))
        kids = kids.withColumn("apart", apart.cast("int"))
        kids = kids.withColumn("branch", F.sum("apart").over(place.rowsBetween(Window.unboundedPreceding, 0)))
        kids = kids.withColumn("name", F.min("seg").over(Window.partitionBy("host", "template", "branch")))
        kids = kids.select(F.col("host").alias("h_"), F.col("template").alias("t_"), F.col("seg").alias("s_"), "name")
        t = t.join(kids, (t["host"] == kids["h_"]) & (t["template"] == kids["t_"]) & (t["seg"] == kids["s_"]), "left")
        step = F.when(F.col("seg") == "", F.lit("")).when(F.col("name").isNotNull(), F.col("name")).otherwise(F.lit("*"))
        t = t.withColumn("template", F.when(F.col("seg").isNull(), F.col("template")).otherwise(F.concat("template", F.lit("/"), step)))
        t = t.withColumn("levels", F.array_append("levels", F.col("template")))
        t = cut_lineage(t.drop("h_", "t_", "s_", "name", "seg"))
    return t.drop("segs")


def graded_templates(tree: DataFrame, depth: int, weight: float) -> DataFrame:
    """(host, template, purity) of the templates of ``tree`` (host, template, levels, labelled, blocked)."""
    nodes = tree.groupBy("host", "levels").agg(F.sum("labelled").alias("l"), F.sum("blocked").alias("b"))
    prior = nodes.agg(F.coalesce(F.try_divide(F.sum("b").cast("double"), F.sum("l").cast("double")), F.lit(0.0))).first()[0]
    nodes = nodes.withColumn("purity", F.lit(float(prior or 0.0)))
    for d in range(depth + 1):
        name = F.element_at("levels", d + 1)
        node = Window.partitionBy("host", name)
        drawn = (F.sum("b").over(node) + F.lit(weight) * F.col("purity")) / (F.sum("l").over(node) + F.lit(weight))
        nodes = nodes.withColumn("purity", drawn if d == 0 else F.when(name == F.element_at("levels", d), F.col("purity")).otherwise(drawn))
    return nodes.select("host", F.element_at("levels", depth + 1).alias("template"), "purity")


def judge_urls(
    pages: DataFrame,
    rules: Sequence[tuple[str, str]] = RULES,
    depth: int = 4,
    common: int = 5,
    z: float = 3.0,
    weight: float = 4.0,
    reject: float = 0.8,
    hidden: Column | None = None,
) -> DataFrame:
    """(page_id, host, path, rule, verdict, template, purity) for every row of ``pages`` (page_id, url).

    A null url and one without "://" have empty host and path and fit no rule. A segment that at least ``common`` URLs of its
    place have stays as it is, others become ``*``; what is deeper than ``depth`` segments is cut. ``purity`` is the share
    of blocked among the labelled URLs of a node with ``weight`` more at the purity of the node above; at ``reject`` or more a
    template is blocked. The tree is built on distinct URLs with counts, so a very common URL is one row. Rules of URLs for
    which ``hidden``, a condition on host and path, holds are no evidence and decide nothing: so verdicts can be tested.
    """
    judged = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    judged = judged.withColumn("host", F.coalesce("host", F.lit(""))).withColumn("path", F.coalesce("path", F.lit("")))
    judged = judged.withColumn("rule", rule_for(F.col("host"), F.col("path"), rules))
    known = F.col("rule").isNotNull() if hidden is None else F.col("rule").isNotNull() & ~hidden
    blocking = F.col("rule").isin([r for v, r in rules if v == "block"])
    distinct = judged.groupBy("host", "path", "rule").agg(F.count("*").alias("n"))
    labelled, blocked = F.when(known, F.col("n")).otherwise(0), F.when(known & blocking, F.col("n")).otherwise(0)
    tree = path_templates(cut_lineage(distinct.withColumn("labelled", labelled).withColumn("blocked", blocked)), depth, common, z)
    graded = cut_lineage(graded_templates(tree, depth, weight))
    if graded.count() <= 500_000:  # some ten MB; beyond, the join is shuffled and its skew split
        graded = F.broadcast(graded)
    named = tree.select("host", "path", "template").join(graded, ["host", "template"]).select(F.col("host").alias("h_"), F.col("path").alias("p_"), "template", "purity")
    named = cut_lineage(named)  # the join stands alone, so that a host with very many URLs can be split
    out = judged.join(named, (judged["host"] == named["h_"]) & (judged["path"] == named["p_"]))
    verdict = F.when(known, F.when(blocking, "block").otherwise("allow")).when(F.col("purity") >= reject, "block").otherwise("allow")
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "template", F.round("purity", 9).alias("purity"))


def op7_url_filter(spark, sf_dir: str) -> DataFrame:
    """All rows of ``pages``; null and odd URLs, ties, repeated rows and empty tables as in ``judge_urls``."""
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"))


def url_sql(pages: str = "pages", rules: Sequence[tuple[str, str]] = RULES, depth: int = 4, common: int = 5) -> str:
    """The same judgement for DuckDB, with the other parameters at their defaults."""
    cases = ""
    for _, rule in sorted(rules, key=lambda r: (-len(r[1]), r[1])):
        name, slash, rest = rule.partition("/")
        cases += f" WHEN (host = '{name}' OR host LIKE '%.{name}') AND starts_with(path, '{slash}{rest}') THEN '{rule}'"
    blocking = ", ".join(f"'{r}'" for v, r in rules if v == "block")
    steps = ""
    for d in range(1, depth + 1):
        place = "PARTITION BY host, template ORDER BY rate NULLS FIRST, seg"
        steps += f""",
k{d} AS (SELECT host, template, segs[{d}] AS seg, sum(n) AS n, sum(labelled)::BIGINT AS l, sum(blocked)::BIGINT AS b FROM t{d - 1} WHERE len(segs) >= {d} AND segs[{d}] <> '' GROUP BY ALL HAVING sum(n) >= {common}),
r{d} AS (SELECT *, CASE WHEN l > 0 THEN b::DOUBLE / l END AS rate FROM k{d}),
p{d} AS (SELECT *, lag(l) OVER w AS l0, lag(b) OVER w AS b0, lag(rate) OVER w AS rate0, (b + lag(b) OVER w + 1)::DOUBLE / (l + lag(l) OVER w + 2) AS pooled FROM r{d} WINDOW w AS ({place})),
a{d} AS (SELECT *, (l > 0 AND coalesce(rate - rate0 > 3.0 * sqrt(pooled * (1 - pooled) * (1.0::DOUBLE / nullif(l, 0) + 1.0::DOUBLE / nullif(l0, 0))), true))::INTEGER AS apart FROM p{d}),
b{d} AS (SELECT *, sum(apart) OVER ({place} ROWS UNBOUNDED PRECEDING) AS branch FROM a{d}),
m{d} AS (SELECT host, template, seg, min(seg) OVER (PARTITION BY host, template, branch) AS name FROM b{d}),
s{d} AS (SELECT t.host, path, n, labelled, blocked, segs, levels,
  t.template || CASE WHEN len(segs) < {d} THEN '' WHEN segs[{d}] = '' THEN '/' ELSE '/' || coalesce(name, '*') END AS template
  FROM t{d - 1} t LEFT JOIN m{d} m ON m.host = t.host AND m.template = t.template AND m.seg = t.segs[{d}]),
t{d} AS (SELECT * REPLACE (list_append(levels, template) AS levels) FROM s{d})"""
    grades = ""
    for d in range(depth + 1):
        drawn = f"(sum(b) OVER (PARTITION BY host, levels[{d + 1}]) + 4.0::DOUBLE * purity) / (sum(l) OVER (PARTITION BY host, levels[{d + 1}]) + 4.0::DOUBLE)"
        grades += f""",
g{d + 1} AS (SELECT host, levels, l, b, {drawn if d == 0 else f"CASE WHEN levels[{d + 1}] = levels[{d}] THEN purity ELSE {drawn} END"} AS purity FROM g{d})"""
    return f"""
WITH u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM {pages}),
h AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{string.ascii_uppercase}', '{string.ascii_lowercase}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
j AS (SELECT *, CASE{cases} END AS rule FROM h),
d AS (SELECT host, path, rule, count(*) AS n FROM j GROUP BY ALL),
t0 AS (SELECT host, path, n, CASE WHEN rule IS NOT NULL THEN n ELSE 0 END AS labelled, CASE WHEN rule IN ({blocking}) THEN n ELSE 0 END AS blocked, string_split(regexp_replace(path, '^/', ''), '/')[1:{depth}] AS segs, '' AS template, [''] AS levels FROM d){steps},
g0 AS (SELECT host, levels, l, b, coalesce(sum(b) OVER ()::DOUBLE / nullif(sum(l) OVER (), 0), 0.0::DOUBLE) AS purity FROM (SELECT host, levels, sum(labelled)::BIGINT AS l, sum(blocked)::BIGINT AS b FROM t{depth} GROUP BY ALL)){grades},
g AS (SELECT host, levels[{depth + 1}] AS template, purity FROM g{depth + 1})
SELECT page_id, j.host, j.path, rule, CASE WHEN rule IN ({blocking}) THEN 'block' WHEN rule IS NOT NULL THEN 'allow' WHEN purity >= 0.8 THEN 'block' ELSE 'allow' END AS verdict, t.template, round(purity, 9) AS purity
FROM j JOIN t{depth} t ON t.host = j.host AND t.path = j.path JOIN g ON g.host = t.host AND g.template = t.template"""
