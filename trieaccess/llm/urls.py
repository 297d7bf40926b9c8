"""URL filters: host/path rules first, then a path-template tree per host.

A rule fits its host and all subdomains if the path starts with the rule's path; the longest rule wins. Up to `COMPILED` rules are compiled
into one expression, more are looked up by host in an Arrow function.

Method for the other urls: digits of a path segment become '#'; per host a tree of segments is grown level by level on
the distinct (host, shaped path) counts, never on pages. A child that holds less than `min_share` of its node's pages
and has under `min_labels` labels, too few to test, becomes '*'. A labelled child whose share of blocked labels is not significantly different (two-proportion z) from that of its
labelled siblings is merged into '*' too. Below level `depth`
a node is split on only where a verdict can depend on it: while it has `min_labels` labels or more and several shapes; '/**' stands for the rest. A template is rejected if it has `min_labels` labelled pages or more and its
smoothed purity (blocked + prior_weight * base rate) / (labelled + prior_weight) is `min_purity` or more; at one half
a page of the template is rather to be blocked than not. Labels are
a column of the input (1 block, 0 allow, null none); where it has none, the verdict of a rule labels the page.

The SQL unrolls `SQL_LEVELS` levels, more than the segments of any given page.

Nulls: a null url or one without '://' has empty host and path and is judged as the template of the empty host. Very long urls are read whole. Ties
between rules of equal length: the first in the list. Repeated rows count each. Empty table: empty result. Extra columns are kept; those named like an output are replaced.
"""

from __future__ import annotations

from itertools import count

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import LOWER, UPPER, Scratch, boxed, lower_ascii, unboxed

COMPILED, SQL_LEVELS = 2000, 6
RULES = (("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/"))


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    return lower_ascii(F.regexp_extract(rest, r"^[^/?#]*", 0)), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def match_rules(host: Column, path: Column, rules: tuple[tuple[str, str, str], ...]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, or nulls."""
    if len(rules) > COMPILED:
        hit = look_up(rules)(host, path)
        return hit["rule"], hit["verdict"]
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for action, h, p in by_length(rules):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        rule, verdict = F.when(fits, h + p).otherwise(rule), F.when(fits, action).otherwise(verdict)
    return rule, verdict


def by_length(rules):
    """Later ones are longer and win; of equal length the first in the list wins."""
    return sorted(reversed(rules), key=lambda r: len(r[1] + r[2]))


def look_up(rules: tuple[tuple[str, str, str], ...]):
    """The same for any number of rules: every parent domain of the host names its rules, the longest first."""
    by_host: dict[str, list[tuple[str, str]]] = {}
    for action, h, p in reversed(by_length(rules)):
        by_host.setdefault(h, []).append((p, action))

    @F.arrow_udf(T.StructType([T.StructField("rule", T.StringType()), T.StructField("verdict", T.StringType())]))
    def judge(hosts: pa.Array, paths: pa.Array) -> pa.Array:
        out = []
        for host, path in zip(hosts.to_pylist(), paths.to_pylist()):
            best, domain = None, host
            while domain is not None:
                hit = next(((domain + p, action) for p, action in by_host.get(domain, ()) if path.startswith(p)), None)
                if hit and (best is None or len(hit[0]) > len(best[0])):
                    best = hit
                domain = domain.split(".", 1)[1] if "." in domain else None
            out.append({"rule": best[0], "verdict": best[1]} if best else {"rule": None, "verdict": None})
        return pa.array(out, pa.struct([("rule", pa.string()), ("verdict", pa.string())]))

    return judge


def shape(path: Column) -> Column:
    return F.regexp_replace(path, r"[0-9]+", "#")


def template_tree(pages: DataFrame, scratch: Scratch, depth: int = 4, min_share: float = 0.05, z: float = 1.96, min_labels: int = 5) -> DataFrame:
    """(host, shaped) -> template, labelled, blocked. `pages` has host, shaped, label; from `depth` on only nodes that a verdict can depend on are split.

    Each level is written: a level's plan reads the one before it three times, which would otherwise triple with every level.
    """
    tree = pages.groupBy("host", "shaped").agg(F.count(F.lit(1)).alias("n"), F.count("label").alias("l"), F.coalesce(F.sum("label"), F.lit(0)).cast("long").alias("b"))
    tree = tree.withColumn("segs", F.split("shaped", "/", -1)).withColumn("template", F.lit(""))
    for d in count(1):
        seg = F.get("segs", F.lit(d))
        sums = lambda *k: (F.sum("n").alias(f"n{len(k)}"), F.sum("l").alias(f"l{len(k)}"), F.sum("b").alias(f"b{len(k)}"))
        tree = tree.withColumn("seg", seg)
        node = tree.groupBy("host", "template").agg(F.sum("n").alias("nn"), F.sum("l").alias("ln"), F.sum("b").alias("bn"), F.count(F.lit(1)).alias("shapes"))
        if d > depth:
            node = node.where((F.col("ln") >= min_labels) & (F.col("shapes") > 1))
        child = tree.where(F.col("seg").isNotNull()).groupBy("host", "template", "seg").agg(F.sum("n").alias("nc"), F.sum("l").alias("lc"), F.sum("b").alias("bc"))
        rest_l, rest_b, pool = F.col("ln") - F.col("lc"), F.col("bn") - F.col("bc"), F.col("bn") / F.col("ln")
        spread = F.sqrt(pool * (1 - pool) * (1 / F.col("lc") + 1 / rest_l))
        alike = (F.col("lc") >= min_labels) & (rest_l >= min_labels) & (F.abs(F.col("bc") / F.col("lc") - rest_b / rest_l) <= z * spread)
        judged = child.join(node, ["host", "template"]).select(
            "host", "template", "seg", F.when(((F.col("nc") < min_share * F.col("nn")) & (F.col("lc") < min_labels)) | F.coalesce(F.when((F.col("lc") > 0) & (rest_l > 0), alike), F.lit(False)), "*").otherwise(F.col("seg")).alias("to"))
        if d > depth:
            judged = scratch.save(judged, f"judged{d}")
            if judged.isEmpty():
                break
        tree = tree.join(judged, ["host", "template", "seg"], "left").withColumn(
            "template", F.when(F.col("to").isNull(), F.col("template")).otherwise(F.concat("template", F.lit("/"), "to"))).drop("to", "seg")
        tree = scratch.save(tree, f"level{d}")
    whole = F.size("segs") <= F.size(F.split("template", "/", -1))
    tree = tree.withColumn("template", F.when(whole, F.col("template")).otherwise(F.concat("template", F.lit("/**"))))
    sums = tree.groupBy("host", "template").agg(F.sum("l").alias("labelled"), F.sum("b").alias("blocked"))
    return tree.select("host", "shaped", "template").join(sums, ["host", "template"])


def judge_urls(pages: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES, label: Column | None = None, min_purity: float = 0.5,
               min_labels: int = 5, prior_weight: float = 4.0, scratch: Scratch | None = None) -> DataFrame:
    """`pages` with host, path, rule, template, purity, verdict."""
    scratch = scratch or Scratch(pages.sparkSession, "urls")
    host, path = host_and_path(F.col("url"))
    rows = pages.select(boxed(pages), host.alias("host"), path.alias("path"), (F.lit(None).cast("int") if label is None else label).alias("given"))
    rule, verdict = match_rules(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("rule", rule).withColumn("by_rule", verdict).withColumn("shaped", shape(F.col("path")))
    rows = rows.withColumn("label", F.coalesce("given", F.when(F.col("by_rule") == "block", 1).when(F.col("by_rule") == "allow", 0)))
    tree = scratch.save(template_tree(rows.select("host", "shaped", "label"), scratch, min_labels=min_labels), "tree")
    per = tree.select("host", "template", "labelled", "blocked").distinct()
    base = per.agg((F.coalesce(F.sum("blocked"), F.lit(0)) / F.greatest(F.coalesce(F.sum("labelled"), F.lit(0)), F.lit(1))).alias("base"))
    known = tree.crossJoin(F.broadcast(base)).select(  # one row
        "host", "shaped", "template", "labelled", ((F.col("blocked") + prior_weight * F.col("base")) / (F.col("labelled") + prior_weight)).alias("purity"))
    out = rows.join(known, ["host", "shaped"])
    bad = (F.col("labelled") >= min_labels) & (F.col("purity") >= min_purity)
    verdict = F.coalesce("by_rule", F.when(bad, "block").otherwise("allow"))
    return unboxed(pages, out, **{c: F.col(c) for c in ("host", "path", "rule", "template", "purity")}, verdict=verdict)


def oracle(rules: tuple[tuple[str, str, str], ...] = RULES, depth: int = 4, min_share: float = 0.05, z: float = 1.96, min_labels: int = 5, min_purity: float = 0.5, prior: float = 4.0) -> str:
    """The same as SQL over `pages`, levels unrolled."""
    fits = [(f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')", h + p, action) for action, h, p in reversed(by_length(rules))]
    case = lambda k: "CASE " + " ".join(f"WHEN {f[0]} THEN '{f[k]}'" for f in fits) + " END"
    out = f"""WITH u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
v AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), '{UPPER}', '{LOWER}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
w AS (SELECT *, {case(1)} AS rule, {case(2)} AS by_rule, regexp_replace(path, '[0-9]+', '#', 'g') AS shaped FROM v),
t0 AS (SELECT host, shaped, count(*) AS n, count(by_rule) AS l, count(*) FILTER (by_rule = 'block') AS b, string_split(shaped, '/') AS segs, '' AS template FROM w GROUP BY host, shaped)"""
    for d in range(1, SQL_LEVELS + 1):
        deep = f"HAVING sum(l) >= {min_labels} AND count(*) > 1" if d > depth else ""
        out += f""",
n{d} AS (SELECT host, template, sum(n) AS nn, sum(l) AS ln, sum(b) AS bn FROM t{d - 1} GROUP BY host, template {deep}),
c{d} AS (SELECT host, template, segs[{d + 1}] AS seg, sum(n) AS nc, sum(l) AS lc, sum(b) AS bc FROM t{d - 1} WHERE segs[{d + 1}] IS NOT NULL GROUP BY ALL),
j{d} AS (SELECT host, template, seg, CASE WHEN (nc < {min_share}::DOUBLE * nn AND lc < {min_labels}) OR CASE WHEN lc >= {min_labels} AND ln - lc >= {min_labels}
    THEN abs(CAST(bc AS DOUBLE) / lc - CAST(bn - bc AS DOUBLE) / (ln - lc)) <= {z}::DOUBLE * sqrt(CAST(bn AS DOUBLE) / ln * (1 - CAST(bn AS DOUBLE) / ln) * (1::DOUBLE / lc + 1::DOUBLE / (ln - lc))) ELSE false END THEN '*' ELSE seg END AS seg_to
  FROM c{d} JOIN n{d} USING (host, template)),
t{d} AS (SELECT t.host, t.shaped, t.n, t.l, t.b, t.segs, CASE WHEN j.seg_to IS NULL THEN t.template ELSE t.template || '/' || j.seg_to END AS template
  FROM t{d - 1} t LEFT JOIN j{d} j ON t.host = j.host AND t.template = j.template AND t.segs[{d + 1}] = j.seg)"""
    return out + f""",
f AS (SELECT host, shaped, l, b, CASE WHEN len(segs) <= len(string_split(template, '/')) THEN template ELSE template || '/**' END AS template FROM t{SQL_LEVELS}),
s AS (SELECT host, template, sum(l) AS labelled, sum(b) AS blocked FROM f GROUP BY host, template),
a AS (SELECT CAST(coalesce(sum(blocked), 0) AS DOUBLE) / greatest(coalesce(sum(labelled), 0), 1) AS base FROM s)
SELECT page_id, host, path, rule, coalesce(by_rule, CASE WHEN labelled >= {min_labels} AND (blocked + {prior}::DOUBLE * base) / (labelled + {prior}::DOUBLE) >= {min_purity}::DOUBLE THEN 'block' ELSE 'allow' END) AS verdict,
  template, (blocked + {prior}::DOUBLE * base) / (labelled + {prior}::DOUBLE) AS purity FROM w JOIN f USING (host, shaped) JOIN s USING (host, template), a"""
