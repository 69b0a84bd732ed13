"""URL verdicts: hand-written host and path rules, else a path-template tree per host.

The tree is grown level by level with grouped aggregates. A segment below a (host, template) node
becomes a wildcard of its shape (number, hex, word with extension, other) where the segments of that
shape vary: where the entropy of their distribution is a large part of the most that their number
allows. The node's own entropy decides where it has support; elsewhere the entropy of that template's
segments under all hosts. Then, at every level from the last to the first, sibling branches with like
continuations are merged if their labelled purity does not differ significantly from that of their
siblings without themselves; a branch without labels is no evidence and joins only siblings that agree
among themselves. A template is rejected when its smoothed labelled purity is below the least; the
smoothing shrinks towards the same template under all hosts of the domain ending, under all hosts, and
the prior. Labels are URLs that the rules decide (allow 1, block 0) or a table.

DataFrame functions only. Segments beyond ``depth`` are written by their shapes.

Defined cases: a null url or one without ``://`` has empty host and path, no rule and the prior's
verdict; an empty path fits no rule; repeated rows are judged each; ties of purity with the least are
allowed; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.llm.common import LOWER, UPPER, ascii_lower, table
from spreadlab.storage import materialize

RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))
SALTS = 32
SUPPORT = 12  # distinct paths below a node from which its own entropy decides
VARIED = 0.6  # share of the largest possible entropy


def host_of(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, ascii_lower(F.regexp_extract(url, r"(?s)\A.*?://([^/?#]*)", 1))).otherwise(F.lit(""))


def path_of(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)\A.*?://[^/?#]*([^?#]*)", 1)).otherwise(F.lit(""))


def fitting_rule(host: Column, path: Column, rules: tuple[tuple[str, str], ...]) -> Column:
    """struct(verdict, rule) of the longest rule that fits, else null."""
    out = F.lit(None).cast("struct<verdict:string,rule:string>")
    for verdict, rule in sorted(rules, key=lambda r: len(r[1])):
        name, slash, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        out = F.when(fits, F.struct(F.lit(verdict).alias("verdict"), F.lit(rule).alias("rule"))).otherwise(out)
    return out


def shape(segment: Column) -> Column:
    """Wildcard that a variable segment becomes."""
    return (
        F.when(segment.rlike(r"\A[0-9]+\z"), "{number}")
        .when(segment.rlike(r"\A[0-9]+\.[A-Za-z0-9]+\z"), F.concat(F.lit("{number}."), F.regexp_extract(segment, r"\.([A-Za-z0-9]+)\z", 1)))
        .when(segment.rlike(r"\A[0-9a-fA-F-]{8,}\z"), "{hex}")
        .when(segment.rlike(r"\.[A-Za-z0-9]{1,5}\z"), F.concat(F.lit("{name}."), F.regexp_extract(segment, r"\.([A-Za-z0-9]{1,5})\z", 1)))
        .when(segment == "", "")
        .otherwise("{text}")
    )


def varied(counts: DataFrame, *node: str) -> DataFrame:
    """counts(node.., segment, c) -> (node.., varies) of the nodes with support: entropy against the log of the number of paths."""
    n = F.sum("c")
    entropy = F.log(n) - F.sum(F.col("c") * F.log("c")) / n
    return counts.groupBy(*node).agg(n.alias("paths"), (entropy >= VARIED * F.log(n)).alias("varies")).filter(F.col("paths") >= SUPPORT).drop("paths")


def template_tree(urls: DataFrame, depth: int = 6) -> DataFrame:
    """urls(host, path, n, good, bad), one row per distinct host and path -> + template.

    Level by level: measure how the segments below a node vary, then choose text or wildcard for each.
    """
    parts = F.split(F.expr("substr(path, 2)"), "/", -1)
    rows = urls.withColumn("parts", F.when(F.col("path") == "", F.array().cast("array<string>")).otherwise(parts)).withColumn("template", F.lit(""))
    salted = lambda nodes: nodes.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    for level in range(depth):
        rows = rows.withColumn("segment", F.get("parts", F.lit(level))).withColumn("kind", shape(F.col("segment"))).withColumn("salt", F.pmod(F.xxhash64("path"), F.lit(SALTS)).cast("int"))
        counts = rows.filter("segment IS NOT NULL").groupBy("host", "template", "kind", "segment").agg(F.count(F.lit(1)).alias("c"))
        # nodes with support are few against the paths below them; they are repeated over salts for hot hosts
        own = salted(varied(counts, "host", "template", "kind").select(F.col("host").alias("h"), F.col("template").alias("t"), F.col("kind").alias("k"), F.col("varies").alias("own_varies"))).withColumnRenamed("s", "own_salt")
        pooled = counts.groupBy("template", "kind", "segment").agg(F.sum("c").alias("c"))
        every = salted(varied(pooled, "template", "kind").select(F.col("template").alias("at"), F.col("kind").alias("ak"), F.col("varies").alias("all_vary")))
        met = rows.join(own, (F.col("host") == F.col("h")) & (F.col("template") == F.col("t")) & (F.col("kind") == F.col("k")) & (F.col("salt") == F.col("own_salt")), "left")
        met = met.join(every, (F.col("template") == F.col("at")) & (F.col("kind") == F.col("ak")) & (F.col("salt") == F.col("s")), "left")
        step = F.when(F.coalesce("own_varies", "all_vary", F.lit(False)), F.col("kind")).otherwise(F.col("segment"))
        rows = met.withColumn("template", F.when(F.col("segment").isNull(), F.col("template")).otherwise(F.concat("template", F.lit("/"), step))).select("host", "path", "n", "good", "bad", "parts", "template")
        if level % 2 == 1:
            rows = materialize(rows, "url-tree")
    tail = F.concat_ws("/", F.transform(F.slice("parts", depth + 1, 1 << 20), shape))
    return rows.withColumn("template", F.when(F.size("parts") > depth, F.concat_ws("/", "template", tail)).otherwise(F.col("template"))).drop("parts")


def merge_branches(templates: DataFrame, depth: int = 6, z: float = 1.96) -> DataFrame:
    """templates(host, template, n, good, bad) -> + merged: at every level siblings that agree share the name ``{branch}`` there."""
    rows = templates.withColumn("merged", F.col("template"))
    for level in range(depth, 0, -1):
        parts = F.split("merged", "/", -1)
        here = F.get(parts, F.lit(level))
        literal = here.isNotNull() & (here != "") & ~here.startswith("{")
        look = F.concat_ws("/", F.slice(parts, 1, level), F.lit("{branch}"), F.slice(parts, level + 2, 1 << 20))
        rows = rows.withColumn("look", F.when(literal, look).otherwise(F.concat(F.lit("="), "merged")))
        # one row a branch first: earlier merges may have given several templates one name
        own = rows.groupBy("host", "look", "merged").agg(F.sum("good").alias("g"), F.sum("bad").alias("b"))
        seen = F.col("g") + F.col("b")
        pools = own.groupBy("host", "look").agg(F.sum("g").alias("pool_g"), F.sum("b").alias("pool_b"), F.sum(F.when(seen > 0, F.col("g") * F.col("g") / seen)).alias("squares"), F.count(F.when(seen > 0, 1)).alias("told"), F.count(F.lit(1)).alias("branches"))
        met = own.join(pools, ["host", "look"]).filter("branches > 1")
        others = F.col("pool_g") + F.col("pool_b") - seen
        rate = lambda g, n: (g + 0.5) / (n + 1)
        mine, theirs, both = rate(F.col("g"), seen), rate(F.col("pool_g") - F.col("g"), others), rate(F.col("pool_g"), F.col("pool_g") + F.col("pool_b"))
        error = F.sqrt(both * (1 - both) * (1 / (seen + 1) + 1 / (others + 1)))
        alike = F.abs(mine - theirs) <= z * error
        # siblings agree: the spread of their rates is what chance gives (chi-square against its mean plus z deviations)
        freedom = F.greatest(F.col("told") - 1, F.lit(0))
        chi = (F.col("squares") - F.col("pool_g") * F.col("pool_g") / (F.col("pool_g") + F.col("pool_b"))) / (both * (1 - both))
        agree = chi <= freedom + z * F.sqrt(2 * freedom)
        joins = F.when(others == 0, F.lit(False)).when(seen == 0, agree).otherwise(alike)
        named = met.filter(joins).select(F.col("host").alias("h"), F.col("merged").alias("m"), F.col("look").alias("name"))
        rows = rows.drop("look").join(named, (F.col("host") == F.col("h")) & (F.col("merged") == F.col("m")), "left").withColumn("merged", F.coalesce("name", "merged")).drop("h", "m", "name")
        if level % 2 == 1:
            rows = materialize(rows, "url-merge")
    return rows


def judge_urls(urls: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, least: float = 0.5, prior: float = 0.5, weight: float = 4.0, id_col: str = "page_id", url_col: str = "url", labels: DataFrame | None = None, hidden: Column | None = None) -> DataFrame:
    """(id, host, path, rule, verdict, template, purity, decided_by) of every url.

    labels(url, good) adds labelled urls to those that the rules decide; ``hidden``, a condition on host and
    path, keeps rule-decided urls out of the labels, so that the method can be held against the rules.
    decided_by is rule, or the nearest level that has labels of the template: host, ending, all, prior.
    """
    host, path = host_of(F.col(url_col).cast("string")), path_of(F.col(url_col).cast("string"))
    rows = urls.select(F.col(id_col).alias("id"), host.alias("host"), path.alias("path"))
    fit = fitting_rule(F.col("host"), F.col("path"), rules)
    told_by = F.when(~hidden, F.col("fit.verdict")) if hidden is not None else F.col("fit.verdict")
    distinct = rows.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n")).withColumn("fit", fit)
    distinct = distinct.withColumn("good", F.coalesce((told_by == "allow").cast("long"), F.lit(0))).withColumn("bad", F.coalesce((told_by == "block").cast("long"), F.lit(0)))
    if labels is not None:
        told = labels.select(host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), F.col("good").cast("long").alias("is_good")).groupBy("host", "path").agg(F.sum("is_good").alias("more_good"), F.sum(1 - F.col("is_good")).alias("more_bad"))
        distinct = distinct.join(told, ["host", "path"], "left").withColumn("good", F.col("good") + F.coalesce("more_good", F.lit(0))).withColumn("bad", F.col("bad") + F.coalesce("more_bad", F.lit(0))).drop("more_good", "more_bad")
    tree = materialize(template_tree(distinct.drop("fit")), "url-templates")
    templates = materialize(tree.groupBy("host", "template").agg(F.sum("n").alias("n"), F.sum("good").alias("good"), F.sum("bad").alias("bad")), "url-counts")
    merged = materialize(merge_branches(templates), "url-merged")
    ending = F.regexp_extract("host", r"([^.]*)\z", 1)
    own = merged.groupBy("host", "merged").agg(F.sum("good").alias("g0"), F.sum("bad").alias("b0"))
    # shrink towards the literal template under the host's ending, then under all hosts, then the prior
    wide = merged.withColumn("ending", ending).groupBy("ending", "template").agg(F.sum("good").alias("g1"), F.sum("bad").alias("b1"))
    most = merged.groupBy("template").agg(F.sum("good").alias("g2"), F.sum("bad").alias("b2"))
    shrunk = lambda g, b, towards: (F.col(g) + weight * towards) / (F.col(g) + F.col(b) + weight)
    scored = merged.select("host", "template", "merged", ending.alias("ending")).join(own, ["host", "merged"]).join(wide, ["ending", "template"]).join(most, ["template"])
    purity = reduce(lambda towards, c: shrunk(*c, towards), (("g2", "b2"), ("g1", "b1"), ("g0", "b0")), F.lit(prior))
    level = F.when(F.col("g0") + F.col("b0") > 0, "host").when(F.col("g1") + F.col("b1") > 0, "ending").when(F.col("g2") + F.col("b2") > 0, "all").otherwise("prior")
    scored = materialize(scored.select("host", "template", purity.alias("purity"), level.alias("level")), "url-purity")
    # verdict per distinct path, then per page; both joins meet hot hosts with the path in the key or salted
    spread = scored.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    paths = tree.select("host", "path", "template").withColumn("salt", F.pmod(F.xxhash64("path"), F.lit(SALTS)).cast("int")).join(spread, ["host", "template", "salt"])
    paths = materialize(paths.select(F.col("host").alias("h"), F.col("path").alias("p"), "template", "purity", "level"), "url-paths")
    judged = rows.join(paths, (F.col("host") == F.col("h")) & (F.col("path") == F.col("p"))).withColumn("fit", fit)
    if hidden is not None:
        judged = judged.withColumn("fit", F.when(~hidden, F.col("fit")))
    verdict = F.coalesce(F.col("fit.verdict"), F.when(F.col("purity") >= least, "allow").otherwise("block"))
    decided_by = F.when(F.col("fit.rule").isNotNull(), "rule").otherwise(F.col("level"))
    return judged.select("id", "host", "path", F.col("fit.rule").alias("rule"), verdict.alias("verdict"), "template", F.round("purity", 9).alias("purity"), decided_by.alias("decided_by"))


def held_out_agreement(urls: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, one_in: int = 5, **options) -> DataFrame:
    """(judged, agree): rule-decided urls hidden from the method, and those that it judges as the rules do."""
    hidden = F.pmod(F.xxhash64("host", "path"), F.lit(one_in)) == 0
    judged = judge_urls(urls, rules, hidden=hidden, **options)
    rule = fitting_rule(F.col("host"), F.col("path"), rules)
    return judged.withColumn("truth", rule["verdict"]).filter(hidden & F.col("truth").isNotNull()).agg(F.count(F.lit(1)).alias("judged"), F.count(F.when(F.col("truth") == F.col("verdict"), 1)).alias("agree"))


def url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, host, path, rule, rule_verdict): what the rules alone say."""
    fit = fitting_rule(F.col("host"), F.col("path"), RULES)
    parts = table(spark, sf_dir, "pages").select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    return parts.select("page_id", "host", "path", fit["rule"].alias("rule"), fit["verdict"].alias("rule_verdict"))


def op3_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = judge_urls(table(spark, sf_dir, "pages").select("page_id", "url"))
    return judged.withColumnRenamed("id", "page_id")


QUERIES = {"op3_url_templates": op3_url_templates, "url_rules": url_rules}
ORACLES = {
    "url_rules": f"""
        WITH u AS (SELECT page_id, instr(url, '://') > 0 AS whole, substr(url, instr(url, '://') + 3) AS rest FROM pages),
        p AS (SELECT page_id, CASE WHEN whole THEN translate(regexp_extract(rest, '^[^/?#]*', 0, 's'), '{UPPER}', '{LOWER}') ELSE '' END AS host,
                     CASE WHEN whole THEN regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's') ELSE '' END AS path FROM u),
        r(rule_verdict, rule) AS (VALUES {", ".join(f"('{verdict}', '{rule}')" for verdict, rule in RULES)}),
        f AS (SELECT page_id, arg_max(rule, length(rule)) AS rule, arg_max(rule_verdict, length(rule)) AS rule_verdict
              FROM p JOIN r ON (host = split_part(rule, '/', 1) OR ends_with(host, '.' || split_part(rule, '/', 1))) AND starts_with(path, substr(rule, instr(rule, '/'))) GROUP BY 1)
        SELECT page_id, host, path, rule, rule_verdict FROM p LEFT JOIN f USING (page_id)""",
}
