"""URL filtering by a tree of path templates per host, in DataFrame operations only.

Runs of digits in a path become ``#``.  Then, level by level below each host and prefix, a branch is compared
with all its siblings together: if neither its labels nor the kinds of its next segments differ significantly
(chi-square), it merges with the other such branches into the wildcard ``*``.  What differs stays a branch of
its own.  Levels go on to the deepest segment.  A template is rejected if its labelled share of
bad urls, smoothed by the overall share, reaches ``threshold``.  Explicit rules come before templates.

Levels work on counts of distinct generalised paths, so a hot host is aggregated before anything is joined.

Labels come with the urls (id, bad), or are weak ones: what an explicit rule says of a url, else bad where its
host holds a word of a short list (as a whole, between dots and hyphens), else none.

Defined cases: a null url, or one without ``://``, has an empty host and path and takes part as such; urls
without labels count for the tree alone; a host without labels has the overall share; without any label
nothing is rejected; repeated urls count as often as they occur; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Fixed rules of the contract: (verdict, host, path).
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
#: Fixed words of hosts whose urls are weakly labelled bad.
BAD_WORDS = ("ads", "adult", "bet", "bets", "betting", "casino", "gambling", "payday", "pills", "poker", "porn", "spam", "viagra", "warez", "xxx")
#: Levels that the SQL form writes out; the operator has no such bound.
SQL_LEVELS = 6
LABELS_DIFFER, KINDS_DIFFER = 6.63, 9.21
PRIOR_WEIGHT = 5.0
THRESHOLD = 0.5
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def with_parts(urls: DataFrame, url: str = "url") -> DataFrame:
    """The rows with host and path: after the first ``://``, cut at the first of / ? #, and at ? or #."""
    # cutting by places and single characters, not by one pattern, keeps line breaks in a url ordinary characters
    after = F.expr(f"CASE WHEN locate('://', `{url}`) > 0 THEN substr(`{url}`, locate('://', `{url}`) + 3) ELSE '' END")
    kept = [F.col(c) for c in urls.columns if c not in ("host", "path")]
    cut = urls.withColumn("__rest", F.coalesce(after, F.lit(""))).withColumn("__host", F.regexp_extract("__rest", "^([^/?#]*)", 1))
    return cut.select(*kept, F.translate("__host", UPPER, LOWER).alias("host"), F.regexp_extract(F.expr("substr(__rest, length(__host) + 1)"), "^([^?#]*)", 1).alias("path"))


def rule_for(host: str = "host", path: str = "path", rules=RULES) -> tuple[F.Column, F.Column]:
    """(rule, verdict) of the longest fitting rule; null without one."""
    rule = verdict = None
    for kind, h, p in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[1] + r[2])):
        fits = ((F.col(host) == h) | F.col(host).endswith("." + h)) & F.col(path).startswith(p)
        rule = F.when(fits, h + p) if rule is None else rule.when(fits, h + p)
        verdict = F.when(fits, kind) if verdict is None else verdict.when(fits, kind)
    return (rule, verdict) if rules else (F.lit(None).cast("string"), F.lit(None).cast("string"))


def weak_labels(host: str = "host", said: str = "__said", words=BAD_WORDS) -> F.Column:
    """true, false or null: the rule's verdict, else whether the host holds a listed word."""
    listed = F.arrays_overlap(F.split(host, "[.-]"), F.array(*(F.lit(w) for w in words))) if words else F.lit(False)
    return F.when(F.col(said) == "block", True).when(F.col(said) == "allow", False).when(listed, True)


def chi_square(own: list[str], rest: list[str]) -> str:
    """SQL for the chi-square statistic of two rows of counts."""
    a, b = f"({' + '.join(own)})", f"({' + '.join(rest)})"
    cells = [f"if({x} + {y} = 0, 0D, pow({x} * {b} - {y} * {a}, 2) / ({x} + {y}))" for x, y in zip(own, rest)]
    return f"if({a} = 0 OR {b} = 0, 0D, ({' + '.join(cells)}) / (cast({a} as double) * {b}))"


def learn(urls: DataFrame, prior_weight: float = PRIOR_WEIGHT, threshold: float = THRESHOLD) -> DataFrame:
    """Templates of rows (host, path, bad: true, false or null): host, shape, template, n, labelled, bad, purity, rejected."""
    shaped = urls.select("host", F.regexp_replace("path", "[0-9]+", "#").alias("shape"), "bad")
    nodes = shaped.groupBy("host", "shape").agg(F.count("*").cast("double").alias("n"), F.count("bad").cast("double").alias("labelled"), F.sum(F.col("bad").cast("int")).cast("double").alias("bad"))
    nodes = nodes.select("host", "shape", "n", "labelled", F.coalesce("bad", F.lit(0.0)).alias("bad"), F.split("shape", "/").alias("segs"), F.lit("").alias("template"))
    nodes, done, d = common.staged(nodes, "url-nodes"), [], 1
    sums = ["n", "labelled", "bad", "ends", "numbers", "words"]
    while True:
        # a template is done where no path goes deeper, or where one shape is left, which would have no siblings
        groups = nodes.groupBy("host", "template").agg(F.expr(f"count(*) = 1 OR max(size(segs)) <= {d}").alias("done"))
        met = common.staged(nodes.join(groups, ["host", "template"]), "url-groups")
        done.append(met.where("done").withColumn("template", F.expr(f"if(size(segs) > {d}, concat(template, '/', array_join(slice(segs, {d + 1}, size(segs)), '/')), template)")).drop("done"))
        nodes = met.where("NOT done").drop("done")
        if nodes.isEmpty():
            break
        d += 1  # the first segment is what stands before the first slash
        seg, after = f"coalesce(get(segs, {d - 1}), '')", f"get(segs, {d})"
        here = nodes.withColumn("seg", F.expr(seg)).withColumn("ends", F.expr(f"if({after} IS NULL, n, 0D)")).withColumn("numbers", F.expr(f"if(contains({after}, '#'), n, 0D)"))
        here = here.withColumn("words", F.expr("n - ends - coalesce(numbers, 0D)")).withColumn("numbers", F.expr("coalesce(numbers, 0D)"))
        branches = here.groupBy("host", "template", "seg").agg(*(F.sum(c).alias(c) for c in sums))
        parents = branches.groupBy("host", "template").agg(F.count("*").alias("width"), *(F.sum(c).alias(f"all_{c}") for c in sums))
        both = branches.join(parents, ["host", "template"])
        labels = chi_square(["bad", "(labelled - bad)"], ["(all_bad - bad)", "(all_labelled - labelled - all_bad + bad)"])
        kinds = chi_square(["ends", "numbers", "words"], ["(all_ends - ends)", "(all_numbers - numbers)", "(all_words - words)"])
        stays = f"seg = '' OR contains(seg, '#') OR width = 1 OR {labels} >= {LABELS_DIFFER} OR {kinds} >= {KINDS_DIFFER}"
        choice = both.select("host", "template", "seg", F.expr(f"if({stays}, seg, '*')").alias("out"))
        nodes = here.join(choice, ["host", "template", "seg"]).select("host", "shape", "n", "labelled", "bad", "segs", F.expr(f"if(size(segs) >= {d}, concat(template, '/', out), template)").alias("template"))
        nodes = common.staged(nodes, "url-nodes")  # each level reads its nodes three times
    nodes = done[0]
    for part in done[1:]:
        nodes = nodes.unionByName(part)
    totals = nodes.groupBy("host", "template").agg(F.sum("n").alias("t_n"), F.sum("labelled").alias("t_labelled"), F.sum("bad").alias("t_bad"))
    share = nodes.agg(F.sum("bad").alias("b"), F.sum("labelled").alias("l")).select(F.expr("if(coalesce(l, 0D) > 0, b / l, 0D)").alias("share"))
    judged = totals.crossJoin(F.broadcast(share)).withColumn("purity", F.expr(f"(t_bad + {prior_weight}D * share) / (t_labelled + {prior_weight}D)"))
    judged = judged.select("host", "template", "purity", F.expr(f"t_labelled > 0 AND purity >= {threshold}D").alias("rejected"))
    return nodes.drop("segs").join(judged, ["host", "template"])


def judge(urls: DataFrame, rules=RULES, labels: DataFrame | None = None, url: str = "url", id_col: str = "page_id", **options) -> DataFrame:
    """All rows with host, path, rule, template, verdict; without labels (id, bad) the weak ones teach the tree."""
    parts = with_parts(urls, url)
    rule, said = rule_for(rules=rules)
    kept = [c for c in parts.columns if c not in ("rule", "verdict", "template")]
    marked = parts.select(*kept, rule.alias("rule"), said.alias("__said"))
    if labels is None:
        taught = marked.select("host", "path", weak_labels().alias("bad"))
    else:
        known = labels.groupBy(F.col(id_col).alias("__id")).agg(F.max("bad").alias("bad"))
        taught = marked.join(known, F.col(id_col) == F.col("__id"), "left").select("host", "path", "bad")
    learnt = learn(taught, **options).select("host", F.col("shape").alias("__shape"), "template", "rejected")
    marked = marked.withColumn("__shape", F.regexp_replace("path", "[0-9]+", "#"))
    met = marked.join(learnt, ["host", "__shape"], "left")
    verdict = F.coalesce("__said", F.when(F.col("rejected"), "block").otherwise("allow"))
    return met.select(*kept, "rule", "template", verdict.alias("verdict"))


def op5_url_templates(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge(pages).select("page_id", "host", "path", "rule", "verdict")
