"""URL filters: fixed rules first, then a path-template tree learned per host.

A rule is a host suffix with a path prefix; the longest that fits decides. The tree is for the rest. Each host's paths are split into
segments, whose variable parts (digits, long hexadecimal) are wildcards from the start; pages of a host with the same shape are one row
of the tree from there on. Level by level a node's children become one wildcard when nearly as many are distinct as are visited, and
children that are statistically like their siblings are merged: the kinds of segments below a child must fit the pooled
distribution (a chi-square test), and so must its blocked share where it has labels. A child without labels is merged by its structure
alone, and shares the merged template's verdict: a template is rejected when the share of blocked pages among its labelled ones,
smoothed towards the share over all labelled pages, reaches the threshold. Labels are the rules' own verdicts unless a
table of labelled URLs is given. A template without any label is never rejected.

Every level is one aggregation by (host, branch, segment) over distinct shapes; nothing is collected, and a host with a third of all
pages costs one row per distinct shape. Verdicts go back to the pages by a salted join, so that no task holds a host.

Defined results: a null URL, or one without ``://``, has an empty host and path, no rule and the verdict allow; repeated rows come back as
often as they occur; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.shared_dir import staged

Rule = tuple[str, str, str]  # verdict, host suffix, path prefix
# The contract's rules.
RULES: tuple[Rule, ...] = (("allow", "com", "/"), ("block", "example.com", "/en/"), ("allow", "www.example.com", "/en/"), ("block", "net", "/es/"), ("block", "net", "/fr/"))
PRIOR_WEIGHT, REJECT_AT = 4.0, 0.8
#: A node's children are values when it has this many and they are at least this share of its visits.
MANY_CHILDREN, DISTINCT_SHARE, SIMILAR_Z = 8, 0.5, 2.0
#: Copies of a verdict, one for each share of the pages it goes to.
SALT = 16
MERGED = "**"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def _decide(rules: tuple[Rule, ...], give) -> Column:
    """The longest fitting rule's value: an ordered chain, longest first."""
    chain = None
    for verdict, host, path in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r)):
        fits = ((F.col("host") == host) | F.col("host").endswith(f".{host}")) & F.col("path").startswith(path)
        value = F.lit(give(verdict, host, path))
        chain = F.when(fits, value) if chain is None else chain.when(fits, value)
    return F.lit(None).cast("string") if chain is None else chain


def shape_of(segment: Column) -> Column:
    """A segment without its variable part: digits and long hexadecimal become a wildcard, a file ending stays."""
    ending = F.regexp_extract(segment, r"(\.[A-Za-z]{1,5})$", 1)
    stem = F.regexp_replace(segment, r"\.[A-Za-z]{1,5}$", "")
    value = stem.rlike(r"^[0-9]+$") | stem.rlike(r"^[0-9A-Fa-f-]{8,}$") | stem.rlike(r"[0-9]{4,}")
    return F.when(value, F.concat(F.lit("*"), ending)).otherwise(segment)


def shapes_of(path: Column) -> Column:
    """A path's segments without their variable parts."""
    return F.transform(F.filter(F.split(path, "/"), lambda x: x != ""), shape_of)


#: What may stand below a branch: nothing, a value, a word, and either with a file ending.
_BELOW = ("end", "value", "value file", "word", "word file")


def _below(shape: Column, level: int) -> Column:
    nxt = F.get(shape, F.lit(level + 1))
    value, file = nxt.startswith("*"), nxt.rlike(r"\.[A-Za-z]{1,5}$")
    return F.when(nxt.isNull(), F.lit(0)).when(value, F.when(file, 2).otherwise(1)).otherwise(F.when(file, 4).otherwise(3))


def template_tree(shapes: DataFrame) -> DataFrame:
    """Adds ``template`` to a staged table (host, shape, n, m, b): pages, labelled ones and blocked ones of each distinct shape.

    A level for each segment, as long as some node with two shapes or more has paths that go on; one shape alone has no siblings.
    """
    rows = shapes.withColumn("template", F.lit(""))
    level, node = 0, ["host", "template"]
    while True:
        segment = F.get("shape", F.lit(level))
        below = [F.sum(F.when(_below(F.col("shape"), level) == k, F.col("n")).otherwise(0)).alias(f"c{k}") for k in range(len(_BELOW))]
        children = rows.groupBy(*node, segment.alias("_segment")).agg(F.count("*").alias("shapes"), F.sum("n").alias("n"), F.sum("m").alias("m"), F.sum("b").alias("b"), *below)
        on = lambda c: F.sum(F.when(F.col("_segment").isNotNull(), F.col(c))).alias(f"all_{c}")  # noqa: E731  paths that go on
        whole = children.groupBy(*node).agg(F.sum("shapes").alias("all_shapes"), F.count("_segment").alias("kinds"), *[on(c) for c in ("n", "m", "b", *(f"c{k}" for k in range(len(_BELOW))))])
        joined = children.where("_segment is not null").join(whole.where("all_shapes > 1"), node)
        values = (F.col("kinds") >= MANY_CHILDREN) & (F.col("kinds") >= DISTINCT_SHARE * F.col("all_n"))
        # Like its siblings by structure: what stands below it fits the pooled shares.
        chi, kinds = F.lit(0.0), F.lit(0)
        for k in range(len(_BELOW)):
            expected = F.col("n") * F.col(f"all_c{k}") / F.col("all_n")
            chi = chi + F.when(expected > 0, (F.col(f"c{k}") - expected) ** 2 / expected).otherwise(0.0)
            kinds = kinds + (expected > 0).cast("int")
        alike = chi <= (kinds - 1) + SIMILAR_Z * F.sqrt(2.0 * (kinds - 1)) + 1e-9
        # And by labels, where it has any: its blocked share lies within the pooled share's error.
        pooled = F.col("all_b") / F.greatest(F.col("all_m"), F.lit(1))
        error = F.sqrt(F.greatest(pooled * (1 - pooled), F.lit(1e-6)) / F.greatest(F.col("m"), F.lit(1)))
        agrees = (F.col("m") == 0) | (F.abs(F.col("b") / F.greatest(F.col("m"), F.lit(1)) - pooled) <= SIMILAR_Z * error)
        branch = F.when(values & ~F.col("_segment").startswith("*"), F.lit("*")).when((F.col("kinds") > 1) & alike & agrees, F.lit(MERGED)).otherwise(F.col("_segment"))
        named = staged(joined.select(*node, "_segment", branch.alias("_branch")), "branches")
        if not named.head(1):
            return rows
        grown = rows.withColumn("_segment", segment).join(named, [*node, "_segment"], "left").drop("_segment")
        grown = grown.withColumn("template", F.when(F.col("_branch").isNull(), F.col("template")).otherwise(F.concat("template", F.lit("/"), "_branch"))).drop("_branch")
        rows = staged(grown, "templates")
        level += 1


def template_verdicts(shapes: DataFrame) -> DataFrame:
    """host, shape, template, purity and the tree's verdict for every distinct shape."""
    rows = template_tree(shapes)
    leaves = rows.groupBy("host", "template").agg(F.sum("m").alias("m"), F.sum("b").alias("b"))
    prior = leaves.agg((F.sum("b") / F.greatest(F.sum("m"), F.lit(1))).alias("prior"))  # a single row
    scored = leaves.join(F.broadcast(prior)).select("host", "template", "m", ((F.col("b") + PRIOR_WEIGHT * F.col("prior")) / (F.col("m") + PRIOR_WEIGHT)).alias("purity"))
    learned = F.when((F.col("m") > 0) & (F.col("purity") >= REJECT_AT), F.lit("block")).otherwise(F.lit("allow"))
    return rows.select("host", "shape", "template").join(scored, ["host", "template"]).select("host", "shape", "template", "purity", learned.alias("learned"))


def judge(pages: DataFrame, rules: tuple[Rule, ...] = RULES, labelled: DataFrame | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict, and the template with its smoothed purity, for every page."""
    parsed = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    parsed = parsed.withColumn("rule", _decide(rules, lambda v, h, p: h + p)).withColumn("given", _decide(rules, lambda v, h, p: v))
    if labelled is None:
        parsed = parsed.withColumn("blocked", F.col("given") == "block")
    else:
        truth = labelled.groupBy("page_id").agg(F.max("blocked").alias("blocked"))
        parsed = parsed.join(truth, "page_id", "left")
    parsed = parsed.withColumn("shape", shapes_of(F.col("path")))
    shapes = parsed.groupBy("host", "shape").agg(F.count("*").alias("n"), F.count("blocked").alias("m"), F.coalesce(F.sum(F.col("blocked").cast("int")), F.lit(0)).alias("b"))
    known = staged(template_verdicts(staged(shapes, "shapes")), "verdicts")
    known = known.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    salted = parsed.withColumn("_salt", F.pmod(F.xxhash64("path", "page_id"), F.lit(SALT)).cast("int"))
    joined = salted.join(known, ["host", "shape", "_salt"], "left")
    return joined.select("page_id", "host", "path", "rule", F.coalesce("given", "learned").alias("verdict"), "template", "purity")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"))
