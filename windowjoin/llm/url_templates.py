"""URL filter: path-template tree per host, merged branches, smoothed labelled purity.

``with_parts`` cuts host and path from a url; ``rule_for`` gives the longest listed rule
that fits. ``learn`` builds the templates, all with DataFrame operations:

* segments are typed: runs of digits, long hexadecimal strings, UUIDs and long slugs
  become ``<n>``, ``<h>``, ``<u>`` and ``<s>``;
* urls are counted per host and typed path, with the counts of allowed and blocked labels;
* level by level, from the root, the branches of a parent that are most often followed by
  the same segment are compared with all of them taken together: a branch is merged into
  ``*`` if what follows it is distributed like what follows them (overlap of the two
  distributions, with an allowance that shrinks with the root of its count), or if it is
  one rare branch of very many, and if the blocked share of its labels does not differ
  significantly; a lone branch stays;
* a template's purity is its blocked share, drawn towards its host's, which is drawn
  towards ``prior``; a template of at least ``reject`` purity is rejected.

Branches meet their parent's sums only as counts per (host, prefix, segment), so a host
with most of the urls is one row per distinct typed branch. What lies deeper than ``levels``
counts as one segment, typed and whole.

Defined cases: a null url, or one without ``://``, has empty host and path, matches no
rule and is judged by the template of the empty host; empty paths are templates too;
repeated rows are judged one by one alike; an empty table gives an empty table; other
columns are not read by the query.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import common

CAPITALS, SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
Rule = tuple[str, str, str]  # host, path, verdict


def with_parts(urls: DataFrame, url: str = "url") -> DataFrame:
    """Adds host and path."""
    at = F.coalesce(F.instr(F.col(url), "://"), F.lit(0))
    rest = F.when(at > 0, F.substring(F.col(url), at + 3, F.length(url))).otherwise("")
    host = F.regexp_extract(rest, r"\A([^/?#]*)", 1)
    tail = F.substring(rest, F.length(host) + 1, F.length(rest))
    return urls.withColumns({"host": F.translate(host, CAPITALS, SMALL), "path": F.regexp_extract(tail, r"\A([^?#]*)", 1)})


def rule_for(rules: Sequence[Rule]) -> tuple[Column, Column]:
    """The longest fitting rule and its verdict, null where none fits."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for host, path, says in sorted(rules, key=lambda r: len(r[0] + r[1])):  # longer ones are asked first
        fits = ((F.col("host") == host) | F.col("host").endswith(f".{host}")) & F.col("path").startswith(path)
        rule, verdict = F.when(fits, F.lit(host + path)).otherwise(rule), F.when(fits, F.lit(says)).otherwise(verdict)
    return rule, verdict


def typed_segments(path: str = "path", levels: int = 8) -> Column:
    """Segments with their variable parts replaced by their kind."""
    parts = F.split(F.regexp_replace(F.col(path), r"\A/", ""), "/")
    uuid = r"(?i)[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}"
    hexadecimal = r"(?i)\b(?=[0-9a-f]*[0-9])(?=[0-9a-f]*[a-f])[0-9a-f]{8,}\b"
    slug = r"[^\-_.]+(?:[\-_][^\-_.]+){3,}"

    def kind(s: Column) -> Column:
        s = F.regexp_replace(F.regexp_replace(s, uuid, "<u>"), hexadecimal, "<h>")
        return F.regexp_replace(F.regexp_replace(s, slug, "<s>"), r"[0-9]+", "<n>")

    typed = F.transform(parts, kind)
    rest = F.array_join(F.slice(typed, levels, 1 << 20), "/")
    return F.when(F.size(typed) > levels, F.concat(F.slice(typed, 1, levels - 1), F.array(rest))).otherwise(typed)


def learn(urls: DataFrame, tolerance: float = 0.05, z: float = 2.5, fan: int = 64, levels: int = 8, weight: float = 5.0, prior: float = 0.1, reject: float = 0.8) -> DataFrame:
    """(host, typed, template, purity, verdict) from ``urls`` (host, path, label allow/block/null)."""
    count = lambda what: F.sum(F.when(F.col("label") == what, 1).otherwise(0)).cast("long")
    typed = urls.select("host", typed_segments(levels=levels).alias("rest"), "label")
    tree = typed.groupBy("host", "rest").agg(F.count("*").alias("n"), count("allow").alias("a"), count("block").alias("b"))
    tree = common.written(tree.select("host", F.array_join("rest", "/").alias("typed"), F.lit("").alias("prefix"), "rest", "n", "a", "b"), "templates")
    depth = tree.agg(F.max(F.size("rest"))).first()[0] or 0
    for _ in range(depth):
        tree = common.written(_merged(tree, tolerance, z, fan), "templates")
    template = F.expr("substring(prefix, 2)")
    sums = lambda *keys: tree.withColumn("template", template).groupBy(*keys).agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    hosts = sums("host").select("host", ((F.col("b") + weight * prior) / (F.col("a") + F.col("b") + weight)).alias("of_host"))
    judged = sums("host", "template").join(hosts, "host")
    purity = (F.col("b") + weight * F.col("of_host")) / (F.col("a") + F.col("b") + weight)
    judged = judged.select("host", "template", purity.alias("purity"), F.when(purity >= reject, "block").otherwise("allow").alias("verdict"))
    return tree.select("host", "typed", template.alias("template")).join(judged, ["host", "template"])


def _merged(tree: DataFrame, tolerance: float, z: float, fan: int) -> DataFrame:
    """The tree with one more level of segments decided."""
    open_ = tree.filter(F.size("rest") > 0).withColumns({"seg": F.col("rest")[0], "next": F.coalesce(F.get("rest", F.lit(1)), F.lit("<end>"))})
    here, group = ["host", "prefix"], ["host", "prefix", "led"]
    add = lambda *names: [F.sum(c).alias(c) for c in names]
    by_next = open_.groupBy(*here, "seg", "next").agg(*add("n", "a", "b"))
    child = by_next.groupBy(*here, "seg").agg(*add("n", "a", "b"), F.max_by("next", F.struct("n", "next")).alias("led"))
    led = by_next.select(*here, "seg", "next", F.col("n").alias("n_next")).join(child, [*here, "seg"])
    pool = led.groupBy(*group, "next").agg(F.sum("n_next").alias("pool_n"))
    parent = child.groupBy(*group).agg(F.sum("n").alias("all_n"), F.sum("a").alias("all_a"), F.sum("b").alias("all_b"), F.count("*").alias("kids"))
    shares = led.join(pool, [*group, "next"]).join(parent, group)
    overlap = F.sum(F.least(F.col("n_next") / F.col("n"), F.col("pool_n") / F.col("all_n"))).alias("overlap")
    facts = shares.groupBy(*group, "seg", "n", "a", "b", "all_n", "all_a", "all_b", "kids").agg(overlap)
    labelled = F.col("a") + F.col("b")
    q = (F.col("all_b") + 1) / (F.col("all_a") + F.col("all_b") + 2)
    alike = (labelled == 0) | (F.abs(F.col("b") / labelled - q) <= z * F.sqrt(q * (1 - q) / labelled))
    shaped = (1 - F.col("overlap") <= tolerance + 1 / F.sqrt("n")) | ((F.col("kids") > fan) & (F.col("n") * fan < F.col("all_n")))
    wants = facts.select(*group, "seg", F.coalesce(alike & shaped, F.lit(False)).alias("wants"))
    enough = wants.groupBy(*group).agg(F.sum(F.col("wants").cast("int")).alias("merging"))
    choice = wants.join(enough, group).select(*here, "seg", F.when(F.col("wants") & (F.col("merging") > 1), "*").otherwise(F.col("seg")).alias("chosen"))
    decided = open_.join(choice, [*here, "seg"])
    decided = decided.select("host", "typed", F.concat("prefix", F.lit("/"), "chosen").alias("prefix"), F.expr("slice(rest, 2, greatest(size(rest) - 1, 0))").alias("rest"), "n", "a", "b")
    return decided.unionByName(tree.filter(F.size("rest") == 0))


def judge(pages: DataFrame, rules: Sequence[Rule], key: str = "page_id", url: str = "url", **options) -> DataFrame:
    """key, host, path, rule, verdict, template and purity of every url."""
    rule, says = rule_for(rules)
    cut = with_parts(pages.select(key, url), url).select(key, "host", "path").withColumns({"rule": rule, "label": says})
    known = common.written(learn(cut.select("host", "path", "label"), **options), "judged").withColumnRenamed("verdict", "learned")
    typed = cut.withColumn("typed", F.array_join(typed_segments(levels=options.get("levels", 8)), "/"))
    joined = typed.join(known, ["host", "typed"], "left")
    return joined.select(key, "host", "path", "rule", F.coalesce("label", "learned", F.lit("allow")).alias("verdict"), "template", "purity")
