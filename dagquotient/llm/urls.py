"""URL filters: explicit rules first, then a tree of path templates judged by labelled purity.

Per host, paths are followed segment by segment. Segments that vary (digits, or values too rare among their siblings)
become the wildcard ``*``; what is left is a tree of templates. Sibling branches whose labelled shares don't differ
significantly merge into the wildcard too. Paths are followed to their end.

Purity is smoothed down the tree. What a branch hands on is its share of labelled bad urls among all urls that go
through it, smoothed towards what its parent hands on, and a host's towards that of all hosts. The purity of a template
is its share of bad among its own labelled urls, smoothed towards what its parent hands on; so a template without labels
is judged by how far labels condemn the branches around it. A template over the bound is rejected. Labels are the
verdicts of the rules unless others are given.

Nulls and urls without ``://`` have an empty host and path and are judged as such. Repeated rows get equal results,
extra columns are ignored, an empty table gives an empty table.
"""

from __future__ import annotations

import string
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import cut, drop, small


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


def rule(text: str) -> Rule:
    """``"block example.com/en/"`` as a rule."""
    verdict, _, where = text.partition(" ")
    host, slash, path = where.partition("/")
    return Rule(verdict, host, slash + path)


def host_of(url: Column) -> Column:
    host = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(host, string.ascii_uppercase, string.ascii_lowercase)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def decided(rules: list[Rule], host: Column, path: Column) -> Column:
    """rule and verdict of the longest rule that fits, both null if none does."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for r in sorted(rules, key=lambda r: (len(r.name), r.name)):
        fits = ((host == r.host) | host.endswith(f".{r.host}")) & path.startswith(r.path)
        out = F.when(fits, F.struct(F.lit(r.name).alias("rule"), F.lit(r.verdict).alias("verdict"))).otherwise(out)
    return out


def _shape(path: Column) -> Column:
    """The segments, digits as ``*``; an array. A suffix like .html stays with its segment."""
    parts = F.filter(F.split(path, "/"), lambda x: x != "")
    return F.transform(parts, lambda x: F.when(x.rlike("[0-9]"), F.regexp_replace(x, "^[^.]*", "*")).otherwise(x))


def templates(urls: DataFrame, least_share: float = 0.02, z: float = 2.0, prior: float = 4.0) -> DataFrame:
    """host, shape, template, seen, good, bad, purity: from rows of host, path and label (1 bad, 0 good, else null).

    A segment value stays if at least ``least_share`` of the urls under its parent have it, however many others there
    are. ``good`` and ``bad`` count the labelled urls of the whole template; ``prior`` is the weight, in urls, of what a
    parent hands on. A round of the loop takes one segment; a shape that has no other beside it any more is taken to
    its end at once, as one step, so one very long path adds no rounds.
    """
    nodes = urls.groupBy("host", _shape(F.col("path")).alias("shape")).agg(F.count("*").alias("seen"), F.sum((F.col("label") == 1).cast("long")).alias("bad"), F.sum((F.col("label") == 0).cast("long")).alias("good")).na.fill(0, ["bad", "good"])
    base = nodes.agg(F.coalesce(F.sum("bad") / F.sum("seen"), F.lit(0.0)).alias("handed"))  # one row
    nodes = cut(nodes.withColumn("template", F.array().cast("array<string>")).crossJoin(F.broadcast(base)))
    ended = F.size("template") == F.size("shape")
    done, depth, spent = nodes.where(ended), 0, [nodes]
    while not (nodes := nodes.where(~ended)).isEmpty():
        nodes = nodes.withColumn("segment", F.get("shape", F.lit(depth)))
        branch = cut(nodes.groupBy("host", "template", "segment").agg(*[F.sum(c).alias(c) for c in ("seen", "bad", "good")], F.count("*").alias("shapes")))
        parent = cut(branch.groupBy("host", "template").agg(*[F.sum(c).alias(f"all_{c}") for c in ("seen", "bad", "good", "shapes")]))
        n_parents = parent.count()
        parent = small(parent, n_parents)  # a host of very many branches is one row of it
        labelled = F.col("bad") + F.col("good")
        rest = F.col("all_bad") + F.col("all_good") - labelled
        share, other = F.col("bad") / labelled, (F.col("all_bad") - F.col("bad")) / rest
        pooled = F.col("all_bad") / (labelled + rest)
        error = F.sqrt(pooled * (1 - pooled) * (1 / labelled + 1 / rest))
        alike = F.when((labelled >= 5) & (rest >= 5), F.when(error > 0, F.abs(share - other) < z * error).otherwise(F.lit(True))).otherwise(F.lit(False))
        keep = (F.col("seen") >= least_share * F.col("all_seen")) & ~alike
        kept = branch.join(parent, ["host", "template"]).where(keep).select("host", "template", "segment", (F.col("all_shapes") == 1).alias("lone"))
        handed = (F.col("all_bad") + prior * F.col("handed")) / (F.col("all_seen") + prior)
        nodes = nodes.join(parent.select("host", "template", "all_bad", "all_seen"), ["host", "template"]).join(kept, ["host", "template", "segment"], "left")
        rest_of_it = F.when(F.col("lone"), F.slice("shape", depth + 1, F.size("shape") - depth)).otherwise(F.array(F.when(F.col("lone").isNotNull(), F.col("segment")).otherwise("*")))
        nodes = cut(nodes.withColumns({"template": F.concat("template", rest_of_it), "handed": handed}).drop("lone", "segment", "all_bad", "all_seen"))
        done, depth = done.unionByName(nodes.where(ended)), depth + 1
        spent.append(nodes)
    # merged branches may come with one template from several rounds or parents: what is handed to them is averaged by urls
    whole = done.groupBy("host", "template").agg(*[F.sum(c).alias(c) for c in ("bad", "good", "seen")], (F.sum(F.col("seen") * F.col("handed")) / F.sum("seen")).alias("handed"))
    purity = (F.col("bad") + prior * F.col("handed")) / (F.col("bad") + F.col("good") + prior)
    out = cut(done.select("host", "shape", "template").join(whole.select("*", purity.alias("purity")).drop("handed"), ["host", "template"]))
    drop(*spent)
    return out


def judge(pages: DataFrame, rules: list[Rule], labels: DataFrame | None = None, prior: float = 4.0, bound: float = 0.6) -> DataFrame:
    """page_id, host, path, rule, verdict, template, purity. ``labels``: page_id and label, in place of the rules' verdicts."""
    rows = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    rows = rows.withColumn("by_rule", decided(rules, F.col("host"), F.col("path")))
    if labels is None:
        rows = rows.withColumn("label", (F.col("by_rule.verdict") == "block").cast("int"))
    else:
        rows = rows.join(labels.select("page_id", "label").dropDuplicates(["page_id"]), "page_id", "left")
    found = templates(rows.select("host", "path", "label"), prior=prior)
    n = found.count()
    found = found.select("host", "shape", F.concat(F.lit("/"), F.array_join("template", "/")).alias("template"), F.round("purity", 9).alias("purity"))
    judged = rows.withColumn("shape", _shape(F.col("path"))).join(small(found, n), ["host", "shape"], "left")
    verdict = F.coalesce("by_rule.verdict", F.when(F.col("purity") > bound, "block").otherwise("allow"))
    return judged.select("page_id", "host", "path", F.col("by_rule.rule").alias("rule"), verdict.alias("verdict"), "template", "purity")
