"""Phase 2: nodes of equal rank and label are grouped by the set of their children's blocks.

A block is named by the smallest node_id in it. ``certify`` takes blocks from the structural hash and proves them in
one pass: bisimilar nodes have equal hashes, so these blocks are never too fine, and if all members of each block have
the same set of child blocks they are not too coarse. Otherwise they are refined from there. ``sweep`` follows the
ranks upwards: a round decides the nodes of one rank and sends their blocks along the edges into a store that is
partitioned by the rank of the addressee, so every edge is moved once. Messages come from all lower ranks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from dagquotient.functions.lineage import cut, fresh_path, small
from dagquotient.operators import ranks
from dagquotient.operators.graph import LabeledDag, disjoint_union

#: What nodes are grouped by before their families are looked at.
INITIAL = {"rank": ["rank"], "rank_label": ["rank", "label"], "rank_label_hash": ["rank", "label", "hash"]}

#: Rows of numbers that a row with text or an array in its keys counts for, where a side may be broadcast.
WIDE = 20


def fingerprint(values: Column) -> Column:
    """A set of numbers as its size and two hashes: sets of different sizes never have the same one."""
    ordered = F.array_sort(F.array_distinct(values))
    return F.struct(F.size(ordered).alias("size"), F.xxhash64(ordered).alias("x"), F.xxhash64(F.lit("second"), ordered).alias("y"))


def _named(df: DataFrame, keys: list[str]) -> DataFrame:
    """node_id, block_id: the smallest node_id of all rows with equal ``keys``; aggregated before it is joined back."""
    blocks = cut(df.groupBy(*keys).agg(F.min("node_id").alias("block_id")))
    on = [df[k].eqNullSafe(blocks[k]) for k in keys]
    cond = on[0]
    for x in on[1:]:
        cond = cond & x
    numbers = all(isinstance(df.schema[k].dataType, NumericType) for k in keys)
    return df.join(small(blocks, blocks.count() * (1 if numbers else WIDE)), cond).select(df["node_id"], blocks["block_id"])


def families(g: LabeledDag, partition: DataFrame) -> DataFrame:
    """node_id, family: the sorted distinct blocks of the children; an empty array where there are none."""
    told = g.edges.join(partition.select(F.col("node_id").alias("child"), "block_id"), "child").select(F.col("parent").alias("node_id"), "block_id").distinct()
    some = told.groupBy("node_id").agg(F.array_sort(F.collect_list("block_id")).alias("family"))
    return g.nodes.select("node_id").join(some, "node_id", "left").select("node_id", F.coalesce("family", F.array().cast("array<long>")).alias("family"))


def decision_values(g: LabeledDag, partition: DataFrame, ranked: DataFrame) -> DataFrame:
    """node_id, rank, label, family: equal for two nodes just if they are bisimilar."""
    return ranked.select("node_id", "rank", "label").join(families(g, partition), "node_id")


def forward_partition(g: LabeledDag, method: str = "certify", initial: str = "rank_label_hash", family: str = "array", ranked: DataFrame | None = None, bits: int = 64) -> DataFrame:
    """node_id, block_id: the bisimulation partition.

    ``method``: certify or sweep. For a sweep, ``initial`` is rank, rank_label or rank_label_hash, and ``family`` is
    array (exact sets as keys), or records (fixed-size rows led by a fingerprint, with exact tests for collisions).
    ``bits`` below 64 shorten the hashes, which must not change the outcome.
    """
    ranked = cut(ranks.by_peeling(g, bits)) if ranked is None else ranked
    if method == "certify":
        return certified(g, ranked)
    if method != "sweep":
        raise ValueError(f"unknown method {method}")
    return _sweep(g, ranked, INITIAL[initial], family, bits)


def certified(g: LabeledDag, ranked: DataFrame) -> DataFrame:
    """Blocks of equal rank, label and hash, refined where one pass shows that they are too coarse."""
    partition = cut(_named(ranked, ["rank", "label", "hash"]))
    if unstable(g, partition).isEmpty():
        return partition
    from dagquotient.operators.refine import by_signature

    return by_signature(g, partition)


def unstable(g: LabeledDag, partition: DataFrame) -> DataFrame:
    """block_id of the blocks whose members don't all have the same set of child blocks."""
    several = cut(partition.groupBy("block_id").agg(F.count("*").alias("n")).where("n > 1").select("block_id"))
    members = cut(partition.join(small(several, several.count()), "block_id", "left_semi"))  # the others' families are not needed
    few = members.select("node_id")
    n_few = few.count()
    own = LabeledDag(few, g.edges.join(small(few.withColumnRenamed("node_id", "parent"), n_few), "parent", "left_semi"))
    seen = families(own, partition).select("node_id", fingerprint(F.col("family")).alias("f")).join(members, "node_id")
    return seen.groupBy("block_id").agg(F.min("f").alias("a"), F.max("f").alias("b")).where("a <> b").select("block_id")


def _laid_out(df: DataFrame, what: str, by: str) -> DataFrame:
    """``df`` as a table in one folder for each value of ``by``, so that a filter on it reads no other rows."""
    spark, at = df.sparkSession, fresh_path(df.sparkSession, what)
    df.write.partitionBy(by).parquet(at)
    return spark.read.schema(df.schema).parquet(at)


def nodes_by_rank(ranked: DataFrame) -> DataFrame:
    """Ranked nodes, laid out by rank."""
    return _laid_out(ranked, "nodes-by-rank", "rank")


def edges_with_ranks(g: LabeledDag, ranked: DataFrame) -> DataFrame:
    """parent, child, parent_rank, child_rank."""
    child, parent = (ranked.select(F.col("node_id").alias(end), F.col("rank").alias(f"{end}_rank")) for end in ("child", "parent"))
    return g.edges.join(child, "child").join(parent, "parent").select("parent", "child", "parent_rank", "child_rank")


def edges_by_rank(g: LabeledDag, ranked: DataFrame) -> DataFrame:
    """Edges with ranks, laid out by the rank of the child."""
    return _laid_out(edges_with_ranks(g, ranked), "edges-by-rank", "child_rank")


def _sweep(g: LabeledDag, ranked: DataFrame, keys: list[str], family: str, bits: int) -> DataFrame:
    spark = g.nodes.sparkSession
    nodes, edges = nodes_by_rank(ranked), edges_by_rank(g, ranked)
    store, message = fresh_path(spark, "messages"), "node_id long, block_id long, parent_rank int"
    out = fresh_path(spark, "blocks")
    top = ranked.agg(F.max("rank")).first()[0]
    for r in range(0, (-1 if top is None else top) + 1):
        here = nodes.where(F.col("rank") == r)
        if r:
            told = spark.read.schema(message).parquet(store).where(F.col("parent_rank") == r).select("node_id", "block_id").distinct()
            decided = _decide(here, told, keys, family, bits)
        else:
            decided = _named(here, sorted({*keys, "label"}))
        now = cut(decided)
        now.write.mode("append").parquet(out)
        send = edges.where(F.col("child_rank") == r).join(now.select(F.col("node_id").alias("child"), "block_id"), "child")
        send.select(F.col("parent").alias("node_id"), "block_id", "parent_rank").distinct().write.mode("append").partitionBy("parent_rank").parquet(store)
    return spark.read.schema("node_id long, block_id long").parquet(out) if top is not None else g.nodes.select("node_id", F.col("node_id").alias("block_id"))


def _decide(here: DataFrame, told: DataFrame, keys: list[str], family: str, bits: int) -> DataFrame:
    """node_id, block_id for the nodes of one rank and the distinct blocks of their children."""
    keys = sorted({*keys, "label"})  # with ranks as the start, the label is looked at here
    if family == "array":
        some = told.groupBy("node_id").agg(F.array_sort(F.collect_list("block_id")).alias("family"))
        return _named(cut(here.join(some, "node_id")), [*keys, "family"])
    marked = cut(records(here, told, keys, bits))
    own = marked.where("kind = 'self'")
    clashes = collisions(marked, keys)
    plain = own.join(clashes, [*keys, "size", "x", "y"], "left_anti")
    out = _named(plain, [*keys, "size", "x", "y"])
    if clashes.isEmpty():
        return out
    rest = own.join(clashes, [*keys, "size", "x", "y"], "left_semi")
    exact = told.join(rest.select("node_id"), "node_id", "left_semi").groupBy("node_id").agg(F.array_sort(F.collect_list("block_id")).alias("family"))
    return out.unionByName(_named(cut(rest.join(exact, "node_id")), [*keys, "family"]))


def records(here: DataFrame, told: DataFrame, keys: list[str], bits: int = 64) -> DataFrame:
    """Rows of fixed size led by a fingerprint of the family: one for each node (self) and each of its child blocks.

    The fingerprint's parts add up over the blocks of a family, so no array is ever formed, however many children.
    """
    half = F.lit(2**32 - 1)
    a, b = F.xxhash64("block_id"), F.xxhash64(F.lit("second"), "block_id")
    parts = told.groupBy("node_id").agg(F.count("*").alias("size"), F.bit_xor(a).alias("x"), F.sum(b.bitwiseAND(half)).alias("y"))
    if bits < 64:
        parts = parts.select("node_id", "size", F.pmod("x", F.lit(2**bits)).alias("x"), F.lit(0).cast("long").alias("y"))
    own = here.join(parts, "node_id")
    each = own.join(told, "node_id")
    lead = [*keys, "size", "x", "y", "node_id"]
    return own.select(*lead, F.lit("self").alias("kind"), F.lit(None).cast("long").alias("value")).unionByName(each.select(*lead, F.lit("child").alias("kind"), F.col("block_id").alias("value")))


def collisions(marked: DataFrame, keys: list[str]) -> DataFrame:
    """The fingerprints under which different families meet: some member lacks a block of the smallest one's family."""
    lead = [*keys, "size", "x", "y"]
    first = marked.where("kind = 'self'").groupBy(*lead).agg(F.min("node_id").alias("first"), F.count("*").alias("members"))
    model = marked.where("kind = 'child'").join(first.where("members > 1"), lead)
    theirs = model.where("node_id = first").select(*lead, "value")
    shared = marked.where("kind = 'child'").join(theirs, [*lead, "value"]).groupBy(*lead, "node_id").agg(F.count("*").alias("common"))
    member = marked.where("kind = 'self'").join(first.where("members > 1"), lead)
    return member.join(shared, [*lead, "node_id"], "left").where("coalesce(common, 0) < size").select(*lead).distinct()


def collision_stats(g: LabeledDag, partition: DataFrame, ranked: DataFrame, initial: str = "rank_label", bits: int = 64) -> DataFrame:
    """rank, keys, colliding_keys, colliding_nodes: secondary hashes of families, ``bits`` long, that meet wrongly."""
    lead = INITIAL[initial]
    values = decision_values(g, partition, ranked.select("node_id", "rank", "label")).join(ranked.select("node_id", "hash"), "node_id")
    key = F.conv(F.substring(F.md5(F.array_join(F.transform("family", lambda x: x.cast("string")), ",")), 1, 15), 16, 10).cast("long")
    values = values.withColumn("key", F.pmod(key, F.lit(2**bits)) if bits < 60 else key).withColumn("size", F.size("family"))
    per_key = values.groupBy(*sorted({*lead, "rank"}), "label", "size", "key").agg(F.countDistinct("family").alias("families"), F.count("*").alias("nodes")) if "label" not in lead else values.groupBy(*lead, "size", "key").agg(F.countDistinct("family").alias("families"), F.count("*").alias("nodes"))
    wrong = F.col("families") > 1
    return per_key.groupBy("rank").agg(F.count("*").alias("keys"), F.sum(wrong.cast("long")).alias("colliding_keys"), F.sum(F.when(wrong, F.col("nodes")).otherwise(0)).alias("colliding_nodes"))


def is_refinement(fine: DataFrame, coarse: DataFrame) -> DataFrame:
    """block_id of blocks of ``fine`` that lie in several blocks of ``coarse``: no row if it refines it."""
    both = fine.join(coarse.withColumnRenamed("block_id", "other"), "node_id")
    return both.groupBy("block_id").agg(F.min("other").alias("a"), F.max("other").alias("b")).where("a <> b").select("block_id")


def same_partition(a: DataFrame, b: DataFrame) -> bool:
    return is_refinement(a, b).isEmpty() and is_refinement(b, a).isEmpty()


def meet(a: DataFrame, b: DataFrame) -> DataFrame:
    """The coarsest partition that refines both."""
    return _named(cut(a.select("node_id", F.col("block_id").alias("one")).join(b.select("node_id", F.col("block_id").alias("two")), "node_id")), ["one", "two"])


def bisimilar(pairs: DataFrame, partition: DataFrame) -> DataFrame:
    """u, v, bisimilar for pairs of nodes of one graph (or of a disjoint union)."""
    a = partition.select(F.col("node_id").alias("u"), F.col("block_id").alias("bu"))
    b = partition.select(F.col("node_id").alias("v"), F.col("block_id").alias("bv"))
    return pairs.join(a, "u").join(b, "v").select("u", "v", (F.col("bu") == F.col("bv")).alias("bisimilar"))


def graphs_bisimilar(a: LabeledDag, b: LabeledDag) -> DataFrame:
    """bisimilar, unmatched: one row; how many blocks of the union have nodes of one graph only."""
    union, names = disjoint_union(a, b)
    per_block = forward_partition(union.cut()).join(names, "node_id").groupBy("block_id").agg(F.countDistinct("graph_no").alias("graphs"))
    alone = F.coalesce(F.sum((F.col("graphs") < 2).cast("long")), F.lit(0))
    return per_block.agg((alone == 0).alias("bisimilar"), alone.alias("unmatched"))


def k_partition(g: LabeledDag, k: int) -> DataFrame:
    """node_id, block_id of forward k-bisimilarity: k rounds of (block so far, set of the children's blocks)."""
    partition = cut(_named(g.nodes, ["label"]))
    for _ in range(k):
        step = families(g, partition).join(partition.withColumnRenamed("block_id", "before"), "node_id")
        partition = cut(_named(cut(step), ["before", "family"]))
    return partition


def ak_index_graph(g: LabeledDag, k: int) -> DataFrame:
    """node_id, block_id of backward k-bisimilarity, by its definition, on any graph."""
    return k_partition(g.reverse(), k)


def partition_error(found: DataFrame, truth: DataFrame) -> DataFrame:
    """merged, split: pairs of nodes that ``found`` has wrongly in one block, and wrongly in two."""

    def pairs(p: DataFrame, *keys: str) -> DataFrame:
        return p.groupBy(*keys).agg(F.count("*").alias("n")).agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2), F.lit(0)).cast("long").alias("p"))

    both = found.join(truth.withColumnRenamed("block_id", "true_id"), "node_id")
    a, b, c = pairs(both, "block_id"), pairs(both, "true_id"), pairs(both, "block_id", "true_id")
    one = a.withColumnRenamed("p", "a").crossJoin(b.withColumnRenamed("p", "b")).crossJoin(c.withColumnRenamed("p", "c"))  # of one row each
    return one.select((F.col("a") - F.col("c")).alias("merged"), (F.col("b") - F.col("c")).alias("split"))
