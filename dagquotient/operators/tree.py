"""Document trees: tags, levels, the 1-index, F&B and A(k) indexes.

HTML is first repaired to a balanced stream of tags: comments and the text of scripts and styles are left out, void
elements are leaves, an end tag closes up to the nearest open element of its name (none: it is ignored), and what is
open at the end closes there. On the balanced stream everything but the stack traces is windows and joins.

A tree is a table of node_id, parent (null at roots), depth, label and doc_id; a forest is many of them in one table.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.functions.lineage import cut
from dagquotient.operators import partition as P
from dagquotient.operators.graph import LabeledDag

#: Elements without content (fixed by HTML).
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Node ids of a document start at its id times this, unless another stride is given; no document may have more nodes.
STRIDE = 1_000_000
#: Tags of a document that one window may hold in ``levels_in_chunks``.
CHUNK = 1_000_000
#: Stands in traces for what is above a root; no label may be it.
PAD = "#"
_comment = re.compile(r"<!--.*?-->", re.S)
_unread = re.compile(r"(<(script|style)\b[^>]*>).*?(</\2)", re.S | re.I)
_tag = re.compile(r"</?[a-zA-Z][a-zA-Z0-9]*")


def balanced(html: str) -> Iterator[tuple[bool, str]]:
    """(is_start, label) of a text's tags after repair."""
    stack: list[str] = []
    for raw in _tag.findall(_unread.sub(r"\1\3", _comment.sub("", html or ""))):
        end = raw[1] == "/"
        name = raw[1 + end :].lower()
        if not end:
            yield True, name
            if name in VOID:
                yield False, name
            else:
                stack.append(name)
        elif name in stack:
            while True:
                top = stack.pop()
                yield False, top
                if top == name:
                    break
    while stack:
        yield False, stack.pop()


def tags(pages: DataFrame, doc: str = "page_id", html: str = "html") -> DataFrame:
    """doc_id, pos, is_start, label: the balanced tags of every text, each text in one task as a whole."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for d, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                found = list(balanced(text))
                if found:
                    start, label = zip(*found, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array([d] * len(found), pa.int64()), pa.array(range(len(found)), pa.int32()), pa.array(start), pa.array(label)], ["doc_id", "pos", "is_start", "label"])

    return pages.select(F.col(doc).cast("long").alias("doc_id"), html).mapInArrow(run, "doc_id long, pos int, is_start boolean, label string")


def _node_id(doc: Column, nth: Column, stride: int) -> Column:
    """Ids of two documents never meet: a document that is larger than the stride is an error."""
    return F.when(nth < stride, doc * stride + nth).otherwise(F.raise_error(F.concat(F.lit(f"more than {stride} elements in document "), doc.cast("string"))))


def levels(stream: DataFrame, stride: int = STRIDE) -> tuple[DataFrame, DataFrame]:
    """(doc_id, depth, id_on_level, node_id, label, parent) of start tags and (doc_id, parent_depth, parent_id, child_id).

    A start tag is a member of its level and asks the level above for its last member so far, in one window.
    """
    order = Window.partitionBy("doc_id").orderBy("pos")
    step = F.when(F.col("is_start"), 1).otherwise(-1)
    starts = stream.withColumns({"depth": (F.sum(step).over(order) - 1).cast("int"), "nth": F.sum(F.col("is_start").cast("long")).over(order) - 1}).where("is_start")
    starts = starts.withColumn("node_id", _node_id(F.col("doc_id"), F.col("nth"), stride))
    asked = starts.select("*", F.explode(F.array(F.struct(F.lit(True).alias("member"), F.col("depth").alias("level")), F.struct(F.lit(False).alias("member"), (F.col("depth") - 1).alias("level")))).alias("x")).select("*", "x.*").where("level >= 0")
    at = Window.partitionBy("doc_id", "level").orderBy("pos")
    counted = asked.withColumns({"count": F.sum(F.col("member").cast("long")).over(at) - 1, "last": F.last(F.when(F.col("member"), F.col("node_id")), ignorenulls=True).over(at)})
    return _paired(counted)


def _paired(counted: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes and edges from the two rows of an element: as a member of its level, and as it asks the one above."""
    both = counted.groupBy("doc_id", "pos", "depth", "node_id", "label").agg(F.max(F.when(F.col("member"), F.col("count"))).alias("id_on_level"), F.max(F.when(~F.col("member"), F.col("count"))).alias("parent_id"), F.max(F.when(~F.col("member"), F.col("last"))).alias("parent"))
    nodes = both.select("doc_id", "depth", "id_on_level", "node_id", "label", "parent")
    edges = both.where("parent IS NOT NULL").select("doc_id", (F.col("depth") - 1).alias("parent_depth"), "parent_id", F.col("id_on_level").alias("child_id"))
    return nodes, edges


def levels_in_chunks(stream: DataFrame, chunk: int = CHUNK, stride: int = STRIDE) -> tuple[DataFrame, DataFrame]:
    """What ``levels`` gives, for documents of any length: no window holds more than ``chunk`` tags.

    Three numbers are carried from chunk to chunk by windows over one row a chunk: the depth and the elements so far,
    and on each level the members so far with the last of them.
    """
    earlier = Window.partitionBy("doc_id").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    step = F.when(F.col("is_start"), 1).otherwise(-1)
    dealt = stream.withColumn("part", F.floor(F.col("pos") / chunk))
    sums = dealt.groupBy("doc_id", "part").agg(F.sum(step).alias("rise"), F.sum(F.col("is_start").cast("long")).alias("born"))
    carried = sums.select("doc_id", "part", F.coalesce(F.sum("rise").over(earlier), F.lit(0)).alias("from_depth"), F.coalesce(F.sum("born").over(earlier), F.lit(0)).alias("from_nth"))
    order = Window.partitionBy("doc_id", "part").orderBy("pos")
    starts = dealt.join(carried, ["doc_id", "part"]).withColumns({"depth": (F.sum(step).over(order) + F.col("from_depth") - 1).cast("int"), "nth": F.sum(F.col("is_start").cast("long")).over(order) + F.col("from_nth") - 1}).where("is_start")
    starts = starts.select("doc_id", "part", "pos", "label", "depth", _node_id(F.col("doc_id"), F.col("nth"), stride).alias("node_id"))
    asked = starts.select("*", F.explode(F.array(F.struct(F.lit(True).alias("member"), F.col("depth").alias("level")), F.struct(F.lit(False).alias("member"), (F.col("depth") - 1).alias("level")))).alias("x")).select("*", "x.*").where("level >= 0")
    on_level = Window.partitionBy("doc_id", "level").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    seen = asked.groupBy("doc_id", "level", "part").agg(F.sum(F.col("member").cast("long")).alias("members"), F.max(F.when(F.col("member"), F.col("node_id"))).alias("newest"))
    seen = seen.select("doc_id", "level", "part", F.coalesce(F.sum("members").over(on_level), F.lit(0)).alias("from_count"), F.max("newest").over(on_level).alias("from_last"))
    at = Window.partitionBy("doc_id", "level", "part").orderBy("pos")
    last = F.last(F.when(F.col("member"), F.col("node_id")), ignorenulls=True).over(at)
    counted = asked.join(seen, ["doc_id", "level", "part"]).withColumns({"count": F.sum(F.col("member").cast("long")).over(at) + F.col("from_count") - 1, "last": F.coalesce(last, F.col("from_last"))})
    return _paired(counted)


def tree_of(stream: DataFrame, stride: int = STRIDE) -> DataFrame:
    """node_id, parent, depth, label, doc_id."""
    return levels(stream, stride)[0].select("node_id", "parent", "depth", "label", "doc_id")


def graph_of(tree: DataFrame) -> LabeledDag:
    return LabeledDag(tree.select("node_id", "label"), tree.where("parent IS NOT NULL").select("parent", F.col("node_id").alias("child")))


def rooted(g: LabeledDag) -> DataFrame:
    """The tree table of a graph in which nobody has two parents; depths by following the edges down."""
    up = g.edges.select(F.col("child").alias("node_id"), "parent")
    all_ = cut(g.nodes.join(up, "node_id", "left"))
    front = cut(all_.where("parent IS NULL").select("node_id", "parent", F.lit(0).alias("depth"), "label"))
    out = front
    while not front.isEmpty():
        front = cut(all_.join(front.select(F.col("node_id").alias("parent"), "depth"), "parent").select("node_id", "parent", (F.col("depth") + 1).alias("depth"), "label"))
        out = out.unionByName(front)
    return out.withColumn("doc_id", F.lit(0).cast("long"))


def one_index(tree: DataFrame, method: str = "sweep") -> DataFrame:
    """node_id, block_id of backward bisimilarity.

    sweep: level by level, by (label, block of the parent). path: nodes of equal label paths from the root, no rounds
    but one for each doubling of the depth. general: the DAG method on reversed edges.
    """
    if method == "general":
        return P.forward_partition(graph_of(tree).reverse())
    if method == "path":
        return _same_paths(tree)
    tree = cut(tree)
    top = tree.agg(F.max("depth")).first()[0]
    done = before = None
    for depth in range((-1 if top is None else top) + 1):
        here = tree.where(F.col("depth") == depth)
        if before is None:
            here = here.withColumn("above", F.lit(-1).cast("long"))
        else:
            here = here.join(before.select(F.col("node_id").alias("parent"), F.col("block_id").alias("above")), "parent")
        before = cut(P._named(cut(here), ["label", "above"]))
        done = before if done is None else done.unionByName(before)
    return done if done is not None else tree.select("node_id", F.col("node_id").alias("block_id"))


def _same_paths(tree: DataFrame) -> DataFrame:
    """node_id, block_id: nodes of equal label paths from the root, told by numbers of fixed size however deep a tree is.

    A block of paths of twice the length is a pair: the node's block, and that of its ancestor as many steps above. Nodes
    of which the whole path is told already (theirs are shorter than ``length``) meet no others again and rest.
    """
    deepest = tree.agg(F.max("depth")).first()[0] or 0
    labelled = cut(tree.select("node_id", F.col("parent").alias("at"), "depth", "label"))
    now = cut(labelled.join(P._named(labelled, ["label"]), "node_id").select("node_id", "at", "depth", "block_id"))
    length = 1
    while length < deepest + 1:
        above = now.select(F.col("node_id").alias("at"), F.col("block_id").alias("over"), F.col("at").alias("up"))
        moving = now.where(F.col("depth") + 1 >= length).withColumnRenamed("block_id", "own")
        step = cut(moving.join(above, "at", "left").select("node_id", "up", "depth", "own", "over"))
        named = step.join(P._named(step, ["own", "over"]), "node_id").select("node_id", F.col("up").alias("at"), "depth", "block_id")
        now = cut(now.where(F.col("depth") + 1 < length).unionByName(named))
        length *= 2
    return now.select("node_id", "block_id")


def fb_index(tree: DataFrame, mode: str = "stable") -> DataFrame:
    """node_id, block_id of the index that looks both ways.

    stable: forward blocks, then nodes of equal paths of these from the root, by doubling; no block can be split further
    from either side. meet: the common refinement of the two one-way partitions, which may be coarser. fixpoint: both ways
    in turn until nothing changes.
    """
    g = graph_of(tree).cut()
    forward = P.forward_partition(g)
    if mode == "meet":
        return P.meet(forward, one_index(tree))
    if mode == "stable":
        seeded = tree.drop("label").join(forward.select("node_id", F.col("block_id").cast("string").alias("label")), "node_id")
        return one_index(cut(seeded), "path")
    return fb_fixpoint(g, forward)


def fb_fixpoint(g: LabeledDag, start: DataFrame | None = None) -> DataFrame:
    """Backward and forward refinement in turn until the number of blocks stays; for any DAG."""
    from dagquotient.operators.refine import _n_blocks, by_signature

    now = P.forward_partition(g) if start is None else start
    n = _n_blocks(now)
    while True:
        now = cut(by_signature(g, cut(by_signature(g.reverse(), now))))
        if (more := _n_blocks(now)) == n:
            return now
        n = more


def _check_pad(tree: DataFrame) -> None:
    if not tree.where(F.col("label") == PAD).isEmpty():
        raise ValueError(f"the label {PAD!r} is reserved for traces")


def ak_joins(tree: DataFrame, k: int) -> DataFrame:
    """node_id, trace: k joins with the parent, one label each."""
    _check_pad(tree)
    names = tree.select(F.col("node_id").alias("at"), F.col("label").alias("name"), F.col("parent").alias("up"))
    out = tree.select("node_id", F.array("label").alias("trace"), F.col("parent").alias("at"))
    for _ in range(k):
        out = out.join(names, "at", "left").select("node_id", F.concat(F.array(F.coalesce("name", F.lit(PAD))), "trace").alias("trace"), F.col("up").alias("at"))
    return out.select("node_id", "trace")


def ak_doubling(tree: DataFrame, k: int) -> DataFrame:
    """node_id, trace: traces of twice the length from two traces, so few joins do for a large k."""
    _check_pad(tree)
    return _doubled(tree, k)


def _doubled(tree: DataFrame, k: int) -> DataFrame:
    out, length = tree.select("node_id", F.array("label").alias("trace"), F.col("parent").alias("at")), 1
    while length < k + 1:
        out = cut(out)
        above = out.select(F.col("node_id").alias("at"), F.col("trace").alias("more"), F.col("at").alias("up"))
        pad = F.array_repeat(F.lit(PAD), length)
        out = out.join(above, "at", "left").select("node_id", F.concat(F.coalesce("more", pad), "trace").alias("trace"), F.col("up").alias("at"))
        length *= 2
    return out.select("node_id", F.slice("trace", -(k + 1), k + 1).alias("trace"))


def ak_stack(stream: DataFrame, k: int, stride: int = STRIDE) -> DataFrame:
    """node_id, trace from a balanced stream: the top of the stack of open labels at each start tag."""

    def run(table: pa.Table) -> pa.Table:
        doc = table.column("doc_id")[0].as_py()
        rows = sorted(zip(table.column("pos").to_pylist(), table.column("is_start").to_pylist(), table.column("label").to_pylist(), strict=True))
        stack, out = [PAD] * k, []
        for _, start, label in rows:
            if start:
                stack.append(label)
                out.append(stack[-(k + 1) :])
            else:
                stack.pop()
        if len(out) > stride:
            raise ValueError(f"more than {stride} elements in document {doc}")
        return pa.table({"node_id": pa.array([doc * stride + i for i in range(len(out))], pa.int64()), "trace": pa.array(out, pa.list_(pa.string()))})

    if not stream.where(F.col("label") == PAD).isEmpty():
        raise ValueError(f"the label {PAD!r} is reserved for traces")
    return stream.groupBy("doc_id").applyInArrow(run, "node_id long, trace array<string>")


def ak_chain(rows: DataFrame, part: list[str], order: str, label: str, node: str, k: int) -> DataFrame:
    """node_id, trace where every node's parent is the one before it: one window."""
    at = Window.partitionBy(*part).orderBy(order)
    return rows.select(F.col(node).alias("node_id"), F.array(*[F.coalesce(F.lag(label, i).over(at), F.lit(PAD)) if i else F.col(label) for i in range(k, -1, -1)]).alias("trace"))


def blocks_of(traces: DataFrame) -> DataFrame:
    """node_id, block_id: nodes of equal trace."""
    return P._named(traces, ["trace"])
