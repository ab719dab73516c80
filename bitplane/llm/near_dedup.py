"""Near-duplicate classes: weighted MinHash bands, exact checks, connected classes.

Nodes are distinct shingle multisets, so exact copies never meet in pairs.  In
every bucket all nodes are first checked against its best-known node, which costs as many
checks as nodes and joins most of a group of copies; after a second round with
other leaders, only nodes of one bucket that are still in different classes are
checked against each other, as far as the elements they could share allow, and a bucket of many is cut
into blocks whose pairs are separate tasks.  Nothing is capped, and tables that grow with the data
stay distributed.  Whatever is joined on a key that may be hot (a bucket, a leader, a class, the
node of many copies) goes through leaves (common.hand_down), so such a key is spread over tasks.
Joins of intermediate tables are merge joins: dozens of small broadcasts a run would all be built in the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import bagminhash as bag
from . import common
from .common import Shelf, leaf_count, leaf_of, lean, merge_up

gather_scatter, hand_down = (partial(f, hint="merge") for f in (common.gather_scatter, common.hand_down))

U = np.uint64
ROWS_AT_ONCE = 256
#: Words of 64 bits in a node's parity bitmap.
SKETCH = 16
#: Stored tables after which the driver gives memory back.
REST = 8


def _parts(batches: Iterator[pa.RecordBatch], rows: int = ROWS_AT_ONCE):
    for batch in batches:
        for i in range(0, batch.num_rows, rows):
            part = batch.slice(i, rows)
            yield part, [t or "" for t in part.column(1).to_pylist()]


def _nodes(n: int, owner: np.ndarray, elements: np.ndarray) -> tuple[list[bytes | None], np.ndarray]:
    """128-bit digests of the element sets and the bounds of each."""
    order = np.lexsort((elements, owner))
    elements = elements[order]
    bound = np.searchsorted(owner[order], np.arange(n + 1))
    raw = memoryview(elements.tobytes())
    digest = [xxhash.xxh3_128_digest(raw[a * 8 : b * 8]) if b > a else None for a, b in zip(bound.tolist(), bound[1:].tolist())]
    return digest, elements, bound


def sign(df: DataFrame, width: int, rows: int, n_bands: int, id_col: str, text_col: str) -> DataFrame:
    """Per row: id, a hash of the text, node (null without words), bands."""

    def run(batches):
        for part, texts in _parts(batches):
            owner, hashes, weights, _ = bag.shingles(texts, width)
            sig = bag.signatures(len(texts), owner, hashes, weights, rows * n_bands)
            nodes, _, _ = _nodes(len(texts), *bag.occurrences(owner, hashes, weights))
            flat = pa.array(bag.bands(sig, rows).ravel())
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32) * n_bands), flat)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(nodes, pa.binary()), lists], ["id", "mark", "node", "bands"])

    rows_in = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("mark"))
    return rows_in.mapInArrow(lean(run), "id long, mark long, node binary, bands array<long>")


def parities(elements: np.ndarray, bound: np.ndarray) -> np.ndarray:
    """SKETCH words a set: bit i tells whether an odd number of its elements fall on i.

    Every element that only one of two sets has flips one bit at most, so the bits in
    which two bitmaps differ are no more than the elements in which the sets differ.
    """
    n, bits = len(bound) - 1, SKETCH * 64
    place = np.repeat(np.arange(n) * bits, np.diff(bound)) + (elements % U(bits)).astype(np.int64)
    odd = (np.bincount(place, minlength=n * bits) & 1).astype(np.uint8)
    return np.packbits(odd, bitorder="little").view(np.int64).reshape(n, SKETCH)


def elements(df: DataFrame, width: int) -> DataFrame:
    """(id, text, want) to (node, n, sketch, elements), for rows whose text is the wanted multiset."""

    def run(batches):
        for part, texts in _parts(batches):
            owner, hashes, weights, _ = bag.shingles(texts, width)
            nodes, flat, bound = _nodes(len(texts), *bag.occurrences(owner, hashes, weights))
            lists = pa.ListArray.from_arrays(pa.array(bound.astype(np.int32)), pa.array(flat.view(np.int64)))
            sketch = pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32) * SKETCH), pa.array(parities(flat, bound).ravel()))
            out = pa.RecordBatch.from_arrays([pa.array(nodes, pa.binary()), pa.array(np.diff(bound).astype(np.int64)), sketch, lists], ["node", "n", "sketch", "elements"])
            yield out.filter(pa.array([a == b for a, b in zip(nodes, part.column(2).to_pylist())]))

    return df.mapInArrow(lean(run), "node binary, n long, sketch array<long>, elements array<long>")


#: Pairs of one node that a task checks; a node with more is read by several tasks.
STAR = 512
#: Open nodes of one bucket that are compared in one task; a bucket of more is cut into blocks.
BLOCK = 256


def pieces(n: Column, size: int) -> Column:
    return F.ceil(n / F.lit(size)).cast("int")


def copies(rows: DataFrame, n: Column, name: str) -> DataFrame:
    """Each row ``n`` times, numbered from 0."""
    return rows.withColumn(name, F.explode(F.sequence(F.lit(0), n - 1)))


def verified(pairs: DataFrame, sets: DataFrame, similarity: float, leaves: int) -> DataFrame:
    """The pairs (a, b) whose multisets overlap enough; the overlap is counted exactly.  Node a may be in many pairs."""
    rows = pairs.select("a", "b", leaf_of(F.col("b"), leaves).alias("__leaf"))
    degree = [F.count(F.lit(1)).alias("pairs")], [F.sum("pairs").alias("pairs")]
    dealt = gather_scatter(rows, ["a"], leaves, *degree, F.lit(True))
    dealt = dealt.select("a", "b", F.pmod(F.xxhash64("b"), pieces(F.col("pairs"), STAR).cast("long")).cast("int").alias("piece"))
    leads = merge_up(rows.groupBy("a", "__leaf").agg(*degree[0]), ["a"], leaves, degree[1])
    left = leads.join(sets.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("elements").alias("ea")).hint("merge"), "a")
    left = copies(left, pieces(F.col("pairs"), STAR), "piece").drop("pairs")
    right = sets.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("elements").alias("eb"))
    both = dealt.join(left.hint("merge"), ["a", "piece"]).join(right.hint("merge"), "b")
    shared = F.size(F.array_intersect("ea", "eb"))
    return both.where(shared >= similarity * (F.col("na") + F.col("nb") - shared) - 1e-9).select("a", "b")


def components(nodes: DataFrame, edges: DataFrame, start: DataFrame | None, leaves: int, shelf: Shelf) -> DataFrame:
    """(node, comp): the smallest node of each connected class, by hooking and pointer jumping.

    Every round is written to the shared folder, so its lineage is one read.
    """
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = shelf.put(both.withColumn("__leaf", leaf_of(F.col("b"), leaves)))
    labels = start if start is not None else shelf.put(nodes.select("node", F.col("node").alias("comp")))
    while True:
        seen = hand_down(both, labels.select(F.col("node").alias("a"), "comp"), ["a"]).groupBy(F.col("b").alias("node")).agg(F.min("comp").alias("near"))
        hooked = labels.join(seen.hint("merge"), "node", "left").select("node", F.col("comp").alias("old"), F.least("comp", F.coalesce("near", "comp")).alias("comp"))
        hooked = shelf.put(hooked.withColumn("__leaf", leaf_of(F.col("node"), leaves)))
        # A class follows the smallest label that any of its nodes has seen.
        roots = hooked.groupBy("old").agg(F.min("comp").alias("root"))
        moved = shelf.put(roots.where("root < old"))
        if moved.isEmpty():
            return labels
        jump = moved.select(F.col("old").alias("root"), F.col("root").alias("next"))
        turned = hand_down(moved.withColumn("__leaf", leaf_of(F.col("old"), leaves)), jump, ["root"], "left")
        moved = shelf.put(turned.select("old", F.coalesce("next", "root").alias("root")))
        labels = shelf.put(hand_down(hooked, moved, ["old"], "left").select("node", F.coalesce("root", "comp").alias("comp")))


def _rest(unresolved: DataFrame, sets: DataFrame, similarity: float, apart: Callable[[str, str, Column], Column], leaves: int, shelf: Shelf) -> DataFrame:
    """Pairs of one bucket and different classes that may still be close, each once.

    An element that no other unresolved node has cannot be shared, so a node with
    u of them shares n - u at most.  Nodes that fail by this bound alone leave
    before the join, pairs that fail by both nodes' bounds inside it.  A node carries its
    buckets (one a band at most), so that a pair is made in the first bucket of those it shares,
    and a parity bitmap, which bounds from below in how many elements two nodes differ.
    A bucket's nodes are dealt over blocks, and a task compares one block with one other.
    """
    nodes = shelf.put(unresolved.groupBy("node", "comp", "n").agg(F.collect_set("bucket").alias("buckets")))
    spread = sets.join(nodes.select("node").hint("merge"), "node").select("node", F.explode("elements").alias("element"))
    alone = spread.groupBy("element").agg(F.count(F.lit(1)).alias("c"), F.any_value("node").alias("node")).where("c = 1").groupBy("node").agg(F.count(F.lit(1)).alias("alone"))
    able = nodes.join(shelf.put(alone).hint("merge"), "node", "left").withColumn("able", F.col("n") - F.coalesce("alone", F.lit(0)))
    able = able.where(F.col("able") >= similarity * F.col("n") - 1e-9).join(sets.select("node", "sketch").hint("merge"), "node")
    able = shelf.put(able.select("node", "comp", "n", "able", "sketch", "buckets", F.explode("buckets").alias("bucket"), leaf_of(F.col("node"), leaves).alias("__leaf")))
    placed = gather_scatter(able, ["bucket"], leaves, [F.count(F.lit(1)).alias("size")], [F.sum("size").alias("size")], F.col("size") > 1)
    blocks = pieces(F.col("size"), BLOCK)
    placed = copies(placed.withColumn("block", F.pmod(F.xxhash64("node"), blocks.cast("long")).cast("int")), blocks, "other")
    placed = placed.withColumns({"low": F.least("block", "other"), "high": F.greatest("block", "other")})
    place = ["bucket", "low", "high"]
    x, y = (placed.select(*place, *[F.col(c).alias(f"{c}{k}") for c in ("node", "comp", "n", "able", "sketch", "buckets", "block")]) for k in "ab")
    differ = F.aggregate(F.zip_with("sketcha", "sketchb", lambda u, v: F.bit_count(u.bitwiseXOR(v))), F.lit(0), lambda t, d: t + d)
    open_ = (F.col("nodea") < F.col("nodeb")) & (F.col("compa") != F.col("compb")) & ~apart("na", "nb", F.least("ablea", "ableb"))
    across = (F.col("low") == F.col("high")) | (F.col("blocka") != F.col("blockb"))
    near = differ * (1 + similarity) <= (1 - similarity) * (F.col("na") + F.col("nb")) + 1e-6
    once = F.array_min(F.array_intersect("bucketsa", "bucketsb")) == F.col("bucket")
    return x.join(y.hint("merge"), place).where(across & open_ & near & once).select(F.col("nodea").alias("a"), F.col("nodeb").alias("b"))


def classes(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: float = 0.8, rows: int = 6, n_bands: int = 32) -> DataFrame:
    """One row per input row: id, class_id (smallest id of its class), class_size, kept.

    Null texts count as empty.  Texts without words form no link and are classes
    of their own.  Rows that repeat an id share class and verdict if their texts do.
    Null ids are never the class id unless a whole class has none.
    """
    leaves, shelf = leaf_count(df.sparkSession), Shelf(df.sparkSession, "near", REST)
    signed = sign(df, width, rows, n_bands, id_col, text_col)
    signed = shelf.put(signed.withColumn("__leaf", leaf_of(F.col("id"), leaves)))
    known = signed.where("node is not null")
    buckets = known.groupBy("node").agg(F.any_value("bands").alias("bands")).select("node", leaf_of(F.col("node"), leaves).alias("__leaf"), F.explode("bands").alias("bucket"))
    buckets = shelf.put(buckets)
    members = gather_scatter(buckets, ["bucket"], leaves, [F.count(F.lit(1)).alias("size")], [F.sum("size").alias("size")], F.col("size") > 1)
    members = shelf.put(members)
    # The better known a node is in its buckets, the more of a group of copies it is close to.
    nodes = shelf.put(members.groupBy("node").agg(F.sum("size").alias("known")))

    firsts = known.groupBy("node").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "mark")).alias("x"))
    wanted = firsts.join(nodes.select("node").hint("merge"), "node").select("x.id", "x.mark", "node")
    docs = df.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).alias("__text")).withColumn("__mark", F.xxhash64("__text"))
    source = docs.join(wanted, docs["__id"].eqNullSafe(wanted["id"]) & (docs["__mark"] == wanted["mark"])).select("__id", "__text", "node")
    sets = shelf.put(elements(source, width).dropDuplicates(["node"]))
    facts = shelf.put(nodes.join(sets.select("node", "n").hint("merge"), "node"))

    def apart(na: str, nb: str, shareable) -> Column:
        """Whether sizes and the elements that could be shared rule the similarity out."""
        most = F.least(na, nb, shareable)
        return most < similarity * (F.col(na) + F.col(nb) - most) - 1e-9

    tried, labels = None, None
    for turn in (1, 2, 3):
        placed = members.select("bucket", "node", "__leaf").join(facts.hint("merge"), "node")
        placed = placed.withColumn("comp", F.col("node")) if labels is None else placed.join(labels.hint("merge"), "node")
        placed = shelf.put(placed)
        lead = F.struct(F.col("known") if turn == 1 else F.lit(0).alias("known"), F.xxhash64("node").alias("h"), "node", "comp", "n")
        first = [F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.max(lead).alias("lead")]
        open_ = gather_scatter(placed, ["bucket"], leaves, first, [F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.max("lead").alias("lead")], F.expr("lo != hi"))
        open_ = shelf.put(open_.select("bucket", "node", "comp", "n", "lead"))
        if open_.isEmpty():
            break
        if turn < 3:
            pairs = open_.where("comp != lead.comp").select(F.col("lead.node").alias("a"), F.col("node").alias("b"), F.col("n").alias("nb"), F.col("lead.n").alias("na"))
            pairs = pairs.where(~apart("na", "nb", F.col("na"))).select("a", "b").distinct()
        else:
            pairs = _rest(open_, sets, similarity, apart, leaves, shelf)
        new = pairs.withColumns({"low": F.least("a", "b"), "high": F.greatest("a", "b")})
        new = shelf.put(new if tried is None else new.join(tried.hint("merge"), ["low", "high"], "left_anti"))
        found = shelf.put(verified(new.select("a", "b"), sets, similarity, leaves))
        seen = new.select("low", "high").distinct()
        tried = seen if tried is None else tried.unionByName(seen)
        labels = components(nodes, found, labels, leaves, shelf)
    if labels is None:
        labels = nodes.select("node", F.col("node").alias("comp"))

    # Node by node, then class by class, and back: a node of many copies and a class of many nodes are spread over leaves.
    held = known.groupBy("node").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies"))
    held = held.join(labels.hint("merge"), "node", "left").select("node", "id", "copies", F.coalesce("comp", "node").alias("comp"), leaf_of(F.col("node"), leaves).alias("__leaf"))
    sums = [F.min("class_id").alias("class_id"), F.sum("size").alias("size")]
    joined = gather_scatter(shelf.put(held), ["comp"], leaves, [F.min("id").alias("class_id"), F.sum("copies").alias("size")], sums, F.col("size") > 1)
    joined = shelf.put(joined.select("node", "class_id", "size"))
    shelf.clear(signed, joined)
    out = hand_down(signed.select("id", "node", "__leaf"), joined, ["node"], "left")
    own = F.col("size").isNull()
    best = F.when(own, F.col("id")).otherwise(F.col("class_id"))
    return out.select(F.col("id").alias(id_col), best.alias("class_id"), F.coalesce("size", F.lit(1)).cast("long").alias("class_size"), F.col("id").eqNullSafe(best).alias("kept"))


def dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """The rows whose id stands for its class, with their own columns."""
    staying = classes(df, id_col, text_col, **how).where("kept").select(F.col(id_col).alias("__kept")).distinct()
    return df.join(staying, df[id_col].eqNullSafe(staying["__kept"]), "left_semi")
