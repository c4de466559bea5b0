"""Placement by a hierarchical weighted hash tree.

A tree of regions, racks and shards carries weights; a row descends from the root, and at each level every child
draws ``-ln(u) / weight`` with u a hash of (child, row key): the smallest draw wins.  A child's chance is its share
of the weight, and a change of weights moves rows only between the changed child and its siblings.

A shard that joins later gets a region and a rack of its own (``grown``): no sibling subtree changes its weight, so
rows move only into the new shard.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_or_empty

#: name -> children; a leaf maps to its weight.
Tree = dict[str, "Tree | float"]

SLOT_GROUPS = 4096


def regular_tree(shards: int = 8, per_rack: int = 2, racks_per_region: int = 2) -> Tree:
    """Equal shards numbered from 0, filled rack by rack and region by region."""
    tree: Tree = {}
    for s in range(shards):
        rack, region = s // per_rack, s // (per_rack * racks_per_region)
        tree.setdefault(f"region{region}", {}).setdefault(f"rack{rack}", {})[str(s)] = 1.0
    return tree


def grown(tree: Tree, shard: int, weight: float = 1.0) -> Tree:
    """The tree with one more shard, in a region of its own."""
    return tree | {f"region-of-{shard}": {f"rack-of-{shard}": {str(shard): weight}}}


def weight_of(node: Tree | float) -> float:
    return sum(map(weight_of, node.values())) if isinstance(node, dict) else float(node)


def draw(node: str, key: Column, weight: float) -> Column:
    u = (F.shiftrightunsigned(F.xxhash64(F.concat(F.lit(f"{node}|"), key)), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
    return -F.log(u) / F.lit(weight)


def descend(tree: Tree, key: Column, path: str = "") -> Column:
    """The leaf that ``key`` (a string column) reaches, as an integer column; children of weight 0 are never reached."""
    children = {f"{path}/{n}": (n, c) for n, c in tree.items() if weight_of(c) > 0}
    if not children:
        raise ValueError("a tree needs a leaf of positive weight")
    below = {p: descend(c, key, p) if isinstance(c, dict) else F.lit(int(n)) for p, (n, c) in children.items()}
    if len(below) == 1:
        return next(iter(below.values()))
    draws = {p: draw(p, key, weight_of(c)) for p, (_, c) in children.items()}
    lowest = F.least(*draws.values())
    out = F.lit(None).cast("int")
    for p in reversed(below):
        out = F.when(draws[p] == lowest, below[p]).otherwise(out)
    return out


def place(docs: DataFrame, tree: Tree, larger: Tree | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, size, text_crc32, law, shard, slot, grown_shard.

    The law is ``key``: the id and the tree decide.  A null id is the key "null"; a null text has no bytes.  Slots
    count each shard's rows from 0 without gaps in the order of (a hash of the id, id, crc, size): counted by groups of
    hashes, so no task holds a whole shard.  An id that repeats stays together.  Empty tables give empty results.
    """
    key = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    rows = docs.select(
        F.col(id_col).alias("id"),
        (F.octet_length(text_or_empty(text_col)) + 1).cast("long").alias("size"),
        F.crc32(text_or_empty(text_col).cast("binary")).alias("text_crc32"),
        descend(tree, key).alias("shard"),
        (descend(larger, key) if larger else F.lit(None).cast("int")).alias("grown_shard"),
        F.pmod(F.xxhash64(F.concat(F.lit("slot|"), key)), F.lit(SLOT_GROUPS)).cast("int").alias("part"),
    )
    counts = rows.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("shard", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    inside = Window.partitionBy("shard", "part").orderBy(F.col("id").asc_nulls_first(), "text_crc32", "size")
    return (
        rows.withColumn("nth", F.row_number().over(inside))
        .join(offsets, ["shard", "part"])
        .select(F.col("id").alias(id_col), "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("start") + F.col("nth") - 1).alias("slot"), "grown_shard")
    )
