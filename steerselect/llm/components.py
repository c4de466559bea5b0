"""Connected components by alternating large-star and small-star steps, as joins and aggregates.

Each step writes its links to the shared folder.  Hot nodes are safe: a node's smallest neighbour comes from a
map-side combined minimum, and the join that follows is one that adaptive execution may split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def _star(links: DataFrame, large: bool) -> DataFrame:
    """Large: joins each node's larger neighbours to its smallest one; small: joins a node and its smaller ones to it."""
    ends = links.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo"))
    if large:
        sides = ends.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(ends.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
    else:
        sides = ends.select(F.col("hi").alias("u"), F.col("lo").alias("v"))
    lowest = sides.groupBy("u").agg(F.min("v").alias("m"))
    met = sides.join(lowest, "u").select("u", "v", F.least("u", "m").alias("m"))
    if large:
        out = met.filter(F.col("v") > F.col("u")).select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = met.select(F.col("v").alias("a"), F.col("m").alias("b")).union(met.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return out.filter(F.col("a") != F.col("b")).distinct()


def components(links: DataFrame, most_rounds: int = 100) -> DataFrame:
    """(node, root): the smallest node of each component, for every node of a link (a, b)."""
    now = links.select("a", "b").filter(F.col("a") != F.col("b"))
    state = None
    for _ in range(most_rounds):
        now = written(_star(_star(now, True), False), "stars")
        last, state = state, tuple(now.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(a, b))"), F.sum(F.pmod(F.xxhash64("b", "a"), F.lit(1 << 31)))).first())
        if state == last or not state[0]:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
    raise RuntimeError(f"components are not settled after {most_rounds} rounds")
