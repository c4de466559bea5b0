"""Near-duplicates of a Jaccard similarity of word shingles: SimHash tiles inside regions of texts that may be alike.

Of two sets with n and m members and similarity s or more, each has one of the other's members among its
n - ceil(s n) + 1 first ones in any common order.  Rare shingles come first, so few sets meet.  Texts that share one of
their rarest shingles, directly or through others, form a region; each text travels to its region once.  There
fingerprints are compared tile by tile with exclusive-or and bit counts, and what lies within the radius is verified
over the whole sets without leaving the tile: only links that hold leave it, at most one for each text.

The radius follows from the similarity: a bit of a SimHash differs with the angle of the sets over pi, so the chance
that a pair at the very bound lies farther apart is a binomial tail; ``MISS`` bounds it, and it falls fast above the bound.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import begin, fresh, slices, text_or_empty, texts, written
from .components import components
from .simhash import majority, near_pairs, shingle_hashes

#: The chance that a pair of exactly the least similarity is missed.
MISS = 1e-9
#: Texts, and shingle hashes, of one tile; larger regions are cut into several.
TILE, TILE_HASHES = 2048, 1 << 21


def radius_for(similarity: float, miss: float = MISS) -> int:
    """The least radius beyond which a pair of that Jaccard similarity lies with a chance of at most ``miss``."""
    p = math.acos(min(1.0, 2 * similarity / (1 + similarity))) / math.pi
    tail = 1.0
    for r in range(65):
        tail -= math.comb(64, r) * p**r * (1 - p) ** (64 - r)
        if tail <= miss:
            return r
    return 64


def prints(docs: DataFrame, id_col: str, text_col: str, size: int) -> DataFrame:
    """(id, fp, n, set): the SimHash of the distinct shingles of each text, their number, and their hashes in order."""

    def run(batches):
        begin("similar")
        for b in slices(batches, most_bytes=4 << 20):
            sets = [np.unique(np.concatenate([np.zeros(0, np.uint64), *shingle_hashes(t.as_py(), size)])) for t in b.column("text")]
            fps = np.array([majority([s]) for s in sets], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(fps), pa.array([len(s) for s in sets], pa.int64()), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["id", "fp", "n", "set"])

    kind = docs.schema[id_col].dataType.simpleString()
    return texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, fp long, n long, set array<long>")


def sparse_prefixes(docs: DataFrame, id_col: str, text_col: str, size: int, similarity: float) -> DataFrame:
    """(id, need, keys): of each text's shingle hashes the first in hash order, at least ``need`` of which any similar set shares.

    Sets of n and more hashes with that Jaccard similarity share o = ceil(similarity * n) of them, so of the first
    n - o + need in a common order they share ``need``.  A set without words has one key of its own.
    """

    def run(batches):
        begin("similar")
        for b in slices(batches):
            needs, keys = [], []
            for t in b.column("text"):
                h = np.unique(np.concatenate([np.zeros(0, np.uint64), *shingle_hashes(t.as_py(), size)]))
                least = shared_least(len(h), similarity)
                needs.append(max(1, min(least, len(h) // 10)))
                keys.append(h[: len(h) - least + needs[-1]].view(np.int64) if len(h) else np.zeros(1, np.int64))
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(needs, pa.int32()), pa.array(keys, pa.list_(pa.int64()))], names=["id", "need", "keys"])

    kind = docs.schema[id_col].dataType.simpleString()
    return texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, need int, keys array<long>")


def shared_least(n: int, similarity: float) -> int:
    return int(np.ceil(similarity * n - 1e-9))


def with_company(docs: DataFrame, id_col: str, text_col: str, size: int, similarity: float) -> DataFrame:
    """(id) of the texts that may have a near copy: enough of their first hashes occur in another text too."""
    first = written(sparse_prefixes(docs, id_col, text_col, size, similarity), "first-shingles").filter(F.col("id").isNotNull())
    marked = first.withColumn("mark", F.xxhash64("id", "keys"))
    rows = marked.select("mark", F.explode("keys").alias("h"))
    several = rows.groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("h")
    held = rows.join(several, "h", "left_semi").groupBy("mark").agg(F.count(F.lit(1)).alias("n"))
    return marked.select("id", "mark", "need").join(held, "mark").filter("n >= need").select("id").distinct()


def distinct_sets(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One row, of the least id, for each distinct set; and links (a, b) of the other ids that have it."""
    mark = F.struct("n", "fp", F.xxhash64("set").alias("x"), F.hash("set").alias("y"))
    marked = sets.withColumn("mark", mark)
    heads = written(marked.groupBy("mark").agg(F.min("id").alias("id"), F.first("fp").alias("fp"), F.first("n").alias("n"), F.first("set").alias("set")), "distinct-sets")
    copies = marked.select("id", "mark").join(heads.select("mark", F.col("id").alias("head")), "mark").filter("id != head")
    return heads.select("id", "fp", "n", "set"), copies.select(F.col("id").alias("a"), F.col("head").alias("b")).distinct()


def rare_prefixes(sets: DataFrame, similarity: float) -> DataFrame:
    """(h, id): of each set the rarest hashes, one of which any similar set has among its rarest.

    Hashes are ordered by the number of sets that hold them; those of one set only come first and meet nothing.
    """
    rows = sets.select("id", F.xxhash64("id", "n", "fp").alias("mark"), "n", F.explode(F.when(F.col("n") > 0, F.col("set")).otherwise(F.array(F.lit(0).cast("long")))).alias("h"))
    held = rows.groupBy("h").agg(F.count(F.lit(1)).alias("held")).filter("held > 1")
    shared = rows.join(held, "h").groupBy("id", "mark", "n").agg(F.sort_array(F.collect_list(F.struct("held", "h"))).alias("order"))
    least = F.ceil(F.lit(similarity) * F.col("n") - 1e-9)
    room = F.col("n") - least + 1 - F.greatest(F.lit(0), F.col("n") - F.size("order"))
    return shared.filter(room > 0).select("id", F.explode(F.slice("order", F.lit(1), room.cast("int"))).alias("k")).select("k.h", "id").distinct()


def regions(rare: DataFrame) -> DataFrame:
    """(node, root) of the ids that share a hash with another one, directly or through others."""
    low = rare.groupBy("h").agg(F.min("id").alias("low"))
    return components(rare.join(low, "h").filter("id != low").select(F.col("id").alias("a"), F.col("low").alias("b")).distinct())


def similar_in(fp: np.ndarray, sets: list[np.ndarray], side: np.ndarray, root: np.ndarray, radius: int, similarity: float, dense: int) -> tuple[np.ndarray, np.ndarray]:
    """Links (u, v) between members of a tile, or of two, that join whatever is similar enough; a forest, no more.

    Only members of different roots need to be joined, and, if there are two sides, only across them.  Fingerprints
    within the radius are candidates.  They are verified in order of distance, ``dense`` for each member at a time, and
    what has been joined meanwhile is left out.
    """
    n = len(fp)
    label = np.unique(root, return_inverse=True)[1]
    by = np.argsort(np.bitwise_count(fp), kind="stable")
    cut = bool(side.any())
    parts = [by[side[by] == 0], by[side[by] == 1]] if cut else [by, by]
    every = np.concatenate(parts) if cut else by
    at: list[np.ndarray] = [np.zeros((3, 0), np.int64)]
    for x in near_pairs(fp[parts[0]], fp[parts[1]], radius, not cut):
        u, v = every[x[0]], every[x[1]]
        on = label[u] != label[v]
        at.append(np.stack((u[on], v[on], x[2][on])))
    u, v, far = np.concatenate(at, 1)
    order = np.argsort(far, kind="stable")
    u, v = u[order], v[order]
    shared = SharedCounts(sets)
    out_u, out_v = [], []

    def join(a, b):
        alike = shared.of(a, b) * (1 + similarity) >= similarity * (shared.sizes[a] + shared.sizes[b]) - 1e-9
        for i, j in zip(a[alike].tolist(), b[alike].tolist()):
            if label[i] != label[j]:
                out_u.append(i)
                out_v.append(j)
                label[label == label[j]] = label[i]

    near = dense * n
    join(u[:near], v[:near])
    u, v = u[near:], v[near:]
    on = np.flatnonzero(label[u] != label[v])
    on = on[np.argsort(u[on], kind="stable")]
    for some in np.split(on, np.flatnonzero(np.diff(u[on])) + 1):  # the rest, one member with all its candidates at a time
        some = some[label[u[some]] != label[v[some]]]
        join(u[some], v[some])
    return np.array(out_u, np.int64), np.array(out_v, np.int64)


class SharedCounts:
    """How many members sets share: bit vectors for members of many sets, lists of holders for the others."""

    def __init__(self, sets: list[np.ndarray]) -> None:
        self.sets, self.sizes, self.index = sets, np.array([len(s) for s in sets], np.int64), None

    def _indexed(self) -> tuple:
        if self.index is None:
            n = len(self.sets)
            _, term, held = np.unique(np.concatenate(self.sets), return_inverse=True, return_counts=True)
            owner = np.repeat(np.arange(n), self.sizes)
            often = held > max(8, n // 64)
            on = often[term]
            place = np.cumsum(often) - 1
            bits = np.zeros((n, -(-int(often.sum()) // 8) * 8), bool)
            bits[owner[on], place[term[on]]] = True
            packed = np.packbits(bits, axis=1)
            packed = np.pad(packed, ((0, 0), (0, -packed.shape[1] % 8))).view(np.uint64)
            seldom = ~on & (held[term] > 1)
            place = np.cumsum(~often) - 1
            term, owner = place[term[seldom]], owner[seldom]
            held = np.bincount(term, minlength=int((~often).sum()))
            own = np.split(term, np.cumsum(np.bincount(owner, minlength=n))[:-1])
            self.index = packed, own, owner[np.argsort(term, kind="stable")], np.cumsum(held) - held, held
        return self.index

    def of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if len(a) < 8 or self.index is None and len(a) < 4 * len(self.sets):
            return np.array([len(np.intersect1d(self.sets[i], self.sets[j], True)) for i, j in zip(a.tolist(), b.tolist())], np.int64)
        bits, own, owners, starts, held = self._indexed()
        out, order = np.empty(len(a), np.int64), np.argsort(a, kind="stable")
        for some in np.split(order, np.flatnonzero(np.diff(a[order])) + 1):
            i, js = a[some[0]], b[some]
            n = held[own[i]]
            ends = np.cumsum(n)
            met = owners[np.repeat(starts[own[i]] - (ends - n), n) + np.arange(ends[-1] if len(ends) else 0)]
            out[some] = np.bincount(met, minlength=len(self.sets))[js] + np.bitwise_count(bits[js] & bits[i]).sum(1, dtype=np.int64)
        return out


def compare(rows: DataFrame, radius: int, similarity: float, dense: int) -> DataFrame:
    """(a, b): links of similar texts inside each (region, one, two) of ``rows`` (with side, id, root, fp, set)."""
    key = ("region", "one", "two")
    kind = rows.schema["id"].dataType.simpleString()

    def settle(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if sum(b.num_rows for b in held) < 2:
            return
        ids = pa.concat_arrays([b.column("id") for b in held])
        fp, side, root = (np.concatenate([b.column(c).to_numpy(zero_copy_only=False) for b in held]) for c in ("fp", "side", "mark"))
        sets = [x.values.to_numpy(zero_copy_only=False).view(np.uint64) for b in held for x in b.column("set")]
        u, v = similar_in(fp.view(np.uint64), sets, side, root, radius, similarity, dense)
        if len(u):
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(u)), ids.take(pa.array(v))], names=["a", "b"])

    def run(batches):
        begin("similar")
        now, held = None, []
        for b in batches:
            if not b.num_rows:
                continue
            keys = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("code", "one", "two")])
            cuts = [0, *(np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(0)) + 1).tolist(), b.num_rows]
            for i, j in zip(cuts, cuts[1:]):
                own = tuple(keys[:, i].tolist())
                if own != now:
                    yield from settle(held)
                    now, held = own, []
                held.append(b.slice(i, j - i))
        yield from settle(held)

    # regions and roots are compared as 64-bit hashes; regions that share one would only meet in one tile
    spread = rows.repartition(*(F.col(c) for c in key)).sortWithinPartitions(*key)
    cols = (F.xxhash64("region").alias("code"), "one", "two", "side", "id", F.xxhash64("root").alias("mark"), "fp", "set")
    return texts(spread, *cols).mapInArrow(run, f"a {kind}, b {kind}")


def links_in_regions(sets: DataFrame, of: DataFrame, radius: int, similarity: float, dense: int, tile: int, tile_hashes: int) -> DataFrame:
    """(a, b): links between the ids of each region, which join whatever is similar enough there.

    A region of several tiles is compared tile by tile first.  Then one text of each group found so far stands for it, as
    long as that joins groups and shortens the list; what is still apart is compared between any two tiles, so that no
    link is lost.
    """
    members = written(sets.join(of.select(F.col("node").alias("id"), F.col("root").alias("region")), "id"), "members")
    shape = members.groupBy("region").agg(F.count(F.lit(1)).alias("texts"), F.sum("n").alias("hashes"))
    tiles = F.greatest(F.ceil(F.col("texts") / F.lit(tile)), F.ceil(F.col("hashes") / F.lit(tile_hashes))).cast("long")
    shape = written(shape.select("region", F.greatest(tiles, F.lit(1).cast("long")).alias("tiles")).filter("tiles > 1"), "large-regions")
    placed = members.join(shape, "region", "left").withColumn("tiles", F.coalesce("tiles", F.lit(1).cast("long")))

    def alone(rows: DataFrame, by: str) -> DataFrame:
        own = F.pmod(F.xxhash64(by), F.col("tiles"))
        return rows.select("region", own.alias("one"), own.alias("two"), F.lit(0).alias("side"), "id", "root", "fp", "set")

    found = written(compare(alone(placed.withColumn("root", F.col("id")), "id"), radius, similarity, dense), "links")
    if not shape.limit(1).count():
        return found
    large = members.join(shape, "region")
    groups = None
    for _ in range(8):
        rooted = written(large.join(components(found).withColumnRenamed("node", "id"), "id", "left").withColumn("root", F.coalesce("root", "id")), "rooted")
        before, groups = groups, rooted.agg(F.countDistinct("region", "root")).first()[0]
        several = rooted.groupBy("region").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low != high").select("region")
        rooted = rooted.join(several, "region", "left_semi")
        if not rooted.limit(1).count():
            return found
        if before is not None and groups > 0.9 * before:
            break
        heads = rooted.filter(F.col("id") == F.col("root")).drop("tiles")
        fewer = heads.groupBy("region").agg(F.greatest(F.lit(1), F.ceil(F.count(F.lit(1)) / F.lit(tile)), F.ceil(F.sum("n") / F.lit(tile_hashes))).cast("long").alias("tiles"))
        found = written(found.union(compare(alone(heads.join(fewer, "region"), "id"), radius, similarity, dense)).distinct(), "links")
    own = F.pmod(F.xxhash64("id"), F.col("tiles"))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("tiles") - 1)).alias("other")
    pairs = rooted.select("region", "id", "root", "fp", "set", own.alias("own"), other).filter("own != other")
    across = pairs.select("region", F.least("own", "other").alias("one"), F.greatest("own", "other").alias("two"), (F.col("own") > F.col("other")).cast("int").alias("side"), "id", "root", "fp", "set")
    return written(found.union(compare(across, radius, similarity, dense)).distinct(), "links")


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5, similarity: float = 0.8, dense: int = 16, miss: float = MISS, tile: int = TILE, tile_hashes: int = TILE_HASHES) -> DataFrame:
    """(node, root) for every row that has a near copy: the sets of ``size``-word shingles, over whole texts, are similar enough.

    The root is the group's smallest id.  Null and wordless texts are copies of each other; rows with a null id take no
    part; where an id repeats, a link of any of its texts counts; an empty table gives an empty result.
    """
    named = written(with_company(docs, id_col, text_col, size, similarity), "company").withColumnRenamed("id", id_col)
    sets, copies = distinct_sets(written(prints(docs.join(named, id_col, "left_semi"), id_col, text_col, size), "shingles"))
    of = regions(written(rare_prefixes(sets, similarity), "rare-shingles"))
    return components(links_in_regions(sets, of, radius_for(similarity, miss), similarity, dense, tile, tile_hashes).union(copies))


def keep_one(docs: DataFrame, id_col: str = "doc_id", **how) -> DataFrame:
    """The rows of ``docs`` without those whose group of similar texts has a smaller id; all columns stay.

    Rows with a null id stay; what ``similar_groups`` says of nulls, empty and repeated texts holds.
    """
    (a,) = fresh(docs, "dropped")
    gone = similar_groups(docs, id_col, **how).filter(F.col("node") != F.col("root")).select(F.col("node").alias(a))
    return docs.join(gone, docs[id_col] == gone[a], "left_anti")
