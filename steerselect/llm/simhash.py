"""SimHash near-duplicates by tiled exact comparison.

Fingerprints are compared as 64-bit words with numpy exclusive-or and bit counts.  Two fingerprints within r bits
agree on at least one of r + 1 blocks of their bits, so fingerprints meet only inside buckets of equal blocks; a bucket
is sorted by population count and cut into tiles, and a pair of tiles whose population counts differ by more than r is
skipped, since exclusive-or then leaves more than r bits.  No pair within the radius is lost.  Buckets beyond
``HOT_BUCKET`` fingerprints are spread over tasks as tiles of one population count each.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, slices, text_or_empty, texts, written
from .components import components

HOT_BUCKET = 16384
TILE = 1024
#: Links of a pair of tiles from which on a spanning forest of them is taken.
DENSE = 2 * TILE


def shingle_hashes(text: str | None, size: int = 3, most: int = 1 << 16) -> Iterator[np.ndarray]:
    """XXH64 (seed 42) of each word shingle, repeats included, in arrays of at most ``most``; A-Z count as a-z."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return
    joined, size = b" ".join(words), min(size, len(words))
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    h = xxhash.xxh64_intdigest
    n = len(words) - size + 1
    for i in range(0, n, most):
        k = min(n, i + most)
        yield np.array([h(joined[a:b], 42) for a, b in zip(starts[i:k].tolist(), ends[i + size - 1 : k + size - 1].tolist())], np.uint64)


def fingerprint(text: str | None, size: int = 3) -> int:
    """A bit is 1 where over half of the shingle hashes have it; no words: zero."""
    return majority(shingle_hashes(text, size))


def majority(hashes: Iterable[np.ndarray]) -> int:
    """The bits that over half of all hashes have; of none: zero."""
    ones, n = np.zeros(64, np.int64), 0
    for h in hashes:
        bits = np.unpackbits(h.astype(">u8").view(np.uint8)).reshape(-1, 64)
        ones += bits.sum(0, dtype=np.int64) if len(bits) < 256 else np.add.reduce(bits, 0, dtype=np.uint32)
        n += len(h)
    return int(np.packbits(2 * ones > n).view(">u8")[0]) if n else 0


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3) -> DataFrame:
    """(id, fp): the fingerprint of each row's whole text as a signed long."""

    def run(batches):
        for b in slices(batches):
            fps = np.array([fingerprint(t.as_py(), size) for t in b.column("text")], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(fps)], names=["id", "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, fp long")


def block_keys(fp: Column, radius: int) -> Column:
    """Structs (block, value) of the radius + 1 blocks."""
    cuts = np.linspace(0, 64, radius + 2).astype(int).tolist()
    return F.array(
        *(
            F.struct(F.lit(i).alias("block"), F.shiftrightunsigned(F.shiftleft(fp, 64 - hi), 64 - hi + lo).alias("value"))
            for i, (lo, hi) in enumerate(zip(cuts, cuts[1:]))
        )
    )


def near_pairs(a: np.ndarray, b: np.ndarray, radius: int, same: bool) -> Iterator[np.ndarray]:
    """Rows (i, j, distance) of fingerprints within the radius, one array for each pair of tiles that has some.

    Both sides come sorted by population count; if ``same``, b is a and i < j; else j counts on from len(a).
    """
    ones_a, ones_b = (np.bitwise_count(x).astype(np.int16) for x in (a, b))
    for i in range(0, len(a), TILE):
        x, lo, hi = a[i : i + TILE, None], ones_a[i], ones_a[min(i + TILE, len(a)) - 1]
        for j in range(i if same else 0, len(b), TILE):
            if ones_b[j] > hi + radius or ones_b[min(j + TILE, len(b)) - 1] < lo - radius:
                continue
            far = np.bitwise_count(x ^ b[None, j : j + TILE])
            u, v = np.nonzero(far <= radius)
            if same and j == i:
                u, v = u[u < v], v[u < v]
            if len(u):
                yield np.stack((u + i, v + j + (0 if same else len(a)), far[u, v].astype(np.int64)))


def forest(pairs: Iterator[np.ndarray], dense: int = DENSE) -> tuple[np.ndarray, bool]:
    """The pairs (i, j), or a spanning forest of them where they are dense; whether any were left out."""
    found, total = [np.zeros((3, 0), np.int64)], 0
    for x in pairs:
        total += x.shape[1]
        found.append(spanning(*x, dense))
    kept = spanning(*np.concatenate(found, 1), dense)
    return kept[:2], kept.shape[1] < total


def tile_links(a: np.ndarray, b: np.ndarray, radius: int, same: bool) -> np.ndarray:
    """Index pairs (i, j) of fingerprints within the radius, or a spanning forest of them where they are dense."""
    return forest(near_pairs(a, b, radius, same))[0]


def spanning(u: np.ndarray, v: np.ndarray, distance: np.ndarray, dense: int = DENSE) -> np.ndarray:
    """Rows (u, v, distance): the links, or, where they are many, their spanning forest of least distances.

    Its links are real ones and join the same members, so a dense group yields no more rows than it has members.
    """
    every = np.stack((u, v, distance.astype(np.int64)))
    if len(u) < dense:
        return every
    every = every[:, np.argsort(distance, kind="stable")]
    nodes, ends = np.unique(every[:2], return_inverse=True)
    s, t = ends.reshape(2, -1)
    label, taken, at = np.arange(len(nodes)), [], np.arange(len(s))
    while len(at):
        best = np.full(len(nodes), len(s))
        np.minimum.at(best, label[s[at]], at)
        np.minimum.at(best, label[t[at]], at)
        new = np.unique(best[best < len(s)])
        taken.append(new)
        link = np.stack((label[s[new]], label[t[new]]))
        while True:
            low = np.minimum(label[link[0]], label[link[1]])
            before = label.copy()
            np.minimum.at(label, label[link[0]], low)
            np.minimum.at(label, label[link[1]], low)
            label = label[label]
            if (label == before).all():
                break
        at = at[label[s[at]] != label[t[at]]]
    return every[:, np.unique(np.concatenate(taken))]


def compare(groups: DataFrame, radius: int) -> DataFrame:
    """Links (a, b) inside each (block, value, one, two) of rows sorted by population count.

    Rows of part 0 meet rows of part 1; where there is no part 1, rows of part 0 meet each other.
    """

    def flush(fp: np.ndarray, part: np.ndarray) -> np.ndarray:
        a, b = fp[part == 0], fp[part == 1]
        every = np.concatenate((a, b))
        if len(b):
            u, v = tile_links(a, b, radius, False)
        else:
            u, v = tile_links(a, a, radius, True)
        return np.stack((every[u], every[v]))

    def run(batches):
        held: list[tuple[np.ndarray, ...]] = []

        def emit(links):
            x = links.view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(x[0]), pa.array(x[1])], names=["a", "b"])

        for b in batches:
            if not b.num_rows:
                continue
            cols = {c: b.column(c).to_numpy(zero_copy_only=False) for c in ("block", "value", "one", "two", "fp", "part")}
            key = np.stack([cols[c].astype(np.int64) for c in ("block", "value", "one", "two")])
            fp, part = cols["fp"].astype(np.int64).view(np.uint64), cols["part"]
            if held:
                key, fp, part = np.concatenate((held[0][0], key), 1), np.concatenate((held[0][1], fp)), np.concatenate((held[0][2], part))
            cut = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(0)) + 1
            last = cut[-1] if len(cut) else 0
            out = small_groups(fp[:last], part[:last], cut[:-1], flush)
            if out.shape[1]:
                yield emit(out)
            held = [(key[:, last:], fp[last:], part[last:])]
        if held:
            out = flush(held[0][1], held[0][2])
            if out.shape[1]:
                yield emit(out)

    def small_groups(fp, part, cut, flush):
        if not len(fp):
            return np.zeros((2, 0), np.uint64)
        starts = np.concatenate(([0], cut)).astype(int)
        sizes = np.diff(np.concatenate((starts, [len(fp)])))
        out = []
        twos = starts[sizes == 2]
        if len(twos):
            plain = (part[twos] == 0) & (part[twos + 1] == 0) | (part[twos] != part[twos + 1])
            near = plain & (np.bitwise_count(fp[twos] ^ fp[twos + 1]) <= radius)
            out.append(np.stack((fp[twos[near]], fp[twos[near] + 1])))
        for s, n in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
            out.append(flush(fp[s : s + n], part[s : s + n]))
        return np.concatenate(out, 1) if out else np.zeros((2, 0), np.uint64)

    return groups.mapInArrow(run, "a long, b long")


def banded(prints: DataFrame, radius: int, meet: Callable, schema: str, tile: int = 8192) -> DataFrame:
    """What ``meet(first, second)`` gives for each two tiles within a radius that is too large for blocks.

    A tile packs the rows (``fp`` first) of one population count and one share of the hashes; pairs of tiles are the
    tasks.  Where a tile meets itself, ``second`` is None.
    """
    share = max(1, -(-prints.count() // (tile * 8)))  # a population count holds a tenth of the fingerprints at most
    tiles = prints.groupBy(F.bit_count("fp").alias("ones"), F.pmod(F.xxhash64("fp"), F.lit(share)).alias("sub")).agg(F.sort_array(F.collect_list(F.struct(*prints.columns))).alias("rows"))
    me = F.col("ones").cast("long") * F.lit(share) + F.col("sub")
    near = F.sequence(F.greatest(F.lit(0), F.col("ones") - radius).cast("long") * F.lit(share), (F.least(F.lit(64), F.col("ones") + radius).cast("long") + 1) * F.lit(share) - 1)
    met = tiles.select("rows", me.alias("me"), F.explode(near).alias("other")).select(
        F.least("me", "other").alias("one"), F.greatest("me", "other").alias("two"), (F.col("me") > F.col("other")).alias("second"), "rows"
    )
    spread = met.repartition(F.col("one"), F.col("two")).sortWithinPartitions("one", "two", "second")

    def run(batches):
        first = None
        for b in batches:
            for one, two, second, rows in zip(*(b.column(c) for c in ("one", "two", "second", "rows"))):
                if one.as_py() == two.as_py():
                    yield from meet(rows.values, None)
                elif not second.as_py():
                    first = (one.as_py(), two.as_py(), rows.values)
                elif first is not None and first[:2] == (one.as_py(), two.as_py()):
                    yield from meet(first[2], rows.values)

    return spread.mapInArrow(run, schema)


def column(rows: pa.StructArray, name: str) -> np.ndarray:
    return rows.field(name).to_numpy(zero_copy_only=False)


def banded_links(prints: DataFrame, radius: int, dense: int = DENSE) -> DataFrame:
    """(a, b, dense): ``links`` for a large radius; ``dense`` marks those of tiles where only a spanning forest is given."""

    def meet(first, second):
        a = column(first, "fp").view(np.uint64)
        b = a if second is None else column(second, "fp").view(np.uint64)
        (u, v), less = forest(near_pairs(a, b, radius, second is None), dense)
        every = (a if second is None else np.concatenate((a, b))).view(np.int64)
        if len(u):
            yield pa.RecordBatch.from_arrays([pa.array(every[u]), pa.array(every[v]), pa.array(np.full(len(u), less))], names=["a", "b", "dense"])

    return banded(prints.select("fp"), radius, meet, "a long, b long, dense boolean")


def banded_pairs_apart(prints: DataFrame, radius: int) -> DataFrame:
    """(a, b): every pair of ``fp`` within the radius whose ``root`` differs, or of which one is ``split``."""

    def meet(first, second):
        sides = (first,) if second is None else (first, second)
        fp, root, split = (np.concatenate([column(x, c) for x in sides]) for c in ("fp", "root", "split"))
        a = column(first, "fp").view(np.uint64)
        b = a if second is None else column(second, "fp").view(np.uint64)
        for u, v, _ in near_pairs(a, b, radius, second is None):
            on = (root[u] != root[v]) | split[u] | split[v]
            if on.any():
                yield pa.RecordBatch.from_arrays([pa.array(fp[u[on]]), pa.array(fp[v[on]])], names=["a", "b"])

    return banded(prints.select("fp", "root", "split"), radius, meet, "a long, b long")


def links(prints: DataFrame, radius: int = 2, hot: int = HOT_BUCKET) -> DataFrame:
    """Links (a, b) between distinct fingerprints ``fp`` whose transitive closure is that of all pairs in the radius."""
    if radius > 3:
        return banded_links(prints, radius).select("a", "b")
    rows = prints.select("fp", F.bit_count("fp").alias("ones"), F.explode(block_keys(F.col("fp"), radius)).alias("k")).select("fp", "ones", "k.block", "k.value")
    # the counts hold one row per bucket beyond ``hot``; most corpora have none
    large = written(rows.groupBy("block", "value").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > hot), "hot-buckets")
    key = ["block", "value", "one", "two"]
    if not large.limit(1).count():
        tiled = rows.select("block", "value", F.lit(0).alias("one"), F.lit(0).alias("two"), "fp", "ones", F.lit(0).alias("part"))
    else:
        # a tile of a hot bucket: one population count and a share of the hashes; it meets itself and the tiles at most
        # ``radius`` further on
        both = rows.join(large, ["block", "value"], "left").withColumn("m", F.ceil(F.coalesce("n", F.lit(0)) / F.lit(hot * 4)).cast("int"))
        sub = F.when(F.col("m") > 0, F.pmod(F.xxhash64("fp"), F.col("m"))).otherwise(0).cast("int")
        tile = (F.col("ones") * F.lit(1 << 20) + sub).cast("long")
        near = F.flatten(
            F.transform(
                F.sequence(F.greatest(F.lit(0), F.col("ones") - radius), F.least(F.lit(64), F.col("ones") + radius)),
                lambda p: F.transform(F.sequence(F.lit(0), F.col("m") - 1), lambda s: (p.cast("long") * F.lit(1 << 20) + s).cast("long")),
            )
        )
        meets = F.when(F.col("m") > 0, F.transform(near, lambda t: F.struct(F.least(t, tile).alias("one"), F.greatest(t, tile).alias("two"), (tile > t).cast("int").alias("part")))).otherwise(
            F.array(F.struct(F.lit(0).cast("long").alias("one"), F.lit(0).cast("long").alias("two"), F.lit(0).alias("part")))
        )
        tiled = both.select("block", "value", "fp", "ones", F.explode(meets).alias("t")).select("block", "value", "t.one", "t.two", "fp", "ones", "t.part")
    spread = tiled.repartition(*(F.col(c) for c in key)).sortWithinPartitions(*key, "ones", "fp")
    return compare(spread, radius).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, radius: int = 2, hot: int = HOT_BUCKET) -> DataFrame:
    """Per row: ``id_col``, fingerprint (16 lower-case hex digits), component_id.

    component_id is the smallest id among all rows reachable through links, the row's own group of equal fingerprints
    included.  Null and wordless texts have fingerprint zero and link like any other; null ids never become a component
    id unless a component has no other; repeated rows give repeated results; an empty table gives an empty result.
    """
    table = written(fingerprints(docs, id_col, text_col, size), "fingerprints")
    prints = written(table.groupBy("fp").agg(F.min("id").alias("low")), "prints")
    found = written(links(prints.select("fp"), radius, hot), "links")
    roots = components(found)
    low = prints.join(roots, prints.fp == roots.node, "left").select("fp", F.coalesce("root", "fp").alias("root"), "low")
    lowest = low.groupBy("root").agg(F.min("low").alias("component_id"))
    of = low.select("fp", "root").join(lowest, "root").select("fp", "component_id")
    return table.join(of, "fp").select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def shingle_sets(docs: DataFrame, id_col: str, text_col: str, size: int) -> DataFrame:
    """(id, set): the distinct shingle hashes of each text."""

    def run(batches):
        for b in slices(batches):
            sets = [np.unique(np.concatenate([np.zeros(0, np.uint64), *shingle_hashes(t.as_py(), size)])).view(np.int64) for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(sets, pa.list_(pa.int64()))], names=["id", "set"])

    kind = docs.schema[id_col].dataType.simpleString()
    return texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, set array<long>")


def alike(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose sets have that Jaccard similarity."""
    common = F.size(F.array_intersect("set_a", "set_b"))
    for s in "ab":
        pairs = pairs.join(sets.select(F.col("id").alias(s), F.col("set").alias(f"set_{s}")), s)
    return pairs.filter(common >= F.lit(similarity) * (F.size("set_a") + F.size("set_b") - common)).select("a", "b")


def verified_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 11, size: int = 5, similarity: float = 0.8, dense: int = DENSE) -> DataFrame:
    """(node, root) for every row that has a near copy: links of SimHash whose word shingles are also similar enough.

    Fingerprints of three-word shingles within ``radius`` name the candidates; the Jaccard similarity of the sets of
    ``size``-word shingles, computed over the whole texts, decides.  The root is the group's smallest id.

    Candidates are verified in two passes.  The first takes one row of each fingerprint and, in dense tiles, a spanning
    forest.  The second takes every pair that the first left out and whose ends it has not joined, so no link between
    groups is missed.
    """
    table = written(fingerprints(docs, id_col, text_col), "fingerprints").filter(F.col("id").isNotNull())
    prints = written(table.groupBy("fp").agg(F.min("id").alias("low"), F.count(F.lit(1)).alias("n")), "prints")
    low = {s: prints.select(F.col("fp").alias(s), F.col("low").alias(f"low_{s}")) for s in "ab"}
    near = written(banded_links(prints, radius, dense), "near")
    between = near.join(low["a"], "a").join(low["b"], "b").select(F.col("low_a").alias("a"), F.col("low_b").alias("b"))
    within = table.join(prints, "fp").filter(F.col("id") != F.col("low")).select(F.col("low").alias("a"), F.col("id").alias("b"))
    pairs = written(between.union(within).distinct(), "pairs")
    named = pairs.select(F.col("a").alias(id_col)).union(pairs.select(F.col("b").alias(id_col))).distinct()
    sets = written(shingle_sets(docs.join(named, id_col, "left_semi"), id_col, text_col, size), "shingles")
    joined = written(alike(pairs, sets, similarity), "alike")
    roots = written(components(joined), "roots")
    rest = written(pairs_left_out(table, prints, near, roots, radius), "left-out")
    if not rest.limit(1).count():
        return roots
    more = written(alike(rest, sets, similarity), "alike")
    return components(joined.union(more)) if more.limit(1).count() else roots


def pairs_left_out(table: DataFrame, prints: DataFrame, near: DataFrame, roots: DataFrame, radius: int) -> DataFrame:
    """Pairs (a, b) of ids within the radius that the first pass left out and whose roots differ.

    A fingerprint is split if its rows have several roots.  Left out are pairs of fingerprints in dense tiles, and
    pairs with a row that is not the least of its fingerprint.
    """
    placed = written(table.join(roots.withColumnRenamed("node", "id"), "id", "left").select("id", "fp", F.coalesce("root", "id").alias("root")), "placed")
    shape = placed.groupBy("fp").agg(F.min("root").alias("root"), (F.min("root") != F.max("root")).alias("split"), (F.count(F.lit(1)) > 1).alias("several"))
    shape = written(shape, "shapes")
    dense = near.filter("dense").select(F.explode(F.array("a", "b")).alias("fp")).distinct()
    found = banded_pairs_apart(shape.join(dense, "fp", "left_semi"), radius)
    ends = {s: shape.select(F.col("fp").alias(s), F.col("root").alias(f"root_{s}"), F.col("split").alias(f"split_{s}"), F.col("several").alias(f"several_{s}")) for s in "ab"}
    single = near.join(ends["a"], "a").join(ends["b"], "b").filter("(root_a != root_b or split_a or split_b) and (several_a or several_b)").select("a", "b")
    own = shape.filter("split").select(F.col("fp").alias("a"), F.col("fp").alias("b"))
    fps = found.union(single).union(own).distinct().select(F.col("a").alias("fp_a"), F.col("b").alias("fp_b"))
    for s in "ab":
        fps = fps.join(placed.select(F.col("id").alias(s), F.col("fp").alias(f"fp_{s}"), F.col("root").alias(f"root_{s}")), f"fp_{s}")
    return fps.filter("root_a != root_b and (fp_a != fp_b or a < b)").select("a", "b").distinct()


def keep_one(docs: DataFrame, id_col: str = "doc_id", **how) -> DataFrame:
    """The rows of ``docs`` without those whose near-duplicate group has a smaller id; all columns stay."""
    (a,) = fresh(docs, "dropped")
    gone = verified_groups(docs, id_col, **how).filter(F.col("node") != F.col("root")).select(F.col("node").alias(a))
    return docs.join(gone, docs[id_col] == gone[a], "left_anti")
