"""Removal of repeated word windows by super-k-mer partitioning.

A window is ``size`` consecutive words.  Its minimiser is the least hash of the word m-grams in it, so equal windows
have equal minimisers.  Consecutive windows that share one occurrence of a minimiser travel as one packed string to the
minimiser's bucket, where the bucket's windows are sorted and counted exactly, by their words.  Equal windows never share
an occurrence, not even in periodic text.

A first pass counts minimisers alone (eight bytes each).  Where one occurs once its windows repeat nowhere, and a
Bloom filter keeps most of them from being shipped; its size has a bound, beyond which it lets more of them pass.
Super-k-mers of the same words are settled where they are read: their windows repeat, so their words are marked in ranges,
one list for a text, and a single copy travels, for others to be found by.
Minimisers above a share of all super-k-mers are hot; there are at most ``1 / HOT_SHARE`` of those, whatever the
corpus.  Their super-k-mers are first counted by their whole words, with map-side combined counts; only distinct ones
are cut into windows, which are dealt out by their own words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, text_or_empty, texts, written

SIZE, MINI = 35, 4
HOT_SHARE, HOT_LEAST = 1e-6, 8000
FILTER_BYTES, RANGE_BYTES = 32 << 20, 1 << 18
#: Texts that a worker cuts at once; their super-k-mers take several times as much.
STEP_BYTES = 2 << 20


def words_of(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split()


def hashed_words(column: pa.Array) -> list[np.ndarray]:
    """The hash of each word of each text; different words of the column are hashed once."""
    split = pc.ascii_split_whitespace(column)
    coded = split.flatten().dictionary_encode()
    h = np.array([xxhash.xxh64_intdigest(w, 7) for w in coded.dictionary.cast(pa.binary()).to_pylist()], np.uint64)
    empty = coded.dictionary.index("").as_py()
    at, ends = coded.indices.to_numpy(zero_copy_only=False), split.offsets.to_numpy() - split.offsets[0].as_py()
    out = []
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist()):
        own = at[a:b]
        out.append(h[own[own != empty] if empty >= 0 else own])
    return out


def super_kmers(words: list[bytes], size: int = SIZE, mini: int = MINI) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first window, number of windows, minimiser) of each run of windows with one occurrence of a minimiser."""
    return runs_of(np.array([xxhash.xxh64_intdigest(w, 7) for w in words], np.uint64), size, mini)


def runs_of(h: np.ndarray, size: int, mini: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same from the hashes of the words."""
    n = len(h) - size + 1
    if n < 1:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.uint64))
    odd = np.uint64(0x9E3779B97F4A7C15)
    grams = h[: len(h) - mini + 1].copy()
    for k in range(1, mini):  # order matters: multiply, then mix in the next word
        grams = grams * odd + h[k : len(h) - mini + 1 + k]
    grams ^= grams >> np.uint64(29)
    grams *= np.uint64(0xBF58476D1CE4E5B9)
    grams ^= grams >> np.uint64(32)
    span, width, low = size - mini + 1, 1, grams
    at = np.arange(len(grams))

    def least(shift: int, count: int) -> None:  # minima of windows wider by ``shift``, the leftmost among equals
        nonlocal low, at
        left = low[:count] <= low[shift : shift + count]
        low, at = np.where(left, low[:count], low[shift : shift + count]), np.where(left, at[:count], at[shift : shift + count])

    while width * 2 <= span:
        least(width, len(low) - width)
        width *= 2
    if width < span:
        least(span - width, n)
    starts = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    return starts, np.diff(np.concatenate((starts, [n]))), low[starts]


class Bloom:
    """A Bloom filter of 64-bit hashes with three probes."""

    def __init__(self, bits: np.ndarray) -> None:
        self.bits, self.n = bits, np.uint64(len(bits) * 8)

    @staticmethod
    def probes(h: np.ndarray, n: np.uint64) -> Iterator[np.ndarray]:
        step = (h >> np.uint64(33)) | np.uint64(1)
        for k in range(3):
            yield (h + np.uint64(k) * step) % n

    def holds(self, h: np.ndarray) -> np.ndarray:
        out = np.ones(len(h), bool)
        for p in self.probes(h, self.n):
            out &= (self.bits[p >> np.uint64(3)] >> (p & np.uint64(7)).astype(np.uint8) & 1).astype(bool)
        return out


def _bloom(repeated: DataFrame, count: int) -> Bloom:
    """The filter of a table of hashes ``m``, ten bits each while that stays within FILTER_BYTES.

    Workers set the bits of one range of bytes each, so the driver gets the filter's bytes and nothing else.
    """
    size = min(max(64, count * 10 // 8), FILTER_BYTES)
    ranges = max(1, -(-size // RANGE_BYTES))
    n = np.uint64(size * 8)

    def dealt(batches):
        for b in batches:
            h = b.column("m").to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            at = np.concatenate(list(Bloom.probes(h, n))).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(at // (RANGE_BYTES * 8)), pa.array(at)], names=["part", "bit"])

    def filled(batches):
        bits: dict[int, np.ndarray] = {}
        for b in batches:
            part, at = (b.column(c).to_numpy(zero_copy_only=False) for c in ("part", "bit"))
            for k in np.unique(part).tolist():
                own = bits.setdefault(k, np.zeros(min(RANGE_BYTES, size - k * RANGE_BYTES), np.uint8))
                x = at[part == k] - k * RANGE_BYTES * 8
                np.bitwise_or.at(own, x >> 3, (1 << (x & 7)).astype(np.uint8))
        yield pa.RecordBatch.from_arrays([pa.array(list(bits), pa.int64()), pa.array([x.tobytes() for x in bits.values()], pa.binary())], names=["part", "bits"])

    rows = repeated.mapInArrow(dealt, "part long, bit long").repartition(ranges, "part").mapInArrow(filled, "part long, bits binary")
    bits = np.zeros(size, np.uint8)
    for b in rows.toArrow().to_batches():  # FILTER_BYTES at most
        for k, x in zip(b.column("part").to_pylist(), b.column("bits").to_pylist()):
            bits[k * RANGE_BYTES : k * RANGE_BYTES + len(x)] |= np.frombuffer(x, np.uint8)
    return Bloom(bits)


def minimisers(docs: DataFrame, size: int, mini: int) -> DataFrame:
    def run(batches):
        for b in slices(batches, most_bytes=STEP_BYTES):
            got = [runs_of(h, size, mini)[2] for h in hashed_words(b.column("text"))]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.uint64), *got]).view(np.int64))], names=["m"])

    return texts(docs, "text").mapInArrow(run, "m long")


def packed_runs(docs: DataFrame, repeated, hot, size: int, mini: int) -> DataFrame:
    """The super-k-mers whose minimiser may repeat, and what can be settled where they are read.

    A row with words is a super-k-mer (key, at, n, m, hot, words, times); if its words come several times in a batch, one
    row without a key stands for all of them.  A row with spans lists the ranges (first, last) of repeated words of a key.
    ``repeated`` and ``hot`` are broadcast: the filter, and hot minimisers in ascending order.
    """
    names = ["key", "at", "n", "m", "hot", "words", "times"]
    kinds = (pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary(), pa.int64())
    span = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))

    def run(batches):
        maybe, warm = repeated.value, hot.value
        for b in slices(batches, most_bytes=STEP_BYTES):
            found: dict[bytes, list[tuple]] = {}  # words -> (key, at, n, m, hot) of all that have them
            for key, t, h in zip(b.column("key").to_pylist(), b.column("text"), hashed_words(b.column("text"))):
                starts, lengths, low = runs_of(h, size, mini)
                on = maybe.holds(low)
                starts, lengths, low = starts[on], lengths[on], low[on]
                if not len(starts):
                    continue
                is_hot = warm[np.minimum(np.searchsorted(warm, low), len(warm) - 1)] == low if len(warm) else np.zeros(len(low), bool)
                words = words_of(t.as_py())
                joined = b" ".join(words)
                ends = np.cumsum([len(w) + 1 for w in words]) - 1
                begins = np.concatenate(([0], ends[:-1] + 1))[starts].tolist()
                ends = ends[starts + lengths + size - 2].tolist()
                for i, j, *row in zip(begins, ends, starts.tolist(), lengths.tolist(), low.view(np.int64).tolist(), is_hot.tolist()):
                    found.setdefault(joined[i:j], []).append((key, *row))
            cols: list[list] = [[] for _ in names]
            marked: dict[bytes, list[tuple[int, int]]] = {}
            for words, rows in found.items():
                key, at, n, m, w = rows[0]
                for c, v in zip(cols, (key if len(rows) == 1 else None, at, n, m, w, words, len(rows))):
                    c.append(v)
                if len(rows) > 1:
                    for key, at, n, _, _ in rows:
                        marked.setdefault(key, []).append((at, at + n + size - 2))
            for i in range(0, len(cols[0]), 10_000):
                part = [pa.array(c[i : i + 10_000], t) for c, t in zip(cols, kinds)]
                yield pa.RecordBatch.from_arrays([*part, pa.nulls(len(part[0]), span)], names=[*names, "spans"])
            if marked:
                lists = [[{"first": a, "last": z} for a, z in merged_ranges(x)] for x in marked.values()]
                yield pa.RecordBatch.from_arrays([pa.array(marked, kinds[0]), *(pa.nulls(len(marked), t) for t in kinds[1:]), pa.array(lists, span)], names=[*names, "spans"])
            del cols, found, marked
            pa.default_memory_pool().release_unused()

    return texts(docs, "key", "text").mapInArrow(run, "key binary, at long, n long, m long, hot boolean, words binary, times long, spans array<struct<first: long, last: long>>")


def merged_ranges(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Ranges joined where they meet."""
    out: list[tuple[int, int]] = []
    for a, z in sorted(ranges):
        if out and a <= out[-1][1] + 1:
            out[-1] = out[-1][0], max(z, out[-1][1])
        else:
            out.append((a, z))
    return out


def repeats_in_buckets(runs: DataFrame, size: int) -> DataFrame:
    """(key, first, last) of word ranges covered by windows that occur more than once in their minimiser's bucket."""

    def settle(group: list[tuple]) -> Iterator[tuple]:
        """Sorts the windows of a bucket by their words; equal ones are neighbours then."""
        if len(group) < 2:
            return
        windows = sorted((w, r, i) for r, (*_, words, _) in enumerate(group) for i, w in enumerate(windows_in(words, size)))
        on: dict[int, list[int]] = {}
        start = 0
        for k in range(1, len(windows) + 1):
            if k == len(windows) or windows[k][0] != windows[start][0]:
                same = windows[start:k]
                if len(same) > 1 or group[same[0][1]][-1] > 1:
                    for _, r, i in same:
                        if group[r][0] is not None:
                            on.setdefault(r, []).append(i)
                start = k
        for r, places in on.items():
            key, at, *_ = group[r]
            for a, z in merged_ranges([(at + i, at + i + size - 1) for i in places]):
                yield key, a, z

    def run(batches):
        held: list[tuple] = []
        now = None
        for b in batches:
            out = []
            for key, at, m, words, times in zip(*(b.column(c).to_pylist() for c in ("key", "at", "m", "words", "times"))):
                if m != now:
                    out += settle(held)
                    held, now = [], m
                held.append((key, at, words, times))
            if out:
                yield batch(out)
        if out := list(settle(held)):
            yield batch(out)

    def batch(rows):
        k, f, t = zip(*rows)
        return pa.RecordBatch.from_arrays([pa.array(k, pa.binary()), pa.array(f, pa.int64()), pa.array(t, pa.int64())], names=["key", "first", "last"])

    spread = runs.filter(~F.col("hot")).select("key", "at", "m", "words", "times").repartition("m").sortWithinPartitions("m")
    return spread.mapInArrow(run, "key binary, first long, last long")


def windows_in(words: bytes, size: int) -> list[bytes]:
    """The windows of a packed super-k-mer, in order."""
    w = words.split(b" ")
    ends = np.cumsum([len(x) + 1 for x in w]) - 1
    begins = [0, *(ends[:-1] + 1).tolist()]
    ends = ends.tolist()
    return [words[begins[i] : ends[i + size - 1]] for i in range(len(w) - size + 1)]


def repeats_of_hot(runs: DataFrame, size: int) -> DataFrame:
    """The same for super-k-mers of hot minimisers, however often one occurs.

    Where the whole words of one occur twice, so do all its windows.  The others are compared window by window with all
    distinct super-k-mers; a super-k-mer has at most ``size`` windows, so lists of them are short.
    """
    run = F.unhex(F.md5("words"))
    hot = runs.filter("hot").select("key", "at", "n", "words", "times")
    lines = written(hot.groupBy("words").agg(F.first("n").alias("n"), F.sum("times").alias("times")).withColumn("run", run), "hot-runs")

    def cut(batches):
        for b in slices(batches, "words", 1 << 20):
            runs_, ats, out, times = [], [], [], []
            for r, words, c in zip(b.column("run").to_pylist(), b.column("words").to_pylist(), b.column("times").to_pylist()):
                for at, w in enumerate(windows_in(words, size)):
                    runs_.append(r)
                    ats.append(at)
                    out.append(w)
                    times.append(c)
            yield pa.RecordBatch.from_arrays([pa.array(runs_, pa.binary()), pa.array(ats, pa.int64()), pa.array(out, pa.binary()), pa.array(times, pa.int64())], names=["run", "at", "window", "times"])

    windows = texts(lines, "run", "words", "times").mapInArrow(cut, "run binary, at long, window binary, times long")
    twice = windows.groupBy("window").agg(F.sum("times").alias("n")).filter("n > 1").select("window")
    single = windows.filter("times = 1").join(twice, "window").groupBy("run").agg(F.collect_list(F.struct(F.col("at").alias("first"), F.col("at").alias("last"))).alias("parts"))
    whole = lines.filter("times > 1").select("run", F.array(F.struct(F.lit(0).cast("long").alias("first"), (F.col("n") - 1).alias("last"))).alias("parts"))
    # each super-k-mer that is not settled yet meets one row
    met = hot.filter(F.col("key").isNotNull()).select("key", "at", run.alias("run")).join(whole.union(single), "run")
    part = F.explode("parts").alias("part")
    return met.select("key", "at", part).select("key", (F.col("at") + F.col("part.first")).alias("first"), (F.col("at") + F.col("part.last") + size - 1).alias("last"))


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE, mini: int = MINI, hot_share: float = HOT_SHARE, hot_least: int = HOT_LEAST) -> DataFrame:
    """Per row: id, n_words, n_removed, kept (the words that stay, joined by single spaces).

    Words are runs of characters other than U+0020 and U+0009 to U+000D.  A word goes if a window over it has the same
    words as a window that starts anywhere else in the input.  Null texts have no words; rows that repeat, ids included,
    repeat each other's windows; null ids are kept; an empty table gives an empty result.
    """
    # rows are named by id and text, so repeated rows share a name and, rightly, a result
    key = F.unhex(F.md5(F.concat(F.coalesce(F.col(id_col).cast("string"), F.lit("null")), F.lit("|"), text_or_empty(text_col))))
    base = docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text"), key.alias("key"))
    counts = written(minimisers(base, size, mini).groupBy("m").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "minimisers")
    distinct, total = counts.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    limit = max(hot_least, int(total * hot_share))
    hot = np.sort(counts.filter(F.col("n") > limit).select("m").toArrow().column("m").to_numpy().astype(np.int64).view(np.uint64))  # 1 / hot_share at most
    send = docs.sparkSession.sparkContext.broadcast  # FILTER_BYTES, and 8 bytes for each hot minimiser
    shipped = written(packed_runs(base, send(_bloom(counts.select("m"), distinct)), send(hot), size, mini), "super-kmers")
    runs = shipped.filter(F.col("words").isNotNull()).drop("spans")
    found = repeats_in_buckets(runs, size)
    if len(hot):
        found = found.union(repeats_of_hot(runs, size))
    lists = found.groupBy("key").agg(F.collect_list(F.struct("first", "last")).alias("spans"))
    lists = lists.union(shipped.filter(F.col("spans").isNotNull()).select("key", "spans"))
    spans = written(lists.groupBy("key").agg(F.flatten(F.collect_list("spans")).alias("spans")), "spans")

    def cut(batches):
        for b in slices(batches, most_bytes=STEP_BYTES):
            n_words, removed, kept = [], [], []
            for t, spans in zip(b.column("text"), b.column("spans").to_pylist()):
                words = words_of(t.as_py())
                n_words.append(len(words))
                if spans:
                    edge = np.zeros(len(words) + 1, np.int64)
                    at = np.array([(s["first"], s["last"]) for s in spans])
                    np.add.at(edge, at[:, 0], 1)
                    np.add.at(edge, at[:, 1] + 1, -1)
                    words = [w for w, c in zip(words, np.cumsum(edge[:-1]).tolist()) if not c]
                removed.append(n_words[-1] - len(words))
                kept.append(b" ".join(words).decode("utf-8", "surrogatepass"))
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(n_words, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], names=["id", "n_words", "n_removed", "kept"])

    kind = docs.schema[id_col].dataType.simpleString()
    # most rows that have no spans are not shuffled to meet any
    may = send(_bloom(spans.select(F.xxhash64("key").alias("m")), spans.count()))
    rows = base.select("id", "text", "key", F.xxhash64("key").alias("m"))
    schema = f"id {kind}, n_words long, n_removed long, kept string"

    def holds(b):
        return may.value.holds(b.column("m").to_numpy().view(np.uint64))

    def meeting(batches):
        for b in batches:
            yield b.filter(pa.array(holds(b)))

    def plain(batches):  # in one step: a second Python worker for each task would double what an executor holds
        none = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))
        for b in batches:
            b = b.filter(pa.array(~holds(b)))
            yield from cut([pa.RecordBatch.from_arrays([b.column("id"), b.column("text"), pa.nulls(b.num_rows, none)], names=["id", "text", "spans"])])

    met = texts(rows).mapInArrow(meeting, f"id {kind}, text string, key binary, m long").join(spans, "key", "left")
    out = texts(met, "id", "text", "spans").mapInArrow(cut, schema).union(texts(rows, "id", "text", "m").mapInArrow(plain, schema))
    return out.withColumnRenamed("id", id_col)


def digest(result: DataFrame) -> DataFrame:
    """The result with the kept words as SHA-256."""
    return result.withColumn("kept_sha256", F.sha2("kept", 256)).drop("kept")
