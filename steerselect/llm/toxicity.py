"""A convolutional text classifier in numpy, for toxic texts.

Words are hashed twice into tables of embeddings and their vectors are added, so that two words collide only if both
hashes do; the vectors of their first five and seven letters are added too, for words of a family.  Filters of several widths run over the whole text, the maximum of each is kept, and a logistic
layer scores the maxima.  The first embedding coordinate starts at the word's log-odds in the training rows and each
filter starts by adding it up; gradient steps then fit all the weights.  Thresholds are calibrated by language, which is
guessed from the text's own function words, and moved into the score so that it decides at 0.5.
"""

from __future__ import annotations

import pickle
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BoundedCache, begin, slices, text_or_empty, texts

#: At most so many labelled rows are used to fit, those of the least hash; the bound is part of the method.
TRAINING_ROWS = 8_000
TABLE = 1 << 15
ROWS, DIMS, WIDTHS, FILTERS = 4, 8, (1, 2, 3), 4
WORD = re.compile(r"\w+")

# Frequent function words by language.
FUNCTION_WORDS = {
    "en": ("the", "of", "and", "to", "in", "that", "is", "was", "for", "with"),
    "fr": ("le", "la", "les", "des", "et", "que", "pour", "dans", "est", "une"),
    "de": ("der", "die", "und", "das", "von", "den", "mit", "nicht", "ein", "ist"),
    "es": ("el", "los", "las", "que", "y", "por", "con", "una", "del", "para"),
}
LANGUAGES = (*FUNCTION_WORDS, "other")
_votes = {w: [i for i, ws in enumerate(FUNCTION_WORDS.values()) if w in ws] for ws in FUNCTION_WORDS.values() for w in ws}


def _slots(word: str) -> bytes:
    """The word's table rows, as 32-bit integers in a row: much smaller than a tuple."""
    h, five, seven = (xxhash.xxh64_intdigest(word[:n], 3) for n in (64, 5, 7))
    return struct.pack("=4i", h % TABLE, TABLE + (h >> 32) % TABLE, 2 * TABLE + five % TABLE, 3 * TABLE + seven % TABLE)


_cache = BoundedCache(_slots, 300_000)


def forget() -> None:
    """Empties the cache of this process; a task's own function would carry a copy of ``_cache`` with it."""
    _cache.forget()


def features(text: str) -> tuple[np.ndarray, int]:
    """(ROWS table rows per word, language guess) of a whole text."""
    words = WORD.findall(text.lower())
    slots = np.frombuffer(b"".join([_cache[w] for w in words]), np.int32).reshape(-1, ROWS)
    _cache.trim()
    counts = [0] * len(FUNCTION_WORDS)
    for w in words:
        for i in _votes.get(w, ()):
            counts[i] += 1
    return slots, int(np.argmax(counts)) if any(counts) else len(FUNCTION_WORDS)


class TextCnn:
    """Weights and the forward and backward passes, for one text at a time."""

    def __init__(self, seed: int = 0) -> None:
        r = np.random.default_rng(seed)
        self.embedding = r.normal(0, 0.05, (ROWS * TABLE, DIMS)).astype(np.float32)
        self.filters = [r.normal(0, 0.1, (w, DIMS, FILTERS)).astype(np.float32) for w in WIDTHS]
        for f in self.filters:
            f[:, 0, :] = 1.0 / len(f)
        n = FILTERS * len(WIDTHS)
        self.out, self.bias = np.full(n, 1.0 / n, np.float32), np.float32(-1.0)
        self.shift = np.zeros(len(LANGUAGES), np.float32)
        self.tables: list[np.ndarray] | None = None

    def start(self, texts: list[np.ndarray], labels: np.ndarray) -> None:
        """Sets the first coordinate from smoothed log-odds of documents that hold a table row."""
        held = np.zeros((2, ROWS * TABLE))
        for slots, y in zip(texts, labels):
            held[int(y), np.unique(slots)] += 1
        n = np.array([np.sum(labels == 0), np.sum(labels == 1)]) + 1.0
        odds = np.log((held[1] + 0.5) / n[1]) - np.log((held[0] + 0.5) / n[0])
        doubt = 1.5 * np.sqrt(1 / (held[1] + 0.5) + 1 / (held[0] + 0.5))  # rows seen in few documents say little
        self.embedding[:, 0] = np.sign(odds) * np.maximum(np.abs(odds) - doubt, 0) / ROWS * 2

    def pooled(self, slots: np.ndarray) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray]]:
        pools, where, used = [], [], []
        for f in self.filters:
            w = len(f)
            padded = slots if len(slots) >= w else np.concatenate((slots, np.repeat(slots[-1:], w - len(slots), 0)))
            x = self.embedding[padded].sum(1)
            z = sum(x[i : len(x) - w + 1 + i] @ f[i] for i in range(w))
            at = z.argmax(0)
            pools.append(np.maximum(z[at, np.arange(FILTERS)], 0))
            where.append(at)
            used.append(padded)
        return np.concatenate(pools), where, used

    def logit(self, slots: np.ndarray) -> float:
        """The score of a text before its language's shift, from tables of every row's product with every filter."""
        if not len(slots):
            return float(self.bias)
        if self.tables is None:
            self.tables = [np.concatenate([self.embedding @ f[i] for i in range(len(f))], 1) for f in self.filters]
        pools = []
        for f, t in zip(self.filters, self.tables):
            w, best = len(f), np.full(FILTERS, -np.inf, np.float32)
            slots_w = slots if len(slots) >= w else np.concatenate((slots, np.repeat(slots[-1:], w - len(slots), 0)))
            for s in range(0, len(slots_w) - w + 1, 1 << 16):  # long texts in bounded steps
                part = slots_w[s : s + (1 << 16) + w - 1]
                x = sum(t[part[:, k]] for k in range(ROWS))
                z = sum(x[i : len(x) - w + 1 + i, i * FILTERS : (i + 1) * FILTERS] for i in range(w))
                best = np.maximum(best, z.max(0))
            pools.append(np.maximum(best, 0))
        return float(np.concatenate(pools) @ self.out + self.bias)

    def fit(self, texts: list[np.ndarray], labels: np.ndarray, epochs: int = 3, rate: float = 0.02, seed: int = 0) -> None:
        r = np.random.default_rng(seed)
        weight = np.where(labels == 1, len(labels) / max(1, 2 * labels.sum()), len(labels) / max(1, 2 * (labels == 0).sum()))
        weight = np.minimum(weight, 8)
        for epoch in range(epochs):
            step = rate / (1 + epoch)
            for n in r.permutation(len(texts)):
                slots = texts[n]
                if not len(slots):
                    continue
                p, where, used = self.pooled(slots)
                z = float(p @ self.out + self.bias)
                error = np.float32((1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels[n]) * weight[n] * step)
                to_pool = error * self.out * (p > 0)
                self.out -= error * p
                self.bias -= error
                for j, (f, at, padded) in enumerate(zip(self.filters, where, used)):
                    d = to_pool[j * FILTERS : (j + 1) * FILTERS]
                    for i in range(len(f)):
                        rows = padded[at + i]
                        x = self.embedding[rows].sum(1)  # (filters, dims)
                        up = d[:, None] * f[i].T
                        f[i] -= (d[:, None] * x).T
                        for k in range(ROWS):
                            np.add.at(self.embedding, rows[:, k], -up)
        self.tables = None

    def calibrate(self, texts: list[np.ndarray], languages: np.ndarray, labels: np.ndarray) -> None:
        """Per language, the shift that puts the threshold of best F1, half-way to the next score, at logit zero."""
        z = np.array([self.logit(s) for s in texts])
        every = self.best_threshold(z, labels)
        for i in range(len(LANGUAGES)):
            own = languages == i
            enough = labels[own].sum() >= 5 and (labels[own] == 0).sum() >= 5
            self.shift[i] = self.best_threshold(z[own], labels[own]) if enough else every

    @staticmethod
    def best_threshold(z: np.ndarray, y: np.ndarray) -> float:
        if not y.sum() or y.all():
            return 0.0
        order = np.argsort(-z, kind="stable")
        z, y = z[order], y[order]
        hit = np.cumsum(y)
        f1 = 2 * hit / (np.arange(1, len(y) + 1) + y.sum())
        f1[:-1][z[1:] == z[:-1]] = -1  # no cut within ties
        k = int(f1.argmax())
        return float((z[k] + z[k + 1]) / 2) if k + 1 < len(z) else float(z[k] - 1)

    def score(self, text: str) -> float:
        slots, language = features(text)
        z = self.logit(slots) - self.shift[language]
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def in_held_out(doc_id) -> bool:
    return zlib.crc32(str(doc_id).encode()) % 5 == 0


def fitted(table: pa.Table | None) -> TextCnn:
    """The classifier of one table of training rows (id, y, slots, language), in whatever order they come."""
    model = TextCnn()
    if table is None or not table.num_rows:
        model.bias, model.out = np.float32(-5.0), np.zeros_like(model.out)
        return model
    ids = table.column("id").to_pylist()
    # the texts stay in the buffers that they came in
    texts = [np.frombuffer(s.as_buffer(), np.int32).reshape(-1, ROWS) if s.as_buffer().size else np.zeros((0, ROWS), np.int32) for c in table.column("slots").chunks for s in c]
    order = sorted(range(len(ids)), key=lambda i: (ids[i], len(texts[i]), texts[i][:50].tobytes()))
    ids, texts = [ids[i] for i in order], [texts[i] for i in order]
    y, language = (np.array(table.column(c).to_pylist(), kind)[order] for c, kind in (("y", np.float32), ("language", int)))
    if not y.sum() or y.all():
        model.bias, model.out = np.float32(-5.0), np.zeros_like(model.out)
        return model
    fits = np.array([zlib.crc32(f"fit|{i}".encode()) % 4 != 0 for i in ids])
    if not y[fits].sum() or not y[~fits].sum():
        fits = np.ones(len(y), bool)
    mine = [t for t, f in zip(texts, fits) if f]
    model.start(mine, y[fits])
    model.fit(mine, y[fits])
    rest = ~fits if not fits.all() else fits
    model.calibrate([t for t, f in zip(texts, rest) if f], language[rest], y[rest])
    model.tables = None  # workers make them again from the weights
    return model


def trained(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most: int = TRAINING_ROWS) -> TextCnn:
    """A classifier fitted on labelled rows outside the held-out fifth, at most ``most`` of them.

    Labels are learnt from texts alone.  Three quarters of the rows fit the weights, the rest set the thresholds; without
    rows of both labels the classifier calls nothing toxic.  One task of a worker fits it, so the driver holds the weights
    alone; a task that is run again gives the same ones.  An empty table gives the classifier that calls nothing toxic.
    """
    fold = F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(5))
    known = labels.filter(F.col(id_col).isNotNull() & F.col(label_col).isin(0, 1) & (fold != 0)).groupBy(id_col).agg(F.max(label_col).alias("y"))
    known = known.orderBy(F.xxhash64(id_col), id_col).limit(most)
    # at most ``most`` rows: they travel to the texts, not the texts to them
    rows = docs.select(F.col(id_col), text_or_empty(text_col).alias("text")).join(F.broadcast(known), id_col).select(F.col(id_col).alias("id"), "y", "text")

    def run(batches):
        begin("toxicity", forget)
        for b in slices(batches):
            out = [features(t.as_py()) for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("y"), pa.array([s.tobytes() for s, _ in out], pa.binary()), pa.array([g for _, g in out], pa.int32())], names=["id", "y", "slots", "language"])

    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}
    table = rows.mapInArrow(run, f"id {kinds['id']}, y {kinds['y']}, slots binary, language int")

    def fit(t):
        begin("toxicity", forget)
        return pa.table({"model": pa.array([pickle.dumps(fitted(t))], pa.binary())})

    model = table.withColumn("whole", F.lit(0)).groupBy("whole").applyInArrow(fit, "model binary").first()
    return pickle.loads(model["model"]) if model else fitted(None)


def scores(docs: DataFrame, model: TextCnn, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, held_out, score in 0 to 1, predicted (score >= 0.5).  Null and wordless texts have scores too.

    A null id counts as not held out; repeated rows get equal scores; an empty table gives an empty result.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # of a fixed size, a few MB

    def run(batches):
        begin("toxicity", forget)
        m = shared.value
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([m.score(t.as_py()) for t in b.column("text")], pa.float64())], names=["id", "score"])

    kind = docs.schema[id_col].dataType.simpleString()
    out = texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, score double")
    held = F.coalesce(F.pmod(F.crc32(F.col("id").cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))
    return out.select(F.col("id").alias(id_col), held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, model: TextCnn, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the classifier does not call toxic, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        begin("toxicity", forget)
        m = shared.value
        for b in slices(batches, text_col):
            yield b.filter(pa.array([m.score(t.as_py() or "") < 0.5 for t in b.column(text_col)], pa.bool_()))

    return texts(docs).mapInArrow(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema))
