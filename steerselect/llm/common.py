"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import ctypes
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The characters that separate words in every contract here (space and U+0009 to U+000D).
BLANKS = " \t\n\x0b\x0c\r"
BATCH_ROWS = 1000


def shared_folder(spark: SparkSession, label: str) -> str:
    """A fresh folder under ``spark.checkpoint.dir``, which every executor sees; a local one only where all runs on one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master) is None:
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = f"file://{tempfile.gettempdir()}/steerselect-shared"
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str) -> DataFrame:
    """``df`` as a table in the shared folder, read again: it survives lost executors and is computed once."""
    spark = df.sparkSession
    path = shared_folder(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def texts(df: DataFrame, *columns: Column) -> DataFrame:
    """The columns of ``df`` on their way to Python, in batches of few rows: texts may be long.

    ``spark.sql.execution.arrow.maxRecordsPerBatch`` may change in a running session; it bounds what a batch holds in
    the executor's and in the worker's memory.
    """
    spark = df.sparkSession
    if not 0 < int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) <= BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    return df.select(*columns) if columns else df


def text_or_empty(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names with as many leading underscores as it takes not to clash with a column of ``df``."""
    taken = {c.lower() for c in df.columns}
    out = []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out


#: The operator whose tables this worker's process holds, and what forgets them.
_holder: list = [None, None]


def begin(operator: str, forget: Callable[[], object] | None = None) -> None:
    """Where a task of ``operator`` begins: what another operator's tasks kept in this process is forgotten by the ``forget``
    that they gave, and memory that nobody uses goes back to the system.

    Workers serve all stages of a chain in turn and would else hold the tables of all of them at once.
    """
    if _holder[0] != operator:
        if _holder[1]:
            _holder[1]()
        _holder[:] = operator, forget
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


class BoundedCache(dict):
    """A dict that computes missing values and holds two generations of at most ``limit`` entries in all.

    When the young generation is full it becomes the old one; what is used again moves on, the rest is forgotten.
    """

    def __init__(self, compute, limit: int) -> None:
        super().__init__()
        self.compute, self.limit, self.old = compute, limit, {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.compute(key)
        self[key] = value
        return value

    def forget(self) -> None:
        self.clear()
        self.old = {}

    def trim(self) -> None:
        if len(self) > self.limit // 2:
            self.old = dict(self)
            self.clear()


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", most_bytes: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Batches cut so that the texts of each hold about ``most_bytes``; a longer text travels alone."""
    for b in batches:
        if not b.num_rows:
            continue
        sizes = pc.binary_length(b.column(text)).to_pylist()
        first, held = 0, 0
        for i, n in enumerate(sizes):
            if held and held + (n or 0) > most_bytes:
                yield b.slice(first, i - first)
                first, held = i, 0
            held += n or 0
        yield b.slice(first)


def gather(flat: np.ndarray, starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """The ranges of ``flat`` that begin at ``starts`` and have ``lens`` values, one after another."""
    ends = np.cumsum(lens)
    at = np.repeat(starts - (ends - lens), lens)
    at += np.arange(len(at))
    return flat[at]


class IdTable:
    """Ids of words, worked out once for each word and held in flat arrays; all is forgotten when a bound is passed."""

    def __init__(self, encode, most_words: int = 700_000, most_ids: int = 6_000_000) -> None:
        """``encode`` gives, for a list of words, their ids in one array and the number of ids of each."""
        self.encode, self.most_words, self.most_ids = encode, most_words, most_ids
        self.clear()

    def clear(self) -> None:
        self.slot: dict[str, int] = {}
        self.flat, self.starts, self.lens, self.used = np.empty(1 << 16, np.uint32), np.empty(1 << 14, np.int64), np.empty(1 << 14, np.int64), 0

    def add(self, words: list[str], ids: np.ndarray, lens: np.ndarray) -> None:
        """Words that are not held yet, each once."""
        first, n, used = len(self.slot), len(self.slot) + len(words), self.used + len(ids)
        while n > len(self.starts):
            self.starts, self.lens = (np.concatenate((x, np.empty_like(x))) for x in (self.starts, self.lens))
        while used > len(self.flat):
            self.flat = np.concatenate((self.flat, np.empty_like(self.flat)))
        self.flat[self.used : used], self.lens[first:n], self.starts[first:n] = ids, lens, self.used + np.cumsum(lens) - lens
        self.slot.update(zip(words, range(first, n)))
        self.used = used

    def slots(self, words: list[str]) -> np.ndarray:
        """The place of each of these different words; what is new is encoded."""
        get = self.slot.get
        at = np.fromiter(map(get, words, repeat(-1)), np.int64, len(words))
        new = np.flatnonzero(at < 0)
        if len(new):
            names = [words[i] for i in new.tolist()]
            at[new] = np.arange(len(self.slot), len(self.slot) + len(names))
            self.add(names, *self.encode(names))
        return at

    def ids(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all words, in order, and the number of each one's."""
        if len(self.slot) > self.most_words or self.used > self.most_ids:
            self.clear()
        coded = words.dictionary_encode()
        at = self.slots(coded.dictionary.to_pylist())[coded.indices.to_numpy(zero_copy_only=False)]
        lens = self.lens[at]
        return gather(self.flat, self.starts[at], lens), lens


def sections(text: str, most: int = 4 << 20) -> Iterator[str]:
    """Parts of a long text of about ``most`` characters that are cut at, and lose, a space between two ASCII letters or digits."""
    at = 0
    while len(text) - at > most:
        cut = text.find(" ", at + most)
        while cut >= 0 and not (text[cut - 1 : cut + 2].isascii() and text[cut - 1].isalnum() and text[cut + 1 : cut + 2].isalnum()):
            cut = text.find(" ", cut + 1)
        if cut < 0:
            break
        yield text[at:cut]
        at = cut + 1
    yield text[at:]
