"""Tokens, their hashed vocabulary and adjacent pairs, as column expressions."""

from __future__ import annotations

from hashlib import md5

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Texts whose words are numbered at once.
SLICE = 1000


def words(text: str | Column) -> Column:
    """Lower-case runs of letters."""
    c = F.col(text) if isinstance(text, str) else text
    return F.filter(F.split(F.lower(c), r"[^\p{L}]+"), lambda w: w != "")


def hash28(c: Column) -> Column:
    """The first 28 bits of the MD5 of a string, as a long; other engines compute the same."""
    return F.conv(F.substring(F.md5(c.cast("string")), 1, 7), 16, 10).cast("long")


def unit(c: Column) -> Column:
    """A number strictly between 0 and 1 that a string fixes: no run, partitioning or retry changes it."""
    return (hash28(c) + F.lit(0.5)) / F.lit(float(1 << 28))


def gumbel(c: Column) -> Column:
    return -F.log(-F.log(unit(c)))


def bucket(c: Column, size: int) -> Column:
    return hash28(c) % size


def tokenized(df: DataFrame, vocabulary: int, id_col: str = "doc_id", text_col: str = "text", limit: int | None = None) -> DataFrame:
    """(id, n_words, toks): hashed tokens of the first ``limit`` words; n_words counts them all."""
    w = df.select(id_col, words(text_col).alias("w"))
    kept = F.col("w") if limit is None else F.slice("w", 1, limit)
    return w.select(id_col, F.size("w").alias("n_words"), F.transform(kept, lambda t: bucket(t, vocabulary)).alias("toks"))


def hashes(strings: pa.Array) -> np.ndarray:
    """``hash28`` of each string of a column, each distinct one hashed once."""
    coded = strings.dictionary_encode()
    digests = b"".join([md5(s).digest() for s in coded.dictionary.cast(pa.binary()).to_pylist()])
    return (np.frombuffer(digests, ">u4")[::4] >> 4).astype(np.int64)[coded.indices.to_numpy()]


def spaced(text: str | Column) -> Column:
    """The words of a text, joined by single spaces: what counts as a letter is decided here, for workers too."""
    c = F.col(text) if isinstance(text, str) else text
    return F.trim(F.regexp_replace(F.lower(c), r"[^\p{L}]+", " "))


def split_column(texts: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """(words of each row, all words) of a column of ``spaced`` texts; null has none."""
    lists = pc.split_pattern(texts, " ")
    n = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    n[pc.fill_null(pc.equal(texts, ""), False).to_numpy(zero_copy_only=False)] = 0
    flat = lists.flatten()
    return n, flat.filter(pc.not_equal(flat, ""))


def as_lists(values: pa.Array, n: np.ndarray, null: pa.Array | None = None) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))), pa.int32()), values, mask=null)


def numbered(df: DataFrame, vocabulary: int, id_col: str = "doc_id", text_col: str = "text", dim: int | None = None) -> DataFrame:
    """(id, n_words, toks): the rows of ``tokenized`` for whole texts, numbered by whole columns in the workers.

    With ``dim``, also ``enc``, the signed sums of hashed words that ``proxy.encode`` scales to unit length.
    """

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                ids, texts = batch.slice(at, SLICE).columns
                n, words = split_column(texts)
                h, null = hashes(words), texts.is_null()
                out = [ids, pa.array(n, pa.int32(), mask=null.to_numpy(zero_copy_only=False)), as_lists(pa.array(h % vocabulary, pa.int32()), n, null)]
                if dim:
                    cell = np.repeat(np.arange(len(n)), n) * dim + h % dim
                    sums = np.bincount(cell, 1 - 2 * (h // dim % 2), len(n) * dim)
                    out.append(as_lists(pa.array(sums.astype(np.int32)), np.full(len(n), dim)))
                yield pa.RecordBatch.from_arrays(out, names=names)

    names = [id_col, "n_words", "toks", "enc"][: 4 if dim else 3]
    return df.select(id_col, spaced(text_col).alias("_s")).mapInArrow(run, f"{id_col} long, n_words int, toks array<int>" + ", enc array<int>" * bool(dim))


def pairs(tokens: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, x, y): each adjacent pair of tokens, repeats included."""
    t, n = F.col("toks"), F.size("toks")
    both = F.zip_with(F.slice(t, 1, F.greatest(n - 1, F.lit(0))), F.slice(t, 2, F.greatest(n - 1, F.lit(0))), lambda a, b: F.struct(a.alias("x"), b.alias("y")))
    return tokens.select(id_col, F.explode(both).alias("p")).select(id_col, "p.x", "p.y")


def shingles(df: DataFrame, size: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, shingle): the distinct word n-grams of each text."""
    w, n = F.col("w"), F.size("w")
    grams = F.transform(F.sequence(F.lit(1), n - size + 1), lambda i: F.concat_ws(" ", F.slice(w, i, size)))
    return df.select(id_col, words(text_col).alias("w")).filter(n >= size).select(id_col, F.explode(F.array_distinct(grams)).alias("shingle"))
