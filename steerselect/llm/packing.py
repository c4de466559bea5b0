"""Sum-of-squares online packing of token sequences into windows of a fixed length.

Documents are tokenised once; a document longer than a window gives whole windows and a remainder.  Remainders are
placed online: among the fill levels at which partially filled windows stand, each goes to the one that leaves the
least sum of squared counts of windows per level.  The counts live in an array by level.  Only lengths are shuffled.
"""

from __future__ import annotations

import functools
import json
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import IdTable, begin, gather, sections, slices, text_or_empty, texts, written

WINDOW = 2048
END_ID = 1
#: Pieces that one task packs; more of them make more groups, each with its own level array.
GROUP = 65536
#: Bytes of texts that are encoded in one step; longer ones go in sections.
LONG = 12 << 20


#: Texts of other characters, or with the mark that begins special tokens, are given to the tokenizer whole.  Within
#: these, white space is ASCII, normalisation to composed form changes nothing, and lower case goes letter by letter.
ODD = r"[^\x02-\x1b\x20-\x7f\x{a1}-\x{12f}\x{131}-\x{17f}]|<\|"
#: A letter or digit and the mark behind it never share a token.
BEFORE_MARK = r"([\pL\pN])([^\s\pL\pN])"


def byte_letters() -> dict[int, str]:
    """The letters that stand for bytes in byte-level vocabularies: printable ones as they are, others from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    rest = iter(range(0x100, 0x200))
    return {b: chr(b if b in plain else next(rest)) for b in range(256)} | {0x20: " "}


BYTE_LETTERS = byte_letters()


class WordEncoder:
    """Ids of texts, by way of a table of their lower-case words.

    The tokenizer drops white space and never merges across it, nor from a letter or digit to a mark behind it, so words
    and the marks behind them are encoded on their own.
    """

    def __init__(self, tokenizer_file: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(tokenizer_file)
        self.table = IdTable(self.encoded)
        self.between = self.whole("\x01")
        spec = json.loads(self.tokenizer.to_str()) | {"normalizer": None, "added_tokens": [], "pre_tokenizer": {"type": "WhitespaceSplit"}}
        self.merges = Tokenizer.from_str(json.dumps(spec))
        vocabulary, suffix = self.tokenizer.get_vocab(), spec["model"].get("end_of_word_suffix") or "\0"
        self.last = np.zeros(max(vocabulary.values()) + 1, bool)
        self.last[[i for w, i in vocabulary.items() if w.endswith(suffix)]] = True

    def whole(self, text: str) -> np.ndarray:
        parts = [np.array(self.tokenizer.encode_batch_fast([t], add_special_tokens=False)[0].ids, np.uint32) for t in sections(text, 1 << 20)]
        return parts[0] if len(parts) == 1 else np.concatenate(parts)

    def encoded(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words, hundreds in one call; where each ends shows by its last token or by a mark put between."""
        plain = np.fromiter(map(str.isalpha, words), bool, len(words))
        lens, parts, order = np.zeros(len(words), np.int64), [np.zeros(0, np.uint32)], []
        for on, some_ids in ((plain, self.letters), (~plain, self.between_marks)):
            at = np.flatnonzero(on)
            for i in range(0, len(at), 256):
                some = [words[k] for k in at[i : i + 256].tolist()]
                ids, n = some_ids(some)
                if n is None or len(n) != len(some):
                    each = [self.whole(w) for w in some]
                    ids, n = np.concatenate(each), np.array([len(x) for x in each])
                lens[at[i : i + 256]] = n
                parts.append(ids)
            order.append(at)
        at = np.concatenate(order)
        starts = np.empty(len(words), np.int64)
        starts[at] = np.cumsum(lens[at]) - lens[at]
        return gather(np.concatenate(parts), starts, lens), lens

    def letters(self, words: list[str]) -> tuple[np.ndarray, np.ndarray | None]:
        """Words of letters alone are one run each, so the merges can be asked directly."""
        text = " ".join(words).encode().decode("latin-1").translate(BYTE_LETTERS)
        ids = np.array(self.merges.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)
        return ids, np.diff(np.flatnonzero(self.last[ids]), prepend=-1) if len(ids) and self.last[ids[-1]] else None

    def between_marks(self, words: list[str]) -> tuple[np.ndarray, np.ndarray | None]:
        if len(self.between) != 1:
            return np.zeros(0, np.uint32), None
        got = self.whole(" \x01 ".join(words))
        is_cut = got == self.between[0]
        return got[~is_cut], np.diff(np.flatnonzero(np.append(is_cut, True)), prepend=-1) - 1

    def encode_all(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text."""
        odd = pc.match_substring_regex(texts, ODD)
        strange = np.flatnonzero(odd.to_numpy(zero_copy_only=False))
        plain = pc.if_else(odd, "", texts) if len(strange) else texts
        if plain.nbytes > LONG:
            return [self.whole(t.as_py()) if o else np.concatenate([self.encode_all(pa.array([x]))[0] for x in sections(t.as_py())]) for o, t in zip(odd.to_pylist(), texts)]
        split = pc.ascii_split_whitespace(pc.replace_substring_regex(pc.utf8_lower(plain), BEFORE_MARK, r"\1 \2"))
        ids, lens = self.table.ids(split.flatten())
        ends = np.concatenate(([0], np.cumsum(lens)))[split.offsets.to_numpy()]
        out = [ids[a:b] for a, b in zip(ends.tolist(), ends[1:].tolist())]
        for i in strange.tolist():
            out[i] = self.whole(texts[i].as_py())
        return out

    def encode(self, text: str) -> bytes:
        return self.encode_all(pa.array([text]))[0].astype("<u4").tobytes()


@functools.lru_cache(2)
def encoder(tokenizer_file: str) -> WordEncoder:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # one core per task
    return WordEncoder(tokenizer_file)


def pieces(docs: DataFrame, tokenizer_file: str, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens) for each cut of each document; the text is read once and never shuffled."""

    def run(batches):
        begin("packing", encoder.cache_clear)
        enc = encoder(tokenizer_file)
        for b in slices(batches, most_bytes=4 << 20):
            ids, starts, lengths, crcs, totals = [], [], [], [], []
            for k, data in enumerate(enc.encode_all(b.column("text"))):
                data = np.append(data, np.uint32(END_ID)).astype("<u4").tobytes()
                n = len(data) // 4
                for s in range(0, n, window):
                    part = data[4 * s : 4 * (s + window)]
                    ids.append(k)
                    starts.append(s)
                    lengths.append(len(part) // 4)
                    crcs.append(zlib.crc32(part))
                    totals.append(n)
            own = b.column("id").take(pa.array(ids, pa.int32()))
            yield pa.RecordBatch.from_arrays([own, *(pa.array(x, pa.int64()) for x in (starts, lengths, crcs, totals))], names=["id", "start", "length", "ids_crc32", "doc_tokens"])

    kind = docs.schema[id_col].dataType.simpleString()
    return texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, start long, length long, ids_crc32 long, doc_tokens long")


class SumOfSquares:
    """Windows being filled; ``place`` returns (window, offset) for a length below the window's."""

    def __init__(self, window: int = WINDOW) -> None:
        self.window = window
        self.counts = np.zeros(window + 1, np.int64)  # by level; 0 and the full level stay empty
        self.standing: list[list[int]] = [[] for _ in range(window + 1)]
        self.opened = 0

    def place(self, length: int) -> tuple[int, int]:
        if length >= self.window:
            self.opened += 1
            return self.opened - 1, 0
        n, top = self.counts, self.window - length
        # the sum grows by 2 (n[h + length] - n[h]) + 2 if a window leaves level h for level h + length, by
        # 1 - 2 n[h] if it becomes full, and by 2 n[length] + 1 if a new window opens
        change = 2 * (n[length + 1 : self.window + 1] - n[1 : top + 1]) + 2
        change[-1] = 1 - 2 * n[top] if top else change[-1]
        change[n[1 : top + 1] == 0] = np.iinfo(np.int64).max
        best = int(change.argmin())
        if change[best] <= 2 * n[length] + 1:
            level = best + 1
            w = self.standing[level].pop()
            n[level] -= 1
        else:
            level, w = 0, self.opened
            self.opened += 1
        if level + length < self.window:
            n[level + length] += 1
            self.standing[level + length].append(w)
        return w, level


def pack(docs: DataFrame, tokenizer_file: str, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, group: int = GROUP) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A null or empty text is the end id alone.  Null ids are kept; rows that repeat are packed each.  Sequence ids are
    group * 2^40 + the window's number in its group; groups are hashes of the id, so results don't depend on how the
    table is partitioned.  An empty table gives an empty result.
    """
    table = written(pieces(docs, tokenizer_file, id_col, text_col, window), "pieces")
    groups = max(1, -(-table.count() // group))
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"

    def run(batches):
        now, state = None, None
        for b in batches:
            seq, off = np.empty(b.num_rows, np.int64), np.empty(b.num_rows, np.int64)
            for i, (g, n) in enumerate(zip(b.column("g").to_pylist(), b.column("length").to_pylist())):
                if g != now:
                    now, state = g, SumOfSquares(window)
                w, off[i] = state.place(n)
                seq[i] = (g << 40) + w
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("id", "start", "length", "ids_crc32", "doc_tokens")), pa.array(seq), pa.array(off)], names=["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    # a hash of whole ids deals the groups: a hot id's own pieces stay below one document's, repeated ids are salted by start
    g = F.pmod(F.xxhash64("id", "start", "ids_crc32"), F.lit(groups))
    dealt = table.withColumn("g", g).repartition(groups, "g").sortWithinPartitions("g", F.xxhash64("id", "start"), "id", "start", "ids_crc32", "length")
    return dealt.mapInArrow(run, schema).withColumnRenamed("id", id_col)


def padding(packed: DataFrame, window: int = WINDOW) -> DataFrame:
    """(sequences, tokens, padding): sequences are padded to the window, but for those whose length is a power of two."""
    filled = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.bit_count("n") == 1, F.lit(0)).otherwise(F.lit(window) - F.col("n"))
    return filled.agg(F.count(F.lit(1)).alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padding"))
