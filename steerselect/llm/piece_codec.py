"""Encoding and decoding with a merge-type (BPE) SentencePiece model by a table of prefixes.

For every prefix of a chunk the last token of its only merge result is stored.  An automaton lists the tokens that end
at a position; the right one is that whose predecessor, the stored last token of the prefix before it, forms a pair
that merging would leave as it is.  Ids are then recovered backwards through the table.

Chunks are runs of spaces with what follows them: no piece of the model holds a space after another character, so no
merge crosses a chunk's border.  Characters without a piece become byte pieces and are borders too, and so are two
neighbours that no piece holds.  A run whose table has no entry at its end is merged plainly, which models whose tokens
can all be made by merging never need.
"""

from __future__ import annotations

import functools
import hashlib
import re

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BoundedCache, IdTable, gather, slices, text_or_empty, texts

SPACE = "▁"
#: Marks that often follow a word.
MARKS = ".,;:!?&%$*"
#: Bytes of texts that are encoded in one step; longer ones go chunk by chunk.
LONG = 12 << 20


class PieceCodec:
    """Encoder and decoder of one model file; both agree with the sentencepiece library."""

    def __init__(self, model_file: str, compare: bool = False) -> None:
        """``compare`` encodes every new chunk with the library too and raises an error if it gives other ids."""
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        with open(model_file, "rb") as f:
            proto = sentencepiece_model_pb2.ModelProto.FromString(f.read())
        n = proto.normalizer_spec
        if proto.trainer_spec.model_type != proto.trainer_spec.BPE or n.precompiled_charsmap or n.remove_extra_whitespaces or not n.add_dummy_prefix:
            raise ValueError("a merge-type model with the identity normaliser and a dummy prefix is needed")
        kinds = proto.SentencePiece
        self.pieces = [p.piece for p in proto.pieces]
        self.plain = {p.piece: i for i, p in enumerate(proto.pieces) if p.type == kinds.NORMAL}
        self.score = {p.piece: p.score for p in proto.pieces if p.type == kinds.NORMAL}
        if any(re.search(f"[^{SPACE}]{SPACE}", p) for p in self.plain):
            raise ValueError("a piece holds a space after another character")
        self.control = {i for i, p in enumerate(proto.pieces) if p.type == kinds.CONTROL}
        self.unknown = proto.trainer_spec.unk_id
        self.begin, self.end = proto.trainer_spec.bos_id, proto.trainer_spec.eos_id
        self.byte_id = {int(p.piece[3:5], 16): i for i, p in enumerate(proto.pieces) if p.type == kinds.BYTE}
        self.raw = [b"" if i in self.control else p.piece.replace(SPACE, " ").encode() for i, p in enumerate(proto.pieces)]
        for value, i in self.byte_id.items():
            self.raw[i] = bytes([value])
        self.raw[self.unknown] = " ⁇ ".encode()
        self.bytes_ = set(self.byte_id.values())
        self.automaton = ahocorasick.Automaton()
        self.halves: dict[str, tuple[str, str] | None] = {}
        self.left, self.right = {}, {}
        for p, i in self.plain.items():
            parts, half = self.merges(p)
            if len(parts) == 1:  # a token that merging never makes ends no prefix
                self.automaton.add_word(p, (len(p), i))
                self.halves[p] = half
        self.automaton.make_automaton()
        self.edges()
        self.known = {p for p in self.plain if len(p) == 1}
        self.fits = BoundedCache(self._fits, 1_000_000)
        #: Neighbours that no piece holds: no merge joins them, so chunks can be cut there.
        self.inside = {p[i : i + 2] for p in self.plain for i in range(len(p) - 1)}
        self.lone = not any("\n" in p for p in self.plain)
        self.table = IdTable(self.encoded)
        lens = [len(x) for x in self.raw]
        self.raw_flat, self.raw_lens = np.frombuffer(b"".join(self.raw), np.uint8), np.array(lens, np.int64)
        self.raw_starts = np.cumsum(self.raw_lens) - self.raw_lens
        self.runs = BoundedCache(self.run, 400_000)
        proto.normalizer_spec.add_dummy_prefix = False
        self.library = sentencepiece.SentencePieceProcessor(model_proto=proto.SerializeToString()) if compare else None

    def merged(self, text: str) -> list[str]:
        """What merging makes of known characters: the adjacent pair of best score first, the leftmost among equals."""
        return self.merges(text)[0]

    def merges(self, text: str) -> tuple[list[str], tuple[str, str] | None]:
        """The same, and the two parts of the last merge."""
        parts, last = list(text), None
        while len(parts) > 1:
            at, best = -1, float("-inf")
            for i in range(len(parts) - 1):
                s = self.score.get(parts[i] + parts[i + 1])
                if s is not None and s > best:
                    at, best = i, s
            if at < 0:
                break
            last = parts[at], parts[at + 1]
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts, last

    def edges(self) -> None:
        """For each token the parts at its left and right end, from a character to the whole.

        Left out are tokens with a part, at any depth, that is merged later than what it is part of.
        """
        for p in sorted(self.halves, key=len):
            half = self.halves[p]
            if half is None or all(x in self.left and (len(x) == 1 or self.score[x] > self.score[p]) for x in half):
                self.left[p] = (*self.left[half[0]], p) if half else (p,)
                self.right[p] = (*self.right[half[1]], p) if half else (p,)

    def _fits(self, pair: int) -> bool:
        """Whether merging leaves two tokens side by side: no pair of their facing parts is merged while both stand there."""
        a, b = self.pieces[pair >> 20], self.pieces[pair & 0xFFFFF]
        if a not in self.right or b not in self.left:
            return self.merged(a + b) == [a, b]
        score, xs, ys = self.score, self.right[a], self.left[b]
        i = j = 0
        none = float("-inf")
        while True:
            next_x = score[xs[i + 1]] if i + 1 < len(xs) else none
            next_y = score[ys[j + 1]] if j + 1 < len(ys) else none
            s = score.get(xs[i] + ys[j])
            if s is not None and s > next_x and s >= next_y:
                return False
            if next_x == next_y == none:
                return True
            if next_x >= next_y:
                i += 1
            else:
                j += 1

    def run(self, text: str) -> list[int]:
        """Ids of a run of known characters."""
        n = len(text)
        last, begins = [-1] * (n + 1), [0] * (n + 1)  # per prefix: the last token of its merge result, and where it starts
        fits = self.fits
        for stop, (size, token) in self.automaton.iter(text):
            stop += 1
            if last[stop] < 0:
                start = stop - size
                if start == 0 or last[start] >= 0 and fits[last[start] << 20 | token]:
                    last[stop], begins[stop] = token, start
        at, out = n, []
        while at:
            if last[at] < 0:
                return [self.plain[p] for p in self.merged(text)]
            out.append(last[at])
            at = begins[at]
        return out[::-1]

    def ids_of(self, chunk: str) -> list[int]:
        known, inside, runs = self.known, self.inside, self.runs
        if known.issuperset(chunk):
            stem = chunk.rstrip(MARKS)
            cut = len(stem)
            return runs[chunk] if cut in (0, len(chunk)) or chunk[cut - 1 : cut + 1] in inside else runs[stem] + runs[chunk[cut:]]
        out: list[int] = []
        start = 0
        for i, c in enumerate(chunk):
            if c not in known:
                if start < i:
                    out += runs[chunk[start:i]]
                out += [self.byte_id[b] for b in c.encode("utf-8", "replace")] if self.byte_id else [self.unknown]
                start = i + 1
            elif start < i and chunk[i - 1 : i + 1] not in inside:
                out += runs[chunk[start:i]]
                start = i
        return out + runs[chunk[start:]] if start < len(chunk) else out

    def encoded(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words that follow a space; one that begins with a line end follows no space."""
        out = [self.ids_of(w if w.startswith("\n") else SPACE + w) for w in words]
        if self.library is not None:
            for w, ids in zip(words, out):
                if self.library.encode(w if w.startswith("\n") else " " + w) != ids:
                    raise ValueError(f"the prefix table and the library differ on {w[:100]!r}")
        self.runs.trim()
        self.fits.trim()
        return np.array([i for ids in out for i in ids], np.uint32), np.fromiter(map(len, out), np.int64, len(out))

    def encode_all(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text between the begin and end ids.

        Words between single spaces are looked up in the table; texts with runs of spaces, or with the character that
        stands for a space, are cut into chunks one by one.
        """
        odd = pc.match_substring_regex(texts, f"^ |  |{SPACE}|^$" + ("" if self.lone else "|\n"))
        strange = odd.to_pylist()
        plain = pc.if_else(odd, "", texts)
        if plain.nbytes > LONG:
            return [self.framed(self.long(t.as_py())) for t in texts]
        split = pc.split_pattern(pc.replace_substring(plain, "\n", " \n"), " ")
        ids, lens = self.table.ids(split.flatten())
        ends = np.concatenate(([0], np.cumsum(lens)))[split.offsets.to_numpy()].tolist()
        return [self.framed(self.long(t.as_py()) if o else ids[a:b]) for t, o, a, b in zip(texts, strange, ends, ends[1:])]

    def framed(self, ids: np.ndarray) -> np.ndarray:
        return np.concatenate((np.array([self.begin], np.uint32), ids, np.array([self.end], np.uint32)))

    def long(self, text: str) -> np.ndarray:
        """Ids of any text without begin and end, chunk by chunk: runs of spaces with what follows them."""
        parts = [np.zeros(0, np.uint32)]
        marked = SPACE + text.replace(" ", SPACE) if text else ""
        for m in re.finditer(f"{SPACE}*[^{SPACE}\n]+|{SPACE}+|\n" if self.lone else f"{SPACE}*[^{SPACE}]+|{SPACE}+", marked):
            parts.append(np.array(self.ids_of(m[0]), np.uint32))
            if len(parts) > 4096:
                parts = [np.concatenate(parts)]
                self.runs.trim()
        return np.concatenate(parts)

    def encode(self, text: str) -> list[int]:
        return self.encode_all(pa.array([text], pa.string()))[0].tolist()

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        """The decoded text in UTF-8."""
        data = gather(self.raw_flat, self.raw_starts[ids], self.raw_lens[ids]).tobytes()
        try:
            data.decode("utf-8")
        except UnicodeDecodeError:
            return self.decode(ids.tolist()).encode()
        first = next((i for i in ids[:4].tolist() if i not in self.control), None)
        return data[1:] if first is not None and first not in self.bytes_ and first != self.unknown and data.startswith(b" ") else data

    def decode(self, ids: list[int]) -> str:
        """Text of ids: byte pieces join into characters, an ill-formed byte is U+FFFD, the dummy prefix goes."""
        first = next((i for i in ids if i not in self.control), None)
        data = b"".join(map(self.raw.__getitem__, ids))
        try:
            text = data.decode("utf-8")
        except UnicodeDecodeError:
            text = self._decode_slowly(ids)
        return text[1:] if first is not None and first not in self.bytes_ and text.startswith(" ") and first != self.unknown else text

    def _decode_slowly(self, ids: list[int]) -> str:
        """Runs of byte pieces on their own, with one U+FFFD for each byte that belongs to no character."""
        out, held = [], bytearray()

        def flush() -> None:
            at = 0
            while at < len(held):
                for n in (1, 2, 3, 4):
                    try:
                        out.append(bytes(held[at : at + n]).decode())
                        at += n
                        break
                    except UnicodeDecodeError:
                        continue
                else:
                    out.append("�")
                    at += 1
            held.clear()

        for i in ids:
            if i in self.bytes_:
                held += self.raw[i]
            else:
                flush()
                out.append(self.raw[i].decode())
        flush()
        return "".join(out)


@functools.lru_cache(2)
def codec(model_file: str) -> PieceCodec:
    return PieceCodec(model_file)


def encode_decode(docs: DataFrame, model_file: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, n_tokens, ids_sha256, decoded_sha256.  A null text is empty: the begin and end ids alone.

    Rows are independent: null ids, repeated rows and extra columns change nothing; an empty table gives an empty result.
    """

    def run(batches):
        c = codec(model_file)
        for b in slices(batches, most_bytes=4 << 20):
            every = c.encode_all(b.column("text"))
            n = [len(x) for x in every]
            digests = [hashlib.sha256(x.astype("<u4").tobytes()).hexdigest() for x in every]
            decoded = [hashlib.sha256(c.decode_bytes(x)).hexdigest() for x in every]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(n, pa.int64()), pa.array(digests, pa.string()), pa.array(decoded, pa.string())], names=["id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[id_col].dataType.simpleString()
    out = texts(docs, F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
    return out.withColumnRenamed("id", id_col)
