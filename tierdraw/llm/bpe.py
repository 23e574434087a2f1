"""BPE encoding and decoding with a given vocabulary of merges.

Encoder: a piece is walked once. At each position an automaton over all token strings names the longest token that starts there; it is kept if
it is compatible with the token before it, else shorter prefixes are tried, and where none fits the last token is taken back and shortened. Two
neighbours are compatible if merging their joined string by rank leaves exactly these two, which is looked up in a memo that is built on demand.
That gives the same ids as applying merges by rank, without a queue of merges and in linear time.
Decoder: token strings lie end to end in one buffer with an offset table; ids index the offsets.

Text goes through the steps that the vocabulary file states: special tokens are cut out of the raw text, then NFC, white space, lower case,
the split pattern and bytes as characters, with a mark for the end of a word.
"""

from __future__ import annotations

import array
import hashlib
import json
import re
import sys
import unicodedata
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import free_memory

#: Pieces whose ids a worker remembers, their longest, and pairs of its compatibility table.
MEMO_PIECES, MEMO_CHARS, MEMO_PAIRS = 200_000, 64, 200_000
#: Characters that the file's \s stands for.
SPACES = "\t\n\x0b\x0c\r \x85\xa0  -     　"


def byte_symbols() -> list[str]:
    """The character that stands for each byte: printable ones for themselves, the others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, extra = {b: chr(b) for b in plain}, 256
    for b in range(256):
        if b not in out:
            out[b], extra = chr(extra), extra + 1
    return [out[b] for b in range(256)]


class BpeCodec:
    """Encoder and decoder of one vocabulary file of the tokenizers library (BPE with an end-of-word mark, byte characters, no decoder)."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.suffix = model.get("end_of_word_suffix") or ""
        vocab: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens") or []}
        self.special_re = regex.compile("|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True))) if self.special else None
        split = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        self.split_re = regex.compile(split.replace(r"[^\s\p{L}\p{N}]", rf"[^{SPACES}\p{{L}}\p{{N}}]"))
        self.space_re = re.compile(f"[{SPACES}]+")
        self.odd_re = re.compile("[\x1c-\x1f]")  # white space to str.split, not to the file
        symbols = byte_symbols()
        # every byte is one character, and the last of a word is another one, so that token strings need no mark inside
        self.inner = {s: chr(b) for b, s in enumerate(symbols)}
        self.final = {s: chr(256 + b) for b, s in enumerate(symbols)}
        self.strings: dict[str, int] = {}
        for token, i in vocab.items():
            self.strings[self._packed(token)] = i
        self.text_of = {i: s for s, i in self.strings.items()}
        self.rank: dict[tuple[int, int], tuple[int, int]] = {}
        self.halves: dict[int, tuple[int, int]] = {}
        self.rank_of: dict[int, int] = {}
        for r, pair in enumerate(model["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            ia, ib, made = vocab[a], vocab[b], vocab[a + b]
            self.rank[ia, ib] = (r, made)
            if made not in self.halves:
                self.halves[made], self.rank_of[made] = (ia, ib), r
        self.automaton = ahocorasick.Automaton()
        for s, i in self.strings.items():
            self.automaton.add_word(s, (len(s), i))
        self.automaton.make_automaton()
        self.size = {i: len(s) for s, i in self.strings.items()}
        self.shorter: dict[int, int] = {}
        for s, i in self.strings.items():  # the next shorter token that begins the same
            self.shorter[i] = next((self.strings[s[:n]] for n in range(len(s) - 1, 0, -1) if s[:n] in self.strings), -1)
        self.longest = max(map(len, self.strings))
        # offset table of the decoder
        names = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        pieces = [names.get(i, "").encode() for i in range(max(names) + 1)]
        self.offsets = np.concatenate([[0], np.cumsum([len(p) for p in pieces])]).astype(np.int64)
        self.buffer = b"".join(pieces)
        self.compatible = lru_cache(MEMO_PAIRS)(self._compatible)
        o = self.offsets.tolist()
        self.names = [self.buffer[i:j] for i, j in zip(o, o[1:], strict=False)]
        self.memo = Memo(self.encode_chunk)

    def _packed(self, token: str) -> str:
        ends = self.suffix and token.endswith(self.suffix)
        body = token[: -len(self.suffix)] if ends else token
        out = [self.inner[c] for c in body]
        if ends:
            out[-1] = self.final[body[-1]]
        return "".join(out)

    def _compatible(self, left: int, right: int) -> bool:
        """Whether merges by rank leave the boundary of these two in their joined string: no merge may cross it."""
        return self.compatible_below(left, right, sys.maxsize)

    def compatible_below(self, left: int, right: int, limit: int) -> bool:
        """The same, but merges from rank ``limit`` on may cross it.

        The later of the two tokens' own merges is undone again and again; a merge across the boundary that comes before it would have been made.
        """
        while True:
            made = self.rank.get((left, right))
            if made and made[0] < limit:
                return False
            rl, rr = self.rank_of.get(left, -1), self.rank_of.get(right, -1)
            if rl < 0 and rr < 0:
                return True
            if rl > rr:
                limit, left = rl, self.halves[left][1]
                if limit_crossed(self.rank.get((left, right)), limit):
                    return False
            else:
                limit, right = rr, self.halves[right][0]
                # at equal rank the left pair merges first
                if limit_crossed(self.rank.get((left, right)), limit + 1):
                    return False

    def _matches(self, s: str) -> list[int]:
        """The longest token that starts at each position, from one pass of the automaton."""
        best = [-1] * len(s)
        for end, (n, i) in self.automaton.iter(s):
            best[end - n + 1] = i  # ends come in order, so the longest is written last
        return best

    def encode_piece(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one piece of a text."""
        s = "".join(map(chr, piece[:-1])) + chr(256 + piece[-1]) if self.suffix else "".join(map(chr, piece))
        if (whole := self.strings.get(s)) is not None and self._reached(whole):
            return (whole,)
        best, shorter, compatible, size, end = self._matches(s), self.shorter, self.compatible, self.size, len(s)
        ids: list[int] = []
        pos, dead, token = 0, set(), best[0]
        while pos < end:
            at = pos + size[token]
            if at not in dead and (not ids or compatible(ids[-1], token)):
                ids.append(token)
                pos = at
                if pos < end:
                    token = best[pos]
                continue
            token = shorter[token]
            while token < 0:  # no token fits here, so nothing that ends here can be part of the result
                dead.add(pos)
                token = ids.pop()
                pos -= size[token]
                token = shorter[token]
        return tuple(ids)

    def _reached(self, token: int) -> bool:
        """Whether merges by rank give this token for its own string."""
        if (pair := self.halves.get(token)) is None:
            return True
        return self._reached(pair[0]) and self._reached(pair[1]) and self.compatible_below(pair[0], pair[1], self.rank_of[token])

    def segments(self, text: str) -> Iterator[str | int]:
        """Normalised stretches of a text, and ids of the special tokens that stand between them."""
        last = 0
        for m in self.special_re.finditer(text) if self.special_re else ():
            yield self._normal(text[last : m.start()])
            yield self.special[m[0]]
            last = m.end()
        yield self._normal(text[last:] if last else text)

    def _normal(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # lower case of each character by itself
        return text.lower()

    def encode_chunk(self, chunk: str) -> tuple[int, ...]:
        """Ids of a stretch without white space: no piece of the pattern crosses any."""
        out: list[int] = []
        for piece in self.split_re.findall(chunk):
            out += self.encode_piece(piece.encode()) if len(piece) == len(chunk) else self.memo[piece]
        return tuple(out)

    def encode(self, text: str | None) -> list[int]:
        """Ids of a text; null and empty have none."""
        out: list[int] = []
        for segment in self.segments(text or ""):
            if type(segment) is int:
                out.append(segment)
            else:
                chunks = self.space_re.split(segment) if self.odd_re.search(segment) else segment.split()
                out.extend(chain.from_iterable(map(self.memo.__getitem__, chunks)))
        return out

    def decode(self, ids: list[int]) -> bytes:
        """What the library's decode gives as UTF-8: the token strings with blanks between, as the file names no decoder."""
        return b" ".join(map(self.names.__getitem__, ids))


class Memo(dict):
    """Ids by chunk; bounded, and long chunks are not kept."""

    def __init__(self, make) -> None:
        super().__init__()
        self.make = make

    def __missing__(self, chunk: str) -> tuple[int, ...]:
        ids = self.make(chunk)
        if len(self) < MEMO_PIECES and len(chunk) <= MEMO_CHARS:
            self[chunk] = ids
        return ids


def limit_crossed(made: tuple[int, int] | None, limit: int) -> bool:
    """Whether a merge across the boundary exists and comes before the one that was undone."""
    return made is not None and made[0] < limit


_codecs: dict[str, BpeCodec] = {}


def codec(path: str) -> BpeCodec:
    """The codec of a file, once per worker."""
    if path not in _codecs:
        _codecs[path] = BpeCodec(path)
    return _codecs[path]


def encode_column(df: DataFrame, path: str, text_col: str, digests: bool) -> DataFrame:
    """Adds ids (array of int) and n_tokens; with ``digests``, instead of ids, their SHA-256 and that of the decoded text.

    Columns of these names that are there already are replaced. Null text counts as empty. Every row is one task's work by itself; memory is
    bounded by the Arrow batch and the longest text. Each executor needs the vocabulary file at ``path``.
    """
    added = [T.StructField("n_tokens", T.LongType()), *([T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())] if digests else [T.StructField("ids", T.ArrayType(T.IntegerType()))])]
    keep = [f for f in df.schema.fields if f.name not in {a.name for a in added}]
    schema = T.StructType([*keep, *added])
    names = [f.name for f in keep]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            n, first, second = [], [], []
            for text in batch.column(batch.schema.get_field_index(text_col)):
                ids = c.encode(text.as_py())
                n.append(len(ids))
                if digests:
                    raw = array.array("I", ids)
                    if sys.byteorder == "big":
                        raw.byteswap()
                    first.append(hashlib.sha256(raw.tobytes()).hexdigest())
                    second.append(hashlib.sha256(c.decode(ids)).hexdigest())
                else:
                    first.append(ids)
            cols = [batch.column(batch.schema.get_field_index(x)) for x in names] + [pa.array(n, pa.int64())]
            cols += [pa.array(first, pa.string()), pa.array(second, pa.string())] if digests else [pa.array(first, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays(cols, names=[f.name for f in schema.fields])
        free_memory()

    return df.select(*[f"`{f.name}`" for f in df.schema.fields]).mapInArrow(run, schema)
