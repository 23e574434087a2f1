"""Substring dedup by sliding sentence spans.

A text is cut into sentences. From every sentence, forward and backward, a run takes as many consecutive sentences as make enough words, two at least; a passage
that repeats is thus covered from its first to its last sentence. Runs are hashed once a text, in Arrow batches, and kept as arrays beside the document's id.
A run that occurs earlier in its own text is settled there. The others, one a text and hash, meet in a global aggregation of two numbers per hash, the least
and the greatest id, which combines on the map side; hashes of several documents are joined back to their places, and sentences that a place other than the
first covers are removed. Both sides of that join are plain tables, so adaptive execution can split a hash that a third of all documents hold.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, free_memory, unused_name

#: Least words and least sentences of a run.
MIN_WORDS, MIN_SENTENCES = 20, 2
#: Pieces that lie end to end over a whole text: up to the marks that end a sentence or line, with the white space after them.
SENTENCE_RE = r"[^.!?\n]*[.!?\n]+[ \t\n]*|[^.!?\n]+"
_SENTENCE = re.compile(SENTENCE_RE.encode())
U = np.uint64
_POWERS = [pow(0x9E3779B97F4A7C15, k + 1, 1 << 64) for k in range(MIN_WORDS + 1)]
#: Bytes of text whose runs are worked out together.
PART_BYTES = 1 << 20


def sentences(text: str | None) -> list[bytes]:
    """Sentences of a text, which together are the text in UTF-8; null counts as empty."""
    return _SENTENCE.findall((text or "").encode())


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(33))) * U(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> U(29))) * U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(32))


def runs(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of some texts, by text and first sentence: number of the text, two hashes, first and last sentence (numbered from 0).

    Sentences without words are passed over. A run is hashed by the words of its sentences, whatever white space parts them.
    """
    doc, number, size, raw = [], [], [], []
    for d, text in enumerate(texts):
        for i, s in enumerate(sentences(text)):
            ws = s.split()
            if ws:
                doc.append(d)
                number.append(i)
                size.append(len(ws))
                raw.append(xxhash.xxh3_128_digest(b" ".join(ws)))
    doc, number, size = (np.array(x, np.int64) for x in (doc, number, size))
    n = len(doc)
    hashes = np.frombuffer(b"".join(raw), U).reshape(n, 2)
    ends = np.cumsum(size)  # words up to the end of each sentence, over all texts
    begins = ends - size
    low, high = np.searchsorted(doc, doc, "left"), np.searchsorted(doc, doc, "right") - 1  # first and last sentence of the text
    at = np.arange(n)
    more = MIN_SENTENCES - 1
    ahead = np.maximum(np.searchsorted(ends, begins + MIN_WORDS, "left"), at + more)
    back = np.minimum(np.searchsorted(begins, ends - MIN_WORDS, "right") - 1, at - more)
    a, b = ahead <= high, back >= low
    first, last = np.concatenate([at[a], back[b]]), np.concatenate([ahead[a], at[b]])
    code = np.unique(first * (MIN_WORDS + 2) + (last - first))  # no run has more sentences than words
    first, width = code // (MIN_WORDS + 2), code % (MIN_WORDS + 2)
    h = np.zeros((len(first), 2), U)
    h += (width.astype(U) + U(1))[:, None]
    for k in range(int(width.max()) + 1 if len(width) else 0):
        some = np.flatnonzero(width >= k)
        h[some] += hashes[first[some] + k] * U(_POWERS[k])
    h = _mix(h)
    return doc[first], h[:, 0], h[:, 1], number[first], number[first + width]


def _marked(spans: np.ndarray) -> list[int]:
    """Sentences that spans (first * 2^32 + last) cover, sorted."""
    return np.unique(np.concatenate([np.arange(s >> 32, (s & 0xFFFFFFFF) + 1) for s in spans.tolist()] or [np.zeros(0, np.int64)])).tolist()


def run_lists(rows: DataFrame) -> DataFrame:
    """id, key, own, h1, h2, span for every row of ``rows`` (id, key, text).

    h1, h2, span: a run's hashes and its place (first * 2^32 + last), once per hash, where it stands first in the text; own: sentences covered by
    runs that stand in the text a second time or later.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column, start = batch.column("text"), 0
            while start < batch.num_rows:
                texts, held, stop = [], 0, start
                while stop < batch.num_rows and (held < PART_BYTES or not texts):
                    texts.append(column[stop].as_py())
                    held += len(texts[-1] or "")
                    stop += 1
                yield _listed(batch.slice(start, stop - start), texts)
                start = stop
        free_memory()

    return rows.mapInArrow(run, "id long, key long, own array<int>, h1 array<long>, h2 array<long>, span array<long>")


def _listed(batch: pa.RecordBatch, texts: list[str | None]) -> pa.RecordBatch:
    doc, h1, h2, first, last = runs(texts)
    span = first << 32 | last
    order = np.lexsort((span, h2, h1, doc))
    doc, h1, h2, span = doc[order], h1[order], h2[order], span[order]
    again = np.zeros(len(doc), bool)
    again[1:] = (doc[1:] == doc[:-1]) & (h1[1:] == h1[:-1]) & (h2[1:] == h2[:-1])
    own = [_marked(x) for x in np.split(span[again], np.searchsorted(doc[again], np.arange(1, len(texts))))]
    once = ~again
    ends = pa.array(np.searchsorted(doc[once], np.arange(len(texts) + 1)).astype(np.int32))
    lists = [pa.ListArray.from_arrays(ends, pa.array(x[once].view(np.int64))) for x in (h1, h2, span)]
    return pa.RecordBatch.from_arrays([batch.column("id"), batch.column("key"), pa.array(own, pa.list_(pa.int32())), *lists], names=["id", "key", "own", "h1", "h2", "span"])


def repeated_sentences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, key (a hash of the text) and removed (sorted sentence numbers) of texts with sentences that a repeated run's place other than the first covers.

    The first place is the least (id, sentence). Rows with one id and one text count as one; rows with one id and different texts are versions of one document:
    neither is a repeat of the other. Rows without an id take no part. Empty table: no rows.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.xxhash64(F.col(f"`{text_col}`")).alias("key"), F.col(f"`{text_col}`").alias("text"))
    lists = cut(run_lists(rows.filter("id is not null")))
    places = lists.select("id", "key", F.explode(F.arrays_zip("h1", "h2", "span")).alias("r"))
    hashes = places.select("id", "r.h1", "r.h2").groupBy("h1", "h2").agg(F.min("id").alias("least"), F.max("id").alias("most"))
    shared = cut(hashes.filter("least < most").select("h1", "h2", "least"))
    later = places.select("id", "key", "r.h1", "r.h2", "r.span").join(shared, ["h1", "h2"]).filter("id > least")
    covered = later.select("id", "key", F.explode(F.expr("sequence(cast(shiftright(span, 32) as int), cast(span & 4294967295L as int))")).alias("s"))
    covered = covered.union(lists.filter(F.size("own") > 0).select("id", "key", F.explode("own").alias("s")))
    return covered.groupBy("id", "key").agg(F.sort_array(F.collect_set("s")).alias("removed"))


def drop_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", counts: tuple[str, str] = ("n_sentences", "n_removed")) -> DataFrame:
    """All rows and columns of ``docs``, the text without repeated sentences, plus two counts (columns of these names are replaced).

    Null text stays null and has no sentences; an empty one stays empty. What stays of a text is unchanged. Repeated rows are cut alike.
    """
    fields = [f for f in docs.schema.fields if f.name not in counts]
    names = [f.name for f in fields]
    text_at = names.index(text_col)
    gone = cut(repeated_sentences(docs, id_col, text_col))
    rows = docs.select(*[F.col(f"`{c}`").alias(f"d{k}") for k, c in enumerate(names)])
    key = F.xxhash64(F.col(f"d{text_at}"))
    rows = rows.join(gone, (F.col(f"d{names.index(id_col)}").cast("long") == F.col("id")) & (key == F.col("key")), "left").drop("id", "key")
    schema = T.StructType([*[T.StructField(f"d{k}", f.dataType) for k, f in enumerate(fields)], T.StructField("n", T.LongType()), T.StructField("r", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, n, r = [], [], []
            for text, removed in zip(batch.column(text_at), batch.column("removed"), strict=True):
                parts = sentences(text := text.as_py())
                if (removed := removed.as_py()) is not None:
                    for i in removed:
                        parts[i] = b""
                    text = b"".join(parts).decode()
                texts.append(text)
                n.append(len(parts))
                r.append(len(removed or ()))
            cols = [pa.array(texts, batch.schema.field(text_at).type) if k == text_at else batch.column(k) for k in range(len(fields))]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(n, pa.int64()), pa.array(r, pa.int64())], names=schema.names)
        free_memory()

    out = rows.mapInArrow(run, schema)
    return out.select(*[F.col(f"d{k}").alias(c) for k, c in enumerate(names)], F.col("n").alias(counts[0]), F.col("r").alias(counts[1]))


def without_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The columns of ``docs``, texts without repeated sentences, without the documents that nothing but white space is left of.

    Columns n_sentences or n_removed of the caller stay as they are; n_chars, where it is there, is counted again.
    """
    names = docs.columns
    counts = unused_name(names, "n_sentences"), unused_name(names, "n_removed")
    out = drop_repeats(docs, id_col, text_col, counts)
    out = out.filter((F.col(f"`{counts[1]}`") == 0) | F.col(f"`{text_col}`").rlike(r"[^\x20\x09-\x0D]"))
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.length(F.col(f"`{text_col}`")).cast(docs.schema["n_chars"].dataType))
    return out.select(*[f"`{c}`" for c in names])
