"""Language-model scores by cross-entropy difference.

Two bigram models of one form and one vocabulary, every word of the texts, score every token: one of the target documents, one of all others. A document's score is
the mean difference of the losses (target minus background): the lower, the more it reads like the target. The models are matched: background counts are scaled
to the target's number of tokens, so that both lean on their smoothing alike. No document is scored by its own words: they are taken out of the model that counted
them. Counts run over all documents and stay in distributed tables.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass
from hashlib import blake2b
from itertools import count

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_memory

#: Weight of the words' frequencies behind a bigram, in tokens; characters of texts of a chunk, on average, and those whose keys a bucket counts.
BACKOFF, CHUNK_CHARS, BUCKET_CHARS = 8.0, 8_000_000, 16_000_000
PAIR, WORD, TARGETS = 0, 1, 2
COUNTS = {PAIR: ("t", "b"), WORD: ("t", "b", "before_t", "before_b")}
BLOCK = pa.schema([("kind", pa.int32()), ("bucket", pa.int32()), ("chunk", pa.int32()), ("n", pa.int32()), ("keys", pa.binary()), *[(c, pa.binary()) for c in COUNTS[WORD]]])
SUMS = pa.schema([*[f for f in BLOCK if f.name != "keys"], *[(c, pa.int64()) for c in ("words", "all_t", "all_b")]])


def _mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """64-bit hashes of pairs of 64-bit numbers."""
    x = a * np.uint64(0x9E3779B97F4A7C15) + b * np.uint64(0xC2B2AE3D27D4EB4F)
    for s, k in ((32, 0xD6E8FEB86659FD93), (29, 0xFF51AFD7ED558CCD)):
        x = (x ^ (x >> np.uint64(s))) * np.uint64(k)
    return x ^ (x >> np.uint64(32))


@dataclass
class Chunk:
    """Tokens of some texts: the text of each, sorted hashes of the distinct bigrams, and of the words and the mark, and each token's places in them."""

    sizes: np.ndarray
    doc: np.ndarray
    pairs: np.ndarray
    words: np.ndarray
    pair_at: np.ndarray
    word_at: np.ndarray
    before_at: np.ndarray

    @classmethod
    def of(cls, texts: pa.ChunkedArray) -> Chunk:
        ids: defaultdict = defaultdict(count().__next__)
        parts = [np.fromiter(map(ids.__getitem__, (t.as_py() or "").encode().split()), np.int32) for t in texts]
        sizes = np.array([len(p) for p in parts], np.int64)
        hashes = np.frombuffer(b"".join(blake2b(w, digest_size=8).digest() for w in [*ids, b""]), "<u8")  # the mark is the empty word
        order = np.argsort(hashes, kind="stable")
        back = np.empty(len(hashes), np.int64)
        back[order] = np.arange(len(hashes))
        words, mark = hashes[order], back[len(ids)]
        word = back[np.concatenate([np.zeros(0, np.int32), *parts])]
        before = np.concatenate([[mark], word])[:-1]
        before[(np.cumsum(sizes) - sizes)[sizes > 0]] = mark
        code, at = np.unique(before * len(words) + word, return_inverse=True)
        pairs = _mix(words[code // len(words)], words[code % len(words)])
        order = np.argsort(pairs, kind="stable")
        back = np.empty(len(pairs), np.int64)
        back[order] = np.arange(len(pairs))
        return cls(sizes, np.repeat(np.arange(len(sizes)), sizes), pairs[order], words, back[at], word, before)

    def counts(self, flags: np.ndarray) -> dict[int, list[np.ndarray]]:
        """By kind what COUNTS names; ``flags``: whether each text is a target."""
        w = flags[self.doc].astype(float)
        pairs, words = len(self.pairs), len(self.words)
        add = lambda at, n: [np.bincount(at, w, n), np.bincount(at, 1 - w, n)]
        return {PAIR: add(self.pair_at, pairs), WORD: add(self.word_at, words) + add(self.before_at, words)}

    def own(self, at: np.ndarray) -> np.ndarray:
        """Of each token, how often what it is at occurs in its text."""
        if not len(at):
            return np.zeros(0)
        _, back, n = np.unique(self.doc * (int(at.max()) + 1) + at, return_inverse=True, return_counts=True)
        return n[back].astype(float)


def _packed(x: np.ndarray) -> bytes:
    """Whole numbers, their bytes ordered by value so that those that are zero shrink."""
    return pa.compress(x.astype("<u8").view(np.uint8).reshape(-1, 8).T.tobytes(), codec="zstd", asbytes=True)


def _unpacked(raw: bytes, n: int) -> np.ndarray:
    return np.frombuffer(pa.decompress(raw, 8 * n, codec="zstd", asbytes=True), np.uint8).reshape(8, n).T.copy().view("<u8").ravel()


def _joined(table: pa.Table, name: str) -> np.ndarray:
    """Numbers of all rows of a column of packed counts, one after the other."""
    return np.concatenate([np.zeros(0), *[_unpacked(x, n) for x, n in zip(table[name].to_pylist(), table["n"].to_pylist(), strict=True) if n]])


def score(docs: DataFrame, targets: DataFrame, backoff: float = BACKOFF) -> DataFrame:
    """doc_id, n_tokens, loss_target, loss_background, score of every row.

    ``targets``: doc_id of target documents (repeated and null ones count once and not at all). Null and empty texts: no tokens, zero losses and score.
    Without target texts, or without others, that model is uniform over the words. Rows with a null id are background; rows of one id are each a text.
    Texts are dealt into chunks. A chunk sends the counts of its distinct bigrams and words, keyed by 64-bit hashes, to buckets of keys; buckets add them up and
    send the sums back in the order of the chunk's keys, so keys travel once. A chunk's keys and their order do not depend on the order of its rows. Every bucket
    of words tells every chunk how many words and tokens it counted: nothing is gathered on the driver.
    """
    n_chars = docs.agg(F.sum(F.length("text"))).first()[0] or 0
    n_chunks, n_buckets = (max(1, -(-n_chars // n)) for n in (CHUNK_CHARS, BUCKET_CHARS))
    home = lambda c: F.pmod(F.xxhash64(c), F.lit(n_chunks)).cast("int")
    rows = docs.select(F.col("doc_id").cast("long"), "text").withColumn("chunk", F.when(F.col("doc_id").isNull(), home("text")).otherwise(home("doc_id")))
    wanted = targets.select(F.col("doc_id").cast("long")).filter("doc_id is not null").withColumn("chunk", home("doc_id"))

    def counted(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        chunk, out, at = Chunk.of(left["text"]), [], key[0].as_py()
        asked = right["doc_id"].combine_chunks()
        counts = chunk.counts(_members(left["doc_id"], asked))
        for kind, keys in ((PAIR, chunk.pairs), (WORD, chunk.words)):
            bucket = ((keys >> np.uint64(32)) * np.uint64(n_buckets) >> np.uint64(32)).astype(np.int64)
            for k, lo, hi in zip(*_runs(bucket), strict=True):
                row = {"kind": kind, "bucket": k, "chunk": at, "n": hi - lo, "keys": _packed(np.diff(keys[lo:hi], prepend=np.uint64(0)))}
                out.append(row | {c: _packed(x[lo:hi]) for c, x in zip(COUNTS[kind], counts[kind], strict=True)})
        out.append({"kind": TARGETS, "bucket": at, "chunk": at, "n": len(asked), "t": asked.to_numpy(zero_copy_only=False).astype("<i8").tobytes()})
        free_memory()
        return pa.Table.from_pylist(out, schema=BLOCK)

    def summed(key: tuple, table: pa.Table) -> pa.Table:
        kind, bucket = (k.as_py() for k in key)
        if kind == TARGETS:  # one chunk's own list
            return pa.Table.from_pylist(table.drop(["keys"]).to_pylist(), schema=SUMS)
        sizes, chunks = table["n"].to_pylist(), table["chunk"].to_pylist()
        steps = [_unpacked(x, n) for x, n in zip(table["keys"].to_pylist(), sizes, strict=True)]
        keys, at = np.unique(np.concatenate([np.cumsum(x, dtype=np.uint64) for x in steps]), return_inverse=True)
        out = [{"kind": kind, "bucket": bucket, "chunk": c, "n": n} for c, n in zip(chunks, sizes, strict=True)]
        told, seen = {}, np.zeros(len(keys))
        for name in COUNTS[kind]:
            total = np.bincount(at, _joined(table, name), len(keys))
            for row, x in zip(out, np.split(total[at], np.cumsum(sizes)[:-1]), strict=True):
                row[name] = _packed(x)
            if kind == WORD and name in ("t", "b"):
                told["all_" + name] = int(total.sum())
                seen += total
        if kind == WORD:
            told["words"] = int((seen > 0).sum())  # the mark is no word
            out += [{"kind": kind, "bucket": bucket, "chunk": c, "n": 0} for c in set(range(n_chunks)) - set(chunks)]
        free_memory()
        return pa.Table.from_pylist([row | told for row in out], schema=SUMS)

    def scored(left: pa.Table, right: pa.Table) -> pa.Table:
        chunk, losses = Chunk.of(left["text"]), []
        if left.num_rows:
            pairs, words = (right.filter(pc.equal(right["kind"], kind)).sort_by("bucket") for kind in (PAIR, WORD))
            lists = [np.frombuffer(x, "<i8") for x in right.filter(pc.equal(right["kind"], TARGETS))["t"].to_pylist()]
            flags = _members(left["doc_id"], pa.array(np.concatenate([np.zeros(0, np.int64), *lists]), pa.int64()))
            pair, word, before = (chunk.own(at) for at in (chunk.pair_at, chunk.word_at, chunk.before_at))
            tokens = {c: sum(words["all_" + c].to_pylist()) for c in ("t", "b")}
            n_words = sum(words["words"].to_pylist())
            for c, counted_in in (("t", flags), ("b", ~flags)):
                scale = tokens["t"] / tokens["b"] if c == "b" and tokens["t"] and tokens["b"] else 1.0
                held = counted_in[chunk.doc].astype(float)  # whether the token is among the model's own
                whole = scale * (tokens[c] - held * chunk.sizes[chunk.doc]) + n_words + 1  # one for every word and one for unknown ones
                p = (scale * (_joined(words, c)[chunk.word_at] - held * word) + 1) / whole
                joint = scale * (_joined(pairs, c)[chunk.pair_at] - held * pair)
                head = scale * (_joined(words, "before_" + c)[chunk.before_at] - held * before)
                losses.append(np.bincount(chunk.doc, -np.log((joint + backoff * p) / (head + backoff)), len(chunk.sizes)) / np.maximum(chunk.sizes, 1))
        t, b = losses or [np.zeros(0)] * 2
        free_memory()
        return pa.table({"doc_id": left["doc_id"].combine_chunks(), "n_tokens": chunk.sizes, "loss_target": t, "loss_background": b})

    numbers, blobs = "kind int, bucket int, chunk int, n int", ", ".join(f"{c} binary" for c in COUNTS[WORD])
    blocks = rows.groupBy("chunk").cogroup(wanted.groupBy("chunk")).applyInArrow(counted, f"{numbers}, keys binary, {blobs}")
    sums = blocks.groupBy("kind", "bucket").applyInArrow(summed, f"{numbers}, {blobs}, words long, all_t long, all_b long")
    out = rows.groupBy("chunk").cogroup(sums.groupBy("chunk")).applyInArrow(scored, "doc_id long, n_tokens long, loss_target double, loss_background double")
    return out.withColumn("score", F.col("loss_target") - F.col("loss_background"))


def _members(ids: pa.ChunkedArray, asked: pa.Array) -> np.ndarray:
    """Whether each id is among the asked ones; null is not."""
    found = pc.fill_null(pc.and_(pc.is_valid(ids), pc.is_in(ids, asked)), False)
    return np.asarray(found.to_numpy(), bool)


def _runs(values: np.ndarray) -> tuple[list, list, list]:
    """Values, starts and ends of runs of equal values."""
    starts = np.flatnonzero(np.diff(values, prepend=-1))
    return values[starts].tolist(), starts.tolist(), np.append(starts, len(values))[1:].tolist()


def oracle_sql(backoff: float = BACKOFF) -> str:
    """The query over ``documents`` with target labels.quality = 1, in DuckDB's SQL, rounded to six digits."""
    return f"""
WITH toks AS MATERIALIZED (SELECT doc_id, unnest(w) AS w, generate_subscripts(w, 1) AS i FROM (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w FROM documents)),
pairs AS MATERIALIZED (SELECT doc_id, coalesce(lag(w) OVER (PARTITION BY doc_id ORDER BY i), '') AS h, w FROM toks),
good AS (SELECT DISTINCT doc_id AS gid FROM labels WHERE quality = 1 AND doc_id IS NOT NULL),
own AS MATERIALIZED (SELECT doc_id, h, w, count(*)::DOUBLE AS c, (max(gid) IS NOT NULL)::INT AS g FROM pairs LEFT JOIN good ON doc_id = gid GROUP BY doc_id, h, w),
own_head AS MATERIALIZED (SELECT doc_id, h, sum(c) AS ch FROM own GROUP BY doc_id, h),
own_word AS MATERIALIZED (SELECT doc_id, w, sum(c) AS cw FROM own GROUP BY doc_id, w),
own_all AS MATERIALIZED (SELECT doc_id, sum(c) AS cn FROM own GROUP BY doc_id),
by_pair AS MATERIALIZED (SELECT h, w, sum(c * g) AS t, sum(c * (1 - g)) AS b FROM own GROUP BY h, w),
by_head AS MATERIALIZED (SELECT h, sum(t) AS ht, sum(b) AS hb FROM by_pair GROUP BY h),
by_word AS MATERIALIZED (SELECT w, sum(t) AS wt, sum(b) AS wb FROM by_pair GROUP BY w),
sums AS MATERIALIZED (SELECT sum(wt) AS nt, sum(wb) AS nb, count(*) AS v, CASE WHEN sum(wt) > 0 AND sum(wb) > 0 THEN sum(wt) / sum(wb) ELSE 1.0 END AS r FROM by_word),
cells AS (
    SELECT doc_id, c,
        -ln((t - g * c + {backoff} * (wt - g * cw + 1) / (nt - g * cn + v + 1)) / (ht - g * ch + {backoff})) AS lt,
        -ln((r * (b - (1 - g) * c) + {backoff} * (r * (wb - (1 - g) * cw) + 1) / (r * (nb - (1 - g) * cn) + v + 1)) / (r * (hb - (1 - g) * ch) + {backoff})) AS lb
    FROM own JOIN own_head USING (doc_id, h) JOIN own_word USING (doc_id, w) JOIN own_all USING (doc_id) JOIN by_pair USING (h, w) JOIN by_head USING (h) JOIN by_word USING (w), sums),
scored AS (SELECT doc_id, sum(c)::BIGINT AS n, sum(c * lt) / sum(c) AS lt, sum(c * lb) / sum(c) AS lb FROM cells GROUP BY doc_id)
SELECT d.doc_id, coalesce(n, 0) AS n_tokens, round(coalesce(lt, 0), 6) AS loss_target, round(coalesce(lb, 0), 6) AS loss_background, round(coalesce(lt - lb, 0), 6) AS score
FROM documents d LEFT JOIN scored s ON s.doc_id = d.doc_id"""
