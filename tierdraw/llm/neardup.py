"""N-gram Jaccard join by chosen paths.

A text is the set of its word n-grams. Texts with one set are one class and go on as one representative. A set is embedded as min-hash tokens, which two
sets share with their Jaccard similarity as chance. A run splits the sets again and again: at every node of its tree a few coordinates are drawn from the
node's path alone, and a set goes on to the child that its own token at this coordinate names; sets that reach one leaf are compared. A run finds a pair
at the threshold with a known chance, so runs are repeated until the target recall is reached.

Leaves with the same members are compared once; small leaves by brute force over sketches, large ones are split further on, or, where their members are alike on
average, taken as one candidate group. Candidate groups are components of what looked alike; within them each text is read once and every pair is decided exactly,
in blocks, so that no pairs are written down: a task gives a count of links per set and a star of links to the least set.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .components import components
from .common import WORD_RE, cut, free_memory, other_columns

WORDS, THRESHOLD = 5, (4, 5)  # words of an n-gram; similarity as a fraction
COORDS, SKETCH, LEVELS, BRANCHES = 128, 64, 4, 2
#: Target recall of a pair at the threshold; members of a leaf that is compared at once; rounds of further splitting; members and n-grams of a block.
RECALL, LEAF, SPLITS, BLOCK, BLOCK_GRAMS = 0.9999, 1000, 3, 1024, 1_000_000
#: Share of sketch coordinates from which on two sets of a leaf are candidates; average agreement from which on a large leaf is one group.
ALIKE, TIGHT = 0.58, 0.5
MEMO_WORDS = 50_000
U = np.uint64


def runs_for(recall: float, similarity: float = THRESHOLD[0] / THRESHOLD[1], levels: int = LEVELS, branches: int = BRANCHES) -> int:
    """Runs that find a pair of the given similarity with the given chance: a path survives with 1 - (1 - s p)^branches."""
    p = 1.0
    for _ in range(levels):
        p = 1 - (1 - similarity * p) ** branches
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - p)))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(33))) * U(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> U(29))) * U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(32))


class _WordHash(dict):
    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word)
        if len(self) < MEMO_WORDS and len(word) < 64:
            self[word] = h
        return h


_words = _WordHash()
_POWERS = _mix(np.arange(1, 64, dtype=U)) | U(1)
_FACTORS = _mix(np.arange(1000, 1000 + COORDS, dtype=U)) | U(1)


def gram_set(text: str | None, words: int = WORDS) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct word n-grams; a shorter text is one n-gram, and one without words has none."""
    ws = (text or "").encode().split()
    if not ws:
        return np.zeros(0, U)
    h = np.fromiter(map(_words.__getitem__, ws), U, len(ws))
    k = min(words, len(ws))
    n = len(ws) - k + 1
    out = np.full(n, U(k), U)
    for j in range(k):
        out += h[j : j + n] * _POWERS[j]
    return np.unique(_mix(out))


def signature(grams: np.ndarray) -> np.ndarray:
    """Least hash of a set under each of COORDS hash functions."""
    best = np.full(COORDS, U(0xFFFFFFFFFFFFFFFF))
    for i in range(0, len(grams), 2048):
        best = np.minimum(best, (grams[i : i + 2048, None] * _FACTORS).min(axis=0))
    return best


def leaves(sigs: np.ndarray, runs: int) -> np.ndarray:
    """Leaf of every path that each set takes: one row a set, runs * BRANCHES ** LEVELS columns."""
    rows = np.arange(len(sigs))
    out = []
    for r in range(runs):
        front = [np.full(len(sigs), _mix(np.array([r + 1], U))[0])]
        for level in range(LEVELS):
            nxt = []
            for path in front:
                for b in range(BRANCHES):
                    node = _mix(path ^ U((level * BRANCHES + b + 1) * 0x9E3779B1))
                    token = sigs[rows, (node % U(COORDS)).astype(np.int64)]
                    nxt.append(_mix(node ^ (token * U(0x9E3779B97F4A7C15))))
            front = nxt
        out += front
    return np.stack(out, axis=1) if len(sigs) else np.zeros((0, runs * BRANCHES**LEVELS), U)


def signatures(docs: DataFrame, id_col: str, text_col: str, runs: int) -> DataFrame:
    """id, key (hash of the text), d1, d2 (digest of the set; null without words), grams (their number), sketch, paths."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                yield _signed(batch.slice(start, 256), runs)
        free_memory()

    rows = _rows(docs, id_col, text_col)
    return rows.mapInArrow(run, "id long, key long, d1 long, d2 long, grams int, sketch binary, paths array<long>")


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, key (a hash of the text), text."""
    text = F.col(f"`{text_col}`")
    return docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.xxhash64(text).alias("key"), text.alias("text"))


def _signed(batch: pa.RecordBatch, runs: int) -> pa.RecordBatch:
    sets = [gram_set(t.as_py()) for t in batch.column("text")]
    some = np.array([len(s) > 0 for s in sets])
    sigs = np.stack([signature(s) for s in sets])
    paths = leaves(sigs, runs).view(np.int64)
    sketch = (_mix(sigs[:, :SKETCH]) >> U(56)).astype(np.uint8)
    digests = np.frombuffer(b"".join(xxhash.xxh3_128_digest(s.tobytes()) for s in sets), np.int64).reshape(-1, 2)
    ends = np.concatenate([[0], np.cumsum(np.where(some, paths.shape[1], 0))]).astype(np.int32)
    columns = {
        "id": batch.column("id"),
        "key": batch.column("key"),
        "d1": pa.array(digests[:, 0], pa.int64(), mask=~some),
        "d2": pa.array(digests[:, 1], pa.int64(), mask=~some),
        "grams": pa.array([len(s) for s in sets], pa.int32()),
        "sketch": pa.array([s.tobytes() for s in sketch], pa.binary()),
        "paths": pa.ListArray.from_arrays(pa.array(ends), pa.array(paths[some].ravel(), pa.int64())),
    }
    return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))


def _groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Groups of equal leading key columns of sorted rows, across batches."""
    held: list[pa.Table] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(keys)]
        changed = np.zeros(batch.num_rows, bool)
        for c in cols:
            changed[1:] |= c[1:] != c[:-1]
        starts = [0, *np.flatnonzero(changed).tolist(), batch.num_rows]
        for a, b in zip(starts, starts[1:], strict=False):
            key = tuple(c[a] for c in cols)
            if last is not None and key != last:
                yield pa.concat_tables(held).combine_chunks()
                held = []
            held.append(pa.Table.from_batches([batch.slice(a, b - a)]))
            last = key
    if held:
        yield pa.concat_tables(held).combine_chunks()


def _roots(near: np.ndarray) -> np.ndarray:
    """Least index of the component of each row of a symmetric boolean matrix."""
    n = len(near)
    root = np.full(n, -1)
    for i in range(n):
        if root[i] < 0:
            root[i], todo = i, near[i].copy()
            while True:
                new = np.flatnonzero(todo & (root < 0))
                if not len(new):
                    break
                root[new] = i
                todo = near[new].any(axis=0)
    return root


def _alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stars of sets of a leaf whose sketches agree: (a, b)."""
    least = math.ceil(ALIKE * SKETCH)
    a_out: list[int] = []
    b_out: list[int] = []
    for g in _groups(batches, 1):
        ids = g.column("id").to_numpy()
        s = np.frombuffer(b"".join(g.column("sketch").to_pylist()), np.uint8).reshape(len(ids), SKETCH)
        order = np.argsort(ids)
        ids, s = ids[order], s[order]
        if len(ids) == 2:
            if (s[0] == s[1]).sum() >= least:
                a_out.append(int(ids[1]))
                b_out.append(int(ids[0]))
        else:
            step = max(1, 4_000_000 // (len(ids) * SKETCH))
            near = np.concatenate([(s[i : i + step, None, :] == s[None, :, :]).sum(axis=2) >= least for i in range(0, len(ids), step)])
            root = _roots(near)
            for i in np.flatnonzero(root != np.arange(len(ids))).tolist():
                a_out.append(int(ids[i]))
                b_out.append(int(ids[root[i]]))
        if len(a_out) >= 50_000:
            yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(b_out, pa.int64())], names=["a", "b"])
            a_out, b_out = [], []
    yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(b_out, pa.int64())], names=["a", "b"])
    free_memory()


def _leaf_members(members: DataFrame) -> DataFrame:
    """path, id, n of leaves with two members or more, one of all leaves that have the same members."""
    tallies = members.groupBy("path").agg(F.count(F.lit(1)).alias("n"), F.expr("bit_xor(xxhash64(id))").alias("x"), F.expr("bit_xor(xxhash64(id, 1))").alias("y"))
    one = tallies.filter("n > 1").groupBy("n", "x", "y").agg(F.min("path").alias("path"))
    return members.join(one.select("path", "n"), "path")


def _child_paths(repeats: int = 2) -> Column:
    """Further paths of a set at a large leaf: two and one coordinates of the sketch in turn, drawn from the path."""

    def grow(path: Column, salt: int) -> Column:
        at = F.pmod(F.xxhash64(path, F.lit(salt)), F.lit(SKETCH)).cast("int")
        return F.xxhash64(path, F.lit(salt), F.substring(F.col("sketch"), at + 1, F.lit(1)))

    out = []
    for r in range(repeats):
        front = [F.col("path")]
        for level, width in enumerate((2, 1, 2, 1)):
            front = [grow(p, 100 * r + 10 * level + b) for p in front for b in range(width)]
        out += front
    return F.array(*out)


def candidate_links(classes: DataFrame) -> DataFrame:
    """a, b: stars that connect representatives which may be similar. ``classes``: id, sketch, paths."""
    sketches = classes.select("id", "sketch")
    members = classes.select(F.explode("paths").alias("path"), "id")
    found = []
    for turn in range(SPLITS + 1):
        leaf = cut(_leaf_members(members).join(sketches, "id"))
        small = leaf.filter(F.col("n") <= LEAF).select("path", "id", "sketch").repartition("path").sortWithinPartitions("path")
        found.append(small.mapInArrow(_alike, "a long, b long"))
        large = leaf.filter(F.col("n") > LEAF)
        if large.isEmpty():
            break
        tight = large.select("path").distinct()
        if turn < SPLITS:
            probe = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.substring("sketch", 1 + k * (SKETCH // 8), 1).alias("v")) for k in range(8)]))
            alike = large.select("path", probe.alias("p")).groupBy("path", "p.k", "p.v").agg(F.count(F.lit(1)).cast("double").alias("c"))
            alike = alike.groupBy("path").agg((8 * F.sum(F.col("c") * F.col("c")) / (F.sum("c") * F.sum("c"))).alias("agree"))
            tight = cut(alike.filter(F.col("agree") >= TIGHT).select("path"))
        centre = large.join(tight, "path", "left_semi").groupBy("path").agg(F.min("id").alias("b"))
        found.append(large.join(centre, "path").filter("id <> b").select(F.col("id").alias("a"), "b"))
        if turn == SPLITS:
            break
        members = large.join(tight, "path", "left_anti").select(F.explode(F.array_distinct(_child_paths())).alias("path"), "id")
    out = found[0]
    for df in found[1:]:
        out = out.union(df)
    return out.distinct()


def shared_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections. Elements of few sets are counted as pairs, those of many as columns of a product."""
    n = len(sets)
    who = np.repeat(np.arange(n), [len(s) for s in sets])
    what = np.concatenate(sets)
    order = np.argsort(what, kind="stable")
    what, who = what[order], who[order]
    starts = np.flatnonzero(np.concatenate([[True], what[1:] != what[:-1]]))
    df = np.diff(np.concatenate([starts, [len(what)]]))
    out = np.zeros((n, n), np.int32)
    few = 1 if n <= 64 else 12
    for k in range(2, few + 1):
        rows = who[starts[df == k][:, None] + np.arange(k)]
        for p in range(k):
            for q in range(p + 1, k):
                code, c = np.unique(rows[:, p] * n + rows[:, q], return_counts=True)
                out.ravel()[code] += c
    out += out.T
    many = np.flatnonzero(df > few)
    width = max(256, 4_000_000 // n)
    for i in range(0, len(many), width):
        cols = many[i : i + width]
        x = np.zeros((n, len(cols)), np.float32)
        sizes = df[cols]
        at = np.repeat(starts[cols], sizes) + np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        x[who[at], np.repeat(np.arange(len(cols)), sizes)] = 1
        out += np.rint(x @ x.T).astype(np.int32)
    return out


def _set_of(body) -> np.ndarray:
    """Set of a group's member: of its text, or the set itself where it was sent."""
    return np.frombuffer(body, U) if isinstance(body, bytes) else gram_set(body)


def _decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Exact links of one pair of blocks of a candidate group: node, root, links (rows linked to)."""
    num, den = THRESHOLD
    for g in _groups(batches, 3):
        lo, hi = g.column("lo")[0].as_py(), g.column("hi")[0].as_py()
        ids, order = np.unique(g.column("node").to_numpy(), return_index=True)  # a class whose row is there twice counts once
        weight, block = (g.column(c).to_numpy()[order] for c in ("weight", "block"))
        sets = [_set_of(g.column("body")[i].as_py()) for i in order.tolist()]
        if len(ids) < 2 or not sum(map(len, sets)):
            continue
        both = shared_counts(sets)
        size = np.array([len(s) for s in sets], np.int32)
        near = den * both >= num * (size[:, None] + size[None, :] - both)
        near &= both > 0
        np.fill_diagonal(near, False)
        if lo != hi:
            near &= block[:, None] != block[None, :]
        links, root = np.array([weight[row].sum() for row in near]), _roots(near)
        some = np.flatnonzero(near.any(axis=1))
        columns = [pa.array(x[some], pa.int64()) for x in (ids, ids[root], links)]
        yield pa.RecordBatch.from_arrays(columns, names=["node", "root", "links"])
    free_memory()


def _sent_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows with the text's set, as bytes, in place of the text: it is worked out once, however many pairs of blocks read it."""
    for batch in batches:
        bodies = pa.array([gram_set(t.as_py()).tobytes() for t in batch.column("body")], pa.binary())
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], bodies], names=batch.schema.names)


def exact_links(members: DataFrame) -> DataFrame:
    """node, root, links of candidate groups. ``members``: root, node, weight, block, blocks, body (text).

    A group of several blocks is decided by pairs of blocks: every set goes to one task per block of its group and no pair of sets is written down.
    """
    one = members.filter("blocks = 1").select("root", F.lit(0).alias("lo"), F.lit(0).alias("hi"), "node", "weight", "block", "body")
    sent = members.filter("blocks > 1").select("root", "node", "weight", "block", "blocks", "body")
    sent = sent.mapInArrow(_sent_sets, "root long, node long, weight long, block int, blocks int, body binary")
    sent = sent.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    many = sent.select("root", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "node", "weight", "block", "body")
    found = [rows.repartition("root", "lo", "hi").sortWithinPartitions("root", "lo", "hi").mapInArrow(_decide, "node long, root long, links long") for rows in (one, many)]
    return found[0].union(found[1])


def _classified(docs: DataFrame, id_col: str, text_col: str, recall: float) -> DataFrame:
    """id, key, copy_of, n_copies, root, class_id, n_links of every row; the middle ones are null where a row takes no part."""
    sig = cut(signatures(docs, id_col, text_col, runs_for(recall)))
    able = sig.filter("id is not null and d1 is not null")
    first = [F.first(c).alias(c) for c in ("grams", "sketch", "paths")]
    classes = able.groupBy("d1", "d2").agg(F.min(F.struct("id", "key")).alias("head"), F.count(F.lit(1)).alias("n"), *first)
    # numbers of classes: several may have one least id, where rows share an id; the written table fixes them
    classes = cut(classes.select(F.monotonically_increasing_id().alias("node"), "head.id", "head.key", "d1", "d2", "n", "grams", "sketch", "paths"))
    groups = cut(components(candidate_links(classes.select(F.col("node").alias("id"), "sketch", "paths"))))
    inside = groups.join(classes.select("node", "id", "key", F.col("n").alias("weight"), "grams"), "node")
    totals = inside.groupBy("root").agg(F.count(F.lit(1)).alias("m"), F.sum("grams").alias("grams_all"))
    blocks = F.greatest(F.ceil(F.col("m") / BLOCK), F.ceil(F.col("grams_all") / BLOCK_GRAMS)).cast("int")
    plan = inside.join(totals.select("root", blocks.alias("blocks")), "root")
    plan = plan.select("id", "key", "node", "root", "weight", "blocks", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block"))
    members = _rows(docs, id_col, text_col).withColumnRenamed("text", "body").join(plan, ["id", "key"])
    decided = cut(exact_links(members))
    roots = components(decided.select(F.col("node").alias("a"), F.col("root").alias("b")))
    roots = cut(classes.select("node", "id").join(roots, "node"))
    least = roots.groupBy("root").agg(F.min("id").alias("class_id"))
    links = decided.groupBy("node").agg(F.sum("links").alias("links"))
    named = classes.select("node", "d1", "d2", "id", "n").join(roots.select("node", "root").join(least, "root"), "node", "left").join(links, "node", "left")
    named = named.select(
        "d1", "d2", F.col("id").alias("copy_of"), F.col("n").alias("n_copies"), F.coalesce("root", "node").alias("root"),
        F.coalesce("class_id", "id").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"),
    )
    joined = sig.select("id", "key", "d1", "d2").join(named, ["d1", "d2"], "left")
    part = F.col("id").isNotNull()
    return joined.select("id", "key", *[F.when(part, F.col(c)).alias(c) for c in ("copy_of", "n_copies", "root", "class_id", "n_links")])


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", recall: float = RECALL) -> DataFrame:
    """doc_id, copy_of, n_copies, class_id, n_links for every row.

    copy_of: least id with the same set of n-grams; n_copies: rows with that set; class_id: least id of the component of links at the threshold or more;
    n_links: other rows at the threshold or more, copies included. Texts without words (null, empty) take no part: they are a class each, without links.
    Rows without an id are returned with nulls and no links. Rows are judged by their own texts: repeated rows of one id are copies of each other, and
    rows of one id with different texts may lie in different classes. Empty table: no rows.
    """
    found = _classified(docs, id_col, text_col, recall)
    return found.select(
        F.col("id").alias(id_col), F.coalesce("copy_of", "id").alias("copy_of"), F.coalesce("n_copies", F.lit(1)).cast("long").alias("n_copies"),
        F.coalesce("class_id", "id").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
    )


def one_per_class(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", recall: float = RECALL) -> DataFrame:
    """Of each class of near duplicates the row with the least id, with all columns.

    Of several such rows the one with the least hash of the text stays, and of rows equal in id and text the first by their other columns. Rows
    without an id or without words are in no class and stay.
    """
    found = _classified(docs, id_col, text_col, recall)
    heads = found.filter("root is not null").groupBy("root").agg(F.min(F.struct("id", "key")).alias("head")).select("head.id", "head.key")
    names = docs.columns
    text, key_of = F.col(f"`{text_col}`"), F.col(f"`{id_col}`").cast("long")
    alone = key_of.isNull() | ~F.coalesce(text.rlike(WORD_RE), F.lit(False))
    rows = docs.select(F.struct(*[f"`{c}`" for c in names]).alias("row"), key_of.alias("id"), F.xxhash64(text).alias("key"), other_columns(names, (id_col, text_col)).alias("rest"), alone.alias("alone"))
    order = Window.partitionBy("id", "key").orderBy("rest")
    first = rows.filter(~F.col("alone")).withColumn("place", F.row_number().over(order)).filter("place = 1")
    kept = first.join(heads, ["id", "key"], "left_semi").select("row").unionByName(rows.filter("alone").select("row"))
    return kept.select(*[F.col("row").getField(c).alias(c) for c in names])
