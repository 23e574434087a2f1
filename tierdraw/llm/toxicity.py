"""Toxicity by a counterfactually regularised linear classifier.

Features are the words of a text and the prefixes of words, as presence. Every labelled text has a counterfactual twin: where it names groups, the names are swapped in
the text for others of their lists; where it names none, a neutral mention of one is put between two of its words. Training adds, to the logistic loss, the squared
difference of the two scores. So a group's name moves no score, and neutral mentions are not taken for insults. A bounded number of labelled rows is
fitted; every row is scored, over its whole text.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MASK64, cut, free_memory, mix64, unused_name

#: Most labelled rows of each class that are fitted (documented bounds of the fitted sample).
MAX_TOXIC, MAX_CLEAN = 4000, 8000
PREFIXES = (4, 5, 6)
#: Names of groups, by list; a name is swapped within its list. Callers may give lists of their own.
GROUP_TERMS = {
    "belief": ["muslim", "christian", "jewish", "hindu", "buddhist", "atheist", "catholic", "sikh", "muslime", "christ", "jude", "musulman", "juif", "judío", "musulmán", "cristiano"],
    "gender": ["woman", "man", "women", "men", "girl", "boy", "female", "male", "transgender", "frau", "mann", "femme", "homme", "mujer", "hombre"],
    "love": ["gay", "lesbian", "straight", "bisexual", "queer", "heterosexual", "homosexual", "schwul", "lesbisch"],
    "origin": ["black", "white", "asian", "african", "european", "mexican", "chinese", "arab", "american", "turkish", "polish", "indian", "immigrant", "refugee"],
    "body": ["deaf", "blind", "disabled", "autistic", "old", "young"],
}
_WORD = re.compile(r"[^\W\d_]+")
Groups = Mapping[str, Sequence[str]]


def words_of(text: str | None) -> set[str]:
    """Lower-case words of a whole text."""
    return set(_WORD.findall((text or "").lower()))


def features(words: set[str]) -> set[str]:
    """Words, and prefixes of longer words marked by their length."""
    out = set(words)
    for n in PREFIXES:
        out |= {f"{n}^{w[:n]}" for w in words if len(w) > n}
    return out


def twin(text: str | None, key: int, groups: Groups = GROUP_TERMS) -> str | None:
    """Counterfactual of a text, in lower case: its group names swapped, each for one other of its list, or else a name put after one of its words.

    Which ones is drawn from ``key``. Null counts as empty. None only if no list has a name to put in.
    """
    text = (text or "").lower()
    places = list(_WORD.finditer(text))
    home = {name: lst for lst, names in groups.items() if len(names) > 1 for name in names}
    named = sorted({m[0] for m in places} & home.keys())
    if named:
        swap = {}
        for k, name in enumerate(named):
            others = [x for x in groups[home[name]] if x != name]
            swap[name] = others[mix64(key + k & MASK64) % len(others)]
        return _WORD.sub(lambda m: swap.get(m[0], m[0]), text)
    names = sorted({x for lst in groups.values() for x in lst})
    if not names:
        return None
    name = names[mix64(key & MASK64) % len(names)]
    at = places[mix64(key + 1 & MASK64) % len(places)].end() if places else 0
    return f"{text[:at]} {name}{text[at:]}"


def fit(xs: Sequence[Sequence[int]], twins: Sequence[Sequence[int] | None], ys: Sequence[int], n_features: int, penalty: float = 1.0, l2: float = 2e-5, steps: int = 400, stands_for: tuple[float, float] = (1.0, 1.0)) -> tuple[np.ndarray, float]:
    """Weights and bias of the logistic loss plus ``penalty`` times the mean squared difference of scores between twins.

    ``stands_for``: how many labelled rows each row of class 0 and of class 1 stands for in the loss.
    """
    y = np.asarray(ys, dtype=np.float64)
    share = np.where(y > 0, stands_for[1], stands_for[0])
    sizes = np.array([len(x) for x in xs])
    row, col = np.repeat(np.arange(len(xs)), sizes), np.concatenate([np.asarray(x, dtype=np.int64) for x in xs] or [np.zeros(0, np.int64)])
    parts = []  # x minus its twin, as entries of +1 and -1
    for k, (x, t) in enumerate((x, t) for x, t in zip(xs, twins, strict=True) if t is not None):
        parts += [(k, f, 1.0) for f in set(x) - set(t)] + [(k, f, -1.0) for f in set(t) - set(x)]
    d_row, d_col = (np.array([p[i] for p in parts], dtype=np.int64) for i in (0, 1))
    d_val, n_twins = np.array([p[2] for p in parts]), max(1, sum(t is not None for t in twins))
    w, b = np.zeros(n_features), math.log((share @ y + 0.5) / (share.sum() - share @ y + 0.5))
    m, v, mb, vb = np.zeros(n_features), np.zeros(n_features), 0.0, 0.0
    for t in range(1, steps + 1):
        s = np.bincount(row, w[col], len(xs)) + b
        err = (1 / (1 + np.exp(-np.clip(s, -40, 40))) - y) * share / share.sum()
        g = np.bincount(col, err[row], n_features) + l2 * w
        if len(parts):
            diff = np.bincount(d_row, w[d_col] * d_val, d_row.max() + 1)
            g = g + 2 * penalty / n_twins * np.bincount(d_col, diff[d_row] * d_val, n_features)
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        mb, vb = 0.9 * mb + 0.1 * err.sum(), 0.99 * vb + 0.01 * err.sum() ** 2
        rate = 0.1 * min(1.0, 3.0 * (1 - t / steps) + 0.02)
        w = w - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
        b = b - rate * (mb / (1 - 0.9**t)) / (math.sqrt(vb / (1 - 0.99**t)) + 1e-8)
    return w, float(b)


def training_labels(labels: DataFrame) -> DataFrame:
    """doc_id, toxic of the documents that may be fitted.

    Only rows whose crc32(doc_id as text) mod 5 is not 0; null ids or labels are left out, and of contradicting labels of one id the higher counts.
    """
    rows = labels.select("doc_id", "toxic").filter("doc_id is not null and toxic is not null").filter(F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
    return rows.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))


def labelled_sample(labels: DataFrame) -> DataFrame:
    """doc_id, toxic of at most MAX_TOXIC and MAX_CLEAN training documents, the first by a hash of the id."""
    rows = training_labels(labels).withColumn("h", F.xxhash64("doc_id"))
    toxic = rows.filter("toxic = 1").orderBy("h", "doc_id").limit(MAX_TOXIC)
    return toxic.union(rows.filter("toxic = 0").orderBy("h", "doc_id").limit(MAX_CLEAN)).drop("h")


def train(docs: DataFrame, labels: DataFrame, penalty: float = 1.0, groups: Groups = GROUP_TERMS, max_features: int | None = None) -> tuple[dict[str, float], float]:
    """Weights by feature, and the bias. Without labels of both classes, no features and a bias that calls nothing toxic.

    Features that tell the classes of the fitted sample apart are kept, all of them or the ``max_features`` that do best, and those of the group names. Null texts
    count as empty; repeated rows of a labelled id are fitted as often as they are there.
    """
    picked = cut(docs.select("doc_id", "text").join(F.broadcast(labelled_sample(labels)), "doc_id"))  # at most MAX_TOXIC + MAX_CLEAN ids
    picked = picked.select(F.col("doc_id").cast("long"), F.col("toxic").cast("int"), "text")

    def featured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            feats = [sorted(features(words_of(t.as_py()))) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("toxic"), pa.array(feats, pa.list_(pa.string()))], names=["toxic", "feats"])

    by_class = {r["toxic"]: r["n"] for r in picked.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    n1, n0 = by_class.get(1, 0), by_class.get(0, 0)
    if not n1 or not n0:
        return {}, -50.0
    seen = picked.mapInArrow(featured, "toxic int, feats array<string>").select("toxic", F.explode("feats").alias("f"))
    seen = seen.groupBy("f").agg(F.sum("toxic").alias("a"), F.count(F.lit(1)).alias("n"))
    p = F.col("n") / (n0 + n1)
    z = (F.col("a") / n1 - (F.col("n") - F.col("a")) / n0) / F.sqrt(p * (1 - p) * (1 / n1 + 1 / n0))
    strong = seen.filter("n >= 3").withColumn("z", z).filter(F.abs("z") >= 4).orderBy(F.abs("z").desc(), "f").select("f")
    names = [r["f"] for r in (strong if max_features is None else strong.limit(max_features)).collect()]  # of the bounded sample
    terms = features({x for lst in groups.values() for x in lst}) - set(names)
    index = {f: k for k, f in enumerate([*names, *sorted(terms)])}
    places = lambda text: sorted(index[f] for f in features(words_of(text)) & index.keys())

    def indexed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column("doc_id").to_pylist(), [t.as_py() for t in batch.column("text")]
            others = [twin(t, i, groups) for t, i in zip(texts, ids, strict=True)]
            xs = [pa.array([None if t is None else places(t) for t in column], pa.list_(pa.int32())) for column in ([t or "" for t in texts], others)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("toxic"), *xs], names=["doc_id", "toxic", "feats", "twin"])

    got = picked.mapInArrow(indexed, "doc_id long, toxic int, feats array<int>, twin array<int>").collect()
    got.sort(key=lambda r: (r["doc_id"], r["feats"]))
    labelled = {r["toxic"]: r["n"] for r in training_labels(labels).groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    stands_for = tuple(max(1.0, labelled.get(c, 0) / most) for c, most in ((0, MAX_CLEAN), (1, MAX_TOXIC)))  # the classes keep their shares where a bound cuts
    w, b = fit([r["feats"] for r in got], [r["twin"] for r in got], [r["toxic"] for r in got], len(index), penalty, stands_for=stands_for)
    return {f: float(w[k]) for f, k in index.items() if abs(w[k]) > 1e-9}, b


def score_text(text: str | None, words: dict[str, float], prefixes: list[tuple[int, dict[str, float]]], bias: float) -> float:
    """Probability that a text is toxic; null counts as empty."""
    ws = words_of(text)
    s = bias + math.fsum([words[w] for w in ws & words.keys()])
    for n, table in prefixes:
        s += math.fsum([table[p] for p in {w[:n] for w in ws if len(w) > n} & table.keys()])
    return 1 / (1 + math.exp(-max(-60.0, min(60.0, s))))


def score(docs: DataFrame, model: tuple[dict[str, float], float], text_col: str = "text", score_col: str = "tox_score") -> DataFrame:
    """All rows and columns of ``docs`` plus ``score_col`` (0 to 1); a column of that name is replaced.

    Null and empty texts get the score of a text without words; equal texts get equal scores. The model, of features of the bounded sample, travels with the tasks.
    """
    weights, bias = model
    keep = [f for f in docs.schema.fields if f.name != score_col]
    schema = T.StructType([*[T.StructField(f"d{k}", f.dataType) for k, f in enumerate(keep)], T.StructField("score", T.DoubleType())])
    text_at = [f.name for f in keep].index(text_col)
    plain = {f: w for f, w in weights.items() if "^" not in f}
    by_len = [(n, {f[2:]: w for f, w in weights.items() if f.startswith(f"{n}^")}) for n in PREFIXES]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = [score_text(t.as_py(), plain, by_len, bias) for t in batch.column(text_at)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], names=schema.names)
        free_memory()

    out = docs.select(*[F.col(f"`{f.name}`").alias(f"d{k}") for k, f in enumerate(keep)]).mapInArrow(run, schema)
    return out.select(*[F.col(f"d{k}").alias(f.name) for k, f in enumerate(keep)], F.col("score").alias(score_col))


def without_toxic(docs: DataFrame, model: tuple[dict[str, float], float], text_col: str = "text") -> DataFrame:
    """Rows that are not called toxic (score below one half), with all columns and none more."""
    name = unused_name(docs.columns, "tox_score")
    return score(docs, model, text_col, name).filter(F.col(f"`{name}`") < 0.5).drop(name)
