"""Operators do the whole job: nothing that is fixed in number stands in for what grows with the input."""

import math
from collections import Counter

import numpy as np
import pytest

from tierdraw.llm import ann, lmscore, toxicity


def test_lm_all_words(spark, monkeypatch):
    """Several chunks and buckets: every word has its own counts, the models are matched, and no text is scored by its own words."""
    monkeypatch.setattr(lmscore, "CHUNK_CHARS", 3000)
    monkeypatch.setattr(lmscore, "BUCKET_CHARS", 5000)
    texts = [(k, " ".join(f"w{k * 7 + j}" for j in range(12))) for k in range(300)] + [(300, None), (301, "\t "), (None, "w1 w2"), (5, "w1 w2 w1")]
    good = {k for k in range(0, 300, 3)}
    split = [(k, (t or "").split()) for k, t in texts]
    n_words = len({x for _, w in split for x in w})

    def tallies(rows):
        pairs, heads, words = Counter(), Counter(), Counter()
        for w in rows:
            pairs.update(zip(["", *w], w, strict=False))
            heads.update(["", *w][:-1] if w else [])
            words.update(w)
        return pairs, heads, words

    models = {flag: tallies([w for k, w in split if (k in good) == flag]) for flag in (True, False)}
    tokens = {flag: sum(m[2].values()) for flag, m in models.items()}

    def loss(k, w, flag):
        scale = 1.0 if flag else tokens[True] / tokens[False]
        mine = tallies([w] if (k in good) == flag else [])
        pairs, heads, words = (lambda x, m=m, o=o: scale * (m[x] - o[x]) for m, o in zip(models[flag], mine, strict=True))
        whole = scale * (tokens[flag] - sum(mine[2].values())) + n_words + 1
        one = [-math.log((pairs((h, x)) + 8 * (words(x) + 1) / whole) / (heads(h) + 8)) for h, x in zip(["", *w], w, strict=False)]
        return sum(one) / len(one) if one else 0.0

    key = lambda r: (r[0] is None, r[0] or 0, r[1])
    want = sorted(((k, len(w), loss(k, w, True), loss(k, w, False)) for k, w in split), key=key)
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    marks = spark.createDataFrame([(k,) for k in good] + [(3,), (None,)], "doc_id long")
    got = lmscore.score(docs, marks).select("doc_id", "n_tokens", "loss_target", "loss_background").collect()
    for g, r in zip(sorted(map(tuple, got), key=key), want, strict=True):
        assert g[:2] == r[:2] and g[2:] == pytest.approx(r[2:], abs=1e-9)
    assert lmscore.score(docs.limit(0), marks).count() == 0


def test_ratio_alone_decides_what_is_read():
    """With many lists within the ratio of the nearest one, a query reads all that the walk of the graph meets: nearly all, and no fixed number."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(6000, 32))
    index = ann.build(x, float(np.sqrt((x * x).sum(axis=1).max())), 64_000, 50)
    assert len(index.centroids) == 1000
    index.ratio = 1.2
    q = index.lift(x[:50], True).astype(float)
    far = np.sqrt(((q[:, None, :] - index.centroids[None].astype(float)) ** 2).sum(axis=2))
    most = 0
    for d, ls in zip(far, index.probes_of(x[:50]), strict=True):
        sure = set(np.flatnonzero(d <= index.ratio * d.min() - 1e-4).tolist())
        assert len(sure & set(ls.tolist())) >= 0.85 * len(sure) and (d[ls] <= index.ratio * d.min() + 1e-4).sum() >= len(ls) - ann.LEAST_PROBES
        most = max(most, len(sure))
    assert most > 200


def test_bounds_of_the_sample_do_not_move_the_cutoff(spark, monkeypatch):
    """A tenth of the labelled texts is toxic; so is what is said of a text without telling words, whichever bound cuts the sample."""
    docs = spark.createDataFrame([(k, ("ab", "cd", "ef")[k % 3]) for k in range(800)], "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(k % 10 == 3)) for k in range(800)], "doc_id long, toxic int")
    nothing = spark.createDataFrame([(1, "zzz")], "doc_id long, text string")
    whole = toxicity.score(nothing, toxicity.train(docs, labels)).first()["tox_score"]
    monkeypatch.setattr(toxicity, "MAX_TOXIC", 40)
    monkeypatch.setattr(toxicity, "MAX_CLEAN", 40)
    assert abs(toxicity.score(nothing, toxicity.train(docs, labels)).first()["tox_score"] - whole) < 0.05 and whole < 0.2
