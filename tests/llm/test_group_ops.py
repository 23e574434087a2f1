"""Joins, search, mixing, URL rules and the pipeline against brute force, with edge rows."""

import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tierdraw.llm import ann, components, mixing, neardup, urlfilter

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute_groups(rows):
    """doc -> (class, links) of rows with words, by comparing all pairs."""
    sets = {}
    for d, t in rows:
        w = WORD.findall(t or "")
        if w:
            k = min(5, len(w))
            sets[d] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    links = dict.fromkeys(sets, 0)
    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            n = len(sets[a] & sets[b])
            if 5 * n >= 4 * (len(sets[a]) + len(sets[b]) - n):
                links[a] += 1
                links[b] += 1
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: (find(d), links[d]) for d in sets}


def near_rows(seed=1, groups=12):
    rng, rows, n = random.Random(seed), [], 0
    for g in range(groups):
        base = [f"{g}w{rng.randint(0, 10**6)}" for _ in range(rng.randint(30, 160))]
        for _ in range(rng.choice([1, 2, 3, 12])):
            w = list(base)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = f"e{rng.randint(0, 10**9)}"
            rows.append((n, " ".join(w)))
            n += 1
        rows.append((n, "shared words " * 12 + " ".join(base[:10])))
        n += 1
    return rows


@pytest.mark.parametrize("leaf", [1000, 3])
def test_near_duplicates_brute(spark, monkeypatch, leaf):
    """Every link is found, with small leaves compared at once and with leaves so small that they are split and grouped."""
    monkeypatch.setattr(neardup, "LEAF", leaf)
    monkeypatch.setattr(neardup, "BLOCK", 5 if leaf == 3 else 1024)
    rows = near_rows() + [(900, None), (901, ""), (902, "a b"), (903, "a b"), (904, "a  b\n")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("class_id", F.lit("clash"))
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in neardup.near_duplicates(docs).collect()}
    want = brute_groups(rows)
    assert {d: got[d] for d in want} == want
    assert got[900] == (900, 0) and got[901] == (901, 0) and len(got) == len(rows)


def test_near_duplicates_edges(spark):
    rows = spark.createDataFrame([(None, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, "x " * 20_000)], "doc_id long, text string")
    out = neardup.near_duplicates(rows).collect()
    assert len(out) == 4 and [r["n_links"] for r in out if r["doc_id"] is None] == [0]
    assert neardup.near_duplicates(rows.limit(0)).count() == 0
    assert neardup.runs_for(0.9999) == 4


def test_near_duplicates_repeated_rows(spark):
    """A repeated row counts once in its class, and rows of one id with different texts are compared by their own texts."""
    a, c = (" ".join(f"{p}{i}" for i in range(60)) for p in "wz")
    near = lambda rows: sorted((r["doc_id"], r["class_id"], r["n_links"]) for r in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert near([(1, a), (1, a), (2, a + " x")]) == [(1, 1, 2), (1, 1, 2), (2, 1, 2)]
    assert near([(1, a), (1, c), (2, a + " x"), (3, c)]) == [(1, 1, 1), (1, 1, 1), (2, 1, 1), (3, 1, 1)]
    rows = spark.createDataFrame([(1, a, "q"), (1, a, "p"), (1, c, "r"), (2, a + " x", "s"), (None, a, "t"), (4, "", "u")], "doc_id long, text string, rn string")
    assert sorted(neardup.one_per_class(rows).select("rn").toPandas()["rn"]) == ["p", "r", "t", "u"]


def test_shared_counts():
    rng = np.random.default_rng(0)
    for n in (5, 90):
        sets = [np.unique(rng.integers(0, 60, rng.integers(1, 40))).astype(np.uint64) for _ in range(n)]
        got = neardup.shared_counts(sets)
        for i in range(n):
            for j in range(n):
                if i != j:
                    assert got[i, j] == len(np.intersect1d(sets[i], sets[j]))


def test_components(spark):
    rng, edges = random.Random(2), []
    for c in range(20):
        nodes = [1000 * c + k for k in range(rng.randint(2, 40))]
        rng.shuffle(nodes)
        edges += [(nodes[i], nodes[i + 1]) for i in range(len(nodes) - 1)]
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {n: min(m for m in got if m // 1000 == n // 1000) for n in got} and len(got) == len({x for e in edges for x in e})
    assert components.components(spark.createDataFrame([(1, 1), (None, 2)], "a long, b long")).count() == 0


def test_search_brute(spark):
    rng = np.random.default_rng(4)
    vecs = rng.normal(size=(700, 12)) * rng.uniform(0.5, 2, size=(700, 1))
    vecs[100:200] = vecs[100]  # one vector many times
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(vecs)] + [(700, None), (720, [0.0] * 12), (740, [float("nan")] * 12), (760, [1.0, 2.0]), (780, [None] * 12), (None, [1.0] * 12)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit("clash"))
    got = {}
    for r in ann.search(df, lambda v: v % 20 == 0).collect():
        got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    assert set(got) == set(range(0, 700, 20))
    hit = 0
    for q, answers in got.items():
        s = vecs @ vecs[q]
        s[q] = -np.inf
        best = np.lexsort((np.arange(700), -s))[:20]
        assert sorted(answers) == list(range(1, 21))
        assert all(answers[k][1] == pytest.approx(s[answers[k][0]], rel=1e-12) for k in answers)
        hit += len({v for v, _ in answers.values()} & set(best.tolist()))
    assert hit / (20 * len(got)) >= 0.95
    hot = [v for v in (got[100][k][0] for k in range(1, 21)) if 100 <= v < 200]
    assert len(hot) > 5 and hot == list(range(101, 101 + len(hot)))  # ties go to the smaller id
    assert ann.search(df.limit(0), lambda v: v % 20 == 0).count() == 0
    assert ann.search(df.filter("vec_id in (0, 1, 2)"), lambda v: v % 20 == 0).count() == 2


def test_search_recall_with_many_lists():
    import itertools

    rng = np.random.default_rng(5)
    x = np.concatenate([rng.normal(size=(1, 16)) + 0.4 * rng.normal(size=(200, 16)) for _ in range(40)])
    index = ann.build(x[::2], float(np.sqrt((x * x).sum(axis=1).max())), len(x), 100)
    lists = index.lists_of(x)
    members = [[] for _ in index.centroids]
    for i, ls in enumerate(lists):
        for l in ls:
            members[l].append(i)
    hit = 0
    for q, ls in zip(x[::200], index.probes_of(x[::200]), strict=True):
        seen = set(itertools.chain.from_iterable(members[l] for l in ls))
        hit += len(seen & set(np.argsort(-(x @ q), kind="stable")[:20].tolist()))
    assert hit / (20 * len(x[::200])) >= 0.9


def test_mixing(spark):
    rng = random.Random(7)
    rows = [(i, rng.choice(["a", "b", "c", "d", None]) if i % 3 else "a", " ".join("w" * rng.randint(1, 4) for _ in range(rng.choice([0, 1, 5, 40, 300])))) for i in range(900)]
    rows += [(5, None, None), (None, "b", "x y z"), (None, "b", "x y z"), (6, "z", "")]
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string").withColumn("mix_copies", F.lit("clash"))
    got = mixing.mix_copies(docs).collect()
    assert len(got) == len(rows)
    held, taken, target = {}, {}, {}
    for r in got:
        assert r["mix_size"] == len(WORD.findall(r["text"] or "")) and 0 <= r["mix_copies"] <= 3
        held[r["source"]] = held.get(r["source"], 0) + r["mix_size"]
        taken[r["source"]] = taken.get(r["source"], 0) + r["mix_size"] * r["mix_copies"]
        target[r["source"]] = r["mix_target"]
    weights = dict(zip(["a", "b", "c", "d", "z", None], [5, 2, 1, 5, 2, 1], strict=True))
    left, want, free = sum(held.values()), {}, set(held)
    while True:
        lam = left / sum(weights[s] for s in free)
        over = {s for s in free if lam * weights[s] > 3 * held[s]}
        if not over:
            break
        for s in over:
            want[s] = 3 * held[s]
            left -= want[s]
        free -= over
    want |= {s: lam * weights[s] for s in free}
    for s in held:
        assert target[s] == pytest.approx(want[s]) and abs(taken[s] - want[s]) <= 40
    again = mixing.mix_copies(docs).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, again))
    assert mixing.mix_copies(docs.limit(0)).count() == 0
    total = mixing.mixture(docs.drop("mix_copies")).count()
    assert total == pytest.approx(sum(r["mix_copies"] for r in got), rel=0.2)


def test_exchange_keeps_mass_and_means():
    sizes, probs = [5, 3, 8, 1, 2, 13], [0.3, 0.6, 0.25, 0.9, 0.5, 0.1]
    mean = np.zeros(6)
    for seed in range(4000):
        out, held = mixing.exchange(sizes, probs, list(range(11, 17)), seed * 7919)
        assert sum(s * p for s, p in zip(sizes, out, strict=True)) == pytest.approx(sum(s * p for s, p in zip(sizes, probs, strict=True)))
        assert sum(0 < p < 1 for p in out) <= 1 and (held < 0 or 0 < out[held] < 1)
        mean += out
    assert mean / 4000 == pytest.approx(probs, abs=0.03)


def test_url_rules(spark):
    urls = [None, "", "nothing", "http://net", "https://x.NET/en/1?q", "https://example.net/en/2", "http://b.example.net/en/#t", "https://example.com/de/3", "ftp://sub.org/fr/4", "https://notexample.net.io/en/", "https://e.org/en/9", "https://e.org/en/9"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("host", F.lit(1))
    got = {r["page_id"]: r for r in urlfilter.judge(df).collect()}
    assert [got[k]["rule"] for k in range(10)] == [None, None, None, None, "net/", "example.net/en/", "example.net/en/", "example.com/de/", "org/fr/", None]
    assert (got[3]["host"], got[3]["path"]) == ("net", "") and (got[4]["host"], got[4]["path"]) == ("x.net", "/en/1") and (got[0]["host"], got[0]["path"]) == ("", "")
    assert got[4]["verdict"] == "block" and got[5]["verdict"] == "allow" and all(r["verdict"] in ("block", "allow") for r in got.values())
    assert urlfilter.judge(df.limit(0)).count() == 0
    labelled = spark.createDataFrame([(f"shop{i}.biz", "/buy", "block") for i in range(40)] + [(f"wiki{i}.edu", "/read", "allow") for i in range(40)], "host string, path string, label string")
    new = spark.createDataFrame([(1, "http://shop99.biz/buy"), (2, "http://wiki99.edu/read")], "page_id long, url string")
    assert {r["page_id"]: r["verdict"] for r in urlfilter.judge(new, labelled).collect()} == {1: "block", 2: "allow"}


def test_pipeline(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = corpus_pipeline.one_of_each_group(spark, docs, SF)
    want = brute_groups([(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()])
    assert {r["doc_id"] for r in kept.collect()} == {d for d, (c, _) in want.items() if c == d} | {r["doc_id"] for r in docs.collect() if not WORD.search(r["text"] or "")}
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, SF).columns == docs.columns
        assert stage(spark, docs.limit(0), SF).count() == 0
    odd = [(None, None, None), (None, "a b", "s"), (1, "", "s"), (2, "x " * 30_000, None), (3, "a b c", "s"), (3, "a b c", "s"), (3, "other words here", "t")]
    clash = "tox_score n_removed n_sentences copies ids k1 place rest alone class_id size".split()
    edges = spark.createDataFrame(odd, "doc_id long, text string, source string").withColumns({c: F.lit("own") for c in clash})
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, edges, SF).cache()
        assert out.columns == edges.columns if name != "bpe" else set(out.columns) == {*edges.columns, "n_tokens"}
        assert out.filter("tox_score <> 'own' or n_removed <> 'own' or place <> 'own'").count() == 0
        assert {"toxicity": 7, "ngram_join": 6, "substring": 7, "bpe": 7}.get(name, out.count()) == out.count()
    out = corpus_pipeline.run(spark, SF)
    assert out.count() > 0 and set(docs.columns) < set(out.columns)
