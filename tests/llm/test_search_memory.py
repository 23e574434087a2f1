"""What a task of the vector search holds does not grow with the queries that read its lists."""

import tracemalloc

import numpy as np
import pyarrow as pa

from tierdraw.llm import ann


def test_answers_of_many_queries_in_bounded_memory():
    rng = np.random.default_rng(3)
    n, d, asked, k = 20_000, 8, 600, 20
    x = rng.normal(size=(n, d))
    x[:200] = np.eye(d)[0]  # many ties
    vectors = lambda a: pa.ListArray.from_arrays(pa.array(np.arange(len(a) + 1) * d, pa.int32()), pa.array(a.ravel()))
    ids = pa.ListArray.from_arrays(pa.array(np.arange(n + 1), pa.int32()), pa.array(np.arange(n)[::-1].copy()))
    h = pa.array(np.arange(n))
    rows = pa.RecordBatch.from_arrays([pa.array(np.arange(n) % 10, pa.int32()), h, h, vectors(x), ids], names=["list", "h1", "h2", "v", "ids"])
    part = ann.Part.of([rows.slice(0, 7000), rows.slice(7000)], d)
    q = np.concatenate([np.eye(d)[:1], rng.normal(size=(asked - 1, d))])
    asks = pa.RecordBatch.from_arrays([pa.array([list(range(10))] * asked, pa.list_(pa.int32())), pa.array(np.arange(asked)), pa.array(np.arange(asked)), vectors(q)], names=["lists", "h1", "h2", "v"])
    tracemalloc.start()
    hits: dict[int, list] = {}
    for batch in part.answers(asks, k, float(np.sqrt((x * x).sum(axis=1).max()))):
        for r in batch.to_pylist():
            hits.setdefault(r["q1"], []).append((r["ids"][0], r["score"]))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120e6  # all products at once take 96 MB, with their places 192
    for r in range(asked):
        s = x @ q[r]
        least = np.arange(n)[::-1]
        want = least[np.lexsort((least, -s.round(12)))[: k + 1]]
        assert [i for i, _ in hits[r]] == want.tolist()
