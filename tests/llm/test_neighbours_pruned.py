"""Recall where most lists are skipped, and the graph over centroids against a plain scan of them."""

import numpy as np
from pyspark.sql import functions as F

from zbox.llm import ann


def clustered(n, d=24, groups=60, seed=3):
    r = np.random.default_rng(seed)
    return (r.normal(size=(groups, d))[r.integers(0, groups, n)] + 0.15 * r.normal(size=(n, d))).astype(np.float32)


def test_recall_where_most_lists_are_skipped(spark):
    x = clustered(12_000)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<float>").withColumns({"V": F.lit(1), "Rep": F.lit("x"), "list": F.lit(0)})
    index = ann.build_index(ann.valid_vectors(df, "vec_id", "embedding"), 21, ann.ListParams())
    q = x[::20].astype(np.float64)
    row, to = index.chosen(q)
    size = {r["list"]: r["n"] for r in index.posts.groupBy("list").agg(F.count("*").alias("n")).collect()}
    lists = len(index.graph.c)
    assert lists > 100 and len(row) < 0.2 * lists * len(q)  # most lists are skipped
    assert sum(size.get(int(k), 0) for k in to) < 0.25 * len(x) * len(q)
    found = {}
    for r in ann.search(df, lambda i: i % 20 == 0).collect():
        found.setdefault(r.query_id, set()).add(r.vec_id)
    y, hits = x.astype(np.float64), 0
    for i in range(0, len(x), 20):
        s = y @ y[i]
        s[i] = -np.inf
        hits += len(found[i] & set(np.lexsort((np.arange(len(x)), -s))[:20].tolist()))
    assert hits >= 0.9 * 20 * len(found) and len(found) == 600


def test_graph_finds_what_a_scan_finds():
    x = clustered(4_000, seed=5).astype(np.float64)
    graph = ann.CentroidGraph(ann.balanced_centroids(x, 400), 16)
    q = x[:300]
    got, d = graph.search(q, 20)
    assert 4 * 20 < len(graph.c)
    all_ = graph.distances(q.astype(np.float32))
    want = np.argsort(all_, axis=1, kind="stable")[:, :20]
    assert np.mean([len(set(a) & set(b)) for a, b in zip(got.tolist(), want.tolist())]) > 0.95 * 20
    assert np.allclose(d**2, np.take_along_axis(all_, got, 1), atol=1e-3)


def test_repeated_rows_and_null_ids(spark):
    rows = [(i, [float(i), 1.0]) for i in range(30)] * 2 + [(None, [1.0, 1.0])] * 3
    got = ann.search(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>"), lambda i: i % 20 == 0).collect()
    assert sorted((r.query_id, r["rank"]) for r in got) == [(q, k) for q in (0, 20) for k in range(1, 21)]
    assert [r.vec_id for r in sorted(got, key=lambda r: (r.query_id, r["rank"])) if r.query_id == 20] == [i for i in range(29, 8, -1) if i != 20]
