"""The language model's scores from its definition."""

import collections
import math
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from zbox.llm import lm_scoring as L


def some_model(unigram, contexts, seed=2):
    r = np.random.default_rng(seed)
    m = L.new_model(unigram, contexts)
    return {k: (v + 0.3 * r.normal(size=v.shape)).astype(np.float32) for k, v in m.items()}


def softmax(m, far, near):
    q = m["mix"][0].astype(float) * m["in"][near] + m["mix"][1].astype(float) * m["in"][far]
    s = m["out"].astype(float) @ q + m["bias"]
    return np.exp(s - s.max()) / np.exp(s - s.max()).sum()


def test_normaliser_is_the_sum_over_all_words():
    m = some_model(np.full(L.BLOCK + 70, 1 / (L.BLOCK + 70)), 6)
    z = L.normaliser(m)
    for a in range(6):
        for b in range(6):
            got = 10 ** L.log10_of(m, z, np.full(L.BLOCK + 70, b), np.full(L.BLOCK + 70, a), np.arange(L.BLOCK + 70))
            assert got.sum() == pytest.approx(1, abs=1e-4) and np.allclose(got, softmax(m, b, a), rtol=1e-3)


def test_every_score_from_its_definition(spark, monkeypatch):
    """All documents of a small corpus, and the probabilities of all words after some context sum to one."""
    texts = ["a b c a b", "A b d zz", None, "", "c c c\tb a", "q r s a unseen", "b a " * 40, "long " * 200_000] * 2
    rows = [(i if i != 9 else None, t) for i, t in enumerate(texts)] + [(3, "")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").withColumns({"SCORE": F.lit("x"), "row": F.lit(1), "Held_out": F.lit(2)})
    models = []

    def train(texts_, shared, unigram, runs, **_):
        voc = L.Vocabulary(shared.value["words"], shared.value["contexts"], shared.value["modelled"])
        models.append((voc, some_model(unigram, voc.contexts)))
        return models[-1][1]

    monkeypatch.setattr(L, "train", train)
    got = L.score(docs, contexts=8, vocabulary=3, head_words=5).collect()
    (voc, m), = models
    learnt = collections.Counter()
    ends = 0
    for i, t in rows:
        if zlib.crc32(("" if i is None else str(i)).encode()) % 7 != 2:
            learnt.update(L.tokens(t))
            ends += 1
    bucket = lambda w: zlib.crc32(w) % L.BUCKETS
    total, kinds = collections.Counter(), collections.Counter()
    for w, c in learnt.items():
        if voc.head.get(w, 9) >= 3:
            total[bucket(w)] += c
            kinds[bucket(w)] += 1

    def prob(p, w):
        if voc.head.get(w, 9) < 3:
            return p[voc.head[w]]
        return p[voc.end + 1 + bucket(w)] * (learnt[w] + 1) / (total[bucket(w)] + kinds[bucket(w)] + 1)

    def context(w):
        i = voc.head.get(w, -1)
        own = voc.end_context
        return i if 0 <= i < own else own + 1 + zlib.crc32(w[-2:]) % voc.suffixes

    want = collections.Counter()
    for i, t in rows:
        w, seen, s = L.tokens(t), [voc.end_context] * 2, 0.0
        cache = {}
        for x in w:
            at = (seen[-2], seen[-1])
            p = cache.setdefault(at, None) if cache.get(at) is not None else cache.update({at: softmax(m, *at)}) or cache[at]
            s += math.log10(prob(p, x))
            seen.append(context(x))
        s += math.log10(softmax(m, seen[-2], seen[-1])[voc.end])
        want[(i, len(w) + 1, round(s, 2) if len(w) < 100 else round(s, -2))] += 1
    assert want == collections.Counter((r.doc_id, r.n_tokens, round(r.score, 2) if r.n_tokens < 101 else round(r.score, -2)) for r in got)
    p = softmax(m, 1, 2)
    words = list(voc.head) + [w for w in learnt if w not in voc.head]
    unseen = sum(p[voc.end + 1 + b] / (total[b] + kinds[b] + 1) for b in range(L.BUCKETS))
    assert sum(prob(p, w) for w in words) + p[voc.end] + unseen == pytest.approx(1)
    empty = L.score(docs.limit(0))
    assert empty.count() == 0


def test_training_reruns_agree_and_learn(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    a, b = ({r.doc_id: r.score for r in L.score(docs, contexts=32, head_words=300).collect()} for _ in range(2))
    assert a == b


def test_average_weighs_rows_by_meetings():
    import pyarrow as pa

    rows = [np.array([[1.0, 2.0], [5.0, 5.0], [7.0, 7.0]], "<f4"), np.array([[4.0, 8.0], [6.0, 6.0], [9.0, 9.0]], "<f4")]
    met = [np.array([1, 0, 0], "<f4"), np.array([2, 3, 0], "<f4")]
    t = pa.table({"name": ["out"] * 2, "at": pa.array([0, 0], pa.int32()), "rows": [r.tobytes() for r in rows], "met": [m.tobytes() for m in met], "trainer": pa.array([1, 0], pa.int32())})
    out = L._average(t)
    assert np.allclose(np.frombuffer(out["rows"][0].as_py(), "<f4").reshape(3, 2)[:2], [[3, 6], [6, 6]])
    assert np.frombuffer(out["met"][0].as_py(), "<f4").tolist() == [3, 3, 0]
