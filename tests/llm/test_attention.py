"""The classifier's score from the definition of gated attention, and odd rows."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from zbox.llm import quality_mil as Q


def test_score_is_gated_attention_over_passages():
    """Passage by passage in plain loops: code, gate, softmax weight, weighted code, logistic."""
    r = np.random.default_rng(3)
    bags = [Q.encode(" ".join(r.choice(["alpha", "Beta,", "1234", "###", "gamma."], n))) for n in (5, 90, 400, 1000, 3)]
    model = Q.AttentionMil(hidden=6, gate=4).fit(bags, np.array([1, 0, 1, 0, 1]), steps=15)
    p = {k: v.astype(float) for k, v in model.p.items()}
    for bag, got in zip(bags, model.score(bags), strict=True):
        codes, marks = [], []
        for x in bag:
            x = [min(8, max(-8, (float(v) - float(m)) / float(s))) for v, m, s in zip(x, model.mean, model.scale)]
            h = [math.tanh(sum(x[i] * p["W"][i][j] for i in range(len(x))) + p["b"][j]) for j in range(6)]
            t = [math.tanh(sum(h[i] * p["V"][i][j] for i in range(6))) for j in range(4)]
            g = [1 / (1 + math.exp(-sum(h[i] * p["U"][i][j] for i in range(6)))) for j in range(4)]
            codes.append(h)
            marks.append(sum(t[j] * g[j] * p["a"][j] for j in range(4)))
        total = sum(math.exp(e) for e in marks)
        z = [sum(math.exp(e) / total * h[j] for e, h in zip(marks, codes)) for j in range(6)]
        assert got == pytest.approx(1 / (1 + math.exp(-(sum(a * b for a, b in zip(z, p["c"])) + p["d"][0]))), abs=2e-4)


def test_gradient_is_the_slope_of_the_loss():
    """One step against finite differences, in every kind of parameter."""
    r = np.random.default_rng(1)
    bags = [r.normal(size=(n, 7)).astype(np.float32) for n in (1, 3, 6)]
    y = np.array([1, 0, 1])
    m = Q.AttentionMil(hidden=3, gate=2)
    m.fit(bags, y, steps=1, rate=0.0, decay=0.0)
    x = np.clip((np.concatenate(bags) - m.mean) / m.scale, -8, 8).astype(float)
    counts = np.array([len(b) for b in bags])
    starts = np.concatenate([[0], np.cumsum(counts)[:-1]])
    base = {k: v.astype(float) for k, v in m.p.items()}

    def loss(p):
        out = m._forward(x, starts, counts, p)[-1]
        return -np.mean(y * np.log(out) + (1 - y) * np.log(1 - out))

    moved = Q.AttentionMil(hidden=3, gate=2).fit(bags, y, steps=1, rate=1e-3, decay=0.0)
    for k in base:  # Adam's first step is against the gradient's sign
        step = moved.p[k].astype(float) - base[k]
        for at in np.ndindex(*base[k].shape):
            up, down = ({q: v.copy() for q, v in base.items()} for _ in range(2))
            up[k][at] += 1e-4
            down[k][at] -= 1e-4
            slope = (loss(up) - loss(down)) / 2e-4
            assert abs(slope) < 1e-4 or np.sign(step[at]) == -np.sign(slope), (k, at)


def test_odd_rows(spark):
    docs = spark.createDataFrame([(None, "a b"), (1, None), (2, ""), (3, "w " * 1_000_000), (4, "x. y"), (4, "x. y")], "doc_id bigint, text string").withColumns({"Score": F.lit("own"), "y": F.lit(1), "ID": F.lit(2)})
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 0), (3, 1, 0), (4, 0, 1), (4, 0, 1), (None, 1, 0), (6, None, 0), (7, 1, 0)], "doc_id bigint, quality int, toxic int")
    model = Q.train(docs, labels)
    got = Q.add_score(docs, model)
    assert got.columns == ["doc_id", "text", "y", "ID", "score"]
    rows = got.collect()
    assert len(rows) == 6 and all(0 <= r.score <= 1 for r in rows) and len({r.score for r in rows if r.doc_id == 4}) == 1
    assert Q.add_score(docs.limit(0), model).count() == 0
    few = Q.labelled_sample(docs, labels, "doc_id", "text", "quality", 5, 4000, 100)[0]
    assert sum(map(len, few)) <= 100  # the long one does not fit
