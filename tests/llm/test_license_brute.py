"""Diagonals, coverage, labels, spans and score by brute force over all places of a text and a template."""

import random

from pyspark.sql import functions as F

from zbox.llm import license_scan as L

TEMPLATES = L.BASE_PHRASES + L.LICENSE_TEXTS


def by_hand(text, min_coverage=0.8, max_shift=3):
    w, labels, spans, best = L.template_words(text or ""), set(), [], 0.0
    for t in TEMPLATES:
        v = L.template_words(t.text)
        k = 2 if t.base or len(v) < 4 else 3
        at: dict = {}
        for i in range(len(w) - k + 1):
            for j in range(len(v) - k + 1):
                if w[i : i + k] == v[j : j + k]:
                    at.setdefault(i - j, []).append((i, j))
        groups, last = [], None
        for d in sorted(at):
            if t.base or last is None or d - last > max_shift:
                groups.append([])
            groups[-1] += at[d]
            last = d
        for g in groups:
            covered = {j + x for _, j in g for x in range(k)}
            share = min(1.0, len(covered) / len(v))
            if not t.base or share >= 1:
                best = max(best, share)
            if share >= (1.0 if t.base else min_coverage):
                labels.add(t.label)
                spans.append((min(i for i, _ in g), max(i for i, _ in g) + k - 1, t.name, t.label, round(share, 9)))
    return len(w), ",".join(sorted(labels)), round(best, 9), sorted(spans)


def test_scan_is_what_brute_force_finds(spark, sf):
    r = random.Random(8)
    some = [None, "", "MIT", "mit license mit license Apache  LICENSE", "word " * 500]
    for t in L.LICENSE_TEXTS:
        v = t.text.split()
        cut = r.randrange(len(v) + 1)
        some += [t.text, " ".join(["before", *v[:cut], *["noise"] * r.randrange(1, 6), *v[cut:], "after"]), " ".join(v[: max(2, len(v) * 3 // 4)]), f"{t.text} and again {t.text.upper()}"]
    some += [x.text for x in spark.read.parquet(f"{sf}/documents.parquet").select("text").limit(60).collect()]
    docs = spark.createDataFrame(list(enumerate(some)), "doc_id bigint, text string").withColumns({"Spans": F.lit(1), "LABELS": F.lit("x"), "n": F.lit(2)})
    got = {x.doc_id: x for x in L.scan(docs).collect()}
    assert len(got) == len(some)
    for i, text in enumerate(some):
        x = got[i]
        assert (x.n_words, x.labels, round(x.score, 9), sorted((*s[:4], round(s[4], 9)) for s in x.spans)) == by_hand(text), text


def test_odd_rows(spark):
    rows = [(None, "mit license"), (None, "mit license"), (1, "w " * 1_000_000 + "general public license")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = L.scan(docs).collect()
    assert len(got) == 3 and [x.labels for x in got if x.doc_id is None] == ["mit", "mit"]
    assert next((x.n_words, x.first_word, x.labels) for x in got if x.doc_id == 1) == (1_000_003, 1_000_000, "gpl")
    assert L.scan(docs.limit(0)).count() == 0
