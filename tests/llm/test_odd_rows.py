"""Null columns, empty and very long texts, repeated rows, clashing names and empty tables."""

import pytest
from pyspark.sql import functions as F

from zbox.llm import packing, quality_rules
from zbox.llm.queries import byte_bpe

LONG = "some words that go on. " * 50_000


@pytest.fixture(scope="module")
def odd(spark):
    rows = [
        (None, None, None, None, None), (None, "no id here.", "en", "s", 11), (None, "no id here.", "en", "s", 11), (1, "", "en", "s", 0), (2, " \n\t", None, "s", 3),
        (3, LONG, "en", None, len(LONG)), (4, "one text of a few words", "en", "s", 23), (4, "one text of a few words", "en", "s", 23), (4, "one text of a few words", "de", "s", 23), (5, "x", "en", "t", 1),
    ]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")


def clashing(docs):
    return docs.withColumns({"_KEY": F.lit(1), "_id": F.lit("x"), "Score": F.lit(2.0), "Size": F.lit("s"), "entities": F.lit("e"), "_text": F.lit(3), "_rank": F.lit(4), "fp": F.lit(5)})


def test_line_rules(odd):
    docs = clashing(odd).withColumns({"Kept": F.lit("own"), "_t": F.lit(1)})
    got = quality_rules.clean_lines(docs).collect()
    assert len(got) == 10 and sum(r.doc_id is None for r in got) == 3
    assert {r.n_words for r in got if r.doc_id == 3} == {250_000} and all(r.kept is False for r in got if r.n_words < 50)
    assert {(r.clean_text, r.kept) for r in got if not (r.text or "").strip()} >= {("", False)}
    assert quality_rules.clean_lines(docs.limit(0)).count() == 0


def test_packing(odd):
    got = packing.pack(odd, byte_bpe()).collect()
    assert sum(r.doc_id is None for r in got) == 3  # one piece each
    long = sorted((r.piece, r.start, r.length) for r in got if r.doc_id == 3)
    assert [p for p, *_ in long] == list(range(len(long))) and all(a[1] + a[2] == b[1] for a, b in zip(long, long[1:])) and sum(n for *_, n in long) > 250_000
    assert sum(r.doc_id == 4 for r in got) == 3
    used: dict = {}
    for r in got:
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in used.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at <= 1024
    assert packing.pack(odd.limit(0), byte_bpe()).count() == 0


def test_stages(spark, odd):
    import corpus_pipeline as p

    docs, sf = clashing(odd), "/root/testdata/sf0.001"
    for name, stage in p.STAGES[:-1]:
        got = stage(spark, docs, sf)
        assert got.columns == docs.columns, name
        rows = got.collect()
        assert {r.Size for r in rows} <= {"s"} and {r.entities for r in rows} <= {"e"}
        assert stage(spark, docs.limit(0), sf).count() == 0, name
        if name == "near duplicates":
            # one of texts without words, one of the equal ones, the long one and the short one
            assert sorted(((r.doc_id, r.lang) for r in rows), key=str) == sorted([(None, None), (None, "en"), (3, "en"), (4, "de"), (5, "en")], key=str)
        if name == "personal data":
            assert len(rows) == 10 and {r.text for r in rows if r.doc_id == 3} == {LONG}
    assert p.STAGES[-1][1](spark, docs, sf).count() >= 10
