"""Surrogates held against plain Python: check digits, countries, dates, names word by word."""

import datetime
import re

from pyspark.sql import functions as F

from zbox.llm import pii

KEY = "test key"


def rewrite(spark, texts, key=KEY):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    return {r.doc_id: r for r in pii.replace(df, key).collect()}


def luhn(digits):
    return sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(digits))) % 10 == 0


def iban_holds(s):
    s = s.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def test_check_digits(spark):
    ibans = ["DE89370400440532013000", "GB82 WEST 1234 5698 7654 32", "FR1420041010050500013M02606"]
    cards = ["4111111111111111", "5500 0055 5555 5559", "340000000000009"]
    wrong = ["DE00370400440532013000", "4111111111111112", "id 1700000000000 ms", "1234 5678 1234 5678"]
    got = rewrite(spark, [f"to {x} now" for x in ibans + cards] + wrong)
    for i, x in enumerate(ibans):
        y = got[i].text[3:-4]
        assert y != x and y[:2] == x[:2] and iban_holds(y) and re.sub("[A-Z]", "A", re.sub(r"\d", "0", y[2:])) == re.sub("[A-Z]", "A", re.sub(r"\d", "0", x[2:]))
    for i, x in enumerate(cards, len(ibans)):
        y = got[i].text[3:-4]
        assert y != x and luhn(y.replace(" ", "")) and [len(p) for p in y.split(" ")] == [len(p) for p in x.split(" ")]
    for i, x in enumerate(wrong, len(ibans) + len(cards)):
        assert got[i].text == x and got[i].n_entities == 0


def test_coreference_of_names(spark):
    """Every word of a name has one surrogate, with and without honorific, in any case, in any text."""
    got = rewrite(spark, [
        "Mr. John Smith met Ms Ann Smith. JOHN SMITH and john smith left; Smith and SMITH stayed; smithy and blacksmith too.",
        "MR. JOHN SMITH", "Mrs Smith and Mr J. K. Smith", "Dr Ann Jones", "no one: John Smith",
    ])
    t = got[0].text
    m = re.match(r"Mr\. (\w+) (\w+) met Ms (\w+) (\w+)\. (\w+ \w+) and (\w+ \w+) left; (\w+) and (\w+) stayed; smithy and blacksmith too\.$", t)
    john, smith, ann = m[1], m[2], m[3]
    assert m[4] == smith and m[5] == f"{john} {smith}".upper() and m[6] == f"{john} {smith}".lower() and (m[7], m[8]) == (smith, smith.upper())
    assert got[1].text == f"MR. {john} {smith}".upper()
    assert re.match(rf"Mrs {smith} and Mr [A-Z]\. [A-Z]\. {smith}$", got[2].text) and "J. K." not in got[2].text
    assert got[3].text.split()[1][:8] == ann[:8] and smith not in got[3].text
    assert got[4].text == "no one: John Smith"
    assert "Smith" not in t.replace("blacksmith", "") and "John" not in t


def test_dates_and_addresses(spark):
    got = rewrite(spark, ["born 1980-02-29", "DOB: 3/4/1990", "date of birth 31.12.1999", "on 1980-02-29", "at 221B Baker Street now", "10 green apples"])
    gap = datetime.date.fromisoformat(got[0].text[-10:]) - datetime.date(1980, 2, 29)
    assert gap.days >= 400
    assert datetime.datetime.strptime(got[1].text[5:], "%d/%m/%Y").date() - datetime.date(1990, 4, 3) == gap
    assert datetime.datetime.strptime(got[2].text[14:], "%d.%m.%Y").date() - datetime.date(1999, 12, 31) == gap
    assert got[3].text == "on 1980-02-29" and got[5].text == "10 green apples"
    assert re.match(r"at \d{3}[A-Z] [A-Z]\w+ Street now$", got[4].text) and "Baker" not in got[4].text


def test_collisions_of_name_words_keep_coreference(spark, monkeypatch):
    """With two syllables only, names collide at once; still distinct words stay distinct, and one word one."""
    monkeypatch.setitem(pii.SYLLABLES, "latin", (["ba", "be"] * 16))
    names = [f"N{chr(97 + i)}x" for i in range(24)]
    got = rewrite(spark, [f"Mr {n} and Mrs. {n} and Dr {names[-1]}" for n in names])
    found = [re.match(r"Mr (\w+) and Mrs\. (\w+) and Dr (\w+)$", got[i].text).groups() for i in range(24)]
    assert all(a == b for a, b, _ in found) and len({a for a, *_ in found}) == 24 and {c for *_, c in found} == {found[-1][0]}


def test_odd_rows(spark):
    rows = [(None, "Mr Al Bo"), (None, "Mr Al Bo"), (1, None), (2, ""), (3, "x " * 1_000_000 + "mail a@b.org")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumns({"Entities": F.lit(1), "N_ENTITIES": F.lit(2), "_e": F.lit(3)})
    got = pii.replace(df, KEY)
    assert got.columns == ["doc_id", "text", "_e", "n_entities", "entities"]
    by = sorted(((r.doc_id, r.text, r.n_entities) for r in got.collect()), key=str)
    assert sum(d is None and n == 1 for d, _, n in by) == 2 and len({t for d, t, _ in by if d is None}) == 1
    assert (1, None, 0) in by and (2, "", 0) in by
    long = next(t for d, t, _ in by if d == 3)
    assert long.startswith("x " * 1_000_000 + "mail ") and "a@b.org" not in long
    assert pii.replace(df.limit(0), KEY).count() == 0
