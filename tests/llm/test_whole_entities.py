"""Personal data of any length and spelling goes whole."""

import pytest
from pyspark.sql import Row

from zbox.llm import pii

LONG = "aZ3_" * 250  # 1,000 characters
WHOLE = {  # a text's entity: what of it may not stay
    "person": {
        "Mr Juan Carlos Garcia": "Juan Carlos Garcia", "Mr John A. Smith": "John Smith", "Mr. J. Smith": "Smith", "Dr J.-P. Martin Lopez": "J.-P. Martin Lopez",
        "Frau Anna Maria Luise von": "Anna Maria Luise", "Mrs A B Clark": "Clark", "Mr " + "Ab" * 40: "Ab" * 40, "Sir X": "X",
    },
    "phone": {"+44 7911 123456": "7911 123456", "+49 170 1234567": "170 1234567", "+49 (170) 1234567": "170 1234567", "+33 6 12 34 56 78": "12 34 56 78", "+1-4155552671": "4155552671"},
    "secret": {
        f"token={LONG}": "aZ3_", "password: hunt3r": "hunt3r", "password=p@ss!gate": "p@ss gate", "api_key: 'a,b;c<d9'": "a,b;c<d9", "Password: sunshine": "sunshine", "secret: Ab1!x": "Ab1",
        "auth=" + "ab12" * 300: "ab12ab12",
    },
}
PLAIN = ["The secret: nothing happens here.", "password: ********", "+1.5 and +10000 of 3", "Mr and Mrs went. Then Dr no"]


@pytest.fixture(scope="module")
def rows(spark):
    lines = [f"so {e} it is" for kind in WHOLE for e in WHOLE[kind]] + PLAIN
    return {r.text0: r for r in pii.replace(spark.createDataFrame([Row(doc_id=i, text=t, text0=t) for i, t in enumerate(lines)]), "key").collect()}


@pytest.mark.parametrize("kind", WHOLE)
def test_nothing_of_an_entity_stays(rows, kind):
    for e, private in WHOLE[kind].items():
        r = rows[f"so {e} it is"]
        assert r.n_entities == 1 and r.entities[kind] == 1, (e, r.text)
        assert r.text.startswith("so ") and r.text.endswith(" it is"), (e, r.text)
        for part in [private] if kind == "phone" else private.split(" "):
            assert part not in r.text[3:-6], (e, r.text)


def test_plain_texts_stay(rows):
    assert [rows[t].text for t in PLAIN] == PLAIN
