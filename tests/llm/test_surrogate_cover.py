"""Telephones of other countries and persons beyond the surrogates' own names."""

import re

from finegrain.llm import surrogates

CASES = {
    "+49 30 1234567": "phone", "+44 20 7946 0958": "phone", "+33 1 42 68 53 00": "phone", "+44 (0)20 7946 0958": "phone", "+34912345678": "phone", "+352 123456": "phone", "+1 (988) 555-2485": "phone",
    "John Smith": "person", "Anna Schmidt": "person", "David Brown": "person", "Anna Maria Schmidt": "person", "Jürgen Müller": "person", "Hélène Dubois": "person", "Иван Петров": "person",
}


def test_other_telephones_and_names(spark):
    df = spark.createDataFrame([(i, f"Then ask {c} about it.") for i, c in enumerate(CASES)] + [(99, "The sum 2+3 is 5. Then Open Water is a place.")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in surrogates.with_surrogates(df).collect()}
    for i, (case, kind) in enumerate(CASES.items()):
        r = got[i]
        assert r["entity_kinds"] == kind and r["n_entities"] == 1, (case, r)
        assert case not in r["text"] and not any(w in r["text"] for w in re.findall(r"[^\W\d]{3,}", case)), (case, r)
        if kind == "phone":  # format and country code stay
            assert re.sub(r"\d", "0", r["text"]) == re.sub(r"\d", "0", f"Then ask {case} about it.")
            code = re.match(r"\+(1|49|44|33|34|352)", case)[0]
            assert f"ask {code}" in r["text"]
    assert got[99]["n_entities"] == 0


def test_many_detected_names():
    drawn = {n for names in surrogates.GIVEN.values() for n in names}
    assert len(surrogates._KNOWN) > 8 * len(drawn) and not drawn & {n for names in surrogates.DETECTED.values() for n in names}
