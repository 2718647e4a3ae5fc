"""The licence index against a plain search of all places, and long texts."""

import random
import re
import time

from finegrain.llm import licences


def plain(text):
    """Every place of every licence text, share by share, and which labels have all key phrases."""
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.translate({i: i + 32 for i in range(65, 91)}))
    line, out = " " + " ".join(words) + " ", set()
    for label, postings in licences.positional_index().items():
        whole = sum(p[2] for p in postings)
        if not all(f" {k} " in line for k in licences.TEXTS[label][1]):
            continue
        for at in range(-max(k for _, k, _ in postings), len(words)):
            share = sum(idf for w, k, idf in postings if 0 <= at + k < len(words) and words[at + k] == w) / whole
            if share >= licences.ENOUGH - 1e-9:
                out.add((label, at, round(share, 9)))
    return out


def edited(rng, words):
    out = []
    for w in words:
        r = rng.random()
        out += [] if r < 0.01 else [w, "extra"] if r < 0.02 else ["other"] if r < 0.06 else [w]
    return out


def test_places_equal_a_plain_search(spark):
    rng = random.Random(5)
    rows = []
    for i in range(160):
        parts = [rng.choice(list(licences.TEXTS.values()))[0].split() for _ in range(rng.randint(1, 3))]
        body = ["before"] * rng.randint(0, 3)
        for p in parts:
            body += edited(rng, p) if i % 4 else p
        rows.append((i, (", " if i % 2 else " ").join(w.upper() if rng.random() < 0.1 else w for w in body[rng.randint(0, 5) :])))
    rows += [(900, "license " * 50), (901, ""), (902, "the quick brown fox"), (903, " ".join(reversed(licences.BODIES["body:mit"][0].split())))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    some = 0
    for r in licences.scan_licences(df).collect():
        want = plain(r["text"])
        assert {(n["label"], n["at"], round(n["share"], 9)) for n in r["notices"]} == want and len(r["notices"]) == len(want), r["doc_id"]
        base = set(r["base_labels"].split(",")) - {""}
        assert set(r["labels"].split(",")) - {""} == base | {label for label, *_ in want}
        assert abs(r["score"] - max([s for *_, s in want], default=0.5 if base else 0.0)) < 1e-9
        some += len(want)
    assert some > 200


def test_whole_bodies_are_found(spark):
    df = spark.createDataFrame([(label, f"x {words} y") for label, (words, _) in licences.TEXTS.items()], "label string, text string")
    for r in licences.scan_licences(df).collect():
        assert r["label"] in r["labels"].split(",") and any(n["label"] == r["label"] and n["at"] == 1 and n["share"] > 0.999 for n in r["notices"])


def test_every_anchor_set_is_enough():
    for postings in licences.positional_index().values():
        left = sum(p[2] for p in postings[licences.anchors_of(postings) :])
        assert left < licences.ENOUGH * sum(p[2] for p in postings)


def test_a_megabyte_of_one_word(spark):
    licences.scan_licences(spark.createDataFrame([(1, "license")], "doc_id long, text string")).collect()
    for unit in ("license ", "gnu ", "program ", "mit license ", licences.BODIES["body:gpl-3.0"][0] + " "):
        scanned = licences.scan_licences(spark.createDataFrame([(1, unit * (1_000_000 // len(unit)))], "doc_id long, text string")).drop("text")
        began = time.perf_counter()
        scanned.collect()
        assert time.perf_counter() - began < 6, unit


def test_clashing_names(spark):
    names = ["doc_id", "text", "row", "words", "found", "base", "candidates", "line", "sure", "body", "a.b", "score"]
    df = spark.createDataFrame([(1, "under the apache license", *(f"v{i}" for i in range(10)))], names)
    got = licences.scan_licences(df)
    assert got.columns == [*names[:-1], *licences.OWN]
    r = got.collect()[0]
    assert tuple(r)[: len(names) - 1] == (1, "under the apache license", *(f"v{i}" for i in range(9))) and r["labels"] == "apache"
