"""Surrogates against a plain search of the same texts: who is replaced, by what, and what never may appear."""

import random
import time

import pytest
import regex
from pyspark.sql import functions as F

from finegrain.llm import surrogates

ANY = regex.compile(surrogates.ANY)


def canonical(m):
    """Type and value of a mention, by plain rules."""
    if "@" in m:
        return "email", m.lower()
    if regex.match(r"(password|token|secret|api)", m):
        return "secret", regex.search(r"[=:]\s*\"?([^\"]+)", m)[1]
    if regex.fullmatch(r"A[KS]IA\w{16}", m):
        return "access_key", m
    if regex.fullmatch(r"\d+\.\d+\.\d+\.\d+", m):
        return "ip", m
    digits = regex.sub(r"\D", "", m)
    if len(digits) >= 13:
        return "card", digits
    if digits:
        return "phone", digits[-10:]
    return "person", m


def luhn(number):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(number))) % 10 == 0


def corpus(n=250, seed=3):
    rng = random.Random(seed)
    first = ["Maria", "John", "Wolfgang", "Hélène", "Carlos", "Ольга", "Иван", "Μαρία", "Anna"]
    last = ["Miller", "Schmidt", "Dubois", "Garcia", "Li", "Оak", "Quux", "Zed", "Brown"]
    phones = [f"{rng.randint(200, 999)}{rng.randint(200, 999)}{rng.randint(1000, 9999)}" for _ in range(40)]
    cards = []
    while len(cards) < 30:
        c = f"4{rng.randrange(10**14):014d}"
        cards.append(next(c + str(d) for d in range(10) if luhn(c + str(d))))
    mails = [f"{rng.choice('abcdefgh')}{rng.choice(['', '.x', '1'])}@{rng.choice(['ab.org', 'mail1.example.com', 'q.net'])}" for _ in range(60)]
    keys = [f"AKIA{''.join(rng.choice('ABCDEFGH234') for _ in range(16))}" for _ in range(20)]
    ips = [f"10.0.{rng.randint(0, 3)}.{rng.randint(0, 5)}" for _ in range(20)]
    out = []
    for d in range(n):
        p, c, m = rng.choice(phones), rng.choice(cards), rng.choice(mails)
        mention = rng.choice([
            f"{p[:3]}-{p[3:6]}-{p[6:]}", f"+1 ({p[:3]}) {p[3:6]}-{p[6:]}", c, f"{c[:4]} {c[4:8]} {c[8:12]} {c[12:]}", m, m.upper(), rng.choice(keys), rng.choice(ips),
            f"password={rng.choice(['deadbeef01', 'Tr0ub4dor3x', 'aaaaaaaa'])}", f"{rng.choice(first)} {rng.choice(last)}", f"Mr {rng.choice(last)}", f"{rng.choice(first)} {rng.choice(last)}",
        ])
        out.append((d, f"|{d}| ask {mention} |and| {rng.choice(ips)} |end"))
    return out


def test_distinct_and_together(spark):
    rows = corpus()
    got = {r["doc_id"]: r for r in surrogates.with_surrogates(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()}
    by_value, real, people = {}, set(), {}
    for d, text in rows:
        found = [m[0] for m in ANY.finditer(text)]
        between = ANY.split(text)
        shape = regex.compile("(.+?)".join(map(regex.escape, between)) + r"\Z", regex.S)
        put = shape.match(got[d]["text"])
        assert put and got[d]["n_entities"] == len(found) >= 1, (text, got[d])
        for old, new in zip(found, put.groups(), strict=True):
            (kind, value), (other, fresh) = canonical(old), canonical(new)
            assert kind == other and old != new
            if kind == "person":
                a, b = regex.sub(r"^Mr ", "", old).split(), regex.sub(r"^Mr ", "", new).split()
                assert len(a) == len(b) and old.startswith("Mr ") == new.startswith("Mr ")
                for x, y, part in zip(a[::-1], b[::-1], ("family", "given"), strict=False):
                    assert people.setdefault((part, x), y) == y and x.lower() not in y.lower()
                    assert bool(regex.search(r"\p{IsCyrillic}", x)) <= bool(regex.search(r"\p{IsCyrillic}", y)) and bool(regex.search(r"\p{IsGreek}", x)) == bool(regex.search(r"\p{IsGreek}", y))
                continue
            real.add((kind, value))
            assert by_value.setdefault((kind, value), fresh) == fresh  # together
            if kind == "card":
                assert luhn(fresh) and regex.sub(r"\d", "0", old)[1:] == regex.sub(r"\d", "0", new)[1:]
            if kind == "phone":
                assert regex.sub(r"\d", "0", old) == regex.sub(r"\d", "0", new)
    for table, names in ((by_value, real), (people, set(people))):
        fresh = [(k, v) for (k, _), v in table.items()]
        assert len(fresh) == len(set(fresh)) > 10 and not set(fresh) & names  # distinct, and no real value


@pytest.mark.parametrize("kind", ["given:female:latin", "given:any:cyrillic", "family", "email", "phone"])
def test_two_thousand_of_a_kind(spark, kind):
    value = {"given:female:latin": lambda i: f"Name{i}", "given:any:cyrillic": lambda i: f"Имя{i}", "family": lambda i: f"Li{i}", "email": lambda i: f"{i}@x.org", "phone": lambda i: f"{i + 10000}"}[kind]
    values = [value(i) for i in range(2000)]
    got = {r["value"]: r["new"] for r in surrogates.assign_surrogates(spark.createDataFrame([(kind, v) for v in values], "kind string, value string")).collect()}
    assert len(got) == 2000 == len({x.lower() for x in got.values()}) and not set(got.values()) & set(values)
    assert not any(v.lower() in x.lower() for v, x in got.items())


def test_no_original_is_written_when_draws_run_out(spark):
    df = spark.createDataFrame([("ip", f"{a}.{b}.1.1") for a in range(20) for b in range(20)], "kind string, value string")
    with pytest.raises(RuntimeError):
        surrogates.assign_surrogates(df.unionByName(spark.createDataFrame([("given:male:latin", n) for n in surrogates.GIVEN["male", "latin"]], "kind string, value string")), most_draws=1).collect()


def long_texts(n):
    """Texts that make each pattern run far."""
    return {
        "labels": "mail x@" + "a." * (n // 2), "labels2": "mail x@" + "ab." * (n // 3) + " end", "local": "a" * n + "@b.org", "signs": "+" * n, "phone": "+1 " + "2 " * (n // 2), "digits": "4" * n, "cards": "4111 " * (n // 5),
        "secret": "password=" + "a" * n, "names": "Maria " * (n // 6), "title": "Mr " * (n // 3), "upper": "A" * n, "key": "AKIA" * (n // 4), "ip": "1." * (n // 2), "cue": "my name is " * (n // 11), "case": "Aa " * (n // 3),
    }


def test_a_megabyte_for_every_pattern(spark):
    df = spark.createDataFrame(list(long_texts(1_000_000).items()), "doc_id string, text string")
    began = time.perf_counter()
    got = {r["doc_id"]: r["n"] for r in df.select("doc_id", F.size(surrogates.mentions(F.col("text"))).alias("n")).collect()}
    assert len(got) == 15 and got["signs"] == 0 and got["labels2"] == 1 and got["secret"] == 1
    assert time.perf_counter() - began < 60


def test_long_texts_are_rewritten_whole(spark):
    n = 200_000
    units = long_texts(n)
    got = {r["doc_id"]: r for r in surrogates.with_surrogates(spark.createDataFrame(list(units.items()), "doc_id string, text string")).selectExpr("doc_id", "length(text) AS n", "n_entities").collect()}
    assert set(got) == set(units) and all(r["n"] > n * 0.6 for r in got.values()) and got["signs"]["n_entities"] == 0


def test_people_by_what_stands_around_them(spark):
    rows = [
        (1, "Hello, my name is Zork Quibble and I like tea."), (2, "Dear Florbel Gnarp, thank you"), (3, "From Florbel Gnarp <flo@gnarp.org> on Monday"), (4, "Regards,\nZork Quibble"), (5, "Je m'appelle Quentine Zorbier."),
        (6, "The Open Water and the High Road are places. Dear Customer Service team"), (7, "Mr Zork Quibble came."), (8, "με λένε Ζορκα Κουιβλα σήμερα"),
    ]
    got = {r["doc_id"]: r for r in surrogates.with_surrogates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[6]["text"] == rows[5][1] and got[6]["n_entities"] == 0
    for d, text in rows:
        if d != 6:
            assert not regex.search(r"Zork|Quibble|Florbel|Gnarp|Quentine|Zorbier|Ζορκα|Κουιβλα", got[d]["text"]) and "person" in got[d]["entity_kinds"], got[d]
    name = regex.search(r"my name is (\S+ \S+) and", got[1]["text"])[1]
    assert name in got[4]["text"] and name in got[7]["text"]
    assert regex.search(r"Dear (\S+ \S+),", got[2]["text"])[1] in got[3]["text"] and regex.search(r"\p{IsGreek}+ \p{IsGreek}+ σήμερα", got[8]["text"])


def test_clashing_names(spark):
    names = ["doc_id", "text", "doc", "row", "word", "bits", "slot", "maybe", "puts", "n", "kinds", "body", "old", "a.b", "n_entities"]
    rows = [(1, "mail a@b.org", *(f"v{i}" for i in range(13))), (2, None, *(f"w{i}" for i in range(13)))]
    got = surrogates.with_surrogates(spark.createDataFrame(rows, names))
    assert got.columns == [*names[:-1], "n_entities", "entity_kinds"]
    by = {r["doc_id"]: tuple(r) for r in got.collect()}
    assert by[1][2:14] == rows[0][2:14] and by[2][1:14] == rows[1][1:14] and by[1][-2:] == (1, "email") and by[2][-2:] == (0, "")
