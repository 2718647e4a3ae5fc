"""Benchmark items that templates alone do not find."""

import pytest

from finegrain.llm import contamination


def rows(spark, item, *texts):
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return contamination.contaminated_documents(docs, bench).orderBy("doc_id").collect()


def found(spark, item, *texts):
    return [r["contaminated"] for r in rows(spark, item, *texts)]


@pytest.mark.parametrize(
    "item",
    ["What is 12 + 35 + 48 - 7 + 3 equal to", "Solve 3 x 5 = 15", "Name 3 primes", "1 2 3 4 5 6 7 8 9 10 11 12 13 14 15 16"],
)
def test_dense_and_short_items_are_found_verbatim(spark, item):
    assert found(spark, item, f"Some text before. {item}. And after, {item}!", item.replace("3", "4"), "Some text before. And after.") == [True, False, False]


@pytest.mark.parametrize(
    "item",
    ["Sarah bought 5 apples and 3 pears for her mother yesterday", "in the shop Sarah bought 5 apples and 3 pears for her old mother yesterday"],
)
def test_forms_add_up(spark, item):
    other = item.replace("Sarah", "Emma")
    assert found(spark, item, other, f"Before that. {other.replace('5', '9')}. And after.", other.replace("bought", "sold").replace("pears", "plums")) == [True, True, False]


def test_value_of_a_number_is_all_of_it(spark):
    item = "A farm sold 1,200 eggs in the first month and 1,500 eggs in the month after that so how many eggs were sold"
    consistent = item.replace("1,200", "2,400").replace("1,500", "3,600")
    other = item.replace("1,200", "1,300").replace("1,500", "1,600")
    plain = "A farm sold 2 eggs in the first month and 3 eggs in the month after that so how many eggs were sold"
    got = rows(spark, item, item, consistent, other, item.replace(",", "."))
    assert [r["contaminated"] for r in got] == [True] * 4 and [r["exact_values"] for r in got] == [True, False, False, True]
    assert found(spark, plain, plain.replace("2 eggs", "1.5 eggs").replace("3 eggs", "1.7 eggs")) == [True]


LONG = (
    "The train leaves the station with 2 engines and then passes over the long bridge near the mill where workers load grain into 2 wagons before it turns north "
    "towards the hills and stops for water at the old tower while the driver checks all of the brakes and 2 guards walk along the side"
)


def test_one_edited_value_leaves_the_other_windows(spark):
    edited, twice = LONG.replace("2 guards", "3 guards"), LONG.replace("2", "9").replace("9 guards", "8 guards")
    got = rows(spark, LONG, LONG, edited, twice)
    assert [r["contaminated"] for r in got] == [True] * 3 and [r["exact_values"] for r in got] == [True, False, False]
    assert got[0]["share"] == 1.0 and 0.5 < got[1]["share"] < 1.0


def test_two_values_may_become_one(spark):
    item = "At the market Tom buys 3 apples and 5 pears for lunch how many pieces of fruit does he carry home"
    assert found(spark, item, item.replace("3", "4").replace("5", "4")) == [True]
    half = "Take 1 2 3 4 5 6 then say how many there are"
    assert found(spark, half, half, half.replace("3", "4"), half.replace("many", "few")) == [True, True, False]


def test_recall_of_reparameterised_items(spark):
    """Of 150 items with numbers, units and names, given other ones throughout, nine in ten or more are found; texts of other words are not."""
    import random

    rng = random.Random(7)
    words = [f"{a}{b}" for a in ("bra", "cel", "dom", "fin", "gor", "hal", "jut", "kem", "lor", "mip") for b in ("ta", "ren", "sil", "vo", "nak", "dul", "pes", "gim", "wor", "bex")]
    names, units = ["Alice", "Robert", "Selma", "Tarik", "Ines"], ["apples", "kg", "miles", "hours", "dollars"]
    items, docs = [], []
    for i in range(150):
        text, values = [], [str(rng.randint(2, 9)), f"{rng.randint(1, 9)},{rng.randint(100, 999)}", rng.choice(names), rng.choice(units)]
        other = [str(rng.randint(20, 99)), f"{rng.randint(1, 9)},{rng.randint(100, 999)}", rng.choice([n for n in names if n != values[2]]), rng.choice(["kg", "miles", "hours"]) if values[3] in ("kg", "miles", "hours") else values[3]]
        for k in range(rng.randint(14, 40)):
            text.append(rng.choice(words))
            if k % 5 == 2:
                text.append("\0" + str(rng.randrange(4)))
        fill = lambda v, t=text: " ".join(v[int(w[1:])] if w[0] == "\0" else w for w in t)
        items.append((i, fill(values)))
        around = [" ".join(rng.choice(words) for _ in range(30)) for _ in range(2)]
        docs += [(i, f"{around[0]}. {fill(other)}. {around[1]}"), (1000 + i, f"{around[1]} {' '.join(rng.choice(words) for _ in text)} {values[0]} {values[3]} {around[0]}")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r["doc_id"]: r for r in contamination.contaminated_documents(spark.createDataFrame(docs, "doc_id long, text string"), bench).collect()}
    hit = sum(str(i) in got[i]["items"].split(",") for i in range(150))
    assert hit >= 135, hit
    assert not any(got[1000 + i]["contaminated"] for i in range(150))
