import hashlib
import re
from collections import defaultdict

import numpy as np
import pytest

from finegrain.llm import exact_dedup, sharding


def norm(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


def test_equals_brute_force(docs, texts):
    groups = defaultdict(list)
    for d, t in texts.items():
        groups[norm(t)].append(d)
    rows = exact_dedup.exact_dedup_digest(docs).collect()
    assert len(rows) == len(texts)
    for r in rows:
        g = groups[norm(texts[r["doc_id"]])]
        assert (r["keep_id"], r["group_size"], r["kept"]) == (min(g), len(g), r["doc_id"] == min(g))
        assert r["text_sha256"] == hashlib.sha256(norm(texts[r["doc_id"]]).encode()).hexdigest()


@pytest.mark.parametrize("bits", [6, 10])
def test_a_full_filter_changes_nothing(docs, bits):
    a = exact_dedup.exact_dedup_digest(docs).select("doc_id", "keep_id", "group_size", "kept")
    assert a.exceptAll(exact_dedup.exact_dedup_digest(docs, slot_bits=bits).select(*a.columns)).count() == 0


def test_odd_rows(odd, no_docs):
    rows = exact_dedup.exact_dedup(odd)
    assert set(odd.columns) <= set(rows.columns) and rows.count() == odd.count()
    kept = rows.filter("kept").groupBy("text_sha256").count().collect()
    assert all(r["count"] == 1 for r in kept)
    by = {(r["doc_id"], r["text"]): r for r in rows.collect()}
    assert by[(3, "")]["keep_id"] == 2 and by[(3, "")]["group_size"] == 2
    assert by[(None, odd.first()["text"])]["keep_id"] == 1
    assert exact_dedup.exact_dedup(no_docs).count() == 0 == exact_dedup.exact_dedup_digest(no_docs).count()


def test_only_native_operators(docs):
    plan = exact_dedup.exact_dedup(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_kept_rows_do_not_depend_on_splits(spark, docs, tmp_path):
    """The plan is made under one split size and run under another, with rows that agree in all columns."""
    path = str(tmp_path / "docs")
    docs.unionByName(docs.filter("doc_id % 7 = 0")).repartition(6).write.parquet(path)
    setting = "spark.sql.files.maxPartitionBytes"
    before = spark.conf.get(setting)
    want = None
    for first, second in (("128m", "64k"), ("64k", "128m"), ("256k", "256k")):
        try:
            spark.conf.set(setting, first)
            kept = exact_dedup.exact_dedup(spark.read.parquet(path)).filter("kept")
            spark.conf.set(setting, second)
            rows = sorted((r["doc_id"], r["text_sha256"]) for r in kept.select("doc_id", "text_sha256").collect())
        finally:
            spark.conf.set(setting, before)
        assert len(rows) == len({sha for _, sha in rows}) == docs.select(exact_dedup.fingerprint()).distinct().count()
        want = want or rows
        assert rows == want


def test_clashing_names(spark):
    names = ["doc_id", "text", "sha", "id", "row", "maybe", "word", "bits", "slot", "spread", "size", "first_id", "ties", "tied", "at", "a.b", "kept"]
    rows = [(i, "same" if i % 3 else f"own {i}", *(f"{n}{i}" for n in names[2:])) for i in range(20)]
    df = spark.createDataFrame([*rows, rows[0], (None, *rows[1][1:])], names)
    got = exact_dedup.exact_dedup(df)
    assert got.columns == [*names[:-1], "text_sha256", "keep_id", "group_size", "kept"]
    assert sorted(map(str, got.select(*(f"`{n}`" for n in names[:-1])).collect())) == sorted(map(str, df.drop("kept").collect()))
    assert got.filter("kept").count() == 8


@pytest.mark.parametrize("n", [1, 2, 3, 7, 40, 1000, 1021, 4096])
def test_permutation(n):
    p = sharding.permute(np.arange(n), n)
    assert sorted(p.tolist()) == list(range(n))
    assert (sharding.permute(p, n, inverse=True) == np.arange(n)).all()
    a, b = sharding.radices(n)
    assert a * b >= n and a * b - n < max(a, 2)


def test_other_keys_shuffle_otherwise():
    assert (sharding.permute(np.arange(1000), 1000, 1) != sharding.permute(np.arange(1000), 1000, 2)).mean() > 0.9


def test_shards(docs, texts):
    import zlib

    rows = sharding.sharded_documents(docs).collect()
    counts = defaultdict(list)
    for r in rows:
        counts[r["shard"]].append(r["slot"])
        body = (texts[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"]) == (len(body) + 16, zlib.crc32(body), "rows")
    assert len(counts) == 40 and max(map(len, counts.values())) - min(map(len, counts.values())) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in counts.values())
    order = sharding.permute(np.arange(len(rows)), len(rows))
    for r in rows:
        assert r["shard"] == order[r["row_number"]] % 40 and r["slot"] == order[r["row_number"]] // 40


def test_shards_of_odd_rows(odd, no_docs):
    rows = sharding.sharded_documents(odd, 4).collect()
    assert len(rows) == odd.count() and sharding.sharded_documents(no_docs).count() == 0
    assert [r["size"] for r in rows if r["doc_id"] == 2] == [16]
    again = sharding.sharded_documents(odd.repartition(5), 4).collect()
    key = lambda r: (str(r["doc_id"]), r["size"], r["shard"], r["slot"])
    assert sorted(map(key, rows)) == sorted(map(key, again))


def test_numbers_of_rows_that_are_alike(spark):
    """A third of all rows agree in id and text: every number is given once, in ranges that stay small."""
    rows = [(None, "same")] * 400 + [(i % 300, f"text {i % 450}") for i in range(800)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5).checkpoint()
    got = sharding.sharded_documents(df, 7, range_rows=20).collect()
    assert sorted(r["row_number"] for r in got) == list(range(1200))
    want = sorted((str(r["doc_id"]), r["size"], r["shard"], r["slot"]) for r in got)
    again = sharding.sharded_documents(df.repartition(3), 7, range_rows=20).collect()
    assert want == sorted((str(r["doc_id"]), r["size"], r["shard"], r["slot"]) for r in again)
