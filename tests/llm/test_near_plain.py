"""Near duplicates whose plain shingle sets are alike and whose weights are not."""

import random

import numpy as np

from finegrain.llm import near_dedup
from finegrain.llm.textkernel import words_of


def test_links_of_both_kinds_are_met(spark):
    rng = random.Random(4)
    common = [f"word{i}" for i in range(60)]
    texts = []
    for i in range(30):  # a line of ten words that stands 50 times in one copy and 10 times in the other
        head = " ".join(f"h{i}x{k}" for k in range(104))
        line = " ".join(f"l{i}x{k}" for k in range(10)) + " "
        texts += [f"{head} {line * 50}", f"{head} {line * 10}"]
    for i in range(30):  # two rare words changed among common ones
        body = [rng.choice(common) for _ in range(120)]
        other = list(body)
        for k in (30, 80):
            body[k], other[k] = f"r{i}x{k}", f"s{i}x{k}"
        texts += [" ".join(body), " ".join(other)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    weights = near_dedup.word_weights(near_dedup.word_document_counts(df))
    parts = []
    for t in texts:
        data = np.frombuffer(t.encode(), np.uint8)
        parts.append(near_dedup.shingles(words_of(data, np.array([0, len(data)])), weights)[1:])
    pairs = [(i, j, *near_dedup.similarity(*parts[i], *parts[j])) for i in range(len(texts)) for j in range(i)]
    links = [(i, j, w) for i, j, w, p in pairs if max(w, p) >= near_dedup.SIMILARITY]
    assert len(links) >= 60 and sum(w < 0.4 for _, _, w in links) >= 30
    classes = {r["doc_id"]: r["class_id"] for r in near_dedup.near_duplicates(df).collect()}
    lost = [x for x in links if classes[x[0]] != classes[x[1]]]
    assert not lost, (len(lost), len(links))


def test_plain_keys_agree_as_the_sets_do():
    rng = np.random.default_rng(1)
    met = []
    for _ in range(400):
        h = np.sort(rng.integers(0, 2**44, 110, dtype=np.uint64))
        keys = near_dedup.plain_band_keys(np.repeat([0, 1], 100), np.concatenate([h[:100], h[10:]]), 2)
        met.append((keys[0] == keys[1]).mean())
    assert abs(np.mean(met) - (90 / 110) ** near_dedup.ROWS) < 0.05
