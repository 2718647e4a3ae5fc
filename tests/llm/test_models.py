import itertools
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from finegrain.llm import contamination, lm, near_dedup, quality


# ------------------------------------------------------------- near duplicates


def words(t):
    return re.findall(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", (t or "").translate({i: i + 32 for i in range(65, 91)}))


def shingle_set(t):
    w = words(t)
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_no_link_is_lost(docs, texts):
    classes = {r["doc_id"]: r["class_id"] for r in near_dedup.near_duplicates(docs).collect()}
    sets = {d: shingle_set(t) for d, t in texts.items()}
    index = defaultdict(list)
    for d, s in sets.items():
        for g in s:
            index[g].append(d)
    pairs = {p for ids in index.values() for p in itertools.combinations(sorted(ids), 2)}
    links = lost = 0
    for a, b in pairs:
        j = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
        links += j >= 0.8
        lost += j >= 0.8 and classes[a] != classes[b]
        assert j >= 0.4 or classes[a] != classes[b]
    assert links > 50 and lost == 0


def weighted_links(docs, texts):
    """Pairs of different texts that the weights make links, by comparison of all that share a shingle, and how many lie in two classes."""
    weights = near_dedup.word_weights(near_dedup.word_document_counts(docs))
    lists, index = {}, defaultdict(list)
    for d, t in texts.items():
        data = np.frombuffer((t or "").encode(), np.uint8)
        lists[d] = near_dedup.shingles(near_dedup.words_of(data, np.array([0, len(data)])), weights)[1:]
        for h in lists[d][0].tolist():
            index[h].append(d)
    classes = {r["doc_id"]: r["class_id"] for r in near_dedup.near_duplicates(docs).collect()}
    links = lost = 0
    for a, b in {p for ids in index.values() for p in itertools.combinations(sorted(ids), 2)}:
        if texts[a] != texts[b] and near_dedup.similarity(*lists[a], *lists[b])[0] >= 0.8:
            links, lost = links + 1, lost + (classes[a] != classes[b])
    return links, lost


def test_weighted_links_of_the_table(docs, texts):
    links, lost = weighted_links(docs, texts)
    assert links >= 10 and lost == 0


def test_weighted_links_of_edited_copies(spark):
    """Copies with words changed, words left out and lines said again, near the threshold."""
    rng = np.random.default_rng(11)
    texts = {}
    for d in range(0, 600, 2):
        base = [f"w{k}" for k in rng.zipf(1.3, 160) % 5000]
        copy = [w if rng.random() > 0.012 else f"e{d}x{i}" for i, w in enumerate(base)]
        texts[d], texts[d + 1] = " ".join(base), " ".join(copy if d % 3 else copy + copy[:12])
    links, lost = weighted_links(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), texts)
    assert links >= 100 and lost <= 0.02 * links, (links, lost)


def test_clashing_names(spark):
    names = ["doc_id", "text", "_key", "key", "id", "row", "word", "bits", "slot", "maybe", "node", "class_id", "a.b"]
    rows = [(i, f"one two three four five six seven {i // 2}" if i < 10 else "so many words that stand in no other text " + " ".join(f"w{i}x{k}" for k in range(9)), *(f"{n}{i}" for n in names[2:])) for i in range(14)]
    df = spark.createDataFrame(rows, names)
    kept = near_dedup.without_near_duplicates(df)
    assert kept.columns == names and {tuple(r) for r in kept.collect()} <= {tuple(r) for r in rows} and kept.count() == 9
    bench = spark.createDataFrame([(1, "so many words that stand in no other text " + " ".join(f"w13x{k}" for k in range(9)))], "item_id long, text string")
    clean = contamination.decontaminated(df, bench)
    assert clean.columns == names and {tuple(r) for r in clean.collect()} == {tuple(r) for r in rows[:13]}


def test_large_group_by_blocks(spark):
    """A family of 300 copies with random edits: same components as all pairs give."""
    rng = np.random.default_rng(4)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for d in range(300):
        t = list(base)
        for at in rng.choice(120, rng.integers(0, 9), replace=False):
            t[at] = f"e{d}x{at}"
        rows.append((d, " ".join(t)))
    rows += [(1000 + d, " ".join(f"u{d}v{i}" for i in range(60))) for d in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3).checkpoint()
    got = {r["doc_id"]: r["class_id"] for r in near_dedup.near_duplicates(df).collect()}
    sets = {d: shingle_set(t) for d, t in rows}
    for a, b in itertools.combinations(range(300), 2):
        if len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8:
            assert got[a] == got[b]
    assert all(got[1000 + d] == 1000 + d for d in range(60))


def test_block_similarities_equal_pairs():
    rng = np.random.default_rng(0)

    def text():
        h = np.unique(rng.integers(0, 300, rng.integers(1, 200))).astype(np.uint32)
        return h, (rng.integers(1, 4, len(h)) * (h % 7 + 1) / 16).astype(np.float32)

    a, b = [text() for _ in range(12)], [text() for _ in range(9)]
    w, p = near_dedup.block_similarities([x[0] for x in a], [x[1] for x in a], [x[0] for x in b], [x[1] for x in b], columns=64)
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            assert np.allclose((w[i, j], p[i, j]), near_dedup.similarity(*x, *y), atol=1e-6)


def test_samples_agree_as_the_weights_do():
    """Over many pairs, a band's keys agree as often as its four samples should: the weighted Jaccard similarity to the fourth."""
    rng = np.random.default_rng(1)
    met, want = [], []
    for _ in range(200):
        h = np.unique(rng.integers(0, 2**44, 300, dtype=np.uint64))
        w = rng.integers(8, 100, len(h)).astype(np.float32) / 8
        keep = rng.random(len(h)) < 0.85
        text = np.concatenate([np.zeros(len(h), np.int64), np.ones(int(keep.sum()), np.int64)])
        keys, _ = near_dedup.band_keys(text, np.concatenate([h, h[keep]]), np.concatenate([w, w[keep]]), 2)
        met.append((keys[0] == keys[1]).mean())
        want.append((w[keep].sum() / w.sum()) ** near_dedup.ROWS)
    assert abs(np.mean(met) - np.mean(want)) < 0.04


def test_near_duplicates_of_odd_rows(odd, no_docs):
    source = odd.checkpoint()
    rows = {(r["doc_id"], i): r for i, r in enumerate(near_dedup.near_duplicates(source).collect())}
    assert len(rows) == odd.count()
    by = defaultdict(list)
    for (d, _), r in rows.items():
        by[d].append(r["class_id"])
    assert by[None] == [1] and by[7] == [6, 6] and by[10] == [9] and by[2] == by[3] == [2] and by[5] == [5] and by[4] == [4]
    kept = near_dedup.without_near_duplicates(source)
    assert kept.columns == odd.columns and kept.count() == len({c for x in by.values() for c in x})
    assert near_dedup.near_duplicates(no_docs).count() == 0 == near_dedup.without_near_duplicates(no_docs).count()


# ------------------------------------------------------------- quality


def auc(score, label):
    rank = np.argsort(np.argsort(score))
    pos = label == 1
    return (rank[pos].sum() - pos.sum() * (pos.sum() - 1) / 2) / (pos.sum() * (~pos).sum())


def test_held_out_quality(docs, spark):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    scored = quality.quality_scores(docs, labels)
    assert scored.count() == docs.count()
    rows = scored.join(labels, "doc_id").filter("held_out").toPandas()
    assert auc(rows["score"].to_numpy(), rows["quality"].to_numpy()) > 0.95
    assert ((rows["score"] >= 0.7).astype(int) == rows["predicted"]).all() and (rows["predicted"] == rows["quality"]).mean() > 0.9
    for r in scored.limit(200).collect():
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2)


def test_labels_of_held_out_rows_are_not_learnt(docs, spark):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    held = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2
    turned = labels.withColumn("quality", F.when(held, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = quality.quality_scores(docs, labels), quality.quality_scores(docs, turned)
    assert a.exceptAll(b).count() == 0


def test_non_negative_risk_beats_its_prior():
    rng = np.random.default_rng(2)
    p = rng.normal(1, 1, (800, quality.WIDTH))
    u = np.vstack([rng.normal(1, 1, (700, quality.WIDTH)), rng.normal(-1, 1, (300, quality.WIDTH))])
    model = quality.fit_nnpu(p, u)
    assert 0.55 < model.prior < 0.85
    assert (model.score(u[700:]) < 0.5).mean() > 0.95 and (model.score(u[:700]) > 0.5).mean() > 0.95


def test_quality_of_odd_rows(odd, no_docs, spark):
    labels = spark.createDataFrame([(1, 1, 0), (1, 1, 0), (6, 0, 0), (None, 1, 0), (99, 1, 1)], "doc_id long, quality int, toxic int")
    rows = quality.quality_scores(odd, labels).collect()
    assert len(rows) == odd.count() and all(0 <= r["score"] <= 1 for r in rows)
    none = quality.quality_scores(odd, labels.filter("false")).collect()
    assert {r["score"] for r in none} == {0.5}
    assert quality.quality_scores(no_docs, labels).count() == 0
    assert quality.keep_good(odd, labels).columns == odd.columns and quality.keep_good(no_docs, labels).count() == 0


# ------------------------------------------------------------- language model


def plain_forward(model, symbols):
    a, total = model.start * model.emit[symbols[0]], 0.0
    for s in symbols[1:]:
        total, a = total + math.log(a.sum()), (a / a.sum()) @ model.step * model.emit[s]
    return (total + math.log(a.sum())) / math.log(10)


def test_counts_across_window_borders():
    """Windows with run-in give what one window over the whole text gives: tokens and transitions of borders included."""
    rng = np.random.default_rng(9)
    m = lm.starting_model(40, 4)
    lengths = np.array([700, 3, 256, 257, 1, 513])
    symbols = rng.integers(0, 40, lengths.sum())
    whole = lm.expected_counts(m, symbols, lengths, window=10_000, halo=0)
    cut = lm.expected_counts(m, symbols, lengths)
    assert abs(cut[1].sum() - (lengths - 1).sum()) < 1e-6 and abs(cut[2].sum() - lengths.sum()) < 1e-6 and abs(cut[0].sum() - len(lengths)) < 1e-9
    for a, b in zip(whole[:3], cut[:3], strict=True):
        assert np.abs(a - b).max() < 2e-3 * max(1, np.abs(a).max())
    assert abs(whole[3] - cut[3]) < 1e-3 * abs(whole[3])


@pytest.mark.parametrize("lengths", [[1], [5, 1, 64, 65, 130, 2, 200], [64, 64]])
def test_forward_is_exact(lengths):
    rng = np.random.default_rng(7)
    m = lm.HiddenMarkov(rng.dirichlet(np.ones(4)), rng.dirichlet(np.ones(4), 4), rng.dirichlet(np.ones(9), 4).T)
    symbols = rng.integers(0, 9, sum(lengths))
    got = lm.forward_log10(m, symbols, np.array(lengths))
    at = np.cumsum([0, *lengths])
    assert np.allclose(got, [plain_forward(m, symbols[a:b]) for a, b in zip(at, at[1:], strict=False)])


def test_expected_counts_equal_all_paths():
    rng = np.random.default_rng(8)
    m = lm.HiddenMarkov(rng.dirichlet(np.ones(2)), rng.dirichlet(np.ones(2), 2), rng.dirichlet(np.ones(3), 2).T)
    symbols = np.array([0, 2, 1, 1, 0])
    start, trans, emit, likelihood = lm.expected_counts(m, symbols, np.array([5]))
    total, s, t, e = 0.0, np.zeros(2), np.zeros((2, 2)), np.zeros((3, 2))
    for path in itertools.product(range(2), repeat=5):
        p = m.start[path[0]] * m.emit[symbols[0], path[0]]
        for i in range(1, 5):
            p *= m.step[path[i - 1], path[i]] * m.emit[symbols[i], path[i]]
        total += p
        s[path[0]] += p
        for i in range(5):
            e[symbols[i], path[i]] += p
            if i:
                t[path[i - 1], path[i]] += p
    assert np.allclose(start, s / total) and np.allclose(trans, t / total) and np.allclose(emit, e / total) and abs(likelihood - math.log(total)) < 1e-9


def test_training_raises_likelihood(docs, spark):
    texts = docs.select(F.col("doc_id").alias("id"), "text", lm.trains("doc_id").alias("trains"))
    counts = lm.word_counts(texts.filter("trains")).checkpoint()
    vocabulary = lm.build_vocabulary(counts, texts.filter("trains").count())
    _, history = lm.baum_welch(lm._encode(texts, vocabulary).checkpoint(), vocabulary.classes, passes=4)
    assert len(history) == 4 and history[-1] > history[1] > history[0]


def test_scores_equal_brute_force(docs, texts):
    low = {i: i + 32 for i in range(65, 91)}
    tokens = {d: [*re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(low)), 0] for d, t in texts.items()}
    held = {d: zlib.crc32(str(d).encode()) % 10 == 0 for d in texts}
    c = Counter(w for d, ws in tokens.items() if not held[d] for w in ws)
    n, v = sum(c.values()), len(c)
    better = 0
    for r in lm.score_documents(docs).collect():
        ws = tokens[r["doc_id"]]
        base = sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws)
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[r["doc_id"]], len(ws), sum(c[w] > 0 for w in ws), n)
        assert abs(r["base_score"] - base) < 1e-6 * abs(base) and r["score"] < 0
        better += r["held_out"] and r["score"] > r["base_score"]
    assert better > 0.8 * sum(held.values())


def test_class_probabilities_sum_to_one(docs):
    """Over all known words and one unseen word for each class."""
    texts = docs.limit(50).select(F.col("doc_id").alias("id"), "text", F.lit(True).alias("trains")).checkpoint()
    counts = lm.word_counts(texts).checkpoint()
    v = lm.build_vocabulary(counts, 50)
    rows = counts.toPandas()
    top = set(v.top.view(np.int64).tolist())
    mass = np.zeros(v.classes)
    for h, form, n in rows.itertuples(index=False):
        if h not in top:
            k = 1 + lm.TOP_WORDS + form
            mass[k] += (n + lm.DELTA) / (v.class_tokens[k] + lm.DELTA * (v.class_words[k] + 1))
    used = v.class_words > 0
    unseen = lm.DELTA / (v.class_tokens + lm.DELTA * (v.class_words + 1))
    assert np.allclose((mass + unseen)[used], 1)
    model = lm.starting_model(v.classes)
    assert np.allclose(model.emit.sum(0), 1) and np.allclose(model.step.sum(1), 1)


def test_language_model_of_odd_rows(odd, no_docs):
    rows = lm.score_documents(odd.checkpoint()).collect()
    assert len(rows) == odd.count() and all(np.isfinite(r["score"]) and np.isfinite(r["base_score"]) for r in rows)
    assert {r["n_tokens"] for r in rows if r["doc_id"] in (2, 3, 4)} == {1}
    assert lm.score_documents(no_docs).count() == 0
