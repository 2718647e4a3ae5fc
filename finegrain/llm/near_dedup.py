"""Near-duplicate detection: improved consistent weighted sampling over TF-IDF shingles and least hashes of plain ones, banded and verified.

1. Document counts of words, the lesser of two hashed slots in tables of fixed size, give word weights; a shingle of five words weighs
   its count in the text times the mean inverse document frequency of its words. (A table of the shingles themselves would be
   as large as the corpus.)
2. Texts with the same words are one node. Every text gets ``BANDS * ROWS`` consistent weighted samples, and as many least hashes of
   its plain shingle set; the samples of a band make one key. So both kinds of link (step 4) have bands that meet at their rate.
3. Nodes that share a band key are candidates. Small groups are compared whole. In a larger group every node is compared with the
   group's hub, the node with most company; that settles groups of copies in a multiple of their size. Where nodes are left
   apart, those outside the largest component are compared with all nodes of the group, block against block. So every pair
   of candidates that could join two classes is compared.
4. A pair is a link when the weighted Jaccard similarity of its shingles is 0.8 or more, or that of the plain shingle
   sets is (weights would otherwise hide copies with a rare word changed). Classes are the connected components.

Defined results: null counts as empty. Texts without words are alike when their bytes are; texts of one to four words are one
shingle. Null ids take part and never name a class unless all ids of it are null. Rows with equal ids and texts are in the
same class. An empty table gives an empty table.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.batches import in_batches
from finegrain.llm.filters import in_table, key_table, without_keys
from finegrain.llm.rows import column, packed, unpacked
from finegrain.llm.textkernel import blocks, mix, words_of
from finegrain.operators.components import connected_components
from finegrain.operators.skew import join_group_facts
from finegrain.sources.staging import staged

SHINGLE, SIMILARITY = 5, 0.8
BANDS, ROWS = 11, 4
#: log2 of the slots of each of the two tables of word counts and of the samples' random numbers. Weights are kept in eighths up to 32,
#: which the rarest word of 10^13 documents does not reach.
WORD_BITS, DRAW_BITS = 18, 14
#: Groups up to this size are compared whole, pair by pair; what hubs leave of larger ones, in blocks of about so many nodes.
SMALL_GROUP, BLOCK_NODES = 12, 64
#: Blocks outside the largest component that one task meets with its group, the most such shares, and the most groups that are broadcast.
SHARE_BLOCKS, MOST_SHARES, MOST_BROADCAST = 8, 64, 100_000
_HASH_BITS, _WEIGHT_BITS = 44, 8
_MOST_TEXTS = 1 << (64 - _HASH_BITS - _WEIGHT_BITS)
_STEP = np.uint64(0xA0761D6478BD642F)
_STEP2 = np.uint64(0xE7037ED1A0B428DB)


def text_blocks(column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Blocks of at most as many texts as a shingle's key has room for."""
    for row, data, offsets in blocks(column):
        for lo in range(0, len(offsets) - 1, _MOST_TEXTS):
            at = offsets[lo : lo + _MOST_TEXTS + 1]
            yield row + lo, data[at[0] : at[-1]], at - at[0]


def node_keys(words, offsets: np.ndarray) -> np.ndarray:
    """A 64-bit key of each text's sequence of words; of the bytes where it has none."""
    n = len(offsets) - 1
    h = words.hashes
    with np.errstate(over="ignore"):
        rank = np.arange(len(h), dtype=np.uint64) - np.repeat(words.first[:-1], words.counts).astype(np.uint64)
        terms = mix(h + mix(rank + np.uint64(11)))
        running = np.concatenate([np.zeros(1, np.uint64), np.cumsum(terms, dtype=np.uint64)])
        keys = mix(running[words.first[1:]] - running[words.first[:-1]] + words.counts.astype(np.uint64))
    for i in np.flatnonzero(words.counts == 0):
        raw = words.data[offsets[i] : offsets[i + 1]].tobytes()
        keys[i] = zlib.crc32(raw) + (len(raw) << 32)
    return keys if n else np.zeros(0, np.uint64)


def _slots(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The slots of words in either table, the second table's after the first's."""
    low = np.uint64((1 << WORD_BITS) - 1)
    return (h & low).astype(np.int64), ((h >> np.uint64(WORD_BITS)) & low).astype(np.int64) + (1 << WORD_BITS)


def word_document_counts(docs: DataFrame, text: str = "text") -> np.ndarray:
    """Documents that hold a word of each slot, over all documents; the last entry is the number of documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2 << WORD_BITS) + 1, np.int64)
        for batch in batches:
            for _, data, offsets in text_blocks(batch.column(0)):
                w = words_of(data, offsets)
                # each word once a text: sorted by text, then by the bits that its slots are made of
                bits = np.uint64(2 * WORD_BITS)
                key = (w.text_of_words().astype(np.uint64) << bits) | (w.hashes & ((np.uint64(1) << bits) - np.uint64(1)))
                key.sort()
                new = np.ones(len(key), bool)
                new[1:] = key[1:] != key[:-1]
                for slots in _slots(key[new]):
                    total += np.bincount(slots, minlength=len(total))
                total[-1] += len(offsets) - 1
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["slot", "n"])

    # a fixed number of slots, whatever the corpus
    summed = docs.select(column(text).alias("text")).transform(in_batches, run, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    counts = np.zeros((2 << WORD_BITS) + 1, np.int64)
    counts[summed["slot"].to_numpy()] = summed["n"].to_numpy()
    return counts


def word_weights(counts: np.ndarray) -> np.ndarray:
    """Smoothed inverse document frequency of each slot, 1 at least; a word has the greater of its two slots'."""
    return (1 + np.log((counts[-1] + 1) / (counts[:-1] + 1.0)).clip(0)).astype(np.float32)


def shingles(words, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct shingles of a block: text, hash (44 bits), weight with the count in the text; in order of text and hash."""
    h, first, counts = words.hashes, words.first, words.counts
    n = len(h)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.float32)
    idf = np.maximum(*(weights[slots] for slots in _slots(h)))
    of = words.text_of_words()
    short = counts < SHINGLE
    m = max(0, n - SHINGLE + 1)
    with np.errstate(over="ignore"):
        total = h[:m].copy()
        for k in range(1, SHINGLE):
            total = total * _STEP + h[k : m + k]
        total = mix(total)
    inside = of[:m] == of[SHINGLE - 1 :] if m else np.zeros(0, bool)
    sums = np.concatenate([[0.0], np.cumsum(idf, dtype=np.float64)])
    mean = (sums[SHINGLE:] - sums[:-SHINGLE]) / SHINGLE if m else np.zeros(0)
    text, hashes, mean = of[:m][inside], total[inside], mean[inside]
    if (few := np.flatnonzero(short & (counts > 0))).size:
        with np.errstate(over="ignore"):
            whole = np.array([mix(np.array([np.sum(h[first[i] : first[i + 1]] * (_STEP2 ** np.arange(counts[i], dtype=np.uint64)), dtype=np.uint64)]))[0] for i in few], np.uint64)
        text = np.concatenate([text, few])
        hashes = np.concatenate([hashes, whole])
        mean = np.concatenate([mean, [(sums[first[i + 1]] - sums[first[i]]) / counts[i] for i in few]])
    level = np.clip(np.rint(mean * 8), 1, (1 << _WEIGHT_BITS) - 1).astype(np.uint64)
    key = (text.astype(np.uint64) << np.uint64(_HASH_BITS + _WEIGHT_BITS)) | ((hashes >> np.uint64(64 - _HASH_BITS)) << np.uint64(_WEIGHT_BITS)) | level
    key.sort()
    at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    count = np.diff(np.append(at, len(key)))
    key = key[at]
    weight = (key & np.uint64((1 << _WEIGHT_BITS) - 1)).astype(np.float32) / 8 * count
    return (key >> np.uint64(_HASH_BITS + _WEIGHT_BITS)).astype(np.int64), (key >> np.uint64(_WEIGHT_BITS)) & np.uint64((1 << _HASH_BITS) - 1), weight.astype(np.float32)


@lru_cache(maxsize=1)
def _draws(samples: int, seed: int = 3) -> tuple[np.ndarray, ...]:
    """Random numbers of the samples by hashed shingle: r, log c, beta and the multipliers of the hashes."""
    rng = np.random.default_rng(seed)
    shape = (samples, 1 << DRAW_BITS)
    r = rng.gamma(2, 1, shape).astype(np.float32) + np.float32(1e-6)
    log_c = np.log(rng.gamma(2, 1, shape)).astype(np.float32)
    beta = rng.random(shape, dtype=np.float32)
    return r, log_c, beta, rng.integers(0, 2**63, samples, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def band_keys(text: np.ndarray, hashes: np.ndarray, weight: np.ndarray, texts: int) -> tuple[np.ndarray, np.ndarray]:
    """Band keys of every text (texts x bands) and which texts have shingles."""
    r, log_c, beta, factor = _draws(BANDS * ROWS)
    starts = np.flatnonzero(np.concatenate([[True], text[1:] != text[:-1]])) if len(text) else np.zeros(0, np.int64)
    filled = text[starts]
    counts = np.diff(np.append(starts, len(text)))
    log_w = np.log(weight)
    slot_of = np.repeat(np.arange(len(starts)), counts)
    keys = np.zeros((texts, BANDS), np.uint64)
    with np.errstate(over="ignore"):
        wide = hashes << np.uint64(64 - _HASH_BITS)
        for band in range(BANDS):
            total = np.full(len(starts), band + 1, np.uint64)
            for k in range(band * ROWS, (band + 1) * ROWS):
                g = (wide * factor[k]) >> np.uint64(64 - DRAW_BITS)
                rk = r[k][g]
                t = np.floor(log_w / rk + beta[k][g])
                a = log_c[k][g] - rk * (t - beta[k][g] + np.float32(1))
                least = np.minimum.reduceat(a, starts) if len(starts) else a
                at = np.flatnonzero(a == least[slot_of])
                of = slot_of[at]
                at = at[np.concatenate([[True], of[1:] != of[:-1]])] if len(at) else at
                total = mix(total * _STEP + hashes[at] + (t[at].astype(np.int64).view(np.uint64) << np.uint64(48)))
            keys[filled, band] = total
    has = np.zeros(texts, bool)
    has[filled] = True
    return keys, has


def plain_band_keys(text: np.ndarray, hashes: np.ndarray, texts: int) -> np.ndarray:
    """Band keys of every text's shingle set without weights (texts x bands): each sample is the shingles' least hash."""
    factor = np.random.default_rng(5).integers(0, 2**63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    starts = np.flatnonzero(np.concatenate([[True], text[1:] != text[:-1]])) if len(text) else np.zeros(0, np.int64)
    keys = np.zeros((texts, BANDS), np.uint64)
    if not len(starts):
        return keys
    with np.errstate(over="ignore"):
        wide = mix(hashes)
        for band in range(BANDS):
            total = np.full(len(starts), band + 1, np.uint64)
            for k in range(band * ROWS, (band + 1) * ROWS):
                total = mix(total * _STEP + np.minimum.reduceat(wide * factor[k], starts))
            keys[text[starts], band] = total
    return keys


def sketches(docs: DataFrame, weights: np.ndarray, id_col: str, text: str) -> DataFrame:
    """Every row's id, key of id and text, node and band keys, weighted ones then plain ones (null where a text has no words)."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    names = [f"b{k}" for k in range(2 * BANDS)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, data, offsets in text_blocks(batch.column(2)):
                n = len(offsets) - 1
                w = words_of(data, offsets)
                of, hashes, weight = shingles(w, shared.value)
                keys, has = band_keys(of, hashes, weight, n)
                keys = np.hstack([keys, plain_band_keys(of, hashes, n)])
                bands = [pa.array(np.ascontiguousarray(keys[:, k]).view(np.int64), mask=~has) for k in range(2 * BANDS)]
                part = batch.slice(row, n)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(node_keys(w, offsets).view(np.int64)), *bands], names=["id", "key", "node", *names])

    rows = docs.select(column(id_col).cast("long").alias("id"), row_key(id_col, text).alias("key"), column(text).alias("text"))
    return rows.transform(in_batches, run, "id long, key long, node long, " + ", ".join(f"{b} long" for b in names))


def row_key(id_col: str, text: str):
    """A 64-bit key of a row's id and text: rows that agree in both share their decision."""
    return F.xxhash64(column(id_col), F.coalesce(column(text), F.lit("")))


def candidate_shingles(docs: DataFrame, chosen: DataFrame, weights: np.ndarray, id_col: str, text: str) -> DataFrame:
    """``(node, hashes, weights)`` of the nodes in ``chosen`` (a table: id of one text of the node, node), packed as binary.

    The texts are read where they lie; a bit table made of ``chosen`` lets few others through.
    """
    spark = docs.sparkSession
    mark = F.col("node").bitwiseXOR(F.shiftleft(F.coalesce("id", F.lit(0)), 4))
    table = spark.sparkContext.broadcast(key_table(chosen.select(mark.alias("k")), "k"))
    shared = spark.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).fill_null(0).to_numpy()
            for row, data, offsets in text_blocks(batch.column(1)):
                n = len(offsets) - 1
                words = words_of(data, offsets)
                nodes = node_keys(words, offsets).view(np.int64)
                hit = np.flatnonzero(in_table(table.value, nodes ^ (ids[row : row + n] << 4)))
                if not len(hit):
                    continue
                of, h, w = shingles(words, shared.value)
                lo, hi = np.searchsorted(of, hit).tolist(), np.searchsorted(of, hit, "right").tolist()
                small, light = (h >> np.uint64(_HASH_BITS - 32)).astype("<u4"), w.astype("<f4")
                packed = [small[a:b].tobytes() for a, b in zip(lo, hi, strict=True)]
                masses = [light[a:b].tobytes() for a, b in zip(lo, hi, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(nodes[hit]), pa.array(packed, pa.binary()), pa.array(masses, pa.binary())], names=["node", "hashes", "weights"])

    rows = docs.select(column(id_col).cast("long").alias("id"), column(text).alias("text"))
    found = rows.transform(in_batches, run, "node long, hashes binary, weights binary")
    return found.join(chosen.select("node"), "node", "left_semi").dropDuplicates(["node"])


def similarity(ha: np.ndarray, wa: np.ndarray, hb: np.ndarray, wb: np.ndarray) -> tuple[float, float]:
    """Weighted and plain Jaccard similarity of two lists of distinct shingles in ascending order."""
    if not len(ha) or not len(hb):
        return 0.0, 0.0
    at = np.minimum(np.searchsorted(hb, ha), len(hb) - 1)
    same = hb[at] == ha
    both = float(np.minimum(wa[same], wb[at[same]]).sum(dtype=np.float64))
    n = int(same.sum())
    return both / (float(wa.sum(dtype=np.float64)) + float(wb.sum(dtype=np.float64)) - both), n / (len(ha) + len(hb) - n)


def verified(pairs: DataFrame, lists: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """The links among ``pairs`` (a, b) of nodes; both are tables. A node of very many pairs, a hub, goes out to many tasks."""
    total, joined = pairs.count(), pairs
    for side, other in (("a", "b"), ("b", "a")):
        own = lists.select(F.col("node").alias(side), F.col("hashes").alias(f"h{side}"), F.col("weights").alias(f"w{side}"))
        met = own.join(pairs.groupBy(side).agg(F.count("*").alias("n")), side)
        joined = join_group_facts(joined, met, side, "n", total, other, "inner").drop("n")
    joined = joined.select("a", "b", "ha", "wa", "hb", "wb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        view = lambda x, kind: np.frombuffer(x.as_buffer(), kind)
        for batch in batches:
            near = []
            for ha, wa, hb, wb in zip(*(batch.column(k) for k in range(2, 6)), strict=True):
                x, y = similarity(view(ha, "<u4"), view(wa, "<f4"), view(hb, "<u4"), view(wb, "<f4"))
                near.append(max(x, y))
            keep = np.array(near) >= least - 1e-9
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(keep)), batch.column(1).filter(pa.array(keep)), pa.array(np.array(near)[keep], pa.float64())], names=["a", "b", "similarity"])

    return joined.transform(in_batches, run, "a long, b long, similarity double")


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.filter("x != y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def near_classes(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Staged ``(id, key, component)`` of every row of ``docs`` (a scan: it is read three times)."""
    weights = word_weights(word_document_counts(docs, text))
    rows = staged(sketches(docs, weights, id_col, text), "sketches")
    names = [f"b{k}" for k in range(2 * BANDS)]
    nodes = rows.groupBy("node").agg(F.min("id").alias("id"), *(F.first(b).alias(b) for b in names))
    banded = nodes.select("node", "id", F.posexplode(F.array(*names)).alias("band", "value")).filter("value is not null")
    banded = banded.select("node", "id", F.xxhash64("band", "value").alias("group"))
    banded = staged(banded, "bands")
    groups = staged(banded.groupBy("group").agg(F.count("*").alias("size")).filter("size > 1"), "groups")
    # narrow rows, most of which meet no group: a skewed key is left to the adaptive join
    members = staged(banded.join(groups, "group"), "members")
    chosen = staged(members.select("id", "node").distinct(), "candidates")
    lists = staged(candidate_shingles(docs, chosen, weights, id_col, text), "shingles")
    component = _linked(members, lists)
    return staged(rows.select("id", "key", "node").join(component, "node", "left").select("id", "key", F.coalesce("component", "node").alias("component")), "classes")


def _linked(members: DataFrame, lists: DataFrame) -> DataFrame:
    """``(node, component)`` of the nodes that a verified link joins to another."""
    # small groups: at most SMALL_GROUP * (SMALL_GROUP - 1) / 2 pairs each
    small = members.filter(F.col("size") <= SMALL_GROUP).groupBy("group").agg(F.array_sort(F.collect_list("node")).alias("all"))
    both = F.flatten(F.transform("all", lambda x, i: F.transform(F.slice(F.col("all"), i + 2, SMALL_GROUP), lambda y: F.struct(x.alias("x"), y.alias("y")))))
    pairs = small.select(F.explode(both).alias("p")).select("p.x", "p.y")
    # large groups: every node meets its group's hub, the node that shares its groups with most others
    large = members.filter(F.col("size") > SMALL_GROUP).select("group", "node", "size")
    total = members.count()
    shared = large.groupBy("node").agg(F.sum("size").alias("shared"))
    hubs = large.join(shared, "node").groupBy("group").agg(F.max(F.struct("shared", "node")).alias("hub"), F.max("size").alias("size"))
    hubs = staged(hubs.select("group", F.col("hub.node").alias("y"), "size"), "hubs")
    met = join_group_facts(large.select("group", F.col("node").alias("x")), hubs, "group", "size", total, "x", "inner").select("x", "y")
    links = staged(verified(staged(_ordered(pairs.unionByName(met)), "pairs"), lists).select("a", "b"), "links")
    state = connected_components(links)
    joined = large.join(state, "node", "left").withColumn("component", F.coalesce("component", "node"))
    apart = joined.groupBy("group").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.max("size").alias("rows")).filter("lo != hi").select("group", "rows")
    still = staged(join_group_facts(joined, staged(apart, "open-groups"), "group", "rows", total, "node", "inner").drop("rows"), "open-members")
    if not still.limit(1).count():
        return state
    rest = staged(_block_links(still, lists), "links")
    return connected_components(links.unionByName(rest))


def _block_links(open_members: DataFrame, lists: DataFrame) -> DataFrame:
    """Links between the components of groups that the hubs have left apart.

    A group's nodes outside its largest component are compared with all its nodes, block against block: a row is a pair of
    blocks, whose similarities are one product of matrices, and only links that join components come out. Shares of a
    group, not groups, are what is dealt out to tasks.
    """
    total = open_members.count()
    sizes = open_members.groupBy("group", "component").agg(F.count("*").alias("n"))
    largest = sizes.groupBy("group").agg(F.max(F.struct("n", "component")).alias("top"), F.sum("n").alias("rows")).select("group", F.col("top.component").alias("main"), "rows")
    sided = join_group_facts(open_members, staged(largest, "main-components"), "group", "rows", total, "node", "inner").drop("rows").withColumn("inner", F.col("component") == F.col("main"))
    counts = sided.groupBy("group", "inner").agg(F.count("*").alias("side")).withColumn("blocks", F.ceil(F.col("side") / F.lit(BLOCK_NODES)))
    keyed = lambda df: df.withColumn("sided", F.xxhash64("group", "inner"))
    facts = staged(keyed(counts).select("sided", "side", "blocks"), "block-counts")
    placed = join_group_facts(keyed(sided), facts, "sided", "side", total, "node", "inner").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")))
    filled = placed.select("group", "inner", "block", "node", "component").join(lists, "node")
    blocks_of = staged(filled.groupBy("group", "inner", "block").agg(F.collect_list(F.struct("node", "component", "hashes", "weights")).alias("nodes")), "blocks")
    # every block outside meets all blocks inside and those outside from its own on; the blocks outside are dealt out in shares of
    # SHARE_BLOCKS or more, and only as many times do the group's blocks go out again
    shares = counts.filter("not inner").select("group", F.least(F.lit(MOST_SHARES), F.ceil(F.col("blocks") / F.lit(SHARE_BLOCKS))).alias("shares"))
    dealt = blocks_of.join(F.broadcast(shares) if shares.count() <= MOST_BROADCAST else shares, "group")
    left = dealt.filter("not inner").select("group", F.pmod("block", F.col("shares")).alias("share"), F.col("block").alias("i"), F.col("nodes").alias("a"))
    right = dealt.select("group", F.explode(F.sequence(F.lit(0).cast("long"), F.col("shares") - 1)).alias("share"), "inner", F.col("block").alias("j"), F.col("nodes").alias("b"))
    met = left.join(right, ["group", "share"]).filter("inner or i <= j").select("a", "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in zip(batch.column(0), batch.column(1), strict=True):
                x, y = block_links(_unpacked(a.values), _unpacked(b.values))
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64())], names=["a", "b"])

    found = met.transform(in_batches, run, "a long, b long")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _unpacked(nodes: pa.StructArray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray], list[np.ndarray]]:
    view = lambda field, kind: [np.frombuffer(x.as_buffer(), kind) for x in nodes.field(field)]
    return nodes.field("node").to_numpy(), nodes.field("component").to_numpy(), view("hashes", "<u4"), view("weights", "<f4")


def block_similarities(ha: list, wa: list, hb: list, wb: list, columns: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """Weighted and plain Jaccard similarity of all texts of one block with all of another.

    The mass that two texts share at a shingle is the lesser of their weights: a shingle with several weights is split into
    levels, a text holds the levels up to its weight, and the shared mass is a product of indicator matrices.
    """
    both = np.intersect1d(np.unique(np.concatenate(ha)), np.unique(np.concatenate(hb)))
    h, w = np.concatenate([*ha, *hb]), np.concatenate([*wa, *wb])
    text = np.repeat(np.arange(len(ha) + len(hb)), [len(x) for x in (*ha, *hb)])
    at = np.minimum(np.searchsorted(both, h), max(0, len(both) - 1))
    keep = both[at] == h if len(both) else np.zeros(len(h), bool)
    col, w, text = at[keep], w[keep].astype(np.float64), text[keep]
    order = np.lexsort((w, col))
    col, w, text = col[order], w[order], text[order]
    fresh = np.concatenate([[True], (col[1:] != col[:-1]) | (w[1:] != w[:-1])]) if len(col) else np.zeros(0, bool)
    level = np.cumsum(fresh) - 1
    level_col, level_w = col[fresh], w[fresh]
    opens = np.concatenate([[True], level_col[1:] != level_col[:-1]]) if len(level_col) else np.zeros(0, bool)
    mass = level_w - np.where(opens, 0.0, np.concatenate([[0.0], level_w[:-1]])) if len(level_w) else level_w
    first_level = np.flatnonzero(opens)[np.cumsum(opens) - 1] if len(opens) else np.zeros(0, np.int64)
    span = level - first_level[level] + 1 if len(level) else level
    items = np.repeat(first_level[level] if len(level) else level, span) + (np.arange(int(span.sum())) - np.repeat(np.cumsum(span) - span, span))
    owner = np.repeat(text, span)
    shared, common = np.zeros((len(ha), len(hb))), np.zeros((len(ha), len(hb)))
    order = np.argsort(items, kind="stable")
    items, owner = items[order], owner[order]
    for lo in range(0, len(mass), columns):
        a, b = np.searchsorted(items, [lo, lo + columns])
        m = np.zeros((len(ha) + len(hb), min(columns, len(mass) - lo)))
        m[owner[a:b], items[a:b] - lo] = 1
        part = slice(lo, lo + m.shape[1])
        shared += (m[: len(ha)] * mass[part]) @ m[len(ha) :].T
        common += (m[: len(ha)] * opens[part]) @ m[len(ha) :].T
    total = lambda ws: np.array([x.sum(dtype=np.float64) for x in ws])
    number = lambda hs: np.array([len(x) for x in hs], dtype=np.float64)
    weighted = shared / np.maximum(total(wa)[:, None] + total(wb)[None, :] - shared, 1e-12)
    return weighted, common / np.maximum(number(ha)[:, None] + number(hb)[None, :] - common, 1e-12)


def block_links(a: tuple, b: tuple, least: float = SIMILARITY) -> tuple[list[int], list[int]]:
    """Pairs of nodes of two blocks that are similar and whose components nothing found before here joins."""
    near = np.maximum(*block_similarities(a[2], a[3], b[2], b[3])) >= least - 1e-9
    near &= a[1][:, None] != b[1][None, :]
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    out: tuple[list[int], list[int]] = ([], [])
    for i, j in zip(*np.nonzero(near), strict=True):
        x, y = root(int(a[1][i])), root(int(b[1][j]))
        if x != y:
            parent[x] = y
            out[0].append(int(a[0][i]))
            out[1].append(int(b[0][j]))
    return out


def marked_rows(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``(id, key, class_id, class_size, kept)`` of every row: kept is the row with the least id, then key, of its class."""
    rows = near_classes(docs, id_col, text)
    first = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "key"))
    facts = staged(rows.groupBy("component").agg(first.alias("first"), F.count("*").alias("class_size")).filter("class_size > 1"), "class-facts")
    joined = join_group_facts(rows, facts, "component", "class_size", rows.count(), "key")
    alone = F.col("class_size").isNull()
    return joined.select(
        "id",
        "key",
        F.when(alone, F.col("id")).otherwise(F.col("first.id")).alias("class_id"),
        F.coalesce("class_size", F.lit(1)).cast("long").alias("class_size"),
        (alone | (F.col("id").eqNullSafe(F.col("first.id")) & (F.col("key") == F.col("first.key")))).alias("kept"),
    )


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each row of ``docs``: ``class_id`` (least id of its class), ``class_size`` (rows) and ``kept``."""
    return marked_rows(docs, id_col, text).select(F.col("id").alias(id_col), "class_id", "class_size", "kept")


def without_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with one document of each class; rows that cannot be among the dropped ones do not shuffle."""
    dropped = staged(marked_rows(docs, id_col, text).filter("not kept").select("key", "id").distinct(), "dropped")
    keyed = packed(docs, key=row_key(id_col, text), id=column(id_col).cast("long"))
    return unpacked(without_keys(keyed, dropped, "key", "id"), docs.columns)
