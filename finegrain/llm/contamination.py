"""Benchmark decontamination by template canonicalisation.

Words are lower-cased; numbers (with their separators) and units become typed placeholders, and in a second form so do
capitalised words as names. Windows of canonical words are hashed; a document's window and a benchmark's window that agree are
joined by hash, matches are lined up by relative position, and a value in the item's placeholders must map to one value of the
document: windows that say otherwise are not counted. So a question with other numbers or names in it is found, and a text that
only shares a template's shape is not.

Document windows pass a bit table of fixed size made of the benchmark's windows before they leave their task.

Windows of placeholders mostly say too little and are left out. An item that they leave without enough windows (dense numbers,
or fewer than ``SHORTEST`` words) is searched by windows of its own words, values included, so that its copies are found.

Defined results: null counts as empty; an item without words is not searched; an item shorter than a window is one window. A document is reported once for each item. Rows with the same id are judged each on its own text.
An empty benchmark leaves every document clean.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.batches import in_batches
from finegrain.llm.filters import in_table, key_table, without_keys
from finegrain.llm.rows import column, packed, unpacked
from finegrain.llm.textkernel import blocks, hash_word, mix, words_of
from finegrain.sources.staging import staged

WINDOW, SHORTEST = 8, 5
#: Windows that must agree at one relative position: this share of the item's, five at least, or all that are searched.
SHARE, LEAST = 0.3, 5
#: Benchmark windows up to this number are broadcast; beyond it the join shuffles, each window's documents over ``SALTS`` tasks.
MOST_BROADCAST, SALTS = 200_000, 16
PLAIN, NAMED, RAW = 0, 1, 2

# Units.
UNITS = (
    "mm", "cm", "m", "km", "inch", "inches", "foot", "feet", "yard", "yards", "mile", "miles", "mg", "g", "kg", "gram", "grams",
    "kilogram", "kilograms", "ton", "tons", "ml", "l", "liter", "liters", "litre", "litres", "gallon", "gallons", "s", "sec", "second",
    "seconds", "min", "minute", "minutes", "h", "hour", "hours", "day", "days", "week", "weeks", "month", "months", "year", "years",
    "dollar", "dollars", "cent", "cents", "euro", "euros", "percent", "degree", "degrees", "meter", "meters", "metre", "metres",
)
_UNIT_HASHES = np.sort(np.array([hash_word(u) for u in UNITS], dtype=np.uint64))
_NUMBER, _UNIT, _NAME = (np.uint64(hash_word(f"<{k}>")) for k in ("number", "unit", "name"))
_STEP = np.uint64(0xC2B2AE3D27D4EB4F)


def _among(sorted_values: np.ndarray, x: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(sorted_values, x), len(sorted_values) - 1)
    return sorted_values[at] == x


class Canonical:
    """Canonical words of a block of texts in one form."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        w = words_of(data, offsets)
        first = data[w.starts] if len(w.starts) else np.zeros(0, np.uint8)
        number = (first >= 48) & (first <= 57)
        if len(number) > 1:
            # "1,200.5" is one number: a number right after one separator belongs to the number before
            gap = (w.starts[1:] - w.ends[:-1] == 1) & np.isin(data[np.minimum(w.ends[:-1], len(data) - 1)], (44, 46))
            inner = np.concatenate([[False], number[1:] & number[:-1] & gap])
            inner[w.first[:-1][w.first[:-1] < len(inner)]] = False
        else:
            inner = np.zeros(len(number), bool)
        keep = ~inner
        self.text = w.text_of_words()[keep]
        self.starts, ends = w.starts[keep], w.ends.copy()
        groups = np.cumsum(keep) - 1
        self.ends = np.zeros(int(keep.sum()), np.int64)
        np.maximum.at(self.ends, groups, ends)
        self.raw, h, self.number = data, w.hashes[keep], number[keep]
        if inner.any():  # the value of a number is that of all its parts in order, whatever separates them
            part = np.flatnonzero(inner)
            rank = (part - np.flatnonzero(keep)[groups[part]]).astype(np.uint64)
            with np.errstate(over="ignore"):
                np.add.at(h, groups[part], mix(w.hashes[part] + rank * _STEP))
        self.unit = _among(_UNIT_HASHES, h) if len(h) else np.zeros(0, bool)
        second = data[np.minimum(self.starts + 1, max(len(data) - 1, 0))] if len(h) else np.zeros(0, np.uint8)
        c = data[self.starts] if len(h) else np.zeros(0, np.uint8)
        accent = (c == 0xC3) & (second >= 0x80) & (second <= 0x9E)
        self.name = ((c >= 65) & (c <= 90)) | accent
        plain = np.where(self.number, _NUMBER, np.where(self.unit, _UNIT, h))
        self.forms = (plain, np.where(self.name & ~self.number & ~self.unit, _NAME, plain))
        self.first = np.searchsorted(self.text, np.arange(len(offsets)))
        self.hashes = h
        self.forms += (h,)

    def slots(self, form: int) -> np.ndarray:
        """Which words are placeholders."""
        if form == RAW:
            return np.zeros(len(self.number), bool)
        out = self.number | self.unit
        return out | self.name if form == NAMED else out

    def windows(self, form: int, length: int) -> tuple[np.ndarray, np.ndarray]:
        """First word and hash of every window of ``length`` words inside one text; windows of placeholders mostly are left out."""
        c = self.forms[form]
        n = len(c) - length + 1
        if n <= 0:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        with np.errstate(over="ignore"):
            total = c[:n].copy()
            for k in range(1, length):
                total = total * _STEP + c[k : n + k]
            total = mix(total + np.uint64(form * 1000 + length))
        ok = self.text[:n] == self.text[length - 1 :]
        fixed = np.concatenate([[0], np.cumsum(~self.slots(form))])
        ok &= fixed[length:] - fixed[:-length] >= min(4, length)  # all windows of the raw form
        if form == NAMED:  # without a name in it the plain form has the same window
            named = np.concatenate([[0], np.cumsum(self.name & ~self.number & ~self.unit)])
            ok &= named[length:] - named[:-length] > 0
        at = np.flatnonzero(ok)
        return at, total[at]

    def values(self, form: int, at: np.ndarray, length: int) -> list[list[int]]:
        """Values in the placeholders of the windows: the words' hashes, 0 where a word is none."""
        marks = self.slots(form)
        wide = at[:, None] + np.arange(length)
        return np.where(marks[wide], (self.hashes[wide] | np.uint64(1)).view(np.int64), 0).tolist()


def item_windows(benchmark: DataFrame, item_col: str = "item_id", text: str = "text") -> DataFrame:
    """Windows of all items: item, form, length, hash, position, how many are searched and must agree, values of the placeholders."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, data, offsets in blocks(batch.column(1)):
                c = Canonical(data, offsets)
                sizes = np.diff(c.first)
                length_of = np.minimum(sizes, WINDOW)
                total = sizes - length_of + 1
                least = np.minimum(total, np.maximum(LEAST, np.ceil(total * SHARE).astype(np.int64)))
                found = {}
                for form in (PLAIN, NAMED, RAW):
                    for length in range(1 if form == RAW else SHORTEST, WINDOW + 1):
                        at, h = c.windows(form, length)
                        fits = length_of[c.text[at]] == length
                        found[form, length] = at[fits], h[fits]
                plain = np.concatenate([c.text[at] for (form, _), (at, _) in found.items() if form == PLAIN])
                searched = np.bincount(plain, minlength=len(sizes))
                template = (searched >= least) | (searched * 2 >= total)
                searched = np.where(template, searched, total)
                for (form, length), (at, h) in found.items():
                    fits = template[c.text[at]] == (form != RAW)
                    at, h = at[fits], h[fits]
                    of = c.text[at]
                    if not len(at):
                        continue
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).slice(row, len(sizes)).take(pa.array(of)), pa.array(np.full(len(at), length, np.int32)), pa.array(np.full(len(at), form, np.int32)), pa.array(h.view(np.int64)), pa.array(mix(h).view(np.int64)), pa.array(at - c.first[of]), pa.array(searched[of]), pa.array(np.minimum(searched, least)[of]), pa.array(c.values(form, at, length), pa.list_(pa.int64()))],
                        names=["item", "length", "form", "hash", "second", "item_at", "item_windows", "needed", "item_values"],
                    )

    id_type = benchmark.schema[item_col].dataType.simpleString()
    rows = benchmark.select(F.col(item_col).alias("item"), F.col(text).alias("text"))
    return rows.transform(in_batches, run, f"item {id_type}, length int, form int, hash long, second long, item_at long, item_windows long, needed long, item_values array<long>")


def _document_windows(docs: DataFrame, table: np.ndarray, kinds: list[tuple[int, int]]) -> DataFrame:
    """Windows of the documents that may be an item's: ``kinds`` are the items' forms and lengths."""
    shared = docs.sparkSession.sparkContext.broadcast(table)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, data, offsets in blocks(batch.column(1)):
                c = Canonical(data, offsets)
                keys = batch.column(0).slice(row, len(offsets) - 1)
                for form, length in kinds:
                    at, h = c.windows(form, length)
                    hit = in_table(shared.value, h)
                    hit[hit] = in_table(shared.value, mix(h[hit]))
                    at, h = at[hit], h[hit]
                    if form == RAW and length < WINDOW and len(at):  # the whole item: once in a text says all
                        order = np.lexsort((at, h, c.text[at]))
                        at, h = at[order], h[order]
                        new = np.concatenate([[True], (h[1:] != h[:-1]) | (c.text[at[1:]] != c.text[at[:-1]])])
                        at, h = at[new], h[new]
                    if len(at):
                        of = c.text[at]
                        yield pa.RecordBatch.from_arrays(
                            [keys.take(pa.array(of)), pa.array(h.view(np.int64)), pa.array(at - c.first[of]), pa.array(c.values(form, at, length), pa.list_(pa.int64()))], names=["key", "hash", "at", "values"]
                        )

    return docs.transform(in_batches, run, "key long, hash long, at long, values array<long>")


def agreeing(found: list[tuple[int, list[tuple[int, int, int]]]]) -> tuple[int, bool]:
    """How many of an item's windows ``(place, [(place of the word, item's value, document's value)])`` agree, and whether all values are the same.

    A value of the item stands for the document's value at all or most of its places, or for itself where no other has most. Windows
    that differ from that are left out; windows with the item's own values count by themselves too.
    """
    at_places: dict[int, Counter] = defaultdict(Counter)
    for _, i, d in {p for _, pairs in found for p in pairs}:
        at_places[i][d] += 1
    means = {}
    for i, seen in at_places.items():
        d, n = seen.most_common(1)[0]
        means[i] = d if 2 * n > seen.total() else i
    fit = {at for at, pairs in found if all(means[i] == d for _, i, d in pairs)}
    same = {at for at, pairs in found if all(i == d for _, i, d in pairs)}
    return max(len(fit), len(same)), all(set(seen) == {i} for i, seen in at_places.items())


def matches(docs: DataFrame, benchmark: DataFrame, item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """``(key, item, windows, item_windows, exact)`` of all documents ``(key, text)`` that hold an item; ``key`` is a 64-bit row key."""
    items = staged(item_windows(benchmark, item_col, item_text), "benchmark-windows")
    table = key_table(items.select("hash").unionByName(items.select(F.col("second").alias("hash"))), "hash")
    kinds = sorted((r["form"], r["length"]) for r in items.select("form", "length").distinct().collect())  # 2 * WINDOW different ones at most
    found = _document_windows(docs.select("key", "text"), table, kinds)
    if items.count() <= MOST_BROADCAST:
        joined = found.join(F.broadcast(items), "hash")
    else:
        salted = found.withColumn("salt", F.pmod(F.xxhash64("key", "at"), F.lit(SALTS)).cast("int"))
        joined = salted.join(items.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["hash", "salt"]).drop("salt")
    joined = joined.withColumn("offset", F.col("at") - F.col("item_at"))
    zipped = F.transform(F.arrays_zip(F.col("item_values").alias("i"), F.col("values").alias("d")), lambda p, k: F.struct((F.col("item_at") + k).alias("at"), p["i"].alias("i"), p["d"].alias("d")))
    # one item at one place of one document, both forms together: at most two rows for each of the item's windows
    lined = joined.withColumn("pairs", F.filter(zipped, lambda p: p["i"] != 0)).groupBy("key", "item", "offset").agg(
        F.count_distinct("item_at").alias("met"), F.max("item_windows").alias("item_windows"), F.max("needed").alias("needed"), F.collect_set(F.struct("item_at", "pairs")).alias("found")
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            judged = [agreeing([(w["item_at"], [(p["at"], p["i"], p["d"]) for p in w["pairs"]]) for w in found.as_py()]) for found in batch.column(4)]
            keep = pa.array([n >= least for (n, _), least in zip(judged, batch.column(3).to_pylist(), strict=True)], pa.bool_())
            windows, exact = pa.array([n for n, _ in judged], pa.int64()), pa.array([same for _, same in judged], pa.bool_())
            yield pa.RecordBatch.from_arrays([x.filter(keep) for x in (batch.column(0), batch.column(1), windows, batch.column(2), exact)], names=["key", "item", "windows", "item_windows", "exact"])

    kept = lined.filter("met >= needed").select("key", "item", "item_windows", "needed", "found")
    kept = kept.transform(in_batches, run, f"key long, item {items.schema['item'].dataType.simpleString()}, windows long, item_windows long, exact boolean")
    return kept.groupBy("key", "item").agg(F.max("windows").alias("windows"), F.max("item_windows").alias("item_windows"), F.max("exact").alias("exact"))


def row_key(id_col: str = "doc_id", text: str = "text"):
    """A 64-bit key of a row's id and text: rows that agree in both get the same decision anyway."""
    return F.xxhash64(column(id_col), F.coalesce(column(text), F.lit("")))


def contaminated_documents(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each document: whether it holds a benchmark item, how many, the items, the best share of an item's windows."""
    keyed = docs.select(column(id_col).alias("id"), column(text).alias("text"), row_key(id_col, text).alias("key"))
    hits = matches(keyed, benchmark).groupBy("key").agg(F.array_sort(F.collect_set("item")).alias("items"), F.max(F.col("windows") / F.col("item_windows")).alias("share"), F.max("exact").alias("exact"))
    hits = staged(hits, "contaminated")
    rows = keyed.select("id", "key").join(hits, "key", "left")
    return rows.select(
        F.col("id").alias(id_col),
        F.col("items").isNotNull().alias("contaminated"),
        F.coalesce(F.array_size("items"), F.lit(0)).cast("long").alias("n_items"),
        F.array_join("items", ",").alias("items"),
        F.coalesce("share", F.lit(0.0)).alias("share"),
        F.coalesce("exact", F.lit(False)).alias("exact_values"),
    )


def decontaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the rows that hold a benchmark item; clean rows do not shuffle."""
    hits = matches(docs.select(column(text).alias("text"), row_key(id_col, text).alias("key")), benchmark)
    hits = staged(hits.select("key").distinct(), "contaminated")
    return unpacked(without_keys(packed(docs, key=row_key(id_col, text)), hits, "key"), docs.columns)
