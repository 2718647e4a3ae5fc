"""Token ids in binary files of patched frame-of-reference blocks.

Texts are encoded where they lie, rows are dealt out by ranges of the id, sorted, and every task writes its ids in blocks: a
block's minimum is subtracted, the rest is packed at the width that a percentile of it needs, what is wider goes to the block's
list of exceptions, and the file's end indexes the block starts. Any block can be read alone.

File layout, little-endian::

    b"FGT1" | blocks of ids | blocks of lengths | id of each row (int64) | null flags (bits) | index | footer
    block:  uint32 minimum, uint8 width, uint16 exceptions, uint16 values, packed values, uint16 positions, uint32 values
    index:  uint64 start of every block, ids' blocks first
    footer: uint64 rows, uint64 ids, uint64 start of lengths, uint64 start of row ids, uint64 start of index, uint64 blocks of ids,
            uint64 blocks of lengths, b"FGT1"

Defined results: null counts as empty and is the end id alone; null ids come first; rows with equal ids keep some order,
the same in ids and index. An empty table writes no file and gives an empty table.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from finegrain.llm.batches import in_batches
from finegrain.llm.textkernel import SpanTable, blocks, hash_spans, per_text_counts
from finegrain.operators.ranking import range_bounds
from finegrain.sources.staging import fresh_path, staged

MAGIC, FOOTER = b"FGT1", struct.Struct("<7Q4s")
BLOCK, PERCENTILE = 1024, 90
#: Ids that one file holds before the task opens the next, and rows that one task is meant to sort.
FILE_IDS, RANGE_ROWS, MOST_RANGES = 8_000_000, 20_000, 4096
END_ID = 1


# ---------------------------------------------------------------- blocks


def _widths(delta: np.ndarray, percentile: int) -> np.ndarray:
    """Bits that the percentile of every row of ``delta`` needs."""
    k = min(delta.shape[1] - 1, delta.shape[1] * percentile // 100)
    at = np.partition(delta, k, axis=1)[:, k]
    return np.where(at == 0, 0, np.floor(np.log2(np.maximum(at, 1))).astype(np.int64) + 1)


def _pack(values: np.ndarray, width: int) -> np.ndarray:
    """Rows of values packed at ``width`` bits, least significant bit first."""
    if width == 0:
        return np.zeros((len(values), 0), np.uint8)
    if width in (8, 16, 32):
        return values.astype(f"<u{width // 8}").view(np.uint8).reshape(len(values), -1)
    bits = (values[:, :, None] >> np.arange(width, dtype=np.uint32)) & np.uint32(1)
    return np.packbits(bits.astype(np.uint8).reshape(len(values), -1), axis=1, bitorder="little")


def _unpack(packed: np.ndarray, width: int, values: int) -> np.ndarray:
    if width == 0:
        return np.zeros((len(packed), values), np.uint32)
    if width in (8, 16, 32):
        return np.ascontiguousarray(packed).view(f"<u{width // 8}").astype(np.uint32)
    bits = np.unpackbits(packed, axis=1, count=width * values, bitorder="little").reshape(len(packed), values, width)
    wide = np.zeros((len(packed), values, 32 if width > 16 else 16), np.uint8)
    wide[:, :, :width] = bits
    return np.packbits(wide.reshape(len(packed), -1), axis=1, bitorder="little").view("<u4" if width > 16 else "<u2").astype(np.uint32)


def encode_blocks(values: np.ndarray, percentile: int = PERCENTILE) -> list[bytes]:
    """The blocks of a run of unsigned 32-bit values."""
    values = np.ascontiguousarray(values, np.uint32)
    full = len(values) // BLOCK
    out: list[bytes] = []
    for part in (values[: full * BLOCK].reshape(full, BLOCK), values[full * BLOCK :].reshape(1, -1)):
        if not part.size:
            continue
        low = part.min(axis=1)
        delta = part - low[:, None]
        widths = _widths(delta, percentile)
        made: list[bytes] = [b""] * len(part)
        for width in np.unique(widths):
            rows = np.flatnonzero(widths == width)
            d = delta[rows]
            over = d >> np.uint32(width) != 0 if width < 32 else np.zeros(d.shape, bool)
            packed = _pack(np.where(over, 0, d).astype(np.uint32), int(width))
            for k, r in enumerate(rows):
                at = np.flatnonzero(over[k])
                made[r] = struct.pack("<IBHH", low[r], width, len(at), part.shape[1]) + packed[k].tobytes() + at.astype("<u2").tobytes() + d[k][at].astype("<u4").tobytes()
        out += made
    return out


def decode_blocks(buffer: bytes | memoryview, starts: np.ndarray) -> np.ndarray:
    """The values of the blocks that begin at ``starts``."""
    heads = [struct.unpack_from("<IBHH", buffer, s) for s in starts]
    if not heads:
        return np.zeros(0, np.uint32)
    raw = np.frombuffer(buffer, np.uint8)
    low, width, exceptions, values = (np.array(x, np.int64) for x in zip(*heads, strict=True))
    begin = np.cumsum(values) - values
    out = np.empty(int(values.sum()), np.uint32)
    for w, n in {(int(a), int(b)) for a, b in zip(width, values, strict=True)}:
        rows = np.flatnonzero((width == w) & (values == n))
        size = -(-w * n // 8)
        at = np.asarray(starts)[rows].astype(np.int64)[:, None] + 9 + np.arange(size)
        got = _unpack(raw[at], w, n)
        for k in np.flatnonzero(exceptions[rows]):
            e, p = int(exceptions[rows[k]]), int(starts[rows[k]]) + 9 + size
            got[k, np.frombuffer(buffer, "<u2", e, p)] = np.frombuffer(buffer, "<u4", e, p + 2 * e)
        out[(begin[rows][:, None] + np.arange(n)).ravel()] = (got + low[rows].astype(np.uint32)[:, None]).ravel()
    return out


def write_file(ids: np.ndarray, lengths: np.ndarray, rows: np.ndarray, nulls: np.ndarray) -> bytes:
    """The bytes of one file."""
    data, counts = encode_blocks(ids), encode_blocks(lengths)
    sizes = np.fromiter(map(len, data + counts), np.int64, len(data) + len(counts))
    starts = len(MAGIC) + np.cumsum(sizes) - sizes
    lengths_at = len(MAGIC) + int(sizes[: len(data)].sum())
    rows_at = len(MAGIC) + int(sizes.sum())
    row_bytes = rows.astype("<i8").tobytes() + np.packbits(nulls, bitorder="little").tobytes()
    index_at = rows_at + len(row_bytes)
    return b"".join([MAGIC, *data, *counts, row_bytes, starts.astype("<u8").tobytes(), FOOTER.pack(len(rows), len(ids), lengths_at, rows_at, index_at, len(data), len(counts), MAGIC)])


def read_file(buffer: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids, lengths, row ids and null flags of one file."""
    rows, ids, _, rows_at, index_at, n_data, n_counts, magic = FOOTER.unpack_from(buffer, len(buffer) - FOOTER.size)
    if magic != MAGIC or buffer[:4] != MAGIC:
        raise ValueError("not a token file")
    starts = np.frombuffer(buffer, "<u8", n_data + n_counts, index_at).astype(np.int64)
    values, lengths = decode_blocks(buffer, starts[:n_data]), decode_blocks(buffer, starts[n_data:])
    if len(values) != ids or len(lengths) != rows or int(lengths.sum()) != ids:
        raise ValueError("a token file's counts do not agree")
    nulls = np.unpackbits(np.frombuffer(buffer, np.uint8, -(-rows // 8), rows_at + 8 * rows), count=rows, bitorder="little").astype(bool)
    return values, lengths.astype(np.int64), np.frombuffer(buffer, "<i8", rows, rows_at), nulls


# ---------------------------------------------------------------- tokens

# Byte classes of texts that the fast path may split by itself: ASCII, and letters from U+00C0 to U+00FF
_SPACE, _LETTER, _DIGIT, _SIGN, _HARD = range(5)
_CLASS = np.array(
    [
        _SPACE if b == 32 or 9 <= b <= 13 else _LETTER if chr(b).isascii() and chr(b).isalpha() else _DIGIT if 48 <= b <= 57 else _SIGN if b < 0x80 else _LETTER if b <= 0xBF or b == 0xC3 else _HARD
        for b in range(256)
    ],
    dtype=np.int8,
)
_LOWER = np.array([b + 32 if 65 <= b <= 90 or (0x80 <= b <= 0x9E and b != 0x97) else b for b in range(256)], dtype=np.uint8)


class FastWords:
    """Encodes with a word-wise BPE tokenizer that lowers case and splits at white space, digits and signs.

    Words are found by byte class and encoded once each by the library; a text in which the classes cannot tell words as the
    library does (other alphabets, apostrophes, signs of U+00C0..U+00FF, special tokens) goes through the library whole.
    """

    def __init__(self, model: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_str(model)
        size = self.library.get_vocab_size()
        self._ends = np.array([(self.library.id_to_token(i) or "").endswith("</w>") for i in range(size)])
        self._table = SpanTable(self._words)

    def _words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of single words: one call of the library, cut where a piece ends a word."""
        ids = np.array(self.library.encode(" ".join(words), add_special_tokens=False).ids, dtype=np.uint32)
        ends = np.flatnonzero(self._ends[ids]) + 1
        if len(ends) == len(words):
            return ids, np.diff(ends, prepend=0)
        lists = [self.library.encode(w, add_special_tokens=False).ids for w in words]
        return np.array([x for one in lists for x in one], np.uint32), np.array([len(x) for x in lists], np.int64)

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts of a block in a row, and how many each has."""
        n = len(offsets) - 1
        kinds = _CLASS[data]
        hard_byte = (kinds == _HARD) | (data == 39)
        hard_byte[1:] |= ((data[1:] == 0x97) | (data[1:] == 0xB7)) & (data[:-1] == 0xC3)
        hard_byte[1:] |= (data[1:] == ord("|")) & (data[:-1] == ord("<"))
        hard = np.zeros(n, bool)
        hard[np.searchsorted(offsets, np.flatnonzero(hard_byte), "right") - 1] = True
        if hard.any():
            kinds = np.where(np.repeat(hard, np.diff(offsets)), _SPACE, kinds)
        edge = np.ones(len(data) + 1, bool)
        edge[1:-1] = (kinds[1:] != kinds[:-1]) | (kinds[1:] == _DIGIT)
        edge[offsets] = True
        at = np.flatnonzero(edge)
        starts, ends = at[:-1], at[1:]
        solid = kinds[starts] != _SPACE if len(data) else np.zeros(0, bool)
        starts, ends = starts[solid], ends[solid]
        low = _LOWER[data]
        raw = low.tobytes()
        ids, size = self._table.lookup(low, starts, ends, hash_spans(low, starts, ends), lambda i: raw[starts[i] : ends[i]].decode())
        counts = per_text_counts(np.searchsorted(starts, offsets), size)
        if not hard.any():
            return ids, counts
        at_hard = np.flatnonzero(hard)
        texts = [data[offsets[i] : offsets[i + 1]].tobytes().decode() for i in at_hard]
        found = [np.array(e.ids, np.uint32) for e in self.library.encode_batch(texts, add_special_tokens=False)]
        pieces = np.split(ids, np.cumsum(counts)[:-1])
        for i, x in zip(at_hard, found, strict=True):
            pieces[i] = x
        return np.concatenate(pieces), np.fromiter(map(len, pieces), np.int64, n)


@lru_cache(maxsize=2)
def _tokenizer(model: str) -> FastWords:
    return FastWords(model)


def with_end(ids: np.ndarray, counts: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """The ids with the end id after each text."""
    lengths = counts + 1
    out = np.full(int(lengths.sum()), end, np.uint32)
    inner = np.ones(len(out), bool)
    inner[np.cumsum(lengths) - 1] = False
    out[inner] = ids
    return out, lengths


# ---------------------------------------------------------------- Spark


def _open(path: str):
    from pyarrow import fs

    if path.startswith("file:"):
        path = "file:///" + path[5:].lstrip("/")
    return fs.FileSystem.from_uri(path)


def write_token_files(docs: DataFrame, model: str, folder: str, id_col: str = "doc_id", text: str = "text", end: int = END_ID) -> DataFrame:
    """Write the ids of all texts below ``folder`` in ascending order of the id; returns the staged list of files
    ``(part, file, path, rows, ids)``. A task that runs twice leaves files that the list does not name."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("text"))
    ranges = min(MOST_RANGES, rows.count() // RANGE_ROWS + 1)
    bounds = np.array(range_bounds(rows.select("id"), "id", ranges), dtype=np.int64)
    shared = spark.sparkContext.broadcast(model)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = _tokenizer(shared.value)
        for batch in batches:
            for row, data, offsets in blocks(batch.column(1)):
                n = len(offsets) - 1
                ids, lengths = with_end(*tokenizer.encode(data, offsets), end)
                key = batch.column(0).slice(row, n)
                part = np.searchsorted(bounds, key.fill_null(-(2**63)).to_numpy(), "right").astype(np.int32)
                raw, at = ids.astype("<u2" if ids.max(initial=0) < 2**16 else "<u4"), np.concatenate([[0], np.cumsum(lengths)])
                item = raw.itemsize
                payload = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer((at * item).astype(np.int32)), pa.py_buffer(raw)])
                yield pa.RecordBatch.from_arrays([key, pa.array(part), pa.array(np.full(n, item, np.int8)), payload], names=["id", "part", "item", "ids"])

    encoded = rows.transform(in_batches, encode, "id long, part int, item byte, ids binary")
    dealt = encoded.repartitionById(len(bounds) + 1, "part").sortWithinPartitions(F.col("id").asc_nulls_first())

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, base = _open(folder)
        system.create_dir(base, recursive=True)
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        count, file = 0, 0
        part = TaskContext.get().partitionId()

        def flush() -> pa.RecordBatch:
            nonlocal count, file, held
            ids, lengths, keys, nulls = (np.concatenate(x) for x in zip(*held, strict=True))
            name = f"part-{part:06d}-{file:06d}-{uuid.uuid4().hex}.tok"
            with system.open_output_stream(f"{base}/{name}") as out:
                out.write(write_file(ids, lengths, keys, nulls))
            made = pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "file": pa.array([file], pa.int32()), "path": [f"{folder}/{name}"], "rows": [len(keys)], "ids": [len(ids)]})
            held, count, file = [], 0, file + 1
            return made

        for batch in batches:
            sizes = batch.column(2).to_numpy()
            for i, payload in enumerate(batch.column(3)):
                ids = np.frombuffer(payload.as_buffer(), f"<u{sizes[i]}").astype(np.uint32)
                key = batch.column(0)[i].as_py()
                held.append((ids, np.array([len(ids)], np.uint32), np.array([key or 0], np.int64), np.array([key is None])))
                count += len(ids)
                if count >= FILE_IDS:
                    yield flush()
        if held:
            yield flush()

    return staged(dealt.transform(in_batches, write, "part int, file int, path string, rows long, ids long"), "token-file-list")


def read_token_files(files: DataFrame) -> DataFrame:
    """Every text of the listed files: id, ``start`` (ids before it), ``n_tokens``, ``ids``."""
    return _read(files, True)


def read_token_digests(files: DataFrame) -> DataFrame:
    """As :func:`read_token_files`, with ``ids_crc32`` in place of the ids."""
    return _read(files, False)


def _read(files: DataFrame, whole: bool) -> DataFrame:
    per_part = files.groupBy("part").agg(F.sum("ids").alias("_n"))
    # one row for each range of ids: bounded by MOST_RANGES
    starts = per_part.select("part", (F.sum("_n").over(Window.orderBy("part")) - F.col("_n")).alias("_part_start"))
    inside = F.sum("ids").over(Window.partitionBy("part").orderBy("file")) - F.col("ids")
    placed = files.withColumn("_in", inside).join(F.broadcast(starts), "part").select("path", (F.col("_in") + F.col("_part_start")).alias("start"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                system, at = _open(path)
                with system.open_input_stream(at) as source:
                    ids, lengths, keys, nulls = read_file(source.read())
                ends = np.cumsum(lengths)
                begins = ends - lengths
                if whole:
                    last = pa.ListArray.from_arrays(pa.array(np.append(begins, ends[-1:]).astype(np.int32)), pa.array(ids.astype(np.int32)))
                else:
                    view = memoryview(ids.astype("<u4")).cast("B")
                    last = pa.array([zlib.crc32(view[4 * b : 4 * e]) for b, e in zip(begins.tolist(), ends.tolist(), strict=True)], pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64(), mask=nulls), pa.array(start + begins), pa.array(lengths), last], names=["id", "start", "n_tokens", "last"])

    schema = f"id long, start long, n_tokens long, last {'array<int>' if whole else 'long'}"
    spread = placed.repartition(max(1, min(files.count(), 4096)), "path")
    return spread.transform(in_batches, read, schema).withColumnRenamed("last", "ids" if whole else "ids_crc32")


def token_digests(spark: SparkSession, docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Write the token files of ``docs`` into the shared folder and report every text from what they hold."""
    with open(tokenizer_path, encoding="utf-8") as source:
        model = source.read()
    files = write_token_files(docs, model, fresh_path(spark, "token-files"), id_col, text)
    return read_token_digests(files).withColumnRenamed("id", id_col)
