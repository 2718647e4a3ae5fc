"""SentencePiece encoding and decoding: an Aho-Corasick automaton over the pieces drives a single-pass Viterbi.

The automaton reads a text once. At every position its output links name all pieces that end there, longest first, and each
relaxes the best score of that position; the path is then read backwards. Characters without a piece of their own can be
passed at the unknown score (least score minus 10) and are spelt as byte pieces. Ties go to the longer piece.

No piece holds a space mark after another character or a line feed beside one (this is checked when the model is loaded), so the
best path of a text is the best paths of its spans - a run of spaces with what follows - put together; every distinct span is
solved once and kept in a bounded table.

Decoding puts the bytes of the pieces together, turns space marks into spaces and takes off the one space that encoding adds.

Defined results: null counts as empty and has no ids. The space mark U+2581 in a text decodes to a space, as the public
library does; such a text is reported with ``exact`` false. Extra columns pass through.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.batches import in_batches
from finegrain.llm.textkernel import SpanTable, blocks, hash_spans, mix, per_text_counts

MARK = "▁"
UNKNOWN_PENALTY = 10.0
# Piece types of the model file.
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6

_SPACE, _LINE = 32, 10


class PieceModel:
    """The pieces, scores and byte pieces of a model file."""

    def __init__(self, model: bytes):
        from sentencepiece import sentencepiece_model_pb2

        proto = sentencepiece_model_pb2.ModelProto()
        proto.ParseFromString(model)
        spec = proto.normalizer_spec
        if spec.precompiled_charsmap or spec.remove_extra_whitespaces or not spec.add_dummy_prefix or not spec.escape_whitespaces:
            raise ValueError("only models that leave texts as they are, but for space marks, are supported")
        normal = [p.score for p in proto.pieces if p.type == NORMAL]
        top, self.unknown_score = max(normal), min(normal) - UNKNOWN_PENALTY
        self.unknown_id = next(i for i, p in enumerate(proto.pieces) if p.type == UNKNOWN)
        self.byte_ids, self.surfaces = [self.unknown_id] * 256, []
        self.automaton, self.single = ahocorasick.Automaton(), set()
        self.scores = np.full(len(proto.pieces), self.unknown_score)
        for i, p in enumerate(proto.pieces):
            surface = p.piece.replace(MARK, " ").encode()
            if p.type == BYTE:
                surface = bytes([int(p.piece[3:5], 16)])
                self.byte_ids[surface[0]] = i
            elif p.type in (NORMAL, USER):
                if MARK in p.piece.lstrip(MARK) or ("\n" in p.piece and p.piece != "\n"):
                    raise ValueError("a piece reaches over a span")
                self.scores[i] = len(p.piece) * top - 0.1 if p.type == USER else p.score
                self.automaton.add_word(p.piece, (len(p.piece), float(self.scores[i]), i))
                if len(p.piece) == 1:
                    self.single.add(p.piece)
            else:
                surface = b""
            self.surfaces.append(surface)
        self.automaton.make_automaton()

    def viterbi(self, span: str) -> list[int]:
        """Ids of the best path over one span (space marks in place of spaces)."""
        n = len(span)
        best, came = [0.0] + [float("-inf")] * n, [(0, -1)] * (n + 1)
        single, unknown, done = self.single, self.unknown_score, 0
        for end, (length, score, piece) in self.automaton.iter(span):
            while done < end:  # positions that the matches have passed
                if span[done] not in single and (x := best[done] + unknown) > best[done + 1]:
                    best[done + 1], came[done + 1] = x, (done, -1)
                done += 1
            start = end + 1 - length
            if (x := best[start] + score) > best[end + 1]:
                best[end + 1], came[end + 1] = x, (start, piece)
        while done < n:
            if span[done] not in single and (x := best[done] + unknown) > best[done + 1]:
                best[done + 1], came[done + 1] = x, (done, -1)
            done += 1
        out: list[int] = []
        at = n
        while at:
            start, piece = came[at]
            if piece >= 0:
                out.append(piece)
            else:
                out += [self.byte_ids[b] for b in reversed(span[start:at].encode())]
            at = start
        out.reverse()
        return out

    def encode(self, text: str) -> list[int]:
        """Ids of one text, solved as a whole."""
        return self.viterbi((MARK + text).replace(" ", MARK)) if text else []

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.surfaces.__getitem__, ids)).decode("utf-8", "replace")[1:] if ids else ""


class BlockEncoder:
    """Encodes and decodes blocks of texts with a table of solved spans."""

    def __init__(self, model: bytes):
        self.model = PieceModel(model)
        self._table = SpanTable(self._solve)
        sizes = np.fromiter(map(len, self.model.surfaces), np.int64)
        self._size, self._start = sizes, np.cumsum(sizes) - sizes
        self._bytes = np.frombuffer(b"".join(self.model.surfaces), np.uint8)

    def _solve(self, spans: list[str]) -> tuple[np.ndarray, np.ndarray]:
        lists = list(map(self.model.viterbi, spans))
        sizes = np.fromiter(map(len, lists), np.int64, len(lists))
        return np.fromiter(chain.from_iterable(lists), np.uint32, int(sizes.sum())), sizes

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and how many each has."""
        space, line = data == _SPACE, data == _LINE
        edge = np.ones(len(data) + 1, bool)
        edge[1:-1] = (space[1:] & ~space[:-1]) | line[1:] | line[:-1]
        edge[offsets] = True
        at = np.flatnonzero(edge)
        starts, ends = at[:-1], at[1:]
        first = np.zeros(len(data) + 1, bool)
        first[offsets[:-1]] = True
        opens = first[starts]
        hashes = hash_spans(data, starts, ends)
        hashes[opens] = mix(hashes[opens] + np.uint64(1))
        raw = data.tobytes()

        def span(i: int) -> str:
            body = raw[starts[i] : ends[i]].decode().replace(" ", MARK)
            return MARK + body if opens[i] else body

        ids, size = self._table.lookup(data, starts, ends, hashes, span, opens)
        return ids, per_text_counts(np.searchsorted(starts, offsets), size)

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all texts in a row, and their offsets."""
        size = self._size[ids]
        ends = np.cumsum(size)
        total = int(ends[-1]) if len(ends) else 0
        out = self._bytes[np.repeat(self._start[ids] - (ends - size), size) + np.arange(total)]
        bounds = np.concatenate([[0], np.cumsum(counts)])
        running = np.concatenate([[0], ends])
        offsets = running[bounds]
        keep = np.ones(total, bool)
        keep[offsets[:-1][counts > 0]] = False  # the space that encoding puts in front
        lengths = np.diff(offsets) - (counts > 0)
        return out[keep], np.concatenate([[0], np.cumsum(lengths)])


@lru_cache(maxsize=2)
def _encoder(model: bytes) -> BlockEncoder:
    return BlockEncoder(model)


def _lists(flat: np.ndarray, counts: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(flat.astype(np.int32)))


def encode_pieces(docs: DataFrame, model: bytes, text: str = "text", ids: str = "ids") -> DataFrame:
    """``docs`` with an array column of piece ids."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop(ids)
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(shared.value)
        for batch in batches:
            for row, data, offsets in blocks(batch.column(at)):
                flat, counts = encoder.encode(data, offsets)
                part = batch.slice(row, len(counts))
                yield pa.RecordBatch.from_arrays([*part.columns, _lists(flat, counts)], names=[*part.schema.names, ids])

    schema = docs.select("*", F.array().cast("array<int>").alias(ids)).schema
    return docs.transform(in_batches, run, schema)


def decode_pieces(rows: DataFrame, model: bytes, ids: str = "ids", text: str = "text") -> DataFrame:
    """``rows`` with the text that an array column of piece ids spells (null for null)."""
    shared = rows.sparkSession.sparkContext.broadcast(model)
    rows = rows.drop(text) if text != ids else rows
    at = rows.columns.index(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = _encoder(shared.value).model
        for batch in batches:
            out = [None if x is None else m.decode(x) for x in batch.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.string())], names=[*batch.schema.names, text])

    schema = rows.select("*", F.lit(None).cast("string").alias(text)).schema
    return rows.transform(in_batches, run, schema)


def piece_digests(docs: DataFrame, model: bytes, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """As :func:`encoded_digests`, without the ids."""
    return _digests(docs, model, id_col, text, False)


def encoded_digests(docs: DataFrame, model: bytes, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Encode every text, decode its ids again, and report: ids' number and checksum (little-endian unsigned 32-bit), byte pieces,
    the path's score, whether decoding gave the text back exactly, and the ids."""
    return _digests(docs, model, id_col, text, True)


def _digests(docs: DataFrame, model: bytes, id_col: str, text: str, whole: bool) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(shared.value)
        scores = encoder.model.scores
        spelt = np.zeros(len(scores), bool)
        spelt[[i for i in encoder.model.byte_ids if i >= 0]] = True
        for batch in batches:
            for row, data, offsets in blocks(batch.column(1)):
                flat, counts = encoder.encode(data, offsets)
                back, at = encoder.decode(flat, counts)
                bounds = np.concatenate([[0], np.cumsum(counts)])
                view = memoryview(np.ascontiguousarray(flat, "<u4")).cast("B")
                checks = [zlib.crc32(view[4 * b : 4 * e]) for b, e in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                of = np.repeat(np.arange(len(counts)), counts)
                total = np.bincount(of, scores[flat], minlength=len(counts))
                byte = np.bincount(of, spelt[flat], minlength=len(counts)).astype(np.int64)
                mine, given = memoryview(back), memoryview(np.ascontiguousarray(data))
                exact = [mine[a:b] == given[c:d] for a, b, c, d in zip(at[:-1].tolist(), at[1:].tolist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                columns = [batch.column(0).slice(row, len(counts)), pa.array(counts), pa.array(checks, pa.int64()), pa.array(byte), pa.array(total), pa.array(exact, pa.bool_())]
                names = ["id", "n_tokens", "ids_crc32", "n_bytes", "path_score", "exact"]
                yield pa.RecordBatch.from_arrays([*columns, _lists(flat, counts)] if whole else columns, names=[*names, "ids"] if whole else names)

    id_type = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"))
    more = ", ids array<int>" if whole else ""
    return rows.transform(in_batches, run, f"id {id_type}, n_tokens long, ids_crc32 long, n_bytes long, path_score double, exact boolean{more}").withColumnRenamed("id", id_col)
