"""Vectorised word hashing over Arrow string columns.

A block of texts is one byte buffer; a class table marks the bytes of words, words never cross the end of a text, and every
word gets a 64-bit keyed hash: eight bytes at a time go through a chain of bijective mixers, so words of up to eight bytes and equal
length never share one. Where an id depends on a span, its bytes are compared as well. Memory follows the block, not the batch.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash

#: Bytes of text that are worked on at once (a longer text is a block of its own).
BLOCK_BYTES = 1 << 19

_KEYS = (np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F))
#: Spans of more bytes are hashed and compared one by one.
_LONG = 256


def _table(pattern) -> np.ndarray:
    return np.array([bool(pattern(b)) for b in range(256)])


#: Word bytes: letters, digits and all bytes of characters beyond ASCII.
ALNUM = _table(lambda b: b >= 0x80 or chr(b).isalnum())
#: Word bytes: everything but white space.
NOT_SPACE = _table(lambda b: not (b == 0x20 or 0x09 <= b <= 0x0D))
#: A-Z folded to a-z.
FOLD = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], dtype=np.uint8)


def mix(z: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer."""
    with np.errstate(over="ignore"):
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


def _eights(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every position on, as one number each (zeros beyond the end)."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    return np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))


def _masked(wide: np.ndarray, at: np.ndarray, left: np.ndarray) -> np.ndarray:
    """The numbers at ``at`` with only their first ``left`` bytes."""
    out = wide[at]
    few = left < 8
    out[few] &= (np.uint64(1) << (left[few].astype(np.uint64) * np.uint64(8))) - np.uint64(1)
    return out


def hash_spans(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of every span ``data[starts[i]:ends[i]]``, by its bytes and length."""
    size = (ends - starts).astype(np.int64)
    with np.errstate(over="ignore"):
        out = mix(size.astype(np.uint64) * _KEYS[1] + _KEYS[0])
        if not len(size):
            return out
        wide = _eights(data)
        for i in np.flatnonzero(size > _LONG).tolist():
            out[i] ^= np.uint64(xxhash.xxh3_64_intdigest(data[starts[i] : ends[i]].tobytes(), seed=int(_KEYS[0])))
        on = np.flatnonzero((size > 0) & (size <= _LONG))
        at, left, h = starts[on], size[on], out[on]
        while len(on):
            h = mix((h ^ _masked(wide, at, left)) * _KEYS[1] + _KEYS[0])
            more = left > 8
            out[on[~more]] = h[~more]
            on, at, left, h = on[more], at[more] + 8, left[more] - 8, h[more]
        return out


def equal_spans(a: np.ndarray, a_starts: np.ndarray, b: np.ndarray, b_starts: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether ``a`` from ``a_starts`` on and ``b`` from ``b_starts`` on hold the same ``size`` bytes, span by span."""
    same = np.ones(len(size), bool)
    for i in np.flatnonzero(size > _LONG).tolist():
        same[i] = np.array_equal(a[a_starts[i] : a_starts[i] + size[i]], b[b_starts[i] : b_starts[i] + size[i]])
    on = np.flatnonzero((size > 0) & (size <= _LONG))
    wide_a, wide_b = _eights(a), _eights(b)
    x, y, left = a_starts[on], b_starts[on], size[on]
    while len(on):
        equal = _masked(wide_a, x, left) == _masked(wide_b, y, left)
        same[on[~equal]] = False
        more = equal & (left > 8)
        on, x, y, left = on[more], x[more] + 8, y[more] + 8, left[more] - 8
    return same


@dataclass
class Words:
    """The words of a block of texts: hash, first and end byte, and where each text's words begin (one entry more than texts)."""

    data: np.ndarray
    offsets: np.ndarray
    hashes: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def text_of_words(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)


def words_of(data: np.ndarray, offsets: np.ndarray, member: np.ndarray = ALNUM, fold: np.ndarray | None = FOLD) -> Words:
    """Find and hash the words of the texts ``data[offsets[i]:offsets[i + 1]]``; ``data`` ends at the last offset."""
    n = len(data)
    edges = np.zeros(n + 1, dtype=np.int8)
    inside = member[data]
    edges[:n] = inside
    edges[1:] -= inside.view(np.int8)
    starts, ends = np.flatnonzero(edges == 1), np.flatnonzero(edges == -1)
    # words that run over the border of two texts are cut there
    inner = offsets[1:-1]
    inner = np.unique(inner[(inner > 0) & (inner < n)])
    cut = inner[inside[inner] & inside[inner - 1]] if n else inner
    if len(cut):
        starts, ends = np.sort(np.concatenate([starts, cut])), np.sort(np.concatenate([ends, cut]))
    hashes = hash_spans(fold[data] if fold is not None else data, starts, ends)
    return Words(data, offsets, hashes, starts, ends, np.searchsorted(starts, offsets))


def blocks(column: pa.Array | pa.ChunkedArray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Blocks ``(row of the first text, bytes, offsets)`` of a string column; null counts as empty."""
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    row = 0
    for chunk in chunks:
        if not len(chunk):
            continue
        chunk = chunk.fill_null("") if chunk.null_count else chunk
        wide = pa.types.is_large_string(chunk.type)
        _, at, body = chunk.buffers()
        offsets = np.frombuffer(at, dtype=np.int64 if wide else np.int32)[chunk.offset : chunk.offset + len(chunk) + 1].astype(np.int64)
        data = np.frombuffer(body, dtype=np.uint8) if body is not None else np.zeros(0, np.uint8)
        lo = 0
        while lo < len(chunk):
            hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + BLOCK_BYTES, "right")) - 1)
            hi = min(hi, len(chunk))
            yield row + lo, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
            lo = hi
        row += len(chunk)


class SpanTable:
    """Token ids of distinct spans of text, kept from block to block and bounded in number and bytes.

    Spans are found by hash and then compared byte by byte, with the first of their hash in the block and with the one in the table; a
    span that shares a hash with another is encoded by itself. Known spans are sorted arrays, a large one and a recent one that
    is merged into it now and then: a few dozen bytes a span. Long spans are not kept.
    """

    def __init__(self, encode, most: int = 1_000_000, recent: int = 1 << 16, most_bytes: int = 1 << 25, longest: int = 4096):
        self._encode, self._most, self._recent, self._most_bytes, self._longest = encode, most, recent, most_bytes, longest
        self._clear()

    def _clear(self) -> None:
        # hash, first id, number of ids, first byte, number of bytes with the mark
        nothing = (np.zeros(0, np.uint64), *(np.zeros(0, np.int32) for _ in range(4)))
        self._known, self._new = nothing, nothing
        # zeros cost no memory until they are written, and arrays of full size are not copied to grow
        self._flat, self._used = np.zeros(self._most_bytes // 4, np.uint32), 0
        self._bytes, self._filled = np.zeros(self._most_bytes, np.uint8), 0

    @staticmethod
    def _merged(a: tuple, b: tuple) -> tuple:
        order = np.argsort(np.concatenate([a[0], b[0]]), kind="stable")
        return tuple(np.concatenate(x)[order] for x in zip(a, b, strict=True))

    def _add(self, hashes: np.ndarray, ids: np.ndarray, sizes: np.ndarray, body: np.ndarray, lengths: np.ndarray, tags: np.ndarray) -> None:
        while self._used + len(ids) > len(self._flat):
            self._flat = np.concatenate([self._flat, np.zeros_like(self._flat)])
        while self._filled + len(body) > len(self._bytes):
            self._bytes = np.concatenate([self._bytes, np.zeros_like(self._bytes)])
        self._flat[self._used : self._used + len(ids)] = ids
        self._bytes[self._filled : self._filled + len(body)] = body
        starts, begins = self._used + np.cumsum(sizes) - sizes, self._filled + np.cumsum(lengths) - lengths
        self._used, self._filled = self._used + len(ids), self._filled + len(body)
        self._new = self._merged(self._new, (hashes, *(x.astype(np.int32) for x in (starts, sizes, begins, tags))))
        if len(self._new[0]) > self._recent:
            self._known = self._merged(self._known, self._new)
            self._new = tuple(x[:0] for x in self._new)

    def lookup(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray, hashes: np.ndarray, span_of, mark: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all spans ``data[starts[i]:ends[i]]`` in a row, and how many each has. ``span_of(i)`` gives what is encoded for span
        ``i`` when it is new; spans with equal bytes and equal ``mark`` must have the same."""
        lengths = (ends - starts).astype(np.int64)
        tags = lengths * 2 + (0 if mark is None else mark)
        distinct, at, inverse = np.unique(hashes, return_index=True, return_inverse=True)
        first = at[inverse]
        later = first != np.arange(len(hashes))
        other, check = np.flatnonzero(later & (tags != tags[first])), np.flatnonzero(later & (tags == tags[first]))
        other = np.concatenate([other, check[~equal_spans(data, starts[check], data, starts[first[check]], lengths[check])]])
        if len(self._known[0]) + len(self._new[0]) + len(distinct) > self._most or self._filled + len(data) > self._most_bytes:
            self._clear()
        start, size = np.full(len(distinct), -1, np.int64), np.zeros(len(distinct), np.int64)
        for keys, ids_at, sizes, begins, held in (self._known, self._new):
            if len(keys) and len(distinct):
                near = np.minimum(np.searchsorted(keys, distinct), len(keys) - 1)
                hit = np.flatnonzero((keys[near] == distinct) & (held[near] == tags[at]))
                hit = hit[equal_spans(data, starts[at[hit]], self._bytes, begins[near[hit]].astype(np.int64), lengths[at[hit]])]
                start[hit], size[hit] = ids_at[near[hit]], sizes[near[hit]]
        # ids that the table does not hold yet follow the table's in one array
        base, more = self._used, []
        new = np.flatnonzero(start < 0)
        if len(new):
            ids, sizes = self._encode([span_of(i) for i in at[new].tolist()])
            sizes = np.asarray(sizes, np.int64)
            start[new], size[new] = base + np.cumsum(sizes) - sizes, sizes
            more.append(ids)
            fresh = (distinct[new], ids, sizes, at[new])
        start, size = start[inverse], size[inverse]
        if len(other):
            ids, sizes = self._encode([span_of(i) for i in other.tolist()])
            sizes = np.asarray(sizes, np.int64)
            start[other], size[other] = base + sum(map(len, more)) + np.cumsum(sizes) - sizes, sizes
            more.append(ids)
        ends_of = np.cumsum(size)
        place = np.repeat(start - (ends_of - size), size) + np.arange(int(ends_of[-1]) if len(ends_of) else 0)
        if more:  # the table itself is not copied
            fresh_ids, beyond = np.concatenate(more), place >= base
            out = np.empty(len(place), np.uint32)
            out[~beyond], out[beyond] = self._flat[place[~beyond]], fresh_ids[place[beyond] - base]
        else:
            out = self._flat[place]
        if len(new):
            self._keep(data, starts, lengths, tags, *fresh)
        return out, size

    def _keep(self, data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, tags: np.ndarray, hashes: np.ndarray, ids: np.ndarray, sizes: np.ndarray, at: np.ndarray) -> None:
        """Put the spans ``at`` with their ids into the table, but for long ones."""
        short = lengths[at] <= self._longest
        held = lengths[at][short]
        begin = np.cumsum(held) - held
        body = data[np.repeat(starts[at][short] - begin, held) + np.arange(int(held.sum()))]
        self._add(hashes[short], ids[np.repeat(short, sizes)], sizes[short], body, held, tags[at][short])


def per_text_counts(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Sums of ``size`` over each text's spans."""
    running = np.concatenate([[0], np.cumsum(size)])
    return running[first[1:]] - running[first[:-1]]


def hash_word(word: str, fold: bool = True) -> int:
    """The kernel's hash of one word."""
    data = np.frombuffer(word.encode(), dtype=np.uint8)
    found = words_of(data, np.array([0, len(data)]), np.ones(256, bool), FOLD if fold else None)
    return int(found.hashes[0])
