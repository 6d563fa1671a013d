"""Vectorised text primitives over Arrow batches: words, word hashes and word shingles of many texts at once.

Texts are treated as their UTF-8 bytes. A word is a maximal run of ASCII letters and digits (A-Z lower-cased)
and of non-ASCII bytes, which are exactly the code points from U+0080 on.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

MASK = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def give_back() -> None:
    """Returns freed memory to the system: workers are kept for later tasks, and should hold little while they wait."""
    pa.default_memory_pool().release_unused()
    pa.system_memory_pool().release_unused()


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column without copying; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, ends, data = column.buffers()
    offsets = np.frombuffer(ends, np.int64 if wide else np.int32, len(column) + 1, column.offset * (8 if wide else 4)).astype(np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


def chunks(column: pa.Array, most: int = 1 << 19) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets from 0) of groups of whole texts, each of about `most` bytes, so that
    working arrays stay in cache; a longer text is a group alone."""
    data, offsets = text_buffers(column)
    row, n = 0, len(offsets) - 1
    while row < n:
        end = int(np.searchsorted(offsets, offsets[row] + most, side="right")) - 1
        end = min(n, max(row + 1, end))
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


_WORD_BYTE = np.zeros(256, bool)
_WORD_BYTE[0x30:0x3A] = _WORD_BYTE[0x41:0x5B] = _WORD_BYTE[0x61:0x7B] = _WORD_BYTE[0x80:] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 32
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    if n:
        out[0] = 1
    return np.multiply.accumulate(out)


class Words:
    """The words of a group of texts: starts, ends (byte offsets), doc (text index), code (64-bit hash)."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        n = len(data)
        low = _LOWER[data]
        inside = np.zeros(n + 2, bool)
        inside[1:-1] = _WORD_BYTE[data]
        # A text's first byte begins a word of its own even where the text before ends inside one.
        edge = inside[1:] != inside[:-1]
        cut = offsets[1:-1]
        cut = cut[(cut > 0) & (cut < n)]
        joined = np.unique(cut[inside[cut] & inside[cut + 1]])
        starts = np.flatnonzero(edge & inside[1:])
        ends = np.flatnonzero(edge & inside[:-1])
        if len(joined):
            starts, ends = np.sort(np.concatenate([starts, joined])), np.sort(np.concatenate([ends, joined]))
        self.starts, self.ends = starts, ends
        self.doc = np.searchsorted(offsets, starts, side="right") - 1
        powers = _powers(_BASE, n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((low.astype(np.uint64) + np.uint64(1)) * powers[:n], out=total[1:])
        back = _powers(_INVERSE, n + 1)
        self.code = mix((total[ends] - total[starts]) * back[starts] + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        #: First word of each text, and one past the last.
        self.first = np.searchsorted(self.doc, np.arange(len(offsets)))

    def shingles(self, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
        """(text index, hash) of every run of `size` words; a text with fewer words, but not none, is one run."""
        counts = np.diff(self.first)
        n = len(self.code)
        doc, parts = [], []
        if n >= size:
            total = np.zeros(n - size + 1, np.uint64)
            for k in range(size):
                total = total * np.uint64(0x100000001B3) + self.code[k : n - size + 1 + k]
            same = self.doc[: n - size + 1] == self.doc[size - 1 :]
            doc.append(self.doc[: n - size + 1][same])
            parts.append(mix(total[same]))
        short = np.flatnonzero((counts > 0) & (counts < size))
        if len(short):
            rows = []
            for d in short:
                value = np.uint64(counts[d])
                for code in self.code[self.first[d] : self.first[d + 1]]:
                    value = np.uint64((int(value) * 0x100000001B3 + int(code)) & 0xFFFFFFFFFFFFFFFF)
                rows.append(value)
            doc.append(short)
            parts.append(mix(np.array(rows, np.uint64)))
        if not doc:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        doc, code = np.concatenate(doc), np.concatenate(parts)
        if len(short):
            order = np.argsort(doc, kind="stable")
            doc, code = doc[order], code[order]
        return doc, code


def sorted_per_doc(doc: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (doc, code) in that order, with how often each occurs."""
    order = np.lexsort((code, doc))
    doc, code = doc[order], code[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (code[1:] != code[:-1])
    at = np.flatnonzero(new)
    return doc[at], code[at], np.diff(np.append(at, len(doc)))
