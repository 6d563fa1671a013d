"""Packing: concatenate all token streams and cut fixed windows.

Two passes. The first tokenises every document once and writes, per partition, each document's ids and its start
within the partition; the partition totals (one number a partition) are summed into prefix offsets. The second adds
its partition's offset to every row, which gives global positions, and cuts at multiples of the window: a document
over a boundary yields one record on each side. No row is shuffled, and only the last window can hold padding.

Defined results: a null or empty text is the end token alone; repeated rows are packed as often as they occur;
a null doc_id stays null; an empty table gives no pieces; other columns of the input are ignored.
"""

from __future__ import annotations

import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import written

WINDOW = 2048
END_ID = 1
#: A worker keeps the ids of so many words at most; beyond that it starts its table anew.
WORDS_KEPT = 350_000
#: Then it keeps those of up to so many letters, which come again most.
SHORT = 9

#: Letters of one case-folded form each, then marks: the vocabulary splits such a word there, whatever the case.
_ODD = re.compile("[\x1c-\x1f]")
_PLAIN = re.compile("([A-Za-zÀ-ÖØ-Þß-öø-ÿ]+)([!-&(-/:-@[-`{-~]*)")


class _Known(dict):
    """Ids of words; a word not known yet is tokenised. Letters, then marks, are the ids of the lower-cased letters and of the marks."""

    def __init__(self, coder: WordTokenizer):
        self.coder = coder

    def __missing__(self, word: str) -> bytes:
        if word.isascii() and word.isalpha() and word.islower():
            ids = self.coder.merges(word)
        elif not (m := _PLAIN.fullmatch(word)):
            ids = self.coder.direct(word)
        elif m[2]:
            ids = self[m[1].lower()] + self.marks(m[2])
        elif (low := word.lower()) == word:
            ids = self.coder.merges(word)
        else:
            ids = self[low]
        self[word] = ids
        return ids

    def marks(self, marks: str) -> bytes:
        if (ids := self.get(marks)) is None:
            ids = self[marks] = self.coder.direct(marks)
        return ids


class WordTokenizer:
    """Ids of whole texts by a `tokenizers` vocabulary that never merges over white space.

    Such a vocabulary gives a text the ids of its white-space-separated words one after another, so each different
    word is tokenised once and kept. A new word of lower-case letters goes straight to
    the vocabulary's merges; any other takes the whole way.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.wide = self.tokenizer.get_vocab_size() > 1 << 16
        self.dtype = np.dtype("<u4" if self.wide else "<u2")
        self.code = "I" if self.wide else "H"
        self.known = _Known(self)
        self.model = self.tokenizer.model
        self.letters = _byte_letters()

    def direct(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def merges(self, word: str) -> bytes:
        # One piece of lower-case letters: nothing is left to do but the merges.
        word = word if word.isascii() else word.encode().decode("latin-1").translate(self.letters)
        return array(self.code, [t.id for t in self.model.tokenize(word)]).tobytes()

    def ids(self, texts: list[str]) -> list[bytes]:
        """The packed ids of each text."""
        if len(self.known) > WORDS_KEPT:
            short = {w: ids for w, ids in self.known.items() if len(w) <= SHORT}
            self.known.clear()
            if len(short) <= WORDS_KEPT // 2:
                self.known.update(short)
        get = self.known.__getitem__
        return [b"".join(map(get, _words(t))) for t in texts]


def _byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in a byte-level vocabulary: itself if printable, else the next from U+0100."""
    printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    others = [b for b in range(256) if b not in printable]
    return {b: chr(b) for b in printable} | {b: chr(0x100 + k) for k, b in enumerate(others)}


def _words(text: str) -> list[str]:
    # The vocabulary folds case letter by letter, as str.lower() does below U+0100; other texts keep their case here.
    try:
        text.encode("latin-1")
        text = text.lower()
    except UnicodeEncodeError:
        pass
    # U+001C to U+001F split str.split() but are no white space to the tokenizer.
    return text.split() if not _ODD.search(text) else [w for w in re.split("[ \t\n\v\f\r]", text) if w]


_TOKENIZERS: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """One tokenizer for a worker process, however many tasks it runs."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = WordTokenizer(path)
    return _TOKENIZERS[path]


def tokenised(docs: DataFrame, tokenizer_path: str, end_id: int = END_ID, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Rows (part, start, n, doc_id, ids): each document's packed ids, and its start within its partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, start, part = tokenizer(tokenizer_path), 0, TaskContext.get().partitionId()
        end = np.array([end_id], coder.dtype).tobytes()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part_of = batch.slice(at, 512)
                ids = [x + end for x in coder.ids([t or "" for t in part_of.column(1).to_pylist()])]
                n = np.array([len(x) // coder.dtype.itemsize for x in ids], np.int64)
                ends = start + np.cumsum(n)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(ids), part, np.int32)), pa.array(ends - n), pa.array(n), part_of.column(0), pa.array(ids, pa.binary())],
                    ["part", "start", "n", "doc_id", "ids"],
                )
                start = int(ends[-1])

    id_type = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"part int, start long, n long, doc_id {id_type}, ids binary")


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, end_id: int = END_ID, text_col: str = "text", id_col: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """Pieces (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids]) of all documents.

    ids, if asked for, are the piece's token ids as little-endian unsigned 32-bit integers.
    """
    spark = docs.sparkSession
    rows = written(tokenised(docs, tokenizer_path, end_id, text_col, id_col), "tokens")
    # One number a partition of the input: this is all that the driver sees.
    totals = rows.groupBy("part").agg(F.sum("n").alias("total")).orderBy("part").collect()
    base, bases = 0, []
    for r in totals:
        bases.append((r["part"], base))
        base += r["total"]
    offsets = spark.createDataFrame(bases, "part int, base long")
    id_type = rows.schema["doc_id"].dataType.simpleString()
    out = f"doc_id {id_type}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids binary" * with_ids

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            first, n = (np.asarray(batch.column(k)) for k in (1, 2))
            opened = first // window
            pieces = (first + n - 1) // window - opened + 1
            row = np.repeat(np.arange(len(n)), pieces)
            nth = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            sequence = opened[row] + nth
            begin = np.maximum(first[row], sequence * window)
            length = np.minimum((first + n)[row], (sequence + 1) * window) - begin
            start = begin - first[row]
            raw = batch.column(3).to_pylist()
            ids = [np.frombuffer(x, "<u2" if len(x) == 2 * k else "<u4").astype("<u4").tobytes() for x, k in zip(raw, n.tolist())]
            parts = [ids[r][4 * s : 4 * (s + k)] for r, s, k in zip(row.tolist(), start.tolist(), length.tolist())]
            columns = [batch.column(0).take(pa.array(row)), pa.array(start), pa.array(length), pa.array([zlib.crc32(x) for x in parts], pa.int64()), pa.array(n[row]), pa.array(sequence), pa.array(begin - sequence * window)]
            yield pa.RecordBatch.from_arrays(columns + [pa.array(parts, pa.binary())] * with_ids, [c.split()[0] for c in out.split(", ")])

    # The offsets have one row for each partition of the scan, so their size follows the task count, not the rows.
    placed = rows.join(F.broadcast(offsets), "part").select("doc_id", (F.col("start") + F.col("base")).alias("first"), "n", "ids")
    return placed.mapInArrow(cut, out)
