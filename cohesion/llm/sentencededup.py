"""Substring dedup over sliding sentence spans.

A sentence ends at a full stop, question or exclamation mark, or line break. One of over NEAR words is cut into pieces of
at most NEAR words, before each word whose hash is the least of some NEAR consecutive ones inside it. From every piece
on, the shortest run of pieces that holds LEAST words, and ends SPAN sentences or holds ENOUGH words, is hashed to 128
bits over its words; the last run of a text is also taken to the text's end, and a text with less but LEAST words is one
run. Runs meet globally; of equal runs the first by (doc_id, text hash, place) stays, and every piece that any other one
covers goes. A piece goes with all up to the next one's start; the counts of sentences are counts of pieces.

A cut is settled by the NEAR - 1 words on either side. Of a passage of 4 NEAR + ENOUGH - 3 = 51 words with equal
sentence ends, NEAR - 1 words at each end may be cut differently; what is left holds a whole run wherever it begins.

Runs are counted by one hash, by partial sums before any shuffle, and the join back to the places of repeated runs splits
under skew, so a passage in a third of all documents stays a list of places, never a group in one task.

Defined results: a null or empty text has no sentences and stays empty; rows equal in doc_id and text are one
document; a null doc_id is the first; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import written
from .textvec import _BASE, _INVERSE, Words, _powers, chunks, mix

SPAN = 3
LEAST = 10
NEAR = 8
ENOUGH = 22

_ENDS = np.zeros(256, bool)
_ENDS[[0x0A, 0x21, 0x2E, 0x3F]] = True


def _least_of_some(key: np.ndarray, near: int) -> np.ndarray:
    """Whether each key is the least of some `near` consecutive ones; beyond both ends all are 0."""
    pad = np.zeros(near - 1, np.uint64)
    low = np.lib.stride_tricks.sliding_window_view(np.concatenate([pad, key, pad]), near).min(axis=1)
    return np.lib.stride_tricks.sliding_window_view(low, near).max(axis=1) == key if len(key) else np.zeros(0, bool)


class Sentences:
    """Sentences of a group of texts, long ones in pieces: begin (first byte), doc, and the place of the first word."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, near: int = NEAR):
        words = Words(data, offsets)
        n = len(words.code)
        ends = np.concatenate([[0], np.cumsum(_ENDS[data])])
        new = np.ones(n, bool)
        new[1:] = (words.doc[1:] != words.doc[:-1]) | (ends[words.starts[1:]] > ends[words.ends[:-1]])
        cut = new | _least_of_some(np.where(new, np.uint64(0), words.code | np.uint64(1)), near)
        first = np.flatnonzero(cut)
        self.begin, self.doc = words.starts[first], words.doc[first]
        #: Whether each piece opens a sentence.
        self.opens = new[first]
        #: Index of each piece's first word, and one past the last word.
        self.at = np.append(first, n)
        # Prefix sums give the hash of any run of words.
        powers, self.back = _powers(_BASE, n + 1), _powers(_INVERSE, n + 1)
        self.sums = []
        for seed in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
            total = np.zeros(n + 1, np.uint64)
            np.cumsum(mix(words.code ^ np.uint64(seed)) * powers[:n], out=total[1:])
            self.sums.append(total)
        #: First piece of each text, and one past the last.
        self.first = np.searchsorted(self.doc, np.arange(len(offsets)))

    def runs(self, span: int, least: int, enough: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[np.ndarray]]:
        """(first piece, end piece, whether it is a text's rest, two hashes) of every run."""
        n = len(self.doc)
        start = np.arange(n)
        last = self.first[self.doc + 1]
        nth = np.cumsum(self.opens) - 1
        # Past the last sentence of all, runs end outside any text.
        opening = np.append(np.flatnonzero(self.opens), np.arange(span) + n)
        words = lambda some: np.searchsorted(self.at, self.at[:n] + some)
        end = np.maximum(np.minimum(opening[nth + span], words(enough)), words(least))
        inside = end <= last
        # What follows a text's last run is too short for one of its own, so that run is also taken to the text's end.
        some = self.first[:-1][np.diff(self.first) > 0]
        counts = np.add.reduceat(inside, some, dtype=np.int64) if n else some
        rest = some + np.maximum(counts, 1) - 1
        rest = rest[(end[rest] != last[rest]) & (self.at[last[rest]] - self.at[rest] >= least)]
        is_rest = np.arange(int(inside.sum()) + len(rest)) >= inside.sum()
        start, end = np.append(start[inside], rest), np.append(end[inside], last[rest])
        a, b = self.at[start], self.at[end]
        return start, end, is_rest, [mix((total[b] - total[a]) * self.back[a] + (b - a).astype(np.uint64)) for total in self.sums]


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).alias("id"), F.xxhash64(text).alias("tie"), text.alias("text"))


def spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = SPAN, least: int = LEAST, near: int = NEAR, enough: int = ENOUGH) -> DataFrame:
    """Rows (h1, h2, id, tie, place): every run of sentences; place counts pieces from 0, and is -1 - place for a text's rest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, end, data, offsets in chunks(batch.column(2)):
                found = Sentences(data, offsets, near)
                start, _, rest, (h1, h2) = found.runs(span, least, enough)
                doc = found.doc[start]
                at = pa.array(first + doc)
                yield pa.RecordBatch.from_arrays([pa.array(h1.view(np.int64)), pa.array(h2.view(np.int64)), batch.column(0).take(at), batch.column(1).take(at), pa.array(np.where(rest, -1, 1) * (start - found.first[doc] + rest))], ["h1", "h2", "id", "tie", "place"])

    rows = _rows(docs, id_col, text_col)
    return rows.mapInArrow(run, f"h1 long, h2 long, id {rows.schema['id'].dataType.simpleString()}, tie long, place long")


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = SPAN, least: int = LEAST, near: int = NEAR, enough: int = ENOUGH) -> DataFrame:
    """Rows (doc_id, n_sentences, n_removed, n_chars_removed, text), one for each row of docs; text is what stays."""
    places = spans(docs, id_col, text_col, span, least, near, enough)
    where = F.struct(F.col("id").isNotNull().alias("known"), "id", "tie", "place")
    # Most runs occur once: only one hash of each is shuffled to find that out, and the runs left are few.
    met = places.groupBy("h1").agg(F.count("*").alias("n")).where("n > 1").select("h1")
    some = written(places.join(met, "h1"), "runs")
    repeated = some.groupBy("h1", "h2").agg(F.min(where).alias("keep"), F.count("*").alias("n")).where("n > 1").drop("n")
    later = some.join(repeated, ["h1", "h2"]).where(~where.eqNullSafe(F.col("keep"))).select("id", "tie", "place")
    gone = later.groupBy("id", "tie").agg(F.collect_set("place").alias("places")).toDF("gid", "gtie", "places")
    rows = _rows(docs, id_col, text_col)
    joined = rows.join(gone, rows["id"].eqNullSafe(gone["gid"]) & (rows["tie"] == gone["gtie"]), "left").select("id", "text", "places")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            runs = batch.column(2).to_pylist()
            total, removed, lost, texts = [], [], [], []
            for first, end, data, offsets in chunks(batch.column(1)):
                found = Sentences(data, offsets, near)
                start, end_of, rest, _ = found.runs(span, least, enough)
                ends = np.zeros(len(found.doc), np.int64)
                ends[start[~rest]] = end_of[~rest]
                for i in range(end - first):
                    a, b = int(found.first[i]), int(found.first[i + 1])
                    raw = data[offsets[i] : offsets[i + 1]].tobytes()
                    total.append(b - a)
                    if not runs[first + i]:
                        removed.append(0)
                        lost.append(0)
                        texts.append(raw)
                        continue
                    gone = np.zeros(b - a, bool)
                    for place in runs[first + i]:
                        gone[place if place >= 0 else -1 - place : ends[a + place] - a if place >= 0 else b - a] = True
                    bounds = np.append(found.begin[a:b], offsets[i + 1]) - offsets[i]
                    parts = [raw[: bounds[0]], *(raw[bounds[k] : bounds[k + 1]] for k in np.flatnonzero(~gone))]
                    kept = b"".join(parts)
                    removed.append(int(gone.sum()))
                    lost.append(len(raw.decode()) - len(kept.decode()))
                    texts.append(kept)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(lost, pa.int64()), pa.array(texts, pa.binary()).cast(pa.string())], ["doc_id", "n_sentences", "n_removed", "n_chars_removed", "text"])

    return joined.mapInArrow(cut, f"doc_id {rows.schema['id'].dataType.simpleString()}, n_sentences long, n_removed long, n_chars_removed long, text string")
