"""Benchmark decontamination: a prefix-filtered set join of item windows with whole documents.

1. Each item is cut into windows of 13 words (an item of fewer words is one window), and windows into shingles of five
   words (a shorter window is one shingle). A bitmap of the shingles' hashes, its size bounded, goes to every task.
2. One pass over the documents finds their segments: stretches of words whose shingles are all in the bitmap, and that
   are long enough for the shortest window (the length bound). Everything later works on segments, which are few.
3. Shingles are ordered by how often they occur in segments. The rarest of a window is its prefix: a document that holds
   the window holds that shingle, and a window with a shingle that no segment has is nowhere. Segments and windows are
   joined on prefixes; the prefix's place fixes where the window would begin (the positional bound), and there the words
   themselves are compared, so hashes never decide.
4. Hit words and items are summed up for each different text.

Items, windows and segments are tables; only the bitmap reaches the driver. Its bits are 16 a word of the benchmark, at
most BITS_MOST; where that fills up, more segments are found, not fewer.

Defined results: a null or empty text has no words and is clean; an item without words has no windows; repeated items
count each; a null item_id reads "null"; no items at all leave every document clean; rows are judged by their text alone,
so repeated rows and null ids need no care; other columns are ignored (or kept as they are by clean()).
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import written
from .textvec import _LOWER, Words, chunks, mix

WINDOW = 13
SHINGLE = 5
#: Share of a document's words inside benchmark windows from which it counts as contaminated: 1 in SHARE.
SHARE = 20
#: Bounds of the bitmap of shingle hashes.
BITS_LEAST, BITS_MOST = 1 << 20, 1 << 27
#: Copies of the prefixes, so that a shingle of very many documents is met in several tasks.
SALTS = 8

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_GAP = re.compile(rb"[\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def grams(words: Words, size: int) -> np.ndarray:
    """A hash of the `size` words from each word on; 0 where they would leave the text."""
    n = len(words.code)
    out = np.zeros(n, np.uint64)
    if n >= size:
        total = np.full(n - size + 1, size, np.uint64)
        for k in range(size):
            total = total * np.uint64(0x100000001B3) + words.code[k : n - size + 1 + k]
        out[: len(total)] = np.where(words.doc[: len(total)] == words.doc[size - 1 :], mix(total) | np.uint64(1), np.uint64(0))
    return out


def _text(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def _items(benchmark: DataFrame, window: int, item_col: str, text_col: str) -> DataFrame:
    """(item, uid, n, w): words of each item that has any, and its window size."""
    w = F.regexp_extract_all(F.translate(_text(text_col), _UPPER, _UPPER.lower()), F.lit(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"), 0)
    rows = benchmark.select(F.coalesce(F.col(item_col).cast("string"), F.lit("null")).alias("item"), F.monotonically_increasing_id().alias("uid"), w.alias("w"))
    return rows.where(F.size("w") > 0).select("item", "uid", F.least(F.size("w"), F.lit(window)).alias("n"), "w")


def _runs(words: str, size: Column) -> Column:
    """All runs of `size` words of an array of words, each as one text."""
    return F.transform(F.sequence(F.lit(1), F.size(words) - size + 1), lambda i: F.array_join(F.slice(words, i, size), " "))


class Sieve:
    """What a task needs to find segments: sizes of shingles, how many must follow each other, and the bitmap."""

    def __init__(self, items: DataFrame):
        found = items.groupBy("n").agg(F.sum(F.size("w")).alias("words")).collect()  # at most 13 rows
        #: (shingle size, shingles in a row that the shortest window of that kind has)
        self.kinds = []
        long = [r["n"] for r in found if r["n"] >= SHINGLE]
        if long:
            self.kinds.append((SHINGLE, min(long) - SHINGLE + 1))
        self.kinds += [(r["n"], 1) for r in sorted(found) if r["n"] < SHINGLE]
        total = sum(r["words"] for r in found)
        self.bits = min(BITS_MOST, max(BITS_LEAST, 1 << (16 * total).bit_length()))
        bits = self.bits

        def spots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                size = np.asarray(batch.column(1)).clip(0, SHINGLE)
                for first, end, data, offsets in chunks(batch.column(0)):
                    words = Words(data, offsets)
                    own = size[first:end][words.doc]
                    for s in np.unique(own).tolist():
                        code = grams(words, s)[own == s]
                        yield pa.RecordBatch.from_arrays([pa.array(np.unique(code[code > 0] & np.uint64(bits - 1)).astype(np.int64) + 1)], ["bit"])

        rows = items.select(F.array_join("w", " ").alias("t"), F.col("n").cast("long")).mapInArrow(spots, "bit long")
        held = rows.groupBy(F.bitmap_bucket_number("bit").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("bit")).alias("m"))
        packed = np.zeros(bits // 8, np.uint8)
        for r in held.collect():  # at most bits / 32768 rows of 4 KB
            packed[(r["b"] - 1) * 4096 : r["b"] * 4096] = np.frombuffer(r["m"], np.uint8)
        self.packed = packed

    def covered(self, words: Words) -> np.ndarray:
        """Whether each word is in a stretch that may hold a window."""
        depth = np.zeros(len(words.code) + 1, np.int64)
        for size, need in self.kinds:
            code = grams(words, size)
            at = code & np.uint64(self.bits - 1)
            seen = (code > 0) & ((self.packed[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 > 0)
            # Runs of neighbours within a text.
            start = np.flatnonzero(seen & ~np.concatenate([[False], seen[:-1] & (words.doc[1:] == words.doc[:-1])])) if len(seen) else np.zeros(0, np.int64)
            stop = np.flatnonzero(seen & ~np.concatenate([seen[1:] & (words.doc[1:] == words.doc[:-1]), [False]])) if len(seen) else start
            long = stop - start + 1 >= need
            np.add.at(depth, start[long], 1)
            np.add.at(depth, stop[long] + size, -1)
        return np.cumsum(depth)[:-1] > 0


def _scanned(docs: DataFrame, sieve: Sieve, text_col: str, id_col: str | None) -> DataFrame:
    """(doc_id, key, n_words, segs): segments of every row, or, without id_col, of rows that have any."""
    kind = docs.schema[id_col].dataType.simpleString() if id_col else "int"
    held = docs.sparkSession.sparkContext.broadcast(sieve)  # of bounded size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = held.value
        for batch in batches:
            n_words, at, text, row = [], [], [], []
            for first, end, data, offsets in chunks(batch.column(2)):
                words = Words(data, offsets)
                n_words.append(np.diff(words.first))
                inside = own.covered(words)
                if not inside.any():
                    continue
                low = _LOWER[data]
                edge = np.flatnonzero(inside & ~np.concatenate([[False], inside[:-1] & (words.doc[1:] == words.doc[:-1])]))
                last = np.flatnonzero(inside & ~np.concatenate([inside[1:] & (words.doc[1:] == words.doc[:-1]), [False]]))
                row += (first + words.doc[edge]).tolist()
                at += (edge - words.first[words.doc[edge]]).tolist()
                text += [_GAP.sub(b" ", low[a:b].tobytes()) for a, b in zip(words.starts[edge].tolist(), words.ends[last].tolist())]
            total = np.concatenate(n_words) if n_words else np.zeros(0, np.int64)
            offsets = np.searchsorted(np.array(row, np.int64), np.arange(batch.num_rows + 1))
            segs = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.StructArray.from_arrays([pa.array(at, pa.int32()), pa.array(text, pa.binary()).cast(pa.string())], ["at", "text"]))
            out = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(total, pa.int64()), segs], ["doc_id", "key", "n_words", "segs"])
            yield out if id_col else out.filter(pa.array(np.diff(offsets) > 0))

    text = _text(text_col)
    rows = docs.select((F.col(id_col) if id_col else F.lit(0)).alias("doc_id"), F.unhex(F.md5(text.cast("binary"))).alias("key"), text.alias("text"))
    return written(rows.mapInArrow(run, f"doc_id {kind}, key binary, n_words long, segs array<struct<at:int,text:string>>"), "segments")


def _places(segments: DataFrame, sieve: Sieve, window: int) -> DataFrame:
    """(key, word, shingle, lead, near): every shingle of the segments with the words that a window through it can have."""

    def of(size: int):
        def one(i: Column) -> Column:
            low = F.greatest(F.lit(1), i - (window - size))
            return F.struct((F.col("at") + i - 1).alias("word"), F.array_join(F.slice("w", i, size), " ").alias("shingle"), (i - low).alias("lead"), F.slice("w", low, i - low + window).alias("near"))

        return one

    out = None
    for size, _ in sieve.kinds:
        rows = segments.where(F.size("w") >= size).select("key", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - size + 1), of(size))).alias("x")).select("key", "x.*")
        out = rows if out is None else out.unionByName(rows)
    return out


def _hits(scanned: DataFrame, items: DataFrame, sieve: Sieve, window: int) -> DataFrame:
    """(key, n_hit, items): of every different text with an occurring window; items are ids, sorted, one for each item."""
    # Rows of one text have the same segments.
    once = scanned.where(F.size("segs") > 0).groupBy("key").agg(F.first("segs").alias("segs"))
    segments = written(once.select("key", F.explode("segs").alias("s")).select("key", "s.at", F.split("s.text", " ").alias("w")), "segments")
    places = _places(segments, sieve, window)
    windows = written(items.select("item", "uid", "n", F.explode(_runs("w", F.col("n"))).alias("window")), "windows")
    size = F.least(F.col("n"), F.lit(SHINGLE))
    each = windows.select("window", "n").distinct().select("window", "n", F.split("window", " ").alias("w")).select("window", "n", F.posexplode(_runs("w", size)).alias("place", "shingle"))
    often = places.groupBy("shingle").agg(F.count("*").alias("often"))
    ordered = each.join(often, "shingle", "left").groupBy("window", "n").agg(F.min(F.struct(F.coalesce("often", F.lit(0)).alias("often"), "shingle", "place")).alias("p"))
    prefixes = ordered.where("p.often > 0").select("window", "n", "p.shingle", "p.place").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    met = places.withColumn("salt", F.pmod(F.xxhash64("key", "word"), F.lit(SALTS)).cast("int")).join(prefixes, ["shingle", "salt"])
    begin = F.col("lead") - F.col("place")
    met = met.where((begin >= 0) & (F.size("near") - begin >= F.col("n"))).where(F.array_join(F.slice("near", begin + 1, F.col("n")), " ") == F.col("window"))
    hits = written(met.select("key", (F.col("word") - F.col("place")).alias("start"), "n", "window"), "hits")
    spans = hits.groupBy("key").agg(F.array_sort(F.collect_set(F.struct("start", (F.col("start") + F.col("n")).alias("stop")))).alias("s"))
    zero = F.struct(F.lit(0).alias("n"), F.lit(0).alias("reach"))
    joined = F.aggregate("s", zero, lambda a, x: F.struct((a["n"] + F.greatest(F.lit(0), x["stop"] - F.greatest(x["start"], a["reach"]))).alias("n"), F.greatest(a["reach"], x["stop"]).alias("reach")), lambda a: a["n"])
    named = hits.select("key", "window").distinct().join(windows.select("window", "item", "uid"), "window").groupBy("key").agg(F.array_sort(F.collect_set(F.struct("item", "uid"))).alias("i"))
    return spans.select("key", joined.cast("long").alias("n_hit")).join(named.select("key", F.transform("i", lambda x: x["item"]).alias("items")), "key")


def _contaminated() -> Column:
    return (F.col("n_hit") > 0) & (SHARE * F.col("n_hit") >= F.col("n_words"))


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id") -> DataFrame:
    """Rows (doc_id, n_words, n_hit, n_items, items_sha256, contaminated, items), one for each row of docs."""
    items = written(_items(benchmark, window, item_col, "text"), "items")
    sieve = Sieve(items)
    scanned = _scanned(docs, sieve, text_col, id_col)
    none = F.lit(0).cast("long"), F.array().cast("array<string>")
    # Rows without segments, nearly all, are not shuffled.
    rows = scanned.where(F.size("segs") == 0).select("doc_id", "n_words", none[0].alias("n_hit"), none[1].alias("items"))
    if sieve.kinds:
        some = scanned.where(F.size("segs") > 0).select("doc_id", "key", "n_words").join(_hits(scanned, items, sieve, window), "key", "left")
        rows = rows.unionByName(some.select("doc_id", "n_words", F.coalesce("n_hit", none[0]).alias("n_hit"), F.coalesce("items", none[1]).alias("items")))
    return rows.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), _contaminated().alias("contaminated"), "items")


def clean(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id") -> DataFrame:
    """The rows of docs that are not contaminated, with the columns of docs."""
    items = written(_items(benchmark, window, item_col, "text"), "items")
    sieve = Sieve(items)
    if not sieve.kinds:
        return docs
    scanned = _scanned(docs, sieve, text_col, None)
    counts = scanned.groupBy("key").agg(F.first("n_words").alias("n_words"))
    bad = written(_hits(scanned, items, sieve, window).join(counts, "key").where(_contaminated()).select(F.col("key").alias("_bad")), "contaminated")
    return docs.join(bad, F.unhex(F.md5(_text(text_col).cast("binary"))) == bad["_bad"], "left_anti").select(*docs.columns)
