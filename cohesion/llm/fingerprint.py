"""Document fingerprints: bottom-k sketches of word-shingle hashes.

A sketch is the k smallest distinct 48-bit hashes of a text's five-word shingles, ascending, six big-endian bytes
each. Sketches merge across parts (the k smallest of their union), and estimate resemblance (share of shingles in
both), containment (share of one's shingles in the other) and the number of distinct shingles.

Defined results: a null text is empty and has an empty sketch; a text with one to four words has one shingle; a text
without words, but not empty, has its whole text as its only shingle; equal texts have equal sketches, and two empty
sketches resemble each other fully. Rows that repeat a doc_id are ordered by a hash of their text, null ids first.
"""

from __future__ import annotations

import base64
import hashlib
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from .textvec import Words, chunks, sorted_per_doc

K = 128
WORDS = 5
#: Keys sampled for each range of documents.
SAMPLED = 16
_BITS = 48


def sketches(texts: pa.Array, k: int = K, words: int = WORDS) -> list[np.ndarray]:
    """The sketch of each text as ascending uint64 values below 2**48."""
    out: list[np.ndarray] = []
    for first, end, data, offsets in chunks(texts):
        doc, code = Words(data, offsets).shingles(words)
        doc, code, _ = sorted_per_doc(doc, code >> np.uint64(64 - _BITS))
        bounds = np.searchsorted(doc, np.arange(end - first + 1))
        for i in range(end - first):
            a, b = bounds[i], bounds[i + 1]
            if a == b and offsets[i] < offsets[i + 1]:
                digest = hashlib.blake2b(data[offsets[i] : offsets[i + 1]].tobytes(), digest_size=_BITS // 8).digest()
                out.append(np.array([int.from_bytes(digest, "big")], np.uint64))
            else:
                out.append(code[a : min(b, a + k)])
    return out


def to_bytes(sketch: np.ndarray) -> bytes:
    return sketch.astype(">u8").view(np.uint8).reshape(-1, 8)[:, 2:].tobytes()


def from_bytes(raw: bytes) -> np.ndarray:
    wide = np.zeros((len(raw) // 6, 8), np.uint8)
    wide[:, 2:] = np.frombuffer(raw, np.uint8).reshape(-1, 6)
    return wide.view(">u8")[:, 0].astype(np.uint64)


def merged(parts: list[np.ndarray], k: int = K) -> np.ndarray:
    """The sketch of the union of the parts."""
    return np.unique(np.concatenate(parts))[:k] if parts else np.zeros(0, np.uint64)


def resemblance(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Estimated share of the shingles of either that both have; exact while their union has at most k."""
    if not len(a) and not len(b):
        return 1.0
    both = np.sort(np.concatenate([a, b]))
    twice = both[1:] == both[:-1]
    distinct = len(both) - int(twice.sum())
    if distinct <= k:
        return float(twice.sum() / distinct)
    new = np.append(True, ~twice)
    last = both[np.flatnonzero(new)[k - 1]]
    return float((twice & (both[1:] <= last)).sum() / k)


def distinct_count(a: np.ndarray, k: int = K) -> float:
    """Estimated number of distinct shingles; exact below k."""
    return float(len(a)) if len(a) < k else (k - 1) * 2.0**_BITS / (float(a[k - 1]) + 1)


def containment(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Estimated share of a's shingles that b has too."""
    if not len(a):
        return 1.0
    union = distinct_count(merged([a, b], k), k)
    return min(1.0, resemblance(a, b, k) * union / distinct_count(a, k))


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = K, words: int = WORDS) -> DataFrame:
    """Rows (id, sketch binary, n_shingles double): one for each row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = sketches(batch.column(1), k, words)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([to_bytes(s) for s in found], pa.binary()), pa.array([distinct_count(s, k) for s in found], pa.float64())], [id_col, "sketch", "n_shingles"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).cast("string")).mapInArrow(run, f"`{id_col}` {kind}, sketch binary, n_shingles double")


def merge_parts(found: DataFrame, by: str, k: int = K) -> DataFrame:
    """Rows (by, sketch, n_shingles): one sketch for each value of `by`, of everything its rows hold.

    Each task first folds what it has into one sketch a value, so a value with a third of all rows sends no more
    than one sketch a task; the second fold streams over these.
    """
    kind = found.schema[by].dataType.simpleString()

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict = {}
        for batch in batches:
            for key, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                own = from_bytes(raw or b"")
                kept[key] = merged([kept[key], own], k) if key in kept else own
                if len(kept) >= 20_000:
                    yield table(kept)
                    kept = {}
        yield table(kept)

    def table(kept: dict) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(kept), types[0]), pa.array([to_bytes(s) for s in kept.values()], pa.binary()), pa.array([distinct_count(s, k) for s in kept.values()], pa.float64())], [by, "sketch", "n_shingles"])

    from pyspark.sql.pandas.types import to_arrow_type

    types = [to_arrow_type(found.schema[by].dataType)]
    out = f"`{by}` {kind}, sketch binary, n_shingles double"
    partial = found.select(by, "sketch").mapInArrow(fold, out)

    def last(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, own, started = None, None, False
        for batch in batches:
            for x, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if started and x == key:
                    own = merged([own, from_bytes(raw)], k)
                else:
                    if started:
                        yield table({key: own})
                    key, own, started = x, from_bytes(raw), True
        if started:
            yield table({key: own})

    return partial.select(by, "sketch").repartition(by).sortWithinPartitions(by).mapInArrow(last, out)


def compare_with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = K, words: int = WORDS) -> DataFrame:
    """Fingerprints of each text, of its edited text and likeness to both the edited and the next document's text.

    The edited text has its last floor(n/4) code points replaced by the first as many of the next document by id.
    Texts are dealt once, by ranges of id; the first document of each range goes to the range before as well.
    """
    spark = docs.sparkSession
    ranges = 4 * max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    keyed = rows.withColumn("tie", F.xxhash64("text"))
    # The driver sees a bounded sample of keys, the bounds it yields, and the first key of each range.
    blank = F.lit("" if isinstance(rows.schema["id"].dataType, StringType) else 0).cast(rows.schema["id"].dataType)
    keyed = keyed.withColumn("known", F.col("id").isNotNull()).withColumn("key", F.coalesce("id", blank))
    some = sorted({(r["known"], r["key"], r["tie"]) for r in keyed.select("known", "key", "tie").orderBy(F.xxhash64("id", "tie")).limit(SAMPLED * ranges).collect()})
    bounds = [some[i * len(some) // ranges] for i in range(1, ranges)] if some else []

    @F.pandas_udf("int")
    def dealt(known, keys, ties):
        import pandas as pd

        none = sum(not b[0] for b in bounds)
        names = np.array([b[1] for b in bounds[none:]])
        null = ~known.to_numpy(bool)
        left, right = (np.full(len(keys), none) for _ in range(2))
        if len(names) and not null.all():
            values = keys.to_numpy()[~null].astype(names.dtype if names.dtype.kind != "U" else "U")
            left[~null], right[~null] = (none + np.searchsorted(names, values, side) for side in ("left", "right"))
        left[null], right[null] = 0, none
        # Rows whose id is a bound are dealt by the second part of the key.
        every = [b[2] for b in bounds]
        for i in np.flatnonzero(left < right).tolist():
            left[i] = bisect_right(every, ties.iloc[i], int(left[i]), int(right[i]))
        return pd.Series(left.astype(np.int32), dtype="int32")

    at = dealt(F.col("known"), F.col("key"), F.col("tie"))
    firsts = keyed.select(at.alias("part"), "id", "tie").groupBy("part").agg(F.min(F.struct(F.col("id").isNotNull().alias("x"), "id", "tie")).alias("f")).orderBy("part").collect()
    parts = [r["part"] for r in firsts]
    also = {(r["f"]["id"], r["f"]["tie"]): parts[i - 1] for i, r in enumerate(firsts)}
    kind = rows.schema["id"].dataType.simpleString()
    tails = F.broadcast(spark.createDataFrame([(i, t, p) for (i, t), p in also.items()], f"tid {kind}, ttie long, also int"))
    joined = keyed.withColumn("part", at).join(tails, keyed["id"].eqNullSafe(tails["tid"]) & (keyed["tie"] == tails["ttie"]), "left").drop("tid", "ttie")
    own = F.struct(F.col("part").alias("part"), F.lit(False).alias("tail"))
    placed = F.when(F.col("also").isNull(), F.array(own)).otherwise(F.array(own, F.struct(F.col("also").alias("part"), F.lit(True).alias("tail"))))
    dealt_rows = joined.withColumn("p", F.explode(placed)).select("p.part", "p.tail", "id", "tie", "text")
    sorted_rows = dealt_rows.repartition("part").sortWithinPartitions("part", "tail", F.col("id").asc_nulls_first(), "tie").drop("tie")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = None
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                kept, out = step(kept, batch.slice(at, 256))
                yield out

    def step(kept, rows):
        part, tail, ids, texts = (c.to_pylist() for c in rows.columns)
        own = sketches(rows.column(3), k, words)
        if kept:
            part, tail, ids, texts, own = ([x, *y] for x, y in zip(kept, (part, tail, ids, texts, own)))
        last = len(part) - 1
        use = [i for i in range(last) if not tail[i] and part[i] == part[i + 1]]
        edited = []
        for i in use:
            cut = len(texts[i]) // 4
            edited.append(texts[i][: len(texts[i]) - cut] + texts[i + 1][:cut])
        other = sketches(pa.array(edited, pa.string()), k, words)
        show = lambda s: base64.b64encode(to_bytes(s)).decode()
        out = pa.RecordBatch.from_arrays(
            [
                pa.array([ids[i] for i in use], rows.schema.field(2).type),
                pa.array([len(texts[i]) for i in use], pa.int64()),
                pa.array([hashlib.sha256(t.encode()).hexdigest() for t in edited], pa.string()),
                pa.array([show(own[i]) for i in use], pa.string()),
                pa.array([show(s) for s in other], pa.string()),
                pa.array([resemblance(own[i], s, k) for i, s in zip(use, other)], pa.float64()),
                pa.array([resemblance(own[i], own[i + 1], k) for i in use], pa.float64()),
                pa.array([distinct_count(own[i], k) for i in use], pa.float64()),
                pa.array([containment(own[i], s, k) for i, s in zip(use, other)], pa.float64()),
            ],
            ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "n_shingles", "contained_in_edited"],
        )
        return (part[last], tail[last], ids[last], texts[last], own[last]), out

    return sorted_rows.mapInArrow(run, f"doc_id {kind}, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, n_shingles double, contained_in_edited double")
