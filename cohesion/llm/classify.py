"""Supervised subword embeddings: hashed word and character n-gram vectors, averaged per document, linear softmax.

Training is plain numpy stochastic gradient descent on a bounded sample of labelled rows; scoring covers every whole
text. For scoring, the product of embeddings and output layer is folded into one table of class scores per bucket, so
a text's logits are means of table rows. Features are the bytes' n-grams and the words (with case and marks kept).

Defined results: a null text is empty, and a text without features gets the class prior; rows with a null label never
train; a table without labelled rows gives a model that knows no class (scores 0.5, predictions null).
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .textvec import chunks, mix

#: Documented bounds of training: rows, and characters learnt from in each.
SAMPLE_ROWS, SAMPLE_CHARS = 4000, 20_000
GRAMS = (2, 3, 4)
BUCKETS = 1 << 16
DIM = 10
EPOCHS = 6
RATE = 0.5


def features(data: np.ndarray, offsets: np.ndarray, buckets: int = BUCKETS, grams: tuple[int, ...] = GRAMS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text index, bucket) arrays, one pair for each n-gram length and one for the words of a group of texts."""
    n = len(data)
    doc = np.repeat(np.arange(len(offsets) - 1, dtype=np.int32), np.diff(offsets))
    wide = data.astype(np.uint32)
    shift = np.uint32(32 - int(buckets).bit_length() + 1)
    code = wide.copy()
    for size in range(2, max(grams) + 1):
        if n < size:
            return
        code = code[: n - size + 1] * np.uint32(0x01000193) + wide[size - 1 :] + np.uint32(1)
        if size in grams:
            same = doc[: n - size + 1] == doc[size - 1 :]
            mixed = (code ^ (code >> np.uint32(15))) * np.uint32(0x9E3779B1 + 2 * size)
            yield doc[: n - size + 1][same], (mixed >> shift)[same]
    # Words: runs between white space, hashed by sums over position-weighted bytes.
    gap = data <= 0x20
    edge = np.ones(n + 1, bool)
    edge[1:n] = (gap[1:] != gap[:-1]) | (doc[1:] != doc[:-1])
    at = np.flatnonzero(edge)
    starts, ends = at[:-1], at[1:]
    kept = ~gap[starts]
    starts, ends = starts[kept], ends[kept]
    if len(starts):
        place = np.arange(n, dtype=np.uint64) - np.repeat(at[:-1], np.diff(at)).astype(np.uint64)
        weighed = mix((data.astype(np.uint64) << np.uint64(32)) + place)
        total = np.concatenate([[np.uint64(0)], np.cumsum(weighed)])
        yield doc[starts], (mix(total[ends] - total[starts]) >> np.uint64(64 - int(buckets).bit_length() + 1)).astype(np.uint32)


@dataclass
class Model:
    classes: list
    table: np.ndarray  # buckets x classes: embedding times output layer
    bias: np.ndarray

    def scores(self, texts: pa.Array) -> np.ndarray:
        """Probability of each class, a row for each text."""
        if not self.classes:
            return np.zeros((len(texts), 0))
        out = []
        for first, end, data, offsets in chunks(texts):
            m, k = end - first, len(self.classes)
            total, count = np.zeros((m, k)), np.zeros(m)
            for doc, bucket in features(data, offsets, len(self.table)):
                count += np.bincount(doc, minlength=m)
                # Two classes need one difference of scores only.
                for c in range(1 if k == 2 else 0, k):
                    total[:, c] += np.bincount(doc, self.columns[c][bucket], minlength=m)
            logits = total / np.maximum(count, 1)[:, None] + self.bias
            logits -= logits.max(axis=1, keepdims=True)
            p = np.exp(logits)
            out.append(p / p.sum(axis=1, keepdims=True))
        return np.concatenate(out) if out else np.zeros((0, len(self.classes)))

    def __post_init__(self):
        if len(self.classes) == 2:
            self.table = self.table - self.table[:, :1]
            self.bias = self.bias - self.bias[0]
        self.columns = [np.ascontiguousarray(self.table[:, c], np.float32) for c in range(self.table.shape[1])]


def train(texts: list[str], labels: list, buckets: int = BUCKETS, dim: int = DIM, epochs: int = EPOCHS, rate: float = RATE, seed: int = 7) -> Model:
    """Fits embeddings and output layer by stochastic gradient descent over mini-batches."""
    classes = sorted(set(labels))
    k = len(classes)
    if not k:
        return Model([], np.zeros((buckets, 0), np.float32), np.zeros(0))
    y = np.array([classes.index(v) for v in labels])
    rng = np.random.default_rng(seed)
    embed = rng.normal(0, 1 / dim, (buckets, dim)).astype(np.float32)
    layer = np.zeros((dim, k), np.float32)
    bias = np.zeros(k, np.float32)
    # Each document once as distinct buckets and their shares.
    rows: list[tuple[np.ndarray, np.ndarray]] = []
    for first, end, data, offsets in chunks(pa.array(texts, pa.string())):
        parts = list(features(data, offsets, buckets))
        doc = np.concatenate([d for d, _ in parts]) if parts else np.zeros(0, np.int32)
        bucket = np.concatenate([b for _, b in parts]) if parts else np.zeros(0, np.uint32)
        key, times = np.unique(doc.astype(np.int64) * buckets + bucket, return_counts=True)
        bounds = np.searchsorted(key, np.arange(end - first + 1) * buckets)
        for i in range(end - first):
            own = slice(bounds[i], bounds[i + 1])
            rows.append(((key[own] % buckets).astype(np.int32), (times[own] / max(1, times[own].sum())).astype(np.float32)))
    weight = len(y) / (k * np.maximum(1, np.bincount(y, minlength=k)))
    steps, total = 0, epochs * (len(rows) // 16 + 1)
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(order), 16):
            own = order[at : at + 16]
            lengths = np.array([len(rows[i][0]) for i in own])
            if not lengths.sum():
                continue
            own, lengths = own[lengths > 0], lengths[lengths > 0]
            buck = np.concatenate([rows[i][0] for i in own])
            share = np.concatenate([rows[i][1] for i in own])
            edges = np.cumsum(lengths) - lengths
            hidden = np.add.reduceat(embed[buck] * share[:, None], edges, axis=0)
            z = hidden @ layer + bias
            z -= z.max(axis=1, keepdims=True)
            p = np.exp(z)
            p /= p.sum(axis=1, keepdims=True)
            p[np.arange(len(own)), y[own]] -= 1
            p *= weight[y[own]][:, None]
            lr = rate * (1 - steps / total)
            back = p @ layer.T
            layer -= lr * hidden.T @ p
            bias -= lr * p.sum(axis=0) / 16
            grad = np.repeat(back, lengths, axis=0) * (share * lr * 40)[:, None]
            uniq, where = np.unique(buck, return_inverse=True)
            for d in range(dim):
                embed[uniq, d] -= np.bincount(where, grad[:, d], minlength=len(uniq)).astype(np.float32)
            steps += 1
    return Model(classes, embed @ layer, bias.astype(np.float64))


def sampled(docs: DataFrame, label: DataFrame | str, rows: int = SAMPLE_ROWS) -> DataFrame:
    """(t, y): a bounded sample of labelled rows of docs (doc_id, text), the same on every run: the smallest hashes of doc_id.

    label: a column of docs, or a table (doc_id, y). The bound is taken on ids; only their texts then move.
    """
    known = docs.select(F.col("doc_id").alias("_id"), F.col(label).alias("_y")) if isinstance(label, str) else label.toDF("_id", "_y")
    chosen = known.where("_y is not null and _id is not null").groupBy("_id").agg(F.max("_y").alias("_y")).orderBy(F.xxhash64("_id"), "_id").limit(rows)
    # At most `rows` pairs of numbers: a proven bound.
    texts = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("t")).join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))
    # Of a long text a piece from its middle is learnt from, so what reaches the fitting task is bounded in bytes too;
    # scoring reads whole texts. Ids that repeat could bring more rows than were chosen.
    n = F.char_length("t")
    piece = F.when(n <= SAMPLE_CHARS, F.col("t")).otherwise(F.substring("t", ((n - SAMPLE_CHARS) / 2).cast("int") + 1, F.lit(SAMPLE_CHARS)))
    return texts.select(piece.alias("t"), F.col("_y").alias("y")).limit(2 * rows)


def fitted(found: DataFrame, fit: Callable[[list[str], list], tuple[Model, float]]) -> tuple[Model, float]:
    """The model and figure that fit makes of the texts and labels of a sample, in order; a task fits, not the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted((t, y) for b in batches for t, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist()))
        model, figure = fit([t for t, _ in rows], [y for _, y in rows])
        made = pickle.dumps((model.classes, model.table, model.bias, figure))
        yield pa.RecordBatch.from_arrays([pa.array([made], pa.binary())], ["made"])

    made = found.repartition(1).mapInArrow(run, "made binary").first()
    if made is None:
        return fit([], [])
    classes, table, bias, figure = pickle.loads(made["made"])
    return Model(classes, table, bias), figure


def sample(docs: DataFrame, label: DataFrame | str, rows: int = SAMPLE_ROWS) -> tuple[list[str], list]:
    """Texts and labels of sampled(), in order, on the driver; fits don't need them there."""
    found = sorted((r["t"], r["y"]) for r in sampled(docs, label, rows).collect())
    return [t for t, _ in found], [y for _, y in found]


def has_letter(text: str | None) -> bool:
    """Whether a text has any letter of any script."""
    return bool(text) and any(c.isalpha() for c in text)


def held_out(id_col: str, folds: int, fold: int) -> Column:
    """Whether a row's crc32 of its id's decimal text falls in the fold kept from training; a null id does not."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(folds)) == fold, F.lit(False))
