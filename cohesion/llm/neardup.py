"""Near-duplicate documents by weighted minwise hashing over hierarchical Poisson processes.

A text is the multiset of its five-word shingles. Each shingle owns independent Poisson processes over dyadic weight
ranges (0,1], (1,2], (2,4], ...; the range that its weight ends in is thinned to the weight. Every point falls into
one of m slots, and a slot keeps its first point. Two texts share a slot's point with a probability equal to their
weighted Jaccard similarity. Points are drawn in order and a process stops once it is later than all slots of its
text, so the work is about shingles + m ln m points a text, not shingles times m.

Equal texts are folded into one class first. Signatures are cut in bands; classes that share a band meet in a bucket,
where short sketches and the size bound rule out unlike pairs. Candidates are then taken in two rounds: stars around
the best-connected members, verified exactly on the multisets and joined to components; then what could still connect
different components: a few candidate pairs, verified too, or, where a bucket has many, the exact overlaps of its
members by one matrix product within a task, of which only a spanning forest leaves it. What is never compared lies in
one component already, so no link between different texts is lost, and no group is expanded into all its pairs.
Buckets beyond BUCKET members are split into blocks and handled by pairs of blocks.

Defined results: a null text is empty; all empty texts are one class, and texts without words are only like equal
texts; texts of one to four words are one shingle; a class is named by its least doc_id (a null id only if it has no
other); repeated rows are members of their class; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import star_labels
from ..session import written
from .textvec import Words, chunks, mix, sorted_per_doc

WORDS = 5
SIMILARITY = 0.8
BANDS, ROWS = 20, 5
#: Sketch: slots compared in a bucket, half a byte each; pairs estimated below SURE under the threshold are left out
#: (five standard deviations, below one in a million).
SLOTS, SURE = 64, 0.25
#: Members of a bucket that one task compares with each other.
BUCKET = 4096
#: Their mean number of shingles at most; longer texts make more blocks.
SHINGLES = 1000
#: Candidate pairs a member up to which a bucket names pairs in the second round.
SPARSE = 2

_GOLD = np.uint64(0x9E3779B97F4A7C15)


def signatures(doc: np.ndarray, code: np.ndarray, weight: np.ndarray, docs: int, m: int) -> np.ndarray:
    """(docs, m) first points of each slot, from distinct (doc, code) rows with integer or real weights."""
    best = np.full(docs * m, np.inf)
    # One process for each weight range that begins below the weight.
    top = np.where(weight > 1, np.ceil(np.log2(np.maximum(weight, 1))).astype(np.int64), 0)
    row = np.repeat(np.arange(len(doc)), top + 1)
    level = np.arange(len(row)) - np.repeat(np.cumsum(top + 1) - (top + 1), top + 1)
    low = np.where(level == 0, 0.0, 2.0 ** (level - 1))
    width = np.where(level == 0, 1.0, low)
    seed = mix(code[row] + level.astype(np.uint64) * np.uint64(0xA0761D6478BD642F))
    owner, limit = doc[row].astype(np.int64), weight[row].astype(np.float64)
    thin = low + width > limit
    time = np.zeros(len(row))
    step = 0
    while len(seed):
        step = (step + int(_GOLD)) & 0xFFFFFFFFFFFFFFFF
        draw = mix(seed + np.uint64(step))
        time = time - np.log(((draw >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / width
        other = mix(draw ^ _GOLD)
        slot = owner * m + ((other >> np.uint64(32)) * np.uint64(m) >> np.uint64(32)).astype(np.int64)
        if thin.any():
            height = low + width * ((other & np.uint64(0xFFFFFFFF)).astype(np.float64) + 1) * 2.0**-32
            kept = ~thin | (height <= limit)
            np.minimum.at(best, slot[kept], time[kept])
        else:
            np.minimum.at(best, slot, time)
        alive = time < best.reshape(docs, m).max(axis=1)[owner]
        seed, owner, limit, thin, time, low, width = (x[alive] for x in (seed, owner, limit, thin, time, low, width))
    return best.reshape(docs, m)


def _bands(best: np.ndarray, bands: int, rows: int) -> np.ndarray:
    bits = best.view(np.uint64).reshape(len(best), -1)[:, : bands * rows].reshape(len(best), bands, rows)
    total = np.broadcast_to(np.arange(bands, dtype=np.uint64), bits.shape[:2]).copy()
    for k in range(rows):
        total = mix(total * np.uint64(0x100000001B3) + bits[:, :, k])
    return total


def _sketch(best: np.ndarray) -> np.ndarray:
    low = (mix(best[:, :SLOTS].view(np.uint64).reshape(len(best), -1)) & np.uint64(15)).astype(np.uint8)
    return low[:, ::2] | (low[:, 1::2] << 4)


def _text_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).alias("id"), text.alias("text"), F.unhex(F.md5(text.cast("binary"))).alias("cls"))


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """One row for each different text: (cls, rep, copies, total, bands, sketch); total is its number of shingles."""
    m = max(bands * rows, SLOTS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total, band, sketch = [], [], []
            for first, end, data, offsets in chunks(batch.column(1)):
                doc, code, times = sorted_per_doc(*Words(data, offsets).shingles(words))
                best = signatures(doc, code, times, end - first, m)
                some = np.bincount(doc, times, minlength=end - first).astype(np.int64)
                total += some.tolist()
                bits = _bands(best, bands, rows)
                band += [b if n else [] for b, n in zip(bits.view(np.int64).tolist(), some.tolist())]
                sketch += [s.tobytes() for s in _sketch(best)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array(total, pa.int64()), pa.array(band, pa.list_(pa.int64())), pa.array(sketch, pa.binary())], ["id", "cls", "total", "bands", "sketch"]
            )

    texts = _text_rows(docs, id_col, text_col)
    kind = texts.schema["id"].dataType.simpleString()
    found = texts.mapInArrow(run, f"id {kind}, cls binary, total long, bands array<long>, sketch binary")
    return found.groupBy("cls").agg(F.min("id").alias("rep"), F.count("*").alias("copies"), F.first("total").alias("total"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch"))


def _met(found: DataFrame, limit: int) -> DataFrame:
    """Members by bucket, (bucket, lo, hi, blk, ...): a bucket beyond the limit is dealt to pairs of its blocks."""
    rows = found.select("*", F.explode("bands").alias("bucket")).drop("bands")
    parts = F.ceil(F.greatest(F.count("*") / limit, F.sum("total") / (limit * SHINGLES))).cast("int")
    large = rows.groupBy("bucket").agg(parts.alias("k")).where("k > 1")
    dealt = rows.join(large, "bucket", "left").withColumn("blk", F.when(F.col("k").isNull(), 0).otherwise(F.pmod(F.xxhash64("cls"), F.col("k")).cast("int")))
    others = F.sequence(F.lit(0), F.coalesce(F.col("k"), F.lit(1)) - 1)
    return dealt.withColumn("j", F.explode(others)).select("bucket", F.least("blk", "j").alias("lo"), F.greatest("blk", "j").alias("hi"), *[c for c in dealt.columns if c not in ("bucket", "k")])


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows of each (bucket, lo, hi), from batches sorted by them."""
    kept: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        key = np.stack([np.asarray(batch.column(k)).astype(np.int64) for k in range(3)])
        edges = [0, *(np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
        for a, b in zip(edges, edges[1:]):
            own = tuple(key[:, a].tolist())
            if kept and own != last:
                yield pa.Table.from_batches(kept)
                kept = []
            kept.append(batch.slice(a, b - a))
            last = own
    if kept:
        yield pa.Table.from_batches(kept)


def _near(group: pa.Table, similarity: float, label: np.ndarray | None) -> np.ndarray:
    """Which members of a bucket may be similar enough, by size and sketch; with labels, only across labels."""
    n, blk = np.asarray(group.column("total")), np.asarray(group.column("blk"))
    packed = np.frombuffer(b"".join(group.column("sketch").to_pylist()), np.uint8).reshape(len(n), -1)
    nibbles = np.concatenate([packed & 15, packed >> 4], axis=1)
    cross = group.column("lo")[0].as_py() != group.column("hi")[0].as_py()
    near = np.zeros((len(n), len(n)), bool)
    for i in range(len(n)):
        ok = np.minimum(n, n[i]) >= similarity * np.maximum(n, n[i])
        ok[i] = False
        if cross:
            ok &= blk != blk[i]
        if label is not None:
            ok &= label != label[i]
        other = np.flatnonzero(ok)
        same = (nibbles[other] == nibbles[i]).sum(axis=1) / SLOTS
        near[i, other[(same - 1 / 16) / (15 / 16) >= similarity - SURE]] = True
    return near


def _sorted(met: DataFrame, columns: list[str]) -> DataFrame:
    return met.select("bucket", "lo", "hi", *columns).repartition("bucket", "lo", "hi").sortWithinPartitions("bucket", "lo", "hi")


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _stars(met: DataFrame, similarity: float) -> DataFrame:
    """Candidate pairs (a, b), at most one for each member of a bucket: with the best-connected member near it.

    Every class with any candidate is in some pair.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, right = [], []
        for group in _groups(batches):
            if group.num_rows < 2:
                continue
            near = _near(group, similarity, None)
            names, degree = group.column("cls").to_pylist(), near.sum(axis=1)
            free = np.ones(len(names), bool)
            for i in np.argsort(-degree, kind="stable").tolist():
                if not degree[i]:
                    break
                if free[i]:
                    free[i] = False
                    own = np.flatnonzero(near[i] & free)
                    if not len(own):
                        own = np.flatnonzero(near[i])[:1]
                    free[own] = False
                    left += [names[i]] * len(own)
                    right += [names[j] for j in own.tolist()]
            if len(left) > 20_000:
                yield pa.RecordBatch.from_arrays([pa.array(left, pa.binary()), pa.array(right, pa.binary())], ["a", "b"])
                left, right = [], []
        yield pa.RecordBatch.from_arrays([pa.array(left, pa.binary()), pa.array(right, pa.binary())], ["a", "b"])

    return _ordered(_sorted(met, ["blk", "cls", "total", "sketch"]).mapInArrow(run, "a binary, b binary"))


def _contested(met: DataFrame, similarity: float) -> DataFrame:
    """What could still connect components (met has their labels): rows (bucket, lo, hi, a, b).

    A bucket with few such pairs names them; one with more than SPARSE a member names its members (b is null), whose
    multisets then meet in one task. Either way the rows are in proportion to the members.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _groups(batches):
            _, label = np.unique(np.array([x.hex() for x in group.column("label").to_pylist()]), return_inverse=True)
            if group.num_rows < 2 or label.max() == 0:
                continue
            near, names = _near(group, similarity, label), group.column("cls").to_pylist()
            a, b = np.nonzero(np.triu(near))
            if not len(a):
                continue
            if len(a) > SPARSE * len(names):
                a, b = np.flatnonzero(near.any(axis=1)), None
            n = len(a)
            yield pa.RecordBatch.from_arrays(
                [
                    *(pa.array([group.column(k)[0].as_py()] * n, group.schema.field(k).type) for k in range(3)),
                    pa.array([names[i] for i in a.tolist()], pa.binary()),
                    pa.array([None] * n if b is None else [names[i] for i in b.tolist()], pa.binary()),
                ],
                ["bucket", "lo", "hi", "a", "b"],
            )

    return _sorted(met, ["blk", "cls", "total", "sketch", "label"]).mapInArrow(run, "bucket long, lo int, hi int, a binary, b binary")


def _multisets(asked: DataFrame, texts: DataFrame, reps: DataFrame, words: int) -> DataFrame:
    """(cls, codes, times): the shingle multisets of the asked classes; times is empty if each occurs once."""

    def shingles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, times = [], []
            for first, end, data, offsets in chunks(batch.column(1)):
                doc, code, many = sorted_per_doc(*Words(data, offsets).shingles(words))
                bounds = np.searchsorted(doc, np.arange(end - first + 1))
                for a, b in zip(bounds, bounds[1:]):
                    codes.append(code[a:b].tobytes())
                    times.append(b"" if (many[a:b] == 1).all() else many[a:b].astype(np.uint32).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(codes, pa.binary()), pa.array(times, pa.binary())], ["cls", "codes", "times"])

    # One text of each class: that of its representative.
    chosen = asked.join(reps.select("cls", "rep"), "cls").select(F.col("cls").alias("c"), "rep")
    own = texts.join(chosen, (texts["cls"] == F.col("c")) & texts["id"].eqNullSafe(F.col("rep"))).select("cls", "text")
    return own.mapInArrow(shingles, "cls binary, codes binary, times binary").dropDuplicates(["cls"])


def _unpacked(codes: bytes, times: bytes) -> tuple[np.ndarray, np.ndarray]:
    x = np.frombuffer(codes, np.uint64)
    return x, np.frombuffer(times, np.uint32).astype(np.int64) if times else np.ones(len(x), np.int64)


def _verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Links (a, b) among the pairs, by exact overlap of shingle multisets."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            # Few rows at a time are copied out of a batch.
            for batch in (whole.slice(at, 256) for at in range(0, whole.num_rows, 256)):
                value = []
                for xc, xt, yc, yt in zip(*(c.to_pylist() for c in batch.columns[2:])):
                    (x, xt), (y, yt) = _unpacked(xc, xt), _unpacked(yc, yt)
                    _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
                    both = int(np.minimum(xt[i], yt[j]).sum())
                    value.append(both >= similarity * (int(xt.sum() + yt.sum()) - both))
                yield pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array(value, pa.bool_()))

    one = pairs.join(sets.toDF("a", "ac", "at"), "a")
    two = one.join(sets.toDF("b", "bc", "bt"), "b").select("a", "b", "ac", "at", "bc", "bt")
    return two.mapInArrow(compare, "a binary, b binary")


#: Members whose overlaps with all others are held at once, and elements of one matrix product.
STRIP, ELEMENTS = 256, 512


def _forest(parts: list[tuple[np.ndarray, np.ndarray]], similarity: float) -> tuple[list[int], list[int]]:
    """Links that span what exact overlaps connect among multisets (codes, times); fewer than multisets.

    Overlaps of a strip of members with those from it on are held at a time, never those of all pairs, and once all are
    connected the rest is not compared.
    """
    n = len(parts)
    total = np.array([t.sum() for _, t in parts], np.float32)
    owner = np.repeat(np.arange(n, dtype=np.int32), [len(x) for x, _ in parts])
    code, times = np.concatenate([x for x, _ in parts]), np.concatenate([t for _, t in parts]).astype(np.uint32)
    # The k-th copy of a shingle is an element of its own, so overlaps of multisets are those of sets.
    more = times > 1
    if more.any():
        again = times[more].astype(np.int64) - 1
        copy = np.arange(again.sum()) - np.repeat(np.cumsum(again) - again, again) + 1
        code = np.concatenate([code, mix(np.repeat(code[more], again) + copy.astype(np.uint64) * _GOLD)])
        owner = np.concatenate([owner, np.repeat(owner[more], again)])
    order = np.argsort(code, kind="stable")
    code, owner = code[order], owner[order]
    del order, times, more
    new = np.ones(len(code) + 1, bool)
    new[1:-1] = code[1:] != code[:-1]
    del code
    shared = ~(new[:-1] & new[1:])
    element = (np.cumsum(new[:-1] & shared) - 1)[shared].astype(np.int32)
    owner = owner[shared]
    elements = int(element[-1]) + 1 if len(element) else 0
    label, left, right = np.arange(n), [], []
    for at in range(0, n, STRIP):
        own = min(STRIP, n - at)
        overlap = np.zeros((own, n - at), np.float32)
        for first in range(0, elements, ELEMENTS):
            a, b = np.searchsorted(element, [first, first + ELEMENTS])
            late = owner[a:b] >= at
            held = np.zeros((n - at, ELEMENTS), np.float32)
            held[owner[a:b][late] - at, element[a:b][late] - first] = 1
            overlap += held[:own] @ held.T
        for i in range(own):
            near = np.flatnonzero(overlap[i] >= similarity * (total[at + i] + total[at:] - overlap[i])) + at
            near = near[label[near] != label[at + i]]
            if len(near):
                found, place = np.unique(label[near], return_index=True)
                left += [at + i] * len(place)
                right += near[place].tolist()
                label[np.isin(label, found)] = label[at + i]
        if (label == label[0]).all():
            break
    return left, right


def _together(members: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Links (a, b) that span what exact overlaps connect within each bucket; at most one a member."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _groups(batches):
            names = group.column("a").to_pylist()
            left, right = _forest([_unpacked(c, t) for c, t in zip(group.column("codes").to_pylist(), group.column("times").to_pylist())], similarity)
            yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in x], pa.binary()) for x in (left, right)], ["a", "b"])

    joined = members.join(sets.withColumnRenamed("cls", "a"), "a")
    return _sorted(joined, ["a", "codes", "times"]).mapInArrow(run, "a binary, b binary")


def _placed(docs: DataFrame, similarity: float, id_col: str, text_col: str, words: int, bands: int, rows: int, bucket: int) -> DataFrame:
    """(cls, rep, copies, label): the different texts and the class each belongs to."""
    texts = _text_rows(docs, id_col, text_col)
    found = written(classes(docs, id_col, text_col, words, bands, rows), "classes")
    met = _met(found.select("cls", "total", "sketch", "bands"), bucket)
    first = written(_stars(met, similarity), "pairs")
    asked = first.select(F.col("a").alias("cls")).unionByName(first.select(F.col("b").alias("cls"))).distinct()
    sets = written(_multisets(asked, texts, found, words), "multisets")
    links = written(_verified(first, sets, similarity), "links")
    labels = star_labels(links.toDF("u", "v"))
    named = found.select("cls", "total", "sketch", "bands").join(labels.withColumnRenamed("node", "cls"), "cls", "left")
    named = named.select("cls", "total", "sketch", "bands", F.coalesce("label", "cls").alias("label"))
    rest = written(_contested(_met(named, bucket), similarity), "contested")
    # Pairs that the first round has looked at are known not to be links.
    second = _ordered(rest.where("b is not null")).join(first, ["a", "b"], "left_anti")
    more = written(_verified(second, sets, similarity).unionByName(_together(rest.where("b is null").drop("b"), sets, similarity)).distinct(), "links")
    if more.limit(1).count():
        labels = star_labels(links.unionByName(more).toDF("u", "v"))
    return found.select("cls", "rep", "copies").join(labels.withColumnRenamed("node", "cls"), "cls", "left").withColumn("label", F.coalesce("label", "cls"))


def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, bands: int = BANDS, rows: int = ROWS, bucket: int = BUCKET) -> DataFrame:
    """Rows (doc_id, class_id, class_size, copies), one for each row of docs; class_id is the least doc_id of its class."""
    placed = _placed(docs, similarity, id_col, text_col, words, bands, rows, bucket)
    sizes = placed.groupBy("label").agg(F.min("rep").alias("class_id"), F.sum("copies").alias("class_size"))
    member = placed.join(sizes, "label").select("cls", "class_id", "class_size", "copies")
    return _text_rows(docs, id_col, text_col).select("id", "cls").join(member, "cls").select(F.col("id").alias("doc_id"), "class_id", "class_size", "copies")


def one_of_each(docs: DataFrame, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, bands: int = BANDS, rows: int = ROWS, bucket: int = BUCKET) -> DataFrame:
    """The rows of docs with the least doc_id of their class, one row for each class."""
    placed = _placed(docs, similarity, id_col, text_col, words, bands, rows, bucket)
    lead = placed.groupBy("label").agg(F.min(F.struct(F.col("rep").isNull().alias("x"), "rep", "cls")).alias("lead"))
    keep = lead.select(F.xxhash64("lead.rep").alias("h"), F.col("lead.cls").alias("cls"))
    own = F.unhex(F.md5(F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")))
    keyed = docs.select(F.struct(*docs.columns).alias("row"), F.xxhash64(F.col(id_col)).alias("h"), own.alias("cls"))
    # Only a table that repeats an id with its text needs the pass that drops repeated rows.
    repeats = keyed.groupBy("h", "cls").count().where("count > 1").limit(1).count()
    kept = keyed.join(keep, ["h", "cls"], "left_semi")
    return (kept.dropDuplicates(["h", "cls"]) if repeats else kept).select("row.*")
