"""Exact substring dedup: every byte inside a string of 200 bytes that also starts anywhere else is removed.

1. Every 200-byte window names the least hash of its 32-byte substrings (winnowing). Equal windows name the same hash,
   so windows can be dealt by it: each text is cut into runs of windows with one name, and a run holds all its windows'
   bytes. Names that occur once in the corpus need no further look.
2. Runs with a repeated name are folded where they are equal byte by byte, with their number.
3. Different runs are dealt by name to shards of bounded size. A shard has a suffix array by Larsson-Sadakane refinement
   (groups of suffixes equal so far are sorted by the rank at double the depth, until all differ), with the common
   prefixes of neighbours by Kasai's algorithm. A window is repeated if a neighbour in suffix order shares 200 bytes with it.
4. A name with more runs than one shard holds is spread over several, and these are merged by binary search: the
   windows of one are looked up among the sorted windows of another. Of a name with more than TOGETHER shards each shard
   is a task of its own; it hands on its different windows in suffix order, and these are merged by a sort over all
   shards, byte by byte, so no name is gathered in one task.
5. Covered bytes go back to the places of each run, and each text is cut once.

Defined results: a null or empty text has no bytes; rows equal in doc_id and text are copies of each other, and each
gets the same result; null doc_ids are ids like others; texts under 200 bytes are left alone; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import discard, written
from .textvec import chunks, give_back, mix

LENGTH = 200
ANCHOR = 32
#: Bytes of one suffix array.
SHARD_BYTES = 1 << 20
#: Shards of one name that are merged within one task.
TOGETHER = 8
#: Bytes of text that one walker of the common prefixes passes.
SEGMENT = 64


def _sliding(x: np.ndarray, width: int, op) -> np.ndarray:
    """op over every `width` neighbours, by doubling."""
    have = 1
    while have * 2 <= width:
        x = op(x[:-have], x[have:])
        have *= 2
    return op(x[: len(x) - (width - have)], x[width - have :]) if width > have else x


def window_runs(data: np.ndarray, length: int = LENGTH, anchor: int = ANCHOR) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(name, first window, last window, whether it may repeat within itself) of the runs of one byte string's windows."""
    if len(data) < length:
        z = np.zeros(0, np.int64)
        return z.astype(np.uint64), z, z, z.astype(bool)
    code, base = data.astype(np.uint64) + np.uint64(1), 0x9E3779B97F4A7C15 | 1
    have = 1
    while have < anchor:
        code = code[:-have] * np.uint64(pow(base, have, 1 << 64)) + code[have:]
        have *= 2
    code = mix(code)
    spread = length - anchor + 1
    least = _sliding(code, spread, np.minimum)
    # A run no longer than the spread keeps runs bounded on periodic text.
    cut = np.flatnonzero(least[1:] != least[:-1]) + 1
    first, last = np.append(0, cut), np.append(cut, len(least)) - 1
    over = np.flatnonzero(last - first >= spread)
    if len(over):
        parts = (last - first) // spread + 1
        row = np.repeat(np.arange(len(first)), parts)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(parts) - parts, parts)
        first, last = first[row] + nth * spread, np.minimum(first[row] + (nth + 1) * spread - 1, last[row])
    name = least[first]
    # A name that is taken twice by anchors near each other may come from a string that repeats within its run.
    high = _sliding(np.concatenate([np.zeros(spread - 1, np.uint64), least, np.zeros(spread - 1, np.uint64)]), spread, np.maximum)
    taken = np.flatnonzero(high[: len(code)] == code)
    twice = np.flatnonzero(code[taken[1:]] == code[taken[:-1]])
    own = np.isin(name, code[taken[twice]]) if len(twice) else np.zeros(len(name), bool)
    return name, first, last, own


def suffix_array(data: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffixes in order of their first `depth` or more bytes, rank of each); equal ones share a rank.

    Begins with eight bytes a key; then only suffixes in groups not yet told apart are sorted again, by the rank of the
    suffix `h` further on, and h doubles.
    """
    n = len(data)
    padded = np.concatenate([data, np.zeros(8, np.uint8)]).astype(np.uint64)
    key = padded[:n].copy()
    for k in range(1, 8):
        key = (key << np.uint64(8)) | padded[k : n + k]
    order = np.argsort(key)
    rank = np.zeros(n + 1, np.int64)  # past the end: below all
    sorted_key = key[order]
    new = np.append(True, sorted_key[1:] != sorted_key[:-1])
    # A last place that never begins a group marks the end.
    begins = np.append(new, True)
    head = np.flatnonzero(new)
    rank[order] = np.repeat(head, np.diff(np.append(head, n))) + 1
    h = 8
    while h < depth:
        at = np.flatnonzero(~(begins[:-1] & begins[1:]))
        if not len(at):
            break
        suffix = order[at]
        further = rank[np.minimum(suffix + h, n)]
        group = rank[suffix]
        sub = np.argsort(group * np.int64(n + 2) + further)
        suffix, further = suffix[sub], further[sub]
        order[at] = suffix
        fresh = np.append(True, (group[1:] != group[:-1]) | (further[1:] != further[:-1]))
        starts = at[fresh]
        rank[suffix] = np.repeat(starts, np.diff(np.append(np.flatnonzero(fresh), len(at)))) + 1
        begins[starts] = True
        h *= 2
    return order, rank[:n]


def common_prefixes(data: np.ndarray, order: np.ndarray, most: int, segment: int = SEGMENT) -> np.ndarray:
    """Common prefix of each suffix with the one before it in a complete suffix order, up to `most`, by Kasai's algorithm.

    The algorithm walks the text: the next position shares at most one byte less with its own predecessor, so each starts
    from what the last one had. Here every segment of the text is walked by its own walker, all in lockstep, eight
    bytes a comparison; only the first position of a segment starts from nothing.
    """
    n = len(order)
    if n < 2:
        return np.zeros(n, np.int64)
    before = np.full(n, -1, np.int64)
    before[order[1:]] = order[:-1]
    padded = np.zeros(n + 8, np.uint8)
    padded[:n] = data
    eight = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(padded, 8)).view(np.uint64)[:, 0]
    shared = np.zeros(n, np.int64)
    have = np.zeros(-(-n // segment), np.int64)
    for step in range(min(segment, n)):
        at = np.arange(step, n, segment)
        other = before[at]
        room = np.where(other < 0, 0, np.minimum(most, n - np.maximum(at, other)))
        have = np.minimum(np.maximum(have[: len(at)] - 1, 0), room)
        live = np.flatnonzero(have < room)
        while len(live):
            left = eight[at[live] + have[live]] ^ eight[other[live] + have[live]]
            same = np.where(left == 0, 8, _zero_bytes(left))
            have[live] = np.minimum(have[live] + same, room[live])
            live = live[(same == 8) & (have[live] < room[live])]
        shared[at] = have
    return shared[order]


def _zero_bytes(x: np.ndarray) -> np.ndarray:
    low = x & (~x + np.uint64(1))
    return np.floor(np.log2(np.maximum(low, np.uint64(1)).astype(np.float64))).astype(np.int64) // 8


class Shard:
    """Pieces of text with their suffix array; repeated[p] tells whether the window that starts at byte p occurs again."""

    def __init__(self, pieces: list[bytes], length: int = LENGTH):
        self.data = np.frombuffer(b"".join(pieces), np.uint8)
        sizes = np.array([len(p) for p in pieces], np.int64)
        self.ends = np.cumsum(sizes)
        self.starts = self.ends - sizes
        self.length = length
        stops = np.repeat(self.ends, sizes)
        order, _ = suffix_array(self.data, len(self.data))
        # Whole windows are equal if no suffix from one to the other parts with its neighbour within their length.
        group = np.cumsum(common_prefixes(self.data, order, length) < length)
        whole = stops[order] - order >= length
        #: Starts of whole windows in suffix order, and a number for each that equal ones share.
        self.order, group = order[whole], group[whole]
        self.group = group
        both = np.zeros(len(group), bool)
        both[1:] = group[1:] == group[:-1]
        both[:-1] |= both[1:].copy()
        self.repeated = np.zeros(len(self.data), bool)
        self.repeated[self.order[both]] = True

    def windows(self) -> tuple[np.ndarray, np.ndarray]:
        """(starts, bytes as fixed-width strings) of the whole windows, in suffix order."""
        return self.order, np.lib.stride_tricks.sliding_window_view(self.data, self.length)

    def merge(self, other: Shard) -> None:
        """Marks in both what occurs in both: each window of the smaller is searched for among the sorted of the other."""
        if len(self.data) > len(other.data):
            other.merge(self)
            return
        mine, view = self.windows()
        theirs, other_view = other.windows()
        if not len(mine) or not len(theirs):
            return
        # Binary search by ever longer prefixes: [low, high) holds their windows equal to mine so far.
        low, high = np.zeros(len(mine), np.int64), np.full(len(mine), len(theirs), np.int64)
        for at in range(0, self.length, 8):
            key, their_key = _eight(view, mine, at), _eight(other_view, theirs, at)
            low, high = _narrow(their_key, key, low, high)
            some = low < high
            mine, low, high = mine[some], low[some], high[some]
            if not len(mine):
                return
        self.repeated[mine] = True
        marks = np.zeros(len(theirs) + 1, np.int64)
        np.add.at(marks, low, 1)
        np.add.at(marks, high, -1)
        other.repeated[theirs[np.cumsum(marks)[:-1] > 0]] = True


def _eight(view: np.ndarray, at: np.ndarray, place: int) -> np.ndarray:
    part = np.zeros((len(at), 8), np.uint8)
    width = min(8, view.shape[1] - place)
    part[:, :width] = view[at, place : place + width]
    return part.view(">u8")[:, 0].astype(np.uint64)


def _narrow(sorted_key: np.ndarray, key: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The part of each [low, high) whose keys equal key; keys ascend within each such part."""
    out = []
    for above in (False, True):
        a, b = low.copy(), high.copy()
        while (open_ := a < b).any():
            mid = (a + b) // 2
            value = sorted_key[np.minimum(mid, len(sorted_key) - 1)]
            right = open_ & ((value <= key) if above else (value < key))
            a = np.where(right, mid + 1, a)
            b = np.where(open_ & ~right, mid, b)
        out.append(a)
    return out[0], out[1]


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    return docs.select(F.xxhash64(F.col(id_col)).alias("k1"), F.xxhash64(text).alias("k2"), text.alias("text"))


def _name_runs(rows: DataFrame, length: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, end, data, offsets in chunks(batch.column(2)):
                long = np.flatnonzero(np.diff(offsets) >= length)
                if not len(long):
                    continue
                # All texts of the group at once; runs that reach over a text's end are cut back to it.
                name, a, b, own = window_runs(data, length)
                doc = np.searchsorted(offsets, a, side="right") - 1
                out = [[], [], [], [], []]
                stop = offsets[doc + 1] - length
                ok = (a <= stop) & (b <= stop)
                over = np.flatnonzero(~ok)
                out[0].append(name[ok]), out[1].append(doc[ok]), out[2].append(a[ok]), out[3].append(b[ok]), out[4].append(own[ok])
                for i in over.tolist():
                    d, x = int(doc[i]), int(a[i])
                    while x <= b[i]:
                        y = min(int(b[i]), int(offsets[d + 1]) - length)
                        if x <= y:
                            out[0].append(name[i : i + 1]), out[1].append(np.array([d])), out[2].append(np.array([x])), out[3].append(np.array([y])), out[4].append(own[i : i + 1])
                        d += 1
                        if d >= end - first:
                            break
                        x = max(x, int(offsets[d]))
                name, doc, a, b, own = (np.concatenate(x) for x in out)
                at = pa.array(first + doc)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(name.view(np.int64)), batch.column(0).take(at), batch.column(1).take(at), pa.array((a - offsets[doc]).astype(np.int32)), pa.array((b - offsets[doc]).astype(np.int32)), pa.array(own)],
                    ["name", "k1", "k2", "a", "b", "own"],
                )
        give_back()

    return rows.mapInArrow(run, "name long, k1 long, k2 long, a int, b int, own boolean")


def _pieces(candidates: DataFrame, length: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                k1, k2, text, runs = (c[row] for c in batch.columns)
                text, runs = text.as_py(), runs.values
                name, a, b = (x.to_numpy() for x in runs.flatten())
                parts = [text[x : y + length] for x, y in zip(a.tolist(), b.tolist())]
                n = len(parts)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(n, k1.as_py())), pa.array(np.full(n, k2.as_py())), pa.array(name), pa.array(a), pa.array(parts, pa.binary()), pa.array([hashlib.md5(p).digest() for p in parts], pa.binary())],
                    ["k1", "k2", "name", "a", "piece", "pid"],
                )
        give_back()

    return candidates.mapInArrow(run, "k1 long, k2 long, name long, a int, piece binary, pid binary")


def _covered(repeated: np.ndarray, length: int) -> list[int]:
    """Starts and ends, in turn, of the bytes covered by windows that start where repeated holds."""
    at = np.flatnonzero(repeated)
    if not len(at):
        return []
    cut = np.flatnonzero(at[1:] > at[:-1] + length) + 1
    return np.stack([at[np.append(0, cut)], at[np.append(cut, len(at)) - 1] + length], axis=1).ravel().tolist()


def _search(pieces: DataFrame, length: int, shard_bytes: int) -> DataFrame:
    """(pid, spans): covered bytes of every different run, from suffix arrays over shards of whole names."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pids: list[bytes] = []
        texts: list[bytes] = []
        many: list[int] = []
        size, name = 0, None

        def flush():
            groups, at, total = [], 0, 0
            for i, t in enumerate(texts):
                total += len(t)
                if total >= shard_bytes or i == len(texts) - 1:
                    groups.append((at, i + 1))
                    at, total = i + 1, 0
            shards = [Shard(texts[a:b], length) for a, b in groups]
            for i in range(len(shards)):
                for j in range(i):
                    shards[i].merge(shards[j])
            spans = []
            for (a, b), shard in zip(groups, shards):
                for i, s, e in zip(range(a, b), shard.starts.tolist(), shard.ends.tolist()):
                    spans.append(_covered(shard.repeated[s:e], length) if many[i] == 1 else [0, e - s])
            return pa.RecordBatch.from_arrays([pa.array(pids, pa.binary()), pa.array(spans, pa.list_(pa.int32()))], ["pid", "spans"])

        for batch in batches:
            for n, p, i, m in zip(*(c.to_pylist() for c in batch.columns)):
                if size >= shard_bytes and n != name:
                    yield flush()
                    pids, texts, many, size = [], [], [], 0
                    give_back()
                pids.append(i), texts.append(p), many.append(m)
                size, name = size + len(p), n
        if pids:
            yield flush()
        give_back()

    dealt = pieces.select("name", "piece", "pid", "n").repartition("name").sortWithinPartitions("name")
    return dealt.mapInArrow(run, "pid binary, spans array<int>").where(F.size("spans") > 0)


def _search_apart(pieces: DataFrame, length: int) -> DataFrame:
    """As _search for names of very many shards (column shard): a task a shard, merged by their sorted windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[bytes, bytes, int]] = []
        last = None

        def flush():
            shard = Shard([p for p, _, _ in held], length)
            owner = np.searchsorted(shard.ends, shard.order, side="right")
            cut = np.append(np.flatnonzero(np.append(True, shard.group[1:] != shard.group[:-1])), len(shard.group)) if len(shard.group) else np.zeros(1, np.int64)
            many = np.array([m for _, _, m in held], np.int64)
            view = np.lib.stride_tricks.sliding_window_view(shard.data, length)
            for x in range(0, len(cut) - 1, 20_000):
                part = cut[x : x + 20_001]
                inside = slice(int(part[0]), int(part[-1]))
                places = pa.StructArray.from_arrays([pa.array([held[i][1] for i in owner[inside].tolist()], pa.binary()), pa.array((shard.order - shard.starts[owner])[inside].astype(np.int32))], ["pid", "at"])
                # Windows of one shard that are equal go as one row, with all their places.
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([view[i].tobytes() for i in shard.order[part[:-1]].tolist()], pa.binary()),
                        pa.array(np.add.reduceat(many[owner[inside]], part[:-1] - part[0])),
                        pa.ListArray.from_arrays(pa.array((part - part[0]).astype(np.int32)), places),
                    ],
                    ["window", "n", "places"],
                )
            held.clear()
            give_back()

        for batch in batches:
            for name, shard, p, i, m in zip(*(c.to_pylist() for c in batch.columns)):
                if held and (name, shard) != last:
                    yield from flush()
                held.append((p, i, m))
                last = (name, shard)
        if held:
            yield from flush()

    dealt = pieces.select("name", "shard", "piece", "pid", "n").repartition("name", "shard").sortWithinPartitions("name", "shard")
    rows = written(dealt.mapInArrow(run, "window binary, n long, places array<struct<pid:binary,at:int>>"), "windows")
    again = rows.groupBy("window").agg(F.sum("n").alias("n")).where("n > 1").select("window")
    found = rows.join(again, "window").select(F.explode("places").alias("p")).groupBy("p.pid").agg(F.collect_set("p.at").alias("ats"))
    ends = F.transform(F.array_sort("ats"), lambda x: F.array(x, x + length))
    return found.select("pid", F.flatten(ends).alias("spans"))


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, shard_bytes: int = SHARD_BYTES, together: int = TOGETHER) -> tuple[DataFrame, DataFrame]:
    """(candidate texts k1, k2, text, runs; spans k1, k2, spans): what to cut from which texts."""
    rows = _rows(docs, id_col, text_col)
    runs = written(_name_runs(rows, length), "runs")
    names = runs.groupBy("name").agg(F.count("*").alias("n"), F.max("own").alias("own")).where("n > 1 or own").select("name")
    again = runs.join(names, "name").groupBy("k1", "k2").agg(F.collect_set(F.struct("name", "a", "b")).alias("runs"))
    candidates = written(rows.join(again, ["k1", "k2"]), "candidates")
    discard(runs)
    found = _pieces(candidates, length)
    different = written(found.groupBy("name", "piece", "pid").agg(F.count("*").alias("n")), "pieces")
    busy = different.groupBy("name").agg(F.ceil(F.sum(F.octet_length("piece")) / shard_bytes).alias("shards")).where(F.col("shards") > together)
    spans = _search(different.join(busy, "name", "left_anti"), length, shard_bytes)
    if busy.limit(1).count():
        spread = different.join(busy, "name").withColumn("shard", F.pmod(F.xxhash64("pid"), F.col("shards")))
        spans = spans.unionByName(_search_apart(spread, length))
    spans = spans.groupBy("pid").agg(F.first("spans").alias("spans"))
    placed = found.select("k1", "k2", "a", "pid").join(spans, "pid").select("k1", "k2", F.transform("spans", lambda x: x + F.col("a")).alias("spans"))
    return candidates.select("k1", "k2", "text"), placed.groupBy("k1", "k2").agg(F.flatten(F.collect_set("spans")).alias("spans"))


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, shard_bytes: int = SHARD_BYTES, together: int = TOGETHER, with_kept: bool = False) -> DataFrame:
    """Rows (doc_id, n_bytes, n_removed, n_spans, kept_sha256[, kept]), one for each row of docs."""
    texts, spans = repeated_spans(docs, id_col, text_col, length, shard_bytes, together)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            removed, n_spans, sha, kept = [], [], [], []
            for text, own in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                pairs = np.array(own, np.int64).reshape(-1, 2)
                pairs = pairs[np.lexsort((pairs[:, 1], pairs[:, 0]))]
                reach = np.maximum.accumulate(pairs[:, 1])
                new = np.append(True, pairs[1:, 0] > reach[:-1])
                starts = pairs[new, 0]
                ends = reach[np.append(np.flatnonzero(new)[1:], len(pairs)) - 1]
                rest = b"".join(text[a:b] for a, b in zip([0, *ends.tolist()], [*starts.tolist(), len(text)]))
                removed.append(len(text) - len(rest))
                n_spans.append(len(starts))
                sha.append(hashlib.sha256(rest).hexdigest())
                kept.append(rest)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(sha, pa.string()), pa.array(kept if with_kept else [None] * len(sha), pa.binary())], ["c1", "c2", "r", "s", "h", "kept"])
        give_back()

    done = texts.join(spans, ["k1", "k2"]).mapInArrow(cut, "c1 long, c2 long, r long, s long, h string, kept binary").dropDuplicates(["c1", "c2"])
    text = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    base = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(F.col(id_col)).alias("k1"), F.xxhash64(text).alias("k2"), F.octet_length(text).cast("long").alias("n_bytes"), F.sha2(text, 256).alias("sha"), *([text.alias("text")] if with_kept else []))
    out = base.join(done, (base["k1"] == done["c1"]) & (base["k2"] == done["c2"]), "left")
    return out.select("doc_id", "n_bytes", F.coalesce("r", F.lit(0)).cast("long").alias("n_removed"), F.coalesce("s", F.lit(0)).cast("long").alias("n_spans"), F.coalesce("h", "sha").alias("kept_sha256"), *([F.when(F.col("r").isNull(), F.col("text")).otherwise(F.col("kept")).alias("kept")] if with_kept else []))
