"""Connected components of a link table, by three methods.

star      alternating large-star and small-star contraction: O(log n) rounds whatever the diameter
minlabel  every node takes the least label near it: as many rounds as the diameter
twophase  components within each hash part of the links first, then stars over what is left

No method gathers a node's neighbours: every step is a min-aggregate and a join, so hubs only skew a join that AQE splits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import discard, written

MAX_ROUNDS = 60


def _state(links: DataFrame) -> tuple:
    r = links.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return r[0], r[1]


def _large(links: DataFrame) -> DataFrame:
    both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small(links: DataFrame) -> DataFrame:
    # Links point from the larger to the smaller end here.
    least = links.groupBy("u").agg(F.min("v").alias("m"))
    moved = links.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return least.select("u", F.col("m").alias("v")).unionByName(moved).distinct()


def star_labels(links: DataFrame) -> DataFrame:
    """(node, label) of every node that has a link; links: columns u, v of one orderable type."""
    now = written(links.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
    before = _state(now)
    for _ in range(MAX_ROUNDS):
        after = written(_small(_large(now)), "links")
        discard(now)
        now, state = after, _state(after)
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct())


def min_labels(links: DataFrame) -> DataFrame:
    """As star_labels, by label propagation."""
    both = written(links.where("u <> v").select("u", "v").unionByName(links.where("u <> v").select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "links")
    now = written(both.groupBy("u").agg(F.least(F.first("u"), F.min("v")).alias("label")).withColumnRenamed("u", "node"), "labels")
    while True:
        near = both.join(now, F.col("v") == F.col("node")).groupBy("u").agg(F.min("label").alias("m"))
        after = written(now.join(near, F.col("node") == F.col("u")).select("node", F.least("label", "m").alias("label"), (F.col("m") < F.col("label")).alias("moved")), "labels")
        discard(now)
        moved = after.where("moved").limit(1).count()
        now = after.select("node", "label")
        if not moved:
            return now


#: Links that one step of a part joins, and nodes whose stars a part holds before it passes them on.
JOINED, HELD = 1 << 20, 1 << 20


def _joined(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its component) of linked nodes, without those that are the least."""
    nodes = np.unique(np.concatenate([u, v]))
    a, b = np.searchsorted(nodes, u), np.searchsorted(nodes, v)
    label = np.arange(len(nodes))
    while len(a):
        # Roots hook to the least root they are linked to, then all paths are halved until they are stars.
        x, y = label[a], label[b]
        far = x != y
        a, b, x, y = a[far], b[far], x[far], y[far]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    moved = label != np.arange(len(nodes))
    return nodes[moved], nodes[label[moved]]


def spanning(links: DataFrame) -> DataFrame:
    """(u, v): stars that connect what the links of each part of the table connect; ends are numbers, no row is shuffled."""

    def shrink(batches):
        stars, wait, n = (np.zeros(0, np.int64),) * 2, [], 0
        for batch in batches:
            wait.append(tuple(np.asarray(batch.column(i)) for i in range(2)))
            n += batch.num_rows
            if n >= JOINED:
                stars = _joined(*(np.concatenate(x) for x in zip(stars, *wait)))
                wait, n = [], 0
                if len(stars[0]) > HELD:  # bounded memory: a part may yield several stars
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in stars], ["u", "v"])
                    stars = (np.zeros(0, np.int64),) * 2
        stars = _joined(*(np.concatenate(x) for x in zip(stars, *wait)))
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in stars], ["u", "v"])

    return links.select(F.col("u").cast("long"), F.col("v").cast("long")).where("u <> v").mapInArrow(shrink, "u long, v long")


def two_phase_labels(links: DataFrame, parts: int = 64) -> DataFrame:
    """As star_labels; each part of the links first shrinks to a spanning star per component of its own."""
    kind = links.schema["u"].dataType.simpleString()

    def shrink(batches):
        parent: dict = {}

        def find(x):
            while parent.setdefault(x, x) != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        def flush():
            pairs = [(x, find(x)) for x in list(parent) if find(x) != x]
            parent.clear()
            return pa.RecordBatch.from_arrays([pa.array([a for a, _ in pairs], kinds), pa.array([b for _, b in pairs], kinds)], ["u", "v"])

        kinds = None
        for batch in batches:
            kinds = batch.schema.field(0).type
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                a, b = find(a), find(b)
                if a != b:
                    parent[max(a, b)] = min(a, b)
            if len(parent) > 1_000_000:  # bounded memory: a part may yield several stars
                yield flush()
        if kinds is not None:
            yield flush()

    small = links.where("u <> v").select("u", "v").repartition(parts, F.xxhash64(F.least("u", "v"))).mapInArrow(shrink, f"u {kind}, v {kind}")
    return star_labels(small)


METHODS = {"star": star_labels, "minlabel": min_labels, "twophase": two_phase_labels}


def components(links: DataFrame, nodes: DataFrame | None = None, method: str = "star") -> DataFrame:
    """(node, label): label is the least node of its component; nodes (column node) adds those without links."""
    found = METHODS[method](links)
    if nodes is None:
        return found
    return nodes.select("node").distinct().join(found, "node", "left").select("node", F.coalesce("label", "node").alias("label"))
