"""Communities: cliques that reach each other through overlaps, their covers and the measures of covers.

A cover is a table of labelled cliques (by, k, community_key, members). The key is the least k-clique of the community,
which is its own only: vertices may be shared, a k-clique never is.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import written
from . import cliques as C
from .components import components, spanning
from .egos import ego_covers

#: Links up to which one task joins components; the count is checked, more links take the distributed way.
LOCAL_LINKS = 500_000
#: Links of a graph, and of one component of a larger graph, whose neighbourhoods one task goes through.
EGO_LINKS, EGO_PART = 1_000_000, 16_000_000


def labels_of(links: DataFrame) -> DataFrame:
    """(node, label) of linked nodes: by one task if the links are few, else by stars."""
    links = written(links, "links")
    if links.count() > LOCAL_LINKS:
        return components(links)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent: dict = {}

        def find(x):
            while parent.setdefault(x, x) != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                a, b = find(a), find(b)
                if a != b:
                    parent[max(a, b)] = min(a, b)
        nodes = list(parent)
        yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.string()), pa.array([find(x) for x in nodes], pa.string())], ["node", "label"])

    return links.select("u", "v").coalesce(1).mapInArrow(run, "node string, label string")


def _keyed(labelled: DataFrame, k: int, by: tuple[str, ...]) -> DataFrame:
    """Labelled cliques (by, label, members) with the community's own key."""
    own = labelled.groupBy(*by, "label").agg(F.min(F.slice("members", 1, k)).alias("least"))
    return labelled.join(own, [*by, "label"]).select(*by, F.lit(k).cast("long").alias("k"), C.name("least").alias("community_key"), "members")


def percolate(edges: DataFrame, k: int, via: str = "maximal", convention: str = "definition", by: tuple[str, ...] = (), strategy: str = "ego") -> DataFrame:
    """The cover at k: labelled cliques. via: maximal cliques and their overlaps, or k-cliques and their faces.

    via "egos" is for graphs so dense that no clique listing ends: see percolate_egos, whose cover has fewer cliques.
    """
    if convention == "printed":
        return percolate(edges, k + 1, via, "definition", by, strategy).withColumn("k", F.lit(k).cast("long"))
    if via == "egos" and k > 2:
        if by:
            raise ValueError("egos knows no parts")
        return percolate_egos(edges, k)
    if via == "kclique" or k == 2:
        found = C.k_cliques(edges, k, by)
        tag = F.concat_ws("|", *by, C.name()) if by else C.name()
        named = written(found.select(*by, tag.alias("clique"), "members"), "cliques")
        links = C.adjacency_links(named, k, by)
    else:
        found = C.maximal_cliques(edges, k, strategy, by)
        tag = F.concat_ws("|", *by, C.name()) if by else C.name()
        named = written(found.select(*by, tag.alias("clique"), "members"), "cliques")
        at = C.clique_overlaps(named, k - 1, by)
        prefix = lambda c: F.concat_ws("|", *by, c) if by else F.col(c)
        links = at.select(prefix("ci").alias("u"), prefix("cj").alias("v"))
    labels = labels_of(links)
    labelled = named.join(labels.withColumnRenamed("node", "clique"), "clique", "left").select(*by, F.coalesce("label", "clique").alias("label"), "members")
    return _keyed(labelled, k, by)


def percolate_egos(edges: DataFrame, k: int, limit: int = EGO_LINKS, most: int = EGO_PART) -> DataFrame:
    """The cover at k by neighbourhoods: of each community one k-clique or more at each of its vertices, not all cliques.

    One task does a graph up to the limit; a larger one falls into its components, a task each, and a component of over
    `most` links goes by maximal cliques.
    """
    links = written(edges.select("src", "dst"), "links")
    kind = "k long, community_key string, members array<long>"

    def solved(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [(np.asarray(b.column(0)), np.asarray(b.column(1))) for b in batches]
        src, dst = (np.concatenate(x) for x in zip(*held)) if held else (np.zeros(0, np.int64),) * 2
        held.clear()
        found = ego_covers(src, dst, k)
        for at in range(0, len(found), 10_000):
            some = found[at : at + 10_000]
            keys = ["-".join(map(str, least)) for least, _ in some]
            yield pa.RecordBatch.from_arrays([pa.array([k] * len(some), pa.int64()), pa.array(keys, pa.string()), pa.array([c for _, c in some], pa.list_(pa.int64()))], ["k", "community_key", "members"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from solved(batches)

    if links.count() <= limit:
        return links.coalesce(1).mapInArrow(solved, kind)
    # Stars of what is near each other in the table: of the links themselves none is shuffled to find components.
    part = written(components(spanning(links.toDF("u", "v"))).select(F.col("node").alias("src"), F.col("label").alias("part")), "components")
    parted = links.join(part, "src").select("src", "dst", "part")
    large = [r["part"] for r in parted.groupBy("part").count().where(F.col("count") > most).select("part").collect()]  # few, each of over `most` links
    found = parted.where(~F.col("part").isin(large)).groupBy("part").applyInArrow(run, kind)
    if not large:
        return found
    return found.unionByName(percolate(parted.where(F.col("part").isin(large)).select("src", "dst"), k))


def percolate_all(edges: DataFrame, k_min: int = 3, k_max: int | None = None, via: str = "maximal") -> DataFrame:
    """Covers at every k from k_min to the largest clique: maximal cliques and overlaps are found once for all k.

    via "egos" needs k_max and goes through the neighbourhoods for each k.
    """
    if via == "egos":
        links, covers = written(edges.select("src", "dst"), "links"), None
        for k in range(k_min, k_max + 1):
            covers = percolate(links, k, via) if covers is None else covers.unionByName(percolate(links, k, via))
        return covers
    found = written(C.maximal_cliques(edges, k_min).select(C.name().alias("clique"), "members"), "cliques")
    overlaps = written(C.clique_overlaps(found, k_min - 1), "overlaps")
    top = found.agg(F.max(F.size("members")).alias("n")).first()["n"] or 0
    covers = None
    for k in range(k_min, min(top, k_max or top) + 1):
        some, over = C.threshold_graph(found, overlaps, k)
        labels = labels_of(over.select(F.col("ci").alias("u"), F.col("cj").alias("v")))
        cover = _keyed(some.join(labels.withColumnRenamed("node", "clique"), "clique", "left").select(F.coalesce("label", "clique").alias("label"), "members"), k, ())
        covers = cover if covers is None else covers.unionByName(cover)
    return covers if covers is not None else _keyed(found.where("false").select(F.col("clique").alias("label"), "members"), k_min, ())


def serial_covers(links: list[tuple[int, int]], k_min: int, k_max: int | None = None) -> list[tuple[int, str, list[int]]]:
    """The single-unit baseline at every k: (k, community key, maximal clique) rows, by plain Python over links in memory.

    Cliques and their overlaps are found once; k_max None goes on to the largest clique.
    """
    ends = np.array(links, np.int64).reshape(-1, 2)
    return serial_covers_of(ends[:, 0], ends[:, 1], k_min, k_max)


class _Near(dict):
    """Neighbours of a vertex as a set, made when first asked for."""

    def __init__(self, near: np.ndarray, bounds: np.ndarray):
        self.near, self.bounds, self.names = near, bounds.tolist(), list(range(len(bounds) - 1))

    def __missing__(self, v: int) -> set[int]:
        # One number object a vertex, however many sets hold it.
        own = self[v] = set(map(self.names.__getitem__, self.near[self.bounds[v] : self.bounds[v + 1]].tolist()))
        return own


def serial_covers_of(src: np.ndarray, dst: np.ndarray, k_min: int, k_max: int | None = None) -> list[tuple[int, str, list[int]]]:
    """serial_covers, of the ends of links."""
    src, dst = src[src != dst], dst[src != dst]
    ids = np.union1d(src, dst)
    n = len(ids)
    src, dst = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    at, near = np.divmod(np.unique(np.concatenate([src * n + dst, dst * n + src])), max(1, n))
    bounds = np.searchsorted(at, np.arange(n + 1))
    rank = np.empty(n, np.int64)
    rank[np.lexsort((np.arange(n), np.diff(bounds)))] = np.arange(n)
    # A clique's other members come later than its root, so a root with too few of them has none that counts.
    ahead = np.bincount(at[rank[near] > rank[at]], minlength=n)
    roots = np.argsort(rank)
    roots = roots[ahead[roots] >= k_min - 1].tolist()
    del src, dst, at, ahead
    adjacent, order, named = _Near(near, bounds), rank.tolist(), ids.tolist()
    found = []
    for v in roots:
        later = {w for w in adjacent[v] if order[w] > order[v]}
        found += [[named[w] for w in c] for c in C.bron_kerbosch(adjacent, v, later, adjacent[v] - later) if len(c) >= k_min]
    adjacent.clear()
    holds: dict[int, list[int]] = defaultdict(list)
    overlaps: list[tuple[int, int, int]] = []
    for i, c in enumerate(found):
        shared: dict[int, int] = defaultdict(int)
        for v in c:
            for j in holds[v]:
                shared[j] += 1
            holds[v].append(i)
        overlaps += [(n, i, j) for j, n in shared.items() if n >= k_min - 1]
    out = []
    top = max(map(len, found), default=0)
    for k in range(k_min, min(top, k_max or top) + 1):
        parent = list(range(len(found)))

        def find(i: int) -> int:
            while parent[i] != i:
                parent[i] = parent[parent[i]]
                i = parent[i]
            return i

        for n, i, j in overlaps:
            if n >= k - 1 and len(found[i]) >= k and len(found[j]) >= k:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
        least: dict[int, list[int]] = {}
        own = [(find(i), c) for i, c in enumerate(found) if len(c) >= k]
        for r, c in own:
            least[r] = min(least.get(r, c[:k]), c[:k])
        out += [(k, "-".join(map(str, least[r])), c) for r, c in own]
    return out


def percolate_local(edges: DataFrame, k: int, by: str | None = None, k_max: int | None = -1) -> DataFrame:
    """The serial method as one task: over the whole graph, or over each value of `by` (a piece that fits a task).

    Covers at k alone; with k_max at every k up to that, and with None up to each graph's largest clique.
    """
    rows = edges.select((F.col(by) if by else F.lit(0)).cast("long").alias("g"), "src", "dst")
    last = k if k_max == -1 else k_max

    def run(table: pa.Table) -> pa.Table:
        found = serial_covers_of(table.column("src").to_numpy(), table.column("dst").to_numpy(), k, last)
        g = table.column("g")[0].as_py()
        return pa.table({"g": pa.array([g] * len(found), pa.int64()), "k": pa.array([n for n, _, _ in found], pa.int64()), "community_key": pa.array([x for _, x, _ in found], pa.string()), "members": pa.array([c for _, _, c in found], pa.list_(pa.int64()))})

    out = rows.groupBy("g").applyInArrow(run, "g long, k long, community_key string, members array<long>")
    return out.withColumnRenamed("g", by) if by else out.drop("g")


def membership(cover: DataFrame, *by: str) -> DataFrame:
    """(by, k, community_key, vid)."""
    return cover.select(*by, "k", "community_key", F.explode("members").alias("vid")).distinct()


def communities(cover: DataFrame, *by: str) -> DataFrame:
    """(by, k, community_key, size)."""
    return membership(cover, *by).groupBy(*by, "k", "community_key").agg(F.count("*").alias("size"))


# ---- choosing k, diagnosis -------------------------------------------------------------------------------------------


def k_profile(covers: DataFrame) -> DataFrame:
    """(k, n_communities, largest, second, covered) of covers at several k."""
    # Few different sizes a k meet in one row, never the communities themselves.
    each = communities(covers).groupBy("k", "size").agg(F.count("*").alias("n"))
    top = each.groupBy("k").agg(F.sum("n").alias("n_communities"), F.max("size").alias("largest"), F.max_by("n", "size").alias("at_top"))
    rest = each.join(top.select("k", "largest"), "k").where(F.col("size") < F.col("largest")).groupBy("k").agg(F.max("size").alias("rest"))
    covered = membership(covers).select("k", "vid").distinct().groupBy("k").agg(F.count("*").alias("covered"))
    second = F.when(F.col("at_top") > 1, F.col("largest")).otherwise(F.coalesce("rest", F.lit(0)))
    return top.join(rest, "k", "left").join(covered, "k").select("k", "n_communities", "largest", second.alias("second"), "covered")


def suggest_k(covers: DataFrame, largest_share: float = 0.5) -> DataFrame:
    """(k): the least k whose largest community no longer dominates what is covered; the largest k if all do."""
    p = k_profile(covers)
    return p.agg(F.coalesce(F.min(F.when(F.col("largest") < largest_share * F.col("covered"), F.col("k"))), F.max("k")).alias("k"))


def uncovered(edges: DataFrame, cover: DataFrame) -> DataFrame:
    """(vid) of vertices in no community."""
    all_ = edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()
    return all_.join(membership(cover).select("vid").distinct(), "vid", "left_anti")


def diagnose(edges: DataFrame, covers: DataFrame, ks: list[int], share: float = 0.5) -> DataFrame:
    """(k, no_cliques, percolating) for each asked k: whether its cover is empty, or one community holds most of the graph."""
    n = edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).agg(F.count_distinct("vid").alias("n"))
    asked = edges.sparkSession.createDataFrame([(k,) for k in sorted(set(ks))], "k long")
    rows = asked.join(k_profile(covers), "k", "left").crossJoin(n)  # one row of n
    return rows.select("k", F.col("n_communities").isNull().alias("no_cliques"), F.coalesce(F.col("largest") >= share * F.col("n"), F.lit(False)).alias("percolating"))


# ---- parts, single links ---------------------------------------------------------------------------------------------


def percolate_by_part(edges: DataFrame, part: str, k: int, k_map: dict | None = None) -> DataFrame:
    """Covers of the parts of a heterogeneous graph apart, each at its own k if k_map names one."""
    if not k_map:
        return percolate(edges, k, "kclique", by=(part,))
    out = None
    for one in sorted({k, *k_map.values()}):
        own = [p for p, v in k_map.items() if v == one]
        rows = edges.where(F.col(part).isin(own)) if one != k else edges.where(~F.col(part).isin([p for p, v in k_map.items() if v != k]))
        cover = percolate(rows, one, "kclique", by=(part,))
        out = cover if out is None else out.unionByName(cover)
    return out


def update_cover(edges: DataFrame, cover: DataFrame, k: int, added: DataFrame | None = None, removed: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(links, cover) after links are added and removed; only communities that touch an end are found anew.

    A community without any changed vertex keeps all its cliques and gains none, so it stays as it is. The others are
    percolated again over the links among their vertices and the neighbourhoods of the changed ends.
    """
    empty = edges.select("src", "dst").where("false")
    added, removed = (x.select("src", "dst") if x is not None else empty for x in (added, removed))
    cover = written(cover, "cover")
    links = written(edges.select("src", "dst").join(removed, ["src", "dst"], "left_anti").unionByName(added).distinct(), "links")
    ends = added.unionByName(removed)
    ends = ends.select(F.col("src").alias("vid")).unionByName(ends.select(F.col("dst").alias("vid"))).distinct()
    hit = membership(cover).join(ends, "vid", "left_semi").select("community_key").distinct()
    kept = cover.join(hit, "community_key", "left_anti")
    from ..graph import both_ways

    near = both_ways(links).join(ends, "vid", "left_semi").select(F.col("other").alias("vid"))
    area = membership(cover).join(hit, "community_key", "left_semi").select("vid").unionByName(near).unionByName(ends).distinct()
    inside = links.join(area.withColumnRenamed("vid", "src"), "src", "left_semi").join(area.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    anew = written(percolate(written(inside, "inside"), k), "anew")
    # Cliques of kept communities may lie in the area too; a new community that holds none of the changed cliques is
    # one of those, whole or in part, and is left to its old row.
    fresh = anew.select("community_key").distinct().join(_seen(kept, anew, k), "community_key", "left_anti")
    return links, kept.unionByName(anew.join(fresh, "community_key", "left_semi"))


def link_impact(edges: DataFrame, u: int, v: int, op: str, k: int) -> DataFrame:
    """(side, k, community_key, size): communities that only the cover before or only the one after a link's change has.

    op is add or remove. Only communities of an end of the link can be among them.
    """
    one = edges.sparkSession.createDataFrame([(min(u, v), max(u, v))], "src long, dst long")
    before = written(percolate(edges, k), "before")
    _, after = update_cover(edges, before, k, **{"added" if op == "add" else "removed": one})
    a, b = (communities(x).select("k", "community_key", "size") for x in (before, written(after, "after")))
    return a.exceptAll(b).select(F.lit("before").alias("side"), "*").unionByName(b.exceptAll(a).select(F.lit("after").alias("side"), "*"))


def _seen(kept: DataFrame, anew: DataFrame, k: int) -> DataFrame:
    """Keys of new communities that share k vertices of one clique with a kept community."""
    a = anew.select("community_key", "members", F.explode("members").alias("vid"))
    # Kept cliques far from the change fall out before their members are carried anywhere.
    near = a.select("vid").distinct()
    b = kept.select(F.col("members").alias("old"), F.explode("members").alias("vid")).join(near, "vid", "left_semi")
    return a.join(b, "vid").where(F.size(F.array_intersect("members", "old")) >= k).select("community_key").distinct()


# ---- weights and directions ------------------------------------------------------------------------------------------


def percolate_weighted(edges: DataFrame, k: int, min_weight) -> DataFrame:
    """Percolation over the links of at least min_weight."""
    return percolate(edges.where(F.col("weight") >= min_weight), k)


def weight_sweep(edges: DataFrame, k: int, thresholds: list) -> DataFrame:
    """(min_weight, n_communities, largest, second, covered) for each threshold: just below percolation, largest is near
    twice the second."""
    out = None
    for w in thresholds:
        row = k_profile(percolate_weighted(edges, k, w)).drop("k").select(F.lit(w).alias("min_weight"), "*")
        out = row if out is None else out.unionByName(row)
    asked = edges.sparkSession.createDataFrame([(w,) for w in thresholds], ["min_weight"])
    return asked.join(out, "min_weight", "left").na.fill(0)


def _from_cliques(cliques: DataFrame, k: int) -> DataFrame:
    named = written(cliques.select(C.name().alias("clique"), "members"), "cliques")
    labels = labels_of(C.adjacency_links(named, k))
    return _keyed(named.join(labels.withColumnRenamed("node", "clique"), "clique", "left").select(F.coalesce("label", "clique").alias("label"), "members"), k, ())


def _pairs_of(cliques: DataFrame) -> DataFrame:
    first = cliques.select("members", F.posexplode("members").alias("i", "a"))
    return first.select("members", "a", F.explode(F.slice("members", F.col("i") + 2, F.size("members"))).alias("b"))


def percolate_intensity(edges: DataFrame, k: int, min_intensity: float) -> DataFrame:
    """Percolation over k-cliques whose links' geometric mean weight is at least min_intensity (weights above 0)."""
    pairs = _pairs_of(C.k_cliques(edges, k)).join(edges.withColumnsRenamed({"src": "a", "dst": "b"}), ["a", "b"])
    strong = pairs.groupBy("members").agg(F.exp(F.avg(F.ln(F.col("weight").cast("double")))).alias("i")).where(F.col("i") >= min_intensity - 1e-9)
    return _from_cliques(strong.select("members"), k)


def percolate_directed(arcs: DataFrame, k: int) -> DataFrame:
    """Percolation over k-cliques that some order of members agrees with: their one-way arcs form no cycle.

    Members are peeled: one without one-way arcs to the rest goes, k times; a clique with a cycle is never emptied.
    """
    from ..graph import to_undirected

    way = arcs.where("src <> dst").select("src", "dst").distinct()
    one_way = way.join(way.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_anti")
    found = C.k_cliques(to_undirected(arcs), k)
    pairs = _pairs_of(found)
    both = pairs.select("members", F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(pairs.select("members", F.col("b").alias("src"), F.col("a").alias("dst")))
    inside = both.join(one_way, ["src", "dst"]).groupBy("members").agg(F.collect_list(F.struct("src", "dst")).alias("arcs"))
    rows = found.join(inside, "members", "left").select("members", F.coalesce("arcs", F.array().cast("array<struct<src:bigint,dst:bigint>>")).alias("arcs"))
    for _ in range(k):
        # A member that heads no remaining arc is last in the order of those left; its arcs go with it.
        rows = rows.withColumn("heads", F.transform("arcs", lambda x: x["src"])).withColumn("arcs", F.filter("arcs", lambda x: F.array_contains("heads", x["dst"]))).drop("heads")
    return _from_cliques(rows.where(F.size("arcs") == 0).select("members"), k)


def brute_force(links: list[tuple[int, int]], k: int) -> set[frozenset[int]]:
    """Communities straight from the definition, by trying all vertex sets; for tests."""
    near = {frozenset(x) for x in links}
    vertices = sorted({v for x in links for v in x})
    found = [frozenset(c) for c in combinations(vertices, k) if all(frozenset(p) in near for p in combinations(c, 2))]
    groups: list[set[frozenset[int]]] = []
    for c in found:
        touching = [g for g in groups if any(len(c & d) >= k - 1 for d in g)]
        groups = [g for g in groups if g not in touching] + [set().union({c}, *touching)]
    return {frozenset().union(*g) for g in groups}
