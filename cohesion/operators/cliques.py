"""Cliques: of fixed size, maximal ones, their faces and overlaps. `by` columns (a piece, a part) keep graphs apart."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import both_ways, oriented

#: Guards that fail loudly instead of flooding the cluster: maximal cliques found at one vertex, k-cliques of one clique.
MAX_CLIQUES = 5_000_000
MAX_SUBSETS = 1_000_000


def k_cliques(edges: DataFrame, k: int, by: tuple[str, ...] = (), rooted: bool = False) -> DataFrame:
    """(by, members): every set of k mutually linked vertices once, members ascending; rooted adds its first vertex, root.

    Cliques grow along the orientation: a row keeps the common later neighbours of its members, so each level is one
    equi-join on the vertex that is added, and rows that can no longer reach k are dropped at once.
    """
    out = oriented(edges, *by)
    later = out.groupBy(*by, "u").agg(F.collect_set("v").alias("later"))
    rows = later.where(F.size("later") >= k - 1).select(*by, F.array("u").alias("members"), F.col("later").alias("common"))
    for size in range(2, k + 1):
        grown = rows.select(*by, "members", "common", F.explode("common").alias("u"))
        members = F.concat("members", F.array("u")).alias("members")
        if size == k:
            rows = grown.select(*by, members)
        else:
            rows = grown.join(later, [*by, "u"]).select(*by, members, F.array_intersect("common", "later").alias("common")).where(F.size("common") >= k - size)
    return rows.select(*by, *([F.col("members")[0].alias("root")] if rooted else []), F.array_sort("members").alias("members"))


def name(members: str = "members"):
    """A clique's own id: its members in order."""
    return F.array_join(F.transform(members, lambda x: x.cast("string")), "-")


def faces(cliques: DataFrame, k: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, face, clique): the k subsets of size k-1 of every k-clique."""
    one = F.transform(F.sequence(F.lit(1), F.lit(k)), lambda i: F.filter("members", lambda x, j: j + 1 != i))
    return cliques.select(*by, "clique", F.explode(one).alias("f")).select(*by, F.array_join(F.transform("f", lambda x: x.cast("string")), "-").alias("face"), "clique")


def adjacency_links(cliques: DataFrame, k: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(u, v) links that connect all k-cliques of a face: a star at its least one, never all pairs."""
    at = faces(cliques, k, by)
    least = at.groupBy(*by, "face").agg(F.min("clique").alias("least"), F.count("*").alias("n")).where("n > 1")
    return at.join(least, [*by, "face"]).where("clique <> least").select(F.col("clique").alias("u"), F.col("least").alias("v"))


def bron_kerbosch(adjacent: dict[int, set[int]], root: int, later: set[int], earlier: set[int]) -> Iterator[list[int]]:
    """Maximal cliques through root whose other members are in later; earlier only rules cliques out. No recursion."""
    stack = [([root], set(later), set(earlier))]
    while stack:
        have, may, not_ = stack.pop()
        if not may:
            if not not_:
                yield sorted(have)
            continue
        pivot = max(may | not_, key=lambda v: len(may & adjacent[v]))
        for v in list(may - adjacent[pivot]):
            stack.append(([*have, v], may & adjacent[v], not_ & adjacent[v]))
            may.discard(v)
            not_.add(v)


def maximal_cliques(edges: DataFrame, min_size: int = 2, strategy: str = "ego", by: tuple[str, ...] = ()) -> DataFrame:
    """(by, members): every maximal clique once, found at its vertex of least (degree, id).

    ego       one row for each vertex with its neighbours' links among themselves; cliques in an Arrow map
    frontier  DataFrame steps only: rows of (clique, may join, must not), a pivot's neighbours set aside at each step
    """
    out = oriented(edges, *by)
    after = out.groupBy(*by, "u").agg(F.collect_set("v").alias("later"))
    if strategy == "frontier":
        near = both_ways(edges, *by).groupBy(*by, "vid").agg(F.array_sort(F.collect_set("other")).alias("near"))
        start = near.join(after.withColumnRenamed("u", "vid"), [*by, "vid"]).select(*by, "vid", "near", "later")
        return _frontier(start, near, by).where(F.size("members") >= min_size)
    # One row a link u -> v: what v's later neighbours and u's have in common. It is read twice: as the links inside
    # u's later neighbourhood, and, at v, as what an earlier neighbour is linked to of v's own. No vertex's whole
    # neighbourhood is ever spread, only the part above it in the orientation.
    wedges = after.select(*by, "u", "later", F.explode("later").alias("v"))
    common = wedges.join(after.withColumnsRenamed({"u": "v", "later": "theirs"}), [*by, "v"], "left").select(*by, "u", "v", F.coalesce(F.array_intersect("later", "theirs"), F.array().cast("array<bigint>")).alias("theirs"))
    # The rows of u name its later neighbours, so no row carries them all on.
    mine = common.groupBy(*by, F.col("u").alias("root")).agg(F.collect_list(F.struct(F.col("v").alias("vid"), "theirs")).alias("net"))
    # Equal sets of several earlier neighbours rule out the same cliques.
    earlier = common.where(F.size("theirs") > 0).select(*by, F.col("v").alias("root"), "theirs").groupBy(*by, "root").agg(F.collect_set("theirs").alias("before"))
    nets = mine.join(earlier, [*by, "root"], "left")
    kinds = [f"{c} {edges.schema[c].dataType.simpleString()}" for c in by]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k = len(by)
        for batch in batches:
            keys, members = [[] for _ in by], []
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                root, net, before = row[k], row[k + 1], row[k + 2] or []
                later = {x["vid"] for x in net}
                adjacent: dict = {v: set() for v in later}
                for x in net:
                    for w in x["theirs"]:
                        adjacent[x["vid"]].add(w)
                        adjacent[w].add(x["vid"])
                for j, some in enumerate(before):
                    adjacent["before", j] = set(some)
                    for w in some:
                        adjacent[w].add(("before", j))
                found = 0
                for clique in bron_kerbosch(adjacent, root, later, {("before", j) for j in range(len(before))}):
                    found += 1
                    if found > MAX_CLIQUES:
                        raise ValueError(f"over {MAX_CLIQUES} maximal cliques at vertex {root} alone: drop weak links first (percolate_weighted)")
                    members.append(clique)
                    for i in range(k):
                        keys[i].append(row[i])
            yield pa.RecordBatch.from_arrays([*(pa.array(x, batch.schema.field(i).type) for i, x in enumerate(keys)), pa.array(members, pa.list_(pa.int64()))], [*by, "members"])

    return nets.mapInArrow(run, ", ".join([*kinds, "members array<long>"])).where(F.size("members") >= min_size)


def maximal_cliques_of(edges: DataFrame, vids: DataFrame, min_size: int = 2) -> DataFrame:
    """(members): maximal cliques of the whole graph that hold any of the given vertices (vid).

    All cliques of a vertex lie in its neighbourhood, and what would extend one does too.
    """
    ids = vids.select("vid").distinct()
    area = both_ways(edges).join(ids, "vid", "left_semi").select(F.col("other").alias("vid")).unionByName(ids).distinct()
    inside = edges.select("src", "dst").join(area.toDF("src"), "src", "left_semi").join(area.toDF("dst"), "dst", "left_semi")
    found = maximal_cliques(inside, min_size)
    return found.select("members", F.explode("members").alias("vid")).join(ids, "vid", "left_semi").select("members").distinct()


def _frontier(start: DataFrame, near: DataFrame, by: tuple[str, ...]) -> DataFrame:
    from ..session import written

    rows = start.select(*by, F.array("vid").alias("members"), F.col("later").alias("may"), F.array_except("near", "later").alias("no"))
    done = None
    while True:
        rows = written(rows, "frontier")
        found = rows.where("size(may) = 0 and size(no) = 0").select(*by, "members")
        done = found if done is None else done.unionByName(found)
        rows = rows.where("size(may) > 0")
        if not rows.limit(1).count():
            return done.select(*by, F.array_sort("members").alias("members"))
        pivot = rows.withColumn("vid", F.element_at("may", 1)).join(near, [*by, "vid"])
        tried = pivot.select(*by, "members", "may", "no", F.array_except("may", "near").alias("tries"))
        each = tried.select(*by, "members", "may", "no", "tries", F.posexplode("tries").alias("i", "vid"))
        past = F.slice("tries", 1, F.col("i"))
        grown = each.join(near, [*by, "vid"])
        rows = grown.select(
            *by, F.concat("members", F.array("vid")).alias("members"), F.array_intersect(F.array_except("may", past), "near").alias("may"), F.array_intersect(F.array_union("no", past), "near").alias("no")
        )


def clique_overlaps(cliques: DataFrame, min_shared: int = 2, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, ci, cj, shared) of clique pairs with min_shared or more common members, sparse.

    Prefix filter: cliques that share t members share one of the s-t+1 rarest of either, so only those are joined.
    """
    named = cliques.select(*by, name().alias("clique"), "members").where(F.size("members") >= min_shared)
    often = named.select(*by, F.explode("members").alias("vid")).groupBy(*by, "vid").agg(F.count("*").alias("often"))
    ranked = named.select(*by, "clique", "members", F.explode("members").alias("vid")).join(often, [*by, "vid"])
    sorted_ = ranked.groupBy(*by, "clique", "members").agg(F.array_sort(F.collect_list(F.struct("often", "vid"))).alias("r"))
    prefix = sorted_.select(*by, "clique", "members", F.explode(F.slice("r", F.lit(1), F.size("r") - min_shared + 1)).alias("x")).select(*by, "clique", "members", F.col("x.vid").alias("vid"))
    other = prefix.withColumnsRenamed({"clique": "cj", "members": "mj"})
    pairs = prefix.join(other, [*by, "vid"]).where("clique < cj").select(*by, F.col("clique").alias("ci"), "cj", F.size(F.array_intersect("members", "mj")).alias("shared"))
    return pairs.where(F.col("shared") >= min_shared).distinct()


def threshold_graph(cliques: DataFrame, overlaps: DataFrame, k: int, convention: str = "definition", by: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """(cliques, links) that percolate at k: sizes from k and overlaps from k-1; printed: sizes above k, overlaps from k."""
    least, shared = (k, k - 1) if convention == "definition" else (k + 1, k)
    return cliques.where(F.size("members") >= least), overlaps.where(F.col("shared") >= shared)
