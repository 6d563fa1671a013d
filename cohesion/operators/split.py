"""Split, solve, merge: pieces of a graph with duplicated borders, covers of the pieces, and the whole cover again.

An owner is given to every vertex; a piece holds its owned vertices, all their neighbours, and the links among them.
Then every clique with an owned vertex is whole in that piece, two adjacent cliques share a vertex whose owner's piece
holds both, and merging local communities that share a k-clique gives exactly the whole graph's cover, for any owners.
"""

from __future__ import annotations

import time
from collections import defaultdict
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph import both_ways, degrees
from ..session import written
from . import cliques as C
from .components import components
from .measures import link_support
from .percolation import labels_of, percolate, percolate_local

#: Links up to which one task grows the pieces; more links grow level by level as DataFrames.
LOCAL_LINKS = 16_000_000


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()


def owners(edges: DataFrame, rule: str = "hash", parts: int = 4, **kw) -> DataFrame:
    """(vid, piece) by rule: hash (of the id), mod, range (of ids), components, bfs."""
    v = vertices(edges)
    if rule == "hash":
        return v.select("vid", F.pmod(F.xxhash64("vid"), F.lit(parts)).cast("long").alias("piece"))
    if rule == "mod":
        return v.select("vid", F.pmod("vid", F.lit(parts)).cast("long").alias("piece"))
    if rule == "range":
        # Bounds by quantiles: a window over all vertices would be one task.
        at = v.agg(F.percentile_approx("vid", [i / parts for i in range(1, parts)] or [1.0], 10_000).alias("q")).first()["q"] or []
        piece = sum((F.when(F.col("vid") > b, 1).otherwise(0) for b in at), F.lit(0)) if parts > 1 else F.lit(0)
        return v.select("vid", piece.cast("long").alias("piece"))
    if rule == "components":
        return components(edges.select(F.col("src").alias("u"), F.col("dst").alias("v"))).select(F.col("node").alias("vid"), F.col("label").alias("piece"))
    if rule == "bfs":
        return bfs_owners(edges, **kw)
    raise ValueError(f"unknown owner rule {rule}")


def choose_seeds(edges: DataFrame, unassigned: DataFrame, n_seeds: int) -> DataFrame:
    """(vid) of the highest-degree unassigned vertices; ties go to the least id."""
    return degrees(edges).join(unassigned, "vid", "left_semi").orderBy(F.desc("degree"), "vid").limit(n_seeds).select("vid")


def grow(links: list[tuple[int, int]], size_limit: int, n_seeds: int) -> tuple[dict[int, int], dict[int, set[int]], list[dict]]:
    """(owner of each vertex, reached vertices of each piece, a trace row for each level), as grown() finds them."""
    ends = np.array(links, np.int64).reshape(-1, 2)
    ids, own, piece, at, trace = grown(ends[:, 0], ends[:, 1], size_limit, n_seeds)
    reach: dict[int, set[int]] = {}
    for p, v in zip(piece.tolist(), ids[at].tolist()):
        reach.setdefault(p, set()).add(v)
    return dict(zip(ids.tolist(), own.tolist())), reach, trace


def grown(src: np.ndarray, dst: np.ndarray, size_limit: int, n_seeds: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[dict]]:
    """(ids, piece that owns each, and the reached (piece, place in ids) pairs, a trace row for each level), in one memory.

    All pieces step one level at a time; a vertex that several reach in a level goes to the piece that was seeded
    first, and the others keep a copy that they do not grow from. Vertices left over are seeded anew.
    """
    ids = np.union1d(src, dst)
    n = len(ids)
    a = np.concatenate([np.searchsorted(ids, src), np.searchsorted(ids, dst)]).astype(np.int32)
    near = np.concatenate([a[len(src) :], a[: len(src)]])[np.argsort(a, kind="stable")]
    degree = np.bincount(a, minlength=n)
    bounds = np.concatenate([[0], np.cumsum(degree)])
    del a
    left = np.lexsort((np.arange(n), -degree))
    own = np.full(n, -1, np.int64)
    held, pieces, trace, round_ = [], 0, [], 0
    while len(left):
        seeds = left[:n_seeds]
        # Pairs of this round as one number, its own piece times n plus the place; earlier pieces step no more.
        have = front = np.arange(len(seeds)) * n + seeds
        own[seeds] = pieces + np.arange(len(seeds))
        size, level = np.ones(len(seeds), np.int64), 0
        while len(front):
            piece, at = np.divmod(front, n)
            steps = size[piece] < size_limit
            piece, at = piece[steps], at[steps]
            far = bounds[at + 1] - bounds[at]
            first = np.repeat(bounds[at] - np.concatenate([[0], np.cumsum(far)])[:-1], far)
            step = np.unique(np.repeat(piece, far) * n + near[first + np.arange(len(first))])
            new = step[have[np.searchsorted(have, step).clip(0, len(have) - 1)] != step]
            if not len(new):
                break
            have = np.sort(np.concatenate([have, new]), kind="stable")
            piece, at = np.divmod(new, n)
            size += np.bincount(piece, minlength=len(size))
            free = own[at] < 0
            taken, first = np.unique(at[free], return_index=True)  # pairs are in the order of pieces
            own[taken] = pieces + piece[free][first]
            stepped = new[free][np.sort(first)]
            trace.append({"round": round_, "level": level, "frontier": len(front), "new": len(stepped)})
            front, level = stepped, level + 1
        held.append((pieces + have // n, have % n))
        pieces += len(seeds)
        left = left[own[left] < 0]
        round_ += 1
    piece, at = (np.concatenate(x) for x in zip(*held)) if held else (np.zeros(0, np.int64),) * 2
    return ids, own, piece, at, trace


def merge_small(owner: dict[int, int], links: list[tuple[int, int]], min_piece: int) -> dict[int, int]:
    """The piece that each ends in once those of fewer than min_piece vertices join the neighbour with most cut links.

    Ties go to the least piece; pieces without neighbours fill bins of min_piece together.
    """
    p, q = (np.array([owner[x[i]] for x in links], np.int64) for i in range(2))
    return _merged(np.array(list(owner.values()), np.int64), p, q, min_piece)


def _merged(own: np.ndarray, p: np.ndarray, q: np.ndarray, min_piece: int) -> dict[int, int]:
    """As merge_small, of the piece of each vertex and of the ends of each link."""
    sizes = dict(zip(*(x.tolist() for x in np.unique(own, return_counts=True))))
    cut = p != q
    n = max(sizes, default=0) + 1
    pairs, times = np.unique(np.minimum(p, q)[cut] * n + np.maximum(p, q)[cut], return_counts=True)
    return merged_into(sizes, list(zip((pairs // n).tolist(), (pairs % n).tolist(), times.tolist())), min_piece)


def merged_into(sizes: dict[int, int], cuts: list[tuple[int, int, int]], min_piece: int) -> dict[int, int]:
    """The piece that each piece ends in, of piece sizes and (p, q, cut links) of pairs, each pair once."""
    size = dict(sizes)
    cut: dict[int, dict[int, int]] = defaultdict(lambda: defaultdict(int))
    for p, q, n in cuts:
        cut[p][q] = cut[q][p] = n
    into = {p: p for p in size}
    alone, filled = None, 0
    for p in sorted(size, key=lambda x: (size[x], x)):
        if size[p] >= min_piece:
            continue
        if cut[p]:
            q = min(cut[p], key=lambda x: (-cut[p][x], x))
            into[p] = q
            size[q] += size.pop(p)
            for r, n in cut.pop(p).items():
                del cut[r][p]
                if r != q:
                    cut[q][r] += n
                    cut[r][q] += n
        else:
            if alone is None or filled >= min_piece:
                alone, filled = p, 0
            into[p] = alone
            filled += size[p]

    def end(p: int) -> int:
        while into[p] != p:
            p = into[p]
        return p

    return {p: end(p) for p in sizes}


def _seeds_of(edges: DataFrame, size_limit: int, n_seeds: int | None) -> int:
    """Seeds a round: as asked, or so many that the first round's pieces can cover a quarter of the graph."""
    return n_seeds or max(1, vertices(edges).count() // (4 * max(1, size_limit)))


def bfs_pieces(edges: DataFrame, size_limit: int = 100, n_seeds: int | None = 4, min_piece: int | None = None, distributed: bool | None = None) -> DataFrame:
    """(piece, vid, owned): pieces as breadth-first growth leaves them, with copies of the vertices that others hold.

    Growth starts from the hubs and again from what is left over; then tiny pieces, of fewer than min_piece vertices
    (the size limit unless named), join neighbours. One task does it up to LOCAL_LINKS links, DataFrames beyond, alike.
    """
    links = edges.select("src", "dst")
    n_seeds = _seeds_of(edges, size_limit, n_seeds)
    least = size_limit if min_piece is None else min_piece
    if distributed or (distributed is None and links.limit(LOCAL_LINKS + 1).count() > LOCAL_LINKS):
        held = _grown_by_levels(edges, size_limit, n_seeds)[0]
        if least > 1:
            end = _small_merged(edges, held.where("owned").select("vid", "piece"), least)
            held = held.join(end, "piece").groupBy(F.col("into").alias("piece"), "vid").agg(F.max("owned").alias("owned"))
        return held.select("piece", "vid", "owned")

    def run(batches):
        src, dst = _ends(batches)
        ids, own, piece, at, _ = grown(src, dst, size_limit, n_seeds)
        yield from _held(ids, own, piece, at, _end(ids, own, src, dst, least))

    return links.coalesce(1).mapInArrow(run, "piece long, vid long, owned boolean")


def _ends(batches) -> tuple[np.ndarray, np.ndarray]:
    """The first two columns of all batches."""
    held = [(np.asarray(b.column(0)), np.asarray(b.column(1))) for b in batches]
    return tuple(np.concatenate(x) for x in zip(*held)) if held else (np.zeros(0, np.int64),) * 2


def _end(ids: np.ndarray, own: np.ndarray, src: np.ndarray, dst: np.ndarray, min_piece: int) -> np.ndarray:
    """By piece, the one that each ends in after the clean-up."""
    end = _merged(own, own[np.searchsorted(ids, src)], own[np.searchsorted(ids, dst)], min_piece)
    return np.array([end[p] for p in range(len(end))], np.int64)


def _held(ids: np.ndarray, own: np.ndarray, piece: np.ndarray, at: np.ndarray, end: np.ndarray):
    """Batches (piece, vid, owned) of reached pairs, once pieces are those they end in."""
    pairs = np.unique(end[piece] * max(1, len(ids)) + at)
    for i in range(0, len(pairs), 1 << 18):
        p, v = np.divmod(pairs[i : i + (1 << 18)], len(ids))
        yield pa.RecordBatch.from_arrays([pa.array(p), pa.array(ids[v]), pa.array(end[own[v]] == p)], ["piece", "vid", "owned"])


def bfs_growth(edges: DataFrame, size_limit: int = 100, n_seeds: int | None = 4, distributed: bool | None = None) -> DataFrame:
    """All that one breadth-first growth finds, as a written table that bfs_owners, tiny_pieces and split_trace read.

    Rows (vid, first, piece) of vertices with their pieces before and after the clean-up of tiny ones, and rows
    (round, level, frontier, new) of the trace.
    """
    links = edges.select("src", "dst")
    n_seeds = _seeds_of(edges, size_limit, n_seeds)
    names = ("vid", "first", "piece", "round", "level", "frontier", "new")
    kind = ", ".join(f"{n} long" for n in names)
    if distributed or (distributed is None and links.limit(LOCAL_LINKS + 1).count() > LOCAL_LINKS):
        held, trace = _grown_by_levels(edges, size_limit, n_seeds)
        own = held.where("owned").select("vid", "piece")
        end = _small_merged(edges, own, size_limit)
        rows = own.join(end, "piece").select("vid", F.col("piece").alias("first"), F.col("into").alias("piece"), *(F.lit(None).cast("long").alias(n) for n in names[3:]))
        return written(rows.unionByName(edges.sparkSession.createDataFrame([(None,) * 3 + tuple(t[n] for n in names[3:]) for t in trace], kind)), "growth")

    def run(batches):
        src, dst = _ends(batches)
        ids, own, _, _, trace = grown(src, dst, size_limit, n_seeds)
        end = _end(ids, own, src, dst, size_limit)
        none = lambda n: [pa.nulls(n, pa.int64())]
        for i in range(0, len(ids), 1 << 18):
            some = own[i : i + (1 << 18)]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (ids[i : i + (1 << 18)], some, end[some])] + 4 * none(len(some)), list(names))
        yield pa.RecordBatch.from_arrays(3 * none(len(trace)) + [pa.array([t[n] for t in trace], pa.int64()) for n in names[3:]], list(names))

    return written(links.coalesce(1).mapInArrow(run, kind), "growth")


def bfs_owners(edges: DataFrame, size_limit: int = 100, n_seeds: int | None = 4, min_piece: int | None = None, distributed: bool | None = None, growth: DataFrame | None = None) -> DataFrame:
    """(vid, piece) by breadth-first growth, see bfs_pieces; of a table by bfs_growth if there is one."""
    if growth is not None:
        return growth.where("vid IS NOT NULL").select("vid", "piece")
    return bfs_pieces(edges, size_limit, n_seeds, min_piece, distributed).where("owned").select("vid", "piece")


#: Tables of one level each that are read together before they are written as one.
DELTAS = 8


def _grown_by_levels(edges: DataFrame, size_limit: int, n_seeds: int) -> tuple[DataFrame, list[dict]]:
    """((piece, vid, owned) and a trace) of the same growth on graphs beyond one task.

    A level is one join of the frontier with the links, written once as what it adds; nothing held before is rewritten but
    every DELTAS levels. All pieces of a round step together.
    """
    spark = edges.sparkSession
    near = written(both_ways(edges), "near")
    ranked = written(degrees(edges), "degrees")
    deltas: list[DataFrame] = []
    pieces, trace, round_ = 0, [], 0

    def held() -> DataFrame:
        nonlocal deltas
        if len(deltas) >= DELTAS:
            whole = deltas[0]
            for d in deltas[1:]:
                whole = whole.unionByName(d)
            deltas = [written(whole, "held")]
        whole = deltas[0]
        for d in deltas[1:]:
            whole = whole.unionByName(d)
        return whole

    while True:
        free = ranked.join(held().where("owned").select("vid"), "vid", "left_anti") if deltas else ranked
        seeds = [r["vid"] for r in free.orderBy(F.desc("degree"), "vid").limit(n_seeds).collect()]
        if not seeds:
            break
        front = spark.createDataFrame([(pieces + i, v, True) for i, v in enumerate(seeds)], "piece long, vid long, owned boolean")
        pieces += len(seeds)
        deltas.append(written(front, "level"))
        front, ahead, level = deltas[-1], len(seeds), 0
        while ahead:
            have = held()
            small = have.groupBy("piece").count().where(F.col("count") < size_limit).select("piece")
            step = front.join(small, "piece", "left_semi").join(near, "vid").select("piece", F.col("other").alias("vid")).distinct().join(have.select("piece", "vid"), ["piece", "vid"], "left_anti")
            # A vertex that several reach in a level goes to the piece that was seeded first.
            free = step.join(have.where("owned").select("vid"), "vid", "left_anti").groupBy("vid").agg(F.min("piece").alias("first"))
            new = written(step.join(free, "vid", "left").select("piece", "vid", F.coalesce(F.col("first") == F.col("piece"), F.lit(False)).alias("owned")), "level")
            r = new.agg(F.count("*").alias("n"), F.count_if("owned").alias("own")).first()
            if not r["n"]:
                break
            trace.append({"round": round_, "level": level, "frontier": ahead, "new": r["own"]})
            deltas.append(new)
            front, ahead, level = new.where("owned"), r["own"], level + 1
        round_ += 1
    return (held() if deltas else spark.createDataFrame([], "piece long, vid long, owned boolean")), trace


def _small_merged(edges: DataFrame, owner: DataFrame, min_piece: int) -> DataFrame:
    """(piece, into) as merge_small has it: vertices and links are counted by DataFrames, and one task walks the pieces."""
    sizes = owner.groupBy(F.col("piece").alias("p")).agg(F.count("*").alias("n")).select("p", F.lit(None).cast("long").alias("q"), "n")
    cuts = boundary(edges, owner).groupBy(F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q")).agg(F.count("*").alias("n"))

    def run(batches):
        rows = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns))]
        end = merged_into({p: n for p, q, n in rows if q is None}, [r for r in rows if r[1] is not None], min_piece)
        yield pa.RecordBatch.from_arrays([pa.array(list(end), pa.int64()), pa.array(list(end.values()), pa.int64())], ["piece", "into"])

    # Rows of pieces and of neighbouring pairs, not of vertices or links.
    return sizes.unionByName(cuts).coalesce(1).mapInArrow(run, "piece long, into long")


def _induced(edges: DataFrame, own: DataFrame) -> DataFrame:
    a, b = own.select("piece", F.col("vid").alias("src")), own.select("piece", F.col("vid").alias("dst"))
    return edges.select("src", "dst").join(a, "src").join(b, ["piece", "dst"]).select("piece", "src", "dst")


def pieces_of(edges: DataFrame, owner: DataFrame, closure: str = "halo", k: int = 3) -> tuple[DataFrame, DataFrame]:
    """(vertices (piece, vid, owned), links (piece, src, dst)).

    closure: halo takes in all neighbours; triangle only those over a link in some triangle, which is smaller and as
    exact from k = 3 on, since each link of a clique of three and more is in a triangle; clique only those that share a
    k-clique with an owned vertex, exact at that k and above; none leaves neighbours out.
    """
    own = owner.select("piece", "vid", F.lit(True).alias("owned"))
    if closure in ("halo", "triangle"):
        over = edges if closure == "halo" else link_support(edges)
        near = both_ways(over).join(owner, "vid").select("piece", F.col("other").alias("vid")).distinct()
    elif closure == "clique":
        found = C.k_cliques(edges, k).select("members", F.explode("members").alias("vid"))
        near = found.join(owner, "vid").select("piece", F.explode("members").alias("vid")).distinct()
    elif closure == "none":
        near = None
    else:
        raise ValueError(f"unknown closure {closure}")
    if near is not None:
        own = own.unionByName(near.join(owner, ["piece", "vid"], "left_anti").select("piece", "vid", F.lit(False).alias("owned")))
    return own, _induced(edges, own)


def printed_pieces(edges: DataFrame, size_limit: int = 100, n_seeds: int | None = 4, min_piece: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Pieces as pieces_of, but with no border taken in: what growth has reached, flagged copies included."""
    own = written(bfs_pieces(edges, size_limit, n_seeds, min_piece), "piece_vertices")
    return own, _induced(edges, own)


def split_by_cut(edges: DataFrame, cut: DataFrame) -> DataFrame:
    """(vid, piece) once the cut links are removed: the components that remain."""
    rest = edges.select("src", "dst").join(cut.select("src", "dst"), ["src", "dst"], "left_anti")
    return components(rest.select(F.col("src").alias("u"), F.col("dst").alias("v")), vertices(edges).withColumnRenamed("vid", "node")).select(F.col("node").alias("vid"), F.col("label").alias("piece"))


def boundary(edges: DataFrame, owner: DataFrame) -> DataFrame:
    """(src, dst, p, q): the cut links with the owners of their ends."""
    return edges.select("src", "dst").join(owner.toDF("src", "p"), "src").join(owner.toDF("dst", "q"), "dst").where("p <> q").select("src", "dst", "p", "q")


def hypergraph(piece_vertices: DataFrame, piece_edges: DataFrame) -> DataFrame:
    """(p, q, shared_vertices, shared_links) of pieces with a common border."""
    a = piece_vertices.select("vid", F.col("piece").alias("p"))
    v = a.join(a.withColumnRenamed("p", "q"), "vid").where("p < q").groupBy("p", "q").agg(F.count("*").alias("shared_vertices"))
    b = piece_edges.select("src", "dst", F.col("piece").alias("p"))
    e = b.join(b.withColumnRenamed("p", "q"), ["src", "dst"]).where("p < q").groupBy("p", "q").agg(F.count("*").alias("shared_links"))
    return v.join(e, ["p", "q"], "left").select("p", "q", "shared_vertices", F.coalesce("shared_links", F.lit(0)).alias("shared_links"))


def percolate_pieces(piece_edges: DataFrame, k: int, executor: str = "local") -> DataFrame:
    """Local covers (piece, k, community_key, members): keyed DataFrame steps for all pieces at once, or a task a piece."""
    return percolate_local(piece_edges, k, "piece") if executor == "local" else percolate(piece_edges, k, by=("piece",))


def active_hyperlinks(hyper: DataFrame, local: DataFrame) -> DataFrame:
    """Hyperlinks whose two pieces both have communities."""
    some = local.select("piece").distinct()
    return hyper.join(some.withColumnRenamed("piece", "p"), "p", "left_semi").join(some.withColumnRenamed("piece", "q"), "q", "left_semi")


def _node(*by: str):
    return F.concat_ws("|", "piece", *[F.col(c).cast("string") for c in by], "community_key")


def _border_cliques(local: DataFrame, piece_vertices: DataFrame, k: int, *by: str) -> DataFrame:
    """(by, node, piece, members): what k or more border vertices leave of each local clique."""
    border = piece_vertices.groupBy("vid").agg(F.count("*").alias("n")).where("n > 1").select("vid")
    rows = local.select(*by, _node(*by).alias("node"), "piece", C.name().alias("c"), F.explode("members").alias("vid")).join(border, "vid", "left_semi")
    return rows.groupBy(*by, "node", "piece", "c").agg(F.array_sort(F.collect_set("vid")).alias("members")).where(F.size("members") >= k).drop("c").distinct()


def _common(left: DataFrame, right: DataFrame, k: int, on: list[str], where: str) -> DataFrame:
    """(on, i, j, common): size of the largest clique common to two communities, from k on.

    Cliques (node, members) meet on one of their s-k+1 least vertices, since common cliques of k share one of those.
    """
    spread = lambda x: x.withColumn("vid", F.explode(F.slice("members", F.lit(1), F.size("members") - k + 1)))
    a, b = spread(left).withColumnRenamed("node", "i"), spread(right).withColumnsRenamed({"node": "j", "members": "mj"})
    met = a.join(b, [*on, "vid"]).where(where).select(*on, "i", "j", F.size(F.array_intersect("members", "mj")).alias("common"))
    return met.where(F.col("common") >= k).groupBy(*on, "i", "j").agg(F.max("common").cast("long").alias("common"))


def community_overlap(local: DataFrame, piece_vertices: DataFrame, k: int) -> DataFrame:
    """(i, j, common): size of the largest clique common to two local communities of different pieces, from k on."""
    rows = _border_cliques(local, piece_vertices, k)
    return _common(rows, rows.withColumnRenamed("piece", "q"), k, [], "piece < q")


def overlap_matrix(local: DataFrame, piece_vertices: DataFrame, k_min: int) -> DataFrame:
    """(k, i, j, common) of local covers at several k: the largest common clique of two communities of one k.

    Cliques of different pieces are compared once, whatever the number of k.
    """
    cliques = local.select("piece", "members").distinct().withColumn("community_key", C.name())
    rows = _border_cliques(cliques, piece_vertices, k_min)
    met = written(_common(rows, rows.withColumnRenamed("piece", "q"), k_min, [], "piece < q"), "common")
    at = local.select("k", _node("k").alias("node"), F.concat_ws("|", "piece", C.name()).alias("c")).distinct()
    both = met.join(at.withColumnsRenamed({"node": "a", "c": "i"}), "i").join(at.withColumnsRenamed({"node": "b", "c": "j"}), ["j", "k"])
    return both.groupBy("k", F.col("a").alias("i"), F.col("b").alias("j")).agg(F.max("common").alias("common")).where(F.col("common") >= F.col("k"))


def _hyperlink_overlap(local: DataFrame, piece_vertices: DataFrame, k: int) -> DataFrame:
    """(i, j): communities that share a k-clique, found at each hyperlink whose two pieces both have communities.

    Only the region that the two pieces share is looked at: local cliques are cut to it before they are compared.
    """
    a = piece_vertices.select("vid", F.col("piece").alias("p"))
    shared = a.join(a.withColumnRenamed("p", "q"), "vid").where("p < q")
    live = active_hyperlinks(shared.groupBy("p", "q").agg(F.count("*").alias("n")).where(F.col("n") >= k).select("p", "q"), local)
    region = shared.join(live, ["p", "q"], "left_semi")
    rows = local.select(_node().alias("node"), "piece", C.name().alias("c"), F.explode("members").alias("vid"))
    cut = lambda end: rows.withColumnRenamed("piece", end).join(region, [end, "vid"]).groupBy("p", "q", "node", "c").agg(F.array_sort(F.collect_set("vid")).alias("members")).where(F.size("members") >= k).drop("c").distinct()
    return _common(cut("p"), cut("q"), k, ["p", "q"], "true").select("i", "j")


def _lifted(local: DataFrame, labels: DataFrame, *by: str) -> DataFrame:
    """The cover (k, community_key, members) of local communities with the labels of those that were joined."""
    rows = local.withColumn("node", _node(*by)).join(labels, "node", "left").select(F.coalesce("label", "node").alias("label"), "k", "members")
    own = rows.groupBy("label").agg(F.min(F.slice("members", F.lit(1), F.col("k").cast("int"))).alias("least"))
    return rows.join(own, "label").select("k", C.name("least").alias("community_key"), "members").distinct()


def merge_local(local: DataFrame, piece_vertices: DataFrame, k: int, method: str = "overlap") -> DataFrame:
    """The whole cover (k, community_key, members) of local covers that share k-cliques.

    overlap    local communities whose largest common clique has k members or more
    kclique    equi-join on the k-cliques of the border, a star for each
    hyperlink  each link of the hyper-network by itself, labels relaxed along all hyperlinks at once until none moves
    """
    if method == "kclique":

        def subsets(batches):
            for batch in batches:
                nodes, cliques = [], []
                for node, members in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                    for n, c in enumerate(combinations(members, k)):
                        if n > C.MAX_SUBSETS:
                            raise ValueError(f"over {C.MAX_SUBSETS} k-cliques in one border clique of {len(members)}; use method overlap")
                        nodes.append(node)
                        cliques.append("-".join(map(str, c)))
                yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.string()), pa.array(cliques, pa.string())], ["node", "c"])

        at = _border_cliques(local, piece_vertices, k).select("node", "members").mapInArrow(subsets, "node string, c string").distinct()
        least = at.groupBy("c").agg(F.min("node").alias("least"), F.count("*").alias("n")).where("n > 1")
        links = at.join(least, "c").where("node <> least").select(F.col("node").alias("u"), F.col("least").alias("v")).distinct()
    elif method == "hyperlink":
        links = _hyperlink_overlap(local, piece_vertices, k).select(F.col("i").alias("u"), F.col("j").alias("v"))
    elif method == "overlap":
        links = community_overlap(local, piece_vertices, k).select(F.col("i").alias("u"), F.col("j").alias("v"))
    else:
        raise ValueError(f"unknown merge {method}")
    return _lifted(local, components(links, method="minlabel") if method == "hyperlink" else labels_of(links))


def _pieces(edges: DataFrame, rule: str, closure: str, k: int, **kw) -> tuple[DataFrame, DataFrame]:
    if closure == "printed":
        pv, pe = printed_pieces(edges, **kw)
    else:
        owner = written(owners(edges, rule, **kw), "owners")
        pv, pe = pieces_of(edges, owner, closure, k)
    return written(pv, "piece_vertices"), written(pe, "piece_edges")


def percolate_split(edges: DataFrame, k: int, rule: str = "bfs", executor: str = "local", method: str = "overlap", closure: str = "halo", measures: dict | None = None, **kw) -> DataFrame:
    """Split, solve, merge. measures, if given, receives seconds of each stage and the pieces' figures."""
    began = time.time()
    edges = written(edges.select("src", "dst"), "edges")
    pv, pe = _pieces(edges, rule, closure, k, **kw)
    split = time.time()
    # Scheduling is what dealing the links to their pieces takes; the rest of the stage is work on them.
    dealt = written(pe.repartition("piece"), "dealt") if measures is not None else pe
    scheduled = time.time()
    local = written(percolate_pieces(dealt, k, executor), "local")
    solved = time.time()
    cover = merge_local(local, pv, k, method)
    if measures is not None:
        cover = written(cover, "cover")
        measures |= {"split_s": split - began, "schedule_s": scheduled - split, "local_s": solved - scheduled, "merge_s": time.time() - solved, "total_s": time.time() - began}
        measures |= {"schedule_merge_s": measures["schedule_s"] + measures["merge_s"]} | figures(pv, pe, local)
    return cover


def percolate_split_all(edges: DataFrame, k_min: int = 3, k_max: int | None = None, rule: str = "bfs", closure: str = "halo", **kw) -> DataFrame:
    """Covers at every k by one split: pieces are solved at all k, one matrix of common cliques serves every threshold."""
    edges = written(edges.select("src", "dst"), "edges")
    pv, pe = _pieces(edges, rule, closure, k_min, **kw)
    local = written(percolate_local(pe, k_min, "piece", k_max), "local")
    links = overlap_matrix(local, pv, k_min).select(F.col("i").alias("u"), F.col("j").alias("v"))
    return _lifted(local, labels_of(links), "k")


def percolate_one_sided(edges: DataFrame, owner: DataFrame, k: int) -> DataFrame:
    """The cover at k with one-sided borders: each k-clique is only in the piece that owns its vertex of least (degree, id).

    Two adjacent cliques need no common piece; local communities are joined where they share a face of k-1 vertices.
    """
    found = C.k_cliques(edges, k, rooted=True)
    at = written(found.join(owner.toDF("root", "piece"), "root").select("piece", F.concat_ws("|", "piece", C.name()).alias("clique"), "members"), "cliques")
    inside = C.adjacency_links(at, k, ("piece",))
    labels = labels_of(inside)
    local = written(at.join(labels.withColumnRenamed("node", "clique"), "clique", "left").select("clique", F.coalesce("label", "clique").alias("local"), "members"), "local")
    # Faces of local communities, each once, joined by a star a face.
    faces = C.faces(local.select(F.col("local").alias("clique"), "members"), k).distinct()
    least = faces.groupBy("face").agg(F.min("clique").alias("least"), F.count("*").alias("n")).where("n > 1")
    links = faces.join(least, "face").where("clique <> least").select(F.col("clique").alias("u"), F.col("least").alias("v")).distinct()
    whole = local.join(labels_of(links).withColumnRenamed("node", "local"), "local", "left").select(F.coalesce("label", "local").alias("label"), "members")
    own = whole.groupBy("label").agg(F.min("members").alias("least"))
    return whole.join(own, "label").select(F.lit(k).cast("long").alias("k"), C.name("least").alias("community_key"), "members")


# ---- figures of pieces -----------------------------------------------------------------------------------------------


def piece_stats(piece_vertices: DataFrame, size_limit: int = 0) -> DataFrame:
    """(pieces, smallest, median, largest, owned_least, owned_most, overshoot): overshoot is what the most owned exceed the limit by."""
    sizes = piece_vertices.groupBy("piece").agg(F.count("*").alias("n"), F.count_if("owned").alias("own"))
    return sizes.agg(
        F.count("*").alias("pieces"), F.min("n").alias("smallest"), F.percentile("n", 0.5).alias("median"), F.max("n").alias("largest"), F.min("own").alias("owned_least"), F.max("own").alias("owned_most"),
        F.greatest(F.lit(0).cast("long"), F.max("own") - size_limit).alias("overshoot"),
    )


def figures(piece_vertices: DataFrame, piece_edges: DataFrame, local: DataFrame) -> dict:
    """Pieces, their sizes, and how much vertices, links and cliques are copied."""
    s = piece_stats(piece_vertices).first()
    r = replication(piece_vertices, piece_edges).first()
    c = duplicated_cliques(local).first()
    return {
        "pieces": s["pieces"], "smallest": s["smallest"], "median": s["median"], "largest": s["largest"], "replication": r["vertex_copies"] / max(1, r["vertices"]), "link_replication": r["link_copies"] / max(1, r["links"]),
        "clique_replication": c["copies"] / max(1, c["cliques"]),
    }


def duplicated_cliques(local: DataFrame) -> DataFrame:
    """(cliques, copies, in_border): local cliques, how often they are found in all, and those found in two pieces or more."""
    each = local.groupBy(C.name().alias("c")).agg(F.count_distinct("piece").alias("n"))
    return each.agg(F.count("*").alias("cliques"), F.coalesce(F.sum("n"), F.lit(0)).alias("copies"), F.count_if(F.col("n") > 1).alias("in_border"))


def replication(piece_vertices: DataFrame, piece_edges: DataFrame) -> DataFrame:
    """(vertex_copies, vertices, link_copies, links)."""
    v = piece_vertices.agg(F.count("*").alias("vertex_copies"), F.count_distinct("vid").alias("vertices"))
    e = piece_edges.agg(F.count("*").alias("link_copies"), F.count_distinct("src", "dst").alias("links"))
    return v.crossJoin(e)


def border_stats(edges: DataFrame, owner: DataFrame) -> DataFrame:
    """(vertices, border_vertices, links, cut_links): how much of a graph lies on the borders of its owners."""
    cut = boundary(edges, owner)
    ends = cut.select(F.col("src").alias("vid")).unionByName(cut.select(F.col("dst").alias("vid")))
    rows = [vertices(edges).agg(F.count("*").alias("vertices")), ends.agg(F.count_distinct("vid").alias("border_vertices")), edges.agg(F.count("*").alias("links")), cut.agg(F.count("*").alias("cut_links"))]
    return rows[0].crossJoin(rows[1]).crossJoin(rows[2]).crossJoin(rows[3])  # one row each


def piece_bytes(piece_edges: DataFrame, link_bytes: int = 200) -> DataFrame:
    """(piece, links, bytes): a proxy of what each piece's adjacency takes in a task."""
    return piece_edges.groupBy("piece").agg(F.count("*").alias("links")).withColumn("bytes", F.col("links") * link_bytes)


def split_trace(edges: DataFrame, size_limit: int = 100, n_seeds: int | None = 4, distributed: bool | None = None, growth: DataFrame | None = None) -> DataFrame:
    """(round, level, frontier, new) of breadth-first growth; rounds after the first are restarts."""
    if growth is not None:
        return growth.where("vid IS NULL").select("round", "level", "frontier", "new")
    links = edges.select("src", "dst")
    n_seeds = _seeds_of(edges, size_limit, n_seeds)
    names = ("round", "level", "frontier", "new")
    if distributed or (distributed is None and links.limit(LOCAL_LINKS + 1).count() > LOCAL_LINKS):
        rows = _grown_by_levels(edges, size_limit, n_seeds)[1]  # a row a level
        return edges.sparkSession.createDataFrame([tuple(t[n] for n in names) for t in rows], "round long, level long, frontier long, new long")

    def run(batches):
        trace = grown(*_ends(batches), size_limit, n_seeds)[4]
        yield pa.RecordBatch.from_arrays([pa.array([t[n] for t in trace], pa.int64()) for n in names], list(names))

    return links.coalesce(1).mapInArrow(run, "round long, level long, frontier long, new long")


def tiny_pieces(edges: DataFrame, size_limit: int, n_seeds: int | None = 4, growth: DataFrame | None = None) -> DataFrame:
    """(pieces, tiny, after): pieces that growth leaves, those below the size limit, and pieces once tiny ones are merged."""
    growth = bfs_growth(edges, size_limit, n_seeds) if growth is None else growth
    before = growth.where("vid IS NOT NULL").groupBy("first").count()
    after = bfs_owners(edges, size_limit, n_seeds, growth=growth).agg(F.count_distinct("piece").alias("after"))
    return before.agg(F.count("*").alias("pieces"), F.count_if(F.col("count") < size_limit).alias("tiny")).crossJoin(after)  # one row each


def clique_coverage(edges: DataFrame, piece_edges: DataFrame, k: int) -> DataFrame:
    """(cliques, lost): k-cliques of the graph, and those that no piece has whole."""
    whole = C.k_cliques(edges, k).select("members")
    held = C.k_cliques(piece_edges, k, ("piece",)).select("members").distinct()
    return whole.agg(F.count("*").alias("cliques")).crossJoin(whole.join(held, "members", "left_anti").agg(F.count("*").alias("lost")))  # one row each


def coverage(edges: DataFrame, piece_edges: DataFrame) -> DataFrame:
    """(links, lost): links in no piece."""
    lost = edges.select("src", "dst").join(piece_edges.select("src", "dst").distinct(), ["src", "dst"], "left_anti")
    return edges.agg(F.count("*").alias("links")).crossJoin(lost.agg(F.count("*").alias("lost")))


def cover_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Membership rows that only one of two covers has: (side, k, community_key, vid)."""
    rows = lambda x, of: x.select("k", "community_key", F.explode("members").alias("vid"), F.lit(of).alias("in_a"))
    each = rows(a, True).unionByName(rows(b, False)).groupBy("k", "community_key", "vid").agg(F.min("in_a").alias("least"), F.max("in_a").alias("most"))
    return each.where(F.col("least") == F.col("most")).select(F.when(F.col("most"), "a").otherwise("b").alias("side"), "k", "community_key", "vid")


def waves(piece_vertices: DataFrame, cores: int) -> DataFrame:
    """(pieces, waves): how often all cores are filled."""
    return piece_vertices.agg(F.count_distinct("piece").alias("pieces")).select("pieces", F.ceil(F.col("pieces") / cores).alias("waves"))


def cut_order(piece_vertices: DataFrame) -> DataFrame:
    """(piece, n, place): pieces by size, the largest first, which is the order to schedule them in."""
    return piece_vertices.groupBy("piece").agg(F.count("*").alias("n")).withColumn("place", F.row_number().over(Window.orderBy(F.desc("n"), "piece")))
