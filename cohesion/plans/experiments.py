"""Experiment runners; each returns one row of figures a setting."""

from __future__ import annotations

import time

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import measures as M
from ..operators import percolation as P
from ..operators import split as S
from ..session import written


_SWEPT = (
    "size_limit int, split_s double, schedule_s double, local_s double, merge_s double, schedule_merge_s double, total_s double, pieces long, waves long, smallest long, median double, largest long, overshoot long, replication double, "
    "link_replication double, clique_replication double, border_vertices double, cut_links double, restarts long, tiny long, branching double, speedup double, differing long"
)


def sweep_size_limit(edges: DataFrame, k: int, limits: list[int], n_seeds: int | None = None, cores: int = 8) -> DataFrame:
    """A row of seconds and figures for each size limit of breadth-first pieces.

    Seconds of each stage; pieces, waves over the cores, sizes and what the most owned exceed the limit by; copies of
    vertices, links and cliques over their number; shares of vertices and links on borders; restarts, tiny pieces before
    the clean-up, branching of the growth; the serial method's seconds over the total; membership rows that differ.
    """
    edges = written(edges.select("src", "dst"), "edges")
    whole = written(P.percolate(edges, k), "cover")
    began = time.time()
    written(P.percolate_local(edges, k), "serial")
    serial = time.time() - began
    rows = []
    for limit in limits:
        m: dict = {}
        began = time.time()
        growth = S.bfs_growth(edges, limit, n_seeds)
        grown = time.time() - began
        cover = S.percolate_split(edges, k, "bfs", measures=m, size_limit=limit, n_seeds=n_seeds, growth=growth)
        m |= {"split_s": m["split_s"] + grown, "total_s": m["total_s"] + grown}
        owner = S.bfs_owners(edges, limit, n_seeds, growth=growth)
        border = S.border_stats(edges, owner).first()
        trace = S.split_trace(edges, limit, n_seeds, growth=growth)
        tiny = S.tiny_pieces(edges, limit, n_seeds, growth=growth).first()
        over = owner.groupBy("piece").count().agg(F.max("count").alias("n")).first()["n"] or 0
        rows.append((
            limit, *(m[x] for x in ("split_s", "schedule_s", "local_s", "merge_s", "schedule_merge_s", "total_s")), m["pieces"], -(-m["pieces"] // cores), m["smallest"], float(m["median"] or 0), m["largest"], max(0, over - limit),
            float(m["replication"]), float(m["link_replication"]), float(m["clique_replication"]), border["border_vertices"] / max(1, border["vertices"]), border["cut_links"] / max(1, border["links"]),
            trace.agg(F.coalesce(F.max("round"), F.lit(0)).alias("r")).first()["r"], tiny["tiny"], float(M.branching_factor(trace).first()["branching"] or 0), serial / m["total_s"], S.cover_diff(whole, cover).count(),
        ))
    return edges.sparkSession.createDataFrame(rows, _SWEPT)


def sweep_fits(swept: DataFrame) -> DataFrame:
    """(model, a, b, r2): splitting seconds as a - b ln(limit), total seconds as a + b / limit, of a sweep."""
    log = M.fit_log(swept, "size_limit", "split_s").select(F.lit("split_s = a - b ln(limit)").alias("model"), "a", "b", "r2")
    inverse = M.fit_inverse(swept, "size_limit", "total_s").select(F.lit("total_s = a + b / limit").alias("model"), "a", "b", "r2")
    return log.unionByName(inverse)


def _pieces_solver(k: int):
    """A grouped map that solves all pieces of its group, one after the other, and counts their communities."""
    from ..operators.percolation import serial_covers

    def solve(table: pa.Table) -> pa.Table:
        held: dict[int, list[tuple[int, int]]] = {}
        for p, a, b in zip(*(table.column(c).to_pylist() for c in ("piece", "src", "dst"))):
            held.setdefault(p, []).append((a, b))
        return pa.table({"found": pa.array([len({key for _, key, _ in serial_covers(links, k, k)}) for links in held.values()], pa.int64())})

    return solve


def core_sweep(edges: DataFrame, k: int, cores: tuple[int, ...] = (1, 2, 4, 8), size_limit: int = 25) -> DataFrame:
    """(cores, pieces, waves, seconds, communities): pieces solved by ever more units, to see where more stop helping.

    The largest pieces go first, dealt in turn; a unit is one group, which solves its pieces one after the other.
    """
    edges = written(edges.select("src", "dst"), "edges")
    owner = written(S.owners(edges, "bfs", size_limit=size_limit, n_seeds=None), "owners")
    pv, pe = S.pieces_of(edges, owner)
    pv, pe = written(pv, "piece_vertices"), written(pe, "piece_edges")
    order = written(S.cut_order(pv), "order")
    n = order.count()

    rows = []
    for c in cores:
        dealt = written(pe.join(F.broadcast(order.select("piece", F.pmod(F.col("place") - 1, F.lit(c)).alias("unit"))), "piece"), "dealt")  # a row a piece
        began = time.time()
        found = dealt.groupBy("unit").applyInArrow(_pieces_solver(k), "found long").agg(F.sum("found").alias("n")).first()["n"]
        rows.append((c, n, -(-n // c), time.time() - began, found))
    return edges.sparkSession.createDataFrame(rows, "cores int, pieces long, waves long, seconds double, communities long")


def serial_vs_split(edges: DataFrame, k: int, size_limit: int = 100) -> DataFrame:
    """(method, seconds, speedup, communities) of the serial baseline, the flat plan and split-and-merge."""
    edges = written(edges.select("src", "dst"), "edges")
    rows = []
    for name, f in (("serial", lambda: P.percolate_local(edges, k)), ("flat", lambda: P.percolate(edges, k)), ("split", lambda: S.percolate_split(edges, k, "bfs", size_limit=size_limit))):
        began = time.time()
        n = P.communities(f()).count()
        rows.append((name, time.time() - began, n))
    found = edges.sparkSession.createDataFrame(rows, "method string, seconds double, communities long")
    return M.speedup(found).join(found.select("method", "communities"), "method")


def border_experiment(edges: DataFrame, k: int, owners: tuple[int, ...] = (2, 4, 8)) -> DataFrame:
    """(owners, replication, differing) of hash owners with borders."""
    whole = written(P.percolate(edges, k), "cover")
    rows = []
    for n in owners:
        m: dict = {}
        cover = S.percolate_split(edges, k, "hash", measures=m, parts=n)
        rows.append((n, float(m["replication"]), S.cover_diff(whole, cover).count()))
    return edges.sparkSession.createDataFrame(rows, "owners int, replication double, differing long")


def closure_ablation(edges: DataFrame, k: int, size_limit: int = 25, n_seeds: int = 4) -> DataFrame:
    """(closure, lost_links, lost_cliques, differing): what no piece holds, and membership rows that differ.

    halo, triangle and clique take borders in; printed has the copies that growth reached, none the owned vertices alone.
    """
    edges = written(edges.select("src", "dst"), "edges")
    whole = written(P.percolate(edges, k), "cover")
    owner = written(S.owners(edges, "bfs", size_limit=size_limit, n_seeds=n_seeds), "owners")
    rows = []
    for closure in ("halo", "triangle", "clique", "printed", "none"):
        pv, pe = S.printed_pieces(edges, size_limit, n_seeds) if closure == "printed" else S.pieces_of(edges, owner, closure, k)
        pv, pe = written(pv, "piece_vertices"), written(pe, "piece_edges")
        cover = S.merge_local(S.percolate_pieces(pe, k), pv, k)
        rows.append((closure, S.coverage(edges, pe).first()["lost"], S.clique_coverage(edges, pe, k).first()["lost"], S.cover_diff(whole, cover).count()))
    return edges.sparkSession.createDataFrame(rows, "closure string, lost_links long, lost_cliques long, differing long")


def ensemble(edges: DataFrame, k: int, runs: int = 3) -> DataFrame:
    """(seed, best_jaccard, f1): how much of the cover rewired graphs of equal degrees reproduce."""
    whole = written(P.percolate(edges, k), "cover")
    out = None
    for seed in range(runs):
        other = written(P.percolate(M.rewire(edges, seed), k), "cover")
        row = M.cover_similarity(whole, other).crossJoin(M.pair_f1(whole, other)).select(F.lit(seed).alias("seed"), "best_jaccard", "f1")  # one row each
        out = row if out is None else out.unionByName(row)
    return out


def objective_after_link(edges: DataFrame, u: int, v: int, k: int) -> DataFrame:
    """(modularity_before, modularity_after, communities_changed): one link's removal moves a global objective, and only
    the communities that touch it."""
    one = edges.sparkSession.createDataFrame([(min(u, v), max(u, v))], "src long, dst long")
    parts = M.label_propagation(edges)
    before = M.modularity(edges, parts).withColumnRenamed("modularity", "modularity_before")
    after = M.modularity(edges.select("src", "dst").join(one, ["src", "dst"], "left_anti"), parts).withColumnRenamed("modularity", "modularity_after")
    changed = P.link_impact(edges, u, v, "remove", k).agg(F.count("*").alias("communities_changed"))
    return before.crossJoin(after).crossJoin(changed)  # one row each
