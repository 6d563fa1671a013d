"""Measures of covers and graphs, and the contrast methods: label propagation, modularity, rewiring."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import both_ways, degrees
from ..session import written
from .cliques import k_cliques
from .percolation import communities, membership


def graph_size(edges: DataFrame) -> DataFrame:
    """(n, m)."""
    return edges.agg(F.count("*").alias("m")).crossJoin(both_ways(edges).agg(F.count_distinct("vid").alias("n"))).select("n", "m")


def degree_distribution(edges: DataFrame) -> DataFrame:
    """(degree, n_vertices, at_least): how many vertices have a degree, and at least that."""
    per = degrees(edges).groupBy("degree").agg(F.count("*").alias("n_vertices"))
    # As many rows as there are degrees meet here, not vertices.
    above = per.select(F.col("degree").alias("d"), F.col("n_vertices").alias("n"))
    return per.join(above, F.col("d") >= F.col("degree")).groupBy("degree", "n_vertices").agg(F.sum("n").alias("at_least"))


def triangles(edges: DataFrame) -> DataFrame:
    """(vid, triangles) of vertices in any."""
    return k_cliques(edges, 3).select(F.explode("members").alias("vid")).groupBy("vid").agg(F.count("*").alias("triangles"))


def clustering(edges: DataFrame) -> DataFrame:
    """(vertices, clustering): mean over vertices of degree two and more of triangles over possible ones."""
    d = degrees(edges).where("degree > 1").join(triangles(edges), "vid", "left")
    each = F.coalesce("triangles", F.lit(0)) * 2.0 / (F.col("degree") * (F.col("degree") - 1))
    return d.agg(F.count("*").alias("vertices"), F.round(F.avg(each), 6).alias("clustering"))


def link_support(edges: DataFrame) -> DataFrame:
    """(src, dst, support): triangles through each link in any; a k-clique's links have k-2 or more."""
    m = F.col("members")
    pairs = F.array(F.struct(m[0].alias("src"), m[1].alias("dst")), F.struct(m[0].alias("src"), m[2].alias("dst")), F.struct(m[1].alias("src"), m[2].alias("dst")))
    return k_cliques(edges, 3).select(F.explode(pairs).alias("l")).groupBy("l.src", "l.dst").agg(F.count("*").alias("support"))


def overlap_vertices(cover: DataFrame) -> DataFrame:
    """(vid, n): vertices in two communities or more."""
    return membership(cover).groupBy("vid").agg(F.count("*").alias("n")).where("n > 1")


def community_graph(cover: DataFrame) -> DataFrame:
    """(a, b, shared): communities with common vertices."""
    m = membership(cover).select("vid", F.col("community_key").alias("a"))
    return m.join(m.withColumnRenamed("a", "b"), "vid").where("a < b").groupBy("a", "b").agg(F.count("*").alias("shared"))


def density(edges: DataFrame, cover: DataFrame) -> DataFrame:
    """(community_key, size, links, density): links among a community's vertices over possible ones."""
    m = membership(cover)
    a = m.select("community_key", F.col("vid").alias("src"))
    inside = edges.select("src", "dst").join(a, "src").join(m.select("community_key", F.col("vid").alias("dst")), ["community_key", "dst"]).groupBy("community_key").agg(F.count("*").alias("links"))
    return communities(cover).join(inside, "community_key").select("community_key", "size", "links", F.round(2.0 * F.col("links") / (F.col("size") * (F.col("size") - 1)), 6).alias("density"))


def cover_stats(cover: DataFrame) -> DataFrame:
    """(size, n_communities): the size distribution."""
    return communities(cover).groupBy("size").agg(F.count("*").alias("n_communities"))


def nesting(covers: DataFrame) -> DataFrame:
    """(k, child, parent): the community at k that holds each community at k+1, found by its key's own clique."""
    child = covers.select("k", "community_key", "members").withColumnsRenamed({"community_key": "child", "members": "mc"})
    child = child.select((F.col("k") - 1).alias("k"), "child", "mc")
    a = child.select("k", "child", F.explode("mc").alias("vid"), "mc")
    b = covers.select("k", F.col("community_key").alias("parent"), F.col("members"), F.explode("members").alias("vid"))
    return a.join(b, ["k", "vid"]).where(F.size(F.array_intersect("mc", "members")) > F.col("k")).select("k", "child", "parent").distinct()


def cover_vs_labels(cover: DataFrame, labels: DataFrame) -> DataFrame:
    """(communities, purity, nmi) against labels (vid, label), over the memberships of labelled vertices.

    purity: share of members with their community's most common label; nmi: mutual information of community and label
    over the mean of their entropies, 0 where either is constant.
    """
    m = membership(cover).join(labels, "vid").groupBy("community_key", "label").agg(F.count("*").alias("n"))
    top = m.groupBy("community_key").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    purity = top.agg(F.count("*").alias("communities"), F.round(F.sum("top") / F.sum("n"), 6).alias("purity"))
    total = m.agg(F.sum("n").cast("double").alias("t"))
    rows = lambda x: x.crossJoin(total).agg(F.sum(F.col("n") / F.col("t") * F.ln(F.col("n") / F.col("t"))).alias("s"))  # noqa: E731  one row of t
    both, a, b = (rows(m.groupBy(*by).agg(F.sum("n").alias("n"))).toDF(name) for by, name in ((("community_key", "label"), "hj"), (("community_key",), "ha"), (("label",), "hb")))
    mean = -(F.col("ha") + F.col("hb")) / 2
    nmi = F.when(mean > 1e-12, F.round((F.col("hj") - F.col("ha") - F.col("hb")) / mean, 6)).otherwise(0.0)
    return purity.crossJoin(both).crossJoin(a).crossJoin(b).select("communities", "purity", nmi.alias("nmi"))  # one row each


def modularity(edges: DataFrame, partition: DataFrame) -> DataFrame:
    """(modularity) of a disjoint partition (vid, label)."""
    m = edges.agg(F.count("*").cast("double").alias("m"))
    inside = edges.join(partition.toDF("src", "ls"), "src").join(partition.toDF("dst", "ld"), "dst").where("ls = ld").groupBy(F.col("ls").alias("label")).agg(F.count("*").alias("inside"))
    ends = degrees(edges).join(partition, "vid").groupBy("label").agg(F.sum("degree").alias("ends"))
    rows = ends.join(inside, "label", "left").crossJoin(m)
    return rows.agg(F.round(F.sum(F.coalesce("inside", F.lit(0)) / F.col("m") - F.pow(F.col("ends") / (2 * F.col("m")), 2)), 6).alias("modularity"))


def label_propagation(edges: DataFrame, rounds: int = 5) -> DataFrame:
    """(vid, label): each vertex takes its neighbours' most common label, the least of ties, for some rounds."""
    near = written(both_ways(edges), "near")
    now = near.select("vid").distinct().withColumn("label", F.col("vid"))
    for _ in range(rounds):
        votes = near.join(now.withColumnRenamed("vid", "other"), "other").groupBy("vid", "label").agg(F.count("*").alias("n"))
        now = written(votes.groupBy("vid").agg(F.min(F.struct(-F.col("n"), "label")).alias("best")).select("vid", F.col("best.label").alias("label")), "labels")
    return now


def gnm(edges: DataFrame, seed: int = 1, buckets: int = 1024) -> DataFrame:
    """A random graph of as many vertices and nearly as many links: each link's ends are drawn by hash among the vertices.

    Vertices are numbered by bucket and place in it, so no window spans them all.
    """
    from pyspark.sql import Window

    ids = written(both_ways(edges).select("vid").distinct().withColumn("b", F.pmod(F.xxhash64("vid", F.lit(seed)), F.lit(buckets))), "ids")
    sizes = sorted((r["b"], r["count"]) for r in ids.groupBy("b").count().collect())  # a row a bucket
    n, starts = 0, []
    for b, size in sizes:
        starts.append((b, n))
        n += size
    offsets = edges.sparkSession.createDataFrame(starts, "b long, first long")
    place = ids.withColumn("r", F.row_number().over(Window.partitionBy("b").orderBy("vid")) - 1).join(F.broadcast(offsets), "b").select("vid", (F.col("r") + F.col("first")).alias("r"))
    take = lambda salt: F.pmod(F.xxhash64("src", "dst", F.lit(seed), F.lit(salt)), F.lit(max(1, n)))
    rows = edges.select(take(1).alias("ra"), take(2).alias("rb")).where("ra <> rb").select(F.least("ra", "rb").alias("ra"), F.greatest("ra", "rb").alias("rb")).distinct()
    a = rows.join(place.toDF("va", "ra"), "ra").join(place.toDF("vb", "rb"), "rb")
    return a.select(F.least("va", "vb").alias("src"), F.greatest("va", "vb").alias("dst"), F.lit(1).cast("long").alias("weight"))


def rewire(edges: DataFrame, seed: int = 1, rounds: int = 3) -> DataFrame:
    """Degree-preserving rewiring: links are paired by hash and swap ends unless that makes a loop or a known link."""
    from pyspark.sql import Window

    now = edges.select("src", "dst")
    for r in range(rounds):
        now = written(now, "rewired")
        # Pairs form inside hash buckets, so no window spans the whole graph.
        mixed = now.withColumn("h", F.xxhash64("src", "dst", F.lit(seed), F.lit(r))).withColumn("b", F.pmod("h", F.lit(64)))
        nth = mixed.withColumn("i", F.row_number().over(Window.partitionBy("b").orderBy("h", "src", "dst")) - 1).withColumn("pair", F.floor(F.col("i") / 2))
        a, b = nth.where("i % 2 = 0"), nth.where("i % 2 = 1").select("b", "pair", F.col("src").alias("s2"), F.col("dst").alias("d2"))
        both = a.join(b, ["b", "pair"], "left").select("src", "dst", "s2", "d2")
        want = both.where("s2 is not null").select("*", F.least("src", "d2").alias("x1"), F.greatest("src", "d2").alias("y1"), F.least("s2", "dst").alias("x2"), F.greatest("s2", "dst").alias("y2")).where("x1 <> y1 and x2 <> y2 and not (x1 = x2 and y1 = y2)")
        known = now.select(F.col("src").alias("x"), F.col("dst").alias("y"))
        want = want.join(known.toDF("x1", "y1"), ["x1", "y1"], "left_anti").join(known.toDF("x2", "y2"), ["x2", "y2"], "left_anti")
        made = want.select("src", "dst", "s2", "d2", F.explode(F.array(F.struct(F.col("x1").alias("a"), F.col("y1").alias("b")), F.struct(F.col("x2").alias("a"), F.col("y2").alias("b")))).alias("l"))
        # Two swaps must not make one link: such swaps are left out.
        often = made.groupBy("l").agg(F.count("*").alias("n")).where("n > 1").select("l")
        bad = made.join(often, "l", "left_semi").select("src", "dst", "s2", "d2").distinct()
        good = want.join(bad, ["src", "dst", "s2", "d2"], "left_anti")
        gone = good.select("src", "dst").unionByName(good.select(F.col("s2").alias("src"), F.col("d2").alias("dst")))
        new = good.select(F.col("x1").alias("src"), F.col("y1").alias("dst")).unionByName(good.select(F.col("x2").alias("src"), F.col("y2").alias("dst")))
        now = now.join(gone, ["src", "dst"], "left_anti").unionByName(new)
    return written(now, "rewired").withColumn("weight", F.lit(1).cast("long"))


def cover_similarity(a: DataFrame, b: DataFrame) -> DataFrame:
    """(best_jaccard): mean over a's communities of the best Jaccard match in b."""
    x, y = membership(a).select("vid", F.col("community_key").alias("ka")), membership(b).select("vid", F.col("community_key").alias("kb"))
    sx, sy = x.groupBy("ka").agg(F.count("*").alias("na")), y.groupBy("kb").agg(F.count("*").alias("nb"))
    met = x.join(y, "vid").groupBy("ka", "kb").agg(F.count("*").alias("n")).join(sx, "ka").join(sy, "kb")
    best = met.groupBy("ka").agg(F.max(F.col("n") / (F.col("na") + F.col("nb") - F.col("n"))).alias("j"))
    return sx.join(best, "ka", "left").agg(F.round(F.avg(F.coalesce("j", F.lit(0.0))), 6).alias("best_jaccard"))


def pair_f1(a: DataFrame, b: DataFrame, most: int = 1_000_000_000) -> DataFrame:
    """(pairs_a, pairs_b, pairs_both, f1) of vertex pairs that share a community.

    The pairs of a community grow with its square, so covers whose communities make more than `most` are refused.
    """

    def pairs(cover: DataFrame) -> DataFrame:
        m = membership(cover).select("community_key", "vid")
        n = communities(cover).agg(F.sum(F.col("size") * (F.col("size") - 1) / 2).alias("n")).first()["n"] or 0
        if n > most:
            raise ValueError(f"{n:.0f} pairs share a community, over {most}; compare by cover_similarity")
        return m.withColumnRenamed("vid", "u").join(m.withColumnRenamed("vid", "v"), "community_key").where("u < v").select("u", "v").distinct()

    x, y = pairs(a), pairs(b)
    rows = x.withColumn("x", F.lit(1)).join(y.withColumn("y", F.lit(1)), ["u", "v"], "full")
    found = rows.agg(F.count("x").alias("pairs_a"), F.count("y").alias("pairs_b"), F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull()).alias("pairs_both"))
    return found.withColumn("f1", F.round(F.coalesce(F.try_divide(F.lit(2.0) * F.col("pairs_both"), F.col("pairs_a") + F.col("pairs_b")), F.lit(1.0)), 6))


def memberships(cover: DataFrame) -> DataFrame:
    """(communities, vertices): in how many communities vertices are."""
    return membership(cover).groupBy("vid").agg(F.count("*").alias("communities")).groupBy("communities").agg(F.count("*").alias("vertices"))


def community_degree(cover: DataFrame) -> DataFrame:
    """(degree, n_communities): with how many others communities share vertices, of those that do."""
    g = community_graph(cover)
    ends = g.select(F.col("a").alias("c")).unionByName(g.select(F.col("b").alias("c")))
    return ends.groupBy("c").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n_communities"))


def mean_distance(edges: DataFrame, one_in: int = 1) -> DataFrame:
    """(pairs, distance): mean steps from all vertices, or a hash sample of one in some, to all they reach."""
    near = written(both_ways(edges), "near")
    held = written(near.select(F.col("vid").alias("root")).distinct().where(F.pmod(F.xxhash64("root"), F.lit(one_in)) == 0).select("root", F.col("root").alias("vid"), F.lit(0).alias("hop")), "hops")
    hop, step = 0, held
    while True:
        hop += 1
        step = step.join(near, "vid").select("root", F.col("other").alias("vid")).distinct().join(held, ["root", "vid"], "left_anti")
        step = written(step.withColumn("hop", F.lit(hop)), "step")
        if not step.limit(1).count():
            break
        held = held.unionByName(step)
    return held.where("hop > 0").agg(F.count("*").alias("pairs"), F.round(F.avg("hop"), 6).alias("distance"))


def fit_inverse(measures: DataFrame, x: str = "size_limit", y: str = "seconds") -> DataFrame:
    """(a, b, r2) of y = a + b / x."""
    inv = 1.0 / F.col(x).cast("double")
    return measures.agg(F.regr_intercept(y, inv).alias("a"), F.regr_slope(y, inv).alias("b"), F.regr_r2(y, inv).alias("r2"))


def speedup(measures: DataFrame, baseline: str = "serial") -> DataFrame:
    """(method, seconds, speedup) of (method, seconds) rows against the baseline's."""
    base = measures.where(F.col("method") == baseline).agg(F.first("seconds").alias("base"))  # one row
    return measures.crossJoin(base).select("method", "seconds", F.round(F.col("base") / F.col("seconds"), 4).alias("speedup"))


def fit_log(measures: DataFrame, x: str = "size_limit", y: str = "seconds") -> DataFrame:
    """(a, b, r2) of y = a - b ln x."""
    ln = F.ln(F.col(x).cast("double"))
    return measures.agg(F.regr_intercept(y, ln).alias("a"), (-F.regr_slope(y, ln)).alias("b"), F.regr_r2(y, ln).alias("r2"))


def branching_factor(trace: DataFrame) -> DataFrame:
    """(branching): mean over levels of new vertices over frontier."""
    return trace.where("frontier > 0").agg(F.avg(F.col("new") / F.col("frontier")).alias("branching"))
