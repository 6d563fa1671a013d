"""Graph layer: normalised link tables.

edges: src < dst, distinct, without loops, weight; arcs: ordered pairs. Rows with a null end are dropped.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def normalise(df: DataFrame, src: str = "src", dst: str = "dst", weight: str | None = None, directed: bool = False, agg: str = "sum") -> DataFrame:
    """Links (src, dst, weight) of raw pairs; repeated pairs are folded by agg, without a weight they are counted."""
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    pair = (a, b) if directed else (F.least(a, b), F.greatest(a, b))
    w = F.col(weight) if weight else F.lit(1).cast("long")
    rows = df.where(a.isNotNull() & b.isNotNull() & (a != b)).select(pair[0].alias("src"), pair[1].alias("dst"), w.alias("weight"))
    return rows.groupBy("src", "dst").agg(getattr(F, agg)("weight").alias("weight"))


def both_ways(edges: DataFrame, *more: str) -> DataFrame:
    """Every link from either end: (vid, other)."""
    return edges.select(*more, F.col("src").alias("vid"), F.col("dst").alias("other")).unionByName(edges.select(*more, F.col("dst").alias("vid"), F.col("src").alias("other")))


def degrees(edges: DataFrame, *by: str) -> DataFrame:
    return both_ways(edges, *by).groupBy(*by, "vid").agg(F.count("*").alias("degree"))


def oriented(edges: DataFrame, *by: str) -> DataFrame:
    """Links (u, v) from the end of lesser (degree, id): out-degrees stay below sqrt(2m), hubs point nowhere."""
    d = degrees(edges, *by)
    rows = edges.select(*by, "src", "dst")
    rows = rows.join(d.withColumnsRenamed({"vid": "src", "degree": "ds"}), [*by, "src"]).join(d.withColumnsRenamed({"vid": "dst", "degree": "dd"}), [*by, "dst"])
    first = F.struct("ds", "src") < F.struct("dd", "dst")
    return rows.select(*by, F.when(first, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(first, F.col("dst")).otherwise(F.col("src")).alias("v"))


def to_undirected(arcs: DataFrame, mode: str = "any") -> DataFrame:
    """Links of arcs: those of any direction, or only mutual ones."""
    a, b = F.least("src", "dst"), F.greatest("src", "dst")
    found = arcs.where("src <> dst").select(a.alias("a"), b.alias("b"), (F.col("src") < F.col("dst")).alias("up")).distinct().groupBy("a", "b").agg(F.count("*").alias("ways"))
    return (found if mode == "any" else found.where("ways = 2")).select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("ways").alias("weight"))


def support_pruned(edges: DataFrame, k: int) -> DataFrame:
    """Links that lie in k-2 triangles or more, repeatedly: no k-clique is lost. Ends when nothing falls."""
    from .operators.measures import link_support
    from .session import written

    now = written(edges, "support")
    n = now.count()
    while True:
        strong = link_support(now).where(F.col("support") >= k - 2).select("src", "dst")
        now = written(now.join(strong, ["src", "dst"], "left_semi"), "support")
        m = now.count()
        if m == n:
            break
        n = m
    return now


def kcore(edges: DataFrame, k: int) -> DataFrame:
    """Links among vertices of degree k and more, repeatedly: no k+1-clique is lost. Ends when nothing falls."""
    from .session import written

    now = written(edges, "core")
    n = now.count()
    while True:
        keep = degrees(now).where(F.col("degree") >= k).select("vid")
        after = written(now.join(keep.withColumnRenamed("vid", "src"), "src", "left_semi").join(keep.withColumnRenamed("vid", "dst"), "dst", "left_semi"), "core")
        m = after.count()
        now = after
        if m == n:
            break
        n = m
    return now
