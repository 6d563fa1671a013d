"""SQL access: views of a graph and its cover, look-ups by vertex, and functions for SQL users."""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import both_ways
from ..operators.cliques import MAX_SUBSETS
from ..operators.percolation import membership


def register(spark: SparkSession, edges: DataFrame, cover: DataFrame) -> None:
    """Views graph_edges and cover_members, functions geometric_mean and k_subsets."""
    edges.createOrReplaceTempView("graph_edges")
    membership(cover).createOrReplaceTempView("cover_members")

    def geometric_mean(v: pd.Series) -> float:
        return float(np.exp(np.log(v.astype(float)).mean()))

    class Subsets:
        def eval(self, members, k):
            if comb(len(members), k) > MAX_SUBSETS:
                raise ValueError(f"{comb(len(members), k)} subsets; at most {MAX_SUBSETS} are listed")
            for c in combinations(members, k):
                yield (list(c),)

    geometric_mean.__annotations__ = {"v": pd.Series, "return": float}  # as types, which postponed hints are not
    spark.udf.register("geometric_mean", F.pandas_udf(geometric_mean, "double"))
    spark.udtf.register("k_subsets", F.udtf(Subsets, returnType="subset array<long>"))


def communities_of(cover: DataFrame, vid: int) -> DataFrame:
    """(k, community_key) of the communities that hold a vertex."""
    return membership(cover).where(F.col("vid") == vid).select("k", "community_key")


def members(cover: DataFrame, key: str) -> DataFrame:
    return membership(cover).where(F.col("community_key") == key).select("k", "vid")


def subgraph(edges: DataFrame, vids: DataFrame) -> DataFrame:
    """Links among the given vertices (vid)."""
    return edges.join(vids.toDF("src"), "src", "left_semi").join(vids.toDF("dst"), "dst", "left_semi")


def neighbours(edges: DataFrame, vid: int, hops: int = 1) -> DataFrame:
    """(vid, hop) of vertices within some steps."""
    near = both_ways(edges)
    held = edges.sparkSession.createDataFrame([(vid, 0)], "vid long, hop int")
    for h in range(1, hops + 1):
        step = held.where(F.col("hop") == h - 1).join(near, "vid").select(F.col("other").alias("vid")).distinct().join(held, "vid", "left_anti")
        held = held.unionByName(step.withColumn("hop", F.lit(h)))
    return held


def inter_community_links(edges: DataFrame, cover: DataFrame) -> DataFrame:
    """Links whose ends share no community, though both have one."""
    m = membership(cover).select("vid", "community_key")
    inside = edges.select("src", "dst").join(m.withColumnRenamed("vid", "src"), "src").join(m.withColumnRenamed("vid", "dst"), ["dst", "community_key"]).select("src", "dst").distinct()
    v = m.select("vid").distinct()
    return subgraph(edges.select("src", "dst"), v).join(inside, ["src", "dst"], "left_anti")
