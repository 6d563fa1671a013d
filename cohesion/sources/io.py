"""Edge-list sources, cover sinks and exports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import normalise
from ..operators.cliques import name
from ..operators.percolation import membership


def read_edge_list(spark: SparkSession, path: str, fmt: str = "text", directed: bool = False, weighted: bool = False) -> DataFrame:
    """Links of a two- or three-column file: text (white space or commas, # comments), csv, json, orc or parquet.

    Rows without two numbers are left out.
    """
    if fmt == "text":
        parts = F.split(F.trim("value"), r"[\s,;]+")
        rows = spark.read.text(path).where(~F.trim("value").startswith("#"))
        at = lambda i, kind: F.expr(f"try_cast(try_element_at(parts, {i}) AS {kind})")
        rows = rows.select(parts.alias("parts")).select(at(1, "bigint").alias("src"), at(2, "bigint").alias("dst"), at(3, "double").alias("weight"))
    elif fmt == "csv":
        rows = spark.read.schema("src long, dst long, weight double").option("mode", "DROPMALFORMED").option("comment", "#").csv(path)
    else:
        rows = getattr(spark.read, fmt)(path)
    return normalise(rows, weight="weight" if weighted else None, directed=directed)


def write_graph(edges: DataFrame, table: str, buckets: int = 64) -> None:
    """Links as a bucketed, sorted table: joins on src need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)


def write_cover(cover: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Membership rows, a folder for each k."""
    rows = membership(cover)
    rows.write.mode("overwrite").partitionBy("k").format(fmt).save(path)


def write_member_lists(cover: DataFrame, path: str) -> None:
    """One community a line: its key, a colon, its vertices in order."""
    held = membership(cover).groupBy("k", "community_key").agg(F.array_sort(F.collect_list("vid")).alias("members"))
    held.select(F.concat("community_key", F.lit(": "), F.array_join(F.transform("members", lambda x: x.cast("string")), " ")).alias("value")).write.mode("overwrite").text(path)


def export_graph(nodes: DataFrame, links: DataFrame, fmt: str = "dot") -> DataFrame:
    """(part, value): lines of a drawing of nodes (id, size) and links (a, b, shared), as dot, graphml or json.

    part orders the lines: head, nodes, links, tail.
    """
    spark = nodes.sparkSession
    text = {
        "dot": ("graph communities {", '  "%s" [size=%s];', '  "%s" -- "%s" [weight=%s];', "}"),
        "graphml": ('<graphml><graph edgedefault="undirected">', '<node id="%s"><data key="size">%s</data></node>', '<edge source="%s" target="%s"><data key="weight">%s</data></edge>', "</graph></graphml>"),
        "json": ('{"lines":[', '{"node":"%s","size":%s},', '{"a":"%s","b":"%s","weight":%s},', "{}]}"),
    }[fmt]
    ends = spark.createDataFrame([(0, text[0]), (3, text[3])], "part int, value string")
    n = nodes.select(F.lit(1).alias("part"), F.format_string(text[1].replace("%s", "%s"), F.col("id").cast("string"), F.col("size").cast("string")).alias("value"))
    e = links.select(F.lit(2).alias("part"), F.format_string(text[2], F.col("a").cast("string"), F.col("b").cast("string"), F.col("shared").cast("string")).alias("value"))
    return ends.unionByName(n).unionByName(e)


def clique_lines(cliques: DataFrame) -> DataFrame:
    """(value): cliques as text lines."""
    return cliques.select(name().alias("value"))
