"""Relational operators that graph users need around the methods: interval and as-of joins, skew-safe joins, ranks of
communities, grouping sets, set operations on covers and JSON properties. All are DataFrame plans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def interval_coactivity(events: DataFrame, seconds: int = 60, by: str = "event_type", who: str = "user_id", ts: str = "ts") -> DataFrame:
    """(src, dst, weight): users with events of one kind at most some seconds apart; weight counts such pairs of events.

    A range join as an equi-join: time is cut in buckets as wide as the interval, and a row meets its own and the next
    bucket only, so no bucket pairs all rows of a kind.
    """
    width = seconds * 1_000_000
    at = F.unix_micros(F.col(ts).cast("timestamp"))
    rows = events.select(F.col(by).alias("kind"), F.col(who).alias("who"), at.alias("at")).where("kind is not null and who is not null and at is not null")
    rows = rows.withColumn("bucket", F.floor(F.col("at") / width))
    later = rows.select("kind", F.col("who").alias("other"), F.col("at").alias("then"), F.explode(F.array(F.col("bucket"), F.col("bucket") - 1)).alias("bucket"))
    # Equal times meet from both sides, so only the lesser user's row counts them.
    near = (F.col("then") - F.col("at")).between(0, width) & (F.col("who") != F.col("other")) & ((F.col("then") > F.col("at")) | (F.col("who") < F.col("other")))
    met = rows.join(later, ["kind", "bucket"]).where(near)
    return met.groupBy(F.least("who", "other").alias("src"), F.greatest("who", "other").alias("dst")).agg(F.count("*").alias("weight"))


def as_of(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, alias: str = "as_of") -> DataFrame:
    """left with right's latest value at or before each row's time, within `by`: one sort of both, no range join."""
    a = left.select(F.struct(*left.columns).alias("row"), F.col(by).alias("_by"), F.col(ts).alias("_ts"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.where(F.col(value).isNotNull()).select(F.lit(None).cast(a.schema["row"].dataType).alias("row"), F.col(by).alias("_by"), F.col(ts).alias("_ts"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    w = Window.partitionBy("_by").orderBy("_ts", "_side", "_v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn("_v", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").select("row.*", F.col("_v").alias(alias))


def salted_join(left: DataFrame, right: DataFrame, on: str, hot: int = 100_000, salts: int = 16) -> DataFrame:
    """Inner join that spreads hot keys: left rows of keys with over `hot` rows are dealt to salts, right's are copied
    to each. The set of hot keys is small: fewer than the rows of left over `hot`. Null keys match nothing."""
    busy = left.where(F.col(on).isNotNull()).groupBy(on).count().where(F.col("count") > hot).select(F.col(on), F.lit(True).alias("_hot"))
    a = left.join(busy, on, "left").withColumn("_salt", F.when(F.col("_hot"), F.pmod(F.xxhash64(*left.columns), F.lit(salts))).otherwise(F.lit(0))).drop("_hot")
    many = F.when(F.col("_hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))).cast("array<long>")
    b = right.join(busy, on, "left").withColumn("_salt", F.explode(many)).drop("_hot")
    return a.withColumn("_salt", F.col("_salt").cast("long")).join(b, [on, "_salt"]).drop("_salt")


def ranked(sizes: DataFrame, per: str = "k") -> DataFrame:
    """(k, community_key, size, place, rank, dense, tile, percent, cumulative, running, lead_size, lag_size, moving) of (k,
    community_key, size) rows within each k, the largest first."""
    order = [F.desc("size"), F.col("community_key")]
    w = Window.partitionBy(per).orderBy(*order)
    ties = Window.partitionBy(per).orderBy(F.desc("size"))
    return sizes.select(
        per, "community_key", "size", F.row_number().over(w).cast("long").alias("place"), F.rank().over(ties).cast("long").alias("rank"), F.dense_rank().over(ties).cast("long").alias("dense"), F.ntile(4).over(w).cast("long").alias("tile"),
        F.round(F.percent_rank().over(ties), 6).alias("percent"), F.round(F.cume_dist().over(ties), 6).alias("cumulative"),
        F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.lead("size").over(w).alias("lead_size"), F.lag("size").over(w).alias("lag_size"),
        F.round(F.avg("size").over(w.rowsBetween(-2, 2)), 6).alias("moving"),
    )


def top_per_k(sizes: DataFrame, n: int = 3, per: str = "k") -> DataFrame:
    """The n largest communities of each k."""
    place = F.row_number().over(Window.partitionBy(per).orderBy(F.desc("size"), "community_key"))
    return sizes.withColumn("place", place).where(F.col("place") <= n).drop("place")


def cube_of(sizes: DataFrame, small: int = 4) -> DataFrame:
    """(k, large, level, n, vertices): communities and their vertices over every grouping of k and size class."""
    rows = sizes.select("k", (F.col("size") > small).cast("int").alias("large"), "size")
    return rows.cube("k", "large").agg(F.grouping_id().alias("level"), F.count("*").alias("n"), F.sum("size").alias("vertices")).select(F.coalesce("k", F.lit(-1)).alias("k"), F.coalesce("large", F.lit(-1)).alias("large"), F.col("level").cast("long").alias("level"), "n", "vertices")


def pivot_sizes(sizes: DataFrame, ks: list[int]) -> DataFrame:
    """(size, k<k>...): how many communities of each size there are at each k."""
    rows = sizes.groupBy("size").pivot("k", ks).agg(F.count(F.lit(1)))
    return rows.select("size", *[F.coalesce(F.col(str(k)), F.lit(0)).cast("long").alias(f"k{k}") for k in ks])


def set_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_a, only_b, both, either): rows of two tables with the same columns, as sets."""
    one = lambda df, name: df.agg(F.count("*").alias(name))
    counts = [one(a.subtract(b), "only_a"), one(b.subtract(a), "only_b"), one(a.intersect(b), "both"), one(a.unionByName(b).distinct(), "either")]
    out = counts[0]
    for c in counts[1:]:
        out = out.crossJoin(c)  # one row each
    return out


def property_of(key: str, kind: str = "long", column: str = "props") -> Column:
    """A property of a JSON column; null where the text is no JSON or lacks it."""
    return F.from_json(F.col(column), f"`{key}` {kind}")[key]


def hash_sample(df: DataFrame, key: str, one_in: int, seed: int = 0) -> DataFrame:
    """The rows of one in so many keys, the same on every run and for every layout."""
    return df.where(F.pmod(F.xxhash64(F.col(key), F.lit(seed)), F.lit(one_in)) == 0)


def is_clique(members: Column, adjacency: Column) -> Column:
    """Whether every two members are linked, by a map from a vertex to its neighbours' array."""
    empty = F.array().cast("array<long>")
    return F.forall(members, lambda a: F.size(F.array_except(F.array_except(members, F.array(a)), F.coalesce(F.try_element_at(adjacency, a), empty))) == 0)
