"""Graphs from the given tables, each with the DuckDB SQL that builds the same links (src, dst, weight)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import normalise
from ..session import load_table, written

#: Last excluded day of the co-purchase windows that begin with 1997.
WINDOWS = {"month": "1997-02-01", "quarter": "1997-04-01", "year": "1998-01-01"}


def order_parts(spark: SparkSession, sf_dir: str, until: str | None = None) -> DataFrame:
    """(key, v): distinct parts of each order, of orders from 1997 on before `until`, or of all."""
    lines = load_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("key"), F.col("l_partkey").alias("v"))
    if until:
        orders = load_table(spark, sf_dir, "orders").where((F.col("o_orderdate") >= F.lit("1997-01-01").cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit(until).cast("timestamp_ntz")))
        lines = lines.join(orders.select(F.col("o_orderkey").alias("key")), "key", "left_semi")
    return lines.distinct()


def project(rows: DataFrame, least: int = 1) -> DataFrame:
    """Links of a bipartite table (key, v): pairs that share keys, weight the number of them.

    Keys are folded to sorted member arrays first, so a pair needs no self join of the rows.
    """
    held = rows.groupBy("key").agg(F.array_sort(F.collect_set("v")).alias("m")).where(F.size("m") > 1)
    first = held.select("m", F.posexplode("m").alias("i", "src"))
    pairs = first.select("src", F.explode(F.slice("m", F.col("i") + 2, F.size("m"))).alias("dst"))
    return pairs.groupBy("src", "dst").agg(F.count("*").alias("weight")).where(F.col("weight") >= least)


def copurchase(spark: SparkSession, sf_dir: str, window: str) -> DataFrame:
    return project(order_parts(spark, sf_dir, WINDOWS[window]))


def copurchase_repeat(spark: SparkSession, sf_dir: str, least: int = 2) -> DataFrame:
    return project(order_parts(spark, sf_dir), least)


def cosupply(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("key"), F.col("l_suppkey").alias("v")).distinct()
    return project(lines)


def word_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(first, second, n): how often one word follows another, different one in documents."""
    words = F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), 0)
    rows = load_table(spark, sf_dir, "documents").select(words.alias("w")).where(F.size("w") > 1)
    pair = F.arrays_zip(F.slice("w", F.lit(1), F.size("w") - 1).alias("first"), F.slice("w", F.lit(2), F.size("w") - 1).alias("second"))
    each = rows.select(F.explode(pair).alias("p")).select("p.first", "p.second").where("first <> second")
    return each.groupBy("first", "second").agg(F.count("*").alias("n"))


def word_assoc(spark: SparkSession, sf_dir: str, least: int = 8, one_in: int = 80_000) -> DataFrame:
    """Links by word, as text ends (a, b, weight): both orders summed.

    A link is kept from `least` on, and from one in `one_in` of all neighbouring pairs on, so that larger corpora keep
    their strong links and not every chance pair.
    """
    pairs = written(word_pairs(spark, sf_dir).groupBy(F.least("first", "second").alias("a"), F.greatest("first", "second").alias("b")).agg(F.sum("n").alias("weight")), "word_pairs")
    bound = pairs.agg(F.greatest(F.lit(least), F.floor(F.sum("weight") / one_in)).alias("bound"))
    return pairs.crossJoin(bound).where(F.col("weight") >= F.col("bound")).select("a", "b", "weight")  # one row


def word_arcs(spark: SparkSession, sf_dir: str, least: int = 8, one_in: int = 80_000) -> DataFrame:
    """Arcs by word in reading order (a, b, weight), kept as in word_assoc."""
    pairs = written(word_pairs(spark, sf_dir), "word_pairs")
    bound = pairs.agg(F.greatest(F.lit(least), F.floor(F.sum("n") / one_in)).alias("bound"))
    return pairs.crossJoin(bound).where(F.col("n") >= F.col("bound")).select(F.col("first").alias("a"), F.col("second").alias("b"), F.col("n").alias("weight"))  # one row


def customer_copart(spark: SparkSession, sf_dir: str, least: int = 4) -> DataFrame:
    """Customers that share parts, from `least` common parts on; with fewer, cliques are more than can be listed."""
    orders = load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("order"), F.col("o_custkey").alias("v"))
    lines = load_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("order"), F.col("l_partkey").alias("key"))
    return project(lines.join(orders, "order").select("key", "v").distinct(), least)


def coded(links: DataFrame, a: str = "a", b: str = "b", directed: bool = False) -> tuple[DataFrame, DataFrame]:
    """(edges, names (vid, name)): text ends as numbers, the first 60 bits of their md5, so no window ranks all names.

    Two names of one number are an error, never one vertex.
    """
    names = links.select(F.col(a).alias("name")).unionByName(links.select(F.col(b).alias("name"))).distinct()
    ids = written(names.select("name", F.conv(F.substring(F.md5(F.col("name").cast("binary")), 1, 15), 16, 10).cast("long").alias("vid")), "names")
    if ids.groupBy("vid").count().where("count > 1").limit(1).count():
        raise ValueError("two names have the same 60-bit code")
    rows = links.join(ids.toDF(a, "va"), a).join(ids.toDF(b, "vb"), b)
    ends = (F.col("va"), F.col("vb")) if directed else (F.least("va", "vb"), F.greatest("va", "vb"))
    return rows.select(ends[0].alias("src"), ends[1].alias("dst"), "weight"), ids


def user_follow(spark: SparkSession, sf_dir: str, minutes: int = 2) -> DataFrame:
    """Arcs user -> next user of the same event type within less than some minutes.

    Event types are few, so windows are per type and slice of time; the first event of the next slice ends a slice. If
    that is not the next event's slice, the next event is too far off anyway.
    """
    width = 10 * minutes * 60_000_000
    rows = load_table(spark, sf_dir, "events").select("event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"), "event_id", "user_id").withColumn("slice", F.floor(F.col("at") / width))
    first = rows.groupBy("event_type", "slice").agg(F.min(F.struct("at", "event_id", "user_id")).alias("f")).select("event_type", "f.at", "f.event_id", "f.user_id", (F.col("slice") - 1).alias("slice"), F.lit(False).alias("own"))
    where = Window.partitionBy("event_type", "slice").orderBy("at", "event_id")
    both = rows.withColumn("own", F.lit(True)).unionByName(first).withColumn("next", F.lead("user_id").over(where)).withColumn("then", F.lead("at").over(where))
    near = both.where(F.col("own") & (F.col("user_id") != F.col("next")) & (F.col("then") - F.col("at") < minutes * 60_000_000))
    return near.groupBy(F.col("user_id").alias("src"), F.col("next").alias("dst")).agg(F.count("*").alias("weight"))


def follow_links(spark: SparkSession, sf_dir: str, minutes: int = 2) -> DataFrame:
    return normalise(user_follow(spark, sf_dir, minutes), weight="weight")


def near_copies(spark: SparkSession, sf_dir: str, least: float = 0.3, most: int | None = None) -> DataFrame:
    """Documents whose distinct trimmed lines have a Jaccard similarity from `least`; weight counts all common lines.

    With `most`, as the SQL of near_copy has it, only lines that 2 to `most` documents hold are common ones.
    """
    docs = load_table(spark, sf_dir, "documents")
    return alike_lines(docs, least) if most is None else alike_rare_lines(docs, least, most)


def alike_rare_lines(docs: DataFrame, least: float, most: int) -> DataFrame:
    """Links (src, dst, weight) of documents (doc_id, text) by the lines that 2 to `most` documents hold.

    weight counts those lines; similarity is it over all lines of the two. A link needs weight from `least` times
    either's lines, so two linked documents meet on one of the first of their counted lines by rarity, and are compared
    over all counted lines. A line meets at most `most` documents, so pairs stay in proportion to the lines.
    """
    trimmed = F.filter(F.transform(F.split("text", "\n"), lambda x: F.trim(x)), lambda x: x != "")
    # Rows of one doc_id are one document.
    rows = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("v"), F.explode(F.array_distinct(trimmed)).alias("line"))
    own = written(rows.select("v", F.unhex(F.md5(F.col("line").cast("binary"))).alias("key")).distinct(), "lines")
    often = own.groupBy("key").agg(F.count("*").alias("often")).where(F.col("often").between(2, most))
    counted = own.join(often, "key").groupBy("v").agg(F.array_sort(F.collect_list(F.struct("often", "key"))).alias("k"))
    held = counted.join(own.groupBy("v").agg(F.count("*").alias("n")), "v").select("v", "n", "k")
    held = written(held.where(F.size("k") >= F.lit(least) * F.col("n") - 1e-9), "counted")
    # A little less than the bound: rounding must not shorten a prefix.
    prefix = held.select("v", F.explode(F.slice("k", F.lit(1), F.size("k") - F.greatest(F.lit(1), F.ceil(F.col("n") * F.lit(least) - 1e-9)).cast("int") + 1)).alias("x")).select("v", "x.key")
    pairs = prefix.toDF("src", "key").join(prefix.toDF("dst", "key"), "key").where("src < dst").select("src", "dst").distinct()
    lines = held.select("v", "n", F.transform("k", lambda x: x["key"]).alias("k"))
    met = pairs.join(lines.toDF("src", "na", "ka"), "src").join(lines.toDF("dst", "nb", "kb"), "dst")
    met = met.select("src", "dst", F.size(F.array_intersect("ka", "kb")).cast("long").alias("weight"), (F.col("na") + F.col("nb")).alias("n"))
    return met.where(F.col("weight") >= F.lit(least) * (F.col("n") - F.col("weight"))).select("src", "dst", "weight")


def alike_lines(docs: DataFrame, least: float) -> DataFrame:
    """Links (src, dst, weight) of documents (doc_id, text) by their lines, `least` above 0.

    Equal line sets are one class. Of two alike sets each has a common line among its first n - ceil(least n) + 1 by
    rarity, so classes meet on those alone and are compared over all lines. Lines are named by their md5.
    """
    trimmed = F.filter(F.transform(F.split("text", "\n"), lambda x: F.trim(x)), lambda x: x != "")
    keys = F.transform(trimmed, lambda x: F.unhex(F.md5(x.cast("binary"))))
    # Rows of one doc_id are one document.
    rows = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("v"), F.array_distinct(keys).alias("lines")).where(F.size("lines") > 0)
    own = written(rows.groupBy("v").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("lines")))).alias("lines")), "lines")
    sets = written(own.groupBy("lines").agg(F.min("v").alias("c"), F.count("*").alias("copies")), "sets")
    each = sets.select("c", F.explode("lines").alias("key"))
    ranked = each.join(each.groupBy("key").agg(F.count("*").alias("often")), "key")
    first = ranked.groupBy("c").agg(F.array_sort(F.collect_list(F.struct("often", "key"))).alias("k"))
    size = F.size("k")
    # A little less than the bound: rounding must not shorten a prefix.
    prefix = first.select("c", F.explode(F.slice("k", F.lit(1), size - F.ceil(size * F.lit(least) - 1e-9).cast("int") + 1)).alias("k")).select("c", "k.key")
    pairs = prefix.toDF("a", "key").join(prefix.toDF("b", "key"), "key").where("a < b").select("a", "b").distinct()
    held = sets.select("c", "lines")
    common = F.size(F.array_intersect("la", "lb")).cast("long")
    met = pairs.join(held.toDF("a", "la"), "a").join(held.toDF("b", "lb"), "b").select("a", "b", common.alias("weight"), (F.size("la") + F.size("lb")).alias("n"))
    met = met.where(F.col("weight") >= F.lit(least) * (F.col("n") - F.col("weight"))).select("a", "b", "weight")
    same = sets.where("copies > 1").select(F.col("c").alias("a"), F.col("c").alias("b"), F.size("lines").cast("long").alias("weight"))
    of = own.join(sets.select("lines", "c"), "lines").select("v", "c")
    rows = met.unionByName(same).join(of.toDF("va", "a"), "a").join(of.toDF("vb", "b"), "b").where("a <> b or va < vb")
    return rows.select(F.least("va", "vb").alias("src"), F.greatest("va", "vb").alias("dst"), "weight")


#: Vectors of one block, and the rows of it that are multiplied at once.
BLOCK, STRIP = 32_768, 256


def cosine_links(spark: SparkSession, sf_dir: str, least: float = 0.3, block: int = BLOCK) -> DataFrame:
    """Vectors of cosine from `least`, all pairs compared: blocks of vectors meet in one task each, by matrix products.

    A null vector, or one with a null in it, has no links, and vectors link only to those of their own length.
    """
    held = load_table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    v = held.where(F.col("vec_id").isNotNull() & F.col("e").isNotNull() & ~F.exists("e", lambda x: x.isNull()))
    blocks = max(4, -(-v.count() // block))
    own = v.select("vec_id", "e", F.size("e").alias("dim"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("b"))
    dealt = own.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumns({"lo": F.least("b", "j"), "hi": F.greatest("b", "j")}).drop("j")

    def run(groups: Iterator[pa.Table]) -> Iterator[pa.RecordBatch]:
        for table in groups:
            lo, hi, dim = (table.column(c)[0].as_py() for c in ("lo", "hi", "dim"))
            ids, b = table.column("vec_id").to_numpy(), table.column("b").to_numpy()
            x = table.column("e").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), dim)
            norm = np.sqrt(_dots(x, x))
            left, right = (np.flatnonzero(b == n) for n in (lo, hi))
            other = x[right]
            for at in range(0, len(left), STRIP):
                some = left[at : at + STRIP]
                dot, bound = x[some] @ other.T, least * norm[some][:, None] * norm[right][None, :]
                # What rounding could decide is looked at again below; a sum that is no number counts as large.
                i, j = np.nonzero(~(dot < bound - 1e-9 * np.abs(bound)))
                p, q = some[i], right[j]
                first = ids[p] < ids[q] if lo == hi else ids[p] != ids[q]
                p, q = p[first], q[first]
                near = ~(_dots(x[p], x[q]) < least * norm[p] * norm[q])
                u, w = ids[p[near]], ids[q[near]]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, w), pa.int64()), pa.array(np.maximum(u, w), pa.int64()), pa.array(np.ones(len(u), np.int64))], ["src", "dst", "weight"])

    rows = dealt.select("lo", "hi", "dim", "b", "vec_id", "e").repartition("lo", "hi", "dim").sortWithinPartitions("lo", "hi", "dim")
    return rows.mapInArrow(lambda batches: run(_grouped(batches)), "src long, dst long, weight long")


def _dots(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Products of rows, summed from the first column on."""
    total = np.zeros(len(x))
    for c in range(x.shape[1]):
        total += x[:, c] * y[:, c]
    return total


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows of each value of the first three columns, from batches sorted by them."""
    kept: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        key = np.stack([np.asarray(batch.column(n)) for n in range(3)])
        edges = [0, *(np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
        for a, b in zip(edges, edges[1:]):
            own = tuple(key[:, a].tolist())
            if kept and own != last:
                yield pa.Table.from_batches(kept)
                kept = []
            kept.append(batch.slice(a, b - a))
            last = own
    if kept:
        yield pa.Table.from_batches(kept)


def nav_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths that pages link to, linked when one page has both; as text ends (a, b, weight)."""
    pages = load_table(spark, sf_dir, "pages").select(F.col("page_id").alias("key"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), 1))).alias("v"))
    return project(pages).toDF("a", "b", "weight")


def customer_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A graph without triangles: customers and parts (as negative ids) that an order joins."""
    orders = load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"), "o_custkey")
    rows = order_parts(spark, sf_dir).join(orders, "key")
    return rows.groupBy((-F.col("v") - 1).alias("src"), F.col("o_custkey").alias("dst")).agg(F.count("*").alias("weight"))


def by_region(spark: SparkSession, sf_dir: str, window: str = "quarter") -> DataFrame:
    """Co-purchase links (part, src, dst, weight) of each customer region apart."""
    t = lambda n: load_table(spark, sf_dir, n)
    region = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_regionkey").cast("long").alias("part"))
    orders = t("orders").join(region, F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").alias("key"), "part")
    held = order_parts(spark, sf_dir, WINDOWS[window]).join(orders, "key").groupBy("key", "part").agg(F.array_sort(F.collect_set("v")).alias("m")).where(F.size("m") > 1)
    first = held.select("part", "m", F.posexplode("m").alias("i", "src"))
    return first.select("part", "src", F.explode(F.slice("m", F.col("i") + 2, F.size("m"))).alias("dst")).groupBy("part", "src", "dst").agg(F.count("*").alias("weight"))


# ---- the same graphs in DuckDB SQL -----------------------------------------------------------------------------------


def _projected(rows: str, least: int = 1, more: str = "") -> str:
    g = f"a.{more}, " if more else ""
    return f"SELECT {g}a.v AS src, b.v AS dst, count(*) AS weight FROM ({rows}) a JOIN ({rows}) b ON a.key = b.key AND a.v < b.v GROUP BY ALL HAVING count(*) >= {least}"


def _parts(until: str | None) -> str:
    where = f" WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderdate >= TIMESTAMP '1997-01-01' AND o_orderdate < TIMESTAMP '{until}')" if until else ""
    return f"SELECT DISTINCT l_orderkey AS key, l_partkey AS v FROM lineitem{where}"


_FOLLOW = (
    "SELECT user_id AS src, nxt AS dst, count(*) AS weight FROM (SELECT user_id, ts, lead(user_id) OVER w AS nxt, lead(ts) OVER w AS thn FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)) "
    "WHERE user_id <> nxt AND epoch_us(thn) - epoch_us(ts) < 120000000 GROUP BY ALL"
)
_LINES = "SELECT DISTINCT doc_id AS v, trim(l, ' ') AS key FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents) WHERE trim(l, ' ') <> ''"
_NEXT = "SELECT unnest(w[:-2]) AS f, unnest(w[2:]) AS s FROM (SELECT regexp_extract_all(lower(text), '\\p{L}+') AS w FROM documents)"
_BOUND = "weight >= greatest(8, (SELECT floor(sum(weight) / 80000) FROM p))"
_WORDS = f"WITH p AS (SELECT least(f, s) AS a, greatest(f, s) AS b, count(*) AS weight FROM ({_NEXT}) WHERE f <> s GROUP BY ALL) SELECT a, b, weight FROM p WHERE {_BOUND}"
_WORD_ARCS = f"WITH p AS (SELECT f AS a, s AS b, count(*) AS weight FROM ({_NEXT}) WHERE f <> s GROUP BY ALL) SELECT a, b, weight FROM p WHERE {_BOUND}"
_NAV = "SELECT DISTINCT page_id AS key, unnest(regexp_extract_all(html, 'href=\"/([^\"]*)\"', 1)) AS v FROM pages"

SQL = {
    **{f"copurchase_{w}": _projected(_parts(d)) for w, d in WINDOWS.items()},
    "copurchase_repeat": _projected(_parts(None), 2),
    "cosupply": _projected("SELECT DISTINCT l_orderkey AS key, l_suppkey AS v FROM lineitem"),
    "word_assoc": _WORDS,
    "word_arcs": _WORD_ARCS,
    "customer_copart": _projected("SELECT DISTINCT l_partkey AS key, o_custkey AS v FROM lineitem JOIN orders ON o_orderkey = l_orderkey", 4),
    "user_follow_arcs": _FOLLOW,
    "user_follow": f"SELECT least(src, dst) AS src, greatest(src, dst) AS dst, CAST(sum(weight) AS BIGINT) AS weight FROM ({_FOLLOW}) GROUP BY least(src, dst), greatest(src, dst)",
    "near_copy": (
        f"WITH l AS ({_LINES}), n AS (SELECT v, count(*) AS n FROM l GROUP BY v), r AS (SELECT key FROM l GROUP BY key HAVING count(*) BETWEEN 2 AND 30), p AS (SELECT a.v AS src, b.v AS dst, count(*) AS weight FROM l a JOIN l b ON a.key = b.key AND a.v < b.v WHERE a.key IN (SELECT key FROM r) GROUP BY ALL) "
        "SELECT src, dst, weight FROM p JOIN n na ON na.v = src JOIN n nb ON nb.v = dst WHERE weight >= 0.3 * (na.n + nb.n - weight)"
    ),
    "near_copy_all": (
        f"WITH l AS ({_LINES}), n AS (SELECT v, count(*) AS n FROM l GROUP BY v), p AS (SELECT a.v AS src, b.v AS dst, count(*) AS weight FROM l a JOIN l b ON a.key = b.key AND a.v < b.v GROUP BY ALL) "
        "SELECT src, dst, weight FROM p JOIN n na ON na.v = src JOIN n nb ON nb.v = dst WHERE weight >= 0.3 * (na.n + nb.n - weight)"
    ),
    "cosine": "SELECT a.vec_id AS src, b.vec_id AS dst, CAST(1 AS BIGINT) AS weight FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) >= 0.3",
    "nav": f"SELECT a.v AS a, b.v AS b, count(*) AS weight FROM ({_NAV}) a JOIN ({_NAV}) b ON a.key = b.key AND a.v < b.v GROUP BY ALL",
    "no_clique": f"SELECT -p.v - 1 AS src, o_custkey AS dst, count(*) AS weight FROM ({_parts(None)}) p JOIN orders ON o_orderkey = p.key GROUP BY ALL",
}
_CODE = "CAST('0x' || substr(md5({}), 1, 15) AS BIGINT)"
for _g in ("nav", "word_assoc"):
    _a, _b = _CODE.format("a"), _CODE.format("b")
    SQL[f"{_g}_coded"] = f"SELECT least({_a}, {_b}) AS src, greatest({_a}, {_b}) AS dst, weight FROM ({SQL[_g]})"
_REGION_ROWS = f"SELECT p.key, p.v, CAST(n_regionkey AS BIGINT) AS part FROM ({_parts(WINDOWS['quarter'])}) p JOIN orders ON o_orderkey = p.key JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey"
SQL["by_region"] = _projected(_REGION_ROWS, more="part")
