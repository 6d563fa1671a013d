"""Sources, sinks, SQL access, streams, experiments, figures and the relational operators."""

import math
import time
from datetime import datetime, timedelta

from pyspark.sql import functions as F

from cohesion.functions import sqlapi
from cohesion.operators import measures as M
from cohesion.operators import percolation as P
from cohesion.operators import relational as R
from cohesion.operators import split as S
from cohesion.plans import experiments, planner
from cohesion.session import load_table
from cohesion.sources import builders as B
from cohesion.sources import io
from cohesion.streaming import links as T


def test_edge_lists_and_sinks(spark, tmp_path):
    path = tmp_path / "links.txt"
    path.write_text("# comment\n1 2 0.5\n2,1 1.5\n2\t3\nbad line\n3 1\n4 4\n")
    e = io.read_edge_list(spark, str(path))
    assert sorted((r["src"], r["dst"], r["weight"]) for r in e.collect()) == [(1, 2, 2), (1, 3, 1), (2, 3, 1)]
    cover = P.percolate(e, 3)
    io.write_cover(cover, str(tmp_path / "cover"))
    assert spark.read.parquet(str(tmp_path / "cover")).count() == 3
    io.write_member_lists(cover, str(tmp_path / "lists"))
    assert [r["value"] for r in spark.read.text(str(tmp_path / "lists")).collect()] == ["1-2-3: 1 2 3"]
    nodes = P.communities(cover).select(F.col("community_key").alias("id"), "size")
    none = spark.createDataFrame([], "a string, b string, shared long")
    lines = [r["value"] for r in io.export_graph(nodes, none).orderBy("part").collect()]
    assert lines == ["graph communities {", '  "1-2-3" [size=3];', "}"]


def test_sql_access(spark, sf):
    e = B.copurchase(spark, sf, "month")
    cover = P.percolate(e, 4)
    sqlapi.register(spark, e, cover)
    assert spark.sql("SELECT count(DISTINCT community_key) AS n FROM cover_members").first()["n"] == 13
    assert abs(spark.sql("SELECT geometric_mean(v) AS g FROM VALUES (1.0D), (1.0D), (8.0D) AS t(v)").first()["g"] - 2) < 1e-9
    assert spark.sql("SELECT count(*) AS n FROM k_subsets(array(1L, 2L, 3L, 4L), 2)").first()["n"] == 6
    v = sqlapi.membership(cover).first()
    assert v["community_key"] in {r["community_key"] for r in sqlapi.communities_of(cover, v["vid"]).collect()}
    assert sqlapi.neighbours(e, v["vid"], 1).count() == 1 + e.where((F.col("src") == v["vid"]) | (F.col("dst") == v["vid"])).count()


def test_stream_equals_batch(spark, sf, tmp_path):
    rows = load_table(spark, sf, "events")
    rows.repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(str(tmp_path / "in"))
    stream = T.once(T.stream_events(spark, str(tmp_path / "in"), rows.schema, late="60 days", files=3))
    seen = {}

    def keep(batch, epoch):
        seen.update({(r["start"], r["event_type"]): r["n"] for r in batch.collect()})

    T.run_to_end(T.windowed_activity(stream), keep, str(tmp_path / "check"), "update")
    batch = T.windowed_activity(rows.withColumn("ts", F.col("ts").cast("timestamp")))
    assert seen == {(r["start"], r["event_type"]): r["n"] for r in batch.collect()}


def test_decayed_weights_and_late_rows(spark, tmp_path):
    start = datetime(2024, 1, 1)
    rows = [(1, 2, 0), (1, 2, 3600), (3, 4, 60)]
    kind = "src long, dst long, ts timestamp"
    for n, part in enumerate((rows, [(3, 4, 7200)], [(5, 6, -86400)])):
        spark.createDataFrame([(a, b, start + timedelta(seconds=s)) for a, b, s in part], kind).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(1.1)  # files are read in the order of their times
    links = spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).withWatermark("ts", "1 minute")
    seen = {}
    q = T.run_to_end(T.link_weights(links), lambda b, _: seen.update({(r["src"], r["dst"]): round(r["weight"], 6) for r in b.collect()}), str(tmp_path / "check"), "update")
    want = {(1, 2): 1.5, (3, 4): round(1 + 0.5 ** (7140 / 3600), 6)}
    assert {k: v for k, v in seen.items() if k != (5, 6)} == want
    counted = links.groupBy(F.window("ts", "1 hour")).count()
    q = T.run_to_end(counted, lambda b, _: b.count(), str(tmp_path / "check2"), "update")
    assert T.late_rows(q) == 1


def test_relational_operators(spark):
    left = spark.createDataFrame([(1, i, "x") for i in range(9)] + [(2, 0, "y"), (None, 0, "z")], "key long, n long, a string")
    right = spark.createDataFrame([(1, "p"), (1, "q"), (2, "r"), (None, "s")], "key long, b string")
    rows = lambda d: sorted(map(tuple, d.select("key", "n", "a", "b").collect()))
    assert rows(R.salted_join(left, right, "key", hot=3, salts=4)) == rows(left.join(right, "key"))
    at = lambda *v: spark.createDataFrame([(u, datetime(2024, 1, 1) + timedelta(seconds=s), x) for u, s, x in v], "u long, ts timestamp, x long")
    found = R.as_of(at((1, 5, 0), (1, 1, 0), (2, 9, 0)), at((1, 2, 7), (1, 5, 8), (1, 6, 9), (2, 1, None)), "u", "ts", "x")
    assert sorted((r["u"], r["ts"].second, r["as_of"]) for r in found.collect()) == [(1, 1, None), (1, 5, 8), (2, 9, None)]
    m = spark.sql("SELECT map(1L, array(2L, 3L), 2L, array(1L, 3L), 3L, array(1L, 2L), 4L, array(1L)) AS m, array(1L, 2L, 3L) AS a, array(1L, 2L, 4L) AS b")
    assert tuple(m.select(R.is_clique(F.col("a"), F.col("m")), R.is_clique(F.col("b"), F.col("m"))).first()) == (True, False)
    half = R.hash_sample(spark.range(1000), "id", 2)
    assert 400 < half.count() < 600 and half.exceptAll(R.hash_sample(spark.range(1000).repartition(7), "id", 2)).count() == 0


def test_fits_and_figures(spark, sf):
    m = spark.createDataFrame([(float(x), 3.0 + 8.0 / x, 5.0 - 2.0 * math.log(x)) for x in (1, 2, 5, 9)], "size_limit double, inv double, log double")
    a = M.fit_inverse(m, y="inv").first()
    b = M.fit_log(m, y="log").first()
    assert [round(v, 6) for v in (*a, *b)] == [3, 8, 1, 5, 2, 1]
    t = spark.createDataFrame([("serial", 4.0), ("split", 8.0)], "method string, seconds double")
    assert {r["method"]: r["speedup"] for r in M.speedup(t).collect()} == {"serial": 1.0, "split": 0.5}
    path = spark.createDataFrame([(1, 2), (2, 3), (3, 4)], "src long, dst long")
    assert tuple(M.mean_distance(path, 1).first()) == (12, 1.666667)
    assert [r["new"] for r in S.split_trace(path, 10, 1).collect()] == [2, 1]


def test_cover_kept_by_a_stream(spark):
    links = spark.createDataFrame([(1, 2), (1, 3), (2, 3), (3, 4), (3, 5), (4, 5)], "src long, dst long")
    state = T.CoverState(links, 3)
    state.step(spark.createDataFrame([(4, 6, "add"), (6, 5, "add"), (1, 2, "remove")], "src long, dst long, op string"), 0)
    assert {r["community_key"] for r in state.cover.collect()} == {r["community_key"] for r in P.percolate(state.edges, 3).collect()} == {"3-4-5"}


def test_experiments_and_planner(spark, sf):
    e = B.copurchase(spark, sf, "month")
    rows = experiments.sweep_size_limit(e, 4, [10, 40]).collect()
    assert [r["differing"] for r in rows] == [0, 0] and rows[0]["pieces"] >= rows[1]["pieces"]
    assert planner.choose_executor(e, 1 << 30) == "serial" and planner.choose_executor(e, 1000, 3.0) == "flat"
    assert planner.recommend_size_limit(e, 1 << 30, 4) == 18


def test_plans(spark, sf):
    plan = B.order_parts(spark, sf, "1997-02-01")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(o_orderdate), GreaterThanOrEqual(o_orderdate" in plan and "CartesianProduct" not in plan
