"""Worked gadgets, brute force, equivalences and oracles of the community methods."""

import random

import duckdb
import numpy as np
import pytest

from cohesion import registry
from cohesion.graph import kcore, normalise
from cohesion.operators import cliques as C
from cohesion.operators import measures as M
from cohesion.operators import percolation as P
from cohesion.operators import split as S
from cohesion.plans import experiments as X
from cohesion.operators.components import METHODS, spanning
from cohesion.operators.egos import ego_covers
from cohesion.sources import builders as B


def edges(spark, links):
    return normalise(spark.createDataFrame([(a, b) for a, b in links] or [(None, None)], "src long, dst long"))


def sets(cover):
    found = {}
    for r in cover.collect():
        found.setdefault(r["community_key"], set()).update(r["members"])
    return sorted(sorted(x) for x in found.values())


K = lambda *v: [(a, b) for a in v for b in v if a < b]
BOW = K(1, 2, 3) + K(3, 4, 5)
HUBS = [("a", f"x{i}") for i in range(5)] + [("d", f"y{i}") for i in range(5)] + [("a", "b1"), ("a", "b2"), ("b1", "b2"), ("d", "c1"), ("d", "c2"), ("c1", "c2"), ("b1", "c1"), ("b1", "c2")]
NAMES = {n: i for i, n in enumerate(sorted({x for p in HUBS for x in p}))}
HUB_LINKS = [(NAMES[a], NAMES[b]) for a, b in HUBS]


@pytest.mark.parametrize(
    "links,k,want",
    [
        (K(1, 2, 3), 3, [[1, 2, 3]]),
        (K(1, 2, 3), 4, []),
        (K(1, 2, 3) + K(2, 3, 4), 3, [[1, 2, 3, 4]]),
        (BOW, 3, [[1, 2, 3], [3, 4, 5]]),
        (BOW, 2, [[1, 2, 3, 4, 5]]),
        (K(1, 2, 3, 4, 5), 4, [[1, 2, 3, 4, 5]]),
        (K(1, 2, 3, 4) + [(3, 5), (4, 5)], 3, [[1, 2, 3, 4, 5]]),
        (K(1, 2, 3, 4) + [(3, 5), (4, 5)], 4, [[1, 2, 3, 4]]),
        ([(a, b) for a in (1, 2, 3) for b in (4, 5, 6)], 3, []),
        ([], 3, []),
        ([(1, 1), (2, 1), (1, 2), (2, 3), (3, 1), (1, None)], 3, [[1, 2, 3]]),
    ],
)
def test_gadgets(spark, links, k, want):
    e = edges(spark, links)
    assert sets(P.percolate(e, k)) == want
    assert sets(P.percolate(e, k, "kclique")) == want


def test_methods_agree_with_the_definition(spark):
    rng = random.Random(4)
    for n, p in ((7, 0.5), (9, 0.6), (10, 0.45)):
        links = [x for x in K(*range(n)) if rng.random() < p]
        e = edges(spark, links)
        for k in (3, 4, 5) if n == 10 else (3, 4):
            want = sorted(sorted(c) for c in P.brute_force(links, k))
            assert sets(P.percolate(e, k)) == want
            assert sets(P.percolate(e, k, strategy="frontier")) == want
            assert sets(P.percolate_local(e, k)) == want
            assert sets(S.percolate_split(e, k, "mod", parts=3)) == want
            assert sets(S.percolate_split(e, k, "bfs", method="kclique", size_limit=3, n_seeds=2)) == want
            if n == 9:
                assert sets(S.percolate_split(e, k, "mod", method="hyperlink", closure="clique", parts=3)) == want
                assert sets(S.percolate_one_sided(e, S.owners(e, "mod", 3), k)) == want
        if n != 9:
            continue
        whole = {k: sorted(sorted(c) for c in P.brute_force(links, k)) for k in (3, 4, 5)}
        covers = S.percolate_split_all(e, 3, 5, rule="mod", parts=3)
        assert {k: sets(covers.where(f"k = {k}")) for k in (3, 4, 5)} == whole
        found = {tuple(r["members"]) for r in C.maximal_cliques(e).collect()}
        some = spark.createDataFrame([(0,), (3,)], "vid long")
        assert {tuple(r["members"]) for r in C.maximal_cliques_of(e, some).collect()} == {c for c in found if {0, 3} & set(c)}
        assert sets(P.percolate(e, 3, convention="printed")) == sets(P.percolate(e, 4))


def test_lost_links_without_borders(spark):
    e = edges(spark, HUB_LINKS)
    named = lambda found: sorted(sorted(n for n, i in NAMES.items() if i in c) for c in found)
    assert named(sets(P.percolate(e, 3))) == [["a", "b1", "b2"], ["b1", "c1", "c2", "d"]]
    assert named(sets(S.percolate_split(e, 3, "bfs", size_limit=8, n_seeds=2))) == [["a", "b1", "b2"], ["b1", "c1", "c2", "d"]]
    owner = S.owners(e, "bfs", size_limit=8, n_seeds=2, min_piece=1)
    lost = S.coverage(e, S.pieces_of(e, owner, "none")[1]).first()["lost"]
    pv, pe = S.printed_pieces(e, 8, 2, min_piece=1)
    # As printed, growth stops at the limit and no piece has the two links between the hubs' neighbours.
    assert S.coverage(e, pe).first()["lost"] == 2 and pv.where("owned").count() == len(NAMES)
    assert S.clique_coverage(e, pe, 3).first()["lost"] == 1
    assert lost > 0 and S.coverage(e, S.pieces_of(e, owner)[1]).first()["lost"] == 0


def test_growth_by_levels_is_the_growth_in_memory(spark, sf):
    e = B.copurchase(spark, sf, "month")
    rows = lambda x: {tuple(r) for r in x.collect()}
    assert rows(S.bfs_pieces(e, 15, 6)) == rows(S.bfs_pieces(e, 15, 6, distributed=True))
    assert rows(S.split_trace(e, 15, 6)) == rows(S.split_trace(e, 15, 6, True))


def test_small_pieces_merge_alike_both_ways(spark, monkeypatch):
    rng = random.Random(2)
    e = edges(spark, K(1, 2, 3, 4, 5) + [(rng.randrange(1, 30), rng.randrange(1, 30)) for _ in range(30)] + [(51, 52), (53, 54)])
    local = {(r["vid"], r["piece"]) for r in S.bfs_owners(e, 6, 6).collect()}
    monkeypatch.setattr(S, "LOCAL_LINKS", 10)
    monkeypatch.setattr(S, "DELTAS", 2)
    assert {(r["vid"], r["piece"]) for r in S.bfs_owners(e, 6, 6).collect()} == local


def test_border_of_two_pieces(spark):
    e = edges(spark, [(1, 2), (1, 3), (2, 3), (2, 4), (3, 4), (3, 5), (4, 5), (4, 6), (5, 6)])
    owner = spark.createDataFrame([(v, 0 if v < 4 else 1) for v in range(1, 7)], "vid long, piece long")
    pv, pe = S.pieces_of(e, owner)
    held = {p: sorted(r["vid"] for r in pv.collect() if r["piece"] == p) for p in (0, 1)}
    assert held == {0: [1, 2, 3, 4, 5], 1: [2, 3, 4, 5, 6]}
    assert S.boundary(e, owner).count() == 3
    for method in ("overlap", "kclique", "hyperlink"):
        assert sets(S.merge_local(S.percolate_pieces(pe, 3), pv, 3, method)) == [[1, 2, 3, 4, 5, 6]]
    assert sets(S.percolate_one_sided(e, owner, 3)) == [[1, 2, 3, 4, 5, 6]]
    cut = spark.createDataFrame([(2, 4), (3, 4), (3, 5)], "src long, dst long")
    assert {(r["vid"], r["piece"]) for r in S.split_by_cut(e, cut).collect()} == {(v, 1 if v < 4 else 4) for v in range(1, 7)}


def test_one_link_changes_only_what_it_touches(spark):
    e = edges(spark, BOW + [(4, 6), (5, 6)])
    cover = P.percolate(e, 3)
    assert sets(cover) == [[1, 2, 3], [3, 4, 5, 6]]
    gone = spark.createDataFrame([(4, 6)], "src long, dst long")
    links, after = P.update_cover(e, cover, 3, removed=gone)
    assert sets(after) == [[1, 2, 3], [3, 4, 5]]
    again = P.update_cover(links, after, 3, added=gone)[1]
    assert sets(again) == [[1, 2, 3], [3, 4, 5, 6]]


def test_directions_and_weights(spark):
    arcs = lambda x: spark.createDataFrame(x, "src long, dst long")
    assert sets(P.percolate_directed(arcs([(1, 2), (2, 3), (3, 1)]), 3)) == []
    assert sets(P.percolate_directed(arcs([(1, 2), (1, 3), (2, 3)]), 3)) == [[1, 2, 3]]
    assert sets(P.percolate_directed(arcs([(1, 2), (2, 3), (3, 4), (4, 1), (1, 3), (3, 1), (2, 4), (4, 2)]), 4)) == []
    assert sets(P.percolate_directed(arcs(K(1, 2, 3) + [(b, a) for a, b in K(1, 2, 3)]), 3)) == [[1, 2, 3]]
    w = normalise(spark.createDataFrame([(1, 2, 1.0), (1, 3, 1.0), (2, 3, 8.0)], "src long, dst long, w double"), weight="w")
    assert sets(P.percolate_intensity(w, 3, 2.0)) == [[1, 2, 3]] and sets(P.percolate_intensity(w, 3, 2.1)) == []
    assert sets(P.percolate_weighted(w, 3, 0)) == [[1, 2, 3]] and sets(P.percolate_weighted(w, 3, 2)) == []


def test_components_agree(spark):
    links = spark.createDataFrame([(1, 2), (2, 3), (5, 4), (7, 8), (8, 9), (9, 7)], "u long, v long")
    want = {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 7: 7, 8: 7, 9: 7}
    for f in METHODS.values():
        assert {r["node"]: r["label"] for r in f(links).collect()} == want


def test_rewiring_keeps_degrees(spark, sf):
    e = B.copurchase(spark, sf, "month")
    from cohesion.graph import degrees

    a, b = ({(r["vid"], r["degree"]) for r in degrees(x).collect()} for x in (e, M.rewire(e)))
    assert a == b


@pytest.mark.parametrize("name", ["q_percolate_month_k4", "q_percolate_split_bfs_k4", "q_clique_overlaps", "q_hypergraph", "q_percolate_by_region", "q_edges_word_assoc"])
def test_oracles(spark, sf, name):
    got = registry.QUERIES[name](spark, sf).toPandas()
    con = duckdb.connect()
    for t in ("lineitem", "orders", "customer", "nation", "documents"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.sql(registry.ORACLES[name]).df()
    rows = lambda d: sorted(map(tuple, d[sorted(d.columns)].astype(str).values.tolist()))
    assert rows(got) == rows(want)


def test_near_copies_count_every_line(spark, tmp_path):
    rng = random.Random(6)
    rows = [(i, "\n".join(["one", " two ", "three", "", "two"])) for i in range(35)]
    rows += [(100 + i, "\n".join(rng.choice("abcdefgh") for _ in range(rng.randrange(9)))) for i in range(60)] + [(200, None), (201, ""), (202, "one\nfour\nfive\nsix")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    held = {i: {x.strip(" ") for x in (t or "").split("\n")} - {""} for i, t in rows}
    want = {(a, b, len(held[a] & held[b])) for a, b in K(*held) if held[a] and held[b] and len(held[a] & held[b]) >= 0.3 * len(held[a] | held[b])}
    got = [tuple(r) for r in B.near_copies(spark, str(tmp_path)).collect()]
    assert len(got) == len(set(got)) and set(got) == want


@pytest.mark.parametrize("name", ["q_edges_near_copy", "q_percolate_near_copy_k3"])
def test_near_copy_queries_match_their_sql(spark, tmp_path, name):
    rng = random.Random(9)
    rows = [(i, "\n".join(["one", " two ", f"own {i // 2}", f"pair {i // 3}", f"pair {i // 3} too"])) for i in range(40)]
    rows += [(100 + i, "\n".join(rng.choice("abcdefghij") for _ in range(rng.randrange(9)))) for i in range(45)]
    rows += [(200, None), (201, ""), (202, "x\ny"), (202, "z\nx"), (203, "x\ny\nz"), (None, "x\ny\nz"), (204, "x \r\n y\n\tz")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    want = sorted(map(tuple, con.sql(registry.ORACLES[name]).df().values.tolist()))
    assert want and sorted(map(tuple, registry.QUERIES[name](spark, str(tmp_path)).toPandas().values.tolist())) == want


def test_near_copy_communities_count_common_lines(spark, tmp_path):
    rows = [(i, f"one\nown {i}") for i in range(35)] + [(100, "a\nb"), (100, "c"), (101, "a\nc"), (102, "b\nc"), (None, "one")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    got = sorted(map(tuple, registry.QUERIES["q_percolate_near_copy_k3"](spark, str(tmp_path)).toPandas().values.tolist()))
    assert got == [(3, "0-1-2", 35), (3, "100-101-102", 3)]
    assert sorted(map(tuple, con.sql(registry.ORACLES["q_percolate_near_copy_k3"]).df().values.tolist())) == got


def test_egos_match_the_serial_covers():
    rng = random.Random(3)
    for _ in range(60):
        n, p = rng.randrange(3, 12), rng.random()
        links = [x for x in K(*range(0, 7 * n, 7)) if rng.random() < p]
        ends = np.array(links, np.int64).reshape(-1, 2)
        for k in (3, 4, 5):
            want, got = {}, [{}, {}]
            for _, key, clique in P.serial_covers(links, k, k):
                want.setdefault(key, set()).update(clique)
            for held, whole in zip(got, (100, 0)):  # bitmaps over the graph, and over each neighbourhood
                for least, clique in ego_covers(ends[:, 0], ends[:, 1], k, whole):
                    held.setdefault("-".join(map(str, least)), set()).update(clique)
            assert got == [want, want]


def test_egos_take_dense_graphs_and_components_apart(spark):
    links = [x for x in K(*range(60)) if (x[0] // 2) != (x[1] // 2)]  # 2^30 maximal cliques
    e = edges(spark, links + K(100, 101, 102) + K(102, 103, 104))
    want = [[*range(60)], [100, 101, 102], [102, 103, 104]]
    for limit in (10_000, 1_000_000):
        assert sets(P.percolate_egos(e, 3, limit)) == want
    assert sets(P.percolate_egos(edges(spark, BOW + K(9, 10, 11, 12)), 3, 5)) == [[1, 2, 3], [3, 4, 5], [9, 10, 11, 12]]
    both = P.percolate_all(e, 3, 4, "egos")
    assert [tuple(r) for r in P.diagnose(e, both, [3, 4, 31]).orderBy("k").collect()] == [(3, False, True), (4, False, True), (31, True, False)]


def test_egos_take_a_component_beyond_the_limit(spark):
    links = [x for x in K(*range(60)) if (x[0] // 2) != (x[1] // 2)]  # 2^30 maximal cliques
    e = edges(spark, links + K(100, 101, 102) + K(102, 103, 104))
    assert sets(P.percolate_egos(e, 3, 100)) == [[*range(60)], [100, 101, 102], [102, 103, 104]]


def test_one_growth_serves_all_figures(spark, sf, monkeypatch):
    e = B.copurchase(spark, sf, "month")
    g = S.bfs_growth(e, 9, 3)
    rows = lambda x: sorted(map(tuple, x.collect()))
    assert rows(S.bfs_owners(e, 9, 3, growth=g)) == rows(S.bfs_owners(e, 9, 3).select("vid", "piece"))
    assert rows(S.split_trace(e, 9, 3, growth=g)) == rows(S.split_trace(e, 9, 3))
    before = S.bfs_pieces(e, 9, 3, 1).where("owned").groupBy("piece").count()
    assert tuple(S.tiny_pieces(e, 9, 3, g).first())[:2] == (before.count(), before.where("count < 9").count())
    calls = []
    one = S.bfs_growth
    monkeypatch.setattr(S, "bfs_growth", lambda *a, **kw: calls.append(a) or one(*a, **kw))
    monkeypatch.setattr(S, "bfs_pieces", None)  # a second growth fails
    assert [r["differing"] for r in X.sweep_size_limit(e, 3, [9]).collect()] == [0] and len(calls) == 1


def test_serial_roots_without_enough_later_neighbours_are_left_out(monkeypatch):
    asked = []
    one = C.bron_kerbosch
    monkeypatch.setattr(C, "bron_kerbosch", lambda a, v, *x: asked.append(v) or one(a, v, *x))
    links = K(1, 2, 3) + [(3, i) for i in range(10, 60)]
    assert P.serial_covers(links, 3, 3) == [(3, "1-2-3", [1, 2, 3])] and len(asked) == 1


def test_spanning_keeps_components(spark):
    rng = random.Random(8)
    links = [(rng.randrange(400), rng.randrange(400)) for _ in range(2600)]
    e = spark.createDataFrame(links, "u long, v long").repartition(3)
    stars = spanning(e)
    want, got = ({tuple(r) for r in METHODS["star"](x).collect()} for x in (e, stars))
    assert got == want and stars.count() < 2600


def test_cosine_links_compare_all_pairs(spark, tmp_path):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(90, 3)).astype(np.float32)
    x[5], x[6] = x[4], 2 * x[4]
    rows = [(int(i), [float(c) for c in v]) for i, v in enumerate(x)] + [(200, None), (201, [1.0, None, 2.0]), (None, [1.0, 0.0, 0.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    y = x.astype(float)
    cosine = (y @ y.T) / np.sqrt((y * y).sum(axis=1)[:, None] * (y * y).sum(axis=1)[None, :])
    want = {(a, b, 1) for a, b in K(*range(90)) if cosine[a, b] >= 0.3}
    for block in (B.BLOCK, 8):
        got = [tuple(r) for r in B.cosine_links(spark, str(tmp_path), block=block).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_mean_distance_counts_all_pairs(spark):
    n = 6
    pairs = [b - a for a, b in K(*range(n))]
    got = M.mean_distance(edges(spark, [(i, i + 1) for i in range(n - 1)])).first()
    assert tuple(got) == (2 * len(pairs), round(sum(pairs) / len(pairs), 6))


def test_cores_peel_to_the_end(spark):
    assert kcore(edges(spark, [(i, i + 1) for i in range(45)]), 2).count() == 0


def test_flagship(spark):
    assert registry.flagship(spark, "/root/testdata/sf0.001").count() == 13


def test_diagnosis_of_graphs_without_structure(spark):
    e = edges(spark, [(a, b) for a in (1, 2, 3) for b in (4, 5, 6)])
    assert [tuple(r) for r in P.diagnose(e, P.percolate_all(e, 3), [3, 4]).orderBy("k").collect()] == [(3, True, False), (4, True, False)]
    e = edges(spark, K(1, 2, 3, 4))
    assert [tuple(r) for r in P.diagnose(e, P.percolate_all(e, 3), [3, 5]).orderBy("k").collect()] == [(3, False, True), (5, True, False)]


def test_guards_refuse_floods(spark, monkeypatch):
    from cohesion.session import shared_folder

    monkeypatch.setattr(C, "MAX_CLIQUES", 2)
    pairs = [(0, v) for v in range(1, 9)] + [(v, w) for v in range(1, 9) for w in range(v + 2, 9)]
    with pytest.raises(Exception, match="maximal cliques"):
        C.maximal_cliques(edges(spark, pairs)).count()
    with pytest.raises(ValueError, match="pairs"):
        M.pair_f1(P.percolate(edges(spark, K(1, 2, 3, 4)), 3), P.percolate(edges(spark, K(1, 2, 3, 4)), 3), most=2)
    assert shared_folder(spark)


def test_pairs_and_random_graphs(spark):
    e = edges(spark, BOW)
    a, b = P.percolate(e, 3), P.percolate(edges(spark, K(1, 2, 3)), 3)
    assert tuple(M.pair_f1(a, b).first()) == (6, 3, 3, round(6 / 9, 6)) and M.pair_f1(a, a).first()["f1"] == 1.0
    ids = {v for x in BOW for v in x}
    g = M.gnm(e, 3, 2).collect()
    assert all(r["src"] < r["dst"] and {r["src"], r["dst"]} <= ids for r in g)


def test_follow_arcs_across_slices(spark, tmp_path):
    rng = random.Random(3)
    at, rows = 0, []
    for i in range(400):
        at += rng.choice([1, 30, 119, 120, 121, 1199, 1200, 4000])
        rows.append((i, "2024-01-01 00:00:00", at, rng.randrange(9), rng.choice("ab")))
    table = spark.createDataFrame(rows, "event_id long, day string, s long, user_id long, event_type string").selectExpr("event_id", "cast(timestampadd(SECOND, s, cast(day as timestamp)) as timestamp_ntz) AS ts", "user_id", "event_type")
    table.write.parquet(f"{tmp_path}/events.parquet")
    want = {}
    for kind in "ab":
        own = [r for r in rows if r[4] == kind]
        for x, y in zip(own, own[1:]):
            if y[2] - x[2] < 120 and x[3] != y[3]:
                want[x[3], y[3]] = want.get((x[3], y[3]), 0) + 1
    assert {(r["src"], r["dst"]): r["weight"] for r in B.user_follow(spark, str(tmp_path)).collect()} == want
