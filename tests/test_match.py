"""Filters, peeling and search on literal and random graphs, against plain Python."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from nbrmatch.operators import baselines, filters, fixpoint, graph, search
from nbrmatch.operators.pattern import Pattern, parse
from nbrmatch.plans import match as m
from nbrmatch.plans import measures
from nbrmatch.sources.graphs import ring
from nbrmatch.sources.tables import in_memory
from nbrmatch.streaming import edgepass

SF = "/root/testdata/sf0.001"
WORKED = parse("(u1:A)-(u2:B), (u1)-(u3:B), (u2)-(u3), (u3)-(u4:C), (u3)-(u5:D)")
LABELS = dict(enumerate("E A B B A D D A B B C E A B B C".split(), 1))
EDGES = [tuple(map(int, e.split("-"))) for e in "1-5 1-6 1-11 2-3 2-4 2-9 2-10 2-15 3-6 3-8 3-12 4-7 6-9 7-8 7-12 7-16 8-10 8-12 8-13 9-11 9-15 10-13 11-15 11-16 15-16".split()]


def plain(labels, edges, q, directed=False):
    """All embeddings by trying every assignment."""
    have = {(a, b): e for a, b, e in edges} if directed else {k: e for a, b, e in edges for k in ((a, b), (b, a))}
    names, out = sorted(q.vertices), []
    for p in itertools.product(*([v for v, n in labels.items() if n == q.vertices[u]] for u in names)):
        at = dict(zip(names, p, strict=True))
        if len(set(p)) == len(p) and all((at[a], at[b]) in have and (e is None or have[at[a], at[b]] == e) for a, b, e in q.edges):
            out.append(p)
    return sorted(out)


def rows(df):
    return sorted(tuple(r) for r in df.select(*sorted(df.columns)).collect())


@pytest.fixture(scope="module")
def traced(spark):
    return in_memory(spark, list(LABELS.items()), EDGES)


def test_codes_after_the_label_stage(traced):
    from nbrmatch.functions.codes import ncode_column

    f = filters.one_hop(filters.start(traced, WORKED, triples=False))
    got = {r["vid"]: (r["pdeg"], r["code"]) for r in f.select("vid", "pdeg", ncode_column([F.col(f"x{k}") for k in range(1, 5)]).alias("code")).collect()}
    assert got == {2: (5, 120), 3: (3, 24), 4: (2, 8), 5: (0, 0), 6: (2, 12), 7: (3, 29), 8: (4, 52), 9: (4, 49), 10: (3, 34), 11: (3, 28), 13: (2, 13), 14: (0, 0), 15: (4, 59), 16: (3, 20)}


@pytest.mark.parametrize("engine", ["frontier", "full", "auto"])
def test_four_rounds(traced, engine):
    p = fixpoint.peel(filters.start(traced, WORKED, triples=False), WORKED, engine=engine)
    assert [(x["removed"], x["by_degree"], x["by_code"]) for x in p.log] == [(4, 2, 2), (1, 0, 1), (1, 0, 1), (2, 0, 2)]
    assert p.engine == ("arrays" if engine == "auto" else engine)
    assert sorted(r["vid"] for r in p.state.collect()) == [2, 6, 9, 11, 15, 16]


@pytest.mark.parametrize("folders", [1, 3])
def test_rounds_that_touch_few_folders_only(spark, monkeypatch, folders):
    """A long chain falls off one vertex a round: rounds with few removals, through folders and merged notes."""
    monkeypatch.setattr(fixpoint, "FOLDER_ROWS", 1 if folders > 1 else 10**9)
    monkeypatch.setattr(fixpoint, "FOLDERS", folders)
    monkeypatch.setattr(fixpoint, "NOTES", 3)
    n = 30
    chain = [(k, "ABC"[k % 3]) for k in range(n)]
    ring_ = [(100 + k, "ABC"[k % 3]) for k in range(60)]
    g = in_memory(spark, chain + ring_, [(k, k + 1) for k in range(n - 1)] + [(100 + k, 100 + (k + 1) % 60) for k in range(60)])
    q = parse("(a:A)-(b:B)-(c:C)-(a)")
    p = fixpoint.peel(filters.start(g, q), q, max_rounds=9, engine="frontier")
    same = fixpoint.peel(filters.start(g, q), q, max_rounds=9)
    assert same.engine == "arrays" and same.log == p.log and rows(same.state) == rows(p.state)
    assert [(x["removed"], x["checked"] <= 4 or x["round"] == 1) for x in p.log] == [(2, True)] * 9
    assert {r["vid"] for r in p.state.collect()} == {*range(9, n - 9), *range(100, 160)}
    assert {r["vid"]: r["pdeg"] for r in p.state.collect()}[9] == 1
    assert {(r["src"], r["dst"]) for r in p.adj.collect()} == {(a, b) for x, y in [(k, k + 1) for k in range(9, n - 10)] + [(100 + k, 100 + (k + 1) % 60) for k in range(60)] for a, b in ((x, y), (y, x))}


def test_a_round_reads_the_folders_it_touches(spark, monkeypatch):
    from nbrmatch.session import cut

    t = cut(spark.range(1000).select(F.col("id").alias("dst"), fixpoint._folder("id", 8).alias("folder")), "t", "folder")
    some = fixpoint._read(t, [2, 5], 8)
    assert len(some.inputFiles()) == len(t.inputFiles())  # listing alone; the scan prunes:
    assert "PartitionFilters: [folder#" in some._jdf.queryExecution().toString() and some.count() == t.where("folder in (2, 5)").count()


def test_edge_labels_peel_vertices_that_plain_codes_keep(spark):
    g = in_memory(spark, [(1, "A"), (2, "B"), (3, "C"), (4, "A"), (5, "B"), (6, "C")], [(1, 2, "x"), (2, 3, "y"), (4, 5, "x"), (5, 6, "x")])
    q = parse("(a:A)-[x]-(b:B)-[y]-(c:C)")
    test, names = filters.code_for(q)
    s = filters.start(g, q, triples=False)
    for engine in ("auto", "frontier"):
        assert sorted(r["vid"] for r in fixpoint.peel(s, q, test, elabels=names, engine=engine).state.collect()) == [1, 2, 3]
    assert len(fixpoint.peel(s, q).state.collect()) == 6
    assert rows(m.match(g, q).embeddings) == [(1, 2, 3)]


def test_rarer_edges_come_first(spark):
    g = in_memory(spark, [(1, "A"), *((k, "B") for k in range(2, 8)), (9, "C")], [*((1, k) for k in range(2, 8)), (2, 9)])
    q = parse("(a:A)-(b:B)-(c:C)")
    assert search.edge_sizes(filters.start(g, q), q) == {("a", "b"): 6, ("b", "c"): 1}
    assert m.match(g, q, how="min_edge_card").order == ["b", "c", "a"]
    assert rows(m.match(g, q, how="min_edge_card").embeddings) == [(1, 2, 9)]


def test_parts_of_a_pattern_multiply(spark):
    g = in_memory(spark, [(k, "AB"[k % 2]) for k in range(8)] + [(9, "C"), (10, "C"), (11, "C")], [(k, k + 1) for k in range(7)])
    for text in ("(a:A)-(b:B), (c:C)", "(c:C), (a:A)", "(a:A)-(b:B), (x:A)"):
        q = parse(text)
        found = m.count(g, q)
        assert found.first()["n"] == m.match(g, q).embeddings.count()
    assert "NestedLoop" not in search.joins(*(lambda x: (x.peeled.adj, x.candidates))(m.match(g, parse("(a:A)-(b:B)"))), parse("(a:A)-(b:B)"))._jdf.queryExecution().toString()


def test_plans_of_searches_are_short(spark):
    """Each pattern edge reads written tables: no view of the graph is built again in the search."""
    from nbrmatch.plans import catalogue

    for rows_ in (m.match(catalogue.view(spark, SF, "T"), catalogue.TAILED).embeddings, baselines.nlf(catalogue.view(spark, SF, "T"), catalogue.TAILED), catalogue.queries()["x_order_containment"](spark, SF)):
        plan = rows_._jdf.queryExecution().executedPlan().toString()
        assert plan.count("FileScan") <= 30, plan.count("FileScan")


def test_label_frequency_rounds(traced):
    p = fixpoint.peel(filters.start(traced, WORKED, triples=False), WORKED, filters.nlf, engine="frontier")
    assert fixpoint.peel(filters.start(traced, WORKED, triples=False), WORKED, filters.nlf).log == p.log
    assert [x["removed"] for x in p.log] == [6, 2]
    assert sorted(r["vid"] for r in p.state.collect()) == [2, 6, 9, 11, 15, 16]


def test_one_embedding(traced):
    for engine in ("joins", "dfs"):
        assert rows(m.match(traced, WORKED, engine=engine).embeddings) == [(2, 15, 9, 11, 6)]
    assert m.exists(traced, WORKED)
    assert m.count(traced, WORKED).first()["n"] == 1


def random_case(seed):
    rng = random.Random(seed)
    labels = {v: rng.choice("ABC") for v in range(12)}
    edges = [(a, b, rng.choice(["x", "y"])) for a in range(12) for b in range(a + 1, 12) if rng.random() < 0.3]
    names = ["p", "q", "r", "s"]
    q_edges = [("p", "q"), ("q", "r"), *((a, b) for a, b in (("p", "r"), ("r", "s")) if rng.random() < 0.6)]
    used = {x for e in q_edges for x in e}
    q = Pattern({n: rng.choice("ABC") for n in names if n in used}, tuple((a, b, rng.choice([None, None, "x"])) for a, b in q_edges))
    return labels, edges, q


@pytest.mark.parametrize("directed", [False, True])
def test_arrays_peel_as_rounds_of_jobs_do(spark, directed):
    rng = random.Random(7)
    labels = [(v, rng.choice("ABC")) for v in range(40)]
    edges = [(a, b, rng.choice("xy")) for a in range(40) for b in range(40) if (a != b if directed else a < b) and rng.random() < 0.06]
    g = in_memory(spark, labels, edges, directed=directed)
    q = Pattern({"a": "A", "b": "B", "c": "C", "d": "A"}, (("a", "b", "x"), ("b", "c", "y"), ("c", "d", "x")), directed)
    test, names = filters.code_for(q)
    s = filters.start(g, q)
    one, two = (fixpoint.peel(s, q, test, engine=e, elabels=names) for e in ("auto", "frontier"))
    assert one.log == two.log and rows(one.state) == rows(two.state) and one.state.columns == two.state.columns
    assert sorted(map(str, one.adj.collect())) == sorted(map(str, two.adj.collect()))


@pytest.mark.parametrize("seed", range(4))
def test_all_matchers_agree_on_random_graphs(spark, seed):
    labels, edges, q = random_case(seed)
    g = in_memory(spark, list(labels.items()), edges)
    want = plain(labels, edges, q)
    got = m.match(g, q)
    assert rows(got.embeddings) == want
    adj, cand = got.peeled.adj, got.candidates
    assert rows(search.dfs(adj, cand, q, lookahead=True)) == want
    assert rows(search.joins_merged(adj, cand, q)) == want
    assert rows(m.match(g, q, access="pass").embeddings) == want
    assert rows(baselines.brute(g, q)) == want
    assert rows(baselines.refined(g, q)) == want
    assert rows(baselines.tree_index_match(baselines.tree_index(g, q), q)) == want
    assert m.count(g, q).first()["n"] == len(want)
    # Filters are sound and nested.
    s = filters.start(g, q)
    f = filters.with_mnd(filters.one_hop(s), s)
    sets = {n: {(r["u"], r["vid"]) for r in filters.candidates(f, q, t).collect()} for n, t in measures.TESTS.items()}
    images = {(u, v) for p in want for u, v in zip(sorted(q.vertices), p, strict=True)}
    for n, found in sets.items():
        assert images <= found, n
    assert sets["nlf"] <= sets["strict"] <= sets["lemma"] <= sets["degree"] <= sets["label"]
    packets = lambda w: {(r["u"], r["vid"]) for r in filters.candidates(f, q, filters.code_packets(w)).collect()}
    assert packets(1) == sets["nlf"] and packets(len(q.labels)) == sets["strict"]


def test_race(spark):
    labels, edges, q = random_case(1)
    g = in_memory(spark, list(labels.items()), edges)
    name, n, _ = baselines.race(spark, {"a": lambda: m.match(g, q).embeddings.count(), "b": lambda: baselines.brute(g, q).count()}, 120)
    assert name in "ab" and n == len(plain(labels, edges, q))


def test_exact_hops_lose_a_match_and_balls_do_not(spark):
    g = in_memory(spark, [(1, "A"), (2, "B"), (3, "C")], [(1, 2), (2, 3), (1, 3)])
    q = parse("(a:A)-(b:B)-(c:C)")
    assert m.match(g, q).embeddings.count() == 1
    hops = filters.hop_counts(filters.start(g, q, triples=False), 2)
    found = lambda t: {r["u"] for r in filters.candidates(hops, q, t).collect()}
    assert found(filters.ball(2)) == found(filters.nested_balls(2)) == {"a", "b", "c"}
    assert found(filters.shell(2)) < {"a", "b", "c"}


def test_two_way_directed_pair_counts_edges(spark):
    g = in_memory(spark, [(1, "A"), (2, "B")], [(1, 2), (2, 1)], directed=True)
    assert rows(m.match(g, parse("(a:A)->(b:B)")).embeddings) == [(1, 2)]


def test_directed_with_labels(spark):
    edges = [(1, 2, "x"), (2, 3, "y"), (3, 1, "x"), (2, 1, "y")]
    g = in_memory(spark, [(1, "A"), (2, "B"), (3, "A")], edges, directed=True)
    for text in ("(a:A)-[x]->(b:B)", "(a:A)->(b:B)->(c:A)", "(b:B)-[y]->(c:A)"):
        q = parse(text)
        assert rows(m.match(g, q).embeddings) == plain({1: "A", 2: "B", 3: "A"}, edges, q, directed=True)


def test_sorted_pass_keeps_both_edges(spark):
    g = in_memory(spark, [(1, "A"), (2, "B"), (3, "C")], [(1, 2), (2, 3)])
    q = parse("(a:A)-(b:B)-(c:C)")
    got = {(r["src"], r["dst"]) for r in edgepass.sorted_pass(filters.start(g, q), q).collect()}
    assert got == {(1, 2), (2, 1), (2, 3), (3, 2)}


@pytest.mark.parametrize("batch", [3, 10_000])
def test_sorted_pass_in_any_batches(spark, batch):
    labels, edges, q = random_case(3)
    g = in_memory(spark, list(labels.items()), edges)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
    try:
        s = filters.start(g, q)
        got = sorted((r["src"], r["dst"]) for r in edgepass.sorted_pass(s, q).collect())
        want = sorted((r["src"], r["dst"]) for r in edgepass.prefilter(s, q).adj.collect())
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert got == want


def test_live_filter_seals_and_restarts(spark, tmp_path):
    from nbrmatch.streaming import live

    q = parse("(a:A)-(b:B)-(c:C)")
    vertices = spark.createDataFrame([(1, "A"), (2, "B"), (3, "C"), (4, "B"), (9, "A")], "vid long, vlabel string")
    schema = "src long, dst long, elabel string, ts timestamp"
    batch = 0

    def feed(edges):
        nonlocal batch
        batch += 1
        spark.createDataFrame([(a, b, None, t) for a, b, t in edges], "src long, dst long, elabel string, ts string").select("src", "dst", "elabel", F.to_timestamp("ts").alias("ts")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream = live.live_filter(spark.readStream.schema(schema).parquet(f"{tmp_path}/in"), vertices, q, idle="1 hour")
        run = stream.writeStream.foreachBatch(lambda df, n: df.write.mode("append").parquet(f"{tmp_path}/out")).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
        run.awaitTermination()
        return spark.read.parquet(f"{tmp_path}/out").collect()

    def last(rows):
        best = {}
        for r in rows:
            best[r["vid"]] = max(best.get(r["vid"], (0, False, False)), (r["pdeg"], r["keep"], r["sealed"]))
        return best

    got = last(feed([(1, 2, "2024-01-01 00:00:00"), (1, 4, "2024-01-01 00:01:00")]))
    assert got[1][:2] == (2, True) and got[2][:2] == (1, False)  # b lacks its c
    got = last(feed([(2, 3, "2024-01-01 00:30:00")]))  # the query starts again from its state
    assert got[2][:2] == (2, True) and got[3][:2] == (1, True)
    rows_ = feed([(9, 9, "2024-01-03 00:00:00"), (1, 4, "2024-01-03 00:00:00")])
    rows_ = feed([(4, 3, "2024-01-01 00:00:10")])  # far too late: vertex 4 doesn't get its c any more
    assert any(r["vid"] == 2 and r["sealed"] and r["keep"] for r in rows_)
    assert not any(r["vid"] == 4 and r["keep"] for r in rows_)


def test_live_counts_of_a_range_share_a_state(spark, tmp_path):
    from nbrmatch.streaming import live

    schema, path = "dst long, ts timestamp", f"{tmp_path}/in"

    def feed(edges):
        spark.createDataFrame(edges, "dst long, ts string").select("dst", F.to_timestamp("ts").alias("ts")).coalesce(1).write.mode("append").parquet(path)
        stream = live.stateful_counts(spark.readStream.schema(schema).parquet(path), idle="1 hour", width=10)
        run = stream.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
        run.awaitTermination()
        states = spark.read.format("statestore").load(f"{tmp_path}/cp").count()
        return states, {tuple(r) for r in spark.read.parquet(f"{tmp_path}/out").collect()}

    states, got = feed([(1, "2024-01-01 00:00:00"), (2, "2024-01-01 00:10:00"), (1, "2024-01-01 00:20:00"), (-3, "2024-01-01 00:00:00"), (25, None), (None, "2024-01-01 00:00:00"), (None, "2024-01-01 00:00:00")])
    assert states <= 3 and got >= {(1, 2, False), (2, 1, False), (-3, 1, False), (25, 1, False), (None, 2, False)}
    _, got = feed([(2, "2024-01-01 00:30:00"), (9, "2024-01-03 00:00:00")])  # starts again from its state; the watermark passes all but 9
    assert got >= {(2, 2, False), (9, 1, False), (1, 2, True), (2, 2, True), (-3, 1, True), (None, 2, True)}
    states, got = feed([(2, "2024-01-01 00:30:00")])  # far too late
    assert states == 1 and not any(v == 2 and n > 2 for v, n, _ in got) and not any(v == 9 and s for v, _, s in got)


def test_dirty_edges(spark):
    from nbrmatch.operators.graph import build, dropped

    v = spark.createDataFrame([(1, "A"), (2, "B"), (3, None), (1, "A")], "vid long, vlabel string")
    e = spark.createDataFrame([(1, 2, None), (2, 1, None), (1, 1, None), (1, 3, None), (None, 1, None)], "src long, dst long, elabel string")
    g = build(v, e)
    assert sorted((r["src"], r["dst"]) for r in g.edges.collect()) == [(1, 2), (1, 3)]
    assert tuple(dropped(e).first()) == (1, 1, 1)
    assert rows(m.match(g, parse("(a:A)-(b:B)")).embeddings) == [(1, 2)]


def test_small_answers(spark):
    g = in_memory(spark, [(1, "A"), (2, "B"), (3, "B")], [(1, 2), (1, 3)])
    assert rows(m.match(g, parse("(b:B)")).embeddings) == [(2,), (3,)]
    assert rows(m.match(g, parse("(a:A)-(x:Z)")).embeddings) == []
    assert rows(m.match(g, parse("(b:B)-(a:A)-(c:B)")).embeddings) == [(1, 2, 3), (1, 3, 2)]
    assert m.match(g, parse("(b:B)-(a:A)-(c:B)"), unique="subgraph").embeddings.count() == 1
    assert rows(m.match(g, parse("(a:A), (b:B)")).embeddings) == [(1, 2), (1, 3)]
    assert m.match(g, parse("(a:A)-(b:B)-(c:A)-(d:B)")).embeddings.count() == 0


def test_filters_do_nothing_on_a_regular_ring(spark):
    g, q = ring(spark, 30), parse("(a:A)-(b:A)-(c:A)")
    p = fixpoint.peel(filters.start(g, q), q)
    assert p.log == [] and p.state.count() == 30
    assert m.match(g, q).embeddings.count() == 60


def test_graph_utilities(spark):
    g = in_memory(spark, [(k, "A") for k in range(1, 8)], [(1, 2), (2, 3), (1, 3), (3, 4), (5, 6)])
    assert {r["vid"] for r in graph.k_core(g, 2).collect()} == {1, 2, 3}
    comps = {r["vid"]: r["component"] for r in graph.connected_components(g).collect()}
    assert comps == {1: 1, 2: 1, 3: 1, 4: 1, 5: 5, 6: 5, 7: 7}
    assert {r["vid"]: r["level"] for r in graph.bfs_levels(g, spark.createDataFrame([(1,)], "vid long")).collect()} == {1: 0, 2: 1, 3: 1, 4: 2}
    assert g.induced(spark.createDataFrame([(1,), (2,), (4,)], "vid long")).edges.count() == 1


def test_walk_patterns_occur(spark):
    from nbrmatch.plans import workloads

    labels, edges, _ = random_case(2)
    g = in_memory(spark, list(labels.items()), edges)
    for kind in ("sparse", "dense"):
        for q in workloads.walk(g, 3, kind, n=2):
            assert len(q.vertices) == 3 and q.connected and parse(workloads.as_text(q)).code("u0") == q.code("u0")
            assert not m.match(g, q).embeddings.isEmpty()


def test_plans_push_labels_and_avoid_products(spark):
    from nbrmatch.plans.catalogue import TRIANGLE, features

    plan = features(spark, "/root/testdata/sf0.001", "T", TRIANGLE)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [In(p_type," in plan or "PushedFilters: [IsNotNull(p_partkey)" in plan or "In(concat(P:, p_type" in plan or "p_type#" in plan and "Filter" in plan
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
