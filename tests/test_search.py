import random

import pytest

from pyspark.sql import functions as F

from waypoint import workloads
from waypoint.operators import answers as A
from waypoint.operators import baselines, search as kernel
from waypoint.operators.paths import iter_paths, k_paths, lazy_paths, paths, paths_balanced, paths_by_level, paths_by_visit, single_paths
from waypoint.operators.search import answers, search
from waypoint.plans.automaton import prepared
from waypoint.sources.graphs import LabelledGraph

S = "src string, label string, dst string"


def graph(spark, rows):
    return spark.createDataFrame(rows, S).distinct()


def counts(spark, rows, regex, source="v", finals="dictionary", **how):
    a = answers(search(graph(spark, rows), prepared(regex, **how), source, finals=finals))
    return {r["node"]: (r["dist"], int(r["num_paths"])) for r in a.collect()}


FIGURE = [("v", "e", "n1"), ("v", "e", "n2"), ("v", "e", "n3"), ("n1", "e", "n4"), ("n2", "e", "n4"), ("n3", "e", "n4"), ("n4", "e", "n5")]


def test_worked_example(spark):
    got = counts(spark, FIGURE, "e*")
    assert got == {"v": (0, 1), "n1": (1, 1), "n2": (1, 1), "n3": (1, 1), "n4": (2, 3), "n5": (3, 3)}
    found = search(graph(spark, FIGURE), prepared("e*"), "v", "links")
    assert found.links.count() == 7
    assert paths(found).count() == 10
    links = [tuple(r) for r in found.links.select("node", "state", "pred", "pred_state", "label").collect()]
    end = found.visited.filter("dist = 3").first()["node"]
    lazy = list(iter_paths(links, end, [0]))
    assert len(lazy) == 3 and all(len(n) == 4 and n[-1] == end and steps <= len(n) for steps, n, _ in lazy)


MICRO = [
    ([("v", "a", "x"), ("v", "b", "x")], "a|b", {"x": (1, 2)}),
    ([("v", "a", "v")], "a", {"v": (1, 1)}),
    ([("v", "a", "v")], "a*", {"v": (0, 1)}),
    ([("v", "a", "x"), ("v", "b", "y"), ("y", "c", "x")], "a|b/c", {"x": (1, 1)}),
    ([("v", "a", "x"), ("v", "b", "x")], "a|b/c?", {"x": (1, 2)}),
    ([("v", "a", "x"), ("x", "a", "y")], "a*/a*", {"v": (0, 1), "x": (1, 1), "y": (2, 1)}),
    ([("v", "a", "x"), ("x", "b", "x"), ("x", "a", "y")], "a/b/a", {"y": (3, 1)}),
    ([("v", "a", "x"), ("v", "a", "x")], "a", {"x": (1, 1)}),
    ([("v", "a", "x"), ("x", "a", "t"), ("v", "a", "y")], "a/b", {}),
    ([("x", "a", "v")], "b?", {"v": (0, 1)}),
]


@pytest.mark.parametrize("finals", ["dictionary", "normalise"])
@pytest.mark.parametrize("rows,regex,want", MICRO)
def test_micro_graphs(spark, rows, regex, want, finals):
    assert counts(spark, rows, regex, finals=finals) == want


def test_backward_edge_and_unknown_source(spark):
    edges = LabelledGraph.from_edges(graph(spark, [("x", "a", "v")])).with_inverses()
    assert [r["node"] for r in answers(search(edges, prepared("^a"), "v")).collect()] == ["x"]
    assert answers(search(edges, prepared("a*"), "nowhere")).count() == 0


def test_ladder_counts_double(spark):
    rows = []
    for i in range(8):
        rows += [(f"d{i}", "a", f"u{i}"), (f"d{i}", "a", f"l{i}"), (f"u{i}", "a", f"d{i + 1}"), (f"l{i}", "a", f"d{i + 1}")]
    assert counts(spark, rows, "a*", "d0")["d8"] == (16, 256)


def listed(df):
    return sorted((r["source"], r["node"], r["dist"], tuple(r["nodes"]), tuple(r["labels"])) for r in df.collect())


def put_together(tables):
    return sorted(x for t in tables for x in listed(t))


def test_random_graphs_against_all_walks(spark):
    rng = random.Random(5)
    for regex in ("(a|b)*/a", "a/b*/a?"):
        rows = list({(str(rng.randrange(6)), rng.choice("ab"), str(rng.randrange(6))) for _ in range(14)} | {("0", "a", "1")})
        automaton, best = prepared(regex), {}
        walks = [(("0",), ())]
        for depth in range(8):
            for nodes, labels in walks:
                if automaton.accepts(labels):
                    d, s = best.get(nodes[-1], (depth, set()))
                    if d == depth:
                        best[nodes[-1]] = (d, s | {(nodes, labels)})
            walks = [((*n, y), (*l, a)) for n, l in walks for x, a, y in rows if x == n[-1]]
        g = LabelledGraph.from_edges(graph(spark, rows))
        found = search(g, automaton, "0", "links")
        every = listed(paths(found))
        got = {}
        for _, node, dist, nodes, labels in every:
            got.setdefault(node, (dist, set()))[1].add((nodes, labels))
        assert got == best
        assert counts(spark, rows, regex, "0") == {n: (d, len(s)) for n, (d, s) in best.items()}
        assert put_together(paths_by_level(g, automaton, "0")) == put_together(paths_by_visit(g, automaton, "0")) == every
        assert listed(lazy_paths(found).drop("steps")) == listed(paths_balanced(found, 3)) == every
        assert len(listed(k_paths(found, 1))) == len(best) and set(listed(k_paths(found, 2))) <= set(every)
        assert listed(baselines.shortest_of(baselines.walks(g, automaton, "0", 7))) == every
        assert A.invalid_paths(g, automaton, paths(found), found).count() == 0
        product = {r["node"]: (r["dist"], int(r["num_paths"])) for r in baselines.product_answers(g, automaton, "0").collect()}
        assert product == {n: (d, len(s)) for n, (d, s) in best.items()}
        one = listed(single_paths(search(g, automaton, "0", "one")))
        assert len(one) == len(best) and set(one) <= set(every)


def test_one_witness_an_answer_with_several_finals(spark):
    rows = [("v", "click", "x"), ("v", "view", "x")]
    found = search(graph(spark, rows), prepared("(click|view/click)*/view?"), "v", "one")
    assert sorted(r["node"] for r in single_paths(found).collect()) == ["v", "x"]


def test_targets_of_several_sources(spark):
    rows = [("a", "e", "t"), ("b", "e", "m"), ("m", "e", "t"), ("b", "e", "u"), ("a", "e", "n"), ("n", "e", "o"), ("o", "e", "u"), ("u", "e", "far")]
    found = answers(search(graph(spark, rows), prepared("e+"), ["a", "b"], targets=["t", "u"]))
    got = {(r["source"], r["node"]): r["dist"] for r in found.collect()}
    assert (got["a", "t"], got["b", "t"], got["a", "u"], got["b", "u"]) == (1, 2, 3, 1) and ("a", "far") not in got


@pytest.mark.parametrize("hub", [2, 10**9])
def test_buckets_and_salted_hubs_change_nothing(spark, monkeypatch, hub):
    rng = random.Random(7)
    rows = list({(rng.choice("vvvwxyz"), rng.choice("ab"), rng.choice("vwxyzpqr")) for _ in range(40)})
    want = counts(spark, rows, "(a|b)*/b")
    monkeypatch.setattr(kernel, "BUCKET_ROWS", 1)
    monkeypatch.setattr(kernel, "HUB", hub)
    assert counts(spark, rows, "(a|b)*/b") == want
    links = search(graph(spark, rows), prepared("(a|b)*/b"), "v", "links")
    assert {n: (d, len(list(g))) for (n, d), g in _grouped(listed(paths(links)))} == want


def _grouped(rows):
    import itertools

    key = lambda r: (r[1], r[2])
    return itertools.groupby(sorted(rows, key=key), key)


def test_levels_of_bucketed_tables_are_not_shuffled(spark, monkeypatch):
    monkeypatch.setattr(kernel, "BUCKET_ROWS", 1)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        g = LabelledGraph.from_edges(graph(spark, [(str(k), "a", str(k + 1)) for k in range(50)]))
        edges = kernel.prepared_edges(g, ["a"])
        frontier = edges.table.select(F.col("src").alias("source"), F.col("src").alias("node"), F.lit(0).alias("state"), F.lit(1).cast("decimal(38,0)").alias("num_paths"))
        plan = edges.after(frontier, spark.createDataFrame([(0, 0, 0)], "state int, label int, next_state int"))._jdf.queryExecution().executedPlan().toString()
        assert "SelectedBucketsCount" in plan
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_counts_raise_when_they_overflow(spark):
    rows = [(f"d{i}", f"l{j}", f"d{i + 1}") for i in range(13) for j in range(1000)]
    g = LabelledGraph.from_edges(graph(spark, rows)).stored()
    with pytest.raises(Exception, match="(?i)overflow|out of range|cannot be represented"):
        answers(search(g, prepared("!(x)*", [f"l{j}" for j in range(1000)]), "d0")).collect()


def test_names_subgraphs_and_saved_searches(spark, tmp_path):
    g = LabelledGraph.from_edges(graph(spark, [("v", "a", "x"), ("x", "b", "y"), ("y", "a", "v"), ("y", "a", "y")]))
    assert {tuple(r) for r in g.labels(["a"]).without_loops().triples().collect()} == {("v", "a", "x"), ("y", "a", "v")}
    some = spark.createDataFrame([("v",), ("x",), ("nowhere",)], "node string")
    assert [tuple(r) for r in g.where_nodes(some).triples().collect()] == [("v", "a", "x")]
    assert {tuple(r) for r in g.reversed().triples().collect()} == {("x", "a", "v"), ("y", "b", "x"), ("v", "a", "y"), ("y", "a", "y")}
    a = prepared("a/b/a")
    found = search(g, a, "v", "links")
    A.save(found, str(tmp_path / "dag"))
    again = A.load(spark, str(tmp_path / "dag"), g, a)
    assert listed(paths(again)) == listed(paths(found)) and len(listed(paths(found))) == 2
    broken = paths(found).withColumn("labels", F.array(F.lit("a"), F.lit("a"), F.lit("a")))
    assert A.invalid_paths(g, a, broken).count() == 2
    assert found.report().count() == len(found.levels)


def test_triples_are_read_and_graphs_written(spark, tmp_path):
    from waypoint.sources import graphs as G

    (tmp_path / "t.nt").write_text('<http://a> <knows> <http://b> .\n# no triple\n<http://b> <name> "B \\"x\\" <y>"@en .\n_:n <knows> <http://a> . # end\nbroken line\n')
    g = G.triples(spark, str(tmp_path / "t.nt"))
    assert {r["label"] for r in g.triples().collect()} == {"knows", "name"} and g.triples().count() == 3
    G.write_graph(g, str(tmp_path / "g"), "json")
    again = G.read_edges(spark, str(tmp_path / "g"), "json")
    assert {tuple(r) for r in again.triples().collect()} == {tuple(r) for r in g.triples().collect()}


def test_near_neighbours_by_cells(spark):
    import numpy as np

    from waypoint.operators.neighbours import nearest

    rng = np.random.default_rng(3)
    x = rng.normal(size=(300, 8))
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(300, None)], "id long, vector array<float>")
    exact = {(r["id"], r["other"]) for r in nearest(df, 4).collect()}
    y = x.astype(np.float32).astype(float)
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    c = y @ y.T
    np.fill_diagonal(c, -2)
    assert exact == {(i, int(j)) for i in range(300) for j in np.argsort(-c[i])[:4]}
    cells = {(r["id"], r["other"]) for r in nearest(df, 4, cells=10, probes=6).collect()}
    assert len(cells & exact) >= 0.9 * len(exact)


def test_overtaken_walks_are_left_out(spark, monkeypatch):
    rows = [(str(x), label, str(y)) for x in range(9) for y in range(9) for label in "ab"]
    sizes, made = [], baselines.counted
    monkeypatch.setattr(baselines, "counted", lambda *how: (sizes.append((out := made(*how))[1]), out)[1])
    g, automaton = LabelledGraph.from_edges(graph(spark, rows)), prepared("a*/b/a")
    few = baselines.walks(g, automaton, "0", 4, "shortest")
    # 8 new nodes by an a and 9 by a b, then 9 * 9 walks to the last state, and none after them
    assert sizes == [17, 81, 0]
    assert listed(baselines.shortest_of(few)) == listed(paths(search(g, automaton, "0", "links"))) == listed(baselines.shortest_of(baselines.walks(g, automaton, "0", 2)))
    rng = random.Random(3)
    for regex in ("(a|b)*/a", "a/b*/a?", "a?"):
        g, automaton = LabelledGraph.from_edges(graph(spark, [(str(rng.randrange(6)), rng.choice("ab"), str(rng.randrange(6))) for _ in range(14)])), prepared(regex)
        assert listed(baselines.shortest_of(baselines.walks(g, automaton, "0", 4, "shortest"))) == listed(baselines.shortest_of(baselines.walks(g, automaton, "0", 4)))


@pytest.fixture
def few_events(spark, tmp_path):
    """Histories by user; nulls are events without a type."""
    histories = {1: ["view", "purchase", "click"], 2: ["purchase", None, "click", "view", "odd"], 3: ["click"], 4: ["purchase", "purchase", "purchase"], 5: [None]}
    rows = [(10 * u + i, f"2024-01-01 00:00:{59 - i:02d}" if u == 4 else "2024-01-01 00:00:00", u, t) for u, ts in histories.items() for i, t in enumerate(ts)]
    spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string").selectExpr("event_id", "cast(ts as timestamp) as ts", "user_id", "event_type").write.parquet(f"{tmp_path}/events.parquet")
    return str(tmp_path), {u: [t for t in ts if t] for u, ts in histories.items()}


def test_costs_of_automata_over_given_events(spark, few_events):
    folder, words = few_events
    got = workloads.QUERIES["cost_automata"](spark, folder)
    assert any("events.parquet" in f for f in got.inputFiles())
    want = [(k, 2 + 4 * (k + 1), 2 ** (k + 1), False, True, True, sum(len(w) > k and w[-1 - k] == "purchase" for w in words.values())) for k in range(1, 7)]
    assert sorted(map(tuple, got.collect())) == want and [x[-1] for x in want] == [2, 1, 1, 0, 0, 0]


def test_moves_of_an_automaton_over_given_events(spark, few_events):
    folder, words = few_events
    got = workloads.QUERIES["udtf_automaton"](spark, folder)
    assert any("events.parquet" in f for f in got.inputFiles())
    seen = {t: (sum(w.count(t) for w in words.values()), sum(t in w for w in words.values())) for t in ("view", "click", "purchase")}
    moves = [(0, "click", 1, False), (0, "view", 0, False), (1, "purchase", 2, True)]
    assert sorted(map(tuple, got.collect())) == [(*m, *seen[m[1]]) for m in moves]
    spark.createDataFrame([], "event_id long, ts timestamp, user_id long, event_type string").write.parquet(f"{folder}/none/events.parquet")
    assert sorted(map(tuple, workloads.QUERIES["udtf_automaton"](spark, f"{folder}/none").collect())) == [(*m, 0, 0) for m in moves]
    none = workloads.QUERIES["cost_automata"](spark, f"{folder}/none").collect()
    assert sorted((r["k"], r["position_states"], r["users"]) for r in none) == [(k, 2 + k + 1, 0) for k in range(1, 7)]
