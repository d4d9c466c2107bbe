import datetime as dt
import os

from pyspark.sql import functions as F

from waypoint.functions.query import PathQuery, run_path_query
from waypoint.functions.words import matches_word
from waypoint.operators.search import answers, search
from waypoint.plans.automaton import determinised, measured, prepared
from waypoint.sources.graphs import LabelledGraph
from waypoint.streaming import stream as T

EDGE = "ts timestamp, src string, label string, dst string"


def files(spark, tmp_path, batches, schema):
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / f"in{k}"))
    out = tmp_path / "in"
    out.mkdir()
    for k in range(len(batches)):
        for f in (tmp_path / f"in{k}").glob("*.parquet"):
            f.rename(out / f"{k}-{f.name}")
            os.utime(out / f"{k}-{f.name}", (1_700_000_000 + 60 * k,) * 2)  # files come in order of time
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(out))


def at(minute):
    return dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minute)


def test_windows_close_and_late_rows_are_counted(spark, tmp_path):
    stream = files(spark, tmp_path, [[(at(1), "v", "a", "x"), (at(2), "x", "a", "y")], [(at(75), "v", "a", "z")], [(at(3), "v", "a", "late"), (at(140), "v", "a", "open")]], EDGE)
    query, sink = T.windowed_rpq(stream, prepared("a+"), "v", "1 hour")
    T.drained(query)
    got = {(r["begins"], r["node"], r["dist"]) for r in sink.table().collect()}
    assert got == {(at(0), "x", 1), (at(0), "y", 2), (at(60), "z", 1)}
    assert T.late_rows(query) == 1


def test_sliding_windows_hold_an_edge_more_than_once(spark, tmp_path):
    stream = files(spark, tmp_path, [[(at(40), "v", "a", "x")], [(at(300), "q", "a", "q")]], EDGE)
    query, sink = T.windowed_rpq(stream, prepared("a"), "v", "1 hour", "30 minutes")
    T.drained(query)
    assert {(r["begins"], r["node"]) for r in sink.table().collect()} == {(at(0), "x"), (at(30), "x")}


def test_chains_step_over_batches(spark, tmp_path):
    schema = "user_id long, ts timestamp, event_id long, event_type string"
    stream = files(spark, tmp_path, [[(1, at(1), 1, "a"), (1, at(2), 2, "b"), (2, at(1), 3, "b")], [(1, at(5), 4, "a"), (2, at(4), 5, "a")]], schema)
    query, sink = T.chain_matcher(stream, prepared("(a/b)*/a"))
    T.drained(query)
    got = {r["user_id"]: (r["events"], r["accepted"]) for r in T.latest(sink.table()).collect()}
    assert got == {1: (3, 2), 2: (2, 0)}


def test_inserted_edges_are_searched_from_the_lowest_level_that_changes(spark):
    rows = [("v", "a", "x"), ("x", "a", "y"), ("y", "a", "z"), ("q", "a", "r"), ("w", "b", "z"), ("v", "b", "w"), ("x", "b", "z")]
    g = LabelledGraph.from_edges(spark.createDataFrame(rows, "src string, label string, dst string"))
    a = prepared("(a|b)*")
    kept = T.Maintained(g.labels(["a"]), a, "v")
    assert kept.insert(g.edges.filter("label = 'b'")) == 0
    want = sorted(tuple(r) for r in answers(search(g, a, "v")).collect())
    assert sorted(tuple(r) for r in kept.answers().collect()) == want
    assert kept.insert(g.edges) is None


def test_repeats_within_the_time_for_late_rows_go(spark, tmp_path):
    stream = files(spark, tmp_path, [[(at(1), "v", "a", "x"), (at(2), "v", "a", "x")], [(at(3), "v", "a", "x")]], EDGE)
    query = T.unrepeated(stream, "1 hour").writeStream.format("memory").queryName("unrepeated").trigger(availableNow=True).start()
    query.awaitTermination()
    assert spark.table("unrepeated").count() == 1


def test_text_queries(spark):
    assert PathQuery.parsed("all  shortest ( c:1 , a/(b|c)* , ?x )") == PathQuery("all shortest", "c:1", "a/(b|c)*", None)
    g = LabelledGraph.from_edges(spark.createDataFrame([("v", "a", "x"), ("x", "b", "y"), ("w", "a", "x")], "src string, label string, dst string"))
    got = sorted(tuple(r) for r in run_path_query(spark, g, "ALL SHORTEST (?s, a/b, y)").collect())
    assert got == [("v", "y", 2, "v/a/x/b/y"), ("w", "y", 2, "w/a/x/b/y")]
    assert [tuple(r) for r in run_path_query(spark, g, "COUNT SHORTEST (v, a/^a, w)").collect()] == [("v", "w", 2, 1)]
    assert sorted(r["node"] for r in run_path_query(spark, g, "ENDPOINTS (v, .*, ?x)").collect()) == ["v", "x", "y"]


def test_words(spark):
    df = spark.createDataFrame([([],), (["a"],), (["a", "b"],), (["b"],), (["c"],)], "w array<string>")
    got = [r[0] for r in df.select(matches_word(F.col("w"), "a/b?")).collect()]
    assert got == [False, True, True, False, False]
    a = determinised(prepared("(a|b)*/a/(a|b)"))
    assert [r[0] for r in df.select(matches_word(F.col("w"), a)).collect()] == [a.accepts(w) for w in ([], ["a"], ["a", "b"], ["b"], ["c"])]
    assert {k: n for k, n, *_ in measured("(a|b)*/a/(a|b)")}["minimal"] == 4


def test_windows_over_a_stream_with_state_of_its_own(spark, tmp_path):
    stream = files(spark, tmp_path, [[(at(1), "v", "a", "x"), (at(1), "v", "a", "x")], [(at(200), "v", "a", "z")]], EDGE)
    query, sink = T.windowed_rpq(T.unrepeated(stream, "0 seconds"), prepared("a"), "v", "1 hour")
    T.drained(query)
    assert {(r["begins"], r["node"]) for r in sink.table().collect()} == {(at(0), "x")}
    assert spark.conf.get(T.TWO_WATERMARKS, "true") == "true"
