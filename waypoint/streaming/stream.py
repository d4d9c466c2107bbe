"""Path queries over streams of edges, of events and of query sources.

Late rows: windowed operators drop what comes behind the watermark; :func:`late_rows` reads their number from a query's progress. Times must be
``timestamp`` (watermarks refuse times without a zone), see :func:`events_stream`.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from waypoint.operators.search import Search, answers, search
from waypoint.plans.automaton import Automaton
from waypoint.plans.storage import counted, shared_folder, written
from waypoint.sources.graphs import LabelledGraph


#: Where it is on, rows are late by the watermark of the batch before, so that a row behind the present one is still counted in.
TWO_WATERMARKS = "spark.sql.streaming.statefulOperator.allowMultiple"


def events_stream(spark: SparkSession, sf_dir: str, files: str = "events.parquet", one_batch_files: int = 1) -> DataFrame:
    """The events table as a file stream (all files of the folder that are named so), with ``ts`` as a timestamp."""
    folder = sf_dir.rstrip("/")
    schema = spark.read.parquet(f"{folder}/{files}").schema if "*" not in files else spark.read.option("pathGlobFilter", files).parquet(folder).schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", files).option("maxFilesPerTrigger", one_batch_files).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def event_edges(events: DataFrame) -> DataFrame:
    """``ts, src, label, dst``: from a user to the key of each of the user's events, under the event's type."""
    key = F.get_json_object("props", "$.k")
    return events.select("ts", F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("src"), F.col("event_type").alias("label"), F.concat(F.lit("k:"), key).alias("dst"))


class Sink:
    """A folder that batches are appended to, one part a batch: a batch that is run again replaces its own part."""

    def __init__(self, spark: SparkSession, name: str, schema: str):
        self.spark, self.schema, self.path = spark, schema, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        spark.createDataFrame([], schema).write.parquet(f"{self.path}/batch=-1")

    def put(self, df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.path}/batch={batch}")

    def table(self) -> DataFrame:
        return self.spark.read.schema(f"{self.schema}, batch int").option("basePath", self.path).parquet(self.path).drop("batch")


def drained(query) -> dict:
    """Waits for a query over what is there; its last progress."""
    query.awaitTermination()
    return query.lastProgress


def late_rows(query) -> int:
    """Rows that came behind the watermark, over all batches."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])


def _start(df: DataFrame, sink: Sink, each, mode: str = "append"):
    spark = df.sparkSession
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}").foreachBatch(lambda batch, n: each(batch, n))
    was = spark.conf.get(TWO_WATERMARKS, None)
    spark.conf.set(TWO_WATERMARKS, "false")  # the query takes over what is set when it starts
    try:
        return writer.start()
    except AnalysisException:  # a stream that holds state of its own before needs both watermarks
        spark.conf.set(TWO_WATERMARKS, "true")
        return writer.start()
    finally:
        spark.conf.unset(TWO_WATERMARKS) if was is None else spark.conf.set(TWO_WATERMARKS, was)


def windowed_rpq(edges: DataFrame, a: Automaton, source: str, width: str, slide: str | None = None, late: str = "0 seconds"):
    """Answers of ``source`` in the snapshot graph of each window that has closed: ``begins, node, dist, num_paths``; the query and its sink.

    ``edges``: ts, src, label, dst. All windows closed in a batch are searched at once, as parts of one graph whose nodes carry their window.
    """
    spark = edges.sparkSession
    sink = Sink(spark, "windows", "begins timestamp, node string, dist int, num_paths long")
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    closed = edges.withWatermark("ts", late).groupBy(window.alias("w"), "src", "label", "dst").agg(F.count("*").alias("n"))

    def each(batch: DataFrame, number: int) -> None:
        sink.put(_by_window(batch.select(F.col("w.start").alias("begins"), "src", "label", "dst"), a, source), number)

    return _start(closed, sink, each), sink


def _by_window(rows: DataFrame, a: Automaton, source: str) -> DataFrame:
    """A search in all snapshots at once; each has its own copy of the source."""
    rows = written(rows, "closed")
    name = lambda c: F.concat_ws("|", F.unix_micros("begins").cast("string"), c)
    both = rows.unionByName(rows.select("begins", F.col("dst").alias("src"), F.concat(F.lit("^"), "label").alias("label"), F.col("src").alias("dst")))
    graph = LabelledGraph.from_edges(both.select(name(F.col("src")).alias("src"), "label", name(F.col("dst")).alias("dst")))
    sources = rows.select(name(F.lit(source)).alias("source")).distinct()
    found = answers(search(graph, a, sources))
    at = F.split("node", r"\|", 2)
    return found.select(F.timestamp_micros(F.get(at, F.lit(0)).cast("long")).alias("begins"), F.get(at, F.lit(1)).alias("node"), "dist", F.col("num_paths").cast("long").alias("num_paths"))


def session_rpq(events: DataFrame, a: Automaton, gap: str, late: str = "0 seconds"):
    """Sessions (by user, closed after ``gap``) whose sequence of event types is a word of the automaton: ``user_id, begins, events``; the query and its sink."""
    from waypoint.functions.words import matches_word

    spark = events.sparkSession
    sink = Sink(spark, "sessions", "user_id long, begins timestamp, events long")
    word = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"])
    closed = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(word.alias("word"))
    good = closed.filter(matches_word(F.col("word"), a)).select("user_id", F.col("w.start").alias("begins"), F.size("word").cast("long").alias("events"))
    return _start(good, sink, sink.put), sink


def chain_matcher(events: DataFrame, a: Automaton):
    """Each user's growing chain of event types stepped through a deterministic automaton: after every batch ``user_id, events, accepted, state`` of the users
    it touched; the query and its sink. State is two counts and the automaton's state a user; ``accepted`` counts the prefixes that are words (state -1: none longer can be).

    Batches must bring a user's events in order of time; within a batch they are put in order.
    """
    if not a.is_deterministic():
        raise ValueError("a deterministic automaton is needed")
    spark = events.sparkSession
    step, finals = {(s, x): t for s, x, t in a.moves}, set(a.finals)
    schema = "user_id long, events long, accepted long, state int"

    def run(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, accepted, at = state.get if state.exists else (0, 0, 0)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for label in rows["event_type"]:
            n += 1
            at = step.get((at, label), -1) if at >= 0 else -1
            accepted += at in finals
        state.update((n, accepted, at))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "accepted": [accepted], "state": [at]})

    out = events.select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(run, schema, "n long, accepted long, at int", "update", GroupStateTimeout.NoTimeout)
    sink = Sink(spark, "chains", schema)
    return _start(out, sink, sink.put, "update"), sink


def latest(table: DataFrame) -> DataFrame:
    """The newest row of each user, the one of most events."""
    return table.groupBy("user_id").agg(F.max(F.struct("events", "accepted", "state")).alias("x")).select("user_id", "x.events", "x.accepted", "x.state")


class Maintained:
    """Answers with counts that are kept up while edges are inserted.

    A new edge leaves product nodes known at some least distance L. Nothing at a distance of L or less can change, so the visited rows up to L stay
    and the search goes on from there; a batch whose edges leave no known product node changes nothing.
    """

    def __init__(self, graph: LabelledGraph, a: Automaton, source):
        self.graph, self.automaton, self.source = graph.stored(), a, source
        self.found: Search = search(self.graph, a, source)

    def insert(self, edges: DataFrame) -> int | None:
        """``edges`` (src, label, dst; numbers of the graph's naming); the level that the search went on from."""
        spark = edges.sparkSession
        new, n = counted(edges.select("src", "label", "dst").distinct().join(self.graph.edges, ["src", "label", "dst"], "left_anti"), "inserted")
        if not n:
            return None
        self.graph = self.graph._with(self.graph.edges.unionByName(new))
        moves = spark.createDataFrame(sorted(self.automaton.moves), "state int, label string, next_state int")
        # a source that was no node may have become one
        if self.found.visited.isEmpty():
            self.found = search(self.graph, self.automaton, self.source)
            return 0
        touched = self.found.visited.join(F.broadcast(moves), "state").join(new.select(F.col("src").alias("node"), "label"), ["node", "label"], "left_semi")
        level = touched.agg(F.min("dist")).first()[0]
        if level is not None:
            self.found = search(self.graph, self.automaton, self.source, resume=(self.found.visited.filter(F.col("dist") <= level), level))
        return level

    def answers(self) -> DataFrame:
        return answers(self.found)


def maintain_counts(stream: DataFrame, graph: LabelledGraph, a: Automaton, source):
    """``stream`` (src, label, dst) inserted batch by batch; the query and the maintained answers."""
    kept = Maintained(graph, a, source)

    def each(batch: DataFrame, number: int) -> None:
        kept.insert(batch)

    spark = stream.sparkSession
    query = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}").foreachBatch(each).start()
    return query, kept


def source_stream(sources: DataFrame, graph: LabelledGraph, a: Automaton, keep: str = "count"):
    """A stream of names, one column, each searched for on the same stored graph: ``source, node, dist, num_paths``; the query and its sink."""
    spark, graph = sources.sparkSession, graph.stored()
    sink = Sink(spark, "asked", "source string, node string, dist int, num_paths long")

    def each(batch: DataFrame, number: int) -> None:
        asked = written(batch.toDF("source").distinct(), "asked")
        sink.put(answers(search(graph, a, asked, keep)).withColumn("num_paths", F.col("num_paths").cast("long")), number)

    return _start(sources, sink, each), sink


def unrepeated(edges: DataFrame, late: str) -> DataFrame:
    """A stream of ``ts, src, label, dst`` without repeats that come within the time allowed for late rows."""
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "label", "dst"])
