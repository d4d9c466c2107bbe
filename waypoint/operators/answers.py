"""Operators on answers, paths and stored searches: set operations, top lists, profiles, validation, saving."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from waypoint.functions.words import matches_word
from waypoint.operators.search import Search, answers, as_graph
from waypoint.plans.automaton import Automaton
from waypoint.sources.graphs import LabelledGraph


def answers_union(a: DataFrame, b: DataFrame) -> DataFrame:
    """Pairs (source, node) that answer either query."""
    return a.select("source", "node").union(b.select("source", "node")).distinct()


def answers_intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("source", "node").intersect(b.select("source", "node"))


def answers_except(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("source", "node").subtract(b.select("source", "node"))


def nearest_answers(ans: DataFrame, k: int) -> DataFrame:
    """The ``k`` nearest answers of each source, ties by name."""
    order = Window.partitionBy("source").orderBy("dist", "node")
    return ans.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k)


def first_answers(ans: DataFrame, n: int) -> DataFrame:
    """The ``n`` nearest answers of all."""
    return ans.orderBy("dist", "source", "node").limit(n)


def distance_profile(ans: DataFrame) -> DataFrame:
    """Answers, paths and the largest number of paths by distance."""
    return ans.groupBy("dist").agg(F.count("*").alias("answers"), F.sum("num_paths").cast("long").alias("paths"), F.max("num_paths").cast("long").alias("most"))


def profile_rollup(ans: DataFrame) -> DataFrame:
    """Answers by kind of node (its name up to the colon) and distance, with subtotals; null stands for all."""
    return ans.rollup(F.regexp_extract("node", "^([^:]*):", 1).alias("kind"), "dist").agg(F.count("*").alias("answers"), F.sum("num_paths").cast("long").alias("paths"))


def output_size(ans: DataFrame) -> DataFrame:
    """``answers, paths, symbols``: the number of all shortest paths and of their nodes, without listing them; and the largest count and distance."""
    n = F.coalesce(F.sum("num_paths"), F.lit(0))
    symbols = F.coalesce(F.sum(F.col("num_paths") * (F.col("dist") + 1)), F.lit(0))
    return ans.agg(F.count("*").alias("answers"), n.cast("long").alias("paths"), symbols.cast("long").alias("symbols"), F.max("num_paths").cast("long").alias("most"), F.max("dist").alias("farthest"))


def invalid_paths(graph: LabelledGraph | DataFrame, a: Automaton, given: DataFrame, found: Search | None = None) -> DataFrame:
    """The rows of ``given`` (source, node, dist, nodes, labels; by name) that are no matching path of the graph from source to node, with ``why``; with ``found``, also those that are not shortest."""
    graph = as_graph(graph)
    ends = (F.get("nodes", F.lit(0)) != F.col("source")) | (F.element_at("nodes", -1) != F.col("node"))
    sizes = (F.size("nodes") != F.size("labels") + 1) | (F.size("labels") != F.col("dist"))
    rows = given.withColumn("_id", F.xxhash64("source", "node", "nodes", "labels"))
    bad = rows.withColumn("why", F.when(sizes, "sizes").when(ends, "ends").when(~matches_word(F.col("labels"), a), "word"))
    steps = rows.filter(F.size("labels") > 0).select("_id", F.explode(F.arrays_zip(F.slice("nodes", F.lit(1), F.size("labels")).alias("src"), F.col("labels").alias("label"), F.expr("slice(nodes, 2, size(labels))").alias("dst"))).alias("s"))
    missing = steps.select("_id", "s.src", "s.label", "s.dst").join(graph.triples(), ["src", "label", "dst"], "left_anti").select("_id").distinct().withColumn("_edge", F.lit("edge"))
    bad = bad.join(missing, "_id", "left").withColumn("why", F.coalesce("why", "_edge")).drop("_edge")
    if found is not None:
        best = answers(found).select("source", "node", F.col("dist").alias("_best"))
        bad = bad.join(best, ["source", "node"], "left").withColumn("why", F.coalesce("why", F.when(F.col("_best").isNull() | (F.col("_best") != F.col("dist")), "length"))).drop("_best")
    return bad.filter("why is not null").drop("_id")


def label_counts(given: DataFrame) -> DataFrame:
    """How often each label stands at each place of the paths."""
    return given.select(F.posexplode("labels").alias("place", "label")).groupBy("place", "label").agg(F.count("*").alias("paths"))


def save(found: Search, path: str) -> None:
    """A search's tables, visited nodes and links by distance, and its answers."""
    found.visited.write.partitionBy("dist").parquet(f"{path}/visited")
    if found.links is not None:
        found.links.write.partitionBy("dist").parquet(f"{path}/links")
    answers(found, named=False).write.parquet(f"{path}/answers")


def load(spark: SparkSession, path: str, graph: LabelledGraph, a: Automaton, with_links: bool = True) -> Search:
    """A saved search; ``graph`` names its nodes."""
    visited = spark.read.parquet(f"{path}/visited")
    links = spark.read.parquet(f"{path}/links") if with_links else None
    depths = [r[0] for r in visited.select("dist").distinct().orderBy("dist").collect()]  # one row a level
    return Search(graph, visited, links, a.finals, False, [{"level": d, "visited": 0, "links": int(d > 0), "seconds": 0.0} for d in depths], a)


def kind_of(node: Column) -> Column:
    return F.regexp_extract(node, "^([^:]*):", 1)
