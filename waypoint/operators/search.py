"""Level-by-level search over the product of a labelled graph and an automaton, which is never materialised.

The edges that the automaton can use are written once: label codes in place of labels, repeats dropped, and above BUCKET_ROWS
rows bucketed by (src, label, salt), so that no level reads the tables behind the graph or shuffles the edges. The edges of a node with more than HUB
of them are dealt to SALTS salts by their other end, and a frontier row at such a node is sent to each salt.

A level joins the frontier with the automaton's moves (a broadcast of a few rows) and with the edges, drops
product nodes seen on earlier levels by an anti-join on (source, node, state) against tables bucketed by these columns, and keeps the rest in one of three ways: all
links (all shortest paths), the least link (one shortest path), or a sum (their number). The anti-join looks at
earlier levels alone, so each link of the new level counts once, and counts are whole before their level expands. A level is one written
table, and its row count comes out of the same job.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from waypoint.plans.automaton import Automaton, single_final
from waypoint.plans.storage import Buckets, counted, written
from waypoint.sources.graphs import LabelledGraph

KEYS = ["source", "node", "state"]
COUNT = "decimal(38,0)"
#: Edges from which on tables are bucketed; smaller ones are cheaper to shuffle or to broadcast.
BUCKET_ROWS = 8_000_000
#: A (node, label) of more edges is salted.
HUB = 1_000_000
SALTS = 64


@dataclass
class Search:
    graph: LabelledGraph
    visited: DataFrame  # source, node, state, dist, num_paths
    links: DataFrame | None  # source, node, state, pred, pred_state, label, dist
    finals: frozenset
    empty: bool  # the empty word is an answer that the automaton has peeled off
    levels: list[dict] = field(default_factory=list)  # for each level: rows visited, links kept, seconds
    automaton: Automaton | None = None

    def ends(self) -> DataFrame:
        """The product nodes that answer."""
        return self.visited.filter(accepting(self.finals, self.empty))

    def report(self) -> DataFrame:
        """A row a level: the measures of the search."""
        rows = [(x["level"], x["visited"], x["links"], float(x["seconds"])) for x in self.levels]
        return self.visited.sparkSession.createDataFrame(rows, "level int, visited long, links long, seconds double")


def accepting(finals: frozenset, empty: bool) -> Column:
    at_final = F.col("state").isin(sorted(finals)) if finals else F.lit(False)
    return at_final | (F.col("dist") == 0) if empty else at_final


def moves_frame(spark: SparkSession, a: Automaton) -> DataFrame:
    """The automaton's moves as a table."""
    return spark.createDataFrame(sorted(a.moves), "state int, label string, next_state int")


def as_graph(graph: LabelledGraph | DataFrame) -> LabelledGraph:
    return LabelledGraph.from_edges(graph) if isinstance(graph, DataFrame) else graph


@dataclass
class Edges:
    """The edges of some labels, written; ``label`` is the label's place in ``labels``."""

    table: DataFrame  # src, label, dst and salt
    labels: list[str]
    hubs: DataFrame | None  # src, label
    rows: int
    buckets: int

    def after(self, frontier: DataFrame, moves: DataFrame) -> DataFrame:
        """``source, node, state, pred, pred_state, label, num_paths``: every product edge that leaves the frontier."""
        step = frontier.join(F.broadcast(moves), "state").withColumnRenamed("node", "src")
        if self.hubs is None:
            step = step.withColumn("salt", F.lit(0))
        else:
            step = step.join(F.broadcast(self.hubs.withColumn("hub", F.lit(True))), ["src", "label"], "left")
            step = step.withColumn("salt", F.explode(F.when(F.col("hub"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0))))).drop("hub")
        keys = ["src", "label", "salt"] if self.hubs is not None else ["src", "label"]
        step = step.join(self.table.drop("salt") if self.hubs is None else self.table, keys)
        return step.select("source", F.col("dst").alias("node"), F.col("next_state").alias("state"), F.col("src").alias("pred"), F.col("state").alias("pred_state"), "label", "num_paths")


def prepared_edges(graph: LabelledGraph, labels: list[str]) -> Edges:
    spark = graph.edges.sparkSession
    code = (F.array_position(F.array(*[F.lit(x) for x in labels]), F.col("label")) - 1).cast("int") if labels else F.lit(0)
    used = graph.edges.filter(F.col("label").isin(labels)) if labels else graph.edges.limit(0)
    table, rows = counted(used.select("src", code.alias("label"), "dst").distinct(), "edges")
    hubs = None
    if rows > HUB:
        hubs, n_hubs = counted(table.groupBy("src", "label").count().filter(F.col("count") > HUB).select("src", "label"), "hubs")  # at most rows / HUB
        hubs = hubs if n_hubs else None
    if hubs is not None:
        salted = table.join(F.broadcast(hubs.withColumn("hub", F.lit(True))), ["src", "label"], "left")
        table = salted.withColumn("salt", F.when(F.col("hub"), F.pmod(F.xxhash64("dst"), F.lit(SALTS)).cast("int")).otherwise(0)).drop("hub")
        if rows <= BUCKET_ROWS:
            table = written(table, "edges")
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions")) if rows > BUCKET_ROWS else 0
    if buckets:
        keys = ["src", "label", "salt"] if hubs is not None else ["src", "label"]
        table = Buckets(spark, "edges", keys, buckets).add(table.repartition(buckets, *keys))[0]
    return Edges(table, labels, hubs, rows, buckets)


def starts(graph: LabelledGraph, source) -> DataFrame:
    """``source`` rows that are nodes of the graph: a name, a list of names, a DataFrame of one column of names, or None for all nodes."""
    spark = graph.edges.sparkSession
    if source is None:
        return graph.nodes().withColumnRenamed("node", "source")
    few = not isinstance(source, DataFrame)
    if few:
        source = spark.createDataFrame([(s,) for s in ([source] if isinstance(source, str) else source)], "source string")
    wanted = graph.ids.numbered(source.toDF("source").distinct(), "source")
    if few:  # names written in the query: the edges are scanned for them, nothing is shuffled
        ids = [r[0] for r in wanted.collect()]
        both = graph.edges.filter(F.col("src").isin(ids) | F.col("dst").isin(ids)) if ids else graph.edges.limit(0)
        return both.select(F.explode(F.array("src", "dst")).alias("source")).filter(F.col("source").isin(ids) if ids else F.lit(False)).distinct()
    return wanted.join(graph.nodes().withColumnRenamed("node", "source"), "source", "left_semi")


def levels(graph: LabelledGraph | DataFrame, a: Automaton, source, keep: str = "count", max_depth: int | None = None, targets: list[str] | None = None, finals: str = "dictionary", resume: tuple[DataFrame, int] | None = None) -> Iterator[Search]:
    """The search as far as it came, after each level; see :func:`search`. ``resume``: visited rows and the level they are whole up to."""
    graph = as_graph(graph)
    spark, empty = graph.edges.sparkSession, False
    if finals == "normalise":
        a, empty = single_final(a)
    labels = sorted(a.labels)
    edges = prepared_edges(graph, labels)
    code = {x: i for i, x in enumerate(labels)}
    moves = spark.createDataFrame([(s, code[x], t) for s, x, t in sorted(a.moves)], "state int, label int, next_state int")
    seeds = starts(graph, source) if resume is None else None
    if source is None and resume is None and not empty and 0 not in a.finals:  # only nodes with a first edge lead anywhere
        seeds = edges.table.join(F.broadcast(moves.filter("state = 0").select("label").distinct()), "label", "left_semi").select(F.col("src").alias("source")).distinct()
    known = Buckets(spark, "visited", KEYS, edges.buckets)
    began = time.time()
    depth = 0
    if resume is None:
        frontier, n = known.add(seeds.select("source", F.col("source").alias("node"), F.lit(0).alias("state"), F.lit(0).alias("dist"), F.lit(1).cast(COUNT).alias("num_paths")))
    else:
        visited, depth = resume
        known.add(visited.filter(F.col("dist") < depth))
        frontier, n = known.add(visited.filter(F.col("dist") == depth))
    said = [{"level": depth, "visited": n, "links": 0, "seconds": time.time() - began}]
    kept_links: list[DataFrame] = []
    names = F.array(*[F.lit(x) for x in labels]) if labels else F.array().cast("array<string>")
    wanted = answered = None
    if targets is not None:
        wanted = graph.ids.numbered(spark.createDataFrame([(t,) for t in set(targets)], "node string"), "node")
        wanted = written(wanted, "targets")

    def so_far() -> Search:
        visited = known.all() if known.parts else frontier
        links = None
        if keep in ("links", "one"):
            links = reduce(DataFrame.unionByName, kept_links).withColumn("label", F.get(names, F.col("label"))) if kept_links else spark.createDataFrame([], "source long, node long, state int, pred long, pred_state int, label string, dist int")
        return Search(graph, visited, links, a.finals, empty, said, a)

    yield so_far()
    open_rows = n
    while open_rows and (max_depth is None or depth < max_depth):
        if wanted is not None:
            # a source is done with when all targets are answered for it; the others go on
            hit = frontier.filter(accepting(a.finals, empty)).join(F.broadcast(wanted), "node", "left_semi").select("source", "node")
            answered, _ = counted((hit if answered is None else answered.unionByName(hit)).distinct(), "answered")
            n_targets = wanted.count()
            done = answered.groupBy("source").agg(F.count("*").alias("n")).filter(F.col("n") >= n_targets).select("source")
            frontier, open_rows = counted(frontier.join(done, "source", "left_anti"), "open")
            if not open_rows or not n_targets:
                break
        depth += 1
        began = time.time()
        step = edges.after(frontier, moves)
        new_keys = known.all(KEYS)
        if keep == "count":
            level, n_links = step.groupBy(*KEYS).agg(F.lit(depth).alias("dist"), F.sum("num_paths").cast(COUNT).alias("num_paths")).join(new_keys, KEYS, "left_anti"), 0
        elif keep == "ends":
            level, n_links = step.select(*KEYS).distinct().join(new_keys, KEYS, "left_anti").select(*KEYS, F.lit(depth).alias("dist"), F.lit(1).cast(COUNT).alias("num_paths")), 0
        else:
            if keep == "one":
                best = step.groupBy(*KEYS).agg(F.min(F.struct("pred", "pred_state", "label")).alias("p"))
                found = best.join(new_keys, KEYS, "left_anti").select(*KEYS, "p.pred", "p.pred_state", "p.label", F.lit(depth).alias("dist"))
            else:
                found = step.drop("num_paths").join(new_keys, KEYS, "left_anti").select(*KEYS, "pred", "pred_state", "label", F.lit(depth).alias("dist"))
            found, n_links = counted(found, "links")
            if n_links:
                kept_links.append(found)
            level = found.select(*KEYS, "dist", F.lit(1).cast(COUNT).alias("num_paths"))
            level = level if keep == "one" else level.distinct()
        frontier, open_rows = known.add(level)
        said.append({"level": depth, "visited": open_rows, "links": n_links, "seconds": time.time() - began})
        yield so_far()


def search(graph: LabelledGraph | DataFrame, a: Automaton, source, keep: str = "count", max_depth: int | None = None, targets: list[str] | None = None, finals: str = "dictionary", resume: tuple[DataFrame, int] | None = None) -> Search:
    """``keep``: ``count``, ``links``, ``one`` or ``ends``. With ``targets`` a source is done with when all of them are answered for it.

    ``finals``: ``dictionary`` keeps the least distance of several final states, ``normalise`` runs on an automaton of one final state with
    the empty word peeled off. Decimal counts raise when they overflow.
    """
    found = None
    for found in levels(graph, a, source, keep, max_depth, targets, finals, resume):
        pass
    return found


def answers(found: Search, checked: bool = True, named: bool = True) -> DataFrame:
    """``source, node, dist, num_paths``: the least distance over the final states, and the paths of that length.

    ``checked=False`` is the ablation without the distance dictionary: each final state answers for itself.
    """
    ends = found.ends()
    if not checked:
        best = ends.select("source", "node", "dist", "num_paths")
    else:
        per = ends.groupBy("source", "node", "dist").agg(F.sum("num_paths").cast(COUNT).alias("num_paths"))
        best = per.groupBy("source", "node").agg(F.min(F.struct("dist", "num_paths")).alias("b")).select("source", "node", "b.dist", "b.num_paths")
    return found.graph.ids.shown(best, ["source", "node"]) if named else best


def examined(graph: LabelledGraph | DataFrame, found: Search) -> DataFrame:
    """``level, visited, examined``: product nodes first seen at each level and the product edges that leave them."""
    graph = as_graph(graph)
    spark = graph.edges.sparkSession
    moves = F.broadcast(moves_frame(spark, found.automaton))
    labels = sorted(found.automaton.labels)
    used = graph.edges.filter(F.col("label").isin(labels)).distinct() if labels else graph.edges.limit(0)
    degree = used.groupBy(F.col("src").alias("node"), "label").agg(F.count("*").alias("edges"))
    out = found.visited.join(moves, "state").join(degree, ["node", "label"]).groupBy("dist").agg(F.sum("edges").alias("examined"))
    seen = found.visited.groupBy("dist").agg(F.count("*").alias("visited"))
    return seen.join(out, "dist", "left").select(F.col("dist").alias("level"), "visited", F.coalesce("examined", F.lit(0)).cast("long").alias("examined"))
