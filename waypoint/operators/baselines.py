"""What the search is compared with: the product graph made first, walks without a visited set, and walks that repeat no edge or no node."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waypoint.operators.paths import PATH
from waypoint.operators.search import COUNT, as_graph, moves_frame, search, starts
from waypoint.plans.automaton import Automaton
from waypoint.plans.storage import counted, written
from waypoint.sources.graphs import LabelledGraph, Packed

#: Bits of a product node's number that hold the state, and the states that they have room for.
STATE_BITS = 3
MOST_STATES = 1 << STATE_BITS


def materialised_product(graph: LabelledGraph | DataFrame, a: Automaton) -> LabelledGraph:
    """The whole product of graph and automaton as an unlabelled graph, stored: a node's number times MOST_STATES plus the state."""
    if a.n > MOST_STATES:
        raise ValueError(f"the automaton has more than {MOST_STATES} states")
    graph = as_graph(graph)
    edges = graph.edges.join(F.broadcast(moves_frame(graph.edges.sparkSession, a)), "label")
    n = F.lit(MOST_STATES)
    return LabelledGraph(edges.select((F.col("src") * n + F.col("state")).alias("src"), F.lit("any").alias("label"), (F.col("dst") * n + F.col("next_state")).alias("dst")), Packed()).stored("product")


def product_answers(graph: LabelledGraph | DataFrame, a: Automaton, source) -> DataFrame:
    """``source, node, dist, num_paths`` by plain search over the stored product."""
    graph = as_graph(graph)
    product = materialised_product(graph, a)
    seeds = starts(graph, source)
    plain = Automaton(1, frozenset([(0, "any", 0)]), frozenset([0]))
    names = seeds.select((F.col("source") * MOST_STATES).cast("string").alias("source"))
    found = search(product, plain, names)
    ends = found.visited.select(F.shiftright("source", STATE_BITS).alias("source"), F.shiftright("node", STATE_BITS).alias("node"), F.pmod("node", F.lit(MOST_STATES)).alias("state"), "dist", "num_paths")
    if 0 in a.finals:  # a start without product edges is no node of the product
        ends = ends.unionByName(seeds.select("source", F.col("source").alias("node"), F.lit(0).cast("long").alias("state"), F.lit(0).alias("dist"), F.lit(1).cast(COUNT).alias("num_paths"))).distinct()
    ends = ends.filter(F.col("state").isin(sorted(a.finals)) if a.finals else F.lit(False))
    per = ends.groupBy("source", "node", "dist").agg(F.sum("num_paths").cast(COUNT).alias("num_paths"))
    best = per.groupBy("source", "node").agg(F.min(F.struct("dist", "num_paths")).alias("b")).select("source", "node", "b.dist", "b.num_paths")
    return graph.ids.shown(best, ["source", "node"])


def walks(graph: LabelledGraph | DataFrame, a: Automaton, source, longest: int, kind: str = "walk", named: bool = True) -> DataFrame:
    """``source, node, dist, nodes, labels`` of all matching walks of up to ``longest`` edges, without a visited set: brute force, for small graphs.

    ``kind``: ``walk``, ``trail`` (no edge twice), ``simple`` (no node twice) or ``shortest`` (no node and state that a shorter walk has come to:
    what goes on from there goes on from the shorter walk too, so every shortest walk to a node is among those that are left).
    """
    graph = as_graph(graph)
    moves = F.broadcast(moves_frame(graph.edges.sparkSession, a))
    labels = sorted(a.labels)
    used = written(graph.edges.filter(F.col("label").isin(labels)).distinct() if labels else graph.edges.limit(0), "walk-edges")
    here = starts(graph, source).select("source", F.col("source").alias("node"), F.lit(0).alias("state"), F.lit(0).alias("dist"), F.array("source").alias("nodes"), F.array().cast("array<string>").alias("labels"))
    here = written(here, "walks")
    out = here
    keys, seen = ["source", "node", "state"], here.select("source", "node", "state")
    for depth in range(1, longest + 1):
        step = here.join(moves, "state").withColumnRenamed("node", "src").join(used, ["src", "label"])
        if kind == "simple":
            step = step.filter(~F.array_contains("nodes", F.col("dst")))
        elif kind == "trail":
            n = F.size("labels")
            again = F.exists(F.sequence(F.lit(0), n - 1), lambda i: (F.get("nodes", i) == F.col("src")) & (F.get("labels", i) == F.col("label")) & (F.get("nodes", i + 1) == F.col("dst")))
            step = step.filter(~F.when(n > 0, again).otherwise(False))
        elif kind not in ("walk", "shortest"):
            raise ValueError(kind)
        step = step.select("source", F.col("dst").alias("node"), F.col("next_state").alias("state"), F.lit(depth).alias("dist"), F.array_append("nodes", F.col("dst")).alias("nodes"), F.array_append("labels", F.col("label")).alias("labels"))
        if kind == "shortest":
            step = step.join(seen, keys, "left_anti")
        here, n = counted(step, "walks")
        if not n:
            break
        if kind == "shortest" and depth < longest:
            seen = seen.unionByName(written(here.select(*keys).distinct(), "walk-ends"))
        out = out.unionByName(here)
    out = out.filter(F.col("state").isin(sorted(a.finals)) if a.finals else F.lit(False)).select(*PATH)
    return graph.ids.shown(out, ["source", "node", "nodes"]) if named else out


def shortest_of(all_walks: DataFrame) -> DataFrame:
    """Of a table of walks, the shortest to each node."""
    least = all_walks.groupBy("source", "node").agg(F.min("dist").alias("dist"))
    return all_walks.join(least, ["source", "node", "dist"], "left_semi")
