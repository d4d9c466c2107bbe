"""Shortest paths out of a search's links: all of them after the search, level by level or link by link while it runs, one by rank, a
bounded number an answer, or one after another from a task.

Every link leads back to the source, so no partial path is a dead end and the work follows the output.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from waypoint.operators.search import COUNT, Search, answers, levels
from waypoint.plans.storage import counted, written

PATH = ["source", "node", "dist", "nodes", "labels"]


def _ends(found: Search, only: DataFrame | None) -> DataFrame:
    """``source, node, dist, state`` of the answers; of the final states that answer at the least distance, the smallest one where one path is asked for."""
    least = answers(found, named=False).select("source", "node", "dist")
    if only is not None:
        least = least.join(found.graph.ids.numbered(only.toDF("node"), "node"), "node", "left_semi")
    return found.ends().join(least, ["source", "node", "dist"]).select("source", "node", "dist", "state")


def unrolled(found: Search, ends: DataFrame, named: bool = True, with_state: bool = False) -> DataFrame:
    """``source, node, dist, nodes, labels`` of all paths to ``ends``, walked back a level at a time.

    The paths of length d + 1 reach their d-th level in the same join as those of length d reach theirs, so each join reads the links of one level alone, from
    the deepest answer on.
    """
    part, n = counted(ends.select("source", "node", "state", "dist", F.col("node").alias("at"), F.col("state").alias("at_state"), F.array("node").alias("nodes"), F.array().cast("array<string>").alias("labels")), "ends")
    links = found.links.select("source", F.col("node").alias("at"), F.col("state").alias("at_state"), "pred", "pred_state", "label", F.col("dist").alias("level"))
    waiting = part.filter("dist > 0")
    done = part.filter("dist = 0")
    deepest = waiting.agg(F.max("dist")).first()[0] if n else None
    moving = None
    for level in range(deepest or 0, 0, -1):
        here = waiting.filter(F.col("dist") == level)
        here = here if moving is None else here.unionByName(moving)
        step = here.join(links.filter(F.col("level") == level).drop("level"), ["source", "at", "at_state"])
        step = step.select("source", "node", "state", "dist", F.col("pred").alias("at"), F.col("pred_state").alias("at_state"), F.array_prepend("nodes", F.col("pred")).alias("nodes"), F.array_prepend("labels", F.col("label")).alias("labels"))
        moving = written(step, "paths")
    out = (done if moving is None else done.unionByName(moving)).select(*PATH, *["state"] * with_state)
    return found.graph.ids.shown(out, ["source", "node", "nodes"]) if named else out


def paths(found: Search, only: DataFrame | None = None, named: bool = True) -> DataFrame:
    """Every path of the links table that ends in an answer (of ``only``, one column of names)."""
    return unrolled(found, _ends(found, only), named)


def single_paths(found: Search, only: DataFrame | None = None, named: bool = True) -> DataFrame:
    """One shortest path an answer: from a search that kept one link a product node, of the smallest final state at the least distance."""
    one = _ends(found, only).groupBy("source", "node", "dist").agg(F.min("state").alias("state"))
    return unrolled(found, one, named)


def paths_by_level(graph, a, source, **how) -> Iterator[DataFrame]:
    """The paths of each level's new answers as soon as the level is whole, grouped by node; a table a level."""
    answered = None
    for found in levels(graph, a, source, "links", **how):
        depth = found.levels[-1]["level"]
        new = found.ends().filter(F.col("dist") == depth).select("source", "node", "dist", "state")
        if answered is not None:
            new = new.join(answered, ["source", "node"], "left_anti")
        new, n = counted(new, "answers")
        if n:
            yield unrolled(found, new)
            pairs = new.select("source", "node").distinct()
            answered = written(pairs if answered is None else answered.unionByName(pairs), "answered")


def paths_by_visit(graph, a, source, parts: int = 4, **how) -> Iterator[DataFrame]:
    """The paths that end in a link as soon as that link is made, ungrouped: a level's links come in ``parts`` lots, dealt by the link's own hash."""
    answered = None
    for found in levels(graph, a, source, "links", **how):
        depth = found.levels[-1]["level"]
        new = found.ends().filter(F.col("dist") == depth).select("source", "node", "dist", "state")
        if answered is not None:
            new = new.join(answered, ["source", "node"], "left_anti")
        new, n = counted(new, "answers")
        if not n:
            continue
        if not depth:
            yield unrolled(found, new)
        else:
            last = found.links.filter(F.col("dist") == depth).join(new, ["source", "node", "state", "dist"])
            last = last.withColumn("lot", F.pmod(F.xxhash64("node", "state", "pred", "pred_state", "label"), F.lit(parts)))
            for lot in range(parts):
                mine = last.filter(F.col("lot") == lot)
                pred = mine.select("source", F.col("pred").alias("node"), F.lit(depth - 1).alias("dist"), F.col("pred_state").alias("state")).distinct()
                before = unrolled(found, pred, False, True).select("source", F.col("node").alias("pred"), F.col("state").alias("pred_state"), F.col("nodes").alias("so_far"), F.col("labels").alias("word"))
                both = mine.join(before, ["source", "pred", "pred_state"])
                out = both.select("source", "node", "dist", F.array_append("so_far", F.col("node")).alias("nodes"), F.array_append("word", F.col("label")).alias("labels"))
                yield found.graph.ids.shown(out, ["source", "node", "nodes"])
        pairs = new.select("source", "node").distinct()
        answered = written(pairs if answered is None else answered.unionByName(pairs), "answered")


def path_text() -> Column:
    """A path as one string: node/label/node ..."""
    rest = F.zip_with("labels", F.slice("nodes", F.lit(2), F.size("labels")), lambda a, n: F.concat_ws("/", a, n))
    return F.when(F.size("labels") == 0, F.get("nodes", F.lit(0))).otherwise(F.concat(F.get("nodes", F.lit(0)), F.lit("/"), F.array_join(rest, "/"))).alias("path")


def ranked_links(found: Search) -> DataFrame:
    """The links with the number of paths through each, and the number through the links before it at the same product node."""
    ways = None
    start = found.visited.filter("dist = 0").select("source", F.col("node").alias("pred"), F.col("state").alias("pred_state"), F.lit(1).cast(COUNT).alias("ways"))
    out: list[DataFrame] = []
    for x in found.levels[1:]:
        if not x["links"]:
            break
        ways = start if ways is None else ways
        here = written(found.links.filter(F.col("dist") == x["level"]).join(ways, ["source", "pred", "pred_state"]), "ways")
        out.append(here)
        ways = here.groupBy("source", F.col("node").alias("pred"), F.col("state").alias("pred_state")).agg(F.sum("ways").cast(COUNT).alias("ways"))
    if not out:
        return found.links.withColumn("ways", F.lit(1).cast(COUNT)).withColumn("before", F.lit(0).cast(COUNT))
    all_of = out[0]
    for o in out[1:]:
        all_of = all_of.unionByName(o)
    order = Window.partitionBy("source", "node", "state").orderBy("pred", "pred_state", "label").rowsBetween(Window.unboundedPreceding, -1)
    return written(all_of.withColumn("before", F.coalesce(F.sum("ways").over(order), F.lit(0)).cast(COUNT)), "ranked")


def paths_by_rank(found: Search, wanted: DataFrame, named: bool = True) -> DataFrame:
    """The paths of ``wanted`` (source, node, state, dist, rank), each found by itself: at every node the link whose range holds the rank.

    The order of an answer's paths is that of their links from the end backwards. No list of paths is made, so any of an exponential number can be had.
    """
    links = ranked_links(found).select("source", F.col("node").alias("at"), F.col("state").alias("at_state"), "pred", "pred_state", "label", "ways", "before", F.col("dist").alias("level"))
    part, n = counted(wanted.select("source", "node", "dist", F.col("rank").cast(COUNT).alias("rank"), F.col("rank").cast(COUNT).alias("left"), F.col("node").alias("at"), F.col("state").alias("at_state"), F.array("node").alias("nodes"), F.array().cast("array<string>").alias("labels")), "ranks")
    done, moving = part.filter("dist = 0 and rank = 0"), None
    deepest = part.agg(F.max("dist")).first()[0] if n else 0
    for level in range(deepest, 0, -1):
        here = part.filter(F.col("dist") == level)
        here = here if moving is None else here.unionByName(moving)
        step = here.join(links.filter(F.col("level") == level).drop("level"), ["source", "at", "at_state"]).filter("left >= before and left < before + ways")
        step = step.select("source", "node", "dist", "rank", (F.col("left") - F.col("before")).cast(COUNT).alias("left"), F.col("pred").alias("at"), F.col("pred_state").alias("at_state"), F.array_prepend("nodes", F.col("pred")).alias("nodes"), F.array_prepend("labels", F.col("label")).alias("labels"))
        moving = written(step, "ranks")
    out = (done if moving is None else done.unionByName(moving)).select("source", "node", "dist", "rank", "nodes", "labels")
    return found.graph.ids.shown(out, ["source", "node", "nodes"]) if named else out


def _counts_by_end(found: Search) -> DataFrame:
    """``source, node, dist, state, ways`` of the answers' final states, with the number of paths that come before in the answer's order."""
    ways = ranked_links(found).groupBy("source", "node", "state").agg(F.sum("ways").cast(COUNT).alias("ways"))
    ends = _ends(found, None).join(ways, ["source", "node", "state"], "left").withColumn("ways", F.coalesce("ways", F.lit(1).cast(COUNT)))
    order = Window.partitionBy("source", "node").orderBy("state").rowsBetween(Window.unboundedPreceding, -1)
    return ends.withColumn("before", F.coalesce(F.sum("ways").over(order), F.lit(0)).cast(COUNT))


def k_paths(found: Search, k: int) -> DataFrame:
    """The first ``k`` paths of each answer, by rank: the cost is in proportion to what comes out, however many paths there are."""
    ends = _counts_by_end(found).filter(F.col("before") < k)
    upto = F.least(F.col("ways"), F.lit(k).cast(COUNT) - F.col("before")).cast("int") - 1
    wanted = ends.select("source", "node", "state", "dist", F.explode(F.sequence(F.lit(0), upto)).alias("rank"))
    return paths_by_rank(found, wanted).select(*PATH)


def paths_balanced(found: Search, parts: int, most: int = 1 << 31) -> DataFrame:
    """All paths in ``parts`` of equal numbers of paths, whatever the sizes of the answers; each path is found by its rank. More than ``most`` paths raise."""
    ends = written(_counts_by_end(found), "ends")
    total = ends.agg(F.sum("ways")).first()[0] or 0
    if total > most:
        raise ValueError(f"{total} paths are more than {most}")
    each = ends.select("source", "node", "state", "dist", F.explode(F.sequence(F.lit(0), F.col("ways").cast("int") - 1)).alias("rank"))
    return paths_by_rank(found, each.repartition(parts)).select(*PATH)


def iter_paths(links: list[tuple], node, finals: list[int], start_state: int = 0, source=None):
    """Paths one by one from a small links table (node, state, pred, pred_state, label), by depth-first search with remembered forks.

    Yields ``(steps, nodes, labels)``; ``steps`` counts the links followed since the path before, at most the path's length.
    """
    before: dict = {}
    for n, s, p, ps, label in links:
        before.setdefault((n, s), []).append((p, ps, label))
    for state in finals:
        steps = 0
        stack = [((node, state), (node, None), None)]
        while stack:
            key, nodes, labels = stack.pop()
            if key not in before:
                if key[1] == start_state and (source is None or key[0] == source):
                    yield steps, _listed(nodes), _listed(labels)
                    steps = 0
                continue
            for p, ps, label in reversed(before[key]):
                stack.append(((p, ps), (p, nodes), (label, labels)))
            steps += 1


def _listed(cell) -> list:
    """A linked list as a Python list; cells are shared between paths, so a fork costs one cell."""
    out = []
    while cell is not None:
        out.append(cell[0])
        cell = cell[1]
    return out


def lazy_paths(found: Search, most_links: int = 1_000_000, named: bool = True) -> DataFrame:
    """``source, node, dist, nodes, labels, steps``: paths by depth-first search in the task that holds a source's links; ``steps`` is the delay.

    For sources of up to ``most_links`` links each (checked); beyond that use :func:`paths` or :func:`paths_balanced`, which split any source.
    """
    per = found.links.groupBy("source").count().agg(F.max("count")).first()[0] or 0
    if per > most_links:
        raise ValueError(f"a source has {per} links, more than {most_links}")
    ends = _ends(found, None)
    rows = found.links.select("source", "node", "state", "pred", "pred_state", "label", F.lit(-1).alias("dist"))
    rows = rows.unionByName(ends.select("source", "node", "state", F.lit(None).cast("long").alias("pred"), F.lit(None).cast("int").alias("pred_state"), F.lit(None).cast("string").alias("label"), "dist"))
    schema = "source long, node long, dist int, nodes array<long>, labels array<string>, steps int"

    def run(table: pa.Table) -> pa.Table:
        links, wanted, source = [], [], None
        for r in table.to_pylist():
            source = r["source"]
            if r["dist"] < 0:
                links.append((r["node"], r["state"], r["pred"], r["pred_state"], r["label"]))
            else:
                wanted.append((r["node"], r["state"], r["dist"]))
        out: dict[str, list] = {k: [] for k in ("source", "node", "dist", "nodes", "labels", "steps")}
        for node, state, dist in sorted(wanted):
            for steps, nodes, labels in [(0, [node], [])] if dist == 0 else iter_paths(links, node, [state], 0, source):
                for k, v in zip(out, (source, node, dist, nodes, labels, steps), strict=True):
                    out[k].append(v)
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.string()), pa.int32()]
        return pa.table([pa.array(v, t) for v, t in zip(out.values(), kinds, strict=True)], names=list(out))

    out = rows.groupBy("source").applyInArrow(run, schema)
    return found.graph.ids.shown(out, ["source", "node", "nodes"]) if named else out
