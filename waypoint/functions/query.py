"""Path queries as text: a mode, a start, an expression and an end, each end a name or a variable.

    ENDPOINTS (c:1, placed/contains, ?x)          nodes that a matching path reaches
    ANY SHORTEST (c:1, placed/contains, ?x)       and one shortest path to each
    ALL SHORTEST (?x, placed/contains, p:7)       or all of them
    COUNT SHORTEST (c:1, placed/contains, ?x)     or their number
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from waypoint.operators.paths import path_text, paths, single_paths
from waypoint.operators.search import answers, search
from waypoint.plans.automaton import prepared, reversed_automaton
from waypoint.sources.graphs import LabelledGraph

_FORM = re.compile(r"\s*(ENDPOINTS|(?:ANY|ALL|COUNT)\s+SHORTEST)\s*\(\s*([^,\s]+)\s*,\s*(.+)\s*,\s*([^,\s]+)\s*\)\s*\Z", re.I | re.S)
KEEP = {"endpoints": "ends", "any shortest": "one", "all shortest": "links", "count shortest": "count"}


@dataclass(frozen=True)
class PathQuery:
    mode: str
    source: str | None
    expression: str
    target: str | None

    @classmethod
    def parsed(cls, text: str) -> PathQuery:
        m = _FORM.match(text)
        if not m:
            raise ValueError(f"no path query: {text!r}")
        end = lambda s: None if s.startswith("?") else s
        return cls(" ".join(m[1].lower().split()), end(m[2]), m[3].strip(), end(m[4]))


def run_path_query(spark: SparkSession, graph: LabelledGraph, query: str | PathQuery) -> DataFrame:
    """``source, node, dist`` and by mode ``num_paths`` or ``path``. A query whose end alone is known runs backwards from there; labels that it walks
    backwards need no inverse edges in ``graph``, they are added here."""
    q = PathQuery.parsed(query) if isinstance(query, str) else query
    alphabet = graph.alphabet() if re.search(r"[.!]", q.expression) else ()
    a = prepared(q.expression, [x for x in alphabet if not x.startswith("^")])
    backwards = q.source is None and q.target is not None
    if backwards:
        a = prepared_reversed(a)
    if any(x.startswith("^") for x in a.labels):
        graph = graph.labels({x.lstrip("^") for x in a.labels}).with_inverses() if not any(x.startswith("^") for x in alphabet) else graph
    targets = [q.target] if q.source is not None and q.target is not None else None
    found = search(graph, a, q.target if backwards else q.source, KEEP[q.mode], targets=targets)
    if q.mode == "all shortest":
        out = paths(found)
    elif q.mode == "any shortest":
        out = single_paths(found)
    else:
        out = answers(found)
    if targets:
        out = out.filter(F.col("node") == q.target)
    if q.mode in ("all shortest", "any shortest"):
        if backwards:
            turned = F.transform("labels", lambda x: F.when(x.startswith("^"), F.substr(x, F.lit(2))).otherwise(F.concat(F.lit("^"), x)))
            out = out.withColumns({"nodes": F.reverse("nodes"), "labels": F.reverse(turned), "source": F.col("node"), "node": F.col("source")})
        return out.select("source", "node", "dist", path_text())
    if backwards:
        out = out.withColumns({"source": F.col("node"), "node": F.col("source")})
    return out.select("source", "node", "dist", *["num_paths"] * (q.mode == "count shortest"))


def prepared_reversed(a):
    """The reversed language's automaton, made unambiguous."""
    from waypoint.plans.automaton import minimised

    return minimised(reversed_automaton(a))
