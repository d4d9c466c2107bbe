"""Words of labels against expressions, in expressions of columns and as table functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from waypoint.plans.automaton import Automaton, determinised, prepared


def matches_word(labels: Column, a: Automaton | str) -> Column:
    """Whether an array of labels is a word of the automaton (or expression): a deterministic automaton is stepped through by map lookups."""
    a = prepared(a) if isinstance(a, str) else (a if a.is_deterministic() else determinised(a))
    if not a.moves:
        return (F.size(labels) == 0) & F.lit(0 in a.finals)
    table = F.create_map(*[F.lit(v) for s, x, t in sorted(a.moves) for v in (f"{s} {x}", t)])
    end = F.aggregate(labels, F.lit(0), lambda s, x: F.coalesce(F.try_element_at(table, F.concat_ws(" ", s.cast("string"), x)), F.lit(-1)))
    return end.isin(sorted(a.finals)) if a.finals else F.lit(False)


@udtf(returnType="state int, label string, next_state int, final boolean")
class AutomatonMoves:
    """``rpq_automaton(expression)``: the moves of its least deterministic automaton, with whether the next state is final."""

    def eval(self, expression: str):
        a = prepared(expression)
        for s, x, t in sorted(a.moves):
            yield s, x, t, t in a.finals


@udtf(returnType="node string, steps int, path string")
class SlicePaths:
    """``enumerate_slice(TABLE(links) PARTITION BY source, finals)``: paths of one source's links (source, node, state, pred, pred_state, label) by depth-first search."""

    def __init__(self):
        self.links, self.source, self.finals = [], None, ""

    def eval(self, row, finals: str):
        self.source, self.finals = row["source"], finals
        self.links.append((row["node"], row["state"], row["pred"], row["pred_state"], row["label"]))

    def terminate(self):
        from waypoint.operators.paths import iter_paths

        finals = {int(s) for s in self.finals.split(",") if s}
        for node, state in sorted({(n, s) for n, s, *_ in self.links if s in finals}):
            for steps, nodes, labels in iter_paths(self.links, node, [state], 0, self.source):
                text = str(nodes[0]) + "".join(f"/{x}/{n}" for x, n in zip(labels, nodes[1:], strict=True))
                yield str(node), steps, text


def register(spark: SparkSession) -> None:
    """Both table functions under their SQL names."""
    spark.udtf.register("rpq_automaton", AutomatonMoves)
    spark.udtf.register("enumerate_slice", SlicePaths)
