"""The registered path queries and the DuckDB SQL that they are held against.

The SQL uses hand-written automata, so that it shares no code with the engine's.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from waypoint.functions import query as Q
from waypoint.functions import words as W
from waypoint.operators import answers as A
from waypoint.operators import baselines as B
from waypoint.operators import paths as P
from waypoint.operators import search as S
from waypoint.plans.automaton import measured, minimised, prepared, reversed_automaton
from waypoint.sources import graphs as G
from waypoint.streaming import stream as T


def _two_way(builder, **how):
    return lambda spark, d: builder(spark, d, **how).with_inverses()


def _figure(spark, d):
    rows = [("v", "any", "n1"), ("v", "any", "n2"), ("v", "any", "n3"), ("n1", "any", "n4"), ("n2", "any", "n4"), ("n3", "any", "n4"), ("n4", "any", "n5")]
    return G.LabelledGraph.from_edges(spark.createDataFrame(rows, "src string, label string, dst string"))


#: What is asked of lines shipped in one year, and of events up to a day.
SHIPPED = ("1995-01-01", "1996-01-01")
GRAPHS = {
    "figure": _figure, "commerce": G.commerce, "commerce2": _two_way(G.commerce), "hops": G.event_hops, "dialogue": G.dialogue, "chain": G.event_chain,
    "weblinks": G.weblinks, "weblinks2": _two_way(G.weblinks), "corpus": G.corpus, "corpus2": _two_way(G.corpus), "quotes2": _two_way(G.corpus, with_quotes=True),
    "similarity": G.similarity, "hourly": lambda s, d: G.event_hops(s, d, hourly=True), "shipped2": _two_way(G.commerce, shipped=SHIPPED),
    "hops_plain": lambda s, d: G.event_hops(s, d).unlabelled(), "commerce_plain": lambda s, d: G.commerce(s, d).with_inverses().unlabelled(),
}

COMMERCE_SQL = """SELECT DISTINCT * FROM (
  SELECT 'c:' || o_custkey AS src, 'placed' AS label, 'o:' || o_orderkey AS dst FROM orders
  UNION ALL SELECT 'o:' || l_orderkey, 'contains', 'p:' || l_partkey FROM lineitem
  UNION ALL SELECT 's:' || l_suppkey, 'supplies', 'p:' || l_partkey FROM lineitem
  UNION ALL SELECT 'c:' || c_custkey, 'in_nation', 'n:' || c_nationkey FROM customer
  UNION ALL SELECT 's:' || s_suppkey, 'in_nation', 'n:' || s_nationkey FROM supplier
  UNION ALL SELECT 'n:' || n_nationkey, 'in_region', 'r:' || n_regionkey FROM nation)"""
HOPS_SQL = """SELECT DISTINCT src, label, dst FROM (
  SELECT lag(k) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src, event_type AS label, k AS dst
  FROM (SELECT *, CAST(CAST(json_extract(props, '$.k') AS INTEGER) AS VARCHAR) AS k FROM events)) WHERE src IS NOT NULL"""
DIALOGUE_SQL = "SELECT DISTINCT conv_id || ':' || turn AS src, role AS label, conv_id || ':' || (turn + 1) AS dst FROM conversations"
WEB_SQL = """SELECT DISTINCT src, label, dst FROM (SELECT regexp_extract(url, '://([^/]*)', 1) AS src, 'links' AS label,
  unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages)"""
CORPUS_SQL = """SELECT DISTINCT * FROM (
  SELECT 'd:' || doc_id AS src, 'in_lang' AS label, 'lang:' || lang AS dst FROM documents
  UNION ALL SELECT 'd:' || doc_id, 'from_source', 'src:' || source FROM documents
  UNION ALL SELECT 'd:' || doc_id, 'rated', 'quality:' || quality FROM labels
  UNION ALL SELECT 'd:' || doc_id, 'flagged', 'toxic:' || toxic FROM labels) WHERE dst IS NOT NULL"""
CHAIN_SQL = "SELECT * FROM (SELECT CAST(lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS VARCHAR) AS src, event_type AS label, CAST(event_id AS VARCHAR) AS dst FROM events) WHERE src IS NOT NULL"
HOURLY_SQL = HOPS_SQL.replace("CAST(CAST(json_extract(props, '$.k') AS INTEGER) AS VARCHAR)", "CAST(CAST(json_extract(props, '$.k') AS INTEGER) * 24 + hour(ts) AS VARCHAR)")
QUOTES_SQL = CORPUS_SQL.replace(") WHERE dst", """
  UNION ALL SELECT 'd:' || doc_id, 'quotes', 'b:' || item_id FROM documents d JOIN benchmark b ON contains(lower(d.text), lower(b.text)) WHERE b.text <> '') WHERE dst""")
SIMILARITY_SQL = """SELECT CAST(a.vec_id AS VARCHAR) AS src, CASE WHEN a.label = b.label THEN 'same' ELSE 'cross' END AS label, CAST(b.vec_id AS VARCHAR) AS dst
  FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id
  QUALIFY row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.vec_id) <= 5"""
SHIPPED_SQL = COMMERCE_SQL.replace("FROM lineitem", "FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'")


def _both(sql: str) -> str:
    return f"SELECT * FROM ({sql}) UNION ALL SELECT dst, '^' || label, src FROM ({sql})"


GRAPH_SQL = {
    "commerce": COMMERCE_SQL, "commerce2": _both(COMMERCE_SQL), "hops": HOPS_SQL, "dialogue": DIALOGUE_SQL, "chain": CHAIN_SQL, "hourly": HOURLY_SQL, "similarity": SIMILARITY_SQL, "weblinks": WEB_SQL, "corpus": CORPUS_SQL, "quotes2": _both(QUOTES_SQL), "shipped2": _both(SHIPPED_SQL), "weblinks2": _both(WEB_SQL), "corpus2": _both(CORPUS_SQL),
    "hops_plain": f"SELECT DISTINCT src, 'any' AS label, dst FROM ({HOPS_SQL})", "commerce_plain": f"SELECT DISTINCT src, 'any' AS label, dst FROM ({_both(COMMERCE_SQL)})",
    "figure": "SELECT * FROM (VALUES ('v','any','n1'),('v','any','n2'),('v','any','n3'),('n1','any','n4'),('n2','any','n4'),('n3','any','n4'),('n4','any','n5')) t(src, label, dst)",
}

# name: graph, source, expression, moves of a hand-written automaton, finals
WORKLOADS = {
    "figure": ("figure", "v", "any*", "(0,'any',0)", "0"),
    "commerce_plain": ("commerce_plain", "c:1", "any*", "(0,'any',0)", "0"),
    "hops_plain": ("hops_plain", "0", "any*", "(0,'any',0)", "0"),
    "hops_any": ("hops", "0", ".*", "(0,'click',0),(0,'view',0),(0,'purchase',0),(0,'login',0),(0,'logout',0),(0,'signup',0),(0,'error',0)", "0"),
    "star": ("hops", "0", "click*", "(0,'click',0)", "0"),
    "prefix_star": ("hops", "0", "view*/click/purchase", "(0,'view',0),(0,'click',1),(1,'purchase',2)", "2"),
    "group_star": ("hops", "0", "(view/click)*", "(0,'view',1),(1,'click',0)", "0"),
    "suffix_star": ("hops", "0", "click/view/purchase*", "(0,'click',1),(1,'view',2),(2,'purchase',2)", "2"),
    "suppliers": ("commerce2", "c:1", "placed/contains/^supplies", "(0,'placed',1),(1,'contains',2),(2,'^supplies',3)", "3"),
    "supplier_regions": ("commerce2", "c:1", "placed/contains/^supplies/in_nation/in_region", "(0,'placed',1),(1,'contains',2),(2,'^supplies',3),(3,'in_nation',4),(4,'in_region',5)", "5"),
    "copurchase": ("commerce2", "c:1", "(placed/contains/^contains/^placed)*", "(0,'placed',1),(1,'contains',2),(2,'^contains',3),(3,'^placed',0)", "0"),
    "nation_or_region": ("commerce2", "c:1", "in_nation/in_region?", "(0,'in_nation',1),(1,'in_region',2)", "1,2"),
    "two_lengths": ("hops", "0", "click|view/purchase", "(0,'click',1),(0,'view',2),(2,'purchase',3)", "1,3"),
    "three_finals": ("hops", "0", "(click|view/click)*/view?", "(0,'view',1),(0,'click',2),(2,'click',2),(2,'view',1),(1,'click',2)", "0,1,2"),
    "ambiguous": ("hops", "0", "click*/click*", "(0,'click',0)", "0"),
    "colink": ("weblinks2", "therha.example.com", "(links/^links)*", "(0,'links',1),(1,'^links',0)", "0"),
    "rated_peers": ("corpus2", "d:0", "from_source/^from_source/rated", "(0,'from_source',1),(1,'^from_source',2),(2,'rated',3)", "3"),
    "fan_out": ("commerce2", "n:1", "^in_nation/placed/contains", "(0,'^in_nation',1),(1,'placed',2),(2,'contains',3)", "3"),
    "similar": ("similarity", "0", "same*/cross/same*", "(0,'same',0),(0,'cross',1),(1,'same',1)", "1"),
    "hourly_star": ("hourly", "100", "click*", "(0,'click',0)", "0"),
    "hourly_prefix_star": ("hourly", "100", "view*/click/purchase", "(0,'view',0),(0,'click',1),(1,'purchase',2)", "2"),
    "not_click": ("hops", "0", "!(click|view)/click", "(0,'purchase',1),(0,'login',1),(0,'logout',1),(0,'signup',1),(0,'error',1),(1,'click',2)", "2"),
    "shipped": ("shipped2", "c:1", "placed/contains/^supplies", "(0,'placed',1),(1,'contains',2),(2,'^supplies',3)", "3"),
    "region_members": ("commerce2", "r:0", "^in_region/^in_nation", "(0,'^in_region',1),(1,'^in_nation',2)", "2"),
}


def bfs_sql(graph: str, source: str, moves: str, finals: str) -> str:
    """A visited-set search: the newest level joins the edges, keys seen before are dropped, counts are summed."""
    return f"""
WITH RECURSIVE edges AS MATERIALIZED ({GRAPH_SQL[graph]}), delta(state, label, next_state) AS (VALUES {moves}),
seen(node, state, dist, cnt) USING KEY (node, state) AS (
  SELECT '{source}', 0, 0, 1::HUGEINT WHERE EXISTS (SELECT 1 FROM edges WHERE src = '{source}' OR dst = '{source}')
  UNION
  SELECT e.dst, a.next_state, min(s.dist) + 1, sum(s.cnt)::HUGEINT
  FROM seen s JOIN edges e ON e.src = s.node JOIN delta a ON a.state = s.state AND a.label = e.label
  LEFT JOIN recurring.seen old ON old.node = e.dst AND old.state = a.next_state
  WHERE old.node IS NULL GROUP BY e.dst, a.next_state),
best AS (SELECT node, min(dist) AS dist FROM seen WHERE state IN ({finals}) GROUP BY node)
SELECT b.node, b.dist::INTEGER AS dist, sum(s.cnt)::BIGINT AS num_paths
FROM best b JOIN seen s ON s.node = b.node AND s.dist = b.dist AND s.state IN ({finals}) GROUP BY b.node, b.dist"""


def _bound(graph: G.LabelledGraph, regex: str, **how):
    return prepared(regex, graph.alphabet() if "." in regex or "!" in regex else (), **how)


def _given(spark, d, name, **how):
    """Graph, automaton and source of a workload."""
    graph, source, regex, _, _ = WORKLOADS[name]
    g = GRAPHS[graph](spark, d)
    return g, _bound(g, regex, **how), source


def _run(spark, d, name, keep, finals="dictionary", **how):
    return S.search(*_given(spark, d, name, **how), keep, finals=finals)


def _long(df: DataFrame) -> DataFrame:
    return df.withColumn("num_paths", F.col("num_paths").cast("long"))


def _count(name, **how):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _long(S.answers(_run(spark, sf_dir, name, "count", **how))).select("node", "dist", "num_paths")

    return query


def _ends(name):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return S.answers(_run(spark, sf_dir, name, "ends")).select("node")

    return query


def _single(name):
    """One shortest path for each answer, by the least (previous node, state, label) all along."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return P.single_paths(_run(spark, sf_dir, name, "one")).select("node", "dist", P.path_text())

    return query


def _all(name, made=P.paths):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return made(_run(spark, sf_dir, name, "links")).select("node", "dist", P.path_text())

    return query


def _early(name, emit):
    """The tables that come out while the search runs, put together."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        parts = list(emit(*_given(spark, sf_dir, name)))
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out.select("node", "dist", P.path_text())

    return query


def _dag(name):
    """Links of the shortest-path DAG by level."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _run(spark, sf_dir, name, "links").links.groupBy("dist").agg(F.count("*").alias("links"), F.countDistinct("node", "state").alias("nodes"))

    return query


def _of_answers(name, made, keep="count"):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return made(S.answers(_run(spark, sf_dir, name, keep)))

    return query


def _of_given(name, made):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return made(*_given(spark, sf_dir, name))

    return query


def seen_sql(name: str) -> str:
    """The head of :func:`bfs_sql`, up to the table of product nodes."""
    graph, source, _, moves, finals = WORKLOADS[name]
    return bfs_sql(graph, source, moves, finals).rpartition("best AS")[0].rstrip().rstrip(",")


QUERIES: dict = {}
ORACLES: dict[str, str] = {}
for _name, (_graph, _source, _regex, _moves, _finals) in WORKLOADS.items():
    QUERIES[f"rpq_count_{_name}"] = _count(_name)
    ORACLES[f"rpq_count_{_name}"] = bfs_sql(_graph, _source, _moves, _finals)
for _name in ("commerce_plain", "star", "prefix_star", "group_star", "suppliers", "three_finals", "similar"):
    _sql = ORACLES[f"rpq_count_{_name}"]
    QUERIES[f"rpq_endpoints_{_name}"] = _ends(_name)
    ORACLES[f"rpq_endpoints_{_name}"] = f"SELECT node FROM ({_sql})"
    QUERIES[f"distance_profile_{_name}"] = _of_answers(_name, A.distance_profile)
    ORACLES[f"distance_profile_{_name}"] = f"SELECT dist, count(*) AS answers, sum(num_paths)::BIGINT AS paths, max(num_paths)::BIGINT AS most FROM ({_sql}) GROUP BY dist"
for _name in ("star", "nation_or_region", "three_finals", "two_lengths", "prefix_star"):
    # one final state with the empty word peeled off, against the distance dictionary
    QUERIES[f"rpq_normalised_{_name}"] = _count(_name, finals="normalise")
    ORACLES[f"rpq_normalised_{_name}"] = ORACLES[f"rpq_count_{_name}"]
for _name in ("figure", "star", "three_finals", "suppliers"):
    # the product graph made first
    QUERIES[f"product_count_{_name}"] = _of_given(_name, lambda g, a, v: _long(B.product_answers(g, a, v)).select("node", "dist", "num_paths"))
    ORACLES[f"product_count_{_name}"] = ORACLES[f"rpq_count_{_name}"]


def single_sql(name: str, order: str, moves: str | None = None, finals: str | None = None) -> str:
    """The parent of each product node is the first by ``order`` of the previous node, then state, then label; paths follow parents from the smallest final state."""
    graph, source, _, hand, ends = WORKLOADS[name]
    head = bfs_sql(graph, source, moves or hand, finals or ends).rpartition("best AS")[0].rstrip().rstrip(",")
    return f"""{head},
par AS (
  SELECT t.node, t.state, s.node AS pred, s.state AS pred_state, e.label FROM seen s JOIN edges e ON e.src = s.node JOIN delta a ON a.state = s.state AND a.label = e.label
  JOIN seen t ON t.node = e.dst AND t.state = a.next_state AND t.dist = s.dist + 1
  QUALIFY row_number() OVER (PARTITION BY t.node, t.state ORDER BY {order.format('s.node')}, s.state, e.label) = 1),
best AS (SELECT node, min(dist) AS dist FROM seen WHERE state IN ({finals or ends}) GROUP BY node),
ends AS (SELECT b.node, b.dist, min(s.state) AS state FROM best b JOIN seen s ON s.node = b.node AND s.dist = b.dist AND s.state IN ({finals or ends}) GROUP BY ALL),
back(node, dist, place, place_state, path) AS (
  SELECT node, dist, node, state, node FROM ends
  UNION ALL SELECT b.node, b.dist, p.pred, p.pred_state, p.pred || '/' || p.label || '/' || b.path FROM back b JOIN par p ON p.node = b.place AND p.state = b.place_state)
SELECT node, dist::INTEGER AS dist, path FROM back b WHERE NOT EXISTS (SELECT 1 FROM par p WHERE p.node = b.place AND p.state = b.place_state)"""


for _name, _order, _moves, _finals in (
    ("figure", "{0}", None, None), ("star", "{0}::BIGINT", None, None), ("prefix_star", "{0}::BIGINT", None, None), ("two_lengths", "{0}::BIGINT", None, None),
    ("suppliers", "split_part({0}, ':', 2)::BIGINT", None, None), ("three_finals", "{0}::BIGINT", "(0,'click',0),(0,'view',1),(1,'click',0)", "0,1"),
):
    QUERIES[f"rpq_single_{_name}"] = _single(_name)
    ORACLES[f"rpq_single_{_name}"] = single_sql(_name, _order, _moves, _finals)


def paths_sql(graph: str, source: str, moves: str, finals: str, longest: int) -> str:
    """All walks up to a length, without any visited set; the shortest of each node."""
    return f"""
WITH RECURSIVE edges AS MATERIALIZED ({GRAPH_SQL[graph]}), delta(state, label, next_state) AS (VALUES {moves}),
walks(node, state, dist, path) AS (
  SELECT '{source}', 0, 0, '{source}'
  UNION ALL
  SELECT e.dst, a.next_state, w.dist + 1, w.path || '/' || e.label || '/' || e.dst
  FROM walks w JOIN edges e ON e.src = w.node JOIN delta a ON a.state = w.state AND a.label = e.label WHERE w.dist < {longest})
SELECT node, dist::INTEGER AS dist, path FROM walks WHERE state IN ({finals}) QUALIFY dist = min(dist) OVER (PARTITION BY node)"""


for _name, _longest in (("figure", 4), ("star", 4), ("prefix_star", 4), ("group_star", 4), ("suppliers", 3), ("two_lengths", 2), ("fan_out", 3), ("rated_peers", 3)):
    _graph, _source, _regex, _moves, _finals = WORKLOADS[_name]
    QUERIES[f"rpq_all_{_name}"] = _all(_name)
    ORACLES[f"rpq_all_{_name}"] = paths_sql(_graph, _source, _moves, _finals, _longest)
for _name in ("figure", "hops_plain", "suppliers", "star"):
    QUERIES[f"dag_links_{_name}"] = _dag(_name)
    ORACLES[f"dag_links_{_name}"] = f"""{seen_sql(_name)}
SELECT (s.dist + 1)::INTEGER AS dist, count(*) AS links, count(DISTINCT (t.node, t.state)) AS nodes
FROM seen s JOIN edges e ON e.src = s.node JOIN delta a ON a.state = s.state AND a.label = e.label
JOIN seen t ON t.node = e.dst AND t.state = a.next_state AND t.dist = s.dist + 1 GROUP BY s.dist"""


for _how, _made in {
    "by_level": lambda n: _early(n, P.paths_by_level), "by_visit": lambda n: _early(n, P.paths_by_visit), "lazy": lambda n: _all(n, P.lazy_paths),
    "balanced": lambda n: _all(n, lambda found: P.paths_balanced(found, 8)),
}.items():
    for _name in ("star", "prefix_star", "two_lengths"):
        QUERIES[f"rpq_all_{_how}_{_name}"] = _made(_name)
        ORACLES[f"rpq_all_{_how}_{_name}"] = ORACLES[f"rpq_all_{_name}"]


def rpq_to_target(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Known end: who bought part 7, by the reversed expression from its end."""
    found = S.search(GRAPHS["commerce2"](spark, sf_dir), reversed_automaton(prepared("placed/contains")), "p:7")
    return _long(S.answers(found)).select("node", "dist", "num_paths")


def rpq_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both ends known: the search stops at the level that answers the target."""
    found = S.search(GRAPHS["commerce2"](spark, sf_dir), prepared("(placed/contains/^contains/^placed)*"), "c:1", targets=["c:3"])
    return _long(S.answers(found)).filter("node = 'c:3'").select("node", "dist", "num_paths")


def rpq_pair_two_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two starts and two ends, answered on different levels."""
    found = S.search(GRAPHS["hops"](spark, sf_dir), prepared("click+"), ["0", "1"], targets=["2", "3"])
    return _long(S.answers(found)).filter("node in ('2', '3')").select("source", "node", "dist", "num_paths")


def rpq_all_sources_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Unknown start: every node's region."""
    found = S.search(G.commerce(spark, sf_dir), prepared("in_nation/in_region"), None)
    return _long(S.answers(found)).select("source", "node", "dist", "num_paths")


def rpq_all_sources_dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations whose whole sequence of roles is an optional system turn and user-assistant pairs."""
    graph = G.dialogue(spark, sf_dir).stored()
    ends = graph.edges.select(F.col("dst").alias("node")).distinct().join(graph.edges.select(F.col("src").alias("node")), "node", "left_anti")
    last = graph.ids.shown(ends, ["node"])
    firsts = graph.triples().filter(F.col("src").endswith(":0")).select("src").distinct()
    found = S.search(graph, prepared("system?/(user/assistant)*"), firsts)
    return S.answers(found).join(last, "node", "left_semi").select("source", "node", "dist")


def rpq_all_sources_similar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Unknown start: vectors of the same label that chains of near neighbours lead to."""
    return _long(S.answers(S.search(G.similarity(spark, sf_dir), prepared("same+"), None))).select("source", "node", "dist", "num_paths")


def rpq_all_sources_quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Unknown start: documents that quote a benchmark passage in common."""
    return _long(S.answers(S.search(GRAPHS["quotes2"](spark, sf_dir), prepared("quotes/^quotes"), None))).select("source", "node", "dist", "num_paths")


def ablation_ambiguous(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ambiguous automaton used as it is: a word of length L counts once for each of its L + 1 runs."""
    return _long(S.answers(_run(spark, sf_dir, "ambiguous", "count", ambiguity="allow"))).select("node", "dist", "num_paths")


def single_ambiguous(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One path an answer needs no unambiguous automaton."""
    found = _run(spark, sf_dir, "ambiguous", "one", ambiguity="allow")
    return P.single_paths(found).groupBy("node", "dist").agg(F.count("*").alias("num_paths"))


def ablation_unchecked_finals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Several finals without the distance dictionary: nodes are answered again at greater lengths."""
    found = S.search(GRAPHS["hops"](spark, sf_dir), prepared("click|view/purchase", ambiguity="allow"), "0")
    return S.answers(found, checked=False).groupBy("node", "dist").agg(F.sum("num_paths").cast("long").alias("num_paths"))


def _walks(kind, longest=3):
    """All walks (trails, simple paths) of up to three clicks, in order of length."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return B.walks(*_given(spark, sf_dir, "star"), longest, kind).select("node", "dist", P.path_text())

    return query


def walks_shortest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shortest of all walks of up to four edges, to each node; walks that a shorter one has overtaken are not gone on with."""
    return B.shortest_of(B.walks(*_given(spark, sf_dir, "prefix_star"), 4, "shortest")).select("node", "dist", P.path_text())


def walks_sql(kind: str, longest: int = 3) -> str:
    again = {"walk": "", "trail": "AND NOT list_contains(w.edges, w.node || '>' || e.dst)", "simple": "AND NOT list_contains(w.nodes, e.dst)"}[kind]
    return f"""
WITH RECURSIVE edges AS MATERIALIZED (SELECT * FROM ({HOPS_SQL}) WHERE label = 'click'),
w(node, dist, path, nodes, edges) AS (
  SELECT '0', 0, '0', ['0'], []::VARCHAR[]
  UNION ALL SELECT e.dst, w.dist + 1, w.path || '/click/' || e.dst, list_append(w.nodes, e.dst), list_append(w.edges, w.node || '>' || e.dst)
  FROM w JOIN edges e ON e.src = w.node WHERE w.dist < {longest} {again})
SELECT node, dist::INTEGER AS dist, path FROM w"""


def k_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two paths an answer, found by their ranks."""
    return P.k_paths(_run(spark, sf_dir, "star", "links"), 2).select("node", "dist", P.path_text())


def cost_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Product nodes first seen at each level, and product edges that leave them."""
    g, a, v = _given(spark, sf_dir, "prefix_star")
    return S.examined(g, S.search(g, a, v))


def cost_memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that lists of links need against rows that counts need."""
    found = _run(spark, sf_dir, "group_star", "links")
    return found.visited.agg(F.count("*").alias("count_rows")).crossJoin(found.links.agg(F.count("*").alias("link_rows")))


def cost_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What determinising costs at worst over the types of the given events: a purchase at the k-th place before the last event; and the users whose histories match."""
    events = G.read(spark, sf_dir, "events").filter("event_type is not null")
    types = sorted({r[0] for r in events.select("event_type").distinct().collect()} | {"purchase"})  # one row a type
    every, rows, matches = f"({'|'.join(types)})", [], []
    word = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"])
    words = events.groupBy("user_id").agg(word.alias("word"))
    for k in range(1, 7):
        text = f"{every}*/purchase" + f"/{every}" * k
        of = {x[0]: x for x in measured(text)}
        rows.append((k, of["position"][1], of["minimal"][1], of["position"][3], of["position"][4], of["minimal"][3]))
        matches.append(F.count_if(W.matches_word(F.col("word"), text)).alias(f"users{k}"))
    found = words.agg(*matches)
    users = found.select(F.explode(F.array(*[F.struct(F.lit(k).cast("long").alias("k"), F.col(f"users{k}").alias("users")) for k in range(1, 7)])).alias("x")).select("x.k", "x.users")
    costs = spark.createDataFrame(rows, "k long, position_states long, minimal_states long, position_deterministic boolean, position_unambiguous boolean, minimal_deterministic boolean")
    return costs.join(F.broadcast(users), "k")


def delay_lazy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths listed one after another, and those that took more steps than they are long."""
    out = P.lazy_paths(_run(spark, sf_dir, "group_star", "links"))
    return out.agg(F.count("*").alias("paths"), F.count_if(F.col("steps") > F.col("dist")).alias("late"))


def invalid_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All shortest paths held against the graph, the expression and the distances: how many there are, and how many fail."""
    g, a, v = _given(spark, sf_dir, "prefix_star")
    g = g.stored()
    found = S.search(g, a, v, "links")
    every = P.paths(found)
    return every.agg(F.count("*").alias("paths")).crossJoin(A.invalid_paths(g, a, every, found).agg(F.count("*").alias("invalid")))


def _pairs(made):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = G.event_hops(spark, sf_dir).stored()
        one, other = (S.answers(S.search(g, prepared(x), "0", "ends")) for x in ("click/click", "view/purchase"))
        return made(one, other).select("node")

    return query


def _text(text, graph="commerce"):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = Q.run_path_query(spark, GRAPHS[graph](spark, sf_dir), text)
        return _long(out) if "num_paths" in out.columns else out

    return query


def graph_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct triples of every graph by label."""
    names = ["commerce", "hops", "dialogue", "chain", "weblinks", "corpus", "similarity", "hourly"]
    parts = [GRAPHS[n](spark, sf_dir).edges.distinct().groupBy("label").agg(F.count("*").alias("triples")).withColumn("graph", F.lit(n)) for n in names]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def words_dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole conversations whose roles match an expression, in one aggregation."""
    c = G.read(spark, sf_dir, "conversations")
    word = F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"])
    return c.groupBy("conv_id").agg(word.alias("word")).filter(W.matches_word(F.col("word"), "system?/(user/assistant)*")).select("conv_id")


def udtf_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moves of an expression's automaton, from SQL, with the events that each can read and the users who have such events."""
    W.register(spark)
    events = G.read(spark, sf_dir, "events")
    return spark.sql("""
WITH read AS (SELECT event_type, count(*) AS events, count(DISTINCT user_id) AS users FROM {events} GROUP BY event_type)
SELECT state, label, next_state, final, coalesce(events, 0) AS events, coalesce(users, 0) AS users
FROM rpq_automaton('view*/click/purchase') LEFT JOIN read ON event_type = label""", events=events)


def udtf_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths of a stored search listed by a table function, from SQL."""
    W.register(spark)
    found = _run(spark, sf_dir, "figure", "links")
    links = found.graph.ids.shown(found.links, ["source", "node", "pred"])
    return spark.sql("SELECT node, path FROM enumerate_slice(TABLE({links}) PARTITION BY (source), '0')", links=links)


def ladder(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Diamonds in a row: the number of shortest paths doubles with each."""
    rows = [e for i in range(5) for e in ((f"d{i}", "a", f"u{i}"), (f"d{i}", "a", f"l{i}"), (f"u{i}", "a", f"d{i + 1}"), (f"l{i}", "a", f"d{i + 1}"))]
    found = S.search(spark.createDataFrame(rows, "src string, label string, dst string"), prepared("(a/a)*"), "d0")
    return _long(S.answers(found)).select("node", "dist", "num_paths")


def stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """In the graph of each day that has closed: users who clicked what user 1 clicked."""
    query, sink = T.windowed_rpq(T.event_edges(T.events_stream(spark, sf_dir)), prepared("click/^click"), "u:1", "1 day")
    T.drained(query)
    return sink.table().select(F.date_format("begins", "yyyy-MM-dd HH:mm:ss").alias("begins"), "node", "dist", "num_paths")


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of users (closed after six hours without an event) that are views and then clicks."""
    query, sink = T.session_rpq(T.events_stream(spark, sf_dir), prepared("view*/click*"), "6 hours")
    T.drained(query)
    return sink.table().select("user_id", F.date_format("begins", "yyyy-MM-dd HH:mm:ss").alias("begins"), "events")


def stream_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's chain of events: how many of its prefixes are words."""
    query, sink = T.chain_matcher(T.events_stream(spark, sf_dir), prepared("(view|click)*/purchase?"))
    T.drained(query)
    return T.latest(sink.table()).select("user_id", "events", "accepted")


def stream_inserts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts kept up while lines come in: orders of customer 1 first, their lines and suppliers as a stream."""
    whole = G.commerce(spark, sf_dir).with_inverses().stored()
    lines = F.col("label").isin("contains", "^contains", "supplies", "^supplies")
    folder = f"{T.shared_folder(spark)}/inserts-{T.uuid.uuid4().hex}"
    whole.edges.filter(lines).repartition(3, "src").write.parquet(folder)
    stream = spark.readStream.schema("src long, label string, dst long").option("maxFilesPerTrigger", 2).parquet(folder)
    query, kept = T.maintain_counts(stream, whole._with(whole.edges.filter(~lines)), prepared("placed/contains/^supplies"), "c:1")
    T.drained(query)
    return _long(kept.answers()).select("node", "dist", "num_paths")


def stream_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream of starts, each searched for on one stored graph."""
    folder = f"{T.shared_folder(spark)}/asked-{T.uuid.uuid4().hex}"
    spark.createDataFrame([("s:1",), ("s:2",), ("c:1",), ("nowhere",)], "source string").write.parquet(folder)
    query, sink = T.source_stream(spark.readStream.schema("source string").parquet(folder), G.commerce(spark, sf_dir), prepared("in_nation/in_region"))
    T.drained(query)
    return sink.table()


QUERIES |= {
    "rpq_to_target": rpq_to_target, "rpq_pair": rpq_pair, "rpq_pair_two_sources": rpq_pair_two_sources, "rpq_all_sources_regions": rpq_all_sources_regions,
    "rpq_all_sources_dialogue": rpq_all_sources_dialogue, "rpq_all_sources_similar": rpq_all_sources_similar, "rpq_all_sources_quotes": rpq_all_sources_quotes,
    "ablation_ambiguous": ablation_ambiguous, "single_ambiguous": single_ambiguous, "ablation_unchecked_finals": ablation_unchecked_finals,
    "walks_bounded": _walks("walk"), "walks_trails": _walks("trail"), "walks_simple": _walks("simple"), "walks_shortest": walks_shortest, "k_paths": k_paths,
    "cost_levels": cost_levels, "cost_memory": cost_memory, "cost_automata": cost_automata, "cost_output": _of_answers("group_star", A.output_size), "delay_lazy": delay_lazy, "invalid_paths": invalid_paths,
    "answers_union": _pairs(A.answers_union), "answers_intersect": _pairs(A.answers_intersect), "answers_except": _pairs(A.answers_except),
    "nearest_answers": _of_answers("star", lambda a: A.nearest_answers(a, 10).select("node", "dist", F.col("place").cast("long").alias("place"))),
    "first_answers": _of_answers("star", lambda a: A.first_answers(a, 25).select("node", "dist")), "profile_rollup": _of_answers("commerce_plain", A.profile_rollup),
    "text_count": _text("COUNT SHORTEST (?x, placed/contains, p:7)"), "text_all": _text("ALL SHORTEST (c:1, placed/contains/^supplies, ?x)"),
    "text_any": _text("ANY SHORTEST (c:1, in_nation/in_region, ?x)"), "text_endpoints": _text("ENDPOINTS (c:1, placed/contains, ?x)"),
    "graph_labels": graph_labels, "words_dialogue": words_dialogue, "udtf_automaton": udtf_automaton, "udtf_paths": udtf_paths, "ladder": ladder,
    "stream_windows": stream_windows, "stream_sessions": stream_sessions, "stream_chains": stream_chains, "stream_inserts": stream_inserts, "stream_sources": stream_sources,
}
_copurchase = ORACLES["rpq_count_copurchase"]
_star, _links = ORACLES["rpq_count_star"], "JOIN edges e ON e.src = s.node JOIN delta a ON a.state = s.state AND a.label = e.label"
_click2, _view_purchase = (f"SELECT DISTINCT f.dst AS node FROM ({HOPS_SQL}) e JOIN ({HOPS_SQL}) f ON e.dst = f.src WHERE e.src = '0' AND e.label = '{x}' AND f.label = '{y}'" for x, y in (("click", "click"), ("view", "purchase")))
_pair = " UNION ALL ".join(f"SELECT '{v}' AS source, * FROM ({bfs_sql('hops', v, _plus, '1')}) WHERE node IN ('2', '3')" for v in "01" for _plus in ["(0,'click',1),(1,'click',1)"])
ORACLES |= {
    "rpq_to_target": "SELECT DISTINCT 'c:' || o_custkey AS node, 2 AS dist, count(DISTINCT o_orderkey)::BIGINT AS num_paths FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_partkey = 7 GROUP BY o_custkey",
    "rpq_pair": f"SELECT * FROM ({_copurchase}) WHERE node = 'c:3'", "rpq_pair_two_sources": _pair,
    "rpq_all_sources_regions": "SELECT 'c:' || c_custkey AS source, 'r:' || n_regionkey AS node, 2 AS dist, 1::BIGINT AS num_paths FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT 's:' || s_suppkey, 'r:' || n_regionkey, 2, 1 FROM supplier JOIN nation ON s_nationkey = n_nationkey",
    "rpq_all_sources_dialogue": "SELECT conv_id || ':0' AS source, conv_id || ':' || (max(turn) + 1) AS node, (max(turn) + 1)::INTEGER AS dist FROM conversations GROUP BY conv_id HAVING regexp_full_match(string_agg(substr(role, 1, 1), '' ORDER BY turn), 's?(ua)*')",
    "rpq_all_sources_similar": f"""
WITH RECURSIVE edges AS MATERIALIZED (SELECT * FROM ({SIMILARITY_SQL}) WHERE label = 'same'),
seen(source, node, dist, cnt) USING KEY (source, node) AS (
  SELECT src, dst, 1, 1::HUGEINT FROM edges
  UNION SELECT s.source, e.dst, min(s.dist) + 1, sum(s.cnt)::HUGEINT FROM seen s JOIN edges e ON e.src = s.node
  LEFT JOIN recurring.seen old ON old.source = s.source AND old.node = e.dst WHERE old.node IS NULL GROUP BY s.source, e.dst)
SELECT source, node, dist::INTEGER AS dist, cnt::BIGINT AS num_paths FROM seen""",
    "rpq_all_sources_quotes": f"WITH q AS (SELECT src, dst FROM ({QUOTES_SQL}) WHERE label = 'quotes') SELECT a.src AS source, b.src AS node, 2 AS dist, count(*)::BIGINT AS num_paths FROM q a JOIN q b ON a.dst = b.dst GROUP BY a.src, b.src",
    "ablation_ambiguous": f"SELECT node, dist, (num_paths * (dist + 1))::BIGINT AS num_paths FROM ({ORACLES['rpq_count_ambiguous']})",
    "single_ambiguous": f"SELECT node, dist, 1::BIGINT AS num_paths FROM ({ORACLES['rpq_count_ambiguous']})",
    "ablation_unchecked_finals": f"{seen_sql('two_lengths')} SELECT node, dist::INTEGER AS dist, sum(cnt)::BIGINT AS num_paths FROM seen WHERE state IN (1, 3) GROUP BY node, dist",
    "walks_bounded": walks_sql("walk"), "walks_trails": walks_sql("trail"), "walks_simple": walks_sql("simple"), "walks_shortest": ORACLES["rpq_all_prefix_star"],
    "k_paths": f"""
WITH RECURSIVE edges AS MATERIALIZED (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({HOPS_SQL}) WHERE label = 'click'),
w(node, dist, path, back) AS (
  SELECT 0, 0, '0', []::BIGINT[] UNION ALL SELECT e.dst, w.dist + 1, w.path || '/click/' || e.dst, list_prepend(w.node, w.back) FROM w JOIN edges e ON e.src = w.node WHERE w.dist < 4),
s AS (SELECT * FROM w QUALIFY dist = min(dist) OVER (PARTITION BY node))
SELECT node::VARCHAR AS node, dist::INTEGER AS dist, path FROM s QUALIFY row_number() OVER (PARTITION BY node ORDER BY back) <= 2""",
    "cost_levels": f"{seen_sql('prefix_star')}, out AS (SELECT s.dist, count(*) AS n FROM seen s {_links} GROUP BY s.dist) SELECT s.dist::INTEGER AS level, count(*) AS visited, coalesce(any_value(o.n), 0)::BIGINT AS examined FROM seen s LEFT JOIN out o ON o.dist = s.dist GROUP BY s.dist",
    "cost_memory": f"{seen_sql('group_star')} SELECT (SELECT count(*) FROM seen) AS count_rows, (SELECT count(*) FROM seen s {_links} JOIN seen t ON t.node = e.dst AND t.state = a.next_state AND t.dist = s.dist + 1) AS link_rows",
    "cost_automata": """WITH e AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) - 1 AS back FROM events WHERE event_type IS NOT NULL),
n AS (SELECT count(DISTINCT t) AS n FROM (SELECT event_type AS t FROM e UNION ALL SELECT 'purchase'))
SELECT k, 2 + n * (k + 1) AS position_states, (1 << (k + 1)::INTEGER)::BIGINT AS minimal_states, false AS position_deterministic, true AS position_unambiguous, true AS minimal_deterministic,
  (SELECT count(*) FROM e WHERE back = k AND event_type = 'purchase') AS users FROM range(1, 7) t(k), n""",
    "cost_output": f"SELECT count(*) AS answers, sum(num_paths)::BIGINT AS paths, sum(num_paths * (dist + 1))::BIGINT AS symbols, max(num_paths) AS most, max(dist) AS farthest FROM ({ORACLES['rpq_count_group_star']})",
    "delay_lazy": f"SELECT sum(num_paths)::BIGINT AS paths, 0::BIGINT AS late FROM ({ORACLES['rpq_count_group_star']})",
    "invalid_paths": f"SELECT sum(num_paths)::BIGINT AS paths, 0::BIGINT AS invalid FROM ({ORACLES['rpq_count_prefix_star']})",
    "answers_union": f"{_click2} UNION {_view_purchase}", "answers_intersect": f"{_click2} INTERSECT {_view_purchase}", "answers_except": f"{_click2} EXCEPT {_view_purchase}",
    "nearest_answers": f"SELECT node, dist, row_number() OVER (ORDER BY dist, node) AS place FROM ({_star}) QUALIFY place <= 10", "first_answers": f"SELECT node, dist FROM ({_star}) ORDER BY dist, node LIMIT 25",
    "profile_rollup": f"SELECT kind, dist, count(*) AS answers, sum(num_paths)::BIGINT AS paths FROM (SELECT split_part(node, ':', 1) AS kind, dist, num_paths FROM ({ORACLES['rpq_count_commerce_plain']})) GROUP BY ROLLUP (kind, dist)",
    "text_all": f"SELECT 'c:1' AS source, * FROM ({ORACLES['rpq_all_suppliers']})",
    "text_any": "SELECT 'c:1' AS source, 'r:' || n_regionkey AS node, 2 AS dist, 'c:1/in_nation/n:' || n_nationkey || '/in_region/r:' || n_regionkey AS path FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_custkey = 1",
    "text_endpoints": "SELECT DISTINCT 'c:1' AS source, 'p:' || l_partkey AS node, 2 AS dist FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey = 1",
    "graph_labels": " UNION ALL ".join(f"SELECT '{n}' AS graph, label, count(*) AS triples FROM ({GRAPH_SQL[n]}) GROUP BY label" for n in ("commerce", "hops", "dialogue", "chain", "weblinks", "corpus", "similarity", "hourly")),
    "words_dialogue": "SELECT conv_id FROM conversations GROUP BY conv_id HAVING regexp_full_match(string_agg(substr(role, 1, 1), '' ORDER BY turn), 's?(ua)*')",
    "udtf_automaton": """SELECT state, label, next_state, final, count(event_type) AS events, count(DISTINCT CASE WHEN event_type IS NOT NULL THEN user_id END) AS users
FROM (VALUES (0, 'view', 0, false), (0, 'click', 1, false), (1, 'purchase', 2, true)) t(state, label, next_state, final) LEFT JOIN events ON event_type = label GROUP BY ALL""",
    "udtf_paths": "SELECT * FROM (VALUES ('n1', 'v/any/n1'), ('n2', 'v/any/n2'), ('n3', 'v/any/n3'), ('n4', 'v/any/n1/any/n4'), ('n4', 'v/any/n2/any/n4'), ('n4', 'v/any/n3/any/n4'), ('n5', 'v/any/n1/any/n4/any/n5'), ('n5', 'v/any/n2/any/n4/any/n5'), ('n5', 'v/any/n3/any/n4/any/n5')) t(node, path)",
    "ladder": "SELECT 'd' || k AS node, (2 * k)::INTEGER AS dist, (1 << k::INTEGER)::BIGINT AS num_paths FROM range(0, 6) t(k)",
    "stream_windows": """WITH e AS (SELECT DISTINCT date_trunc('day', ts) AS d, user_id AS u, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events WHERE event_type = 'click' AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events))
SELECT strftime(a.d, '%Y-%m-%d %H:%M:%S') AS begins, 'u:' || b.u AS node, 2 AS dist, count(*)::BIGINT AS num_paths FROM e a JOIN e b ON a.d = b.d AND a.k = b.k WHERE a.u = 1 GROUP BY a.d, b.u""",
    "stream_sessions": """WITH e AS (SELECT *, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM e)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS begins, count(*)::BIGINT AS events FROM s GROUP BY user_id, n
HAVING regexp_full_match(string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id), 'v*c*') AND max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events)""",
    "stream_chains": """SELECT user_id, count(*) AS events, count(*) FILTER (WHERE regexp_full_match(word, '[vc]*p?')) AS accepted
FROM (SELECT user_id, string_agg(substr(event_type, 1, 1), '') OVER (PARTITION BY user_id ORDER BY ts, event_id) AS word FROM events) GROUP BY user_id""",
    "stream_inserts": ORACLES["rpq_count_suppliers"],
    "stream_sources": "SELECT * FROM (SELECT 'c:' || c_custkey AS source, 'r:' || n_regionkey AS node, 2 AS dist, 1::BIGINT AS num_paths FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT 's:' || s_suppkey, 'r:' || n_regionkey, 2, 1 FROM supplier JOIN nation ON s_nationkey = n_nationkey) WHERE source IN ('s:1', 's:2', 'c:1')",
}
ORACLES["text_count"] = f"SELECT node AS source, 'p:7' AS node, dist, num_paths FROM ({ORACLES['rpq_to_target']})"
