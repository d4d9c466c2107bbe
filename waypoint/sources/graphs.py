"""Labelled graphs (sets of ``src, label, dst`` triples) built from the given tables.

Inside the engine a node is a 64-bit number. Where nodes are a kind and a whole number the number is worked out from both in an
expression (no dictionary, no shuffle); other names get numbers from a written dictionary.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from waypoint.plans.storage import written

_KEY_BITS = 56


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


@dataclass(frozen=True)
class Packed:
    """Numbers of nodes named by a kind's prefix and a whole number from 0 to 2^56 - 1: the kind's place above the number."""

    prefixes: tuple[str, ...] = ("",)

    def id(self, prefix: str, key) -> Column:
        key = F.col(key) if isinstance(key, str) else key
        return F.shiftleft(F.lit(self.prefixes.index(prefix)).cast("long"), _KEY_BITS).bitwiseOR(key.cast("long"))

    def shown_column(self, id_: Column) -> Column:
        kind, key = F.shiftrightunsigned(id_, _KEY_BITS).cast("int"), id_.bitwiseAND(F.lit((1 << _KEY_BITS) - 1))
        return F.concat(F.get(F.array(*[F.lit(p) for p in self.prefixes]), kind), key.cast("string"))

    def shown(self, df: DataFrame, columns: Iterable[str]) -> DataFrame:
        return df.withColumns({c: F.transform(c, self.shown_column) if df.schema[c].dataType.typeName() == "array" else self.shown_column(F.col(c)) for c in columns})

    def numbered(self, df: DataFrame, column: str) -> DataFrame:
        text = F.col(column)
        by = [F.when(text.rlike(f"^{p}[0-9]+$"), self.id(p, F.substr(text, F.lit(len(p) + 1)))) for p in self.prefixes]
        return df.withColumn(column, F.coalesce(*by)).filter(F.col(column).isNotNull())


@dataclass(frozen=True)
class Turns:
    """Numbers of nodes named ``a:b``, two whole numbers: a above 20 bits of b."""

    def id(self, a: Column, b: Column) -> Column:
        return F.shiftleft(a.cast("long"), 20).bitwiseOR(b.cast("long"))

    def shown_column(self, id_: Column) -> Column:
        return F.concat_ws(":", F.shiftright(id_, 20).cast("string"), id_.bitwiseAND(F.lit((1 << 20) - 1)).cast("string"))

    shown = Packed.shown

    def numbered(self, df: DataFrame, column: str) -> DataFrame:
        parts = F.split(F.col(column), ":")
        return df.filter(F.col(column).rlike("^[0-9]+:[0-9]+$")).withColumn(column, self.id(F.get(parts, F.lit(0)), F.get(parts, F.lit(1))))


@dataclass(frozen=True)
class Dictionary:
    """Numbers of any names, from a written table ``id, key``."""

    table: DataFrame

    def shown(self, df: DataFrame, columns: Iterable[str]) -> DataFrame:
        for c in columns:
            names = self.table.select(F.col("id").alias("_id"), F.col("key").alias("_key"))
            if df.schema[c].dataType.typeName() != "array":
                df = df.join(names, df[c] == names["_id"]).withColumn(c, F.col("_key")).drop("_id", "_key")
                continue
            row = df.withColumn("_row", F.monotonically_increasing_id())
            row = written(row, "shown")
            each = row.select("_row", F.posexplode(c).alias("_at", "_id")).join(names, "_id").groupBy("_row").agg(F.array_sort(F.collect_list(F.struct("_at", "_key"))).alias("_l"))
            df = row.join(each, "_row", "left").withColumn(c, F.coalesce(F.col("_l._key"), F.array().cast("array<string>"))).drop("_row", "_l")
        return df

    def numbered(self, df: DataFrame, column: str) -> DataFrame:
        names = self.table.select(F.col("id").alias("_id"), F.col("key").alias("_key"))
        return df.join(names, df[column] == names["_key"]).withColumn(column, F.col("_id")).drop("_id", "_key")


@dataclass(frozen=True)
class LabelledGraph:
    """``edges`` (src, label, dst) with numbers for nodes (repeats allowed until :meth:`distinct`), and how nodes are named."""

    edges: DataFrame
    ids: Packed | Turns | Dictionary

    @classmethod
    def from_edges(cls, triples: DataFrame) -> LabelledGraph:
        """A graph of string triples; names get numbers from a dictionary, in the order of the names."""
        triples = triples.filter("src is not null and label is not null and dst is not null").distinct()
        names = triples.select(F.explode(F.array("src", "dst")).alias("key")).distinct()
        table = written(names.orderBy("key").select(F.monotonically_increasing_id().alias("id"), "key"), "names")
        ids = Dictionary(table)
        return cls(ids.numbered(ids.numbered(triples, "src"), "dst").select("src", "label", "dst"), ids)

    def _with(self, edges: DataFrame) -> LabelledGraph:
        return replace(self, edges=edges)

    def inverted(self) -> LabelledGraph:
        return self._with(self.edges.select(F.col("dst").alias("src"), F.concat(F.lit("^"), "label").alias("label"), F.col("src").alias("dst")))

    def with_inverses(self) -> LabelledGraph:
        """With each triple walked backwards under ``^label``."""
        return self._with(self.edges.unionByName(self.inverted().edges))

    def reversed(self) -> LabelledGraph:
        """Every triple turned round, under its own label."""
        return self._with(self.edges.select(F.col("dst").alias("src"), "label", F.col("src").alias("dst")))

    def unlabelled(self, label: str = "any") -> LabelledGraph:
        return self._with(self.edges.select("src", F.lit(label).alias("label"), "dst"))

    def labels(self, labels: Iterable[str]) -> LabelledGraph:
        return self._with(self.edges.filter(F.col("label").isin(sorted(labels))))

    def where_edges(self, predicate: Column | str) -> LabelledGraph:
        return self._with(self.edges.filter(predicate))

    def where_nodes(self, names: DataFrame) -> LabelledGraph:
        """The subgraph of the nodes named in the one column of ``names``."""
        wanted = self.ids.numbered(names.toDF("node").distinct(), "node")
        ends = self.edges.join(wanted.withColumnRenamed("node", "src"), "src", "left_semi")
        return self._with(ends.join(wanted.withColumnRenamed("node", "dst"), "dst", "left_semi"))

    def without_loops(self) -> LabelledGraph:
        return self._with(self.edges.filter("src <> dst"))

    def distinct(self) -> LabelledGraph:
        return self._with(self.edges.distinct())

    def stored(self, name: str = "graph") -> LabelledGraph:
        """Written once, so that searches do not build it again."""
        return self._with(written(self.edges.distinct(), name))

    def nodes(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()

    def alphabet(self) -> list[str]:
        return [r[0] for r in self.edges.select("label").distinct().collect()]  # one row a label

    def triples(self) -> DataFrame:
        """Distinct triples with the nodes' names."""
        return self.ids.shown(self.edges.distinct(), ["src", "dst"]).select("src", "label", "dst")


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts).filter("src is not null and dst is not null")


def commerce(spark: SparkSession, sf_dir: str, shipped: tuple[str, str] | None = None) -> LabelledGraph:
    """``shipped``: only lines shipped from the first date to before the second (pushed to the scan)."""
    ids = Packed(("c:", "s:", "p:", "o:", "n:", "r:"))

    def part(table: str, a: str, src: str, label: str, b: str, dst: str) -> DataFrame:
        rows = read(spark, sf_dir, table)
        if shipped and table == "lineitem":
            rows = rows.filter((F.col("l_shipdate") >= F.lit(shipped[0])) & (F.col("l_shipdate") < F.lit(shipped[1])))
        return rows.select(ids.id(a, src).alias("src"), F.lit(label).alias("label"), ids.id(b, dst).alias("dst"))

    return LabelledGraph(_union([
        part("orders", "c:", "o_custkey", "placed", "o:", "o_orderkey"), part("lineitem", "o:", "l_orderkey", "contains", "p:", "l_partkey"),
        part("lineitem", "s:", "l_suppkey", "supplies", "p:", "l_partkey"), part("customer", "c:", "c_custkey", "in_nation", "n:", "c_nationkey"),
        part("supplier", "s:", "s_suppkey", "in_nation", "n:", "s_nationkey"), part("nation", "n:", "n_nationkey", "in_region", "r:", "n_regionkey"),
    ]), ids)


def hops_of(events: DataFrame, hourly: bool = False) -> DataFrame:
    """From the key of a user's event to that of the next one; the label is the later event's type."""
    k = F.get_json_object("props", "$.k").cast("long")
    node = k * 24 + F.hour("ts") if hourly else k
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = events.withColumn("node", node)
    return e.select(F.lag("node").over(w).alias("src"), F.col("event_type").alias("label"), F.col("node").alias("dst")).filter("src is not null and dst is not null and label is not null")


def event_hops(spark: SparkSession, sf_dir: str, hourly: bool = False, as_of: str | None = None) -> LabelledGraph:
    """``as_of``: only events up to that time."""
    events = read(spark, sf_dir, "events")
    return LabelledGraph(hops_of(events.filter(F.col("ts") <= F.lit(as_of)) if as_of else events, hourly), Packed())


def event_chain(spark: SparkSession, sf_dir: str) -> LabelledGraph:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = read(spark, sf_dir, "events")
    return LabelledGraph(e.select(F.lag("event_id").over(w).alias("src"), F.col("event_type").alias("label"), F.col("event_id").alias("dst")).filter("src is not null"), Packed())


def dialogue(spark: SparkSession, sf_dir: str) -> LabelledGraph:
    """Each turn leads to the next; the label is the role of the turn being left."""
    ids, c = Turns(), read(spark, sf_dir, "conversations")
    return LabelledGraph(c.select(ids.id(F.col("conv_id"), F.col("turn")).alias("src"), F.col("role").alias("label"), ids.id(F.col("conv_id"), F.col("turn") + 1).alias("dst")), ids)


def weblinks(spark: SparkSession, sf_dir: str) -> LabelledGraph:
    p = read(spark, sf_dir, "pages")
    hrefs = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    return LabelledGraph.from_edges(p.select(F.regexp_extract("url", "://([^/]*)", 1).alias("src"), F.lit("links").alias("label"), hrefs.alias("dst")))


def quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``doc_id, item_id`` where the lower-cased text holds the lower-cased passage, without comparing all pairs.

    A passage's longest word is its key (words are runs other than space, tab and line ends); a text that holds the passage holds that word, or one that ends
    with it or begins with it where the passage begins or ends within a word. So a passage's inner words alone serve as keys; a passage without
    an inner word is compared by its whole text, and there are as many of those as short items in the benchmark.
    """
    word = r"[^ \t\n\r]+"
    items = read(spark, sf_dir, "benchmark").select("item_id", F.lower("text").alias("passage")).filter("passage <> ''")
    inner = F.expr("slice(ws, 2, greatest(size(ws) - 2, 0))")
    items = items.withColumn("ws", F.regexp_extract_all("passage", F.lit(word), F.lit(0))).withColumn("inner", inner)
    longest = F.aggregate("inner", F.lit(""), lambda a, x: F.when(F.length(x) > F.length(a), x).otherwise(a))
    items = items.withColumn("key", longest).select("item_id", "passage", "key")
    docs = read(spark, sf_dir, "documents").select("doc_id", F.lower("text").alias("t")).filter("t is not null")
    keyed = items.filter("key <> ''")
    words = docs.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all("t", F.lit(word), F.lit(0)))).alias("key"))
    found = words.join(keyed.select("key", "item_id"), "key").select("doc_id", "item_id")
    held = found.join(docs, "doc_id").join(keyed.select("item_id", "passage"), "item_id").filter(F.contains("t", "passage")).select("doc_id", "item_id")
    short = items.filter("key = ''").groupBy().agg(F.collect_list(F.struct("item_id", "passage")).alias("short"))
    # one row of short passages, sent along with every text
    few = docs.join(F.broadcast(short)).select("doc_id", F.explode(F.filter("short", lambda s: F.contains(F.col("t"), s["passage"]))).alias("s")).select("doc_id", "s.item_id")
    return held.unionByName(few).distinct()


def corpus(spark: SparkSession, sf_dir: str, with_quotes: bool = False) -> LabelledGraph:
    d, lab = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")

    def part(rows: DataFrame, label: str, prefix: str, dst: str) -> DataFrame:
        return rows.select(F.concat(F.lit("d:"), F.col("doc_id").cast("string")).alias("src"), F.lit(label).alias("label"), F.concat(F.lit(prefix), F.col(dst).cast("string")).alias("dst"))

    parts = [part(d, "in_lang", "lang:", "lang"), part(d, "from_source", "src:", "source"), part(lab, "rated", "quality:", "quality"), part(lab, "flagged", "toxic:", "toxic")]
    if with_quotes:
        parts.append(part(quotes(spark, sf_dir), "quotes", "b:", "item_id"))
    return LabelledGraph.from_edges(_union(parts))


def similarity(spark: SparkSession, sf_dir: str, k: int = 5, cells: int | None = None, probes: int = 8) -> LabelledGraph:
    """From each vector to its ``k`` best others by cosine, ties by id; label ``same`` or ``cross`` by the vectors' labels.

    Without ``cells`` every vector is compared with all, blocks of queries against blocks of vectors in matrix products (exact; for
    tables of up to some 100,000 vectors). With ``cells`` vectors are dealt to that many cells by their nearest centre, a sample of the vectors, and each is compared
    with those of the ``probes`` cells nearest to it.
    """
    from waypoint.operators.neighbours import nearest

    v = read(spark, sf_dir, "embeddings")
    near = nearest(v.select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector")), k, cells, probes)
    names = v.select(F.col("vec_id").alias("id"), F.col("label").alias("kind"))
    e = near.join(names.toDF("id", "a"), "id").join(names.toDF("other", "b"), "other")
    return LabelledGraph(e.select(F.col("id").alias("src"), F.when(F.col("a") == F.col("b"), "same").otherwise("cross").alias("label"), F.col("other").alias("dst")), Packed())


def triples(spark: SparkSession, path: str) -> LabelledGraph:
    """A text file of triples, one a line: three names in angle brackets (or ``_:`` names, or quoted literals as the last) and a full stop."""
    name = r"(<[^>]*>|_:\S+)"
    line = rf'^\s*{name}\s+<([^>]*)>\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"\S*)\s*\.\s*(?:#.*)?$'
    bare = lambda c: F.regexp_replace(c, r"^<(.*)>$", "$1")
    rows = spark.read.text(path).filter(F.col("value").rlike(line))
    return LabelledGraph.from_edges(rows.select(bare(F.regexp_extract("value", line, 1)).alias("src"), F.regexp_extract("value", line, 2).alias("label"), bare(F.regexp_extract("value", line, 3)).alias("dst")))


def read_edges(spark: SparkSession, path: str, form: str = "parquet", **options) -> LabelledGraph:
    """A graph from a stored table of ``src, label, dst`` (``parquet``, ``orc``, ``json`` or ``csv`` with a header)."""
    reader = spark.read.format(form).schema("src string, label string, dst string").options(**({"header": True} if form == "csv" else {}) | options)
    return LabelledGraph.from_edges(reader.load(path))


def write_graph(graph: LabelledGraph, path: str, form: str = "parquet", mode: str = "errorifexists") -> None:
    """Triples by name, a folder for each label."""
    graph.triples().repartition("label", "src").write.format(form).mode(mode).partitionBy("label").save(path)


Builder = Callable[[SparkSession, str], LabelledGraph]
