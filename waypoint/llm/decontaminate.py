"""Benchmark passages in documents, by SimHash of item-sized windows, in DataFrame operations alone.

A window of an item's word count that is similar to the item shares a shingle of K words with it (one that shares none has a similarity of 0), so windows are laid
where a shingle of the document meets one of the benchmark: at the places where the two shingles come to lie on
each other. An item of fewer than K words is one shingle, the whole, and documents are cut into shingles of that many words too. Windows and items get 64-bit
SimHash fingerprints of their weighted shingles. A multi-index finds all fingerprints within RADIUS bits: of PARTS parts of a fingerprint one differs in RADIUS / PARTS
bits at most, so the windows' parts with up to half of those bits turned and the items' parts with up to the other half turned meet in a join on
(word count, part, bits); windows of one content are looked up once. The pairs that it yields are verified by their exact weighted Jaccard similarity.
A shingle's weight falls with the number of items that have it, so what many items share counts less.

Up to MOST_SHINGLES of the benchmark's shingles stand in the filter that picks the documents to cut, which saves a shuffle of all shingles; with a larger benchmark the same documents are
found by a join. Everything of the documents is joined and aggregated. Defined results: null or empty texts meet nothing; items without text or id are found nowhere;
a document shorter than an item is one window; repeated rows are reported alike; a null id is reported as null; several places of one item are
reported once, at the best; an empty table gives an empty result; extra columns stay in :func:`decontaminated`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from waypoint.llm.store import kept

K = 5
LEAST = 0.8
RADIUS = 19
PARTS = 4
_BITS = 64
#: Benchmark shingles that a filter may hold; a larger benchmark is joined.
MOST_SHINGLES = 50_000


def _clean(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[\x20\x09-\x0D]+", " "))


def _n_words(clean: Column) -> Column:
    return F.when(clean == "", 0).otherwise(F.length(clean) - F.length(F.replace(clean, F.lit(" "), F.lit(""))) + 1)


def shingle_texts(clean: Column, k: int = K) -> Column:
    """All k-word shingles of a cleaned text in order; a shorter one is a shingle itself."""
    pattern = "(?= (" + " ".join(["[^ ]+"] * k) + "))"
    all_of = F.regexp_extract_all(F.concat(F.lit(" "), clean), F.lit(pattern), F.lit(1))
    return F.when(clean == "", F.array().cast("array<string>")).when(_n_words(clean) < k, F.array(clean)).otherwise(all_of)


def _fingerprint(h: Column, w: Column) -> list[Column]:
    return [F.sum(F.when(F.shiftright(h, b).bitwiseAND(1) == 1, w).otherwise(-w)).alias(f"b{b}") for b in range(_BITS)]


def _packed(names=None) -> Column:
    out = F.lit(0).cast("long")
    for b in range(_BITS):
        out = out.bitwiseOR(F.shiftleft(F.when(F.col(f"b{b}") > 0, F.lit(1)).otherwise(F.lit(0)).cast("long"), b))
    return out


def _parts(print_: Column, turned: int) -> Column:
    """``part, value``: every part of a fingerprint with up to ``turned`` of its bits turned."""
    width = _BITS // PARTS
    masks = [m for m in range(1 << width) if m.bit_count() <= turned]
    part = F.array(*[F.struct(F.lit(p).alias("part"), F.shiftrightunsigned(print_, p * width).bitwiseAND(F.lit((1 << width) - 1).cast("long")).cast("int").alias("value")) for p in range(PARTS)])
    return F.flatten(F.transform(part, lambda x: F.transform(F.array(*[F.lit(m) for m in masks]), lambda m: F.struct(x["part"].alias("part"), x["value"].bitwiseXOR(m).alias("value")))))


def near_prints(windows: DataFrame, items: DataFrame, radius: int) -> DataFrame:
    """``n, print, item_id, distance`` of all pairs of equal word count whose fingerprints are within ``radius`` bits; ``windows``: n, print, ``items``: item_id, n, item_print."""
    per = radius // PARTS
    mine = windows.select("n", "print", F.explode(_parts(F.col("print"), (per + 1) // 2)).alias("x")).select("n", "print", "x.*")
    theirs = items.select("item_id", "n", "item_print", F.explode(_parts(F.col("item_print"), per // 2)).alias("x")).select("item_id", "n", "item_print", "x.*")
    near = mine.join(theirs, ["n", "part", "value"]).withColumn("distance", F.bit_count(F.col("print").bitwiseXOR(F.col("item_print")))).filter(F.col("distance") <= radius)
    return near.select("n", "print", "item_id", "distance").distinct()


def _spots(clean: Column, k: int, short: list[int]) -> Column:
    """``p, h``: place and hash of every shingle of k words, and of every one of as many words as a short item has."""
    lists = [shingle_texts(clean, k)] + [F.when(_n_words(clean) >= n, shingle_texts(clean, n)).otherwise(F.array().cast("array<string>")) for n in short]
    return F.flatten(F.array(*[F.transform(x, lambda s, p: F.struct(p.alias("p"), F.xxhash64(s).alias("h"))) for x in lists]))


def touched(words: DataFrame, items: DataFrame, k: int, short: list[int]) -> DataFrame:
    """The texts that share a shingle with an item, written. Up to MOST_SHINGLES of the benchmark stand in the
    filter itself, so that no text is shuffled; beyond that the texts are found by a join of shingles."""
    known = [r["h"] for r in items.select("h").distinct().limit(MOST_SHINGLES + 1).collect()]
    if not known:
        return words.limit(0)
    if len(known) <= MOST_SHINGLES:
        listed = ", ".join(f"{h}L" if h > -(2**63) else "bigint('-9223372036854775808')" for h in known)
        return kept(words.withColumn("sh", _spots(F.col("t"), k, short)).filter(F.expr(f"exists(sh, s -> s.h IN ({listed}))")).drop("sh"), "dc-touched")
    spots = words.select("doc_id", F.explode(_spots(F.col("t"), k, short)).alias("s")).select("doc_id", "s.h")
    hit = spots.join(items.select("h").distinct(), "h", "left_semi").select(F.col("doc_id").alias("hit_id")).distinct().hint("shuffle_hash")
    return kept(words.join(hit, F.col("doc_id").eqNullSafe(F.col("hit_id")), "left_semi"), "dc-touched")


def leaks(docs: DataFrame, items: DataFrame, least: float = LEAST, radius: int = RADIUS, k: int = K) -> DataFrame:
    """``doc_id, item_id, start`` (word number), ``distance`` and ``similarity`` of every document with a window like an item."""
    items = items.filter("item_id is not null").select("item_id", _clean(F.col("text")).alias("t")).filter("t <> ''").select("item_id", _n_words(F.col("t")).alias("n"), F.posexplode(shingle_texts(F.col("t"), k)).alias("q", "s"))
    items = kept(items.select("item_id", "n", "q", F.xxhash64("s").alias("h")), "dc-items")
    short = sorted(r["n"] for r in items.filter(F.col("n") < k).select("n").distinct().collect())  # k - 1 lengths at most
    total = F.lit(items.select("item_id").distinct().count())
    weights = items.groupBy("h").agg(F.count_distinct("item_id").alias("df")).select("h", F.round(4 * (1 + F.log2(total / F.col("df")))).cast("long").alias("w"))
    heaviest = F.round(4 * (1 + F.log2(total))).cast("long")
    sets = items.select("item_id", "n", "h").distinct().join(weights, "h")
    known = sets.groupBy("item_id", "n").agg(F.collect_list("h").alias("hs"), F.map_from_entries(F.collect_list(F.struct("h", "w"))).alias("ws"), F.sum("w").alias("weight"), *_fingerprint(F.col("h"), F.col("w")))
    known = kept(known.select("item_id", "n", "hs", "ws", "weight", _packed().alias("item_print")), "dc-known")

    # where shingles of documents meet those of items
    words = touched(docs.select("doc_id", _clean(F.col("text")).alias("t")), items, k, short)
    words = words.withColumn("row", F.md5(F.col("t").cast("binary")))
    spots = words.select("row", "t").distinct().select("row", F.explode(_spots(F.col("t"), k, short)).alias("s")).select("row", "s.p", "s.h")
    met = spots.join(items, "h").select("row", "n", (F.col("p") - F.col("q")).alias("start"))
    windows = kept(met.distinct(), "dc-windows")
    of = windows.groupBy("row").agg(F.collect_set(F.struct("n", "start")).alias("spots"))
    texts = words.select("row", "t").distinct().join(of, "row").select("row", _n_words(F.col("t")).alias("len"), "t", "spots")
    size = F.greatest(F.lit(1), F.col("spot.n") - (k - 1))
    start = F.greatest(F.lit(0), F.least(F.col("spot.start"), F.col("len") - F.col("spot.n"))).cast("int")
    hashed = lambda n: F.transform(shingle_texts(F.col("t"), n), lambda s: F.xxhash64(s))
    texts = texts.select("row", "len", hashed(k).alias("sh"), *[hashed(n).alias(f"sh{n}") for n in short], F.explode("spots").alias("spot")).withColumn("start", start)
    hs = F.array_distinct(F.slice("sh", F.col("start") + 1, size.cast("int")))
    for n in short:
        hs = F.when((F.col("spot.n") == n) & (F.col("len") >= n), F.array(F.get(f"sh{n}", F.col("start")))).otherwise(hs)
    cut = kept(texts.select("row", F.col("spot.n").alias("n"), "start", hs.alias("hs")).dropDuplicates(["row", "n", "start", "hs"]), "dc-cut")
    bits = cut.select("row", "n", "start", F.explode("hs").alias("h")).join(weights, "h", "left").withColumn("w", F.coalesce("w", heaviest))
    prints = bits.groupBy("row", "n", "start").agg(F.sum("w").alias("weight"), *_fingerprint(F.col("h"), F.col("w"))).select("row", "n", "start", "weight", _packed().alias("print"))

    mine = kept(prints, "dc-prints")
    near = near_prints(mine.select("n", "print").distinct(), known.select("item_id", "n", "item_print"), radius)
    near = mine.join(near, ["n", "print"]).select("row", "n", "start", "weight", "item_id", "distance")
    both = near.join(cut, ["row", "n", "start"]).join(known.select("item_id", F.col("hs").alias("item_hs"), "ws", F.col("weight").alias("item_weight")), "item_id")
    common = F.aggregate(F.transform(F.array_intersect("hs", "item_hs"), lambda h: F.col("ws")[h]), F.lit(0).cast("long"), lambda a, x: a + x)
    both = both.withColumn("common", common).withColumn("similarity", F.col("common") / (F.col("weight") + F.col("item_weight") - F.col("common"))).filter(F.col("similarity") >= least)
    best = both.groupBy("row", "item_id").agg(F.max(F.struct("similarity", -F.col("start"), -F.col("distance"))).alias("b"))
    best = best.select("row", "item_id", (-F.col("b.col2")).alias("start"), (-F.col("b.col3")).alias("distance"), "b.similarity")
    return words.select("doc_id", "row").distinct().join(best, "row").select("doc_id", "item_id", "start", "distance", "similarity")


def decontaminated(docs: DataFrame, items: DataFrame, **how) -> DataFrame:
    """The rows of ``docs`` without a benchmark passage, with all columns; rows of null id stay."""
    gone = leaks(docs.filter("doc_id is not null"), items, **how).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
