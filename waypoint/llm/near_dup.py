"""Near duplicates: SuperMinHash signatures, banding, verification on full shingle sets, and components.

A signature of M places comes from one random permutation an element: in round j every element draws a place (a
step of a Fisher-Yates shuffle of its own) and bids ``j + uniform`` there; a place keeps the least bid. Ranks within
an element's permutation are all different, which correlates the places and lowers the variance. A text stops as
soon as all its places hold bids under the next round's number: one round is enough for long texts.

Candidates. Texts of equal shingle sets are one class (its smallest id stands for it). Classes that agree in a
band's R places share a bucket, and bucket mates are compared unless they are in one component already. That is
done without emitting all pairs: in a bucket of many members one member leads, the one whose other buckets are the fullest (in a family of
edited copies, that is the text which most of them come from). It is compared with every other member and is then done with, components are found
anew, and once few members are outside a bucket's largest component each of them is compared with all others.

What is still open after the first round is dealt anew by rare shingles: with all shingles in one order, rarest first, two linked sets
share an early one, and the place of the first that they share bounds how much they can have in common. An entry (a text under one of its early shingles)
whose bound no size in its bucket fits is left out, which takes out all texts that are too far from any other; the rest goes on with leaders, the entries of earliest
place first. So no link between different components of bucket mates is lost, whatever the size of the bucket. Every link is confirmed on full sets.

Defined results: a null or empty text (or one without words) has an empty set and is linked with nothing, not
even with another empty one; fewer than K words are one shingle; repeated rows of one id are judged alike; an empty table gives
an empty result; extra columns stay in :func:`deduplicated`. Shingles are told apart by 64-bit hashes.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from waypoint.llm import packed
from waypoint.llm.components import components
from waypoint.llm.store import counted, kept

U64 = np.uint64
PLACES, ROWS = 80, 4
BANDS = PLACES // ROWS
#: With up to PAIRS members outside a bucket's largest component all open pairs are compared; after the first round also
#: where those are up to MOST_PAIRS in all.
PAIRS, MOST_PAIRS = 8, 16384
#: Members that lead in other buckets in the first round; sixteen times as many in each of the next three rounds.
LEADERS = 1


def signatures(hashes: np.ndarray, first: np.ndarray, m: int = PLACES) -> np.ndarray:
    """SuperMinHash signatures of texts whose distinct shingle hashes lie one text after another.

    Bids are 64-bit integers: the round number on top, 56 random bits below. An empty set's are all ones.
    """
    n = len(first) - 1
    sig = np.full((n, m), np.iinfo(np.uint64).max, dtype=U64)
    size = np.diff(first)
    open_texts = np.flatnonzero(size > 0)
    perm = perm_of = None
    for j in range(m):
        if not len(open_texts):
            break
        counts = size[open_texts]
        row = np.repeat(open_texts, counts)
        at = np.repeat(first[open_texts], counts) + np.arange(int(counts.sum())) - np.repeat(np.cumsum(counts) - counts, counts)
        draw = packed.mixed(hashes[at] + U64((0xA0761D6478BD642F * (2 * j + 1)) & 0xFFFFFFFFFFFFFFFF))
        k = (j + (draw >> U64(40)) % U64(m - j)).astype(np.int64)
        if j == 0:
            place = k
        else:
            if perm is None:  # few texts are left: their elements get whole permutations
                perm_of = np.full(len(hashes), -1, dtype=np.int64)
                perm_of[at] = np.arange(len(at))
                perm = np.tile(np.arange(m, dtype=np.uint8 if m <= 256 else np.int32), (len(at), 1))
                d0 = packed.mixed(hashes[at] + U64(0xA0761D6478BD642F))
                k0 = ((d0 >> U64(40)) % U64(m)).astype(np.int64)
                _swap(perm, np.arange(len(at)), 0, k0)
            rows = perm_of[at]
            _swap(perm, rows, j, k)
            place = perm[rows, j].astype(np.int64)
        bid = (U64(j) << U64(56)) | (packed.mixed(draw) >> U64(8))
        np.minimum.at(sig.reshape(-1), row * m + place, bid)
        worst = sig[open_texts].max(axis=1) >> U64(56)
        open_texts = open_texts[worst > U64(j)]
    return sig


def _swap(perm: np.ndarray, rows: np.ndarray, j: int, k: np.ndarray) -> None:
    a, b = perm[rows, j].copy(), perm[rows, k].copy()
    perm[rows, j], perm[rows, k] = b, a


def band_keys(sig: np.ndarray, rows: int = ROWS) -> np.ndarray:
    n, m = sig.shape
    out = np.zeros((n, m // rows), dtype=U64)
    for b in range(m // rows):
        key = np.full(n, b + 1, dtype=U64)
        for r in range(rows):
            key = packed.mixed(key * U64(packed.BASE) + sig[:, b * rows + r])
        out[:, b] = key
    return out


def _sets(column: pa.Array, k: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    raw, off = packed.texts(column)
    for i, j in packed.pieces(off):
        h, doc = packed.word_hashes(raw[off[i] : off[j]], off[i : j + 1] - off[i])
        yield i, j, *packed.shingles(h, doc, j - i, k)


def _lists(values: np.ndarray, first: np.ndarray) -> pa.Array:
    return pa.LargeListArray.from_arrays(pa.array(first, pa.int64()), pa.array(values.view(np.int64))).cast(pa.list_(pa.int64()))


def signed(docs: DataFrame, k: int) -> DataFrame:
    """``doc_id, n_shingles, d1, d2`` (two digests of the set) and ``bands``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, s, first in _sets(batch.column(1), k):
                total = np.concatenate([[U64(0)], np.cumsum(packed.mixed(s), dtype=U64)])
                other = np.concatenate([[U64(0)], np.cumsum(packed.mixed(s ^ U64(0x5851F42D4C957F2D)), dtype=U64)])
                keys = band_keys(signatures(s, first))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(i, j - i), pa.array(np.diff(first)), pa.array((total[first[1:]] - total[first[:-1]]).view(np.int64)),
                        pa.array((other[first[1:]] - other[first[:-1]]).view(np.int64)), _lists(keys.reshape(-1), np.arange(j - i + 1) * keys.shape[1]),
                    ],
                    names=["doc_id", "n_shingles", "d1", "d2", "bands"],
                )

    return docs.select("doc_id", F.col("text").cast("binary").alias("text")).mapInArrow(run, "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>")


def shingle_sets(docs: DataFrame, k: int) -> DataFrame:
    """``doc_id, shingles`` (sorted hashes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, s, first in _sets(batch.column(1), k):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), _lists(s, first)], names=["doc_id", "shingles"])

    return docs.select("doc_id", F.col("text").cast("binary").alias("text")).mapInArrow(run, "doc_id long, shingles array<long>")


def _linked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The ``pairs`` (a, b) whose sets are alike, as links (u, v). Pairs are written first, so few of them are sent to the sets."""
    pairs = kept(pairs.distinct(), "nd-pairs")
    left = sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("sb"))
    inter = F.size(F.array_intersect("sa", "sb")).cast("long")
    both = pairs.join(left, "a").join(right, "b").select("a", "b", inter.alias("inter"), (F.size("sa") + F.size("sb")).cast("long").alias("n"))
    return both.filter(F.col("inter") * 100 >= (F.col("n") - F.col("inter")) * percent).select(F.col("a").alias("u"), F.col("b").alias("v"))


def _most(size: Column, before: Column, percent: int) -> Column:
    """The largest set that one of ``size``, with ``before`` shingles ahead of the first common one, can be linked with."""
    return F.floor((size - before) * (100 + percent) / percent) - size


def by_rare_shingles(buckets: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Buckets of many unlike members (those that share a long common passage, say) dealt anew, by rare shingles.

    With all shingles in one order, rarest first, two sets of n shingles or more that are alike share one of the
    first n - ceil(percent * n) + 1 of each: so no link between the members is lost, and what many share seldom comes first.
    """
    members = buckets.select("doc_id", "size", "c").distinct()
    each = sets.join(members, "doc_id").select("doc_id", "size", "c", F.explode("shingles").alias("s"))
    often = each.groupBy("s").agg(F.count("*").alias("df"))
    listed = each.join(often, "s").groupBy("doc_id", "size", "c").agg(F.array_sort(F.collect_list(F.struct("df", "s"))).alias("l"))
    first = F.slice("l", F.lit(1), (F.col("size") - F.ceil(F.col("size") * percent / 100) + 1).cast("int"))
    dealt = listed.select("doc_id", "size", "c", F.posexplode(first).alias("before", "x")).filter("x.df > 1")
    entries = dealt.select(F.col("x.s").alias("bucket"), "doc_id", "size", "c", F.col("before").cast("long"))
    return viable(kept(entries.withColumn("rank", -F.col("before")), "nd-entries"), percent)


def viable(entries: DataFrame, percent: int) -> DataFrame:
    """The entries that some size in their bucket fits, by a table of the bucket's sizes and the largest partner that each size allows."""
    reach = entries.select("bucket", "size", _most(F.col("size"), F.col("before"), percent).alias("most")).groupBy("bucket", "size").agg(F.max("most").alias("most"), F.count("*").alias("n"))
    kinds = entries.select("bucket", "size", "before").distinct().withColumn("reach", _most(F.col("size"), F.col("before"), percent))
    other = reach.select("bucket", F.col("size").alias("other"), "most", "n")
    fits = (F.col("other") <= F.col("reach")) & (F.col("most") >= F.col("size")) & ((F.col("other") != F.col("size")) | (F.col("n") > 1))
    good = kinds.join(other, (kinds["bucket"] == other["bucket"]) & fits, "left_semi").select("bucket", "size", "before")
    return entries.join(good, ["bucket", "size", "before"], "left_semi").select(*entries.columns)


def linked_classes(classes: DataFrame, docs: DataFrame, k: int, percent: int, rounds: int = 40) -> DataFrame:
    """``node, component`` of the classes that a verified link joins to another, by all links between bucket mates.

    It goes on until no bucket is open: each round settles a member of every open bucket at least. After ``rounds`` rounds
    the number that lead doubles each round, so a bucket of any size is done with in few more.
    """
    members = classes.filter("n_shingles > 0").select("doc_id", F.col("n_shingles").alias("size"), F.posexplode("bands").alias("band", "key"))
    shared = members.groupBy("band", "key").agg(F.count("*").alias("n")).filter("n > 1")
    buckets = kept(members.join(shared, ["band", "key"]).select(F.xxhash64("band", "key").alias("bucket"), "doc_id", "size", "n"), "nd-shared")
    fullest = buckets.groupBy("doc_id").agg(F.sum("n").alias("rank"))
    buckets = buckets.join(fullest, "doc_id").select("bucket", "doc_id", "size", F.col("doc_id").alias("c"), F.lit(0).cast("long").alias("before"), "rank")
    buckets = kept(buckets, "nd-buckets")
    # the ids are the hashed side, so texts pass by unsorted
    sets = kept(shingle_sets(docs.select("doc_id", "text").join(buckets.select("doc_id").distinct().hint("shuffle_hash"), "doc_id", "left_semi"), k), "nd-sets")
    comp = None
    for turn in itertools.count():
        # the largest component of each bucket, and how many members are outside it
        parts = buckets.groupBy("bucket", "c").agg(F.count("*").alias("n"))
        main = parts.groupBy("bucket").agg(F.sum("n").alias("n"), F.max(F.struct("n", "c")).alias("m")).select("bucket", "n", F.col("m.c").alias("main"), (F.col("n") - F.col("m.n")).alias("outside"))
        most = MOST_PAIRS if turn else PAIRS * PAIRS
        main = main.withColumn("final", (F.col("outside") <= PAIRS) | (F.col("outside") * F.col("n") <= most))
        sized = buckets.join(main.filter("outside > 0"), "bucket")
        outer = sized.filter(F.col("c") != F.col("main"))
        last = outer.filter("final").select("bucket", F.col("doc_id").alias("a"), F.col("c").alias("ca"), F.col("size").alias("sa"), F.col("before").alias("ba"))
        # a bucket with many members outside: some of those are compared with all and are then done with
        leaders = LEADERS * 4 ** min(2 * turn, 6) * 2 ** min(max(turn - rounds, 0), 40)
        lots = outer.filter("not final").groupBy("bucket", F.pmod(F.xxhash64("doc_id", F.lit(turn)), F.lit(leaders)).alias("lot"))
        led = lots.agg(F.max(F.struct("rank", "doc_id", "c", "size", "before")).alias("l")).select("bucket", F.col("l.doc_id").alias("a"), F.col("l.c").alias("ca"), F.col("l.size").alias("sa"), F.col("l.before").alias("ba"))
        led, n_led = counted(led, "nd-leaders")
        # sets of too different sizes can't be alike, nor can those whose first common shingle in the order of the buckets has too few after it
        common = F.least(F.col("sa") - F.col("ba"), F.col("size") - F.col("before"))
        alike = (F.col("ca") != F.col("c")) & (common * (100 + percent) >= (F.col("sa") + F.col("size")) * percent)
        pairs = last.unionByName(led).join(buckets, "bucket").filter(alike).select(F.least("a", "doc_id").alias("a"), F.greatest("a", "doc_id").alias("b"))
        links = _linked(pairs, sets, percent)
        if comp is not None:
            links = links.unionByName(comp.filter("node <> component").select(F.col("node").alias("u"), F.col("component").alias("v")))
        comp = kept(components(links), "nd-components")
        if not n_led:
            return comp
        rest = sized.filter("not final").select("bucket", "doc_id", "size", "before", "rank").join(led.select("bucket", F.col("a").alias("doc_id")), ["bucket", "doc_id"], "left_anti")
        rest = rest.join(comp, rest["doc_id"] == comp["node"], "left").select("bucket", "doc_id", "size", F.coalesce("component", "doc_id").alias("c"), "before", "rank")
        buckets = kept(rest, "nd-buckets")
        if not turn:
            buckets = kept(by_rare_shingles(buckets, sets, percent), "nd-buckets")


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` of every document; linked means 100 * intersection >= percent * union."""
    signs = kept(signed(docs, k), "nd-signs")
    alone = (F.col("n_shingles") == 0) | F.col("doc_id").isNull()
    keys = ["n_shingles", "d1", "d2"]
    classes = kept(signs.filter(~alone).groupBy(*keys).agg(F.min("doc_id").alias("doc_id"), F.first("bands").alias("bands")), "nd-classes")
    comp = linked_classes(classes, docs, k, percent)
    named = classes.select(*keys, F.col("doc_id").alias("node")).join(comp, "node", "left").select(*keys, F.coalesce("component", "node").alias("component_id"))
    joined = signs.filter(~alone).drop("bands").join(named, keys).select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))
    return joined.unionByName(signs.filter(alone).select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"), F.lit(True).alias("kept")))


def deduplicated(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """One document of each component, the one of the smallest id, with all columns; rows of null id stay."""
    gone = near_duplicates(docs.filter("doc_id is not null"), k, percent).filter(~F.col("kept")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
