"""Mixing sources to target weights by entropy balancing, in DataFrame operations alone.

Each document gets an inclusion rate between 0 and ``cap``. Among all rates that meet a source's token
target, entropy balancing picks those nearest to the untilted rate cap/2 in bounded (binary) entropy:
``rate = cap * sigmoid(lambda_source * size / scale_source)``. That is an exponential tilt of the odds; a plain exponential tilt of the rates would
pass the cap. The dual is convex with one unknown for each
source, and Newton's steps solve it from sums over (source, size) counts, kept as a table. Rates are rounded
to whole copies by a fixed hash of the row; a threshold for each source, read off a histogram of a fixed
number of bins, puts the sum of copies near the target, and what is still missing or too much (a few long documents may weigh a source down) is made up by
single documents: in each of FLIPS rounds the one whose size comes nearest to the rest is taken once more or once less, if that helps.

Edge cases: a null text has size 0; a null source is a source of its own, after all others; documents of size
0 are taken 0 times; an empty table gives an empty result. Repeated rows, also of one id in several sources, are mixed one by one (ties of the
hash share a bin). Null ids are mixed like others. Extra columns are passed through by :func:`mixed_documents` and ignored by the query. Sources are ranked in one task, a row a source.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from waypoint.llm.store import kept

#: Runs of other characters than the six of white space.
WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (3, 1, 2)
BINS = 4096
FLIPS = 3


def word_count(text) -> F.Column:
    return F.coalesce(F.size(F.regexp_extract_all(text, F.lit(WORD), F.lit(0))), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """Targets of the sources (``source, source_size, target``), by water-filling under ``cap`` x size.

    Resharing an excess by weight until no source is above its stop ends at the level L at which the sum
    of min(cap * size, weight * L) is the total; sources stop in order of cap * size / weight.
    """
    rank = Window.orderBy(F.col("source").asc_nulls_last())
    choices = F.array(*[F.lit(float(w)) for w in weights])
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("w", F.element_at(choices, ((F.row_number().over(rank) - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("stop", F.col("source_size") * F.lit(float(cap)))
    by_level = Window.orderBy((F.col("stop") / F.col("w")).asc(), F.col("source").asc_nulls_last())
    earlier, later = by_level.rowsBetween(Window.unboundedPreceding, -1), by_level.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    s = s.withColumn("left", F.sum("source_size").over(whole) * F.lit(float(share)) - F.coalesce(F.sum("stop").over(earlier), F.lit(0.0)))
    s = s.withColumn("level", F.col("left") / F.sum("w").over(later))
    s = s.withColumn("place", F.row_number().over(by_level))
    first_open = F.min(F.when(F.col("stop") > F.col("w") * F.col("level"), F.struct("place", "level"))).over(whole)
    s = s.withColumn("open_level", first_open["level"])
    target = F.least(F.col("stop"), F.coalesce(F.col("w") * F.col("open_level"), F.col("stop")))
    return s.select("source", "source_size", target.alias("target"))


def _rate(cap: float):
    z = F.greatest(F.least(F.col("lam") * F.col("size") / F.col("scale"), F.lit(700.0)), F.lit(-700.0))
    return F.when(F.col("full"), F.lit(cap)).otherwise(F.lit(cap) / (F.lit(1.0) + F.exp(-z)))


def balanced(counts: DataFrame, targets: DataFrame, cap: float, steps: int = 40, close: float = 1e-4) -> DataFrame:
    """Newton's iterations for every source at once: ``source, lam, scale, full``.

    ``counts`` has ``source, size, n``. The sum is monotone in lambda; the step is kept inside the bracket
    found so far, and halves it where Newton would leave it.
    """
    per = counts.groupBy("source").agg((F.sum(F.col("size") * F.col("n")) / F.greatest(F.sum("n"), F.lit(1))).alias("scale"))
    state = targets.alias("t").join(per.alias("p"), F.col("t.source").eqNullSafe(F.col("p.source"))).select("t.*", "p.scale")
    state = state.select(
        "source", "target", F.when(F.col("scale") > 0, F.col("scale")).otherwise(1.0).alias("scale"),
        (F.col("target") >= F.col("source_size") * F.lit(cap * (1 - 1e-9))).alias("full"),
        F.lit(0.0).alias("lam"), F.lit(-1e4).alias("low"), F.lit(1e4).alias("high"), F.lit(False).alias("done"),
    )
    state = kept(state, "mix-state")
    for _ in range(steps):
        rate = _rate(cap)
        sums = (
            counts.alias("c").join(state.alias("s"), F.col("c.source").eqNullSafe(F.col("s.source")))
            .select("s.source", "size", "n", "lam", "scale", "full")
            .groupBy("source").agg(
                F.sum(rate * F.col("size") * F.col("n")).alias("got"),
                F.sum(rate * (1 - rate / F.lit(cap)) * F.col("size") * F.col("size") / F.col("scale") * F.col("n")).alias("slope"),
            )
        )
        state = state.alias("s").join(sums.alias("g"), F.col("s.source").eqNullSafe(F.col("g.source")), "left").select("s.*", "got", "slope")
        off = F.col("got") - F.col("target")
        state = state.withColumn("done", F.col("full") | F.col("got").isNull() | (F.abs(off) <= F.greatest(F.col("target") * close, F.lit(0.5))))
        state = state.withColumn("low", F.when(off < 0, F.col("lam")).otherwise(F.col("low"))).withColumn("high", F.when(off > 0, F.col("lam")).otherwise(F.col("high")))
        newton = F.col("lam") - (F.col("got") - F.col("target")) / F.greatest(F.col("slope"), F.lit(1e-12))
        inside = (newton > F.col("low")) & (newton < F.col("high"))
        state = state.withColumn("lam", F.when(F.col("done"), F.col("lam")).when(inside, newton).otherwise((F.col("low") + F.col("high")) / 2)).drop("got", "slope")
        state = kept(state, "mix-state")
        if state.filter(~F.col("done")).isEmpty():
            break
    return state.select("source", "target", "lam", "scale", "full")


def mix(docs: DataFrame, weights=WEIGHTS, share: float = 1.5, cap: float = 2.0, key: str = "doc_id") -> DataFrame:
    """``doc_id, size, source_size, target, rate, copies, taken`` of every row of ``docs``."""
    rows = docs.select(F.col(key).alias("doc_id"), F.col("source"), word_count(F.col("text")).alias("size"), F.monotonically_increasing_id().alias("row"))
    return _mixed(kept(rows, "mix-sizes"), weights, share, cap).drop("row")


def _mixed(rows: DataFrame, weights, share: float, cap: float) -> DataFrame:
    """The mix of written rows ``doc_id, source, size, row``, with ``row``."""
    counts = kept(rows.groupBy("source", "size").agg(F.count("*").alias("n")), "mix-counts")
    sums = counts.select("source", (F.col("size") * F.col("n")).alias("size"))
    targets = kept(source_targets(sums, weights, share, cap), "mix-targets")
    solved = balanced(counts, targets, cap)
    solved = targets.alias("t").join(solved.alias("s"), F.col("t.source").eqNullSafe(F.col("s.source"))).select("t.source", "t.source_size", "t.target", "s.lam", "s.scale", "s.full")
    rated = rows.alias("r").join(solved.alias("s"), F.col("r.source").eqNullSafe(F.col("s.source"))).select("r.row", "r.doc_id", "r.source", "r.size", "s.source_size", "s.target", "s.lam", "s.scale", "s.full")
    rated = rated.withColumn("rate", _rate(cap)).drop("lam", "scale", "full")
    whole = F.floor("rate")
    uniform = F.pmod(F.xxhash64(F.lit("copies"), "doc_id", "size"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    rated = rated.withColumn("whole", whole).withColumn("gain", F.when(whole < cap, F.col("rate") - whole - uniform))
    bin_of = F.floor((F.col("gain") + 1) * (BINS // 2))
    rated = rated.withColumn("bin", bin_of)
    # the threshold of each source, from sums over at most BINS + 1 bins
    bins = rated.groupBy("source", "bin").agg(F.sum("size").alias("gained"), F.sum(F.col("whole") * F.col("size")).alias("base"), F.first("target").alias("target"))
    from_top = Window.partitionBy("source").orderBy(F.col("bin").desc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    all_of = Window.partitionBy("source")
    cut = bins.withColumn("sum", F.sum("gained").over(from_top) + F.sum("base").over(all_of)).withColumn("none", F.sum("base").over(all_of))
    cut = cut.filter(F.col("bin").isNotNull()).withColumn("miss", F.abs(F.col("sum") - F.col("target")))
    best = cut.groupBy("source").agg(F.min(F.struct("miss", F.col("bin").alias("cut"))).alias("b"), F.min(F.abs(F.col("none") - F.col("target"))).alias("miss_none"))
    best = best.select("source", F.when(F.col("b.miss") <= F.col("miss_none"), F.col("b.cut")).otherwise(F.lit(BINS + 1)).alias("cut"))
    out = rated.alias("r").join(best.alias("b"), F.col("r.source").eqNullSafe(F.col("b.source")), "left")
    copies = F.col("whole") + F.when(F.col("bin") >= F.col("cut"), 1).otherwise(0)
    out = kept(out.select("r.row", "r.doc_id", "r.source", "r.size", "r.source_size", "r.target", "r.rate", copies.cast("long").alias("copies")), "mix-copies")
    flips = _flips(out, cap)
    out = out.join(flips, "row", "left").withColumn("copies", F.col("copies") + F.coalesce("change", F.lit(0))).drop("change", "source")
    return out.withColumn("taken", F.col("copies") * F.col("size"))


def _flips(out: DataFrame, cap: float) -> DataFrame:
    """``row, change``: single documents taken once more or less, so that the sums come nearer to the targets."""
    size = F.col("size")
    sums = out.groupBy("source").agg(F.first("target").alias("target"), F.sum(F.col("copies") * size).alias("got"))
    rest = sums.select(F.col("source").alias("of"), (F.col("target") - F.col("got")).alias("rest"))
    flips = kept(out.select("row", F.lit(0).cast("long").alias("change"), F.col("source").alias("of"), F.lit(0).cast("long").alias("by")).limit(0), "mix-flips")
    for _ in range(FLIPS):
        done = flips.groupBy("row").agg(F.sum("change").alias("change"))
        left = rest.join(flips.groupBy(F.col("of").alias("_of")).agg(F.sum("by").alias("by")), F.col("of").eqNullSafe(F.col("_of")), "left")
        left = left.select("of", (F.col("rest") - F.coalesce("by", F.lit(0))).alias("rest")).filter(F.abs("rest") >= 1)
        now = out.join(done, "row", "left").withColumn("copies", F.col("copies") + F.coalesce("change", F.lit(0))).select("row", "doc_id", "source", "size", "copies")
        now = now.join(left, F.col("source").eqNullSafe(F.col("of")))
        may = F.when(F.col("rest") > 0, F.col("copies") + 1 <= cap).otherwise(F.col("copies") > 0) & (size > 0)
        off = F.abs(F.abs("rest") - size)
        best = now.filter(may & (off < F.abs("rest"))).groupBy("of").agg(F.min(F.struct(off, F.xxhash64("doc_id", "size"), "row", "size", "rest")).alias("b"))
        new = best.select(F.col("b.row").alias("row"), F.signum("b.rest").cast("long").alias("change"), "of", (F.signum("b.rest") * F.col("b.size")).cast("long").alias("by"))
        flips = kept(flips.unionByName(new), "mix-flips")
    return flips.groupBy("row").agg(F.sum("change").alias("change"))


def mixed_documents(docs: DataFrame, weights=WEIGHTS, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """``docs`` with the columns ``target``, ``taken`` and ``copies`` of the mix, every row kept.

    The rows are written first, so that each has a number of its own; repeated ids are told apart by it.
    Clashing names: columns of ``docs`` with these names are replaced.
    """
    rows = kept(docs.withColumn("_row", F.monotonically_increasing_id()), "mix-rows")
    m = _mixed(rows.select("doc_id", "source", word_count(F.col("text")).alias("size"), F.col("_row").alias("row")), weights, share, cap)
    clean = rows.drop("size", "source_size", "target", "copies", "taken")
    return clean.join(m.select(F.col("row").alias("_row"), "target", "copies", "taken"), "_row").drop("_row")
