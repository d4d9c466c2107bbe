"""Secrets in texts, by patterns and by sliding-window entropy, in DataFrame operations alone.

Three base kinds are patterns whose matches are dropped when too short. The entropy method adds a fourth
kind: maximal runs of key characters that hold a digit or letters of both cases are candidates; each has a class
(``hex``, ``base64`` or ``letters``), and a window of 20 characters slides over it. The sum of c*log2(c) over the window's character
counts changes in two places as the window moves, so it is carried along instead of being counted anew. The
run is a span when some window's entropy reaches its class's threshold, unless an allow-list pattern matches
the run or a base span covers all of it.

Letters of one case without a digit are not judged: words joined by marks look alike. Runs and texts of any length take time in proportion to it.
Places are code points, end exclusive, in whole texts. Edge cases: a null or empty text has no spans; rows
are judged one by one, so repeated rows repeat their result and an empty table gives an empty one; extra
columns of ``docs`` stay (a column named like an added one is replaced).
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The base patterns.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 12, 18, 16
KINDS = ("assign", "access", "hex", "entropy")

WINDOW = 20
#: A maximal run of key characters of at least a window's length with a digit in it, or with letters of both cases.
CANDIDATE = r"(?<![A-Za-z0-9+/_=-])(?:(?=[A-Za-z+/_=-]*[0-9])|(?=[a-z+/_=-]*[A-Z])(?=[A-Z+/_=-]*[a-z]))[A-Za-z0-9+/_=-]{20,}"
#: Bits a character; a window of 20 holds 4.32 at most, hex 3.92.
THRESHOLDS = {"hex": 2.9, "base64": 3.75, "letters": 3.75}
#: Runs that look random but are known not to be keys.
ALLOWED = (
    r"^[0-9_/+=-]+$",  # digits only: numbers, dates, phone numbers
    r"^[a-z]+(?:[-_/][a-z]+)*[-_/]?[0-9]{1,6}$",  # a slug or path with a number after it
    r"^[-_/+=]*+(?:(?:[A-Z]?[a-z]{2,}+|[A-Z]{2,}+|[aAI](?![a-z]))[-_/+=]*+)++$",  # words in a row, by case or marks
    r"(?i)example|xxxx|0123456789|abcdef0123|lorem|placeholder",
)

#: Matches, windows of a run and characters of a text that are handled together.
HITS, PIECE, CHUNK = 256, 256, 4096
_HIT = "struct<start:int,end:int,hit:string>"


def _let(value: Column, body) -> Column:
    """``body`` of a value that is worked out once; inside a lambda an expression would be worked out at every step."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _walked(n: Column, begin: Column, advance, item, kind: str, keep=None) -> Column:
    """``item(state, i)`` of 0 <= i < n (those that ``keep``), where the state is carried along by ``advance(state, i)``.

    States are first carried over blocks of HITS and items then collected block by block, so that a long list costs little more an item than a short one.
    """
    none = F.array().cast(f"array<{kind}>")

    def of_block(k):
        return F.sequence(k * HITS, F.least((k + 1) * HITS, n) - 1)

    def over(acc, k):
        return F.struct(F.aggregate(of_block(k), acc["at"], advance).alias("at"), F.array_append(acc["out"], acc["at"]).alias("out"))

    def step(acc, i):
        out = F.array_append(acc["out"], item(acc["at"], i))
        return F.struct(advance(acc["at"], i).alias("at"), (out if keep is None else F.when(keep(i), out).otherwise(acc["out"])).alias("out"))

    blocks = F.sequence(F.lit(0), F.floor((n - 1) / HITS).cast("int"))
    begins = F.aggregate(blocks, F.struct(begin.alias("at"), F.array().cast("array<int>").alias("out")), over, lambda acc: acc["out"])
    inside = F.transform(begins, lambda at, k: F.aggregate(of_block(k), F.struct(at.alias("at"), none.alias("out")), step, lambda acc: acc["out"]))
    return F.when(n > 0, F.flatten(inside)).otherwise(none)


def _hits(text: Column, pattern: str, worth: str | None = None) -> Column:
    """All leftmost non-overlapping matches with their places, which are running sums of the lengths of matches and of what lies
    between; ``worth``: a cheap pattern that any row with a kept match has."""

    def located(p):
        def begin(at, i):
            return at + F.length(F.get(p["parts"], i))

        def end(at, i):
            return begin(at, i) + F.length(F.get(p["hits"], i))

        def item(at, i):
            return F.struct(begin(at, i).alias("start"), end(at, i).alias("end"), F.get(p["hits"], i).alias("hit"))

        return _walked(F.size(p["hits"]), F.lit(0), end, item, _HIT)

    both = F.struct(F.split(text, pattern, -1).alias("parts"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"))
    return F.when(text.rlike(worth or pattern), _let(both, located)).otherwise(F.array().cast(f"array<{_HIT}>"))


def _uncovered(hits: Column, base: Column) -> Column:
    """The hits that no base span covers whole: in one order by start, the furthest end of base spans so far is carried along."""
    as_hits = F.transform(base, lambda b: F.struct(b["start"].alias("start"), F.lit(0).alias("of"), b["end"].alias("end"), F.lit("").alias("hit")))
    tagged = F.transform(hits, lambda h: F.struct(h["start"].alias("start"), F.lit(1).alias("of"), h["end"].alias("end"), h["hit"].alias("hit")))

    def open_(all_of):
        def at(i):
            return F.get(all_of, i)

        def advance(end, i):
            return F.when(at(i)["of"] == 0, F.greatest(end, at(i)["end"])).otherwise(end)

        def item(end, i):
            return F.struct(at(i)["start"].alias("start"), F.when(end >= at(i)["end"], F.lit(-1)).otherwise(at(i)["end"]).alias("end"), at(i)["hit"].alias("hit"))

        return F.filter(_walked(F.size(all_of), F.lit(-1), advance, item, _HIT, lambda i: at(i)["of"] == 1), lambda h: h["end"] >= 0)

    return F.when((F.size(hits) == 0) | (F.size(base) == 0), hits).otherwise(_let(F.array_sort(F.concat(as_hits, tagged)), open_))


def _kind(hits: Column, kind: int, good) -> Column:
    return F.transform(F.filter(hits, good), lambda h: F.struct(h["start"].alias("start"), F.lit(kind).alias("kind"), h["end"].alias("end")))


def base_spans(text: Column) -> tuple[Column, Column, Column]:
    """The three base kinds. Runs of hex and access keys are maximal, so their least length can stand in the pattern."""
    assign = _hits(text, ASSIGN, ASSIGN[:-2] + "{%d,})" % 1)
    return (
        _kind(assign, 0, lambda h: F.length(F.regexp_extract(h["hit"], ASSIGN, 2)) >= ASSIGN_LEAST),
        _kind(_hits(text, ACCESS[:-1] + "{%d,}" % (ACCESS_LEAST - 4)), 1, lambda h: F.lit(True)),
        _kind(_hits(text, HEX[:-1] + "{%d,}" % HEX_LEAST), 2, lambda h: F.lit(True)),
    )


def window_entropy(run: Column, width: int = WINDOW) -> Column:
    """Largest entropy in bits of any window of ``width`` characters; -1 for a shorter run.

    A run is cut into pieces of PIECE windows (by one pass of a pattern), so the cost is in proportion to its length.
    """
    pieces = F.regexp_extract_all(run, F.lit("(?s)(?=(.{1,%d})).{1,%d}" % (PIECE + width - 1, PIECE)), F.lit(1))
    return F.when(F.length(run) >= width, F.array_max(F.transform(pieces, lambda p: _piece_entropy(p, width)))).otherwise(F.lit(-1.0))


def _piece_entropy(run: Column, width: int) -> Column:
    table = F.array(*[F.lit(0.0 if c < 2 else c * math.log2(c)) for c in range(width + 2)])

    def term(c):
        return F.get(table, c)

    def count(window, ch):
        return F.length(window) - F.length(F.replace(window, ch, F.lit("")))

    def slid(first):
        chars = F.filter(F.array_distinct(F.split(first, "")), lambda c: c != "")
        start = F.aggregate(chars, F.lit(0.0), lambda acc, c: acc + term(count(first, c)))
        zero = _let(start, lambda x: F.struct(x.alias("sum"), x.alias("least")))
        return F.aggregate(steps, zero, step, lambda acc: acc["least"])

    def step(acc, i):
        window = F.substr(run, i, F.lit(width))
        gone, come = F.substr(run, i, F.lit(1)), F.substr(run, i + width, F.lit(1))
        moved = _let(F.struct(count(window, gone).alias("was"), count(window, come).alias("had")), lambda x: acc["sum"] - term(x["was"]) + term(x["was"] - 1) - term(x["had"]) + term(x["had"] + 1))
        now = F.when(gone == come, acc["sum"]).otherwise(moved)
        return _let(now, lambda x: F.struct(x.alias("sum"), F.least(acc["least"], x).alias("least")))

    steps = F.when(F.length(run) > width, F.sequence(F.lit(1), F.length(run) - width)).otherwise(F.array().cast("array<int>"))
    least = _let(F.substring(run, 1, width), slid)
    return F.when(F.length(run) >= width, F.lit(math.log2(width)) - least / width).otherwise(F.lit(-1.0))


def entropy_spans(text: Column, base: Column, thresholds=THRESHOLDS, allowed=ALLOWED) -> Column:
    def good(h):
        run = h["hit"]
        least = F.when(run.rlike("^[0-9a-fA-F]+$"), thresholds["hex"]).when(run.rlike("[0-9]"), thresholds["base64"]).otherwise(thresholds["letters"])
        ok = window_entropy(run) >= least
        for pattern in allowed:
            ok = ~run.rlike(pattern) & ok
        return ok

    return _kind(_let(_hits(text, CANDIDATE), lambda hits: _uncovered(hits, base)), 3, good)


def _said(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))))


def secret_spans(docs: DataFrame, text: str = "text", **how) -> DataFrame:
    """``docs`` with ``assign_spans, access_spans, hex_spans, base_spans`` and ``secret_spans`` (all kinds), each sorted by start, then kind."""
    clear = F.coalesce(F.col(text), F.lit(""))
    a, k, h = base_spans(clear)
    out = docs.withColumns({"assign_spans": a, "access_spans": k, "hex_spans": h})
    out = out.withColumn("base_spans", F.array_sort(F.concat("assign_spans", "access_spans", "hex_spans")))
    return out.withColumn("secret_spans", F.array_sort(F.concat("base_spans", entropy_spans(clear, F.col("base_spans"), **how))))


def scanned(docs: DataFrame) -> DataFrame:
    """One row a document: the counts of base spans, their digest, and all spans as text."""
    out = secret_spans(docs.select("doc_id", "text"))
    return out.select(
        "doc_id", F.size("assign_spans").cast("long").alias("n_assign"), F.size("access_spans").cast("long").alias("n_access"), F.size("hex_spans").cast("long").alias("n_hex"),
        F.sha2(_said(F.col("base_spans")), 256).alias("base_sha256"), _said(F.col("secret_spans")).alias("spans"),
    )


def redacted(docs: DataFrame, mark: str = "[secret]") -> DataFrame:
    """``docs`` with every span replaced by ``mark``; rows without spans are unchanged, none is dropped."""
    names = docs.columns
    found = secret_spans(docs.select("*", F.col("text").alias("_text")).drop("assign_spans", "access_spans", "hex_spans", "base_spans", "secret_spans"), "_text")
    text = F.col("_text")

    def cut(chunk, k):
        lo = k * CHUNK
        before = F.array_max(F.transform(F.filter("secret_spans", lambda s: s["start"] < lo), lambda s: s["end"]))
        mine = F.filter("secret_spans", lambda s: (s["start"] >= lo) & (s["start"] < lo + CHUNK))

        def step(acc, s):
            piece = F.concat(acc["out"], F.substr(chunk, acc["at"] - lo + 1, F.greatest(s["start"] - acc["at"], F.lit(0))), F.when(s["start"] < acc["at"], F.lit("")).otherwise(F.lit(mark)))
            return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(s["end"] <= acc["at"], acc["out"]).otherwise(piece).alias("out"))

        zero = F.struct(F.greatest(lo, F.coalesce(before, lo)).alias("at"), F.lit("").alias("out"))
        return F.aggregate(mine, zero, step, lambda acc: F.concat(acc["out"], F.substr(chunk, acc["at"] - lo + 1, F.lit(CHUNK))))

    # by chunks of the text, so that no long prefix is copied at each span
    clean = F.array_join(F.transform(F.regexp_extract_all(text, F.lit("(?s).{1,%d}" % CHUNK), F.lit(0)), cut), "")
    hit = F.size("secret_spans") > 0
    new = {"text": F.when(hit, clean).otherwise(text)}
    if "n_chars" in names:
        new["n_chars"] = F.when(hit, F.length(clean).cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    return found.withColumns(new).select(*names)
