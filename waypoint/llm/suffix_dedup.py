"""Exact removal of repeated byte strings, by suffix arrays built one bucket at a time with a difference cover.

A position is repeated if the LENGTH bytes from it also start somewhere else. Which suffixes can tie that long is
found first: of all GRAM-byte strings in a window the one of least hash is its anchor, equal windows have equal
anchors at equal offsets, and suffixes whose anchor occurs once in the corpus are single (no sort is needed for
them). The others go to suffix buckets by content: a bucket holds the suffixes that have one anchor at an offset of
one range of STRIDE and share all bytes that windows of that range have in common, so suffixes of different buckets
differ within LENGTH bytes and each bucket is sorted alone. Passages of equal bytes are one member of a bucket.

Within a bucket the suffixes are ordered by their first V bytes; longer ties are resolved by ranks that were computed before
for a sample of positions, a difference cover modulo V: for any two positions some shift under V brings both into the sample. The
sample's ranks come from doubling, so memory is a few words a byte of the buckets in hand, however long the ties. A bucket of
more than MEMBERS passages is split by longer content until its members are equal: at the full length, a count
decides. No bucket, group of copies or text is capped.

Defined results: a null or empty text has no bytes and the digest of the empty string; texts shorter than LENGTH lose nothing; very long
texts (to 256 MB) are read whole; repeated rows remove each other; an empty table gives an empty one; extra columns are ignored.
Strings are told apart by 64-bit hashes when anchors, contents and equal passages are matched.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waypoint.llm import packed
from waypoint.llm.store import kept

U64 = np.uint64
LENGTH = 400
GRAM = 200
STRIDE = 100
V = 32
MEMBERS = 256
#: Bytes of buckets sorted together.
BLOCK = 1 << 21
_POS = 28  # bits of a place in a run of texts


def difference_cover(v: int) -> list[int]:
    """A small set in which every difference modulo v occurs: 0..r-1 and the multiples of r."""
    r = int(np.ceil(np.sqrt(v)))
    cover = sorted({*range(r), *range(0, v, r)})
    assert {(a - b) % v for a in cover for b in cover} == set(range(v))
    return cover


COVER = difference_cover(V)
_in_cover = np.zeros(V, dtype=bool)
_in_cover[COVER] = True
#: The shift that brings residues r and s both into the cover.
SHIFT = np.array([[next(d for d in range(V) if _in_cover[(r + d) % V] and _in_cover[(s + d) % V]) for s in range(V)] for r in range(V)])


def anchors(raw: np.ndarray, off: np.ndarray, length: int = LENGTH, gram: int = GRAM):
    """For each anchor: its place, the first and last window start that it serves, its hash; with the prefix hashes."""
    prefix = packed.prefix_hash(raw)
    none = np.zeros(0, dtype=np.int64)
    m, w = len(raw) - gram + 1, length - gram + 1
    if m < w:
        return none, none, none, np.zeros(0, dtype=U64), prefix
    if m >> _POS:
        raise ValueError("a text is longer than 256 MB")
    h = packed.gram_hashes(prefix, gram)
    key = h >> U64(_POS)
    key <<= U64(_POS)
    key |= np.arange(m, dtype=U64)
    blocks = -(-m // w)
    grid = np.full(blocks * w, np.iinfo(np.uint64).max, dtype=U64)
    grid[:m] = key
    grid = grid.reshape(blocks, w)
    ahead = np.minimum.accumulate(grid, axis=1).reshape(-1)
    behind = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    n_windows = m - w + 1
    chosen = np.minimum(behind[:n_windows], ahead[w - 1 : w - 1 + n_windows]) & U64((1 << _POS) - 1)
    # windows that stay within their text
    size = np.diff(off)
    has = np.flatnonzero(size >= length)
    inside = np.zeros(n_windows + 1, dtype=np.int8)
    np.add.at(inside, off[has], 1)
    np.add.at(inside, np.minimum(off[has + 1] - length + 1, n_windows), -1)
    starts = np.flatnonzero(np.cumsum(inside[:-1]))
    if not len(starts):
        return none, none, none, np.zeros(0, dtype=U64), prefix
    chosen = chosen[starts].astype(np.int64)
    new = np.ones(len(starts), dtype=bool)
    new[1:] = (chosen[1:] != chosen[:-1]) | (starts[1:] != starts[:-1] + 1)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(starts)) - 1
    a = chosen[first]
    return a, starts[first], starts[last], h[a], prefix


def _runs(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    raw, off = packed.texts(column)
    for i, j in packed.pieces(off):
        yield i, j, raw[off[i] : off[j]], off[i : j + 1] - off[i]


def _anchor_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, raw, off in _runs(batch.column(2)):
            a, _, _, h, _ = anchors(raw, off)
            owner = np.searchsorted(off, a, "right") - 1
            order = np.lexsort((h, owner))
            owner, h = owner[order], h[order]
            new = np.ones(len(h), dtype=bool)
            new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
            first = np.flatnonzero(new)
            n = np.diff(np.append(first, len(h)))
            take = pa.array(owner[first] + i)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(take), batch.column(1).take(take), pa.array(h[first].view(np.int64)), pa.array(n)], names=["doc_id", "rid", "h", "n"])


def _strings(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> pa.Array:
    size = ends - starts
    first = np.concatenate([[0], np.cumsum(size)])
    idx = np.arange(first[-1]) + np.repeat(starts - first[:-1], size)
    return pa.Array.from_buffers(pa.large_binary(), len(size), [None, pa.py_buffer(first.astype(np.int64)), pa.py_buffer(raw[idx])]).cast(pa.binary())


def _passage_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Passages around repeated anchors: bucket key, content hash, place and bytes."""
    for batch in batches:
        for i, j, raw, off in _runs(batch.column(2)):
            lists = batch.column(3).slice(i, j - i)
            wanted = lists.flatten().to_numpy(zero_copy_only=False).view(U64)
            of = np.repeat(np.arange(j - i), np.diff(lists.offsets.to_numpy()))
            a, lo, hi, h, prefix = anchors(raw, off)
            owner = np.searchsorted(off, a, "right") - 1
            # a pair (text, hash) as one sortable number; a clash only lets a needless passage in
            mine = packed.mixed(h + packed.mixed(owner.astype(U64)))
            ok = np.isin(mine, packed.mixed(wanted + packed.mixed(of.astype(U64))))
            a, lo, hi, h, owner = a[ok], lo[ok], hi[ok], h[ok], owner[ok]
            for c in range((LENGTH - GRAM) // STRIDE + 1):
                near, far = c * STRIDE, min((c + 1) * STRIDE - 1, LENGTH - GRAM)
                p, q = np.maximum(lo, a - far), np.minimum(hi, a - near)
                ok = p <= q
                pa_, p, q, own = a[ok], p[ok], q[ok], owner[ok]
                key = packed.mixed(packed.span_hash(prefix, pa_ - near, pa_ - far + LENGTH) + U64(c))
                full = packed.mixed(packed.mixed(packed.span_hash(prefix, p, q + LENGTH) + (pa_ - p).astype(U64)) + h[ok])
                for s in range(0, len(p), 8192):
                    t = slice(s, s + 8192)
                    take = pa.array(own[t] + i)
                    yield pa.RecordBatch.from_arrays(
                        [
                            batch.column(0).take(take), batch.column(1).take(take), pa.array(key[t].view(np.int64)), pa.array(full[t].view(np.int64)),
                            pa.array(p[t] - off[own[t]]), pa.array(q[t] - off[own[t]]), pa.array((pa_ - p)[t]), _strings(raw, p[t], q[t] + LENGTH),
                        ],
                        names=["doc_id", "rid", "key", "full", "lo", "hi", "reach", "passage"],
                    )


_PASSAGE = "doc_id long, rid long, key long, full long, lo long, hi long, reach long, passage binary"


def _words(text: np.ndarray, at: np.ndarray, n_bytes: int) -> list[np.ndarray]:
    """The bytes from each place as big-endian 64-bit words, most significant first."""
    eight = sum(text[k : len(text) - 7 + k].astype(U64) << U64(56 - 8 * k) for k in range(8))
    return [eight[at + 8 * k] for k in range(n_bytes // 8)]


def _ranked(keys: list[np.ndarray]) -> np.ndarray:
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), dtype=np.int64)
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    out = np.empty(len(order), dtype=np.int64)
    out[order] = np.cumsum(new)
    return out


def cover_ranks(text: np.ndarray, n: int, depth: int = LENGTH) -> np.ndarray:
    """Ranks of the sample's suffixes by their first ``depth`` bytes or more, at their places in an array.

    ``text`` is zero-filled for 2 * depth bytes past ``n``.
    """
    place = np.flatnonzero(_in_cover[np.arange(n) % V])
    rank = np.zeros(len(text) + V, dtype=np.int64)
    rank[place] = _ranked(_words(text, place, V)) + 1
    reach = V
    while reach < depth:
        rank[place] = _ranked([rank[place], rank[np.minimum(place + reach, n + V)]]) + 1
        reach *= 2
    return rank


def suffix_order(text: np.ndarray, n: int, bucket: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Order of the suffixes at ``at`` by bucket, then content to LENGTH bytes at least."""
    rank = cover_ranks(text, n)
    first = _ranked([bucket.astype(U64), *_words(text, at, V)])
    residue = at % V
    shift = SHIFT[residue, residue]
    order = np.lexsort((rank[at + shift], residue, first))
    # a tie of several residues is put in order by comparing sample ranks at common shifts
    f, r = first[order], residue[order]
    cut = np.flatnonzero(np.concatenate([[True], f[1:] != f[:-1], [True]]))
    change = np.concatenate([[0], np.cumsum((r[1:] != r[:-1]) & (f[1:] == f[:-1]))])
    for s, e in zip(cut[:-1], cut[1:], strict=True):
        if e - s > 1 and change[e - 1] != change[s]:
            def less(x: int, y: int) -> int:
                d = SHIFT[x % V, y % V]
                return int(rank[x + d]) - int(rank[y + d])

            mine = order[s:e]
            by = sorted(range(e - s), key=functools.cmp_to_key(lambda x, y, mine=mine, less=less: less(int(at[mine[x]]), int(at[mine[y]]))))
            order[s:e] = mine[by]
    return order


def repeated_starts(passages: list[np.ndarray], bucket: np.ndarray, reach: np.ndarray, windows: np.ndarray, length: int = LENGTH) -> list[np.ndarray]:
    """For each passage, which of its first ``windows`` suffixes have an equal one (to ``length`` bytes) in its bucket.

    Passages are laid out with their anchors at multiples of V, so equal suffixes mostly have equal residues.
    """
    size = np.array([len(p) for p in passages])
    lead = (-reach) % V
    room = -(-(size + lead) // V) * V
    begin = np.cumsum(room) - room + lead
    n = int(room.sum())
    text = np.zeros(n + 2 * length + V, dtype=np.uint8)
    for b, p in zip(begin, passages, strict=True):
        text[b : b + len(p)] = p
    owner = np.repeat(np.arange(len(passages)), windows)
    inner = np.arange(len(owner)) - np.repeat(np.cumsum(windows) - windows, windows)
    at = begin[owner] + inner
    order = suffix_order(text, n, bucket[owner], at)
    s, b = at[order], bucket[owner][order]
    pair = np.flatnonzero(b[1:] == b[:-1])
    # common prefixes of neighbours, up to the length asked for
    eight = sum(text[k : len(text) - 7 + k].astype(U64) << U64(56 - 8 * k) for k in range(8))
    for k in [*range(0, length - 7, 8), length - 8]:
        pair = pair[eight[s[pair] + k] == eight[s[pair + 1] + k]]
    hit = np.zeros(len(at), dtype=bool)
    hit[order[pair]] = True
    hit[order[pair + 1]] = True
    return np.split(hit, np.cumsum(windows)[:-1])


def _intervals(hit: np.ndarray) -> tuple[list[int], list[int]]:
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return np.flatnonzero(edge == 1).tolist(), (np.flatnonzero(edge == -1) - 1).tolist()


def _sorted_buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by key; whole buckets are sorted together until they make a block."""

    def solved(rows: list[tuple]) -> pa.RecordBatch:
        keys = np.array([r[0] for r in rows])
        passages = [np.frombuffer(r[4], dtype=np.uint8) for r in rows]
        reach, windows = np.array([r[2] for r in rows]), np.array([r[3] for r in rows])
        hits = repeated_starts(passages, np.unique(keys, return_inverse=True)[1], reach, windows)
        spans = [_intervals(h) for h in hits]
        good = [x for x, s in enumerate(spans) if s[0]]
        return pa.RecordBatch.from_arrays(
            [pa.array([rows[x][0] for x in good], pa.int64()), pa.array([rows[x][1] for x in good], pa.int64()), pa.array([spans[x][0] for x in good], pa.list_(pa.int64())), pa.array([spans[x][1] for x in good], pa.list_(pa.int64()))],
            names=["key", "full", "starts", "ends"],
        )

    held: list[tuple] = []
    size = 0
    for batch in batches:
        for row in zip(*[c.to_pylist() for c in batch.columns], strict=True):
            if size >= BLOCK and held[-1][0] != row[0]:
                yield solved(held)
                held, size = [], 0
            held.append(row)
            size += len(row[4])
    if held:
        yield solved(held)


def _window_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every suffix of oversized buckets with the hash of its LENGTH bytes."""
    for batch in batches:
        keys, fulls, _, windows, texts = (batch.column(k) for k in range(5))
        raw, off = packed.texts(texts)
        n = windows.to_numpy()
        for i, j in packed.pieces(off):
            prefix = packed.prefix_hash(raw[off[i] : off[j]])
            own = np.repeat(np.arange(i, j), n[i:j])
            inner = np.arange(len(own)) - np.repeat(np.cumsum(n[i:j]) - n[i:j], n[i:j])
            at = off[own] - off[i] + inner
            take = pa.array(own)
            yield pa.RecordBatch.from_arrays([keys.take(take), fulls.take(take), pa.array(inner), pa.array(packed.span_hash(prefix, at, at + LENGTH).view(np.int64))], names=["key", "full", "start", "content"])


def _cut_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, texts, starts, ends = batch.column(0), batch.column(2), batch.column(3), batch.column(4)
        out = []
        for k in range(len(ids)):
            text = texts[k].as_py() or b""
            s, e = starts[k].as_py(), ends[k].as_py()
            runs = merged(s, e) if s else []
            rest, at = hashlib.sha256(), 0
            for x, y in runs:
                rest.update(text[at:x])
                at = y
            rest.update(text[at:])
            out.append((len(text), sum(y - x for x, y in runs), len(runs), rest.hexdigest(), [x for x, _ in runs], [y for _, y in runs]))
        n, r, c, d, a, b = zip(*out, strict=True) if out else ([],) * 6
        ints = pa.list_(pa.int64())
        yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(r, pa.int64()), pa.array(c, pa.int64()), pa.array(d, pa.string()), pa.array(a, ints), pa.array(b, ints)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "starts", "ends"])


def merged(starts: list[int], ends: list[int]) -> list[tuple[int, int]]:
    """Maximal runs of half-open intervals; touching ones are one run."""
    s, e = np.array(starts, dtype=np.int64), np.array(ends, dtype=np.int64)
    order = np.argsort(s, kind="stable")
    s, e = s[order], np.maximum.accumulate(e[order])
    new = np.ones(len(s), dtype=bool)
    new[1:] = s[1:] > e[:-1]
    first = np.flatnonzero(new)
    return list(zip(s[first].tolist(), e[np.append(first[1:], len(s)) - 1].tolist(), strict=True))


def repeated_spans(docs: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept_sha256`` and the removed runs (``starts``, ``ends``) of every row."""
    rows = docs.select("doc_id", F.xxhash64("doc_id", "text").alias("rid"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))
    found = rows.filter(F.length("text") >= LENGTH).mapInArrow(_anchor_rows, "doc_id long, rid long, h long, n long")
    found = kept(found, "sa-anchors")
    twice = found.groupBy("h").agg(F.sum("n").alias("n")).filter("n > 1").select("h")
    wanted = found.select("doc_id", "rid", "h").join(twice, "h").groupBy("rid", "doc_id").agg(F.collect_set("h").alias("hs"))
    same = [F.col("w.rid") == F.col("r.rid"), F.col("w.doc_id").eqNullSafe(F.col("r.doc_id"))]
    passages = rows.alias("r").join(wanted.alias("w"), same).select("r.doc_id", "r.rid", "r.text", "w.hs").mapInArrow(_passage_rows, _PASSAGE)
    passages = kept(passages, "sa-passages")
    members = passages.groupBy("key", "full").agg(F.count("*").alias("n"), F.min(F.struct("rid", "lo")).alias("one"))
    buckets = members.groupBy("key").agg(F.count("*").alias("members")).filter("members > 1")
    status = kept(members.join(buckets, "key", "left").filter("n > 1 or members > 1"), "sa-status")
    open_ = status.filter("members > 1")
    # one row with its bytes for each member, found by its place, since a member itself may be a large part of all rows
    content = passages.select("key", "full", "rid", "lo", "reach", (F.col("hi") - F.col("lo") + 1).alias("windows"), "passage")
    one = open_.select("key", "full", F.col("one.rid").alias("rid"), F.col("one.lo").alias("lo"), "members")
    reps = content.join(one, ["key", "full", "rid", "lo"]).groupBy("key", "full").agg(F.first("reach").alias("reach"), F.first("windows").alias("windows"), F.first("passage").alias("passage"), F.first("members").alias("members"))
    reps = kept(reps, "sa-members")
    columns = ["key", "full", "reach", "windows", "passage"]
    fits = reps.filter(F.col("members") <= MEMBERS).select(*columns)
    result = "key long, full long, starts array<long>, ends array<long>"
    hits = fits.repartition("key").sortWithinPartitions("key").mapInArrow(_sorted_buckets, result)
    windows = kept(reps.filter(F.col("members") > MEMBERS).select(*columns).mapInArrow(_window_rows, "key long, full long, start long, content long"), "sa-windows")
    equal = windows.groupBy("key", "content").agg(F.count("*").alias("n")).filter("n > 1").select("key", "content")
    deep = windows.join(equal, ["key", "content"]).groupBy("key", "full").agg(F.collect_set("start").alias("starts")).select("key", "full", "starts", F.col("starts").alias("ends"))
    hits = kept(hits.unionByName(deep), "sa-hits")
    # back to all rows: a passage that occurs twice is repeated as a whole
    judged = status.filter("n > 1").select("key", "full", F.array(F.lit(0).cast("long")).alias("starts"), F.lit(None).cast("array<long>").alias("ends"))
    single = status.filter("n = 1").select("key", "full").join(hits, ["key", "full"])
    judged = judged.unionByName(single)
    spans = passages.select("doc_id", "rid", "key", "full", "lo", "hi").join(judged, ["key", "full"])
    spans = spans.select(
        "doc_id", "rid", F.transform("starts", lambda s: F.col("lo") + s).alias("starts"),
        F.coalesce(F.transform("ends", lambda e: F.col("lo") + e + LENGTH), F.array(F.col("hi") + LENGTH)).alias("ends"),
    ).groupBy("rid", "doc_id").agg(F.collect_list(F.struct("starts", "ends")).alias("runs"))
    spans = spans.select("rid", "doc_id", F.flatten("runs.starts").alias("starts"), F.flatten("runs.ends").alias("ends"))
    return rows.alias("r").join(spans.alias("w"), same, "left").select("r.doc_id", "r.rid", "r.text", "w.starts", "w.ends").mapInArrow(_cut_rows, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, starts array<long>, ends array<long>")
