"""Language-model scores from an n-gram trie in Elias-Fano levels, memory-mapped where texts are scored.

Counting. Each task counts the distinct words and word pairs of its training texts and sends them, delta-coded and dealt by
a hash of the n-gram (so no frequent context gathers anywhere), to shards. A shard merges its counts and writes its part of the trie:
level 1 holds the words and the running sums of their counts (exact); level 2 holds the contexts, monotone pointers to
the ranges of their successors, the successors' whole hashes rising in each range, and quantised log counts of all pairs,
those seen once too. Monotone sequences are Elias-Fano coded: low bits in byte planes, high bits in unary with sampled ranks;
the pointers are the high bits of the successors (a context's rank on top of each).

Scoring. Texts aren't moved: each task maps the shard files (from the shared folder; a copy that is unlinked
at once where that isn't local) and looks up its distinct n-grams: a context is searched in its level, and the successor
between the pointers of its rank. The probability of w after v is MIX c(v,w) / c(v) + (1 - MIX) p(w), with c(v,w) 0
for pairs never seen, p(w) after an unknown v, and p the add-one unigram
estimate, which is also the base score.

The end of a text is a token, and the start a context. Defined results: a null or empty text is one end token; very long texts are
read whole; repeated rows count and score one by one; without training rows N and V are 0; an empty table gives an empty
result; extra columns are ignored. Words are told apart by 64-bit hashes, in pairs too.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waypoint.llm import packed
from waypoint.llm.labelled import fold
from waypoint.llm.store import kept, shared_folder

U64 = np.uint64
END, START = U64(0x243F6A8885A308D3), U64(0x13198A2E03707344)
MIX = 0.3
STEP = 1 << 21

_zeros = np.array([8 - bin(b).count("1") for b in range(256)], dtype=np.uint8)
_zero_at = np.zeros((256, 8), dtype=np.uint8)  # place of the r-th zero bit
for _b in range(256):
    for _r, _p in enumerate([p for p in range(8) if not _b >> p & 1]):
        _zero_at[_b, _r] = _p


class EliasFano:
    """A strictly rising sequence of 64-bit numbers with search; every part is an array that can be mapped."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray, ranks: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.ranks = n, low_bits, low, high, ranks

    @classmethod
    def coded(cls, values: np.ndarray) -> EliasFano:
        n = len(values)
        top = int(values[-1]) if n else 0
        low_bits = max(0, ((top // n) | 1).bit_length() - 1) if n else 0
        planes = -(-low_bits // 8)
        low = (values & U64((1 << low_bits) - 1)).view(np.uint8).reshape(n, 8)[:, :planes].T.copy() if n else np.zeros((planes, 0), np.uint8)
        return cls._of((values >> U64(low_bits)).astype(np.int64), low, low_bits)

    @classmethod
    def ranged(cls, rank: np.ndarray, low: np.ndarray) -> EliasFano:
        """Whole 64-bit numbers, rising among those of one rank; they lie as they are, not in planes."""
        return cls._of(rank.astype(np.int64), np.ascontiguousarray(low).view(np.uint8).reshape(8, len(low)), 64)

    @classmethod
    def _of(cls, up: np.ndarray, low: np.ndarray, low_bits: int) -> EliasFano:
        n = len(up)
        bits = np.zeros((n + (int(up[-1]) if n else 0) + 1 + 64) // 64 * 64, dtype=np.uint8)
        bits[up + np.arange(n)] = 1
        high = np.packbits(bits, bitorder="little")
        ranks = np.cumsum(_zeros[high].reshape(-1, 8).sum(axis=1, dtype=np.int64)).astype(np.uint64)
        return cls(n, low_bits, low, high, ranks)

    def arrays(self) -> list[np.ndarray]:
        return [np.array([self.n, self.low_bits], dtype=np.uint64), self.low.reshape(-1), self.high, self.ranks]

    @classmethod
    def mapped(cls, parts: Iterator[np.ndarray]) -> EliasFano:
        head, low, high, ranks = (next(parts) for _ in range(4))
        n, low_bits = int(head.view(np.uint64)[0]), int(head.view(np.uint64)[1])
        return cls(n, low_bits, low.reshape(-(-low_bits // 8), n), high, ranks.view(np.uint64))

    def _low(self, at: np.ndarray) -> np.ndarray:
        if self.low_bits == 64:
            return self.low.reshape(-1).view(U64)[at]
        out = np.zeros(len(at), dtype=U64)
        for k in range(self.low.shape[0]):
            out |= self.low[k][at].astype(U64) << U64(8 * k)
        return out

    def _zero(self, k: np.ndarray) -> np.ndarray:
        """Place of the k-th zero of the high bits."""
        word = np.searchsorted(self.ranks, k, "right")
        rest = k - np.where(word > 0, self.ranks[np.maximum(word, 1) - 1], U64(0)).astype(np.int64)
        eight = self.high.reshape(-1, 8)[word]
        cum = np.cumsum(_zeros[eight], axis=1, dtype=np.int64)
        byte = (cum <= rest[:, None]).sum(axis=1)
        before = np.where(byte > 0, cum[np.arange(len(k)), np.maximum(byte, 1) - 1], 0)
        return word * 64 + byte * 8 + _zero_at[eight[np.arange(len(k)), byte], rest - before]

    def find(self, wanted: np.ndarray) -> np.ndarray:
        """The index of each wanted number, or -1; the first one not under it is reached by a successor search."""
        return self.search((wanted >> U64(self.low_bits)).astype(np.int64), wanted & U64((1 << self.low_bits) - 1))

    def search(self, up: np.ndarray, low: np.ndarray) -> np.ndarray:
        """The index of each number, given by its high and its low bits, or -1."""
        out = np.full(len(up), -1, dtype=np.int64)
        if not self.n or not len(up):
            return out
        in_reach = up < int(self.ranks[-1])
        todo = np.flatnonzero(in_reach)
        up, low = up[todo], low[todo]
        # those of the same high bits, and a binary search among them
        at = np.where(up > 0, self._zero(np.maximum(up - 1, 0)) + 1 - up, 0)
        end = self._zero(up) - up
        stop = end.copy()
        while (open_ := np.flatnonzero(at < stop)).size:
            mid = (at[open_] + stop[open_]) >> 1
            under = self._low(mid) < low[open_]
            at[open_] = np.where(under, mid + 1, at[open_])
            stop[open_] = np.where(under, stop[open_], mid)
        hit = np.flatnonzero(at < end)
        hit = hit[self._low(at[hit]) == low[hit]]
        out[todo[hit]] = at[hit]
        return out

    def values(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n]
        return ((ones - np.arange(self.n)).astype(U64) << U64(self.low_bits)) | self._low(np.arange(self.n))


def quantised(counts: np.ndarray) -> np.ndarray:
    """Log counts in 16 bits, in steps of 1/1024 of a doubling: every count up to 2^63 comes back within 0.04 percent."""
    return np.round(np.log2(np.maximum(counts, 1)) * 1024).astype(np.uint16)


def restored(q: np.ndarray) -> np.ndarray:
    return np.exp2(q / 1024.0)


def shard_of(keys: np.ndarray, n: int) -> np.ndarray:
    """The shards of words (one row of hashes) or pairs (contexts and successors), by all their bits."""
    key = keys[0] if len(keys) == 1 else packed.mixed(keys[0]) + keys[1]
    return (packed.mixed(key ^ U64(0x452821E638D01377)) % U64(n)).astype(np.int64)


def numbered(w: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct words with START, rising, and each token's and its context's places among them."""
    words, place = np.unique(np.append(w, START), return_inverse=True)
    context = np.full(len(w), place[-1])
    inside = np.flatnonzero(v[1:] != START) + 1
    context[inside] = place[inside - 1]
    return words, place[:-1], context


def tokens(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all tokens, their contexts, and their texts; the last token of each text is its end."""
    h, doc = packed.word_hashes(raw, off)
    n = len(off) - 1
    count = np.bincount(doc, minlength=n) if len(doc) else np.zeros(n, dtype=np.int64)
    text = np.repeat(np.arange(n), count + 1)
    last = np.cumsum(count + 1) - 1
    out = np.full(len(text), END, dtype=U64)
    mask = np.ones(len(text), dtype=bool)
    mask[last] = False
    out[mask] = h
    context = np.full(len(text), START, dtype=U64)
    context[1:] = out[:-1]
    context[np.append(0, last[:-1] + 1)[:n]] = START
    return out, context, text


def _coded(keys: np.ndarray) -> bytes:
    """Rising numbers as eight planes of the bytes of their differences; the upper planes are mostly zeros. Successors follow as they are."""
    d = keys[0].copy()
    d[1:] -= keys[0, :-1]
    return d.view(np.uint8).reshape(-1, 8)[:, ::-1].T.tobytes() + keys[1:].tobytes()


def _decoded(blob: bytes, width: int) -> np.ndarray:
    raw = np.frombuffer(blob, dtype=np.uint8).reshape(width, -1)
    d = raw[0].reshape(8, -1).T[:, ::-1].copy().view(U64).reshape(-1)
    return np.concatenate([np.cumsum(d, dtype=U64)[None], raw[1:].view(U64)])


def _counted(n_shards: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, off = packed.texts(batch.column(0))
            found: list[list[tuple[np.ndarray, np.ndarray]]] = [[], []]
            for i, j in packed.pieces(off, STEP):
                w, v, _ = tokens(raw[off[i] : off[j]], off[i : j + 1] - off[i])
                words, place, context = numbered(w, v)
                seen = np.bincount(place, minlength=len(words))
                found[0].append((words[None, seen > 0], seen[seen > 0]))
                pairs, seen = np.unique(context * len(words) + place, return_counts=True)
                found[1].append((np.stack([words[pairs // len(words)], words[pairs % len(words)]]), seen))
            for kind in range(2):
                if not found[kind]:
                    continue
                keys, counts = _summed([k for k, _ in found[kind]], [c for _, c in found[kind]])
                shard = shard_of(keys, n_shards)
                order = np.argsort(shard, kind="stable")
                edges = np.searchsorted(shard[order], np.arange(n_shards + 1))
                for s in range(n_shards):
                    mine = order[edges[s] : edges[s + 1]]
                    if len(mine):
                        yield pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([s], pa.int32()), pa.array([_coded(keys[:, mine])], pa.binary()), pa.array([counts[mine].astype(np.int64).tobytes()], pa.binary())], names=["kind", "shard", "keys", "counts"])

    return run


def _summed(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    if len(keys) == 1:
        return keys[0], counts[0].astype(np.int64)
    k, c = np.concatenate(keys, axis=1), np.concatenate(counts).astype(np.int64)
    order = np.lexsort(k[::-1])
    k = k[:, order]
    first = np.flatnonzero(np.concatenate([[True], (k[:, 1:] != k[:, :-1]).any(axis=0)]))
    return k[:, first], np.add.reduceat(c[order], first) if k.size else c


def _trie(kind: int, keys: np.ndarray, counts: np.ndarray) -> list[np.ndarray]:
    if kind == 0:
        return [*EliasFano.coded(keys[0]).arrays(), np.cumsum(counts).astype(np.uint64)]
    contexts, rank = np.unique(keys[0], return_inverse=True)
    return [*EliasFano.coded(contexts).arrays(), *EliasFano.ranged(rank, keys[1]).arrays(), quantised(counts)]


def _write(folder: str, name: str, parts: list[np.ndarray]) -> str:
    """Arrays one after another, each at a multiple of 8 bytes, with a table of their sizes in front."""
    fs, path = pafs.FileSystem.from_uri(folder)
    fs.create_dir(path, recursive=True)
    with fs.open_output_stream(f"{path}/{name}") as f:
        f.write(np.array([len(parts), *[p.nbytes for p in parts]], dtype=np.uint64).tobytes())
        for p in parts:
            f.write(np.ascontiguousarray(p).tobytes() + b"\0" * (-p.nbytes % 8))
    return f"{folder}/{name}"


def _map(uri: str) -> Iterator[np.ndarray]:
    fs, path = pafs.FileSystem.from_uri(uri)
    if fs.type_name == "local":
        data = np.memmap(path, dtype=np.uint8, mode="r")
    else:
        with tempfile.NamedTemporaryFile(delete=False) as f, fs.open_input_stream(path) as src:
            while chunk := src.read(1 << 22):
                f.write(chunk)
        data = np.memmap(f.name, dtype=np.uint8, mode="r")
        os.unlink(f.name)
    n = int(data[:8].view(np.uint64)[0])
    sizes = data[8 : 8 + 8 * n].view(np.uint64).astype(np.int64)
    at = 8 + 8 * n
    for size in sizes:
        yield data[at : at + size]
        at += int(size) + int(-size % 8)


def _built(folder: str):
    def solved(kind: int, shard: int, keys: list, counts: list) -> pa.RecordBatch:
        k, c = _summed(keys, counts)
        path = _write(folder, f"{kind}-{shard}-{uuid.uuid4().hex}", _trie(kind, k, c))
        return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([shard], pa.int32()), pa.array([path]), pa.array([k.shape[1]], pa.int64()), pa.array([int(c.sum())], pa.int64())], names=["kind", "shard", "path", "n", "total"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, keys, counts, size = None, [], [], 0
        for batch in batches:
            for r in range(batch.num_rows):
                key = (batch.column(0)[r].as_py(), batch.column(1)[r].as_py())
                if at is not None and key != at:
                    yield solved(*at, keys, counts)
                    keys, counts, size = [], [], 0
                at = key
                keys.append(_decoded(batch.column(2)[r].as_buffer().to_pybytes(), key[0] + 1))
                counts.append(np.frombuffer(batch.column(3)[r].as_buffer().to_pybytes(), dtype=np.int64).astype(np.int32))
                size += keys[-1].shape[1]
                if size > 1 << 22 and len(keys) > 8:  # merge early, so that a shard in hand stays near its own size
                    k, c = _summed(keys, counts)
                    keys, counts, size = [k], [c], 0
        if at is not None:
            yield solved(*at, keys, counts)

    return run


class Model:
    """The mapped trie."""

    def __init__(self, files: list[tuple[int, int, str]], n_shards: int, n: int, v: int):
        self.n_shards, self.n, self.v = n_shards, n, v
        self.words, self.pairs = {}, {}
        for kind, shard, path in files:
            parts = _map(path)
            if kind == 0:
                self.words[shard] = (EliasFano.mapped(parts), next(parts).view(np.uint64))
            else:
                self.pairs[shard] = (EliasFano.mapped(parts), EliasFano.mapped(parts), next(parts).view(np.uint16))

    def _by_shard(self, keys: np.ndarray, levels: dict, look) -> np.ndarray:
        out = np.zeros(keys.shape[1])
        shard = shard_of(keys, self.n_shards)
        order = np.argsort(shard, kind="stable")
        edges = np.searchsorted(shard[order], np.arange(self.n_shards + 1))
        for s, level in levels.items():
            mine = order[edges[s] : edges[s + 1]]
            if len(mine):
                out[mine] = look(level, keys[:, mine])
        return out

    def word_counts(self, keys: np.ndarray) -> np.ndarray:
        def look(level, wanted):
            places, sums = level
            at = places.find(wanted[0])
            hit = np.maximum(at, 0)
            c = sums[hit].astype(np.int64) - np.where(hit > 0, sums[np.maximum(hit, 1) - 1], 0).astype(np.int64)
            return np.where(at >= 0, c, 0)

        return self._by_shard(keys[None], self.words, look)

    def pair_counts(self, keys: np.ndarray) -> np.ndarray:
        def look(level, wanted):
            contexts, successors, q = level
            rank = contexts.find(wanted[0])
            known = np.flatnonzero(rank >= 0)
            at = successors.search(rank[known], wanted[1, known])
            out = np.zeros(wanted.shape[1])
            out[known[at >= 0]] = restored(q[at[at >= 0]])
            return out

        return self._by_shard(keys, self.pairs, look)

    def scores(self, raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, ...]:
        w, v, text = tokens(raw, off)
        n = len(off) - 1
        words, place, context = numbered(w, v)
        c = self.word_counts(words)[place]
        p = (c + 1.0) / (self.n + (self.v + 1.0))
        of_context = np.zeros(len(w))
        of_context[1:] = c[:-1]
        starts = v == START
        ends = float(self.word_counts(np.array([END], dtype=U64))[0])
        of_context[starts] = ends  # as many starts as ends
        pair = np.zeros(len(w))
        maybe = np.flatnonzero((of_context > 0) & (c > 0))
        pairs, back = np.unique(context[maybe] * len(words) + place[maybe], return_inverse=True)
        keys = np.stack([words[pairs // len(words)], words[pairs % len(words)]])
        pair[maybe] = np.minimum(self.pair_counts(keys)[back], np.minimum(of_context[maybe], c[maybe]))
        known = of_context > 0
        smooth = np.where(known, MIX * pair / np.maximum(of_context, 1) + (1 - MIX) * p, p)
        total = lambda x: np.bincount(text, weights=x, minlength=n)
        return np.bincount(text, minlength=n), total(c > 0).astype(np.int64), total(np.log10(p)), total(np.log10(smooth))


def model_files(docs: DataFrame) -> tuple[list[tuple[int, int, str]], int, int, int]:
    """Count the training texts and write the trie: files by kind and shard, the number of shards, N and V."""
    spark = docs.sparkSession
    n_shards = max(4, int(spark.conf.get("spark.sql.shuffle.partitions")))
    folder = shared_folder(spark)
    folder = f"{folder if '://' in folder or folder.startswith('file:') else 'file://' + folder}/lm-{uuid.uuid4().hex}"
    training = docs.filter(fold(F.col("doc_id"), 7) != 2).select(F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))
    counted = training.mapInArrow(_counted(n_shards), "kind int, shard int, keys binary, counts binary")
    dealt = counted.repartition(2 * n_shards, "kind", "shard").sortWithinPartitions("kind", "shard")
    built = kept(dealt.mapInArrow(_built(folder), "kind int, shard int, path string, n long, total long"), "lm-files")
    rows = built.collect()  # two rows a shard
    words = [r for r in rows if r["kind"] == 0]
    return [(r["kind"], r["shard"], r["path"]) for r in rows], n_shards, sum(r["total"] for r in words), sum(r["n"] for r in words)


def scored(docs: DataFrame) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score`` of every document."""
    files, n_shards, n, v = model_files(docs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = Model(files, n_shards, n, v)
        for batch in batches:
            raw, off = packed.texts(batch.column(2))
            for i, j in packed.pieces(off, STEP):
                n_tokens, n_known, base, score = model.scores(raw[off[i] : off[j]], off[i : j + 1] - off[i])
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.array(n_tokens), pa.array(n_known), pa.array(np.full(j - i, n)), pa.array(base), pa.array(score)],
                    names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
                )

    rows = docs.select("doc_id", (fold(F.col("doc_id"), 7) == 2).alias("held_out"), F.col("text").cast("binary").alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
