"""Operators that SQL cannot express, against plain Python on small tables, held-out rows or whole given tables."""

import collections
import hashlib
import html
import math
import random
import re
import zlib

import numpy as np
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from waypoint.llm import components, decontaminate, html_text, mixing, quality, secrets, toxicity

from test_llm import brute_components, docs, words

GIVEN = "/root/testdata/sf0.01"


def auc(score, y):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(score))
    rank[order] = np.arange(1, len(score) + 1)
    return (rank[y == 1].sum() - y.sum() * (y.sum() + 1) / 2) / (y.sum() * (y == 0).sum())


@pytest.mark.parametrize(("module", "label", "least", "given"), [(toxicity, "toxic", 0.93, "/root/testdata/sf0.1"), (quality, "quality", 0.99, GIVEN)])
def test_classifiers_on_held_out_rows(spark, module, label, least, given):
    d, labels = (spark.read.parquet(f"{given}/{t}.parquet") for t in ("documents", "labels"))
    rows = module.scored(d, labels).join(labels.filter(f"{label} is not null").select("doc_id", label), "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 for r in rows)
    assert all(r["predicted"] == (r["score"] >= (0.7 if label == "toxic" else 0.5)) for r in rows)
    y = np.array([r[label] for r in held])
    assert auc(np.array([r["score"] for r in held]), y) >= least
    found = np.array([r["predicted"] for r in held])
    assert found[y == 1].mean() >= 0.65 and found[y == 0].mean() <= 0.05 or label == "quality"


def test_held_out_labels_teach_nothing(spark):
    rng = random.Random(3)
    texts = [words(rng, 30) + (" stinker" if k % 5 == 0 else "") for k in range(120)]
    rows = [(k, 0, int(k % 5 == 0)) for k in range(120)]
    other = [(k, q, 1 - t if zlib.crc32(str(k).encode()) % 3 == 1 else t) for k, q, t in rows]
    table = docs(spark, texts)
    schema = "doc_id long, quality int, toxic int"
    one, two = ({r["doc_id"]: r["score"] for r in toxicity.scored(table, spark.createDataFrame(x, schema)).collect()} for x in (rows, other))
    assert one == two


def test_best_cut():
    y = np.array([0, 0, 0, 1, 1, 1])
    assert 0.3 < toxicity.best_cut(np.array([0.1, 0.2, 0.3, 0.6, 0.7, 0.8]), y) < 0.6
    assert toxicity.best_cut(np.array([-3.0, -2.0, -9.0, 4.0, 5.0, 6.0]), y) == 1.0


def test_training_sample_is_bounded_by_rows_and_bytes(spark):
    from waypoint.llm.labelled import gathered, training_rows

    table = docs(spark, ["a" * 100, "b" * 5000, None, "c" * 50, "d" * 60])
    labels = spark.createDataFrame([(k, 1, 0) for k in range(5)] + [(None, 1, 1)], "doc_id long, quality int, toxic int")
    rows = training_rows(table, labels, "toxic", 10, 1000)
    assert all(len(r["text"]) <= 1000 for r in rows.collect())
    batches = rows.orderBy("place", "doc_id").toArrow().to_batches()
    texts, y = gathered(iter(batches), 2, 120)
    assert len(texts) == len(y) <= 2 and sum(map(len, texts.to_pylist())) <= 120


def read_article(page):
    """The article element's text by regular expressions; the given pages are regular enough for that."""
    inside = re.search(r"<article>(.*?)</article>", page, re.S)
    if not inside:
        return ""
    body = re.sub(r'<div class="comments">.*?</div>', "", inside[1], flags=re.S)
    parts = re.split(r"</?(?:p|h\d|div|ul|li|section|blockquote|table|tr|td|aside|figure|pre)\b[^>]*>", body)
    parts = [" ".join(html.unescape(re.sub(r"<[^>]*>", "", re.sub(r"<br\s*/?>", " ", x))).split()) for x in parts]
    return "\n".join(x for x in parts if x)


def test_all_given_pages(spark):
    got = {r["page_id"]: (r["text"], r["n_chars"]) for r in html_text.extracted(spark.read.parquet(f"{GIVEN}/pages.parquet")).collect()}
    for r in pq.read_table(f"{GIVEN}/pages.parquet").to_pylist():
        want = read_article(r["html"])
        assert got[r["page_id"]] == (want, len(want))


def filler(c, n):
    return " ".join(f"{c}{k}" for k in range(n))


@pytest.mark.parametrize(
    ("page", "want"),
    [
        ('<body><div><a href="/">Home page</a> <a href="/">About us</a></div><p>{a40}</p><p>{b12}</p><p>{c10}</p></body>', "a40 b12 c10"),
        ('<div class="social-story"><article><div class="post-header"><h1>{t6}</h1></div><p>{a40}</p></article></div>', "t6 a40"),
        ('<article class="social-story"><div class="post-header"><h1>{t6}</h1></div><p>{a40}</p></article>', "t6 a40"),
        ('<nav><a>x</a></nav><div class="ad">{z9}</div><article><h1>{t6}</h1><p>{a4}</p><p>{b90}</p><div class="comments"><p>{q50}</p></div></article><footer>{f20}</footer>', "t6 a4 b90"),
        ('<div id="header">{x5}</div><div id="sidebar">{s60}</div><div id="content"><h1>{t6}</h1><p>{b90}</p><p>{c70}</p></div><div class="cookie-notice">{k30}</div><div id="footer">{f20}</div>', "t6 b90 c70"),
        ("<header><h1>Site</h1></header><main><header><h1>{t6}</h1></header><p>{a30}</p><aside>{s30}</aside><form>{f10}</form></main>", "t6 a30"),
    ],
)
def test_pages_of_other_layouts(page, want):
    tree = html_text.grow(html_text.labelled_table())
    names = re.findall(r"\{(\w)(\d+)\}", page)
    made = page
    for c, n in names:
        made = made.replace("{%s%s}" % (c, n), filler(c, int(n)))
    assert html_text.main_text(made, tree).split("\n") == [filler(w[0], int(w[1:])) for w in want.split()]


def water_filled(sizes, weights=(3, 1, 2), share=1.5, cap=2.0):
    """Shares by weight; what passes a source's stop is shared anew among the others until nothing does."""
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: weights[k % 3] for k, s in enumerate(names)}
    left, open_, target = share * sum(sizes.values()), set(names), {}
    while open_:
        total = sum(weight[s] for s in open_)
        over = {s for s in open_ if left * weight[s] / total > cap * sizes[s]}
        if not over:
            return target | {s: left * weight[s] / total for s in open_}
        for s in over:
            target[s] = cap * sizes[s]
            left -= target[s]
        open_ -= over
    return target


@pytest.mark.parametrize("long", [1, 400])
def test_mixing_targets_and_sums(spark, long):
    rng = random.Random(13)
    texts, sources = [], []
    for s, n in (("a", 200), ("b", 60), ("Ä", 40), (None, 25), ("z", 3), ("empty", 2)):
        texts += [words(rng, rng.randint(1, 60) * rng.choice([1, 1, 1, long]) // (1 if long == 1 else 4) + 1) if s != "empty" else "" for _ in range(n)]
        sources += [s] * n
    rows = mixing.mix(docs(spark, texts, sources)).collect()
    sizes = collections.Counter()
    for t, s in zip(texts, sources, strict=True):
        sizes[s] += len(t.split())
    want, got, target = water_filled(sizes), collections.Counter(), {}
    for r in rows:
        s = sources[r["doc_id"]]
        got[s] += r["taken"]
        target[s] = r["target"]
        assert r["taken"] <= 2 * r["size"] and r["source_size"] == sizes[s]
    assert all(abs(target[s] - want[s]) <= 1e-6 * max(1, want[s]) for s in want)
    # the rest is less than what the best single document would mend
    for s in ("a", "b", "Ä", None):
        assert abs(got[s] - want[s]) <= max(2, 0.01 * want[s]), (s, got[s], want[s])


def test_mixed_documents_tell_repeated_ids_apart(spark):
    rows = [(1, "a b c", "en", "x", 5, 7), (1, "a b c", "en", "y", 5, 8), (1, "a b c", "en", "y", 5, 9), (None, None, None, None, None, 10)]
    table = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, copies int")
    out = mixing.mixed_documents(table).collect()
    assert len(out) == 4 and all(set(r.asDict()) == {"doc_id", "text", "lang", "source", "n_chars", "target", "copies", "taken"} for r in out)
    assert {r["source"] for r in out} == {"x", "y", None}


def weighted_windows(text, items, k=5):
    """The best weighted Jaccard similarity of any window of an item's word count, for each item."""
    split = lambda t: re.split(r"[\x20\x09-\x0D]+", (t or "").lower().strip())
    shingle = lambda w: [" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else [" ".join(w)]
    sets = {i: set(shingle(split(t))) for i, t in items.items()}
    df = collections.Counter(s for x in sets.values() for s in x)
    half_up = lambda x: math.floor(x + 0.5)
    weight = lambda s: half_up(4 * (1 + math.log2(len(items) / df.get(s, 1)))) if s in df else half_up(4 * (1 + math.log2(len(items))))
    w, best = split(text), {}
    for i, t in items.items():
        n = len(split(t))
        for p in range(max(1, len(w) - n + 1)):
            mine = set(shingle(w[p : p + n]))
            common = sum(weight(s) for s in mine & sets[i])
            best[i] = max(best.get(i, 0), common / sum(weight(s) for s in mine | sets[i]))
    return best


def test_decontamination_against_all_windows(spark):
    rng = random.Random(21)
    items = {k: words(rng, n) for k, n in enumerate((40, 30, 55, 24, 3, 1, 4))}
    items[7] = items[0].rsplit(" ", 1)[0] + " other"
    texts = []
    for k in range(60):
        w = items[k % 8].split()
        for _ in range(k // 16):
            w[rng.randrange(len(w))] = words(rng, 1)
        texts.append(" ".join([words(rng, rng.randint(1, 30)), *w, words(rng, rng.randint(1, 30))]))
    texts += [items[1].upper(), items[4], "x " + items[5], " ".join(items[0].split()[:20]), "", None, words(rng, 200)]
    bench = spark.createDataFrame([*items.items(), (99, None), (98, " ")], "item_id long, text string")
    want = {(d, i) for d, t in enumerate(texts) for i, s in weighted_windows(t, items).items() if s >= 0.8 and (t or "").strip()}
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(docs(spark, texts), bench).collect()}
    assert got == want and len(want) > 20


def test_joined_benchmark_gives_the_same(spark, monkeypatch):
    rng = random.Random(22)
    items = [words(rng, n) for n in (40, 3)]
    table = docs(spark, [words(rng, 20) + " " + items[0], "a " + items[1] + " b", words(rng, 50), None])
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    one = sorted(tuple(r) for r in decontaminate.leaks(table, bench).collect())
    monkeypatch.setattr(decontaminate, "MOST_SHINGLES", 1)
    assert sorted(tuple(r) for r in decontaminate.leaks(table, bench).collect()) == one and [r[:2] for r in one] == [(0, 0), (1, 1)]


def test_index_finds_all_prints_within_the_radius(spark):
    rng = random.Random(23)
    prints = [rng.getrandbits(64) for _ in range(40)]
    near = [p ^ sum(1 << b for b in rng.sample(range(64), rng.choice([0, 5, 12, 18, 19, 20, 25]))) for p in prints for _ in range(4)]
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    windows = spark.createDataFrame([(7, signed(p)) for p in near], "n long, print long")
    items = spark.createDataFrame([(k, 7, signed(p)) for k, p in enumerate(prints)], "item_id long, n long, item_print long")
    got = {(r["print"], r["item_id"], r["distance"]) for r in decontaminate.near_prints(windows, items, 19).collect()}
    assert got == {(signed(p), k, (p ^ q).bit_count()) for p in near for k, q in enumerate(prints) if (p ^ q).bit_count() <= 19}


def brute_entropy(text):
    """The entropy spans by plain counting of every window."""
    out = []
    for m in re.finditer(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}", text):
        run = m[0]
        mixed = re.search("[a-z]", run) and re.search("[A-Z]", run)
        if not (re.search("[0-9]", run) or mixed) or any(re.search(p, run) for p in secrets.ALLOWED):
            continue
        kind = "hex" if re.fullmatch("[0-9a-fA-F]+", run) else "base64" if re.search("[0-9]", run) else "letters"
        most = max(-sum(c / 20 * math.log2(c / 20) for c in collections.Counter(run[p : p + 20]).values()) for p in range(len(run) - 19))
        if most >= secrets.THRESHOLDS[kind] - 1e-9:
            out.append((m.start(), m.end()))
    return out


def test_entropy_spans_against_counting(spark):
    rng = random.Random(31)
    pick = lambda alphabet, n: "".join(rng.choice(alphabet) for _ in range(n))
    key = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_="
    texts = [" ".join(pick(rng.choice([key, "abAB12", "0123456789", "XYZxyz", key[:52]]), rng.choice([5, 19, 20, 21, 60, 300, 700])) for _ in range(12)) for _ in range(25)]
    texts += ["é" * 300 + " " + pick(key, 40), pick("ab1", 5000) + pick(key, 30), pick(key, 20000)]
    for r in secrets.scanned(docs(spark, texts)).collect():
        text = texts[r["doc_id"]]
        spans = [tuple(map(int, s.split(":")[1:])) for s in r["spans"].split(",") if s.startswith("entropy")]
        base = [tuple(map(int, s.split(":")[1:])) for s in r["spans"].split(",") if s and not s.startswith("entropy")]
        want = [(s, e) for s, e in brute_entropy(text) if not any(a <= s and b >= e for a, b in base)]
        assert spans == want


def test_redaction_over_chunks(spark, monkeypatch):
    monkeypatch.setattr(secrets, "CHUNK", 7)
    monkeypatch.setattr(secrets, "HITS", 2)
    key = "f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda"
    texts = [f"é😀 {key} a {key}b {key} token={key[:20]}!", key, f"x{key}", "nothing here"]
    clean = {r["doc_id"]: r["text"] for r in secrets.redacted(docs(spark, texts)).collect()}
    assert clean[0] == "é😀 [secret] a [secret] [secret] [secret]!" and clean[1] == "[secret]" and clean[3] == texts[3]


def test_components_by_one_task_and_by_stars(spark, monkeypatch):
    rng = random.Random(41)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000 + k, 1001 + k) for k in range(60)] + [(5, 5)]
    table = spark.createDataFrame(links, "u long, v long")
    one = sorted(tuple(r) for r in components.components(table).collect())
    monkeypatch.setattr(components, "ONE_TASK", 0)
    assert sorted(tuple(r) for r in components.components(table).collect()) == one
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for u, v in links:
        if u != v:
            a, b = find(u), find(v)
            root[max(a, b)] = min(a, b)
    assert one == sorted((x, find(x)) for x in root)


def test_pipeline_against_plain_python(spark, tmp_path):
    rng = random.Random(51)
    texts, toxic = [], {}
    for k in range(240):
        w = words(rng, 40).split()
        if k % 6 == 0:
            w[rng.randrange(40)] = "stinkerhead"
            toxic[k] = 1
        texts.append(" ".join(w))
    base = words(rng, 60)
    item, key = words(rng, 30), "f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda"
    texts += [base, base + " more", "other " + base, words(rng, 20) + " " + item, "see " + key + " " + words(rng, 30), None, "", "  ", words(rng, 30)]
    table = docs(spark, texts, [rng.choice(["a", "b", None]) for _ in texts])
    table.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(k, 1, toxic.get(k, 0)) for k in range(240)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    labels, bench = (spark.read.parquet(str(tmp_path / f"{t}.parquet")) for t in ("labels", "benchmark"))
    accepted = sorted(r["doc_id"] for r in toxicity.accepted(table, labels).collect())
    assert len(set(toxic) & set(accepted)) < len(toxic) / 2 and len(set(range(240)) - set(toxic) - set(accepted)) < 20
    roots = brute_components([texts[i] for i in accepted], 5, 80)
    unique = [i for k, i in enumerate(accepted) if roots[k][1] == k]
    clean = [i for i in unique if not (texts[i] or "").strip() or weighted_windows(texts[i], {0: item})[0] < 0.8]
    assert 243 not in clean and {240, 244, 245, 246, 247} <= set(clean) and not {241, 242} & set(clean)
    out = {r["doc_id"]: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert sorted(out) == clean
    redacted = [(texts[i] or "").replace(key, "[secret]") for i in clean]
    assert [out[i]["size"] for i in clean] == [len(t.split()) for t in redacted]
    assert all(out[i]["taken"] == out[i]["copies"] * out[i]["size"] and out[i]["copies"] in (0, 1, 2) for i in clean)
    stages = [n for n, _ in corpus_pipeline.STAGES]
    assert stages == ["toxicity", "near_duplicates", "decontamination", "secrets", "mixing"]
    now = table
    for _, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, str(tmp_path))
        assert now.columns == table.columns


def odd(spark):
    """Nulls in every column, empty and very long texts, ties, repeats, and columns named like the operators' own."""
    rng = random.Random(61)
    long = words(rng, 30000)
    texts = ["same text here twice over", "same text here twice over", None, "", " \t\n", long, "tie a b c d e", "tie a b c d e", "x", "😀 é", words(rng, 80)]
    ids = [1, 1, 2, 3, 4, 5, 6, 7, None, None, 8]
    rows = [(i, t, None if k % 4 == 0 else "en", None if k % 3 == 0 else "s", None, "c", 1.0, 2, 3, 4, "b", 5) for k, (i, t) in enumerate(zip(ids, texts, strict=True))]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, component_id string, score double, size int, rank int, row long, spans string, copies int"), rows


def test_repeated_bytes_of_given_documents(spark):
    """The registered query on all of sf0.01, against a count of every 400-byte window."""
    from waypoint.llm.registry import QUERIES

    rows = pq.read_table(f"{GIVEN}/documents.parquet", columns=["doc_id", "text"]).to_pylist()
    texts = [(r["text"] or "").encode() for r in rows]
    windows = [np.array([int.from_bytes(hashlib.blake2b(t[p : p + 400], digest_size=8).digest()) for p in range(len(t) - 399)], dtype=np.uint64) for t in texts]
    content, n = np.unique(np.concatenate(windows), return_counts=True)
    want = {}
    for row, t, w in zip(rows, texts, windows, strict=True):
        edge = np.zeros(len(t) + 1, dtype=int)
        at = np.flatnonzero(n[np.searchsorted(content, w)] > 1)
        np.add.at(edge, at, 1)
        np.add.at(edge, at + 400, -1)
        gone = np.cumsum(edge[:-1]) > 0
        kept = np.frombuffer(t, np.uint8)[~gone].tobytes()
        want[row["doc_id"]] = (len(t), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest())
    got = QUERIES["op1_suffix_dedup"](spark, GIVEN).collect()
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == want and len(got) == len(rows)
    assert 0 < sum(w[1] > 0 for w in want.values()) < len(rows)


def test_passages_are_measured_in_bytes_not_words(spark):
    """Over 50 words that two documents share are removed from 400 bytes on; n_bytes tells of the whole text either way."""
    from waypoint.llm import suffix_dedup

    rng = random.Random(17)
    short, long = " ".join(["abcdef"] * 50 + ["abcdefg", "z"]), words(rng, 100)[:400]
    assert len(short.split()) > 50 and len(short) < 400 and len(long.split()) > 50
    texts = [f"{a}{passage}{b}" for passage in (short, long) for a, b in (("1 ", " 2"), ("3 ", " 4"))]
    got = suffix_dedup.repeated_spans(docs(spark, texts)).orderBy("doc_id").collect()
    assert [r["n_bytes"] for r in got] == [len(t) for t in texts]
    assert [(r["n_removed"], r["n_spans"]) for r in got] == [(0, 0), (0, 0), (402, 1), (402, 1)]


def test_odd_tables(spark):
    from waypoint.llm import language_model, near_dup, search, suffix_dedup

    table, rows = odd(spark)
    labels = spark.createDataFrame([(1, 1, 0), (1, 0, 1), (5, None, 1), (6, 1, 0), (None, 1, 1), (8, 0, 0)], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([(1, "a b c d e"), (2, None), (None, "x"), (1, "a b c d e")], "item_id long, text string")
    for empty in (False, True):
        t = table.limit(0) if empty else table
        n = 0 if empty else len(rows)
        every = {
            "suffix": suffix_dedup.repeated_spans(t), "near": near_dup.near_duplicates(t), "toxic": toxicity.scored(t, labels), "quality": quality.scored(t, labels),
            "mixing": mixing.mix(t), "secrets": secrets.scanned(t), "model": language_model.scored(t),
        }
        for name, out in every.items():
            got = out.collect()
            assert len(got) == n, name
            assert collections.Counter(r["doc_id"] for r in got) == collections.Counter(r[0] for r in rows[:n]), name
        same = [toxicity.accepted(t, labels), near_dup.deduplicated(t), decontaminate.decontaminated(t, bench), secrets.redacted(t)]
        assert all(x.columns == t.columns for x in same)
        kept = [x.count() for x in same]
        assert kept[3] == n and all(k <= n for k in kept)
        leaks = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(t, bench).collect()}
        assert leaks == (set() if empty else {(6, 1), (7, 1)})
        hits = search.search(t, t.filter("doc_id = 6").selectExpr("doc_id as query_id", "text"), k=2).collect()
        assert [(r["rank"], r["doc_id"]) for r in hits] == ([] if empty else [(1, 6), (2, 7)])
    for no in (labels.limit(0), labels.withColumn("toxic", F.lit(None).cast("int"))):
        assert {round(r["score"], 3) for r in toxicity.scored(table, no).collect()} == {0.5}
    assert decontaminate.leaks(table, bench.limit(0)).count() == 0
    near = {(r["doc_id"], r["n_shingles"]): r for r in near_dup.near_duplicates(table).collect()}
    assert near[7, 2]["component_id"] == 6 and near[None, 1]["component_id"] is None and near[None, 1]["kept"] and near[2, 0]["component_id"] == 2
    digest = hashlib.sha256(b"").hexdigest()
    assert {r["doc_id"] for r in suffix_dedup.repeated_spans(table).collect() if r["kept_sha256"] == digest} == {2, 3}
    pages = spark.createDataFrame([(1, None, None, "t"), (None, "u", "", None), (3, "u", "<article><p>" + "w " * 50000 + "</p>", "t"), (3, "u", "<article><p>a", "t")], "page_id long, url string, html string, text string")
    assert sorted(r["n_chars"] for r in html_text.extracted(pages).collect()) == [0, 0, 1, 99999] and html_text.extracted(pages.limit(0)).count() == 0
