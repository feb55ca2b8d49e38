"""Each corpus operator on small tables: edge cases, and brute force where SQL has no say."""

import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from heavyhitters.llm import decontamination, exact_topk, jaccard_join, language_id, line_dedup, mixing, quality, suffix_dedup, token_counts, warc
from heavyhitters.llm.components import components

LONG = "word " * 4000

#: Nulls, empty and long texts, repeated rows and ids, and columns with clashing names.
EDGE = [
    (1, "Alpha beta gamma delta epsilon zeta\nsame line here", "a", 7), (2, "same line here\n\nother", "a", 7), (3, None, "b", 7), (4, "", None, 7), (5, LONG, "b", 7),
    (6, "  SAME line HERE\t\n12 34", "c", 7), (6, "  SAME line HERE\t\n12 34", "c", 7), (None, "same line here", "c", 7), (8, "Alpha beta gamma delta epsilon zeta\nsame line here", "a", None),
]


@pytest.fixture(scope="module")
def edge(spark):
    return spark.createDataFrame(EDGE, "doc_id long, text string, source string, n_lines int").withColumn("rank", F.lit("x")).withColumn("digest", F.lit("y"))


@pytest.fixture(scope="module")
def none(edge):
    return edge.limit(0)


def rows(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)


# ---- 1 ----------------------------------------------------------------------------------


def lines_by_hand(data, least):
    strip = " \t\n\x0b\x0c\r"
    key = lambda line: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in line.strip(strip))
    seen = Counter(k for _, t, *_ in data for k in {key(x) for x in (t or "").split("\n")} if k)
    out = []
    for i, t, *_ in data:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not key(x) or seen[key(x)] < least]
        out.append((i, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=repr)


@pytest.mark.parametrize("limit", [line_dedup.BROADCAST_BYTES, 0])
def test_lines(edge, none, limit):
    got = line_dedup.dedup_lines(edge, min_docs=3, bits=1 << 16, broadcast_bytes=limit)
    assert rows(got, "doc_id", "n_lines", "n_dropped", "kept_sha256") == lines_by_hand(EDGE, 3)
    assert line_dedup.dedup_lines(none, min_docs=2, bits=1 << 16).collect() == []
    back = line_dedup.dedup_lines(edge, min_docs=3, bits=1 << 16, output="documents", broadcast_bytes=limit)
    assert back.columns == edge.columns and back.count() == len(EDGE)
    assert {r.text for r in back.filter("doc_id = 3").collect()} == {None}
    clash = edge.select(*[F.lit(n).alias(c) for n, c in enumerate(("_row", "row", "keys", "_AT", "at", "c1", "first"))], "*")
    again = line_dedup.dedup_lines(clash, min_docs=3, bits=1 << 16, output="documents", broadcast_bytes=limit)
    assert again.columns == clash.columns and rows(again, "doc_id", "text") == rows(back, "doc_id", "text")
    assert {(r["_row"], r["row"], r["first"]) for r in again.collect()} == {(0, 1, 6)}
    first = line_dedup.dedup_lines(edge, min_docs=3, output="lines", keep_first=True, broadcast_bytes=limit)
    assert {r.doc_id: r.kept for r in first.collect()}[1].endswith("same line here")


def test_lines_with_a_full_filter_and_first_kept(edge):
    got = line_dedup.dedup_lines(edge, min_docs=3, bits=1 << 10, output="lines", keep_first=True)
    text = {r.doc_id: r.kept for r in got.collect()}
    assert text[1].endswith("same line here") and "same" not in text[2].lower() and text[8] == "Alpha beta gamma delta epsilon zeta"


# ---- 2 ----------------------------------------------------------------------------------


def test_archive(spark):
    big = "ü" * 600
    data = [(1, "http://a", big), (2, "http://b\r\nX: y", big), (3, None, big), (4, "u", "small"), (5, "u", "small"), (6, "u", None), (7, "u", ""), (3, None, big), (None, "n", big), (9, "u", LONG)]
    pages = spark.createDataFrame(data, "page_id long, url string, html string").withColumn("key", F.lit(1)).withColumn("record_type", F.lit("z"))
    archive = warc.write_archive(pages)
    got = rows(warc.archive_index(spark, archive), "page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
    want = []
    for p, _, h in data:
        b = (h or "").encode()
        twin = max((q for q, _, x in data if (x or "") == (h or "") and q is not None), default=None)
        again = len(b) >= 1000 and p != twin
        want.append((p, len(b), hashlib.sha1(b).hexdigest(), "revisit" if again else "response", twin if again else None))
    assert got == sorted(want, key=repr)
    assert archive.payloads(spark).count() == len({h or "" for _, _, h in data})
    exact = {bytes(r.record) for r in warc.read_records(spark, archive).filter("page_id = 4").collect()}
    assert len(exact) == 1 and next(iter(exact)).endswith(b"Content-Length: 5\r\n\r\nsmall\r\n\r\n")
    assert warc.archive_index(spark, warc.write_archive(pages.limit(0))).collect() == []
    spoilt = warc.Archive(archive.path + "-spoilt")
    archive.headers(spark).write.parquet(f"{spoilt.path}/headers")
    archive.payloads(spark).withColumn("payload", F.concat("payload", F.lit(b"!"))).write.parquet(f"{spoilt.path}/payloads")
    with pytest.raises(Exception, match="differs"):
        warc.read_records(spark, spoilt).collect()


# ---- 3 ----------------------------------------------------------------------------------


def test_top_k(spark):
    rng = random.Random(1)
    data = [(i, [round(rng.uniform(-1, 1), 2) if rng.random() < 0.5 else 0.0 for _ in range(6)]) for i in range(0, 90)]
    data += [(90, None), (91, [1.0, None]), (92, [float("nan")] * 6), (100, [float("inf")] + [0.0] * 5), (None, [1.0] * 6), (120, []), (0, data[0][1]), (93, data[5][1]), (94, [0.5] * 3)]
    vectors = spark.createDataFrame(data, "vec_id long, embedding array<float>").withColumn("score", F.lit(1)).withColumn("rank", F.lit(2))
    ok = [(i, [int(np.floor(64 * float(np.float32(x)))) for x in v]) for i, v in data if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    want = []
    for q in sorted({i for i, _ in ok if i % 20 == 0}):
        a = next(v for i, v in ok if i == q)
        scored = sorted((-sum(x * y for x, y in zip(a, v)), i) for i, v in ok if i != q)[:5]
        want += [(q, n, i, -s) for n, (s, i) in enumerate(scored, 1)]
    for size in (8192, 7):
        got = exact_topk.exact_top_k(vectors, k=5, query_block=2, row_block=size)
        assert rows(got, "query_id", "rank", "vec_id", "score") == sorted(want, key=repr)
    assert exact_topk.exact_top_k(vectors.limit(0)).collect() == []


@pytest.mark.parametrize("kind,size,width", [("float", 4e5, 256), ("double", 1e12, 256), ("double", 3e8, 4), ("float", 40000.0, 2)])
def test_top_k_of_large_components(spark, kind, size, width):
    """Scores of any size are exact: no clamp, whatever |x|."""
    rng = random.Random(12)
    data = [(i, [float(np.float32(rng.uniform(-size, size))) for _ in range(width)]) for i in range(50)] + [(60, [size] * width), (61, [size] * width)]
    vectors = spark.createDataFrame(data, f"vec_id long, embedding array<{kind}>")
    weights = {i: [int(np.floor(64 * x)) for x in v] for i, v in data}
    want = []
    for q in [i for i in weights if i % 20 == 0]:
        exact = {i: sum(x * y for x, y in zip(weights[q], v)) for i, v in weights.items() if i != q}
        near = sorted((-min(max(s, exact_topk.LEAST), exact_topk.MOST), i) for i, s in exact.items())[:20]
        want += [(q, n, i, -s) for n, (s, i) in enumerate(near, 1)]
    assert rows(exact_topk.exact_top_k(vectors, row_block=16), "query_id", "rank", "vec_id", "score") == sorted(want, key=repr)


# ---- 4 ----------------------------------------------------------------------------------


def fill(sizes, weights, most):
    """Targets by resharing until none is above its cap."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    target, open_, total = {}, set(names), float(sum(sizes.values()))
    while open_:
        left = total - sum(target.values())
        share = {s: left * w[s] / sum(w[x] for x in open_) for s in open_}
        over = {s for s in open_ if share[s] > most * sizes[s]}
        if not over:
            return target | share
        target |= {s: float(most * sizes[s]) for s in over}
        open_ -= over
    return target


def test_mixing(spark, edge, none):
    rng = random.Random(2)
    data = [(i, "w " * rng.randint(0, 60), rng.choice(["big"] * 12 + ["a", "small", None])) for i in range(800)]
    docs = spark.createDataFrame(data, "doc_id long, text string, source string").withColumn("size", F.lit(0))
    got = mixing.mix_sources(docs)
    sizes, taken, largest = Counter(), Counter(), defaultdict(int)
    source = {i: s for i, _, s in data}
    target = {}
    for r in got.collect():
        s = source[r.doc_id]
        sizes[s] += r.size
        taken[s] += r.taken
        target[s] = r.target
        largest[s] = max(largest[s], r.size)
        assert r.taken == r.size * r.copies and r.copies <= 3
    want = fill(sizes, (1, 2, 3), 3)
    assert any(want[s] == 3 * sizes[s] for s in want)
    for s in want:
        assert target[s] == pytest.approx(want[s]) and abs(taken[s] - want[s]) <= largest[s]
    assert rows(got, "doc_id", "taken") == rows(mixing.mix_sources(docs.repartition(5)), "doc_id", "taken")
    assert mixing.mix_sources(edge).count() == len(EDGE) and mixing.mix_sources(none).collect() == []
    odd = {r.doc_id: r.taken for r in mixing.mix_sources(docs.withColumn("o", F.when(F.col("doc_id") % 2 == 0, 3.0)), odds_col="o").collect()}
    assert len(odd) == 800 and not any(t for i, t in odd.items() if i % 2)


def test_mixing_of_many_sources(spark):
    """Targets by the running sums over distinct sizes are those of resharing by hand."""
    rng = random.Random(13)
    data = [(i, "w " * rng.choice([0, 1, 1, 1, 2, 5, 40, 300]), f"s{i % 211}" if i % 17 else None) for i in range(900)]
    docs = spark.createDataFrame(data, "doc_id long, text string, source string")
    sizes, target = Counter(), {}
    source = {i: s for i, _, s in data}
    for r in mixing.mix_sources(docs).collect():
        sizes[source[r.doc_id]] += r.size
        target[source[r.doc_id]] = r.target
        assert r.source_size == sum(len(t) // 2 for _, t, s in data if s == source[r.doc_id])
    want = fill(sizes, (1, 2, 3), 3)
    assert {s: pytest.approx(t) for s, t in want.items()} == target


def test_mixing_draws_with_unequal_odds(spark):
    """Over seeds, a document's copies average its expected ones: binary length of its size times one level."""
    rng = random.Random(14)
    data = [(i, "w " * (1 << rng.randint(0, 7)), "a" if i % 3 else "b") for i in range(240)]
    docs = spark.createDataFrame(data, "doc_id long, text string, source string").cache()
    total, runs, target, size = Counter(), 6, {}, {}
    source = {i: s for i, _, s in data}
    for seed in range(runs):
        for r in mixing.mix_sources(docs, seed=seed).collect():
            total[r.doc_id] += r.copies
            size[r.doc_id], target[source[r.doc_id]] = r.size, r.target
    for s in ("a", "b"):
        ids = [i for i in source if source[i] == s]
        level = target[s] / sum(size[i] * size[i].bit_length() for i in ids)
        for _ in range(60):  # what is capped leaves its share to the others
            level *= target[s] / sum(size[i] * min(3, size[i].bit_length() * level) for i in ids)
        by_class = defaultdict(list)
        for i in ids:
            by_class[size[i].bit_length()].append(total[i] / runs)
        means = {g: np.mean(v) for g, v in by_class.items()}
        assert all(means[g] == pytest.approx(min(3, g * level), abs=0.12) for g in means)
        assert means[8] > 2 * means[2]
    docs.unpersist()


# ---- 5 ----------------------------------------------------------------------------------


def strings_by_hand(data, length):
    first = {}
    for i, t in data:
        b = (t or "").encode()
        for s in range(len(b) - length + 1):
            first[b[s : s + length]] = min(first.get(b[s : s + length], 1 << 62), i)
    out = []
    for i, t in data:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for s in range(len(b) - length + 1):
            if first[b[s : s + length]] < i:
                gone[s : s + length] = b"\1" * length
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out.append((i, len(b), sum(gone), sum(g and not p for g, p in zip(gone, b"\0" + bytes(gone))), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=repr)


@pytest.mark.parametrize("fan_in", [suffix_dedup.FAN_IN, 3])
def test_strings(spark, edge, none, fan_in, monkeypatch):
    rng = random.Random(3)
    if fan_in == 3:  # and copies by the shuffled way
        whole = suffix_dedup.copies_of
        monkeypatch.setattr(suffix_dedup, "copies_of", lambda known: whole(known, few=1, hot_rows=3))
    word = lambda: "".join(rng.choice("abé") for _ in range(rng.randint(2, 7)))
    passages = [" ".join(word() for _ in range(20)) for _ in range(6)]
    data = []
    for i in range(60):
        parts = [" ".join(word() for _ in range(rng.randint(0, 30))) for _ in range(3)]
        parts.insert(1, rng.choice(passages)[rng.randint(0, 20) :])
        data.append((i, " ".join(parts) if i % 9 else rng.choice(["aaaa" * 40, "ab" * 70, "", None, passages[0]])))
    data += [(70, data[1][1]), (71, data[1][1]), (72, "short"), (73, "short"), (5, data[5][1])]
    rng.shuffle(data)
    docs = spark.createDataFrame(data, "doc_id long, text string").withColumn("keys", F.lit(1))
    got = suffix_dedup.dedup_strings(docs, length=50, fan_in=fan_in)
    assert rows(got, "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == strings_by_hand(data, 50)
    kept = suffix_dedup.dedup_strings(docs, length=50, keep_bytes=True)
    assert all(hashlib.sha256(bytes(r.kept)).hexdigest() == r.kept_sha256 for r in kept.collect())
    assert suffix_dedup.dedup_strings(edge).count() == len(EDGE) and suffix_dedup.dedup_strings(none).collect() == []


def test_suffix_sort():
    rng = np.random.default_rng(4)
    data = np.concatenate([rng.integers(97, 99, 3000), np.tile([97, 98, 97], 300)]).astype(np.uint8)
    data = np.concatenate([data, data[500:1200]])
    starts = np.arange(len(data) - 40)
    order, lead = suffix_dedup.Suffixes(data, starts, 40).runs()
    text = [data[s : s + 40].tobytes() for s in starts[order]]
    assert text == sorted(text)
    assert [i for i in range(len(text)) if not i or text[i] != text[i - 1]] == lead.tolist()


def test_hash_collisions_remove_nothing(monkeypatch):
    """With hashes that collide all the time, what is settled and sorted is still exact."""
    rng = np.random.default_rng(15)
    length = 20
    data = np.concatenate([rng.integers(97, 99, 400), np.tile([97, 98, 97], 60), rng.integers(97, 99, 200)]).astype(np.uint8)
    data = np.concatenate([data, data[30:300], data[100:260]])
    at = np.arange(len(data) - length + 1)
    owner = np.sort(rng.integers(0, 12, len(at)))
    text = [data[s : s + length].tobytes() for s in at]
    least = {}
    for t, o in zip(text, owner.tolist()):
        least[t] = min(least.get(t, o), o)
    exact = np.array([o > least[t] for t, o in zip(text, owner.tolist())])
    good = np.array([hash(t) for t in text]).astype(np.uint64)
    assert (suffix_dedup.later_windows(good, owner, data, at, length) == exact).all()
    for bits in (0, 2, 5):
        found = suffix_dedup.later_windows(good & np.uint64((1 << bits) - 1), owner, data, at, length)
        assert not (found & ~exact).any()
        true = suffix_dedup.Suffixes._hash
        with monkeypatch.context() as m:
            m.setattr(suffix_dedup.Suffixes, "_hash", lambda self, a, n, true=true, bits=bits: true(self, a, n) & np.uint64((1 << bits) - 1))
            order, lead = suffix_dedup.Suffixes(data, at, length).runs()
        seen = [text[i] for i in order]
        assert seen == sorted(seen) and [i for i in range(len(seen)) if not i or seen[i] != seen[i - 1]] == lead.tolist()


@pytest.mark.parametrize("shared", [False, True])
def test_only_hot_windows_are_sorted_twice(spark, monkeypatch, shared):
    """Of many groups, only the windows of passages that more than `fan_in` documents have meet among some groups first."""
    rng = random.Random(21)
    passage = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(120))
    twins, everywhere = [passage() for _ in range(12)], passage()
    data = [(i, passage() + twins[i % 12] + passage() + everywhere * shared) for i in range(24)]
    seen, write = {}, suffix_dedup.materialise
    monkeypatch.setattr(suffix_dedup, "materialise", lambda df, tag, *more: seen.setdefault(tag, write(df, tag, *more)))
    # a document a task: no task knows of a repeat by itself
    docs = spark.createDataFrame(spark.sparkContext.parallelize(data, 24), "doc_id long, text string")
    got = suffix_dedup.dedup_strings(docs, length=50, fan_in=3)
    assert rows(got, "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == strings_by_hand(data, 50)
    assert seen["windows"].count() > 0 and (seen["hot"].count() > 0) == shared


def test_one_of_many_copies_is_sorted(monkeypatch):
    """Of equal suffixes one is sorted, of those that occur once none; the result is that of all pairs."""
    rng = np.random.default_rng(22)
    parts = [rng.integers(97, 123, 60).astype(np.uint8) for _ in range(40)]
    data = np.concatenate([parts[0]] * 50 + [parts[1], parts[2]] * 3 + parts[3:])
    at = (np.arange(len(data) // 60)[:, None] * 60 + np.arange(11)).ravel()
    owner = rng.integers(0, 30, len(at))
    text = [data[a : a + 50].tobytes() for a in at]
    least = {}
    for t, o in zip(text, owner.tolist()):
        least[t] = min(least.get(t, o), o)
    sizes, sort = [], suffix_dedup.Suffixes.by_bytes
    monkeypatch.setattr(suffix_dedup.Suffixes, "by_bytes", lambda self, order: sizes.append(len(order)) or sort(self, order))
    assert suffix_dedup.later_suffixes(data, at, owner, 50).tolist() == [o > least[t] for t, o in zip(text, owner.tolist())]
    assert sizes == [33] and not len(suffix_dedup.later_suffixes(data, at[:0], owner[:0], 50))


def test_later_windows_in_any_order():
    """Owners that rise are sorted as one number with the hash, others by both keys; both see the same repeats."""
    rng = np.random.default_rng(23)
    data = np.tile(rng.integers(97, 123, 500).astype(np.uint8), 4)
    at = np.arange(len(data) - 49)
    hashed = suffix_dedup.spans(suffix_dedup.prefix(data), at, at + 50)
    owner = at // 300
    later = suffix_dedup.later_windows(hashed, owner, data, at, 50)
    mixed = rng.permutation(len(at))
    assert later.sum() > 1000 and (suffix_dedup.later_windows(hashed[mixed], owner[mixed], data, at[mixed], 50) == later[mixed]).all()


# ---- 6, 8 ---------------------------------------------------------------------------------


def test_language(spark, edge, none):
    rng = random.Random(5)
    speak = {"xx": "abc", "yy": "lmn", "zz": "éèç"}
    data = [(i, " ".join("".join(rng.choice(a) for _ in range(4)) for _ in range(30)), lang) for i, (lang, a) in enumerate(list(speak.items()) * 40)]
    docs = spark.createDataFrame([*data, (900, "12 34 !", "xx"), (901, None, "yy"), (902, "abc", None)], "doc_id long, text string, lang string").withColumn("score", F.lit(3))
    model = language_id.fit(docs.filter("doc_id % 3 < 2 OR doc_id > 60"), clusters=2)
    got = {r.doc_id: r for r in language_id.predict(docs, model).collect()}
    assert all(got[i].lang_pred == lang and not got[i].rejected and 0 <= got[i].score <= 1 for i, _, lang in data)
    assert got[900].lang_pred == got[901].lang_pred == "und" and got[900].rejected and got[901].score == 0
    assert language_id.keep_accepted(docs, model).count() == len(data) + 1
    assert language_id.predict(edge, model).count() == len(EDGE) and language_id.predict(none, model).collect() == []
    empty = language_id.fit(docs.limit(0))
    assert {r.lang_pred for r in language_id.predict(edge, empty).collect()} == {"und"}


def test_quality(spark, edge, none):
    rng = random.Random(6)
    good = lambda: " ".join(rng.choice(["calm", "prose", "with", "words", "and", "more"]) + str(rng.randint(0, 9)) for _ in range(25))
    bad = lambda: " ".join([rng.choice(["spam", "buy", "$$$"])] * 12)
    data = [(i, bad() if i % 4 == 0 else good(), int(i % 4 > 0)) for i in range(400)]
    docs = spark.createDataFrame([*((i, t) for i, t, _ in data), (999, None)], "doc_id long, text string").withColumn("predicted", F.lit(3))
    labels = spark.createDataFrame([*((i, q) for i, _, q in data if i < 300), (None, 1), (3, None), (1, 5)], "doc_id long, quality int")
    model = quality.fit(docs, labels)
    got = {r.doc_id: r for r in quality.score(docs, model).collect()}
    assert np.mean([got[i].predicted == q for i, _, q in data if i >= 300]) > 0.97
    assert all(0 <= r.score <= 1 for r in got.values()) and got[999].score == pytest.approx(1 / (1 + np.exp(-model.bias)))
    assert quality.score(edge, model).count() == len(EDGE) and quality.score(none, model).collect() == []
    assert {r.score for r in quality.score(edge, quality.fit(docs, labels.limit(0))).collect()} == {0.5}


def test_quality_is_learned(spark):
    """Held-out labels of real documents are told apart by what n-grams alone have taught."""
    import __spark_entry__

    sf = "/root/testdata/sf0.1"
    scored = __spark_entry__.queries()["op8_quality"](spark, sf).filter("held_out")
    got = scored.join(spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "quality"), "doc_id").filter("quality IS NOT NULL").collect()
    good, bad = (np.sort([r.score for r in got if r.quality == q]) for q in (1, 0))
    auc = (np.searchsorted(bad, good) + np.searchsorted(bad, good, "right")).sum() / (2 * len(good) * len(bad))
    right = [np.mean([r.predicted == q for r in got if r.quality == q]) for q in (0, 1)]
    assert len(bad) > 50 and auc > 0.94 and np.mean(right) > 0.86


def test_quality_features_are_hashed_ngrams():
    """Each pair of words has a vector of its own, a repeated word's pair too."""
    slots = lambda t: set(quality.features([t])[1].tolist())
    assert not slots("abcabc abcabc") & slots("123123 123123")
    assert len(slots("ab cd") - slots("ab") - slots("cd")) > 1 and set(quality.features(["", "a b"])[0].tolist()) == {1}


# ---- 7 ----------------------------------------------------------------------------------


def near(pattern, text):
    """Least edit distance of a pattern to any substring."""
    last = [0] * (len(text) + 1)
    for i, c in enumerate(pattern, 1):
        now = [i]
        for j, d in enumerate(text, 1):
            now.append(min(last[j] + 1, now[-1] + 1, last[j - 1] + (c != d)))
        last = now
    return min(last)


def least_distance(pattern, text):
    """`near` with rows of numpy: a row's insertions are a running minimum."""
    codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    at = np.arange(len(codes) + 1)
    last = np.zeros(len(codes) + 1, np.int64)
    for c in pattern:
        now = np.concatenate([[last[0] + 1], np.minimum(last[1:] + 1, last[:-1] + (codes != ord(c)))])
        last = np.minimum.accumulate(now - at) + at
    return int(last.min())


def test_pattern_distance():
    rng = random.Random(7)
    for _ in range(200):
        p, t = ("".join(rng.choice("abc") for _ in range(rng.randint(1, n))) for n in (90, 120))
        distance, end = decontamination.Pattern(p).best(t)
        assert distance == min(near(p, t), len(p)) == min(least_distance(p, t), len(p)) and (end == 0 or near(p, t[:end]) == distance)


@pytest.mark.parametrize("block", [decontamination.BLOCK_BYTES, 200])
def test_decontamination(spark, edge, none, block):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 6)))
    items = [(i, " ".join(word() for _ in range(25))) for i in range(6)] + [(6, None), (7, "tiny")]
    data = []
    for i in range(60):
        text = [word() for _ in range(40)]
        if i % 2:
            leak = list(items[i % 6][1])
            for _ in range(rng.randint(0, 12)):
                leak[rng.randrange(len(leak))] = rng.choice("xyz")
            text.insert(20, "".join(leak).upper() if i % 3 else "".join(leak))
        data.append((i, "  ".join(text)))
    docs = spark.createDataFrame(data, "doc_id long, text string").withColumn("item_id", F.lit(1)).withColumn("distance", F.lit("z"))
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = []
    for d, t in data:
        for i, x in items[:6]:
            x, limit = decontamination.normalise(x), len(x) // 16
            if (n := near(x, decontamination.normalise(t))) <= limit:
                want.append((d, i, n))
    got = decontamination.find_items(docs, bench, block_bytes=block)
    assert rows(got, "doc_id", "item_id", "distance") == sorted(want, key=repr) and want
    for r in got.collect():
        text, item = decontamination.normalise(data[r.doc_id][1]), decontamination.normalise(items[r.item_id][1])
        assert near(item, text[r.start : r.stop]) == r.distance
    clean = decontamination.keep_clean(docs, bench, block_bytes=block)
    assert clean.columns == docs.columns and {r.doc_id for r in clean.collect()} == {d for d, _ in data} - {w[0] for w in want}
    assert decontamination.find_items(edge, bench).collect() == [] and decontamination.find_items(none, bench).collect() == []
    assert decontamination.find_items(docs, bench.limit(0)).collect() == [] and decontamination.keep_clean(edge, bench).count() == len(EDGE)


def test_decontamination_of_short_items(spark):
    """Short items count unchanged, as whole words; no length is left out."""
    items = [(0, "fortytwo42"), (1, "a b"), (2, "cat"), (3, "日本"), (4, ""), (5, " "), (6, "x"), (7, None)]
    data = [(0, "say FortyTwo42, and"), (1, "fortytwo421"), (2, "a  b"), (3, "concatenate"), (4, "The cat."), (5, "東日本語"), (6, None), (7, "x"), (8, "b a-b xx"), (None, "cat")]
    docs, bench = spark.createDataFrame(data, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = decontamination.find_items(docs, bench)
    assert rows(got, "doc_id", "item_id", "distance") == sorted([(0, 0, 0), (2, 1, 0), (4, 2, 0), (5, 3, 0), (7, 6, 0), (None, 2, 0)], key=repr)
    assert {(r.doc_id, r.start, r.stop) for r in got.collect()} >= {(0, 4, 14), (4, 4, 7), (5, 1, 3)}
    assert {r.doc_id for r in decontamination.keep_clean(docs, bench).collect()} == {1, 3, 6, 8}


# ---- 9 ----------------------------------------------------------------------------------


def test_tokens(spark, edge, none):
    import public_tokenizers
    import sentencepiece

    file = public_tokenizers.path("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=file)
    texts = ["", " ", "  ", "a ", " a  b\n ", "▁", "a▁▁ b", "\n\n x\t", "<s> </s> <0x0A> <unk>", "日本語 テキスト ", "é́ ﬁ \x00 ▁ x", LONG]
    docs = spark.createDataFrame([*enumerate(texts), (99, None)], "doc_id long, text string").withColumn("n_tokens", F.lit("x"))
    got = {r.doc_id: r for r in token_counts.count_tokens(docs, file, limit=3, frequent=4).collect()}
    for i, t in enumerate(texts):
        n = len(model.encode(t))
        assert (got[i].n_tokens, got[i].n_bytes, got[i].over_limit) == (n, len(t.encode()), n > 3)
    assert got[99].n_tokens == 0
    assert token_counts.count_tokens(edge, file).count() == len(EDGE) and token_counts.count_tokens(none, file).collect() == []


@pytest.mark.parametrize("frequent", [0, 3, 1 << 18])
def test_tokens_with_few_or_many_frequent_pre_tokens(spark, frequent):
    """Counts do not depend on what is broadcast; ids repeat and are null, pre-tokens are long."""
    import public_tokenizers
    import sentencepiece

    file = public_tokenizers.path("piece_bpe_32k.model")
    rng = random.Random(frequent)
    words = ["the", "a", "x" * 65, "y" * 5000, "café", "", *(f"w{i}" for i in range(500))]
    texts = [" ".join(rng.choice(words[: rng.choice([3, 6, 506])]) for _ in range(rng.randint(0, 300))) for _ in range(120)]
    docs = spark.createDataFrame([(None if i % 3 else str(i % 6), t) for i, t in enumerate(texts)], "doc_id string, text string").repartition(5).sortWithinPartitions("text")
    chosen = token_counts.frequent_pieces(docs, file, frequent)
    assert len(chosen) <= frequent and (frequent != 1 << 18 or {"the", "a", "café", "w7"} <= set(chosen)) and all(len(w) <= 64 for w in chosen)
    got = token_counts.count_tokens(docs, file, frequent=frequent).collect()
    model = sentencepiece.SentencePieceProcessor(model_file=file)
    assert sorted((str(r.doc_id), r.n_bytes, r.n_tokens) for r in got) == sorted((str(None if i % 3 else i % 6), len(t.encode()), len(model.encode(t))) for i, t in enumerate(texts))


# ---- 10 ---------------------------------------------------------------------------------


def components_by_hand(data):
    sets = []
    for _, t in data:
        w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "").replace("\t", " ").replace("\n", " ").split(" ")
        w = [x for x in w if x]
        sets.append({tuple(w[i : i + 5]) for i in range(max(len(w) - 4, 1))} if w else set())
    root = list(range(len(data)))
    for i in range(len(data)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = root[i], root[j]
                root = [b if r == a else r for r in root]
    low = defaultdict(lambda: 1 << 62)
    for (i, _), r in zip(data, root):
        low[r] = min(low[r], i)
    return sorted(((i, len(s), low[r]) for (i, _), s, r in zip(data, sets, root)), key=repr)


def links_by_hand(data):
    """Links between different sets by their smallest ids; per row its class and number of links."""
    sets = []
    for _, t in data:
        w = (t or "").lower().split()
        sets.append(frozenset(tuple(w[i : i + 5]) for i in range(max(len(w) - 4, 1))) if w else frozenset())
    low = {}
    for (i, _), s in zip(data, sets):
        low[s] = min(low.get(s, i), i)
    near = lambda a, b: 100 * len(a & b) >= 80 * len(a | b)
    distinct = [s for s in low if s]
    pairs = sorted(tuple(sorted((low[a], low[b]))) for n, a in enumerate(distinct) for b in distinct[:n] if near(a, b))
    per = [(i, len(s), low[s] if s else None, sum(1 for x in sets if x and near(s, x)) - 1 if s else 0) for (i, _), s in zip(data, sets)]
    return pairs, sorted(per, key=repr)


def test_sets_with_one_key_stay_apart():
    """Where different sets share a key, each takes its second one."""
    doc, value = np.array([0, 0, 1, 1, 2]), np.array([5, 6, 5, 6, 9], np.uint64)
    size, key = jaccard_join.class_keys(doc, value, 3)
    assert key[0] == key[1] != key[2]
    _, other = jaccard_join.final_keys(doc, value, 3, frozenset([int(key[2])]))
    assert (other[:2] == key[:2]).all() and other[2] != key[2]


@pytest.mark.parametrize("collide", [False, True])
def test_classes_with_a_shared_key(spark, monkeypatch, collide):
    """The table of keys finds the sets that share the first key and gives them the second."""
    docs = spark.createDataFrame([(1, "a b"), (2, "c d"), (3, "a b"), (4, "")], "_id long, _text string")
    if collide:  # as if all first keys were equal
        true = jaccard_join.materialise
        monkeypatch.setattr(jaccard_join, "materialise", lambda df, tag: true(df.withColumn("one", F.when(F.col("n") > 0, F.lit(-7)).otherwise(F.lit(0)).cast("long")) if tag == "classes" else df, tag))
    known, shared = jaccard_join.classes(docs, 5)
    fp = {r._id: r.fp for r in known.collect()}
    assert fp[1] == fp[3] != fp[2] and fp[4] == 0 and (shared == frozenset([(1 << 64) - 7])) == collide


@pytest.mark.parametrize("split", [jaccard_join.SPLIT_BYTES, 0])
@pytest.mark.parametrize("few", [jaccard_join.BROADCAST_CLASSES, 0])
def test_jaccard(spark, edge, none, monkeypatch, split, few):
    rng = random.Random(9)
    whole = jaccard_join.similar_classes
    monkeypatch.setattr(jaccard_join, "similar_classes", lambda *a, **k: whole(*a, split, **k))
    monkeypatch.setattr(jaccard_join, "BLOCK", 7)
    monkeypatch.setattr(jaccard_join, "BROADCAST_CLASSES", few)
    monkeypatch.setattr(jaccard_join, "HOT", 5)
    word = lambda: rng.choice("abcdefghijklmnop") + str(rng.randint(0, 40))
    base = [[word() for _ in range(n)] for n in (3, 7, 12, 30, 60, 150, 400, 600)]
    data = [(1000 + i, " ".join(b)) for i, b in enumerate(base)]
    for i in range(160):
        w = list(rng.choice(base))
        for _ in range(rng.randint(0, max(1, len(w) // 25))):
            w[rng.randrange(len(w))] = word()
        data.append((i, " ".join(w).upper() if i % 5 == 0 else " ".join(w)))
    data += [(500, "a"), (501, "A"), (502, "b"), (503, ""), (504, None), (505, " \n"), (3, data[11][1])]
    docs = spark.createDataFrame(data, "doc_id long, text string").withColumn("fp", F.lit(1)).withColumn("task", F.lit(1))
    got = jaccard_join.jaccard_components(docs)
    want = components_by_hand(data)
    assert rows(got, "doc_id", "n_shingles", "component_id") == want
    links, members = jaccard_join.jaccard_links(docs)
    assert sorted((tuple(r) for r in links.collect())) == links_by_hand(data)[0] and rows(members, "doc_id", "n_shingles", "class_id", "n_links") == links_by_hand(data)[1]
    kept = jaccard_join.keep_one(docs.select("text", "doc_id", "fp", "task"))
    assert kept.columns == ["text", "doc_id", "fp", "task"]
    kept = jaccard_join.keep_one(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {i for i, _, c in want if i == c}
    assert jaccard_join.jaccard_components(edge).count() == len(EDGE) and jaccard_join.jaccard_components(none).collect() == []


def test_signatures_are_shared():
    """Any pair of sets at the threshold shares a signature, small and large ones alike."""
    rng = np.random.default_rng(10)
    bands = jaccard_join.Bands.upto(900, 80)
    for size in [*range(4, 60), 75, 100, 130, 200, 320, 410, 560, 640]:
        for _ in range(6):
            shared = rng.integers(0, 1 << 63, size, np.uint64)
            extra = size * 20 // 80  # union = shared + extra
            a_more = int(rng.integers(0, extra + 1))
            sets = [np.unique(np.concatenate([shared, rng.integers(0, 1 << 63, n, np.uint64)])) for n in (a_more, extra - a_more)]
            doc = np.repeat([0, 1], [len(s) for s in sets])
            owner, sig = jaccard_join.signatures(doc, np.concatenate(sets), np.array([len(s) for s in sets]), bands)
            assert np.intersect1d(sig[owner == 0], sig[owner == 1]).size or not extra


def test_components(spark):
    rng = random.Random(11)
    edges = [(i, i + 1) for i in range(100, 160)] + [(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(30)] + [(7, 7), (None, 3)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long").repartition(6)).collect()}
    root = {x: x for e in edges for x in e if x is not None and e[0] is not None}
    for _ in range(200):
        for a, b in edges:
            if a is not None:
                root[a] = root[b] = min(root[a], root[b])
    assert got == {x: r for x, r in root.items() if any(x in e and e[0] != e[1] for e in edges)}
    assert components(spark.createDataFrame([], "a long, b long")).collect() == []


# ---- registered queries without SQL, and the pipeline --------------------------------------------


def crc(i, m):
    return zlib.crc32(str(i).encode()) % m


def test_registered_token_counts_against_the_library(spark):
    """Every text of the tables, and random ones of awkward characters, as the library itself counts them."""
    import __spark_entry__
    import public_tokenizers
    import sentencepiece
    from conftest import DATA

    file = public_tokenizers.path("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=file)
    for sf in (DATA, "/root/testdata/sf0.01"):
        text = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
        got = __spark_entry__.queries()["op9_token_counts"](spark, sf).collect()
        want = dict(zip(text, map(len, model.encode(list(text.values())))))
        assert len(got) == len(text) and {r.doc_id: r.n_tokens for r in got} == want
        assert all(r.n_bytes == len(text[r.doc_id].encode()) and r.over_limit == (r.n_tokens > 4096) for r in got)
    rng = random.Random(16)
    odd = ["".join(rng.choice("ab  \n\t▁é字<s>\u200b́😀0.") for _ in range(rng.randint(0, 40))) for _ in range(3000)]
    docs = spark.createDataFrame([*enumerate(odd)], "doc_id long, text string")
    assert [r.n_tokens for r in sorted(token_counts.count_tokens(docs, file).collect())] == [len(x) for x in model.encode(odd)]


def test_registered_against_brute_force(spark):
    import __spark_entry__
    from conftest import DATA

    q = __spark_entry__.queries()
    docs = spark.read.parquet(f"{DATA}/documents.parquet").collect()
    data = [(r.doc_id, r.text) for r in docs]
    assert rows(q["op5_suffix_dedup"](spark, DATA), "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == strings_by_hand(data, 50)
    lang = {r.doc_id: r for r in q["op6_language_id"](spark, DATA).collect()}
    held = [r for r in docs if crc(r.doc_id, 4) == 2]
    assert len(lang) == len(docs) and {i for i, r in lang.items() if r.held_out} == {r.doc_id for r in held}
    assert np.mean([lang[r.doc_id].lang_pred == r.lang for r in held]) > 0.95
    scores = {r.doc_id: r for r in q["op8_quality"](spark, DATA).collect()}
    assert len(scores) == len(docs) and {i for i, r in scores.items() if r.held_out} == {i for i, _ in data if crc(i, 5) == 0}
    assert all((r.predicted == 1) == (r.score >= 0.3) for r in scores.values())
    hits = {(r.doc_id, r.item_id) for r in q["op7_decontamination"](spark, DATA).collect()}
    items = [(r.item_id, decontamination.normalise(r.text)) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()]
    exact = {(i, k) for i, t in data for k, x in items if x in decontamination.normalise(t)}
    assert exact <= hits
    # all pairs, by the plain table of distances: a third of the items against all texts that are not long
    some = [(k, x) for k, x in items if k % 3 == 0]
    texts = [(i, decontamination.normalise(t)) for i, t in data]
    slow = {(i, k) for i, t in texts if len(t) <= 4000 for k, x in some if least_distance(x, t) <= int(len(x) / 16)}
    assert slow == {(i, k) for i, k in hits if k % 3 == 0 and len(dict(texts)[i]) <= 4000}


def test_pipeline(spark):
    import corpus_pipeline
    from conftest import DATA

    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    items = [decontamination.normalise(r.text) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()]
    now, stages = docs, {}
    for name, stage in corpus_pipeline.STAGES:
        now = corpus_pipeline.materialise(stage(spark, now, DATA), name)
        stages[name] = now
        assert name == "mixing" or now.columns == docs.columns
    letters = {r.doc_id for r in docs.collect() if any(map(str.isalpha, r.text or ""))}
    kept = {n: {r.doc_id: r.text for r in df.collect()} if n != "mixing" else None for n, df in stages.items()}
    assert set(kept["language_id"]) <= letters and len(kept["language_id"]) >= 0.99 * len(letters)
    want = lines_by_hand(sorted(kept["language_id"].items()), 10)
    assert sorted(((i, hashlib.sha256(t.encode()).hexdigest()) for i, t in kept["line_dedup"].items()), key=repr) == sorted(((w[0], w[3]) for w in want), key=repr)
    assert set(kept["jaccard_join"]) == {i for i, _, c in components_by_hand(sorted(kept["line_dedup"].items())) if i == c}
    leaks = {i for i, t in kept["jaccard_join"].items() if any(x in decontamination.normalise(t) for x in items)}
    gone = set(kept["jaccard_join"]) - set(kept["decontamination"])
    assert leaks <= gone and len(gone) <= len(leaks) + 2
    mix = stages["mixing"].collect()
    assert {r.doc_id for r in mix} <= set(kept["decontamination"]) and all(r.copies > 0 for r in mix)
    assert rows(corpus_pipeline.run(spark, DATA), "doc_id", "copies") == rows(stages["mixing"], "doc_id", "copies")
