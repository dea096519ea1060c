"""Licence scan, quality, language, dropout codec, exact dedup: values and edges."""

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from knotwork.llm import exact_dedup, language_id, license_scan, merge_dropout, quality, queries
from knotwork.llm.tokenization import PieceEncoder, tokenizer_path

from .helpers import AWKWARD, LONG, docs


def lev(a, b, cap):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
        if min(row) > cap:
            return cap + 1
    return row[-1]


def brute_scan(text):
    """Best similarity of each label over every window of words."""
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (text or ""))
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lowered)
    out = {}
    for label, notice, edits in license_scan.NOTICES:
        n = notice.count(" ") + 1
        for i in range(len(words)):
            for m in range(max(1, n - edits), n + edits + 1):
                window = " ".join(words[i : i + m])
                if i + m <= len(words) and abs(len(window) - len(notice)) <= edits and (d := lev(window, notice, edits)) <= edits:
                    out[label] = max(out.get(label, 0), 1 - d / len(notice))
    places = [(i, v) for p, v in license_scan.BASE.items() for i in range(len(words)) if words[i : i + p.count(" ") + 1] == p.split()]
    return words, places, out


VARIANTS = [
    "Released under the MIT License.", "the mti license", "MIT licence text", "Apachee Licens 2", "Licensed under the Apache-License, v2", "gnu genral public licence",
    "General\nPublic License and general public license", "redistribution & use in source and binary forms", "redistributoin and use in source an binary forms",
    "Creative Commons Atribution", "licensed under CC-BY 4", "unit license", "mozila publik license", "permision is hereby granted free of charge", "it is a licence of mine", "mit", "é mit license é",
]


def test_license_scan_equals_brute_force(spark):
    rnd = random.Random(3)
    filler = "alpha beta gamma license public general mit source forms use and of the".split()
    texts = VARIANTS + [" ".join(rnd.choice(filler) for _ in range(40)) + " " + rnd.choice(VARIANTS) for _ in range(60)]
    texts += [t for _, t, *_ in AWKWARD if t is None or len(t) < 1000]
    rows = {r["doc_id"]: r for r in license_scan.scan(docs(spark, list(enumerate(texts)))).collect()}
    for i, t in enumerate(texts):
        words, places, best = brute_scan(t)
        r = rows[i]
        assert (r["n_words"], r["n_base"]) == (len(words), len(places)), t
        assert r["first_word"] == min((p for p, _ in places), default=None) and r["last_word"] == max((p for p, _ in places), default=None)
        assert r["base_labels"] == ",".join(sorted({v for _, v in places}))
        assert r["labels"] == ",".join(sorted({v for _, v in places} | set(best))), t
        assert r["score"] == pytest.approx(max([*best.values(), 1.0 if places else 0.0], default=0.0)), t
        spans = {}
        for _, notice, e in license_scan.NOTICES:
            n = notice.count(" ") + 1
            for i in range(len(words)):
                for m in range(max(1, n - e), n + e + 1):
                    window = " ".join(words[i : i + m])
                    if i + m <= len(words) and abs(len(window) - len(notice)) <= e and (d := lev(window, notice, e)) <= e:
                        spans[notice] = min(spans.get(notice, (9, 0, 0)), (d, i, m))
        assert r["best"] == "|".join(f"{x}:{i}:{m}:{d}" for x, (d, i, m) in sorted(spans.items())), t
        for s in r["spans"]:
            window = " ".join(words[s["first_word"] : s["first_word"] + s["n_words"]])
            assert lev(window, s["notice"], 9) == s["edits"]


def test_license_scan_of_long_texts_and_empty_tables(spark):
    long = "filler words " * 30_000 + "apache licence" + " more" * 30_000
    row = license_scan.scan(docs(spark, [(1, long)])).first()
    assert row["labels"] == "apache" and row["n_words"] == 60_000 + 2 + 30_000 and row["spans"][0]["first_word"] == 60_000
    assert license_scan.scan(docs(spark, [])).count() == 0


def test_normalisation_of_white_space():
    for t in ("", " ", "a", " a", "a \n", "\t a\r\n\x0b\x0cb ", "a b", "\x1c a"):
        assert exact_dedup.normalise(t.encode()).decode() == re.sub(r"[\x20\x09-\x0D]+", " ", t)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.tuples(st.booleans(), st.integers(0, 400)), max_size=300))
def test_cuckoo_bucket_equals_a_dictionary(steps):
    bucket, truth = exact_dedup.Bucket(), {}
    for adds, x in steps:
        d = hashlib.sha256(str(x).encode()).digest()
        if adds:
            assert bucket.add(d, x, 1) == (d not in truth)
            truth[d] = truth.get(d, 0) + 1
        else:
            left = truth.pop(d, 0) - 1
            assert bucket.settle(d, x, left) == (left >= 0)
            if left > 0:
                truth[d] = left
    assert {k: v[1] for k, v in bucket.keys.items()} == truth and bucket.filter.held == len(truth)
    assert all(bucket.filter.might_hold(d) for d in truth)


def test_cuckoo_filter_resizes_without_losing_keys():
    b = exact_dedup.Bucket()
    keys = [hashlib.sha256(str(i).encode()).digest() for i in range(5000)]
    for i, k in enumerate(keys):
        b.add(k, i, 1)
    assert b.resized > 2 and all(b.filter.might_hold(k) for k in keys)
    other = [hashlib.sha256(f"x{i}".encode()).digest() for i in range(5000)]
    assert sum(map(b.filter.might_hold, other)) < 50
    again = exact_dedup.Bucket(__import__("pandas").Series(b.row(3)))
    assert again.keys == b.keys and again.filter.table == b.filter.table


def test_exact_dedup_cases(spark):
    rows = {}
    for r in exact_dedup.classify(docs(spark, AWKWARD)).collect():
        rows.setdefault(r["doc_id"], []).append(r)
    assert rows[6][0]["keep_id"] == 5 and rows[5][0]["kept"] and not rows[6][0]["kept"] and rows[7][0]["group_size"] == 1
    assert rows[10][0]["keep_id"] == 9 and rows[16][0]["keep_id"] == 15 and len(rows[8]) == 2 and rows[8][0]["group_size"] == 2
    assert rows[None][0]["keep_id"] is None and rows[None][0]["kept"]
    assert rows[5][0]["text_sha256"] == hashlib.sha256(b"").hexdigest()
    kept = sorted((r["doc_id"] for r in exact_dedup.keep_first(docs(spark, AWKWARD)).collect()), key=str)
    assert kept == [11, 12, 13, 14, 15, 5, 7, 8, 9, None]
    assert exact_dedup.classify(docs(spark, [])).count() == 0 and exact_dedup.keep_first(docs(spark, [])).count() == 0


def live(index):
    return sorted(((r["keep_id"], r["group_size"]) for r in index.entries().collect()), key=str)


def test_exact_index_over_batches(spark):
    a, b = docs(spark, [(1, "x"), (2, "y"), (4, "x")]), docs(spark, [(0, "x"), (3, "z"), (None, "n")])
    index = exact_dedup.CuckooIndex.build(exact_dedup.digests(a)).insert(exact_dedup.digests(b))
    assert live(index) == [(0, 3), (2, 1), (3, 1), (None, 1)]
    index = index.delete(exact_dedup.digests(docs(spark, [(2, "y"), (4, "x"), (9, "never"), (7, "x"), (None, "n")])))
    assert live(index) == [(0, 2), (3, 1)]


def test_deletion_leaves_the_smallest_live_id(spark):
    rows = [(1, "a"), (5, "a"), (5, "a"), (9, "a"), (2, "b"), (None, "b")]
    index = exact_dedup.CuckooIndex.build(exact_dedup.digests(docs(spark, rows)))
    gone = []
    for step in ([(1, "a")], [(5, "a"), (2, "b")], [(5, " a".strip())], [(9, "a"), (9, "a"), (None, "b")]):
        index, gone = index.delete(exact_dedup.digests(docs(spark, step))), gone + step
        left = list(rows)
        for r in gone:
            if r in left:
                left.remove(r)
        want = [(min((i for i, t in left if t == x and i is not None), default=None), sum(t == x for _, t in left)) for x in "ab" if any(t == x for _, t in left)]
        assert live(index) == sorted(want, key=str)
        filters = [exact_dedup.Bucket(r).filter.held for _, r in index.table.toPandas().iterrows()]
        assert sum(filters) == len(want)


def test_index_grows_with_its_batches(spark):
    first = exact_dedup.digests(docs(spark, [(i, f"t{i}") for i in range(20)]))
    index = exact_dedup.CuckooIndex.build(first, per_bucket=20)
    more = index.insert(exact_dedup.digests(docs(spark, [(i, f"t{i % 400}") for i in range(20, 500)])))
    assert more.buckets > index.buckets
    want = {}
    for i in range(500):
        want.setdefault(f"t{i}" if i < 20 else f"t{i % 400}", []).append(i)
    assert live(more) == sorted(((min(v), len(v)) for v in want.values()), key=str)


REPEATED = [(1, "alpha one"), (1, "beta two"), (2, "alpha one"), (None, "gamma three"), (None, "gamma three"), (None, "alpha one"), (3, "delta  four"), (3, "delta four"), (4, "same row"), (4, "same row")]


def test_no_text_under_a_repeated_or_missing_id_is_lost(spark):
    kept = [(r["doc_id"], r["text"]) for r in exact_dedup.keep_first(docs(spark, REPEATED)).collect()]
    assert len(kept) == 5 and {exact_dedup.normalise(t.encode()) for _, t in kept} == {exact_dedup.normalise(t.encode()) for _, t in REPEATED}
    assert {i for i, t in kept if t == "alpha one"} == {1} and exact_dedup.keep_first(docs(spark, REPEATED)).columns == docs(spark, []).columns


def test_quality_separates_and_resamples(spark):
    rnd = random.Random(5)
    words = [f"w{i}" for i in range(200)]
    good = [" ".join(rnd.choice(words) for _ in range(60)) + "." for _ in range(300)]
    junk = [" ".join(rnd.choice(words) + rnd.choice(["$$$", "%%%", "!!"]) for _ in range(60)) for _ in range(60)] + ["same " * 80] * 5
    rows = [(i, t) for i, t in enumerate(good + junk)]
    labels = spark.createDataFrame([(i, int(i < 300), 0) for i in range(0, 365, 2)] + [(None, 1, 0), (3, None, None)], "doc_id long, quality int, toxic int")
    out = {r["doc_id"]: r for r in quality.resample(docs(spark, rows + [(900, None), (901, ""), (902, " \n")]), labels).collect()}
    assert sum(out[i]["kept"] for i in range(300)) >= 297 and sum(out[i]["kept"] for i in range(300, 365)) <= 3
    assert all(out[i]["log_weight"] is None and not out[i]["kept"] for i in (900, 901, 902))
    kept = quality.select(docs(spark, rows), labels)
    assert kept.columns == docs(spark, []).columns
    alone = quality.resample(docs(spark, rows), labels)  # the texts without words take no part in either
    assert {r["doc_id"] for r in kept.collect()} == {r["doc_id"] for r in alone.where("kept").collect()}


def brute_weights(rows, labels, sample=20_000, buckets=1 << 13, smooth=0.02, seed=17):
    """Log weight and key of each row, from the definitions."""
    import math

    import xxhash

    h = xxhash.xxh3_64_intdigest
    def grams(text):
        t = [h(x) for x in re.findall(rb"[a-z0-9\x80-\xff]+|[^\sa-z0-9\x80-\xff]+", (text or "").encode().lower())]
        pairs = []
        for a, b in zip(t, t[1:]):
            p = (a * 0x9E3779B97F4A7C15 + b) % (1 << 64)
            pairs.append(2 * buckets if a == b else (p ^ p >> 31) % buckets + buckets)
        return [x % buckets for x in t] + pairs

    fitted = {i for i in {i for i, q in labels if i is not None and q == 1} if h(f"{seed}:{i}".encode()) % 5}
    raw, good = [0] * (2 * buckets + 1), [0] * (2 * buckets + 1)
    for i, t in rows:
        for g in grams(t):
            raw[g] += 1
            good[g] += i in fitted
    ratio = {}
    for low, high in ((0, buckets), (buckets, 2 * buckets + 1)):
        n, m = sum(raw[low:high]) + 0.5 * (high - low), max(1, sum(good[low:high]))
        for g in range(low, high):
            p = (raw[g] + 0.5) / n
            ratio[g] = math.log((1 - smooth) * good[g] / m + smooth * p) - math.log(p)
    out = []
    for i, t in rows:
        f = grams(t)
        u = ((h(f"g{seed}:{i}".encode()) >> 11) + 0.5) / (1 << 53)
        w = math.fsum(ratio[g] for g in f) if f else None
        out.append((i, w, None if w is None else w - math.log(-math.log(u))))
    return out


def test_quality_equals_the_definitions(spark):
    rnd = random.Random(11)
    rows = [(i, " ".join(rnd.choice(["ab", "cd!", "ef, ef", "Gé", "x1 $$"]) for _ in range(rnd.randint(0, 30)))) for i in range(200)]
    rows += [(7, "another text of seven"), (None, "ab cd"), (300, None), (301, " "), (302, "ab " * 30_000)]
    labels = [(i, int(i % 3 > 0)) for i in range(120)] + [(None, 1), (5, None)]
    want = brute_weights(rows, labels)
    table = spark.createDataFrame([(*r, 0) for r in labels], "doc_id long, quality int, toxic int")
    for k in (None, 0, 10, 500):
        got = quality.resample(docs(spark, rows), table, k=k).collect()
        key = lambda r: (str(r[0]), -1e18 if r[1] is None else r[1])
        for r, w in zip(sorted(map(tuple, got), key=key), sorted(want, key=key), strict=True):
            assert r[0] == w[0] and (r[1] is None) == (w[1] is None)
            assert w[1] is None or (r[1] == pytest.approx(w[1], rel=1e-9, abs=1e-9) and r[2] == pytest.approx(w[2], rel=1e-9, abs=1e-9))
        if k is not None:
            keys = sorted((w[2] for w in want if w[2] is not None), reverse=True)
            cut = keys[min(k, len(keys)) - 1] if k else float("inf")
            assert sorted(str(r["doc_id"]) for r in got if r["kept"]) == sorted(str(w[0]) for w in want if w[2] is not None and w[2] >= cut - 1e-9)


def test_quality_edges(spark):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r["doc_id"] for r in quality.resample(docs(spark, AWKWARD), none).where("kept").collect()} == {8, 9, 10, 11, 12, 13, 14, 15, 16, None}
    assert quality.resample(docs(spark, []), none).count() == 0


def test_kth_largest_is_exact(spark):
    rnd = random.Random(2)
    values = [rnd.gauss(0, 1e3) for _ in range(500)] + [0.0, -0.0, 5.0, 5.0]
    df = spark.createDataFrame([(int(x),) for x in quality.ordered_bits(np.array(values))] + [(None,)], "b long")
    bits = sorted((int(x) for x in quality.ordered_bits(np.array(values))), reverse=True)
    for k in (1, 2, 250, 504):
        assert quality.kth_largest(df, "b", k) == bits[k - 1]
    assert quality.kth_largest(df, "b", 505) is None and quality.kth_largest(df, "b", 0) is None
    assert (np.diff(quality.ordered_bits(np.sort(values))) >= 0).all()


def test_gumbel_keys_sample_in_proportion():
    w = np.array([1.0, 2.0, 4.0])
    first = np.zeros(3)
    for s in range(4000):
        first[(np.log(w) + quality.gumbel([0, 1, 2], s)).argmax()] += 1
    assert np.allclose(first / 4000, w / w.sum(), atol=0.03)


def test_language_network(spark, sf):
    table = spark.read.parquet(f"{sf}/documents.parquet")
    net = language_id.train(table, per_language=100)
    rows = language_id.predict(table, net).join(table.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r["lang"] == r["lang_pred"] for r in rows) >= 0.9 * len(rows) and all(0 <= r["score"] <= 1 for r in rows)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)
    odd = {r["doc_id"]: r for r in language_id.predict(docs(spark, AWKWARD), net).collect()}
    assert all(odd[i]["lang_pred"] == "und" and odd[i]["score"] == 0 for i in (5, 6, 7, 11)) and odd[13]["lang_pred"] in net.labels
    assert language_id.predict(docs(spark, []), net).count() == 0
    long = [(13, LONG), (12, AWKWARD[7][1])]
    rows = language_id.predict(docs(spark, long), net).collect()
    for (_, text), r in zip(long, rows, strict=True):  # every window of the whole text, one by one
        raw = text.encode()
        p = np.mean([net.windows_probabilities(language_id.windows(raw[at : at + 256], 256))[0].astype(float) for at in range(0, len(raw), 256)], axis=0)
        assert r["lang_pred"] == net.labels[p.argmax()] and r["score"] == pytest.approx(p.max(), abs=1e-5)


def test_training_reads_whole_texts_and_each_language(spark):
    head = "the same heading in front of every text " * 40
    rows = [(i, head + ("ouvre la porte maintenant " if i % 2 else "öffne jetzt bitte die tür ") * 300, "fr" if i % 2 else "de") for i in range(60)]
    rows += [(100 + i, "otra lengua muy rara aquí", "es") for i in range(6)] + [(200 + i, "a copy that stands everywhere", "en") for i in range(300)]
    some = language_id.training_windows(docs(spark, rows), per_language=5, languages=9, per_text=2, length=256)
    assert {y for _, y in some} == {"fr", "de", "es", "en"} and sum(y == "en" for _, y in some) == 1 and sum(y == "fr" for _, y in some) <= 10
    assert any(b"porte" in w for w, _ in some) and any("tür".encode() in w for w, _ in some)
    assert {y for _, y in language_id.training_windows(docs(spark, rows), 5, 1, 2, 256)} == {"en"}
    assert len(language_id.drawn_windows(b"x" * 10_000, 256, 3, 1)) == 3 and language_id.drawn_windows(b"ab", 256, 3, 1) == [b"ab"]


def test_language_without_training_rows(spark):
    rows = language_id.predict(docs(spark, AWKWARD), language_id.train(docs(spark, [(1, "x")]))).collect()
    assert {r["lang_pred"] for r in rows} == {"und"}


def test_language_rejects_only_texts_without_a_letter(spark, monkeypatch):
    lettered = {8, 9, 10, 12, 13, 14, 15, 16, None}
    nameless = docs(spark, [(i, t) for i, t, *_ in AWKWARD])
    assert {r["doc_id"] for r in language_id.select(nameless).collect()} == lettered

    class Unsure:
        labels = ["a", "b", "c", "d", "e"]

        def predict(self, texts):
            return [("a", 0.2) if language_id.has_letter(t or b"") else ("und", 0.0) for t in texts]

    monkeypatch.setattr(language_id, "train", lambda docs: Unsure())
    assert {r["doc_id"] for r in language_id.select(docs(spark, AWKWARD)).collect()} == lettered
    assert language_id.select(docs(spark, AWKWARD), least=0.3).count() == 0


def test_network_gradients_and_compilation():
    rng = np.random.default_rng(0)
    net = language_id.ByteCNN(["a", "b", "c"], length=20, widths=(2, 3, 4), filters=3, embed=4)
    x, y = rng.integers(0, 60, (6, 20)), rng.integers(0, 3, 6)
    loss = lambda: -np.log(net.forward(x)[0][np.arange(6), y]).mean()
    for p, g in zip(net.parameters(), net.gradients(x, y), strict=True):
        for at in [tuple(rng.integers(0, s) for s in p.shape) for _ in range(5)]:
            old, eps = p[at], 1e-6
            p[at] = old + eps
            up = loss()
            p[at] = old - eps
            down = loss()
            p[at] = old
            assert g[at] == pytest.approx((up - down) / (2 * eps), abs=1e-5)
    assert np.allclose(net.compile().windows_probabilities(x), net.forward(x)[0], atol=1e-5)


@pytest.fixture(scope="module")
def pieces():
    import sentencepiece

    path = tokenizer_path("piece_bpe_32k.model")
    return merge_dropout.Vocabulary(path), sentencepiece.SentencePieceProcessor(model_file=path)


TEXTS = st.text(st.sampled_from(list(" \n\tab'sZé1,.x\x01\x02ﬁ①中😀▁theingtion")), max_size=120)


@settings(max_examples=300, deadline=None)
@given(TEXTS)
def test_no_dropout_is_the_models_own_encoding(pieces, text):
    v, sp = pieces
    ids = np.frombuffer(merge_dropout.MergeDropout(v, 0.0, 1, 0).encode(pa.array([text]))[0], "<u4").tolist()
    assert v.decode(ids).decode() == text
    if "▁" not in text:
        assert ids == sp.encode(text)


@settings(max_examples=200, deadline=None)
@given(TEXTS, st.integers(0, 5), st.sampled_from([0.1, 0.5, 1.0]))
def test_dropout_is_lossless_and_repeatable(pieces, text, seed, rate):
    v, _ = pieces
    run = lambda: merge_dropout.MergeDropout(v, rate, seed, 0).encode(pa.array([text, None, ""]))
    a = run()
    assert v.decode(np.frombuffer(a[0], "<u4").tolist()).decode() == text and a == run() and a[1] == a[2] == b""


def test_dropout_varies_and_both_agendas_agree(pieces):
    v, _ = pieces
    e = merge_dropout.MergeDropout(v, 0.3, 1, 0)
    for w in ("tokenization", "information", "a" * 40):
        assert e._short(list(w), 99) == e._long(list(w), 99)
    ways = {tuple(merge_dropout.MergeDropout(v, 0.3, s, 0).segment("▁tokenization")) for s in range(40)}
    assert len(ways) > 5


def test_dropout_queries(spark):
    table = docs(spark, AWKWARD)
    rows = merge_dropout.round_trip(table, rate=0.2).collect()
    assert len(rows) == len(AWKWARD) and all(r["lossless"] for r in rows)
    back = {r["doc_id"]: r["text"] for r in merge_dropout.decode(merge_dropout.encode(table)).collect()}
    assert all(back[i] == (t or "") for i, t, *_ in AWKWARD)
    assert merge_dropout.round_trip(docs(spark, [])).count() == 0


def plain_agenda(v, segments, key, rate):
    """Ids of a text's segments from the definition alone: agenda and keyed hash."""
    m64, piece_, place_, mix_ = (1 << 64) - 1, 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93

    def scrambled(x):
        x = x * mix_ & m64
        return (x ^ x >> 32) * mix_ & m64

    out = []
    for n, segment in enumerate(segments, 1):
        base = key + n * piece_ & m64
        base = scrambled(base)
        base ^= base >> 32
        symbols = [(c, i) for i, c in enumerate(segment)]
        skipped = set()
        while True:
            best = None
            for j, ((a, i), (b, _)) in enumerate(zip(symbols, symbols[1:])):
                if a + b in v.ids and (a, b, i) not in skipped and (best is None or v.rank[a + b][0] < best[0]):
                    best = v.rank[a + b][0], j
            if best is None:
                break
            j = best[1]
            (a, i), (b, _) = symbols[j : j + 2]
            if scrambled(base ^ (v.ids[a + b] * piece_ + i * place_ & m64)) >> 11 < int(rate * (1 << 53)):
                skipped.add((a, b, i))
                continue
            symbols[j : j + 2] = [(a + b, i)]
        for s, _ in symbols:
            out += [v.ids[s]] if s in v.ids else [v.bytes_[x] for x in s.encode()]
    return out


@pytest.mark.parametrize("rate", [0.1, 0.5])
def test_dropout_equals_a_plain_agenda(pieces, rate):
    v, _ = pieces
    rnd = random.Random(6)
    words = ["the", "tokenization", "information,", "naïve", "中文", "internationalization", "5731", "\n", "aaaaaaa"]
    texts = [" ".join(rnd.choice(words) for _ in range(30)) for _ in range(40)] + ["", " lead", "x  y"]
    e = merge_dropout.MergeDropout(v, rate, 3, 0)
    keys = e.keys(list(range(len(texts))), pa.array(texts))
    got = [np.frombuffer(x, "<u4").tolist() for x in e.encode(pa.array(texts), keys=keys)]
    segments = e._pieces(pa.array(texts)).to_pylist()
    assert ["".join(s).replace("▁", " ") for s in segments] == [" " + t if t else "" for t in texts]
    assert got == [plain_agenda(v, s, int(k), rate) for s, k in zip(segments, keys, strict=True)]


def test_dropout_draws_every_occurrence_anew(spark, pieces):
    v, _ = pieces
    table = docs(spark, [(i, "tokenization " * 50) for i in range(40)] + [(None, "tokenization"), (None, "tokenization tokenization")])
    ways, texts = set(), set()
    for r in merge_dropout.encode(table, rate=0.3).collect():
        texts.add(tuple(r["ids"]))
        words = "\0".join(v.raw[i].decode() for i in r["ids"]).split(" ")
        ways.update(w.strip("\0") for w in words)
    assert len(ways) > 20 and len(texts) >= 41


@pytest.mark.parametrize("rate", [0.1, 0.5, 1.0])
def test_dropout_of_many_equals_one_by_one(pieces, rate):
    v, _ = pieces
    rnd = random.Random(4)
    words = ["the", "tokenization", "a", "information,", "naïve", "中文", "x" * 60, "▁", "", "5731"] + ["".join(rnd.choice("theingtionZéabc1,") for _ in range(rnd.randint(1, 41))) for _ in range(40)]
    texts = [" ".join(rnd.choice(words) for _ in range(40)) for _ in range(200)]
    e = merge_dropout.MergeDropout(v, rate, 1, 0)
    keys = e.keys(list(range(len(texts))), pa.array(texts))
    for got, text, key in zip(e.encode(pa.array(texts), keys=keys), texts, keys.tolist(), strict=True):
        ids = []
        for place, p in enumerate(e._pieces(pa.array([text])).to_pylist()[0], 1):
            x = (key + place * merge_dropout._PIECE) * merge_dropout._MIX & merge_dropout._M64
            x = (x ^ x >> 32) * merge_dropout._MIX & merge_dropout._M64
            ids += e.segment(p, x ^ x >> 32)
        assert np.frombuffer(got, "<u4").tolist() == ids
    small = merge_dropout.MergeDropout(v, rate, 1, 0, limit=60)
    assert small.encode(pa.array(texts), at_once=20, keys=keys) == e.encode(pa.array(texts), keys=keys)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from([*" \n\t  ab'sZé1,. \x1c\x85́İ\x01\x02", "<|endoftext|>", "'s", " the", "ABC", ", ", ". "]), max_size=60).map("".join))
@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_piece_encoder_is_exact(name, text):
    e = ENCODERS.setdefault(name, PieceEncoder(tokenizer_path(name), limit=200))
    got = np.frombuffer(e.encode(pa.array([text, None]))[0], "<u4").tolist()
    assert got == e.tokenizer.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"])
def test_piece_encoder_on_blocks(name):
    rnd = random.Random(8)
    texts = [t for _, t, *_ in AWKWARD] + ["", "\na", "b\n", "x  y", None, "\n\n", ", .", "a, b. c"]
    texts += ["".join(rnd.choice([*"ab ,.\n", "the ", "A", "é"]) for _ in range(rnd.randint(0, 80))) for _ in range(400)]
    if name.endswith("json"):
        e = PieceEncoder(tokenizer_path(name), limit=60)
        own = lambda t: e.tokenizer.encode(t, add_special_tokens=False).ids
    else:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=tokenizer_path(name))
        e = merge_dropout.MergeDropout(merge_dropout.Vocabulary(tokenizer_path(name)), 0.0, 1, 0, limit=60)
        own = sp.encode
    for size in (1, 7, 1000):
        got = e.encode(pa.array(texts), at_once=size, gather=3)
        assert all(np.frombuffer(g, "<u4").tolist() == (own(t) if t else []) for g, t in zip(got, texts, strict=True) if "▁" not in (t or ""))


ENCODERS: dict = {}


def test_queries_are_registered():
    assert sorted(int(q[2:].split("_")[0]) for q in queries.QUERIES) == list(range(1, 11))
