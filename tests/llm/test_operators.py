"""Each operator against brute force, on edge cases and on small tables."""

import hashlib
import itertools
import re
import struct
import time
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F

from spectral_ridge.llm import bundles, byte_bpe, components, jpeg_media, line_dedup, mixing, outliers, queries, ranking, severity, sharding, trie_join

WORD = re.compile(r"[^\x20\x09-\x0D]+")
RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")


def rows(df, key="doc_id"):
    return sorted(df.collect(), key=lambda r: (r[key] is not None, r[key] or 0))


# ---------------------------------------------------------------- op1

def brute_counts(text):
    words = WORD.findall(text or "")
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    windows = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    hit = {i + k for i in range(len(words) - 7) if windows[tuple(words[i : i + 8])] > 1 for k in range(8)}
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit)


def test_outlier_counts_match_brute_force(spark, sf, odd_docs):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for table in (docs, odd_docs):
        texts = [(r.doc_id, r.text) for r in table.select("doc_id", "text").collect()]
        want = Counter((i, *brute_counts(t)) for i, t in texts)
        got = outliers.judge_documents(table)
        assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got.collect()) == want
        for r in got.collect():
            assert r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words)
            assert not (r.base_failed and r.kept)


def test_outliers_reject_far_rows_and_keep_the_cloud(spark):
    rng = np.random.default_rng(0)
    vocabulary = [f"w{k}" for k in range(500)]
    texts = [(i, " ".join(rng.choice(vocabulary, 120)), "en", "s") for i in range(300)]
    texts += [(1000 + i, " ".join(f"{w}%%%" for w in rng.choice(vocabulary, 120)), "en", "s") for i in range(40)]
    docs = spark.createDataFrame(texts, "doc_id long, text string, lang string, source string")
    kept = {r.doc_id: r.kept for r in outliers.judge_documents(docs).collect()}
    assert all(kept[i] for i in range(300)) and not any(kept[1000 + i] for i in range(40))
    salted = outliers.judge_documents(docs, outliers.OutlierRules(broadcast_groups=0))
    assert {r.doc_id: r.kept for r in salted.collect()} == kept


def test_outliers_judge_small_tables_and_rare_groups(spark):
    rng = np.random.default_rng(1)
    vocabulary = [f"w{k}" for k in range(500)]
    plain = lambda: " ".join(rng.choice(vocabulary, 120))
    junk = lambda: " ".join(f"{w}%%%" for w in rng.choice(vocabulary, 120))
    small = [(i, plain(), "en", "s") for i in range(45)] + [(1000 + i, junk(), "en", "s") for i in range(5)]
    rare = [(i, plain(), "en", "s") for i in range(200)] + [(1000 + i, junk(), "xx", "t") for i in range(60)]
    for rows in (small, rare):
        docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
        kept = {r.doc_id: r.kept for r in outliers.judge_documents(docs).collect()}
        assert len(kept) == len(rows) and all(kept[i] == (i < 1000) for i in kept)


def test_repeated_words_edges():
    ids = lambda s: np.array([ord(c) for c in s])
    assert outliers.repeated_words(ids("abcdefgh")) == 0
    assert outliers.repeated_words(ids("abcdefgh" * 2)) == 16
    assert outliers.repeated_words(ids("a" * 9)) == 9
    assert outliers.repeated_words(ids("abcdefghXYabcdefgh")) == 16


def plain_mcd(x, coverage=0.75, steps=60):
    """Concentration by exact order statistics, from the medians, in NumPy alone."""
    floors = np.array(list(outliers.FLOORS.values()))
    q = np.quantile(x, [0.25, 0.5, 0.75], axis=0)
    mean, cov = q[1], np.diag(np.maximum((q[2] - q[0]) / 1.349, floors) ** 2)
    for _ in range(steps):
        d = np.einsum("ni,ij,nj->n", x - mean, np.linalg.inv(cov), x - mean)
        inner = x[np.argsort(d, kind="stable")[: int(np.ceil(coverage * len(x)))]]
        mean, cov = outliers.scatter(len(inner), len(x), inner.sum(axis=0), inner.T @ inner)
    return np.einsum("ni,ij,nj->n", x - mean, np.linalg.inv(cov), x - mean), np.linalg.slogdet(cov)[1]


def test_robust_groups_against_plain_concentration(spark):
    rng = np.random.default_rng(8)
    table, want, logdet = [], {}, {}
    for name, n, bad in (("a", 900, 0.0), ("b", 700, 0.2), ("c", 150, 0.1)):
        root = rng.normal(size=(outliers.P, outliers.P)) * 0.3
        x = rng.normal(size=(n, outliers.P)) @ root + rng.normal(size=outliers.P)
        k = int(bad * n)
        x[:k] += 6  # a far cluster: plain mean and covariance would hide it
        d, logdet[name] = plain_mcd(x)
        want |= {(name, i): (d[i], i < k) for i in range(n)}
        table += [(name, i, *map(float, v)) for i, v in enumerate(x)]
    df = spark.createDataFrame(table, "grp string, i int, " + ", ".join(f"{v} double" for v in outliers.VECTOR))
    model = outliers.fit_groups(df)
    for r in model.collect():  # the least determinant of several starts, up to the width of a bin
        assert r.logdet <= logdet[r.grp] + 0.15
    cut = outliers.chi2_quantile(1 - 1e-7, outliers.P)
    rules = outliers.OutlierRules()
    got = outliers._with_model(df, model, rules).select("grp", "i", outliers._distance().alias("d")).collect()
    assert len(got) == len(want)
    for r in got:
        plain, planted = want[(r.grp, r.i)]
        assert abs(np.log(r.d / plain)) < 0.35
        assert (r.d > cut) == planted


# ---------------------------------------------------------------- op2

def test_ranking_held_out_accuracy(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    model = ranking.learn(docs, labels)
    scored = ranking.score_documents(docs, model).join(labels, "doc_id").collect()
    held = [r for r in scored if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in scored)
    assert sum(r.predicted == r.quality for r in held) >= 0.97 * len(held)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in scored)


def test_ranking_edge_cases(spark, odd_docs, no_docs):
    labels = spark.createDataFrame([(1, 1, 0), (6, 0, 0), (None, 1, 0), (4, None, 0)], "doc_id long, quality int, toxic int")
    model = ranking.learn(odd_docs, labels)
    assert ranking.score_documents(odd_docs, model).count() == odd_docs.count()
    empty = ranking.learn(no_docs, labels.limit(0))
    assert ranking.score_documents(no_docs, empty).count() == 0
    assert {r.predicted for r in ranking.score_documents(odd_docs, empty).collect()} == {1}
    assert ranking.keep_good(odd_docs, empty).schema == odd_docs.schema


def test_training_rows_stay_bounded_when_ids_repeat(spark, monkeypatch):
    """An id with most of the rows, and labels given twice, are one training row each."""
    table = [(i, f"plain words of text number {i} and some more") for i in range(40)] + [(1, "other")] * 500
    docs = spark.createDataFrame([(i, t + (" vile" if i % 3 == 0 else "")) for i, t in table], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2, int(i % 3 == 0)) for i in range(40)] * 3 + [(1, 0, 1)], "doc_id long, quality int, toxic int")
    held = []
    for module, name in ((ranking, "fit_ranker"), (severity, "fit_texts")):
        monkeypatch.setattr(module, name, lambda *x: held.append(x))
    ranking.learn(docs, labels)
    severity.learn(docs, labels, min_z=0.0)
    trained = [i for i in range(40) if zlib.crc32(str(i).encode()) % 5]
    assert held[0][1].tolist() == [int(i % 2 and i != 1) for i in trained]
    assert len(held[1][0]) == 40 and held[1][1].sum() == 15


def test_pairwise_fit_orders_a_planted_score():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(600, 5))
    y = (x @ [2, -1, 0, 0.5, 0] > -1).astype(int)
    model = ranking.fit_ranker(x, y)
    s = model.score(x)
    assert np.mean((s >= 0.3) == y) > 0.97 and s[y == 1].mean() > s[y == 0].mean()


# ---------------------------------------------------------------- op3

def brute_components(texts, percent=75):
    sets = {}
    for i, t in texts:
        w = WORD.findall((t or "").translate({c: c + 32 for c in range(65, 91)}))
        sets[i] = frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()
    root = {i: i for i in sets}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in sets}


def test_trie_join_edges(odd_docs, no_docs):
    got = trie_join.link_documents(odd_docs)
    assert got.count() == odd_docs.count()
    want = brute_components([(r.doc_id, r.text) for r in odd_docs.collect() if r.doc_id is not None])
    for r in got.collect():
        if r.doc_id is None:
            assert r.component_id is None and r.n_shingles > 0
        else:
            assert (r.n_shingles, r.component_id) == want[r.doc_id]
    assert trie_join.link_documents(no_docs).count() == 0


def test_trie_join_near_copies_in_chunks(spark, monkeypatch):
    """Chains of near copies, exact copies and short texts, with blocks small enough to be chunked
    and without broadcasts."""
    rng = np.random.default_rng(5)
    base = [f"t{k}" for k in range(60)]
    texts = []
    for i in range(90):
        words = list(base) if i < 60 else [f"u{i}_{k}" for k in range(40)]
        for _ in range(int(rng.integers(0, 4))):
            words[int(rng.integers(0, len(words)))] = f"x{int(rng.integers(0, 50))}"
        texts.append((i, " ".join(words)))
    texts += [(200, texts[3][1]), (201, texts[3][1].upper()), (202, "T1 t2"), (203, "t1 t2"), (204, "t1  t2 t3")]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(5)
    for bounds in ((16, 1 << 20, 0), (1024, 4000, 0)):  # by members, by bytes
        monkeypatch.setattr(trie_join.block_rows, "__defaults__", bounds)
        found = trie_join.link_documents(docs, broadcast_rows=0)
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in found.collect()}
        assert got == brute_components(texts)


def test_trie_join_one_id_with_two_texts(spark):
    a, b = (" ".join(f"{c}{k}" for k in range(30)) for c in "ab")
    docs = spark.createDataFrame([(5, a), (5, b), (6, b), (7, a), (8, b + " more"), (9, "else")], "doc_id long, text string")
    got = Counter(map(tuple, trie_join.link_documents(docs).collect()))
    assert got == Counter([(5, 26, 5), (5, 26, 5), (6, 26, 5), (7, 26, 5), (8, 27, 5), (9, 1, 9)])


def test_similar_groups_against_all_pairs():
    rng = np.random.default_rng(3)
    for trial in range(60):
        sets = []
        for _ in range(int(rng.integers(2, 30))):
            base = np.arange(40) + 40 * int(rng.integers(0, 3))
            s = np.unique(np.concatenate([base[rng.random(40) > rng.random() * 0.3], rng.integers(0, 120, 3)]))
            sets.append(s.astype(np.uint64))
        sides = rng.integers(0, 2, len(sets)) if trial % 2 else None
        pairs = [(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if (sides is None or sides[i] != sides[j]) and 100 * len(np.intersect1d(sets[i], sets[j])) >= 75 * len(np.union1d(sets[i], sets[j]))]
        u, v = (np.array([p[k] for p in pairs], dtype=int) for k in (0, 1))
        want = components.roots(len(sets), u, v)
        got = trie_join.similar_groups(sets, 75, sides)
        assert all((got[i] == got[j]) == (want[i] == want[j]) for i, j in itertools.combinations(range(len(sets)), 2))


def test_connected_components(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100 + i, 100) for i in range(1, 60)] + [(300, 301), (7, 7), (None, 3)]
    got = {r.node: r.root for r in components.connected(spark.createDataFrame(chain, "u long, v long").repartition(7)).collect()}
    assert got == {**{i: 0 for i in range(1, 41)}, **{100 + i: 100 for i in range(1, 60)}, 301: 300}
    assert components.connected(spark.createDataFrame([], "u long, v long")).count() == 0


# ---------------------------------------------------------------- op4

def test_mixing_meets_its_targets(spark, odd_docs, no_docs):
    docs = spark.createDataFrame([(i, "w " * (50 + i % 7), "en", "big" if i % 10 else f"s{i % 30}", 0) for i in range(600)], "doc_id long, text string, lang string, source string, n_chars long")
    weights = {r.source: r for r in mixing.mix_weights(mixing.token_table(docs), mixing.MixPlan(repetition_limit=3.0)).collect()}
    assert abs(sum(r.weight for r in weights.values()) - 1) < 1e-9
    assert max(r.epochs for r in weights.values()) == pytest.approx(3.0, abs=1e-6) and weights["big"].epochs == pytest.approx(1.0)
    mixed = mixing.mix_documents(docs, mixing.MixPlan(repetition_limit=3.0, block_tokens=1000)).collect()
    times = Counter(r.doc_id for r in mixed)
    assert set(times) == set(range(600)) and max(times.values()) <= 3
    for s, w in weights.items():
        emitted = sum(r.n_tokens for r in mixed if r.source == s)
        assert abs(emitted - w.epochs * w.tokens) <= 60
    entropy = mixing.mix_weights(mixing.token_table(docs), mixing.MixPlan(repetition_limit=None, entropy=0.9)).collect()
    assert -sum(r.weight * np.log(r.weight) for r in entropy) == pytest.approx(0.9 * np.log(len(entropy)), abs=1e-6)
    small = mixing.mix_documents(docs, mixing.MixPlan(budget_tokens=5000)).collect()
    assert abs(sum(r.n_tokens for r in small) - 5000) <= 60 * len(weights)
    assert {r.doc_id for r in mixing.mix_documents(odd_docs).collect()} == {r.doc_id for r in odd_docs.collect()}
    assert mixing.mix_documents(no_docs).count() == 0 and mixing.mixed_documents(no_docs).count() == 0
    assert mixing.mixed_documents(docs).columns == docs.columns


def test_mixed_documents_are_the_emitted_rows(spark):
    """Repeated ids, null ids, one id with several texts, and a source with most of the rows."""
    table = [(i, f"w{i} " * (1 + i % 40), "big") for i in range(600)] + [(5, "w5 " * 6, "big")] * 4
    table += [(900, "a b", "x"), (900, "a b", "x"), (900, "c d e", "x"), (901, None, "x"), (None, "n n n", None), (None, "n n n", None), (None, "other", "x")]
    docs = spark.createDataFrame([(*r, 7) for r in table], "doc_id long, text string, source string, epoch int")
    plan = mixing.MixPlan(repetition_limit=2.5, block_tokens=64)
    size = lambda t: len(WORD.findall(t or ""))
    emitted = Counter((r.doc_id, r.source, r.n_tokens) for r in mixing.mix_documents(docs, plan).collect())
    got = mixing.mixed_documents(docs, plan)
    assert got.columns == docs.columns
    assert Counter((r.doc_id, r.source, size(r.text)) for r in got.collect()) == emitted
    assert set(emitted) == {(i, s, size(t)) for i, t, s in table}


def test_block_order_needs_no_window_over_a_source(spark):
    sums = spark.createDataFrame([(s, e, b, (b * 7) % 50) for s in ("a", None) for e in (0, 1) for b in range(300)], "of string, epoch int, block long, block_tokens long")
    plan = mixing.MixPlan()
    wide, narrow = (sorted(map(tuple, mixing._block_places(sums, plan, bins).collect()), key=repr) for bins in (1, 64))
    assert wide == narrow and len(wide) == 1200
    assert sorted(r[3] for r in wide if r[:2] == ("a", 1)) == list(range(300))


# ---------------------------------------------------------------- op5

def test_severity_on_labels_it_never_saw(spark, odd_docs, no_docs):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    unseen = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 0
    model = severity.learn(docs, labels.where(~unseen))
    marks = labels.where(unseen).select(F.col("doc_id").alias("of"), F.col("toxic").alias("mark"))
    got = severity.grade_documents(docs, model).join(F.broadcast(marks), F.col("doc_id") == F.col("of")).join(docs.select("doc_id", "lang"), "doc_id").collect()
    hit, toxic, called = (sum(map(f, got)) for f in (lambda r: r.toxic * r.mark, lambda r: r.mark, lambda r: r.toxic))
    assert toxic > 90 and hit >= 0.9 * toxic and hit >= 0.9 * called
    for lang in ("de", "fr", "es"):
        mine = [r for r in got if r.lang == lang and r.mark]
        assert sum(r.toxic for r in mine) >= 0.8 * len(mine)
    assert all(r.p_mild >= r.p_marked >= r.p_severe and abs(r.severity - r.p_mild - r.p_marked - r.p_severe) < 1e-9 for r in got)
    assert severity.grade_documents(odd_docs, model).count() == odd_docs.count()
    none = severity.learn(no_docs, labels)
    assert {r.toxic for r in severity.grade_documents(odd_docs, none).collect()} == {0}


def test_ordinal_fit_recovers_order():
    rng = np.random.default_rng(2)
    x = rng.random((900, 6)) < 0.4
    z = x @ [3, 2, 1, 0, 0, 0] + rng.logistic(size=900) * 0.3
    y = np.digitize(z, [1.5, 3, 4.5])
    w, theta = severity.fit_ordinal(severity.Presence([np.flatnonzero(r).tolist() for r in x], 6), y, 4)
    assert w[0] > w[1] > w[2] > np.abs(w[3:]).max() and (np.diff(theta) > 0).all()


# ---------------------------------------------------------------- op6

def test_archives_round_trip(spark):
    big = "<p>" + "x" * 1200 + "</p>"
    pages = [(1, "u1", big), (2, None, big), (3, "u\r\n3", big), (4, "u4", "small"), (5, "u5", "small"), (6, "u6", None), (7, "u7", ""), (8, "u8", "é日本" * 400), (None, "u9", "nothing"), (3, "u\r\n3", big)]
    df = spark.createDataFrame([(*p, "extra", 0) for p in pages], "page_id long, url string, html string, digest string, refers_to int")
    stored = bundles.store_archives(df, "file:///tmp/checkpoints/test-archives")
    got = bundles.read_archives(stored).collect()
    assert len(got) == len(pages)
    for r in got:
        html = next(p[2] for p in pages if p[0] == r.page_id) or ""
        assert (r.payload_bytes, r.payload_digest) == (len(html.encode()), hashlib.sha1(html.encode()).hexdigest())
        assert (r.record_type, r.refers_to) == (("revisit", 3) if r.page_id in (1, 2) else ("response", None))
    place = bundles.fetch_record(stored, "page:8").collect()
    data = stored.where(F.col("bundle_id") == place[0].bundle_id).first().data
    head, payload = bundles.parse_record(bundles.BundleReader(bytes(data)).record(place[0].frame, place[0].offset, place[0].length))
    assert payload.decode() == "é日本" * 400 and head["WARC-Type"] == "response"
    assert bundles.read_archives(bundles.write_archives(df.limit(0))).count() == 0


def test_bundle_frames_are_independent():
    writer = bundles.BundleWriter()
    records = [bytes([65 + i % 26]) * (100_000 + i) for i in range(12)]
    for i, r in enumerate(records):
        writer.add(str(i), r)
    data = writer.finish()
    reader = bundles.BundleReader(data)
    assert len(reader.places) > 2
    for i in (11, 0, 7):
        at = writer.index[i]
        assert reader.record(at["frame"], at["offset"], at["length"]) == records[i]
    import zstandard

    assert zstandard.ZstdDecompressor().stream_reader(data, read_across_frames=True).read() == b"".join(records)


# ---------------------------------------------------------------- op7

def test_bpe_equals_the_library():
    coder = byte_bpe.codec(RANKS)
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=coder.ranks, special_tokens={})
    rng = np.random.default_rng(4)
    parts = ["'s", "'t", "'re", "'ve", "'ll", "'d", "'m", "'", "''s", "s", "re", " ", "  ", "\n", "\t", "a", "é", "1", "²", "!", "?", " ", "　", "😀", "日本", "\x1c", "\x85", "'S", "́", "\r\n", "﻿", "word", " 12"]
    texts = ["".join(rng.choice(parts, int(rng.integers(0, 50)))) for _ in range(1500)] + ["", " ", "a" * 3000, "é" * 500, "!?" * 700, " \n" * 300]
    ids, cuts = coder.encode(texts)
    offsets = coder.offsets(ids, cuts)
    assert coder.decode(ids, cuts, offsets) == [t.encode() for t in texts]
    for t, a, b in zip(texts, cuts, cuts[1:]):
        assert ids[a:b].tolist() == library.encode_ordinary(t)
        for k in range(a, min(b, a + 5)):
            rest = coder.decode(ids[k:b], np.array([0, b - k]), offsets[k:b] - offsets[k])
            assert rest == [t.encode()[offsets[k] :]]


def test_cache_that_starts_anew_changes_nothing(monkeypatch):
    texts = [f"word{k} {k * 7919} zq{k}x" for k in range(300)]
    coder = byte_bpe.Codec(RANKS)
    want = [x.tolist() for x in coder.encode(texts)]
    monkeypatch.setattr(byte_bpe, "CACHE_LIMIT", 5)
    small = byte_bpe.Codec(RANKS)
    small.encode(texts[:150])
    assert [x.tolist() for x in small.encode(texts)] == want


def test_bpe_on_documents(odd_docs, no_docs):
    got = byte_bpe.token_digests(odd_docs, RANKS).collect()
    want = Counter((r.doc_id, hashlib.sha256((r.text or "").encode()).hexdigest()) for r in odd_docs.collect())
    assert Counter((r.doc_id, r.decoded_sha256) for r in got) == want
    encoded = byte_bpe.encode_documents(odd_docs, RANKS)
    back = Counter((r.doc_id, r.text) for r in byte_bpe.decode_documents(encoded, RANKS).collect())
    assert back == Counter((r.doc_id, r.text or "") for r in odd_docs.collect())
    assert byte_bpe.token_digests(no_docs, RANKS).count() == 0


def test_lanes_do_not_change_boundaries():
    text = ("it's  we'll\n\n now 12 ''x " * 40)[:777]
    codes = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.int32)
    ends = np.zeros(len(codes), bool)
    ends[[100, 101, 500, -1]] = True
    want = byte_bpe.piece_starts(codes, ends, 1)
    for lanes in (2, 7, 64, 2048):
        assert (byte_bpe.piece_starts(codes, ends, lanes) == want).all()


# ---------------------------------------------------------------- op8

def test_media_round_trip(odd_docs, no_docs):
    rng = np.random.default_rng(0)
    payloads = [jpeg_media.pad(x) for x in (b"", b"a", b"\xff" * 200, bytes(rng.integers(0, 256, 70_000, dtype=np.uint8)), b"\x00" * 64, b"ab" * 300_000)]
    media = jpeg_media.encode_payloads(payloads)
    back = jpeg_media.read_thumbnails(media)
    assert [b for b, _ in back] == payloads
    assert back[0][1] == [(512, 8)] and back[-1][1][0] == (512, 65_528)
    assert all(m[:2] == b"\xff\xd8" and m[-2:] == b"\xff\xd9" for m in media)
    # the decoder of any baseline image agrees with the lockstep one
    assert jpeg_media.luminance_thumbnail(jpeg_media.Image(media[2])).tobytes() == payloads[2]
    got = jpeg_media.store_and_read(odd_docs, rounds=2).collect()
    want, features = Counter(), {}
    for d in odd_docs.collect():
        payload = jpeg_media.pad((d.text or "").encode())
        want[(d.doc_id, len((d.text or "").encode()), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))] += 1
    assert Counter((r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in got) == want
    for r in got:
        assert features.setdefault(r.payload_sha256, r.feature) == r.feature
    assert jpeg_media.store_and_read(no_docs, rounds=1).count() == 0


def hand_built_jpeg(shape, planes, width, height, interval=0, apart=False):
    """A baseline image from quantised coefficients. ``shape``: (across, down) of each component;
    ``planes``: for each one an array (rows, columns, 64) in zigzag order. All codes of a table have
    one length: 4 bits for the DC sizes, 8 for the 162 AC symbols."""
    symbols = [0x00, 0xF0, *[r << 4 | s for r in range(16) for s in range(1, 11)]]
    segment = lambda marker, body: bytes([0xFF, marker]) + (len(body) + 2).to_bytes(2, "big") + body
    frame = b"\x08" + height.to_bytes(2, "big") + width.to_bytes(2, "big") + bytes([len(shape)])
    frame += b"".join(bytes([k + 1, h << 4 | v, k > 0]) for k, (h, v) in enumerate(shape))
    out = b"\xff\xd8" + segment(0xE0, b"JFIF\0 any") + segment(0xDB, bytes([0, 16] + [7] * 63) + bytes([0x11, 0, 9] + [0, 5] * 63)) + segment(0xC0, frame)
    out += segment(0xC4, bytes([0x00, 0, 0, 0, 12, *[0] * 12, *range(12)]) + bytes([0x10, *[0] * 7, 162, *[0] * 8, *symbols]))
    out += segment(0xDD, interval.to_bytes(2, "big"))
    most = max(h for h, _ in shape), max(v for _, v in shape)

    def number(x):
        n = abs(x).bit_length()
        return n, format(x if x > 0 else x + (1 << n) - 1, f"0{n}b") if n else ""

    def coded(blocks):
        bits, before = "", {}
        for k, block in blocks:
            n, extra = number(int(block[0]) - before.get(k, 0))
            before[k] = int(block[0])
            bits += format(n, "04b") + extra
            run = 0
            last = max([i for i in range(1, 64) if block[i]], default=0)
            for x in block[1 : last + 1]:
                if not x:
                    run += 1
                    continue
                bits += format(symbols.index(0xF0), "08b") * (run // 16)
                n, extra = number(int(x))
                bits += format(symbols.index((run % 16) << 4 | n), "08b") + extra
                run = 0
            bits += format(0, "08b") if last < 63 else ""
        bits += "1" * (-len(bits) % 8)
        return bytes(int(bits[i : i + 8], 2) for i in range(0, len(bits), 8)).replace(b"\xff", b"\xff\0")

    groups = [[k] for k in range(len(shape))] if apart else [list(range(len(shape)))]
    for ks in groups:
        out += segment(0xDA, bytes([len(ks), *[x for k in ks for x in (k + 1, 0)], 0, 63, 0]))
        if len(ks) == 1:
            h, v = shape[ks[0]]
            cols, rows_ = (-(-(-(-n * a // m)) // 8) for n, a, m in ((width, h, most[0]), (height, v, most[1])))
            units = [[(ks[0], planes[ks[0]][r, c])] for r in range(rows_) for c in range(cols)]
        else:
            across, down = -(-width // (8 * most[0])), -(-height // (8 * most[1]))
            units = [[(k, planes[k][r * shape[k][1] + y, c * shape[k][0] + x]) for k in ks for y in range(shape[k][1]) for x in range(shape[k][0])] for r in range(down) for c in range(across)]
        step = interval or len(units)
        runs = [coded([b for u in units[i : i + step] for b in u]) for i in range(0, len(units), step)]
        out += b"".join(run + (bytes([0xFF, 0xD0 + i % 8]) if i + 1 < len(runs) else b"") for i, run in enumerate(runs))
    return out + b"\xff\xd9"


@pytest.mark.parametrize("shape, apart", [([(1, 1)], False), ([(1, 1)] * 3, False), ([(2, 2), (1, 1), (1, 1)], False), ([(2, 1), (1, 1), (1, 1)], True)])
def test_thumbnails_of_any_baseline_image(shape, apart):
    rng = np.random.default_rng(len(shape))
    width, height = 83, 45
    for interval in (0, 1, 3):
        most = max(h for h, _ in shape), max(v for _, v in shape)
        across, down = -(-width // (8 * most[0])), -(-height // (8 * most[1]))
        planes = []
        for h, v in shape:
            x = np.where(rng.random((down * v, across * h, 64)) < 0.2, rng.integers(-500, 500, (down * v, across * h, 64)), 0)
            x[..., 0] = rng.integers(-60, 60, x.shape[:2])
            planes.append(x)
        data = hand_built_jpeg(shape, planes, width, height, interval, apart)
        ((thumbnail, dims),) = jpeg_media.read_thumbnails([data])
        want = np.clip(planes[0][:6, :11, 0] * 2 + 128, 0, 255).astype(np.uint8)  # quantiser 16
        assert dims == [(width, height)] and thumbnail == want.tobytes()


def test_damaged_images_are_refused():
    (media,) = jpeg_media.encode_payloads([bytes(range(64)) * 2])
    progressive = media.replace(b"\xff\xc0", b"\xff\xc2", 1)
    for bad in (b"", media[:-1], media[2:], progressive, media.replace(b"\xff\xd0", b"", 1)):
        if bad:
            with pytest.raises((ValueError, IndexError, struct.error)):
                jpeg_media.read_thumbnails([bad])


# ---------------------------------------------------------------- op9

def test_line_dedup_keeps_one_line_of_each_component(spark, odd_docs, no_docs):
    line = "This is a rather long line of ordinary text that is going to be repeated with small edits here and there"
    other = "Nothing in this line has anything to do with the others, it is alone in the whole of the collection"
    docs = [(5, f"{line}\nshort\n{other}"), (2, f"intro line only in two, kept since nothing else is like it at all\n{line}."), (9, f"short\n{line.replace('rather', 'rathar')}\n\n{line}"), (None, line), (3, None), (4, "")]
    df = spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, n_lines int")
    got = {r.doc_id: r for r in line_dedup.dedup_documents(df).collect()}
    assert got[2].text == docs[1][1] and got[2].n_removed == 0
    assert got[5].text == f"short\n{other}" and got[5].n_removed == 1
    assert got[9].text == "short\n" and (got[9].n_lines, got[9].n_removed) == (4, 2)
    assert got[None].text == line and got[3].text is None and got[4].text == ""
    small = {r.doc_id: r.text for r in line_dedup.remove_lines(df, line_dedup.duplicate_lines(df, broadcast_rows=0)).collect()}
    assert small == {i: r.text for i, r in got.items()}
    assert line_dedup.dedup_documents(odd_docs).count() == odd_docs.count()
    assert line_dedup.dedup_documents(no_docs).count() == 0


def test_line_dedup_recall_against_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    lines = {x for r in docs.collect() for x in r.text.encode().split(b"\n") if line_dedup.eligible(x)}
    sets = {x: line_dedup.char_shingles(x) for x in lines}
    ordered = sorted(lines, key=lambda x: len(sets[x]))
    want = set()
    for i, a in enumerate(ordered):
        for b in ordered[i + 1 :]:
            if len(sets[a]) * 100 < 80 * len(sets[b]):
                break
            both = len(np.intersect1d(sets[a], sets[b], assume_unique=True))
            if 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                want.add((a, b))
    removed = line_dedup.duplicate_lines(docs).collect()
    text = {r.doc_id: r.text.encode().split(b"\n") for r in docs.collect()}
    kept_for = {text[r.doc_id][r.pos]: text[r.keep_doc_id][r.keep_pos] for r in removed}
    same = lambda a, b: kept_for.get(a, a) == kept_for.get(b, b)
    assert sum(same(a, b) for a, b in want) >= 0.98 * len(want)


def plain_alike(a, b, chars=8, percent=80):
    """Jaccard similarity of character shingle sets, by Python sets."""
    x, y = ({t[i : i + chars] for i in range(max(1, len(t) - chars + 1))} for t in (a, b))
    return 100 * len(x & y) >= percent * len(x | y)


def test_groups_of_a_block_against_all_pairs():
    rng = np.random.default_rng(6)
    blocks = []
    for size in [2] * 20 + [3, 5, 9, 30, 52, 53, 90]:
        base, lines = "".join(rng.choice(list("abcdef ghij"), 260)), []
        for _ in range(size):
            x = list(base[: int(rng.integers(60, 260))])
            for _ in range(int(rng.integers(0, 5))):
                x[int(rng.integers(0, len(x)))] = "z"
            lines.append("".join(x).encode())
        blocks.append((None, lines))
    blocks.append((None, [b"abc", b"abc ", b"abc"]))
    for (_, lines), got in zip(blocks, line_dedup.alike_groups(blocks), strict=True):
        t = [x.decode() for x in lines]
        alike = lambda a, b: plain_alike(a, b) or (max(len(a), len(b)) < 200 and plain_alike(a, b, 3, 70))
        pairs = [(i, j) for i, j in itertools.combinations(range(len(t)), 2) if alike(t[i], t[j])]
        want = components.roots(len(t), *(np.array([p[k] for p in pairs], dtype=int) for k in (0, 1)))
        assert (got == want).all()


def test_removed_lines_are_alike_to_a_kept_or_removed_one(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    text = {r.doc_id: r.text.split("\n") for r in docs.collect()}
    groups = {}
    for r in line_dedup.duplicate_lines(docs, exact_short=True).collect():
        group = groups.setdefault((r.keep_doc_id, r.keep_pos), {text[r.keep_doc_id][r.keep_pos]})
        group.add(text[r.doc_id][r.pos])
    assert len(groups) > 20
    for lines in groups.values():
        alike = lambda a, b: plain_alike(a, b) or (max(len(a), len(b)) < 200 and plain_alike(a, b, 3, 70))
        left, reached = set(lines), [lines.pop()]
        left.discard(reached[0])
        for a in reached:
            near = {b for b in left if alike(a, b)}
            left -= near
            reached += near
        assert not left


def _family(size, seed=8):
    """Near and not so near copies of one line, as a component of many lines has them."""
    rng, out = np.random.default_rng(seed), []
    words = ["".join(rng.choice(list("abcdefghijkl"), int(rng.integers(2, 8)))) for _ in range(60)]
    for _ in range(size):
        x = [w if rng.random() > rng.choice([0.02, 0.2]) else str(rng.integers(1 << 30)) for w in words[: int(rng.integers(25, 60))]]
        out.append(" ".join(x).encode())
    return out


@pytest.mark.parametrize("chars,percent", [(8, 80), (3, 70)])
def test_a_large_component_is_joined_by_products_in_less_time(chars, percent):
    lines = _family(700)
    sides = np.random.default_rng(3).integers(0, 2, len(lines))
    spent = {}
    for parted in (None, sides):
        began = time.process_time()
        got = line_dedup.alike_groups([(parted, lines)], percent)[0] if chars == 8 else line_dedup.tile_groups(lines, percent, chars, parted)
        spent["products"] = spent.get("products", 0) + time.process_time() - began
        began = time.process_time()
        want = trie_join.similar_groups([line_dedup.char_shingles(x, chars) for x in lines], percent, parted)
        spent["trie"] = spent.get("trie", 0) + time.process_time() - began
        if chars == 8:  # the short lines' links come on top
            short = np.flatnonzero([line_dedup.is_short(x) for x in lines])
            more = trie_join.similar_groups([line_dedup.char_shingles(lines[i], 3) for i in short], 70, None if parted is None else parted[short])
            want = components.roots(len(lines), np.concatenate([np.arange(len(lines)), short]), np.concatenate([want, short[more]]))
        assert (got == want).all() and 1 < len(set(got.tolist())) < len(lines)
    assert spent["products"] < spent["trie"] / 2


def test_lines_of_a_large_component_are_sent_once(spark, monkeypatch):
    """3000 lines in one candidate component are one block, and its rows no copies of them."""
    bounds, kept = [], line_dedup.joined_blocks
    monkeypatch.setattr(line_dedup, "joined_blocks", lambda *a: (bounds.extend(a[4:]), kept(*a))[1])
    line_dedup.duplicate_lines(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    members = spark.createDataFrame([(k, x) for k, x in enumerate(_family(3000))], "sid long, line binary")
    candidate = spark.range(1, 3000).select(F.col("id").alias("node"), F.lit(0).cast("long").alias("root"))
    assert trie_join.block_rows(members, candidate, "line", *bounds)[0].count() == 3000


def test_band_values_are_not_written(spark, monkeypatch):
    """Of a scan only links and places reach the shared folder."""
    kinds, kept = set(), line_dedup.materialise

    def watch(df, label, **options):
        out = kept(df, label, **options)
        if "kind" in out.columns:
            kinds.update(r.kind for r in out.select("kind").distinct().collect())
        return out

    monkeypatch.setattr(line_dedup, "materialise", watch)
    line_dedup.duplicate_lines(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    assert kinds == {1, 2}


def test_line_dedup_finds_small_edits_of_short_lines(spark):
    """Planted edits: one character at every length, one word from 50 characters on; unlike lines stay."""
    rng = np.random.default_rng(11)
    words = ["".join(rng.choice(list("abcdefghijklmnoprstuvw"), int(rng.integers(4, 9)))) for _ in range(3000)]
    docs, pairs, wanted = [], {"char": [], "word": []}, 240
    for k in range(wanted):
        size, line = 20 + k * 131 // wanted, []
        while len(" ".join(line)) < size:
            line.append(str(rng.choice(words)))
        at, kind = int(rng.integers(1, len(line) - 1)), "char" if k % 2 or size < 50 else "word"
        other = [*line[:at], line[at][:1] + "z" + line[at][2:] if kind == "char" else str(rng.choice(words)), *line[at + 1 :]]
        docs += [(2 * k, " ".join(line)), (2 * k + 1, " ".join(other))]
        pairs[kind].append(k)
    table = spark.createDataFrame(docs, "doc_id long, text string")
    found = {r.doc_id: r.keep_doc_id for r in line_dedup.duplicate_lines(table).collect()}
    assert all(a == b + 1 and b % 2 == 0 for a, b in found.items())
    for kind, least in (("char", 1.0), ("word", 0.9)):
        assert sum(2 * k + 1 in found for k in pairs[kind]) >= least * len(pairs[kind])


def test_gap_values_meet_by_one_word():
    lines = [b"one two three four five six", b"one two THREE four five six", b"one two four five six", b"one two three four five six seven", b"two one three four five six", b"alone here"]
    number, value = line_dedup.gap_values(lines, trie_join.WordHashes())
    of = [set(value[number == k].tolist()) for k in range(len(lines))]
    assert all(of[0] & of[k] for k in (1, 2, 3)) and not of[2] & of[4] and not of[5] and len(of[0]) == 7


# ---------------------------------------------------------------- op10

def test_shards_are_even_and_gapless(spark, odd_docs, no_docs):
    docs = spark.createDataFrame([(i, "same text" if i % 3 == 0 else "x" * (i % 50)) for i in range(3000)] + [(9000, "y" * 4000)], "doc_id long, text string")
    for table, kwargs in ((docs, {}), (docs, {"rows_per_range": 10, "min_ranges": 40}), (odd_docs, {})):
        got = sharding.shard_documents(table, **kwargs).collect()
        source = Counter((r.doc_id, len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode())) for r in table.collect())
        assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == source
        total, largest = sum(r.size for r in got), max(r.size for r in got)
        for s in range(16):
            slots = sorted(r.slot for r in got if r.shard == s)
            assert slots == list(range(len(slots)))
            assert abs(sum(r.size for r in got if r.shard == s) - total / 16) < 2 * largest
        codes = {zlib.crc32((d.text or "").encode()): hashlib.md5((d.text or "").encode()).hexdigest() for d in table.collect()}
        order = [codes[r.text_crc32] for r in sorted(got, key=lambda r: (r.shard, r.slot))]
        assert order == sorted(order)
    assert sharding.shard_documents(no_docs).count() == 0


def test_splitters_resolve_ties(spark):
    s = sharding.Splitters(np.array([5, 5, 7]), np.array([1, 9, 0]))
    hashes, ids, want = [4, 5, 5, 5, 6, 7, 8], [0, 0, 1, 10, 0, -1, 0], [0, 0, 1, 2, 2, 2, 3]
    assert s.locate(np.array(hashes), np.array(ids)).tolist() == want
    rows = spark.createDataFrame(list(zip(hashes, ids)), "order_hash long, order_id long")
    got = {(r.order_hash, r.order_id): r.range for r in sharding.with_range(rows, s).collect()}
    assert [got[k] for k in zip(hashes, ids)] == want
    none = sharding.Splitters(np.zeros(0), np.zeros(0))
    assert {r.range for r in sharding.with_range(rows, none).collect()} == {0}


# ---------------------------------------------------------------- registration

def test_every_operator_is_registered():
    names = queries.queries()
    assert sorted(int(n[2:].split("_")[0]) for n in names) == list(range(1, 11))
    assert set(queries.oracle_sql()) <= set(names)
