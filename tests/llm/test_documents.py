import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from unscramble.llm import fingerprints as fp
from unscramble.llm import neardup as nd
from unscramble.llm import personal, quality
from unscramble.llm.common import may_hold


def test_fingerprints_against_plain_edits(spark, odd, none):
    rows = {r["doc_id"]: r for r in fp.edited_fingerprints(odd).collect()}
    texts = [r["text"] or "" for r in odd.orderBy("doc_id").collect()]
    for i, a in enumerate(texts):
        b = texts[(i + 1) % len(texts)]
        edited = a[: len(a) - len(a) // 4] + b[: len(a) // 4]
        r = rows[i]
        assert r["n_chars"] == len(a) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert r["fingerprint"] == fp.fingerprint(a).tobytes().hex() and r["edited_fingerprint"] == fp.fingerprint(edited).tobytes().hex()
        assert r["near_next"] == fp.likeness(fp.fingerprint(a), fp.fingerprint(b)) and 0 <= r["near_edited"] <= 1
    assert fp.edited_fingerprints(none).count() == 0


def test_fingerprints_with_ties_and_one_row(spark):
    df = spark.createDataFrame([(5, "b" * 40), (5, "a" * 40), (None, "c" * 40), (9, "d" * 40)], "doc_id long, text string")
    assert fp.edited_fingerprints(df).count() == 4
    assert fp.edited_fingerprints(df.limit(1)).count() == 1


def test_fingerprints_with_ids_that_doubles_do_not_hold(spark):
    g = random.Random(7)
    ids = [g.randrange(-(1 << 63), 1 << 63) for _ in range(300)] + [(1 << 62) + 1 + i for i in range(60)]
    texts = {i: "".join(g.choice("abcd") for _ in range(20)) for i in ids}
    got = {r["doc_id"]: r["edited_sha256"] for r in fp.edited_fingerprints(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    order = sorted(texts)
    assert got == {a: hashlib.sha256((texts[a][:15] + texts[b][:5]).encode()).hexdigest() for a, b in zip(order, order[1:] + order[:1], strict=True)}


def test_likeness_falls_with_edits_and_feels_order():
    g = random.Random(0)
    words = ["".join(g.choice("abcdefghij") for _ in range(6)) for _ in range(400)]
    base = " ".join(words)
    near, far = list(words), list(words)
    for k in g.sample(range(400), 8):
        near[k] = "zzz"
    for k in g.sample(range(400), 120):
        far[k] = "zzz"
    turned = " ".join(words[200:] + words[:200])
    like = [fp.likeness(fp.fingerprint(base), fp.fingerprint(t)) for t in (base, " ".join(near), turned, " ".join(far))]
    assert like[0] == 1 and like[1] > like[2] > like[3] and like[1] > 0.4


def test_sampling_estimates_the_similarity():
    g = np.random.default_rng(0)
    s = np.sort(g.integers(0, 1 << 63, 3000, dtype=np.uint64))
    w = g.random(3000).astype(np.float32) * 5 + 1
    v = (w * np.where(g.random(3000) < 0.3, 1.7, 1)).astype(np.float32)
    keep = g.random(3000) < 0.9
    a, b = (s, w), (s[keep], v[keep])
    true = nd.weighted_jaccard(a, b)
    assert abs((nd.samples(*a) == nd.samples(*b)).mean() - true) < 0.17 and (nd.samples(*a) == nd.samples(*a)).all()


@pytest.mark.parametrize(("n", "pairs"), [(300, 60), (2_000, 40), (20_000, 40), (100_000, 10)])
def test_sampling_of_long_texts_whose_edits_are_rare_words(n, pairs):
    g = np.random.default_rng(n)
    true, equal, band = [], [], 0
    for _ in range(pairs):
        rare = n // 53  # at weights of 2.5 and 16.5 on average the similarity is 0.8
        s = g.integers(0, 1 << 63, n + 2 * rare, dtype=np.uint64)
        w = np.where(np.arange(len(s)) < n, g.uniform(1, 4, len(s)), g.uniform(14, 19, len(s))).astype(np.float32)
        a, b = (np.r_[0:n, n + k * rare : n + (k + 1) * rare] for k in (0, 1))
        a, b = ((s[i[np.argsort(s[i])]], w[i[np.argsort(s[i])]]) for i in (a, b))
        x, y = nd.samples(*a), nd.samples(*b)
        true.append(nd.weighted_jaccard(a, b))
        equal.append(int((x == y).sum()))
        band += bool((nd.bands(x) == nd.bands(y)).any())
    error = (0.16 / nd.SAMPLES / pairs) ** 0.5
    assert 0.79 < np.mean(true) < 0.83 and abs(np.mean(equal) / nd.SAMPLES - np.mean(true)) < 4 * error
    assert min(equal) >= nd.ALIKE and band == pairs


def brute_classes(rows, weights):
    texts = {r["doc_id"]: r["text"] or "" for r in rows}
    v = {k: weights.shingles(t) for k, t in texts.items()}
    up = {k: k for k in texts}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    keys = sorted(texts)
    words = {k: nd.word_hashes(texts[k]).tolist() or texts[k] for k in keys}
    for i, a in enumerate(keys):
        for b in keys[:i]:
            if words[a] == words[b] or nd.weighted_jaccard(v[a], v[b]) >= nd.THRESHOLD:
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return {k: find(k) for k in keys}


def copies(spark, n=160, seed=2):
    """Groups of near copies with growing numbers of edits, and documents of their own."""
    g = random.Random(seed)
    word = lambda: "".join(g.choice("abcdefghijklmnop") for _ in range(g.randint(2, 8)))
    bases = [[word() for _ in range(g.randint(60, 200))] for _ in range(12)]
    rows = []
    for i in range(n):
        t = list(bases[i % 4 if g.random() < 0.6 else g.randrange(12)])
        for _ in range(g.randint(0, len(t) // 25)):
            t[g.randrange(len(t))] = word()
        rows.append((i, " ".join(t)))
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_near_duplicate_classes_against_brute_force(spark, odd):
    df = copies(spark)
    counts, n = nd.document_frequencies(df)
    want = brute_classes(df.collect(), nd.Weights(counts, n))
    got = {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(df).collect()}
    assert set(got) == set(want)
    wrong = [k for k in want if got[k] != want[k]]
    assert len(wrong) <= 2  # a pair at the threshold may share no band
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in nd.near_duplicates(odd).collect()}
    assert got[12] == (0, 0) and got[1][0] == 0 and got[5] == (4, 0) and got[6][0] == 6 and got[7][0] == 7 and got[8] == (8, 0)


def test_open_members_in_small_blocks_and_lanes(spark, monkeypatch):
    df = copies(spark)
    want = {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(df).collect()}
    assert {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(df, alike=0).collect()} == want  # every candidate pair verified
    monkeypatch.setattr(nd, "BLOCK", 3)
    monkeypatch.setattr(nd, "LANE", 7)
    assert {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(df).collect()} == want


def test_samples_that_must_be_equal_follow_the_threshold():
    assert nd.ALIKE == 36 and [nd.least_equal(t) for t in (0.5, 0.7, 0.9, 1.0)] == [15, 28, 45, 64]


def test_bit_map_loses_no_key(spark):
    rows = spark.range(3000).withColumn("h", F.xxhash64("id"))
    keys = rows.filter("id % 10 = 3").select(F.col("h").alias("k"))
    for most in (1 << 29, 1 << 15, 64):
        got = may_hold(keys, "k", rows, F.col("h"), most).collect()
        assert len(got) == 3000 and all(r["_may"] for r in got if r["id"] % 10 == 3)
        others = sum(r["_may"] for r in got if r["id"] % 10 != 3)
        assert others < (150 if most > 1 << 14 else 2701)
    assert not any(r["_may"] for r in may_hold(keys.limit(0), "k", rows, F.col("h")).collect())


def test_one_document_of_each_class_stays(spark, none):
    df = copies(spark, 60).withColumns({c: F.lit("x") for c in ("lang", "_digest", "_may", "_row", "head", "k", "first")})
    both = df.unionByName(df.filter("doc_id < 5")).unionByName(spark.createDataFrame([(None, "no id", *["x"] * 7)], df.schema))
    kept = nd.one_of_each_class(both).collect()
    classes = {r["class_id"] for r in nd.near_duplicates(df).collect()}
    assert sorted(r["doc_id"] for r in kept if r["doc_id"] is not None) == sorted(classes) and sum(r["doc_id"] is None for r in kept) == 1
    assert nd.near_duplicates(none).count() == 0 and nd.one_of_each_class(none).columns == none.columns


def test_rows_that_share_a_doc_id_with_different_texts(spark):
    g = random.Random(8)
    base = [[f"{k}w{g.randrange(10**6)}" for _ in range(150)] for k in range(5)]
    near = [b[:149] + ["other"] for b in base]
    rows = [(0, near[0]), (1, base[0]), (1, base[1]), (2, near[1]), (9, base[2]), (9, base[3]), (9, base[3]), (12, near[3]), (12, base[4])]
    df = spark.createDataFrame([(i, " ".join(t)) for i, t in rows], "doc_id long, text string")
    got = sorted((r["doc_id"], r["class_id"]) for r in nd.near_duplicates(df).collect())
    assert got == [(0, 0), (1, 0), (1, 1), (2, 1), (9, 9), (9, 9), (9, 9), (12, 9), (12, 12)]
    kept = sorted((r["doc_id"], r["text"]) for r in nd.one_of_each_class(df).collect())
    assert kept == sorted((i, " ".join(t)) for i, t in [(0, near[0]), (1, base[1]), (9, base[2]), (9, base[3]), (12, base[4])])


def test_components_both_ways(spark):
    g = random.Random(4)
    rows = [(g.randrange(300), g.randrange(300)) for _ in range(220)] + [(1000 + i, 1001 + i) for i in range(40)]
    edges = spark.createDataFrame(rows, "a long, b long").repartition(5)
    one = {r["node"]: r["label"] for r in nd.components(edges).collect()}
    two = {r["node"]: r["label"] for r in nd.components(edges, one_task=0).collect()}
    moved = {a for a, b in rows if a != b} | {b for a, b in rows if a != b}
    assert {k: v for k, v in one.items() if k in moved} == {k: v for k, v in two.items() if k in moved}


PLAIN = (
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m.split("."))),
    ("card", r"[0-9]([\x20-]?[0-9])+", lambda m: 13 <= len(re.sub(r"\D", "", m)) <= 19 and sum(sum(divmod(int(c) * (2 if i % 2 else 1), 10)) for i, c in enumerate(reversed(re.sub(r"\D", "", m)))) % 10 == 0),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(re.sub(r"\D", "", m)) <= 15),
)


def plain_spans(t):
    return [f"{k}:{m.start()}:{m.end()}" for k, p, ok in PLAIN for m in re.finditer(p, t) if ok(m[0])]


def test_base_spans_against_the_plain_rules(spark, odd):
    g = random.Random(6)
    alphabet = ["1", "2", "0", "255", ".", "-", " ", "@", "a", "b.c", "+", "+1", "(", ")", "4111 1111 1111 1111", "x@y.z", "_", "é", "🙂", "10.0.0.1", "00", "  "]
    texts = ["".join(g.choice(alphabet) for _ in range(g.randint(1, 25))) for _ in range(800)]
    texts += ["a@b.c_d@e.f", "1.2.3.4.5.6.7.8", "9" * 20_000, "1 " * 9_000, "a" * 50_000, "a@b.c@d.e", "+1+1 555 123 4567", "000255.1.1.1", "256.1.1.1"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").unionByName(odd.select((F.col("doc_id") + 10_000).alias("doc_id"), "text"))
    found = personal.find_spans(df)
    for r in found.collect():
        got = [f"{personal.KINDS[s['kind_no']]}:{s['start']}:{s['end']}" for s in r["base_spans"]]
        assert got == plain_spans(r["text"] or ""), r["text"]


def test_trees_add_spelled_out_data_and_leave_prose_alone(spark):
    rows = [(0, "contact: jan [at] example [dot] org today"), (1, "phone 415-555-0134 please"), (2, "order no 415-555-0134 shipped"), (3, "version 10.2.33 of part 12345-6789 on page 12"), (4, "look (at) this. now")]
    found = {r["doc_id"]: r["added_spans"] for r in personal.find_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [len(found[i]) for i in range(5)] == [1, 1, 0, 0, 0]
    out = {r["doc_id"]: r["text"] for r in personal.redact(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert out[0] == "contact: [EMAIL] today" and out[1] == "phone [PHONE] please" and out[4] == rows[4][1]


def test_probabilities_are_calibrated_and_overlaps_are_settled(spark):
    model = personal.fitted(spark)
    assert model.curve[0] > 0 and all(0.5 <= x <= 1 for x in model.limits.values())
    g = np.random.default_rng(0)
    score = g.normal(0, 2, 4000)
    y = (g.random(4000) < 1 / (1 + np.exp(-(0.7 * score - 0.4)))).astype(float)
    assert np.allclose(personal.calibrate(score, y), (0.7, -0.4), atol=0.12)
    rows = [(0, "phone 415-555-0134 415-555-0135, call 0044 123 456 789"), (1, "mail me at a@b.co [at] example [dot] org"), (2, "visa 4111.1111.1111.1111 4111-1111-1111-1111")]
    for r in personal.find_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        spans = sorted((s["start"], s["end"]) for s in r["added_spans"])
        assert all(a[1] <= b[0] for a, b in zip(spans, spans[1:]))
        assert not any(s["start"] < b["end"] and b["start"] < s["end"] for s in r["added_spans"] for b in r["base_spans"])


def test_clashing_names_in_redaction_and_scores(spark):
    rows = [(1, "x@y.zz", 5, "a", "b", "c", 0.5, 3)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_chars long, base_spans string, _m0 string, _pii_whole string, score double, added_spans int")
    assert personal.redact(df).collect()[0] == (1, "[EMAIL]", 7, "a", "b", "c", 0.5, 3)
    found = personal.find_spans(df)
    assert found.columns == ["doc_id", "text", "n_chars", "_m0", "_pii_whole", "score", "base_spans", "added_spans"]
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    scored = quality.with_scores(df, quality.fit(df, labels))
    assert scored.columns == [c for c in df.columns if c != "score"] + ["score"] and scored.count() == 1


def test_redaction_keeps_columns_and_updates_length(spark, odd, none):
    out = personal.redact(odd)
    assert out.columns == odd.columns and personal.redact(none).count() == 0
    r = out.filter("doc_id = 11").first()
    assert r["text"] == "[EMAIL], [CARD], [PHONE], [IP]" and r["n_chars"] == len(r["text"])
    plan = personal.find_spans(odd)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


@pytest.fixture(scope="module")
def scored(spark):
    sf = "/root/testdata/sf0.01"
    return quality.op4_quality(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").toPandas()


def test_quality_on_held_out_documents(scored):
    held = scored[scored.held_out]
    assert len(held) > 50 and (held.predicted == held.quality).mean() > 0.97 and scored.score.between(0, 1).all()


def test_quality_of_odd_documents(spark, odd, none):
    labels = spark.createDataFrame([(4, 1), (5, 1), (6, 0), (7, 0), (8, 1), (None, 1), (9, None)], "doc_id long, quality int")
    model = quality.fit(odd, labels)
    rows = {r["doc_id"]: r["score"] for r in quality.with_scores(odd, model).collect()}
    assert len(rows) == 13 and rows[0] == rows[1] == pytest.approx(model.prior) and all(0 <= s <= 1 for s in rows.values())
    empty = quality.fit(none, labels)
    assert quality.with_scores(odd, empty).count() == 13 and quality.with_scores(none, model).count() == 0


def test_votes_against_brute_force(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    model = quality.fit(docs, labels)
    got = {r["doc_id"]: r["score"] for r in quality.with_scores(docs, model).collect()}
    wanted = {r["doc_id"]: r["quality"] for r in labels.collect() if r["quality"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 5}
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    place = {}
    for i in sorted(k for k in wanted if k in texts):
        at, value = quality.terms(texts[i])
        v = (value * model.idf[at]) @ model.axes[at] if len(at) else np.zeros(model.axes.shape[1])
        place[i] = v / max(float(np.linalg.norm(v)), 1e-9)
    assert len(place) == len(model.labels)
    for i, t in list(texts.items())[::3]:
        at, value = quality.terms(t)
        if not len(at):
            assert got[i] == pytest.approx(model.prior)
            continue
        v = (value * model.idf[at]) @ model.axes[at]
        near = sorted(((float(np.dot(v, u) / np.linalg.norm(v)), k) for k, u in place.items()), key=lambda x: -x[0])[: quality.NEIGHBOURS]
        weight = sum(max(c, 0) ** 4 for c, _ in near)
        vote = sum(max(c, 0) ** 4 * wanted[k] for c, k in near)
        assert got[i] == pytest.approx((vote + quality.PRIOR_WEIGHT * model.prior) / (weight + quality.PRIOR_WEIGHT), abs=2e-3)


def test_near_duplicates_of_the_table_against_all_pairs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    counts, n = nd.document_frequencies(docs)
    want = brute_classes(docs.select("doc_id", "text").collect(), nd.Weights(counts, n))
    assert {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(docs).collect()} == want
