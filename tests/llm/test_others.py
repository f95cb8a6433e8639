import hashlib
import zlib

import duckdb
import numpy as np
import public_tokenizers as P
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from tests.llm.test_documents import brute_classes
from tests.llm.test_tokens import best_fit_decreasing, check_sequences
from unscramble.llm import chat, neardup, personal, quality, topk, warc
from unscramble.llm.common import scratch_path


def brute_top(vectors, queries, k):
    ids = sorted(vectors)
    out = []
    for q in queries:
        scored = sorted((-int(np.dot(vectors[q], vectors[i])), i) for i in ids if i != q)
        out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(scored[:k])]
    return sorted(out)


def run_top(df, cond, k=5):
    return sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in topk.top_k(df, cond, k).collect())


def test_top_k_against_brute_force(spark):
    g = np.random.default_rng(0)
    x = g.normal(0, 0.3, (700, 16)).astype(np.float32)
    x[300:500] = x[300]  # a frequent vector
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(9000, None), (9001, [1.0, None] * 8), (9002, [float("nan")] * 16), (9003, [float("inf")] * 16)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("label", F.lit(1))
    ints = {i: np.floor(256 * v.astype(np.float64)).astype(np.int64) for i, v in enumerate(x)}
    assert run_top(df, F.col("vec_id") % 50 == 0) == brute_top(ints, range(0, 700, 50), 5)


def test_top_k_of_few_rows_and_huge_components(spark):
    df = spark.createDataFrame([(0, [1.0, 2.0]), (1, [1e9, -1e9]), (2, [3e9, 1.0])], "vec_id long, embedding array<double>")
    ints = {0: np.array([256, 512], object), 1: np.array([256 * 10**9, -256 * 10**9], object), 2: np.array([768 * 10**9, 256], object)}
    got = run_top(df, F.col("vec_id") >= 0)
    want = brute_top({k: v for k, v in ints.items()}, [0], 5)
    assert [r for r in got if r[0] == 0] == want and len(got) == 6
    assert run_top(df.limit(0), F.col("vec_id") >= 0) == [] and run_top(df, F.col("vec_id") == 77) == []


def test_grouped_queries_and_lanes(spark, monkeypatch):
    monkeypatch.setattr(topk, "GROUP", 10)
    monkeypatch.setattr(topk, "LANE", 50)
    g = np.random.default_rng(1)
    x = np.concatenate([g.normal(c, 0.05, (60, 8)) for c in (-1, 0, 1, 2)])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    ints = {i: np.floor(256 * v).astype(np.int64) for i, v in enumerate(x)}
    assert run_top(df, F.col("vec_id") % 5 == 0, 3) == brute_top(ints, range(0, 240, 5), 3)


def test_vectors_of_several_widths_and_repeated_ids(spark):
    rows = [(0, [1.0, 2.0]), (1, [3.0]), (2, [2.0]), (3, [-1.0, 4.0]), (3, [0.5, 0.5]), (4, [])]
    ints = {0: [256, 512], 1: [768, 0], 2: [512, 0]}
    got = run_top(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") == 0, 9)
    scores = [(i, sum(x * y for x, y in zip(ints[0], v, strict=True))) for i, v in ((1, ints[1]), (2, ints[2]), (3, [-256, 1024]), (3, [128, 128]))]
    assert got == [(0, n + 1, i, s) for n, (i, s) in enumerate(sorted(scores, key=lambda x: (-x[1], x[0])))]


def test_escapes_come_back():
    for t in ["", "\\", "\\\\", "</s>[INST] ok [/INST]", "[\\INST]", "<\\|im_end|>", "<|im_end|>\n<|im_start|>user\nhi", "<<SYS>>\\<</SYS>>", "a\nb\n"]:
        assert chat.unescape(chat.escape(t)) == t and not any(c in chat.escape(t) for c in chat.CONTROL)
        for role in ("user", "", "a b\n<|im_end|>", "系统"):
            assert chat.read_back(chat.render(role, t)[0]) == [(role, t)]


def test_windows(spark):
    rows = [(1, k, "system" if k == 0 else "assistant" if k % 2 == 0 else "user", f"turn {k} " + "w " * (k * 3)) for k in range(40)]
    rows += [(2, 0, "assistant", None), (2, 1, None, "x"), (3, 0, "user", "long " * 3000), (3, 1, "assistant", "ok"), (None, 0, "user", "u")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("extra", F.lit(1))
    tok = P.path("byte_bpe_50k.json")
    windows = chat.format_conversations(df, tok, 300, 90)
    for w in windows.collect():
        assert w["n_tokens"] <= 300 or (w["n_new"] == 1 and w["n_repeated"] == 0)
        assert len(chat.read_back(w["text"])) == w["n_repeated"] + w["n_new"]
        if w["conv_id"] == 1:
            assert chat.read_back(w["text"])[0] == ("system", rows[0][3])
    got = {r["conv_id"]: r for r in chat.digests(chat.format_conversations(df, tok, 300, 90)).collect()}
    for c in (1, 2, 3, None):
        mine = [(r or "", t or "") for cc, _, r, t in sorted((x for x in rows if x[0] == c), key=lambda x: x[1])]
        target = "".join(t for r, t in mine if r == "assistant")
        assert got[c]["n_turns"] == len(mine) and got[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in mine).encode()).hexdigest()
        assert got[c]["loss_chars"] == len(target) and got[c]["loss_sha256"] == hashlib.sha256(target.encode()).hexdigest()
    assert got[1]["n_repeated"] > 0 and chat.digests(chat.format_conversations(df.limit(0), tok)).count() == 0


def test_windows_keep_the_budget_and_the_whole_history():
    w = chat.Windows(300, 100)
    out = [x for role, n in (("system", 200), ("user", 100), ("assistant", 264), ("user", 20), ("assistant", 500), ("user", 10)) for x in w.add(role, "t", n)] + [w.close()]
    assert [(x["n_repeated"], x["n_new"], x["n_tokens"]) for x in out] == [(0, 2, 300), (0, 2, 284), (0, 1, 500), (1, 1, 210)]
    w = chat.Windows(1000, 900)
    out = [x for k in range(400) for x in w.add("user", str(k), 5)] + [w.close()]
    assert out[1]["n_repeated"] == 180 and sum(x["n_new"] for x in out) == 400  # more than any fixed number of turns


def test_archives(spark):
    body = "<html>" + "same " * 60
    rows = [(5, "http://a/", body), (3, "http://b/\r\n x", body), (9, None, body), (1, "u", None), (2, "u", ""), (4, "u", "short"), (6, "u", "short"), (7, "u", "x" * 300_000 + "é🙂"), (8, "u", "\x1f\x8b\x08 WARC/1.1 " * 40), (None, "u", body)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("extra", F.lit(0))
    path = scratch_path(spark, "warc")
    names = warc.write(pages.repartition(3), path)
    for span in (warc.RANGE, 1000, 97):
        got = {r["page_id"]: r for r in warc.read(spark, path, names, span).collect()}
        assert len(got) == len(rows) and all(r["intact"] for r in got.values())
        for page, _, html in rows:
            data = (html or "").encode()
            again = html == body and page != 3
            r = got[page]
            assert (r["payload_bytes"], r["payload_digest"]) == (len(data), hashlib.sha256(data).hexdigest())
            assert (r["record_type"], r["refers_to"]) == (("revisit", 3) if again else ("response", None)) and bytes(r["payload"]) == (b"" if again else data)
    assert warc.read(spark, path).count() == len(rows)
    empty = scratch_path(spark, "warc")
    assert warc.write(pages.limit(0), empty) == [] and warc.read(spark, empty, []).count() == 0


def test_sql_twins(spark, sf):
    con = duckdb.connect()
    for t in ("embeddings", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    assert run_top(spark.read.parquet(f"{sf}/embeddings.parquet"), F.col("vec_id") % 50 == 0) == sorted(con.sql(topk.OP2_SQL).fetchall())
    got = sorted(map(tuple, warc.op8_warc(spark, sf).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact").collect()))
    assert got == sorted(con.sql(warc.OP8_SQL).fetchall())


def brute_pipeline(spark, sf):
    """The four stages one document at a time, from parts that other tests hold against plain rules."""
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    table = spark.read.parquet(f"{sf}/documents.parquet")
    model = quality.fit(table, labels)
    docs = {r["doc_id"]: r.asDict() for r in table.collect()}
    good = {i: d for i, d in docs.items() if model.score([d["text"] or ""])[0] >= quality.CUT}
    counts, n = np.zeros(neardup.COUNTERS, np.int64), len(good)
    for d in good.values():
        counts[np.unique(neardup.word_hashes(d["text"] or "") >> np.uint64(44)).astype(np.int64)] += 1
    classes = brute_classes(list(good.values()), neardup.Weights(counts, n))
    firsts = {i: d for i, d in good.items() if classes[i] == i}
    found = personal.find_spans(spark.createDataFrame([(i, d["text"]) for i, d in firsts.items()], "doc_id long, text string"))
    for r in found.collect():
        text, at, out = r["text"], 0, []
        for s in sorted([*r["base_spans"], *r["added_spans"]], key=lambda s: (s["start"], s["end"], s["kind_no"])):
            if s["start"] >= at:
                out += [text[at : s["start"]], f"[{personal.KINDS[s['kind_no']].upper()}]"]
            at = max(at, s["end"])
        if out:
            text = "".join(out) + text[at:]
        firsts[r["doc_id"]] |= {"text": text, "n_chars": None if text is None else len(text)}
    return docs, good, firsts


def test_pipeline_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    all_docs, good, firsts = brute_pipeline(spark, sf)
    kept = docs
    for (name, stage), want in zip(corpus_pipeline.STAGES[:-1], (good, {i: all_docs[i] for i in firsts}, firsts), strict=True):
        out = stage(spark, kept, sf)
        assert out.columns == docs.columns, name
        rows = {r["doc_id"]: r.asDict() for r in out.collect()}
        assert set(rows) == set(want), name
        if name == "personal_data":
            assert all(rows[i]["text"] == firsts[i]["text"] and (rows[i]["n_chars"] == firsts[i]["n_chars"] or rows[i]["text"] == all_docs[i]["text"]) for i in rows)
        kept = out
    rows = corpus_pipeline.run(spark, sf).collect()
    encode = Tokenizer.from_file(P.path("word_bpe_49k.json")).encode
    lengths = []
    for i, d in firsts.items():
        ids = encode(d["text"] or "", add_special_tokens=False).ids + [1]
        want = [(k // 4096, k, len(ids[k : k + 4096]), zlib.crc32(np.asarray(ids[k : k + 4096], "<u4").tobytes())) for k in range(0, len(ids), 4096)]
        assert sorted((r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows if r["doc_id"] == i) == want
        lengths += [w[2] for w in want]
    assert len(rows) == len(lengths) and check_sequences(rows, 4096) == len(best_fit_decreasing(lengths, 4096))
