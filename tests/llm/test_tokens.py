import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import sentencepiece
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from unscramble.llm import chunks, packing, pieces, token_counts
from unscramble.llm.common import scratch_path

ODD = ["", " ", "  a", "a  b\n\n c ", "it's <|endoftext|> !'s _x_ don't", "x\x1cy \x85z", "ÀÉ Straße. İ Σίσυφος", "é tést", "1234 56,7%", "日本語 テキスト🙂", "a" * 500, "<|startoftext|>hi<|endoftext|>", "\t\ttabs nbsp　wide", "word,word;word!! *** |"]


def random_texts(n=300):
    g = random.Random(3)
    alphabet = "abc ABC  \n\t.,!?'’-_%&0123éÉß́日🙂 "
    return ["".join(g.choice(alphabet) for _ in range(g.randint(0, 60))) for _ in range(n)]


def test_counts_and_ids_are_the_libraries_own():
    texts = ODD + random_texts()
    byte, word = P.path("byte_bpe_50k.json"), P.path("word_bpe_49k.json")
    t = Tokenizer.from_file(byte)
    assert chunks.count_ids(texts, byte) == [len(t.encode(x, add_special_tokens=False).ids) for x in texts]
    t = Tokenizer.from_file(word)
    assert [np.frombuffer(b, "<u4").tolist() for b in chunks.id_bytes(texts, word)] == [t.encode(x, add_special_tokens=False).ids for x in texts]


def test_memo_is_bounded_and_stays_right():
    m = chunks.Memo(str.upper, limit=3)
    narrow = chunks.Memo(str.upper, room=8 * chunks.ENTRY)
    for k in range(20):
        for w in (f"w{k}", "w0", "x" * 100):
            assert m[w] == narrow[w] == w.upper()
        assert len(m) <= 5 and "x" * 100 not in m and len(narrow) + len(narrow.old) <= 10


def test_pieces_are_the_librarys_and_come_back():
    path = P.path("piece_bpe_32k.model")
    lib = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = ODD + random_texts() + ["▁", "a▁b ▁c▁ d", " ▁ ", "▁▁x", "\x00a\x00", "🙂🙂 日本\n\n 語"]
    got = [np.frombuffer(b, "<u4").tolist() for b in pieces.encode(texts, path)]
    assert got == [lib.encode(x) for x in texts]
    model = pieces.compiled(path)[0]
    assert [model.decode(ids) for ids in got] == [x.replace("▁", " ") for x in texts]
    for ids, ends, block in pieces.encode_blocks(texts, path):
        assert [b.decode() for b in pieces.decode_blocks(model, ids, ends)] == [x.replace("▁", " ") for x in block.to_pylist()]


@pytest.mark.parametrize("rule", ["nmt_nfkc", "nfkc", "nmt_nfkc_cf", "nfkc_cf"])
def test_character_maps_give_the_librarys_normal_text(rule):
    lib = sentencepiece.SentencePieceNormalizer(rule_name=rule)
    spec = dict(pieces._fields(next(v for f, v in pieces._fields(lib.serialized_model_proto()) if f == 3)))
    normal = pieces.Normaliser(spec[2], bool(spec.get(4, 1)))
    g = random.Random(5)
    alphabet = "ab AB  ﬁ①ｆ　éé가각ÅΩ²½…'“\t\n\u200b\ufeff🙂ㅏ㎏Ⅷ"
    texts = ODD + random_texts(100) + ["".join(g.choice(alphabet) for _ in range(g.randint(0, 40))) for _ in range(400)]
    for t in texts:
        want = lib.normalize(t).replace("▁", " ")
        assert normal(t).replace("▁", " ") == want.removeprefix(" " if spec.get(3, 1) else ""), t
    assert pieces.Normaliser(b"", True)("  a   b ") == "a b" and pieces.Normaliser(b"", False)("  a ") == "  a "


def test_shortest_path_of_a_unigram_model():
    t = pieces.Transducer.__new__(pieces.Transducer)
    t.kind, t.bytes, t.unknown, t.prefix = 1, {}, 0, False
    t.ids, t.scores = {"a": 1, "b": 2, "ab": 3, "aba": 4}, [0.0, -1.0, -1.0, -1.5, -1.9]
    t.longest, t.heads = 3, pieces._states(t.ids)
    assert t.shortest_path("abab") == ["aba", "b"]


def test_encode_and_decode_tables(spark, odd, none):
    path = P.path("piece_bpe_32k.model")
    back = {r["doc_id"]: r["text"] for r in pieces.decode_documents(pieces.encode_documents(odd, path), path).collect()}
    assert back == {r["doc_id"]: r["text"] or "" for r in odd.collect()}
    assert pieces.encode_documents(none, path).count() == 0


def test_packing_is_tight_and_whole(spark, odd):
    tok = P.path("word_bpe_49k.json")
    t = Tokenizer.from_file(tok)
    rows = packing.pack_documents(odd, tok, limit=64).collect()
    texts = {r["doc_id"]: r["text"] or "" for r in odd.collect()}
    for doc in texts:
        ids = t.encode(texts[doc], add_special_tokens=False).ids + [1]
        mine = sorted((r for r in rows if r["doc_id"] == doc), key=lambda r: r["piece"])
        assert [r["start"] for r in mine] == list(range(0, len(ids), 64)) and sum(r["length"] for r in mine) == len(ids)
        for r in mine:
            assert zlib.crc32(np.asarray(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes()) == r["ids_crc32"]
    check_sequences(rows, 64)


def check_sequences(rows, limit):
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= limit
    return len(by)


def best_fit_decreasing(lengths, limit):
    gaps = []
    for n in sorted(lengths, reverse=True):
        fit = [g for g in gaps if g >= n]
        if fit:
            gaps.remove(min(fit))
            gaps.append(min(fit) - n)
        else:
            gaps.append(limit - n)
    return sorted(gaps)


def test_supersteps_are_sequential_best_fit(spark, none):
    g = random.Random(1)
    for trial in range(30):
        limit = g.choice([10, 37, 100])
        lengths = [g.randint(1, limit) if g.random() < 0.7 else g.choice([1, 3, limit // 2, limit]) for _ in range(g.randint(0, 200))]
        counts = {n: lengths.count(n) for n in set(lengths)}
        fill = {}
        for size, _, ranks, first, fit, base in packing.place_classes(counts, limit):
            for k in range(ranks):
                s = first + k // fit
                assert fill.get(s, 0) == base + (k % fit) * size
                fill[s] = fill.get(s, 0) + size
        assert sorted(limit - x for x in fill.values()) == best_fit_decreasing(lengths, limit), trial
    rows = spark.createDataFrame([(i % 50, i, g.randint(1, 40), 0) for i in range(500)], "doc_id long, piece int, length long, start long")
    got = packing.pack(rows, 40).collect()
    assert len(got) == 500 and check_sequences(got, 40) == len(best_fit_decreasing([r["length"] for r in rows.collect()], 40))
    clash = rows.selectExpr("*", "'a' AS lane", "2 AS rank", "3 AS offset", "4 AS n", "5 AS row", "6 AS first_rank").unionByName(rows.limit(1).selectExpr("*", "'a' AS lane", "2 AS rank", "3 AS offset", "4 AS n", "5 AS row", "6 AS first_rank"))
    odd = packing.pack(clash, 40)  # names that pack has too, and a row that occurs twice
    assert odd.columns == [c for c in clash.columns if c != "offset"] + ["sequence_id", "offset"]
    odd = odd.collect()
    assert len(odd) == 501 and all((r["lane"], r["rank"], r["n"], r["row"], r["first_rank"]) == ("a", 2, 4, 5, 6) for r in odd) and check_sequences(odd, 40)
    assert packing.pack_documents(none, P.path("word_bpe_49k.json")).count() == 0


def test_cache_is_used_and_grows(spark, odd, none):
    tok, path = P.path("byte_bpe_50k.json"), scratch_path(spark, "cache")
    t = Tokenizer.from_file(tok)
    got = {r["doc_id"]: (r["n_bytes"], r["n_tokens"]) for r in token_counts.count_tokens(odd, tok, path).collect()}
    want = {r["doc_id"]: (len((r["text"] or "").encode()), len(t.encode(r["text"] or "", add_special_tokens=False).ids)) for r in odd.collect()}
    assert got == want
    stored = spark.read.parquet(path)
    assert stored.count() == odd.select(F.coalesce("text", F.lit(""))).distinct().count()
    token_counts.count_tokens(odd, tok, path).collect()
    assert spark.read.parquet(path).count() == stored.count()  # nothing was encoded twice
    before = stored.count()
    more = odd.unionByName(spark.createDataFrame([(90, "one more text", "en", "s", 13), (91, "one", "en", "s", 3)], odd.schema))
    got = {r["doc_id"]: r["n_tokens"] for r in token_counts.count_tokens(more, tok, path).collect()}
    assert spark.read.parquet(path).count() == before + 1 and len(got) == 15  # 14 hits, one miss
    assert got[90] == len(t.encode("one more text", add_special_tokens=False).ids) and got[91] == got[3]
    assert token_counts.count_tokens(none, tok, path).count() == 0


@pytest.mark.parametrize("text", ["abab", "a b", "x"])
def test_chunks_join_to_the_text(text):
    for cut in (chunks.before_spaces, chunks.before_spaces_and_stops, pieces.compiled(P.path("piece_bpe_32k.model"))[0].cut):
        assert "".join(x for block, _, _ in chunks.parts_of([text, "", text], cut) for x in block.to_pylist()) == text * 2
