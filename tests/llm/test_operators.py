"""Operators against brute force, libraries and round trips, on small and awkward tables."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from sheetgraph.llm import bpe_count, langid, lattice, licenses, mpeg, order_minhash, perplexity, pfair, rendezvous, sstable
from sheetgraph.llm._shared import Scratch

PIECES, WORDS = public_tokenizers.path("piece_bpe_32k.model"), public_tokenizers.path("word_bpe_49k.json")
LONG = "lorem ipsum dolor " * 4000
TEXTS = [None, "", " ", "a", "Grüße, Welt!\n\nzwei  drei ", "x" * 700, LONG, "中文 😀 #1", "same text here", "same text here", "tab\tand\x0bnewline\r\n"]


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls in every column, repeated rows and identifiers, and columns named like results."""
    rows = [(i, t, "en" if i % 2 else None, None if i % 3 else "s", 7) for i, t in enumerate(TEXTS)] + [(None, "no id", None, None, None), (9, "same text here", None, "s", 7)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, shard int")


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false")


def test_rendezvous(docs, empty):
    rows = rendezvous.assign(docs, [1.0, 2.0, 1.0]).collect()
    assert len(rows) == docs.count()
    for shard in range(3):
        assert sorted(r.slot for r in rows if r.shard == shard) == list(range(sum(r.shard == shard for r in rows)))
    for r in rows:
        assert r.grown_shard in (r.shard, 3) and r.law == "key"
    by_id = {r.doc_id: r for r in rows}
    assert by_id[0].size == 8 and by_id[0].text_crc32 == 0
    assert by_id[4].text_crc32 == zlib.crc32(TEXTS[4].encode()) and by_id[4].size == len(TEXTS[4].encode()) + 8
    assert rendezvous.assign(empty, [1.0]).count() == 0


def test_rendezvous_weights(spark):
    rows = rendezvous.assign(spark.range(20_000).select(F.col("id").alias("doc_id"), F.lit("").alias("text")), [1.0, 3.0]).groupBy("shard").count().collect()
    assert abs({r.shard: r["count"] for r in rows}[1] - 15_000) < 400


def test_sorted_string_tables(spark, docs, empty):
    manifest = sstable.write_shards(docs, WORDS, Scratch(spark, "t"), shard_bytes=20_000)
    got = sstable.read_shards(manifest).collect()
    assert len(got) == docs.count()
    from tokenizers import Tokenizer

    tok, start = Tokenizer.from_file(WORDS), 0
    want = sorted(((r.doc_id, tok.encode(r.text or "", add_special_tokens=False).ids + [1]) for r in docs.collect()), key=lambda x: (x[0] is not None, x[0] or 0, np.array(x[1], "<u2").tobytes()))
    for r, (i, ids) in zip(sorted(got, key=lambda r: r.start), want):
        assert (r.doc_id, r.start, r.n_tokens) == (i, start, len(ids))
        assert r.ids_crc32 == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    files = manifest.collect()
    assert [list(x) for x in sstable.look_up(files, 4)] == [want[[w[0] for w in want].index(4)][1]]
    assert len(sstable.look_up(files, 9)) == 2 and sstable.look_up(files, 10_000) == []
    assert sstable.read_shards(sstable.write_shards(empty, WORDS, Scratch(spark, "t"))).count() == 0


def test_words_alone_and_together_encode_the_same():
    random.seed(3)
    for alphabet in ("abcdeéèñ's't're,.!!#019 ABÉ\n<|", "aßΣ 's\n\t\x0b\x85\xa0 thein<|endoftext|>01#😀中文́\x00ÀÖ×ÿ"):
        texts = ["".join(random.choice(alphabet) for _ in range(random.randint(0, 50))) for _ in range(500)]
        assert sstable.encode_texts(WORDS, texts) == sstable.encode_texts(WORDS, texts, False)


def test_damaged_block_is_noticed(tmp_path):
    import io

    out = io.BytesIO()
    table = sstable.Writer(out, 2, block_bytes=64)
    for k in range(40):
        table.add(sstable.record_key(k * 3, 0), bytes([k, 0]))
    size = table.close()
    body = bytearray(out.getvalue())
    assert len(body) == size and len(sstable.Reader(io.BytesIO(bytes(body)), size).get(39)) == 1
    body[12] ^= 1
    with pytest.raises(ValueError):
        list(sstable.Reader(io.BytesIO(bytes(body)), size).scan())


def test_token_counts(docs, empty):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    for r in bpe_count.count_tokens(docs, PIECES).join(docs.select("doc_id", "text").distinct(), "doc_id").collect():
        assert r.n_tokens == len(sp.encode(r.text or "")) and r.over_limit == (r.n_tokens > 4096)
    random.seed(1)
    table = bpe_count.PieceTable(PIECES)
    for _ in range(400):
        t = "".join(random.choice("aabbcdeéñß \n\tthein▁<s>01#=😀中") for _ in range(random.randint(0, 60)))
        units = [u if u[:1] == "▁" else "▁" + u for u in bpe_count.units(t)]
        assert bpe_count.merged_counts(table, units).sum() == len(sp.encode(t))
    assert bpe_count.count_tokens(empty, PIECES).count() == 0


def test_language_id(spark, sf, docs, empty):
    given = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.fit(given, PIECES, ~langid.held_out())
    got = langid.predict(given, model).where(langid.held_out())
    assert got.where("lang = lang_pred").count() >= 0.95 * got.count()
    out = {r.doc_id: r for r in langid.predict(docs, model).collect()}
    assert out[0].lang_pred == out[1].lang_pred == "und" and 0 <= out[4].score <= 1 and out[8].lang_pred == out[9].lang_pred
    assert langid.predict(empty, model).count() == 0
    assert {r.lang_pred for r in langid.predict(docs, langid.fit(empty, PIECES, F.lit(True))).collect()} == {"und"}


def test_forward_sums_all_segmentations():
    pieces = langid.pieces_of(PIECES)
    rng = np.random.default_rng(1)
    table = rng.random((pieces.size + 2, 2)) / pieces.size
    table[pieces.size], table[pieces.size + 1] = 0, langid.UNKNOWN
    number = {n: i for i, n in enumerate(pieces.names)}

    def brute(word):
        if not word:
            return np.ones(2)
        total = np.zeros(2)
        for k in range(1, len(word) + 1):
            piece = number.get(word[:k], pieces.size + 1 if k == 1 else None)
            if piece is not None:
                total = total + table[piece] * brute(word[k:])
        return total

    for word in ("▁the", "▁straße", "▁中a", "▁internation"):
        assert np.allclose(langid.log_likelihoods(pieces, table, [word])[0], np.log(brute(word)))


def test_lattice(spark, docs, empty):
    pieces = lattice.Pieces(PIECES)
    out = lattice.encode(docs, PIECES, Scratch(spark, "t"))
    for r in out.collect():
        spelled = "▁" + r.text.replace(" ", "▁") if r.text else ""
        assert list(r.ids) == pieces.best(spelled)
        assert lattice.decode_ids(pieces, np.array(r.ids, np.int64)) == (r.text or "")
    assert {r.decoded for r in lattice.decode(out, PIECES).where("doc_id = 4").collect()} == {TEXTS[4]}
    assert lattice.encode(empty, PIECES, Scratch(spark, "t")).count() == 0


def test_best_path_is_the_best():
    pieces = lattice.Pieces(PIECES)

    def brute(s):
        if not s:
            return 0.0
        found = [pieces.score[s[:k]][0] + brute(s[k:]) for k in range(1, len(s) + 1) if s[:k] in pieces.score]
        return max(found + ([pieces.fallback + brute(s[1:])] if s[0] not in pieces.score else []))

    score = {i: s for s, i in ((v[0], v[1]) for v in pieces.score.values())}
    for word in ("▁hello", "▁straße", "▁abc中"):
        ids = pieces.best(word)
        bytes_ = set(pieces.byte_id.values())
        got = sum(score[i] for i in ids if i not in bytes_) + pieces.fallback * any(i in bytes_ for i in ids)
        assert got == brute(word)


def test_edit_distances():
    random.seed(1)

    def full(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            new = [i]
            for j, y in enumerate(b, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
            row = new
        return row[-1]

    for _ in range(500):
        a, b = ([random.randint(1, 3) for _ in range(random.randint(0, 12))] for _ in "ab")
        band, d = random.randint(0, 12), full(a, b)
        assert order_minhash.banded_distance(a, b, band) == (d if d <= band else None)
        got = order_minhash.band_distances([np.array(a, np.uint64)], [np.array(b, np.uint64)], band)[0]
        assert got == d if d <= band else got > band


def test_near_duplicates_against_brute_force(spark):
    random.seed(7)
    words = [f"w{k}" for k in range(300)]
    texts = []
    for _ in range(12):
        base = [random.choice(words) for _ in range(random.randint(20, 120))]
        for _ in range(random.randint(1, 6)):
            t = list(base)
            for _ in range(random.randint(0, max(1, len(t) // 25))):
                t[random.randrange(len(t))] = random.choice(words)
            texts.append(" ".join(t))
    texts += ["", None, "one two", "one two"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    label = list(range(len(texts)))
    lists = [order_minhash.words_of(t or "") for t in texts]
    for i in range(len(texts)):
        for j in range(i):
            if lists[i] and lists[j] and order_minhash.similarity(lists[i], lists[j]) is not None:
                a, b = sorted((label[i], label[j]))
                label = [a if x == b else x for x in label]
    got = {r.doc_id: r.class_id for r in order_minhash.classes(docs, Scratch(spark, "t")).collect()}
    assert got == dict(enumerate(label))
    kept = order_minhash.keep_first(docs.withColumn("label", F.lit(1)), Scratch(spark, "t"))
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(label))


def test_near_duplicates_awkward(spark, docs, empty):
    out = order_minhash.classes(docs, Scratch(spark, "t")).collect()
    assert len(out) == docs.count()
    same = {r.doc_id: r.class_id for r in out}
    assert same[8] == same[9] == 8 and same[1] == 1
    assert order_minhash.keep_first(docs, Scratch(spark, "t")).where("text = 'same text here'").count() == 1
    assert order_minhash.classes(empty, Scratch(spark, "t")).count() == 0


def test_perplexity(spark, docs, empty):
    scratch = Scratch(spark, "t")
    scored = perplexity.score(docs, perplexity.fit(docs, scratch))
    out = {r.doc_id: r for r in perplexity.verdicts(scratch.keep(scored)).collect()}
    assert out[0].base_failed and not out[0].kept and out[0].log_ppl is None
    text, words = TEXTS[4], TEXTS[4].encode().split()
    assert out[4].n_words == len(words) and out[4].word_chars == sum(len(w.decode()) for w in words)
    assert out[6].base_failed and out[6].n_repeat_words == 12_000
    assert perplexity.repeat_words([b"a", b"b", b"c", b"d", b"e", b"x", b"a", b"b", b"c", b"d", b"e"]) == 10
    assert perplexity.features_of("a\nb\na\n\n a", text.encode().split())[3] == 1
    assert perplexity.verdicts(perplexity.score(empty, perplexity.fit(empty, scratch))).count() == 0


def test_kneser_ney_sums_to_one(spark):
    docs = spark.createDataFrame([("en", "abba baab abab aaab bbba cab"), ("en", "acab abc")], "lang string, text string")
    levels = perplexity.fit(docs, Scratch(spark, "t")).load("en")
    grams, p, *_ = levels[0]
    # all symbols of the alphabet, seen or not, after the shortest context
    seen = (2.0 ** p.astype(float)).sum()
    assert seen <= 1.0001
    own = perplexity.log2_probabilities(levels, ["abab"])[0]
    assert own > perplexity.log2_probabilities(levels, ["zzzz"])[0]


def test_licenses(spark, docs, empty):
    texts = {
        1: "Foo.\nReleased under the MIT License.\nbar",
        2: "This work is licensed under the GNU General Public License, version 3.",
        3: "nothing here",
        4: "our license is secret.",
        5: "Redistribution and use in source and binary forms, with or without modification,\nare permitted provided that the following conditions are met:\n1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        6: None,
    }
    rows = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    out = {r.doc_id: r for r in licenses.scan(rows).collect()}
    assert out[1].licenses == ["MIT (named)"] and out[2].licenses == ["GPL-3"]
    assert [out[k].verdict for k in (1, 2, 3, 4, 6)] == ["known", "known", "none", "unknown", "none"]
    assert out[5].verdict == "partial"
    assert licenses.scan(docs).count() == docs.count() and licenses.scan(empty).count() == 0
    plan = licenses.scan(rows)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_mpeg(spark, docs, empty):
    random.seed(1)
    for n in (64, 1024, 1021 * 64):
        body = random.randbytes(n)
        media = mpeg.wrap(body)
        s = mpeg.read(media)
        assert s.payload == body and s.intact and s.table_frames == len(s.offsets) and s.samples == 1152 * len(s.offsets)
        hurt = mpeg.read(media[:1500] + b"junk" + media[1500:])
        assert hurt.skipped and not hurt.intact
    assert mpeg.read(b"").payload == b"" and mpeg.read(b"abc").skipped == 3
    for r in mpeg.store_and_measure(docs, Scratch(spark, "t")).join(docs.select("doc_id", "text").distinct(), "doc_id").collect():
        raw = (r.text or "").encode()
        pad = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(pad), hashlib.sha256(pad).hexdigest(), zlib.crc32(pad[-64:]))
        assert r.intact
    assert mpeg.store_and_measure(empty, Scratch(spark, "t")).count() == 0


def test_pfair(spark, docs, empty):
    random.seed(1)
    for _ in range(60):
        quanta = {f"s{i}": random.randint(1, 9) for i in range(random.randint(1, 7))}
        plan = pfair.epochs({s: random.randint(0, 50) for s in quanta}, quanta)
        seen = {e["start"] + i // e["quanta"] * e["total"] + e["offsets"][i % e["quanta"]]: e for e in plan for i in range(e["blocks"])}
        assert sorted(seen) == list(range(sum(e["blocks"] for e in plan)))
        done: dict = {}
        for slot in sorted(seen):
            e = seen[slot]
            done[e["start"], e["source"]] = done.get((e["start"], e["source"]), 0) + 1
            for x in plan:
                if x["start"] == e["start"]:
                    assert abs(done.get((x["start"], x["source"]), 0) - (slot - x["start"] + 1) * x["quanta"] / x["total"]) < 1
    out = pfair.schedule(docs, {"s": 2}, block_rows=2)
    rows = out.collect()
    assert len(rows) == docs.count() and len({r.position for r in rows}) == len(rows)
    assert pfair.in_order(out).count() == docs.count()
    assert pfair.schedule(empty, {"s": 2}).count() == 0
