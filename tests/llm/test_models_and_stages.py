"""Language and perplexity models against brute force; the pipeline's stages on awkward tables."""

import math
import random
from collections import Counter, defaultdict

import public_tokenizers
from pyspark.sql import functions as F

import corpus_pipeline
from sheetgraph.llm import langid, mpeg, perplexity, pfair, rendezvous
from sheetgraph.llm._shared import Scratch

PIECES = public_tokenizers.path("piece_bpe_32k.model")


def plain_kneser_ney(words: list[str]):
    """log2 p of the characters and the end of a word, by interpolated modified Kneser-Ney in plain Python."""
    start, end, order = "<", ">", perplexity.ORDER

    def grams(w):
        s = [start] * (order - 1) + list(w) + [end]
        return [tuple(s[k : k + order]) for k in range(len(w) + 1)]

    counts = {order: Counter(g for w in words for g in grams(w))}
    for k in range(order - 1, 0, -1):
        counts[k] = Counter(g[1:] for g in counts[k + 1])
    discounts = {}
    for k, of in counts.items():
        n = Counter(of.values())
        y = n[1] / (n[1] + 2 * n[2]) if n[1] else 0.5
        raw = {i: i - (i + 1) * y * n[i + 1] / n[i] if n[i] else None for i in (1, 2, 3)}
        discounts[k] = {i: x if x is not None and 0.05 <= x <= i - 0.05 else 0.25 + 0.25 * i for i, x in raw.items()}
    contexts = {k: defaultdict(list) for k in counts}
    for k, of in counts.items():
        for g, n in of.items():
            contexts[k][g[:-1]].append(n)

    def p(g):
        k = len(g)
        if not k:
            return 1 / (1 << perplexity.BITS)
        seen = contexts[k].get(g[:-1])
        if not seen:
            return p(g[1:])
        d, n = discounts[k], counts[k].get(g, 0)
        kept = sum(d[min(x, 3)] for x in seen)
        return (max(0, n - d[min(n, 3)]) if n else 0) / sum(seen) + kept / sum(seen) * p(g[1:])

    return lambda w: sum(math.log2(p(g)) for g in grams(w))


def test_kneser_ney_against_brute_force(spark):
    random.seed(4)
    words = ["".join(random.choice("aabcé") for _ in range(random.randint(1, 7))) for _ in range(120)]
    docs = spark.createDataFrame([("", " ".join(words[:60])), (None, " ".join(words[60:]))], "lang string, text string")
    model = perplexity.fit(docs, Scratch(spark, "t"))
    assert model.langs == ["und"]
    truth, tries = plain_kneser_ney(words), [*words[:30], "zz", "abcabcabc", "é"]
    got = perplexity.log2_probabilities(model.load("und"), tries)
    assert all(abs(x - truth(w)) < 1e-3 for w, x in zip(tries, got))
    scored = {r.lang: r for r in perplexity.score(docs.withColumn("log_ppl", F.lit("old")).union(spark.createDataFrame([("xx", "ab", "new")], "a string, b string, c string")), model).collect()}
    assert abs(scored[""].log_ppl + sum(truth(w) for w in words[:60]) / 60) < 1e-3
    assert scored["xx"].log_ppl is None


def test_no_two_characters_share_a_symbol():
    wide = [chr(c) for c in (0x7FF, 0x800, 0x4E2D, 0x4E2E, 0x52D, 0x1F600, 0x1FA00, 0x10FFFF)]
    keys = [tuple(perplexity.symbols_of([c + "a"])[0]) for c in wide]
    assert len(set(keys)) == len(wide)
    owner = perplexity.symbols_of(["中a", "b"])[1].tolist()
    assert owner == [0, 0, 0, 0, 1, 1]


def test_quartiles_are_exact_and_ignore_partitions(spark):
    random.seed(2)
    xs = [random.gauss(13, 1) for _ in range(999)]
    rows = spark.createDataFrame([("en", x) for x in xs] + [("de", 3.0)], "lang string, x double")
    got = [{r.lang: (r.low, r.high) for r in perplexity.quartiles(rows.repartition(n)).collect()} for n in (1, 7)]
    assert got[0] == got[1] and abs(got[0]["de"][0] - 3) < 1 / 256
    low, high = sorted(xs)[249], sorted(xs)[748]
    assert abs(got[0]["en"][0] - low) <= 1 / 256 and abs(got[0]["en"][1] - high) <= 1 / 256


def test_bands_reject_planted_junk_and_keep_the_rest(spark, sf):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang", "text")
    random.seed(3)
    noise = [(-k - 1, "en", " ".join("".join(random.choice("bcdfgjkpqvwxz") for _ in range(8)) for _ in range(80))) for k in range(5)]
    docs = docs.union(spark.createDataFrame(noise, docs.schema))
    scratch = Scratch(spark, "t")
    out = perplexity.verdicts(scratch.keep(perplexity.score(docs, perplexity.fit(docs, scratch)))).collect()
    assert not any(r.kept for r in out if r.doc_id < 0)
    passed = [r for r in out if r.doc_id >= 0 and not r.base_failed]
    lost = [r for r in passed if not r.kept]
    assert 0 < len(lost) < 0.06 * len(passed)
    labels = {r.doc_id: r.quality for r in spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect()}
    good = [r for r in passed if labels.get(r.doc_id) == 1]
    assert sum(r.kept for r in good) >= 0.99 * len(good)


def test_texts_of_no_learned_language(spark, sf):
    given = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.fit(given, PIECES, ~langid.held_out())
    random.seed(1)
    strange = [" ".join("".join(random.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(7)) for _ in range(60)), "привет как дела это русский текст", "これは日本語のテキストです今日は天気がいいですね" * 30]
    rows = spark.createDataFrame(list(enumerate(strange)), "doc_id long, text string")
    assert all(r.margin < 0 for r in langid.predict(rows, model).collect())
    assert langid.predict(given, model).where("text rlike '[a-z]' and margin <= 0").count() == 0


def test_winning_shard_is_the_least_cost(spark):
    weights = [1.0, 2.5, 0.5]
    keys = spark.range(200).select(F.col("id").alias("doc_id"), F.lit(None).cast("string").alias("text"))
    hashes = keys.select("doc_id", *[F.xxhash64("doc_id", F.lit(k)).alias(f"h{k}") for k in range(3)]).collect()
    want = {r.doc_id: min(range(3), key=lambda k: -math.log((((r[f"h{k}"] % (1 << 64)) >> 11) + 0.5) / 2**53) / weights[k]) for r in hashes}
    assert {r.doc_id: r.shard for r in rendezvous.assign(keys, weights).collect()} == want
    few = rendezvous.assign(keys, weights, buckets=1).orderBy("doc_id").collect()
    assert sorted((r.shard, r.slot) for r in few) == sorted((r.shard, r.slot) for r in rendezvous.assign(keys, weights, buckets=50).collect())


def test_a_cut_table_frame_is_read():
    base = bytearray(mpeg.wrap(bytes(64)))
    at = max(base.find(b"Xing"), base.find(b"Info"))
    for n in range(at, at + 130, 3):
        mpeg.read(bytes(base[:n]))
    # an MPEG-2 frame of 24 bytes that ends inside its table
    head = next(h for h in (bytes([0xFF, 0xF3, b, 0xC0]) for b in range(0x10, 0xF0, 4)) if mpeg.header(h) and mpeg.header(h).size >= 24)
    h = mpeg.header(head)
    frame = bytearray(head + bytes(h.size - 4))
    frame[4 + h.side : 8 + h.side] = b"Xing"
    frame[8 + h.side : 12 + h.side] = b"\0\0\0\7"
    frame = frame[: h.size]
    s = mpeg.read(bytes(frame))
    assert s.table == "Xing" and len(s.points) in (0, 100)


def test_vbri_tables():
    head = next(h for h in (bytes([0xFF, 0xFB, b, 0xC0]) for b in range(0x10, 0xF0, 4)) if mpeg.header(h) and mpeg.header(h).size >= 200)
    size = mpeg.header(head).size
    body = b"VBRI" + bytes(6) + (5000).to_bytes(4, "big") + (7).to_bytes(4, "big") + (3).to_bytes(2, "big") + (2).to_bytes(2, "big") + (2).to_bytes(2, "big") + bytes(2)
    body += b"".join(x.to_bytes(2, "big") for x in (10, 20, 30))
    frame = head + bytes(32) + body
    s = mpeg.read(frame + bytes(size - len(frame)) + head + bytes(size - 4))
    assert (s.table, s.table_bytes, s.table_frames, s.points, len(s.offsets)) == ("VBRI", 5000, 7, [20, 40, 60], 1)


def awkward(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, and columns named like inner ones."""
    en = "the house of the king is in the north of the land and it was built for him by the people of that time "
    texts = [None, "", " ", "a", en, en, en + "x", "x" * 700, en * 40, "中文 😀 #1", "1 2 3", en.upper()]
    inner = ("__lang", "__score", "__margin", "__q_n_words", "__q_kept", "n_words", "__node", "__sketches", "__m_slot", "__m_position", "slot", "position", "pool", "__pool", "ids", "kept", "class_id", "__text", "__low", "chunk", "segment")
    rows = [(i, t, ["en", None, ""][i % 3], None if i % 4 == 0 else f"src{i % 3}", len(t or ""), *[i] * len(inner)) for i, t in enumerate(texts)]
    rows += [(None, en, None, None, None, *[None] * len(inner))] * 2 + [rows[1]] * 2 + [rows[4]]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` int" for c in inner))


def test_every_stage_takes_awkward_tables(spark, sf):
    docs = awkward(spark)
    for name, stage in corpus_pipeline.STAGES:
        for table, least in ((docs, 1), (docs.where("false"), 0)):
            out = stage(spark, table, sf)
            rows = out.collect()
            assert len(rows) <= table.count(), name
            if name != "sentencepiece":
                assert out.columns == table.columns
            else:
                assert len(rows) == table.count() and len({r.position for r in rows}) == len(rows)
            if name in ("mix_sources", "sentencepiece", "near_dedup"):
                assert len(rows) >= least
            if name == "mix_sources":
                assert len(rows) == table.count()


def test_near_duplicates_keep_one_of_repeated_rows_without_words(spark):
    docs = spark.createDataFrame([(1, ""), (1, ""), (2, ""), (None, "a b"), (None, "a b"), (5, None)], "doc_id long, text string")
    kept = corpus_pipeline.drop_near_duplicates(spark, docs, "")
    assert sorted(kept.collect(), key=str) == sorted([(1, ""), (2, ""), (5, None), (None, "a b")], key=str)


def test_schedule_ignores_the_number_of_buckets(spark):
    docs = spark.range(300).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 2 == 0, "a").alias("source"), F.lit(1).alias("slot"))
    for buckets in (1, 64):
        out = pfair.schedule(docs, {"a": 2}, block_rows=8, buckets=buckets).collect()
        assert len({r.position for r in out}) == 300 and out[0].__fields__.count("slot") == 1
        by_slot = {}
        for r in out:
            assert by_slot.setdefault(r.slot, r.pool) == r.pool
