"""The merging lattice gives the sentencepiece library's own ids, in Spark and in a worker."""

import random
import zlib

import numpy as np
import public_tokenizers
import sentencepiece

from sheetgraph.llm import lattice, queries
from sheetgraph.llm._shared import Scratch

PIECES = public_tokenizers.path("piece_bpe_32k.model")


def test_ids_are_the_librarys(spark):
    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    random.seed(5)
    texts = ["", " ", "the thought of abc中 😀", "Grüße, Welt!\n\nzwei  drei ", "x" * 700, "=" * 59 + " " + "=" * 60 + "a" * 61, "internationalisation " * 50]
    texts += ["".join(random.choice("aabbcdeéñß \n\tthein▁01#=😀中") for _ in range(random.randint(1, 90))) for _ in range(300)]
    pieces = lattice.Pieces(PIECES)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in lattice.encode(docs, PIECES, Scratch(spark, "t"), merged=True).collect():
        want = sp.encode(r.text)
        assert list(r.ids) == want
        assert pieces.merged("▁" + r.text.replace(" ", "▁") if r.text else "") == want
    # without the workers' own folds
    words = sorted({s for t in texts for w in lattice.words_of(t) for s in pieces.cut(w if w[:1] == "▁" else "▁" + w) if len(s) <= lattice.MERGED_LONG})
    rows = spark.createDataFrame([(w,) for w in words], "segment string")
    got = {r.segment: list(r.ids) for r in lattice.merged_paths(rows, PIECES).collect()}
    assert got == {w: pieces.merged(w) for w in words}


def test_the_query_gives_the_librarys_ids(spark, sf):
    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}
    for r in queries.op5_piece_lattice(spark, sf).collect():
        ids = sp.encode(texts[r.doc_id] or "")
        assert (r.n_tokens, r.ids_crc32, r.round_trip) == (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()), True)


def test_texts_stay_in_the_workers_and_a_spoiled_dictionary_is_noticed(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "one two"), (2, "two")], "doc_id long, text string")
    out = lattice.encode(docs, PIECES, Scratch(spark, "t"), finish=lattice.DIGEST, merged=True, keep_text=False)
    assert out.columns == ["doc_id", "n_tokens", "ids_crc32", "round_trip"] and all(r.round_trip for r in out.collect())
    real = lattice.merged_paths
    monkeypatch.setattr(lattice, "merged_paths", lambda s, m: real(s, m).selectExpr("segment", "IF(segment LIKE '%one', array(300), ids) AS ids"))
    out = lattice.encode(docs, PIECES, Scratch(spark, "t"), finish=lattice.DIGEST, merged=True, keep_text=False)
    assert {r.doc_id: r.round_trip for r in out.collect()} == {1: False, 2: True}


def test_what_another_operator_held_goes():
    from sheetgraph.llm import _shared

    mine, other = _shared.held("one"), _shared.held("two")
    mine["x"] = other["x"] = 1
    _shared.make_room("one")
    assert mine and not other


def test_a_word_of_letters_and_one_with_marks_beside_share_a_segment(spark):
    pieces = lattice.Pieces(PIECES)
    assert any("vxqkjz"[k : k + 2] not in pieces.pairs for k in range(5))
    assert pieces.cut("▁vxqkjz,") == ["▁vxqkjz", ","]
    docs = spark.createDataFrame([(1, "vxqkjz vxqkjz, (vxqkjz)")], "doc_id long, text string").coalesce(1)
    seen = [r.segment for r in lattice.segments_seen(docs, PIECES, "text", lattice.MERGED_LONG).collect()]
    assert len(seen) == len(set(seen)) and seen.count("▁vxqkjz") == 1
    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    out = lattice.encode(docs, PIECES, Scratch(spark, "t"), merged=True)
    assert [list(r.ids) for r in out.collect()] == [sp.encode("vxqkjz vxqkjz, (vxqkjz)")]
    assert out.folded_in_workers.value == 0


def test_only_a_run_of_a_batchs_texts_is_made_objects_at_a_time(monkeypatch):
    import pyarrow as pa

    made = []
    monkeypatch.setattr(lattice, "texts_of", lambda c: made.append(len(c)) or ["" if x is None else x for x in c.to_pylist()])
    monkeypatch.setattr(lattice, "CHUNK", 10)
    texts = ["abc", None, "", "defgh", "ijk", "l" * 30, "m", "n"]
    dealt = lattice._Chunks(0).deal(pa.array(texts), 6)
    assert next(dealt) == (0, ["abc", "", ""]) and made == [3]
    rest = list(dealt)
    assert [t for _, some in rest for t in some] == ["defgh", "ijk", "l" * 30, "m", "n"]
    assert [c for c, some in rest for _ in some] == [0, 0, 1, 2, 2]


def test_words_seen_are_kept_as_eight_bytes_each():
    seen, words = lattice._Seen(), {f"word{k}" for k in range(1000)}
    assert set(seen.fresh(words)) == words and seen.fresh(words) == [] and seen.fresh(set()) == []
    assert sorted(seen.fresh({"word1", "other"})) == ["other"] and seen.hashes.nbytes == 8 * 1001
