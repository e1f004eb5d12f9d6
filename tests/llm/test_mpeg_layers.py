"""Checksums of other layers are not taken for good, and the audio query keeps its seek offsets."""

from sheetgraph.llm import mpeg, queries


def test_layer_two_with_a_wrong_checksum_is_not_intact():
    for head, layer in ((b"\xff\xfc\x80\xc0", 2), (b"\xff\xfe\x40\xc0", 1)):
        h = mpeg.header(head)
        assert h.layer == layer and h.crc
        s = mpeg.read((head + b"\x12\x34" + bytes(h.size - 6)) * 3)
        assert len(s.offsets) == s.unverified == 3 and not s.intact
    s = mpeg.read(mpeg.wrap(bytes(64)))
    assert s.intact and s.unverified == 0


def test_the_query_keeps_frame_offsets(spark, sf):
    for r in queries.op9_mpeg_audio(spark, sf).select("n_frames", "frame_offsets", "intact").collect():
        assert r.intact and len(r.frame_offsets) == r.n_frames and sorted(r.frame_offsets) == r.frame_offsets
