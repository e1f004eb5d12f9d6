"""Token ids in sorted-string-table shards: writer, reader with binary-search lookup, and the Spark job.

File: header magic; data blocks; a Bloom filter; a sparse index with each block's last key; a footer of
fixed size. A block holds entries in key order, each key cut by the prefix it shares with the one before
(written whole at every RESTART-th entry), restart offsets, and a CRC. The key of a record is one byte for
null or not, its identifier as 8 big-endian bytes with the sign bit turned (so bytes sort as numbers), and
4 bytes that tell equal identifiers apart. The value is the ids, 2 bytes each where the vocabulary allows.

The job encodes where the text is read, shuffles ids only, deals them out by ranges of the identifier and
writes one file a range under a name that a failed attempt can't share; the manifest, written by Spark,
names the files that count. Offsets of documents are prefix sums, of ranges and inside each.

Defined results: null text encodes as the empty text (the end id alone); null identifiers sort first;
equal identifiers keep a row each, ordered by their ids; an empty table gives an empty table.
"""

from __future__ import annotations

import bisect
import re
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sheetgraph.llm._shared import Scratch, file_system, map_arrow, prepare, runs_of, texts_of

HEADER = b"SGSSTAB1"
FOOTER = struct.Struct("<QQQQQIII8s")
RESTART = 16
CACHE_ENTRIES = 600_000
MAX_SHARDS = 20_000


def record_key(doc_id: int | None, copy: int) -> bytes:
    body = b"\0" * 9 if doc_id is None else b"\1" + ((doc_id + (1 << 63)) & ((1 << 64) - 1)).to_bytes(8, "big")
    return body + copy.to_bytes(4, "big")


def key_id(key: bytes) -> int | None:
    return int.from_bytes(key[1:9], "big") - (1 << 63) if key[0] else None


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(buf: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = buf[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def _bloom_hashes(key: bytes) -> tuple[int, int]:
    import xxhash

    h = xxhash.xxh3_128_intdigest(key)
    return h & ((1 << 64) - 1), h >> 64 | 1


class Writer:
    """Takes records in key order; close() ends the file."""

    def __init__(self, out, width: int, block_bytes: int = 65_536, bits_per_key: int = 10):
        self.out, self.width, self.block_bytes, self.bits = out, width, block_bytes, bits_per_key
        self.at = out.write(HEADER) or len(HEADER)
        self.block, self.restarts, self.index, self.hashes = bytearray(), [], [], []
        self.inside, self.count, self.last = 0, 0, b""

    def add(self, key: bytes, value: bytes) -> None:
        if self.count and key <= self.last:
            raise ValueError("keys must come in order")
        shared = 0
        if self.inside % RESTART == 0:
            self.restarts.append(len(self.block))
        else:
            most = min(len(key), len(self.last))
            while shared < most and key[shared] == self.last[shared]:
                shared += 1
        self.block += _varint(shared) + _varint(len(key) - shared) + _varint(len(value)) + key[shared:] + value
        self.hashes.append(_bloom_hashes(key[:9]))
        self.inside, self.count, self.last = self.inside + 1, self.count + 1, key
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _flush(self) -> None:
        if self.inside:
            body = bytes(self.block) + struct.pack(f"<{len(self.restarts)}II", *self.restarts, len(self.restarts))
            body += struct.pack("<I", zlib.crc32(body))
            self.out.write(body)
            self.index.append((self.last, self.at, len(body)))
            self.at += len(body)
            self.block, self.restarts, self.inside = bytearray(), [], 0

    def close(self) -> int:
        self._flush()
        m = max(64, self.count * self.bits)
        filter_bits = np.zeros((m + 7) // 8, dtype=np.uint8)
        probes = max(1, round(self.bits * 0.69))
        for a, b in self.hashes:
            for i in range(probes):
                bit = ((a + i * b) & ((1 << 64) - 1)) % m
                filter_bits[bit >> 3] |= 1 << (bit & 7)
        bloom = struct.pack("<QI", m, probes) + filter_bits.tobytes()
        index = b"".join(_varint(len(k)) + k + struct.pack("<QI", at, n) for k, at, n in self.index)
        self.out.write(bloom + index)
        tail = (self.at, len(bloom), self.at + len(bloom), len(index), self.count, self.width, zlib.crc32(bloom), zlib.crc32(index))
        self.out.write(FOOTER.pack(*tail, HEADER))
        return self.at + len(bloom) + len(index) + FOOTER.size


class Reader:
    """Reads a file through any seekable file object: get() by binary search, scan() in order."""

    def __init__(self, source, size: int):
        self.source = source
        source.seek(size - FOOTER.size)
        bloom_at, bloom_n, index_at, index_n, self.count, self.width, bloom_crc, index_crc, magic = FOOTER.unpack(source.read(FOOTER.size))
        if magic != HEADER:
            raise ValueError("not a sorted-string table")
        source.seek(bloom_at)
        bloom, index = source.read(bloom_n), source.read(index_n)
        if zlib.crc32(bloom) != bloom_crc or zlib.crc32(index) != index_crc:
            raise ValueError("damaged filter or index")
        self.m, self.probes = struct.unpack_from("<QI", bloom)
        self.bloom = bloom[12:]
        self.lasts, self.places, at = [], [], 0
        while at < len(index):
            n, at = _read_varint(index, at)
            self.lasts.append(index[at : at + n])
            self.places.append(struct.unpack_from("<QI", index, at + n))
            at += n + 12

    def _block(self, k: int) -> tuple[bytes, list[int], int]:
        at, n = self.places[k]
        self.source.seek(at)
        body = self.source.read(n)
        if zlib.crc32(body[:-4]) != struct.unpack_from("<I", body, n - 4)[0]:
            raise ValueError("damaged block")
        (count,) = struct.unpack_from("<I", body, n - 8)
        return body, list(struct.unpack_from(f"<{count}I", body, n - 8 - 4 * count)), n - 8 - 4 * count

    @staticmethod
    def _entries(body: bytes, at: int, end: int) -> Iterator[tuple[bytes, bytes]]:
        key = b""
        while at < end:
            shared, at = _read_varint(body, at)
            own, at = _read_varint(body, at)
            size, at = _read_varint(body, at)
            key = key[:shared] + body[at : at + own]
            at += own + size
            yield key, body[at - size : at]

    def scan(self) -> Iterator[tuple[bytes, bytes]]:
        for k in range(len(self.places)):
            body, _, end = self._block(k)
            yield from self._entries(body, 0, end)

    def may_hold(self, doc_id: int | None) -> bool:
        a, b = _bloom_hashes(record_key(doc_id, 0)[:9])
        bits = (((a + i * b) & ((1 << 64) - 1)) % self.m for i in range(self.probes))
        return all(self.bloom[x >> 3] >> (x & 7) & 1 for x in bits)

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """Ids of every record with this identifier: filter, index, restart points, then a short scan."""
        if not self.may_hold(doc_id):
            return []
        first, prefix, out = record_key(doc_id, 0), record_key(doc_id, 0)[:9], []
        for k in range(bisect.bisect_left(self.lasts, first), len(self.places)):
            body, restarts, end = self._block(k)
            lo, hi = 0, len(restarts) - 1
            while lo < hi:
                mid = (lo + hi + 1) // 2
                lo, hi = (mid, hi) if next(self._entries(body, restarts[mid], end))[0] <= first else (lo, mid - 1)
            for key, value in self._entries(body, restarts[lo], end):
                if key[:9] == prefix:
                    out.append(self.ids(value))
                elif key[:9] > prefix:
                    return out
        return out

    def ids(self, value: bytes) -> np.ndarray:
        return np.frombuffer(value, dtype="<u2" if self.width == 2 else "<u4")


_encoders: dict[str, tuple] = {}


def encoder(path: str):
    """The library's tokenizer and this worker's memory of what it gave for recent words."""
    if path not in _encoders:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        width = 2 if tok.get_vocab_size(with_added_tokens=True) <= 1 << 16 else 4
        _encoders[path] = (tok, width, {})
    return _encoders[path]


def encode_texts(path: str, texts: list[str], by_word: bool = True) -> list[bytes]:
    """Little-endian ids of each text, without special tokens added.

    by_word: for tokenizers that drop white space and never join across it (word_bpe_49k), the library
    encodes each distinct word between spaces and line ends once, and texts are put together from these.
    """
    tok, width, cache = encoder(path)
    kind = "<u2" if width == 2 else "<u4"
    if not by_word:
        return [np.array(e.ids, dtype=kind).tobytes() for e in tok.encode_batch(texts, add_special_tokens=False)]
    out: list[bytes] = []
    for some in runs_of(texts):
        lists = [parts_of(t) for t in some]
        if len(cache) > CACHE_ENTRIES:
            cache.clear()
        new = set()
        for u in lists:
            new.update(u)
        _remember(tok, kind, cache, [w for w in new if w not in cache])
        get = cache.__getitem__
        out += [b"".join(map(get, u)) for u in lists]
    return out


#: Texts of these characters alone fall into parts as PARTS says: lower case and composition change no boundary.
PLAIN = re.compile(r"[A-Za-z0-9 \n!-/:-@\[-`{-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]*")
PARTS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^a-z0-9 \n\u00df-\u00f6\u00f8-\u00ff]+")


def parts_of(text: str) -> list[str]:
    """What the tokenizer merges inside: its own parts of a plain text, else all between spaces and line ends."""
    if PLAIN.fullmatch(text) and "<|" not in text:
        return PARTS.findall(text.lower())
    return text.replace("\n", " ").split(" ")


def _remember(tok, kind: str, cache: dict[str, bytes], words: list[str]) -> None:
    """Encode words with the library, those that are one part many in one call, told apart by their last ids.

    Where the number of ends is not the number of words, or a word is no single part, it goes alone.
    """
    single, alone = [], []
    for w in words:
        one = PARTS.fullmatch(w) and PLAIN.fullmatch(w) and w == w.lower() and "<|" not in w
        (single if one else alone).append(w)
    width = np.dtype(kind).itemsize
    ends = _ends(tok)
    for k in range(0, len(single), 20_000):
        part = single[k : k + 20_000]
        ids = np.array(tok.encode(" ".join(part), add_special_tokens=False).ids, dtype=kind)
        cuts = ((np.flatnonzero(ends[ids]) + 1) * width).tolist()
        if len(cuts) != len(part):
            alone += part
            continue
        body = ids.tobytes()
        cache.update(zip(part, (body[a:b] for a, b in zip([0, *cuts], cuts))))
    for k in range(0, len(alone), 1024):
        part = alone[k : k + 1024]
        for w, e in zip(part, tok.encode_batch(part, add_special_tokens=False)):
            cache[w] = np.array(e.ids, dtype=kind).tobytes()


def _ends(tok) -> np.ndarray:
    """Whether each id ends a part of a word, by the vocabulary's suffix."""
    if id(tok) not in _end_marks:
        out = np.zeros(tok.get_vocab_size(with_added_tokens=True), dtype=bool)
        for piece, i in tok.get_vocab(with_added_tokens=True).items():
            out[i] = piece.endswith("</w>")
        _end_marks[id(tok)] = out
    return _end_marks[id(tok)]


_end_marks: dict[int, np.ndarray] = {}


def ids_crc32(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def write_shards(docs: DataFrame, tokenizer_path: str, scratch: Scratch, end_id: int = 1, by_word: bool = True, shard_bytes: int = 64 << 20, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Encode, sort and write; returns the manifest: part, path, rows, tokens, file_bytes."""
    spark = docs.sparkSession
    prepare(spark)
    docs = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = int(min(MAX_SHARDS, max(1, -(-total // shard_bytes))))
    bounds: list[int] = []
    if shards > 1:
        at = [k / shards for k in range(1, shards)]
        got = docs.agg(F.percentile_approx("doc_id", at, max(10_000, 10 * shards))).first()[0]
        bounds = sorted(set(got or []))
    shards = len(bounds) + 1

    def make_encode():
        edges = np.array(bounds, dtype=np.int64)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            width = encoder(tokenizer_path)[1]
            tail = end_id.to_bytes(width, "little")
            ids = [x + tail for x in encode_texts(tokenizer_path, texts_of(batch.column(1)), by_word)]
            keys = batch.column(0)
            low = np.searchsorted(edges, keys.fill_null(-(1 << 63)).to_numpy(zero_copy_only=False), side="left")
            return pa.RecordBatch.from_arrays([pa.array(low.astype(np.int32)), keys, pa.array(ids, pa.binary())], names=["part", "doc_id", "ids"])

        return step

    folder = f"{scratch.root}/sst"

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = file_system(folder)
        width = encoder(tokenizer_path)[1]
        out = None
        tokens, last, copy, part = 0, object(), 0, 0
        for batch in batches:
            for p, doc_id, ids in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                if out is None:
                    part, name = p, f"part-{p:05d}-{uuid.uuid4().hex}.sst"
                    fs.create_dir(base, recursive=True)
                    out = fs.open_output_stream(f"{base}/{name}.tmp")
                    table = Writer(out, width)
                copy = copy + 1 if doc_id == last else 0
                last = doc_id
                table.add(record_key(doc_id, copy), ids)
                tokens += len(ids) // width
        if out is not None:
            size = table.close()
            out.close()
            fs.move(f"{base}/{name}.tmp", f"{base}/{name}")
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "path": [f"{folder}/{name}"], "rows": pa.array([table.count]), "tokens": pa.array([tokens]), "file_bytes": pa.array([size])})

    encoded = map_arrow(docs, make_encode, "part int, doc_id long, ids binary")
    dealt = encoded.repartitionById(shards, F.col("part")).sortWithinPartitions("doc_id", "ids")
    return scratch.keep(dealt.mapInArrow(write, "part int, path string, rows long, tokens long, file_bytes long"))


def read_shards(manifest: DataFrame, files_per_task: int = 1) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every record, from the files alone."""
    prepare(manifest.sparkSession)
    order = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each file
    starts = manifest.select("path", "part", F.coalesce(F.sum("tokens").over(order), F.lit(0)).alias("start"))
    files = max(1, manifest.count())
    starts = starts.repartitionById(-(-files // files_per_task), F.col("part"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist()):
                fs, local = file_system(path)
                with fs.open_input_file(local) as source:
                    table = Reader(source, source.size())
                    rows: list[tuple] = []
                    for k, value in table.scan():
                        ids = table.ids(value)
                        rows.append((key_id(k), start, len(ids), ids_crc32(ids)))
                        start += len(ids)
                        if len(rows) == 20_000:
                            yield _rows(rows)
                            rows = []
                    if rows:
                        yield _rows(rows)

    return starts.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    names = ("doc_id", "start", "n_tokens", "ids_crc32")
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows)], names=list(names))


def look_up(manifest_rows: list, doc_id: int) -> list[np.ndarray]:
    """Ids of one document out of a manifest's files, for use outside Spark."""
    found = []
    for row in manifest_rows:
        fs, local = file_system(row["path"])
        with fs.open_input_file(local) as source:
            found += Reader(source, source.size()).get(doc_id)
    return found


