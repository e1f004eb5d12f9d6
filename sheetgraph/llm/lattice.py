"""SentencePiece encoding and decoding over a relational lattice.

A text is spelled the library's way (a mark before it and for every space) and cut into segments that no
piece can cross: before a run of marks, and between two characters that stand side by side in no piece.
Each distinct segment becomes a lattice in DataFrames: its substrings up to the longest piece's length are
exploded, an equi-join to the piece table leaves the edges, a character without a piece gets an edge of its
bytes, edges are grouped by segment, and a fold with a higher-order aggregate finds the best path (the
greatest sum of the pieces' scores; of equals, the one whose last piece is longest, and so on backwards).

Scores of a BPE file are ranks of merges and not log probabilities, so the best sum is not that model's
encoding. With merged=True, as the queries use it, the fold follows the merges over the same edges: of those
that join two symbols which stand side by side, the one of the highest score, of equals the leftmost, until
none is left; the ids are the library's. The ends of symbols are the bits of one number, so a segment in the
lattice has up to MERGED_LONG characters.

Segments go to the lattice once for the whole corpus, and come back to the task that holds the texts: a
first pass emits each segment of a chunk (CHUNK characters of one partition's texts, in their order) with
the chunk's number; a join brings the segment's ids to every chunk that has it, and the dictionary is
stored by chunk in the shared folder. A task so holds what CHUNK characters need, whatever the corpus or
the partition holds; there is no broadcast but the fixed piece table. Segments over LONG or MERGED_LONG
characters are folded by the same rule in the worker (with a heap where merged). So would be segments that
a chunk does not find, were rows to come in another order the second time; the result's accumulator
`folded_in_workers` counts those, 0 in all runs so far.

Defined results: null or empty text has no ids and decodes to the empty text; equal texts get equal ids; an
empty table gives an empty table; columns named like the results are replaced; a null doc_id and repeated
rows are rows like others.
"""

from __future__ import annotations

import heapq
import re
import zlib
from itertools import chain, compress

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sheetgraph.llm._shared import Scratch, file_system, held, make_room, map_arrow, prepare, texts_of, without

MARK = "▁"
LONG = 256
MERGED_LONG = 60
CUT_ENTRIES = 100_000
#: Longer parts of words with other characters than letters are also cut between letters.
WHOLE = 24
NO_LETTER = re.compile(r"[\W\d_]")
#: Characters of a partition's texts whose segments share one dictionary, and bits of a chunk's number.
CHUNK, CHUNK_BITS = 32_000_000, 24
#: Characters whose words are looked up in it together.
RUN = 1_000_000


class Pieces:
    """The vocabulary: scores, byte pieces, and which characters stand side by side in a piece."""

    def __init__(self, model_path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
        self.rows, self.byte_id, self.text = [], {}, []
        for i in range(sp.get_piece_size()):
            name = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte_id[int(name[3:5], 16)] = i
                self.text.append(bytes([int(name[3:5], 16)]))
            elif sp.is_control(i) or sp.is_unknown(i):
                self.text.append(b"")
            else:
                self.rows.append((name, i, float(sp.get_score(i))))
                self.text.append(name.replace(MARK, " ").encode())
        self.score = {name: (score, i) for name, i, score in self.rows}
        self.longest = max(len(name) for name, *_ in self.rows)
        # equal scores share a rank, so that only the place decides between them
        ranks = {x: k for k, x in enumerate(sorted({-score for *_, score in self.rows}))}
        self.rank = {name: ranks[-score] for name, _, score in self.rows}
        # a character without a piece costs more than any path of pieces could
        self.fallback = 2.0 * min(score for *_, score in self.rows)
        self.bytes_of = pa.array(self.text, pa.large_binary())
        self.pairs = {name[k : k + 2] for name, *_ in self.rows for k in range(len(name) - 1)}

    def cut(self, word: str) -> list[str]:
        """A word in parts that no piece crosses; a word of letters alone stays whole, as they join in most ways.

        Other words are cut beside what is no letter, so that their letters make the segments that such words
        have; only long parts also between letters.
        """
        if word[1:].isalpha():
            return [word]
        out, start, pairs = [], 0, self.pairs
        for found in NO_LETTER.finditer(word, 1):
            at = found.start()
            for k in (at, at + 1):
                if start < k < len(word) and word[k - 1 : k + 1] not in pairs:
                    out.append(word[start:k])
                    start = k
        out.append(word[start:])
        if len(word) <= WHOLE:
            return out
        return [s for part in out for s in (self._cut_all(part) if len(part) > WHOLE else (part,))]

    def _cut_all(self, part: str) -> list[str]:
        out, start = [], 0
        for k in range(1, len(part)):
            if part[k - 1 : k + 1] not in self.pairs:
                out.append(part[start:k])
                start = k
        return [*out, part[start:]]

    def best(self, segment: str) -> list[int]:
        """The fold of the lattice, edge by edge in the same order, for one segment in this process."""
        score, back = [0.0], [(0, ())]
        for end in range(1, len(segment) + 1):
            top = None
            for start in range(max(0, end - self.longest), end):
                hit = self.score.get(segment[start:end])
                if hit is None and start == end - 1:
                    hit = (self.fallback, tuple(self.byte_id[b] for b in segment[start:end].encode("utf-8", "surrogatepass")))
                if hit and (top is None or score[start] + hit[0] > top):
                    top, link = score[start] + hit[0], (start, hit[1] if isinstance(hit[1], tuple) else (hit[1],))
            score.append(top)
            back.append(link)
        at, ids = len(segment), []
        while at:
            ids[:0] = back[at][1]
            at = back[at][0]
        return ids

    def merged(self, segment: str) -> list[int]:
        """The model's merges of one segment in this process, by a heap of the pairs that may merge."""
        n, rank = len(segment), self.rank
        after, before = list(range(1, n + 1)), list(range(-1, n))  # end of the symbol from here, start of the one up to here
        heap = [(rank[segment[k : k + 2]], k, k + 1, k + 2) for k in range(n - 1) if segment[k : k + 2] in rank]
        heapq.heapify(heap)
        while heap:
            _, start, mid, end = heapq.heappop(heap)
            if after[start] != mid or after[mid] != end:
                continue
            after[start], after[mid], before[end] = end, -1, start
            for a, b, c in ((before[start], start, end), (start, end, after[end] if end < n else -1)):
                if a >= 0 and c > 0 and c - a <= self.longest and segment[a:c] in rank:
                    heapq.heappush(heap, (rank[segment[a:c]], a, b, c))
        at, ids = 0, []
        while at < n:
            hit = self.score.get(segment[at : after[at]])
            ids += [hit[1]] if hit else [self.byte_id[b] for b in segment[at].encode("utf-8", "surrogatepass")]
            at = after[at]
        return ids


_pieces: dict[str, Pieces] = held("lattice")


def pieces_of(path: str) -> Pieces:
    """The vocabulary, read once in a process."""
    if path not in _pieces:
        _pieces[path] = Pieces(path)
    return _pieces[path]


def words_of(text: str) -> list[str]:
    """Words with their marks; put together they are the spelled text."""
    if not text:
        return []
    words = text.split(" ")
    if "" not in words and MARK not in text:
        return words  # the usual case: each has one mark in front
    spelled = MARK + text.replace(" ", MARK)
    out, start = [], 0
    for k in range(1, len(spelled)):
        if spelled[k] == MARK and spelled[k - 1] != MARK:
            out.append(spelled[start:k])
            start = k
    return [*out, spelled[start:]]


def _spelled(word: str) -> str:
    return word if word[:1] == MARK else MARK + word


class _Chunks:
    """Deals the texts of a partition into chunks by their lengths alone, so that two passes agree."""

    def __init__(self, partition: int):
        self.at, self.chars = partition << CHUNK_BITS, 0

    def deal(self, column: pa.Array, most: int):
        """(chunk, texts) for consecutive texts, at most about `most` characters at a time; only those are made objects."""
        start = size = 0
        for k, n in enumerate(pc.fill_null(pc.utf8_length(column), 0).to_pylist()):
            full = self.chars >= CHUNK
            if k > start and (full or size + n > most):
                yield self.at, texts_of(column.slice(start, k - start))
                start, size = k, 0
            if full:
                self.at, self.chars = self.at + 1, 0
            self.chars += n
            size += n
        if start < len(column):
            yield self.at, texts_of(column.slice(start))


class _Seen:
    """Texts seen so far, as their hashes in order: eight bytes each.

    Of two texts with one hash the second counts as seen; the chunk then lacks it, and the worker folds it.
    """

    def __init__(self):
        self.hashes = np.zeros(0, np.int64)

    def fresh(self, texts: set[str]) -> list[str]:
        """Those not seen, which now are."""
        some = list(texts)
        new = np.fromiter(map(hash, some), np.int64, len(some))
        if len(self.hashes):
            at = np.minimum(np.searchsorted(self.hashes, new), len(self.hashes) - 1)
            is_new = self.hashes[at] != new
            some, new = list(compress(some, is_new.tolist())), new[is_new]
        self.hashes = np.sort(np.concatenate([self.hashes, new]), kind="stable")
        return some


def segments_seen(docs: DataFrame, model_path: str, text: str, longest: int = LONG) -> DataFrame:
    """chunk, segment for the distinct segments in each chunk of docs, those of up to longest characters."""

    def make():
        from pyspark import TaskContext

        make_room("lattice")
        pieces = pieces_of(model_path)
        chunks = _Chunks(TaskContext.get().partitionId())
        now, words_seen, parts_seen = -1, _Seen(), _Seen()

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            nonlocal now, words_seen, parts_seen
            out: list[pa.Array] = []
            numbers: list[np.ndarray] = []
            for chunk, some in chunks.deal(batch.column(0), RUN):
                if chunk != now:
                    now, words_seen, parts_seen = chunk, _Seen(), _Seen()
                new: set[str] = set()
                for t in some:
                    new.update(words_of(t))
                del some
                fresh = words_seen.fresh(new)
                del new
                letters = [w for w in fresh if w.isalpha()]
                parts = set(chain.from_iterable(pieces.cut(_spelled(w)) for w in fresh if not w.isalpha()))
                # a part that a word of letters has for its segment counts as that word
                heads = {s[1:] for s in parts if s[:1] == MARK and s[1:].isalpha()}
                parts = {s for s in parts if len(s) <= longest and not (s[:1] == MARK and s[1:] in heads)}
                segments = [MARK + w for w in chain(letters, words_seen.fresh(heads)) if len(w) < longest]
                segments += parts_seen.fresh(parts)
                out.append(pa.array(segments, pa.string()))
                numbers.append(np.full(len(segments), chunk, np.int64))
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(numbers)), pa.concat_arrays(out)], names=["chunk", "segment"])

        return step

    return map_arrow(docs.select(F.col(f"`{text}`").alias("text")), make, "chunk long, segment string")


def _edges(segments: DataFrame, pieces: Pieces, edge, several: F.Column | None = None) -> DataFrame:
    """segment, edges: each segment's lattice, an edge in the number that edge(start, len, id, rank) gives.

    several: that number again where the edge also belongs in a column `several`.
    """
    table = segments.sparkSession.createDataFrame([(name, i, pieces.rank[name]) for name, i, _ in pieces.rows], "piece string, id int, rank int")
    n = F.length("segment")
    # one row for each start, then one for each length: all substrings up to the longest piece
    starts = segments.select("segment", F.explode(F.sequence(F.lit(0), n - 1)).alias("start"))
    lengths = F.sequence(F.lit(1), F.least(F.lit(pieces.longest), n - F.col("start")))
    subs = starts.select("segment", "start", F.explode(lengths).alias("len"))
    subs = subs.select("segment", "start", "len", F.substring("segment", F.col("start") + 1, F.col("len")).alias("piece"))
    edges = subs.join(F.broadcast(table), "piece", "left").where(F.col("id").isNotNull() | (F.col("len") == 1))  # a fixed vocabulary
    edges = edges.select("segment", edge(F.col("start"), F.col("len"), F.coalesce("id", F.lit(0)).cast("long"), F.coalesce("rank", F.lit(0))).alias("edge"), "len")
    more = [] if several is None else [F.sort_array(F.collect_list(several)).alias("several")]
    return edges.groupBy("segment").agg(F.sort_array(F.collect_list("edge")).alias("edges"), *more)


def _ids_of(pieces: Pieces, start: F.Column, piece: F.Column) -> F.Column:
    """The piece, or the bytes of a character without one, as ids."""
    char = F.hex(F.encode(F.substring("segment", start + 1, F.lit(1)), "UTF-8"))
    byte = F.transform(F.sequence(F.lit(1), F.length(char) - 1, F.lit(2)), lambda k: F.conv(F.substring(char, k, F.lit(2)), 16, 10).cast("int") + F.lit(pieces.byte_id[0]))
    return F.when(piece > 0, F.array(piece)).otherwise(byte)


def merged_paths(segments: DataFrame, model_path: str) -> DataFrame:
    """The segments with ids, the path that the model's merges leave of each one's lattice."""
    pieces = pieces_of(model_path)

    one, two, done = (F.lit(x).cast("long") for x in (1, 2, -(1 << 63)))

    def edge(start: F.Column, length: F.Column, piece: F.Column, rank: F.Column) -> F.Column:
        # in the order of the merges: rank, start, end, piece
        return F.shiftleft(rank.cast("long"), 32) + F.shiftleft(start.cast("long"), 26) + F.shiftleft((start + length).cast("long"), 20) + piece

    # a shift of a long goes by the last six bits of its number, which are those of the start and of the end
    def at_start(e: F.Column, bits: F.Column) -> F.Column:
        return F.call_function("shiftleft", bits, F.shiftright(e, 26).cast("int"))

    def at_end(e: F.Column, bits: F.Column) -> F.Column:
        return F.call_function("shiftleft", bits, F.shiftright(e, 20).cast("int"))

    def places(e: F.Column) -> F.Column:
        """Bits of an edge's ends, and of the places between them."""
        return F.struct((at_end(e, one) + at_start(e, one)).alias("ends"), (at_end(e, one) - at_start(e, two)).alias("inner"))

    n = F.length("segment")
    several = F.transform("several", places)

    def merge(edges: F.Column) -> F.Column:
        def step(at: F.Column, _: F.Column) -> F.Column:
            # the ends of symbols; the first edge over just two of them merges, and without one the sign says so
            hit = F.slice(F.filter(edges, lambda x: (at.bitwiseAND(x["ends"]) == x["ends"]) & (F.bit_count(at.bitwiseAND(x["inner"])) == 1)), 1, 1)
            return F.when(at < 0, at).otherwise(F.aggregate(hit, at.bitwiseOR(done), lambda _, x: at.bitwiseAND(F.bitwise_not(x["inner"]))))

        return F.aggregate(F.sequence(F.lit(1), n), F.call_function("shiftleft", one, n + 1) - 1, step, lambda at: at.bitwiseAND(F.lit((1 << 63) - 1)))

    def bound(value: F.Column, body) -> F.Column:
        """body(value) as an array; the value is found once, where the optimizer would put it in all its places."""
        return F.transform(F.array(value), body)

    def symbols(at: F.Column) -> F.Column:
        """Edges whose ends stand with none between, as start and piece."""
        kept = F.filter("edges", lambda e: at.bitwiseAND(at_end(e, two) - at_start(e, one)) == at_end(e, one) + at_start(e, one))
        return F.sort_array(F.transform(kept, lambda e: F.shiftleft(F.shiftright(e, 26).bitwiseAND(F.lit(63)), 20) + e.bitwiseAND(F.lit(0xFFFFF))))

    def ids(path: F.Column) -> F.Column:
        def piece(x: F.Column) -> F.Column:
            return x.bitwiseAND(F.lit(0xFFFFF)).cast("int")

        spelled = F.flatten(F.transform(path, lambda x: _ids_of(pieces, F.shiftright(x, 20).cast("int"), piece(x))))
        return F.when(F.exists(path, lambda x: piece(x) == 0), spelled).otherwise(F.transform(path, piece))

    found = _edges(segments, pieces, edge, F.when(F.col("len") > 1, F.col("edge")))
    path = F.transform(bound(several, merge), symbols)
    return found.select("segment", F.flatten(F.transform(path, ids)).alias("ids"))


def best_paths(segments: DataFrame, model_path: str) -> DataFrame:
    """The segments with ids, the best path through each one's lattice."""
    pieces = pieces_of(model_path)

    def edge(start: F.Column, length: F.Column, piece: F.Column, rank: F.Column) -> F.Column:
        # in the order of the fold: end, start, piece (0: a character without one)
        return F.shiftleft((start + length).cast("long"), 48) + F.shiftleft(start.cast("long"), 32) + piece

    grouped = _edges(segments, pieces, edge)
    by_id = [pieces.fallback] * (max(i for _, i, _ in pieces.rows) + 1)
    for _, i, score in pieces.rows:
        by_id[i] = score
    scores = F.split(F.lit(",".join(map(repr, by_id))), ",").cast("array<double>")  # folded to one literal
    cell = "struct<s:double,p:array<int>>"
    first = F.array(F.struct(F.lit(0.0).alias("s"), F.array().cast("array<int>").alias("p"))).cast(f"array<{cell}>")

    def fold(acc: F.Column, e: F.Column) -> F.Column:
        end = F.shiftright(e, 48).cast("int")
        start = F.shiftright(e, 32).bitwiseAND(F.lit(0xFFFF)).cast("int")
        piece = e.bitwiseAND(F.lit(0xFFFFFFFF)).cast("int")
        before = F.get(acc, start)
        total = before["s"] + F.get(scores, piece)
        new = F.array(F.struct(total.alias("s"), F.concat(before["p"], _ids_of(pieces, start, piece)).alias("p")))
        fresh = F.size(acc) <= end
        return F.when(fresh, F.concat(acc, new)).when(total > F.get(acc, end)["s"], F.concat(F.slice(acc, F.lit(1), end), new)).otherwise(acc)

    return grouped.select("segment", F.aggregate("edges", first, fold, lambda acc: F.element_at(acc, -1)["p"]).alias("ids"))


def encode(docs: DataFrame, model_path: str, scratch: Scratch, text: str = "text", ids_col: str = "ids", finish=None, merged: bool = False, keep_text: bool = True) -> DataFrame:
    """All columns of docs with ids, the best path of every whole text, or the one that the model's merges leave.

    finish: (schema, function of pieces, texts and a list of id arrays) for what is to stand in place of ids,
    computed where they are. Without keep_text, texts do not come back from the workers.
    """
    spark = docs.sparkSession
    prepare(spark)
    schema, last = finish or (f"`{ids_col}` array<int>", _as_ids)
    added = T._parse_datatype_string(schema)
    docs = without(docs, *added.names)
    limit = MERGED_LONG if merged else LONG
    seen = segments_seen(docs, model_path, text, limit).repartition("segment")
    # the condition always holds; by it both sides of the join read all of one shuffle, which so runs once
    once = seen.groupBy("segment").agg(F.min("chunk").alias("least")).where("least >= 0").select("segment")
    paths = (merged_paths if merged else best_paths)(once, model_path)
    folder = f"{scratch.root}/dictionary"
    seen.join(paths, "segment").select("chunk", "segment", "ids").repartition("chunk").write.partitionBy("chunk").parquet(folder)
    columns = docs.columns
    at = columns.index(text)
    back = [k for k in range(len(columns)) if keep_text or k != at]
    names = [*(columns[k] for k in back), *added.names]
    missed = spark.sparkContext.accumulator(0)

    def make():
        from pyspark import TaskContext

        make_room("lattice")
        pieces = pieces_of(model_path)
        path_of = pieces.merged if merged else pieces.best
        chunks = _Chunks(TaskContext.get().partitionId())
        now, known, words = -1, None, {}

        def spell(new: set[str]) -> None:
            """Look the words up in the chunk's dictionary, all at once; what it lacks is folded here."""
            letters = [w for w in new if w.isalpha()]
            others = {w: pieces.cut(_spelled(w)) for w in new.difference(letters)}
            segments = [MARK + w for w in letters]
            segments += set(chain.from_iterable(others.values()))
            ids_of = known.find(segments)
            for k, ids in enumerate(ids_of):
                if ids is None:
                    if len(segments[k]) <= limit:
                        missed.add(1)
                    ids_of[k] = np.array(path_of(segments[k]), np.int32).tobytes()
            words.update(zip(letters, ids_of))
            get = dict(zip(segments[len(letters) :], ids_of[len(letters) :])).__getitem__
            words.update((w, b"".join(map(get, parts))) for w, parts in others.items())

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            nonlocal now, known
            made = []
            for chunk, some in chunks.deal(batch.column(at), RUN):
                if chunk != now:
                    known = None  # the old one goes first
                    now, known = chunk, _Dictionary(folder, chunk)
                    words.clear()
                lists = [words_of(t) for t in some]
                if len(words) > CUT_ENTRIES:
                    words.clear()
                new: set[str] = set()
                for u in lists:
                    new.update(u)
                new -= words.keys()
                spell(new)
                get = words.__getitem__
                made.append(last(pieces, some, [np.frombuffer(b"".join(map(get, u)), np.int32) for u in lists]))
                del some, lists, new  # before the next ones are made
            cols = [pa.concat_arrays(c) for c in zip(*made)]
            return pa.RecordBatch.from_arrays([*(batch.column(k) for k in back), *cols], names=names)

        return step

    fields = docs.schema.fields
    out = map_arrow(docs, make, T.StructType([*(fields[k] for k in back), *added.fields]))
    out.folded_in_workers = missed
    return out


def _as_ids(pieces: Pieces, texts: list[str], ids: list[np.ndarray]) -> list[pa.Array]:
    offsets = np.zeros(len(ids) + 1, np.int32)
    offsets[1:] = np.cumsum([len(x) for x in ids])
    return [pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(ids), pa.int32()))]


def _as_digest(pieces: Pieces, texts: list[str], ids: list[np.ndarray]) -> list[pa.Array]:
    crc = [zlib.crc32(x.astype("<u4", copy=False)) for x in ids]
    sizes = [len(x) for x in ids]
    return [pa.array(sizes, pa.int64()), pa.array(crc, pa.int64()), pa.array(_same(pieces, texts, ids), pa.bool_())]


def _same(pieces: Pieces, texts: list[str], ids: list[np.ndarray]) -> list[bool]:
    """Whether ids decode to their text; bytes that differ are decoded, as those of no character have a look too."""
    whole = pieces.bytes_of.take(pa.array(np.concatenate([*ids, [0]]), pa.int32()))  # never without an id
    body, cuts = memoryview(whole.buffers()[2]), np.frombuffer(whole.buffers()[1], np.int64)
    ends = cuts[np.cumsum([0, *map(len, ids)])].tolist()
    out = []
    for k, t in enumerate(texts):
        want = (" " + t).replace(MARK, " ").encode() if t else b""
        out.append(body[ends[k] : ends[k + 1]] == want or decode_ids(pieces, ids[k]) == t.replace(MARK, " "))
    return out


#: n_tokens, ids_crc32 (of little-endian 32 bits), and whether the ids decode to the text.
DIGEST = ("n_tokens long, ids_crc32 long, round_trip boolean", _as_digest)


class _Dictionary:
    """Segment to ids, as the lattice gave them for one chunk, in Arrow's arrays: a fifth of what objects of Python take."""

    def __init__(self, folder: str, chunk: int):
        import pyarrow.dataset as ds
        from pyarrow import fs as pafs

        fs, path = file_system(f"{folder}/chunk={chunk}")
        found = fs.get_file_info(pafs.FileSelector(path, allow_not_found=True))
        names = [f.path for f in found if f.path.endswith(".parquet")]
        self.segments, self.ids, self.cuts = pa.array([], pa.string()), b"", np.zeros(1, np.int64)
        if names:
            table = ds.dataset(names, filesystem=fs, format="parquet").to_table(columns=["segment", "ids"], use_threads=False)
            self.segments = table["segment"].combine_chunks()
            sizes = pc.list_value_length(table["ids"]).to_numpy()
            self.cuts = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)]) * 4
            self.ids = b"".join(c.flatten().cast(pa.int32()).to_numpy(zero_copy_only=False).tobytes() for c in table["ids"].chunks)

    def find(self, segments: list[str]) -> list[bytes | None]:
        """The segments' ids, None for one that is not there."""
        at = pc.index_in(pa.array(segments, pa.string()), value_set=self.segments).fill_null(-1).to_numpy()
        starts, ends = self.cuts[at], self.cuts[at + 1]
        ends[at < 0] = -1
        ids = self.ids
        return [None if b < 0 else ids[a:b] for a, b in zip(starts.tolist(), ends.tolist())]


def decode_ids(pieces: Pieces, ids: np.ndarray) -> str:
    """The text of ids: pieces and bytes put together, without the mark in front."""
    body = b"".join(map(pieces.text.__getitem__, ids.tolist()))
    return body[1:].decode("utf-8", "replace") if body[:1] == b" " else body.decode("utf-8", "replace")


def decode(encoded: DataFrame, model_path: str, ids_col: str = "ids", out_col: str = "decoded") -> DataFrame:
    """All columns with the text of the ids."""
    prepare(encoded.sparkSession)
    encoded = without(encoded, out_col)
    columns = encoded.columns
    at = columns.index(ids_col)

    def make():
        pieces = pieces_of(model_path)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [None if x is None else decode_ids(pieces, x) for x in _lists(batch.column(at))]
            return pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], names=[*columns, out_col])

        return step

    return map_arrow(encoded, make, T.StructType([*encoded.schema.fields, T.StructField(out_col, T.StringType())]))


def _lists(column: pa.Array):
    values = column.flatten().to_numpy(zero_copy_only=False)
    offsets = column.offsets.to_numpy() - column.offsets[0].as_py()
    for k in range(len(column)):
        yield values[offsets[k] : offsets[k + 1]] if column[k].is_valid else None
