"""Near-duplicate classes by Order MinHash and banded alignment.

Texts are compared as sequences of lower-case words; a link is a pair whose word edit similarity,
1 - distance / longer length, is 0.8 or more, found by an alignment inside the band that this allows.
Candidates are pairs that agree on a key:

* Sketches, for texts of EXACT words and more. A text's shingles are labelled with the number of their
  occurrence; each hash function takes the smallest few and keeps them in text order, so two texts agree if
  they share those shingles in that order, which follows their edit similarity. FAMILIES has five-word
  shingles, and three-word ones, as a change of every fifth word leaves few runs of five words whole.
  A pair agrees on one of s sketches of t shingles with chance 1 - (1 - j^t)^s at shingle Jaccard j.
* Segments, for pairs whose shorter text has fewer words. d changes leave one of d + 1 segments of the
  shorter text whole, in a place near its own, so every link is a candidate: this route is exact.

Measured share of true links that become candidates, see the tests: 0.95 and more at a similarity of 0.85,
0.9 at 0.8 to 0.82, and all below EXACT words.

Classes are the connected components of the links. Equal word sequences are one node, by 128 bits. Instead
of all pairs in a bucket, every node is first aligned with one representative; components form; components
that share a bucket meet by one node each, a few times; last, all nodes of one bucket that are still in
different components are aligned, but for those that bounds on the distance rule out, so no candidate link
is lost.

Defined results: texts without a word are classes of their own, by doc_id; the class id is the smallest
doc_id of the class; rows with one doc_id and one word sequence are the same node; a null doc_id may belong
to a class and gives its id only if all are null; an empty table gives an empty table; other columns, also
those named like inner ones, take no part.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sheetgraph.llm._shared import Scratch, map_arrow, prepare, runs_of, texts_of, unused

SIMILARITY = 0.8
#: Words of a shingle, shingles of a sketch, sketches.
FAMILIES = ((5, 3, 16), (3, 3, 64))
#: Words from which a pair's shorter text is found by sketches, and the longest text that pairs with a shorter one.
EXACT = 25
LONGEST_EXACT = int((EXACT - 1) / SIMILARITY + 1e-9)
WORD = re.compile(r"\w+")
WORD_CACHE = 150_000
#: Rounds in which components meet by one node each, before all their nodes do.
STAR_ROUNDS = 2
#: Bins of a word histogram, coarse ones, and rows of a bucket in one block of comparisons.
BINS, COARSE, BLOCK = 256, 32, 256
#: Words up to which many texts are aligned in step; longer ones go one by one along furthest points.
LONG_WORDS = 2_000
#: Texts from which one of a block is compared with them at once, and words whose bits are kept. Either way gives the same distances.
LANES_FROM, LANE_WORDS = 4, 1_000
#: Hashes computed at once.
MATRIX = 500_000

_rng = np.random.default_rng(20_240_607)
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_STEP = _rng.integers(1, 1 << 63, 8, dtype=np.uint64) | np.uint64(1)
_SEEDS = [_rng.integers(1, 1 << 32, n, dtype=np.uint32) for *_, n in FAMILIES]
_FACTORS = [_rng.integers(1, 1 << 32, n, dtype=np.uint32) | np.uint32(1) for *_, n in FAMILIES]


class _WordHashes(dict):
    def __missing__(self, word: str) -> int:
        import xxhash

        self[word] = h = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return h


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


def shingles(ids: np.ndarray, width: int) -> np.ndarray:
    """Occurrence-labelled hashes of the shingles of `width` words, in text order."""
    n = len(ids) - width + 1
    h = np.zeros(n, np.uint64)
    for k in range(width):
        h = (h + ids[k : k + n]) * _STEP[k]
    order = np.argsort(h, kind="stable")
    sorted_ = h[order]
    same = sorted_[1:] == sorted_[:-1]
    if same.any():
        starts = np.r_[True, ~same]
        place = np.arange(n)
        occurrence = place - np.maximum.accumulate(np.where(starts, place, 0))
        label = np.empty(n, np.uint64)
        label[order] = occurrence
        h = h + label * _MIX1
    return _mixed(h)


def smallest(h: np.ndarray, seeds: np.ndarray, factors: np.ndarray, take: int) -> np.ndarray:
    """For each hash function a row of the places, in order, of its `take` smallest hashes."""
    out, low = [], h.astype(np.uint32)
    per = max(1, MATRIX // len(h))
    for k in range(0, len(seeds), per):
        x = (low ^ seeds[k : k + per, None]) * factors[k : k + per, None]
        at = np.empty((len(x), take), np.int64)
        every = np.arange(len(x))
        for j in range(take):
            at[:, j] = x.argmin(axis=1)
            x[every, at[:, j]] = 0xFFFFFFFF
        at.sort(axis=1)
        out.append(at)
    return np.concatenate(out)


def order_sketches(ids: np.ndarray, family: int) -> np.ndarray:
    """For each hash function, a hash of its smallest shingles taken in text order."""
    width, take, count = FAMILIES[family]
    h = shingles(ids, width)
    at = smallest(h, _SEEDS[family], _FACTORS[family], take)
    v = np.full(count, width, np.uint64)
    for j in range(take):
        v = (v + h[at[:, j]]) * _STEP[j]
    return _mixed(v + np.arange(count, dtype=np.uint64))


def _changes(words: int) -> int:
    """Distance up to which a text of so many words links with one that is not longer."""
    return int((1 - SIMILARITY) * words + 1e-9)


def segments(words: int, changes: int) -> list[tuple[int, int]]:
    """Start and length of changes + 1 even segments."""
    ends = [(k + 1) * words // (changes + 1) for k in range(changes + 1)]
    return [(a, b - a) for a, b in zip([0, *ends], ends)]


def exact_keys(ids: np.ndarray) -> np.ndarray:
    """Keys of which any two short texts that link share one: segments of a text, and what may meet those of others.

    With d changes and j segments before one, the segment that stays whole is moved by at most j places
    against its start, and by at most d - j against its end, as later segments have a change each.
    """
    n, out = len(ids), set()

    def add(length: int, changes: int, j: int, start: int, size: int) -> None:
        v = np.uint64(length << 16 | changes << 8 | j)
        for w in ids[start : start + size]:
            v = (v + w) * _STEP[7] ^ (v >> np.uint64(29))
        out.add(int(v))

    with np.errstate(over="ignore"):
        if n < EXACT:
            for changes in {_changes(m) for m in range(n, LONGEST_EXACT + 1) if m - n <= _changes(m)}:
                for j, (start, size) in enumerate(segments(n, changes)):
                    add(n, changes, j, start, size)
        d = _changes(n)
        for length in range(n - d, min(n, EXACT - 1) + 1):
            moved = n - length
            for j, (start, size) in enumerate(segments(length, d)):
                low = max(start - j, start + moved - (d - j), 0)
                high = min(start + j, start + moved + (d - j), n - size)
                for p in range(low, high + 1):
                    add(length, d, j, p, size)
    return _mixed(np.fromiter(out, np.uint64, len(out)))


def keys_of(ids: np.ndarray) -> np.ndarray:
    """All keys of a text; under four words only equal texts link, and there are none."""
    found = [order_sketches(ids, k) for k in range(len(FAMILIES))] if len(ids) >= EXACT else []
    if 4 <= len(ids) <= LONGEST_EXACT:
        found.append(exact_keys(ids))
    return np.unique(np.concatenate(found)) if found else np.zeros(0, np.uint64)


def banded_distance(a: list, b: list, band: int) -> int | None:
    """Edit distance of two sequences if it is at most band, by furthest points on the band's diagonals."""
    n, m = len(a), len(b)
    if abs(n - m) > band:
        return None
    lead = 0
    while lead < n and lead < m and a[lead] == b[lead]:
        lead += 1
    tail = 0
    while tail < min(n, m) - lead and a[n - 1 - tail] == b[m - 1 - tail]:
        tail += 1
    a, b = a[lead : n - tail], b[lead : m - tail]
    n, m = len(a), len(b)
    if not n or not m:
        return max(n, m) if max(n, m) <= band else None
    common = sum((Counter(a) & Counter(b)).values())
    if max(n, m) - common > band:
        return None
    far = {0: 0}
    if n == m == 0:
        return 0
    for e in range(1, band + 1):
        now = {}
        for d in range(max(-e, -m), min(e, n) + 1):
            i = max(far.get(d, -2) + 1, far.get(d - 1, -2) + 1, far.get(d + 1, -2))
            if i < 0 or i < d:
                continue
            i = min(i, n, m + d)
            while i < n and i - d < m and a[i] == b[i - d]:
                i += 1
            now[d] = i
        far = now
        if far.get(n - m, -1) >= n:
            return e
    return None


def similarity(a: list, b: list, least: float = SIMILARITY) -> float | None:
    """Edit similarity where it is at least `least`."""
    longer = max(len(a), len(b))
    if not longer:
        return None
    d = banded_distance(a, b, int((1 - least) * longer + 1e-9))
    return None if d is None else 1 - d / longer


def _keyed(docs: DataFrame, text: str, keys: bool = False, names: tuple[str, str, str] = ("__node", "__check", "__keys"), bits: int = 64) -> DataFrame:
    """docs with __node and __check, 128 bits that stand for the word sequence (null without words), and __keys."""
    columns = docs.columns
    at = columns.index(text)
    added = [*names[: 2 + keys]]

    def make():
        import xxhash

        hashes = _WordHashes()

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            nodes, checks, found = [], [], []
            for some in runs_of(texts_of(batch.column(at))):
                if len(hashes) > WORD_CACHE:
                    hashes.clear()
                for t in some:
                    words = words_of(t)
                    if not words:
                        nodes.append(None)
                        checks.append(None)
                        found.append(None)
                        continue
                    h = xxhash.xxh3_128_intdigest("\x1f".join(words).encode("utf-8", "surrogatepass"))
                    nodes.append((h >> 128 - bits) - (1 << 63))
                    checks.append((h & (1 << 64) - 1) - (1 << 63))
                    if keys:
                        found.append(keys_of(np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))).view(np.int64))
            cols = [*batch.columns, pa.array(nodes, pa.int64()), pa.array(checks, pa.int64())]
            if keys:
                cols.append(pa.array(found, pa.list_(pa.int64())))
            return pa.RecordBatch.from_arrays(cols, names=[*columns, *added])

        return step

    types = [T.LongType(), T.LongType(), T.ArrayType(T.LongType())]
    return map_arrow(docs, make, T.StructType([*docs.schema.fields, *(T.StructField(n, t) for n, t in zip(added, types))]))


def _told_apart(rows: DataFrame, clashes: DataFrame | None, node: str = "__node", check: str = "__check") -> DataFrame:
    """rows without the check; where two word sequences share a node, all but one get another."""
    if clashes is not None:
        least = unused(rows.columns, "__least", "__of")
        rows = rows.join(clashes.toDF(least[1], least[0]), F.col(node) == F.col(least[1]), "left")
        rows = rows.withColumn(node, F.when(F.col(check) > F.col(least[0]), F.xxhash64(node, check)).otherwise(F.col(node))).drop(*least)
    return rows.drop(check)


def _aligned(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) whose texts align."""
    both = pairs.join(texts.select(F.col("__node").alias("a"), F.col("__text").alias("ta")), "a")
    both = both.join(texts.select(F.col("__node").alias("b"), F.col("__text").alias("tb")), "b").select("a", "b", "ta", "tb")

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            keep = [similarity(words_of(x), words_of(y)) is not None for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
            return pa.RecordBatch.from_arrays([c.filter(pa.array(keep)) for c in batch.columns[:2]], names=["a", "b"])

        return step

    return map_arrow(both, make, "a long, b long")


def band_distances(xs: list[np.ndarray], ys: list[np.ndarray], band: int) -> np.ndarray:
    """Edit distances of pairs of texts, all along one band in step; what exceeds the band comes out greater."""
    n, m = (np.array([len(v) for v in side], np.int64) for side in (xs, ys))
    width, longest = 2 * band + 1, int(n.max(initial=0))
    names = np.unique(np.concatenate([*xs, *ys]))
    x = np.zeros((len(xs), longest), np.int32)  # 0 and -1, outside the texts, match nothing
    y = np.full((len(xs), longest + width), -1, np.int32)
    inside = np.abs(n - m) <= band
    for k in np.flatnonzero(inside):
        x[k, : n[k]] = np.searchsorted(names, xs[k]) + 1
        y[k, band : band + m[k]] = np.searchsorted(names, ys[k]) + 1
    far = np.int16(1 << 13)  # above any distance of texts up to LONG_WORDS
    steps = np.arange(width, dtype=np.int16)
    row = np.tile(np.where(steps >= band, steps - band, far).astype(np.int16), (len(xs), 1))
    out = np.where(inside & (n == 0), m, band + 1)
    for i in range(1, longest + 1):
        new = row + (y[:, i - 1 : i - 1 + width] != x[:, i - 1 : i])
        np.minimum(new[:, :-1], row[:, 1:] + 1, out=new[:, :-1])
        if i <= band:  # the empty prefix of the other text
            new[:, : band - i] = far
            new[:, band - i] = i
        row = np.minimum.accumulate(new - steps, axis=1) + steps
        ends = np.flatnonzero(inside & (n == i))
        out[ends] = row[ends, m[ends] - i + band]
    return out


class Lanes:
    """Edit distances of one text to many: a bit for each word of the many, all columns of their tables in one number.

    Each text has a lane of its words and a bit that takes the carry; a step by bits moves all tables on by one
    word, and what vertical steps remain in a lane give its distance.
    """

    def __init__(self, texts: list[np.ndarray]):
        sizes = np.array([len(v) for v in texts], np.int64)
        self.starts = np.cumsum(sizes + 1) - sizes - 1
        self.total = int((sizes + 1).sum())
        words = np.concatenate(texts) if texts else np.zeros(0, np.uint32)
        places = np.arange(len(words)) + np.repeat(np.arange(len(texts)), sizes)
        order = np.argsort(words, kind="stable")
        self.places = places[order]
        self.names, first = np.unique(words[order], return_index=True)
        self.ends = np.append(first, len(words))
        self.known: dict[int, int] = {}
        self.low, self.inside = self._number(self.starts[sizes > 0]), self._number(places)

    def _number(self, places: np.ndarray) -> int:
        bits = np.zeros(self.total, np.uint8)
        bits[places] = 1
        return int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")

    def _of(self, word: int) -> int:
        found = self.known.get(word)
        if found is None:
            at = int(np.searchsorted(self.names, word))
            there = at < len(self.names) and self.names[at] == word
            if len(self.known) >= LANE_WORDS:
                self.known.clear()
            found = self.known[word] = self._number(self.places[self.ends[at] : self.ends[at + 1]]) if there else 0
        return found

    def distances(self, text: np.ndarray) -> np.ndarray:
        inside, low = self.inside, self.low
        more, less = inside, 0
        for word in text.tolist():
            same = self._of(word)
            diagonal = ((((same & more) + more) ^ more) | same | less) & inside
            right = ((less | inside ^ (diagonal | more)) << 1) & inside | low
            more, less = ((diagonal & more) << 1) & inside | inside ^ (diagonal | right), right & diagonal
        size = self.total + 7 >> 3
        steps = (np.unpackbits(np.frombuffer(x.to_bytes(size, "little"), np.uint8), bitorder="little")[: self.total].astype(np.int64) for x in (more, less))
        up, down = steps
        return len(text) + np.add.reduceat(up - down, self.starts) if self.total else np.zeros(0, np.int64)


def linked(xs: list[np.ndarray], ys: list[np.ndarray]) -> np.ndarray:
    """Whether each pair has enough edit similarity."""
    out = np.zeros(len(xs), bool)
    longer = np.array([max(len(a), len(b)) for a, b in zip(xs, ys)], np.int64)
    most = ((1 - SIMILARITY) * longer + 1e-9).astype(np.int64)
    order = np.argsort(longer, kind="stable")
    start = 0
    while start < len(order):
        size = max(1, min(1_024, 4_000_000 // max(1, int(longer[order[start]]) + 1)))
        part = order[start : start + size]
        start += size
        if longer[part].max() > LONG_WORDS:
            for k in part:
                out[k] = similarity(xs[k].tolist(), ys[k].tolist()) is not None
        else:
            out[part] = band_distances([xs[k] for k in part], [ys[k] for k in part], int(most[part].max())) <= most[part]
    return out


def _near(k: int, may: np.ndarray, n: np.ndarray, bins: np.ndarray, coarse: np.ndarray) -> np.ndarray:
    """Those of may whose texts bounds on the distance do not rule out: lengths, then histograms of words."""
    most = ((1 - SIMILARITY) * np.maximum(n[may], n[k]) + 1e-9).astype(np.int64)
    near = np.abs(n[may] - n[k]) <= most
    for table in (coarse, bins):
        may, most = may[near], most[near]
        near = np.abs(table[may] - table[k]).sum(axis=1, dtype=np.int64) <= 2 * most
    return may[near]


def _signed(texts: DataFrame) -> DataFrame:
    """node, n, bins, ids: of each text its words' number, a histogram of up to 255 in a bin, and the words in 32 bits each."""

    def make():
        hashes = _WordHashes()

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            counts, bins, ids = [], [], []
            for t in batch.column(1).to_pylist():
                words = words_of(t)
                v = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words)).astype(np.uint32)
                counts.append(len(v))
                bins.append(np.minimum(np.bincount((v % np.uint32(BINS)).astype(np.int64), minlength=BINS), 255).astype(np.uint8).tobytes())
                ids.append(v.tobytes())
                if len(hashes) > WORD_CACHE:
                    hashes.clear()
            cols = [batch.column(0), pa.array(counts, pa.int64()), pa.array(bins, pa.binary()), pa.array(ids, pa.large_binary()).cast(pa.binary())]
            return pa.RecordBatch.from_arrays(cols, names=["node", "n", "bins", "ids"])

        return step

    return map_arrow(texts.select("__node", "__text"), make, "node long, n long, bins binary, ids binary")


def _late_links(open_: DataFrame, texts: DataFrame, scratch: Scratch) -> DataFrame:
    """Links (a, b) between the components that share a bucket: one for each two, if there is any.

    open_: h, node, label, main. Nodes outside a bucket's main component meet all others, in blocks. A bucket
    is split by the lengths of texts first: those that link are of one level of lengths or of two neighbours, so
    a node goes to its own level and to the one below. The difference in length, and half that of two word
    histograms, is at most the edit distance; a first pass carries these alone and leaves the rows that
    have a partner in their block, a second one aligns them: rows come out for nodes and links, not for pairs.
    Two nodes that share several buckets meet in that of their smallest common key. A word goes in 32
    bits, which can only make texts seem nearer, so the caller aligns the links found by their words.
    """
    open_ = scratch.keep(open_)
    some = texts.join(open_.select(F.col("node").alias("__node")).distinct(), "__node", "left_semi")
    shared = open_.groupBy("node").agg(F.collect_set("h").alias("keys"))  # of the buckets that are open, not all
    signed = scratch.keep(_signed(some).join(shared, "node"))
    # a little more than the ratio of lengths that links allow, so that rounding does not part them
    level = F.floor(F.log("n") / math.log(1.01 / SIMILARITY))
    placed = open_.join(signed.select("node", level.alias("level")), "node")
    placed = placed.select("h", "node", "label", "main", "level", F.explode(F.array(F.col("level"), F.col("level") - 1)).alias("c"))
    placed = placed.withColumn("low", F.col("level") == F.col("c")).drop("level")
    minor = F.count_if(F.col("label") != F.col("main"))
    sizes = placed.groupBy("h", "c").agg(F.ceil(F.count(F.lit(1)) / BLOCK).alias("blocks"), F.ceil(minor / BLOCK).alias("minor_blocks"), F.bool_or("low").alias("any"), F.min("label").alias("la"), F.max("label").alias("lb"))
    sizes = sizes.where("any and la < lb").drop("any", "la", "lb")
    placed = scratch.keep(placed.join(sizes, ["h", "c"]))
    rows = placed.join(signed.select("node", "n", "bins"), "node")
    columns = ["h", "c", "node", "label", "main", "low", "n", "bins"]
    own, own_minor = (F.pmod(F.xxhash64("node"), name) for name in ("blocks", "minor_blocks"))
    x = rows.where("label != main").select(*columns, F.lit(True).alias("asks"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("i"), own_minor.alias("j"))
    y = rows.select(*columns, F.lit(False).alias("asks"), own.alias("i"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("minor_blocks") - 1)).alias("j"))

    def pairs(table: pa.Table, n: np.ndarray, bins: np.ndarray):
        """Each row that asks, and the others that may link with it."""
        asks, low = table["asks"].to_numpy(), table["low"].to_numpy()
        node, label = table["node"].to_numpy(), table["label"].to_numpy()
        minor = label != table["main"].to_numpy()
        coarse = bins.reshape(len(n), COARSE, -1).sum(axis=2, dtype=np.int32)
        others = np.flatnonzero(~asks)
        for k in np.flatnonzero(asks):
            may = others[(label[others] != label[k]) & (low[others] | low[k]) & ~(minor[others] & (node[others] > node[k]))]
            yield k, _near(k, may, n, bins, coarse)

    def partnered(table: pa.Table) -> pa.Table:
        bins = np.frombuffer(b"".join(table["bins"].to_pylist()), np.uint8).reshape(-1, BINS).astype(np.int16)
        stays = np.zeros(len(bins), bool)
        for k, may in pairs(table, table["n"].to_numpy(), bins):
            if len(may):
                stays[k] = stays[may] = True
        return table.drop_columns(["n", "bins"]).filter(pa.array(stays))

    def aligned(table: pa.Table) -> pa.Table:
        node, label = table["node"].to_numpy(), table["label"].to_numpy()
        ids = [np.frombuffer(b, np.uint32) for b in table["ids"].to_pylist()]
        bins = np.stack([np.bincount((v % np.uint32(BINS)).astype(np.int64), minlength=BINS).astype(np.int32) for v in ids])
        keys = [frozenset(x) for x in table["keys"].to_pylist()]
        h, left, right, hits = table["h"][0].as_py(), [], [], []
        n = np.array([len(v) for v in ids])
        inside = [k for k in np.flatnonzero(~table["asks"].to_numpy()).tolist() if n[k] <= LONG_WORDS]
        all_lanes = None
        for k, may in pairs(table, n, bins):
            here = [x for x in may.tolist() if min(keys[x] & keys[k]) == h]
            beside = [x for x in here if n[x] <= LONG_WORDS] if n[k] <= LONG_WORDS else []
            if len(beside) >= LANES_FROM:
                if 2 * len(beside) > len(inside):
                    all_lanes = all_lanes or Lanes([ids[x] for x in inside])
                    far = dict(zip(inside, all_lanes.distances(ids[k]).tolist()))
                else:
                    far = dict(zip(beside, Lanes([ids[x] for x in beside]).distances(ids[k]).tolist()))
                hits += [(k, x) for x in beside if far[x] <= int((1 - SIMILARITY) * max(n[x], n[k]) + 1e-9)]
                here = [x for x in here if x not in far]
            left += [k] * len(here)
            right += here
        near = linked([ids[k] for k in left], [ids[k] for k in right])
        hits += [(left[k], right[k]) for k in np.flatnonzero(near)]
        found = {(k, label[x]): (int(node[k]), int(node[x])) for k, x in hits}
        out = list(found.values())
        a, b = zip(*out) if out else ((), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    # a stated number of partitions: the blocks are small in bytes but not in work
    parts = int(open_.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    at = ["h", "c", "i", "j"]
    left_over = "h long, c long, node long, label long, main long, low boolean, asks boolean, i long, j long"
    met = scratch.keep(x.unionByName(y).repartition(parts, *at).groupBy(*at).applyInArrow(partnered, left_over))
    blocks = met.join(signed.select("node", "ids", "keys"), "node").repartition(parts, *at)
    return scratch.keep(blocks.groupBy(*at).applyInArrow(aligned, "a long, b long").distinct())


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """node, label (the smallest node of its component) for every node of the edges (a, b)."""
    both = scratch.keep(edges.union(edges.select("b", "a")).toDF("node", "other").distinct())
    labels = scratch.keep(both.groupBy("node").agg(F.least(F.col("node"), F.min("other")).alias("label")))
    while True:
        # a label moves along edges, then every node takes its label's label
        seen = both.join(labels.select(F.col("node").alias("other"), F.col("label").alias("near")), "other")
        best = seen.groupBy("node").agg(F.min("near").alias("near")).join(labels, "node").select("node", F.least("near", "label").alias("label"), F.col("label").alias("old"))
        jump = labels.select(F.col("node").alias("label"), F.col("label").alias("next"))
        new = best.join(jump, "label", "left").select("node", F.least("label", F.coalesce("next", "label")).alias("label"), "old")
        new = scratch.keep(new)
        moved = new.where(F.col("label") != F.col("old")).limit(1).count()
        scratch.drop(labels)
        labels = new
        if not moved:
            return labels.select("node", "label")


def _merged(labels: DataFrame, edges: DataFrame, scratch: Scratch) -> DataFrame:
    """labels with the components that the edges join made one; works on the joined components alone."""
    at = {c: labels.select(F.col("node").alias(c), F.col("label").alias(f"l{c}")) for c in "ab"}
    between = edges.join(at["a"], "a").join(at["b"], "b").where("la != lb").select(F.col("la").alias("a"), F.col("lb").alias("b")).distinct()
    joined = components(scratch.keep(between), scratch).select(F.col("node").alias("label"), F.col("label").alias("root"))
    return scratch.keep(labels.join(joined, "label", "left").select("node", F.coalesce("root", "label").alias("label")))


def links(docs: DataFrame, scratch: Scratch, key: str = "doc_id", text: str = "text", bits: int = 64) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """(rows: doc_id and __node of every document; labels: node and label of every node that has a link; clashes).

    clashes: node and least check of different word sequences that share a node's 64 bits, None if there are none.
    """
    prepare(docs.sparkSession)
    docs = docs.select(F.col(f"`{key}`").alias("doc_id"), F.col(f"`{text}`").alias("__text"))
    rows = scratch.keep(_keyed(docs, "__text", True, bits=bits).drop("__text"))
    shared = rows.where(F.col("__node").isNotNull()).groupBy("__node").agg(F.min("__check").alias("least"), F.max("__check").alias("most"))
    clashes = scratch.keep(shared.where("least < most").select("__node", "least"))
    if not clashes.limit(1).count():
        clashes = None
    rows = _told_apart(rows, clashes)
    nodes = rows.where(F.col("__node").isNotNull()).groupBy("__node").agg(F.first("__keys").alias("__keys"))
    bands = nodes.select(F.col("__node").alias("node"), F.explode("__keys").alias("h"))
    full = bands.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("rep")).where("n > 1").drop("n")
    members = scratch.keep(bands.join(full, "h"))
    texts = _told_apart(_keyed(docs, "__text", bits=bits).drop("doc_id"), clashes).join(members.select(F.col("node").alias("__node")).distinct(), "__node")
    texts = scratch.keep(texts.groupBy("__node").agg(F.first("__text").alias("__text")))
    labels = scratch.keep(members.select("node", F.col("node").alias("label")).distinct())
    first = members.groupBy("node").agg(F.min("rep").alias("b")).where("b < node").select(F.col("node").alias("a"), "b")
    tried = scratch.keep(first)
    labels = _merged(labels, _aligned(tried, texts), scratch)
    for k in range(STAR_ROUNDS + 1):
        # buckets whose nodes are in several components yet: all others meet the largest one
        placed = scratch.keep(members.select("h", "node").join(labels, "node"))
        sizes = placed.groupBy("h", "label").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("head"))
        main = sizes.groupBy("h").agg(F.count(F.lit(1)).alias("kinds"), F.max(F.struct("n", "label", "head")).alias("top")).where("kinds > 1")
        main = main.select("h", F.col("top.label").alias("main"), F.col("top.head").alias("main_head"))
        if k < STAR_ROUNDS:  # by one node of each, and one pair of nodes for two components
            heads = sizes.join(main, "h").where("label != main").select("label", "main", F.least("head", "main_head").alias("b"), F.greatest("head", "main_head").alias("a"))
            pairs = heads.select("a", "b", "label", "main").join(tried, ["a", "b"], "left_anti")
            pairs = pairs.groupBy("label", "main").agg(F.min(F.struct("a", "b")).alias("x")).select("x.a", "x.b").distinct()
        else:  # by all nodes, so that no link between components is lost
            late = _late_links(placed.join(main.select("h", "main"), "h"), texts, scratch)
            labels = _merged(labels, _aligned(late, texts), scratch)
            break
        pairs = scratch.keep(pairs)
        if not pairs.limit(1).count():
            continue
        labels = _merged(labels, _aligned(pairs, texts), scratch)
        tried = scratch.keep(tried.union(pairs))
    scratch.drop(members, texts)
    return rows.select("doc_id", "__node"), labels.where("node != label").union(labels.where("node != label").select("label", "label").distinct()), clashes


def _classed(docs: DataFrame, scratch: Scratch, key: str, text: str, bits: int = 64) -> tuple[DataFrame, DataFrame | None]:
    """(doc_id, __node and label of the class for every document, clashes of nodes)."""
    rows, labels, clashes = links(docs, scratch, key, text, bits)
    rows = rows.withColumn("own", F.when(F.col("__node").isNull(), F.concat(F.lit("id "), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))).otherwise(F.col("__node").cast("string")))
    labels = labels.select(F.col("node").alias("__node"), F.col("label").cast("string").alias("label"))
    return scratch.keep(rows.join(labels, "__node", "left").select("doc_id", "__node", F.coalesce("label", "own").alias("label"))), clashes


def classes(docs: DataFrame, scratch: Scratch, key: str = "doc_id", text: str = "text", bits: int = 64) -> DataFrame:
    """doc_id, class_id (smallest doc_id of the class), class_size for every document."""
    rows, _ = _classed(docs, scratch, key, text, bits)
    sizes = rows.groupBy("label").agg(F.min("doc_id").alias("class_id"), F.count(F.lit(1)).alias("class_size"))
    return rows.join(sizes, "label").select("doc_id", "class_id", "class_size")


def keep_first(docs: DataFrame, scratch: Scratch, key: str = "doc_id", text: str = "text") -> DataFrame:
    """All columns of the one row of each class that has the smallest identifier."""
    found, clashes = _classed(docs, scratch, key, text)
    rows = found.groupBy("label", "doc_id", "__node").agg(F.count(F.lit(1)).alias("n"))
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "__node")
    first = rows.groupBy("label").agg(F.min(order).alias("first"), F.sum("n").alias("size")).where("size > 1")
    stays = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & F.col("__node").eqNullSafe(F.col("first.__node"))
    node, check, id_, of, gone, n = unused(docs.columns, "__node", "__check", "__id", "__of", "__gone", "__n")
    marks = rows.join(first, "label").select(F.col("doc_id").alias(id_), F.col("__node").alias(of), (~stays).alias(gone), F.col("n").alias(n))
    marks = scratch.keep(marks.where(F.col(gone) | (F.col(n) > 1)))
    keyed = _told_apart(_keyed(docs, text, names=(node, check, "")), clashes, node, check)
    kept = keyed.join(marks, F.col(node).eqNullSafe(F.col(of)) & F.col(f"`{key}`").eqNullSafe(F.col(id_)), "left").where(~F.coalesce(F.col(gone), F.lit(False)))
    columns = [F.col(f"`{c}`") for c in docs.columns]
    if not marks.where(~F.col(gone)).limit(1).count():
        return kept.select(*columns)
    # several rows with one identifier and one word sequence are one row of the class
    once, again = kept.where(F.col(n).isNull() | (F.col(n) == 1)), kept.where(F.col(n) > 1)
    return once.select(*columns).unionByName(again.dropDuplicates([key, node]).select(*columns))
