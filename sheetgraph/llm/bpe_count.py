"""Token counts by rank-synchronous array merging of a sentencepiece BPE vocabulary.

Pre-tokens (a run of word marks and what follows it; no piece crosses such a boundary) are held as ragged
numpy arrays: one flat array of symbol ids and one of sequence numbers. Each round looks up the rank of
every neighbouring pair in a sorted table, finds each sequence's lowest rank, merges its leftmost pair of
that rank in all sequences at once, and compacts the arrays. Sequences without a pair leave; what is left
is counted, a symbol outside the vocabulary as one token per UTF-8 byte.

Ranks: the pair (a, b) may merge if its joined text is a piece; lower piece ids merge first, as their
scores are higher. Merging one leftmost pair a round is the library's own order, so counts are equal.

A worker keeps counts of recent pre-tokens, up to CACHE_ENTRIES, and forgets them all beyond that.
Defined results: null or empty text has no token; equal texts equal counts; an empty table stays empty;
other columns are ignored.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from sheetgraph.llm._shared import map_arrow, prepare, runs_of, texts_of

MARK = "▁"
CACHE_ENTRIES = 500_000
#: Symbols merged in one array at a time; bounds memory whatever a batch holds.
CHUNK_SYMBOLS = 2_000_000
#: Longer pre-tokens merge by a heap-free linked scan of their own, see long_count.
LONG_SYMBOLS = 4_096
UNIT = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"


class PieceTable:
    """The vocabulary as arrays: characters, and the merged piece of each pair of pieces."""

    def __init__(self, model_path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
        size = sp.get_piece_size()
        special = [sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) for i in range(size)]
        self.pieces = {sp.id_to_piece(i): i for i in range(size) if not special[i]}
        score = np.array([sp.get_score(i) for i in range(size)])
        # equal scores share a rank, so that only the place decides between them
        ranks = np.unique(-score, return_inverse=True)[1]
        keys, to, rank = [], [], []
        for piece, i in self.pieces.items():
            for cut in range(1, len(piece)):
                a, b = self.pieces.get(piece[:cut]), self.pieces.get(piece[cut:])
                if a is not None and b is not None:
                    keys.append(a << 32 | b)
                    to.append(i)
                    rank.append(int(ranks[i]))
        # a character outside the vocabulary may still be part of no merge, so pieces alone make keys
        order = np.argsort(np.array(keys, dtype=np.int64))
        self.keys = np.array(keys, dtype=np.int64)[order]
        self.to = np.array(to, dtype=np.int64)[order]
        self.rank = np.array(rank, dtype=np.int64)[order]
        self.char = {p: i for p, i in self.pieces.items() if len(p) == 1}
        self.pair = {int(k): (int(r), int(t)) for k, r, t in zip(self.keys, self.rank, self.to)}

    def symbols(self, word: str) -> list[int]:
        """Ids of the characters; -n for one outside the vocabulary with n bytes in UTF-8."""
        get = self.char.get
        return [get(c) if c in self.char else -len(c.encode("utf-8", "surrogatepass")) for c in word]

    def look_up(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and merged id of each pair; rank 2**62 for a pair that doesn't merge."""
        key = (left << 32) | (right & 0xFFFFFFFF)
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = (self.keys[at] == key) & (left >= 0) & (right >= 0)
        return np.where(hit, self.rank[at], 1 << 62), self.to[at]


def merged_counts(table: PieceTable, words: list[str]) -> np.ndarray:
    """Tokens of each word, all merged in step."""
    out = np.zeros(len(words), dtype=np.int64)
    start = 0
    while start < len(words):
        end, total = start, 0
        while end < len(words) and (end == start or total + len(words[end]) <= CHUNK_SYMBOLS):
            total += len(words[end])
            end += 1
        out[start:end] = _merge_chunk(table, words[start:end])
        start = end
    return out


def _merge_chunk(table: PieceTable, words: list[str]) -> np.ndarray:
    counts = np.zeros(len(words), dtype=np.int64)
    short = [k for k, w in enumerate(words) if len(w) <= LONG_SYMBOLS]
    for k, w in enumerate(words):
        if len(w) > LONG_SYMBOLS:
            counts[k] = long_count(table, w)
    flat: list[int] = []
    lengths = []
    for k in short:
        flat += table.symbols(words[k])
        lengths.append(len(words[k]))
    sym = np.array(flat, dtype=np.int64)
    seq = np.repeat(np.array(short, dtype=np.int64), np.array(lengths, dtype=np.int64))
    while len(sym) > 1:
        rank, to = table.look_up(sym[:-1], sym[1:])
        rank[seq[:-1] != seq[1:]] = 1 << 62
        # per sequence: lowest rank, then leftmost place, as one minimum over rank and place
        order = np.where(rank < 1 << 62, (rank << 24) | np.arange(len(rank)), 1 << 62)
        heads = np.flatnonzero(np.r_[True, seq[1:-1] != seq[:-2]]) if len(order) > 1 else np.array([0])
        best = np.minimum.reduceat(order, heads)
        best = best[best < 1 << 62]
        if not len(best):
            break
        at = best & ((1 << 24) - 1)
        sym[at] = to[at]
        keep = np.ones(len(sym), dtype=bool)
        keep[at + 1] = False
        # sequences that merged nothing in this round are done: count them and let them go
        busy = np.zeros(len(words), dtype=bool)
        busy[seq[at]] = True
        done = keep & ~busy[seq]
        _add(counts, seq[done], sym[done])
        keep &= busy[seq]
        sym, seq = sym[keep], seq[keep]
    _add(counts, seq, sym)
    return counts


def _add(counts: np.ndarray, seq: np.ndarray, sym: np.ndarray) -> None:
    counts += np.bincount(seq, weights=np.where(sym < 0, -sym, 1), minlength=len(counts)).astype(np.int64)


def long_count(table: PieceTable, word: str) -> int:
    """The same order of merges for one very long pre-token, by a heap over a linked list."""
    import heapq

    sym = table.symbols(word)
    n = len(sym)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    pair = table.pair
    heap = []

    def offer(a: int, b: int) -> None:
        if sym[a] >= 0 and sym[b] >= 0 and (hit := pair.get(sym[a] << 32 | sym[b])):
            heapq.heappush(heap, (hit[0], a, sym[a], sym[b], hit[1]))

    for i in range(n - 1):
        offer(i, i + 1)
    gone = [False] * n
    while heap:
        _, a, x, y, to = heapq.heappop(heap)
        b = after[a] if not gone[a] else n
        if b >= n or sym[a] != x or sym[b] != y:
            continue
        sym[a], gone[b] = to, True
        after[a] = after[b]
        if after[b] < n:
            before[after[b]] = a
            offer(a, after[a])
        if before[a] >= 0:
            offer(before[a], a)
    return sum(-s if s < 0 else 1 for s, g in zip(sym, gone) if not g)


_tables: dict[str, tuple[PieceTable, dict[str, int]]] = {}


def worker_state(model_path: str) -> tuple[PieceTable, dict[str, int]]:
    if model_path not in _tables:
        _tables[model_path] = (PieceTable(model_path), {})
    return _tables[model_path]


def units(text: str) -> list[str]:
    """Pre-tokens of a text: the library's own spelling of spaces, cut where no piece can cross."""
    if not text:
        return []
    if MARK in text or "  " in text or text[-1] == " " or text[0] == " ":
        return UNIT.findall(MARK + text.replace(" ", MARK))
    return text.split(" ")  # the usual case: single spaces, each unit has one mark in front of it


def count_tokens(docs: DataFrame, model_path: str, limit: int = 4096, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit) for every text."""
    prepare(docs.sparkSession)

    def make():
        table, cache = worker_state(model_path)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = texts_of(batch.column(1))
            n_tokens: list[int] = []
            for some in runs_of(texts):
                # a unit of single-spaced text goes without its mark, also as the cache's key
                lists = [units(t) for t in some]
                if len(cache) > CACHE_ENTRIES:
                    cache.clear()
                new = set()
                for u in lists:
                    new.update(u)
                new = [w for w in new if w not in cache]
                spelled = [w if w[:1] == MARK else MARK + w for w in new]
                cache.update(zip(new, merged_counts(table, spelled).tolist()))
                get = cache.__getitem__
                n_tokens += [sum(map(get, u)) for u in lists]
            n_bytes = [len(t.encode("utf-8", "surrogatepass")) for t in texts]
            return pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens], pa.bool_())],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

        return step

    return map_arrow(docs.select(docs[key].alias("doc_id"), docs[text].alias("text")), make, SCHEMA)
