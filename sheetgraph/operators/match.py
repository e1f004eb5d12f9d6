"""Matching of actual and expected statements, cell by cell, and grading.

The statements of a cell leave one row resource, so a cell's graph is a star. A match maps resources of the
actual graph to resources of the expected one, each to at most one and at most one to each; the best match
makes the greatest number of mapped statements meet expected ones, then maps the most resources, then
leaves the most names as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import permutations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sheetgraph.session import prepare

CELL = ("sheet_id", "row_id", "col")


class Match:
    """An injective partial map of resources, grown one statement pair at a time."""

    def __init__(self):
        self.forth: dict[str, str] = {}
        self.back: dict[str, str] = {}

    def fits(self, a: tuple, e: tuple) -> list[tuple[str, str]] | None:
        """The pairs that two statements add, or None where they clash with the match or in kind."""
        if (a[2] == "iri") != (e[2] == "iri"):
            return None
        pairs = [(a[0], e[0])] + ([(a[1], e[1])] if a[2] == "iri" else [])
        if a[2] != "iri" and a[1:] != e[1:]:
            return None
        new: dict[str, str] = {}
        taken: dict[str, str] = {}
        for x, y in pairs:
            if self.forth.get(x, new.get(x, y)) != y or self.back.get(y, taken.get(y, x)) != x:
                return None
            if x not in self.forth:
                new[x], taken[y] = y, x
        return list(new.items())

    def add(self, pairs: list[tuple[str, str]]) -> None:
        for x, y in pairs:
            self.forth[x], self.back[y] = y, x

    def remove(self, pairs: list[tuple[str, str]]) -> None:
        for x, y in pairs:
            del self.forth[x], self.back[y]


def distance(a: tuple, e: tuple, match: Match, d: int = 1) -> int:
    """0, and the match grows, where the statements agree under it; d else. Statements: (p, o, kind, datatype)."""
    pairs = match.fits(a, e)
    if pairs is None:
        return d
    match.add(pairs)
    return 0


def identity(actual: list[tuple], expected: list[tuple]) -> int:
    """Statements that are equal as they stand."""
    return len(set(actual) & set(expected))


def greedy(actual: list[tuple], expected: list[tuple], literal_first: bool = True, threshold: int | None = None, objective: str = "overlap") -> tuple[int, dict[str, str], int]:
    """Best overlap, its map and the number of pairings tried, by permuting the longer list against the shorter.

    literal_first: literal pairs are tried first, as they clash soonest. threshold: pairings with more
    clashes are given up; without it, those that can't reach the best overlap so far.
    """
    swap = len(actual) < len(expected)
    a, e = (expected, actual) if swap else (actual, expected)
    if literal_first:
        a, e = (sorted(x, key=lambda s: s[2] == "iri") for x in (a, e))
    best: tuple = (-1, -1, -1)
    best_map: dict[str, str] = {}
    visits = 0
    match, used = Match(), [False] * len(a)

    def key(overlap: int) -> tuple:
        same = sum(x == y for x, y in match.forth.items())
        return (overlap, len(match.forth), same) if objective == "overlap" else (len(match.forth), same, overlap)

    def go(k: int, overlap: int, clashes: int) -> None:
        nonlocal best, best_map, visits
        if k == len(e):
            if key(overlap) > best:
                best, best_map = key(overlap), dict(match.forth)
            return
        if threshold is None and objective == "overlap" and overlap + len(e) - k < best[0]:
            return
        for i in range(len(a)):
            if used[i]:
                continue
            visits += 1
            pairs = match.fits(a[i], e[k])
            if pairs is None:
                continue
            used[i] = True
            match.add(pairs)
            go(k + 1, overlap + 1, clashes)
            match.remove(pairs)
            used[i] = False
        if threshold is None or clashes + 1 <= threshold:  # this one stays without a partner
            go(k + 1, overlap, clashes + 1)

    go(0, 0, 0)
    overlap = best[0] if objective == "overlap" else best[2]
    return max(overlap, 0), {y: x for x, y in best_map.items()} if swap else best_map, visits


def star(actual: list[tuple], expected: list[tuple]) -> int:
    """The same overlap for stars, by an assignment of predicates; exact where no resource has two predicates."""

    def by_predicate(x: list[tuple]) -> dict[str, tuple[set, set]]:
        out: dict[str, tuple[set, set]] = {}
        for p, o, kind, datatype in set(x):
            out.setdefault(p, (set(), set()))[kind == "iri"].add((o, datatype))
        return out

    a, e = by_predicate(actual), by_predicate(expected)
    gain = [[len(x[0] & y[0]) + min(len(x[1]), len(y[1])) for y in e.values()] for x in a.values()]
    return _assignment(gain)


def shares_resources(graph: list[tuple]) -> bool:
    """Whether a resource stands under two predicates, which the star matcher can't see."""
    under: dict[str, str] = {}
    return any(kind == "iri" and under.setdefault(o, p) != p for p, o, kind, _ in graph)


def best_overlap(actual: list[tuple], expected: list[tuple]) -> int:
    """Exact at any size: by assignment where no resource has two predicates, by search else."""
    return greedy(actual, expected)[0] if shares_resources(actual) or shares_resources(expected) else star(actual, expected)


def _assignment(gain: list[list[int]]) -> int:
    """Greatest sum of a one-to-one choice of rows and columns, by shortest augmenting paths."""
    if not gain or not gain[0]:
        return 0
    n = max(len(gain), len(gain[0]))
    cost = [[-(gain[i][j] if i < len(gain) and j < len(gain[0]) else 0) for j in range(n)] for i in range(n)]
    inf = float("inf")
    u, v, at = [0.0] * (n + 1), [0.0] * (n + 1), [0] * (n + 1)
    for i in range(1, n + 1):
        at[0], j0 = i, 0
        low, seen, way = [inf] * (n + 1), [False] * (n + 1), [0] * (n + 1)
        while True:
            seen[j0], i0, step, j1 = True, at[j0], inf, 0
            for j in range(1, n + 1):
                if not seen[j]:
                    now = cost[i0 - 1][j - 1] - u[i0] - v[j]
                    if now < low[j]:
                        low[j], way[j] = now, j0
                    if low[j] < step:
                        step, j1 = low[j], j
            for j in range(n + 1):
                if seen[j]:
                    u[at[j]] += step
                    v[j] -= step
                else:
                    low[j] -= step
            j0 = j1
            if at[j0] == 0:
                break
        while j0:
            at[j0], j0 = at[way[j0]], way[j0]
    return -sum(cost[at[j] - 1][j - 1] for j in range(1, n + 1))


def brute_force(actual: list[tuple], expected: list[tuple]) -> int:
    """Greatest overlap over all injective maps of predicates and of objects; for tests on small graphs."""
    pa_, pe = sorted({x[0] for x in actual}), sorted({x[0] for x in expected})
    oa, oe = (sorted({x[1] for x in g if x[2] == "iri"}) for g in (actual, expected))

    def maps(x: list, y: list):
        pad = y + [None] * len(x)
        for p in set(permutations(pad, len(x))):
            yield dict(zip(x, p))

    goal, best = set(expected), 0
    for mp in maps(pa_, pe):
        for mo in maps(oa, oe):
            got = {(mp[p], mo[o] if k == "iri" else o, k, d) for p, o, k, d in actual}
            best = max(best, len(got & goal))
    return best


def _sides(actual: DataFrame, expected: DataFrame) -> DataFrame:
    """A row for each cell with the statements of either side as arrays."""
    one = F.struct("p", "o", "o_kind", F.coalesce("o_datatype", F.lit("")).alias("o_datatype"))
    both = actual.select(*CELL, one.alias("one"), F.lit(True).alias("ours")).unionByName(expected.select(*CELL, one.alias("one"), F.lit(False).alias("ours")))
    sides = [F.sort_array(F.collect_set(F.when(F.col("ours") == x, F.col("one")))).alias(name) for name, x in (("a", True), ("e", False))]
    return both.groupBy(*CELL).agg(*sides)  # one shuffle, and no join


def match_cells(actual: DataFrame, expected: DataFrame, method: str = "auto") -> DataFrame:
    """tp, fp, fn of each cell. auto: closed form where each side has one predicate, search for the rest."""
    sides = _sides(actual, expected)
    if method == "identity":
        tp = F.size(F.array_intersect("a", "e"))
        return sides.select(*CELL, tp.alias("tp"), (F.size("a") - tp).alias("fp"), (F.size("e") - tp).alias("fn"))

    def literals(side: str):
        return F.transform(F.filter(side, lambda x: x["o_kind"] != "iri"), lambda x: F.struct(x["o"], x["o_datatype"]))

    def iris(side: str):
        return F.size(F.filter(side, lambda x: x["o_kind"] == "iri"))

    def single(side: str):
        return F.size(F.array_distinct(F.transform(side, lambda x: x["p"]))) <= 1

    closed = single("a") & single("e")
    tp = F.size(F.array_intersect(literals("a"), literals("e"))) + F.least(iris("a"), iris("e"))
    easy = sides.where(closed).select(*CELL, tp.alias("tp"), F.size("a").alias("na"), F.size("e").alias("ne"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                a, e = ([tuple(x.values()) for x in r[k]] for k in "ae")
                tp = greedy(a, e)[0] if method == "greedy" else star(a, e) if method == "star" else best_overlap(a, e)
                out.append((*(r[k] for k in CELL), tp, len(a), len(e)))
            cols = list(zip(*out)) if out else [()] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if k < 3 else pa.int32()) for k, c in enumerate(cols)], names=[*CELL, "tp", "na", "ne"])

    prepare(actual.sparkSession)
    hard = (sides if method in ("greedy", "star") else sides.where(~closed)).mapInArrow(run, "sheet_id string, row_id string, col string, tp int, na int, ne int")
    all_ = hard if method in ("greedy", "star") else easy.unionByName(hard)
    return all_.select(*CELL, "tp", (F.col("na") - F.col("tp")).alias("fp"), (F.col("ne") - F.col("tp")).alias("fn"))


def ratios(sums: DataFrame) -> DataFrame:
    """precision, recall and f from sums of tp, fp, fn; 0 where undefined."""

    def share(x, y):
        return F.round(F.coalesce(F.try_divide(x.cast("double"), y.cast("double")), F.lit(0.0)), 6)

    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return sums.withColumn("precision", share(tp, tp + fp)).withColumn("recall", share(tp, tp + fn)).withColumn("f", share(2 * tp, 2 * tp + fp + fn))


def grade(actual: DataFrame, expected: DataFrame, method: str = "auto", by: tuple[str, ...] = ("sheet_id",)) -> DataFrame:
    cells = match_cells(actual, expected, method)
    return ratios(cells.groupBy(*by).agg(*[F.sum(c).cast("long").alias(c) for c in ("tp", "fp", "fn")]))


def sheet_scope(actual: DataFrame, expected: DataFrame) -> DataFrame:
    """Stricter: an actual property maps to one expected property in the whole sheet, the one most cells vote for."""
    a = actual.select(*CELL, F.col("p").alias("pa")).distinct()
    e = expected.select(*CELL, F.col("p").alias("pe")).distinct()
    votes = a.join(e, list(CELL)).groupBy("sheet_id", "pa", "pe").agg(F.count(F.lit(1)).alias("n"))
    best = votes.groupBy("sheet_id", "pa").agg(F.max_by("pe", F.struct("n", "pe")).alias("pe")).toDF("voted_sheet", "pa", "pe")
    named = actual.join(best, (F.col("sheet_id") == F.col("voted_sheet")) & (F.col("p") == F.col("pa")), "left").withColumn("p", F.coalesce("pe", "p"))
    renamed = named.select(*actual.columns)
    return grade(renamed, expected, "auto")


def summary(graded: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """Mean and both standard deviations of the ratios."""
    cols = []
    for m in ("precision", "recall", "f"):
        cols += [F.round(F.avg(m), 6).alias(f"{m}_mean"), F.round(F.stddev_pop(m), 6).alias(f"{m}_sd"), F.round(F.coalesce(F.stddev_samp(m), F.lit(0.0)), 6).alias(f"{m}_sd_sample")]
    return graded.groupBy(*by).agg(*cols)
