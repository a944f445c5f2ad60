"""Column order advice from histograms alone."""

from __future__ import annotations

from itertools import permutations
from math import ceil, comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .codes import bitmaps_needed, effective_k
from .profile import WORD, column_profile, histogram


def _clean_cost(p: float, n_words: float) -> float:
    """Expected marker-format words of a bitmap whose bits fall at random with share p."""
    q = (1 - p) ** WORD
    return n_words * (1 - q) + n_words * q * (1 - q) + 1


def predicted_words(frequencies: dict[str, list[tuple[int, int]]], n: int, order: list[str], k: int = 1) -> float:
    """Words of an index of k bitmaps a value, for rows sorted by `order`. frequencies: (frequency, values that have it).

    Within the groups that the columns before it make, a column's value is one run; groups
    multiply with each column until every row is its own, from where bits fall at random. With
    k > 1 a column has fewer bitmaps, each of which holds many values: its share of rows is the
    sum of theirs, and so are its runs, but neighbouring codes share a leading bitmap.
    """
    n_words, groups, total = ceil(n / WORD), 1.0, 0.0
    for col in order:
        values = sum(times for _, times in frequencies[col])
        kk = effective_k(values, k)
        if kk == 1:
            for f, times in frequencies[col]:
                total += times * min(_clean_cost(f / n, n_words), 3 * min(float(f), groups) + 1)
        else:
            size = bitmaps_needed(values, kk)
            for place in range(kk):  # a code's first position changes least often
                runs = min(float(n), groups * min(float(values), float(comb(size, place + 1))))
                total += min(size / kk * _clean_cost(kk / size, n_words), 3 * runs + size / kk)
        groups = min(float(n), groups * values)
    return total


def best_order(frequencies: dict[str, list[tuple[int, int]]], n: int, cols: list[str], k: int = 1) -> list[str]:
    """A greedy search: from each of the orders by cardinality, columns are moved as long as the prediction falls."""
    best, least = list(cols), predicted_words(frequencies, n, cols, k)
    for start in (list(cols), list(cols)[::-1]):
        now, cost, better = start, predicted_words(frequencies, n, start, k), True
        while better:
            better = False
            for i, j in permutations(range(len(now)), 2):
                moved = now[:i] + now[i + 1 :]
                moved.insert(j, now[i])
                if (c := predicted_words(frequencies, n, moved, k)) < cost * (1 - 1e-12):
                    now, cost, better = moved, c, True
        if cost < least:
            best, least = now, cost
    return best


def vertical_groups(cols: list[str], size: int) -> list[list[str]]:
    """Columns in groups of at most `size`, each to be sorted and indexed as its own projection."""
    return [cols[i : i + size] for i in range(0, len(cols), size)]


def vertical_projections(df: DataFrame, key: list[str], cols: list[str], size: int) -> list[tuple[list[str], DataFrame]]:
    """Each group's columns and its own table (row keys and columns), sorted by its columns from the largest cardinality down."""
    profile = {r["attr"]: r["ndv"] for r in column_profile(df, cols).collect()}  # one row for each column
    ranked = sorted(cols, key=lambda c: (profile[c], c))
    return [(g, df.select(*key, *[c for c in g if c not in key]).orderBy(*[F.col(c).asc_nulls_first() for c in reversed(g)])) for g in vertical_groups(ranked, size)]


def advise_order(df: DataFrame, cols: list[str], strategy: str = "frequency", k: int = 1) -> list[str]:
    """Columns, the one to sort by first in front.

    asc, desc: by cardinality. frequency: descending cardinality, but columns of which less
    than a quarter of the rows hold a value seen 32 times or more do not lead. model: the order
    with the fewest predicted words for k bitmaps a value, by a greedy search.
    """
    profile = {r["attr"]: r for r in column_profile(df, cols).collect()}  # one row for each column
    asc = sorted(cols, key=lambda c: (profile[c]["ndv"], c))
    if strategy == "asc":
        return asc
    if strategy == "desc":
        return asc[::-1]
    if strategy == "frequency":
        often = [c for c in asc if 4 * profile[c]["rows_in_frequent"] >= profile[c]["n"]]
        return often[::-1] + [c for c in asc if c not in often]
    if strategy == "model":
        counts = histogram(df, cols).groupBy("attr", "freq").agg(F.count("*").alias("times"))
        frequencies: dict[str, list[tuple[int, int]]] = {c: [] for c in cols}
        for r in counts.collect():  # distinct frequencies, at most about sqrt(2 n) for each column
            frequencies[r["attr"]].append((r["freq"], r["times"]))
        return best_order(frequencies, profile[cols[0]]["n"], asc, k)
    raise ValueError(f"no such strategy: {strategy}")
