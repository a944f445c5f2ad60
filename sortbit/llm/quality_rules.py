"""Quality rules: an ordered decision list learned from labelled statistics.

`statistics` counts, for each whole text, what the rules look at. `learn` covers the
rows labelled bad one rule after another: a rule is a conjunction of thresholds on
ratios, grown by the largest information gain on two thirds of the rows and pruned on the
other third by precision; rows that a rule covers leave, until no rule reaches
`least_precision`. `verdict` turns the list into one ordered CASE expression, so applying
it runs in the JVM. The labelled sample is bounded by `sample` rows.

Words are `[^\\x20\\x09-\\x0D]+`. A null text has no words and no lines. Without any row
labelled bad there is no rule, and every text passes.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import bounded_sample, ship, text_chunks
from .bytewords import SpanHash, count_inside, mix, per_text, spans, text_bytes, windows, words

COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_digits", "n_marks"]


def _flags(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_SYMBOL, _UPPER, _DIGIT, _MARK = _flags(b"#*$%&|<>"), _flags(bytes(range(65, 91))), _flags(b"0123456789"), _flags(b"!?")


def _seen_before(hashes: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each entry: does an equal one stand earlier in its text, and is there any other."""
    key = mix(hashes ^ mix(text.astype(np.uint64) + np.uint64(1)))
    order = np.argsort(key, kind="stable")
    same = np.zeros(len(key) + 1, bool)
    same[1:-1] = key[order][1:] == key[order][:-1]
    earlier, other = np.zeros(len(key), bool), np.zeros(len(key), bool)
    earlier[order] = same[:-1]
    other[order] = same[:-1] | same[1:]
    return earlier, other


def text_counts(column: pa.Array) -> dict[str, np.ndarray]:
    data, offsets = text_bytes(column)
    n = len(offsets) - 1
    starts, ends, text = words(data, offsets)
    hashes = SpanHash(data)
    inside = np.zeros(len(data) + 1, np.int64)
    np.add.at(inside, starts, 1)
    np.add.at(inside, ends, -1)
    in_word = np.cumsum(inside[:-1]) > 0
    out = {"n_words": per_text(text, n), "word_chars": count_inside(in_word & ((data & 0xC0) != 0x80), offsets)}
    out["n_symbols"] = count_inside(_SYMBOL[data], offsets)

    line_start, line_end, line_text = spans(data != 0x0A, offsets)
    word_line = np.searchsorted(line_start, starts, side="right") - 1
    with_word = np.zeros(len(line_start), bool)
    with_word[word_line] = True
    ls, le, lt = line_start[with_word], line_end[with_word], line_text[with_word]
    earlier, _ = _seen_before(hashes.of(ls, le), lt)
    out["n_dup_lines"] = per_text(lt[earlier], n)

    three, at = windows(hashes.of(starts, ends), text, 3)
    _, other = _seen_before(three, text[at])
    repeated = np.zeros(len(starts) + 2, bool)
    for k in range(3):
        repeated[at[other] + k] = True
    out["n_repeat_words"] = per_text(text[repeated[: len(starts)]], n)
    out["n_lines"] = per_text(lt, n)
    for name, table in (("n_upper", _UPPER), ("n_digits", _DIGIT), ("n_marks", _MARK)):
        out[name] = count_inside(table[data], offsets)
    return out


def statistics(docs: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The id and COUNTS (long) for every row."""
    ship(docs.sparkSession)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in text_chunks(batches):
            found = text_counts(batch.column("text"))
            yield pa.record_batch({id_col: batch.column(id_col), **{k: pa.array(found[k], pa.int64()) for k in COUNTS}})

    return docs.select(id_col, "text").mapInArrow(run, f"{id_col} {kind}, " + ", ".join(f"{c} long" for c in COUNTS))


#: Ratio: (numerator, denominator); a denominator of 0 counts as 1.
RATIOS = {
    "words": ("n_words", None),
    "chars_per_word": ("word_chars", "n_words"),
    "symbols_per_word": ("n_symbols", "n_words"),
    "dup_line_share": ("n_dup_lines", "n_lines"),
    "repeat_share": ("n_repeat_words", "n_words"),
    "upper_share": ("n_upper", "word_chars"),
    "digit_share": ("n_digits", "word_chars"),
    "marks_per_word": ("n_marks", "n_words"),
    "words_per_line": ("n_words", "n_lines"),
}


def ratio(name: str) -> Column:
    top, below = RATIOS[name]
    return F.col(top).cast("double") if below is None else F.col(top) / F.greatest(F.col(below), F.lit(1))


def ratios(counts: dict[str, np.ndarray]) -> np.ndarray:
    return np.column_stack([counts[t].astype(float) if b is None else counts[t] / np.maximum(counts[b], 1) for t, b in RATIOS.values()])


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


@dataclass(frozen=True)
class Rule:
    """A conjunction of (ratio, above, threshold); above: the ratio is at least the threshold, else below it."""

    terms: tuple[tuple[str, bool, float], ...]

    def covers(self, x: np.ndarray) -> np.ndarray:
        names = list(RATIOS)
        out = np.ones(len(x), bool)
        for name, above, threshold in self.terms:
            column = x[:, names.index(name)]
            out &= column >= threshold if above else column < threshold
        return out

    def condition(self) -> Column:
        out = F.lit(True)
        for name, above, threshold in self.terms:
            out &= ratio(name) >= threshold if above else ratio(name) < threshold
        return out


def _grow(x: np.ndarray, bad: np.ndarray, max_terms: int, cuts: int = 64) -> Rule:
    rule, live, names = Rule(()), np.ones(len(x), bool), list(RATIOS)
    while len(rule.terms) < max_terms and (~bad[live]).any():
        p, n = bad[live].sum(), (~bad[live]).sum()
        best, term = 0.0, None
        for j, name in enumerate(names):
            values = x[live, j]
            for threshold in np.unique(np.quantile(values, np.linspace(0, 1, cuts))):
                for above in (True, False):
                    hit = values >= threshold if above else values < threshold
                    tp, fp = bad[live][hit].sum(), (~bad[live][hit]).sum()
                    gain = tp * (np.log2(tp / (tp + fp)) - np.log2(p / (p + n))) if tp else 0
                    if gain > best + 1e-9:
                        best, term = gain, (name, above, float(threshold))
        if term is None:
            break
        rule = Rule((*rule.terms, term))
        live = rule.covers(x)
    return rule


def _precision(rule: Rule, x: np.ndarray, bad: np.ndarray) -> float:
    hit = rule.covers(x)
    return (bad[hit].sum() + 1) / (hit.sum() + 2)


def cover(x: np.ndarray, bad: np.ndarray, least_precision: float = 0.9, least_rows: int = 5, max_rules: int = 12, max_terms: int = 4, seed: int = 3) -> list[Rule]:
    rng, rules, live = np.random.default_rng(seed), [], np.ones(len(x), bool)
    while bad[live].sum() >= least_rows and len(rules) < max_rules:
        at = rng.permutation(np.flatnonzero(live))
        grow, prune = at[: 2 * len(at) // 3], at[2 * len(at) // 3 :]
        rule = _grow(x[grow], bad[grow], max_terms)
        options = [Rule(rule.terms[:k]) for k in range(1, len(rule.terms) + 1)]
        if not options:
            break
        rule = max(options, key=lambda r: (_precision(r, x[prune], bad[prune]), -len(r.terms)))
        hit = live & rule.covers(x)
        if bad[hit].sum() < least_rows or bad[hit].mean() < least_precision or _precision(rule, x[prune], bad[prune]) < least_precision - 0.1:
            break
        rules.append(rule)
        live &= ~hit
    return rules


def learn(stats: DataFrame, labels: DataFrame, id_col: str = "doc_id", **how) -> list[Rule]:
    """Rules against quality 0, from the rows of `stats` that `labels` marks and that pass the base."""
    marked = labels.where(F.col("quality").isNotNull()).groupBy(id_col).agg(F.min("quality").alias("quality"))
    rows = stats.join(marked, id_col).where(~base_failed()).select("quality", *COUNTS).toPandas()
    if not len(rows):
        return []
    return cover(ratios({c: rows[c].to_numpy() for c in COUNTS}), rows["quality"].to_numpy() == 0, **how)


def fit(docs: DataFrame, labels: DataFrame, sample: int = 12_000, id_col: str = "doc_id", **how) -> list[Rule]:
    """Learns on at most about `sample` labelled rows; the sample's ids are small enough to broadcast."""
    some = bounded_sample(labels.where(F.col("quality").isNotNull()).select(id_col, "quality"), id_col, sample)
    texts = docs.select(id_col, "text").join(F.broadcast(some.select(id_col)), id_col, "left_semi")
    return learn(statistics(texts, id_col), some, id_col, **how)


def verdict(rules: list[Rule]) -> Column:
    """True for a text that no rule rejects: the ordered list as a conditional expression."""
    if not rules:
        return F.lit(True)
    out = F.when(rules[0].condition(), F.lit(False))
    for rule in rules[1:]:
        out = out.when(rule.condition(), F.lit(False))
    return out.otherwise(F.lit(True))


def apply_rules(stats: DataFrame, rules: list[Rule]) -> DataFrame:
    """stats with base_failed and kept."""
    return stats.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & verdict(rules))
