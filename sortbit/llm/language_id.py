"""Language identification with hyperdimensional profiles.

Every letter symbol has a random vector of +1 and -1. An n-gram's vector is the product
(binding) of its letters' vectors, each permuted by its place; a text's vector is the
sum (bundle) of its n-grams' vectors. A language's prototype bundles the normalised
vectors of its learning texts. A text gets the language with the largest cosine; its
score is that cosine, not below 0. Equal cosines go to the first language by name.

Symbols are folded bytes of UTF-8: a-z, one for each run of anything else in ASCII, and
classes of lead and continuation bytes, so any script works without a list of letters.

Defined cases: a null text, an empty one and one without any letter give `und`, score 0;
without learning rows every text is `und`.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import bounded_sample, fold_is_held_out, ship, text_chunks
from .bytewords import LOWER, text_bytes

SYMBOLS = 64
UNKNOWN = "und"


def symbol_table() -> np.ndarray:
    """0: no letter; 1-26: a-z; 27-31: lead bytes; 32-63: continuation bytes, lower case where Latin has two."""
    out = np.zeros(256, np.uint8)
    out[LOWER[np.arange(65, 91)]] = out[65:91] = np.arange(1, 27)
    out[0xC0:] = 27 + (np.arange(0xC0, 0x100) & 0x0F) % 5
    out[0x80:0xC0] = 32 + (np.arange(0x80, 0xC0) & 0x1F)
    return out


@dataclass
class Profiles:
    languages: list[str]
    prototypes: np.ndarray
    dimension: int
    seed: int = 11

    def letters(self) -> list[np.ndarray]:
        """The letter vectors permuted for the first, second and third place."""
        base = np.random.default_rng(self.seed).choice(np.array([-1, 1], np.float32), (SYMBOLS, self.dimension))
        return [np.roll(base, 2, axis=1), np.roll(base, 1, axis=1), base]


def bundles(column: pa.Array, letters: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Each text's vector, and whether it has any symbol but the blank."""
    data, offsets = text_bytes(column)
    symbols = symbol_table()[data]
    a, b, c = letters
    out = np.zeros((len(offsets) - 1, a.shape[1]), np.float32)
    any_symbol = np.zeros(len(out), bool)
    for i, (start, end) in enumerate(zip(offsets[:-1], offsets[1:], strict=True)):
        s = symbols[start:end]
        if not s.any():
            continue
        any_symbol[i] = True
        held = np.ones(len(s), bool)
        held[1:] = (s[1:] != 0) | (s[:-1] != 0)
        s = np.concatenate(([0], s[held], [0])).astype(np.int64)
        counts = np.bincount((s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:])
        grams = np.flatnonzero(counts)
        for at in range(0, len(grams), 4096):
            g = grams[at : at + 4096]
            out[i] += counts[g].astype(np.float32) @ (a[g >> 12] * b[(g >> 6) & 63] * c[g & 63])
    return out, any_symbol


def normalised(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=-1, keepdims=True), 1e-12)


def fit(docs: DataFrame, sample: int = 12_000, dimension: int = 512, seed: int = 11) -> Profiles:
    """Prototypes from at most about `sample` rows (doc_id, text, lang) outside the held-out fold."""
    ship(docs.sparkSession)
    letters = Profiles([], np.zeros((0, dimension)), dimension, seed).letters()
    learn = bounded_sample(docs.select("doc_id", "text", "lang").where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~fold_is_held_out(F.col("doc_id"))), "doc_id", sample)

    def run(batches):
        sums: dict[str, np.ndarray] = {}
        for batch in text_chunks(batches):
            vectors = normalised(bundles(batch.column("text"), letters)[0])
            langs = np.array(batch.column("lang").to_pylist(), object)
            for lang in set(langs):
                sums[lang] = sums.get(lang, 0) + vectors[langs == lang].sum(axis=0)
        yield pa.record_batch({"lang": pa.array(list(sums), pa.string()), "bundle": pa.array([v.astype("<f4").tobytes() for v in sums.values()], pa.binary())})

    total: dict[str, np.ndarray] = {}
    for lang, bundle in learn.mapInArrow(run, "lang string, bundle binary").collect():
        total[lang] = total.get(lang, 0) + np.frombuffer(bundle, "<f4").astype(np.float64)
    languages = sorted(total)
    return Profiles(languages, normalised(np.array([total[x] for x in languages]).reshape(len(languages), dimension)), dimension, seed)


def detect(docs: DataFrame, profiles: Profiles, id_col: str = "doc_id") -> DataFrame:
    """(id, lang_pred, score) for the whole text of every row."""
    ship(docs.sparkSession)
    kind = docs.schema[id_col].dataType

    def run(batches):
        letters = profiles.letters()
        names = np.array([*profiles.languages, UNKNOWN], object)
        for batch in text_chunks(batches):
            column = batch.column("text")
            vectors, known = bundles(column, letters)
            ascii_letter = (symbol_table() > 0) & (np.arange(256) < 0x80)
            data, offsets = text_bytes(column)
            sums = np.concatenate(([0], np.cumsum(ascii_letter[data])))
            plain = sums[offsets[1:]] > sums[offsets[:-1]]
            for i in np.flatnonzero(known & ~plain):
                known[i] = any(ch.isalpha() for ch in column[int(i)].as_py())
            if not profiles.languages:
                known[:] = False
            best, score = np.full(len(known), len(names) - 1), np.zeros(len(known))
            if known.any():
                cosines = normalised(vectors[known].astype(np.float64)) @ profiles.prototypes.T
                best[known] = cosines.argmax(axis=1)
                score[known] = np.clip(cosines.max(axis=1), 0, 1)
            yield pa.record_batch({id_col: batch.column(id_col), "lang_pred": pa.array(names[best], pa.string()), "score": pa.array(score)})

    return docs.select(id_col, "text").mapInArrow(run, f"{id_col} {kind.simpleString()}, lang_pred string, score double")
