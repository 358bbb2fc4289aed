"""Language identification by sparse multinomial logistic regression on TF-IDF of character n-grams.

n-grams of one to three characters of the lower-cased text are hashed to DIMENSIONS slots; TF-IDF vectors have unit
length. Weights come from follow-the-regularised-leader steps with elastic-net penalties, and a temperature fitted on
rows set aside from training calibrates the probabilities. Document frequencies are counted over every training row; the
weights are fitted on a sample of at most about PER_LANGUAGE labelled rows a language (the documented bound).

Defined results: a text that is null or without a letter is `und` with score 0; without training rows every text is
`und`; equal scores go to the language first in code-point order; repeated rows give equal results.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from . import common

DIMENSIONS = 1 << 15
PER_LANGUAGE = 400
EPOCHS = 3
# Odd multipliers of the slot hash.
PRIMES = (0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35)
_LETTER = re.compile(r"[^\W\d_]")
_PIECE = 1 << 20


def slots(text: str) -> Iterator[np.ndarray]:
    """Slots of all n-grams of the text, in pieces of bounded size that overlap by what n-grams need."""
    text = f" {text.lower()} "
    shift = np.uint32(32 - (DIMENSIONS - 1).bit_length())
    for at in range(0, len(text), _PIECE):
        c = np.frombuffer(text[at : at + _PIECE + 2].encode("utf-32-le", "surrogatepass"), "<u4")
        own = min(_PIECE, len(text) - at)
        with np.errstate(over="ignore"):
            one = c * np.uint32(PRIMES[0])
            two = (one[:-1] ^ np.uint32(0x5BD1E995)) * np.uint32(PRIMES[1]) + c[1:] * np.uint32(PRIMES[2])
            three = (two[:-1] ^ (two[:-1] >> np.uint32(15))) * np.uint32(PRIMES[0]) + c[2:] * np.uint32(PRIMES[1]) + np.uint32(7)
            yield np.concatenate([(x ^ (x >> np.uint32(13))) * np.uint32(PRIMES[2]) >> shift for x in (one[:own], two[:own], three[:own])])


def term_counts(text: str) -> np.ndarray:
    total = None
    for s in slots(text):
        found = np.bincount(s, minlength=DIMENSIONS)
        total = found if total is None else total + found
    return total


def has_letter(text: str | None) -> bool:
    return bool(text) and bool(_LETTER.search(text))


def vector(text: str, idf: np.ndarray) -> np.ndarray:
    x = term_counts(text) * idf
    return x / max(float(np.sqrt(x @ x)), 1e-12)


def fit_ftrl(rows: list[tuple[np.ndarray, np.ndarray, int]], classes: int, alpha: float = 0.5, beta: float = 1.0, l1: float = 1e-3, l2: float = 1e-3, epochs: int = EPOCHS, seed: int = 0) -> np.ndarray:
    """Weights (dimension, class) from sparse rows (slots, values, class): per-coordinate proximal steps with elastic net."""
    z, n = np.zeros((DIMENSIONS, classes)), np.zeros((DIMENSIONS, classes))
    order = np.arange(len(rows))
    rng = np.random.default_rng(seed)

    def weights(zi: np.ndarray, ni: np.ndarray) -> np.ndarray:
        return np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(ni)) / alpha + l2))

    for _ in range(epochs):
        rng.shuffle(order)
        for k in order:
            at, x, y = rows[k]
            zi, ni = z[at], n[at]
            w = weights(zi, ni)
            s = x @ w
            p = np.exp(s - s.max())
            p /= p.sum()
            p[y] -= 1
            g = x[:, None] * p[None, :]
            sigma = (np.sqrt(ni + g * g) - np.sqrt(ni)) / alpha
            z[at] = zi + g - sigma * w
            n[at] = ni + g * g
    return weights(z, n)


def temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The divisor of the logits that gives rows set aside the least log loss, by a search over a fine grid of its logarithm."""
    if not len(y):
        return 1.0

    def loss(t: float) -> float:
        s = logits / t
        s = s - s.max(1, keepdims=True)
        return float(np.mean(np.log(np.exp(s).sum(1)) - s[np.arange(len(y)), y]))

    return float(min(np.exp(np.linspace(-4, 3, 141)), key=loss))


class Model:
    def __init__(self, names: list[str], idf: np.ndarray, weights: np.ndarray, heat: float) -> None:
        self.names, self.idf, self.heat = names, idf.astype(np.float32), heat
        self.weights = weights.astype(np.float32)

    def predict(self, text: str | None) -> tuple[str, float]:
        if not self.names or not has_letter(text):
            return "und", 0.0
        s = (vector(text, self.idf) @ self.weights) / self.heat
        p = np.exp(s - s.max())
        at = int(np.argmax(p))
        return self.names[at], float(p[at] / p.sum())


def document_frequencies(train: DataFrame) -> tuple[np.ndarray, int]:
    """Number of rows that hold each slot, over all rows of column text: an array of fixed size, and the number of rows."""
    out = T._parse_datatype_string("slot int, n long")
    arrow = to_arrow_schema(out)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, rows = np.zeros(DIMENSIONS + 1, np.int64), 0
        flags = np.zeros(DIMENSIONS, bool)
        for batch in batches:
            for text in batch.column(0).to_pylist():
                rows += 1
                flags[:] = False
                for s in slots(text):
                    flags[s] = True
                df[:-1] += flags
        df[-1] = rows
        used = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array(df[used], pa.int64())], schema=arrow)

    got = train.select("text").mapInArrow(task, out).groupBy("slot").agg(F.sum("n").alias("n")).toPandas()  # DIMENSIONS + 1 rows at most
    df = np.zeros(DIMENSIONS + 1, np.int64)
    df[got.slot.to_numpy(np.int64)] = got.n.to_numpy(np.int64)
    return df[:-1], int(df[-1])


def learn(docs: DataFrame, use: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = PER_LANGUAGE) -> Model:
    """A model from the rows where `use` holds and lang is not null."""
    train = docs.where(use & F.col(lang_col).isNotNull()).select(F.col(id_col).alias("doc_id"), F.col(lang_col).cast("string").alias("lang"), common.text_or_empty(text_col).alias("text"))
    df, rows = document_frequencies(train)
    if not rows:
        return Model([], np.zeros(DIMENSIONS), np.zeros((DIMENSIONS, 0)), 1.0)
    idf = (np.log((1 + rows) / (1 + df)) + 1.0).astype(np.float32)
    counts = {r.lang: r.n for r in train.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a language
    names = sorted(counts)
    place = F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(1 << 20))
    bound = F.lit(0)
    for name, n in counts.items():
        bound = F.when(F.col("lang") == name, F.lit(int(min(1.0, per_language / n) * (1 << 20)) + 1)).otherwise(bound)
    sample = train.where(place < bound).select("lang", "text", place.alias("place"))
    shared = docs.sparkSession.sparkContext.broadcast(idf)  # DIMENSIONS numbers

    def run(cols: dict) -> dict:
        at, values = [], []
        for text in cols["text"]:
            x = vector(text, shared.value)
            used = np.flatnonzero(x)
            at.append(used.astype(np.int32))
            values.append(x[used].astype(np.float32))
        return {"lang": cols["lang"], "place": cols["place"], "at": at, "x": values}

    got = common.map_columns(sample, ["lang", "text", "place"], run, "lang string, place long, at array<int>, x array<float>").toArrow()
    number = {n: i for i, n in enumerate(names)}
    data = sorted(zip(got["place"].to_pylist(), got["lang"].to_pylist(), range(got.num_rows), strict=True))
    at, xs = got["at"].combine_chunks(), got["x"].combine_chunks()
    row = lambda i, lang: (at[i].values.to_numpy(), xs[i].values.to_numpy().astype(float), number[lang])
    aside = [row(i, lang) for k, (_, lang, i) in enumerate(data) if k % 5 == 0]
    fitted = [row(i, lang) for k, (_, lang, i) in enumerate(data) if k % 5]
    weights = fit_ftrl(fitted or aside, len(names))
    logits = np.array([x @ weights[a] for a, x, _ in aside]).reshape(len(aside), len(names))
    return Model(names, idf, weights, temperature(logits, np.array([y for _, _, y in aside], int)))


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) for each row, from the whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a fixed number of weights a language

    def run(cols: dict) -> dict:
        made = [shared.value.predict(t) for t in cols["text"]]
        return {"doc_id": cols["doc_id"], "lang_pred": [m[0] for m in made], "score": [m[1] for m in made]}

    kind = docs.schema[id_col].dataType.simpleString()
    return common.map_columns(docs, [docs[id_col].alias("doc_id"), docs[text_col].cast("string").alias("text")], run, f"doc_id {kind}, lang_pred string, score double")
