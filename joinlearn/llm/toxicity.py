"""Toxicity by a learned lexicon, Levenshtein automata over its trie, and context-window scores.

Lexicon: document counts of words and their beginnings among labelled rows; those whose share of toxic documents cannot
be chance (a binomial bound, corrected for how many candidates there are) become terms: whole words, or stems where the
endings vary. Near copies among the labelled rows count once, or all words of a copied document would look telling. Words
near a term that clean documents use themselves are no misspellings. Matching: an automaton that accepts every term within an edit distance, built lazily as sets of (trie node,
edits), reads each word. Context: hits add up over a window of words; hits inside a quotation of any length or within three words after a
word of reporting count less. A logistic function of these evidence values, fitted to the same labelled rows, gives the score.

Only text and labels.toxic are read for learning. The rows learned from are at most about SAMPLE (a documented bound on
a bounded model); scoring covers the whole of every text.

Defined results: null and empty texts score as texts without hits; labels that are null are not learned from; without any
toxic label in the sample every score is 0; repeated rows score alike.
"""

from __future__ import annotations

import bisect
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from . import common

SAMPLE = 20_000
STEMS = range(3, 13)
WINDOW = 12
EDITS, FUZZY_LEAST = 1, 5
QUOTED = 0.35
THRESHOLD = 0.7

_WORD = re.compile(r"\w+")
# Words of speaking about a word, in the languages of the tables.
REPORTING = {"word", "words", "term", "terms", "called", "said", "says", "quote", "quoted", "slur", "insult", "wort", "sagte", "mot", "terme", "dit", "palabra", "dijo"}


#: How the learned terms are matched: swapped letters are one edit, and terms from four letters on may have one.
LOOSE = {"fuzzy_least": 4, "swaps": True}
_QUOTE = re.compile(r"[\"“”„«»‹›‘’]|\n\s*\n")
_ENDS = {'"': '"', "“": "”", "„": "“”", "«": "»", "»": "«", "‹": "›", "›": "‹", "‘": "’"}


def quotations(text: str) -> list[tuple[int, int]]:
    """Spans between an opening quotation mark and the one that closes it; none runs over a blank line or stays unclosed."""
    out, opened = [], None
    for m in _QUOTE.finditer(text):
        c, a, b = m.group(), m.start(), m.end()
        if c[0] == "\n":
            opened = None
        elif opened is not None and c in _ENDS[text[opened]]:
            if c not in "\"’" or (not text[a - 1].isspace() and not text[b : b + 1].isalnum()):
                out.append((opened, b))
                opened = None
        elif opened is None and c in _ENDS and not text[max(0, a - 1) : a].isalnum() and text[b : b + 1].strip():
            opened = a
    return out


class Automaton:
    """All terms within `edits` of a word: deterministic states made on demand over a trie."""

    def __init__(self, terms: dict[str, float], edits: int = EDITS, fuzzy_least: int = FUZZY_LEAST, innocent: frozenset = frozenset(), swaps: bool = False) -> None:
        self.edits, self.fuzzy_least, self.innocent = edits, fuzzy_least, innocent
        self.children: list[dict[str, int]] = [{}]
        self.value: list[tuple[float, bool, int] | None] = [None]  # weight, whether a stem, length
        self.longest: list[int] = [0]
        for term, weight in terms.items():
            stem = term.endswith("*")
            at, text = 0, term.rstrip("*")
            self.longest[0] = max(self.longest[0], len(text))
            for c in text:
                if c not in self.children[at]:
                    self.children.append({})
                    self.value.append(None)
                    self.longest.append(0)
                    self.children[at][c] = len(self.children) - 1
                at = self.children[at][c]
                self.longest[at] = max(self.longest[at], len(text))
            self.value[at] = (weight, stem, len(text))
        #: Terms with two neighbouring letters swapped, whole words apart from stems.
        self.swaps: tuple[dict[str, float], dict[str, float]] = ({}, {})
        for term, weight in terms.items() if swaps else ():
            text = term.rstrip("*")
            for i in range(len(text) - 1) if len(text) >= fuzzy_least else ():
                made, held = text[:i] + text[i + 1] + text[i] + text[i + 2 :], self.swaps[term.endswith("*")]
                if made != text:
                    held[made] = max(held.get(made, 0.0), weight)
        self._reset()

    def _reset(self) -> None:
        self.states: dict[frozenset, int] = {frozenset(): 0}
        self.sets: list[frozenset] = [frozenset()]
        self.moves: list[dict[str, int]] = [{}]
        self.start = self._state(self._closure({(0, 0)}))
        self.heads: dict[str, int] = {}
        self.swap_heads = {v[:4] for held in self.swaps for v in held}
        self.swap_lengths = sorted({len(v) for v in self.swaps[1]})

    def __getstate__(self) -> dict:
        return {k: getattr(self, k) for k in ("edits", "fuzzy_least", "innocent", "children", "value", "longest", "swaps")}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state)
        self._reset()

    def _allowed(self, node: int, e: int) -> bool:
        return e == 0 or (e <= self.edits and self.longest[node] >= self.fuzzy_least)

    def _closure(self, pairs: set) -> frozenset:
        """With skipped term letters; of the same node only the fewest edits stay."""
        todo, best = list(pairs), {}
        while todo:
            node, e = todo.pop()
            if best.get(node, 9) <= e or not self._allowed(node, e):
                continue
            best[node] = e
            todo += [(c, e + 1) for c in self.children[node].values()]
        return frozenset(best.items())

    def _state(self, s: frozenset) -> int:
        if s not in self.states:
            self.states[s] = len(self.sets)
            self.sets.append(s)
            self.moves.append({})
        return self.states[s]

    def move(self, state: int, c: str) -> int:
        to = self.moves[state].get(c)
        if to is None:
            nxt = set()
            for node, e in self.sets[state]:
                for d, child in self.children[node].items():
                    nxt.add((child, e + (c != d)))
                if e < self.edits:
                    nxt.add((node, e + 1))
            to = self.moves[state][c] = self._state(self._closure(nxt))
        return to

    def head(self, four: str) -> int:
        """The state after a word's first letters; 0 is dead unless a short term was accepted on the way (then -1)."""
        s, accepted = self.start, False
        for c in four:
            s = self.move(s, c)
            accepted |= any(self.value[n] and self.value[n][1] for n, _ in self.sets[s])
            if not s:
                break
        if len(self.heads) > 200_000:
            self.heads.clear()
        accepted |= any(four[:k] in self.swap_heads for k in range(1, 5))
        self.heads[four] = got = -1 if accepted and not s else s
        return got

    def match(self, word: str) -> tuple[float, int]:
        """Weight and edits of the best term for the word: stems accept any continuation. (0, 0) if none."""
        best, s = (0.0, 0), self.start
        for i, c in enumerate(word):
            s = self.move(s, c)
            if not s:
                break
            last = i == len(word) - 1
            for node, e in self.sets[s]:
                v = self.value[node]
                if v and (v[1] or last) and (e == 0 or v[2] >= self.fuzzy_least) and v[0] * (0.5**e) > best[0]:
                    best = (v[0] * (0.5**e), e)
        for weight in (self.swaps[0].get(word, 0.0), *(self.swaps[1].get(word[:k], 0.0) for k in self.swap_lengths if k <= len(word))):
            if 0.5 * weight > best[0]:
                best = (0.5 * weight, 1)
        return (0.0, 0) if best[1] and word in self.innocent else best


def hits_of(text: str | None, automaton: Automaton) -> list[tuple[int, float, int, bool]]:
    """(word number, weight, edits, quoted) of each word that matches a term, over the whole text."""
    if not text:
        return []
    text = text.lower()
    words = _WORD.findall(text)
    heads = automaton.heads
    alive = [i for i, w in enumerate(words) if (heads[h] if (h := w[:4]) in heads else automaton.head(h))]
    found = [(i, *m) for i in alive if (m := automaton.match(words[i]))[0]]
    if not found:
        return []
    wanted = {i for i, _, _ in found}
    places = {i: m.span() for i, m in enumerate(_WORD.finditer(text)) if i in wanted}
    out, spans = [], quotations(text)
    starts = [a for a, _ in spans]
    for i, weight, edits in found:
        a, b = places[i]
        at = bisect.bisect_right(starts, a) - 1
        quoted = (at >= 0 and b <= spans[at][1]) or any(w in REPORTING for w in words[max(0, i - 3) : i])
        out.append((i, weight, edits, quoted))
    return out


def evidence(hits: list[tuple[int, float, int, bool]], window: int = WINDOW) -> tuple[float, float]:
    """Best window sums of exact and of misspelled hits, quotation weighed down."""
    best = [0.0, 0.0]
    for fuzzy in (0, 1):
        mine = [(i, w * (QUOTED if q else 1.0)) for i, w, e, q in hits if bool(e) == bool(fuzzy)]
        total, first = 0.0, 0
        for i, w in mine:
            total += w
            while mine[first][0] <= i - window:
                total -= mine[first][1]
                first += 1
            best[fuzzy] = max(best[fuzzy], total)
    return best[0], best[1]


def _features(pairs: list[tuple[float, float]]) -> np.ndarray:
    x = np.array(pairs, float).reshape(-1, 2)
    return np.column_stack([np.ones(len(x)), np.minimum(x[:, 0], 8.0) / 4, np.minimum(x[:, 1], 8.0) / 4])


def fit_logistic(x: np.ndarray, y: np.ndarray, l2: float = 0.05, steps: int = 60) -> np.ndarray:
    """Newton's method on the penalised log-likelihood; the constant term is not penalised, evidence weights stay at least 0."""
    w = np.zeros(x.shape[1])
    ridge = np.diag([1e-6, *[l2] * (x.shape[1] - 1)])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (p - y) + ridge @ w
        hess = (x * (p * (1 - p))[:, None]).T @ x + ridge + 1e-9 * np.eye(len(w))
        step = np.linalg.solve(hess, grad)
        w = w - step * min(1.0, 5 / max(np.abs(step).max(), 1e-12))
        w[1:] = np.maximum(w[1:], 0)
        if np.abs(step).max() < 1e-8:
            break
    return w


class Model:
    def __init__(self, terms: dict[str, float], weights: list[float], automaton: Automaton | None = None) -> None:
        self.automaton, self.weights = automaton or Automaton(terms), weights
        self.terms = terms

    def scores(self, texts: list) -> list[float]:
        if not self.terms:
            return [0.0] * len(texts)
        z = _features([evidence(hits_of(t, self.automaton)) for t in texts]) @ np.array(self.weights)
        return (1 / (1 + np.exp(-np.clip(z, -30, 30)))).tolist()


def _sketches(text: str) -> tuple[int, int]:
    """The smallest hashes of the text's five-word runs under two seeds: near copies mostly share one of them."""
    words = text.lower().split()
    runs = [" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))]
    return tuple(min(xxhash.xxh64_intdigest(r, seed) for r in runs) >> 1 for seed in (1, 2))


def _word_counts(sample: DataFrame) -> DataFrame:
    """(word, t, n): toxic and other documents that hold it, counted in each task before the shuffle."""
    out = T._parse_datatype_string("word string, t long, n long")
    arrow = to_arrow_schema(out)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, list[int]] = {}

        def flush() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([pa.array(list(counts)), pa.array([c[0] for c in counts.values()], pa.int64()), pa.array([c[1] for c in counts.values()], pa.int64())], schema=arrow)
            counts.clear()
            return made

        for batch in batches:
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for w in set(_WORD.findall((text or "").lower())):
                    counts.setdefault(w, [0, 0])[0 if toxic else 1] += 1
                if len(counts) > 300_000:
                    yield flush()
        yield flush()

    return sample.select("text", "toxic").mapInArrow(task, out)


def choose_terms(counts: list[tuple[str, int, int]], support: dict[int, int], toxic: int, clean: int, chance: float = 0.05) -> dict[str, float]:
    """Terms with weights (log odds) from candidates (stems end in *, whole words in nothing).

    A candidate passes if a chance bound on its toxic share, times the number of candidates of its support or more, is below
    `chance`. Of nested stems, the longest that keeps nearly all of the support is taken; a whole word wins over its stem."""
    share = toxic / max(1, toxic + clean)
    at_least = {}
    total = 0
    for s in sorted(support, reverse=True):
        total += support[s]
        at_least[s] = total
    top = max(support, default=0)

    def passes(t: int, n: int) -> bool:
        m = t + n
        p = t / m
        if p <= share:
            return False
        bound = m * (p * math.log(p / share) + ((1 - p) * math.log((1 - p) / (1 - share)) if p < 1 else 0.0))
        return bound > math.log(at_least.get(min(m, top), 1) / chance) and p > max(0.6, min(3 * share, (1 + share) / 2))

    good = {term: (t, n) for term, t, n in counts if passes(t, n)}
    children: dict[str, list[str]] = {}
    for term in good:
        body = term.rstrip("*")
        up = body[:-1] + "*" if term.endswith("*") else body + "*"
        children.setdefault(up, []).append(term)
        if not term.endswith("*") and len(body) > max(STEMS):
            children.setdefault(body[: max(STEMS)] + "*", []).append(term)
    roots = [term for term in good if term.endswith("*") and term[:-2] + "*" not in good]
    chosen: dict[str, float] = {}
    for root in roots:
        at = root
        while True:
            kids = sorted(children.get(at, ()), key=lambda k: -good[k][0])
            if kids and good[kids[0]][0] >= 0.93 * good[at][0]:
                at = kids[0]
                if at.endswith("*"):
                    continue
            elif kids and sum(good[k][0] for k in kids[:4]) >= 0.97 * good[at][0] and len(at) - 1 < 5 and all(k.endswith("*") for k in kids[:2]):
                for k in kids[1:]:
                    roots.append(k)
                at = kids[0]
                continue
            break
        t, n = good[at]
        chosen[at] = math.log((t + 0.5) / (n + 0.5) * (clean + 1) / (toxic + 1))
    return chosen


def learn(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = SAMPLE) -> Model:
    """A model from labelled rows; where they are more than `sample`, from those with the smallest hashes of the id."""
    marks = labels.where(F.col(label_col).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label_col).alias("toxic"))
    total = marks.count()
    share = min(1.0, sample / max(1, total))
    picked = marks.where(F.pmod(F.xxhash64("doc_id", F.lit(8)), F.lit(1 << 20)) < int(share * (1 << 20)) + 1)
    rows = docs.select(docs[id_col].alias("doc_id"), common.text_or_empty(text_col).alias("text")).join(picked, "doc_id")

    def sketched(cols: dict) -> dict:
        made = [_sketches(t) for t in cols["text"]]
        return cols | {"k1": [m[0] for m in made], "k2": [m[1] for m in made]}

    kinds = {c: rows.schema[c].dataType.simpleString() for c in ("doc_id", "toxic")}
    rows = common.cut(common.map_columns(rows, ["doc_id", "text", "toxic"], sketched, f"doc_id {kinds['doc_id']}, text string, toxic {kinds['toxic']}, k1 long, k2 long"))
    # of rows that share a sketch the one with the smallest id stays
    firsts = rows.groupBy("k1").agg(F.min("doc_id").alias("doc_id"), F.min_by("k2", "doc_id").alias("k2")).groupBy("k2").agg(F.min("doc_id").alias("doc_id"))
    rows = common.cut(rows.join(firsts.select("doc_id"), "doc_id", "left_semi").select("text", "toxic"))
    sizes = {r.toxic: r.n for r in rows.groupBy((F.col("toxic") > 0).cast("int").alias("toxic")).agg(F.count(F.lit(1)).alias("n")).collect()}
    toxic, clean = sizes.get(1, 0), sizes.get(0, 0)
    if not toxic or not clean:
        return Model({}, [0.0, 0.0, 0.0])
    words = common.cut(_word_counts(rows).groupBy("word").agg(F.sum("t").alias("t"), F.sum("n").alias("n")))
    stems = F.transform(F.sequence(F.lit(STEMS.start), F.least(F.length("word"), F.lit(STEMS.stop - 1))), lambda k: F.concat(F.substring(F.col("word"), F.lit(1), k), F.lit("*")))
    long = words.where(F.length("word") >= STEMS.start)
    terms = long.select(F.explode(F.concat(F.array("word"), stems)).alias("term"), "t", "n").groupBy("term").agg(F.sum("t").alias("t"), F.sum("n").alias("n"))
    terms = common.cut(terms.where("t > 0"))
    support = {r.s: r.c for r in terms.groupBy(F.least(F.col("t") + F.col("n"), F.lit(64)).alias("s")).agg(F.count(F.lit(1)).alias("c")).collect()}
    # few pass: candidates must be mostly toxic, and they come from a bounded sample
    counts = [(r.term, r.t, r.n) for r in terms.where((F.col("t") >= 3) & (F.col("t") > 1.5 * F.col("n"))).collect()]
    chosen = choose_terms(counts, support, toxic, clean)
    plain = docs.sparkSession.sparkContext.broadcast(Automaton(chosen, **LOOSE))

    def near(cols: dict) -> dict:
        return {"word": cols["word"], "edits": [plain.value.match(w)[1] if plain.value.head(w[:4]) else 0 for w in cols["word"]]}

    usual = words.where((F.col("n") >= 2) & (F.col("t") < F.col("n")))
    usual = common.map_columns(usual, ["word"], near, "word string, edits int", text=None).where("edits > 0")
    innocent = frozenset(r.word for r in usual.collect())  # words of the bounded sample, one edit from a term
    shared = docs.sparkSession.sparkContext.broadcast(Automaton(chosen, innocent=innocent, **LOOSE))

    def run(cols: dict) -> dict:
        made = [evidence(hits_of(t, shared.value)) for t in cols["text"]]
        return {"toxic": cols["toxic"], "x": [m[0] for m in made], "y": [m[1] for m in made]}

    kind = rows.schema["toxic"].dataType.simpleString()
    got = common.map_columns(rows, ["text", "toxic"], run, f"toxic {kind}, x double, y double").toPandas()  # about `sample` rows of numbers
    weights = fit_logistic(_features(list(zip(got.x, got.y, strict=True))), (got.toxic > 0).to_numpy(float))
    return Model(chosen, weights.tolist(), Automaton(chosen, innocent=innocent, **LOOSE))


def score(docs: DataFrame, model: Model, keep: list[str] | dict[str, str], text_col: str = "text") -> DataFrame:
    """The keep columns and score for each row; the model (its lexicon is bounded by the sample) is broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    shown = {c: f"k{i}" for i, c in enumerate(keep)}

    def run(cols: dict) -> dict:
        texts = cols["__text"]
        return {k: cols[k] for k in shown.values()} | {"score": shared.value.scores(texts)}

    schema = ", ".join([*(f"{k} {docs.schema[c].dataType.simpleString()}" for c, k in shown.items()), "score double"])
    out = common.map_columns(docs, [*(docs[c].alias(k) for c, k in shown.items()), docs[text_col].cast("string").alias("__text")], run, schema, text="__text")
    names = common.named(keep)
    return out.select(*[F.col(k).alias(names[c]) for c, k in shown.items()], "score")


def accepted(docs: DataFrame, model: Model, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """docs without the rows whose score reaches the threshold; all columns as they came."""
    names = common.masked(docs)
    return common.unmasked(score(docs, model, names, text_col).where(F.col("score") < threshold), names)
