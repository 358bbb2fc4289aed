"""Benchmark decontamination with suffix arrays over shards of the training text.

Each task reads its documents in shards of a bounded number of words and numbers the words by the benchmark's vocabulary (any
other word can match nothing and separates). The shard's suffix array is built by prefix doubling; the names of the doubled
prefixes are places in the benchmark's own sorted prefixes, so a suffix that no benchmark suffix begins like drops out at the
first doubling. Every benchmark suffix is then binary-searched in the array, which gives the places of every verbatim match.
Places that follow one another in a text and in an item are one match: the longest for each item is kept with its place. Nothing
is shuffled.

The benchmark is read in blocks of bounded size (BLOCK_BYTES). The driver collects one at a time, each is broadcast, and a
task unpacks one at a time, so memory is that of one block however many there are; work is one pass of a run of texts a block.

Defined results: null or empty texts have no words, no hits; items without words match nothing; items of fewer words
than the window are matched whole; repeated rows and items give equal results and count once an item id; a null item id
is written as the empty text; an empty benchmark leaves every document clean; texts beyond a shard are read in overlapping
pieces. Of equally long matches of an item the first in the text is kept.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Words that count: 0-9, a-z after lower-casing, and every character from U+0080 on.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
WINDOW = 10
SHARD_WORDS = 1_000_000
BLOCK_BYTES = 8 << 20
#: Pairs of places in a text and in items that are looked at together.
PAIRS = 2_000_000


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []


def _keyed(first: np.ndarray, second: np.ndarray, base: int) -> np.ndarray:
    """One number for two names, in their order; 0 where one of them is none."""
    return np.where((first > 0) & (second > 0), first * base + second, 0)


def _ahead(names: np.ndarray, by: int) -> np.ndarray:
    """The names `by` places further on; none beyond the end."""
    out = np.zeros(len(names), np.int64)
    out[: max(0, len(names) - by)] = names[by:]
    return out


def _named(keys: np.ndarray, known: np.ndarray) -> np.ndarray:
    """The place of each key in the sorted known ones, from 1; 0 for keys that are not among them."""
    out = np.zeros(len(keys), np.int64)
    live = np.flatnonzero(keys)
    if len(known) and len(live):
        at = np.minimum(np.searchsorted(known, keys[live]), len(known) - 1)
        out[live] = np.where(known[at] == keys[live], at + 1, 0)
    return out


def _chain(size: int) -> list[tuple[int, int]]:
    """(offset, power of two) pieces that make up a prefix of that many words, the largest first."""
    out, at = [], 0
    while at < size:
        k = 1 << ((size - at).bit_length() - 1)
        out.append((at, k))
        at += k
    return out


class Block:
    """A block of the benchmark in arrays: its words numbered, its sorted prefixes at each doubling, its suffixes by name."""

    def __init__(self, items: list[tuple[str, str]], window: int = WINDOW) -> None:
        self.window = window
        self.vocabulary: dict[bytes, int] = {}
        self.items = sorted({i for i, _ in items})
        number = {i: n for n, i in enumerate(self.items)}
        ids: list[int] = []
        owner: list[int] = []
        size: list[int] = []  # of the suffix that begins here; 0 where none does
        for name, text in items:
            words = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of(text)]
            n = min(window, len(words))
            ids += [*words, 0]
            owner += [number[name]] * (len(words) + 1)
            size += [n] * (len(words) - n + 1) + [0] * n if words else [0]
        self.owner, sizes = np.array(owner, np.int32), np.array(size, np.int32)
        levels = {1: np.array(ids, np.int64)}
        self.base = max(2, len(ids) + 2)
        self.prefixes: dict[int, np.ndarray] = {}
        k = 1
        while 2 * k <= window:
            keys = _keyed(levels[k], _ahead(levels[k], k), self.base)
            self.prefixes[2 * k] = np.unique(keys[keys > 0])
            levels[2 * k] = _named(keys, self.prefixes[2 * k])
            k *= 2
        self.steps: dict[int, list[np.ndarray]] = {}
        self.starts: dict[int, np.ndarray] = {}  # of each size, the places of its suffixes by name
        self.places: dict[int, np.ndarray] = {}
        for n in np.unique(sizes[sizes > 0]).tolist():
            names, self.steps[n] = self._suffixes(levels, n, None)
            names = np.where(sizes == n, names, 0)
            kinds, names[names > 0] = np.unique(names[names > 0], return_inverse=True)
            names[sizes == n] += 1
            self.steps[n].append(kinds)
            order = np.argsort(names, kind="stable")
            order = order[names[order] > 0]
            self.places[n] = order
            self.starts[n] = np.searchsorted(names[order], np.arange(1, len(kinds) + 2))

    def _suffixes(self, levels: dict[int, np.ndarray], size: int, steps: list[np.ndarray] | None) -> tuple[np.ndarray, list[np.ndarray]]:
        """Names of the prefixes of that many words; the sorted keys are made where steps are not given."""
        (_, k), *rest = _chain(size)
        names, made = levels[k], []
        for i, (offset, k) in enumerate(rest):
            keys = _keyed(names, _ahead(levels[k], offset), self.base)
            made.append(np.unique(keys[keys > 0]) if steps is None else steps[i])
            names = _named(keys, made[-1])
        return names, made

    def suffix_array(self, ids: np.ndarray) -> dict[int, tuple[np.ndarray, np.ndarray]]:
        """For each size of benchmark suffixes: the shard's places in the order of their suffixes, and these suffixes' names.

        Places whose suffix no benchmark suffix equals are not in it."""
        levels = {1: ids}
        for k, known in self.prefixes.items():
            levels[k] = _named(_keyed(levels[k // 2], _ahead(levels[k // 2], k // 2), self.base), known)
        out = {}
        for size, steps in self.steps.items():
            names = _named(self._suffixes(levels, size, steps)[0], steps[-1])
            at = np.flatnonzero(names)
            order = at[np.argsort(names[at], kind="stable")]
            out[size] = order, names[order]
        return out

    def find(self, ids: np.ndarray) -> list[tuple[int, np.ndarray, np.ndarray]]:
        """Every place of every benchmark suffix in ids, by binary search in the suffix array: (size, names, places)."""
        found = []
        for size, (order, names) in self.suffix_array(ids).items():
            if not len(order):
                continue
            queries = np.arange(1, len(self.starts[size]))
            low, high = np.searchsorted(names, queries, "left"), np.searchsorted(names, queries, "right")
            found.append((size, np.repeat(queries, high - low), order[low[0] : high[-1]]))
        return found

    def search(self, documents: list[list[bytes]]) -> list[tuple[list[tuple[int, int]], list[str], list[tuple[str, int, int]]]]:
        """For each document: covered word spans, ids of items with occurring windows, longest match of each (item, start, words)."""
        get = self.vocabulary.get
        # (document, first word, words): a document beyond a shard is cut into pieces that share window - 1 words
        step = max(1, SHARD_WORDS - self.window + 1)
        pieces = [(i, at, d[at : at + SHARD_WORDS] if len(d) > SHARD_WORDS else d) for i, d in enumerate(documents) for at in (range(0, max(1, len(d) - self.window + 1), step) if len(d) > SHARD_WORDS else (0,))]
        hits: dict[int, dict[int, list[tuple[np.ndarray, np.ndarray]]]] = {}
        start = 0
        while start < len(pieces):
            end, total = start, 0
            while end < len(pieces) and (end == start or total + len(pieces[end][2]) <= SHARD_WORDS):
                total += len(pieces[end][2]) + 1
                end += 1
            shard = pieces[start:end]
            first = np.cumsum([0, *(len(d) + 1 for _, _, d in shard)])
            ids = np.zeros(int(first[-1]), np.int64)
            for (_, _, d), at in zip(shard, first, strict=False):
                ids[at : at + len(d)] = [get(w, 0) for w in d]
            for size, names, places in self.find(ids):
                order = np.argsort(places, kind="stable")
                names, places = names[order], places[order]
                owner = np.searchsorted(first, places, "right") - 1
                for low, high in _stretches(owner):
                    i, offset, _ = shard[owner[low]]
                    hits.setdefault(i, {}).setdefault(size, []).append((places[low:high] - first[owner[low]] + offset, names[low:high]))
            start = end
        found: list = [([], [], [])] * len(documents)
        for i, by_size in hits.items():
            found[i] = self._document({n: _joined(parts) for n, parts in by_size.items()})
        return found

    def _document(self, hits: dict[int, tuple[np.ndarray, np.ndarray]]) -> tuple[list, list, list]:
        starts = np.concatenate([p for p, _ in hits.values()])
        stops = np.concatenate([p + n for n, (p, _) in hits.items()])
        order = np.argsort(starts, kind="stable")
        starts, stops = starts[order], np.maximum.accumulate(stops[order])
        new = np.r_[True, starts[1:] > stops[:-1]]
        spans = list(zip(starts[new].tolist(), stops[np.r_[new[1:], True]].tolist(), strict=True))
        best: dict[int, tuple[int, int]] = {}
        for size, (places, names) in hits.items():
            for item, at, words in self._matches(size, places, names):
                if item not in best or (words, -at) > (best[item][1], -best[item][0]):
                    best[item] = at, words
        longest = sorted(((self.items[o], at, words) for o, (at, words) in best.items()), key=lambda x: (x[1], x[0]))
        return spans, [self.items[o] for o in sorted(best)], longest

    def _matches(self, size: int, places: np.ndarray, names: np.ndarray):
        """(item, start, words) of each stretch of suffixes that follow one another in the text and in an item.

        Pairs of a place and a place in the benchmark are looked at PAIRS at a time; stretches go on from one to the next."""
        begin, count = self.starts[size][names - 1], self.starts[size][names] - self.starts[size][names - 1]
        ends = np.cumsum(count)
        low, carried = 0, (np.zeros(0, np.int64), np.zeros(0, np.int64), -2)
        while low < len(places):
            high = max(low + 1, int(np.searchsorted(ends, (ends[low - 1] if low else 0) + PAIRS, "right")))
            n = count[low:high]
            place = np.repeat(places[low:high], n)
            within = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            there = self.places[size][np.repeat(begin[low:high], n) + within]
            line = place - there
            order = np.lexsort((place, line))
            place, there, line = place[order], there[order], line[order]
            new = np.r_[True, (line[1:] != line[:-1]) | (place[1:] != place[:-1] + 1)]
            first, last = np.flatnonzero(new), np.flatnonzero(np.r_[new[1:], True])
            start = place[first]
            if len(carried[0]):
                at = np.minimum(np.searchsorted(carried[0], line[first]), len(carried[0]) - 1)
                start = np.where((carried[0][at] == line[first]) & (start == carried[2] + 1), carried[1][at], start)
            yield from zip(self.owner[there[first]].tolist(), start.tolist(), (place[last] - start + size).tolist(), strict=True)
            final = int(places[high - 1])
            open_ = place[last] == final
            carried = line[first][open_], start[open_], final
            low = high


def _stretches(values: np.ndarray) -> list[tuple[int, int]]:
    """(first, end) of each stretch of equal values."""
    at = np.flatnonzero(np.r_[True, values[1:] != values[:-1]]) if len(values) else np.zeros(0, int)
    return list(zip(at.tolist(), [*at[1:].tolist(), len(values)], strict=True))


def _joined(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Places and names of all pieces of a document, in order of place; short suffixes may lie in two pieces."""
    places, names = (np.concatenate(x) for x in zip(*parts, strict=True))
    kept = np.unique(places, return_index=True)[1]
    return places[kept], names[kept]


def blocks_of(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", limit: int = BLOCK_BYTES) -> list[list[tuple[str, str]]]:
    """The benchmark in blocks of at most about `limit` bytes; its size is measured first, and one block is collected at a time."""
    rows = benchmark.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("id"), common.text_or_empty(text_col).alias("text"))
    total = rows.agg(F.coalesce(F.sum(F.octet_length("text") + F.lit(64)), F.lit(0))).first()[0]
    n = max(1, -(-int(total) // limit))
    if n == 1:
        yield [(r.id, r.text) for r in rows.collect()]
        return
    for k in range(n):
        yield [(r.id, r.text) for r in rows.where(F.pmod(F.xxhash64("id", "text"), F.lit(n)) == k).collect()]


RESULT = "n_words long, spans array<struct<start:long,end:long>>, items array<string>, longest array<struct<item:string,start:long,words:long>>"


def contaminated(docs: DataFrame, benchmark: DataFrame, keep: list[str] | dict[str, str] | None = None, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW) -> DataFrame:
    """keep columns (the id if not given) with n_words, spans of hit words, items and longest matches, for each row of docs."""
    spark = docs.sparkSession
    keep = common.named(keep or [id_col])
    carried = "__text"
    shown = {c: f"k{i}" for i, c in enumerate(keep)}
    kinds = [f"k{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep)]
    blocks = [spark.sparkContext.broadcast(Block(items, window)) for items in blocks_of(benchmark)]  # each of at most BLOCK_BYTES of text

    def run(cols: dict) -> dict:
        words = [words_of(t) for t in cols[carried]]
        got = [([], [], [])] * len(words)
        for shared in blocks:
            found = shared.value.search(words)
            got = found if len(blocks) == 1 else [_united(a, b) for a, b in zip(got, found, strict=True)]
            if len(blocks) > 1:
                shared.__dict__.pop("_value", None)  # one unpacked block at a time
        made = {"n_words": list(map(len, words)), "spans": [[{"start": a, "end": b} for a, b in g[0]] for g in got], "items": [g[1] for g in got], "longest": [[{"item": i, "start": s, "words": w} for i, s, w in g[2]] for g in got]}
        return {c: cols[c] for c in shown.values()} | made

    picked = [*(docs[c].alias(k) for c, k in shown.items()), docs[text_col].cast("string").alias(carried)]
    out = common.map_columns(docs, picked, run, ", ".join([*kinds, RESULT]), text=carried)
    return out.select(*[F.col(k).alias(keep[c]) for c, k in shown.items()], "n_words", "spans", "items", "longest")


def _united(a: tuple, b: tuple) -> tuple[list, list, list]:
    """What two blocks found in one document."""
    spans: list[tuple[int, int]] = []
    for start, end in sorted([*a[0], *b[0]]):
        if spans and start <= spans[-1][1]:
            spans[-1] = spans[-1][0], max(spans[-1][1], end)
        else:
            spans.append((start, end))
    best: dict[str, tuple[int, int]] = {}
    for item, at, words in [*a[2], *b[2]]:
        best[item] = max(best.get(item, (0, 0)), (words, -at))
    return spans, sorted({*a[1], *b[1]}), sorted(((i, -at, words) for i, (words, at) in best.items()), key=lambda x: (x[1], x[0]))


def remove(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW) -> DataFrame:
    """docs without the rows that hold a window of the benchmark; all columns as they came."""
    names = common.masked(docs)
    return common.unmasked(contaminated(docs, benchmark, names, id_col, text_col, window).where(F.size("spans") == 0), names)


def items_digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()


def oracle(window: int = WINDOW) -> str:
    """The query in SQL for DuckDB: windows as texts, equal ones joined, hits counted as word positions,
    longest matches as windows that follow one another in the text and in the item."""
    fold = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    words = rf"regexp_extract_all({fold}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    return f"""WITH d AS MATERIALIZED (SELECT doc_id, {words} AS w FROM documents),
b AS MATERIALIZED (SELECT row_number() OVER () AS item_row, coalesce(CAST(item_id AS VARCHAR), '') AS item, w, least({window}, len(w)) AS size FROM (SELECT item_id, {words} AS w FROM benchmark) WHERE len(w) > 0),
item_windows AS MATERIALIZED (SELECT item, item_row, j, size, array_to_string(w[j : j + size - 1], ' ') AS g FROM (SELECT item, item_row, size, w, unnest(range(1, len(w) - size + 2)) AS j FROM b)),
sizes AS (SELECT DISTINCT size FROM b),
doc_windows AS (SELECT doc_id, size, i, array_to_string(w[i : i + size - 1], ' ') AS g FROM (SELECT doc_id, size, w, unnest(range(1, len(w) - size + 2)) AS i FROM d, sizes WHERE len(w) >= size)),
met AS MATERIALIZED (SELECT doc_id, item, item_row, size, i, j FROM doc_windows JOIN item_windows USING (size, g)),
hits AS (SELECT doc_id, count(*) AS n FROM (SELECT DISTINCT doc_id, unnest(range(i, i + size)) AS at FROM (SELECT DISTINCT doc_id, i, size FROM met)) GROUP BY 1),
items AS (SELECT doc_id, count(*) AS n, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT doc_id, item FROM met) GROUP BY 1),
runs AS (SELECT doc_id, item_row, size, count(*) + size - 1 AS words FROM (SELECT *, i - row_number() OVER (PARTITION BY doc_id, item_row, i - j ORDER BY i) AS run FROM met) GROUP BY doc_id, item_row, size, i - j, run),
longest AS (SELECT doc_id, max(words) AS words FROM runs GROUP BY 1)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(hits.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(items.n, 0) AS BIGINT) AS n_items,
 sha256(coalesce(items.ids, '')) AS items_sha256, coalesce(hits.n, 0) > 0 AS contaminated, CAST(coalesce(longest.words, 0) AS BIGINT) AS longest_match
FROM d LEFT JOIN hits USING (doc_id) LEFT JOIN items USING (doc_id) LEFT JOIN longest USING (doc_id)"""
