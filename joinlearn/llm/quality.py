"""Host-level quality rules.

Each document is held against line and word rules; failures are counted by host, a beta prior fitted to all hosts by the
method of moments shrinks each host's failure rate, and the host's verdict is joined back to its documents. The spread of the
prior is what the hosts' rates vary by beyond the chance of small hosts, so that it alone decides how much a small host counts.

Defined results: a null text has no words and fails; a null host is a host of its own; repeated rows count each time;
with no rows the result is empty. Words are runs of anything but ASCII white space.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

_SYMBOLS = re.compile(r"[#*$%&|<>]")
SPACES = " \t\n\v\f\r"
#: A host is rejected if its shrunk failure rate is above this.
HOST_LIMIT = 0.5
FEATURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


#: From so many words on, windows are counted as numbers: tuples of all of them would fill an executor.
LONG = 200_000


def repeated_words(words: list[bytes]) -> int:
    """How many words lie in a three-word window that occurs twice or more; by numbered pairs, then numbered triples."""
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, len(words))
    pair = np.unique(ids[:-1] * (len(number) + 1) + ids[1:], return_inverse=True)[1].astype(np.int64)
    _, at, count = np.unique(pair[:-1] * (len(number) + 1) + ids[2:], return_inverse=True, return_counts=True)
    hit = np.zeros(len(words), bool)
    twice = count[at] > 1
    for k in range(3):
        hit[k : len(words) - 2 + k] |= twice
    return int(hit.sum())


def features(text: str | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of a whole text."""
    if not text:
        return 0, 0, 0, 0, 0
    words = text.encode("utf-8", "surrogatepass").split()  # bytes split on the six ASCII spaces only
    n = len(words)
    dup = 0
    if "\n" in text:
        seen: set[str] = set()
        for line in text.split("\n"):
            if line in seen:
                dup += 1
            elif line.strip(SPACES):
                seen.add(line)
    repeated = 0
    if n >= LONG:
        repeated = repeated_words(words)
    elif n > 3:
        windows = list(zip(words, words[1:], words[2:], strict=False))
        first: dict[tuple, int] = {}
        if len(set(windows)) < len(windows):
            end = 0  # words before this index are counted already or not repeated
            twice: set[tuple] = set()
            for w in windows:
                if w in first:
                    twice.add(w)
                else:
                    first[w] = 1
            for i, w in enumerate(windows):
                if w in twice:
                    repeated += i + 3 - max(i, end)
                    end = i + 3
    return n, len(text) - sum(map(text.count, SPACES)), len(_SYMBOLS.findall(text)), dup, repeated


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """(doc_id, host, features..., base_failed) for each row."""

    def run(cols: dict) -> dict:
        found = [features(t) for t in cols["text"]]
        made = dict(zip(("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"), map(list, zip(*found, strict=True)), strict=True))
        return {"doc_id": cols["doc_id"], "host": cols["host"]} | made

    kind = docs.schema[id_col].dataType.simpleString()
    rows = common.map_columns(docs, [docs[id_col].alias("doc_id"), docs[host_col].cast("string").alias("host"), docs[text_col].cast("string").alias("text")], run, f"doc_id {kind}, host string, {FEATURES}")
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return rows.withColumn("base_failed", failed)


def host_verdicts(rows: DataFrame, limit: float = HOST_LIMIT) -> DataFrame:
    """(host, n_docs, n_failed, shrunk_rate, host_kept). Prior by moments: mean m and spread v of host rates, less the binomial
    part of the spread, give a+b = m(1-m)/v - 1."""
    hosts = rows.groupBy("host").agg(F.count(F.lit(1)).alias("n_docs"), F.sum(F.col("base_failed").cast("long")).alias("n_failed"))
    rate = F.col("n_failed") / F.col("n_docs")
    prior = hosts.agg(F.sum("n_failed").alias("f"), F.sum("n_docs").alias("n"), F.coalesce(F.var_samp(rate), F.lit(0.0)).alias("v"), F.avg(1 / F.col("n_docs")).alias("chance")).select(
        ((F.col("f") + 0.5) / (F.col("n") + 1.0)).alias("m"), "v", "chance"
    )
    prior = prior.select("m", (F.col("v") - F.col("m") * (1 - F.col("m")) * F.col("chance")).alias("v"))
    strength = F.greatest(F.lit(1.0), F.least(F.lit(1e6), F.col("m") * (1 - F.col("m")) / F.greatest(F.col("v"), F.lit(1e-12)) - 1))
    # one row of two numbers meets every host
    shrunk = (F.col("n_failed") + F.col("m") * strength) / (F.col("n_docs") + strength)
    out = hosts.join(F.broadcast(prior), F.lit(True)).withColumn("shrunk_rate", shrunk)
    return out.select("host", "n_docs", "n_failed", "shrunk_rate", (F.col("shrunk_rate") <= limit).alias("host_kept"))


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", limit: float = HOST_LIMIT) -> DataFrame:
    """Features, base_failed, the host's shrunk rate and kept, for each row. Texts are read once; hosts are joined by key."""
    rows = common.cut(measured(docs, id_col, text_col, host_col))
    hosts = common.cut(host_verdicts(rows, limit)).select(F.col("host").alias("__host"), "shrunk_rate", "host_kept")
    joined = rows.join(hosts, rows.host.eqNullSafe(hosts["__host"]), "left").drop("__host")
    return joined.withColumn("kept", ~F.col("base_failed") & F.col("host_kept"))


def oracle(limit: float = HOST_LIMIT) -> str:
    """The query in SQL for DuckDB."""
    blank = r"[\x20\x09-\x0D]"
    word = r"[^\x20\x09-\x0D]"
    return f"""WITH d AS MATERIALIZED (SELECT doc_id, source AS host, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{word}+') AS w FROM documents),
lines AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d) WHERE regexp_matches(line, '{word}') GROUP BY 1),
windows AS MATERIALIZED (SELECT doc_id, i, array_to_string(w[i : i + 2], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d)),
repeated AS (SELECT doc_id, count(*) AS n FROM (SELECT DISTINCT doc_id, unnest(range(i, i + 3)) AS at FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS times FROM windows) WHERE times > 1) GROUP BY 1),
f AS MATERIALIZED (SELECT doc_id, host, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(t, '{blank}', '', 'g')) AS BIGINT) AS word_chars,
 CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(lines.n, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(repeated.n, 0) AS BIGINT) AS n_repeat_words
 FROM d LEFT JOIN lines USING (doc_id) LEFT JOIN repeated USING (doc_id)),
j AS MATERIALIZED (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM f),
hosts AS MATERIALIZED (SELECT host, count(*) AS n, count(*) FILTER (WHERE base_failed) AS bad FROM j GROUP BY 1),
prior AS (SELECT (sum(bad) + 0.5::DOUBLE) / (sum(n) + 1.0::DOUBLE) AS m, coalesce(var_samp(bad / n), 0) AS v0, avg(1 / n) AS chance FROM hosts),
strength AS (SELECT m, greatest(1.0::DOUBLE, least(1e6::DOUBLE, m * (1 - m) / greatest(v0 - m * (1 - m) * chance, 1e-12::DOUBLE) - 1)) AS s FROM prior),
verdicts AS (SELECT host, n, (bad + m * s) / (n + s) AS rate FROM hosts, strength)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND rate <= {limit} AS kept, round(rate, 9) AS host_rate
FROM j JOIN verdicts ON j.host IS NOT DISTINCT FROM verdicts.host"""
