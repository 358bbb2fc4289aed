"""Secret scan by assignment-aware lexing.

Statements of the shape ``name = value`` (source code, YAML with block scalars, JSON, INI, shell), augmented assignments,
calls that set a name (``define("NAME", "value")``), XML elements and lists of literals are read into name-literal pairs.
String constants that an earlier line of the same text bound to a name are propagated into later expressions and forgotten
when the name is bound to something else; a call is no literal. Each literal is scored by how sensitive the name is that it reaches and by how much it, or the joined value it is a piece of,
looks like a key.

Defined results: a null or empty text has no spans; a very long text is read once by one task; rows are never dropped, repeated rows give equal results;
offsets are code points, ends are exclusive.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter

from pyspark.sql import DataFrame

from . import common

# The base patterns of the contract, least lengths, and their order at equal starts.
BASE = {
    "assign": (re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A | re.I), 6),
    "access": (re.compile(r"AKIA[A-Z0-9]+"), 20),
    "hex": (re.compile(r"[0-9a-f]{24,}"), 24),
}
KINDS = ["assign", "access", "hex", "literal", "constant"]

# Words of target names, with how sensitive a name is that holds them.
SENSITIVE = {
    "password": 1.0, "passwd": 1.0, "passphrase": 1.0, "pwd": 0.9, "pass": 0.7, "secret": 1.0, "secrets": 1.0,
    "token": 0.9, "apikey": 1.0, "credential": 0.9, "credentials": 0.9, "bearer": 0.8, "authorization": 0.8,
    "privatekey": 1.0, "accesskey": 1.0, "signingkey": 0.9, "encryptionkey": 0.9, "auth": 0.6, "dsn": 0.6,
}
#: Pairs of neighbouring name words that count like the joined word.
PAIRS = {"api key": 1.0, "private key": 1.0, "access key": 1.0, "secret key": 1.0, "signing key": 0.9, "encryption key": 0.9, "client secret": 1.0, "connection string": 0.8}
#: Literals that stand for a value to be filled in.
PLACEHOLDER = re.compile(r"(?i)^(?:change_?me|example|placeholder|redacted|none|null|undefined|true|false|todo|your[_-].*|x{4,}|\*{3,}|\.{3,}|<.*>|\$\{.*\}|\{\{.*\}\}|%\w+%|os\.environ.*|process\.env.*|getenv.*|\$\w+)$")

_NAME_BEFORE = re.compile(r"""([A-Za-z_$][A-Za-z0-9_$.-]*)["'\]]{0,2}[ \t]*$""")
_TYPED = re.compile(r"[ \t]*[A-Za-z_][A-Za-z0-9_.]*(?:\[[A-Za-z0-9_, .\[\]]*\])?[ \t]*=(?!=)")
_OPERATOR = re.compile(r"[:=]")
_REST = re.compile(r"[ \t]*")
_STRING = re.compile(r'''"((?:[^"\\\n]|\\.)*)"|'((?:[^'\\\n]|\\.)*)'|`([^`\n]*)`''')
_SETTER = re.compile(r"""\b(?:define|putenv|setenv|setProperty|set|put|const)\([ \t]*["']([A-Za-z_$][A-Za-z0-9_$.-]*)["'][ \t]*,[ \t]*""")
_ELEMENT = re.compile(r"<([A-Za-z_][A-Za-z0-9_.:-]*)>[ \t]*([^<>\s]+)[ \t]*</")
_BLOCK = re.compile(r"[|>][+-]?[0-9]?[ \t]*\n")
_INDENTED = re.compile(r"[ \t]+([^ \t\n][^\n]*)(?:\n|$)")
_BLANKS = re.compile(r"\s*,?\s*")
_BARE = re.compile(r"[A-Za-z0-9+/_.=~@!%&*^$-]+")
_JOIN = re.compile(r"[ \t]*(?:\+|\.\.|\.(?=[ \t]*[\"'$]))[ \t]*")
_PARTS = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[0-9]+")
#: How far before an operator a name is looked for at first; one that reaches further back is read on to its start.
NAME_REACH = 96
_NAME_LETTERS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789_$.-")


def name_score(name: str) -> float:
    parts = [p.lower() for p in _PARTS.findall(name)]
    best = max((SENSITIVE.get(p, 0.0) for p in parts), default=0.0)
    best = max(best, SENSITIVE.get("".join(parts), 0.0))
    return max([best, *(PAIRS.get(f"{a} {b}", 0.0) for a, b in zip(parts, parts[1:], strict=False))])


def literal_score(value: str) -> float:
    """0 to 1: length, mixture of character classes and entropy; 0 for placeholders and values under six characters."""
    n = len(value)
    if n < 6 or PLACEHOLDER.match(value) or " " in value.strip():
        return 0.0
    entropy = -sum(c / n * math.log2(c / n) for c in Counter(value).values())
    classes = sum(bool(re.search(p, value)) for p in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]"))
    return min(1.0, 0.25 * (n >= 8) + 0.15 * (n >= 16) + 0.2 * (classes >= 2) + 0.1 * (classes >= 3) + 0.5 * min(1.0, entropy / 3.5))


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    if "=" in text or ":" in text:
        pattern, least = BASE["assign"]
        found += [(*m.span(), "assign") for m in pattern.finditer(text) if m.end(2) - m.start(2) >= least]
    if "AKIA" in text:
        pattern, least = BASE["access"]
        found += [(*m.span(), "access") for m in pattern.finditer(text) if m.end() - m.start() >= least]
    found += [(*m.span(), "hex") for m in BASE["hex"][0].finditer(text)]
    return found


def name_before(text: str, low: int, at: int) -> str | None:
    """The name that ends before the operator at `at`, on the same line and not before low. No stretch is read for two
    operators, as none lies inside a name or the blanks after it."""
    near = max(low, at - NAME_REACH)
    before = text[near:at]
    line = before.rfind("\n") + 1
    name = _NAME_BEFORE.search(before[line:])
    if line or near == low or (name and name.start()):
        return name.group(1) if name else None
    end = at
    while end > low and text[end - 1] in " \t":
        end -= 1
    for _ in range(2):
        end -= end > low and text[end - 1] in "\"']"
    first = end
    while first > low and text[first - 1] in _NAME_LETTERS:
        first -= 1
    return text[first:end].lstrip("0123456789.-") or None


class Literals:
    """String literals of a text at given places; triple quotes that do not close are looked for once."""

    def __init__(self, text: str) -> None:
        self.text, self.gone = text, set()

    def at(self, p: int) -> tuple[str, int, int, int] | None:
        """(value, start, end, where it is over) of the string that begins at p."""
        quotes = self.text[p : p + 3]
        if quotes in ('"""', "'''") and quotes not in self.gone:
            stop = self.text.find(quotes, p + 3)
            if stop >= 0:
                return self.text[p + 3 : stop], p + 3, stop, stop + 3
            self.gone.add(quotes)
        if s := _STRING.match(self.text, p):
            g = s.lastindex or 1
            return s.group(g), *s.span(g), s.end()
        return None


def pairs(text: str) -> list[tuple[str, str, int, int, str, str]]:
    """Name-literal pairs: (target name, literal, start, end, 'literal' or 'constant', joined value), constants propagated.

    The joined value is that of all constant pieces of the expression."""
    out = [(m.group(1), m.group(2), *m.span(2), "literal", m.group(2)) for m in _ELEMENT.finditer(text)] if "</" in text else []
    strings = Literals(text)
    if "(" in text:
        for m in _SETTER.finditer(text):
            if found := strings.at(m.end()):
                out.append((m.group(1), *found[:3], "literal", found[0]))
    if "=" not in text and ":" not in text:
        return out
    constants: dict[str, list[tuple[str, int, int]]] = {}
    done = 0
    for m in _OPERATOR.finditer(text):
        at = m.start()
        if at < done:
            continue
        left = at
        if text[at] == "=" and text[at - 1 : at] and text[at - 1] in "+.?|":  # augmented: the name ends before the sign
            left = at - 2 if text[at - 2 : at] in ("||", "??") else at - 1
        target = name_before(text, done, left)
        if not target:
            continue
        p = at + 1
        if text[p : p + 1] in ("=", ">") and text[at] == "=":
            if text[p] == "=":
                continue
            p += 1
        elif text[at] == ":" and text[p : p + 1] == "=":
            p += 1
        elif text[at] == ":" and (typed := _TYPED.match(text, p)):
            p = typed.end()
        p = _REST.match(text, p).end()
        if text[at] == ":" and (block := _BLOCK.match(text, p)):  # YAML block scalar: its indented lines
            p = block.end()
            lines = []
            while line := _INDENTED.match(text, p):
                lines.append((line.group(1).rstrip(), line.start(1), line.start(1) + len(line.group(1).rstrip())))
                p = line.end()
            out += [(target, *x, "literal", x[0]) for x in lines]
            constants.pop(target, None)
            done = max(done, p - 1)
            continue
        if text[p : p + 1] in ("[", "(", "{") and (found := strings.at(_BLANKS.match(text, p + 1).end())):  # a list of literals
            while found:
                out.append((target, *found[:3], "literal", found[0]))
                done = found[3]
                found = strings.at(_BLANKS.match(text, done).end())
            constants.pop(target, None)
            continue
        pieces, joined, called = [], False, False
        while True:
            if s := strings.at(p):
                pieces.append((*s[:3], "literal"))
                p = s[3]
            elif s := _BARE.match(text, p):
                word = s.group().rstrip(".")
                p = s.end()
                if text[p : p + 1] in ("(", "["):
                    called = True
                elif word in constants:
                    pieces += [(*c, "constant") for c in constants[word]]
                else:
                    pieces.append((word, s.start(), s.start() + len(word), "bare"))
            else:
                break
            if called or not (j := _JOIN.match(text, p)):
                break
            p, joined = j.end(), True
        done = max(done, p) if pieces else done
        if not joined and not called and pieces and pieces[0][3] == "bare":
            pieces = [(*pieces[0][:3], "literal")]
        kept = [x for x in pieces if x[3] != "bare"]
        before = constants.pop(target, [])
        if kept:
            constants[target] = [*(before if left < at else []), *(x[:3] for x in kept)]
        whole = "".join(x[0] for x in kept)
        out += [(target, *x, whole) for x in kept]
    return out


def scan(text: str | None, threshold: float = 0.5) -> list[tuple[int, int, str, float]]:
    """All spans (start, end, kind, score), by start and then kind as listed: the base ones and those the lexer adds.

    A literal inside a base span is not reported twice."""
    if not text:
        return []
    base = base_spans(text)
    spans = [(*s, 1.0) for s in base]
    seen: set[tuple[int, int]] = set()
    for target, value, start, end, kind, whole in pairs(text):
        named = name_score(target)
        if not named or start == end or (start, end) in seen:
            continue
        score = named * max(literal_score(value), literal_score(whole) if whole != value else 0.0)
        if score >= threshold and not any(a <= start and end <= b for a, b, _ in base):
            seen.add((start, end))
            spans.append((start, end, kind, score))
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """One row a document: the id and its spans array<struct<start,end,kind,score>> over the whole text; nothing is shuffled."""

    def run(cols: dict) -> dict:
        return {"doc_id": cols["doc_id"], "spans": [[{"start": a, "end": b, "kind": k, "score": s} for a, b, k, s in scan(t, threshold)] for t in cols["text"]]}

    kind = docs.schema[id_col].dataType.simpleString()
    return common.map_columns(docs, [docs[id_col].alias("doc_id"), docs[text_col].cast("string").alias("text")], run, f"doc_id {kind}, spans array<struct<start:int,end:int,kind:string,score:double>>")


def digest(spans: list) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def sha256(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()
