"""Variable orders: rooted forests in which every relation's variables lie on one path from a root."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from .query import FeatureQuery


@dataclass(frozen=True)
class VariableOrder:
    roots: tuple[str, ...]
    children: dict[str, tuple[str, ...]]
    parent: dict[str, str | None] = field(default_factory=dict)

    @staticmethod
    def parse(text: str) -> VariableOrder:
        """From nested names: ``A(B(C, D), E)``; several roots are separated by commas."""
        tokens = re.findall(r"[A-Za-z_][A-Za-z0-9_]*|[(),]", text)
        if "".join(tokens) != re.sub(r"\s+", "", text):
            raise ValueError(f"cannot read the order {text!r}")
        children: dict[str, list[str]] = {}
        parent: dict[str, str | None] = {}
        roots: list[str] = []
        stack: list[str] = []
        last = None
        for t in tokens:
            if t == "(":
                if last is None:
                    raise ValueError("a bracket follows no variable")
                stack.append(last)
            elif t == ")":
                if not stack:
                    raise ValueError("a bracket is closed that was not opened")
                last = stack.pop()
            elif t != ",":
                if t in parent:
                    raise ValueError(f"{t} occurs twice")
                parent[t] = stack[-1] if stack else None
                (children.setdefault(stack[-1], []) if stack else roots).append(t)
                last = t
        if stack:
            raise ValueError("a bracket stays open")
        return VariableOrder(tuple(roots), {v: tuple(children.get(v, ())) for v in parent}, parent)

    def __str__(self) -> str:
        show = lambda v: v + (f"({', '.join(map(show, self.children[v]))})" if self.children[v] else "")
        return ", ".join(map(show, self.roots))

    def ancestors(self, v: str) -> list[str]:
        out: list[str] = []
        while (v := self.parent[v]) is not None:
            out.append(v)
        return out[::-1]

    def subtree(self, v: str) -> list[str]:
        return [v, *(x for c in self.children[v] for x in self.subtree(c))]

    def validate(self, query: FeatureQuery) -> VariableOrder:
        if lacking := set(query.variables()) - set(self.parent):
            raise ValueError(f"the order lacks {sorted(lacking)}")
        if foreign := set(self.parent) - set(query.variables()):
            raise ValueError(f"no relation uses {sorted(foreign)}")
        for r in query.relations:
            own = query.attributes(r)
            if own and not any(set(own) <= {v, *self.ancestors(v)} for v in own):
                raise ValueError(f"the variables of {r} are not on one path")
        return self

    def anchor(self, query: FeatureQuery, relation: str) -> str:
        return max(query.attributes(relation), key=lambda v: len(self.ancestors(v)))

    def dependencies(self, query: FeatureQuery) -> dict[str, list[str]]:
        """For each variable the ancestors that its subtree shares a relation with, topmost first."""
        out = {}
        for v in self.parent:
            below = set(self.subtree(v))
            needed = {a for r in query.relations if below & set(query.attributes(r)) for a in query.attributes(r)}
            out[v] = [a for a in self.ancestors(v) if a in needed]
        return out

    @staticmethod
    def suggest(query: FeatureQuery, prefer_group_top: bool = True) -> VariableOrder:
        """A valid order: the variable of most relations goes on top, the rest falls into parts that share no variable."""
        children: dict[str, list[str]] = {}
        parent: dict[str, str | None] = {}
        roots: list[str] = []

        def place(relations: dict[str, set[str]], up: str | None) -> None:
            relations = {r: v for r, v in relations.items() if v}
            while relations:
                part, grown = {next(iter(relations))}, True
                while grown:
                    mine = {v for r in part for v in relations[r]}
                    more = {r for r, v in relations.items() if v & mine}
                    grown, part = more != part, more
                inside = {r: relations.pop(r) for r in sorted(part)}
                names = sorted({v for vs in inside.values() for v in vs})
                top = max(names, key=lambda v: (sum(v in vs for vs in inside.values()), prefer_group_top and v in query.categorical, -names.index(v)))
                parent[top] = up
                (roots if up is None else children.setdefault(up, [])).append(top)
                place({r: vs - {top} for r, vs in inside.items()}, top)

        place({r: set(query.attributes(r)) for r in query.relations}, None)
        return VariableOrder(tuple(roots), {v: tuple(children.get(v, ())) for v in parent}, parent)
