"""Lowering of a variable order to a graph of keyed, shared Spark aggregations ("views").

Variables of one path that no relation ends between form a bag. For each bag it is decided whether its partial sums are
grouped before they are joined further up (see `Views.pushes`); a bag that is not grouped is absorbed by the one above it. What
remains is a tree of stages, each of which is grouped by what it depends on and by the categorical keys its consumers need.

All key sets that need the same partial sums of a stage are one view: one scan and one join, grouped by several key sets at
once, with the united payload of all consumers. Key sets whose union has few groups are first grouped together and then
rolled up. A view packs its sums in one array column, so every consumer reads the same columns and its exchange is reused."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce
from math import ceil

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .monomials import Monomial, by_keys
from .order import VariableOrder
from .query import FeatureQuery
from .statistics import Size, Statistics

#: Payload columns of one grouping: wider ones leave whole-stage code generation (its limit is 100 fields).
WIDEST = 80
#: A bag is grouped before its join if that leaves at most this share of the rows that its sums are made from; a larger share
#: will do where the bag depends on fewer variables than lie above it, as its sums then serve several assignments of the others,
#: and where the join above multiplies its rows.
SHRINK, SHRINK_SHARED = 1 / 16, 1 / 8
#: Key sets are grouped together first if their union has at most this share of the rows.
COVER = 0.125
#: Inputs of at least so many rows are dealt out to all cores where their files make too few splits.
SPREAD = 50_000
#: Joined relations of at most so many rows are sent to every task, so that the rows they meet stay where they are.
SENT = 100_000
#: Rows of the join in each part that is dealt out by a variable, and most rows of a relation in a part that are hashed there.
PART_ROWS, HASHED = 250_000, 200_000

Keys = tuple[str, ...]


@dataclass
class Bag:
    variables: list[str]
    dep: list[str]
    above: list[str]
    relations: list[str]
    children: list[Bag] = field(default_factory=list)
    below: set[str] = field(default_factory=set)


@dataclass
class Stage:
    """Bags that are evaluated by one join and grouping: the top one and those it absorbs."""

    name: str
    variables: set[str]
    dep: list[str]
    relations: list[str]
    children: list[Stage]
    below: set[str]
    needs: dict[Keys, dict[Monomial, None]] = field(default_factory=dict)
    families: dict[tuple[Monomial, ...], list[Keys]] = field(default_factory=dict)
    family_of: dict[Keys, tuple[Monomial, ...]] = field(default_factory=dict)

    @property
    def shape(self) -> tuple:
        return (self.name, tuple(sorted(self.variables)), tuple(c.shape for c in self.children))


@dataclass
class View:
    """A grouped frame of several key sets: its set number column, key columns (null where a set lacks them) and sums."""

    frame: DataFrame
    number: str
    sets: dict[Keys, int]
    keys: Keys
    at: dict[Monomial, str]
    payloads: list[Monomial]
    packed: str


def contract(order: VariableOrder, query: FeatureQuery) -> list[Bag]:
    """The order's bags, one tree a root."""
    deps = order.dependencies(query)
    anchored: dict[str, list[str]] = {}
    for r in query.relations:
        if query.attributes(r):
            anchored.setdefault(order.anchor(query, r), []).append(r)

    def bag(v: str) -> Bag:
        path, above = [v], order.ancestors(v)
        while v not in anchored and len(order.children[v]) == 1:
            v = order.children[v][0]
            path.append(v)
        made = Bag(path, deps[path[0]], above, anchored.get(v, []), [bag(c) for c in order.children[v]])
        made.below = {*path, *(x for c in made.children for x in c.below)}
        return made

    return [bag(r) for r in order.roots]


def power(name: str, exponent: int) -> Column:
    return reduce(lambda a, b: a * b, [F.col(name)] * exponent)


def product(factors: list[Column], exact: bool) -> Column:
    return reduce(lambda a, b: a * b, factors) if factors else F.lit(1).cast("decimal(38,0)" if exact else "double")


def product_sql(factors: list[str], exact: bool) -> str:
    """The product as SQL text: wide payloads are many expressions, and each text is one call to the JVM."""
    return " * ".join(factors) if factors else "cast(1 as decimal(38,0))" if exact else "1D"


def power_sql(name: str, exponent: int) -> str:
    return " * ".join([f"`{name}`"] * exponent)


def plain(m: Monomial) -> Monomial:
    return Monomial(m.cont, ())


class Views:
    """Builds the views of a query under an order.

    eager: None decides for each bag by statistics; True groups every bag, False none; or a callable that decides for a bag."""

    def __init__(self, query: FeatureQuery, order: VariableOrder, eager=None, statistics: Statistics | None = None) -> None:
        self.query, self.order = query, order.validate(query)
        bags = contract(order, query)
        self.root = bags[0] if len(bags) == 1 else Bag([], [], [], [], bags, {x for b in bags for x in b.below})
        self.eager = eager
        self.exact = query.scale is not None
        self._statistics = statistics
        self.made: dict[tuple, View] = {}
        self.number = 0

    @property
    def statistics(self) -> Statistics:
        if self._statistics is None:
            self._statistics = Statistics.of(self.query)
        return self._statistics

    # --- which bags are grouped ---

    def pushes(self, wanted: dict[Keys, list[Monomial]]) -> dict[int, bool]:
        """For each bag below the root whether it is grouped, for key sets with their monomials.

        The estimate is of the rows times sums that reach the bag above, with the grouping and without it. Without it, the
        join of the bag above repeats each row as often as that join is larger."""
        found: dict[int, bool] = {}
        raw: dict[int, Size] = {}

        def joined(sizes: list[Size]) -> Size:
            return reduce(Size.joined, connected(sizes, lambda f: f.distinct.keys(), lambda f: f.rows))

        def measure(bag: Bag) -> Size:
            raw[id(bag)] = joined([*(self.statistics.size(r) for r in bag.relations), *map(measure, bag.children)])
            return raw[id(bag)]

        def visit(bag: Bag, above: float) -> Size:
            frames = [self.statistics.size(r) for r in bag.relations]
            for c in bag.children:
                inner = visit(c, raw[id(bag)].rows)
                if not found[id(c)]:
                    frames.append(inner)
                    continue
                need = projected(wanted, c.below)
                groups = max(self.statistics.groups(inner, [*c.dep, *ks]) for ks in need)
                kept = {*c.dep, *(k for ks in need for k in ks)}
                frames.append(Size(groups, {v: min(n, groups) for v, n in inner.distinct.items() if v in kept}))
            size, need = joined(frames), projected(wanted, bag.below)
            grouped = sum(self.statistics.groups(size, [*bag.dep, *ks]) * len(ms) for ks, ms in need.items())
            share = grouped / max(1.0, sum(size.rows * len(ms) for ms in need.values()))
            repeated = max(1.0, above / max(1.0, raw[id(bag)].rows))
            found[id(bag)] = share <= min(0.5, (SHRINK_SHARED if set(bag.dep) < set(bag.above) else SHRINK) * repeated)
            return size

        def ask(bag: Bag, decide) -> None:
            found[id(bag)] = bool(decide(bag))
            for c in bag.children:
                ask(c, decide)

        if self.eager is None:
            visit(self.root, measure(self.root).rows)
        else:
            ask(self.root, self.eager if callable(self.eager) else lambda _: self.eager)
        return found

    def _stage(self, bag: Bag, pushed: dict[int, bool]) -> Stage:
        made = Stage(bag.variables[0] if bag.variables else "", set(), bag.dep, [], [], bag.below)

        def absorb(b: Bag) -> None:
            made.variables |= set(b.variables)
            made.relations += b.relations
            for c in b.children:
                if pushed[id(c)]:
                    made.children.append(self._stage(c, pushed))
                else:
                    absorb(c)

        absorb(bag)
        return made

    def _require(self, stage: Stage, wanted: dict[Keys, list[Monomial]]) -> None:
        """Unite what all consumers need of the stage and of those below."""
        for ks, ms in wanted.items():
            stage.needs.setdefault(ks, {}).update(dict.fromkeys(ms))
        for c in stage.children:
            self._require(c, projected(wanted, c.below))

    def _settle(self, stage: Stage) -> None:
        """Key sets of equal needs become one view."""
        for ks, ms in stage.needs.items():
            family = tuple(sorted(ms))
            stage.families.setdefault(family, []).append(ks)
            stage.family_of[ks] = family
        for c in stage.children:
            self._settle(c)

    def planned(self, monomials: list[Monomial]) -> list[Stage]:
        """Root stages with what each view computes; key sets whose bags are grouped alike share a tree."""
        groups: dict[tuple, dict[Keys, list[Monomial]]] = {}
        for ks, ms in by_keys(monomials).items():
            groups.setdefault(tuple(sorted(map(plain, ms))), {})[ks] = list(map(plain, ms))
        trees: dict[tuple, Stage] = {}
        for wanted in groups.values():
            stage = self._stage(self.root, self.pushes(wanted))
            self._require(trees.setdefault(stage.shape, stage), wanted)
        for t in trees.values():
            self._settle(t)
        return list(trees.values())

    # --- views ---

    def _name(self, prefix: str) -> str:
        self.number += 1
        return f"__{prefix}{self.number}"

    def view(self, stage: Stage, family: tuple[Monomial, ...], final: bool = False) -> list[View]:
        """The view of a family of the stage's key sets: one; at the root one for each WIDEST payloads."""
        at = (stage.shape, family, tuple(stage.families[family]))
        if at not in self.made:
            pieces = [self._piece(stage, family, list(family[i : i + WIDEST])) for i in range(0, len(family), WIDEST)]
            self.made[at] = pieces if final else [reduce(self._beside, pieces)]
        return self.made[at]

    def _beside(self, a: View, b: View) -> View:
        """Two payloads of the same key sets in one frame."""
        by = [c for c in a.frame.columns if c != a.packed]
        dep = [c for c in by if c != a.number]
        other = b.frame.select(F.col(b.number).alias("__n"), *[F.col(c).alias(f"__r{i}") for i, c in enumerate(dep)], b.packed)
        on = reduce(lambda x, y: x & y, [a.frame[c].eqNullSafe(other[f"__r{i}"]) for i, c in enumerate(dep)], a.frame[a.number] == other["__n"])
        joined = a.frame.join(other, on).drop("__n", *[f"__r{i}" for i in range(len(dep))])
        packed = self._name("p")
        frame = joined.select(*by, F.concat(a.packed, b.packed).alias(packed))
        payloads = [*a.payloads, *b.payloads]
        return View(frame, a.number, a.sets, a.keys, {m: f"`{packed}`[{i}]" for i, m in enumerate(payloads)}, payloads, packed)

    def _piece(self, stage: Stage, family: tuple[Monomial, ...], payloads: list[Monomial]) -> View:
        sets = stage.families[family]
        keys = tuple(sorted({k for ks in sets for k in ks}))
        numbers = {ks: i for i, ks in enumerate(sets)}
        number, names = self._name("s"), [self._name("v") for _ in payloads]
        by_children: dict[tuple, list[Keys]] = {}
        for ks in sets:
            by_children.setdefault(tuple(c.family_of[cut(ks, c.below)] for c in stage.children), []).append(ks)
        parts = []
        for families, mine in by_children.items():
            below = [self.view(c, f)[0] for c, f in zip(stage.children, families, strict=True)]
            frame, size = self._frame(stage, below)
            exprs = []
            for m in payloads:
                factors = [power_sql(v, e) for v, e in m.cont if v in stage.variables]
                factors += [b.at[plain(m.on(c.below))] for c, b in zip(stage.children, below, strict=True)]
                exprs.append(product_sql(factors, self.exact))
            if below:
                parts.append(self._matched(frame, stage, below, mine, numbers, keys, number, [F.expr(f"{e} AS `{n}`") for e, n in zip(exprs, names, strict=True)]))
            else:  # all of the family's sets: a stage without grouped children has one kind of them
                return self._grouped(frame, size, stage.dep, numbers, keys, number, exprs, names, payloads)
        rows = reduce(DataFrame.unionByName, parts)
        return self._packed(self._summed(rows, [number, *stage.dep, *keys], names), numbers, keys, number, names, payloads, stage.dep)

    def _frame(self, stage: Stage, below: list[View], last: str | None = None, dealt: bool = False) -> tuple[DataFrame, Size | None]:
        """The stage's relations and child views, joined from the largest on along shared variables.

        last: a variable whose relation is joined at the end, which leaves the rows dealt by what it shares.
        dealt: whatever the plan, all rows of a value of `last` are in one part."""
        known = self.eager is None
        units = [(self.query.bound(r), self.statistics.size(r) if known else Size(0.0, {})) for r in stage.relations]
        units += [(b.frame, Size(0.0, {})) for b in below]
        ordered = connected(folded(units) if known else units, lambda u: u[0].columns, lambda u: u[1].rows)
        ordered = [ordered[0], *sorted(ordered[1:], key=lambda u: last in u[0].columns)]
        frame = self._spread(*ordered[0]) if known else ordered[0][0]
        n = self._parts(frame, reduce(Size.joined, [s for _, s in ordered]).rows) if dealt else 0
        for i, (other, rows) in enumerate(ordered[1:], 2):
            on = [c for c in other.columns if c in frame.columns]
            if n and on == [last] and i == len(ordered):  # the join keeps rows where their value of `last` has put them
                frame, other, n = frame.repartition(n, last), other if rows.rows <= SENT else other.repartition(n, last).hint("shuffle_hash" if rows.rows <= n * HASHED else "merge"), 0
            other = F.broadcast(other) if 0 < rows.rows <= SENT and on else other
            frame = frame.join(other, on) if on else frame.crossJoin(other)
        frame = frame.repartition(n, last) if n else frame
        return frame, reduce(Size.joined, [s for _, s in ordered]) if known and not below else None

    def _spread(self, rows: DataFrame, size: Size) -> DataFrame:
        """Rows that come in fewer splits than there are cores are dealt out; tables of many files are read as they are."""
        cores = rows.sparkSession.sparkContext.defaultParallelism
        few = 2 * self.statistics.splits.get(tuple(rows.columns), cores) <= cores
        return rows.repartition(cores) if few and size.rows >= SPREAD else rows

    def _parts(self, rows: DataFrame, n: float) -> int:
        return max(1, min(rows.sparkSession.sparkContext.defaultParallelism, ceil(n / 10_000)), ceil(n / PART_ROWS))

    def _matched(self, frame: DataFrame, stage: Stage, below: list[View], sets: list[Keys], numbers: dict[Keys, int], keys: Keys, number: str, payloads: list[Column]) -> DataFrame:
        """Rows of joined child views, each once for every key set that its children's sets make up, other keys masked."""
        wants: dict[tuple, list[int]] = {}
        for ks in sets:
            wants.setdefault(tuple(b.sets[cut(ks, c.below)] for c, b in zip(stage.children, below, strict=True)), []).append(numbers[ks])
        chosen = None
        for place, targets in wants.items():
            here = reduce(lambda a, b: a & b, [F.col(b.number) == n for b, n in zip(below, place, strict=True)])
            value = F.array(*map(F.lit, targets))
            chosen = F.when(here, value) if chosen is None else chosen.when(here, value)
        rows = frame.select(F.explode(chosen).alias(number), "*")
        return rows.select(number, *stage.dep, *masked(keys, numbers, sets, number, rows.columns), *payloads)

    def _grouped(self, frame: DataFrame, size: Size | None, dep: list[str], numbers: dict[Keys, int], keys: Keys, number: str, exprs: list[str], names: list[str], payloads: list[Monomial]) -> View:
        """Group plain rows by every key set at once; sets whose union has few groups share one grouping, which is rolled up."""
        sets = list(numbers)
        if len(sets) == 1:
            sums = self._sums(exprs, names)
            grouped = frame.groupBy(*dep, *keys).agg(*sums).withColumn(number, F.lit(0))
            return self._packed(grouped, numbers, keys, number, names, payloads, dep)
        covers = self._covers(size, dep, sets)
        order = [*dep, *keys]
        bits = {c: 1 << (len(order) - 1 - i) for i, c in enumerate(order)}
        marks = {c: sum(b for k, b in bits.items() if k in keys and k not in c) for c in covers}
        if len(covers) == 1:
            (cover,) = covers
            grouped = frame.groupBy(*dep, *cover).agg(*self._sums(exprs, names)).withColumn("__g", F.lit(marks[cover]).cast("long"))
        else:
            by = [[F.col(c) for c in (*dep, *cover)] for cover in covers]
            grouped = frame.groupingSets(by, *order).agg(F.grouping_id().cast("long").alias("__g"), *self._sums(exprs, names))
        if all(len(inside) == 1 for inside in covers.values()):
            number_of = reduce(lambda w, c: w.when(F.col("__g") == marks[c], numbers[c]), covers, F)
            return self._packed(grouped.withColumn(number, number_of), numbers, keys, number, names, payloads, dep)
        targets = None
        for cover, inside in covers.items():
            value = F.array(*[F.lit(numbers[ks]) for ks in inside])
            targets = F.when(F.col("__g") == marks[cover], value) if targets is None else targets.when(F.col("__g") == marks[cover], value)
        rows = grouped.select(F.explode(targets).alias(number), "*")
        rows = rows.select(number, *dep, *masked(keys, numbers, sets, number, rows.columns), *names)
        return self._packed(self._summed(rows, [number, *dep, *keys], names), numbers, keys, number, names, payloads, dep)

    def _covers(self, size: Size | None, dep: list[str], sets: list[Keys]) -> dict[Keys, list[Keys]]:
        """Unions of key sets to group by, each with the sets that are rolled up from it."""
        if size is None:
            return {ks: [ks] for ks in sets}
        count = {ks: self.statistics.groups(size, [*dep, *ks]) for ks in sets}
        covers: list[tuple[set[str], list[Keys]]] = []
        for ks in sorted(sets, key=lambda s: (-count[s], s)):
            for union, inside in covers:
                both = union | set(ks)
                if self.statistics.groups(size, [*dep, *both]) <= COVER * size.rows:
                    union |= both
                    inside.append(ks)
                    break
            else:
                covers.append((set(ks), [ks]))
        return {tuple(sorted(union)): inside for union, inside in covers}

    def _sums(self, exprs: list[str], names: list[str]) -> list[Column]:
        total = "cast(sum({}) as decimal(38,0))" if self.exact else "sum({})"
        return [F.expr(f"{total.format(e)} AS `{n}`") for e, n in zip(exprs, names, strict=True)]

    def _summed(self, rows: DataFrame, by: list[str], names: list[str]) -> DataFrame:
        return rows.groupBy(*by).agg(*self._sums([f"`{n}`" for n in names], names))

    def _packed(self, grouped: DataFrame, numbers: dict[Keys, int], keys: Keys, number: str, names: list[str], payloads: list[Monomial], dep: list[str]) -> View:
        packed = self._name("p")
        frame = grouped.select(number, *dep, *keys, F.expr(f"array({', '.join(names)}) AS {packed}"))
        return View(frame, number, numbers, keys, {m: f"`{packed}`[{i}]" for i, m in enumerate(payloads)}, payloads, packed)

    # --- results ---

    def results(self, monomials: list[Monomial]) -> list[View]:
        """Views that hold all monomials by all their key sets."""
        return [v for stage in self.planned(monomials) for family in stage.families for v in self.view(stage, family, True)]

    def roots(self, monomials: list[Monomial]) -> Iterator[tuple[Keys, list[Monomial], DataFrame]]:
        """For each key set: monomials and a DataFrame of keys and columns m0, m1, ... in their order."""
        found, given = [], by_keys(monomials)
        for v in self.results(monomials):
            for ks, n in v.sets.items():
                one = v.frame.where(F.col(v.number) == n) if len(v.sets) > 1 else v.frame
                wanted = [m for m in given[ks] if plain(m) in v.at]
                found.append((ks, wanted, one.select(*ks, *[F.expr(f"{v.at[plain(m)]} AS m{i}") for i, m in enumerate(wanted)])))
        return iter(sorted(found, key=lambda r: (len(r[0]), r[0])))

    def joined(self, last: str | None = None, dealt: bool = False) -> DataFrame:
        """The join itself, in the order that moves the largest relation least. last, dealt: see `_frame`."""
        return self._frame(self._stage(self.root, dict.fromkeys(_ids(self.root), False)), [], last, dealt)[0]

    def finest(self, monomials: list[Monomial], last: str | None = None) -> tuple[DataFrame, list[Monomial]]:
        """Joined rows with every needed key, for the kernel that groups by all key sets in one pass over them.

        The payload columns m0, m1, ... are the distinct continuous parts of the monomials."""
        keys = tuple(sorted({k for m in monomials for k in m.cats}))
        wanted = list(dict.fromkeys(map(plain, monomials)))
        frame = self.joined(last)
        return frame.select(*keys, *[F.expr(f"{product_sql([power_sql(v, e) for v, e in m.cont], self.exact)} AS m{i}") for i, m in enumerate(wanted)]), wanted


def _ids(bag: Bag) -> list[int]:
    return [id(bag), *(i for c in bag.children for i in _ids(c))]


def cut(keys: Keys, below: set[str]) -> Keys:
    return tuple(k for k in keys if k in below)


def projected(wanted: dict[Keys, list[Monomial]], below: set[str]) -> dict[Keys, list[Monomial]]:
    """What the given monomials by key set need of a subtree, by its own key sets."""
    out: dict[Keys, dict[Monomial, None]] = {}
    for ks, ms in wanted.items():
        out.setdefault(cut(ks, below), {}).update(dict.fromkeys(plain(m.on(below)) for m in ms))
    return {ks: list(ms) for ks, ms in out.items()}


def connected(units: list, columns, rows) -> list:
    """The units in join order: the largest first, then always the smallest that shares a variable with those before."""
    todo = sorted(units, key=rows)
    out = [todo.pop()]
    seen = set(columns(out[0]))
    while todo:
        at = next((i for i, u in enumerate(todo) if seen & set(columns(u))), 0)
        out.append(todo.pop(at))
        seen |= set(columns(out[-1]))
    return out


def folded(units: list[tuple[DataFrame, Size]]) -> list[tuple[DataFrame, Size]]:
    """Units that meet a single other one, and do not repeat its rows, joined to it first unless it is the largest.

    The largest then moves once for each unit beside it, not once for each relation of a branch."""
    units = list(units)
    while True:
        top = max(units, key=lambda u: u[1].rows)
        for u in units:
            near = [v for v in units if v is not u and set(v[0].columns) & set(u[0].columns)]
            if u is not top and len(near) == 1 and near[0] is not top:
                (v,) = near
                size = v[1].joined(u[1])
                if u[1].rows and v[1].rows and size.rows <= 1.1 * v[1].rows:
                    both = v[0].join(F.broadcast(u[0]) if u[1].rows <= SENT else u[0], [c for c in u[0].columns if c in v[0].columns])
                    units = [(both, size) if w is v else w for w in units if w is not u]
                    break
        else:
            return units


def masked(keys: Keys, numbers: dict[Keys, int], sets: list[Keys], number: str, present: list[str]) -> list[Column]:
    """Each key where the row's key set has it, else null."""
    out = []
    for k in keys:
        having = [numbers[ks] for ks in sets if k in ks]
        if k not in present:
            out.append(F.lit(None).alias(k))
        elif len(having) == len(sets):
            out.append(F.col(k))
        else:
            out.append(F.when(F.col(number).isin(having), F.col(k)).alias(k))
    return out
