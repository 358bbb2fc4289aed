"""Mixing sources to target weights by entropy balancing, DataFrame functions only.

Targets: sources in code-point order (null last) weigh 3, 1, 2, repeating, and share 1.5 times all words; a target stops
at twice its source's words and the excess is shared again by weight. Rates: of all document rates r in [0, 2] whose
expected words meet the targets, those closest to 1 in relative entropy, sum of r*log(r) - r, are
r = min(2, exp(lambda_s * size / mean size)): each source's multiplier solves a convex dual whose gradient and curvature
are sums over its documents, so one Newton step for all sources is one grouped sum. Steps that leave the bracket are
halved into it. Rounding: documents of a source in order of size, their fractional rates summed up; an extra copy is given
where the running sum passes a whole number, and what is then missing is settled with documents smaller than twice the gap
until none has room.

Rates depend on size alone, so the Newton steps run on counts by (source, size) and never on the documents.

Defined results: a null text has size 0 and is taken 0 words; a null source is a source of its own, last in order;
repeated rows are rounded one by one; sources without words have target 0; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

WEIGHTS = (3, 1, 2)
SHARE, MOST = 1.5, 2.0
STEPS, TOLERANCE = 200, 1e-9
#: Rounds of settling in one plan; plans follow until all is settled.
SETTLE = 5
#: One window partition of the rounding holds the rows of a source and size whose ids and texts share a hash modulo the salts:
#: at least SALTS, and one for each SALT_ROWS rows of the table.
SALTS, SALT_ROWS = 64, 1_000_000


def targets(sources: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """(source, source_size, target) from (source, source_size).

    With targets min(cap, w*level), the level is found from sources sorted by cap/w: the first place where the level that
    serves all later ones is at most their ratio. The windows hold one row a source."""
    order = Window.orderBy(F.asc_nulls_last("source"))
    ranked = sources.withColumn("w", F.element_at(F.array(*map(F.lit, weights)), (F.row_number().over(order) - 1) % len(weights) + 1).cast("double"))
    by = Window.orderBy("ratio", F.asc_nulls_last("source"))
    ahead = by.rowsBetween(Window.unboundedPreceding, -1)
    all_ = Window.partitionBy()
    cap = most * F.col("source_size")
    steps = ranked.withColumn("cap", cap).withColumn("ratio", F.col("cap") / F.col("w"))
    steps = steps.withColumn("left", share * F.sum("source_size").over(all_) - F.coalesce(F.sum("cap").over(ahead), F.lit(0.0)))
    steps = steps.withColumn("open", F.sum("w").over(all_) - F.coalesce(F.sum("w").over(ahead), F.lit(0.0)))
    steps = steps.withColumn("level", F.col("left") / F.col("open")).withColumn("place", F.row_number().over(by))
    level = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("place", "level"))).over(all_)["level"]
    return steps.withColumn("level", level).select("source", "source_size", F.least("cap", F.coalesce(F.col("w") * F.col("level"), F.col("cap"))).alias("target"))


def multipliers(cells: DataFrame, goals: DataFrame, most: float = MOST, steps: int = STEPS) -> DataFrame:
    """(source, lam, mean) by safeguarded Newton steps over cells (source, size, n); goals has source, target and mean.

    The state is a table of one row a source, written in the shared folder after each step."""
    state = common.cut(goals.select("source", "target", "mean", F.lit(0.0).alias("lam"), F.lit(None).cast("double").alias("lo"), F.lit(None).cast("double").alias("hi"), F.lit(False).alias("done")))
    cap = F.log(F.lit(float(most)))
    for _ in range(steps):
        s = state.select(F.col("source").alias("__s"), "target", "mean", "lam", "lo", "hi", "done")
        x = F.col("size") / F.col("mean")
        rate = F.exp(F.least(F.col("lam") * x, cap))
        open_ = F.col("lam") * x < cap
        sums = cells.join(s.where("not done"), cells.source.eqNullSafe(s["__s"])).groupBy("__s", "target", "mean", "lam", "lo", "hi").agg(
            F.sum(F.col("n") * F.col("size") * rate).alias("words"), F.sum(F.when(open_, F.col("n") * F.col("size") * x * rate).otherwise(0.0)).alias("slope")
        )
        off = F.col("words") - F.col("target")
        lo, hi = F.when(off < 0, F.col("lam")).otherwise(F.col("lo")), F.when(off > 0, F.col("lam")).otherwise(F.col("hi"))
        newton = F.col("lam") - off / F.when(F.col("slope") > 0, F.col("slope"))
        reach = F.greatest(F.lit(4.0), 3 * F.abs(F.col("lam")))
        step = F.greatest(F.col("lam") - reach, F.least(F.col("lam") + reach, newton))
        middle = F.when(F.col("lo").isNull(), 2 * F.col("lam") - 1.0).when(F.col("hi").isNull(), 2 * F.col("lam") + 1.0).otherwise((F.col("lo") + F.col("hi")) / 2)
        moved = sums.withColumns({"lo": lo, "hi": hi, "step": step})
        inside = F.col("step").isNotNull() & (F.col("lo").isNull() | (F.col("step") > F.col("lo"))) & (F.col("hi").isNull() | (F.col("step") < F.col("hi")))
        near = F.abs(off) <= TOLERANCE * F.greatest(F.col("target"), F.lit(1.0))
        near |= F.col("hi").isNotNull() & F.col("lo").isNotNull() & (F.col("hi") - F.col("lo") < 1e-13)
        near |= F.col("lam") > 1e6  # a target of twice the source is met by large rates only in the limit
        new = moved.select(F.col("__s").alias("source"), "target", "mean", F.when(near, F.col("lam")).when(inside, F.col("step")).otherwise(middle).alias("lam"), "lo", "hi", near.alias("done"))
        state = common.cut(new.unionByName(state.where("done")))
        if state.where("not done").isEmpty():
            return state.select("source", "lam", "mean")
    raise ArithmeticError(f"the dual is not solved after {steps} Newton steps; the state is {state.where('not done').take(3)}")


def rates(docs: DataFrame, source_col: str = "source", text_col: str = "text", weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST, salts: int = SALTS, id_col: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """Cells (source, size, salt, rate, cell, extra, ahead) and the sources' sizes and targets.

    cell documents share source and size, extra copies are added to (or taken from) floor(rate) of each, and ahead of them have a smaller salt."""
    sized = docs.select(F.col(source_col).cast("string").alias("source"), common.word_count(text_col).alias("size"), _salt(id_col, text_col, salts).alias("salt"))
    salted = common.cut(sized.groupBy("source", "size", "salt").agg(F.count(F.lit(1)).alias("n")))
    cells = common.cut(salted.groupBy("source", "size").agg(F.sum("n").alias("n")))
    totals = cells.groupBy("source").agg(F.sum(F.col("n") * F.col("size")).alias("source_size"), F.sum("n").alias("rows"))
    goals = common.cut(targets(totals.select("source", "source_size"), weights, share, most))
    means = totals.select(F.col("source").alias("__m"), (F.col("source_size") / F.col("rows")).alias("mean"))
    solved = multipliers(cells.where("size > 0"), goals.join(means, goals.source.eqNullSafe(means["__m"])).where((F.col("source_size") > 0) & (F.col("target") < most * F.col("source_size") * (1 - 1e-12))), most)
    lam = solved.select(F.col("source").alias("__l"), "lam", "mean")
    goal = goals.select(F.col("source").alias("__g"), "target", (F.col("target") >= most * F.col("source_size") * (1 - 1e-12)).alias("full"))
    at = cells.join(lam, cells.source.eqNullSafe(lam["__l"]), "left").join(goal, cells.source.eqNullSafe(goal["__g"]), "left")
    rate = F.when(F.col("size") == 0, 0.0).when(F.col("full"), float(most)).otherwise(F.coalesce(F.exp(F.least(F.col("lam") * F.col("size") / F.col("mean"), F.log(F.lit(float(most))))), F.lit(0.0)))
    cells = _rounded(at.select("source", "size", "n", "target", rate.alias("rate")), most)
    firsts = cells.select(F.col("source").alias("__c"), F.col("size").alias("__n"), "rate", "extra", F.col("n").alias("cell"))
    inner = F.coalesce(F.sum("n").over(Window.partitionBy("source", "size").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = salted.withColumn("ahead", inner).join(firsts, salted.source.eqNullSafe(firsts["__c"]) & (salted["size"] == firsts["__n"]))
    return placed.select("source", "size", "salt", "rate", "cell", "extra", "ahead"), goals


def _rounded(cells: DataFrame, most: float = MOST) -> DataFrame:
    """Cells (source, size, n, target, rate) with extra: how many copies above floor(rate) a cell's documents get together.

    First by the running sum of fractional rates over a source's cells in order of size. What then is missing to the target is
    settled in rounds until no document smaller than twice the gap has room. Where the size nearest to the gap is above it, one
    such document is moved; else sizes up to the gap are, from the largest down, as many of each as fit. Documents stay within a copy of their rate as long as
    that finds one; else they take 0 to `most` copies. Every round makes the gap smaller."""
    base, part = F.floor("rate"), F.col("rate") - F.floor("rate")
    ahead = Window.partitionBy("source").orderBy("size").rowsBetween(Window.unboundedPreceding, -1)
    larger = Window.partitionBy("source").orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("source")
    before = F.coalesce(F.sum(F.col("n") * part).over(ahead), F.lit(0.0))
    rows = cells.withColumn("k", F.floor(before + F.col("n") * part + 0.5) - F.floor(before + 0.5))
    rows = rows.withColumn("k", F.least(F.greatest(F.col("k"), F.lit(0)), F.when(part > 0, F.col("n")).otherwise(0)))
    rows = rows.withColumn("missing", F.col("target") - F.sum((F.col("n") * base + F.col("k")) * F.col("size")).over(whole))
    gap, up = F.abs("missing"), F.col("missing") > 0
    near = F.when(up, F.when(part > 0, F.col("n") - F.col("k"))).otherwise(F.col("k"))
    wide = F.when(up, F.col("n") * (F.lit(int(most)) - base) - F.col("k")).otherwise(F.col("n") * base + F.col("k"))
    fits = lambda room: (room > 0) & (F.col("size") > 0) & (F.col("size") < 2 * gap)
    some = lambda x: F.coalesce(F.max(x).over(whole), F.lit(False))
    while True:
        for _ in range(SETTLE):
            room = F.greatest(F.coalesce(F.when(some(fits(near)), near).otherwise(wide), F.lit(0)), F.lit(0))
            rows = rows.withColumn("room", room).withColumn("fits", fits(F.col("room")))
            under = F.col("fits") & (F.col("size") <= gap)
            used = F.coalesce(F.sum(F.when(under, F.col("room") * F.col("size")).otherwise(0)).over(larger), F.lit(0))
            greedy = F.when(under, F.greatest(F.lit(0), F.least(F.col("room"), F.floor((gap - used) / F.greatest("size", F.lit(1))))))
            best = F.min(F.when(F.col("fits"), F.struct(F.abs(gap - F.col("size")), "size"))).over(whole)["size"]
            moved = F.coalesce(F.when(best <= gap, greedy).when(F.col("size") == best, 1), F.lit(0)) * F.signum("missing").cast("long")
            rows = rows.withColumn("k", F.col("k") + moved)
            rows = rows.withColumn("missing", F.col("target") - F.sum((F.col("n") * base + F.col("k")) * F.col("size")).over(whole))
        rows = common.cut(rows.select("source", "size", "n", "target", "rate", F.col("k").cast("long").alias("k"), "missing"))
        if rows.where(fits(wide)).isEmpty():
            return rows.select("source", "size", "n", "rate", F.col("k").alias("extra"))


def _salt(id_col: str, text_col: str, salts: int) -> Column:
    """By id and text, so that rows without an id, or with one id, are spread as well."""
    return F.pmod(F.xxhash64(F.coalesce(F.col(id_col).cast("string"), F.lit("")), common.text_or_empty(text_col), F.lit(3)), F.lit(salts))


def _key(source: str) -> Column:
    """The source as a text that is never null, so that joins and windows share a partitioning."""
    return F.coalesce(F.concat(F.lit("="), F.col(source)), F.lit(""))


def mix(docs: DataFrame, keep: list[str] | dict[str, str], id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """The keep columns, size, source_size, target, rate and copies (0, 1 or 2) for each row of docs."""
    salts = max(SALTS, docs.count() // SALT_ROWS)
    placed, goals = rates(docs, source_col, text_col, weights, share, most, salts, id_col)
    placed = common.cut(placed).select(_key("source").alias("__s"), F.col("size").alias("__n"), F.col("salt").alias("__t"), "rate", "cell", "extra", "ahead")
    goals = goals.select(F.col("source").alias("__g"), "source_size", "target")
    shown = {c: f"__k{i}" for i, c in enumerate(keep)}
    rows = docs.select(*[F.col(c).alias(k) for c, k in shown.items()], F.col(source_col).cast("string").alias("source"), common.word_count(text_col).alias("size"), _salt(id_col, text_col, salts).alias("salt"), F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("__id"), F.xxhash64(common.text_or_empty(text_col)).alias("__x"))
    # numbered first, by keys that are never null: the join then finds the rows shuffled and sorted as it needs them
    number = F.row_number().over(Window.partitionBy("__key", "size", "salt").orderBy("__id", "__x"))
    rows = rows.withColumn("__key", _key("source")).withColumn("__number", number)
    rows = rows.join(placed, (rows["__key"] == placed["__s"]) & (rows["size"] == placed["__n"]) & (rows["salt"] == placed["__t"]))
    at = F.col("ahead") + F.col("__number")  # 1 to cell; the extra copies are spread evenly over these numbers
    step = lambda i: F.floor(i * F.col("extra") / F.col("cell"))
    rows = rows.withColumn("__at", at).withColumn("copies", (F.floor("rate") + step(F.col("__at")) - step(F.col("__at") - 1)).cast("long"))
    out = rows.join(goals, rows.source.eqNullSafe(goals["__g"]))
    names = common.named(keep)
    return out.select(*[F.col(k).alias(names[c]) for c, k in shown.items()], F.col("size"), "source_size", "target", "rate", "copies")


def replicated(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """docs with each row as often as the mix takes it; all columns as they came."""
    names = common.masked(docs)
    rows = mix(docs, names, id_col, source_col, text_col, weights, share, most)
    rows = rows.select(*names.values(), F.explode(F.array_repeat(F.lit(0), F.col("copies").cast("int"))).alias("__copy"))
    return common.unmasked(rows, names)
