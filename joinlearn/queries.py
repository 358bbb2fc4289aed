"""Driver queries of the learner: each runs a method, variant, baseline or measure, with SQL beside it where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import experiments, sqltext, workloads
from .baselines import design, least_squares, stochastic
from .functions import bgd as solver
from .functions.layout import FeatureLayout, SigmaIndex
from .functions.models import FactorizationMachine, Linear, rmse
from .functions.penalties import Ridge
from .operators import dependencies as fd
from .operators import joins, measures, predict
from .operators.moments import keyed_table, linear_entries, lower, moments, occurrences, onehot_query
from .plans.monomials import ONE, Monomial, aggregate_monomials, by_keys, feature_monomials, variable
from .plans.order import VariableOrder
from .plans.query import FeatureQuery
from .plans.registers import build_registers, sharing
from .plans.views import Views
from .sources.tables import table
from .streaming import moments as streams

LAM = 1e-3
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
#: Small feature sets for degree-two plans that are compared with SQL entry by entry.
SMALL_CONT, SMALL_CATS = ("l_discount", "p_size"), ("l_returnflag", "o_orderstatus", "c_mktsegment")


def query(sql: str | None = None):
    def add(f: Callable) -> Callable:
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


# --- moments ---


def _lr(workload: str) -> tuple[Callable, str]:
    cats = {"W1": workloads.CATEGORICAL, "W2": workloads.CATEGORICAL, "W3": (*workloads.CATEGORICAL, "s_nationkey"), "W4": (*workloads.CATEGORICAL, "partkey"), "W4F": tuple(c for c in (*workloads.CATEGORICAL, "partkey") if c not in workloads.PART.determined)}[workload]
    wanted = aggregate_monomials(feature_monomials(workloads.CONTINUOUS, cats), "l_quantity")

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, order = workloads.star(spark, sf_dir, workload, exact=True)
        return keyed_table(lower(q, wanted, order))

    return run, sqltext.star_moments(wanted, workload)


for _name, _w in (("moments_lr_v1", "W1"), ("moments_lr_v2", "W2"), ("moments_lr_v3", "W3"), ("moments_lr_v4", "W4"), ("moments_lr_v4_fd", "W4F")):
    QUERIES[_name], SQL[_name] = _lr(_w)

_PR2 = aggregate_monomials(feature_monomials(SMALL_CONT, SMALL_CATS, 2), "l_quantity")
_FM = aggregate_monomials(feature_monomials(SMALL_CONT, SMALL_CATS, 2, squares=False), "l_quantity")
_LR_SMALL = aggregate_monomials(feature_monomials(SMALL_CONT, SMALL_CATS), "l_quantity")
_W5 = aggregate_monomials(feature_monomials(("value", "l_discount"), ("event_type", "o_orderpriority")), "l_quantity")


def _small(spark: SparkSession, sf_dir: str, workload: str = "W1", exact: bool = True) -> tuple[FeatureQuery, VariableOrder]:
    return workloads.star(spark, sf_dir, workload, exact, SMALL_CONT, SMALL_CATS)


@query(sqltext.star_moments(_PR2, "W1"))
def moments_pr2_v1(spark, sf_dir):
    q, order = _small(spark, sf_dir)
    return keyed_table(lower(q, _PR2, order))


@query(sqltext.star_moments(_FM, "W1"))
def moments_fm_v1(spark, sf_dir):
    q, order = _small(spark, sf_dir)
    return keyed_table(lower(q, _FM, order))


#: Categories of the degree-two plans over the other workloads; W4F is W4 after its dependency partkey -> p_brand.
DEGREE_TWO = {"W2": SMALL_CATS, "W3": ("l_returnflag", "o_orderstatus", "s_nationkey"), "W4": ("l_returnflag", "partkey", "p_brand"), "W4F": ("l_returnflag", "partkey")}


def _degree_two(workload: str, squares: bool) -> tuple[Callable, str]:
    wanted = aggregate_monomials(feature_monomials(SMALL_CONT, DEGREE_TWO[workload], 2, squares=squares), "l_quantity")

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, order = workloads.star(spark, sf_dir, workload, True, SMALL_CONT, DEGREE_TWO[workload])
        return keyed_table(lower(q, wanted, order))

    return run, sqltext.star_moments(wanted, workload)


for _w, _tail in (("W2", "v2"), ("W3", "v3"), ("W4", "v4"), ("W4F", "v4_fd")):
    for _kind, _squares in (("pr2", True), ("fm", False)):
        QUERIES[f"moments_{_kind}_{_tail}"], SQL[f"moments_{_kind}_{_tail}"] = _degree_two(_w, _squares)


def _both(name: str, doc: str | None, run: Callable, sql: Callable) -> None:
    """A query over W1 (a subset of the rows) and as name_v2 over W2 (all rows), each beside its SQL."""
    for tail, workload in (("", "W1"), ("_v2", "W2")):

        def one(spark: SparkSession, sf_dir: str, workload: str = workload) -> DataFrame:
            return run(spark, sf_dir, workload)

        one.__name__, one.__doc__ = f"{name}{tail}", doc
        query(sql(workload))(one)


def _strategy(name: str, doc: str | None, wanted: list[Monomial], ordered: bool, **options) -> None:
    def run(spark: SparkSession, sf_dir: str, workload: str) -> DataFrame:
        q, order = _small(spark, sf_dir, workload)
        return keyed_table(lower(q, wanted, order if ordered else None, **options))

    _both(name, doc, run, lambda w: sqltext.star_moments(wanted, w))


_strategy("moments_all_views_grouped", "Every bag aggregated eagerly, as the variable order says.", _LR_SMALL, True, eager=True)
_strategy("materialized_moments", None, _LR_SMALL, False, strategy="materialize")
_strategy("individual_aggregates", None, _LR_SMALL[:12], False, strategy="individual")
_strategy("order_per_key_set_moments", None, _LR_SMALL, False, strategy="order_per_keys")


@query(f"""WITH {sqltext.STAR.format(where="")} SELECT l_returnflag, o_orderstatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity,
 CAST(grouping(l_returnflag) * 2 + grouping(o_orderstatus) AS BIGINT) AS gid FROM star GROUP BY GROUPING SETS ((), (l_returnflag), (o_orderstatus), (l_returnflag, o_orderstatus))""")
def grouping_sets_moments(spark, sf_dir):
    q, _ = _small(spark, sf_dir, "W2", exact=False)
    sets = [[], ["l_returnflag"], ["o_orderstatus"], ["l_returnflag", "o_orderstatus"]]
    rows = q.listing().groupingSets([[F.col(c) for c in s] for s in sets], "l_returnflag", "o_orderstatus")
    return rows.agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.grouping_id().cast("long").alias("gid"))


@query(f"""WITH {sqltext.STAR.format(where="")} SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM star GROUP BY ROLLUP (o_orderpriority, o_orderstatus)""")
def rollup_cats(spark, sf_dir):
    return _listing(spark, sf_dir).rollup("o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query(f"""WITH {sqltext.STAR.format(where="")} SELECT l_returnflag, l_linestatus, count(*) AS n FROM star GROUP BY CUBE (l_returnflag, l_linestatus)""")
def cube_cats(spark, sf_dir):
    return _listing(spark, sf_dir).cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


def _listing(spark, sf_dir):
    return workloads.star(spark, sf_dir, "W2")[0].listing()


_ONEHOT_SQL_COLS = [("l_returnflag", v) for v in ("A", "N", "R")] + [("l_linestatus", v) for v in ("F", "O")]


def _star(workload: str) -> str:
    return sqltext.STAR.format(where="WHERE l_orderkey % 5 = 0" if workload == "W1" else "")


def _onehot_sql(workload: str) -> str:
    return (f"""WITH {_star(workload)}, x AS (SELECT l_quantity, """ + ", ".join(f"CAST({c} = '{v}' AS BIGINT) AS c{i}" for i, (c, v) in enumerate(_ONEHOT_SQL_COLS)) + """ FROM star)
""" + "\nUNION ALL\n".join([f"SELECT {i} AS i, {j} AS j, CAST(sum(c{i} * c{j}) AS DOUBLE) AS value FROM x" for i in range(5) for j in range(i, 5)] + [f"SELECT {i} AS i, 5 AS j, CAST(sum(c{i} * CAST(l_quantity AS BIGINT)) AS DOUBLE) AS value FROM x" for i in range(5)]))


def _onehot_moments(spark, sf_dir, workload):
    q, order = workloads.star(spark, sf_dir, workload, False, (), ("l_returnflag", "l_linestatus"))
    hot = onehot_query(spark, q)
    order = VariableOrder.suggest(hot)
    names = list(hot.continuous)
    y = variable("l_quantity", False)
    pairs = [(i, j, variable(a, False) * (variable(names[j], False) if j < len(names) else y)) for i, a in enumerate(names) for j in range(i, len(names) + 1)]
    (_, wanted, df), = lower(hot, list(dict.fromkeys(m for _, _, m in pairs)), order)
    at = {m: f"m{i}" for i, m in enumerate(wanted)}
    return df.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(at[m]).alias("value")) for i, j, m in pairs])).alias("e")).select("e.*")


_both("linear_only_onehot_moments", "The linear-only prototype: indicators as continuous columns of the relations, dense scalars.", _onehot_moments, _onehot_sql)


_SCALAR = [m for m in aggregate_monomials(feature_monomials(workloads.CONTINUOUS, ()), "l_quantity") if not m.cats]


@query(sqltext.star_moments(_SCALAR, "W2"))
def scalar_moments_star(spark, sf_dir):
    q, order = workloads.star(spark, sf_dir, "W2", True, categorical=())
    return keyed_table(lower(q, _SCALAR, order))


_PAIRS = [Monomial((), p) for p in by_keys(aggregate_monomials(feature_monomials((), workloads.CATEGORICAL))) if len(p) == 2]


@query(sqltext.star_moments(_PAIRS, "W2"))
def cat_pair_counts(spark, sf_dir):
    q, order = workloads.star(spark, sf_dir, "W2", True, continuous=())
    return keyed_table(lower(q, _PAIRS, order))


_SUMS = [variable(c, True) * variable(z, False) for c in workloads.CATEGORICAL for z in workloads.CONTINUOUS]


@query(sqltext.star_moments(_SUMS, "W2"))
def cat_cont_sums(spark, sf_dir):
    q, order = workloads.star(spark, sf_dir, "W2", True)
    return keyed_table(lower(q, _SUMS, order))


@query("SELECT l_suppkey AS suppkey, CAST(sum(CAST(l_quantity AS BIGINT) * p_size) AS DOUBLE) AS total FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def group_by_root_sum(spark, sf_dir):
    """W8: sum of a product whose factors lie in two branches, for each value of the root."""
    rel = workloads.star_relations(spark, sf_dir)
    q = FeatureQuery({"lineitem": rel["lineitem"].select("partkey", "suppkey", "l_quantity"), "part": rel["part"].select("partkey", "p_size"), "supplier": rel["supplier"].select("suppkey")}, ("p_size",), ("suppkey",), "l_quantity", scale=workloads.SCALES)
    m = Monomial((("l_quantity", 1), ("p_size", 1)), ("suppkey",))
    (_, _, df), = lower(q, [m], VariableOrder.parse("suppkey(partkey(p_size, l_quantity))"))
    return df.select("suppkey", F.col("m0").cast("double").alias("total"))


@query("SELECT count(*) AS n FROM events JOIN orders ON user_id = o_custkey JOIN lineitem ON l_orderkey = o_orderkey")
def count_factorized_w5(spark, sf_dir):
    return measures.count_query(*workloads.many_to_many(spark, sf_dir))


@query(sqltext.moments_sql(_W5, sqltext.EVENTS))
def sum_product_w5(spark, sf_dir):
    q, order = workloads.many_to_many(spark, sf_dir, exact=True)
    return keyed_table(lower(q, _W5, order))


@query(sqltext.moments_sql(_W5, sqltext.EVENTS))
def sum_product_w5_materialized(spark, sf_dir):
    q, _ = workloads.many_to_many(spark, sf_dir, exact=True)
    return keyed_table(lower(q, _W5, strategy="materialize"))


_TOY = """WITH q AS (SELECT c_custkey AS A, c_nationkey AS B, c_acctbal AS C, s_acctbal AS D, o_orderpriority AS E FROM customer JOIN supplier ON c_nationkey = s_nationkey JOIN orders ON c_custkey = o_custkey) """


@query(_TOY + "SELECT variable, entries, local, levels FROM (VALUES ('A', 19, 3), ('B', 9, 2), ('C', 3, 3), ('D', 3, 3), ('E', 2, 2)) t(variable, entries, local) JOIN (" + " UNION ALL ".join(f"SELECT '{v}' AS variable, count(DISTINCT {v}) AS levels FROM q" for v in "ABCDE") + ") USING (variable)")
def toy_registers(spark, sf_dir):
    """Registers of the order, and how many values of each variable they are kept for over the join."""
    q, order = workloads.small_tree(spark, sf_dir)
    found = sharing(build_registers(order.validate(q), q.aggregates(1)), order)
    levels = measures.variable_counts(q, order, grouped=True).withColumnRenamed("n", "levels")
    return measures.table_of(spark, [(v, n, k) for v, n, k, _, _ in found], "variable string, entries int, local int").join(levels, "variable")


@query(_TOY + "SELECT B, E, CAST(count(*) AS DOUBLE) AS n, (SELECT CAST(sum(CAST(round(C * 100) AS HUGEINT) * CAST(round(D * 100) AS HUGEINT)) AS DOUBLE) FROM q) AS cd FROM q GROUP BY B, E")
def toy_counts(spark, sf_dir):
    q, order = workloads.small_tree(spark, sf_dir, exact=True)
    roots = {k: df for k, _, df in lower(q, [Monomial((), ("B", "E")), Monomial((("C", 1), ("D", 1)))], order)}
    return roots[("B", "E")].crossJoin(roots[()].select(F.col("m0").cast("double").alias("cd"))).select("B", "E", F.col("m0").cast("double").alias("n"), "cd")


# --- measures ---


@query("SELECT unnest(['orderkey','partkey','suppkey','custkey','l_quantity','l_extendedprice','l_discount','l_tax','l_returnflag','l_linestatus','p_brand','p_type','p_name','p_size','p_retailprice','o_orderpriority','o_orderstatus','o_totalprice','c_mktsegment','c_acctbal','s_acctbal','s_nationkey']) AS variable, (SELECT count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey) AS n")
def var_counts_star(spark, sf_dir):
    q, order = workloads.star(spark, sf_dir, "W2", extra=("s_nationkey",))
    return measures.variable_counts(q, order)


_W5_SIZES = {"custkey": "custkey", "event_type": "custkey, event_type", "value": "custkey, event_type, value", "orderkey": "custkey, orderkey", "o_orderpriority": "custkey, orderkey, o_orderpriority", "o_orderstatus": "custkey, orderkey, o_orderpriority, o_orderstatus", "o_totalprice": "custkey, orderkey, o_orderpriority, o_orderstatus, o_totalprice", "l_discount": "orderkey, l_discount", "l_extendedprice": "orderkey, l_discount, l_extendedprice", "l_quantity": "orderkey, l_discount, l_extendedprice, l_quantity"}


@query(f"WITH {sqltext.EVENTS} " + " UNION ALL ".join(f"SELECT '{v}' AS variable, count(*) AS n FROM (SELECT DISTINCT {c} FROM star)" for v, c in _W5_SIZES.items()))
def factorized_sizes_w5(spark, sf_dir):
    return measures.factorized_sizes(*workloads.many_to_many(spark, sf_dir))


@query(f"WITH {sqltext.EVENTS}, f AS (SELECT sum(n) AS factorized FROM (" + " UNION ALL ".join(f"SELECT count(*) AS n FROM (SELECT DISTINCT {c} FROM star)" for c in _W5_SIZES.values()) + ")) SELECT (SELECT count(*) * 10 FROM star) AS listing, CAST(factorized AS BIGINT) AS factorized, round((SELECT count(*) * 10 FROM star) / CAST(factorized AS DOUBLE), 6) AS ratio FROM f")
def listing_vs_factorized_w5(spark, sf_dir):
    return measures.compression(*workloads.many_to_many(spark, sf_dir))


_FACT = "suppkey, orderkey, partkey"
_LINE = ("l_returnflag", "l_linestatus", "l_discount", "l_tax", "l_extendedprice", "l_quantity")
#: What each variable of the star's order depends on, itself last.
_W2_SIZES = [
    "suppkey", "suppkey, s_acctbal", "suppkey, s_acctbal, s_nationkey", "suppkey, orderkey", "orderkey, custkey", "custkey, c_mktsegment", "custkey, c_mktsegment, c_acctbal",
    "orderkey, custkey, o_orderpriority", "orderkey, custkey, o_orderpriority, o_orderstatus", "orderkey, custkey, o_orderpriority, o_orderstatus, o_totalprice", _FACT,
    *(", ".join(("partkey", "p_brand", "p_type", "p_name", "p_size", "p_retailprice")[:k]) for k in range(2, 7)), *(", ".join((_FACT, *_LINE[:k])) for k in range(1, 7)),
]


@query(f"WITH {sqltext.STAR.format(where='')}, f AS (SELECT CAST(sum(n) AS BIGINT) AS factorized FROM (" + " UNION ALL ".join(f"SELECT count(*) AS n FROM (SELECT DISTINCT {c} FROM star)" for c in _W2_SIZES) + ")) SELECT (SELECT count(*) * 22 FROM star) AS listing, factorized, round((SELECT count(*) * 22 FROM star) / CAST(factorized AS DOUBLE), 6) AS ratio FROM f")
def compression_w2(spark, sf_dir):
    q, order = workloads.star(spark, sf_dir, "W2", extra=("s_nationkey",))
    return measures.compression(q, order)


def _all_categories(spark, sf_dir):
    """The categories of all workloads over all rows, to be counted once for W2 to W4F."""
    return workloads.star(spark, sf_dir, "W2", continuous=(), categorical=(*workloads.CATEGORICAL, "s_nationkey", "partkey"))


@query("SELECT w AS workload, CAST(9 AS BIGINT) AS continuous, n AS categorical FROM (" + " UNION ALL ".join(f"SELECT '{w}' AS w, (SELECT sum(n)::BIGINT FROM ({' UNION ALL '.join(f'SELECT count(DISTINCT {c}) AS n FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey' for c in cats)})) AS n" for w, cats in (("W2", workloads.CATEGORICAL), ("W3", (*workloads.CATEGORICAL, "s_nationkey")), ("W4", (*workloads.CATEGORICAL, "l_partkey")))) + ")")
def feature_counts(spark, sf_dir):
    _, found = occurrences(*_all_categories(spark, sf_dir), pairs=False)
    rows = []
    for w in ("W2", "W3", "W4"):
        q, _ = workloads.star(spark, sf_dir, w)
        rows.append((w, 1 + len(q.continuous), sum(found[(c,)] for c in q.categorical)))
    return measures.table_of(spark, rows, "workload string, continuous long, categorical long")


def _entry_counts_sql(workload: str) -> str:
    """Rows, one-hot width and occurring pairs of a workload in one pass; the counting identities give the rest."""
    cats = {"W3": (*workloads.CATEGORICAL, "s_nationkey"), "W4": (*workloads.CATEGORICAL, "partkey"), "W4F": tuple(c for c in (*workloads.CATEGORICAL, "partkey") if c not in workloads.PART.determined)}.get(workload, workloads.CATEGORICAL)
    levels = " + ".join(f"count(DISTINCT {c})" for c in cats)
    pairs = " + ".join(f"count(DISTINCT ({a}, {b}))" for i, a in enumerate(cats) for b in cats[i + 1 :])
    where = "WHERE orderkey % 5 = 0" if workload == "W1" else ""
    return f"SELECT '{workload}' AS workload, CAST(count(*) AS DOUBLE) AS n_rows, {levels} AS onehot, {pairs} AS pairs FROM star {where}"


def _entries_sql(*names: str) -> str:
    return f"WITH {sqltext.STAR.format(where='')}, c AS ({' UNION ALL '.join(map(_entry_counts_sql, names))}), e AS (SELECT workload, n_rows, CAST(55 AS BIGINT) AS scalar, onehot * 10 + pairs AS grouped, 9 + onehot AS width FROM c) "


@query(_entries_sql("W1", "W2", "W3", "W4", "W4F") + "SELECT *, CAST(width * (width + 1) AS DOUBLE) / 2 / (scalar + grouped) AS dense_per_entry FROM e")
def aggregate_counts_lr(spark, sf_dir):
    """Scalar and grouped entries with and without the dependency, and dense pairs for each entry."""
    rows, of = [], {"W1": occurrences(*workloads.star(spark, sf_dir, "W1", continuous=()))}
    whole = occurrences(*_all_categories(spark, sf_dir))
    for w in ("W1", "W2", "W3", "W4", "W4F"):
        n, found = of.get(w, whole)
        s, g, width = linear_entries(workloads.star(spark, sf_dir, w)[0], found)
        rows.append((w, float(n), s, g, width, measures.sparsity_gain(width, s + g)))
    return measures.table_of(spark, rows, "workload string, n_rows double, scalar long, grouped long, width long, dense_per_entry double")


@query(_entries_sql("W4") + "SELECT width * (width + 1) // 2 AS dense, scalar + grouped AS entries, CAST(width * (width + 1) AS DOUBLE) / 2 / (scalar + grouped) AS ratio FROM e")
def dense_vs_sparse_ratio(spark, sf_dir):
    _, found = occurrences(*workloads.star(spark, sf_dir, "W4", continuous=()))
    s, g, width = linear_entries(workloads.star(spark, sf_dir, "W4")[0], found)
    return measures.table_of(spark, [(width * (width + 1) // 2, s + g, measures.sparsity_gain(width, s + g))], "dense long, entries long, ratio double")


@query(_entries_sql("W2", "W3", "W4") + "SELECT workload, 8 AS continuous, onehot, c.pairs, scalar AS scalars, grouped FROM e JOIN c USING (workload)".replace("onehot", "CAST(c.onehot AS BIGINT) AS onehot"))
def entry_identities(spark, sf_dir):
    """The counting identities of each workload, from the levels and pairs that occur in its join."""
    _, found = occurrences(*_all_categories(spark, sf_dir))
    rows = []
    for w in ("W2", "W3", "W4"):
        q, _ = workloads.star(spark, sf_dir, w)
        k, onehot = len(q.continuous), sum(found[(c,)] for c in q.categorical)
        pairs = sum(n for ks, n in found.items() if len(ks) == 2 and set(ks) <= set(q.categorical))
        rows.append((w, k, onehot, pairs, measures.expected_scalars(k), measures.expected_lr_entries(onehot, k, pairs)))
    return measures.table_of(spark, rows, "workload string, continuous int, onehot long, pairs long, scalars long, grouped long")


# --- functional dependencies ---


@query("SELECT 'p_brand' AS determined, (SELECT count(*) FROM (SELECT p_partkey FROM part GROUP BY 1 HAVING count(DISTINCT p_brand) > 1)) AS violations UNION ALL SELECT 'p_type', (SELECT count(*) FROM (SELECT p_partkey FROM part GROUP BY 1 HAVING count(DISTINCT p_type) > 1)) UNION ALL SELECT 'brand->type', (SELECT count(*) FROM (SELECT p_brand FROM part GROUP BY 1 HAVING count(DISTINCT p_type) > 1))")
def fd_check_part(spark, sf_dir):
    part = workloads.star_relations(spark, sf_dir)["part"]
    cases = [("p_brand", "partkey", "p_brand"), ("p_type", "partkey", "p_type"), ("brand->type", "p_brand", "p_type")]
    out = None
    for name, a, b in cases:
        n = fd.violations(part, a, b).agg(F.count(F.lit(1)).alias("violations")).select(F.lit(name).alias("determined"), "violations")
        out = n if out is None else out.unionByName(n)
    return out


@query("SELECT p_brand, count(DISTINCT p_partkey) AS n, CAST(min(p_partkey) AS BIGINT) AS first, CAST(max(p_partkey) AS BIGINT) AS last FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem) GROUP BY 1")
def fd_map_brand(spark, sf_dir):
    q, _ = workloads.star(spark, sf_dir, "W4")
    m = fd.dependency_map(q, "partkey", "p_brand")
    return m.select("p_brand", F.size("members").cast("long").alias("n"), F.array_min("members").alias("first"), F.array_max("members").alias("last"))


@query("SELECT p_brand AS determined, count(*) AS n, CAST(sum(p_size) AS DOUBLE) AS total, CAST(sum(p_size) AS DOUBLE) / (1 + count(*)) AS share FROM part GROUP BY 1")
def fd_penalty_group_sums(spark, sf_dir):
    part = workloads.star_relations(spark, sf_dir)["part"]
    gamma = part.select(F.col("partkey").alias("level"), F.col("p_size").cast("double").alias("value"))
    return fd.penalty_table(gamma, part.select(F.col("partkey").alias("level"), F.col("p_brand").alias("determined")))


def _fit(mom, model, **options):
    return model.attach(SigmaIndex(FeatureLayout(mom, model.h))), options


def _result(spark, rows):
    return measures.table_of(spark, rows, "method string, runs long, status string, objective double, rmse double, gap double")


@query()
def fd_chain_supplier(spark, sf_dir):
    """W9: fit with and without the chain dependency; gap is the largest difference of recovered parameters."""
    q, order, dep = workloads.supplier_chain(spark, sf_dir)
    full = Linear(q).attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), order, kernel="sql"), q.feature_map(1))))
    exact = solver.solve_exact(full, LAM)
    r, rorder, _ = workloads.supplier_chain(spark, sf_dir, reduced=True)
    small = Linear(r).attach(SigmaIndex(FeatureLayout(moments(r, r.aggregates(1), rorder, kernel="sql"), r.feature_map(1))))
    groups = fd.groupings(q, dep, small.layout)
    pen = fd.merged_penalty(small, dep, groups)
    fit = solver.bgd(small, LAM, penalty=pen, max_iter=5000, tol=1e-10, precondition="diag")
    own = fd.recover(small, fit.theta, dep, groups)["suppkey"]
    gap = float(np.abs(own - exact[full.layout.block(variable("suppkey", True))]).max())
    from .functions.models import objective

    return _result(spark, [("full", 0, "exact", objective(full, exact, LAM, Ridge(full.width)), rmse(full, exact), 0.0), ("dependency", fit.runs, fit.status, fit.objective, rmse(small, fit.theta), gap)])


# --- fits ---


def _fm_start(model: FactorizationMachine, seed: int = 0) -> np.ndarray:
    """The random start with the factors of large columns made small: raw prices would start, and stay, far off."""
    theta = model.start(seed)
    size = np.sqrt(np.maximum(model.sigma.diagonal()[1 : model.linear], 1.0))
    theta[model.linear : model.linear + model.factors * model.rank] /= np.repeat(size, model.rank)
    return theta


def _fit_query(model_of, workload="W1", small=False, **options):
    def run(spark, sf_dir):
        q, order = workloads.star(spark, sf_dir, workload, False, *((SMALL_CONT, DEGREE_TWO.get(workload, SMALL_CATS)) if small else ()))
        model = model_of(q)
        mom = moments(q, aggregate_monomials(model.h, q.response), order)
        model.attach(SigmaIndex(FeatureLayout(mom, model.h)))
        fit = solver.bgd(model, LAM, theta0=_fm_start(model) if isinstance(model, FactorizationMachine) else None, **options)
        gap = 0.0
        if type(model) is Linear and model.width < 3000:
            gap = float(abs(fit.objective - solver.objective(model, solver.solve_exact(model, LAM), LAM, Ridge(model.width))))
        return _result(spark, [("bgd", fit.runs, fit.status, fit.objective, rmse(model, fit.theta), gap)])

    return run


_LR_FIT = {"precondition": "diag", "tol": 1e-7, "max_iter": 2000}
QUERIES["lr_fit_v1"] = _fit_query(Linear, "W1", **_LR_FIT)
QUERIES["lr_fit_v2"] = _fit_query(Linear, "W2", **_LR_FIT)
QUERIES["lr_fit_v3"] = _fit_query(Linear, "W3", **_LR_FIT)
QUERIES["lr_fit_v4"] = _fit_query(Linear, "W4", **_LR_FIT)
QUERIES["lr_fit_bb2"] = _fit_query(Linear, "W2", **_LR_FIT, step="bb2")
_FM_FIT = {"precondition": "diag", "tol": None, "max_iter": 300}
#: fm_fit_vN learn all features of W1 to W4, pr2_fit_vN those of W1 to W3; pr2_fit_v4, and those named small, learn five columns.
for _name, _w, _few in (("v1", "W1", False), ("v2", "W2", False), ("v3", "W3", False), ("v4", "W4", True), ("small_v1", "W1", True), ("small_v2", "W2", True), ("small_v3", "W3", True)):
    QUERIES[f"pr2_fit_{_name}"] = _fit_query(lambda q: Linear(q, 2), _w, _few, **_LR_FIT)
    _few = _few and _w != "W4"
    QUERIES[f"fm_fit_{_name}"] = _fit_query(lambda q: FactorizationMachine(q, 8), _w, _few, **_FM_FIT)


@query()
def lr_fit_v4_fd(spark, sf_dir):
    """LR over the reduced features of W4 with the reparameterised penalty."""
    q, order = workloads.star(spark, sf_dir, "W4F")
    model = Linear(q).attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), order), q.feature_map(1))))
    groups = fd.groupings(q, workloads.PART, model.layout)
    fit = solver.bgd(model, LAM, penalty=fd.merged_penalty(model, workloads.PART, groups), **_LR_FIT)
    return _result(spark, [("bgd+fd", fit.runs, fit.status, fit.objective, rmse(model, fit.theta), 0.0)])


def _fd_small(spark, sf_dir):
    cats = ("partkey", "p_brand", "p_type", "l_returnflag")
    full = workloads.star(spark, sf_dir, "W2", False, ("l_discount",), cats)
    return full, workloads.star(spark, sf_dir, "W2", False, ("l_discount",), ("partkey", "l_returnflag")), fd.Dependency("partkey", ("p_brand", "p_type"))


@query()
def pr2_fit_fd(spark, sf_dir):
    (fq, forder), (rq, rorder), dep = _fd_small(spark, sf_dir)
    rows = []
    for name, q, order in (("full", fq, forder), ("dependency", rq, rorder)):
        model = Linear(q, 2)
        model.attach(SigmaIndex(FeatureLayout(moments(q, aggregate_monomials(model.h, q.response), order), model.h)))
        pen = fd.merged_penalty(model, dep, fd.groupings(fq, dep, model.layout)) if name == "dependency" else None
        fit = solver.bgd(model, LAM, penalty=pen, **_LR_FIT)
        rows.append((name, fit.runs, fit.status, fit.objective, rmse(model, fit.theta), abs(fit.objective - rows[0][3]) if rows else 0.0))
    return _result(spark, rows)


@query()
def fm_fit_fd(spark, sf_dir):
    (fq, _), (rq, rorder), dep = _fd_small(spark, sf_dir)
    model = fd.DependentFM(rq, dep, 4)
    model.attach(SigmaIndex(FeatureLayout(moments(rq, aggregate_monomials(model.h, rq.response), rorder), model.h)))
    model.with_groups(fd.groupings(fq, dep, model.layout))
    fit = solver.bgd(model, LAM, tol=None, max_iter=100, seed=1, penalty=model)
    return _result(spark, [("fm+fd", fit.runs, fit.status, fit.objective, rmse(model, fit.theta), 0.0)])


_RIDGE = """SELECT CAST(round(w, 9) AS DOUBLE) AS slope, CAST(round((sy - w * sx) / n / (1 + 0.001), 9) AS DOUBLE) AS intercept FROM (SELECT n, sx, sy,
 (sxy / n - sx * sy / (n * n) / 1.001) / (sxx / n + 0.001 - sx * sx / (n * n) / 1.001) AS w FROM (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(sum(p_size) AS DOUBLE) AS sx,
 CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS sy, CAST(sum(p_size * p_size) AS DOUBLE) AS sxx, CAST(sum(p_size * CAST(l_quantity AS BIGINT)) AS DOUBLE) AS sxy FROM lineitem JOIN part ON l_partkey = p_partkey))"""


def _one_feature(spark, sf_dir):
    rel = workloads.star_relations(spark, sf_dir)
    q = FeatureQuery({"lineitem": rel["lineitem"].select("partkey", "l_quantity"), "part": rel["part"].select("partkey", "p_size")}, ("p_size",), (), "l_quantity", scale=workloads.SCALES)
    return Linear(q).attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), VariableOrder.parse("partkey(p_size, l_quantity)"), kernel="sql"), q.feature_map(1))))


@query(_RIDGE)
def ridge_one_feature(spark, sf_dir):
    theta = solver.solve_exact(_one_feature(spark, sf_dir), LAM)
    return measures.table_of(spark, [(round(float(theta[1]), 9), round(float(theta[0]), 9))], "slope double, intercept double")


@query(_RIDGE.replace(', 9)', ', 6)'))
def ridge_by_descent(spark, sf_dir):
    """The same parameters from batch gradient descent run to convergence."""
    fit = solver.bgd(_one_feature(spark, sf_dir), LAM, tol=1e-14, max_iter=5000, precondition="diag")
    return measures.table_of(spark, [(round(float(fit.theta[1]), 6), round(float(fit.theta[0]), 6))], "slope double, intercept double")


@query("WITH RECURSIVE m AS (SELECT CAST(sum(p_size) AS DOUBLE) / count(*) AS sx, CAST(sum(p_size * p_size) AS DOUBLE) / count(*) AS sxx, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) / count(*) AS sy, CAST(sum(p_size * CAST(l_quantity AS BIGINT)) AS DOUBLE) / count(*) AS sxy FROM lineitem JOIN part ON l_partkey = p_partkey), b(run, a, w) AS (SELECT 0, CAST(0 AS DOUBLE), CAST(0 AS DOUBLE) UNION ALL SELECT run + 1, a - 0.001 * (a + sx * w - sy + 0.001 * a), w - 0.001 * (sx * a + sxx * w - sxy + 0.001 * w) FROM b, m WHERE run < 50) SELECT run, round(a, 9) AS intercept, round(w, 9) AS slope FROM b WHERE run IN (1, 10, 50)")
def bgd_fixed_recursive(spark, sf_dir):
    model = _one_feature(spark, sf_dir)
    rows = []
    for n in (1, 10, 50):
        fit = solver.bgd(model, LAM, tol=None, max_iter=n, step="fixed", fixed_step=0.001)
        rows.append((n, round(float(fit.theta[0]), 9), round(float(fit.theta[1]), 9)))
    return measures.table_of(spark, rows, "run int, intercept double, slope double")


@query("SELECT l_returnflag, round(s / n / (CAST(n AS DOUBLE) / t + 0.001) * (CAST(n AS DOUBLE) / t), 9) AS coefficient FROM (SELECT l_returnflag, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS s, (SELECT count(*) FROM lineitem) AS t FROM lineitem GROUP BY 1)")
def ridge_per_category(spark, sf_dir):
    """One categorical feature without an intercept: its normal equations are diagonal."""
    q = FeatureQuery({"lineitem": workloads.star_relations(spark, sf_dir)["lineitem"].select("l_returnflag", "l_quantity")}, (), ("l_returnflag",), "l_quantity", scale=workloads.SCALES)
    (_, _, df), (_, _, per) = lower(q, [ONE, Monomial((), ("l_returnflag",)), Monomial((("l_quantity", 1),), ("l_returnflag",))])
    total = df.select(F.col("m0").cast("double").alias("t"))
    n, s = F.col("m0").cast("double"), F.col("m1").cast("double")
    return per.crossJoin(F.broadcast(total)).select("l_returnflag", F.round(s / n / (n / F.col("t") + LAM) * (n / F.col("t")), 9).alias("coefficient"))


def _small_model(spark, sf_dir, workload="W2"):
    q, order = workloads.star(spark, sf_dir, workload, False, SMALL_CONT, SMALL_CATS)
    model = Linear(q).attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), order), q.feature_map(1))))
    return q, model, solver.solve_exact(model, LAM)


@query()
def predict_lr(spark, sf_dir):
    """Scores of all rows of the join with coefficients fitted from moments."""
    q, model, theta = _small_model(spark, sf_dir)
    return predict.predict(model, theta, q.listing())


@query()
def rmse_from_moments(spark, sf_dir):
    """Error from moments beside the error of actual predictions."""
    q, model, theta = _small_model(spark, sf_dir)
    e = predict.predict(model, theta, q.listing()).agg(F.sqrt(F.avg((F.col("prediction") - F.col("l_quantity")) ** 2)).alias("from_rows"))
    return e.withColumn("from_moments", F.lit(rmse(model, theta)))


def _matvec_sql(workload: str) -> str:
    return f"""WITH {_star(workload)}, r AS MATERIALIZED (SELECT row_number() OVER () AS rid, CAST(l_quantity AS DOUBLE) AS y, * FROM star),
x AS MATERIALIZED (SELECT rid, y, 0 AS block, '' AS level, CAST(1 AS DOUBLE) AS v FROM r UNION ALL SELECT rid, y, 1, '', l_discount FROM r UNION ALL SELECT rid, y, 2, '', p_size FROM r
 UNION ALL SELECT rid, y, 3, l_returnflag, 1 FROM r UNION ALL SELECT rid, y, 4, o_orderstatus, 1 FROM r UNION ALL SELECT rid, y, 5, c_mktsegment, 1 FROM r),
c AS (SELECT block, level, sum(v * y) / (SELECT count(*) FROM r) AS c FROM x GROUP BY ALL), s AS (SELECT rid, sum(v * c) AS s FROM x JOIN c USING (block, level) GROUP BY 1),
p AS (SELECT block, level, round(sum(v * s) / (SELECT count(*) FROM r), 4) AS p FROM x JOIN s USING (rid) GROUP BY ALL)
SELECT row_number() OVER (ORDER BY block, level) - 1 AS i, p AS value, p AS driver FROM p"""


def _matvec(spark, sf_dir, workload):
    _, model, _ = _small_model(spark, sf_dir, workload)
    g = model.sigma.c
    gdf = measures.table_of(spark, [(i, float(v)) for i, v in enumerate(g)], "i long, value double")
    own = measures.table_of(spark, [(i, float(v)) for i, v in enumerate(model.sigma.matvec(g))], "i long, driver double")
    return predict.matvec_table(predict.sigma_table(model.sigma, spark), gdf).join(own, "i").select("i", F.round("value", 4).alias("value"), F.round("driver", 4).alias("driver"))


_both("distributed_matvec", "Sigma times the response correlations, as a join and a grouping, beside the driver's product.", _matvec, _matvec_sql)


# --- baselines ---


def _encoded(spark, sf_dir, drop_first=True, workload="W2"):
    q, _ = workloads.star(spark, sf_dir, workload, False, SMALL_CONT, SMALL_CATS)
    return design.onehot_encode(q.listing(), list(SMALL_CATS), drop_first)


def _onehot_width_sql(workload: str) -> str:
    return f"WITH {_star(workload)} SELECT count(*) AS n, (SELECT count(DISTINCT l_returnflag) + count(DISTINCT o_orderstatus) + count(DISTINCT c_mktsegment) FROM star) AS width FROM star"


def _onehot_width(spark, sf_dir, workload):
    rows, names = _encoded(spark, sf_dir, False, workload)
    return rows.agg(F.count(F.lit(1)).alias("n"), F.lit(len(names)).cast("long").alias("width"))


_both("onehot_width", None, _onehot_width, _onehot_width_sql)


def _zero_suppressed_sql(workload: str) -> str:
    return f"WITH {_star(workload)} SELECT CAST(l_quantity AS DOUBLE) AS label, (CASE WHEN l_discount <> 0 THEN 1 ELSE 0 END) + (CASE WHEN p_size <> 0 THEN 1 ELSE 0 END) + 3 AS kept, count(*) AS n FROM star GROUP BY 1, 2"


def _zero_suppressed(spark, sf_dir, workload):
    q, _ = workloads.star(spark, sf_dir, workload, False, SMALL_CONT, SMALL_CATS)
    rows = design.to_sparse_rows(q.listing(), list(SMALL_CONT), list(SMALL_CATS), "l_quantity")
    return rows.groupBy("label", F.size("indices").alias("kept")).agg(F.count(F.lit(1)).alias("n"))


_both("zero_suppressed_rows", None, _zero_suppressed, _zero_suppressed_sql)


def _coefficients(spark, columns, theta):
    return measures.table_of(spark, [(n, float(t)) for n, t in zip(["1", *columns], theta, strict=True)], "feature string, coefficient double")


def _dense_columns(names):
    return [*SMALL_CONT, *names]


@query()
def ols_closed_form(spark, sf_dir):
    rows, names = _encoded(spark, sf_dir)
    return _coefficients(spark, _dense_columns(names), least_squares.closed_form(rows, _dense_columns(names), "l_quantity"))


@query()
def ols_qr(spark, sf_dir):
    rows, names = _encoded(spark, sf_dir)
    return _coefficients(spark, _dense_columns(names), least_squares.by_qr(rows, _dense_columns(names), "l_quantity"))


@query()
def ols_glm(spark, sf_dir):
    rows, names = _encoded(spark, sf_dir)
    return _coefficients(spark, _dense_columns(names), least_squares.glm(rows, _dense_columns(names), "l_quantity"))


@query()
def rank_deficient_chunks(spark, sf_dir):
    rows, names = _encoded(spark, sf_dir, drop_first=False)
    return least_squares.chunk_ranks(rows, _dense_columns(names), 500)


@query()
def design_limits(spark, sf_dir):
    """Which competitor stops, and why, at limits scaled to these tables."""
    rows, names = _encoded(spark, sf_dir, drop_first=False)
    cols = _dense_columns(names)
    cases = [("closed_form", lambda: least_squares.closed_form(rows, cols, "l_quantity", max_columns=8)), ("qr", lambda: least_squares.by_qr(rows, cols, "l_quantity", value_limit=1000)), ("chunked", lambda: least_squares.chunked(rows, cols, "l_quantity", 500))]
    return measures.table_of(spark, [(n, measures.status_of(f)[0]) for n, f in cases], "method string, status string")


@query()
def sgd_ftrl_fit(spark, sf_dir):
    """One epoch in stored order, minibatches of 1,000."""
    q, order = workloads.star(spark, sf_dir, "W2", False, SMALL_CONT, SMALL_CATS)
    rows, width = design.sparse_rows(Views(q, order).joined(), list(SMALL_CONT), list(SMALL_CATS), "l_quantity")
    scale = np.ones(width)
    scale[1] = 50.0
    w, n = stochastic.sgd_ftrl(rows, width, 1000, alpha=5.0, scale=scale)
    return measures.table_of(spark, [(i, float(x), n) for i, x in enumerate(w)], "slot int, weight double, batches int")


@query()
def fm_sgd_fit(spark, sf_dir):
    rows, names = _encoded(spark, sf_dir, False)
    errors = [(s, stochastic.fm_sgd(rows, _dense_columns(names), "l_quantity", 4, s, 10)[1]) for s in (1e-4, 10.0)]
    return measures.table_of(spark, [(s, float(e)) for s, e in errors], "step double, rmse double")


@query()
def fm_mcmc_fit(spark, sf_dir):
    q, order = workloads.star(spark, sf_dir, "W2", False, SMALL_CONT, SMALL_CATS)
    rows, width = design.sparse_rows(Views(q, order).joined(), list(SMALL_CONT), list(SMALL_CATS), "l_quantity")
    got = stochastic.fm_mcmc(rows, width, max_rows=10_000_000)  # a driver that cannot hold all combinations of features fails
    return measures.table_of(spark, [(got["rmse"], got["baseline_rmse"], got["runs"])], "rmse double, spread double, runs int")


@query("SELECT '1' AS feature, round(-CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) / count(*), 6) AS gradient FROM lineitem JOIN part ON l_partkey = p_partkey UNION ALL SELECT 'p_size', round(-CAST(sum(CAST(l_quantity AS BIGINT) * p_size) AS DOUBLE) / count(*), 6) FROM lineitem JOIN part ON l_partkey = p_partkey")
def factorized_gradient(spark, sf_dir):
    """The first gradient (at zero) pushed through the join instead of moments."""
    rel = workloads.star_relations(spark, sf_dir)
    g = least_squares.gradient_through_joins(rel["lineitem"].select("partkey", "l_quantity"), [(rel["part"], "partkey", ["p_size"])], [], "l_quantity", {"1": 0.0, "p_size": 0.0})
    return g.select("feature", F.round("gradient", 6).alias("gradient"))


# --- operators around ---


@query("SELECT count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def semi_join_reduce(spark, sf_dir):
    q, _ = workloads.star(spark, sf_dir, "W2")
    return measures.semi_reduced(q, 1)["orders"].agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderkey AS orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def anti_join_dangling(spark, sf_dir):
    q, _ = workloads.star(spark, sf_dir, "W2")
    return measures.dangling(q, "orders", "lineitem").select("orderkey")


@query("WITH a AS (SELECT user_id, day(ts) AS dom, count(*) AS n_events, max(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) AS saw_click FROM events GROUP BY 1, 2) SELECT saw_click, CAST(count(*) AS BIGINT) AS n, CAST(sum(n_events) AS BIGINT) AS events FROM orders JOIN a ON o_custkey = user_id AND day(o_orderdate) = dom GROUP BY 1")
def activity_composite_join(spark, sf_dir):
    q, order = workloads.composite(spark, sf_dir, exact=True)
    c = variable("saw_click", True)
    (_, _, df), = lower(q, [c, c * variable("n_events", False)], order)
    return df.select("saw_click", F.col("m0").cast("long").alias("n"), F.col("m1").cast("long").alias("events"))


@query("SELECT c_mktsegment, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(round(c_acctbal * 100) AS HUGEINT) * CAST(round(s_acctbal * 100) AS HUGEINT)) AS DOUBLE) AS total FROM customer JOIN supplier ON c_nationkey = s_nationkey GROUP BY 1")
def nation_mn_join(spark, sf_dir):
    q, order = workloads.nation_pairs(spark, sf_dir, exact=True)
    c = variable("c_mktsegment", True)
    (_, _, df), = lower(q, [c, c * variable("c_acctbal", False) * variable("s_acctbal", False)], order)
    return df.select("c_mktsegment", F.col("m0").cast("long").alias("n"), F.col("m1").cast("double").alias("total"))


@query("WITH r AS (SELECT DISTINCT l_partkey AS a, l_suppkey AS b FROM lineitem), s AS (SELECT DISTINCT l_suppkey AS b, o_custkey AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey), t AS (SELECT DISTINCT l_partkey AS a, o_custkey AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey) SELECT count(*) AS n FROM r JOIN s ON r.b = s.b JOIN t ON r.a = t.a AND s.c = t.c")
def triangle_count(spark, sf_dir):
    rel = workloads.star_relations(spark, sf_dir)
    both = rel["lineitem"].join(rel["orders"], "orderkey").select(F.col("partkey").alias("a"), F.col("suppkey").alias("b"), F.col("custkey").alias("c"))
    return joins.triangles(both.select("a", "b"), both.select("b", "c"), both.select("a", "c"), rel["lineitem"].count())


@query("SELECT p_name, n, CAST(rank() OVER (ORDER BY n DESC, p_name) AS INTEGER) AS place FROM (SELECT p_name, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1) ORDER BY n DESC, p_name LIMIT 10")
def topk_levels(spark, sf_dir):
    rel = workloads.star_relations(spark, sf_dir)
    by = rel["lineitem"].join(rel["part"], "partkey").groupBy("p_name").agg(F.count(F.lit(1)).alias("n"))
    top = by.orderBy(F.desc("n"), "p_name").limit(10)
    return top.withColumn("place", F.rank().over(Window.orderBy(F.desc("n"), "p_name")))


@query("SELECT event_type, event_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS cents, count(*) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM events")
def window_running_moments(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("event_type").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.select("event_type", "event_id", F.sum(F.round(F.col("value") * 100).cast("long")).over(w).alias("cents"), F.count(F.lit(1)).over(w).alias("n"))


@query("SELECT (SELECT count(*) FROM (SELECT o_custkey FROM orders INTERSECT SELECT user_id FROM events)) AS both_sides, (SELECT count(*) FROM (SELECT o_custkey FROM orders EXCEPT SELECT user_id FROM events)) AS orders_only, (SELECT count(*) FROM (SELECT o_custkey FROM orders UNION SELECT user_id FROM events)) AS either")
def set_ops_domains(spark, sf_dir):
    a = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"))
    b = table(spark, sf_dir, "events").select(F.col("user_id").alias("k"))
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return n(a.intersect(b), "both_sides").crossJoin(n(a.subtract(b), "orders_only")).crossJoin(n(a.union(b).distinct(), "either"))


@query("""SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS INTEGER)) AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1""")
def events_props_json(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int").k.alias("k"))
    return e.groupBy("event_type").agg(F.sum("k").alias("k"), F.count(F.lit(1)).alias("n"))


@query("SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS s1 FROM events GROUP BY 1, 2")
def tumbling_event_moments(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("cents", F.round(F.col("value") * 100).cast("long"))
    return streams.windowed(e, ["event_type"], "cents").drop("window_end")


@query("SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) - INTERVAL (d) DAY AS window_start, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS s1 FROM events, generate_series(0, 6) t(d) GROUP BY 1")
def sliding_event_moments(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("cents", F.round(F.col("value") * 100).cast("long"))
    return streams.windowed(e, [], "cents", "7 days", "1 day").drop("window_end")


@query("WITH x AS (SELECT user_id, ts, CAST(round(value * 100) AS BIGINT) AS cents, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 1 WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS fresh FROM events), y AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM x) SELECT user_id, min(ts) AS window_start, count(*) AS n, CAST(sum(cents) AS BIGINT) AS s1 FROM y GROUP BY user_id, s")
def session_event_moments(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("cents", F.round(F.col("value") * 100).cast("long"))
    return streams.sessions(e, ["user_id"], "cents").drop("window_end")


@query("SELECT count(*) AS n, round(CAST(sum(list_sum([CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT) * CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT) for x in embedding])) AS DOUBLE), 3) AS trace FROM embeddings")
def embedding_gram_trace(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    squares = F.aggregate("embedding", F.lit(0).cast("long"), lambda a, x: a + F.round(x.cast("double") * 1000).cast("long") * F.round(x.cast("double") * 1000).cast("long"))
    return e.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(squares).cast("double"), 3).alias("trace"))


@query()
def embedding_lr(spark, sf_dir):
    """W11: 64 continuous features, one Gram kernel."""
    q = workloads.embedding_query(spark, sf_dir)
    model = Linear(q).attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), kernel="arrow"), q.feature_map(1))))
    fit = solver.bgd(model, LAM, **_LR_FIT)
    return _result(spark, [("bgd", fit.runs, fit.status, fit.objective, rmse(model, fit.theta), 0.0)])


@query("SELECT o.o_orderkey, (SELECT max(e.value) FROM events e WHERE e.user_id = o.o_custkey AND e.ts = (SELECT max(f.ts) FROM events f WHERE f.user_id = o.o_custkey AND f.ts <= o.o_orderdate)) AS value_as_of FROM orders o")
def as_of_event_value(spark, sf_dir):
    """An intensional feature: the customer's last event value at or before the order."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"))
    e = table(spark, sf_dir, "events").select("user_id", "ts", "value")
    return joins.as_of(o, e, "user_id", "ts", "value").select("o_orderkey", "value_as_of")


@query("SELECT a.s_suppkey AS a, b.c_custkey AS b FROM supplier a, customer b WHERE abs(a.s_acctbal - b.c_acctbal) <= 1.0")
def banded_join(spark, sf_dir):
    s = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("a"), "s_acctbal")
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("b"), "c_acctbal")
    return joins.banded(s, c, "s_acctbal", "c_acctbal", 1.0).select("a", "b")


@query("SELECT n_nationkey AS nationkey, n_regionkey, count(c_custkey) AS n_customers, CAST(coalesce(sum(CAST(round(c_acctbal * 100) AS BIGINT)), 0) AS BIGINT) AS cents FROM nation LEFT JOIN customer ON n_nationkey = c_nationkey GROUP BY 1, 2")
def census_relation(spark, sf_dir):
    return workloads.census(spark, sf_dir)


@query("SELECT o_orderstatus, CAST(count(*) FILTER (WHERE l_returnflag = 'A') AS BIGINT) AS a, CAST(count(*) FILTER (WHERE l_returnflag = 'N') AS BIGINT) AS n, CAST(count(*) FILTER (WHERE l_returnflag = 'R') AS BIGINT) AS r FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def pivot_counts(spark, sf_dir):
    rel = workloads.star_relations(spark, sf_dir)
    rows = rel["lineitem"].join(rel["orders"], "orderkey").groupBy("o_orderstatus").pivot("l_returnflag", ["A", "N", "R"]).count()
    return rows.select("o_orderstatus", *[F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "ANR"])


@query(f"WITH {sqltext.STAR.format(where='')} SELECT p_brand, CAST(count(*) AS DOUBLE) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS quantity FROM star GROUP BY 1")
def rolled_up_view(spark, sf_dir):
    """A coarser view from a finer one."""
    from .operators.moments import rolled_up

    q, order = workloads.star(spark, sf_dir, "W2", True, continuous=(), categorical=("p_brand", "p_type"))
    both = ("p_brand", "p_type")
    (_, _, finer), = lower(q, [Monomial((), both), Monomial((("l_quantity", 1),), both)], order)
    out = rolled_up(finer, ["p_brand"], ["m0", "m1"])
    return out.select("p_brand", F.col("m0").cast("double").alias("n"), F.col("m1").cast("double").alias("quantity"))


@query("SELECT monomial, CAST(sum(value) AS DOUBLE) AS value FROM (SELECT unnest([{'monomial': '1', 'value': 1}, {'monomial': 'q', 'value': q}, {'monomial': 'q^2', 'value': q * q}, {'monomial': 'q*s', 'value': q * s}, {'monomial': 's', 'value': s}, {'monomial': 's^2', 'value': s * s}], recursive := true) FROM (SELECT CAST(l_quantity AS BIGINT) AS q, CAST(p_size AS BIGINT) AS s FROM lineitem JOIN part ON l_partkey = p_partkey)) GROUP BY 1")
def expanded_monomials(spark, sf_dir):
    from .functions.scoring import expand

    rel = workloads.star_relations(spark, sf_dir)
    rows = rel["lineitem"].join(rel["part"], "partkey")
    each = rows.select(F.explode(expand([("q", F.col("l_quantity")), ("s", F.col("p_size"))])).alias("e")).select("e.*")
    return each.groupBy("monomial").agg(F.sum("value").alias("value"))


@query("SELECT c_custkey, CAST(ntile(4) OVER w AS INTEGER) AS quarter, CAST(rank() OVER w AS INTEGER) AS place, round(percent_rank() OVER w, 9) AS share FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey)")
def window_ranks(spark, sf_dir):
    c = table(spark, sf_dir, "customer")
    w = Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")
    return c.select("c_custkey", F.ntile(4).over(w).alias("quarter"), F.rank().over(w).alias("place"), F.round(F.percent_rank().over(w), 9).alias("share"))


for _name in ("rows_and_categories", "strategies", "sharing", "onehot_against_sparse", "degree_two_entries", "epoch_against_descent", "minibatch_sizes"):
    QUERIES[f"experiment_{_name}"] = getattr(experiments, _name)


@query()
def fm_scores(spark, sf_dir):
    """Vectorised factor scoring of the join's rows by fitted factors."""
    from .functions.scoring import fm_scores as score

    q, order = workloads.star(spark, sf_dir, "W2", False, SMALL_CONT, SMALL_CATS)
    model = FactorizationMachine(q, 4)
    model.attach(SigmaIndex(FeatureLayout(moments(q, aggregate_monomials(model.h, q.response), order), model.h)))
    return score(model, solver.bgd(model, LAM, theta0=_fm_start(model), **_FM_FIT).theta, q.listing())


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """LR on W1 end to end: factorized moments, descent, predictions for the join's rows."""
    q, order = workloads.star(spark, sf_dir, "W1", False, SMALL_CONT, SMALL_CATS)
    model = Linear(q)
    model.attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), order), model.h)))
    fit = solver.bgd(model, LAM, **_LR_FIT)
    return predict.predict(model, fit.theta, q.listing())


