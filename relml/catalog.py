"""Named queries with their SQL oracles: language, derivation, views, moments, learners, baselines, measures."""

from __future__ import annotations

import itertools
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import datasets as ds
from . import frontend, rewrite
from .ir import SetLit, Var
from .learn import linear, others, tree
from .moments import MomentMatrix, gram, moment_matrix, moment_tensor
from .plans import compiler
from .plans.lower import evaluate, is_data, lower
from .plans.views import Emitter, aggregate, batch_stats, build_join_tree, monomials, naive_join, push_down, view_keys
from .sources.io import load
from .spec import Feature, JoinSpec, Relation

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn

    return keep


#: Engines break decimal ties in their own ways, so values are moved off them by less than a digit shown.
OFF_TIES = 1.00000000013


def sig(c: Column) -> Column:
    """Seven digits as text, alike in both engines."""
    return F.format_string("%.6e", c.cast("double") * F.lit(OFF_TIES) + F.lit(0.0))


def sig_sql(e: str) -> str:
    return f"printf('%.6e', CAST({e} AS DOUBLE) * CAST({OFF_TIES!r} AS DOUBLE) + 0.0)"


# --- language -------------------------------------------------------------------------------------------------

LANGUAGE = {
    "ir_fold_sum": ("sum(L(x) * x.l_quantity * x.l_linenumber for x in keys(L))", "SELECT sum(l_quantity * l_linenumber) AS value FROM lineitem"),
    "ir_fold_min": ("min(x.l_extendedprice for x in keys(L))", "SELECT min(l_extendedprice) AS value FROM lineitem"),
    "ir_fold_set_union": (None, "SELECT DISTINCT l_returnflag AS element FROM lineitem"),
    "ir_tabulate": ("{k: sum((x.l_returnflag == k.l_returnflag) * (L(x) * x.l_quantity) for x in keys(L)) for k in keys(D)}", "SELECT l_returnflag, sum(l_quantity) AS value FROM lineitem GROUP BY 1"),
    "ir_keys": ("keys(D)", "SELECT DISTINCT l_returnflag FROM lineitem"),
    "ir_lookup_join": ("sum(L(x) * V(x.l_suppkey) * x.l_quantity for x in keys(L))", "SELECT CAST(sum(l_quantity * s_nationkey) AS DOUBLE) AS value FROM lineitem JOIN supplier ON l_suppkey = s_suppkey"),
    "ir_conditional": ("sum((x.l_quantity if x.l_discount > 0.05 else -x.l_quantity) for x in keys(L))", "SELECT sum(CASE WHEN l_discount > 0.05 THEN l_quantity ELSE -l_quantity END) AS value FROM lineitem"),
    "ir_record_access": (None, "SELECT sum(l_quantity) AS q, sum(l_linenumber * l_quantity) AS w FROM lineitem"),
    "ir_bag_union": (None, "SELECT k, CAST(count(*) AS BIGINT) AS value FROM (SELECT l_linenumber AS k FROM lineitem UNION ALL SELECT p_size AS k FROM part) GROUP BY 1"),
}


def _language(name: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        from .ir import Const, Fold, Keys, Lookup, MapLit, Proj, Rec

        line = load(spark, sf, "lineitem")
        tables = {"L": line, "D": line.select("l_returnflag"), "P": load(spark, sf, "part"), "S": load(spark, sf, "supplier")}
        source, x = LANGUAGE[name][0], Var("x")
        if name == "ir_fold_set_union":
            return lower(Fold("x", Keys(Var("L")), SetLit((Proj(x, "l_returnflag"),)), "union"), tables)
        if name == "ir_record_access":
            return lower(Fold("x", Keys(Var("L")), Rec(("q", "w"), (Proj(Rec(("a",), (Proj(x, "l_quantity"),)), "a"), Proj(x, "l_linenumber") * Proj(x, "l_quantity")))), tables)
        if name == "ir_bag_union":
            one = lambda t, c: Fold("x", Keys(Var(t)), MapLit((Rec(("k",), (Proj(x, c),)),), (Const(1),)))
            return lower(one("L", "l_linenumber") + one("P", "p_size"), tables).select("k", F.col("value").cast("bigint").alias("value"))
        if name == "ir_lookup_join":
            view = Fold("x", Keys(Var("S")), MapLit((Rec(("s_suppkey",), (Proj(x, "s_suppkey"),)),), (Proj(x, "s_nationkey"),)))
            tables["V"] = lower(view, tables)
        return lower(frontend.parse(source), tables)

    return run


for _name, (_, _sql) in LANGUAGE.items():
    query(_name, _sql)(_language(_name))

# --- derivation of the running example -------------------------------------------------------------------------

FEATURES3 = ["i", "s", "c", "p"]
THETA0 = {"i": 1, "s": 2, "c": 3, "p": 4}
JOIN3 = "SELECT l_partkey AS i, l_suppkey AS s, s_nationkey AS c, CAST(round(p_retailprice * 100) AS BIGINT) AS p, CAST(l_quantity AS BIGINT) AS u FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey"
DERIVE_SQL = f"WITH j AS ({JOIN3}) " + " UNION ALL ".join(f"SELECT '{f}' AS feature, CAST({THETA0[f]} - sum(CAST({f} AS HUGEINT) * ({' + '.join(f'{THETA0[g]} * CAST({g} AS HUGEINT)' for g in FEATURES3)})) AS VARCHAR) AS theta FROM j" for f in FEATURES3)


def update(Q, T0):  # read as source, never run
    F = ["i", "s", "c", "p"]
    theta = T0
    while round < 1:
        theta = {f1: theta(f1) - sum(Q(x) * sum(theta(f2) * x[f2] for f2 in F) * x[f1] for x in keys(Q)) for f1 in F}  # noqa: F821
    return theta


def running_stages() -> dict:
    """The running example after each phase."""
    return rewrite.stages(frontend.program(update), lambda e: len(e.items) if isinstance(e, SetLit) else float("inf"), lambda e: is_data(e, "Q"))


STAGES = ["naive", "normalised", "scheduled", "factored", "memoised", "hoisted", "specialised"]
PLANS = ["pushdown", "merged", "multi", "trie"]
DERIVE = ["derive_00_naive_join", "derive_01_normalised", "derive_02_scheduled", "derive_03_factored", "derive_04_memoised", "derive_05_hoisted", "derive_06_specialised", "derive_07_pushdown", "derive_08_merged", "derive_09_multi_aggregate", "derive_10_trie"]


def derive(spark: SparkSession, sf: str, k: int) -> DataFrame:
    spec, features, _ = ds.running3(spark, sf)
    if k < len(STAGES):
        joined = naive_join(spec, features, exact=True)
        theta = evaluate(running_stages()[STAGES[k]], "Q", joined, {"T0": THETA0}, mult="__mult")
        theta = dict(theta) if not isinstance(theta, dict) else theta
    else:
        theta = compiler.compile_program(update, spec, features).run({"T0": THETA0}, PLANS[k - len(STAGES)], exact=True)
    return spark.createDataFrame([(f, str(theta[f])) for f in FEATURES3], "feature string, theta string")


for _k, _name in enumerate(DERIVE):
    query(_name, DERIVE_SQL)(lambda spark, sf, k=_k: derive(spark, sf, k))

# --- views ------------------------------------------------------------------------------------------------------


def view(spark: SparkSession, sf: str, batch: list, relation: str, names: list[str], unique: bool = False) -> DataFrame:
    """The view that a relation publishes for a batch, aggregated as if its key were not declared."""
    from dataclasses import replace

    spec, features, _ = ds.running3(spark, sf)
    spec = replace(spec, relations={n: replace(r, unique=unique) for n, r in spec.relations.items()})
    em = Emitter(spec, build_join_tree(spec, "lineitem"), features, True)
    node = next(n for n in push_down(batch, em.tree, em.owner).walk() if n.relation == relation)
    got = em.node(node)
    return got.df.select(F.col(f"k_{relation}_{node.key[0]}").alias("k"), *[got.value[m].cast("string").alias(n) for m, n in zip(node.values, names)])


query("view_stores", "SELECT s_suppkey AS k, CAST(sum(s_nationkey) AS VARCHAR) AS c FROM supplier GROUP BY 1")(lambda spark, sf: view(spark, sf, [("c", "p")], "supplier", ["c"]))
query("view_items", "SELECT p_partkey AS k, CAST(sum(CAST(round(p_retailprice * 100) AS HUGEINT)) AS VARCHAR) AS p FROM part GROUP BY 1")(lambda spark, sf: view(spark, sf, [("c", "p")], "part", ["p"]))
query("view_merged_stores", "SELECT s_suppkey AS k, CAST(sum(s_nationkey) AS VARCHAR) AS c, CAST(sum(s_nationkey * s_nationkey) AS VARCHAR) AS cc FROM supplier GROUP BY 1")(lambda spark, sf: view(spark, sf, [("c", "p"), ("c", "c")], "supplier", ["c", "cc"]))
query("view_merged_items", "SELECT p_partkey AS k, CAST(sum(CAST(round(p_retailprice * 100) AS HUGEINT)) AS VARCHAR) AS p, CAST(count(*) AS VARCHAR) AS n FROM part GROUP BY 1")(lambda spark, sf: view(spark, sf, [("c", "p"), ("c", "c")], "part", ["p", "n"]))
query("view_count_only", "SELECT p_partkey AS k, CAST(count(*) AS VARCHAR) AS n FROM part GROUP BY 1")(lambda spark, sf: view(spark, sf, [("c", "c")], "part", ["n"]))


@query("view_snowflake_customer_orders", "SELECT o_orderkey AS k, CAST(count(*) AS VARCHAR) AS n, CAST(sum(CAST(round(c_acctbal * 100) AS HUGEINT)) AS VARCHAR) AS b, CAST(sum(CAST(round(c_acctbal * 100) AS HUGEINT) * CAST(round(o_totalprice * 100) AS HUGEINT)) AS VARCHAR) AS bt FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def view_snowflake(spark: SparkSession, sf: str) -> DataFrame:
    spec = JoinSpec({n: Relation(n, r.df) for n, r in ds.relations(spark, sf, "lineitem", "orders", "customer").items()}, (ds.EDGES["orders"], ds.EDGES["customer"]))
    fs = [Feature("b", "customer", "c_acctbal", scale=2), Feature("t", "orders", "o_totalprice", scale=2)]
    em = Emitter(spec, build_join_tree(spec, "lineitem"), fs, True)
    node = push_down([(), ("b",), ("b", "t")], em.tree, em.owner).children[0]
    got = em.node(node)
    return got.df.select(F.col("k_orders_o_orderkey").alias("k"), *[got.value[m].cast("string").alias(n) for m, n in zip(node.values, ("n", "b", "bt"))])


# --- moments ----------------------------------------------------------------------------------------------------


def moments_sql(join: str, names: list[str], how: Callable[[str, str], str]) -> str:
    pairs = [(a, b) for i, a in enumerate(names) for b in names[i:]]
    sums = ", ".join(f"{how(a, b)} AS v{k}" for k, (a, b) in enumerate(pairs))
    return f"WITH j AS ({join}), m AS (SELECT {sums} FROM j) " + " UNION ALL ".join(f"SELECT '{a}' AS f1, '{b}' AS f2, v{k} AS value FROM m" for k, (a, b) in enumerate(pairs))


def _exact_sum(a: str, b: str) -> str:
    parts = [f"CAST({x} AS HUGEINT)" for x in (a, b) if x != "1"]
    return f"CAST({'sum(' + ' * '.join(parts) + ')' if parts else 'count(*)'} AS VARCHAR)"


MOMENTS3 = moments_sql(JOIN3, ["1", *FEATURES3, "u"], _exact_sum)
for _s in ("materialised", "pushdown", "merged", "trie"):
    query(f"moments_running3_{_s}", MOMENTS3)(lambda spark, sf, s=_s: moment_matrix(*ds.running3(spark, sf), strategy=s, exact=True).to_df(spark))

NARROW = ["l_extendedprice", "l_discount", "l_tax", "o_totalprice", "p_retailprice", "s_acctbal"]
FROM_NARROW = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"
CENTS = ", ".join(f"CAST(round({n} * 100) AS BIGINT) AS {n}" for n in NARROW) + ", CAST(l_quantity AS BIGINT) AS l_quantity"
LAST = "(SELECT max(l_shipdate) - INTERVAL 1 MONTH FROM lineitem)"
query("moments_narrow6", moments_sql(f"SELECT {CENTS} FROM {FROM_NARROW}", ["1", *NARROW, "l_quantity"], _exact_sum))(lambda spark, sf: moment_matrix(*ds.narrow6(spark, sf), exact=True).to_df(spark))
WIDE_JOIN = "SELECT " + ", ".join(f"CAST({e.replace('dow(', 'dayofweek(')} AS DOUBLE) AS {n}" for n, _, e in ds.WIDE) + ", l_quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"
query("moments_wide35_gram", moments_sql(WIDE_JOIN, ["1", *[n for n, *_ in ds.WIDE], "l_quantity"], lambda a, b: sig_sql(f"sum(CAST({a} AS DOUBLE) * CAST({b} AS DOUBLE))")))(lambda spark, sf: (m := moment_matrix(*ds.wide35(spark, sf), strategy="gram").to_df(spark)).select("f1", "f2", sig(m.value).alias("value")))


@query("moments_by_part_type", f"SELECT p_type, CAST(count(*) AS VARCHAR) AS n, CAST(sum(CAST(l_quantity AS HUGEINT)) AS VARCHAR) AS q, CAST(sum(CAST(l_quantity AS HUGEINT) * CAST(round(s_acctbal * 100) AS HUGEINT)) AS VARCHAR) AS qb FROM {FROM_NARROW} GROUP BY 1")
def moments_by_part_type(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf)
    every = [*fs, y, Feature("p_type", "part", "p_type", "cat")]
    got = aggregate(spec, every, [(), ("l_quantity",), ("l_quantity", "s_acctbal")], exact=True, groups=["p_type"], root="part")
    return got.select("p_type", *[F.col(f"a{i}").cast("string").alias(n) for i, n in enumerate(("n", "q", "qb"))])


FROM_ONEHOT = FROM_NARROW + " JOIN customer ON o_custkey = c_custkey JOIN region ON n_regionkey = r_regionkey"


def _sparse_sql() -> str:
    cats, out = [n for n, _ in ds.CATEGORIES], []
    for k, a in enumerate(cats):
        ca = f"CAST({a} AS VARCHAR)"
        out.append(f"SELECT '{a}' AS f1, {ca} AS c1, '{a}' AS f2, {ca} AS c2, {sig_sql('count(*)')} AS value FROM {FROM_ONEHOT} GROUP BY {a}")
        out += [f"SELECT '{a}', {ca}, '{x}', '', {sig_sql(f'sum({x})')} FROM {FROM_ONEHOT} GROUP BY {a}" for x in NARROW]
        out += [f"SELECT '{a}', {ca}, '{b}', CAST({b} AS VARCHAR), {sig_sql('count(*)')} FROM {FROM_ONEHOT} GROUP BY {a}, {b}" for b in cats[k + 1 :]]
    return " UNION ALL ".join(out)


query("moments_sparse_onehot", _sparse_sql())(lambda spark, sf: moment_tensor(*ds.onehot(spark, sf)).select("f1", "c1", "f2", "c2", sig(F.col("value")).alias("value")))


@query("moments_multi_root", f"SELECT p_brand AS g, {sig_sql('sum(l_quantity)')} AS value FROM {FROM_NARROW} GROUP BY 1 UNION ALL SELECT CAST(n_regionkey AS VARCHAR), {sig_sql('sum(l_quantity)')} FROM {FROM_NARROW} GROUP BY n_regionkey")
def moments_multi_root(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf)
    parts = []
    for name, owner in (("p_brand", "part"), ("n_regionkey", "nation")):
        got = aggregate(spec, [y, Feature(name, owner, name, "cat")], [(y.name,)], groups=[name], root=owner)
        parts.append(got.select(F.col(name).cast("string").alias("g"), sig(F.col("a0")).alias("value")))
    return parts[0].unionByName(parts[1])


@query("moments_delta_merge", moments_sql(f"SELECT {CENTS} FROM {FROM_NARROW}", ["1", *NARROW, "l_quantity"], _exact_sum))
def moments_delta_merge(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf)
    old, new = (moment_matrix(spec.filtered(lineitem=c), fs, y, exact=True) for c in ("l_orderkey % 5 <> 0", "l_orderkey % 5 = 0"))
    return (old + new).to_df(spark)


@query("moments_duplicate_dimension_keys", "WITH s AS (SELECT * FROM supplier UNION ALL SELECT * FROM supplier WHERE s_suppkey % 3 = 0) SELECT CAST(count(*) AS VARCHAR) AS n, CAST(sum(CAST(l_quantity AS HUGEINT) * s_nationkey) AS VARCHAR) AS uc, CAST(sum(CAST(s_nationkey AS HUGEINT) * s_nationkey) AS VARCHAR) AS cc FROM lineitem JOIN s ON l_suppkey = s_suppkey")
def moments_duplicates(spark: SparkSession, sf: str) -> DataFrame:
    twice = load(spark, sf, "supplier")
    twice = twice.unionAll(twice.where("s_suppkey % 3 = 0"))
    spec = JoinSpec({"lineitem": Relation("lineitem", load(spark, sf, "lineitem")), "supplier": Relation("supplier", twice)}, (ds.EDGES["supplier"],))
    fs = [Feature("u", "lineitem", "l_quantity"), Feature("c", "supplier", "s_nationkey")]
    got = aggregate(spec, fs, [(), ("c", "u"), ("c", "c")], exact=True, root="lineitem")
    return got.select(*[F.col(f"a{i}").cast("string").alias(n) for i, n in enumerate(("n", "uc", "cc"))])


# --- linear regression --------------------------------------------------------------------------------------------


def _two(spark: SparkSession, sf: str) -> tuple[JoinSpec, list[Feature], Feature]:
    spec, fs, y = ds.narrow6(spark, sf)
    return spec, [f for f in fs if f.name in ("l_discount", "l_tax")], y


def bgd_sql(rounds: int, alpha: float) -> str:
    m = "SELECT count(*) AS n, sum(l_discount) AS d, sum(l_tax) AS t, sum(l_discount * l_discount) AS dd, sum(l_discount * l_tax) AS dt, sum(l_tax * l_tax) AS tt, sum(l_quantity) AS y, sum(l_quantity * l_discount) AS yd, sum(l_quantity * l_tax) AS yt FROM lineitem"
    step = f"SELECT k + 1, a - {alpha} / n * (n * a + d * b + t * c - y), b - {alpha} / n * (d * a + dd * b + dt * c - yd), c - {alpha} / n * (t * a + dt * b + tt * c - yt) FROM r, m WHERE k < {rounds}"
    return f"WITH RECURSIVE m AS ({m}), r(k, a, b, c) AS (SELECT 0, CAST(0 AS DOUBLE), CAST(0 AS DOUBLE), CAST(0 AS DOUBLE) UNION ALL {step}) " + " UNION ALL ".join(f"SELECT '{n}' AS feature, {sig_sql(v)} AS theta FROM r WHERE k = {rounds}" for n, v in (("1", "a"), ("l_discount", "b"), ("l_tax", "c")))


def _theta(spark: SparkSession, model: linear.LinearModel) -> DataFrame:
    df = model.to_df(spark)
    return df.select("feature", sig(df.theta).alias("theta"))


query("linreg_bgd_1_step", bgd_sql(1, 0.5))(lambda spark, sf: _theta(spark, linear.bgd(moment_matrix(*_two(spark, sf), exact=True), 0.5, 1, raw=True)))
query("linreg_bgd_50_steps", bgd_sql(50, 0.5))(lambda spark, sf: _theta(spark, linear.bgd(moment_matrix(*_two(spark, sf), exact=True), 0.5, 50, raw=True)))


def compiled_descent(spark: SparkSession, sf: str, rounds: int, strategy: str = "multi") -> DataFrame:
    """The program of least squares, from source text to one batch of sums and a compiled loop."""
    spec, fs, y = _two(spark, sf)
    names = [compiler.ONE, *[f.name for f in fs]]
    got = compiler.compile_program(compiler.least_squares(names, y.name), spec, [*fs, y]).run({"A": 0.5, "R": rounds, "T0": dict.fromkeys(names, 0.0)}, strategy)
    rows = [("1" if n == compiler.ONE else n, float(v)) for n, v in got.items()]
    return spark.createDataFrame(rows, "feature string, theta double").select("feature", sig(F.col("theta")).alias("theta"))


for _s in ("pushdown", "merged", "multi", "trie"):
    query(f"program_bgd_50_{_s}", bgd_sql(50, 0.5))(lambda spark, sf, s=_s: compiled_descent(spark, sf, 50, s))


@query("program_explain")
def program_explain(spark: SparkSession, sf: str) -> DataFrame:
    """The running example's program after each phase, its sums, what each relation publishes, the plan of its one job and what
    that job gives on the tables."""
    spec, features, _ = ds.running3(spark, sf)
    c = compiler.compile_program(update, spec, features)
    rows = [(k, n, c.explain(n, exact=True)) for k, n in enumerate([*c.stages, "sums", "views", "spark"])]
    got = c.sums("multi", True).first()
    rows.append((len(rows), "result", "\n".join(f"{'*'.join(m) or 'count'}: {v}" for m, v in zip(c.batch, got))))
    return spark.createDataFrame(rows, "step int, stage string, text string")


query("linreg_bgd_naive_50", bgd_sql(50, 0.5))(lambda spark, sf: _theta(spark, linear.bgd_naive(*_two(spark, sf), max_iter=50, alpha=0.5, raw=True)))


@query("linreg_loss", f"SELECT {sig_sql('sum((20 + 3 * l_discount - 2 * l_tax - l_quantity) * (20 + 3 * l_discount - 2 * l_tax - l_quantity)) / (2 * count(*))')} AS loss FROM lineitem")
def linreg_loss(spark: SparkSession, sf: str) -> DataFrame:
    value = linear.loss(moment_matrix(*_two(spark, sf), exact=True), np.array([20.0, 3.0, -2.0]))
    return spark.createDataFrame([(value,)], "loss double").select(sig(F.col("loss")).alias("loss"))


@query("linreg_closed_form_1d", f"SELECT {sig_sql('regr_slope(l_quantity, p_retailprice)')} AS slope, {sig_sql('regr_intercept(l_quantity, p_retailprice)')} AS intercept FROM lineitem JOIN part ON l_partkey = p_partkey")
def closed_form_1d(spark: SparkSession, sf: str) -> DataFrame:
    spec = ds.star(spark, sf, "part")
    m = linear.solve_normal(moment_matrix(spec, [Feature("p", "part", "p_retailprice", scale=2)], Feature("u", "lineitem", "l_quantity"), exact=True))
    return spark.createDataFrame([(float(m.theta[1]), float(m.theta[0]))], "slope double, intercept double").select(sig(F.col("slope")).alias("slope"), sig(F.col("intercept")).alias("intercept"))


query("linreg_closed_form_narrow6")(lambda spark, sf: linear.solve_normal(moment_matrix(*ds.narrow6(spark, sf, "train"), exact=True)).to_df(spark))


@query("linreg_ridge", f"WITH m AS (SELECT avg(l_discount) AS ax, avg(l_quantity) AS ay, var_pop(l_discount) AS v, covar_pop(l_quantity, l_discount) AS c FROM lineitem) SELECT {sig_sql('c / (v * 1.5)')} AS slope, {sig_sql('ay - c / (v * 1.5) * ax')} AS intercept FROM m")
def ridge(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = _two(spark, sf)
    m = linear.ridge(moment_matrix(spec, fs[:1], y, exact=True), 0.5)
    return spark.createDataFrame([(float(m.theta[1]), float(m.theta[0]))], "slope double, intercept double").select(sig(F.col("slope")).alias("slope"), sig(F.col("intercept")).alias("intercept"))


@query("linreg_predict", f"SELECT l_orderkey, l_linenumber, l_partkey, CAST(20 AS DOUBLE) + CAST(3 AS DOUBLE) * l_discount + CAST(-2 AS DOUBLE) * l_tax AS prediction FROM lineitem")
def predict(spark: SparkSession, sf: str) -> DataFrame:
    model = linear.LinearModel(["1", "l_discount", "l_tax"], np.array([20.0, 3.0, -2.0]))
    return model.predict(load(spark, sf, "lineitem")).select("l_orderkey", "l_linenumber", "l_partkey", "prediction")


def _ols(d: str) -> str:
    return f"(SELECT avg(l_quantity) AS ay, avg({d}) AS ax, covar_pop(l_quantity, {d}) / var_pop({d}) AS b FROM lineitem WHERE l_shipdate <= {LAST})"


@query("linreg_rmse_test", f"SELECT {sig_sql('sqrt(avg((ay + b * (l_tax - ax) - l_quantity) * (ay + b * (l_tax - ax) - l_quantity)))')} AS rmse FROM lineitem, {_ols('l_tax')} WHERE l_shipdate > {LAST}")
def rmse_test(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf, "train")
    tax = [f for f in fs if f.name == "l_tax"]
    model = linear.solve_normal(moment_matrix(spec, tax, y, exact=True))
    test = naive_join(ds.narrow6(spark, sf, "test")[0], [*tax, y])
    return spark.createDataFrame([(linear.rmse(model.predict(test), y.name),)], "rmse double").select(sig(F.col("rmse")).alias("rmse"))


@query("linreg_planted", " UNION ALL ".join(f"SELECT '{n}' AS feature, CAST({v} AS DOUBLE) AS theta" for n, v in (("1", 12.5), ("l_quantity", 2), ("p_size", 0.5), ("p_retailprice", -0.01))))
def planted(spark: SparkSession, sf: str) -> DataFrame:
    return linear.solve_normal(moment_matrix(*ds.planted_linear(spark, sf))).to_df(spark, 6)


@query("linreg_per_group", f"SELECT p_type, {sig_sql('regr_slope(l_quantity, p_retailprice)')} AS slope FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def per_group(spark: SparkSession, sf: str) -> DataFrame:
    spec = ds.star(spark, sf, "part")
    fs = [Feature("p", "part", "p_retailprice", scale=2), Feature("u", "lineitem", "l_quantity"), Feature("p_type", "part", "p_type", "cat")]
    got = aggregate(spec, fs, [(), ("p",), ("u",), ("p", "p"), ("p", "u")], exact=True, groups=["p_type"], root="part")
    n, p, u, pp, pu = (F.col(f"a{i}") for i in range(5))
    num, den = (n * pu).cast("decimal(38,0)") - (p * u).cast("decimal(38,0)"), (n * pp).cast("decimal(38,0)") - (p * p).cast("decimal(38,0)")
    return got.select("p_type", sig(100 * num.cast("double") / den.cast("double")).alias("slope"))


query("coordinate_descent")(lambda spark, sf: linear.coordinate_descent(moment_matrix(*ds.narrow6(spark, sf, "train"), exact=True), l1=1e-3).to_df(spark))


@query("sgd_one_epoch")
def sgd_one_epoch(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf, "train")
    joined = naive_join(spec, [*fs, y])
    return linear.sgd(joined, [f.name for f in fs], y.name, moment_matrix(spec, fs, y), 100_000, 1).to_df(spark)


@query("feature_subset_search", f"WITH r AS (" + " UNION ALL ".join(f"SELECT '{n}' AS features, regr_syy(l_quantity, {n}) - regr_sxy(l_quantity, {n}) * regr_sxy(l_quantity, {n}) / regr_sxx(l_quantity, {n}) AS rss FROM {FROM_NARROW}" for n in NARROW) + f") SELECT CAST(1 AS BIGINT) AS size, features, {sig_sql('rss')} AS rss FROM r ORDER BY rss LIMIT 1")
def subset(spark: SparkSession, sf: str) -> DataFrame:
    rows = linear.select_features(moment_matrix(*ds.narrow6(spark, sf), exact=True), 1, "all")
    return spark.createDataFrame(rows, "size long, features string, rss double").select("size", "features", sig(F.col("rss")).alias("rss"))


# --- trees ---------------------------------------------------------------------------------------------------------


def split_sql(source: str, exprs: list[tuple[str, str]], y: str) -> str:
    """Best split of each feature over all rows, by running sums."""
    parts = []
    for name, e in exprs:
        parts.append(f"SELECT * FROM (SELECT '{name}' AS feature, v AS threshold, ls AS left_n, {sig_sql('(l2 - l1 * l1 / ls) + ((t2 - l2) - (t1 - l1) * (t1 - l1) / (tn - ls))')} AS cost, (l2 - l1 * l1 / ls) + ((t2 - l2) - (t1 - l1) * (t1 - l1) / (tn - ls)) AS c FROM (SELECT v, sum(n) OVER w AS ls, sum(s1) OVER w AS l1, sum(s2) OVER w AS l2, sum(n) OVER () AS tn, sum(s1) OVER () AS t1, sum(s2) OVER () AS t2 FROM (SELECT CAST({e} AS DOUBLE) AS v, CAST(count(*) AS DOUBLE) AS n, sum({y}) AS s1, sum({y} * {y}) AS s2 FROM {source} GROUP BY 1) WINDOW w AS (ORDER BY v ROWS UNBOUNDED PRECEDING)) WHERE tn > ls ORDER BY c, v LIMIT 1)")
    return "SELECT feature, threshold, left_n, cost FROM (" + " UNION ALL ".join(parts) + ")"


CONT = [("l_discount", "l_discount"), ("l_tax", "l_tax"), ("p_size", "p_size"), ("p_retailprice", "p_retailprice"), ("s_acctbal", "s_acctbal")]


def _tree_spec(spark: SparkSession, sf: str) -> tuple[JoinSpec, list[Feature], Feature]:
    spec = ds.star(spark, sf, "part", "supplier")
    return spec, [Feature(n, {"l": "lineitem", "p": "part", "s": "supplier"}[n[0]], n) for n, _ in CONT], Feature("l_quantity", "lineitem", "l_quantity")


@query("tree_root_split_continuous", split_sql("lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey", CONT, "l_quantity"))
def root_split(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = _tree_spec(spark, sf)
    g = tree.Grower(spec, fs, y, tree.Measure("sse"), None)
    stats = g.statistics()
    best = g.best_splits(stats.withColumn("node", F.col("fid")), 1)  # a node for each feature: the best of each
    names = F.element_at(F.array(*[F.lit(f.name) for f in fs]), F.col("fid") + 1)
    return best.select(names.alias("feature"), F.col("val").alias("threshold"), F.col("l0").alias("left_n"), sig(F.col("cost")).alias("cost"))


@query("tree_root_split_categorical", f"WITH s AS (SELECT p_type AS cat, CAST(count(*) AS DOUBLE) AS n, sum(l_quantity) AS s1, sum(l_quantity * l_quantity) AS s2 FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1), r AS (SELECT cat, s1 / n AS m, sum(n) OVER w AS ls, sum(s1) OVER w AS l1, sum(s2) OVER w AS l2, sum(n) OVER () AS tn, sum(s1) OVER () AS t1, sum(s2) OVER () AS t2 FROM s WINDOW w AS (ORDER BY s1 / n, cat ROWS UNBOUNDED PRECEDING)) SELECT ls AS left_n, {sig_sql('(l2 - l1 * l1 / ls) + ((t2 - l2) - (t1 - l1) * (t1 - l1) / (tn - ls))')} AS cost FROM r WHERE tn > ls ORDER BY (l2 - l1 * l1 / ls) + ((t2 - l2) - (t1 - l1) * (t1 - l1) / (tn - ls)) LIMIT 1")
def root_split_categorical(spark: SparkSession, sf: str) -> DataFrame:
    g = tree.Grower(ds.star(spark, sf, "part"), [Feature("p_type", "part", "p_type", "cat")], Feature("y", "lineitem", "l_quantity"), tree.Measure("sse"), None)
    return g.best_splits(g.statistics(), 1).select(F.col("l0").alias("left_n"), sig(F.col("cost")).alias("cost"))


@query("tree_level_stats", "SELECT CAST(p_size AS DOUBLE) AS val, CAST(count(*) AS DOUBLE) AS n, sum(l_quantity) AS s1, sum(l_quantity * l_quantity) AS s2 FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def level_stats(spark: SparkSession, sf: str) -> DataFrame:
    g = tree.Grower(ds.star(spark, sf, "part"), [Feature("p_size", "part", "p_size")], Feature("y", "lineitem", "l_quantity"), tree.Measure("sse"), None)
    return g.statistics().select("val", F.col("s0").alias("n"), "s1", "s2")


def _grown(spark: SparkSession, sf: str, depth: int, part: str = "train") -> tuple[tree.TreeModel, list[Feature], Feature]:
    spec, fs, y = ds.narrow6(spark, sf, part)
    return tree.grow_regression_tree(spec, fs, y, depth), fs, y


def depth2_sql(source: str, features: list[str], y: str) -> str:
    """The three tests of a tree of depth 2: running sums for the root, then for both sides of its test."""
    cost = "(l2 - l1 * l1 / ls) + ((t2 - l2) - (t1 - l1) * (t1 - l1) / (tn - ls))"
    names = ", ".join(f"'{f}'" for f in features)

    def best(rows: str) -> str:
        stats = f"SELECT node, fid, v, CAST(count(*) AS DOUBLE) AS n, sum(y) AS s1, sum(y * y) AS s2 FROM {rows} GROUP BY 1, 2, 3"
        run = f"SELECT node, fid, v, sum(n) OVER w AS ls, sum(s1) OVER w AS l1, sum(s2) OVER w AS l2, sum(n) OVER g AS tn, sum(s1) OVER g AS t1, sum(s2) OVER g AS t2 FROM ({stats}) WINDOW w AS (PARTITION BY node, fid ORDER BY v ROWS UNBOUNDED PRECEDING), g AS (PARTITION BY node, fid)"
        return f"SELECT node, fid, v, tn, ls FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY {cost}, fid, v) AS k FROM ({run}) WHERE tn > ls) WHERE k = 1"

    long = " UNION ALL ".join(f"SELECT id, {k} AS fid, CAST({f} AS DOUBLE) AS v, y FROM j" for k, f in enumerate(features))
    side = "SELECT u.id, CASE WHEN u.v <= b.v THEN 2 ELSE 3 END AS node FROM u JOIN b1 b ON u.fid = b.fid"
    return f"WITH j AS MATERIALIZED (SELECT row_number() OVER () AS id, {', '.join(features)}, {y} AS y FROM {source}), u AS (SELECT 1 AS node, * FROM ({long})), b1 AS MATERIALIZED ({best('u')}), a AS ({side}), w AS (SELECT a.node, u.fid, u.v, u.y FROM u JOIN a USING (id)), b2 AS ({best('w')}) SELECT CAST(node AS INTEGER) AS node_id, list_extract([{names}], fid + 1) AS feature, v AS threshold, tn AS n, ls AS left_n FROM (SELECT * FROM b1 UNION ALL SELECT * FROM b2)"


def _splits(spark: SparkSession, m: tree.TreeModel) -> DataFrame:
    rows = [(k, n.feature, n.threshold, n.n, m.nodes[2 * k].n) for k, n in sorted(m.nodes.items()) if n.feature]
    return spark.createDataFrame(rows, "node_id int, feature string, threshold double, n double, left_n double")


query("tree_depth2_splits", depth2_sql(f"{FROM_NARROW} WHERE l_shipdate <= {LAST}", NARROW, "l_quantity"))(lambda spark, sf: _splits(spark, _grown(spark, sf, 2)[0]))


@query("tree_filtered_dimensions", depth2_sql("lineitem JOIN (SELECT * FROM part WHERE p_size > 20 UNION ALL SELECT * FROM part WHERE p_size > 20 AND p_partkey % 5 = 0) ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey WHERE s_acctbal > 0", [n for n, _ in CONT], "l_quantity"))
def tree_filtered(spark: SparkSession, sf: str) -> DataFrame:
    """Rows without partners are out and repeated dimension rows count as often as they join."""
    part = load(spark, sf, "part")
    spec, fs, y = _tree_spec(spark, sf)
    spec = JoinSpec({**spec.relations, "part": Relation("part", part.unionAll(part.where("p_partkey % 5 = 0")))}, spec.on).filtered(part="p_size > 20", supplier="s_acctbal > 0")
    return _splits(spark, tree.grow_regression_tree(spec, fs, y, 2))


query("tree_depth2")(lambda spark, sf: _grown(spark, sf, 2)[0].to_df(spark))
query("tree_depth4_narrow6")(lambda spark, sf: _grown(spark, sf, 4)[0].to_df(spark))


@query("tree_predict", f"SELECT l_orderkey, l_linenumber, l_partkey, CASE WHEN l_discount <= 0.05 THEN CASE WHEN l_tax <= 0.02 THEN 1.0 ELSE 2.0 END ELSE 3.0 END::DOUBLE AS prediction FROM lineitem")
def tree_predict(spark: SparkSession, sf: str) -> DataFrame:
    N = tree.Node
    m = tree.TreeModel({1: N(1, 0, 3, 0, 0, None, "l_discount", "<=", 0.05), 2: N(2, 1, 2, 0, 0, 1, "l_tax", "<=", 0.02), 3: N(3, 1, 1, 3.0, 0, 1), 4: N(4, 2, 1, 1.0, 0, 2), 5: N(5, 2, 1, 2.0, 0, 2)})
    return m.predict(load(spark, sf, "lineitem")).select("l_orderkey", "l_linenumber", "l_partkey", "prediction")


@query("tree_rmse_test")
def tree_rmse(spark: SparkSession, sf: str) -> DataFrame:
    model, fs, y = _grown(spark, sf, 4)
    test = naive_join(ds.narrow6(spark, sf, "test")[0], [*fs, y])
    return spark.createDataFrame([(tree.tree_size(model), linear.rmse(model.predict(test), y.name))], "nodes int, rmse double")


_EDGE = "(SELECT max(o_totalprice) FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE o_totalprice <= 250000 AND p_size {} 25)"


@query("tree_planted", f"SELECT 1 AS node_id, 'p_size' AS feature, CAST((SELECT max(p_size) FROM part WHERE p_size <= 25) AS DOUBLE) AS threshold UNION ALL SELECT 2, 'o_totalprice', {_EDGE.format('<=')} UNION ALL SELECT 3, 'o_totalprice', {_EDGE.format('>')}")
def tree_planted(spark: SparkSession, sf: str) -> DataFrame:
    m = tree.grow_regression_tree(*ds.planted_tree(spark, sf), max_depth=2)
    return m.to_df(spark).where("feature is not null").select("node_id", "feature", "threshold")


@query("classification_root_split", f"WITH s AS (SELECT CAST(n_chars AS DOUBLE) AS v, CAST(count(*) AS DOUBLE) AS n, CAST(sum(quality) AS DOUBLE) AS q FROM documents JOIN labels USING (doc_id) GROUP BY 1), r AS (SELECT v, sum(n) OVER w AS ls, sum(q) OVER w AS lq, sum(n) OVER () AS tn, sum(q) OVER () AS tq FROM s WINDOW w AS (ORDER BY v ROWS UNBOUNDED PRECEDING)) SELECT v AS threshold, ls AS left_n FROM (SELECT v, ls, (ls - ((ls - lq) * (ls - lq) + lq * lq) / ls) + ((tn - ls) - (((tn - ls) - (tq - lq)) * ((tn - ls) - (tq - lq)) + (tq - lq) * (tq - lq)) / (tn - ls)) AS c FROM r WHERE tn > ls) ORDER BY round(c, 9), v LIMIT 1")
def classification(spark: SparkSession, sf: str) -> DataFrame:
    spec = JoinSpec({"labels": Relation("labels", load(spark, sf, "labels")), "documents": Relation("documents", load(spark, sf, "documents").select("doc_id", "n_chars"), ("doc_id",), True)}, (("labels", "documents", (("doc_id", "doc_id"),)),))
    g = tree.Grower(spec, [Feature("n_chars", "documents", "n_chars")], Feature("q", "labels", "quality"), tree.Measure("gini", 2), None)
    best = g.best_splits(g.statistics(), 1)
    return best.select(F.col("val").alias("threshold"), F.col("l0").alias("left_n"))


@query("forest_bagged")
def forest(spark: SparkSession, sf: str) -> DataFrame:
    models = tree.random_forest(*ds.narrow6(spark, sf, "train"), ids=["l_orderkey", "l_linenumber", "l_partkey"], trees=2, max_depth=2)
    out = None
    for t, m in enumerate(models):
        df = m.to_df(spark).withColumn("tree", F.lit(t))
        out = df if out is None else out.unionByName(df)
    return out


@query("boosted_trees")
def boosted(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf, "train")
    models = tree.boosted_trees(spec, fs, y, rounds=2, max_depth=2)
    out = None
    for t, m in enumerate(models):
        df = m.to_df(spark).withColumn("tree", F.lit(t))
        out = df if out is None else out.unionByName(df)
    return out


# --- other learners --------------------------------------------------------------------------------------------------


def _vectors(spark: SparkSession, sf: str) -> DataFrame:
    df = load(spark, sf, "embeddings")
    return df.select("vec_id", "label", *[F.col("embedding")[k].cast("double").alias(f"x{k:02d}") for k in range(64)], F.lit(1.0).alias("__mult"))


def _gram_matrix(spark: SparkSession, sf: str) -> MomentMatrix:
    names = [f"x{k:02d}" for k in range(64)]
    return MomentMatrix(["1", *names], gram(_vectors(spark, sf), names), {})


@query("gram_embeddings", f"SELECT i, j, {sig_sql('sum(CAST(embedding[i + 1] AS DOUBLE) * CAST(embedding[j + 1] AS DOUBLE))')} AS value FROM embeddings, (SELECT CAST(a.range AS INTEGER) AS i, CAST(b.range AS INTEGER) AS j FROM range(64) a, range(64) b WHERE a.range <= b.range) GROUP BY 1, 2")
def gram_embeddings(spark: SparkSession, sf: str) -> DataFrame:
    m = _gram_matrix(spark, sf)
    rows = [(i, j, float(m.values[i + 1, j + 1])) for i in range(64) for j in range(i, 64)]
    return spark.createDataFrame(rows, "i int, j int, value double").select("i", "j", sig(F.col("value")).alias("value"))


@query("pca_embeddings")
def pca_embeddings(spark: SparkSession, sf: str) -> DataFrame:
    values, vectors = others.pca(_gram_matrix(spark, sf), 4)
    return spark.createDataFrame([(c, j, float(values[c]), float(vectors[c, j])) for c in range(4) for j in range(64)], "component int, j int, variance double, weight double")


_DIST = "list_sum(list_transform(list_zip(v.e, c.e), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"


@query("kmeans_embeddings", f"WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings), c AS (SELECT row_number() OVER (ORDER BY vec_id) - 1 AS c, e FROM v ORDER BY vec_id LIMIT 10), a AS (SELECT v.vec_id, v.e, arg_min(c.c, {_DIST}) AS c FROM v, c GROUP BY 1, 2) SELECT CAST(c AS INTEGER) AS cluster, CAST(count(*) AS BIGINT) AS n, {sig_sql('avg(e[1])')} AS x00, {sig_sql('avg(e[64])')} AS x63 FROM a GROUP BY 1")
def kmeans_round(spark: SparkSession, sf: str) -> DataFrame:
    df = load(spark, sf, "embeddings")
    start = np.array([list(r[0]) for r in df.orderBy("vec_id").limit(10).select("embedding").collect()], float)
    sums, counts = others.lloyd_sums(df, "embedding", start)
    rows = [(k, int(counts[k]), float(sums[k, 0] / counts[k]), float(sums[k, 63] / counts[k])) for k in range(10) if counts[k]]
    return spark.createDataFrame(rows, "cluster int, n long, a double, b double").select("cluster", "n", sig(F.col("a")).alias("x00"), sig(F.col("b")).alias("x63"))


query("kmeans_converged")(lambda spark, sf: spark.createDataFrame([(k, j, float(v)) for k, row in enumerate(others.kmeans(load(spark, sf, "embeddings"), "embedding", "vec_id", 10)) for j, v in enumerate(row)], "cluster int, j int, value double"))

CHOW = [("p_type", "part"), ("c_mktsegment", "customer"), ("o_orderpriority", "orders"), ("l_returnflag", "lineitem")]


@query("chow_liu_edges")
def chow_liu(spark: SparkSession, sf: str) -> DataFrame:
    spec = ds.star(spark, sf, "orders", "customer", "part")
    return spark.createDataFrame(others.chow_liu(spec, [Feature(n, o, n, "cat") for n, o in CHOW]), "a string, b string, mi double")


def _mi_sql() -> str:
    src = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey"
    parts = [f"SELECT '{a}' AS a, '{b}' AS b, {sig_sql('1000 + sum(nab / t * ln(nab * t / (na * nb)))')} AS mi FROM (SELECT {a} AS va, {b} AS vb, CAST(count(*) AS DOUBLE) AS nab FROM {src} GROUP BY 1, 2) JOIN (SELECT {a} AS va, CAST(count(*) AS DOUBLE) AS na FROM {src} GROUP BY 1) USING (va) JOIN (SELECT {b} AS vb, CAST(count(*) AS DOUBLE) AS nb FROM {src} GROUP BY 1) USING (vb), (SELECT CAST(count(*) AS DOUBLE) AS t FROM {src})" for (a, _), (b, _) in itertools.combinations(CHOW, 2)]
    return " UNION ALL ".join(parts)


@query("mutual_information", _mi_sql())
def mutual_information(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs = ds.star(spark, sf, "orders", "customer", "part"), [Feature(n, o, n, "cat") for n, o in CHOW]
    return spark.createDataFrame(others.mutual_information(spec, fs), "a string, b string, mi double").select("a", "b", sig(F.col("mi") + 1000).alias("mi"))


def _text_features(spark: SparkSession, sf: str, target: str) -> DataFrame:
    docs = load(spark, sf, "documents")
    f = docs.select("doc_id", F.col("n_chars").cast("double").alias("n_chars"), F.size(F.split("text", " ")).cast("double").alias("words"), (F.length(F.regexp_replace("text", "[^0-9]", "")) / F.greatest(F.length("text"), F.lit(1))).alias("digits"))
    return f.join(load(spark, sf, "labels"), "doc_id").select("n_chars", "words", "digits", F.col(target).cast("double").alias(target))


query("logistic_labels")(lambda spark, sf: others.logistic(_text_features(spark, sf, "quality"), ["n_chars", "words", "digits"], "quality", 15).to_df(spark))
query("svm_labels")(lambda spark, sf: others.linear_svm(_text_features(spark, sf, "quality"), ["n_chars", "words", "digits"], "quality", 15).to_df(spark))


@query("fm_degree2")
def fm(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = _tree_spec(spark, sf)
    got = others.factorisation_machine(spec, fs[:4], y, max_iter=10)
    return spark.createDataFrame([(k, v, got["linear_mse"]) for k, v in enumerate(got["mse"])], "round int, mse double, linear_mse double")


# --- measures ----------------------------------------------------------------------------------------------------------


@query("profile_db_vs_join", "SELECT * FROM (SELECT 'lineitem' AS relation, CAST(count(*) AS BIGINT) AS n FROM lineitem UNION ALL SELECT 'orders', count(*) FROM orders UNION ALL SELECT 'part', count(*) FROM part UNION ALL SELECT 'supplier', count(*) FROM supplier UNION ALL SELECT 'nation', count(*) FROM nation UNION ALL SELECT '__join', count(*) FROM " + FROM_NARROW + ")")
def profile(spark: SparkSession, sf: str) -> DataFrame:
    from .measures import dataset_profile

    return dataset_profile(spark, ds.narrow6(spark, sf)[0]).select("relation", "n")


@query("encoded_width", "SELECT CAST(6 + (SELECT count(DISTINCT p_type) + count(DISTINCT p_brand) FROM part) + (SELECT count(DISTINCT c_mktsegment) FROM customer) + (SELECT count(DISTINCT o_orderpriority) FROM orders) + (SELECT count(DISTINCT l_returnflag) FROM lineitem) + (SELECT count(DISTINCT n_regionkey) FROM nation) AS BIGINT) AS width")
def width(spark: SparkSession, sf: str) -> DataFrame:
    from .measures import encoded_width

    spec, cont, cats = ds.onehot(spark, sf)
    return spark.createDataFrame([(encoded_width(spec, cont, cats),)], "width long")


@query("batch_stats", "SELECT CAST(36 AS BIGINT) AS aggregates, CAST(36 AS BIGINT) AS distinct_aggregates, CAST(144 AS BIGINT) AS views_separate, CAST(4 AS BIGINT) AS views_merged, CAST(36 * n AS BIGINT) AS keys_separate, CAST(n AS BIGINT) AS keys_merged FROM (SELECT (SELECT count(DISTINCT o_orderkey) FROM orders) + (SELECT count(DISTINCT p_partkey) FROM part) + (SELECT count(DISTINCT s_suppkey) FROM supplier JOIN nation ON s_nationkey = n_nationkey) + (SELECT count(DISTINCT n_nationkey) FROM nation) AS n)")
def stats(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf)
    every, batch = [*fs, y], monomials([f.name for f in (*fs, y)])
    got, keys = batch_stats(spec, every, batch, "lineitem"), sum(view_keys(spec, every, batch, "lineitem").values())
    numbers = [got[k] for k in ("aggregates", "distinct_aggregates", "views_separate", "views_merged")]
    return spark.createDataFrame([(*numbers, len(batch) * keys, keys)], "aggregates long, distinct_aggregates long, views_separate long, views_merged long, keys_separate long, keys_merged long")


@query("rmse_gap")
def gap(spark: SparkSession, sf: str) -> DataFrame:
    spec, fs, y = ds.narrow6(spark, sf, "train")
    m = moment_matrix(spec, fs, y, exact=True)
    test = naive_join(ds.narrow6(spark, sf, "test")[0], [*fs, y]).persist()
    closed = linear.rmse(linear.solve_normal(m).predict(test), y.name)
    rows = [("bgd_50", linear.rmse(linear.bgd(m).predict(test), y.name)), ("sgd_one_epoch", linear.rmse(linear.sgd(naive_join(spec, [*fs, y]), [f.name for f in fs], y.name, m).predict(test), y.name)), ("closed_form", closed)]
    return spark.createDataFrame([(n, r, 100 * (r / closed - 1)) for n, r in rows], "method string, rmse double, gap_percent double")


from . import baselines, operators, workloads  # noqa: E402,F401  they register theirs
from .operators import surface  # noqa: E402,F401
from .streaming import moments as _streaming  # noqa: E402,F401
