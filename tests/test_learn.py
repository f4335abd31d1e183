"""Learners against closed forms, brute force and planted answers."""

import numpy as np
import pytest
from relml import baselines, datasets as ds
from relml.learn import linear, others, tree
from relml.measures import jobs_of, rmse_gap
from relml.moments import moment_matrix, moment_tensor
from relml.plans.views import naive_join
from relml.spec import Feature, JoinSpec, Relation


def test_descent_reaches_closed_form(spark, sf):
    m = moment_matrix(*ds.narrow6(spark, sf, "train"), exact=True)
    closed = linear.solve_normal(m)
    assert rmse_gap(linear.loss(m, linear.bgd(m).theta) ** 0.5, linear.loss(m, closed.theta) ** 0.5) < 1
    want = baselines.numpy_lstsq(*ds.narrow6(spark, sf, "train")).theta
    assert np.allclose(closed.theta, want, rtol=1e-5, atol=1e-8)
    assert linear.coordinate_descent(m).theta == pytest.approx(closed.theta, rel=1e-5)
    assert linear.rss(m, linear.ridge(m, 1.0)) >= linear.rss(m, closed)


def test_naive_rounds_equal_hoisted_and_cost_jobs(spark, sf):
    spec, fs, y = ds.narrow6(spark, sf, "quarter")
    m = moment_matrix(spec, fs, y)
    assert linear.bgd_naive(spec, fs, y, m, max_iter=3).theta == pytest.approx(linear.bgd(m, max_iter=3).theta, rel=1e-6)
    assert jobs_of(spark, lambda: linear.bgd(m, max_iter=500)) == 0
    few, many = (jobs_of(spark, lambda t=t: linear.bgd_naive(spec, fs, y, m, max_iter=t)) for t in (1, 4))
    assert many > few


def test_planted_linear(spark, sf):
    m = linear.solve_normal(moment_matrix(*ds.planted_linear(spark, sf)))
    assert m.theta == pytest.approx([12.5, 2, 0.5, -0.01], abs=1e-6)


def test_degenerate_inputs(spark):
    one = JoinSpec({"t": Relation("t", spark.createDataFrame([(1.0, 5.0, 2.0)], "x double, c double, y double"))})
    m = linear.solve_normal(moment_matrix(one, [Feature("x", "t", "x"), Feature("c", "t", "c")], Feature("y", "t", "y")))
    assert m.theta == pytest.approx([2, 0, 0])
    flat = JoinSpec({"t": Relation("t", spark.createDataFrame([(float(k), 7.0) for k in range(5)], "x double, y double"))})
    got = tree.grow_regression_tree(flat, [Feature("x", "t", "x")], Feature("y", "t", "y"))
    assert len(got.nodes) == 1 and got.nodes[1].prediction == 7
    single = tree.grow_regression_tree(one, [Feature("x", "t", "x")], Feature("y", "t", "y"))
    assert len(single.nodes) == 1 and single.nodes[1].n == 1


def brute_tree(x, y, depth, at=1, out=None):
    out = {} if out is None else out
    sse = lambda v: float((v**2).sum() - v.sum() ** 2 / len(v)) if len(v) else 0.0
    out[at] = (len(y), float(y.mean()), None, None)
    if depth and len(y) > 1:
        best = None
        for f in range(x.shape[1]):
            for t in np.unique(x[:, f])[:-1]:
                left = x[:, f] <= t
                c = (sse(y[left]) + sse(y[~left]), f, t)
                best = c if best is None or c < best else best
        if best and best[0] < sse(y) - 1e-9 * max(1, sse(y)):
            out[at] = (len(y), float(y.mean()), best[1], best[2])
            left = x[:, best[1]] <= best[2]
            brute_tree(x[left], y[left], depth - 1, 2 * at, out)
            brute_tree(x[~left], y[~left], depth - 1, 2 * at + 1, out)
    return out


def test_tree_equals_brute_force(spark, sf):
    spec = ds.star(spark, sf, "part", "supplier", "orders", "customer").filtered(lineitem="l_orderkey < 60")
    fs = [Feature("l_tax", "lineitem", "l_tax"), Feature("p_size", "part", "p_size"), Feature("s_nationkey", "supplier", "s_nationkey"), Feature("c_nationkey", "customer", "c_nationkey")]
    y = Feature("y", "lineitem", "l_quantity")
    got = tree.grow_regression_tree(spec, fs, y, 3)
    pdf = naive_join(spec, [*fs, y]).toPandas()
    want = brute_tree(pdf[[f.name for f in fs]].to_numpy(float), pdf["y"].to_numpy(float), 3)
    assert set(got.nodes) == set(want)
    for k, (n, mean, f, t) in want.items():
        node = got.nodes[k]
        assert (node.n, round(node.prediction, 9)) == (n, round(mean, 9))
        assert node.feature == (None if f is None else fs[f].name) and node.threshold == t
    leaves = [k for k in got.nodes.values() if k.feature is None]
    assert sum(k.n for k in leaves) == got.nodes[1].n
    assert got.sse() < got.nodes[1].cost and tree.tree_size(got) <= 31
    pred = got.predict(naive_join(spec, [*fs, y])).toPandas()
    assert ((pred.prediction - pred.y) ** 2).sum() == pytest.approx(got.sse())


def joined_rows(spec, fs, y):
    """Features and label of the inner join, by nested loops."""
    import itertools

    rows = {n: [r.asDict() for r in spec.rows(n).collect()] for n in spec.relations}
    names, out = list(rows), []
    for combo in itertools.product(*rows.values()):
        at = dict(zip(names, combo))
        if all(at[a][p] == at[b][c] for a, b, cols in spec.on for p, c in cols):
            times = int(np.prod([at[n].get(r.mult, 1) if r.mult else 1 for n, r in spec.relations.items()]))
            out += [[at[f.owner][f.expr] for f in fs] + [at[y.owner][y.expr]]] * times
    return np.array(out, float).reshape(len(out), len(fs) + 1)


@pytest.mark.parametrize("shape,seed,unique", [("star", 1, False), ("star", 2, True), ("snowflake", 3, False), ("snowflake", 8, True), ("snowflake", 11, False)])
def test_tree_is_grown_on_the_join(spark, shape, seed, unique):
    """Keys repeat, dangle and miss; a dimension is filtered; the root's rows have multiplicities."""
    from test_plans import make

    spec, fs = make(spark, shape, seed, unique)
    root = spec.relations["root"]
    spec = JoinSpec({**spec.relations, "root": Relation("root", root.df.selectExpr("*", "(u * 7 + k1 * 3 + k2) % 11 as y", "1 + u % 2 as m"), mult="m")}, spec.on).filtered(d1="v > 0")
    y = Feature("y", "root", "y")
    data = joined_rows(spec, fs, y)
    got = tree.grow_regression_tree(spec, fs, y, 3)
    binned = tree.grow_regression_tree(spec, fs, y, 3, max_bins=16)  # more bins than values
    assert binned.rows() == got.rows()
    if not len(data):
        assert len(got.nodes) == 1 and got.nodes[1].n == 0
        return
    want = brute_tree(data[:, :-1], data[:, -1], 3)
    assert set(got.nodes) == set(want)
    for k, (n, mean, f, t) in want.items():
        node = got.nodes[k]
        assert node.n == n and node.prediction == pytest.approx(mean)
        assert node.feature == (None if f is None else fs[f].name) and node.threshold == t


@pytest.mark.parametrize("most", [1 << 20, 0])
def test_binned_tree_looks_partners_up(spark, monkeypatch, most):
    """A level explodes no row by its features; branches that are sent around and ones held in parts give the same tree.  Keys
    dangle, miss and are null; the root and a dimension have multiplicities; a dimension is filtered."""
    monkeypatch.setattr(tree, "LOOKUP", most)
    monkeypatch.setattr(tree, "DEALT", most)
    rng = np.random.default_rng(6)
    root = spark.createDataFrame([(int(a) if a < 9 else None, int(b), float(u), int(t), int(m)) for a, b, u, t, m in zip(*(rng.integers(0, k, 40) for k in (10, 7, 9, 50, 3)))], "k1 long, k2 long, u double, t long, m long")
    table = lambda keys, k, names: spark.createDataFrame([(i, *map(int, rng.integers(0, k, 2))) for i in keys], names)
    rel = {"root": Relation("root", root, mult="m"), "d1": Relation("d1", table(range(2, 12), 5, "a long, b long, v long"), ("a",), True), "d2": Relation("d2", table(range(6), 4, "c long, w long, n long"), ("c",), True, "n"), "d3": Relation("d3", table(range(1, 5), 8, "e long, z long, x long"), ("e",), True)}
    spec = JoinSpec(rel, (("root", "d1", (("k1", "a"),)), ("root", "d2", (("k2", "c"),)), ("d1", "d3", (("b", "e"),)))).filtered(d3="x > 0")
    fs, y = [Feature("z", "d3", "z"), Feature("u", "root", "u"), Feature("w", "d2", "w"), Feature("v", "d1", "v")], Feature("t", "root", "t")
    data = joined_rows(spec, fs, y)
    grower = tree.Grower(spec, fs, y, tree.Measure("sse"), 4000)  # more bins than values, and more than a byte tells
    try:
        plan = grower.looked.rows._jdf.queryExecution().optimizedPlan().toString()
        got = grower.grow(3, 1)
    finally:
        grower.close()
    want = brute_tree(data[:, :-1], data[:, -1], 3)
    assert "Generate" not in plan and len(data) and want[1][0] == got.nodes[1].n
    assert {k: (n.n, n.feature, n.threshold) for k, n in got.nodes.items()} == {k: (n, None if f is None else fs[f].name, t) for k, (n, _, f, t) in want.items()}


def test_quantiles_of_columns(spark, monkeypatch):
    """Ranks of the edges are off by three in KEPT of the rows at most; few values are exact, and NaN is no edge."""
    monkeypatch.setattr(tree, "KEPT", 256)
    df = spark.range(40_000, numPartitions=5).selectExpr("cast(id * 7919 % 40000 as double) as x", "cast(id % 3 as double) as z", "case when id % 2 = 0 then double('NaN') else cast(id % 8 as double) end as n")
    got = tree.quantiles(df, 8)
    assert len(got["x"]) == 8 and np.abs((np.array(got["x"]) + 1) / 40_000 - np.arange(1, 9) / 8).max() <= 3 / 256 and got["x"][-1] == 39_999
    assert got["z"] == [0, 1, 2] and got["n"] == [1, 3, 5, 7]
    assert tree.quantiles(df.where("x < 0"), 8) == {"x": [], "z": [], "n": []}


def test_filtered_dimension_has_no_say(spark):
    """Two of three fact rows join nothing; they must not be learned from."""
    fact = spark.createDataFrame([(1, 1.0, 10.0), (1, 2.0, 20.0), (2, 3.0, 99.0)], "k long, x double, y double")
    dim = spark.createDataFrame([(1, 5.0), (2, 8.0)], "d long, z double")
    spec = JoinSpec({"f": Relation("f", fact), "d": Relation("d", dim, ("d",), True)}, (("f", "d", (("k", "d"),)),)).filtered(d="z > 7.5")
    got = tree.grow_regression_tree(spec, [Feature("x", "f", "x"), Feature("z", "d", "z")], Feature("y", "f", "y"))
    assert len(got.nodes) == 1 and (got.nodes[1].n, got.nodes[1].prediction) == (1, 99)


def test_deep_tree(spark):
    """All 511 nodes of depth 8 over 256 rows, two relations in turn."""
    rng = np.random.default_rng(4)
    y = rng.permutation(256)
    fact = spark.createDataFrame([(i, float(i % 16), float(y[i])) for i in range(256)], "k long, x double, y double")
    dim = spark.createDataFrame([(i, float(i)) for i in range(256)], "d long, z double")
    spec = JoinSpec({"f": Relation("f", fact), "d": Relation("d", dim, ("d",), True)}, (("f", "d", (("k", "d"),)),))
    got = tree.grow_regression_tree(spec, [Feature("x", "f", "x"), Feature("z", "d", "z")], Feature("y", "f", "y"), 8)
    want = brute_tree(np.array([[i % 16, i] for i in range(256)], float), y.astype(float), 8)
    assert {k: (n.n, n.feature, n.threshold) for k, n in got.nodes.items()} == {k: (n, None if f is None else "xz"[f], t) for k, (n, _, f, t) in want.items()}
    assert max(n.depth for n in got.nodes.values()) == 8


def test_boosting_on_the_join_equals_boosting_on_joined_rows(spark):
    from test_plans import make

    spec, fs = make(spark, "snowflake", 3, False)
    y = Feature("y", "root", "u * 3 + k1 - k2")
    fs = [f for f in fs if f.name != "u"]
    models = tree.boosted_trees(spec, fs, y, rounds=3, max_depth=2, max_bins=None)
    rows = naive_join(spec, [*fs, y]).toPandas()
    x, rest = rows[[f.name for f in fs]].to_numpy(float), rows["y"].to_numpy(float)
    for m in models:
        want = brute_tree(x, rest, 2)
        assert {k: (n.n, n.feature, n.threshold) for k, n in m.nodes.items()} == {k: (n, None if f is None else fs[f].name, t) for k, (n, _, f, t) in want.items()}
        at = np.ones(len(x), int)
        for _ in range(2):
            at = np.array([k if want[k][2] is None else 2 * k + (x[i, want[k][2]] > want[k][3]) for i, k in enumerate(at)])
        rest = rest - 0.5 * np.array([want[k][1] for k in at])


def test_planted_tree_and_categories(spark, sf):
    m = tree.grow_regression_tree(*ds.planted_tree(spark, sf), max_depth=2)
    assert m.sse() == pytest.approx(0, abs=1e-6) and m.nodes[1].feature == "p_size"
    df = spark.createDataFrame([(c, v) for c, v in zip("aabbccdd", [1.0, 1.0, 9.0, 9.0, 1.0, 1.0, 9.0, 9.0])], "c string, y double")
    got = tree.grow_regression_tree(JoinSpec({"t": Relation("t", df)}), [Feature("c", "t", "c", "cat")], Feature("y", "t", "y"), 2)
    assert got.nodes[1].categories == ["a", "c"] and got.sse() == 0
    labels = JoinSpec({"t": Relation("t", df.selectExpr("c", "cast(y > 5 as int) as y"))})
    for cost in ("gini", "entropy"):
        g = tree.grow_classification_tree(labels, [Feature("c", "t", "c", "cat")], Feature("y", "t", "y"), 2, cost)
        assert g.nodes[2].prediction == 0 and g.nodes[3].prediction == 1


def test_other_learners(spark, sf):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 2))
    rows = [(float(p), float(q), float(2 * p - q > 0.3)) for p, q in x]
    df = spark.createDataFrame(rows, "p double, q double, y double")
    for fit in (others.logistic, others.linear_svm):
        m = fit(df, ["p", "q"], "y", 25)
        assert np.mean(((x @ m.theta[1:] + m.theta[0]) > 0) == [r[2] for r in rows]) > 0.95
    spec = JoinSpec({"t": Relation("t", df.selectExpr("p", "q", "3 * p * q + p as y"))})
    fm = others.factorisation_machine(spec, [Feature("p", "t", "p"), Feature("q", "t", "q")], Feature("y", "t", "y"), 1, 20)
    assert fm["mse"][-1] < 0.05 * fm["linear_mse"]
    vecs = spark.createDataFrame([(i, [float(i % 2) * 10 + 0.1 * (i % 3), 1.0]) for i in range(20)], "id long, v array<double>")
    assert sorted(others.kmeans(vecs, "v", "id", 2)[:, 0].round()) == [0, 10]
    values, comps = others.pca(moment_matrix(JoinSpec({"t": Relation("t", df)}), [Feature("p", "t", "p"), Feature("q", "t", "q")], strategy="gram"), 2)
    assert np.allclose(sorted(np.linalg.eigvalsh(np.cov(x.T, bias=True))), sorted(values))
    cats = JoinSpec({"t": Relation("t", spark.createDataFrame([(str(i % 2), str(i % 2), str(i % 3)) for i in range(60)], "a string, b string, c string"))})
    edges = others.chow_liu(cats, [Feature(n, "t", n, "cat") for n in "abc"])
    assert edges[0][:2] == ("a", "b") and len(edges) == 2


def test_one_epoch_is_worse_or_equal_on_train(spark, sf):
    spec, fs, y = ds.narrow6(spark, sf, "train")
    m = moment_matrix(spec, fs, y)
    one = linear.sgd(naive_join(spec, [*fs, y]), [f.name for f in fs], y.name, m, 1000)
    assert linear.loss(m, one.theta) >= linear.loss(m, linear.solve_normal(m).theta)


def test_memory_failure(spark, sf):
    spec, fs, y = ds.narrow6(spark, sf)
    with pytest.raises(baselines.MemoryBudgetExceeded):
        baselines.dense_copy(spec, fs, 1000)


def test_models_are_saved(spark, tmp_path):
    m = linear.LinearModel(["1", "x"], np.array([1.0, 2.0]))
    m.save(spark, str(tmp_path / "l"))
    assert sorted(linear.LinearModel.load(spark, str(tmp_path / "l")).theta) == [1, 2]
    t = tree.TreeModel({1: tree.Node(1, 0, 3, 0.5, 0)})
    t.save(spark, str(tmp_path / "t"))
    assert tree.TreeModel.load(spark, str(tmp_path / "t")).rows() == t.rows()


def test_workloads_cover_their_grids(monkeypatch, spark, sf):
    from relml import workloads as w

    trees, planned, naive = [], [], []
    monkeypatch.setattr(w, "end_to_end_tree", lambda s, d, name, v, clock: trees.append((name, v)))
    monkeypatch.setattr(w, "aggregate", lambda spec, every, batch, *a, **k: planned.append(len(batch)))
    monkeypatch.setattr(w, "planning_seconds", lambda df: 0.0)
    monkeypatch.setattr(w.linear, "bgd_naive", lambda *a, max_iter, **k: naive.append(max_iter))
    catalog = w.query.__globals__["QUERIES"]
    try:
        catalog["wl_tree"](spark, sf)
    except Exception:
        assert trees  # a clock without rows makes no table
    sizes = [r["size"] for r in catalog["wl_planning"](spark, sf).collect() if r.model == "linear"]
    catalog["wl_rounds_sweep"](spark, sf)
    assert sorted(trees) == sorted((d, v) for d in w.DATASETS for v in ("full", "quarter"))
    assert sum(planned) == sum(sizes) and max(planned) <= 90
    assert naive == [1, 10, 50, 100, 500]


def test_rivals_of_accuracy_share_their_join(monkeypatch, spark, sf):
    """wl_accuracy joins the training rows once for its rivals, holds them, and lets them go."""
    from relml import workloads as w

    used, made, learn, grow = [], [], w.linear.sgd, w.baselines.library_tree
    held = w.baselines.held_rows
    monkeypatch.setattr(w, "DATASETS", {"wide35": ds.wide35})
    monkeypatch.setattr(w.baselines, "held_rows", lambda *a: made.append(held(*a)) or made[-1])
    monkeypatch.setattr(w.linear, "sgd", lambda df, *a: used.append((df, df.is_cached)) or learn(df, *a))
    monkeypatch.setattr(w.baselines, "library_tree", lambda *a, rows=None: used.append((rows, rows.is_cached)) or grow(*a, rows=rows))
    got = w.query.__globals__["QUERIES"]["wl_accuracy"](spark, sf).collect()
    assert [r.method for r in got] == ["closed_form", "bgd_50", "one_epoch", "tree", "library_tree"]
    assert len(made) == 1 and all(df is made[0] and cached for df, cached in used) and len(used) == 2 and not made[0].is_cached
    spec, fs, y = ds.wide35(spark, sf, "train")
    want = naive_join(spec, [*fs, y])
    assert made[0].select(*[c for c in want.columns]).exceptAll(want).isEmpty() and made[0].count() == want.count()


def test_sgd_blocks_and_scale(spark, sf):
    """Batches of the rows in order, as one loop over them would take them."""
    spec, fs, y = ds.narrow6(spark, sf)
    names = [f.name for f in (*fs, y)]
    rows = naive_join(spec, [*fs, y]).orderBy(*names).coalesce(1).persist()
    scale = linear.Scale.of(rows, names)
    got = linear.sgd(rows, names[:-1], y.name, scale, 700, 2)
    z = (rows.toPandas()[names].to_numpy(float) - scale.mean) / scale.dev
    w = np.zeros(len(names))
    for _ in range(2):
        for lo in range(0, len(z), 700):
            x = np.column_stack([np.ones(len(z[lo : lo + 700])), z[lo : lo + 700]])
            w = w - 0.1 * (x[:, :-1].T @ (x[:, :-1] @ w - x[:, -1])) / len(x)
    b = w[1:] * scale.dev[-1] / scale.dev[:-1]
    assert got.theta == pytest.approx([scale.mean[-1] + w[0] * scale.dev[-1] - b @ scale.mean[:-1], *b], rel=1e-6)


def test_sgd_takes_blocks_of_many_partitions_at_once(monkeypatch, spark, sf):
    """The driver's jobs do not grow with partitions, and few bytes at a time change no weight."""
    spec, fs, y = ds.narrow6(spark, sf)
    names = [f.name for f in (*fs, y)]
    parts = naive_join(spec, [*fs, y]).repartitionByRange(40, names[0]).persist()
    scale = linear.Scale.of(parts, names)
    z = [(np.array([tuple(r)[: len(names)] for r in p]) - scale.mean) / scale.dev for p in parts.rdd.glom().collect()]
    w = np.zeros(len(names))
    for p in z:
        for lo in range(0, len(p), 100):
            x = np.column_stack([np.ones(len(p[lo : lo + 100])), p[lo : lo + 100]])
            w = w - 0.1 * x[:, :-1].T @ (x[:, :-1] @ w - x[:, -1]) / len(x)
    want = linear._back(scale, w[1:], scale.mean, scale.dev)
    want[0] += w[0] * scale.dev[-1]
    got = []
    jobs = jobs_of(spark, lambda: got.append(linear.sgd(parts, names[:-1], y.name, scale, 100)))
    assert len(z) == 40 and jobs < 12
    monkeypatch.setattr(linear, "TURN_BYTES", 4000)
    got.append(linear.sgd(parts, names[:-1], y.name, scale, 100))
    for m in got:
        assert m.theta == pytest.approx(want, rel=1e-8)
    parts.unpersist()


def test_protocol_holds_relations_by_their_join_attributes(spark, sf):
    """The protocol's relations are indexed before the clock starts: the root's first join exchanges nothing."""
    from relml.layout import held_indexed

    past = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for dataset in (ds.narrow6, ds.wide35):
            given, fs, y = dataset(spark, sf)
            want = naive_join(given, [*fs, y])
            with held_indexed(spark, given) as spec:
                got = naive_join(spec, [*fs, y])
                plan = got._jdf.queryExecution().executedPlan().toString().split("InMemoryRelation")[0]
                assert "Exchange hashpartitioning(k_lineitem_l_orderkey" not in plan and "SortMergeJoin" in plan
                assert got.exceptAll(want).isEmpty() and got.count() == want.count()
                held = [r.df for r in spec.relations.values()]
                assert all(df.is_cached for df in held)
            assert not any(df.is_cached for df in held)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", past)


def test_protocol_uses_the_held_relations(monkeypatch, spark, sf):
    from relml import workloads as w

    seen, real = [], w.moment_matrix
    monkeypatch.setattr(w, "DATASETS", {"narrow6": ds.narrow6})
    monkeypatch.setattr(w, "moment_matrix", lambda spec, *a: seen.append(all(r.df.is_cached for r in spec.relations.values())) or real(spec, *a))
    got = w.query.__globals__["QUERIES"]["wl_protocol"](spark, sf).collect()
    assert [(r.method, r.runs) for r in got] == [(m, 4) for m in ("relml", "join_only", "library_normal", "one_epoch_sgd")]
    assert seen == [True] * 5 and all(r.seconds > 0 for r in got)


def test_layouts(spark, sf):
    from pyspark.sql import functions as F
    from relml.layout import flatten_single, session_conf, stored_sorted
    from relml.measures import resources

    df = spark.range(3).select("id", F.struct(F.lit(1).alias("x")).alias("a"), F.struct(F.struct(F.lit(2).alias("y")).alias("b"), F.lit(3).alias("z")).alias("c"))
    assert flatten_single(df).columns == ["id", "a", "c_b", "c_z"]
    with pytest.raises(ValueError):
        flatten_single(df.withColumn("c_z", F.lit(1)))
    assert session_conf()["spark.memory.offHeap.enabled"] == "true"
    spec, fs, y = ds.narrow6(spark, sf)
    want = moment_matrix(spec, fs, y, exact=True, root="lineitem")
    with stored_sorted(spark, spec, "orders", 4, "lineitem") as stored:
        got = moment_matrix(stored, fs, y, "sorted", exact=True, root="lineitem")
        assert (got.values == want.values).all()
    used = resources(spark, lambda: spark.range(1000).repartition(3).count())
    assert used["shuffle_bytes"] > 0 and used["stages"] >= 2


def test_pair_counts_by_sets_equal_counting(spark):
    """Null categories, multiplicities, repeated rows and clashing names."""
    import itertools
    from collections import Counter

    rows = [(["x", "y", None][i % 3], str(i % 2 if i % 3 else 0), "z" if i % 5 else None, float(i), float(i % 4)) for i in range(90)]
    df = spark.createDataFrame(rows, "n string, value string, f1 string, c1 double, m double")
    spec = JoinSpec({"t": Relation("t", df, mult="m")})
    names, cats = ["n", "value", "f1"], [Feature(c, "t", c, "cat") for c in ("n", "value", "f1")]

    def counted(s):
        out = Counter()
        for r in rows:
            out[tuple(r[names.index(c)] for c in s)] += r[4]
        return out

    total = sum(r[4] for r in rows)
    for a, b, mi in others.mutual_information(spec, cats):
        ab, ca, cb = counted((a, b)), counted((a,)), counted((b,))
        assert abs(mi - sum(v / total * np.log(v * total / (ca[x,] * cb[y,])) for (x, y), v in ab.items() if v)) < 1e-9
    want = Counter()
    for c in names:
        for (x,), v in counted((c,)).items():
            want[c, x, c, x] += v
        for r in rows:
            want[c, r[names.index(c)], "c1", ""] += r[3] * r[4]
    for a, b in itertools.combinations(names, 2):
        for (x, y), v in counted((a, b)).items():
            want[a, x, b, y] += v
    got = moment_tensor(spec, [Feature("c1", "t", "c1")], cats).collect()
    assert len(got) == len(want) and all(abs(want[tuple(r)[:4]] - r[4]) < 1e-6 for r in got)
    none = JoinSpec({"t": Relation("t", df.where("false"), mult="m")})
    assert not moment_tensor(none, [], cats[:1]).collect() and all(mi == 0 for *_, mi in others.mutual_information(none, cats)) and others.chow_liu(none, cats[:1]) == []


def test_lstsq_takes_any_number_of_rows(spark):
    """More rows than the driver may hold as a frame, with multiplicities."""
    df = spark.range(250_000).selectExpr("id", "id % 7 as a", "id % 11 as b", "3 + 2 * (id % 7) - (id % 11) + case when id % 77 = 5 then 1 else 0 end as y", "1 + id % 2 as m")
    spec = JoinSpec({"r": Relation("r", df, mult="m")})
    fs = [Feature(n, "r", n) for n in ("a", "b")]
    got = baselines.numpy_lstsq(spec, fs, Feature("y", "r", "y"))
    x = np.array(df.select("a", "b", "y", "m").collect(), float)
    w = np.sqrt(x[:, 3])
    want = np.linalg.lstsq(np.column_stack([np.ones(len(x)), x[:, :2]]) * w[:, None], x[:, 2] * w, rcond=None)[0]
    assert np.allclose(got.theta, want, rtol=1e-9)


def test_frames_take_any_number_of_rows(spark):
    df = spark.range(250_000).selectExpr("id % 7 as a", "id % 11 as b")
    assert tuple(baselines.frame_totals(df, "a", "b").first()) == (250_000, float(sum(k % 7 * (k % 11) for k in range(250_000))))
    assert baselines.frame_totals(df.where("a < 0"), "a", "b").first().n == 0


def test_benchmark_clears_up_off_the_clock():
    import time

    from relml.measures import benchmark

    calls = []
    assert benchmark(lambda: calls.append("run"), 2, after=lambda: (calls.append("after"), time.sleep(0.2))) < 0.1
    assert calls == ["run", "after"] * 3
