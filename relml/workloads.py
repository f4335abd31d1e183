"""The paper's experiments on the given tables; each returns its table of measurements."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines
from . import datasets as ds
from .catalog import query
from .learn import linear, tree
from .layout import drop_dir, held_indexed, scratch_dir, stored_sorted
from .measures import Clock, benchmark, counts_of, dataset_profile, encoded_width, let_go, observed, planning_seconds, resources, values_of
from .moments import moment_matrix, moment_tensor
from .plans.views import aggregate, monomials, naive_join, passes

DATASETS = {"narrow6": ds.narrow6, "wide35": ds.wide35}


def end_to_end_linear(spark: SparkSession, sf: str, dataset: str, variant: str, clock: Clock) -> None:
    """Ours in one step; the others build the joined rows first and take nothing from ours."""
    spec, fs, y = DATASETS[dataset](spark, sf, variant)
    names = [f.name for f in (*fs, y)]
    with clock.timed("relml", dataset, variant, "learn"):
        linear.bgd(moment_matrix(spec, fs, y))
    joined = naive_join(spec, [*fs, y])
    for method in ("library_normal", "one_epoch_sgd"):
        with clock.timed(method, dataset, variant, "join"):
            rows = joined.persist()
            rows.count()
        with clock.timed(method, dataset, variant, "learn"):
            if method == "library_normal":
                from pyspark.ml.regression import LinearRegression

                LinearRegression(labelCol=y.name, solver="normal").fit(baselines.assembled(rows, names[:-1]))
            else:
                linear.sgd(rows, names[:-1], y.name, linear.Scale.of(rows, names))
        rows.unpersist()


def end_to_end_tree(spark: SparkSession, sf: str, dataset: str, variant: str, clock: Clock, max_bins: int = 64) -> None:
    from pyspark.ml.regression import DecisionTreeRegressor, GBTRegressor

    spec, fs, y = DATASETS[dataset](spark, sf, variant)
    with clock.timed("relml", dataset, variant, "learn"):
        tree.grow_regression_tree(spec, fs, y, 4, max_bins=max_bins)
    with clock.timed("library", dataset, variant, "join"):
        rows = naive_join(spec, [*fs, y]).persist()
        rows.count()
    for method, learner in (("library_tree", DecisionTreeRegressor(labelCol=y.name, maxDepth=4, maxBins=max_bins)), ("library_boosted", GBTRegressor(labelCol=y.name, maxIter=1, maxDepth=4, maxBins=max_bins, seed=1))):
        with clock.timed(method, dataset, variant, "learn"):
            learner.fit(baselines.assembled(rows, [f.name for f in fs]))
    rows.unpersist()
    let_go(spark)


@query("wl_protocol")
def wl_protocol(spark: SparkSession, sf: str) -> DataFrame:
    """Means of four runs after one that warms up, on relations that are held by their join attributes before the clock starts."""
    rows = []
    for d in DATASETS:
        given, fs, y = DATASETS[d](spark, sf)
        names = [f.name for f in (*fs, y)]
        with held_indexed(spark, given) as spec:

            def one_epoch():
                joined = naive_join(spec, [*fs, y]).persist()
                try:
                    linear.sgd(joined, names[:-1], y.name, linear.Scale.of(joined, names))
                finally:
                    joined.unpersist()

            for method, fn in (("relml", lambda: linear.bgd(moment_matrix(spec, fs, y))), ("join_only", lambda: naive_join(spec, [*fs, y]).write.format("noop").mode("overwrite").save()), ("library_normal", lambda: baselines.library_linear(spec, fs, y)), ("one_epoch_sgd", one_epoch)):
                rows.append((d, method, 4, benchmark(fn, after=lambda: let_go(spark))))
    return spark.createDataFrame(rows, "dataset string, method string, runs int, seconds double")


@query("wl_linreg")
def wl_linreg(spark: SparkSession, sf: str) -> DataFrame:
    clock = Clock()
    for d in DATASETS:
        for v in ("full", "quarter"):
            end_to_end_linear(spark, sf, d, v, clock)
    return clock.to_df(spark)


@query("wl_tree")
def wl_tree(spark: SparkSession, sf: str) -> DataFrame:
    clock = Clock()
    for d in DATASETS:
        for v in ("full", "quarter"):
            end_to_end_tree(spark, sf, d, v, clock)
    return clock.to_df(spark)


@query("wl_accuracy")
def wl_accuracy(spark: SparkSession, sf: str) -> DataFrame:
    """Test RMSE by method, and its gap to the closed form in per cent.  The rivals learn from one set of joined rows."""
    rows = []
    for d in DATASETS:
        spec, fs, y = DATASETS[d](spark, sf, "train")
        m, names = moment_matrix(spec, fs, y), [f.name for f in (*fs, y)]
        test = naive_join(DATASETS[d](spark, sf, "test")[0], [*fs, y]).persist()
        found = {k: linear.rmse(model.predict(test), y.name) for k, model in (("closed_form", linear.solve_normal(m)), ("bgd_50", linear.bgd(m)))}
        let_go(spark)
        found["tree"] = linear.rmse(tree.grow_regression_tree(spec, fs, y, 4, max_bins=32).predict(test), y.name)
        let_go(spark)
        joined = baselines.held_rows(spec, [*fs, y])
        found["one_epoch"] = linear.rmse(linear.sgd(joined, names[:-1], y.name, linear.Scale.of(joined, names)).predict(test), y.name)
        lib = baselines.library_tree(spec, fs, y, rows=joined)
        joined.unpersist()
        found["library_tree"] = linear.rmse(lib.transform(baselines.assembled(test, names[:-1])), y.name)
        rows += [(d, k, float(found[k]), 100 * (found[k] / found["closed_form"] - 1)) for k in ("closed_form", "bgd_50", "one_epoch", "tree", "library_tree")]
        test.unpersist()
        let_go(spark)
    return spark.createDataFrame(rows, "dataset string, method string, rmse double, gap_percent double")


@query("wl_onehot")
def wl_onehot(spark: SparkSession, sf: str) -> DataFrame:
    """Encoded width; sums that dense and sparse codes need, and their seconds."""
    spec, cont, cats = ds.onehot(spark, sf)
    clock = Clock()
    with clock.timed("sparse", "onehot", "full", "moments"):
        pairs = moment_tensor(spec, cont, cats).count()
    from .spec import Feature

    dense = list(cont)
    for c in cats:
        for r in spec.rows(c.owner).selectExpr(f"{c.expr} as v").distinct().orderBy("v").collect():
            dense.append(Feature(f"{c.name}_{r.v}", c.owner, f"case when {c.expr} = '{r.v}' then 1 else 0 end"))
    with clock.timed("dense", "onehot", "full", "moments"):
        moment_matrix(spec, dense, Feature("l_quantity", "lineitem", "l_quantity"), strategy="gram")
    w = encoded_width(spec, cont, cats)
    return spark.createDataFrame([(r[0], w, pairs if r[0] == "sparse" else (w + 2) * (w + 3) // 2, r[5]) for r in clock.rows], "method string, width int, sums int, seconds double")


@query("wl_tuples_sweep")
def wl_tuples(spark: SparkSession, sf: str) -> DataFrame:
    """50 rounds over growing inputs, hoisted and naive."""
    clock = Clock()
    spec0, fs, y = ds.narrow6(spark, sf)
    top = spec0.relations["orders"].df.count()
    for share in (0.05, 0.1, 0.25, 0.5, 1.0):
        spec = spec0.filtered(lineitem=f"l_orderkey <= {int(top * share)}")
        m = moment_matrix(spec, fs, y)
        with clock.timed("hoisted", "narrow6", str(share), "total"):
            linear.bgd(moment_matrix(spec, fs, y), max_iter=50)
        with clock.timed("naive", "narrow6", str(share), "total"):
            linear.bgd_naive(spec, fs, y, m, max_iter=50)
    return clock.to_df(spark)


@query("wl_rounds_sweep")
def wl_rounds(spark: SparkSession, sf: str) -> DataFrame:
    clock = Clock()
    spec, fs, y = ds.narrow6(spark, sf)
    tuples, orders = (spec.relations[r].df.count() for r in ("lineitem", "orders"))
    spec = spec.filtered(lineitem=f"l_orderkey <= {orders * 10_000 // tuples}")  # about 10 000 tuples
    m = moment_matrix(spec, fs, y)
    for rounds in (1, 10, 50, 100, 500):
        with clock.timed("hoisted", "narrow6", str(rounds), "total"):
            linear.bgd(moment_matrix(spec, fs, y), max_iter=rounds)
        with clock.timed("naive", "narrow6", str(rounds), "total"):
            linear.bgd_naive(spec, fs, y, m, max_iter=rounds)
    return clock.to_df(spark)


@query("wl_aggregate_layers")
def wl_layers(spark: SparkSession, sf: str) -> DataFrame:
    """The moment matrix of the running example by each strategy, floating and exact; the exact ones must agree.  speed_up:
    seconds of the strategy before by its own."""
    rows, sums = [], set()
    spec, fs, y = ds.running3(spark, sf)
    every, batch = [*fs, y], monomials([f.name for f in (*fs, y)])
    for exact in (False, True):
        past = None
        for s in ("materialised", "pushdown", "merged", "multi", "trie"):
            clock, got = Clock(), None
            for run in range(2):  # the first one warms up
                with clock.timed(s, "running3", "full", "moments", run):
                    got = tuple(aggregate(spec, every, batch, s, exact=exact).first())
            if exact:
                sums.add(got)
            seconds = clock.rows[-1][5]
            rows.append((s, exact, seconds, past / seconds if past else None))
            past = seconds
    if len(sums) != 1:
        raise AssertionError("strategies differ")
    return spark.createDataFrame(rows, "method string, exact boolean, seconds double, speed_up double")


@query("wl_layout_layers")
def wl_layout(spark: SparkSession, sf: str) -> DataFrame:
    """Layouts of the same 36 sums: row-at-a-time Python, interpreted, generated, hashed or merged look-ups, relations stored
    sorted, Arrow blocks."""
    clock = Clock()
    spec, fs, y = ds.narrow6(spark, sf)
    every = [*fs, y]
    batch, names = monomials([f.name for f in every]), [f.name for f in every]
    places = [[names.index(n) for n in m] for m in batch]

    def products(*row):
        out = []
        for at in places:
            v = 1.0
            for k in at:
                v *= row[k]
            out.append(v)
        return out

    each = F.udf(products, "array<double>")
    with clock.timed("row_udf", "narrow6", "full", "moments"):
        rows = naive_join(spec, every).select(each(*names).alias("p"))
        rows.agg(*[F.sum(F.col("p")[k]) for k in range(len(batch))]).first()
    held = spark.conf.get("spark.sql.codegen.wholeStage")
    try:
        spark.conf.set("spark.sql.codegen.wholeStage", "false")
        with clock.timed("interpreted", "narrow6", "full", "moments"):
            aggregate(spec, every, batch, "multi").first()
    finally:
        spark.conf.set("spark.sql.codegen.wholeStage", held)
    for s in ("multi", "hashed", "sorted"):
        with clock.timed({"multi": "generated"}.get(s, s), "narrow6", "full", "moments"):
            aggregate(spec, every, batch, s).first()
    with stored_sorted(spark, spec, "orders", root="lineitem") as stored, clock.timed("stored_sorted", "narrow6", "full", "moments"):
        aggregate(stored, every, batch, "sorted", root="lineitem").first()
    with clock.timed("arrow_blocks", "narrow6", "full", "moments"):
        moment_matrix(spec, fs, y, strategy="gram")
    return clock.to_df(spark)


@query("wl_streamed_full")
def wl_streamed(spark: SparkSession, sf: str) -> DataFrame:
    """The full data set where a library that holds it in memory fails: the joined rows go through a text file in
    mini-batches instead."""
    rows = []
    for d in DATASETS:
        spec, fs, y = DATASETS[d](spark, sf)
        names = [f.name for f in (*fs, y)]
        try:
            baselines.dense_copy(spec, [*fs, y], baselines.DENSE_BUDGET)
            rows.append((d, "dense_copy", "ok", None))
        except MemoryError as e:
            rows.append((d, "dense_copy", type(e).__name__, None))
        path = scratch_dir(spark, "csv")
        try:
            model = baselines.sgd_from_csv(spark, spec, fs, y, path)
            rows.append((d, "streamed_csv", "ok", linear.rmse(model.predict(naive_join(spec, [*fs, y])), y.name)))
        finally:
            drop_dir(spark, path)
        closed = linear.solve_normal(moment_matrix(spec, fs, y))
        rows.append((d, "relml", "ok", linear.rmse(closed.predict(naive_join(spec, [*fs, y])), y.name)))
    return spark.createDataFrame(rows, "dataset string, method string, status string, rmse double")


@query("wl_resources")
def wl_resources(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes shuffled and spilled, peak execution memory and rows read by the way of computing the same sums.  Where a sum has a
    pass of its own, the passes run one after the other, each without the files of those before."""
    spec, fs, y = ds.narrow6(spark, sf)
    every = [*fs, y]
    batch, rows = monomials([f.name for f in every]), []

    def one_by_one(s: str) -> None:
        left = passes(spec, every, batch, s)
        while left:  # a pass's frame goes with its shuffle files
            left.pop(0).first()
            let_go(spark)

    for s in ("materialised", "pushdown", "merged", "multi", "trie", "gram"):
        if s in ("pushdown", "merged"):
            got = resources(spark, lambda s=s: one_by_one(s))
        elif s == "gram":
            got = resources(spark, lambda: moment_matrix(spec, fs, y, strategy="gram"))
        else:
            got = resources(spark, lambda s=s: aggregate(spec, every, batch, s).first())
        let_go(spark)
        rows.append((s, *[got[k] for k in ("stages", "shuffle_bytes", "spill_bytes", "peak_bytes", "input_rows")]))
    return spark.createDataFrame(rows, "method string, stages int, shuffle_bytes long, spill_bytes long, peak_bytes long, input_rows long")


@query("profile_attributes", "SELECT table_name AS relation, CAST(count(*) AS INTEGER) AS attributes FROM information_schema.columns WHERE table_name IN ('lineitem', 'orders', 'part', 'supplier', 'nation') GROUP BY 1")
def profile_attributes(spark: SparkSession, sf: str) -> DataFrame:
    return dataset_profile(spark, ds.narrow6(spark, sf)[0]).where("relation <> '__join'").select("relation", "attributes")


def _counts_sql() -> str:
    narrow = [(n, "orders" if n[0] == "o" else "part" if n[0] == "p" else "supplier" if n[0] == "s" else "lineitem") for n in ("l_extendedprice", "l_discount", "l_tax", "o_totalprice", "p_retailprice", "s_acctbal")]
    sets = {"narrow6": ("lineitem orders part supplier nation", 6, 0, narrow), "wide35": ("lineitem orders customer part supplier", 35, 0, [(e.replace("dow(", "dayofweek("), o) for _, o, e in ds.WIDE]), "onehot": ("lineitem orders customer part supplier nation region", 6, 6, [*narrow, *ds.CATEGORIES])}
    whole = lambda parts: "CAST(" + " + ".join(f"(SELECT count({e}) FROM {o})" for e, o in parts) + " AS BIGINT)"
    return " UNION ALL ".join(f"SELECT '{d}' AS dataset, CAST({len(rel.split())} AS INTEGER) AS relations, CAST({cont} AS INTEGER) AS continuous, CAST({cat} AS INTEGER) AS categorical, {whole([('*', r) for r in rel.split()])} AS tuples, {whole(fs)} AS feature_values" for d, (rel, cont, cat, fs) in sets.items())


@query("profile_counts", _counts_sql())
def profile_counts(spark: SparkSession, sf: str) -> DataFrame:
    """Relations and features of each data set, the rows of its relations and the values that the features have there."""
    rows = []
    spec, cont, cats = ds.onehot(spark, sf)
    for d, spec, fs in [*[(d, *DATASETS[d](spark, sf)[:2]) for d in DATASETS], ("onehot", spec, [*cont, *cats])]:
        rows.append((d, *counts_of(spec, fs), *values_of(spec, fs)))
    return spark.createDataFrame(rows, "dataset string, relations int, continuous int, categorical int, tuples long, feature_values long")


@query("observed_join", "SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(l_linenumber) AS DOUBLE) AS total FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey")
def observed_join(spark: SparkSession, sf: str) -> DataFrame:
    """Rows and multiplicities as a join's own run reports them; line numbers stand for multiplicities."""
    from dataclasses import replace

    spec, fs, _ = ds.running3(spark, sf)
    rel = spec.relations["lineitem"]
    spec = replace(spec, relations=spec.relations | {"lineitem": replace(rel, mult="l_linenumber")})
    df, seen = observed(naive_join(spec, fs), "join", "__mult")
    df.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["rows"], seen.get["total"])], "n long, total double")


@query("wl_planning")
def wl_planning(spark: SparkSession, sf: str) -> DataFrame:
    rows = []
    for d in DATASETS:
        spec, fs, y = DATASETS[d](spark, sf)
        batch = monomials([f.name for f in (*fs, y)])
        rows.append((d, "linear", len(batch), sum(planning_seconds(aggregate(spec, [*fs, y], batch[k : k + 90], "multi")) for k in range(0, len(batch), 90))))
        rows.append((d, "tree", len(fs), planning_seconds(tree.Grower(spec, fs, y, tree.Measure("sse"), None).statistics())))
    return spark.createDataFrame(rows, "dataset string, model string, size int, seconds double")


@query("wl_profile")
def wl_profile(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for d in DATASETS:
        df = dataset_profile(spark, DATASETS[d](spark, sf)[0]).withColumn("dataset", F.lit(d))
        out = df if out is None else out.unionByName(df)
    return out
