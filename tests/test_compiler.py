"""From source text to sums and a compiled loop."""

import numpy as np
import pytest
from relml import catalog
from relml import datasets as ds
from relml.ir import interpret
from relml.learn import linear
from relml.moments import moment_matrix
from relml.plans import compiler
from relml.plans.views import naive_join
from relml.spec import Feature, JoinSpec, Relation


def test_program_becomes_one_batch(spark, sf):
    spec, fs, y = ds.narrow6(spark, sf)
    names = [compiler.ONE, *[f.name for f in fs]]
    c = compiler.compile_program(compiler.least_squares(names, y.name), spec, [*fs, y])
    assert not c.residual and len(set(c.batch)) == 1 + 6 + 21 + 1 + 6
    env = {"A": 1e-14, "R": 7, "T0": dict.fromkeys(names, 0.5)}
    got = c.run(env)
    m = moment_matrix(spec, fs, y, strategy="multi")
    want = linear.bgd(m, 1e-14, 7, raw=True, theta0=np.full(7, 0.5)).theta
    assert [got[n] for n in names] == pytest.approx(list(want), rel=1e-9)
    assert dict(c.run(env, compiled=False)) == pytest.approx(dict(got))
    for stage in ("naive", "specialised", "sums", "views", "spark"):
        assert c.explain(stage)
    assert "lineitem" in c.explain("views") and "Physical Plan" in c.explain("spark")


def test_compiled_step_is_straight_line():
    stages = catalog.running_stages()
    loop = compiler.extract_aggregates(stages["specialised"], "Q")[1]
    env = {f"agg{i}": i + 1 for i in range(10)} | {"T0": {"i": 1, "s": 2, "c": 3, "p": 4}}
    assert dict(compiler.run_program(loop, env)) == {k: interpret(loop, env).get(k) for k in "iscp"}
    with pytest.raises(compiler.NotCompiled):
        compiler.compile_step(compiler.frontend.parse("{f: (1 if theta(f) > 0 else 2) for f in F}"), "theta", ["a"], {"F": ("a",)})


def test_more_features_than_rows_stays_in_the_loop(spark):
    df = spark.createDataFrame([(1.0, 2.0, 3.0, 4.0), (2.0, 1.0, 1.0, 6.0)], "a double, b double, c double, y double")
    spec = JoinSpec({"t": Relation("t", df)})
    fs = [Feature(n, "t", n) for n in "abcy"]
    source = compiler.least_squares([compiler.ONE, "a", "b", "c"], "y")
    env = {"A": 0.1, "R": 3, "T0": dict.fromkeys([compiler.ONE, "a", "b", "c"], 0.0)}
    few, many = compiler.compile_program(source, spec, fs, rows=2), compiler.compile_program(source, spec, fs)
    assert few.residual and not many.residual
    got, want = few.run(env), many.run(env)
    assert {k: float(got[k]) for k in want} == pytest.approx(want)


def test_other_sums_are_asked_of_the_join(spark):
    df = spark.createDataFrame([(1.0, 2.0), (3.0, 1.0)], "a double, b double")
    spec = JoinSpec({"t": Relation("t", df)})
    fs = [Feature(n, "t", n) for n in "ab"]
    c = compiler.compile_program("s = sum(Q(x) * (x.a if x.b > 1.5 else 0) for x in keys(Q))\nreturn s", spec, fs)
    assert c.residual and float(c.run({}, exact=False)) == 1.0
    assert naive_join(spec, fs).count() == 2
