"""Every strategy gives the sums of the join."""

import itertools
import random

import pytest
from relml import datasets as ds
from relml.measures import scans
from relml.moments import MomentMatrix, moment_matrix
from relml.plans.views import STRATEGIES, aggregate, batch_stats, merge_views, monomials, push_down
from relml.spec import CyclicJoin, Feature, JoinSpec, Relation, build_join_tree
from relml.typing import SchemaError


def make(spark, shape: str, seed: int, unique: bool):
    """A root with two branches; in a snowflake the first has a child of its own.  Keys repeat, dangle and miss."""
    r = random.Random(seed)
    table = lambda cols, n: spark.createDataFrame([tuple(r.randrange(4) for _ in cols) for _ in range(n)] or [], ", ".join(f"{c} long" for c in cols))
    root = table(["k1", "k2", "u"], 12)
    d1 = spark.createDataFrame([(k, r.randrange(3), r.randrange(5)) for k in range(3)], "a long, b long, v long") if unique else table(["a", "b", "v"], 5)
    d2 = table(["c", "w"], 4)
    rel = {"root": Relation("root", root), "d1": Relation("d1", d1, ("a",), unique), "d2": Relation("d2", d2)}
    on = [("root", "d1", (("k1", "a"),)), ("root", "d2", (("k2", "c"),))]
    fs = [Feature("u", "root", "u"), Feature("v", "d1", "v"), Feature("w", "d2", "w")]
    if shape == "snowflake":
        rel["d3"] = Relation("d3", table(["e", "z"], 4))
        on.append(("d1", "d3", (("b", "e"),)))
        fs.append(Feature("z", "d3", "z"))
    return JoinSpec(rel, tuple(on)), fs


def brute(spec, fs, batch):
    rows = {n: [r.asDict() for r in rel.df.collect()] for n, rel in spec.relations.items()}
    names, out = list(rows), [0] * len(batch)
    for combo in itertools.product(*rows.values()):
        at = dict(zip(names, combo))
        if all(at[a][p] == at[b][c] for a, b, cols in spec.on for p, c in cols):
            for k, m in enumerate(batch):
                v = 1
                for f in m:
                    v *= at[next(g.owner for g in fs if g.name == f)][f]
                out[k] += v
    return out


@pytest.mark.parametrize("shape,seed,unique", [("star", 1, False), ("star", 2, True), ("snowflake", 3, False), ("snowflake", 4, True)])
def test_strategies_agree(spark, shape, seed, unique):
    spec, fs = make(spark, shape, seed, unique)
    batch = monomials([f.name for f in fs])
    want = brute(spec, fs, batch)
    for s in STRATEGIES:
        got = aggregate(spec, fs, batch, s, exact=True, root="root").first()
        assert [int(v or 0) for v in got] == want, s
    for order in ([], ["d2"], ["d1"], ["d1", "d2"], ["d2", "d1"]):
        got = aggregate(spec, fs, batch, "trie", exact=True, root="root", order=order).first()
        assert [int(v or 0) for v in got] == want, order
    assert [float(v or 0) for v in aggregate(spec, fs, batch, "multi", root="d2").first()] == [float(v) for v in want]
    m = moment_matrix(spec, fs, exact=True, strategy="gram")
    assert [m.at(*(list(x) + ["1", "1"])[:2]) for x in batch] == want


def test_exact_blocks():
    import numpy as np
    from relml.moments import exact_block

    rng = np.random.default_rng(3)
    x = np.column_stack([np.ones(5000, np.int64), rng.integers(-(10**18), 10**18, 5000), rng.integers(0, 50, 5000), rng.integers(-(10**9), 10**9, 5000)])
    for weight in (np.ones(5000, np.int64), rng.integers(0, 4, 5000)):
        want = (x.astype(object) * weight.astype(object)[:, None]).T @ x.astype(object)
        assert (exact_block(x, weight) == want).all()


def test_empty_relation(spark):
    spec, fs = make(spark, "star", 5, False)
    empty = JoinSpec({**spec.relations, "d2": Relation("d2", spec.relations["d2"].df.where("false"))}, spec.on)
    m = moment_matrix(empty, fs[:2], fs[2], exact=True, root="root")
    assert m.count == 0 and all(v == 0 for row in m.values for v in row)


def test_group_by_and_multiplicity(spark):
    spec, fs = make(spark, "star", 6, False)
    twice = JoinSpec({**spec.relations, "root": Relation("root", spec.relations["root"].df.selectExpr("*", "2 as m"), mult="m")}, spec.on)
    a = aggregate(spec, fs, [(), ("u", "w")], exact=True, root="root").first()
    b = aggregate(twice, fs, [(), ("u", "w")], exact=True, root="root").first()
    assert [2 * int(v) for v in a] == [int(v) for v in b]
    cat = Feature("v", "d1", "cast(v as string)", "cat")
    rows = aggregate(spec, [fs[0], cat], [(), ("u",)], groups=["v"], root="d1").collect()
    assert sum(r.a0 for r in rows) == int(a[0])


def test_cyclic_and_ears(spark):
    t = lambda *c: spark.createDataFrame([tuple(range(len(c)))], ", ".join(f"{x} int" for x in c))
    with pytest.raises(CyclicJoin):
        JoinSpec.natural([Relation("r", t("a", "b")), Relation("s", t("b", "c")), Relation("t", t("c", "a"))])
    chain = JoinSpec.natural([Relation("r", t("a", "b")), Relation("s", t("b", "c")), Relation("t", t("c", "d")), Relation("q", t("d", "e"))])
    tree = build_join_tree(chain, "r")
    assert tree.below("r") == {"r", "s", "t", "q"}
    with pytest.raises(CyclicJoin):
        build_join_tree(JoinSpec(chain.relations, chain.on[:2]))


def test_structure(spark, sf):
    spec, fs, y = ds.narrow6(spark, sf)
    batch = monomials([f.name for f in (*fs, y)])
    assert len(batch) == 1 + 7 + 28
    stats = batch_stats(spec, [*fs, y], batch, "lineitem")
    assert stats["views_merged"] == 4 and stats["views_separate"] == 4 * 36
    tree = build_join_tree(spec, "lineitem")
    owner = {f.name: f.owner for f in (*fs, y)}
    merged = merge_views([push_down([m], tree, owner) for m in batch])
    assert all(len(set(n.values)) == len(n.values) for n in merged.walk())
    assert all(n == 1 for n in scans(aggregate(spec, [*fs, y], batch)).values())


def test_unknown_and_null(spark):
    df = spark.createDataFrame([(1, 2.0), (2, None)], "k long, v double")
    spec = JoinSpec({"t": Relation("t", df)})
    with pytest.raises(SchemaError):
        moment_matrix(spec, [Feature("z", "t", "zz")])
    with pytest.raises(SchemaError):
        moment_matrix(JoinSpec({"t": Relation("t", spark.createDataFrame([("a",)], "s string"))}), [Feature("s", "t", "s")])
    with pytest.raises(Exception, match="NULL in feature"):
        moment_matrix(spec, [Feature("v", "t", "v")])
    assert moment_matrix(JoinSpec(spec.relations, null_policy="drop"), [Feature("v", "t", "v")]).count == 1
    assert moment_matrix(JoinSpec(spec.relations, null_policy="zero"), [Feature("v", "t", "v")]).count == 2


def test_declared_key_is_checked(spark):
    with pytest.raises(SchemaError):
        Relation("t", spark.createDataFrame([(1,), (1,)], "k int"), ("k",), True).checked()


def test_matrix_algebra(spark, tmp_path):
    spec, fs = make(spark, "star", 7, False)
    m = moment_matrix(spec, fs[:2], fs[2], exact=True, root="root")
    assert (m + m - m).values.tolist() == m.values.tolist()
    m.save(spark, str(tmp_path / "m"))
    assert MomentMatrix.load(spark, str(tmp_path / "m")).values.tolist() == m.values.tolist()
    assert m.select(["1", "v"]).at("1", "v") == m.at("1", "v")
    gram = moment_matrix(spec, fs[:2], fs[2], strategy="gram", root="root")
    assert abs(gram.floats() - m.floats()).max() < 1e-9


def test_passes_are_the_columns_of_the_aggregate(spark, sf):
    from relml.plans.views import passes

    spec, fs, y = ds.running3(spark, sf)
    every, batch = [*fs, y], monomials([f.name for f in (*fs, y)])[:4]
    for s in ("pushdown", "merged"):
        ones = passes(spec, every, batch, s, exact=True)
        assert [tuple(x.columns) for x in ones] == [(f"a{k}",) for k in range(4)]
        assert [x.first()[0] for x in ones] == list(aggregate(spec, every, batch, s, exact=True).first())
