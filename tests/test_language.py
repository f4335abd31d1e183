"""Rules keep values, guards hold, and the derivation ends where it should."""

from hypothesis import given, settings
from hypothesis import strategies as st

import pytest
from relml import catalog, frontend, rewrite
from relml.ir import Add, Const, DynProj, FieldName, Fold, Iterate, Keys, Let, Lookup, MapLit, Mul, Neg, Proj, Rec, Record, SetLit, Tabulate, Var, alpha_equal, free, interpret, show, substitute
from relml.typing import INT, REAL, STR, SchemaError, map_of, rec, typecheck

x, y, a, b = Var("x"), Var("y"), Var("a"), Var("b")
bags = st.dictionaries(st.builds(lambda p, q: Record({"p": p, "q": q}), st.integers(-4, 4), st.integers(-4, 4)), st.integers(1, 3), max_size=4)
rows = lambda body: Fold("x", Keys(Var("Q")), Var("Q")(x) * body)

CASES = {
    rewrite.norm_distribute: [a * (b + Proj(Rec(("z",), (a,)), "z")), (a + b) * b],
    rewrite.norm_push_factor: [a * rows(Proj(x, "p")), rows(Proj(x, "q")) * a],
    rewrite.norm_neg_product: [a * Neg(b), Neg(a) * b],
    rewrite.norm_neg_fold: [Neg(rows(Proj(x, "p")))],
    rewrite.factor_common: [a * b + a * a],
    rewrite.factor_out_of_fold: [Fold("x", Keys(Var("Q")), a * Proj(x, "p"))],
    rewrite.hoist_from_fold: [Fold("x", Keys(Var("Q")), Let("z", a * b, Var("z") * Proj(x, "p")))],
    rewrite.hoist_from_loop: [Iterate("t", a, catalog.frontend.parse("round < 3"), Let("z", a * b, Var("t") + Var("z")), Var("t"))],
    rewrite.unroll_fold: [Fold("f", SetLit((Const(1), Const(2), Const(5))), Var("f") * a)],
    rewrite.merge_same_key: [MapLit((FieldName("k"),), (a,)) + MapLit((FieldName("k"),), (b,))],
    rewrite.merge_diff_key: [MapLit((FieldName("k"),), (a,)) + MapLit((FieldName("l"),), (b,))],
    rewrite.spec_access: [DynProj(Rec(("p",), (a,)), FieldName("p"))],
    rewrite.fuse_folds: [Let("s", rows(Proj(x, "p")), Let("t", rows(Proj(x, "q")), Var("s") * Var("t")))],
    rewrite.gen_inline: [Let("z", Const(3), Var("z") * a)],
    rewrite.gen_dead: [Let("z", a, b)],
    rewrite.gen_flatten: [Let("s", Let("t", a, Var("t") + b), Var("s") * b)],
    rewrite.gen_cse: [Let("s", a * b, Let("t", a * b, Var("s") + Var("t")))],
}


@pytest.mark.parametrize("rule", CASES, ids=lambda r: r.__name__)
@settings(max_examples=20, deadline=None)
@given(bag=bags, p=st.integers(-5, 5), q=st.integers(-5, 5))
def test_rule_keeps_value(rule, bag, p, q):
    env = {"Q": bag, "a": p, "b": q}
    for e in CASES[rule]:
        new = rule(e)
        assert new is not None and new != e
        assert interpret(new, env) == interpret(e, env)


def test_guards_hold():
    assert rewrite.factor_out_of_fold(Fold("x", Keys(Var("Q")), Proj(x, "p"))) is None
    assert rewrite.hoist_from_fold(Fold("x", Keys(Var("Q")), Let("z", Proj(x, "p"), Var("z")))) is None
    assert rewrite.hoist_from_loop(Iterate("t", a, Const(False), Let("z", Var("t"), Var("z")), Var("t"))) is None
    assert rewrite.gen_dead(Let("z", a, Var("z"))) is None
    assert rewrite.merge_diff_key(MapLit((a,), (b,)) + MapLit((b,), (a,))) is None
    assert rewrite.merge_same_key(MapLit((FieldName("k"),), (a,)) + MapLit((FieldName("l"),), (b,))) is None
    assert rewrite.fuse_folds(Let("s", rows(Proj(x, "p")), Let("t", rows(Var("s")), Var("t")))) is None
    assert rewrite.gen_cse(Let("s", a, Let("t", b, Var("t")))) is None
    assert rewrite.spec_dict(MapLit((a,), (b,))) is None
    assert rewrite.spec_tabulate(Tabulate("f", SetLit((a,)), b)) is None
    assert rewrite.unroll_fold(Fold("f", Keys(Var("Q")), a)) is None


def test_substitution_does_not_capture():
    e = Fold("x", Keys(Var("Q")), Proj(x, "p") * a)
    new = substitute(e, "a", x)
    assert "x" in free(new) and interpret(new, {"Q": {Record({"p": 2}): 1}, "x": 10}) == 20
    assert alpha_equal(Fold("u", Keys(Var("Q")), Proj(Var("u"), "p")), Fold("v", Keys(Var("Q")), Proj(Var("v"), "p")))


def test_push_factor_does_not_capture():
    e = Mul(x, Fold("x", Keys(Var("Q")), Proj(x, "p")))
    env = {"Q": {Record({"p": 2}): 1, Record({"p": 3}): 1}, "x": 10}
    assert interpret(rewrite.norm_push_factor(e), env) == interpret(e, env) == 50


@settings(max_examples=25, deadline=None)
@given(st.dictionaries(st.builds(lambda i, s, c, p: Record({"i": i, "s": s, "c": c, "p": p}), *[st.integers(0, 3)] * 4), st.integers(1, 2), max_size=5))
def test_derivation_keeps_value(bag):
    env = {"Q": bag, "T0": catalog.THETA0}
    got = [dict(interpret(e, env)) for e in catalog.running_stages().values()]
    assert all(g == got[0] for g in got)


def test_derivation_hoists():
    stages = catalog.running_stages()
    assert isinstance(stages["hoisted"], Let) and isinstance(stages["hoisted"].body, Iterate)
    assert "Q" not in free(stages["hoisted"].body)
    assert isinstance(stages["specialised"].value, Rec) and "sum[" not in show(stages["specialised"].body)


def test_more_features_than_rows_changes_nothing():
    few = rewrite.stages(frontend.program(catalog.update), lambda e: len(e.items) if isinstance(e, SetLit) else 2, lambda e: e == Keys(Var("Q")))
    assert few["scheduled"] == few["normalised"]
    assert "Q" in free(few["hoisted"].step if isinstance(few["hoisted"], Iterate) else few["hoisted"].body)


def test_spec_lookup_only_converted_dictionaries():
    assert rewrite.spec_lookup(Lookup(Var("d"), FieldName("k"))) is None
    e = Let("d", Rec(("k",), (a,)), Lookup(Var("d"), FieldName("k")))
    assert interpret(rewrite.everywhere(e, [rewrite.spec_lookup, rewrite.spec_access]), {"a": 4}) == 4


def test_types():
    q = map_of(rec(p=INT, n=STR), INT)
    assert typecheck(Fold("x", Keys(Var("Q")), Var("Q")(x) * Proj(x, "p")), {"Q": q}) == INT
    assert typecheck(Add(a, Const(1.5)), {"a": INT}) == REAL
    for bad in (Proj(x, "z"), Add(Proj(x, "n"), Const(1)), DynProj(x, Var("f"))):
        with pytest.raises(SchemaError):
            typecheck(bad, {"x": rec(p=INT, n=STR), "f": STR})


def test_frontend_rejects_what_it_does_not_know():
    with pytest.raises(SyntaxError):
        frontend.parse("lambda x: x")
    assert interpret(frontend.parse("{k: k * 2 for k in [1, 2]}")) == {1: 2, 2: 4}
    assert interpret(frontend.parse("max(k for k in [1, 7, 3])")) == 7
