"""Statements, text, relations, joins with unbound variables, batches and recursion."""

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from graphloop.algorithms.reach import graph_catalog, reach_avoiding, reach_procedure
from graphloop.operators import compat
from graphloop.plans import batches, locality, recursion, rewrite, runtime
from graphloop.plans import query as q
from graphloop.plans.catalog import Catalog
from graphloop.plans.compiler import compile_query
from graphloop.plans.parser import SyntaxProblem, parse_procedure, parse_query
from graphloop.plans.procedure import AskTrue, Fixpoint, Loop, MalformedProcedure, Procedure, Times, Until, validate
from graphloop.relation import Relation, fingerprint, same_set
from graphloop.algorithms.procedures import text_of
from graphloop.workloads.language import REACH

ONE = q.Values(("v",), ((1,),))


def grown(step, until, **options):
    body = Procedure().let("x", q.Project(q.VarRef("x"), ((q.call("+", "?v", step), "v"),)))
    return Procedure().let("x", ONE).loop(body, until, **options).ret("x")


def value(spark, proc, **options):
    return runtime.run(proc, Catalog(spark), **options).df.first()[0]


def test_do_until(spark):
    assert value(spark, grown(1, Times(1))) == 2
    done = AskTrue(q.Filter(q.VarRef("x"), q.call(">", "?v", 0)))
    assert value(spark, grown(5, done)) == 6  # the body runs before the condition is looked at
    with pytest.raises(runtime.RoundLimit):
        value(spark, grown(0, AskTrue(q.Filter(q.VarRef("x"), q.call(">", "?v", 99)))), max_rounds=3)
    with pytest.raises(runtime.TimeLimit):
        value(spark, grown(0, Until(lambda env, before: False)), timeout_s=0.001)
    with pytest.raises(runtime.StateCycle):
        value(spark, grown(0, Until(lambda env, before: False), guard=("x",)))


def test_global_scope_and_include(spark):
    inner = Procedure().let("y", q.Values(("w",), ((7,),)))
    proc = Procedure().let("x", ONE).loop(inner, Times(1)).ret("y")
    assert value(spark, proc) == 7
    assert value(spark, Procedure().include(grown(1, Times(2)), "z").ret("z")) == 3


def test_well_formedness():
    let = Procedure().let("a", ONE).statements[0]
    assert validate(Procedure([let]).ret("a")) == []
    bad = [
        Procedure([let]),
        Procedure().let("b", q.VarRef("a")).ret("b"),
        Procedure([let, Loop((let,), Times(0))]).ret("a"),
        Procedure([let, Loop((let,), Fixpoint("c"))]).ret("a"),
        Procedure().ret("a"),
        Procedure([*Procedure([let]).ret("a").statements, let]),
    ]
    assert all(validate(p) for p in bad)
    assert validate(bad[1], strict=False) == []


def test_malformed_is_not_run(spark):
    with pytest.raises(MalformedProcedure):
        runtime.run(Procedure().ret("a"), Catalog(spark))
    with pytest.raises(KeyError):
        compile_query(q.Pattern("?a", "nothing", "?b"), {}, Catalog(spark))


def test_text(spark):
    for text in (REACH, text_of("pr")):
        assert validate(parse_procedure(text)) == []
    assert validate(parse_procedure("LET x = (SELECT * WHERE { }); DO ( LET x = (SELECT * WHERE { }); ) WHILE (FIXPOINT(x)) RETURN(x)")) == []
    for wrong in ("LET x = SELECT", "RETURN x", "SELECT ?x", "LET x = (SELECT ?x WHERE { ?x }); RETURN(x);"):
        with pytest.raises(SyntaxProblem):
            parse_procedure(wrong)
    with pytest.raises(SyntaxProblem):
        parse_query("SELECT ?x WHERE { ?x g:p ?y ")
    found = compile_query(parse_query('SELECT (?a + 2 * 3 AS ?b) WHERE { VALUES ?a { 1 2 } FILTER(?a < 2 || ?a = -1) }'), {}, Catalog(spark)).df
    assert [r.b for r in found.collect()] == [7]


def test_errors_become_unbound(spark):
    rows = q.Values(("a", "b"), ((1, 0), (4, 2), (5, None)))
    found = compile_query(q.Extend(rows, "c", q.call("/", "?a", "?b")), {}, Catalog(spark))
    assert {(r.a, r.c) for r in found.df.collect()} == {(1, None), (4, 2.0), (5, None)}
    assert "c" in found.maybe
    kept = compile_query(q.Filter(rows, q.call(">", q.call("/", "?a", "?b"), 0)), {}, Catalog(spark)).df
    assert [r.a for r in kept.collect()] == [4]


MAYBE = st.one_of(st.none(), st.integers(0, 2))
ROWS = st.lists(st.tuples(MAYBE, MAYBE), max_size=6)


@settings(max_examples=12, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(a=ROWS, b=ROWS)
def test_unbound_joins_equal_the_definition(spark, a, b):
    left = Relation.of(spark.createDataFrame([(*r, k) for k, r in enumerate(a)], "x long, y long, i long"))
    right = Relation.of(spark.createDataFrame([(*r, k) for k, r in enumerate(b)], "x long, y long, j long"))
    fits = lambda m, n: all(p is None or r is None or p == r for p, r in zip(m, n, strict=True))
    meets = lambda m, n: any(p is not None and p == r for p, r in zip(m, n, strict=True))
    merged = lambda m, n: tuple(p if p is not None else r for p, r in zip(m, n, strict=True))
    pairs = [(*merged(m, n), i, j) for i, m in enumerate(a) for j, n in enumerate(b) if fits(m, n)]
    key = lambda rows: sorted(map(str, rows))
    assert key(tuple(r) for r in compat.join(left, right).df.select("x", "y", "i", "j").collect()) == key(pairs)
    gone = [(*m, i) for i, m in enumerate(a) if not any(fits(m, n) and meets(m, n) for n in b)]
    assert key(tuple(r) for r in compat.minus(left, right).df.select("x", "y", "i").collect()) == key(gone)
    some = [(*m, i) for i, m in enumerate(a) if any(fits(m, n) for n in b)]
    assert key(tuple(r) for r in compat.exists(left, right, False).df.select("x", "y", "i").collect()) == key(some)
    lone = [(*m, i, None) for i, m in enumerate(a) if not any(fits(m, n) for n in b)]
    assert key(tuple(r) for r in compat.left_join(left, right).df.select("x", "y", "i", "j").collect()) == key(pairs + lone)


def test_minus_and_not_exists_differ(spark):
    a = Relation(spark.createDataFrame([(1,)], "x long"))
    b = Relation(spark.createDataFrame([(2,)], "y long"))
    assert compat.minus(a, b).df.count() == 1
    assert compat.exists(a, b, negated=True).df.count() == 0


def test_products_are_guarded(spark, monkeypatch):
    monkeypatch.setattr(compat, "CROSS_ROWS", 2)
    big = lambda name: Relation(spark.range(5).toDF(name))
    with pytest.raises(compat.CrossJoinTooLarge):
        compat.join(big("a"), big("b"))


def test_fingerprints(spark):
    a = spark.createDataFrame([(1, None, 0.0), (2, "x", float("nan"))], "i long, s string, d double")
    b = spark.createDataFrame([(float("nan"), "x", 2), (-0.0, None, 1), (0.0, None, 1)], "d double, s string, i long")
    assert fingerprint(a) == fingerprint(b)
    moved = spark.createDataFrame([(1, "x", 0.0), (2, None, float("nan"))], "i long, s string, d double")
    assert fingerprint(a) != fingerprint(moved) and not same_set(a, moved)
    assert fingerprint(a.limit(0)) == fingerprint(b.limit(0))


def lanes(spark):
    rows = [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (6, 1)]
    return spark.createDataFrame(rows, "src long, dst long")


@pytest.mark.parametrize("options", [{}, {"rewrite": False}, {"rewrite": False, "mode": "inline"}, {"rewrite": False, "mode": "batched"}, {"include_source": True}])
def test_modes_agree(spark, options):
    found = reach_avoiding(lanes(spark), 2, spark.createDataFrame([(4,)], "node long"), **options)
    assert {r[0] for r in found.df.collect()} == {1, 2, 3}


def test_inline_has_a_limit(spark):
    with pytest.raises(runtime.InlineLimit):
        runtime.run(reach_procedure(2), graph_catalog(lanes(spark)), mode="inline", inline_rows=2)


def test_rewrites(spark):
    proc = reach_procedure(2)
    better = rewrite.optimise(proc)
    loops = [s for s in better.statements if isinstance(s, Loop)]
    assert len(loops) == 1 and isinstance(loops[0].until, AskTrue)
    assert rewrite.delta_rewrite(Loop(loops[0].body, Times(3))) is None
    inner = Procedure().let("k", q.VarRef("base")).let("x", q.Join(q.VarRef("x"), q.VarRef("k")))
    moved = rewrite.hoist_invariants(Loop(tuple(inner.statements), Times(2)))
    assert [getattr(s, "var", "loop") for s in moved] == ["k", "loop"]
    assert rewrite.dead_after(proc)["passable"] == 2


def test_columns_reach_the_scan(spark):
    """A constant subject reaches the scan of its table."""
    from graphloop.plans.catalog import tables_catalog

    found = compile_query(q.Pattern("?c", "customer_nation", "?n"), {}, tables_catalog(spark, "/root/testdata/sf0.001")).df
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "c_name" not in plan and "c_acctbal" not in plan


def test_batches_union_is_not_always_exact(spark):
    share = Relation(spark.createDataFrame([(1, 0.4), (2, 0.3)], "node long, share double"))
    total = q.Group(q.VarRef("share"), (), (("rest", q.Agg("sum", q.Var("share"))),))
    assert batches.exactness(total, "node", {"links": 1}, {"links"}) == "UNKNOWN"
    catalog = Catalog(spark)
    plan = batches.map_split({"share": share}, "node", [], catalog)
    per_value, n = batches.eval_batches(total, plan, {}, catalog, batches.reduce_union(), "per_value")
    assert n == 2 and per_value.df.count() == 2  # the full answer is one row
    with pytest.raises(ValueError):
        batches.eval_batches(q.Slice(q.VarRef("share"), (), 1), plan, {}, catalog, batches.reduce_union())


def test_split_drops_unbound(spark):
    rows = Relation.of(spark.createDataFrame([(1, None), (1, 2), (None, 2)], "x long, y long"))
    plan = batches.map_split({"r": rows}, "y", [], Catalog(spark))
    assert plan.rules == {"r": 1}
    assert {tuple(r) for r in plan.parts["r"].df.collect()} == {(1, 2, 2), (None, 2, 2)}
    bag = spark.createDataFrame([(1, 1), (1, 1), (2, 1), (1, 2), (2, 2), (2, 2)], "v long, __c long")
    both = batches.reduce_intersect(bag=True).merge(bag, spark.createDataFrame([(1,), (2,)], "c long"))
    assert sorted(r[0] for r in both.collect()) == [1, 2]


def test_recursion(spark):
    from graphloop.workloads.expressive import ANCESTORS, _flip

    catalog = graph_catalog(lanes(spark))
    pairs = {tuple(r) for r in recursion.recursive_graph(ANCESTORS, catalog).df.collect()}
    assert (6, 5) in pairs and (1, 1) in pairs and (5, 1) not in pairs
    with pytest.raises(recursion.NotMonotone):
        recursion.recursive_graph(_flip(), catalog)
    assert recursion.recursive_graph(_flip(), catalog, "partial").df.count() == 0
    assert not recursion.is_well_designed(q.Join(q.LeftJoin(q.Pattern("?a", "p", "?b"), q.Pattern("?c", "p", "?d")), q.Pattern("?d", "p", "?e")))
    assert locality.outside_domain(spark.createDataFrame([(1, 77)], "a long, b long"), catalog).collect() == [("b", "77")]
