import itertools
import random

import pytest

from rulepush.operators.dedup import SetStore
from rulepush.operators.drivers import Options, evaluate
from rulepush.operators.encode import dictionary, join_domains
from rulepush.operators.local import CLOSURE, closure
from rulepush.operators.shapes import evaluate_batched
from rulepush.plans.facttypes import TooManyFactTypes, build_app_graph, program_report
from rulepush.plans.ir import Const, UnsafeRuleError, binding_patterns, components, parse_program, spill_plan
from rulepush.plans.rewrite import propagate_invariant, rewrite_goal, rewrite_magic
from rulepush.streaming.push import IncrementalClosure
from rulepush.workloads.paper import CHAIN, EAV, ontology, program_sizes


def brute(p, edb):
    """Naive evaluation in plain Python."""
    facts = {k: set(v) for k, v in edb.items()}
    while True:
        new = set()
        for r in p.rules:
            envs = [{}]
            for x in r.body:
                if x.pred == "=":
                    val = lambda a, e: a.value if isinstance(a, Const) else e[a.name]
                    envs = [e for e in envs if val(x.args[0], e) == val(x.args[1], e)]
                    continue
                out = []
                for e, f in itertools.product(envs, facts.get(x.pred, ())):
                    e2, ok = dict(e), True
                    for a, v in zip(x.args, f):
                        if isinstance(a, Const):
                            ok &= a.value == v
                        else:
                            ok &= e2.setdefault(a.name, v) == v
                    if ok:
                        out.append(e2)
                envs = out
            for e in envs:
                new.add((r.head.pred, tuple(a.value if isinstance(a, Const) else e[a.name] for a in r.head.args)))
        before = sum(map(len, facts.values()))
        for q, f in new:
            facts.setdefault(q, set()).add(f)
        if sum(map(len, facts.values())) == before:
            break
    q = p.query
    return {f for f in facts.get(q.pred, ()) if all(not isinstance(a, Const) or a.value == v for a, v in zip(q.args, f))}


def rows(df):
    return {tuple(r) for r in df.collect()}


GRAPHS = {
    "loop": [(1, 1)], "two": [(1, 2), (2, 1)], "chain": [(1, 2), (2, 3), (3, 4), (4, 5)], "diamond": [(1, 2), (1, 3), (2, 4), (3, 4)],
    "parts": [(1, 2), (8, 9), (9, 8)], "random": sorted({(random.Random(5).randint(1, 9), y) for y in range(1, 9)} | {(3, 1), (2, 7), (7, 2)}),
}


@pytest.mark.parametrize("name", sorted(GRAPHS))
def test_closures_agree(spark, name):
    edges = GRAPHS[name]
    df = spark.createDataFrame(edges, "a long, b long")
    p = parse_program(CLOSURE)
    want = brute(p, {"par": edges})
    assert rows(closure(df)) == want
    assert rows(evaluate(spark, p, {"par": df})) == want
    for text in (CLOSURE.replace("?- tc(X, Y)", "?- tc(1, Y)"), CLOSURE.replace("?- tc(X, Y)", "?- tc(X, 1)")):
        p = parse_program(text)
        want = brute(p, {"par": edges})
        for how in (rewrite_goal, rewrite_magic, propagate_invariant, lambda p, q: rewrite_goal(p, q, simplify=True)):
            r = how(p, p.query)
            assert brute(r, {"par": edges}) == want
        assert rows(evaluate(spark, rewrite_goal(p, p.query), {"par": df})) == want


@pytest.mark.parametrize("body", ["tc(X, Z), par(Z, Y)", "tc(X, Z), tc(Z, Y)", "par(X, Z), tc(Z, Y)"])
def test_rewritings_of_other_recursions(body):
    for q in ("tc(1, Y)", "tc(X, 4)", "tc(1, 4)", "tc(X, Y)"):
        p = parse_program(f"tc(X, Y) :- par(X, Y). tc(X, Y) :- {body}. ?- {q}.")
        for edges in GRAPHS.values():
            want = brute(p, {"par": edges})
            for how in (rewrite_goal, rewrite_magic):
                assert brute(how(p, p.query), {"par": edges}) == want, (how, body, q)


def test_drivers_and_options_agree(spark):
    edges = GRAPHS["random"]
    df = spark.createDataFrame([*edges, edges[0], (None, 1)], "a long, b long")
    p = parse_program("even(X, Y) :- par(X, Z), odd(Z, Y). odd(X, Y) :- par(X, Y). odd(X, Y) :- par(X, Z), even(Z, Y). ?- even(X, Y).")
    want = brute(p, {"par": edges})
    for driver in ("push", "seminaive", "naive", "tabled"):
        assert rows(evaluate(spark, p, {"par": df}, driver)) == want
    for kind in ("words", "nested"):
        assert rows(evaluate(spark, p, {"par": df}, options=Options(dedup_kind=kind))) == want
    assert rows(evaluate(spark, p, {"par": df}, "tabled", schedule="batched", index=True)) == want


def test_empty_relation(spark):
    p = parse_program(CLOSURE)
    assert rows(evaluate(spark, p, {"par": spark.createDataFrame([], "a long, b long")})) == set()
    assert rows(closure(spark.createDataFrame([], "a long, b long"))) == set()


def test_analysis():
    with pytest.raises(UnsafeRuleError):
        parse_program("h(X, Y) :- b(X).")
    with pytest.raises(ValueError):
        components(parse_program("h(X) :- b(X), not h(X)."))
    assert [x for _, x in binding_patterns(parse_program(EAV).rules[0])] == ["ff", "bf", "bf", "bf"]
    chain = parse_program(CHAIN + "?- top(X, Y).")
    assert set(spill_plan(chain)) == {"left"} or set(spill_plan(chain)) == {"right"}
    assert program_report(ontology()) == {"rules": 957, "idb": 225, "edb": 113, "recursive_idb": 224}
    assert len(join_domains(parse_program(EAV))) == 3


def test_goal_rewriting_lowers_arity():
    p = parse_program(CLOSURE.replace("?- tc(X, Y)", "?- tc(1, Y)"))
    got = rewrite_goal(p, p.query)
    assert max(len(r.head.args) for r in got.rules if r.head.pred != got.query.pred) == 1


def test_fact_types():
    p = parse_program("p(a, X) :- e(X). p(b, X) :- e(X). q(Y, X) :- p(Y, X). r(X) :- q(c, X). ?- r(X).")
    assert len(build_app_graph(p, "general").types) == 3
    special = build_app_graph(p, "specialised")
    assert ("q", ("a", None)) in special.types and not any(t[0] == "r" for t in special.types)
    with pytest.raises(TooManyFactTypes):
        build_app_graph(p, "specialised", max_types=1)
    assert ("p", (None, None)) in build_app_graph(p, "mixed", max_types=1).types


def test_batched_rules(spark):
    p = parse_program("a(X) :- e(X). b(X) :- a(X). b(Y) :- f(X, Y), b(X). c(X) :- a(X), b(X). a(X) :- c(X). ?- c(X).")
    edb = {"e": [(1,), (2,)], "f": [(1, 5), (5, 6)]}
    dfs = {"e": spark.createDataFrame(edb["e"], "x long"), "f": spark.createDataFrame(edb["f"], "x long, y long")}
    facts, stats = evaluate_batched(spark, p, dfs)
    got = {(r[0], r[1]) for r in facts.collect()}
    want = {(q, f[0]) for q in "abc" for f in brute(parse_program(f"{' '.join(['a(X) :- e(X). b(X) :- a(X). b(Y) :- f(X, Y), b(X). c(X) :- a(X), b(X). a(X) :- c(X).'])} ?- {q}(X)."), edb)}
    assert got == want and stats["shapes"] < len(p.rules)


def test_batched_rules_by_words(spark):
    """A variable twice in a literal, more choices than a word has bits, and a join through pairs with new facts on either side."""
    many = " ".join(f"c{i}(Y) :- r(X, Y), a{i}(X), b{i}(Y). b{i}(X) :- c{i}(X). a{i}(X) :- e{i % 3}(X). b{i}(X) :- f(X, X), e{i % 3}(X). goal(X) :- c{i}(X)." for i in range(70))
    edb = {"e0": [(1,), (2,)], "e1": [(3,)], "e2": [(2,), (4,)], "f": [(1, 1), (2, 2), (3, 4), (4, 4)], "r": [(1, 2), (2, 1), (3, 3), (4, 2), (2, 4), (2, 4)]}
    dfs = {q: spark.createDataFrame(v, "x long" if len(v[0]) == 1 else "x long, y long") for q, v in edb.items()}
    p = parse_program(many + " ?- goal(X).")
    facts, stats = evaluate_batched(spark, p, dfs)
    got = {(r[0], r[1]) for r in facts.collect()}
    want = {(q, f[0]) for q in ("goal", "c0", "c1", "c68", "b69", "a69") for f in brute(parse_program(f"{many} ?- {q}(X)."), edb)}
    assert {x for x in got if x[0] in ("goal", "c0", "c1", "c68", "b69", "a69")} == want and stats["fired"] < stats["rounds"] * 2 * stats["shapes"]


def test_dictionary(spark):
    got = {r[0]: r[1] for r in dictionary(spark.createDataFrame([(x,) for x in ["b", "a", None, "c", "a"]], "v string"), 3).collect()}
    assert got == {"a": 0, "b": 1, "c": 2}


def test_set_store_and_stream(spark):
    s = SetStore("words")
    s.add(spark.createDataFrame([(1, 0), (1, 63), (1, 64)], "c0 long, c1 long"))
    new, n = s.add(spark.createDataFrame([(1, 63), (1, 65), (2, 0)], "c0 long, c1 long"))
    assert n == 2 and rows(new) == {(1, 65), (2, 0)}
    inc = IncrementalClosure()
    for part in ([(1, 2), (3, 4)], [(2, 3)], [(4, 1)]):
        inc(spark.createDataFrame(part, "a long, b long"))
    assert rows(inc.result()) == set(itertools.product(range(1, 5), repeat=2))


def test_program_sizes_follow_the_tables(spark, tmp_path):
    spark.createDataFrame([(1, "b", "t", 1), (2, "c", "t", 3)], "p_partkey long, p_brand string, p_type string, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame([(0, 0), (1, 1), (2, 1)], "n_nationkey int, n_regionkey int").write.parquet(f"{tmp_path}/nation.parquet")
    got = {tuple(r) for r in program_sizes(spark, str(tmp_path)).filter("program = 'ontology'").collect()}
    assert got == {("ontology", 47, 16, 12, 15)} and program_report(ontology(2, 1, 2, 3, 2)) == {"rules": 47, "idb": 16, "edb": 12, "recursive_idb": 15}
