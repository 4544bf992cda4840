"""Push inside tasks, stores, fact types, codes, phases and the other ways to run a program, against plain Python."""

import itertools
import random

import pytest

from rulepush import metrics
from rulepush.operators.dedup import SetStore, compose_words, from_words, to_words
from rulepush.operators.drivers import CompiledProgram, DeltaDriver, Options, PushDriver, SemiNaiveDriver, TabledDriver, compare, evaluate
from rulepush.operators.encode import decode, dictionary, encode
from rulepush.operators.fixpoint import fixpoint
from rulepush.operators.local import CLOSURE, linear_plan, local_push
from rulepush.plans.facttypes import specialised_program
from rulepush.plans.ir import ProgramBuilder, UnsafeRuleError, components, parse_program
from rulepush.sources.catalog import ChainSource, EdbCatalog, write
from rulepush.storage import discard, spill, stored_bytes
from rulepush.workloads.paper import CHAIN, EAV, TYPED
from test_engine import brute, rows


def plan_of(text):
    p = parse_program(text)
    return linear_plan(p, components(p)[-1])


def test_arguments_that_are_carried():
    assert plan_of(CLOSURE).carried == [1] and plan_of(CLOSURE).keys == [0]
    assert plan_of("tc(X, Y) :- par(X, Y). tc(X, Y) :- tc(X, Z), par(Z, Y). ?- tc(X, Y).").carried == [0]
    assert plan_of("s(X) :- a(X). s(Y) :- s(X), par(X, Y). ?- s(X).").carried == []
    three = plan_of("r(X, Y, L) :- e(X, Y, L). r(X, Y, L) :- e(X, Z, M), r(Z, Y, L), M < 3. ?- r(X, Y, L).")
    assert three.carried == [1, 2] and three.keys == [0]
    assert plan_of("tc(X, Y) :- par(X, Y). tc(X, Y) :- tc(X, Z), tc(Z, Y). ?- tc(X, Y).") is None
    assert plan_of("p(X, Y) :- e(X, Y). p(X, Y) :- p(Y, X). ?- p(X, Y).") is None  # nothing to step by
    assert plan_of("p(X, Y) :- e(X, Y). p(X, Y) :- e(X, Z), p(Z, Y), Y < 5. ?- p(X, Y).") is None


PROGRAMS = [
    CLOSURE,
    "tc(X, Y) :- par(X, Y). tc(X, Y) :- tc(X, Z), par(Z, Y). ?- tc(X, Y).",
    "s(2). s(Y) :- s(X), par(X, Y). ?- s(X).".replace("s(2). ", "s(X) :- par(2, X). "),
    "r(X, Y) :- par(X, Y), X < Y. r(X, Y) :- par(X, Z), r(Z, Y), Z <> 3. ?- r(X, Y).",
    "d(X, Y, Z) :- par(X, Y), par(Y, Z). d(X, Y, Z) :- par(X, W), d(W, Y, Z). d(X, Y, Z) :- par(W, X), d(W, Y, Z). ?- d(X, Y, Z).",
    "k(X, 1) :- par(X, X). k(X, C) :- par(X, Y), k(Y, C). k(X, 2) :- par(X, 4). ?- k(X, C).",
    "t(X, Y) :- par(X, Y). t(X, Y) :- par(X, Z), t(Z, Y), par(Y, Y). ?- t(X, Y).",
    "g(X, X) :- par(X, Y). g(X, Y) :- par(X, A), g(A, B), par(Y, B). ?- g(X, Y).",
]


@pytest.mark.parametrize("text", PROGRAMS)
def test_push_agrees_with_rounds(spark, text):
    r = random.Random(len(text))
    p = parse_program(text)
    edges = sorted({(r.randint(1, 8), r.randint(1, 8)) for _ in range(14)} | {(2, 3), (3, 4), (4, 4)})
    df = spark.createDataFrame([*edges, (None, 3), edges[0]], "a long, b long").repartition(3)
    want = brute_with_comparisons(p, {"par": edges})
    pushed = PushDriver(spark, p, {"par": df})
    assert rows(pushed.run()) == want
    assert rows(SemiNaiveDriver(spark, p, {"par": df}).run()) == want
    assert PushDriver.fixpoint is not DeltaDriver.fixpoint and SemiNaiveDriver.fixpoint is DeltaDriver.fixpoint
    names = spark.createDataFrame([(f"n{a}", f"n{b}") for a, b in edges], "a string, b string")
    if not any(c.isdigit() for c in text) and "<" not in text:
        assert rows(PushDriver(spark, p, {"par": names}).run()) == {tuple(f"n{x}" for x in t) for t in want}


def brute_with_comparisons(p, edb):
    """Naive evaluation in plain Python, comparisons by their meaning."""
    import operator

    from rulepush.plans.ir import COMPARISONS, Const

    ops = {"<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge, "=": operator.eq, "<>": operator.ne}
    facts = {k: set(v) for k, v in edb.items()}
    size = -1
    while sum(map(len, facts.values())) != size:
        size = sum(map(len, facts.values()))
        for r in p.rules:
            envs = [{}]
            for x in r.joins:
                out = []
                for e, f in itertools.product(envs, list(facts.get(x.pred, ()))):
                    e2, ok = dict(e), True
                    for a, v in zip(x.args, f):
                        ok &= a.value == v if isinstance(a, Const) else e2.setdefault(a.name, v) == v
                    if ok:
                        out.append(e2)
                envs = out
            val = lambda a, e: a.value if isinstance(a, Const) else e[a.name]
            for x in r.body:
                if x.pred in COMPARISONS:
                    envs = [e for e in envs if ops[x.pred](val(x.args[0], e), val(x.args[1], e))]
            facts.setdefault(r.head.pred, set()).update(tuple(val(a, e) for a in r.head.args) for e in envs)
    return facts.get(p.query.pred, set())


def test_push_of_many_carried_values(spark):
    """More values than lanes, in every task, on a long chain and a dense part; and steps over the bound."""
    edges = [(i, i + 1) for i in range(150)] + [(i, j) for i in range(200, 230) for j in range(200, 230) if (i * j) % 7]
    df = spark.createDataFrame(edges, "a long, b long")
    reach = {}
    for a, b in edges:
        reach.setdefault(a, set()).add(b)

    def from_(a):
        seen, todo = set(), [a]
        while todo:
            for b in reach.get(todo.pop(), ()):
                if b not in seen:
                    seen.add(b)
                    todo.append(b)
        return seen

    want = {(a, b) for a in reach for b in from_(a)}
    p = parse_program(CLOSURE)
    assert rows(evaluate(spark, p, {"par": df})) == want
    assert local_push(df.toDF("c0", "c1"), df.toDF("c0", "c1"), [0], [1], most_steps=5) is None
    small = parse_program(CLOSURE.replace("tc(X, Y).", "tc(X, 230).").replace("tc(X, 230) :-", "tc(X, Y) :-"))
    assert small.query is not None
    chain = spark.createDataFrame([(i, i + 1) for i in range(40)], "a long, b long")
    assert evaluate(spark, p, {"par": chain}, options=Options(local_steps=5)).count() == 820


@pytest.mark.parametrize("kind,partitions", [("hash", "auto"), ("hash", 3), ("hash", "doubling"), ("words", "auto"), ("nested", "auto")])
def test_stores(spark, kind, partitions):
    r = random.Random(1)
    store, seen = SetStore(kind, partitions, full=40), set()
    for _ in range(11):  # more slices than are kept apart
        part = [(r.randint(-3, 5), r.randint(-70, 130)) for _ in range(25)]
        new, n = store.add(spark.createDataFrame(part, "c0 long, c1 long"))
        assert rows(new) == set(part) - seen and n == len(set(part) - seen)
        seen |= set(part)
        store.sweep(new)
    assert rows(store.known()) == seen and store.known().count() == len(seen) == store.rows
    assert store.add(spark.createDataFrame(part, "c0 long, c1 long"))[1] == 0
    assert partitions != "doubling" or store.parts > 1


def test_words_compose(spark):
    r = random.Random(2)
    a, b = ({(r.randint(0, 9), r.randint(0, 9)) for _ in range(30)} for _ in range(2))
    da, db = (spark.createDataFrame(sorted(x), "c0 long, c1 long") for x in (a, b))
    got = from_words(compose_words(da, to_words(db)))
    assert rows(got) == {(x, y) for x, z in a for w, y in b if z == w}
    assert got.count() == len(rows(got))


@pytest.mark.parametrize("options", [{"encode": True}, {"load": "partitioned"}, {"order": "textual"}, {"codegen": False}, {"fact_types": "specialised"}, {"fact_types": "mixed", "max_types": 1}, {"dedup_kind": "words"}, {"dedup_kind": "nested"}, {"dedup_kind": "auto"}, {"dedup": "result_only"}])
def test_options_change_nothing(spark, options):
    r = random.Random(3)
    edb = {"ord": [(i, r.choice(["1-URGENT", "2-HIGH", "3-MEDIUM", "5-LOW"])) for i in range(20)], "line": [(r.randint(0, 19), r.randint(0, 15)) for _ in range(40)]}
    dfs = {"ord": spark.createDataFrame(edb["ord"], "a long, b string"), "line": spark.createDataFrame(edb["line"], "a long, b long")}
    p = parse_program(TYPED)
    assert rows(evaluate(spark, p, dfs, options=Options(**options))) == brute(p, edb)
    pairs = {f"k{i}": sorted({(r.randint(0, 9), r.randint(0, 9)) for _ in range(25)}) for i in range(1, 6)}
    p = parse_program(CHAIN + "?- top(X, Y).")
    assert rows(evaluate(spark, p, {k: spark.createDataFrame(v, "a long, b long") for k, v in pairs.items()}, options=Options(**options))) == brute(p, pairs)


def test_specialised_programs():
    p = parse_program(TYPED)
    got = specialised_program(p)
    arity = {x.pred: len(x.args) for r in got.rules for x in (r.head, *r.body)}
    assert {q: n for q, n in arity.items() if q.startswith("kind")} == {"kind__t0": 1, "kind__t1": 1}
    assert not any(x.pred.startswith("sent") and len(x.args) == 2 for r in got.rules for x in r.body)
    recursive = parse_program("t(a, X) :- e(X). t(b, Y) :- t(a, X), f(X, Y). t(K, Y) :- t(K, X), f(X, Y). h(X) :- t(b, X). ?- h(X).")
    edb = {"e": [(1,), (2,)], "f": [(1, 3), (3, 4), (4, 5), (9, 1)]}
    assert brute(specialised_program(recursive), edb) == brute(recursive, edb)


def test_phases_and_interfaces(spark):
    p = parse_program(CLOSURE)
    compiled = CompiledProgram(p)
    for edges in ([(1, 2), (2, 3)], [(5, 6)], []):  # compiled once, run on several states
        loaded = compiled.load(spark, {"par": spark.createDataFrame(edges, "a long, b long")})
        want = brute(p, {"par": edges})
        assert loaded.count() == len(want) and {tuple(r) for r in loaded.iterate()} == want
    ms = loaded.timed()
    assert set(ms) == {"compile", "load", "exec"} and min(ms.values()) >= 0
    got = rows(compare(spark, parse_program(CLOSURE.replace("?- tc(X", "?- tc(1")), {"par": spark.createDataFrame([(1, 2), (2, 3), (7, 8)], "a long, b long")}))
    assert len(got) == 8 and {n for _, _, n in got} == {2}
    driver = PushDriver(spark, parse_program(EAV), {"att": spark.createDataFrame([("1", "title", "x")], "a string, b string, c string")})
    assert "answer(I, T, A, Y, M) :- att(I, title, T)" in driver.explain() and "map" in driver.explain("paths") and "0: answer" in driver.explain("strata")
    assert "init -> answer" in driver.explain("types") and "Scan" in driver.explain("physical")
    with pytest.raises(RuntimeError):
        evaluate(spark, p, {"par": spark.createDataFrame([(i, i + 1) for i in range(9)], "a long, b long")}, "seminaive", Options(max_rounds=2))


def test_measures(spark):
    report = metrics.phase_report(lambda: {"exec": 1.0}, n=2)
    assert report["exec"] == 1 and report["runs"] == 2
    assert metrics.base_memory_kb(spark) > 10_000 and metrics.factor(6, 3) == 2
    assert metrics.derivation_report(100, 10)["ratio"] == 10
    clock = metrics.PhaseClock()
    with clock.phase("load"):
        pass
    assert clock.ms["load"] >= 0 and metrics.repeat(lambda: None, n=2)["runs"] == 2
    driver = SemiNaiveDriver(spark, parse_program(CHAIN + "?- top(X, Y)."), {f"k{i}": spark.createDataFrame([(1, 1)], "a long, b long") for i in range(1, 6)})
    driver.run()
    assert {tuple(r)[:3] for r in metrics.structure_report(spark, driver.stats).collect()} == {(q, "result", 1) for q in ("inner", "left", "right", "top")}
    df = spill(spark.range(5), "some")
    assert stored_bytes(df) > 0 and df.count() == 5
    discard(df)
    assert stored_bytes(spark.range(1)) == 0


def test_builder():
    p = ProgramBuilder().rule("h(X)", "b(X, 3)", "not d(X)", "X < 9").query("h(X)").build()
    assert [x.pred for x in p.rules[0].body] == ["b", "d", "<"] and p.rules[0].body[1].negated and p.edb == {"b", "d"}
    with pytest.raises(UnsafeRuleError):
        ProgramBuilder().rule("h(X, Y)", "b(X)").build()


def test_codes_round_trip(spark):
    df = spark.createDataFrame([("x", 1), ("b", 2), ("x", 3)], "v string, n long")
    codes = dictionary(df.select("v"))
    coded = encode(df, "v", codes)
    assert {(r["v"], r["n"]) for r in coded.collect()} == {(1, 1), (0, 2), (1, 3)}
    assert {(r["v"], r["n"]) for r in decode(coded, "v", codes).collect()} == {("x", 1), ("b", 2), ("x", 3)}


def test_fixpoint_of_frames(spark):
    e = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (3, 4)], "x long, y long")
    step = lambda new: new.join(e.toDF("y", "z"), "y").selectExpr("x", "z AS y")
    assert len(rows(fixpoint(e, step))) == 12
    assert fixpoint(e, step, max_rounds=1).count() == 8
    assert fixpoint(e.limit(0), step).count() == 0
    acyclic = spark.createDataFrame([(1, 2), (2, 3), (1, 3), (3, 4)], "x long, y long")
    bag = fixpoint(acyclic, lambda new: new.join(acyclic.toDF("y", "z"), "y").selectExpr("x", "z AS y"), dedup=False)
    assert bag.count() == 8


def test_sources(spark, tmp_path):
    rows_ = spark.createDataFrame([(1, "it's"), (2, "b, c")], "k long, v string")
    for fmt in ("parquet", "csv", "json", "facts"):
        write(rows_, f"{tmp_path}/{fmt}", fmt, "v")
        got = EdbCatalog(spark).read("v", fmt, f"{tmp_path}/{fmt}", "k long, v string", 2).relations()["v"]
        assert {(int(r[0]), r[1]) for r in got.collect()} == {(1, "it's"), (2, "b, c")}, fmt
    write(rows_, "", "noop")
    url = f"jdbc:derby:{tmp_path}/db;create=true"
    driver = {"driver": "org.apache.derby.iapi.jdbc.AutoloadedDriver"}
    spark.range(20).selectExpr("id AS a", "id + 1 AS b").write.format("jdbc").options(url=url, dbtable="edges", **driver).save()
    edges = EdbCatalog(spark).jdbc("par", url, 'SELECT "a", "b" FROM edges', "a", (0, 20), 3, **driver).relations()
    assert edges["par"].rdd.getNumPartitions() == 3
    assert evaluate(spark, parse_program(CLOSURE), edges).count() == 210
    spark.dataSource.register(ChainSource)
    assert spark.read.format("rulepush_chains").options(length="3", chains="5").load().count() == 15
    assert rows(spark.read.format("rulepush_chains").options(lengths="2,0,1").load()) == {(0, 1), (1, 2), (6, 7)}


def test_words_are_chosen_for_small_domains(spark):
    p = parse_program(CHAIN + "?- top(X, Y).")
    small = {f"k{i}": spark.createDataFrame([(1, 900), (900, 1)], "a long, b long") for i in range(1, 6)}
    assert PushDriver(spark, p, small, Options(dedup_kind="auto")).options.dedup_kind == "words"
    assert PushDriver(spark, p, small | {"k3": spark.createDataFrame([(1, 1 << 40), (7, 1)], "a long, b long")}, Options(dedup_kind="auto")).options.dedup_kind == "hash"
    assert PushDriver(spark, p, small | {"k3": spark.createDataFrame([("a", "b")], "a string, b string")}, Options(dedup_kind="auto")).options.dedup_kind == "hash"


def test_share_options(spark):
    p = parse_program("pair(A, B) :- s(K, A), s(K, B), A < B. s(K, P) :- line(K, P, X). ?- pair(A, B).")
    line = spark.createDataFrame([(1, 2, 0), (1, 3, 0), (2, 3, 1), (1, 3, 9)], "k long, p long, x long")
    for share in ("auto", "persist", "recompute"):
        driver = PushDriver(spark, p, {"line": line}, Options(share=share))
        assert rows(driver.run()) == {(2, 3)} and "s" in driver.stats.stored


@pytest.mark.parametrize(("driver", "more", "last"), [(PushDriver, {"options": Options(dedup="result_only")}, ""), (TabledDriver, {"tabled": "query_only"}, "__ff")])
def test_unchecked_predicates_are_bags_of_counted_facts(spark, driver, more, last):
    """Every pair has 20 derivations a join: the bag holds each fact once, with the number of its derivations."""
    every = spark.createDataFrame(list(itertools.product(range(20), range(20))), "x long, y long")
    d = driver(spark, parse_program(CHAIN + "?- left(X, Y)."), {k: every for k in ("k1", "k2", "k3", "k4", "k5")}, **more)
    assert rows(d.run()) == set(itertools.product(range(20), range(20)))
    inner = [tuple(r) for r in d.relations[f"inner{last}"].collect()]
    assert len(inner) == 400 and {n for *_, n in inner} == {20.0}


def test_bags_over_several_rules(spark):
    """Facts of two rules and of a repeated base row add up; a predicate without arguments and a recursive reader take facts only."""
    e = spark.createDataFrame([(1, 2), (1, 2), (2, 3), (3, 1)], "x long, y long")
    text = "both(X, Y) :- e(X, Y). both(X, Y) :- e(X, Z), e(Z, W), e(W, Y). on :- both(X, Y). tc(X, Y) :- both(X, Y), on. tc(X, Y) :- both(X, Z), tc(Z, Y). ?- tc(X, Y)."
    p = parse_program(text)
    d = PushDriver(spark, p, {"e": e}, Options(dedup="result_only"))
    assert rows(d.run()) == rows(evaluate(spark, p, {"e": e}))
    assert {tuple(r) for r in d.relations["both"].collect()} == {(1, 2, 2.0), (2, 3, 1.0), (3, 1, 1.0), (1, 1, 2.0), (2, 2, 2.0), (3, 3, 2.0)}
