"""Bottom-up evaluation: push, semi-naive, naive and tabled, over the same rule compiler.

Push. A derived fact flows into its consumers inside one lazy plan; facts are stored only at the points the spill plan
names, at duplicate checks of recursion, and where several consumers share a costly plan. In a recursive component
only applications with a non-empty delta run.

Facts with a null argument are dropped at load: null joins nothing.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from ..plans.facttypes import build_app_graph, specialised_program
from ..plans.ir import COMPARISONS, Const, Literal, Program, Rule, binding_patterns, components, recursive, spill_plan
from ..plans.rewrite import propagate_invariant, rewrite_goal, rewrite_magic
from ..storage import discard, shared_dir, spill
from .compile import counted, facts_of, positional, rule_df, specialise
from .dedup import SetStore, compose_words, from_words, to_words
from .encode import encode_program
from .local import linear_plan, local_push


@dataclass
class Options:
    dedup: str = "all"  # all | recursive_only | result_only (bags in between, equal derivations as one row with their number) | none
    dedup_kind: str = "hash"  # hash | words | nested | auto: words where the stored pairs fill a small domain
    share: str = "auto"  # auto | persist | recompute
    max_rounds: int | None = None  # None: until the fixpoint
    partitions: int | str = "auto"  # of a hash store: auto | a number | doubling
    full: int = 1_000_000  # rows a part of a doubling store holds
    fact_types: str = "general"  # general | specialised | mixed
    max_types: int = 64
    encode: bool = False  # values as dense codes, a dictionary for each join domain
    load: str = "lazy"  # lazy: a filter for each literal; partitioned: one scan for all, written by constant
    order: str = "greedy"  # of body literals: greedy | textual
    local_steps: int = 4_000_000  # linear recursion over fewer steps is pushed inside tasks; 0: never
    codegen: bool = True  # False: the engine interprets plans


@dataclass
class Stats:
    rounds: int = 0
    fired: int = 0
    possible: int = 0
    stored: dict = field(default_factory=dict)
    kinds: dict = field(default_factory=dict)


def _union(dfs: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.union(b), dfs)


class Driver:
    def __init__(self, spark: SparkSession, program: Program, edb: dict[str, DataFrame], options: Options | None = None):
        self.spark, self.options = spark, options or Options()
        o = self.options
        missing = program.edb - set(edb)
        if missing:
            raise KeyError(f"no relation for {sorted(missing)}")
        self.relations = {k: positional(v).dropna() for k, v in edb.items()}
        self.decode = None
        if o.encode:
            program, self.relations, self.decode = encode_program(spark, program, self.relations)
        self.program = specialised_program(program, o.fact_types, o.max_types) if o.fact_types != "general" else program
        if o.load == "partitioned":
            for pred in sorted(self.program.edb):
                self.relations[pred] = self.by_constant(pred)
        if o.dedup_kind == "auto":
            self.options = replace(o, dedup_kind="words" if self.small_domain() else "hash")
        self.stats = Stats()

    def small_domain(self, most: int = 1 << 24) -> bool:
        """Whether all stored pairs are of whole numbers whose ranges make at most `most` bits."""
        pairs = [df for q, df in self.relations.items() if q in self.program.edb and len(df.columns) == 2]
        if not pairs or any(t not in ("int", "bigint") for df in pairs for _, t in df.dtypes):
            return False
        wide = _union([df.agg(((F.max("c0") - F.min("c0") + 1) * (F.max("c1") - F.min("c1") + 1)).cast("double").alias("n")) for df in pairs])
        return (wide.agg(F.max("n")).first()[0] or 0) <= most

    def by_constant(self, pred: str) -> DataFrame:
        """The relation's facts that literals ask for, written once, a folder for each value of the column where all have a constant."""
        asked = [x.args for r in self.program.rules for x in r.body if x.pred == pred]
        spots = [i for i in range(len(asked[0])) if all(isinstance(a[i], Const) for a in asked)]
        df = self.relations[pred]
        if not spots:
            return df
        col = f"c{spots[0]}"
        path = f"{shared_dir(self.spark)}/{pred}-by-{col}-{time.time_ns()}"
        df.filter(F.col(col).isin(sorted({a[spots[0]].value for a in asked}))).write.partitionBy(col).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path).select(*df.columns)

    def relation(self, pred: str) -> DataFrame:
        return facts_of(self.relations[pred])

    def run(self) -> DataFrame:
        key = "spark.sql.codegen.wholeStage"
        held = self.spark.conf.get(key)
        if not self.options.codegen:
            self.spark.conf.set(key, "false")
        try:
            for comp in components(self.program):
                if recursive(self.program, comp):
                    self.fixpoint(comp)
                else:
                    self.plain(comp[0])
            out = self.answer()
            return out if self.options.codegen else spill(out, "answer")
        finally:
            if not self.options.codegen:
                self.spark.conf.set(key, held)

    def answer(self) -> DataFrame:
        out = self.plain_answer()
        return self.decode(out) if self.decode else out

    def plain_answer(self) -> DataFrame:
        q = self.program.query
        df = self.relation(q.pred)
        names = {v: f"q{i}" for i, v in enumerate(q.vars)}
        if len(names) < len(q.args):
            got = specialise(df, q, names)
            df = got.select(*[F.lit(a.value).alias(f"c{i}") if not hasattr(a, "name") else F.col(names[a.name]).alias(f"c{i}") for i, a in enumerate(q.args)])
        return df.dropDuplicates() if self.options.dedup in ("all", "result_only") else df

    def plain(self, pred: str) -> None:
        raise NotImplementedError

    def fixpoint(self, comp: list[str]) -> None:
        raise NotImplementedError

    def derive(self, r: Rule, read=None, start: int | None = None) -> DataFrame:
        self.stats.fired += 1
        return rule_df(self.spark, r, read or (lambda i, x: self.relation(x.pred)), start, self.options.order)

    def bag(self, pred: str) -> DataFrame:
        """Derivations of a predicate that no duplicate check is for, where a later one makes a set of what comes of them.

        No derivation is dropped: equal ones are one row with their number, so that chains of joins don't multiply rows.
        """
        rules = self.program.of(pred)
        self.stats.fired += len(rules)
        return counted(_union([rule_df(self.spark, r, lambda i, x: self.relations[x.pred], None, self.options.order, bag=True) for r in rules]))

    def past(self, comp: list[str]) -> None:
        self.stats.rounds += 1
        self.stats.possible += sum(r.head.pred in comp for r in self.program.rules)
        if self.options.max_rounds is not None and self.stats.rounds > self.options.max_rounds:
            raise RuntimeError(f"no fixpoint of {comp} in {self.options.max_rounds} rounds")

    def explain(self, mode: str = "rules") -> str:
        """rules, strata, paths (access patterns), types (the graph of rule applications) or physical (the answer's plan)."""
        show = lambda x: ("not " if x.negated else "") + f"{x.pred}({', '.join(str(a.value) if isinstance(a, Const) else a.name for a in x.args)})"
        if mode == "rules":
            return "\n".join(f"{show(r.head)} :- {', '.join(map(show, r.body))}." for r in self.program.rules)
        if mode == "strata":
            return "\n".join(f"{i}: {', '.join(c)}{' (recursive)' if recursive(self.program, c) else ''}" for i, c in enumerate(components(self.program)))
        if mode == "paths":
            kind = lambda b: "list" if "b" not in b else "set" if "f" not in b else "map"
            return "\n".join(f"{show(r.head)}: " + ", ".join(f"{q} {b} {kind(b)}" for q, b in binding_patterns(r)) for r in self.program.rules)
        if mode == "types":
            return build_app_graph(self.program).explain()
        return self.run()._jdf.queryExecution().explainString(self.spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


class DeltaDriver(Driver):
    """Rounds over deltas: of k literals of the component, version j reads the delta at j, everything before it, and what was known earlier after it."""

    def fixpoint(self, comp: list[str]) -> None:
        stores = {q: SetStore(self.options.dedup_kind, self.options.partitions, self.options.full) for q in comp}
        rules = [r for r in self.program.rules if r.head.pred in comp]
        delta: dict[str, DataFrame] = {}
        for q in comp:
            base = [self.derive(r) for r in rules if r.head.pred == q and not any(x.pred in comp for x in r.joins)]
            if base:
                df, n = stores[q].add(_union(base), q)
                if n:
                    delta[q] = df
        while delta:
            self.past(comp)
            out: dict[str, list[DataFrame]] = {}
            every = {q: s.known() for q, s in stores.items()}
            old = {q: self._before(stores[q], delta.get(q)) for q in comp}
            for r in rules:
                inner = [i for i, x in enumerate(r.body) if x.pred in comp and not x.negated]
                for j in inner:
                    if r.body[j].pred not in delta:
                        continue  # nothing new to fire this application

                    def read(i: int, x: Literal, j=j, inner=inner) -> DataFrame | None:
                        if i not in inner:
                            return self.relation(x.pred)
                        return delta[x.pred] if i == j else every[x.pred] if i < j else old[x.pred]

                    if all(read(i, r.body[i]) is not None for i in inner):
                        out.setdefault(r.head.pred, []).append(self.derive(r, read, j))
            delta = {}
            for q, dfs in out.items():
                df, n = stores[q].add(_union(dfs), q)
                if n:
                    delta[q] = df
            for s in stores.values():
                s.sweep(*delta.values())
        for q in comp:
            known = stores[q].known()
            if known is None:
                r = next(r for r in rules if r.head.pred == q)
                known = self.spark.createDataFrame([], self._schema(r, comp))
            self.relations[q] = known
            self.stats.stored[q], self.stats.kinds[q] = stores[q].rows, self.options.dedup_kind

    @staticmethod
    def _before(store: SetStore, delta: DataFrame | None) -> DataFrame | None:
        slices = [s for s in store.slices if s is not delta]
        if delta is not None and len(slices) == len(store.slices) and slices:  # merged slices hold the delta too
            return slices[0].join(delta, delta.columns, "left_anti")
        return _union(slices) if slices else None

    def _schema(self, r: Rule, comp: list[str]) -> str:
        return ", ".join(f"c{i} long" for i in range(len(r.head.args))) or "c_ int"


class PushDriver(DeltaDriver):
    def plain(self, pred: str) -> None:
        df = self.composed(pred)
        o = self.options
        last = pred == self.program.query.pred
        if df is None and o.dedup == "result_only" and not last:
            df = self.bag(pred)
        elif df is None:
            df = _union([self.derive(r) for r in self.program.of(pred)])
            if o.dedup == "all" and not last:
                df = SetStore(o.dedup_kind).distinct(df)
        consumers = sum(x.pred == pred for r in self.program.rules for x in r.body)
        if consumers and (pred in spill_plan(self.program) or (consumers > 1 and o.share != "recompute") or o.share == "persist"):
            df = spill(df, pred)
            self.stats.stored[pred], self.stats.kinds[pred] = df.count(), spill_plan(self.program).get(pred, "shared")
        self.relations[pred] = df

    def composed(self, pred: str) -> DataFrame | None:
        """A predicate that is one composition of two binary relations, h(X, Y) :- a(X, Z), b(Z, Y), as words of bits."""
        rules = self.program.of(pred)
        if self.options.dedup_kind != "words" or len(rules) != 1 or len(rules[0].body) != 2:
            return None
        (r,) = rules
        a, b = r.body
        names = [[getattr(x, "name", None) for x in lit.args] for lit in (r.head, a, b)]
        if a.negated or b.negated or any(len(n) != 2 or None in n for n in names) or len({*names[1], *names[2]}) != 3:
            return None
        if names[1] != [names[0][0], names[2][0]] or names[2][1] != names[0][1]:
            return None
        left, right = self.relation(a.pred), self.relation(b.pred)
        if {t for df in (left, right) for _, t in df.dtypes} - {"int", "bigint"}:
            return None
        self.stats.fired += 1
        return from_words(compose_words(left, to_words(right)))

    def fixpoint(self, comp: list[str]) -> None:
        """Linear recursion is driven inside tasks, without a stored round; other components go by rounds."""
        plan = linear_plan(self.program, comp) if self.options.local_steps else None
        base = [self.derive(r) for r in plan.base] if plan else []
        if not base:
            return super().fixpoint(comp)
        steps = _union([self.derive(r) for r in plan.steps])
        out = local_push(_union(base), steps, plan.keys, plan.carried, self.options.local_steps)
        if out is None:
            return super().fixpoint(comp)
        self.stats.rounds += 1
        self.stats.kinds[plan.pred] = "in tasks"
        self.relations[plan.pred] = out


class SemiNaiveDriver(DeltaDriver):
    """The same rounds, but every derived relation is stored and read back, the query's result too."""

    def plain(self, pred: str) -> None:
        df = _union([self.derive(r) for r in self.program.of(pred)])
        df = self.relations[pred] = spill(df.dropDuplicates() if self.options.dedup == "all" else df, pred)
        self.stats.stored[pred], self.stats.kinds[pred] = df.count(), "result"


class NaiveDriver(Driver):
    """All rules of a component on everything known, until a round adds nothing."""

    def plain(self, pred: str) -> None:
        self.relations[pred] = spill(_union([self.derive(r) for r in self.program.of(pred)]).dropDuplicates(), pred)

    def fixpoint(self, comp: list[str]) -> None:
        rules = [r for r in self.program.rules if r.head.pred in comp]
        held: dict[str, DataFrame] = {}
        sizes: dict[str, int] = {}
        while True:
            self.past(comp)
            new: dict[str, DataFrame] = {}
            for q in comp:
                ready = [r for r in rules if r.head.pred == q and all(x.pred not in comp or x.pred in held for x in r.joins)]
                if ready:
                    new[q] = spill(_union([self.derive(r, lambda i, x: held[x.pred] if x.pred in comp else self.relation(x.pred)) for r in ready]).dropDuplicates(), q)
            now = {q: df.count() for q, df in new.items()}
            discard(*held.values())
            held = new
            if now == sizes:
                break
            sizes = now
        for q in comp:
            self.relations[q] = held.get(q) if q in held else self.spark.createDataFrame([], "c0 long")


class TabledDriver(DeltaDriver):
    """Call and answer tables evaluated together, set at a time.

    Calls are the binding sets the magic rewriting derives; answers are kept per call pattern. schedule='local' finishes
    a component of calls and answers before its callers read it, 'batched' puts the whole program in one component and
    interleaves its rounds. index keeps base relations partitioned on the first argument; tabled='query_only' leaves
    non-recursive derived predicates untabled, as bags without duplicate checks.
    """

    def __init__(self, spark, program, edb, options=None, schedule: str = "local", index: bool = False, tabled: str = "all"):
        rewritten = rewrite_magic(program, program.query)
        super().__init__(spark, rewritten, edb, options)
        self.schedule, self.tabled = schedule, tabled
        if index:
            for k, v in self.relations.items():
                self.relations[k] = spill(v.repartition("c0").sortWithinPartitions("c0"), k)

    def plain(self, pred: str) -> None:
        if self.tabled == "all" or pred == self.program.query.pred:
            self.relations[pred] = spill(_union([self.derive(r) for r in self.program.of(pred)]).dropDuplicates(), pred)
        else:
            self.relations[pred] = self.bag(pred)

    def run(self) -> DataFrame:
        if self.schedule == "batched":
            self.fixpoint(sorted(self.program.idb))
            return self.answer()
        return super().run()


DRIVERS = {"push": PushDriver, "seminaive": SemiNaiveDriver, "naive": NaiveDriver, "tabled": TabledDriver}


def evaluate(spark: SparkSession, program: Program, edb: dict[str, DataFrame], driver: str = "push", options: Options | None = None, **more) -> DataFrame:
    return DRIVERS[driver](spark, program, edb, options, **more).run()


REWRITINGS = {
    "none": lambda p: p,
    "goal": lambda p: rewrite_goal(p, p.query),
    "goal_simple": lambda p: rewrite_goal(p, p.query, simplify=True),
    "magic": lambda p: rewrite_magic(p, p.query),
    "invariant": lambda p: propagate_invariant(p, p.query),
}


class CompiledProgram:
    """Compiled once, for any state of the relations: load() gives a program that can run."""

    def __init__(self, program: Program, driver: str = "push", options: Options | None = None, rewriting: str = "none", **more):
        began = time.perf_counter()
        self.program = REWRITINGS[rewriting](program)
        components(self.program)
        self.driver, self.options, self.more = driver, options, more
        self.ms = {"compile": 1000 * (time.perf_counter() - began)}

    def load(self, spark: SparkSession, edb: dict[str, DataFrame], store: bool = True) -> LoadedProgram:
        """store: the relations are read and written once here, so that execution starts from them."""
        return LoadedProgram(self, spark, edb, store)


class LoadedProgram:
    def __init__(self, compiled: CompiledProgram, spark: SparkSession, edb: dict[str, DataFrame], store: bool):
        began = time.perf_counter()
        self.compiled, self.spark = compiled, spark
        used = {x.pred for r in compiled.program.rules for x in r.body if x.pred not in COMPARISONS}
        self.edb = {k: spill(v, k) if store else v for k, v in edb.items() if k in used}
        self.ms = compiled.ms | {"load": 1000 * (time.perf_counter() - began)}
        self.stats: Stats | None = None

    def execute(self) -> DataFrame:
        c = self.compiled
        driver = DRIVERS[c.driver](self.spark, c.program, self.edb, c.options, **c.more)
        out = driver.run()
        self.stats = driver.stats
        return out

    def count(self) -> int:
        return self.execute().count()

    def iterate(self) -> Iterator[Row]:
        """Answers one by one, a partition at a time."""
        return self.execute().toLocalIterator(prefetchPartitions=True)

    def timed(self) -> dict[str, float]:
        """Milliseconds to compile, load and execute, the answers going nowhere."""
        began = time.perf_counter()
        self.execute().write.format("noop").mode("overwrite").save()
        return self.ms | {"exec": 1000 * (time.perf_counter() - began)}


def compare(spark: SparkSession, program: Program, edb: dict[str, DataFrame], drivers=("push", "seminaive", "naive", "tabled"), rewritings=("none", "goal")) -> DataFrame:
    """(driver, rewriting, answers): every driver on every rewriting of one program."""
    rows = [(d, w, CompiledProgram(program, d, rewriting=w).load(spark, edb, store=False).count()) for w in rewritings for d in drivers]
    return spark.createDataFrame(rows, "driver string, rewriting string, answers long")
