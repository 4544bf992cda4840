"""Push inside a task, for linear recursion: a derived fact drives its consumers at once, and no round is stored.

A recursive predicate whose rules hold it once each splits its arguments: carried ones, which every recursive rule
hands on unchanged, and keys, which move by the rule's other literals. These, joined, are steps from key to key. Facts
are dealt by their carried values once; a task then drives 64 carried values at a time through the steps, one bit
each, until nothing is new, and keeps its duplicate check to itself. The steps are sent to all tasks, so their number is
counted first; larger step relations take the rounds of the push driver. Without carried arguments one task does it.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ir import COMPARISONS, Literal, Program, Rule, Var, parse_program
from ..storage import spill

CLOSURE = "tc(X, Y) :- par(X, Y). tc(X, Y) :- par(X, Z), tc(Z, Y). ?- tc(X, Y)."
STEP = "step__"


@dataclass
class LinearPlan:
    pred: str
    keys: list[int]
    carried: list[int]
    base: list[Rule]
    steps: list[Rule]  # heads step__(keys before..., keys after...)


def invariant_arguments(rules: list[Rule], pred: str) -> list[int]:
    """Positions that each recursive rule hands on unchanged, and that nothing else in it looks at."""
    arity = len(rules[0].head.args)
    out = []
    for i in range(arity):
        ok = True
        for r in rules:
            (call,) = [x for x in r.body if x.pred == pred]
            v = r.head.args[i]
            seen = sum(a == v for x in (r.head, *r.body) for a in x.args)
            ok &= isinstance(v, Var) and call.args[i] == v and seen == 2
        if ok:
            out.append(i)
    return out


def linear_plan(p: Program, comp: list[str]) -> LinearPlan | None:
    """How the component's predicate can be pushed inside tasks, or None."""
    if len(comp) != 1:
        return None
    (pred,) = comp
    calls = lambda r: sum(x.pred == pred for x in r.body)
    rules = p.of(pred)
    moving = [r for r in rules if calls(r)]
    if any(calls(r) > 1 or any(x.negated for x in r.body) for r in moving):
        return None
    carried = invariant_arguments(moving, pred)
    keys = [i for i in range(len(rules[0].head.args)) if i not in carried]
    if not keys:
        return None
    steps = []
    for r in moving:
        (call,) = [x for x in r.body if x.pred == pred]
        rest = tuple(x for x in r.body if x.pred != pred)
        bound = {v for x in rest if x.pred not in COMPARISONS for v in x.vars}
        head = Literal(STEP, tuple(call.args[i] for i in keys) + tuple(r.head.args[i] for i in keys))
        if not bound or set(head.vars) - bound or {v for x in rest for v in x.vars} - bound:
            return None
        steps.append(Rule(head, rest))
    return LinearPlan(pred, keys, carried, [r for r in rules if not calls(r)], steps)


class Adjacency:
    """Steps between numbered keys, by where they start and by where they end."""

    def __init__(self, source: np.ndarray, target: np.ndarray, n: int):
        out, into = np.argsort(source, kind="stable"), np.argsort(target, kind="stable")
        self.n = n
        self.targets = target[out].astype(np.int32)
        self.first = np.searchsorted(source[out], np.arange(n + 1))
        self.sources = source[into].astype(np.int32)
        heads = np.searchsorted(target[into], np.arange(n + 1))
        self.ends = np.nonzero(np.diff(heads))[0]
        self.heads = heads[self.ends]

    def reach(self, held: np.ndarray) -> np.ndarray:
        """held: bits by key. All bits that steps carry on to, held ones too."""
        new = held.copy()
        while True:
            active = np.nonzero(new)[0]
            if not len(active):
                return held
            size = self.first[active + 1] - self.first[active]
            total = int(size.sum())
            got = np.zeros(self.n, np.uint64)
            if 4 * total > len(self.targets):
                if len(self.ends):
                    got[self.ends] = np.bitwise_or.reduceat(new[self.sources], self.heads)
            elif total:
                at = np.arange(total) + np.repeat(self.first[active] - np.cumsum(size) + size, size)
                np.bitwise_or.at(got, self.targets[at], np.repeat(new[active], size))
            new = got & ~held
            held = held | new


def local_push(seeds: DataFrame, steps: DataFrame, keys: list[int], carried: list[int], most_steps: int = 4_000_000) -> DataFrame | None:
    """All facts that steps reach from seeds(c0, ...), or None if there are over most_steps steps.

    steps: columns c0.. with the keys before, then the keys after. Null keys and null carried values don't occur.
    """
    spark, k = seeds.sparkSession, len(keys)
    names = [f"c{i}" for i in range(len(seeds.columns))]
    seeds = seeds.toDF(*names)
    # one type for a key wherever it stands
    after = steps.select(*[F.col(f"c{k + j}").alias(f"k{j}") for j in range(k)])
    before = steps.select(*[F.col(f"c{j}").alias(f"k{j}") for j in range(k)])
    kinds = seeds.select(*[F.col(f"c{i}") for i in keys]).union(before).union(after).dtypes
    key_type = [t for _, t in kinds]
    steps = steps.select(*[F.col(f"c{j}").cast(key_type[j % k]).alias(f"c{j}") for j in range(2 * k)])
    seeds = seeds.select(*[F.col(c).cast(key_type[keys.index(i)]).alias(c) if i in keys else F.col(c) for i, c in enumerate(names)])
    steps = spill(steps.dropDuplicates(), "steps")
    if steps.count() > most_steps:
        return None
    # at most most_steps rows: numbers for the keys, made in the tasks' order of values
    held = steps.toArrow()
    rows = [pa.chunked_array([*held.column(j).chunks, *held.column(k + j).chunks]).combine_chunks() for j in range(k)]
    at, first = _numbered(rows)
    n, half = len(first), held.num_rows
    table = pa.table({f"k{j}": rows[j].take(pa.array(first)) for j in range(k)})
    graph = Adjacency(at[:half], at[half:], n)
    sent = spark.sparkContext.broadcast((graph, table))
    nodes = spark.createDataFrame(table.append_column("_node", pa.array(np.arange(n), pa.int32()))) if n else None
    seeds = spill(seeds, "seeds")
    if nodes is None:
        return seeds.dropDuplicates()
    nodes = nodes.select(*[F.col(f"k{j}").cast(key_type[j]).alias(f"k{j}") for j in range(k)], "_node")
    match = [F.col(names[i]) == F.col(f"k{j}") for j, i in enumerate(keys)]
    cond = match[0]
    for m in match[1:]:
        cond = cond & m
    numbered = seeds.join(F.broadcast(nodes), cond, "left").select(*names, "_node")
    outside = numbered.filter("_node IS NULL").select(*names).dropDuplicates()
    values = [names[i] for i in carried]
    inside = numbered.filter("_node IS NOT NULL").select(*values, "_node")
    dealt = inside.repartition(*values).sortWithinPartitions(*values) if values else inside.dropDuplicates().coalesce(1)

    def run(batches):
        graph, table = sent.value
        lanes: dict[tuple, int] = {}
        kept: list[pa.RecordBatch] = []
        bits = np.zeros(graph.n, np.uint64)

        def drive():
            reached = graph.reach(bits)
            owners = pa.Table.from_batches(kept) if kept else None
            for lane in range(len(lanes) or 1):
                node = np.nonzero(reached >> np.uint64(lane) & np.uint64(1))[0]
                for lo in range(0, len(node), 1 << 16):
                    part = pa.array(node[lo : lo + (1 << 16)])
                    own = owners.take(pa.array(np.full(len(part), lane))) if owners is not None else None
                    cols = {f"c{i}": table.column(j).take(part) for j, i in enumerate(keys)}
                    cols |= {v: own.column(v) for v in values}
                    yield from pa.table({c: cols[c] for c in names}).combine_chunks().to_batches()

        for b in batches:
            node = b.column(len(values)).to_numpy(zero_copy_only=False)
            if not values:
                bits[node] = 1
                continue
            owner = list(zip(*(b.column(j).to_pylist() for j in range(len(values)))))
            for i, v in enumerate(owner):
                lane = lanes.get(v)
                if lane is None:
                    if len(lanes) == 64:
                        yield from drive()
                        lanes.clear()
                        kept.clear()
                        bits[:] = 0
                    lane = lanes[v] = len(lanes)
                    kept.append(b.select(values).slice(i, 1))
                bits[node[i]] |= np.uint64(1 << lane)
        if not values or lanes:
            yield from drive()

    schema = ", ".join(f"{c} {t}" for c, t in seeds.dtypes)
    return dealt.mapInArrow(run, schema).unionByName(outside)


def _numbered(columns: list[pa.Array]) -> tuple[np.ndarray, np.ndarray]:
    """(number of each row among the distinct ones, a row of each number)."""
    at = np.zeros(len(columns[0]), np.int64)
    for c in columns:
        codes = c.dictionary_encode()
        code = codes.indices.to_numpy(zero_copy_only=False).astype(np.int64) if len(c) else at
        at = np.unique(at * (len(codes.dictionary) + 1) + code, return_inverse=True)[1]
    first = np.unique(at, return_index=True)[1]
    return at, first


def closure(edges: DataFrame, options=None) -> DataFrame:
    """(c0, c1): pairs joined by a path of edges(c0, c1), by the push driver."""
    from .drivers import evaluate

    return evaluate(edges.sparkSession, parse_program(CLOSURE), {"par": edges}, "push", options)
