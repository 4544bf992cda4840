"""Rule-shape batching: rules alike up to predicates and constants are rows of a rule table.

Facts are tagged rows (p, a0, a1). A round evaluates one join per shape and delta position, whatever the number of
rules, and only for rules that a new fact activates and whose other predicates have facts. In a join a row is a binding
of variables with a word that has a bit for each choice of predicates for the other slots: a relation is passed once
for all of them, and bindings go as soon as no later literal asks for their variables.
"""

from __future__ import annotations

from collections import defaultdict
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.ir import Const, Program, Rule
from ..storage import discard, spill
from .dedup import SetStore


def shape_of(r: Rule) -> tuple[tuple, tuple]:
    """(skeleton, slot values): predicates and constants become slots."""
    names: dict[str, int] = {}
    slots: list = []
    skeleton = []
    for x in (r.head, *r.joins):
        slots.append(x.pred)
        skeleton.append(tuple(("c",) if isinstance(a, Const) else names.setdefault(a.name, len(names)) for a in x.args))
        slots += [a.value for a in x.args if isinstance(a, Const)]
    if any(isinstance(a, Const) for x in (r.head, *r.joins) for a in x.args):
        raise ValueError("constants in batched rules are not handled")
    return tuple(skeleton), tuple(slots)


#: Bits of a word, and rows up to which a side of a join is sent to the tasks, so that the other one stays where it is.
BITS, SENT = 62, 2_000_000


def slot_words(rules: list[tuple], bits: dict[tuple, int], j: int, i: int) -> dict[int, int]:
    """For each predicate in slot i the choices (rules without slot j) that have it there."""
    out: dict[int, int] = defaultdict(int)
    for r in rules:
        out[r[i]] |= 1 << bits[r[:j] + r[j + 1 :]]
    return dict(out)


def matched(facts: DataFrame, variables: tuple, words: dict[int, int]) -> DataFrame:
    """Facts of some predicates as (variables, m): columns x0.. and the word of the predicate."""
    low, high = min(words), max(words)
    side = facts.filter(F.col("p").isin(sorted(words)))
    if len(set(variables)) < len(variables):
        side = side.filter("a0 = a1")
    word = F.lit(next(iter(words.values()))) if len(set(words.values())) == 1 else F.expr(f"element_at(array({', '.join(f'{words.get(q, 0)}L' for q in range(low, high + 1))}), p - {low} + 1)")
    return side.select(*[F.col(f"a{variables.index(v)}").alias(f"x{v}") for v in dict.fromkeys(variables)], word.cast("long").alias("m"))


def heads(state: DataFrame, head: tuple, words: dict[int, int]) -> DataFrame:
    """(p, a0, a1) for each head predicate that has a bit in m."""
    if len(words) == 1:
        p = F.lit(next(iter(words)))
    else:
        pairs = ", ".join(f"struct({q} AS p, {w}L AS w)" for q, w in words.items())
        state = state.withColumn("h", F.explode(F.expr(f"filter(array({pairs}), s -> (s.w & m) <> 0)")))
        p = F.col("h.p")
    return state.select(p.cast("int").alias("p"), F.col(f"x{head[0]}").alias("a0"), (F.col(f"x{head[1]}") if len(head) > 1 else F.lit(-1).cast("long")).alias("a1"))


def apply_shape(skeleton: tuple, rules: list[tuple], j: int, delta, known, new: dict[int, int], counts: dict[int, int]) -> list[DataFrame]:
    """Heads of the rules of one shape, their literal j among new facts.

    delta and known give the facts of predicates; new and counts say how many they are.
    """
    out = []
    rules = sorted(rules, key=lambda r: (r[j], r))
    choices = list(dict.fromkeys(r[:j] + r[j + 1 :] for r in rules))
    for k in range(0, len(choices), BITS):
        bits = {c: i for i, c in enumerate(choices[k : k + BITS])}
        here = [r for r in rules if r[:j] + r[j + 1 :] in bits]
        words = slot_words(here, bits, j, j)
        left = [i for i in range(1, len(skeleton)) if i != j]
        needed = lambda: {*skeleton[0], *(v for i in left for v in skeleton[i])}  # noqa: E731, B023
        state, bound, n = matched(delta(words), skeleton[j], words), set(skeleton[j]), sum(new[q] for q in words)
        most, grouped = n, len(words) > 1
        while True:
            if grouped or bound - needed():
                bound &= needed()
                state = state.groupBy(*[f"x{v}" for v in sorted(bound)]).agg(F.bit_or("m").alias("m"))
            if not left:
                break
            i = next((i for i in left if bound & set(skeleton[i])), left[0])
            left.remove(i)
            words = slot_words(here, bits, j, i)
            side, m = matched(known(words), skeleton[i], words).withColumnRenamed("m", "m2"), sum(counts[q] for q in words)
            shared = [f"x{v}" for v in sorted(bound & set(skeleton[i]))]
            if n <= SENT and n <= m:
                state = side.join(F.broadcast(state), shared) if shared else side.crossJoin(F.broadcast(state))
            else:
                side = F.broadcast(side) if m <= SENT else side
                state = state.join(side, shared) if shared else state.crossJoin(side)
            inside = bound <= set(skeleton[i])  # a binding of the side meets one row of the state
            n, most = m if inside else n if set(skeleton[i]) <= bound else n * m, max(most, m)
            bound |= set(skeleton[i])
            state = state.withColumn("m", F.col("m").bitwiseAND(F.col("m2"))).drop("m2")
            if len(words) > 1:
                state = state.filter("m <> 0")
            grouped = len(words) > 1
        one = heads(state, skeleton[0], slot_words(here, bits, j, 0))
        out.append(spill(one, "applied") if most > SENT else one)  # one large join at a time: what it sends is held no longer
    return out


def evaluate_batched(spark: SparkSession, p: Program, edb: dict[str, DataFrame], max_rounds: int = 1000) -> tuple[DataFrame, dict]:
    """(p, a0, a1) of all derived facts, and counts: rounds, shapes, fired joins."""
    code = {q: i for i, q in enumerate(sorted(p.idb | p.edb))}
    shapes: dict[tuple, list[tuple]] = defaultdict(list)
    for r in p.rules:
        skeleton, slots = shape_of(r)
        shapes[skeleton].append(tuple(code[s] for s in slots))

    def tagged(q: str) -> DataFrame:
        df = edb[q]
        cols = df.columns
        return df.dropna().select(F.lit(code[q]).alias("p"), F.col(cols[0]).cast("long").alias("a0"), (F.col(cols[1]).cast("long") if len(cols) > 1 else F.lit(-1).cast("long")).alias("a1"))

    def per_predicate(df: DataFrame) -> dict[int, int]:
        return dict(map(tuple, df.groupBy("p").count().collect()))  # at most one row a predicate

    # Relations of pairs are stored each as it is dealt; those of single values in one table, whose readers skip what they don't ask for.
    pairs = [q for q in sorted(p.edb) if len(edb[q].columns) > 1]
    base = {frozenset([code[q]]): spill(tagged(q), "base") for q in pairs}
    singles = [tagged(q) for q in sorted(p.edb) if q not in pairs]
    if singles:
        base[frozenset(code[q] for q in p.edb if q not in pairs)] = spill(reduce(DataFrame.union, singles).dropDuplicates().sortWithinPartitions("p"), "base")
    nothing = spark.createDataFrame([], "p int, a0 long, a1 long")

    derivable = {code[q] for q in p.idb}

    def read(more: DataFrame | None):
        def of(asked) -> DataFrame:
            parts = [df for preds, df in base.items() if preds & set(asked)]
            return reduce(DataFrame.union, parts + [more] if more is not None and derivable & set(asked) else parts)

        return of

    derived = SetStore()
    counts: dict[int, int] = {}
    for df in base.values():
        counts |= per_predicate(df)
    new, delta, rounds, fired = dict(counts), read(None), 0, 0
    while True:
        rounds += 1
        if rounds > max_rounds:
            raise RuntimeError("no fixpoint")
        out = []
        known = read(derived.known())
        for skeleton, rows in shapes.items():
            for j in range(1, len(skeleton)):
                rules = [r for r in rows if r[j] in new and all(x in counts for x in r[1:])]
                if rules:
                    fired += 1
                    out += apply_shape(skeleton, rules, j, delta, known, new, counts)
        if not out:
            break
        fresh, n = derived.add(reduce(DataFrame.union, out), "derived")
        discard(*out)
        if not n:
            break
        new = per_predicate(fresh)
        for q, n in new.items():
            counts[q] = counts.get(q, 0) + n
        delta = lambda asked, fresh=fresh: fresh
    got = derived.known()
    names = spark.createDataFrame([(i, q) for q, i in code.items()], "p int, pred string")
    facts = (got if got is not None else nothing).join(F.broadcast(names), "p").select("pred", "a0", "a1")
    return facts, {"rounds": rounds, "shapes": len(shapes), "fired": fired, "rules": len(p.rules)}
