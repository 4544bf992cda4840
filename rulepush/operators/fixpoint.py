"""The fixpoint of a step over frames, for recursion that isn't written as rules."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from ..storage import spill
from .dedup import SetStore


def fixpoint(seed: DataFrame, step: Callable[[DataFrame], DataFrame], keys: list[str] | None = None, dedup: bool = True, max_rounds: int | None = None) -> DataFrame:
    """seed and everything step makes of what is new, until nothing is.

    keys: columns that tell rows apart (all by default); of rows with equal keys the first round's stays, the least within
    a round. dedup=False keeps every row and ends when a round is empty, so the step must run out or max_rounds be set.
    """
    names = keys or seed.columns
    store = SetStore()
    if not dedup:
        delta = spill(seed, "fixpoint")
        every, rounds = [delta], 0
        while not delta.isEmpty() and (max_rounds is None or rounds < max_rounds):
            delta = spill(step(delta).select(*seed.columns), "fixpoint")
            every.append(delta)
            rounds += 1
        out = every[0]
        for df in every[1:]:
            out = out.unionByName(df)
        return out
    rest = [c for c in seed.columns if c not in names]

    def fresh(df: DataFrame) -> DataFrame:
        from pyspark.sql import functions as F

        df = df.select(*seed.columns)
        if rest:
            df = df.groupBy(*names).agg(F.min(F.struct(*rest)).alias("r")).select(*names, "r.*").select(*seed.columns)
            known = store.known()
            df = df.join(known, names, "left_anti") if known is not None else df
        return df

    delta, n = store.add(fresh(seed), "fixpoint")
    rounds = 0
    while n and (max_rounds is None or rounds < max_rounds):
        delta, n = store.add(fresh(step(delta)), "fixpoint")
        rounds += 1
    known = store.known()
    return known if known is not None else seed.limit(0)
