"""Phase times, memory, factors and repeated runs."""

from __future__ import annotations

import re
import time
from contextlib import contextmanager
from pathlib import Path
from statistics import mean, pstdev


class PhaseClock:
    def __init__(self):
        self.ms: dict[str, float] = {}

    @contextmanager
    def phase(self, name: str):
        t = time.perf_counter()
        try:
            yield
        finally:
            self.ms[name] = self.ms.get(name, 0) + 1000 * (time.perf_counter() - t)


def factor(a: float, b: float) -> float:
    return a / b if b else float("inf")


def peak_memory_kb(pids: list[int]) -> int:
    """Sum of the peak resident sizes of processes."""
    total = 0
    for p in pids:
        if m := re.search(r"VmHWM:\s+(\d+)", Path(f"/proc/{p}/status").read_text()):
            total += int(m[1])
    return total


def repeat(run, n: int = 10, timeout_s: float = 1800) -> dict[str, float]:
    """Mean and spread of n runs after one to warm up; stops early past the time limit."""
    times, began = [], time.perf_counter()
    run()
    for _ in range(n):
        t = time.perf_counter()
        run()
        times.append(time.perf_counter() - t)
        if time.perf_counter() - began > timeout_s:
            break
    return {"mean_s": mean(times), "spread_s": pstdev(times), "runs": len(times)}


def resident_kb() -> int:
    """Peak resident size of this process and all below it: the driver, its JVM and the workers that are alive."""
    import os

    below: dict[int, list[int]] = {}
    for f in Path("/proc").glob("[0-9]*/stat"):
        try:
            parts = f.read_text().rpartition(")")[2].split()
        except OSError:
            continue
        below.setdefault(int(parts[1]), []).append(int(f.parent.name))
    own, todo = [], [os.getpid()]
    while todo:
        own.append(p := todo.pop())
        todo += below.get(p, [])
    return peak_memory_kb([p for p in own if Path(f"/proc/{p}/status").exists()])


def base_memory_kb(spark) -> int:
    """Memory of a session that has neither data nor rules."""
    spark.range(1).count()
    return resident_kb()


def structure_report(spark, stats, sizes: dict[str, int] | None = None):
    """(name, kind, rows, bytes) of what a driver stored."""
    rows = [(q, stats.kinds.get(q, "rows"), n, (sizes or {}).get(q)) for q, n in sorted(stats.stored.items())]
    return spark.createDataFrame(rows, "name string, kind string, rows long, bytes long")


def phase_report(make, n: int = 10, timeout_s: float = 1800) -> dict[str, float]:
    """Mean milliseconds of each phase of n runs after one to warm up; make() gives a run's phases."""
    runs, began = [], time.perf_counter()
    make()
    for _ in range(n):
        t = time.perf_counter()
        ms = make()
        runs.append(ms | {"total": 1000 * (time.perf_counter() - t)})
        if time.perf_counter() - began > timeout_s:
            break
    return {k: mean(r[k] for r in runs) for k in runs[0]} | {"spread": pstdev(r["total"] for r in runs), "runs": len(runs)}


def derivation_report(bag: int, answers: int) -> dict[str, float]:
    return {"derivations": bag, "answers": answers, "ratio": factor(bag, answers)}
