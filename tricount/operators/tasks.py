"""Tasks of consecutive ids: equal ones, one per worker, and ones that shrink with the work that is left; replay on a cost clock.

Cutting needs the costs in order. Beyond UNITS ids, so many consecutive ids become one unit, so that the driver holds at
most UNITS sums whatever the network. Cuts are exact all the same: the units tell in which of them a cut falls, and the
costs of the ids of that unit alone are then fetched.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable
from itertools import accumulate

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut

#: Units whose ids' sums the driver keeps beside those of all units.
KEPT = 64
UNITS = 1 << 20
TASK = "seq int, phase string, v long, t long, size decimal(38,0)"


class Costs:
    """Sums of cost below each unit of ``step`` consecutive ids (``upto``), and inside a unit from ``fine``; ``n`` ids in all.

    fine: gives the sums below the ids of one unit, from the first; a unit of one id needs none. What it gave last is kept.
    """

    def __init__(self, upto: list[int], step: int, n: int, fine: Callable[[int], list[int]] | None = None):
        self.upto, self.step, self.n, self.fine = upto, step, n, fine
        self._near: dict[int, list[int]] = {}

    def below(self, i: int) -> int:
        """The cost of the ids below i."""
        unit, inside = divmod(i, self.step)
        if not inside or i >= self.n:
            return self.upto[-1] if i >= self.n else self.upto[unit]
        if unit not in self._near:
            if len(self._near) >= KEPT:
                self._near.pop(next(iter(self._near)))
            self._near[unit] = self.fine(unit)
        return self.upto[unit] + self._near[unit][inside]

    def twice(self, i: int) -> int:
        return 2 * self.below(i)

    def size(self, a: int, b: int) -> int:
        return self.below(b) - self.below(a)


def collected(cost: DataFrame, units: int = UNITS) -> Costs:
    top = cost.agg(F.max("id")).collect()[0][0]
    n = 0 if top is None else top + 1
    step = max(1, -(-n // units))
    if step > 1:
        cost = cut(cost.select("id", "f"))  # looked into again, a unit at a time
    sums = dict(cost.groupBy(F.expr(f"id div {step}").alias("u")).agg(F.sum(F.col("f").cast("decimal(38,0)"))).collect())  # at most ``units`` rows
    upto = [0]
    for u in range(-(-n // step)):
        upto.append(upto[-1] + int(sums.get(u, 0)))

    def fine(unit: int) -> list[int]:
        each = dict(cost.where(F.col("id").between(unit * step, (unit + 1) * step - 1)).groupBy("id").agg(F.sum(F.col("f").cast("decimal(38,0)"))).collect())  # at most ``step`` rows
        return list(accumulate((int(each.get(unit * step + i, 0)) for i in range(step - 1)), initial=0))

    return Costs(upto, step, n, fine)


def task_size(cost: DataFrame, v: int, t: int) -> DataFrame:
    """The cost of the task of t ids from v."""
    return cost.where(F.col("id").between(v, v + t - 1)).agg(F.coalesce(F.sum(F.col("f").cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)").alias("size"))


def _first(c: Costs, low: int, reached: Callable[[int, int], bool], sums: Callable[[int], int] | None = None) -> int:
    """The smallest id above ``low`` at which ``reached`` holds (it is monotone), or the number of ids: by units, then inside one.

    reached gets the id and ``sums`` of it: twice the cost below it, unless told otherwise. Units are judged by the former.
    """

    def search(a, b, holds):
        while a < b:
            m = (a + b) // 2
            if holds(m):
                b = m
            else:
                a = m + 1
        return b

    sums = sums or c.twice
    unit = search(low // c.step + 1, len(c.upto) - 1, lambda u: reached(min(c.n, u * c.step), 2 * c.upto[u]))
    return search(max(low + 1, (unit - 1) * c.step), min(c.n, unit * c.step), lambda i: reached(i, sums(i)))


def half_id(c: Costs) -> int:
    """The number of ids that hold the first half of the cost."""
    return _first(c, 0, lambda _, s: s >= c.upto[-1]) if c.n else 0


def _spans(c: Costs, start: int, end: int, part: Callable[[int, int], int], sums: Callable[[int], int]) -> list[tuple[int, int]]:
    """The ids from ``start`` to ``end`` cut where ``part`` of an id and its ``sums``, which never falls, changes: one search for each cut."""
    edges = [start]
    while edges[-1] < end:
        now = part(edges[-1], sums(edges[-1]))
        edges.append(min(end, _first(c, edges[-1], lambda i, s, now=now: i >= end or part(i, s) > now, sums)))
    return list(zip(edges[:-1], edges[1:], strict=True))


def initial_tasks(c: Costs, workers: int) -> list[tuple[int, int]]:
    """The first half of the work in one task per worker: the k-th ends where k worker's shares are first reached."""
    half = half_id(c)
    total = c.twice(half) if half else 0
    return _spans(c, 0, half, lambda i, s: min(workers - 1, s * workers // total if total else i * workers // max(1, half)), c.twice)


def shrinking_tasks(c: Costs, workers: int, start: int) -> list[tuple[int, int]]:
    """The rest in tasks of a workers-th of what is left, never less than an id."""
    out = []
    while start < c.n:
        before = c.below(start)
        left = c.upto[-1] - before
        end = c.n if not left else _first(c, start, lambda _, s, before=before, left=left: workers * (s - 2 * before) >= 2 * left)
        out.append((start, end))
        start = end
    return out


def equal_tasks(c: Costs, k: int, start: int = 0) -> list[tuple[int, int]]:
    """k tasks of nearly equal cost over the ids from ``start``: an id goes where the middle of its cost falls."""
    before = c.below(start)
    total = c.upto[-1] - before
    span = c.n - start
    return _spans(c, start, c.n, lambda i, s: min(k - 1, (s - 2 * before) * k // (2 * total) if total else (i - start) * k // max(1, span)), lambda i: c.below(i) + c.below(i + 1))


def plan(c: Costs, processors: int, granularity: str = "shrinking", queue: int | None = None) -> list[tuple[str, int, int]]:
    """(phase, first id, end id) in the order in which they are handed out; one processor coordinates.

    static: one task per worker. equal: half up front, the rest in ``queue`` equal tasks. shrinking: half up front, the
    rest in shrinking tasks.
    """
    workers = processors - 1
    if workers < 1:
        raise ValueError("two processors at least: one coordinates")
    if granularity == "static":
        return [("initial", *x) for x in equal_tasks(c, workers)]
    first = initial_tasks(c, workers)
    half = first[-1][1] if first else 0
    rest = shrinking_tasks(c, workers, half) if granularity == "shrinking" else equal_tasks(c, queue or 2 * workers, half) if half < c.n else []
    return [("initial", *x) for x in first] + [("queue", *x) for x in rest]


def table(spark: SparkSession, cost: DataFrame, processors: int, granularity: str = "shrinking", queue: int | None = None) -> DataFrame:
    """seq, phase, v, t, size of the tasks."""
    from decimal import Decimal

    c = collected(cost)
    rows = [(i, phase, a, b - a, Decimal(c.size(a, b))) for i, (phase, a, b) in enumerate(plan(c, processors, granularity, queue))]
    return spark.createDataFrame(rows, TASK)


def replay(work: list[int], workers: int, first: int) -> tuple[list[tuple[int, int, int, int]], list[int]]:
    """(seq, worker, start, finish) when idle workers pull tasks in order, and each worker's idle time at the end.

    The first ``first`` tasks go one to each worker; ties go to the smaller worker.
    """
    free = [(0, w) for w in range(workers)]
    log, busy = [], [0] * workers
    for i, x in enumerate(work):
        at, w = (0, i) if i < min(first, workers) else heapq.heappop(free)
        if i < min(first, workers):
            free = [f for f in free if f[1] != w]
            heapq.heapify(free)
        log.append((i, w, at, at + x))
        busy[w] = at + x
        heapq.heappush(free, (at + x, w))
    end = max(busy, default=0)
    return log, [end - b for b in busy]


def idle_share(work: list[int], workers: int, first: int) -> float:
    """Idle time over all workers as a share of workers x makespan."""
    log, idle = replay(work, workers, first)
    end = max((x[3] for x in log), default=0)
    return sum(idle) / (workers * end) if end else 0.0


def gini(values: list[float]) -> float:
    x = np.sort(np.asarray(values, dtype=float))
    n = len(x)
    return float((2 * np.arange(1, n + 1) - n - 1) @ x / (n * x.sum())) if n and x.sum() else 0.0
