"""Measures of runs."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.operators.relation import COUNT, KeyedRelation


@dataclass
class Run:
    """Seconds and tuples of each batch; ``stopped`` if the limit ended it."""

    seconds: list[float] = field(default_factory=list)
    tuples: list[int] = field(default_factory=list)
    training: float = 0.0
    stopped: bool = False

    @property
    def throughput(self) -> float:
        return sum(self.tuples) / max(sum(self.seconds), 1e-9)

    def curve(self, parts: int = 10) -> list[float]:
        """Throughput of each part of the stream."""
        out, total, goal = [], sum(self.tuples), 0.0
        n = s = 0.0
        for t, x in zip(self.seconds, self.tuples, strict=True):
            n, s, goal = n + x, s + t, goal + x
            if goal >= total * (len(out) + 1) / parts:
                out.append(n / max(s, 1e-9))
                n = s = 0.0
        return out

    @property
    def training_share(self) -> float:
        return self.training / max(sum(self.seconds), 1e-9)

    @property
    def mark(self) -> str:
        return "*" if self.stopped else ""


def run_stream(batches: Iterable[tuple[str, DataFrame]], apply: Callable[[str, DataFrame], object], force: Callable[[], object], limit: float = float("inf"), train: Callable[[], object] | None = None) -> Run:
    """Feed batches until they or the time end; ``force`` makes the work happen, ``train`` is timed apart."""
    out, start = Run(), time.perf_counter()
    for relation, delta in batches:
        if time.perf_counter() - start > limit:
            out.stopped = True
            break
        n = delta.count()
        t = time.perf_counter()
        apply(relation, delta)
        force()
        if train is not None:
            u = time.perf_counter()
            train()
            out.training += time.perf_counter() - u
        out.seconds.append(time.perf_counter() - t)
        out.tuples.append(n)
    return out


def rounds(limit: float, batch: Callable[[int], Iterable[tuple[str, DataFrame]]], apply: Callable[[str, DataFrame], object], force: Callable[[], object], most: int = 1_000_000) -> int:
    """Rounds (one batch for each copy of the relation) that end within the limit."""
    start, done = time.perf_counter(), 0
    while done < most:
        for relation, delta in batch(done):
            apply(relation, delta)
            force()
            if time.perf_counter() - start > limit:
                return done
        done += 1
    return done


def enum_run(batches: Sequence[tuple[str, DataFrame]], mode, interval: int) -> tuple[int, float]:
    """(requests, seconds) with an enumeration after every ``interval`` batches."""
    start, requests = time.perf_counter(), 0
    for i, (relation, delta) in enumerate(batches, 1):
        mode.apply(relation, delta)
        if i % interval == 0:
            mode.result().df.write.format("noop").mode("overwrite").save()
            requests += 1
    return requests, time.perf_counter() - start


def best3of4(f: Callable[[], float]) -> float:
    """Mean of the best three of four."""
    return sum(sorted(f() for _ in range(4))[:3]) / 3


def max_abs_diff(a: KeyedRelation, b: KeyedRelation) -> float:
    """Largest difference of any slot of two relations, a missing entry counting as zero."""
    slots = sorted(set(a.slots) | set(b.slots))
    by = [*a.keys, *a.inner]
    side = lambda r, n: r.df.select(*by, *[(F.col(s).cast("double") if s in r.slots else F.lit(0.0)).alias(f"{n}{s}") for s in slots])
    x, y = side(a, "x_"), side(b, "y_")
    both = x.join(y, by, "full") if by else x.crossJoin(y)
    diff = [F.max(F.abs(F.coalesce(f"x_{s}", F.lit(0.0)) - F.coalesce(f"y_{s}", F.lit(0.0)))) for s in slots]
    return max((v or 0.0 for v in both.agg(*diff).first()), default=0.0)


def rows_touched(df: DataFrame) -> int:
    """Rows of all scans, joins and aggregates of a plan that has run, from Spark's own metrics."""
    df.write.format("noop").mode("overwrite").save()
    store = df.sparkSession._jsparkSession.sharedState().statusStore()
    runs = store.executionsList()
    last = runs.apply(runs.size() - 1)
    values = store.executionMetrics(last.executionId())
    total = 0
    for m in _scala(last.metrics()):
        if m.name() == "number of output rows" and values.contains(m.accumulatorId()):
            total += int(values.apply(m.accumulatorId()).replace(",", ""))
    return total


def _scala(seq) -> list:
    return [seq.apply(i) for i in range(seq.size())]


def result_size(rel: KeyedRelation) -> int:
    """Values stored: keys and payload of each entry."""
    return rel.size() * (len(rel.keys) + len(rel.df.columns) - len(rel.keys) - (COUNT in rel.df.columns))
